"""Grouping, relevance, plan graphs, plans and their execution; measures and workloads."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from spanfold import workloads as W
from spanfold.engine import Engine
from spanfold.operators import combine as C
from spanfold.operators.measures import accuracy, accuracy_difference_frame, coverage_frame
from spanfold.plans import planner as P
from spanfold.plans.costs import LinearCost
from spanfold.plans.ranges import Range, gaps
from spanfold.plans.relevance import Kept, group_descriptors, relevant_by_closure, relevant_contained
from spanfold.registry.base import ENDS_SQL, GROUPS_SQL, MODELS_SQL, ends_of, events_sql, linreg_sql, models_of, query, request_of
from spanfold.registry.state import bayes_rows, linreg_rows, size_of
from spanfold.sources.layout import event_source, lineitem_source
from spanfold.sources.points import CLASS3, GNB_EVENTS, GNB_LINES, LINREG, PointSource, load

def kept_of(spark, sf_dir) -> tuple[list[Kept], Range, int]:
    """Descriptors over the events' keys, a request, and the number of events."""
    n = size_of(event_source(spark, sf_dir))
    return [Kept(lo, hi, m) for m, lo, hi in models_of(n)], Range(*request_of(n)), n


def models_frame(spark, sf_dir):
    return spark.createDataFrame(models_of(size_of(event_source(spark, sf_dir))), "model_id string, lo long, hi long")


def example(source) -> tuple[dict, list[Kept], Range]:
    """The running example on events: four overlapping models, one request."""
    e = ends_of(size_of(source))
    models = [Kept(e["a"], e["c"], "D1"), Kept(e["a"], e["b"], "D2"), Kept(e["b"], e["d"], "D3"), Kept(e["d"], e["f"], "D4")]
    return e, models, Range(e["c"], e["e"])


@query(f"with {MODELS_SQL}, {GROUPS_SQL} select glo, ghi, n_models, model_ids from grouped")
def group_descriptors_chains(spark, sf_dir):
    """Enhanced descriptors: maximal chains of overlapping ranges."""
    return group_descriptors(models_frame(spark, sf_dir))


@query(f"""
with recursive {MODELS_SQL},
rel(model_id, lo, hi) as (
  select model_id, lo, hi from models, ask where lo < b and hi > a
  union select m.model_id, m.lo, m.hi from models m, rel r where m.lo < r.hi and r.lo < m.hi)
select model_id, lo, hi from rel""")
def relevant_closure(spark, sf_dir):
    kept, ask, _ = kept_of(spark, sf_dir)
    return spark.createDataFrame([(m.model_id, m.lo, m.hi) for m in relevant_by_closure(kept, ask)], "model_id string, lo long, hi long")


@query(f"""
with {MODELS_SQL}, {GROUPS_SQL}
select i.model_id, i.lo, i.hi from islands i join grouped g using (island), ask where g.glo < b and g.ghi > a""")
def relevant_by_groups(spark, sf_dir):
    """Through groups, as joins: request × groups, then group × models."""
    models, ask = models_frame(spark, sf_dir), kept_of(spark, sf_dir)[1]
    groups = group_descriptors(models).where((F.col("glo") < ask.hi) & (F.col("ghi") > ask.lo))
    return models.join(F.broadcast(groups.select("glo", "ghi")), (F.col("lo") >= F.col("glo")) & (F.col("hi") <= F.col("ghi"))).select("model_id", "lo", "hi")


@query(f"with {MODELS_SQL} select model_id, lo, hi from models, ask where lo >= a and hi <= b")
def relevant_inside(spark, sf_dir):
    kept, ask, _ = kept_of(spark, sf_dir)
    return spark.createDataFrame([(m.model_id, m.lo, m.hi) for m in relevant_contained(kept, ask)], "model_id string, lo long, hi long")


_EDGE_SQL = """
with {models}, near as (select model_id, lo, hi from models, ask where {where}),
best as (select lo, hi, min(1.0) as c, min(model_id) as model_id from near group by lo, hi),
nodes as (select lo as x from near union select hi from near union select a from ask union select b from ask),
up as (select p.x as u, q.x as v, best.model_id as m, case when best.c <= q.x - p.x then best.c end as c from nodes p join nodes q on p.x < q.x left join best on best.lo = p.x and best.hi = q.x),
one as (select u, v, case when c is null then 'scan' else 'model' end as kind, case when c is null then null else m end as model_id, cast(coalesce(c, v - u) as double) as cost from up)
"""


@query(_EDGE_SQL.format(models=MODELS_SQL, where="true") + "select u, v, kind, model_id, cost from one union all select v, u, kind, model_id, cost from one")
def plan_edges_undirected(spark, sf_dir):
    return P.edges_frame(models_frame(spark, sf_dir), kept_of(spark, sf_dir)[1])


@query(_EDGE_SQL.format(models=MODELS_SQL, where="lo >= a and hi <= b") + "select u, v, kind, model_id, cost from one")
def plan_edges_directed(spark, sf_dir):
    return P.edges_frame(models_frame(spark, sf_dir), kept_of(spark, sf_dir)[1], directed=True)


_PATH_SQL = f"""
with recursive {ENDS_SQL},
kept as (select a as lo, c as hi, k1 as w from ends, cost union all select a, b, k2 from ends, cost union all select b, d, k3 from ends, cost union all select d, f, k4 from ends, cost),
cost as (select unnest([1, 1000, 1000, 10000]) as k1, unnest([1, 1000, 1000, 10000]) as k2, unnest([1, 1, 1200, 10000]) as k3, unnest([1, 1, 1, 10000]) as k4, unnest([0, 1, 2, 3]) as variant),
tagged as (select variant, e.a as lo, e.c as hi, k1 as w from ends e, cost union all select variant, e.a, e.b, k2 from ends e, cost union all select variant, e.b, e.d, k3 from ends e, cost union all select variant, e.d, e.f, k4 from ends e, cost),
nodes as (select unnest([a, b, c, d, e, f]) as x from ends),
edges as (select variant, p.x as u, q.x as v, least(abs(p.x - q.x), coalesce((select min(w) from tagged t where t.variant = g.variant and t.lo = least(p.x, q.x) and t.hi = greatest(p.x, q.x)), abs(p.x - q.x))) as w
  from nodes p, nodes q, (select variant from cost) g where p.x <> q.x),
walk(variant, spot, seen, total) as (
  select variant, c, [c], 0 from ends, cost
  union all select walk.variant, edges.v, list_append(seen, edges.v), total + edges.w from walk, edges, ends
  where edges.variant = walk.variant and edges.u = walk.spot and walk.spot <> ends.e and not list_contains(seen, edges.v))
select cast(walk.variant as int) as variant, cast(min(total) as double) as cost from walk, ends where spot = ends.e group by walk.variant"""

COSTS = [(1, 1, 1, 1), (1000, 1000, 1, 1), (1000, 1000, 1200, 1), (10000,) * 4]


@query(_PATH_SQL.replace("kept as (select a as lo, c as hi, k1 as w from ends, cost union all select a, b, k2 from ends, cost union all select b, d, k3 from ends, cost union all select d, f, k4 from ends, cost),\n", ""))
def best_plan_cost(spark, sf_dir):
    """Cheapest plan of the running example under four settings of model costs."""
    source = event_source(spark, sf_dir)
    _, models, ask = example(source)
    rows = []
    for i, costs in enumerate(COSTS):
        own = [Kept(m.lo, m.hi, m.model_id, float(c)) for m, c in zip(models, costs)]
        rows.append((i, float(P.best_plan(own, ask, LinearCost(), source.directory).cost)))
    return spark.createDataFrame(rows, "variant int, cost double")


_WALKS = _PATH_SQL.replace("kept as (select a as lo, c as hi, k1 as w from ends, cost union all select a, b, k2 from ends, cost union all select b, d, k3 from ends, cost union all select d, f, k4 from ends, cost),\n", "")


@query(_WALKS.replace("total + edges.w from", "total + edges.w + 0.5 from").replace("select variant, c, [c], 0 from", "select variant, c, [c], cast(-0.5 as double) from"))
def plan_cost_merges(spark, sf_dir):
    """The same where each merge of two segments costs half a point."""
    source = event_source(spark, sf_dir)
    _, models, ask = example(source)
    cost = LinearCost(merge=0.5)
    plans = [P.best_plan([Kept(m.lo, m.hi, m.model_id, float(c)) for m, c in zip(models, cs)], ask, cost, source.directory) for cs in COSTS]
    return spark.createDataFrame([(i, float(P.plan_cost(p.segments, cost))) for i, p in enumerate(plans)], "variant int, cost double")


@query(_WALKS.split("select cast(walk.variant")[0] + "select cast(r as int) as rank, cast(total as double) as cost from (select total, row_number() over (order by total) as r from walk, ends where spot = ends.e and walk.variant = 0) where r <= 6")
def k_cheapest_plans(spark, sf_dir):
    """The six cheapest plans of the example, by cost."""
    source = event_source(spark, sf_dir)
    _, models, ask = example(source)
    plans = P.k_best_plans(models, ask, 6, LinearCost(), source.directory)
    return spark.createDataFrame([(i, float(p.cost)) for i, p in enumerate(plans, 1)], "rank int, cost double")


_FORWARD_SQL = f"""
with recursive {MODELS_SQL}, inside as (select distinct lo, hi from models, ask where lo >= a and hi <= b),
nodes as (select lo as x from inside union select hi from inside union select a from ask union select b from ask),
steps as (select x as u, lead(x) over (order by x) as v from nodes),
edges as (select u, v, cast(v - u as double) as w from steps where v is not null union all select lo, hi, 1.0 from inside),
walk(spot, total) as (select a, cast(0 as double) from ask union all select e.v, total + e.w from walk join edges e on e.u = walk.spot)
select min(total) as cost from walk, ask where spot = b"""


@query(_FORWARD_SQL)
def best_plan_cost_add_only(spark, sf_dir):
    """Cheapest plan that only adds: models inside the request and scans between them."""
    kept, ask, n = kept_of(spark, sf_dir)
    return spark.createDataFrame([(float(P.best_plan(kept, ask, directed=True).cost),)], "cost double")


@query(f"with {ENDS_SQL} select cast(i as int) as variant, cast(e - c as double) as cost from ends, (select unnest(range(4)) as i)")
def best_plan_cost_directed(spark, sf_dir):
    """Without subtraction no model of the example lies inside the request: it is scanned."""
    source = event_source(spark, sf_dir)
    _, models, ask = example(source)
    rows = [(i, float(P.best_plan([Kept(m.lo, m.hi, m.model_id, float(c)) for m, c in zip(models, cs)], ask, LinearCost(), source.directory, directed=True).cost)) for i, cs in enumerate(COSTS)]
    return spark.createDataFrame(rows, "variant int, cost double")


@query(f"""
with {ENDS_SQL}
select 0 as seq, -1 as sign, 'model' as kind, a as lo, c as hi, 'D1' as model_id from ends union all
select 1, 1, 'model', a, b, 'D2' from ends union all select 2, 1, 'model', b, d, 'D3' from ends union all
select 3, 1, 'model', d, f, 'D4' from ends union all select 4, -1, 'scan', e, f, null from ends""")
def plan_segments_running_example(spark, sf_dir):
    source = event_source(spark, sf_dir)
    _, models, ask = example(source)
    return P.segments_frame(spark, {0: P.best_plan(models, ask, LinearCost(), source.directory)}).select("seq", "sign", "kind", "lo", "hi", "model_id")


def _kept_example(spark, sf_dir):
    source = event_source(spark, sf_dir)
    _, models, ask = example(source)
    engine = Engine(spark)
    W.keep_exact(engine, source, GNB_EVENTS, [m.range for m in models])
    return source, engine, ask


_IN_REQUEST = events_sql("event_id >= n * 35 // 100 and event_id < n * 85 // 100")


@query(_IN_REQUEST)
def execute_plan_gnb(spark, sf_dir):
    """Plan and run the example: the signed combination is the model of the request."""
    source, engine, ask = _kept_example(spark, sf_dir)
    return bayes_rows(spark, engine.fit(source, GNB_EVENTS, *ask).state, GNB_EVENTS)


@query(_IN_REQUEST)
def execute_plan_add_only(spark, sf_dir):
    source, engine, ask = _kept_example(spark, sf_dir)
    plan = engine.plan(source, GNB_EVENTS, *ask, directed=True)
    return bayes_rows(spark, engine.fit(source, GNB_EVENTS, *ask, plan=plan).state, GNB_EVENTS)


@query(_IN_REQUEST)
def execute_plan_largest_overlap(spark, sf_dir):
    source, engine, ask = _kept_example(spark, sf_dir)
    plan = P.largest_overlap_plan(engine.store.relevant(GNB_EVENTS, ask), ask, LinearCost(), source.directory)
    return bayes_rows(spark, engine.fit(source, GNB_EVENTS, *ask, plan=plan).state, GNB_EVENTS)


@query(linreg_sql("pid >= n * 35 // 100 and pid < n * 85 // 100"))
def execute_plan_linreg(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    e = ends_of(size_of(source))
    engine = Engine(spark)
    W.keep_exact(engine, source, LINREG, [Range(e["a"], e["c"]), Range(e["a"], e["b"]), Range(e["b"], e["d"]), Range(e["d"], e["f"])])
    return linreg_rows(spark, engine.fit(source, LINREG, e["c"], e["e"]).state)


@query(f"""with {ENDS_SQL}
select 'best' as plan, cast(4 + f - e as double) as cost, cast(f - e as double) as scan_points, 4 as n_models, 5 as n_segments from ends
union all select p, cast(e - c as double), cast(e - c as double), 0, 1 from ends, (select unnest(['add only', 'scan only', 'greedy']) as p)
union all select 'largest overlap', cast(1 + (c - b) + (e - d) as double), cast((c - b) + (e - d) as double), 1, 3 from ends""")
def plan_alternatives(spark, sf_dir):
    """The chosen plan of the example beside the others, with costs and points to read."""
    source, engine, ask = _kept_example(spark, sf_dir)
    rows = [(k, float(p.cost), float(p.scan_points), len(p.models), len(p.segments)) for k, p in engine.explain(source, GNB_EVENTS, *ask).items()]
    return spark.createDataFrame(rows, "plan string, cost double, scan_points double, n_models int, n_segments int")


@query(f"""
with recursive {MODELS_SQL}, inside as (select *, row_number() over (order by lo, hi desc, model_id) as r from models, ask where lo >= a and hi <= b),
pick(r, spot, model_id, lo, hi, used) as (
  select cast(0 as bigint), cast(a as bigint), '', cast(0 as bigint), cast(0 as bigint), false from ask
  union all select i.r, case when i.lo >= spot then i.hi else spot end, i.model_id, i.lo, i.hi, i.lo >= spot from pick join inside i on i.r = pick.r + 1)
select model_id, lo, hi from pick where used""")
def greedy_cover(spark, sf_dir):
    kept, ask, _ = kept_of(spark, sf_dir)
    plan = P.greedy_cover(kept, ask)
    return spark.createDataFrame([(s.model_id, s.lo, s.hi) for s in plan.segments if s.kind == "model"], "model_id string, lo long, hi long")


@query(f"""
with {MODELS_SQL} select model_id, lo, hi, least(hi, b) - greatest(lo, a) as shared from models, ask
order by shared desc, lo, model_id desc limit 1""")
def largest_overlap(spark, sf_dir):
    """The model that shares most points with the request."""
    ask = kept_of(spark, sf_dir)[1]
    m = models_frame(spark, sf_dir).withColumn("shared", F.least("hi", F.lit(ask.hi)) - F.greatest("lo", F.lit(ask.lo)))
    return m.orderBy(F.desc("shared"), "lo", F.desc("model_id")).limit(1)


_MANY_SQL = f"""
with recursive {MODELS_SQL}, reqs as (select i as req_id, (i * 7919) % (n - n // 20) as a, (i * 7919) % (n - n // 20) + n // 40 + (i * 31) % (n // 40) as b from ask, (select unnest(range(1000)) as i)),
inside as (select distinct req_id, lo, hi from models m, reqs r where m.lo >= r.a and m.hi <= r.b),
nodes as (select req_id, lo as x from inside union select req_id, hi from inside union select req_id, a from reqs union select req_id, b from reqs),
steps as (select req_id, x as u, lead(x) over (partition by req_id order by x) as v from nodes),
edges as (select req_id, u, v, cast(v - u as double) as w from steps where v is not null union all select req_id, lo, hi, 1.0 from inside where hi - lo > 1),
walk(req_id, spot, total) as (select req_id, a, cast(0 as double) from reqs union all select e.req_id, e.v, total + e.w from walk join edges e on e.req_id = walk.req_id and e.u = walk.spot)
select w.req_id, min(total) as cost from walk w join reqs r on r.req_id = w.req_id where spot = r.b group by w.req_id"""


def _asks(n: int) -> list[tuple]:
    return [(i, a := (i * 7919) % (n - n // 20), a + n // 40 + (i * 31) % (n // 40)) for i in range(1000)]


@query(_MANY_SQL)
def plan_many(spark, sf_dir):
    """A thousand requests planned by the executors over the kept descriptors, adding only."""
    kept, _, n = kept_of(spark, sf_dir)
    frame = spark.createDataFrame(_asks(n), "req_id long, lo long, hi long")
    return P.plan_many(frame.repartition(8), kept, directed=True).select("req_id", "cost")


@query()
def plan_many_signed(spark, sf_dir):
    """The same with subtraction; checked against brute force on small sets in tests."""
    kept, _, n = kept_of(spark, sf_dir)
    frame = spark.createDataFrame(_asks(n), "req_id long, lo long, hi long")
    return P.plan_many(frame.repartition(8), kept)


@query(f"""with {MODELS_SQL}, reqs as (select i as req_id, (i * 7919) % (n - n // 20) as a, (i * 7919) % (n - n // 20) + n // 40 + (i * 31) % (n // 40) as b from ask, (select unnest(range(1000)) as i))
select req_id, event_type as class, count(*) as n, cast(sum(cast(cast(value as decimal(18,2)) * 100 as bigint)) as bigint) as cents from reqs join events on event_id >= a and event_id < b group by req_id, event_type""")
def fit_many_requests(spark, sf_dir):
    """A thousand requests answered together: planned one by one over kept models, all scans of all
    plans read in one job."""
    source = event_source(spark, sf_dir)
    n = size_of(source)
    engine = Engine(spark)
    W.keep_exact(engine, source, GNB_EVENTS, [Range(lo, hi) for _, lo, hi in models_of(n) if lo < hi])
    asks = _asks(n)
    answers = engine.fit_many(source, GNB_EVENTS, [Range(a, b) for _, a, b in asks])
    rows = [(i, c, k, s[0]) for (i, _, _), a in zip(asks, answers) for c, (k, s, _) in a.state.classes.items() if k]
    return spark.createDataFrame(rows, "req_id long, class string, n long, cents long")


# measures


@query(f"with {MODELS_SQL}, {GROUPS_SQL} select cast(sum(ghi - glo) as bigint) as covered, sum(ghi - glo) * cast(100 as double) / max(n) as pct from grouped, n_events")
def coverage_pct(spark, sf_dir):
    return coverage_frame(models_frame(spark, sf_dir), size_of(event_source(spark, sf_dir)))


@query(f"with {MODELS_SQL} select count(distinct event_id) as covered from events join models on event_id >= lo and event_id < hi")
def covered_points_distinct(spark, sf_dir):
    """Covered points counted one by one; the same number as the sweep's on dense keys."""
    points = event_source(spark, sf_dir).df.select("event_id")
    models = F.broadcast(models_frame(spark, sf_dir))  # 25 rows
    return points.join(models, (F.col("event_id") >= F.col("lo")) & (F.col("event_id") < F.col("hi"))).agg(F.count_distinct("event_id").alias("covered"))


@query(f"""
with {MODELS_SQL}, {GROUPS_SQL}, ends as (select ghi as lo, lead(glo, 1, (select n from n_events)) over (order by glo) as hi from grouped union all select 0, (select min(glo) from grouped))
select lo, hi from ends where lo < hi""")
def uncovered_ranges(spark, sf_dir):
    kept, _, n = kept_of(spark, sf_dir)
    return spark.createDataFrame(gaps(Range(0, n), [m.range for m in kept]), "lo long, hi long")


@query("select 'linreg' as kind, cast(8 * (12 * 13 / 2 + 12 + 1) as bigint) as nbytes union all select 'gnb', cast(8 * 5 * (1 + 4 + 4) as bigint)")
def store_bytes(spark, sf_dir):
    """Bytes kept for one model: independent of the points behind it."""
    lines, events = lineitem_source(spark, sf_dir), event_source(spark, sf_dir)
    rows = [("linreg", C.build(lines, LINREG, 0, size_of(lines)).state.nbytes), ("gnb", C.build(events, GNB_EVENTS, 0, size_of(events)).state.nbytes)]
    return spark.createDataFrame(rows, "kind string, nbytes long")


@query("""
with r as (select 1000 + (o_orderkey * 137) % 5000 as size, 0.86 + (o_custkey % 17) / 1000.0 as acc_base, 0.86 + (o_orderkey % 19) / 1000.0 as acc from orders)
select cast(size // 1000 as bigint) as size_bin, count(*) as n, round(avg(acc_base - acc), 6) as mean_diff, round(coalesce(avg(acc_base - acc) filter (where acc_base > acc), 0), 6) as mean_positive, round(max(acc_base - acc), 6) as max_diff
from r group by size // 1000""")
def accuracy_difference_summary(spark, sf_dir):
    """The summary of accuracy differences by size, over one made-up run an order."""
    rows = load(spark, sf_dir, "orders").select((F.lit(1000) + F.col("o_orderkey") * 137 % 5000).alias("size"), (F.lit(0.86) + F.col("o_custkey") % 17 / 1000.0).alias("acc_base"), (F.lit(0.86) + F.col("o_orderkey") % 19 / 1000.0).alias("acc"))
    out = accuracy_difference_frame(rows, 1000)
    return out.select("size_bin", "n", *[F.round(c, 6).alias(c) for c in ("mean_diff", "mean_positive", "max_diff")])


# workloads: plan costs over seeded request sets (no SQL form: shortest paths over thousands of plans)


def _rows(spark, rows: list[dict]):
    names = list(rows[0])
    return spark.createDataFrame([tuple(float(r[k]) for k in names) for r in rows], ", ".join(f"{k} double" for k in names))


def _lines(spark, sf_dir) -> int:
    return size_of(lineitem_source(spark, sf_dir))


def _orders_of_lines(spark, sf_dir) -> tuple:
    """The directory of lineitem by its order keys, counted by Spark in some four thousand blocks of
    keys, and the number of keys: what ranges are drawn on, while the points below them cost."""
    from spanfold.sources.layout import build_directory, directory_of

    rows = load(spark, sf_dir, "lineitem").where("l_orderkey is not null")
    last = rows.agg(F.max("l_orderkey")).first()[0]
    return directory_of(build_directory(rows, "l_orderkey", max(1, (last + 1) // 4096))), last + 1


@query()
def workload_gain_by_coverage(spark, sf_dir):
    """Share of a scan's cost against coverage over a thousand requests on lineitem's order keys, with
    subtraction and add-only (W1 to W3: the additive kinds have the former, the logistic kind the latter)."""
    directory, n = _orders_of_lines(spark, sf_dir)
    return W.planned_frame(spark, directory, [W.coverage_case(n, c) for c in W.COVERAGES])


@query("""
with s as (select count(*) as n, greatest(2, cast(round(5000 * (count(*) / 5e6)) as bigint)) as size from lineitem), c as (select unnest([20, 40, 60, 80, 90]) as coverage),
m as (select coverage, n, least(n // size, cast(round(n * coverage / 100.0 / size) as bigint)) as models from s, c)
select cast(coverage as double) as coverage, cast(models as double) as models, cast(models * 8 * 91 as double) as bytes, round(100.0 * models * 8 * 91 / (n * 88), 6) as percent from m""")
def workload_storage(spark, sf_dir):
    """Bytes of kept models against coverage (W4)."""
    source = lineitem_source(spark, sf_dir)
    return _rows(spark, W.storage_by_coverage(spark, source, LINREG, size_of(source))).withColumn("percent", F.round("percent", 6))


@query()
def workload_gain_by_model_size(spark, sf_dir):
    """Gain against model size at half coverage, small and large requests, a thousand each, with
    subtraction (W5) and add-only (W6)."""
    directory, n = _orders_of_lines(spark, sf_dir)
    cost = 400 * float(directory.running[-1]) / 600_000  # of using a model, in scanned points
    return W.planned_frame(spark, directory, [W.size_case(n, s, W.Sizes("fixed", q), cost, tags=(("request", q),)) for q in (50_000, 100_000) for s in W.MODEL_SIZES])


@query()
def workload_model_sets(spark, sf_dir):
    """Cost against coverage for four model sets, a thousand small or large requests (W7, W8, W18)."""
    directory, n = _orders_of_lines(spark, sf_dir)
    cases = []
    for large, asks in ((0, W.SMALL), (1, W.LARGE)):
        for i, (_, sizes) in enumerate(sorted(W.MODEL_SETS.items()), 1):
            cases += [W.coverage_case(n, c, sizes, asks, seed=i, tags=(("large", large), ("model_set", i))) for c in W.COVERAGES]
    return W.planned_frame(spark, directory, cases)


def _written(spark, sf_dir, spec):
    """The line points with the spec's features written out, so that few points need no job."""
    from spanfold.sources.layout import materialize

    source = lineitem_source(spark, sf_dir)
    if getattr(source.projected.get(spec.shape_id), "reader", None) is None:
        materialize(source, spec)
    return source


def _logit(n: int, chunk: int, **more):
    from spanfold.sources.points import LOGIT

    return replace(LOGIT, chunk=max(50, int(chunk * n / 5e6)), **more)


def _seconds(spark, sf_dir, spec, **options):
    source = _written(spark, sf_dir, spec)
    return _rows(spark, W.time_by_coverage(spark, source, spec, size_of(source), **options))


@query()
def workload_time_linreg(spark, sf_dir):
    """Seconds of linear-regression requests against coverage, split into planning, reading and
    merging, beside the seconds from raw points (W1, W10); twenty requests a coverage are timed."""
    return _seconds(spark, sf_dir, LINREG)


@query()
def workload_time_gnb(spark, sf_dir):
    """The same for Gaussian naive Bayes (W2, W10)."""
    return _seconds(spark, sf_dir, GNB_LINES)


@query()
def workload_time_logistic(spark, sf_dir):
    """The same for logistic regression, by chunk reuse (W3, W10, and the seconds of W11, W12)."""
    n = _lines(spark, sf_dir)
    rows = []
    for chunk in W.CHUNKS:
        spec = _logit(n, chunk)
        rows += [{"chunk": spec.chunk} | r for r in W.time_by_coverage(spark, _written(spark, sf_dir, spec), spec, n, count=8)]
    return _rows(spark, rows)


@query()
def workload_time_model_sets(spark, sf_dir):
    """Seconds against coverage for the four model sets on naive Bayes, small requests and large
    ones (W7, W8); five requests a point are timed."""
    source = _written(spark, sf_dir, GNB_LINES)
    n = size_of(source)
    rows = []
    for large, asks in ((0, W.SMALL), (1, W.LARGE)):
        for i, (_, sizes) in enumerate(sorted(W.MODEL_SETS.items()), 1):
            rows += [{"large": large, "model_set": i} | r for r in W.time_by_coverage(spark, source, GNB_LINES, n, (0, 50, 90), sizes, asks, 5, seed=i)]
    return _rows(spark, rows)


@query()
def workload_time_model_size(spark, sf_dir):
    """Seconds against model size at half coverage, naive Bayes (W5) and logistic (W6); five requests
    a size are timed. The seconds from raw points, which no kept model enters, are measured once a
    request and stand beside every size."""
    n = _lines(spark, sf_dir)
    rows = []
    for kind, specs in ((0, [GNB_LINES for _ in W.MODEL_SIZES]), (1, [_logit(n, size) for size in W.MODEL_SIZES])):
        source = _written(spark, sf_dir, specs[0])
        engines = W.engines_by_size(spark, source, specs, n, 50, W.MODEL_SIZES)
        for q in (50_000, 100_000):
            asks = W.requests(n, 6, W.Sizes("fixed", q), seed=8)
            base = [W.base_seconds(engines[0], source, specs[0], r) for r in asks]
            rows += [{"request": q, "size": size, "logistic": kind} | W.timed(e, source, spec, asks, base) for size, spec, e in zip(W.MODEL_SIZES, specs, engines)]
    return _rows(spark, rows)


@query()
def workload_many_requests(spark, sf_dir):
    """A thousand requests in one job at each coverage, with kept models and without (seconds)."""
    source = _written(spark, sf_dir, LINREG)
    n = size_of(source)
    rows = [{"coverage": c} | W.timed_many(W.engine_at(spark, source, LINREG, n, c, seed=c), source, LINREG, W.requests(n, 1000, W.NORMAL, seed=3)) for c in (0, 90)]
    return _rows(spark, rows)


@query()
def workload_logistic_accuracy(spark, sf_dir):
    """Accuracy of plain descent minus that of chunk reuse over a thousand requests, by size of the
    request: mean, mean of the positive cases and maximum, for two chunk sizes (W11, W12)."""
    n = _lines(spark, sf_dir)
    specs = [_logit(n, chunk) for chunk in W.CHUNKS]
    source = _written(spark, sf_dir, specs[0])
    cases = [(Engine(spark), spec, W.requests(n, 1000, W.Sizes("uniform", 50_000, 200_000), seed=chunk)) for spec, chunk in zip(specs, W.CHUNKS)]
    out = None
    for spec, got in zip(specs, W.logistic_accuracies(source, cases)):
        runs = spark.createDataFrame([(float(s), a, b) for s, a, b in got], "size double, acc_base double, acc double")
        part = accuracy_difference_frame(runs, 50_000 * n / 5e6).select(F.lit(spec.chunk).alias("chunk"), "*")
        out = part if out is None else out.unionByName(part)
    return out


@query()
def workload_more_classes(spark, sf_dir):
    """Three classes by one against the rest: accuracy of averaged chunks and of plain descent on
    the same points (W13)."""
    import numpy as np

    from spanfold.functions import logistic as G

    n = _lines(spark, sf_dir)
    source = lineitem_source(spark, sf_dir)
    rows = []
    for i in range(5):
        lo, size = i * (n // 6), n // 30
        own = PointSource(source.scan_range(lo, lo + size), "pid")
        spec = replace(_logit(n, 10_000), label=CLASS3)
        averaged = G.one_vs_rest(own.df, spec, GNB_LINES.classes, G.make_chunks(lo, lo + size, spec.chunk))
        plain = G.one_vs_rest(own.df, spec, GNB_LINES.classes, [Range(lo, lo + size)])
        found = [accuracy(G.ovr_predict(own.df, spec, m), CLASS3).first()["accuracy"] for m in (plain, averaged)]
        gone = max(float(np.linalg.norm(plain[c].w - averaged[c].w)) for c in plain)
        rows.append({"lo": lo, "points": size, "acc_base": found[0], "acc": found[1], "weights_apart": gone})
    return _rows(spark, rows)


@query()
def workload_bound(spark, sf_dir):
    """Observed distance of averaged and whole-range weights against the bound: five chunk sizes,
    twenty seeded ranges each, and the share of ranges beyond the bound (W14)."""
    from spanfold.functions.logistic import largest_norm

    n = _lines(spark, sf_dir)
    spec = _logit(n, 5_000, l2=0.1, step_size=0.05)
    source = _written(spark, sf_dir, spec)
    radius = largest_norm(source.df, spec).first()["radius"]
    sizes = [max(20, round(c * n / 600_000)) for c in (300, 600, 1200, 2400, 4800)]
    return _rows(spark, [{"l2": 0.1} | r for r in W.bound_study(source, spec, sizes, 2 * sizes[-1], 20, radius)])


@query()
def workload_cost_fidelity(spark, sf_dir):
    """Scan costs calibrated on measured jobs, and how they rank other sizes' times."""
    source = lineitem_source(spark, sf_dir)
    return _rows(spark, [W.cost_study(spark, source, GNB_LINES, size_of(source), 12)])


@query()
def workload_real_data(spark, sf_dir):
    """Small requests on given data (W9): events, and 32 components of the vectors with ten classes.
    Cost relative to scanning, and the distance to the scratch state, which is 0."""
    from spanfold.operators.measures import state_distance
    from spanfold.plans.costs import Directory
    from spanfold.sources.points import Feature, ModelSpec

    vectors = load(spark, sf_dir, "embeddings")
    parts = tuple(Feature(f"e{i}", f"embedding[{i}]", 6, 1) for i in range(32))
    wide = ModelSpec("gnb", "embeddings", "vec_id", parts, "cast(label as string)")
    dense = PointSource(vectors, "vec_id", sf_dir, directory=Directory.dense(vectors.count()))
    rows = []
    for i, (source, spec) in enumerate(((event_source(spark, sf_dir), GNB_EVENTS), (dense, wide))):
        n = size_of(source)
        engine = Engine(spark)
        W.keep_exact(engine, source, spec, W.place_models(n, 90, W.Sizes("uniform", 25_000, 50_000), seed=4, unit=n / 1e6))
        for r in W.requests(n, 3, W.SMALL, seed=6, unit=n / 1e6):
            answer = engine.fit(source, spec, *r)
            rows.append({"table": i, "lo": r.lo, "hi": r.hi, "share": answer.plan.cost / (r.hi - r.lo), "points": answer.points_read, "distance": state_distance(answer.state, C.build(source, spec, *r).state)})
    return _rows(spark, rows)


@query(f"with {MODELS_SQL}, {GROUPS_SQL} select g.glo, g.ghi, g.n_models, count(*) as inside from grouped g join models m on m.lo >= g.glo and m.hi <= g.ghi group by g.glo, g.ghi, g.n_models")
def sql_views(spark, sf_dir):
    """Kept models and their groups as views for SQL."""
    from spanfold.functions.udfs import register_views
    from spanfold.sources.store import ModelStore

    source = event_source(spark, sf_dir)
    store = ModelStore(spark)
    state = C.build(source, GNB_EVENTS, 0, 10).state
    for m in kept_of(spark, sf_dir)[0]:
        store.put(GNB_EVENTS, m.range, state)
    register_views(store, GNB_EVENTS)
    return spark.sql("select g.glo, g.ghi, g.n_models, count(*) as inside from model_groups g join kept_models m on m.lo >= g.glo and m.hi <= g.ghi group by all")


@query(f"""with {MODELS_SQL}, inside as (select distinct on (lo, hi) model_id, lo, hi from models, ask where lo >= a and hi <= b and hi - lo > 1 order by lo, hi, model_id),
clear as (select * from inside i where not exists (select 1 from inside o where o.model_id <> i.model_id and o.lo < i.hi and i.lo < o.hi)) select 'model' as kind, 1 as sign, lo, hi, model_id from clear""")
def plan_table_function(spark, sf_dir):
    """An add-only plan as a table function: models of the request that overlap no other are used
    whole (those that do compete, and are left out here)."""
    from spanfold.functions.udfs import register_table_functions

    kept, ask, _ = kept_of(spark, sf_dir)
    register_table_functions(spark, kept, directed=True)
    inside = [m for m in kept if ask.lo <= m.lo and m.hi <= ask.hi]
    lone = [m.model_id for m in inside if not any(o.model_id != m.model_id and o.lo < m.hi and m.lo < o.hi for o in inside)]
    plan = spark.sql(f"select kind, sign, lo, hi, model_id from plan_segments({ask.lo}, {ask.hi})")
    return plan.where(F.col("model_id").isin(lone))

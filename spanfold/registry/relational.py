"""Operators around the models: scans, joins, windows, grouping sets, set operations, streams."""

from __future__ import annotations

import uuid
from dataclasses import replace

from pyspark.sql import Window
from pyspark.sql import functions as F

from spanfold.functions.logistic import mixed
from spanfold.operators.baselines import scratch_gnb
from spanfold.operators.batch import cell_states, prefix_states, sliding_states
from spanfold.operators.combine import scan_state
from spanfold.plans.planner import Segment
from spanfold.registry.base import LINES, MODELS_SQL, events_sql, linreg_sql, query
from spanfold.registry.planning import models_frame
from spanfold.plans.ranges import Range
from spanfold.registry.state import _GNB_LINE_PARAMS, bayes_rows, linreg_rows, size_of, tidy_linreg
from spanfold.sources.layout import assign_position, build_directory, event_source, lineitem_source, work_dir
from spanfold.sources.points import CLASS3, DESIGN, GNB_EVENTS, GNB_LINES, LINEITEM_KEY, LINREG, Feature, ModelSpec, load, load_as, validate_key
from spanfold.streaming import states as S

VALUE = ModelSpec("gnb", "events", "event_id", (Feature("value", "value", 2, 1000),), "event_type")
CENTS = "cast(cast(value as decimal(18,2)) * 100 as bigint)"


@query("select l_orderkey, l_linenumber, l_partkey, l_suppkey, row_number() over (order by l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate) - 1 as pid from lineitem")
def assign_positions(spark, sf_dir):
    """Dense positions without a one-task sort."""
    return assign_position(load(spark, sf_dir, "lineitem"), LINEITEM_KEY).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "pid")


@query("select count(*) as n, count(distinct event_id) as distinct_keys, cast(0 as bigint) as null_keys, min(event_id) as min_key, max(event_id) as max_key, true as valid from events")
def validate_event_key(spark, sf_dir):
    return validate_key(load(spark, sf_dir, "events"), "event_id")


@query("select cast(l_orderkey // 500 as bigint) as bucket, min(l_orderkey) as min_key, max(l_orderkey) as max_key, count(*) as n, cast(sum(count(*)) over (order by l_orderkey // 500) as bigint) as cum_n from lineitem group by l_orderkey // 500")
def block_directory(spark, sf_dir):
    """Counts by block for a key with ties and gaps."""
    return build_directory(load(spark, sf_dir, "lineitem"), "l_orderkey", 500)


@query("select count(*) as n from lineitem where l_orderkey >= 1000 and l_orderkey < 3000")
def count_points_by_directory(spark, sf_dir):
    """Block-aligned counts need no scan of points."""
    blocks = build_directory(load(spark, sf_dir, "lineitem"), "l_orderkey", 500)
    return blocks.where("bucket >= 2 and bucket < 6").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


@query(f"with {LINES} select count(*) as n, cast(sum(v2) as bigint) as cents, min(pid) as lo, max(pid) as hi from full_pts, size where pid >= n // 5 and pid < 2 * n // 5")
def range_scan(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    n = size_of(source)
    rows = source.scan_range(n // 5, 2 * n // 5)
    return rows.agg(F.count("*").alias("n"), F.sum(F.expr("cast(cast(l_extendedprice as decimal(18,2)) * 100 as bigint)")).alias("cents"), F.min("pid").alias("lo"), F.max("pid").alias("hi"))


@query(events_sql("event_id >= n // 8 and event_id < n // 2"))
def multi_range_signed_scan(spark, sf_dir):
    """Two scans added, one taken off, in one job; cells that cancel are not read."""
    source = event_source(spark, sf_dir)
    n = size_of(source)
    segments = [Segment(1, "scan", 0, n // 2), Segment(1, "scan", n // 2, 3 * n // 4), Segment(-1, "scan", n // 2, 3 * n // 4), Segment(-1, "scan", 0, n // 8)]
    return bayes_rows(spark, scan_state(source, GNB_EVENTS, segments), GNB_EVENTS)


_CELLS = f"with size as (select count(*) as n from events), cells as (select cast(event_id // (n // 20) as int) as cell, event_type as class, count(*) as n, sum({CENTS}) as s0 from events, size where event_id < n // 20 * 20 group by event_id // (n // 20), event_type)"


def _event_cells(spark, sf_dir):
    source = event_source(spark, sf_dir)
    step = size_of(source) // 20
    return cell_states(source, VALUE, [i * step for i in range(21)]).select("cell", "class", "n", "s0")


@query(_CELLS + " select cell, class, cast(sum(n) over w as bigint) as n, cast(sum(s0) over w as bigint) as s0 from cells window w as (partition by class order by cell rows between unbounded preceding and current row)")
def prefix_state(spark, sf_dir):
    return prefix_states(_event_cells(spark, sf_dir), ["class"], ["n", "s0"])


@query(_CELLS + " select cell, class, cast(sum(n) over w as bigint) as n, cast(sum(s0) over w as bigint) as s0 from cells window w as (partition by class order by cell range between 6 preceding and current row)")
def sliding_week_state(spark, sf_dir):
    return sliding_states(_event_cells(spark, sf_dir), ["class"], ["n", "s0"], 7)


_QTY = "cast(sum(cast(cast(l_quantity as decimal(18,2)) * 100 as bigint)) as bigint)"


def _lattice(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").withColumn("c_", F.expr("cast(cast(l_quantity as decimal(18,2)) * 100 as bigint)"))


@query(f"select l_returnflag, l_linestatus, count(*) as n, {_QTY} as cents from lineitem group by rollup (l_returnflag, l_linestatus)")
def rollup_class_state(spark, sf_dir):
    return _lattice(spark, sf_dir).rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("c_").alias("cents"))


@query(f"select l_returnflag, l_linestatus, count(*) as n, {_QTY} as cents from lineitem group by cube (l_returnflag, l_linestatus)")
def cube_class_state(spark, sf_dir):
    return _lattice(spark, sf_dir).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("c_").alias("cents"))


@query(f"select l_returnflag, l_linestatus, count(*) as n, {_QTY} as cents from lineitem group by grouping sets ((l_returnflag), (l_linestatus))")
def grouping_sets_state(spark, sf_dir):
    _lattice(spark, sf_dir).createOrReplaceTempView("lattice_points")
    return spark.sql("select l_returnflag, l_linestatus, count(*) as n, sum(c_) as cents from lattice_points group by grouping sets ((l_returnflag), (l_linestatus))")


@query("""select event_type as class, round(avg(value) filter (where hour(ts) < 6), 4) as h0, round(avg(value) filter (where hour(ts) >= 6 and hour(ts) < 12), 4) as h1,
round(avg(value) filter (where hour(ts) >= 12 and hour(ts) < 18), 4) as h2, round(avg(value) filter (where hour(ts) >= 18), 4) as h3 from events group by event_type""")
def pivot_params(spark, sf_dir):
    rows = load(spark, sf_dir, "events").withColumn("part", F.concat(F.lit("h"), F.floor(F.hour("ts") / 6).cast("string")))
    return rows.groupBy(F.col("event_type").alias("class")).pivot("part", ["h0", "h1", "h2", "h3"]).agg(F.round(F.avg("value"), 4))


def _joined(spark, sf_dir, how):
    points = load(spark, sf_dir, "events")
    models = F.broadcast(models_frame(spark, sf_dir))  # 25 rows
    return points.join(models, (F.col("event_id") >= F.col("lo")) & (F.col("event_id") < F.col("hi")), how)


@query(f"with {MODELS_SQL} select event_type, count(*) as n from events where exists (select 1 from models where event_id >= lo and event_id < hi) group by event_type")
def semi_covered_points(spark, sf_dir):
    return _joined(spark, sf_dir, "left_semi").groupBy("event_type").agg(F.count("*").alias("n"))


@query(f"with {MODELS_SQL} select event_type, count(*) as n from events where not exists (select 1 from models where event_id >= lo and event_id < hi) group by event_type")
def anti_uncovered_points(spark, sf_dir):
    return _joined(spark, sf_dir, "left_anti").groupBy("event_type").agg(F.count("*").alias("n"))


@query(f"with {MODELS_SQL} select model_id, count(*) as n, cast(sum({CENTS}) as bigint) as cents from events join models on event_id >= lo and event_id < hi group by model_id")
def range_join_points(spark, sf_dir):
    """Points × model ranges by buckets of keys: an equality join first, then the exact range."""
    n = size_of(event_source(spark, sf_dir))
    width = max(1, n // 20)
    points = load(spark, sf_dir, "events").select("event_id", "value").withColumn("kb", F.floor(F.col("event_id") / width))
    models = models_frame(spark, sf_dir).withColumn("kb", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1) / width))))
    met = points.join(models, "kb").where("event_id >= lo and event_id < hi")
    return met.groupBy("model_id").agg(F.count("*").alias("n"), F.sum(F.expr(CENTS)).alias("cents"))


@query(f"""with {MODELS_SQL} select event_id, hi as last_hi from events asof left join (select distinct hi from models) on event_id >= hi""")
def asof_last_model(spark, sf_dir):
    """For each point the last model that ended before it: union and a running last value."""
    points = load(spark, sf_dir, "events").select(F.col("event_id").alias("k"), F.lit(1).alias("side"), F.lit(None).cast("long").alias("hi"))
    ends = models_frame(spark, sf_dir).select(F.col("hi").alias("k"), F.lit(0).alias("side"), F.col("hi"))
    # blocks of keys run side by side; a running maximum over one row a block carries the last end on
    width = max(1, size_of(event_source(spark, sf_dir)) // 64)
    both = points.unionByName(ends).withColumn("kb", F.floor(F.col("k") / width))
    tops = both.groupBy("kb").agg(F.max("hi").alias("top"))
    before = tops.select("kb", F.max("top").over(Window.orderBy("kb").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))
    order = Window.partitionBy("kb").orderBy("k", "side").rowsBetween(Window.unboundedPreceding, 0)
    seen = both.withColumn("seen", F.last("hi", ignorenulls=True).over(order)).where("side = 1")
    return seen.join(F.broadcast(before), "kb").select(F.col("k").alias("event_id"), F.coalesce("seen", "before").alias("last_hi"))


@query(f"""with {MODELS_SQL}, one as (select event_id from events join models on lo <= event_id and event_id < hi where model_id < 'm12'), two as (select event_id from events join models on lo <= event_id and event_id < hi where model_id >= 'm12')
select 'union' as op, count(*) as n from (select event_id from one union select event_id from two) union all select 'both', count(*) from (select event_id from one intersect select event_id from two)
union all select 'only first', count(*) from (select event_id from one except select event_id from two)""")
def set_ops_cells(spark, sf_dir):
    """Coverage of two model sets, point by point, by set operations."""
    points = load(spark, sf_dir, "events").select("event_id")
    models = models_frame(spark, sf_dir)
    sides = [points.join(F.broadcast(models.where(w)), (F.col("lo") <= F.col("event_id")) & (F.col("event_id") < F.col("hi"))).select("event_id") for w in ("model_id < 'm12'", "model_id >= 'm12'")]  # 25 rows
    one, two = sides
    parts = (("union", one.union(two).distinct()), ("both", one.intersect(two)), ("only first", one.distinct().exceptAll(two.distinct())))
    out = None
    for name, rows in parts:
        n = rows.agg(F.lit(name).alias("op"), F.count("*").alias("n"))
        out = n if out is None else out.unionByName(n)
    return out


@query("select event_type as class, count(*) as n, cast(sum(cast(props->>'$.k' as bigint)) as bigint) as s from events group by event_type")
def json_feature_state(spark, sf_dir):
    k = F.from_json("props", "k int")["k"]
    return load(spark, sf_dir, "events").groupBy(F.col("event_type").alias("class")).agg(F.count("*").alias("n"), F.sum(k.cast("long")).alias("s"))


@query("""select n_regionkey, count(*) as n, cast(sum(p_size) as bigint) as size, cast(sum(cast(cast(p_retailprice as decimal(18,2)) * 100 as bigint)) as bigint) as cents
from lineitem join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey group by n_regionkey""")
def enriched_join_state(spark, sf_dir):
    """Dimension features joined to the points; dimensions broadcast by their measured size."""
    lines = load(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey")
    part = load(spark, sf_dir, "part").select("p_partkey", "p_size", "p_retailprice")
    supp = load(spark, sf_dir, "supplier").join(load(spark, sf_dir, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_regionkey")
    rows = lines.join(part, F.col("l_partkey") == F.col("p_partkey")).join(supp, F.col("l_suppkey") == F.col("s_suppkey"))
    return rows.groupBy("n_regionkey").agg(F.count("*").alias("n"), F.sum("p_size").alias("size"), F.sum(F.expr("cast(cast(p_retailprice as decimal(18,2)) * 100 as bigint)")).alias("cents"))


@query(f"select o_orderpriority, count(*) as n, {_QTY} as cents from lineitem join orders on l_orderkey = o_orderkey group by o_orderpriority")
def sort_merge_enriched_state(spark, sf_dir):
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority").hint("merge")
    rows = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum(F.expr("cast(cast(l_quantity as decimal(18,2)) * 100 as bigint)")).alias("cents"))


def _timed_events(spark, sf_dir):
    return load(spark, sf_dir, "events").withColumn("at", F.col("ts").cast("timestamp"))


def _stamp(c):
    return F.unix_timestamp(c).alias(c)


@query(f"select cast(epoch(date_trunc('day', ts)) as bigint) as w_start, event_type as class, count(*) as n, cast(sum({CENTS}) as bigint) as s0, min(event_id) as key_lo, max(event_id) + 1 as key_hi from events group by 1, 2")
def tumbling_states(spark, sf_dir):
    """One exact state a day and class: what a stream's closed windows keep."""
    return S.window_states(_timed_events(spark, sf_dir), VALUE, "1 day").select(_stamp("w_start"), "class", "n", "s0", "key_lo", "key_hi")


@query(f"""select cast(epoch(date_trunc('day', ts)) as bigint) - 86400 * k as w_start, event_type as class, count(*) as n, cast(sum({CENTS}) as bigint) as s0 from events, (select unnest(range(3)) as k) group by 1, 2""")
def sliding_window_states(spark, sf_dir):
    """Overlapping windows of three days, one a day."""
    return S.window_states(_timed_events(spark, sf_dir), VALUE, "3 days", "1 day").select(_stamp("w_start"), "class", "n", "s0")


@query(f"""with o as (select *, case when lag(ts) over w is null or ts - lag(ts) over w >= interval 12 hour then 1 else 0 end as new from events window w as (partition by user_id order by ts, event_id)),
s as (select *, sum(new) over (partition by user_id order by ts, event_id rows unbounded preceding) as sid from o)
select user_id, epoch_us(min(ts)) // 1000000 as w_start, count(*) as n, cast(sum({CENTS}) as bigint) as s0 from s group by user_id, sid""")
def session_window_states(spark, sf_dir):
    out = S.session_states(_timed_events(spark, sf_dir), VALUE, "12 hours", "user_id")
    return out.select("user_id", _stamp("w_start"), "n", "s0")


@query(f"select cast(epoch(date_trunc('day', ts)) as bigint) as w_start, event_type as class, count(*) as n, cast(sum({CENTS}) as bigint) as s0 from events group by 1, 2")
def stream_equals_batch(spark, sf_dir):
    """The same windows from a stream over files with a watermark, and a last event to close them."""
    base = f"{work_dir(spark)}/streams/{uuid.uuid4().hex}"
    events = load(spark, sf_dir, "events")
    last = events.orderBy(F.desc("event_id")).limit(1).withColumn("ts", F.expr("ts + interval 30 days"))
    events.repartitionByRange(4, "event_id").write.parquet(f"{base}/in")
    last.write.mode("append").parquet(f"{base}/in")
    rows = S.event_stream(spark, f"{base}/in", events.schema, files=100)
    name = f"w_{uuid.uuid4().hex}"
    closed = S.window_states(rows, VALUE, "1 day", watermark="1 hour")
    closed.writeStream.outputMode("append").option("checkpointLocation", f"{base}/ck").format("memory").queryName(name).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name).select(_stamp("w_start"), "class", "n", "s0")


@query("select event_id, event_type, rank() over (partition by event_type order by value desc) as r, dense_rank() over (partition by event_type order by value desc) as dr, ntile(4) over (partition by event_type order by event_id) as q, lag(event_id) over (partition by event_type order by event_id) as before from events")
def window_ranks(spark, sf_dir):
    by_value, by_id = Window.partitionBy("event_type").orderBy(F.desc("value")), Window.partitionBy("event_type").orderBy("event_id")
    return load(spark, sf_dir, "events").select("event_id", "event_type", F.rank().over(by_value).alias("r"), F.dense_rank().over(by_value).alias("dr"), F.ntile(4).over(by_id).alias("q"), F.lag("event_id").over(by_id).alias("before"))


@query("select o_orderkey, o_custkey, o_orderstatus, o_totalprice from orders")
def file_round_trip(spark, sf_dir):
    """Orders through CSV, JSON and ORC with explicit schemas."""
    base = f"{work_dir(spark)}/formats/{uuid.uuid4().hex}"
    rows = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice")
    schema = "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double"
    rows.write.option("header", True).csv(f"{base}/csv")
    load_as(spark, f"{base}/csv", "csv", schema).write.json(f"{base}/json")
    load_as(spark, f"{base}/json", "json", schema).write.orc(f"{base}/orc")
    return load_as(spark, f"{base}/orc", "orc", schema)


@query("select cast(month(ts) as int) as month, cast(day(ts) as int) as day, count(*) as n, cast(epoch_us(min(ts)) as bigint) as first_us from events group by 1, 2")
def date_features(spark, sf_dir):
    rows = load(spark, sf_dir, "events")
    return rows.groupBy(F.month("ts").alias("month"), F.dayofmonth("ts").alias("day")).agg(F.count("*").alias("n"), F.unix_micros(F.min("ts").cast("timestamp")).alias("first_us"))


@query("select lang, cast(sum(len(regexp_extract_all(lower(text), '[a-z]+'))) as bigint) as words, cast(sum(length(text)) as bigint) as chars from documents group by lang")
def string_counts(spark, sf_dir):
    return load(spark, sf_dir, "documents").groupBy("lang").agg(F.sum(F.regexp_count(F.lower("text"), F.lit("[a-z]+"))).alias("words"), F.sum(F.length("text")).cast("long").alias("chars"))


@query("select label, round(sum(list_sum(list_transform(embedding, lambda x: cast(x as double) * x))), 4) as norms, round(sum(cast(embedding[1] as double) + embedding[2]), 4) as firsts from embeddings group by label")
def array_functions(spark, sf_dir):
    rows = load(spark, sf_dir, "embeddings")
    norm = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    first = F.element_at("embedding", 1).cast("double") + F.element_at("embedding", 2).cast("double")
    return rows.groupBy("label").agg(F.round(F.sum(norm), 4).alias("norms"), F.round(F.sum(first), 4).alias("firsts"))


@query("select event_type as class, k as feature, cast(sum(v) as bigint) as s from (select event_type, unnest(['k', 'user']) as k, unnest([cast(props->>'$.k' as bigint), user_id % 10]) as v from events) group by 1, 2")
def map_state(spark, sf_dir):
    """Class states as maps, unfolded to rows."""
    rows = load(spark, sf_dir, "events")
    per = rows.groupBy(F.col("event_type").alias("class")).agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k"), F.sum(F.col("user_id") % 10).alias("user"))
    return per.select("class", F.explode(F.create_map(F.lit("k"), F.col("k"), F.lit("user"), F.col("user"))).alias("feature", "s"))


@query("select event_type, value, event_id from events order by value desc, event_id limit 10")
def top_values(spark, sf_dir):
    """A top-ten report."""
    return load(spark, sf_dir, "events").select("event_type", "value", "event_id").orderBy(F.desc("value"), "event_id").limit(10)


_HASH = {"h1": "((event_id % 2147483648) * 2654435761) % 2147483648", "h2": "(xor(h1, h1 >> 15) * 2246822519) % 2147483648", "h3": "xor(h2, h2 >> 13)"}


@query(f"""with a as (select event_id, event_type, ({_HASH['h1']})::bigint as h1 from events), b as (select *, ({_HASH['h2']})::bigint as h2 from a)
select event_id, event_type from b where ({_HASH['h3']}) < 214748364""")
def sample_by_key(spark, sf_dir):
    """A repeatable one-in-ten sample by hashed key (a sampling operator)."""
    return load(spark, sf_dir, "events").where(mixed(F.col("event_id")) < 214748364).select("event_id", "event_type")


@query()
def approx_covered_points(spark, sf_dir):
    return _joined(spark, sf_dir, "inner").agg(F.approx_count_distinct("event_id", 0.01).alias("covered"))


@query(f"with {LINES} select l_returnflag, count(*) as n, round(avg(2.0 + 0.5 * v1 / 100.0 + 3 * v3 / 100.0), 6) as mean_linear, round(avg(1 / (1 + exp(-(0.1 - 0.02 * v1 / 100.0 + 4 * v3 / 100.0)))), 6) as mean_logit from full_pts group by l_returnflag")
def sql_predictors(spark, sf_dir):
    """Predictions through registered pandas functions in SQL."""
    from spanfold.functions.udfs import register_predictors

    register_predictors(spark, [2.0, 0.5, 3.0], [0.1, -0.02, 4.0])
    load(spark, sf_dir, "lineitem").createOrReplaceTempView("line_points")
    return spark.sql(
        "select l_returnflag, count(*) as n, round(avg(predict_linear(array(1D, l_quantity, l_discount))), 6) as mean_linear, "
        "round(avg(predict_logit(array(1D, l_quantity, l_discount))), 6) as mean_logit from line_points group by l_returnflag"
    )


@query(f"with {_GNB_LINE_PARAMS} select c3 as prediction, count(*) as n, count_if(truth = c3) as correct from top where rk = 1 group by c3")
def sql_bayes_predictor(spark, sf_dir):
    """Gaussian naive Bayes as a SQL function: trained on the first half, applied to the second."""
    from spanfold.functions.udfs import register_bayes

    source = lineitem_source(spark, sf_dir)
    n = size_of(source)
    spec = replace(GNB_LINES, features=(DESIGN[0], DESIGN[2], DESIGN[3]))
    register_bayes(spark, scratch_gnb(source, spec, 0, n // 2))
    source.scan_range(n // 2, n).withColumn("truth", F.expr(CLASS3)).createOrReplaceTempView("bayes_points")
    return spark.sql("select p as prediction, count(*) as n, count_if(truth = p) as correct from (select truth, predict_nb(array(l_quantity, l_discount, l_tax)) as p from bayes_points) group by p")


@query("""
with k as (select event_type, min(event_id) as first, max(event_id) + 1 as stop, greatest(1, (max(event_id) + 1 - min(event_id)) // 300) as m from events group by event_type)
select event_type, cast(i as int) as seq, first + i * 300 as lo, case when i = m - 1 then stop else first + (i + 1) * 300 end as hi from (select *, unnest(range(m)) as i from k)""")
def chunk_table_function(spark, sf_dir):
    """Chunks of 300 keys over the events of each type, by the table function on a table of ranges."""
    from spanfold.functions.udfs import register_table_functions

    register_table_functions(spark, [])
    load(spark, sf_dir, "events").groupBy("event_type").agg(F.min("event_id").alias("first"), (F.max("event_id") + 1).alias("stop")).createOrReplaceTempView("type_ranges")
    return spark.sql("select event_type, c.seq, c.lo, c.hi from type_ranges r, lateral chunk_ranges(r.first, r.stop, 300) c")


@query(linreg_sql("pid >= n // 10 and pid < n * 9 // 10"))
def linreg_state_clustered_cells(spark, sf_dir):
    """A state summed from cells: additive at every level."""
    source = lineitem_source(spark, sf_dir)
    n = size_of(source)
    cells = cell_states(source, LINREG, [n // 10, n // 3, n // 2, n * 9 // 10])
    sums = cells.agg(*[F.sum(c).alias(c) for c in cells.columns if c != "cell"])
    return tidy_linreg(sums, LINREG)


@query(events_sql("event_id >= n // 2"))
def store_round_trip(spark, sf_dir):
    """Three kept models written, one dropped, compacted, opened again and subtracted."""
    from spanfold.operators.combine import build
    from spanfold.sources.store import ModelStore

    source = event_source(spark, sf_dir)
    n = size_of(source)
    base = f"{work_dir(spark)}/stores/{uuid.uuid4().hex}"
    store = ModelStore(spark, base)
    for lo, hi in ((0, n), (0, n // 2), (n // 4, n // 2)):
        store.put(GNB_EVENTS, Range(lo, hi), build(source, GNB_EVENTS, lo, hi).state, source.version)
        store.flush()
    store.drop(GNB_EVENTS, next(m for m in store.models(GNB_EVENTS) if m.lo))
    again = ModelStore.open(spark, store.compact(f"{base}-compact").path)
    whole, half = sorted(again.models(GNB_EVENTS), key=lambda m: -m.hi)
    states = again.fetch([whole.model_id, half.model_id], source.version)
    return bayes_rows(spark, states[whole.model_id].combine(states[half.model_id], -1), GNB_EVENTS)


def _late(spark, source, spec, spans, late):
    """States of kept models built without some points, after these came in late: of an opened store."""
    from spanfold.operators.batch import range_states
    from spanfold.sources.points import PointSource
    from spanfold.sources.store import ModelStore

    base = f"{work_dir(spark)}/stores/{uuid.uuid4().hex}"
    store = ModelStore(spark, base)
    early = PointSource(source.df.where(~late), source.key, source.version, source.bucket_width, source.directory)
    for r, state in zip(spans, range_states(early, spec, spans)):
        store.put(spec, r, state, source.version)
    S.insert_late(store, spec, source.scan_range(min(r.lo for r in spans), max(r.hi for r in spans)).where(late))
    again = ModelStore.open(spark, base)
    found = again.fetch([m.model_id for m in again.models(spec)])
    return {m.range: found[m.model_id] for m in again.models(spec)}


@query(events_sql("event_id < n // 3"))
def late_points_inserted(spark, sf_dir):
    """Two overlapping kept models built without every seventh point take these in when they come
    late; the store has them when it is opened again."""
    source = event_source(spark, sf_dir)
    n = size_of(source)
    spans = [Range(0, n // 3), Range(n // 6, n // 2)]
    return bayes_rows(spark, _late(spark, source, GNB_EVENTS, spans, F.expr("event_id % 7 = 0"))[spans[0]], GNB_EVENTS)


@query(linreg_sql("pid >= n // 6 and pid < n // 2"))
def late_points_inserted_linreg(spark, sf_dir):
    """The same for linear regression."""
    source = lineitem_source(spark, sf_dir)
    n = size_of(source)
    spans = [Range(0, n // 3), Range(n // 6, n // 2)]
    return linreg_rows(spark, _late(spark, source, LINREG, spans, F.expr("pid % 7 = 0"))[spans[1]])

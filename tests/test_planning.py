"""Ranges, relevance and plans, without Spark."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from spanfold.functions.logistic import distance_bound, make_chunks
from spanfold.plans import planner as P
from spanfold.plans.costs import AffineCost, BlockCost, Directory, LinearCost, check_monotone, fit_cost
from spanfold.plans.ranges import Range, contains, gaps, hull, meet, minus, overlaps, union
from spanfold.plans.relevance import DescriptorIndex, Kept, group_models, relevant_by_closure, relevant_contained

EXAMPLE = dict(zip("abcdef", (1000, 2000, 3500, 6000, 8500, 9000)))


def example(costs=(1, 1, 1, 1)):
    e = EXAMPLE
    ends = ((e["a"], e["c"]), (e["a"], e["b"]), (e["b"], e["d"]), (e["d"], e["f"]))
    return [Kept(lo, hi, f"D{i + 1}", float(c)) for i, ((lo, hi), c) in enumerate(zip(ends, costs))], Range(e["c"], e["e"])


def random_set(rng, span=60, most=5):
    models = []
    for i in range(rng.randint(0, most)):
        lo = rng.randrange(span - 1)
        models.append(Kept(lo, rng.randint(lo + 1, span), f"m{i}", float(rng.choice([0, 1, 5, 20]))))
    lo = rng.randrange(span - 1)
    return models, Range(lo, rng.randint(lo + 1, span))


def test_range_algebra():
    a, b = Range(0, 10), Range(10, 20)
    assert not overlaps(a, b) and overlaps(a, Range(9, 11)) and contains(a, Range(3, 3))
    assert minus(Range(0, 10), Range(3, 5)) == [Range(0, 3), Range(5, 10)] and minus(a, b) == [a] and minus(a, a) == []
    assert meet(a, Range(5, 30)) == Range(5, 10) and meet(a, b).empty and hull(a, b) == Range(0, 20)
    assert union([b, a, Range(30, 31)]) == [Range(0, 20), Range(30, 31)]
    assert gaps(Range(0, 40), [Range(5, 10), Range(8, 20)]) == [Range(0, 5), Range(20, 40)]
    assert 9 in a and 10 not in a


def test_grouping_of_the_example_and_edge_cases():
    models, _ = example()
    assert [(g, {m.model_id for m in own}) for g, own in group_models(models)] == [(Range(1000, 6000), {"D1", "D2", "D3"}), (Range(6000, 9000), {"D4"})]
    assert group_models([]) == []
    chain = [Kept(0, 10, "x"), Kept(5, 15, "y"), Kept(14, 30, "z"), Kept(40, 50, "p"), Kept(40, 50, "q"), Kept(60, 160, "big"), Kept(80, 90, "in")]
    assert [g for g, _ in group_models(chain)] == [Range(0, 30), Range(40, 50), Range(60, 160)]
    index = DescriptorIndex(chain)
    assert index.query(Range(30, 40)) == [] and index.query(Range(160, 170)) == [] and len(index.query(Range(29, 41))) == 5


def test_relevance_by_groups_is_the_closure():
    rng = random.Random(1)
    for _ in range(500):
        models, ask = random_set(rng, most=9)
        index = DescriptorIndex()
        order = list(models)
        rng.shuffle(order)
        for m in order:
            index.add(m)
        assert set(index.query(ask)) == relevant_by_closure(models, ask)
        assert index.groups() == group_models(models)
        if models:
            index.remove(models[0])
            assert index.groups() == group_models(models[1:])
        assert relevant_contained(models, ask) == {m for m in models if ask.lo <= m.lo and m.hi <= ask.hi}


@pytest.mark.parametrize("costs, cost, path", [((1, 1, 1, 1), 504, "cabdfe"), ((1000, 1000, 1, 1), 2002, "cbdfe"), ((1000, 1000, 1200, 1), 3001, "cdfe"), ((10000,) * 4, 5000, "ce")])
@pytest.mark.parametrize("graph", ["dense", "sparse"])
def test_example_plans(costs, cost, path, graph):
    models, ask = example(costs)
    plan = P.best_plan(models, ask, graph=graph)
    assert plan.cost == cost and plan.nodes == [EXAMPLE[c] for c in path]
    assert P.check_net(plan.segments, ask)
    assert P.best_plan(models, ask, directed=True).cost == 5000


def test_merge_cost_is_paid_between_segments():
    models, ask = example()
    plan = P.best_plan(models, ask, LinearCost(merge=0.5))
    assert plan.cost == 506 and P.plan_cost(plan.segments, LinearCost(merge=0.5)) == 506


def test_plans_are_optimal_and_sound():
    rng = random.Random(2)
    better = 0
    for n in range(400):
        models, ask = random_set(rng, most=3)
        cost = rng.choice([LinearCost(merge=rng.choice([0, 1])), AffineCost(setup=7.0, merge=rng.choice([0.0, 2.0]))])
        for directed in (False, True):
            exact = P.brute_force_cost(models, ask, cost, directed=directed) if n < 120 else None
            dense = P.best_plan(models, ask, cost, directed=directed, graph="dense")
            sparse = P.best_plan(models, ask, cost, directed=directed, graph="sparse")
            assert dense.cost == pytest.approx(sparse.cost)
            if exact is not None:
                assert dense.cost == pytest.approx(exact)
            if directed:
                assert P.best_plan(models, ask, cost, directed=True, graph="dag").cost == pytest.approx(dense.cost)
            for p in (dense, sparse):
                assert P.check_net(p.segments, ask) and P.plan_cost(p.segments, cost) == pytest.approx(p.cost)
        both = P.best_plan(models, ask, cost)
        add = P.best_plan(models, ask, cost, directed=True)
        better += both.cost < add.cost - 1e-9
        pruned = P.best_plan(DescriptorIndex(models).query(ask), ask, cost)
        assert pruned.cost == pytest.approx(both.cost)
        assert both.cost <= add.cost + 1e-9 and both.cost <= P.scan_plan(ask, cost).cost + 1e-9
        for other in (P.greedy_cover(models, ask, cost), P.largest_overlap_plan(models, ask, cost)):
            assert P.check_net(other.segments, ask) and other.cost >= both.cost - 1e-9
        assert P.greedy_cover(models, ask, cost).cost >= add.cost - 1e-9
        more = models + [Kept(ask.lo, min(ask.hi, ask.lo + 5), "extra", 0.0)]
        assert P.best_plan(more, ask, cost).cost <= both.cost + 1e-9
    assert better > 10


def test_k_cheapest_plans():
    from itertools import permutations

    rng = random.Random(7)
    for _ in range(40):
        models, ask = random_set(rng, most=2)
        weight = {(u, v): c for u, v, _, _, c in P.plan_edges(models, ask)}
        inner = sorted({x for e in weight for x in e} - {ask.lo, ask.hi})
        paths = [(ask.lo, *mid, ask.hi) for k in range(len(inner) + 1) for mid in permutations(inner, k)]
        costs = sorted(sum(weight[e] for e in zip(p, p[1:])) for p in paths)
        plans = P.k_best_plans(models, ask, 5)
        assert [p.cost for p in plans] == pytest.approx(costs[:5])
        assert all(P.check_net(p.segments, ask) for p in plans) and len({tuple(p.nodes) for p in plans}) == len(plans)


def test_equal_descriptors_and_cheap_scans():
    ask = Range(0, 10)
    assert P.best_plan([Kept(0, 10, "x", 9.0), Kept(0, 10, "y", 2.0)], ask).models == ["y"]
    assert P.best_plan([Kept(0, 10, "x", 50.0)], ask).models == []
    assert P.best_plan([], Range(5, 5)).segments == []


def test_shared_setup_is_paid_once():
    ask = Range(0, 100)
    models = [Kept(10, 40, "x", 0.0), Kept(50, 90, "y", 0.0)]
    cost = AffineCost(setup=30.0, model=0.0)
    assert P.best_plan(models, ask, cost, graph="shared").cost == 30 + 10 + 10 + 10
    assert P.best_plan([Kept(0, 100, "all", 5.0)], ask, cost, graph="shared").cost == 5


def test_opposite_scans_cancel():
    seg = [P.Segment(1, "scan", 0, 50), P.Segment(-1, "scan", 20, 50), P.Segment(1, "model", 20, 60, "m")]
    kept = P.cancel_scans(seg)
    assert [(s.lo, s.hi, s.sign) for s in kept if s.kind == "scan"] == [(0, 20, 1)]


def test_costs_and_directory():
    for c in (LinearCost(), AffineCost(), BlockCost(block=10)):
        assert check_monotone(c)
    f = fit_cost([(0, 200.0), (1000, 300.0), (2000, 400.0)])
    assert f.setup == pytest.approx(200) and f.per_point == pytest.approx(0.1)
    d = Directory([0, 100, 500], [10, 40, 5], [50, 200, 501])
    assert d.count(0, 1000) == 55 and d.count(100, 150) == 20 and d.count(200, 500) == 0
    assert Directory.dense(10).count(3, 7) == 4
    with pytest.raises(ValueError):
        P.best_plan([], Range(0, 9), BlockCost(block=2), graph="sparse")


def test_chunks():
    assert make_chunks(0, 10, 4) == [Range(0, 4), Range(4, 10)]
    assert make_chunks(0, 10, 4, tail="own") == [Range(0, 4), Range(4, 8), Range(8, 10)]
    assert make_chunks(0, 10, 4, tail="drop") == [Range(0, 4), Range(4, 8)]
    assert make_chunks(0, 3, 4) == [Range(0, 3)] and make_chunks(5, 5, 4) == []
    assert make_chunks(3, 17, 5, tail="own", anchor="grid") == [Range(3, 5), Range(5, 10), Range(10, 15), Range(15, 17)]
    assert make_chunks(3, 17, 5, anchor="grid") == [Range(3, 10), Range(10, 17)]
    for tail in ("merge", "own"):
        for anchor in ("request", "grid"):
            got = make_chunks(7, 101, 10, tail, anchor)
            assert got[0].lo == 7 and got[-1].hi == 101 and all(a.hi == b.lo for a, b in zip(got, got[1:]))


def test_bound_falls_with_chunk_and_regulariser():
    assert distance_bound(3.0, 0.1, 1000, 10000, 0.05) < distance_bound(3.0, 0.1, 100, 10000, 0.05)
    assert distance_bound(3.0, 1.0, 100, 10000, 0.05) == pytest.approx(distance_bound(3.0, 0.1, 100, 10000, 0.05) / 10)


def test_workload_trends():
    from spanfold import workloads as W

    n = 600_000
    by = W.gain_by_coverage(n, (0, 40, 90), count=80)
    assert [round(r["actual"]) for r in by] == [0, 40, 90]
    assert by[0]["best"] == pytest.approx(1) and by[0]["best"] > by[1]["best"] > by[2]["best"] and by[2]["points_share"] <= 0.5
    assert all(r["best"] <= r["add_only"] + 1e-9 <= r["greedy"] + 2e-9 for r in by)
    best = {}
    for request in (50_000, 100_000):
        rows = W.gain_by_model_size(n, W.Sizes("fixed", request), 400.0, count=60)
        for k in ("best", "add_only"):
            sizes = [r["size"] for r in rows]
            best[request, k] = sizes[int(np.argmin([r[k] for r in rows]))]
            assert sizes[0] < best[request, k] < sizes[-1]
        assert best[request, "add_only"] <= best[request, "best"]
    assert best[100_000, "best"] >= best[50_000, "best"]
    small = {m: W.gain_by_coverage(n, (90,), s, W.SMALL, count=30, seed=1)[0] for m, s in W.MODEL_SETS.items()}
    assert small["M1"]["best"] < small["M2"]["best"] < small["M3"]["best"] and small["M4"]["add_only"] == pytest.approx(1)
    large = {m: W.gain_by_coverage(n, (90,), s, W.LARGE, count=15, seed=1)[0] for m, s in W.MODEL_SETS.items()}
    assert all(r["best"] < 0.6 for r in large.values())


def test_requests_are_seeded_and_inside():
    from spanfold import workloads as W

    a, b = W.requests(10_000, 50, W.NORMAL, seed=4), W.requests(10_000, 50, W.NORMAL, seed=4)
    assert a == b and all(0 <= r.lo < r.hi <= 10_000 for r in a)
    grid = W.place_models(600_000, 20, W.Sizes("fixed", 5000), grid=True)
    assert len(grid) == 200 and W.actual_coverage(600_000, grid) == pytest.approx(20)
    deep = W.place_models(60_000, 50, W.NORMAL, depth=2.0)
    assert sum(r.hi - r.lo for r in deep) >= 2 * 60_000


@pytest.mark.parametrize("name", ["chunk_ranges", "chunk_table_function", "workload_gain_by_coverage", "workload_gain_by_model_size", "workload_model_sets"])
def test_planning_queries_follow_their_table(spark, tiny, tmp_path, monkeypatch, name):
    """The same number of rows, other keys: these queries answer from the table, not from its size."""
    from spanfold import queries as Q
    from spanfold import workloads as W

    monkeypatch.setattr(W.coverage_case, "__defaults__", (W.NORMAL, W.NORMAL, 20, W.LinearCost(), 0, ()))
    monkeypatch.setattr(W, "MODEL_SIZES", (20_000, 50_000))
    monkeypatch.setattr(W, "COVERAGES", (40,))
    lines, events = (spark.read.parquet(f"{tiny}/{t}.parquet") for t in ("lineitem", "events"))
    crowded = F.when(F.col("l_orderkey") % 10 == 0, F.col("l_orderkey")).otherwise((F.col("l_orderkey") / 4).cast("long"))
    lines.withColumn("l_orderkey", crowded).write.parquet(f"{tmp_path}/lineitem.parquet")
    kind = F.when(F.col("event_id") < 500, "early").otherwise("late")
    events.withColumn("event_type", kind).withColumn("value", F.col("value") + 1).write.parquet(f"{tmp_path}/events.parquet")
    given, other = (sorted(map(tuple, Q.queries()[name](spark, d).collect())) for d in (tiny, str(tmp_path)))
    assert given and other and given != other


def test_costs_count_the_points_of_the_table(spark, tiny):
    from spanfold import workloads as W
    from spanfold.registry.planning import _orders_of_lines

    directory, n = _orders_of_lines(spark, tiny)
    keys = np.array([r[0] for r in spark.read.parquet(f"{tiny}/lineitem.parquet").select("l_orderkey").collect()])
    assert n == keys.max() + 1 and directory.count(0, n) == len(keys)
    asks = W.requests(n, 30, W.NORMAL, seed=2, unit=n / 1e6)
    assert [directory.count(*r) for r in asks] == [((keys >= r.lo) & (keys < r.hi)).sum() for r in asks]
    models = W.place_models(n, 50, W.NORMAL, seed=4)
    row = W.planned_frame(spark, directory, [W.Case((("coverage", 50),), models, asks)]).first()
    index = W.DescriptorIndex(W.as_kept(models))
    want = np.mean([W.strategies(index, directory, r, W.LinearCost()) for r in asks], axis=0)
    assert np.allclose([row[c] for c in W.STRATEGIES], want) and row.requests == 30
    below = np.zeros(n, dtype=bool)
    for m in models:
        below[m.lo : m.hi] = True
    assert row.actual == pytest.approx(100 * below[keys].mean())
    assert W.strategies(index, directory, Range(n + 5, n + 9), W.LinearCost())[:5] == (1.0,) * 5

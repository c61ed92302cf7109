"""States, models and the engine on the smallest tables."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.engine import Engine
from spanfold.functions import bayes, linear, logistic
from spanfold.operators import baselines as B
from spanfold.operators import combine as C
from spanfold.operators import measures as M
from spanfold.operators.batch import range_states
from spanfold.plans.costs import LinearCost
from spanfold.plans.planner import best_plan, scan_plan
from spanfold.plans.ranges import Range
from spanfold.sources import layout as L
from spanfold.sources.points import CLASS2, DESIGN, GNB_EVENTS, LINREG, LOGIT, PointSource, check_rows, load, validate_key
from spanfold.sources.store import ModelStore


@pytest.fixture(scope="module")
def lines(spark, tiny):
    return L.lineitem_source(spark, tiny)


@pytest.fixture(scope="module")
def events(spark, tiny):
    return L.event_source(spark, tiny)


@pytest.fixture(scope="module")
def table(lines):
    """Design matrix, target and class of all points in key order, as numpy."""
    cols = [f.real().alias(f.name) for f in DESIGN] + [LINREG.target.real().alias("y"), F.expr(CLASS2).alias("c")]
    p = lines.df.select("pid", *cols).toPandas().sort_values("pid")
    x = np.hstack([np.ones((len(p), 1)), p[[f.name for f in DESIGN]].to_numpy(float)])
    return x, p["y"].to_numpy(float), p["c"].to_numpy(float)


def test_state_and_weights(lines, table):
    x, y, _ = table
    state = C.build(lines, LINREG, 1000, 4000).state
    z = np.hstack([x, y[:, None]])[1000:4000]
    assert np.allclose(state.matrix(), z.T @ z, rtol=1e-12) and state.n == 3000
    w = linear.linreg_solve(state, 2.0)
    assert np.allclose(w, np.linalg.solve(x[1000:4000].T @ x[1000:4000] + 2 * np.eye(11), x[1000:4000].T @ y[1000:4000]), atol=1e-6)
    fast = linear.linreg_state(lines.scan_range(1000, 4000), LINREG, arithmetic="double")
    assert np.allclose(fast.matrix(), state.matrix(), rtol=1e-9)
    free = linear.linreg_solve(state, 5.0, penalize_intercept=False, intercept=True)
    assert not np.allclose(free, linear.linreg_solve(state, 5.0))
    a = linear.linreg_anova(state, linear.linreg_solve(state), True)
    e = y[1000:4000] - x[1000:4000] @ linear.linreg_solve(state)
    assert a["sse"] == pytest.approx(e @ e, rel=1e-6) and a["r2"] > 0.97


def test_library_weights(lines, table):
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import LinearRegression

    x, y, _ = table
    names = [f.name for f in DESIGN]
    rows = VectorAssembler(inputCols=names, outputCol="features").transform(lines.df.select(*[f.real().alias(f.name) for f in DESIGN], LINREG.target.real().alias("label")))
    ridge = 3.0
    fit = LinearRegression(solver="normal", standardization=False, fitIntercept=False, regParam=ridge / len(y) * np.std(y)).fit(rows)
    spec = replace(LINREG, intercept=False)
    assert np.allclose(B.scratch_linreg(lines, spec, 0, len(y), ridge), fit.coefficients.toArray(), atol=1e-6)


def test_singular_state_is_solved(lines):
    spec = replace(LINREG, features=(DESIGN[0], replace(DESIGN[0], name="again")))
    w = linear.linreg_solve(C.build(lines, spec, 0, 500).state)
    assert np.isfinite(w).all() and w[1] == pytest.approx(w[2], rel=1e-3)


def test_adding_and_removing_is_the_identity(lines, events):
    for source, spec in ((lines, LINREG), (events, GNB_EVENTS)):
        a, b = C.build(source, spec, 100, 400).state, C.build(source, spec, 400, 650).state
        assert M.state_distance(a.combine(b).combine(b, -1), a) == 0
        assert M.state_distance(a.combine(b), b.combine(a)) == 0
        assert M.state_distance(a.combine(b), C.build(source, spec, 100, 650).state) == 0


def test_single_points(lines, events):
    cols = LINREG.columns() + [LINREG.target]
    row = list(lines.scan_range(50, 51).select(*[(c.integer() / F.lit(c.unit)).alias(f"v{i}") for i, c in enumerate(cols)]).first())
    state = linear.linreg_add(linear.empty_state(LINREG), LINREG, row[1:-1], row[-1])
    assert M.state_distance(state, C.build(lines, LINREG, 50, 51).state) == 0
    assert M.state_distance(linear.linreg_remove(state, LINREG, row[1:-1], row[-1]), linear.empty_state(LINREG)) == 0
    e = events.scan_range(7, 8).select(*[f.real().alias(f.name) for f in GNB_EVENTS.features], "event_type").first()
    one = bayes.point_state(GNB_EVENTS, list(e)[:4], e.event_type)
    assert M.state_distance(one, C.build(events, GNB_EVENTS, 7, 8).state) == 0
    assert one.combine(one, -1).classes == {}


def test_three_forms_of_overlap_agree(events):
    a, b = C.build(events, GNB_EVENTS, 0, 600), C.build(events, GNB_EVENTS, 450, 900)
    want = C.build(events, GNB_EVENTS, 0, 900).state
    for via in ("minus_intersection", "first_plus_rest", "second_plus_rest", "auto"):
        assert M.state_distance(C.combine(a, b, events, GNB_EVENTS, via).state, want) == 0
    with pytest.raises(ValueError):
        C.combine(a, C.build(events, GNB_EVENTS, 700, 800), events, GNB_EVENTS)
    with pytest.raises(ValueError):
        a.state.combine(linear.empty_state(LINREG))
    cut = C.subtract(C.build(events, GNB_EVENTS, 0, 900), a)
    assert cut.range == Range(600, 900) and M.state_distance(cut.state, C.build(events, GNB_EVENTS, 600, 900).state) == 0
    moved = C.adjust(a, 300, 700, events, GNB_EVENTS)
    assert M.state_distance(moved.state, C.build(events, GNB_EVENTS, 300, 700).state) == 0


def test_moving_a_model_by_equal_counts(lines, events):
    """As many points come in as go out, in all and in a class: the net count is 0, the sums are not."""
    for source, spec in ((lines, LINREG), (events, GNB_EVENTS)):
        moved = C.adjust(C.build(source, spec, 40, 90), 20, 70, source, spec)
        assert M.state_distance(moved.state, C.build(source, spec, 20, 70).state) == 0
    classes = [r.event_type for r in events.df.orderBy("event_id").select("event_type").limit(60).collect()]
    i = next(i for i in range(1, 40) if classes[i - 1] == classes[i + 9])
    moved = C.adjust(C.build(events, GNB_EVENTS, i, i + 10), i - 1, i + 9, events, GNB_EVENTS)
    assert M.state_distance(moved.state, C.build(events, GNB_EVENTS, i - 1, i + 9).state) == 0


def test_library_bayes(spark, events):
    from pyspark.ml.classification import NaiveBayes
    from pyspark.ml.feature import StringIndexer, VectorAssembler

    names = [f.name for f in GNB_EVENTS.features]
    rows = events.df.select(*[f.real().alias(f.name) for f in GNB_EVENTS.features], "event_type")
    rows = StringIndexer(inputCol="event_type", outputCol="label", stringOrderType="alphabetAsc").fit(rows).transform(rows)
    rows = VectorAssembler(inputCols=names, outputCol="features").transform(rows)
    gauss = NaiveBayes(modelType="gaussian").fit(rows)
    n = rows.count()
    p = B.scratch_gnb(events, GNB_EVENTS, 0, n)
    for i, c in enumerate(sorted(p)):
        assert np.allclose(p[c][1], gauss.theta.toArray()[i]) and np.allclose(p[c][2], gauss.sigma.toArray()[i], rtol=1e-5)
    multi = NaiveBayes(modelType="multinomial", smoothing=1.0).fit(rows)
    spec = replace(GNB_EVENTS, kind="mnb", features=GNB_EVENTS.features[1:])
    counts = VectorAssembler(inputCols=names[1:], outputCol="f2").transform(rows)
    multi = NaiveBayes(modelType="multinomial", smoothing=1.0, featuresCol="f2").fit(counts)
    theta = B.scratch_mnb(events, spec, 0, n)
    for i, c in enumerate(sorted(theta)):
        assert np.allclose(np.log(theta[c][1]), multi.theta.toArray()[i])


def test_zero_variance_and_ties(spark):
    df = spark.createDataFrame([(0, "x", 5), (1, "x", 5), (2, "y", 7), (3, "y", 9)], "k long, c string, v int")
    from spanfold.sources.points import Feature, ModelSpec

    spec = ModelSpec("gnb", "t", "k", (Feature("v", "v", 0, 10),), "c")
    params = bayes.gnb_params(bayes.bayes_state(df, spec))
    assert params["x"][2] == [0.0]
    got = {r.v: r.prediction for r in bayes.predict(bayes.featured(df, spec), bayes.gnb_scores(spec, params)).collect()}
    assert got[9] == "y" and got[7] == "y"
    assert bayes.gnb_params(bayes.bayes_state(df, spec), var_floor=0.5)["x"][2] == [0.5]
    coefficient = df.select(bayes.mnb_log_likelihood(spec, [0.5], True).alias("l")).first().l
    assert coefficient == pytest.approx(5 * np.log(0.5))


def test_descriptors_key_and_nulls(spark, lines, tiny):
    n = lines.df.count()
    assert lines.df.agg(F.min("pid"), F.max("pid"), F.count_distinct("pid")).first()[:] == (0, n - 1, n)
    assert validate_key(lines.df, "pid").first().valid and not validate_key(load(spark, tiny, "lineitem"), "l_orderkey").first().valid
    bad = spark.createDataFrame([(1, None, 1.0)], "pid long, l_quantity double, y double")
    spec = replace(LINREG, features=(DESIGN[0],), target=replace(LINREG.target, expr="y"))
    with pytest.raises(Exception, match="null"):
        check_rows(bad, spec).collect()
    assert check_rows(bad, replace(spec, null_policy="drop")).count() == 0


def test_clustered_scan_prunes(lines):
    n = lines.df.count()
    few = lines.scan_range(n // 2, n // 2 + 10)
    text = few._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(bucket" in text.replace("\n", " ") or "bucket" in text.split("PartitionFilters")[1].split("]")[0]
    assert "PushedFilters" in text and "GreaterThanOrEqual(pid" in text
    assert len(few.inputFiles()) >= len(few.select("pid").distinct().where("pid >= 0").inputFiles())
    plan = linear.linreg_states(few, LINREG)._jdf.queryExecution().executedPlan().toString()
    assert "HashAggregate" in plan and "CartesianProduct" not in plan


def test_every_plan_gives_the_scratch_state(spark, lines):
    rng = np.random.default_rng(5)
    n = lines.df.count()
    ranges = []
    for _ in range(9):
        lo = int(rng.integers(0, n - 200))
        ranges.append(Range(lo, int(rng.integers(lo + 50, n))))
    engine = Engine(spark, cost=LinearCost(model=5.0))
    for r, s in zip(ranges, range_states(lines, LINREG, ranges)):
        assert M.state_distance(s, C.build(lines, LINREG, *r).state) == 0
        engine.store.put(LINREG, r, s, lines.version)
    for lo, hi in ((100, 2500), (ranges[0].lo, ranges[0].hi), (17, n), (500, 501)):
        want = C.build(lines, LINREG, lo, hi).state
        answer = engine.fit(lines, LINREG, lo, hi)
        assert M.state_distance(answer.state, want) == 0 and answer.plan.cost <= scan_plan(Range(lo, hi)).cost
        add = engine.plan(lines, LINREG, lo, hi, directed=True)
        assert M.state_distance(engine.fit(lines, LINREG, lo, hi, plan=add).state, want) == 0
    jobs = lines.stats["jobs"]
    covered = engine.fit(lines, LINREG, *ranges[3])
    assert lines.stats["jobs"] == jobs and covered.points_read == 0
    kept = engine.fit(lines, LINREG, 40, 90, keep=True)
    assert engine.fit(lines, LINREG, 40, 90).plan.models == kept.new_models
    assert engine.fit(lines, LINREG, 10, 10).state.n == 0
    moved = engine.extend(lines, kept, 20, 70)
    assert M.state_distance(moved.state, C.build(lines, LINREG, 20, 70).state) == 0


def test_logistic_trainers_and_reuse(spark, lines, table):
    x, _, c = table
    xs = x / np.array([1, *LOGIT.scales])
    one = replace(LOGIT, trainer="batch", steps=4, step_size=0.5, l2=0.01, chunk=600)
    rows = logistic.train_chunks(lines.df, one, [Range(0, 600), Range(600, 1300)]).collect()
    for r in rows:
        assert np.allclose(r.w, logistic.train_arrays(xs[r.chunk_lo : r.chunk_hi], c[r.chunk_lo : r.chunk_hi], one), atol=1e-9)
    assert np.allclose(B.scratch_batch(lines, one, 0, 900, 4).w, logistic.train_arrays(xs[:900], c[:900], one), atol=1e-9)
    assert np.allclose(B.scratch_sgd(lines, LOGIT, 200, 1500).w, logistic.train_arrays(xs[200:1500], c[200:1500], LOGIT), atol=1e-9)
    losses = [logistic.logit_loss(lines.df, LOGIT, logistic.train_arrays(xs, c, replace(one, steps=t)), 0.01).first().loss for t in (0, 1, 4, 16)]
    assert losses == sorted(losses, reverse=True)
    engine = Engine(spark)
    cold = Engine(spark).fit(lines, one, 600, 3000, anchor="grid").state
    engine.fit(lines, one, 1200, 2400, keep=True, anchor="grid")
    warm = engine.fit(lines, one, 600, 3000, keep=True, anchor="grid")
    assert warm.points_read == 1200 and np.allclose(warm.state.w, cold.w) and warm.state.n_chunks == 4
    again = engine.fit(lines, one, 600, 3000, anchor="grid")
    assert again.points_read == 0 and again.plan.scan_points == 0 and np.allclose(again.state.w, cold.w)
    with pytest.raises(logistic.NotSubtractable):
        warm.state.combine(cold, -1)
    longer = engine.extend(lines, warm, 600, 3600)
    assert longer.state.n_chunks == 5 and longer.state.n == 3000
    with pytest.raises(logistic.NotSubtractable):
        engine.extend(lines, warm, 600, 2400)
    nested = logistic.average_models([logistic.average_models([logistic.LogisticState("s", 5, np.array([1.0])), logistic.LogisticState("s", 5, np.array([3.0]))]), logistic.LogisticState("s", 90, np.array([8.0]))])
    assert nested.w[0] == pytest.approx(4.0)


@pytest.mark.parametrize("trainer", ["batch", "each-2-batch"])
def test_full_batch_steps_gather_no_chunk(spark, lines, table, monkeypatch, trainer):
    """Chunks too long for a task: the same weights by sums, and no task sees a whole chunk."""
    x, _, c = table
    xs = x / np.array([1, *LOGIT.scales])
    one = replace(LOGIT, trainer=trainer, steps=3, step_size=0.5, l2=0.01)
    cuts = [Range(0, 600), Range(600, len(c))]
    y = c if trainer == "batch" else c + 1
    points = logistic.project(lines.df, one, keep=["pid"]).withColumn("y_", F.col("y_") + int(trainer != "batch"))
    monkeypatch.setattr(logistic, "IN_TASK", 1000)
    trained = logistic.train_chunks(points, one, cuts, key="pid", ready=True)
    assert "MapInPandas" not in trained._jdf.queryExecution().toString()
    for r in trained.collect():
        assert r.n == r.chunk_hi - r.chunk_lo
        assert np.allclose(r.w, logistic.train_arrays(xs[r.chunk_lo : r.chunk_hi], y[r.chunk_lo : r.chunk_hi], one), atol=1e-12)
    assert trained.count() == 2


def test_ranges_are_trained_in_one_pass(spark, lines, table):
    """Overlapping ranges, also equal and empty ones: each as the plain loop trains it."""
    x, _, c = table
    xs = x / np.array([1, *LOGIT.scales])
    r = np.random.default_rng(5)
    ranges = [Range(int(a), int(a) + int(s)) for a, s in zip(r.integers(0, 4000, 40), r.integers(1, 1900, 40))]
    ranges += [ranges[3], Range(7, 7), Range(0, len(c)), Range(len(c) + 5, len(c) + 9)]
    for spec in (LOGIT, replace(LOGIT, l2=0.01)):
        got = logistic.train_ranges(lines, spec, ranges)
        for a, state in zip(ranges, got):
            assert state.n == len(c[a.lo : a.hi])
            assert np.allclose(state.w, logistic.train_arrays(xs[a.lo : a.hi], c[a.lo : a.hi], spec), atol=1e-9)
    hits = logistic.range_hits(lines, LOGIT, ranges[:40], [np.stack([s.w, -s.w]) for s in got[:40]])
    for a, s, h in zip(ranges, got, hits):
        assert h.tolist() == [(((xs[a.lo : a.hi] @ v) >= 0) == (c[a.lo : a.hi] == 1)).mean() for v in (s.w, -s.w)]
    with pytest.raises(ValueError):
        logistic.train_ranges(lines, replace(LOGIT, steps=2), ranges)


def test_logistic_requests_together_and_accuracy(spark, lines, table, monkeypatch):
    """A set of requests as one by one; accuracies by the driver's loop, though it reads no points."""
    from spanfold import workloads as W

    x, _, c = table
    xs = x / np.array([1, *LOGIT.scales])
    asks = W.requests(len(c), 12, W.Sizes("uniform", 1000, 3000), seed=3, unit=1.0)
    engine, other = Engine(spark), Engine(spark)
    W.keep_chunks(other, lines, LOGIT, [Range(a, a + LOGIT.chunk) for a in range(0, len(c) - LOGIT.chunk + 1, LOGIT.chunk)])
    monkeypatch.setattr(W, "_points", None)
    monkeypatch.setattr(DataFrame, "toArrow", None)
    rows = W.logistic_accuracy(engine, lines, LOGIT, asks)
    for r, (size, base, acc), many in zip(asks, rows, other.fit_many(lines, LOGIT, asks, tail="own")):
        one = other.fit(lines, LOGIT, *r, tail="own")
        assert np.allclose(many.state.w, one.state.w, atol=1e-9) and many.state.n_chunks == one.state.n_chunks and many.points_read == one.points_read
        own, y = xs[r.lo : r.hi], c[r.lo : r.hi] == 1
        hit = [(((own @ w) >= 0) == y).mean() for w in (logistic.train_arrays(own, c[r.lo : r.hi], LOGIT), one.state.w)]
        assert size == r.hi - r.lo and (base, acc) == pytest.approx(tuple(hit), abs=1e-12)


def test_written_points_are_stepped_through_without_a_shuffle(spark, lines, table, monkeypatch):
    """Tasks read written features in key order, across gaps and row groups; none is dealt or sorted."""
    x, _, c = table
    xs = x / np.array([1, *LOGIT.scales])
    own = PointSource(lines.df, lines.key, lines.version, lines.bucket_width, lines.directory)
    L.materialize(own, LOGIT)
    monkeypatch.setattr(DataFrame, "repartitionById", None)
    monkeypatch.setattr(DataFrame, "sortWithinPartitions", None)
    monkeypatch.setattr(logistic, "SIDE_BY_SIDE", 700)
    ranges = [Range(3, 2500), Range(40, 41), Range(2000, 2300), Range(3100, len(c)), Range(3300, 3400), Range(len(c), len(c) + 3)]
    for spec in (LOGIT, replace(LOGIT, l2=0.01)):
        for a, state in zip(ranges, logistic.train_ranges(own, spec, ranges)):
            assert state.n == len(c[a.lo : a.hi])
            assert np.allclose(state.w, logistic.train_arrays(xs[a.lo : a.hi], c[a.lo : a.hi], spec), atol=1e-9)


def test_runs_of_ranges_are_even():
    """No run of overlapping ranges has far more keys below it than the others."""
    from spanfold import workloads as W
    from spanfold.plans.ranges import union

    ranges = list(dict.fromkeys([*W.requests(5_000_000, 1000, W.Sizes("uniform", 50_000, 200_000), seed=1), Range(0, 5_000_000 // 7)]))
    for parts in (1, 6, 20):
        runs = logistic._runs(ranges, parts)
        keys = [sum(r.hi - r.lo for r in union(ranges[i] for i in run)) for run in runs]
        assert len(runs) <= parts and sorted(i for run in runs for i in run) == list(range(len(ranges)))
        assert max(keys) <= 1.1 * max(5_000_000 / 7, (5_000_000 + 200_000 * (parts - 1)) / parts)


@pytest.mark.parametrize("rows", [1, 7])
def test_steps_in_blocks_are_single_steps(rows):
    """Weights after blocks, a broken block too, as the plain loop leaves them; also far out."""
    r = np.random.default_rng(rows)
    for n, spread, l2 in ((1, 1, 0.0), (31, 1, 0.1), (32, 1, 0.0), (200, 1, 0.02), (100, 400, 0.0)):
        x, y = r.normal(0, spread, (n, 4)), r.integers(0, 2, n).astype(float)
        w = r.normal(size=(rows, 4))
        spec = replace(LOGIT, l2=l2, step_size=0.5)
        want = [logistic.train_arrays(x, y, spec, v) for v in w]
        logistic._steps(w, x, y, 0.5, 1 - 2 * 0.5 * l2)
        assert np.allclose(w, want, rtol=1e-9, atol=1e-9)


def test_accuracies_of_all_chunk_sizes_from_one_pass(spark, lines, monkeypatch):
    """Two chunk sizes: grids, requests and ends are trained by one pass, counted by another, with the
    results of each size alone."""
    from spanfold import engine as E
    from spanfold import workloads as W

    n, passes = int(lines.directory.running[-1]), []
    specs = [replace(LOGIT, chunk=c) for c in (400, 900)]
    asks = [W.requests(n, 6, W.Sizes("uniform", 1000, 3000), seed=s, unit=1.0) for s in (1, 2)]
    alone = [W.logistic_accuracy(Engine(spark), lines, spec, own) for spec, own in zip(specs, asks)]
    for module, name in ((W, "train_ranges"), (E, "train_ranges"), (W, "range_hits")):
        run = lambda source, spec, ranges, *more, f=getattr(module, name): passes.extend(["pass"] * bool(ranges)) or f(source, spec, ranges, *more)
        monkeypatch.setattr(module, name, run)
    cases = [(Engine(spark), spec, own) for spec, own in zip(specs, asks)]
    together = W.logistic_accuracies(lines, cases)
    assert passes == ["pass"] * 2
    assert np.allclose(np.array(together), np.array(alone), atol=1e-12)
    for engine, spec, _ in cases:
        assert [m.range for m in engine.store.models(spec)] == [Range(a, a + spec.chunk) for a in range(0, n - spec.chunk + 1, spec.chunk)]


def test_engines_of_all_sizes_from_one_pass(spark, lines):
    from spanfold import workloads as W
    from spanfold.sources.points import GNB_LINES

    n, sizes = int(lines.directory.running[-1]), (300_000, 700_000)
    for specs in ([GNB_LINES, GNB_LINES], [replace(LOGIT, chunk=s * n // 5_000_000) for s in sizes]):
        jobs = lines.stats["jobs"]
        together = W.engines_by_size(spark, lines, specs, n, 50, sizes)
        assert lines.stats["jobs"] <= jobs + 1
        for spec, size, e in zip(specs, sizes, together):
            alone = W.engine_at(spark, lines, spec, n, 50, W.Sizes("fixed", size), seed=size)
            models = e.store.models(spec)
            assert [m.range for m in models] == [m.range for m in alone.store.models(spec)]
            for a, b in zip(models, alone.store.models(spec)):
                a, b = e.store.states[a.model_id], alone.store.states[b.model_id]
                assert a.n == b.n and a.spec_id == b.spec_id and (np.allclose(a.w, b.w, atol=1e-9) if spec.kind == "logit" else M.state_distance(a, b) == 0)


def test_logistic_bound_and_library(lines, table):
    x, _, c = table
    xs = x / np.array([1, *LOGIT.scales])
    spec = replace(LOGIT, l2=0.1, step_size=0.05, chunk=500)
    radius = logistic.largest_norm(lines.df, LOGIT).first().radius
    assert radius == pytest.approx(np.sqrt((xs**2).sum(axis=1).max()))
    distances = []
    for lo in (0, 1500, 3000):
        chunks = [logistic.train_arrays(xs[a : a + 500], c[a : a + 500], spec) for a in range(lo, lo + 2500, 500)]
        distances.append(logistic.parameter_distance(np.mean(chunks, axis=0), logistic.train_arrays(xs[lo : lo + 2500], c[lo : lo + 2500], spec)))
    report = M.bound_report(distances, logistic.distance_bound(radius, 0.1, 500, 2500, 0.05))
    assert report["violations"] == 0
    plain = replace(LOGIT, intercept=False)  # the library gives a constant column no weight
    best, xs = B.library_logistic(lines, plain, 0, len(c), 0.1), xs[:, 1:]
    loss = lambda w: float(np.mean(np.logaddexp(0, xs @ w) - c * (xs @ w)) + 0.1 * w @ w)
    assert all(loss(best) <= loss(best + d) for d in np.vstack([0.01 * np.eye(10), -0.01 * np.eye(10)]))


def test_logistic_accuracy_of_chunks(table):
    x, _, c = table
    xs = x / np.array([1, *LOGIT.scales])
    runs = []
    for lo in range(0, 3000, 1000):
        a, b = xs[lo : lo + 3000], c[lo : lo + 3000]
        base = logistic.train_arrays(a, b, LOGIT)
        mean = np.mean([logistic.train_arrays(a[i : i + 600], b[i : i + 600], LOGIT) for i in range(0, 3000, 600)], axis=0)
        acc = lambda w: float((((a @ w) >= 0) == (b == 1)).mean())
        runs.append((3000, acc(base), acc(mean)))
    row = M.accuracy_difference(runs)[0]
    assert row["max"] < 0.03 and row["mean"] < 0.01


def test_store(spark, events, tmp_path):
    store = ModelStore(spark, f"file://{tmp_path}/s", hot=1)
    ids = [store.put(GNB_EVENTS, Range(lo, lo + 100), C.build(events, GNB_EVENTS, lo, lo + 100).state, events.version) for lo in (0, 50, 300)]
    assert len(store.states) == 1 and set(store.fetch(ids)) == set(ids)
    with pytest.raises(ValueError):
        store.fetch(ids, "another version")
    state = store.fetch(ids)[ids[0]]
    assert store.put(GNB_EVENTS, Range(0, 10), state, batch_id="b1") and store.put(GNB_EVENTS, Range(0, 10), state, batch_id="b1") is None
    again = ModelStore.open(spark, store.compact(f"file://{tmp_path}/s2").path)
    assert [(m.lo, m.hi) for m in again.models(GNB_EVENTS)] == [(m.lo, m.hi) for m in store.models(GNB_EVENTS)]
    assert M.store_size(again, GNB_EVENTS) == M.store_size(store, GNB_EVENTS) > 0
    assert not again.states  # descriptors only, until a state is asked for
    third = again.models(GNB_EVENTS)[-1]
    assert M.state_distance(again.fetch([third.model_id])[third.model_id], C.build(events, GNB_EVENTS, 300, 400).state) == 0
    again.drop(GNB_EVENTS, third)
    again.replace(again.models(GNB_EVENTS)[0].model_id, state)
    again.flush()
    third_time = ModelStore.open(spark, f"file://{tmp_path}/s2")
    assert [m.range for m in third_time.models(GNB_EVENTS)] == [m.range for m in again.models(GNB_EVENTS)] and third_time.seq == again.seq
    assert again.evict(GNB_EVENTS, 0) and not again.models(GNB_EVENTS) and not ModelStore.open(spark, f"file://{tmp_path}/s2").models(GNB_EVENTS)
    assert M.coverage(store.models(GNB_EVENTS), events.directory) == pytest.approx(25)


def test_kept_models_outlive_a_session(spark, tiny, events, tmp_path):
    engine = Engine(spark, ModelStore(spark, f"file://{tmp_path}/kept"))
    engine.fit(events, GNB_EVENTS, 100, 400, keep=True)
    engine.store.flush()
    same = L.event_source(spark, tiny)  # the same files: the same version
    again = Engine(spark, ModelStore.open(spark, f"file://{tmp_path}/kept"))
    answer = again.fit(same, GNB_EVENTS, 100, 400)
    assert answer.points_read == 0 and M.state_distance(answer.state, C.build(events, GNB_EVENTS, 100, 400).state) == 0
    load(spark, tiny, "events").write.parquet(f"file://{tmp_path}/sf/events.parquet")
    other = L.event_source(spark, f"file://{tmp_path}/sf")  # rewritten files: kept models do not count
    assert other.version != same.version and again.fit(other, GNB_EVENTS, 100, 400).points_read == 300


def test_late_points_count_once_in_overlapping_models(spark, events):
    from spanfold.streaming.states import insert_late

    store = ModelStore(spark)
    ranges = [Range(0, 300), Range(200, 500)]
    early = events.df.where("event_id % 10 <> 3")
    for r in ranges:
        store.put(GNB_EVENTS, r, bayes.bayes_state(early.where(f"event_id >= {r.lo} and event_id < {r.hi}"), GNB_EVENTS), events.version)
    assert insert_late(store, GNB_EVENTS, events.df.where("event_id % 10 = 3")) == {"inserted": 50, "unplaced": 50}
    for m in store.models(GNB_EVENTS):
        assert M.state_distance(store.fetch([m.model_id])[m.model_id], C.build(events, GNB_EVENTS, *m.range).state) == 0


def test_driver_reads_give_the_states_of_jobs(spark, lines):
    from spanfold.sources.points import GNB_LINES

    n = lines.df.count()
    own = PointSource(lines.df, lines.key, lines.version, lines.bucket_width, lines.directory)
    for spec in (LINREG, GNB_LINES):
        L.materialize(own, spec)
        for lo, hi in ((0, n), (17, 18), (n // 3, n // 2), (5, 5)):
            jobs = own.stats["jobs"]
            assert M.state_distance(C.build(own, spec, lo, hi).state, C.build(lines, spec, lo, hi).state) == 0 and own.stats["jobs"] == jobs
    L.materialize(own, LOGIT)
    assert np.allclose(B.scratch_sgd(own, LOGIT, 200, 1500).w, B.scratch_sgd(lines, LOGIT, 200, 1500).w, atol=1e-9)
    spec = replace(LOGIT, chunk=300)
    a, b = (Engine(spark).fit(s, spec, 100, 2000, keep=True).state for s in (own, lines))
    assert np.allclose(a.w, b.w, atol=1e-9) and a.n_chunks == b.n_chunks


def test_exact_products_of_wide_numbers():
    from spanfold.sources.local import exact_gram

    rng = np.random.default_rng(3)
    x = rng.integers(-(1 << 40), 1 << 40, (5000, 3))
    want = [[sum(int(a) * int(b) for a, b in zip(x[:, i], x[:, j])) for j in range(3)] for i in range(3)]
    assert exact_gram(x) == want


def test_many_requests_in_one_job(spark, events):
    engine = Engine(spark)
    for r, s in zip((Range(0, 300), Range(250, 700)), range_states(events, GNB_EVENTS, [Range(0, 300), Range(250, 700)])):
        engine.store.put(GNB_EVENTS, r, s, events.version)
    asks = [Range(i * 7 % 900, i * 7 % 900 + 40 + i % 50) for i in range(120)] + [Range(5, 5)]
    jobs = events.stats["jobs"]
    answers = engine.fit_many(events, GNB_EVENTS, asks)
    assert events.stats["jobs"] == jobs + 1
    for r, a in list(zip(asks, answers))[::30]:
        assert M.state_distance(a.state, C.build(events, GNB_EVENTS, *r).state) == 0


def test_chunks_side_by_side(table):
    x, _, c = table
    xs = x / np.array([1, *LOGIT.scales])
    spec = replace(LOGIT, l2=0.01)
    parts = [(xs[a:b], c[a:b]) for a, b in ((0, 100), (100, 350), (350, 360), (360, 900), (900, 901))]
    for w, (a, b) in zip(logistic.train_many(parts, spec), parts):
        assert np.allclose(w, logistic.train_arrays(a, b, spec), atol=1e-9)


def test_subsamples_are_drawn_with_replacement(spark, lines, table):
    x, _, c = table
    xs = x / np.array([1, *LOGIT.scales])
    spec = replace(LOGIT, trainer="batch", steps=3, l2=0.01)

    def low(v):
        return v % (1 << 31)

    def mixed(v):
        v = low(low(v) * 2654435761)
        v = low((v ^ (v >> 15)) * 2246822519)
        return v ^ (v >> 13)

    n, ws = len(c), []
    for s in range(3):
        at = [int(mixed(s * 400 + t + 1_000_003) / (1 << 31) * n) for t in range(400)]
        assert len(set(at)) < 400  # a point may come twice
        ws.append(logistic.train_arrays(xs[at], c[at], spec))
    got = logistic.average_of_subsamples(lines.df, spec, p=3, m=400, n=n)
    assert got.n == 1200 and np.allclose(got.w, np.mean(ws, axis=0), atol=1e-9)


def test_one_against_the_rest(spark, lines, table):
    from spanfold.sources.points import CLASS3, GNB_LINES

    x, _, _ = table
    xs = x / np.array([1, *LOGIT.scales])
    names = np.array([r.k for r in lines.df.select("pid", F.expr(CLASS3).alias("k")).orderBy("pid").collect()])
    got = logistic.one_vs_rest(lines.df, replace(LOGIT, label=CLASS3), GNB_LINES.classes, [Range(0, 500), Range(500, 1100)])
    for k in GNB_LINES.classes:
        want = np.mean([logistic.train_arrays(xs[a:b], (names[a:b] == k).astype(float), LOGIT) for a, b in ((0, 500), (500, 1100))], axis=0)
        assert np.allclose(got[k].w, want, atol=1e-9)


def test_key_checks_on_dense_and_sparse_lines(spark):
    def facts(keys):
        return tuple(validate_key(spark.createDataFrame([(k,) for k in keys], "k long"), "k").first())

    assert facts([]) == (0, 0, 0, None, None, True)
    assert facts([3, 1, 2, -40000, 70000]) == (5, 5, 0, -40000, 70000, True)
    assert facts([0, 4, 5, 1, 2, 6] * 2) == (12, 6, 0, 0, 6, False)
    assert facts([1, None, 10**15, 1]) == (4, 2, 1, 1, 10**15, False)
    assert facts([None, None, 5])[-1] is False


def test_measures():
    g = M.gain([(1.0, 2.0), (1.0, 4.0)])
    assert g["speedup"] == 3 and g["time_ratio"] == pytest.approx(1 / 3) and g["mean_speedup"] == 3
    assert M.cost_fidelity([1, 2, 3], [10, 20, 40]) == pytest.approx(1)
    d = M.accuracy_difference([(10, 0.9, 0.8), (10, 0.8, 0.9)])[0]
    assert d["mean"] == pytest.approx(0) and d["mean_positive"] == pytest.approx(0.1) and d["max"] == pytest.approx(0.1)


def test_merge_signed_in_spark(spark):
    rows = spark.createDataFrame([("s", 1, [1.0, 2.0]), ("s", 1, [10.0, 20.0]), ("s", -1, [4.0, 5.0])], "spec_id string, sign int, values array<double>")
    assert [r.v for r in C.merge_signed(rows).orderBy("i").collect()] == [7.0, 17.0]


def test_many_scan_cells_use_one_join(spark, events):
    from spanfold.plans.planner import Segment

    segments = [Segment(1, "scan", lo, lo + 3) for lo in range(0, 900, 9)]
    rows = events.scan_segments(segments)
    assert rows.count() == 300 and rows.agg(F.sum("sign")).first()[0] == 300
    cells = range_states(events, GNB_EVENTS, [Range(i, i + 30) for i in range(0, 900, 9)])
    assert M.state_distance(cells[4], C.build(events, GNB_EVENTS, 36, 66).state) == 0


def test_plan_of_1000_requests(spark):
    from spanfold import workloads as W

    models = W.as_kept(W.place_models(10_000, 60, W.NORMAL, seed=1))
    asks = W.requests(10_000, 40, W.NORMAL, seed=2)
    from spanfold.plans.planner import plan_many

    got = {r.req_id: r.cost for r in plan_many(spark.createDataFrame([(i, r.lo, r.hi) for i, r in enumerate(asks)], "req_id long, lo long, hi long"), models).collect()}
    assert all(got[i] == pytest.approx(best_plan(models, r).cost) for i, r in enumerate(asks))


def test_gram_of_vectors(spark, tiny):
    from spanfold.functions.udfs import gram_agg

    rows = load(spark, tiny, "embeddings")
    x = np.stack(rows.toPandas().embedding.to_numpy()).astype(float)
    got = {(r.i, r.j): r.v for r in linear.linreg_state_arrow(rows, "embedding").collect()}
    assert np.allclose([got[i, j] for i, j in zip(*np.triu_indices(64))], (x.T @ x)[np.triu_indices(64)])
    packed = rows.groupBy().agg(gram_agg()("embedding").alias("g")).first().g
    assert np.allclose(packed, (x.T @ x)[np.triu_indices(64)])


def test_source_is_a_point_source(lines):
    assert isinstance(lines, PointSource) and lines.directory.count(0, 10**9) == lines.df.count()

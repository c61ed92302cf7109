"""Seeded model and request sets of the experiments, and runs over them.

Sizes are those of five million points scaled by `unit` = points / 5,000,000.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

import numpy as np

from spanfold.engine import Engine, new_chunks
from spanfold.functions import bayes, linear
from spanfold.functions.logistic import LogisticState, arrays_of, distance_bound, make_chunks, parameter_distance, project, range_hits, train_chunks, train_many, train_ranges
from spanfold.operators.baselines import scratch_sgd
from spanfold.operators.batch import range_states
from spanfold.operators.measures import bound_report, cost_fidelity, gain, storage_overhead, store_size, time_split, work
from spanfold.plans.costs import AffineCost, Directory, LinearCost, fit_cost
from spanfold.plans.planner import Segment, best_plan, greedy_cover, largest_overlap_plan
from spanfold.plans.ranges import Range, union
from spanfold.plans.relevance import DescriptorIndex, Kept
from spanfold.sources.points import ModelSpec, PointSource
from spanfold.sources.store import ModelStore


@dataclass(frozen=True)
class Sizes:
    """fixed a | uniform a…b | normal mean a, deviation b; in points of the five-million data set."""

    kind: str
    a: float
    b: float = 0.0

    def draw(self, rng, unit: float, n: int) -> int:
        x = self.a if self.kind == "fixed" else rng.uniform(self.a, self.b) if self.kind == "uniform" else rng.normal(self.a, self.b)
        return int(min(n, max(2, round(x * unit))))


# Sizes of the experiments' models and requests.
NORMAL = Sizes("normal", 50_000, 12_500)
SMALL, LARGE = Sizes("uniform", 50_000, 100_000), Sizes("uniform", 500_000, 750_000)
MODEL_SETS = {"M1": Sizes("uniform", 25_000, 50_000), "M2": Sizes("uniform", 75_000, 100_000), "M3": Sizes("uniform", 150_000, 200_000), "M4": Sizes("uniform", 250_000, 500_000)}
COVERAGES = (0, 20, 40, 60, 80, 90)
MODEL_SIZES = (5_000, 10_000, 20_000, 30_000, 40_000, 50_000, 70_000)
CHUNKS = (10_000, 20_000)


def requests(n: int, count: int, sizes: Sizes, seed: int = 0, unit: float | None = None) -> list[Range]:
    rng = np.random.default_rng(seed)
    unit = n / 5e6 if unit is None else unit
    out = []
    for _ in range(count):
        s = sizes.draw(rng, unit, n)
        lo = int(rng.integers(0, n - s + 1))
        out.append(Range(lo, lo + s))
    return out


def place_models(n: int, target: float, sizes: Sizes, seed: int = 0, unit: float | None = None, depth: float = 0.0, grid: bool = False) -> list[Range]:
    """Ranges placed anywhere until their union covers `target` percent (the last one trimmed), and
    until points lie below `depth` models on average. grid: distinct cells of a fixed size."""
    rng = np.random.default_rng(seed)
    unit = n / 5e6 if unit is None else unit
    goal = n * target / 100
    if goal <= 0:
        return []
    if grid:
        size = sizes.draw(rng, unit, n)
        cells = rng.permutation(n // size)[: round(goal / size)]
        return [Range(int(c) * size, int(c + 1) * size) for c in cells]
    out: list[Range] = []
    covered, total = np.zeros(n, dtype=bool), 0
    done = 0
    while done < goal or total < depth * n:
        s = sizes.draw(rng, unit, n)
        lo = int(rng.integers(0, n - s + 1))
        hi = lo + s
        fresh = np.flatnonzero(~covered[lo:hi])
        if done < goal and len(fresh) > goal - done:
            hi = lo + int(fresh[max(0, int(round(goal - done)) - 1)]) + 1
        if hi <= lo:
            continue
        done += int((~covered[lo:hi]).sum())
        covered[lo:hi] = True
        total += hi - lo
        out.append(Range(lo, hi))
    return out


def actual_coverage(n: int, ranges) -> float:
    return 100.0 * sum(r.hi - r.lo for r in union(ranges)) / n


def as_kept(ranges) -> list[Kept]:
    return [Kept(r.lo, r.hi, f"m{i:05d}") for i, r in enumerate(ranges)]


def strategies(index: DescriptorIndex, directory: Directory, r: Range, cost) -> tuple:
    """A request's plan cost relative to scanning it, by strategy, and the size of the best plan."""
    near = index.query(r)
    points = directory.count(*r)
    base = cost.scan_cost(points)
    best = best_plan(near, r, cost, directory)
    if not points:  # nothing to scan, so no plan is dearer or cheaper
        return (1.0, 1.0, 1.0, 1.0, 1.0, 0, best.graph_nodes)
    add = best_plan(near, r, cost, directory, directed=True)
    return (best.cost / base, add.cost / base, greedy_cover(near, r, cost, directory).cost / base, largest_overlap_plan(near, r, cost, directory).cost / base, best.scan_points / points, len(best.models), best.graph_nodes)


STRATEGIES = ("best", "add_only", "greedy", "largest", "points_share", "models_used", "graph_nodes")


def planned(n: int, models: list[Range], asks: list[Range], cost=LinearCost()) -> dict:
    """Mean plan cost of a request set relative to scanning, by strategy."""
    index, directory = DescriptorIndex(as_kept(models)), Directory.dense(n)
    m = np.array([strategies(index, directory, r, cost) for r in asks], dtype=float).mean(axis=0)
    return dict(zip(STRATEGIES, map(float, m)))


@dataclass(frozen=True)
class Case:
    """One point of an experiment: what it is, the kept models' ranges, the requests, the costs."""

    tags: tuple  # (name, number) pairs
    models: list
    asks: list
    cost: LinearCost = LinearCost()


def planned_frame(spark, directory: Directory, cases: list[Case]):
    """A row a case: its tags, models, requests and mean relative plan costs, by the directory's counts
    of points.

    Every request is planned by an executor; descriptors travel with the function (24 bytes a
    model) and the means are taken in Spark, so a case may have any number of requests.
    """
    from pyspark.sql import functions as F

    points = float(directory.running[-1])
    covered = lambda case: 100.0 * sum(directory.count(*r) for r in union(case.models)) / points
    rows = [(c, i, r.lo, r.hi) for c, case in enumerate(cases) for i, r in enumerate(case.asks)]
    kept = [(as_kept(case.models), case.cost) for case in cases]

    def run(batches):
        import pandas as pd

        made = {}
        for b in batches:
            out = []
            for c, lo, hi in zip(b["case"].tolist(), b["lo"].tolist(), b["hi"].tolist()):
                if c not in made:
                    made[c] = DescriptorIndex(kept[c][0])
                out.append((c, *strategies(made[c], directory, Range(lo, hi), kept[c][1])))
            yield pd.DataFrame(out, columns=["case", *STRATEGIES])

    asks = spark.createDataFrame(rows, "case int, req_id int, lo long, hi long").repartition(4 * spark.sparkContext.defaultParallelism, "case", "req_id")
    each = asks.mapInPandas(run, "case int, " + ", ".join(f"{s} double" for s in STRATEGIES))
    means = each.groupBy("case").agg(F.count("*").cast("double").alias("requests"), *[F.avg(s).alias(s) for s in STRATEGIES])
    names = [k for k, _ in cases[0].tags]
    tags = spark.createDataFrame([(c, *[float(v) for _, v in case.tags], float(len(case.models)), covered(case)) for c, case in enumerate(cases)], "case int, " + ", ".join(f"{k} double" for k in names) + ", models double, actual double")
    return means.join(F.broadcast(tags), "case").select(*names, "actual", "models", "requests", *STRATEGIES)  # a row a case


def coverage_case(n: int, c: int, sizes: Sizes = NORMAL, asks: Sizes = NORMAL, count: int = 1000, cost=LinearCost(), seed: int = 0, tags=()) -> Case:
    return Case((*tags, ("coverage", c)), place_models(n, c, sizes, seed + c), requests(n, count, asks, seed + 1000), cost)


def gain_by_coverage(n: int, coverages=COVERAGES, sizes: Sizes = NORMAL, asks: Sizes = NORMAL, count: int = 200, cost=LinearCost(), seed: int = 0, depth: float = 0.0) -> list[dict]:
    """Gain against coverage; also time against coverage for the four model sets."""
    out = []
    for c in coverages:
        models = place_models(n, c, sizes, seed + c, depth=depth * c / 100)
        out.append({"coverage": c, "actual": actual_coverage(n, models), "models": len(models)} | planned(n, models, requests(n, count, asks, seed + 1000), cost))
    return out


def size_case(n: int, size: int, asks: Sizes, model_cost: float, target: float = 50, count: int = 1000, seed: int = 0, tags=()) -> Case:
    return Case((*tags, ("size", size)), place_models(n, target, Sizes("fixed", size), seed + size), requests(n, count, asks, seed + 7), LinearCost(model=model_cost))


def gain_by_model_size(n: int, asks: Sizes, model_cost: float, sizes=MODEL_SIZES, target: float = 50, count: int = 200, seed: int = 0) -> list[dict]:
    """Gain against model size at a fixed coverage; model_cost in scanned points of this data."""
    out = []
    for s in sizes:
        case = size_case(n, s, asks, model_cost, target, count, seed)
        out.append({"size": s, "models": len(case.models)} | planned(n, case.models, case.asks, case.cost))
    return out


def keep_exact(engine: Engine, source: PointSource, spec: ModelSpec, ranges: list[Range]) -> None:
    """Build and keep models of many ranges in one job."""
    for r, state in zip(ranges, range_states(source, spec, ranges)):
        engine.store.put(spec, r, state, source.version)


def keep_chunks(engine: Engine, source: PointSource, spec: ModelSpec, ranges: list[Range]) -> None:
    """Train and keep logistic models of many disjoint chunks in one job."""
    ranges = sorted(ranges)
    if ranges:
        for r in train_chunks(source.prepared(spec, project).df, spec, ranges, ready=True).collect():  # a row a chunk
            engine.store.put(spec, Range(r.chunk_lo, r.chunk_hi), LogisticState(spec.spec_id, r.n, np.array(r.w)), source.version)


def _projection(spec: ModelSpec):
    return {"linreg": linear.project, "logit": project}.get(spec.kind, bayes.project)


def engine_at(spark, source: PointSource, spec: ModelSpec, n: int, coverage: float, sizes: Sizes = NORMAL, seed: int = 0) -> Engine:
    """An engine whose kept models cover so many percent; logistic models are cells of the spec's
    chunk size. Its costs are calibrated where scans are read on the driver."""
    engine = Engine(spark, ModelStore(spark), LinearCost() if source.prepared(spec, _projection(spec)).reader is None else calibrated(source, spec))
    if spec.kind == "logit":
        keep_chunks(engine, source, spec, place_models(n, coverage, Sizes("fixed", spec.chunk), seed, unit=1.0, grid=True))
    else:
        keep_exact(engine, source, spec, place_models(n, coverage, sizes, seed))
    return engine


def engines_by_size(spark, source: PointSource, specs: list[ModelSpec], n: int, coverage: float, sizes) -> list[Engine]:
    """An engine for each model size, as `engine_at` makes them; the models of all sizes come from
    one pass through the points, and costs are calibrated once. Specs differ in their chunks only."""
    cost = LinearCost() if source.prepared(specs[0], _projection(specs[0])).reader is None else calibrated(source, specs[0])
    engines = [Engine(spark, ModelStore(spark), cost) for _ in specs]
    logit = specs[0].kind == "logit"
    placed = [sorted(place_models(n, coverage, Sizes("fixed", spec.chunk), s, unit=1.0, grid=True)) if logit else place_models(n, coverage, Sizes("fixed", s), s) for spec, s in zip(specs, sizes)]
    every = [r for own in placed for r in own]
    states = iter(train_ranges(source, specs[0], every) if logit else range_states(source, specs[0], every))
    for engine, spec, own in zip(engines, specs, placed):
        for r, state in zip(own, states):
            engine.store.put(spec, r, replace(state, spec_id=spec.spec_id) if logit else state, source.version)
    return engines


def calibrated(source: PointSource, spec: ModelSpec, model: float = 3e-4) -> AffineCost:
    """Costs in seconds, fitted to scans measured on this source: a set-up and a slope; `model` is
    what fetching and merging a kept state takes."""
    from spanfold.operators.combine import scan_state

    n = int(source.directory.running[-1])
    samples = []
    for size in (64, 1000, 4000, 16_000, 60_000):
        size = min(size, n)
        for turn in range(4):
            lo = (n - size) * turn // 4
            began = time.perf_counter()
            if spec.kind == "logit":
                scratch_sgd(source, spec, lo, lo + size)
            else:
                scan_state(source, spec, [Segment(1, "scan", lo, lo + size)])
            if turn:
                samples.append((size, time.perf_counter() - began))
    return fit_cost(samples, model=model)


def storage_by_coverage(spark, source: PointSource, spec: ModelSpec, n: int, coverages=(20, 40, 60, 80, 90), size: int = 5_000) -> list[dict]:
    out = []
    for c in coverages:
        engine = Engine(spark, ModelStore(spark))
        ranges = place_models(n, c, Sizes("fixed", size), seed=3, grid=True)
        keep_exact(engine, source, spec, ranges)
        out.append({"coverage": c, "models": len(ranges), "bytes": store_size(engine.store, spec), "percent": storage_overhead(engine.store, spec, n)})
    return out


def base_seconds(engine: Engine, source: PointSource, spec: ModelSpec, r: Range) -> float:
    """Wall-clock seconds of a request from raw points only."""
    began = time.perf_counter()
    if spec.kind == "logit":
        scratch_sgd(source, spec, *r)
    else:
        engine.scratch(source, spec, *r)
    return time.perf_counter() - began


def timed(engine: Engine, source: PointSource, spec: ModelSpec, asks: list[Range], base: list[float] | None = None) -> dict:
    """Wall-clock gain and time split of requests answered one by one; the first is a warm-up.
    `base`: the seconds from raw points, where they were measured before."""
    runs, answers = [], []
    for i, r in enumerate(asks):
        a = engine.fit(source, spec, *r)
        scratch = base_seconds(engine, source, spec, r) if base is None else base[i]
        if i:
            runs.append((a.t_total, scratch))
            answers.append(a)
    split, counts = time_split(answers), [work(a) for a in answers]
    return gain(runs) | split | {"t_base": float(np.mean([b for _, b in runs])), "points_read": float(np.mean([a.points_read for a in answers])), "base_points": float(np.mean([r.hi - r.lo for r in asks[1:]])), "requests": len(runs)} | {k: float(np.mean([c[k] for c in counts])) for k in ("models_read", "graph_nodes", "plan_cost")}


def timed_many(engine: Engine, source: PointSource, spec: ModelSpec, asks: list[Range]) -> dict:
    """Seconds of a request set answered in one job, with kept models and without any."""
    bare = Engine(engine.spark, ModelStore(engine.spark))
    seconds = []
    for e in (engine, bare, engine, bare):
        began = time.perf_counter()
        e.fit_many(source, spec, asks)
        seconds.append(time.perf_counter() - began)
    return {"many_requests": len(asks), "many_seconds": seconds[2], "many_base_seconds": seconds[3], "many_speedup": seconds[3] / seconds[2], "many_per_request_ms": 1000 * seconds[2] / len(asks)}


def time_by_coverage(spark, source: PointSource, spec: ModelSpec, n: int, coverages=COVERAGES, sizes: Sizes = NORMAL, asks: Sizes = NORMAL, count: int = 20, seed: int = 0) -> list[dict]:
    """Seconds of requests against coverage, beside those from raw points. `count` requests are
    timed at each coverage: a bounded sample of the request set."""
    out = []
    for c in coverages:
        engine = engine_at(spark, source, spec, n, c, sizes, seed + c)
        out.append({"coverage": c} | timed(engine, source, spec, requests(n, count + 1, asks, seed + 9)))
    return out


def _points(source: PointSource, spec: ModelSpec, r: Range) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of a range, in key order: read on the driver where few, else collected
    by a job; for the studies, whose requests have a stated size."""
    ready = source.prepared(spec, project)
    table = ready.reader.read(*r) if ready.reader is not None else ready.scan_range(*r).orderBy(source.key).toArrow()
    return arrays_of(table, spec)


def logistic_accuracy(engine: Engine, source: PointSource, spec: ModelSpec, asks: list[Range]) -> list[tuple]:
    """(request size, accuracy of plain descent, accuracy with chunk reuse) on each request's points."""
    return logistic_accuracies(source, [(engine, spec, asks)])[0]


def logistic_accuracies(source: PointSource, cases: list[tuple[Engine, ModelSpec, list[Range]]]) -> list[list[tuple]]:
    """For each case (engine, spec, requests), whose specs differ in their chunks only: (request
    size, accuracy of plain descent, accuracy with chunk reuse) on each request's points.

    Chunks on a grid are trained once and kept; a request averages those inside it with new models
    of its two ends. Plain descent goes point by point through each request. Plans depend on ranges
    only, so grids, requests and ends of all cases share one pass through the points, and a second
    counts what the models tell right; points stay with the executors.
    """
    n = int(source.directory.running[-1])
    spec = cases[0][1]
    grids, ends = [], []
    for engine, own, asks in cases:
        grids.append([] if engine.store.models(own) else [Range(a, a + own.chunk) for a in range(0, n - own.chunk + 1, own.chunk)])
        ends.append(_ends(engine, source, own, asks, grids[-1]))
    every = [r for (_, _, asks), grid, new in zip(cases, grids, ends) for r in (*grid, *asks, *new)]
    states = iter(train_ranges(source, spec, every))
    models = []
    for (engine, own, asks), grid, new in zip(cases, grids, ends):
        kept, plain, made = ([replace(s, spec_id=own.spec_id) for _, s in zip(part, states)] for part in (grid, asks, new))
        for r, state in zip(grid, kept):
            engine.store.put(own, r, state, source.version)
        reused = engine.fit_many(source, own, asks, tail="own", made=dict(zip(new, made)))
        models += [np.stack([p.w, a.state.w]) for p, a in zip(plain, reused)]
    hits = iter(range_hits(source, spec, [r for _, _, asks in cases for r in asks], models))
    return [[(r.hi - r.lo, *map(float, h)) for r, h in zip(asks, hits)] for _, _, asks in cases]


def _ends(engine: Engine, source: PointSource, spec: ModelSpec, asks: list[Range], grid: list[Range]) -> list[Range]:
    """New chunks that the plans of requests will have once models of the grid are kept: planned
    with the grid's descriptors, before there are models."""
    if grid:
        engine = Engine(engine.spark, ModelStore(engine.spark), engine.cost, engine.planner)
        for r in grid:
            engine.store.put(spec, r, LogisticState(spec.spec_id, 0, np.zeros(0)), source.version)
    return sorted({c for r in asks for c in new_chunks(engine.plan(source, spec, *r), spec, "own")})


def bound_study(source: PointSource, spec: ModelSpec, chunks, size: int, runs: int, radius: float, delta: float = 0.05, seed: int = 0) -> list[dict]:
    """Distance of averaged and whole-range weights against the bound, over seeded ranges."""
    n = int(source.directory.running[-1])
    rng = np.random.default_rng(seed)
    asks = [Range(int(a), int(a) + size) for a in rng.integers(0, n - size + 1, runs)]
    points = [_points(source, spec, r) for r in asks]
    plain = train_many(points, spec)
    out = []
    for chunk in chunks:
        gone = []
        for (x, y), w0 in zip(points, plain):
            cuts = make_chunks(0, size, chunk)
            models = train_many([(x[c.lo : c.hi], y[c.lo : c.hi]) for c in cuts], spec)
            gone.append(parameter_distance(np.mean(models, axis=0), w0))
        out.append({"chunk": chunk} | bound_report(gone, distance_bound(radius, spec.l2, chunk, size, delta)))
    return out


def cost_study(spark, source: PointSource, spec: ModelSpec, n: int, count: int = 20, seed: int = 0) -> dict:
    """Set-up and slope fitted to measured scans, and how well planned costs rank measured times."""
    sizes = np.linspace(0.02, 0.9, count)
    samples = []
    engine = Engine(spark, ModelStore(spark))
    for s in [0.5, *sizes]:
        began = time.perf_counter()
        engine.scratch(source, spec, 0, int(n * s))
        samples.append((int(n * s), time.perf_counter() - began))
    fitted = fit_cost(samples[1:])
    planned_cost = [fitted.scan_cost(p) for p, _ in samples[1:]]
    return {"setup_seconds": fitted.setup, "seconds_per_million": 1e6 * fitted.per_point, "rank_correlation": cost_fidelity(planned_cost, [t for _, t in samples[1:]]), "runs": count}

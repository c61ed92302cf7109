"""Logistic regression over ranges by chunks: trainers, averaging, bound."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.plans.ranges import Range, union
from spanfold.sources.points import ModelSpec, PointSource, check_rows, in_cells


class NotSubtractable(ValueError):
    """Averaged weights cannot lose points; only whole chunks can be left out of an average."""


@dataclass
class LogisticState:
    spec_id: str
    n: int
    w: np.ndarray
    n_chunks: int = 1

    @property
    def nbytes(self) -> int:
        return 8 * (len(self.w) + 2)

    def combine(self, other: "LogisticState", sign: int = 1) -> "LogisticState":
        if sign < 0:
            raise NotSubtractable("a logistic model has no points to take away; average its chunks anew")
        if self.spec_id != other.spec_id:
            raise ValueError("models of different specs do not combine")
        return average_models([self, other])


def make_chunks(lo: int, hi: int, size: int, tail: str = "merge", anchor: str = "request") -> list[Range]:
    """Ranges of `size` keys in ascending order. anchor: cut from the request's start, or at
    multiples of size (so that requests share chunks). tail: what is too short joins its
    predecessor, stands alone, or is dropped; alone in its gap it always stands."""
    if hi <= lo:
        return []
    first = lo if anchor == "request" else min(hi, -(-lo // size) * size)
    cuts = [lo] + [c for c in range(first if first > lo else first + size, hi, size)] + [hi]
    out = [Range(a, b) for a, b in zip(cuts, cuts[1:])]
    if tail == "own" or len(out) == 1:
        return out
    if tail == "drop":
        return [r for r in out if r.hi - r.lo >= size] or out[:1]
    merged: list[Range] = []
    for r in out:
        if merged and (r.hi - r.lo < size or merged[-1].hi - merged[-1].lo < size):
            merged[-1] = Range(merged[-1].lo, r.hi)
        else:
            merged.append(r)
    return merged


def scaled(spec: ModelSpec) -> list:
    """Feature columns divided by the spec's fixed constants, the constant first."""
    divisors = spec.scales or (1.0,) * len(spec.features)
    return ([F.lit(1.0)] if spec.intercept else []) + [f.real() / F.lit(float(s)) for f, s in zip(spec.features, divisors)]


def margin(spec: ModelSpec, w):
    z = F.lit(0.0)
    for x, v in zip(scaled(spec), w):
        z = z + x * F.lit(float(v))
    return z


def logit_loss(df: DataFrame, spec: ModelSpec, w, l2: float = 0.0) -> DataFrame:
    """Mean cross entropy plus l2 times the squared weights, in a form that cannot overflow."""
    z = margin(spec, w)
    y = F.expr(spec.label).cast("double")
    one = F.greatest(z, F.lit(0.0)) - z * y + F.log1p(F.exp(-F.abs(z)))
    return df.agg((F.avg(one) + F.lit(l2 * float(np.dot(w, w)))).alias("loss"))


def logit_gradient(df: DataFrame, spec: ModelSpec, w, l2: float = 0.0, by=()) -> DataFrame:
    """Full-batch gradient g0… of each group, and its count."""
    error = F.lit(1.0) / (F.lit(1.0) + F.exp(-margin(spec, w))) - F.expr(spec.label).cast("double")
    cols = [(F.avg(error * x) + F.lit(2 * l2 * float(w[j]))).alias(f"g{j}") for j, x in enumerate(scaled(spec))]
    return df.groupBy(*by).agg(F.count("*").alias("n"), *cols)


def logit_predict(df: DataFrame, spec: ModelSpec, w, threshold: float = 0.5, name: str = "prediction") -> DataFrame:
    p = F.lit(1.0) / (F.lit(1.0) + F.exp(-margin(spec, w)))
    return df.withColumn(f"{name}_p", p).withColumn(name, F.when(p >= threshold, 1).otherwise(0))


def train_arrays(x: np.ndarray, y: np.ndarray, spec: ModelSpec, w: np.ndarray | None = None) -> np.ndarray:
    """batch: `steps` full-gradient steps from zero. sgd: one step a point, in the order given.
    each-k-…: y numbers k classes from 1; weights of each class against the rest, end to end."""
    if spec.trainer.startswith("each-"):
        _, k, trainer = spec.trainer.split("-", 2)
        own = replace(spec, trainer=trainer)
        return np.concatenate([train_arrays(x, (y == c).astype(float), own) for c in range(1, int(k) + 1)])
    w = np.zeros(x.shape[1]) if w is None else w.copy()
    if spec.trainer == "batch":
        for _ in range(spec.steps):
            h = 1 / (1 + np.exp(-np.clip(x @ w, -500, 500)))
            w -= spec.step_size * (x.T @ (h - y) / max(1, len(y)) + 2 * spec.l2 * w)
        return w
    step, shrink = spec.step_size, 1 - 2 * spec.step_size * spec.l2
    for _ in range(spec.steps):
        for row, target in zip(x, y):
            z = float(row @ w)
            h = 1 / (1 + math.exp(-z)) if z > -500 else 0.0
            w = shrink * w - step * (h - target) * row
    return w


def project(df: DataFrame, spec: ModelSpec, keep=()) -> DataFrame:
    """Label and scaled features as doubles, the columns a trainer needs."""
    df = check_rows(df, spec)
    return df.select(*keep, F.expr(spec.label).cast("double").alias("y_"), *[c.alias(f"x{j}") for j, c in enumerate(scaled(spec))])


def arrays_of(table, spec: ModelSpec) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of projected points held in memory, in key order."""
    names = [f"x{j}" for j in range(len(spec.columns()))]
    return np.stack([table.column(c).to_numpy() for c in names], axis=1), table.column("y_").to_numpy()


def train_many(parts: list[tuple[np.ndarray, np.ndarray]], spec: ModelSpec) -> list[np.ndarray]:
    """Weights of many chunks, each as `train_arrays` gives: single-point steps of all chunks are
    taken side by side, one matrix operation a step, since chunks do not depend on one another."""
    if spec.trainer != "sgd" or len(parts) < 4:
        return [train_arrays(x, y, spec) for x, y in parts]
    order = sorted(range(len(parts)), key=lambda i: -len(parts[i][1]))
    size = np.array([len(parts[i][1]) for i in order])
    d = parts[0][0].shape[1]
    x, y = np.zeros((size.max(initial=0), len(order), d)), np.zeros((size.max(initial=0), len(order)))
    for at, i in enumerate(order):
        x[: size[at], at], y[: size[at], at] = parts[i]
    w = np.zeros((len(order), d))
    step, shrink = spec.step_size, 1 - 2 * spec.step_size * spec.l2
    live = np.searchsorted(-size, -np.arange(1, len(x) + 1), side="right")
    for _ in range(spec.steps):
        for t, m in enumerate(live.tolist()):
            row = x[t, :m]
            h = 1 / (1 + np.exp(-np.maximum(np.einsum("ij,ij->i", row, w[:m]), -500)))
            w[:m] = shrink * w[:m] - (step * (h - y[t, :m]))[:, None] * row
    out: list = [None] * len(parts)
    for at, i in enumerate(order):
        out[i] = w[at]
    return out


SIDE_BY_SIDE = 1 << 16  # points that a task trains at once; a longer chunk is trained alone
IN_TASK = 1 << 20  # keys of a chunk up to which a task holds its points for full-batch steps
BLOCK = 32  # points whose steps are taken between two moves of the weights
BATCH = 1 << 13  # points whose products a task holds at once


def train_chunks(points: DataFrame, spec: ModelSpec, chunks: list[Range], key: str | None = None, ready: bool = False) -> DataFrame:
    """(chunk_lo, chunk_hi, n, w): a model for each chunk, trained where the chunk's rows meet.

    One shuffle by chunk. A task gets whole chunks sorted by key, and steps neighbouring ones side
    by side up to a bound of points; a chunk fits a task, as chunks have a size. Full-batch steps
    over chunks of more than IN_TASK keys gather no points: each is a job of sums. `ready`: the
    points are projected already.
    """
    key = key or spec.key
    rows = points if ready else project(points, spec, keep=[key])
    lows = [c.lo for c in chunks]
    if len(lows) <= 16:
        table = F.array(*[F.lit(x).cast("long") for x in lows])
        at = F.size(F.filter(table, lambda x: x <= F.col(key))) - 1
        rows = rows.where((F.col(key) >= lows[0]) & (F.col(key) < chunks[-1].hi)).withColumn("chunk_lo", F.element_at(table, (at + 1).cast("int")))
        ends = F.create_map(*[F.lit(v).cast("long") for c in chunks for v in (c.lo, c.hi)])
        rows = rows.withColumn("chunk_hi", ends[F.col("chunk_lo")]).where(F.col(key) < F.col("chunk_hi"))
    else:
        rows = rows.where((F.col(key) >= lows[0]) & (F.col(key) < chunks[-1].hi))
        rows = in_cells(rows, key, [(c.lo, c.hi, 0) for c in chunks], "unused_ int").drop("unused_").withColumnsRenamed({"cell_lo": "chunk_lo", "cell_hi": "chunk_hi"})
    d = len(spec.columns())
    names = [f"x{j}" for j in range(d)]
    rows = rows.select("chunk_lo", "chunk_hi", F.col(key).alias("key_"), "y_", *names)
    if spec.trainer.split("-")[-1] == "batch" and max(c.hi - c.lo for c in chunks) > IN_TASK:
        return _descend(rows, spec, names)

    def train(batches):
        held: list = []  # (lo, hi, x, y) of chunks read whole, the last still growing

        def settle(done):
            if done:
                ws = train_many([(np.concatenate(x), np.concatenate(y)) for _, _, x, y in done], spec)
                yield pd.DataFrame({"chunk_lo": [c[0] for c in done], "chunk_hi": [c[1] for c in done], "n": [sum(map(len, c[3])) for c in done], "w": ws})

        for pdf in batches:
            lo, hi = pdf["chunk_lo"].to_numpy(), pdf["chunk_hi"].to_numpy()
            x, y = pdf[names].to_numpy(), pdf["y_"].to_numpy()
            cut = np.concatenate(([0], np.flatnonzero(lo[1:] != lo[:-1]) + 1, [len(lo)]))
            for a, b in zip(cut[:-1], cut[1:]):
                if a == b:
                    continue
                if held and held[-1][0] == lo[a]:
                    held[-1][2].append(x[a:b])
                    held[-1][3].append(y[a:b])
                    continue
                if sum(len(p) for c in held for p in c[3]) >= SIDE_BY_SIDE:
                    yield from settle(held)
                    held = []
                held.append((lo[a], hi[a], [x[a:b]], [y[a:b]]))
        yield from settle(held)

    parts = max(1, min(len(chunks), int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    dealt = rows.repartition(parts, "chunk_lo").sortWithinPartitions("chunk_lo", "key_")
    return dealt.mapInPandas(train, "chunk_lo long, chunk_hi long, n long, w array<double>")


def _runs(ranges: list[Range], parts: int) -> list[list[int]]:
    """Numbers of the ranges, in order of their starts, cut into `parts` runs at most. Keys below ends
    of two runs count in both, so the least share of keys is sought with which runs suffice."""
    order = sorted(range(len(ranges)), key=lambda i: ranges[i])

    def cut(share):
        out: list[list[int]] = []
        used, end = 0, 0
        for i in order:
            lo, hi = ranges[i]
            more = max(0, hi - max(lo, end))
            if not out or used + more > share:
                out.append([])
                used, end, more = 0, lo, hi - lo
            out[-1].append(i)
            used, end = used + more, max(end, hi)
        return out

    least, most = max(hi - lo for lo, hi in ranges), sum(r.hi - r.lo for r in union(ranges))
    while least < most:
        share = (least + most) // 2
        least, most = (least, share) if len(cut(share)) <= parts else (share + 1, most)
    return cut(least)


def train_ranges(source: PointSource, spec: ModelSpec, ranges: list[Range]) -> list[LogisticState]:
    """Models of many ranges, which may overlap, by one pass of single-point steps over each.

    A task takes ranges that start near each other and goes once, in key order, through the points
    below them: each point is a step of all ranges that hold it. It holds weights and one batch of
    points, however long the ranges. Written features are read in key order by each task that needs
    them; points of other sources are dealt and sorted. The driver gets a row a range.
    """
    if spec.trainer != "sgd" or spec.steps != 1:
        raise ValueError("ranges are stepped through together in one pass of single points")
    wanted = [Range(*r) for r in dict.fromkeys(map(tuple, ranges)) if r[0] < r[1]]
    none = LogisticState(spec.spec_id, 0, np.zeros(len(spec.columns())))
    if not wanted:
        return [none for _ in ranges]
    ready = source.prepared(spec, project)
    runs = _runs(wanted, ready.df.sparkSession.sparkContext.defaultParallelism)
    spans = [(min(wanted[i].lo for i in run), max(wanted[i].hi for i in run)) for run in runs]
    names = [f"x{j}" for j in range(len(spec.columns()))]
    step, shrink = spec.step_size, 1 - 2 * spec.step_size * spec.l2
    key = F.col(source.key)

    def walk(points):
        """Ranges open at a key are rows of w; between two ends of ranges the rows stay the same."""
        state: dict = {}
        w, live, cuts, at = np.zeros((0, len(names))), [], [], 0
        for i, k, x, y in points:
            if not cuts:
                run = runs[i]
                cuts = sorted({c for i in run for c in wanted[i]})
                opens: dict = {}
                for i in run:
                    opens.setdefault(wanted[i].lo, []).append(i)
                at = -1
            t = 0
            while t < len(k):
                while at + 1 < len(cuts) and cuts[at + 1] <= k[t]:
                    at += 1
                    state.update({i: (n, v) for (i, n), v in zip(live, w)})
                    live = [(i, n) for i, n in live if wanted[i].hi > cuts[at]]
                    live += [(i, 0) for i in opens.get(cuts[at], ())]
                    w = np.array([state[i][1] if i in state else np.zeros(len(names)) for i, _ in live]).reshape(-1, len(names))
                stop = int(np.searchsorted(k, cuts[at + 1])) if at + 1 < len(cuts) else len(k)
                if live:
                    _steps(w, x[t:stop], y[t:stop], step, shrink)
                    live = [(i, n + stop - t) for i, n in live]
                t = stop
        state.update({i: (n, v) for (i, n), v in zip(live, w)})
        if state:
            yield pd.DataFrame({"id": list(state), "n": [n for n, _ in state.values()], "w": [v for _, v in state.values()]})

    def dealt(batches):
        return walk((int(pdf["task_"].iloc[0]), pdf["key_"].to_numpy(), np.ascontiguousarray(pdf[names].to_numpy()), pdf["y_"].to_numpy()) for pdf in batches if len(pdf))

    schema = "id int, n long, w array<double>"
    if ready.reader is not None:
        from spanfold.sources.local import LocalReader

        place, own = (ready.reader.path, ready.reader.key, ready.reader.width), source.key

        def pieces(i):
            reader = LocalReader(*place)
            for lo, hi in union(wanted[j] for j in runs[i]):
                for a in range(lo, hi, SIDE_BY_SIDE):
                    table = reader.read(a, min(a + SIDE_BY_SIDE, hi))
                    for t in range(0, table.num_rows, BATCH):
                        part = table.slice(t, BATCH)
                        yield i, part.column(own).to_numpy(), *arrays_of(part, spec)

        def read(batches):
            for pdf in batches:
                for i in pdf["id"].tolist():
                    yield from walk(pieces(i))

        rows = ready.df.sparkSession.range(0, len(runs), 1, len(runs)).mapInPandas(read, schema)
    else:
        task = F.array_compact(F.array(*[F.when((key >= lo) & (key < hi), F.lit(i)) for i, (lo, hi) in enumerate(spans)]))
        rows = ready.scan_range(min(lo for lo, _ in spans), max(hi for _, hi in spans)).select(F.explode(task).alias("task_"), key.alias("key_"), "y_", *names)
        rows = rows.repartitionById(len(runs), F.col("task_")).sortWithinPartitions("key_").mapInPandas(dealt, schema)
    found = {wanted[r.id]: LogisticState(spec.spec_id, r.n, np.array(r.w)) for r in rows.collect()}
    return [found.get(Range(*r), none) for r in ranges]


def _steps(w: np.ndarray, x: np.ndarray, y: np.ndarray, step: float, shrink: float) -> None:
    """Single-point steps of all rows of w at once, in place.

    Weights are moved once a block of points. Within a block a point's margin is that of the weights
    before the block, less the steps of the points between, which are products of points and so the
    same for all rows: a step is one product and one tanh(margin / 2) = 2 * probability - 1.
    """
    v, n = np.ascontiguousarray(w.T), len(x) // BLOCK * BLOCK
    for a, size, count in ((0, BLOCK, len(x) // BLOCK), (n, len(x) - n, 1)):
        if not size or not count:
            continue
        p, c = x[a : a + size * count].reshape(count, size, -1), 1 - 2 * y[a : a + size * count].reshape(count, size, 1)
        at = np.arange(size)
        gap = at[:, None] - at - 1
        pull = np.where(gap >= 0, p @ p.transpose(0, 2, 1) * (-step / 4 * shrink ** np.maximum(gap, 0.0)), 0.0)
        known = pull @ c
        pull[:, at, at] = 1
        half = p * (shrink**at / 2)[:, None]
        push = (p * (step / 2 * shrink ** (size - 1.0 - at))[:, None]).transpose(0, 2, 1).copy()
        moved = push @ c
        u, line, z = np.empty((size, len(w))), np.empty((size, size)), np.empty(len(w))
        turns = [(line[t, : t + 1], u[: t + 1], u[t]) for t in range(size)]
        for k in range(count):
            np.dot(half[k], v, out=u)
            u += known[k]
            line[:] = pull[k]
            for own, before, now in turns:
                np.dot(own, before, z)
                np.tanh(z, now)
            if shrink != 1:
                v *= shrink**size
            v -= push[k] @ u
            v -= moved[k]
    w[:] = v.T


def range_hits(source: PointSource, spec: ModelSpec, ranges: list[Range], models: list[np.ndarray]) -> list[np.ndarray]:
    """Shares of each range's points that its models (rows of weights) tell right; batches of points
    send counts, the driver gets a row a range."""
    ready = source.prepared(spec, project)
    names = [f"x{j}" for j in range(len(spec.columns()))]
    los, his = (np.array([r[e] for r in ranges], dtype=np.int64) for e in (0, 1))
    width = len(models[0])

    def count(batches):
        for pdf in batches:
            pdf = pdf if pdf["key_"].is_monotonic_increasing else pdf.sort_values("key_")
            k, x, y = pdf["key_"].to_numpy(), pdf[names].to_numpy(), pdf["y_"].to_numpy() == 1
            first, last = np.searchsorted(k, los), np.searchsorted(k, his)
            out = [(i, last[i] - first[i], *((models[i] @ x[first[i] : last[i]].T >= 0) == y[first[i] : last[i]]).sum(axis=1)) for i in np.flatnonzero(last > first)]
            yield pd.DataFrame(out, columns=["id", "n", *[f"h{j}" for j in range(width)]]).astype("int64")

    schema = "id long, n long, " + ", ".join(f"h{j} long" for j in range(width))
    rows = ready.scan_range(int(los.min()), int(his.max())).select(F.col(source.key).alias("key_"), "y_", *names)
    got = rows.mapInPandas(count, schema).groupBy("id").agg(F.sum("n").alias("n"), *[F.sum(f"h{j}").alias(f"h{j}") for j in range(width)])
    share = {r.id: np.array(r[2:], dtype=float) / r.n for r in got.collect()}
    return [share.get(i, np.full(width, np.nan)) for i in range(len(ranges))]


def _descend(rows: DataFrame, spec: ModelSpec, names: list[str]) -> DataFrame:
    """(chunk_lo, chunk_hi, n, w) by full-batch steps, one job a step: each batch of points sends its
    gradient sums, chunks only send a row to the driver. Points are read where they lie."""
    classes = int(spec.trainer.split("-")[1]) if spec.trainer.startswith("each-") else 0
    targets = [float(c) for c in range(1, classes + 1)] or [None]
    d, width = len(names), len(names) * len(targets)
    sums = ", ".join(f"g{j} double" for j in range(width))
    now: dict = {}

    def gradients(ws):
        def run(batches):
            for pdf in batches:
                lo, x, y = pdf["chunk_lo"].to_numpy(), pdf[names].to_numpy(), pdf["y_"].to_numpy()
                out = []
                for c in np.unique(lo):
                    own = lo == c
                    a, b = x[own], y[own]
                    w = ws.get(int(c), np.zeros(width)).reshape(-1, d)
                    errors = [1 / (1 + np.exp(-np.clip(a @ v, -500, 500))) - (b if t is None else b == t) for t, v in zip(targets, w)]
                    out.append((c, pdf["chunk_hi"].to_numpy()[own][0], len(b), *np.concatenate([a.T @ e for e in errors])))
                if out:
                    yield pd.DataFrame(out, columns=["chunk_lo", "chunk_hi", "n", *[f"g{j}" for j in range(width)]])

        return run

    for _ in range(max(1, spec.steps)):
        each = rows.mapInPandas(gradients({c: w for c, (_, _, w) in now.items()}), f"chunk_lo long, chunk_hi long, n long, {sums}")
        total = each.groupBy("chunk_lo", "chunk_hi").agg(F.sum("n").alias("n"), *[F.sum(f"g{j}").alias(f"g{j}") for j in range(width)])
        for r in total.collect():  # a row a chunk
            w = now[r.chunk_lo][2] if r.chunk_lo in now else np.zeros(width)
            if spec.steps:
                w = w - spec.step_size * (np.array(r[3:]) / r.n + 2 * spec.l2 * w)
            now[r.chunk_lo] = (r.chunk_hi, r.n, w)
    return rows.sparkSession.createDataFrame([(c, hi, n, [float(v) for v in w]) for c, (hi, n, w) in sorted(now.items())], "chunk_lo long, chunk_hi long, n long, w array<double>")


def average_models(models, weighting: str = "uniform") -> LogisticState:
    """Mean of weights; a stored average counts as its chunks (or its points)."""
    models = [m for m in models if m.n]
    share = np.array([m.n_chunks if weighting == "uniform" else m.n for m in models], dtype=float)
    w = (np.stack([m.w for m in models]) * (share / share.sum())[:, None]).sum(axis=0)
    return LogisticState(models[0].spec_id, sum(m.n for m in models), w, sum(m.n_chunks for m in models))


def average_frame(models: DataFrame, weighting: str = "uniform") -> DataFrame:
    """(i, w): the same average inside Spark, for more chunks than a driver should hold."""
    share = F.col("n_chunks") if weighting == "uniform" and "n_chunks" in models.columns else F.lit(1) if weighting == "uniform" else F.col("n")
    each = models.select(share.cast("double").alias("m"), F.posexplode("w").alias("i", "v"))
    return each.groupBy("i").agg((F.sum(F.col("m") * F.col("v")) / F.sum("m")).alias("w"))


def mixed(x):
    """An arithmetic hash of a whole number to 31 bits, the same in any SQL; no product leaves 63 bits."""
    low = lambda v: F.pmod(v, F.lit(1 << 31))
    x = low(low(x) * F.lit(2654435761))
    x = low(x.bitwiseXOR(F.shiftright(x, 15)) * F.lit(2246822519))
    return x.bitwiseXOR(F.shiftright(x, 13))


def average_of_subsamples(points: DataFrame, spec: ModelSpec, p: int, m: int, seed: int = 1, key: str | None = None, mu=None, n: int | None = None) -> LogisticState:
    """Weights averaged over p sub-samples of m points each, drawn independently and with
    replacement from dense keys below n (the number of points by default); mu weighs them (even by
    default).

    Draws are made in the plan, p·m short rows, and joined to the points by key; a point drawn twice
    counts twice. A sub-sample's rows meet in a task and are taken in the order drawn.
    """
    key = key or spec.key
    n = points.count() if n is None else n
    t = F.col("id")
    spot = F.floor(mixed(t + F.lit(seed * 1_000_003)).cast("double") / float(1 << 31) * F.lit(float(n))).cast("long")
    draws = points.sparkSession.range(p * m).select(F.floor(t / m).cast("int").alias("sub"), (t % m).alias("turn_"), spot.alias(key))
    draws = F.broadcast(draws) if p * m <= 1 << 20 else draws
    rows = project(points, spec, keep=[key]).join(draws, key)
    names = [f"x{j}" for j in range(len(spec.columns()))]

    def train(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("turn_")
        w = train_arrays(pdf[names].to_numpy(), pdf["y_"].to_numpy(), spec)
        return pd.DataFrame({"sub": [pdf["sub"].iloc[0]], "n": [len(pdf)], "w": [w]})

    got = sorted(rows.groupBy("sub").applyInPandas(train, "sub int, n long, w array<double>").collect(), key=lambda r: r["sub"])
    share = np.ones(len(got)) if mu is None else np.array([mu[r["sub"]] for r in got], dtype=float)
    w = (np.array([r.w for r in got]) * (share / share.sum())[:, None]).sum(axis=0)
    return LogisticState(spec.spec_id, sum(r.n for r in got), w, len(got))


def one_vs_rest(points: DataFrame, spec: ModelSpec, classes, chunks: list[Range]) -> dict[str, LogisticState]:
    """One averaged model for each class against the others. Points are read and shuffled once:
    they carry the number of their class, and each chunk trains all classes where it lies."""
    names = sorted(classes)
    which = F.array_position(F.array(*map(F.lit, names)), F.expr(spec.label).cast("string")).cast("double")
    rows = project(points, spec, keep=[F.col(spec.key), which.alias("class_")]).drop("y_").withColumnRenamed("class_", "y_")
    models = {}
    for r in train_chunks(rows, replace(spec, trainer=f"each-{len(names)}-{spec.trainer}"), chunks, ready=True).collect():  # one row a chunk
        for c, w in zip(names, np.array(r.w).reshape(len(names), -1)):
            models.setdefault(c, []).append((r.chunk_lo, LogisticState(spec.spec_id, r.n, w)))
    return {c: average_models([s for _, s in sorted(own, key=lambda x: x[0])]) for c, own in models.items()}


def ovr_predict(df: DataFrame, spec: ModelSpec, models: dict, name: str = "prediction") -> DataFrame:
    from spanfold.functions.bayes import predict

    return predict(df, [(c, margin(spec, models[c].w)) for c in sorted(models)], name)


def largest_norm(points: DataFrame, spec: ModelSpec) -> DataFrame:
    square = F.lit(0.0)
    for x in scaled(spec):
        square = square + x * x
    return points.agg(F.sqrt(F.max(square)).alias("radius"))


def distance_bound(radius: float, l2: float, chunk: int, n: int, delta: float) -> float:
    """With probability 1 - delta, averaged and whole-range weights differ by this much at most."""
    p = max(1, n // chunk)
    near = radius * math.sqrt(2) / l2 * (1 / math.sqrt(chunk) + 1 / math.sqrt(n))
    return near + 2 * math.sqrt(2) * radius / (l2 * math.sqrt(p * chunk)) * math.sqrt(math.log(1 / delta))


def parameter_distance(a, b) -> float:
    return float(np.linalg.norm(np.asarray(a) - np.asarray(b)))

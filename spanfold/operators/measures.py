"""Cost, storage and accuracy measures of the experiments."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.plans.ranges import union
from spanfold.plans.relevance import group_descriptors


def coverage(models, directory) -> float:
    """Percentage of all points below at least one model."""
    total = float(directory.running[-1])
    return 100.0 * sum(directory.count(r.lo, r.hi) for r in union(m.range for m in models)) / total if total else 0.0


def coverage_frame(models: DataFrame, n_points: int) -> DataFrame:
    """The same on dense keys as one row: covered points and percentage."""
    groups = group_descriptors(models)
    return groups.agg(F.coalesce(F.sum(F.col("ghi") - F.col("glo")), F.lit(0)).alias("covered")).withColumn("pct", F.col("covered") * 100.0 / n_points)


def gain(runs) -> dict:
    """(time with reuse, time from raw points) pairs to the ratio printed and the speedup meant,
    each as a ratio of means and as a mean of ratios."""
    t, t0 = np.array([r[0] for r in runs], float), np.array([r[1] for r in runs], float)
    return {"time_ratio": t.mean() / t0.mean(), "speedup": t0.mean() / t.mean(), "mean_time_ratio": (t / t0).mean(), "mean_speedup": (t0 / t).mean()}


def time_split(answers) -> dict:
    """Mean seconds of planning, reading and merging; the three make the total."""
    return {k: float(np.mean([getattr(a, k) for a in answers])) for k in ("t_plan", "t_io", "t_merge", "t_total")}


def store_size(store, spec) -> int:
    return sum(store.rows[m.model_id]["nbytes"] for m in store.models(spec))


def storage_overhead(store, spec, n_points: int, bytes_per_point: int | None = None) -> float:
    """Bytes of kept models in percent of the base data's."""
    base = n_points * (bytes_per_point or 8 * (len(spec.features) + 1))
    return 100.0 * store_size(store, spec) / base


def work(answer) -> dict:
    p = answer.plan
    return {
        "points_read": answer.points_read, "models_read": len(p.models), "segments": len(p.segments), "graph_nodes": p.graph_nodes, "graph_edges": p.graph_edges, "plan_cost": p.cost,
    }


def accuracy(predicted: DataFrame, label: str, prediction: str = "prediction") -> DataFrame:
    """n, correct, accuracy of a frame with predictions."""
    hit = F.expr(label).cast("string") == F.col(prediction).cast("string")
    return predicted.agg(F.count("*").alias("n"), F.count_if(hit).alias("correct")).withColumn("accuracy", F.col("correct") / F.col("n"))


def accuracy_difference(runs, edges=None) -> list[dict]:
    """(size, accuracy from raw points, accuracy with reuse) to mean, mean of positive cases and
    maximum of the difference, by size bin."""
    runs = np.array(runs, dtype=float)
    edges = [-np.inf, np.inf] if edges is None else edges
    out = []
    for lo, hi in zip(edges, edges[1:]):
        d = (runs[:, 1] - runs[:, 2])[(runs[:, 0] >= lo) & (runs[:, 0] < hi)]
        if len(d):
            out.append({"lo": lo, "hi": hi, "n": len(d), "mean": d.mean(), "mean_positive": d[d > 0].mean() if (d > 0).any() else 0.0, "max": d.max()})
    return out


def accuracy_difference_frame(runs: DataFrame, width: float) -> DataFrame:
    """The same of a table (size, acc_base, acc), binned by width."""
    d = F.col("acc_base") - F.col("acc")
    return runs.groupBy(F.floor(F.col("size") / width).cast("long").alias("size_bin")).agg(
        F.count("*").alias("n"), F.avg(d).alias("mean_diff"), F.coalesce(F.avg(F.when(d > 0, d)), F.lit(0.0)).alias("mean_positive"), F.max(d).alias("max_diff")
    )


def state_distance(a, b) -> float:
    """Largest difference of two exact states; 0 means identical models."""
    if hasattr(a, "cross"):
        return float(max(abs(x - y) for x, y in zip([a.n, *a.cross, *a.total], [b.n, *b.cross, *b.total])))
    if set(a.classes) != set(b.classes):
        return float("inf")
    flat = lambda s: [x for c in sorted(s.classes) for x in (s.classes[c][0], *s.classes[c][1], *s.classes[c][2])]
    return float(max((abs(x - y) for x, y in zip(flat(a), flat(b))), default=0))


def bound_report(distances, bound: float) -> dict:
    d = np.array(list(distances), float)
    return {"runs": len(d), "bound": bound, "max_distance": float(d.max()), "mean_distance": float(d.mean()), "violations": float((d > bound).mean())}


def cost_fidelity(planned, measured) -> float:
    """Rank correlation of planned cost and measured time."""
    rank = lambda x: np.argsort(np.argsort(x)).astype(float)
    a, b = rank(np.array(planned)), rank(np.array(measured))
    return float(np.corrcoef(a, b)[0, 1]) if len(a) > 1 and a.std() and b.std() else 1.0

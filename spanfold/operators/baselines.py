"""Models from raw points only, against which reuse is measured."""

from __future__ import annotations

import numpy as np
import pandas as pd

from pyspark.sql import functions as F

from spanfold.functions.bayes import gnb_params, mnb_params
from spanfold.functions.linear import linreg_solve
from spanfold.functions.logistic import LogisticState, arrays_of, logit_gradient, project, scaled, train_arrays
from spanfold.operators.combine import build
from spanfold.sources.local import MOST_POINTS
from spanfold.sources.points import ModelSpec, PointSource


def scratch_linreg(source: PointSource, spec: ModelSpec, lo: int, hi: int, ridge: float = 0.0) -> np.ndarray:
    return linreg_solve(build(source, spec, lo, hi).state, ridge, intercept=spec.intercept)


def scratch_gnb(source: PointSource, spec: ModelSpec, lo: int, hi: int, var_floor: float = 0.0) -> dict:
    return gnb_params(build(source, spec, lo, hi).state, var_floor)


def scratch_mnb(source: PointSource, spec: ModelSpec, lo: int, hi: int, alpha: float = 1.0) -> dict:
    return mnb_params(build(source, spec, lo, hi).state, alpha)


def scratch_sgd(source: PointSource, spec: ModelSpec, lo: int, hi: int) -> LogisticState:
    """One pass of single-point steps over the whole range in key order.

    Sequential by its nature: one task, which carries only the weights from batch to batch. A range
    that the source's reader may read on the driver is stepped through there.
    """
    ready = source.prepared(spec, project)
    if ready.reader is not None and hi - lo <= MOST_POINTS:
        x, y = arrays_of(ready.reader.read(lo, hi), spec)
        return LogisticState(spec.spec_id, len(y), train_arrays(x, y, spec))
    names = [f"x{j}" for j in range(len(spec.columns()))]
    rows = ready.scan_range(lo, hi).select(F.col(source.key).alias("key_"), "y_", *names)

    def run(batches):
        w, n = np.zeros(len(names)), 0
        for pdf in batches:
            w = train_arrays(pdf[names].to_numpy(), pdf["y_"].to_numpy(), spec, w)
            n += len(pdf)
        yield pd.DataFrame({"n": [n], "w": [w]})

    row = rows.repartition(1).sortWithinPartitions("key_").mapInPandas(run, "n long, w array<double>").first()
    return LogisticState(spec.spec_id, row.n, np.array(row.w))


def scratch_batch(source: PointSource, spec: ModelSpec, lo: int, hi: int, steps: int) -> LogisticState:
    """Full-batch descent over the whole range: one aggregation job a step."""
    w = np.zeros(len(spec.columns()))
    n = 0
    for _ in range(steps):
        g = logit_gradient(source.scan_range(lo, hi), spec, w, spec.l2).first()
        w = w - spec.step_size * np.array([g[f"g{j}"] for j in range(len(w))])
        n = g["n"]
    return LogisticState(spec.spec_id, n, w)


def library_logistic(source: PointSource, spec: ModelSpec, lo: int, hi: int, l2: float, iterations: int = 100) -> np.ndarray:
    """The optimum by an independent solver; its penalty is half ours, hence twice the weight."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    names = [f"x{j}" for j in range(len(spec.columns()))]
    rows = source.scan_range(lo, hi).select(F.expr(spec.label).cast("double").alias("label"), *[c.alias(n) for c, n in zip(scaled(spec), names)])
    vec = VectorAssembler(inputCols=names, outputCol="features").transform(rows)
    fit = LogisticRegression(regParam=2 * l2, fitIntercept=False, standardization=False, maxIter=iterations, tol=1e-12).fit(vec)
    return fit.coefficients.toArray()

"""Models in SQL: prediction functions, plan and chunk table functions, an aggregate."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from spanfold.functions.logistic import make_chunks
from spanfold.plans.costs import LinearCost
from spanfold.plans.planner import best_plan
from spanfold.plans.ranges import Range


def register_predictors(spark: SparkSession, w_linear, w_logit) -> None:
    """predict_linear(array<double>) and predict_logit(array<double>); column expressions are
    faster where the weights are known when the plan is built."""
    wl, wg = np.asarray(w_linear, float), np.asarray(w_logit, float)

    def predict_linear(x: pd.Series) -> pd.Series:
        return pd.Series(np.stack(x.to_numpy()) @ wl if len(x) else [], dtype=float)

    def predict_logit(x: pd.Series) -> pd.Series:
        return pd.Series(1 / (1 + np.exp(-(np.stack(x.to_numpy()) @ wg))) if len(x) else [], dtype=float)

    spark.udf.register("predict_linear", F.pandas_udf(predict_linear, "double"))
    spark.udf.register("predict_logit", F.pandas_udf(predict_logit, "double"))


def register_bayes(spark: SparkSession, params: dict, name: str = "predict_nb") -> None:
    """predict_nb(array<double>): the likeliest class by Gaussian parameters (class -> prior, means,
    variances); ties go to the smaller name, and a feature that never varied fits its value only."""
    names = sorted(params)
    prior = np.log([params[c][0] for c in names])
    mean, var = (np.array([params[c][i] for c in names], dtype=float) for i in (1, 2))

    def predict_nb(x: pd.Series) -> pd.Series:
        if not len(x):
            return pd.Series([], dtype=str)
        gap = np.stack(x.to_numpy())[:, None, :] - mean
        with np.errstate(divide="ignore", invalid="ignore"):
            part = np.where(var > 0, -0.5 * np.log(2 * np.pi * var) - gap * gap / (2 * var), np.where(gap == 0, 0.0, -np.inf))
        return pd.Series(np.array(names)[(prior + part.sum(axis=2)).argmax(axis=1)])

    spark.udf.register(name, F.pandas_udf(predict_nb, "string"))


def gram_agg():
    """Grouped aggregate: packed second moments of a vector column. For small groups only."""

    def gram(x: pd.Series) -> list:
        m = np.stack(x.to_numpy()).astype(float)
        g = m.T @ m
        return g[np.triu_indices(len(g))].tolist()

    gram.__annotations__ = {"x": pd.Series, "return": list}
    from pyspark.sql.functions import PandasUDFType, pandas_udf

    return pandas_udf(gram, "array<double>", PandasUDFType.GROUPED_AGG)


def register_table_functions(spark: SparkSession, models, cost=LinearCost(), directed: bool = False) -> None:
    """plan_segments(lo, hi) lists the plan over the given descriptors; chunk_ranges(lo, hi, size)."""
    kept = list(models)

    @F.udtf(returnType="seq int, sign int, kind string, lo long, hi long, model_id string, cost double")
    class PlanSegments:
        def eval(self, lo: int, hi: int):
            for i, s in enumerate(best_plan(kept, Range(lo, hi), cost, directed=directed).segments):
                yield i, s.sign, s.kind, s.lo, s.hi, s.model_id, float(s.cost)

    @F.udtf(returnType="seq int, lo long, hi long")
    class ChunkRanges:
        def eval(self, lo: int, hi: int, size: int):
            for i, r in enumerate(make_chunks(lo, hi, size)):
                yield i, r.lo, r.hi

    spark.udtf.register("plan_segments", PlanSegments)
    spark.udtf.register("chunk_ranges", ChunkRanges)


def register_views(store, spec, models=None) -> None:
    """models and model_groups as temporary views."""
    from spanfold.plans.relevance import group_descriptors

    d = store.descriptors(spec)
    d.createOrReplaceTempView("kept_models")
    group_descriptors(d).createOrReplaceTempView("model_groups")

"""Gaussian and multinomial naive Bayes from additive state."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from fractions import Fraction

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.sources.points import ModelSpec, check_rows


@dataclass
class BayesState:
    """Per class: count, and for each feature the sum and (Gaussian) the sum of squares, exact."""

    spec_id: str
    units: tuple
    classes: dict = field(default_factory=dict)  # class -> [n, sums, squares]

    @property
    def n(self) -> int:
        return sum(c[0] for c in self.classes.values())

    def combine(self, other: "BayesState", sign: int = 1) -> "BayesState":
        if self.spec_id != other.spec_id:
            raise ValueError("models of different specs do not combine")
        out = {c: [v[0], list(v[1]), list(v[2])] for c, v in self.classes.items()}
        for c, (n, s, q) in other.classes.items():
            mine = out.setdefault(c, [0, [0] * len(s), [0] * len(q)])
            mine[0] += sign * n
            mine[1] = [a + sign * b for a, b in zip(mine[1], s)]
            mine[2] = [a + sign * b for a, b in zip(mine[2], q)]
        # a difference may have count 0 and sums that are not: only an empty class goes
        return BayesState(self.spec_id, self.units, {c: v for c, v in out.items() if v[0] or any(v[1]) or any(v[2])})

    @property
    def nbytes(self) -> int:
        return sum(8 * (1 + len(s) + len(q)) for _, s, q in self.classes.values())


def project(df: DataFrame, spec: ModelSpec, keep=()) -> DataFrame:
    """Class and features as integers, the columns a state needs."""
    df = check_rows(df, spec)
    return df.select(*keep, F.expr(spec.label).cast("string").alias("class"), *[f.integer().alias(f"v{i}") for i, f in enumerate(spec.features)])


_aggregates: dict = {}


def sums(rows: DataFrame, spec: ModelSpec, by=(), sign: str | None = None) -> DataFrame:
    """Aggregate projected rows by class; squares are decimals where a bound could leave 64 bits."""
    at = (id(rows.sparkSession), spec.spec_id, sign)
    if at not in _aggregates:
        s = F.col(sign) if sign else F.lit(1)
        aggs = [F.sum(s.cast("bigint")).alias("n")]
        aggs += [F.sum(F.col(f"v{i}") * s).alias(f"s{i}") for i in range(len(spec.features))]
        for i, f in enumerate(spec.features if spec.kind == "gnb" else ()):
            square = F.col(f"v{i}") * F.col(f"v{i}") * s
            aggs.append(F.sum(square.cast("decimal(28,0)") if f.limit * f.limit >= 1 << 31 else square).alias(f"q{i}"))
        _aggregates[at] = aggs
    return rows.groupBy(*by, "class").agg(*_aggregates[at])


def bayes_states(df: DataFrame, spec: ModelSpec, by=(), sign: str | None = None) -> DataFrame:
    """Rows (by…, class, n, s0…, q0…): integer sums of scaled features and of their squares.
    Multinomial specs keep no squares."""
    return sums(project(df, spec, [*by, *([sign] if sign else [])]), spec, by, sign)


def state_from_rows(rows, spec: ModelSpec) -> BayesState:
    d = len(spec.features)
    out = BayesState(spec.spec_id, tuple(f.unit for f in spec.features))
    for r in rows:
        q = [int(r[f"q{i}"]) for i in range(d)] if spec.kind == "gnb" else []
        s = [int(r[f"s{i}"]) for i in range(d)]
        if r["n"] or any(s) or any(q):
            out.classes[r["class"]] = [int(r["n"]), s, q]
    return out


def state_of_table(table, spec: ModelSpec) -> BayesState:
    """Exact state of projected points held in memory (an Arrow table with class, v0, v1, …)."""
    out = BayesState(spec.spec_id, tuple(f.unit for f in spec.features))
    if not table.num_rows:
        return out
    x = np.stack([table.column(f"v{i}").to_numpy() for i in range(len(spec.features))], axis=1)
    most = int(np.abs(x).max(initial=0))
    squares = x * x if most * most * len(x) < 1 << 62 else x.astype(object) ** 2
    names, which = np.unique(table.column("class").to_numpy(zero_copy_only=False).astype(str), return_inverse=True)
    for c, name in enumerate(names):
        own = which == c
        q = [int(v) for v in squares[own].sum(axis=0)] if spec.kind == "gnb" else []
        out.classes[str(name)] = [int(own.sum()), [int(v) for v in x[own].sum(axis=0)], q]
    return out


def bayes_state(df: DataFrame, spec: ModelSpec, sign: str | None = None) -> BayesState:
    return state_from_rows(bayes_states(df, spec, sign=sign).collect(), spec)  # one row a class


def point_state(spec: ModelSpec, values, label: str) -> BayesState:
    v = [int(round(x * f.unit)) for x, f in zip(values, spec.features)]
    return BayesState(spec.spec_id, tuple(f.unit for f in spec.features), {label: [1, v, [x * x for x in v] if spec.kind == "gnb" else []]})


def class_prior(state: BayesState) -> dict:
    total = state.n
    return {c: v[0] / total for c, v in state.classes.items()}


def gnb_params(state: BayesState, var_floor: float = 0.0) -> dict:
    """Class -> (prior, means, population variances); variances come from exact numbers."""
    total, out = state.n, {}
    for c, (n, s, q) in state.classes.items():
        means = [float(Fraction(a, n * u)) for a, u in zip(s, state.units)]
        variances = [max(var_floor, float(Fraction(n * b - a * a, n * n * u * u))) for a, b, u in zip(s, q, state.units)]
        out[c] = (n / total, means, variances)
    return out


def mnb_params(state: BayesState, alpha: float = 1.0) -> dict:
    """Class -> (prior, smoothed feature probabilities); alpha 1 is add-one smoothing."""
    total, out = state.n, {}
    for c, (n, s, _) in state.classes.items():
        mass = sum(s)
        out[c] = (n / total, [(x + alpha) / (mass + alpha * len(s)) for x in s])
    return out


def featured(df: DataFrame, spec: ModelSpec) -> DataFrame:
    """The points with their features as columns f_0, f_1, …, so that scores of many classes do
    not work them out again."""
    return df.withColumns({f"f_{i}": f.real() for i, f in enumerate(spec.features)})


def gnb_scores(spec: ModelSpec, params: dict):
    """(class, column of its log posterior up to a constant over `featured` points) by class name. A class
    with a feature that never varied fits only that value exactly."""
    out = []
    for c in sorted(params):
        prior, means, variances = params[c]
        score = F.lit(math.log(prior))
        for i, (m, v) in enumerate(zip(means, variances)):
            x = F.col(f"f_{i}")
            if v > 0:
                score = score - F.lit(0.5 * math.log(2 * math.pi * v)) - (x - F.lit(m)) * (x - F.lit(m)) / F.lit(2 * v)
            else:
                score = score + F.when(x == F.lit(m), 0.0).otherwise(float("-inf"))
        out.append((c, score))
    return out


def mnb_scores(spec: ModelSpec, params: dict):
    out = []
    for c in sorted(params):
        prior, theta = params[c]
        score = F.lit(math.log(prior))
        for i, t in enumerate(theta):
            score = score + F.col(f"f_{i}") * F.lit(math.log(t))
        out.append((c, score))
    return out


def mnb_log_likelihood(spec: ModelSpec, theta, with_coefficient: bool = False):
    """Column: log probability of a point's counts in one class; the coefficient needs lgamma,
    built here from sums of logs of each count's factorial."""
    score = F.lit(0.0)
    for f, t in zip(spec.features, theta):
        score = score + f.real() * F.lit(math.log(t))
    if with_coefficient:
        log_factorial = lambda x: F.coalesce(F.aggregate(F.sequence(F.lit(1), F.greatest(F.lit(1), x)), F.lit(0.0), lambda a, k: a + F.log(k.cast("double"))), F.lit(0.0))
        total = F.lit(0)
        for f in spec.features:
            total = total + f.integer()
            score = score - log_factorial(f.integer())
        score = score + log_factorial(total)
    return score


def mnb_state_sparse(df: DataFrame, spec: ModelSpec, tokens) -> BayesState:
    """Multinomial state from tokens; features of the spec are named as the tokens."""
    names = [f.name for f in spec.features]
    out = BayesState(spec.spec_id, tuple(1 for _ in names))
    for r in df.groupBy(F.expr(spec.label).cast("string").alias("class")).count().collect():  # one row a class
        out.classes[r["class"]] = [r["count"], [0] * len(names), []]
    each = df.select(F.expr(spec.label).cast("string").alias("class"), F.explode(tokens).alias("feature")).where(F.col("feature").isin(names))
    at = {n: i for i, n in enumerate(names)}
    for r in each.groupBy("class", "feature").count().collect():  # one row a class and feature
        out.classes[r["class"]][1][at[r["feature"]]] = r["count"]
    return out


def mnb_predict_sparse(df: DataFrame, spec: ModelSpec, tokens, params: dict, key: str) -> DataFrame:
    """(key, class, prediction): log probabilities of a point's tokens, summed by point.

    The model is a broadcast row a token with its log probabilities by class (vocabulary × classes
    doubles). A point's tokens are neighbours, so they combine before the one shuffle, which moves a
    row a point. Points without a known token are told by the priors.
    """
    names = sorted(params)
    rows = [(f.name, *[math.log(params[c][1][i]) for c in names]) for i, f in enumerate(spec.features)]
    table = F.broadcast(df.sparkSession.createDataFrame(rows, "feature string, " + ", ".join(f"w{j} double" for j in range(len(names)))))
    each = df.select(F.col(key).alias("key"), F.expr(spec.label).cast("string").alias("class"), F.explode_outer(tokens).alias("feature"))
    sums = each.join(table, "feature", "left").groupBy("key", "class").agg(*[F.coalesce(F.sum(f"w{j}"), F.lit(0.0)).alias(f"w{j}") for j in range(len(names))])
    return predict(sums, [(c, F.col(f"w{j}") + F.lit(math.log(params[c][0]))) for j, c in enumerate(names)]).select("key", "class", "prediction")


def predict(df: DataFrame, scores, name: str = "prediction") -> DataFrame:
    """The class of the highest score; ties go to the smaller name."""
    made = df.withColumns({f"s_{i}": s for i, (_, s) in enumerate(scores)})
    best = F.greatest(*[F.col(f"s_{i}") for i in range(len(scores))]) if len(scores) > 1 else F.col("s_0")
    pick = F.lit(None).cast("string")
    for i in reversed(range(len(scores))):
        pick = F.when(F.col(f"s_{i}") == F.col("best_"), scores[i][0]).otherwise(pick)
    return made.withColumn("best_", best).withColumn(name, pick).drop("best_", *[f"s_{i}" for i in range(len(scores))])


def posteriors(df: DataFrame, scores, name: str = "posterior") -> DataFrame:
    """Map of class probabilities by log-sum-exp."""
    tops = [s for _, s in scores]
    top = F.greatest(*tops) if len(tops) > 1 else tops[0]
    df = df.withColumn("top_", top)
    parts = [(c, F.exp(s - F.col("top_"))) for c, s in scores]
    total = parts[0][1]
    for _, p in parts[1:]:
        total = total + p
    df = df.withColumn("sum_", total)
    return df.withColumn(name, F.create_map(*[x for c, p in parts for x in (F.lit(c), p / F.col("sum_"))])).drop("top_", "sum_")

"""Linear regression from additive state: X'X, X'y, y'y, sum of y, count."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.sources.local import exact_gram
from spanfold.sources.points import Feature, ModelSpec, check_rows


@dataclass
class LinearState:
    """Sums over a set of points. Exact states hold integers scaled by the features' units, so that
    adding and removing points never rounds; fast states hold floats."""

    spec_id: str
    n: int
    cross: list  # packed upper triangle over (features…, target)
    total: list  # sums of (features…, target)
    units: tuple

    def combine(self, other: "LinearState", sign: int = 1) -> "LinearState":
        if self.spec_id != other.spec_id:
            raise ValueError("models of different specs do not combine")
        return LinearState(
            self.spec_id, self.n + sign * other.n, [a + sign * b for a, b in zip(self.cross, other.cross)], [a + sign * b for a, b in zip(self.total, other.total)], self.units
        )

    @property
    def width(self) -> int:
        return len(self.total)

    def matrix(self) -> np.ndarray:
        """Second moments of features and target in real units."""
        d = self.width
        m = np.zeros((d, d))
        it = iter(self.cross)
        for i in range(d):
            for j in range(i, d):
                m[i, j] = m[j, i] = _ratio(next(it), self.units[i] * self.units[j])
        return m

    def sums(self) -> np.ndarray:
        return np.array([_ratio(t, u) for t, u in zip(self.total, self.units)])

    @property
    def nbytes(self) -> int:
        return 8 * (len(self.cross) + len(self.total) + 1)


def _ratio(a, b) -> float:
    return a / b if isinstance(a, float) else float(a / b) if abs(a) < 1 << 52 else int(a) / int(b)


def empty_state(spec: ModelSpec) -> LinearState:
    cols = spec.columns() + [spec.target]
    d = len(cols)
    return LinearState(spec.spec_id, 0, [0] * (d * (d + 1) // 2), [0] * d, tuple(c.unit for c in cols))


def _limbs(a: Feature, b: Feature, points: int) -> bool:
    return a.limit * b.limit * points >= 1 << 62


def state_aggregates(spec: ModelSpec, arithmetic: str = "int", sign=None, points: int = 1 << 31):
    """Aggregates whose values make a state, with names.

    int: bigint sums, in two limbs where features' bounds times `points` could leave 64 bits.
    decimal: reference form. double: fast form. `sign` multiplies each point.
    """
    cols = spec.columns() + [spec.target]
    s = F.lit(1) if sign is None else F.col(sign)
    out = [F.sum(s.cast("bigint")).alias("n")]
    for i, a in enumerate(cols):
        for j in range(i, len(cols)):
            b = cols[j]
            if arithmetic == "double":
                out.append(F.sum(F.col(f"v{i}") * F.col(f"v{j}") * s).alias(f"c{i}_{j}"))
                continue
            p = F.col(f"v{i}") * F.col(f"v{j}")
            p = p if sign is None else p * s
            if arithmetic == "decimal":
                out.append(F.sum(p.cast("decimal(28,0)")).alias(f"c{i}_{j}"))
            elif _limbs(a, b, points):
                out.append(F.sum(F.shiftright(p, 32)).alias(f"c{i}_{j}_hi"))
                out.append(F.sum(p.bitwiseAND(F.lit(0xFFFFFFFF))).alias(f"c{i}_{j}_lo"))
            else:
                out.append(F.sum(p).alias(f"c{i}_{j}"))
    for i in range(len(cols)):
        out.append(F.sum(F.col(f"v{i}") * s).alias(f"t{i}"))
    return out


def project(df: DataFrame, spec: ModelSpec, arithmetic: str = "int", keep=()) -> DataFrame:
    """Only the columns a state needs, as integers (or doubles)."""
    cols = spec.columns() + [spec.target]
    df = check_rows(df, spec)
    return df.select(*keep, *[(c.real() if arithmetic == "double" else c.integer()).alias(f"v{i}") for i, c in enumerate(cols)])


_aggregates: dict = {}


def sums(rows: DataFrame, spec: ModelSpec, by=(), sign: str | None = None, arithmetic: str = "int", points: float = 1 << 31) -> DataFrame:
    """Aggregate projected rows of at most `points` points. With fewer points fewer products need
    two limbs, and below 100 sums the aggregate is compiled. A spec's expressions are made once."""
    bits = max(1, int(points)).bit_length()
    at = (id(rows.sparkSession), spec.spec_id, arithmetic, sign, bits)
    if at not in _aggregates:
        _aggregates[at] = state_aggregates(spec, arithmetic, sign, 1 << bits)
    return rows.groupBy(*by).agg(*_aggregates[at])


def linreg_states(df: DataFrame, spec: ModelSpec, by: list[str] = (), sign: str | None = None, arithmetic: str = "int", points: float = 1 << 31) -> DataFrame:
    """One row of sums for each group of `by` (one row without). Partial sums combine before the
    shuffle, so only sums move."""
    return sums(project(df, spec, arithmetic, keep=[F.col(c) for c in (*by, *([sign] if sign else []))]), spec, by, sign, arithmetic, points)


def state_from_row(row, spec: ModelSpec, arithmetic: str = "int") -> LinearState:
    cols = spec.columns() + [spec.target]
    row = row.asDict() if hasattr(row, "asDict") else row
    if row.get("n") is None:  # no row at all; a net count of 0 may still move sums
        return empty_state(spec)
    number = float if arithmetic == "double" else int
    cross = []
    for i in range(len(cols)):
        for j in range(i, len(cols)):
            name = f"c{i}_{j}"
            cross.append((int(row[f"{name}_hi"]) << 32) + int(row[f"{name}_lo"]) if f"{name}_hi" in row else number(row[name]))
    units = tuple(1 if arithmetic == "double" else c.unit for c in cols)
    return LinearState(spec.spec_id, int(row["n"]), cross, [number(row[f"t{i}"]) for i in range(len(cols))], units)


def state_of_table(table, spec: ModelSpec) -> LinearState:
    """Exact state of projected points held in memory (an Arrow table with v0, v1, …)."""
    cols = spec.columns() + [spec.target]
    if not table.num_rows:
        return empty_state(spec)
    x = np.stack([table.column(f"v{i}").to_numpy() for i in range(len(cols))], axis=1)
    g = exact_gram(x)
    cross = [g[i][j] for i in range(len(cols)) for j in range(i, len(cols))]
    return LinearState(spec.spec_id, len(x), cross, [int(t) for t in x.sum(axis=0)], tuple(c.unit for c in cols))


def linreg_state(df: DataFrame, spec: ModelSpec, sign: str | None = None, arithmetic: str = "int") -> LinearState:
    return state_from_row(linreg_states(df, spec, sign=sign, arithmetic=arithmetic).first(), spec, arithmetic)


def linreg_state_arrow(df: DataFrame, vector: str, label: str | None = None, fan_in: int = 64) -> DataFrame:
    """(i, j, v): second moments of a vector column, for widths whose sums no code block holds.

    Each batch is multiplied by its transpose; a task sends one matrix, and matrices are added in
    two levels so that no reducer sees all of them.
    """
    import pyarrow as pa

    def run(batches):
        total = None
        for b in batches:
            col = b.column(0)
            if len(col):
                x = np.asarray(col.flatten(), dtype=np.float64).reshape(len(col), -1)
                if b.num_columns > 1:
                    x = np.hstack([x, np.asarray(b.column(1), dtype=np.float64)[:, None]])
                g = x.T @ x
                total = g if total is None else total + g
        if total is not None:
            i, j = np.triu_indices(len(total))
            yield pa.record_batch([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(total[i, j])], names=["i", "j", "v"])

    cols = [F.col(vector)] + ([F.col(label).cast("double")] if label else [])
    parts = df.select(*cols).mapInArrow(run, "i int, j int, v double")
    salted = parts.groupBy("i", "j", F.pmod(F.spark_partition_id(), F.lit(fan_in)).alias("salt")).agg(F.sum("v").alias("v"))
    return salted.groupBy("i", "j").agg(F.sum("v").alias("v"))


def linreg_states_long(df: DataFrame, spec: ModelSpec) -> DataFrame:
    """Reference form: (i, j, v) by exploding each point twice. For tests."""
    cols = spec.columns() + [spec.target]
    rows = project(df, spec).select(F.array(*[F.col(f"v{i}") for i in range(len(cols))]).alias("x"))
    a = rows.select("x", F.posexplode("x").alias("i", "xi"))
    b = a.select("i", "xi", F.posexplode("x").alias("j", "xj")).where("i <= j")
    return b.groupBy("i", "j").agg(F.sum((F.col("xi") * F.col("xj")).cast("decimal(28,0)")).alias("v"))


def linreg_solve(state: LinearState, ridge: float = 0.0, penalize_intercept: bool = True, intercept: bool = False) -> np.ndarray:
    """Weights from the state alone; least squares where the matrix is singular."""
    m = state.matrix()
    a, b = m[:-1, :-1], m[:-1, -1]
    penalty = np.eye(len(a)) * ridge
    if intercept and not penalize_intercept:
        penalty[0, 0] = 0.0
    try:
        if np.linalg.cond(a + penalty) > 1e15:
            raise np.linalg.LinAlgError
        return np.linalg.solve(a + penalty, b)
    except np.linalg.LinAlgError:
        return np.linalg.lstsq(a + penalty, b, rcond=None)[0]


def linreg_predict(df: DataFrame, spec: ModelSpec, w, name: str = "prediction") -> DataFrame:
    out = F.lit(0.0)
    for c, v in zip(spec.columns(), w):
        out = out + c.real() * F.lit(float(v))
    return df.withColumn(name, out)


def linreg_anova(state: LinearState, w, intercept: bool) -> dict:
    """SSE, SST, R², F and AIC from the state; valid for weights without a penalty."""
    m, n = state.matrix(), state.n
    w = np.asarray(w)
    sse = float(m[-1, -1] - 2 * w @ m[:-1, -1] + w @ m[:-1, :-1] @ w)
    sst = float(m[-1, -1] - state.sums()[-1] ** 2 / n) if intercept else float(m[-1, -1])
    q = len(w) - int(intercept)
    free = n - q - int(intercept)
    return {
        "n": n, "sse": sse, "sst": sst, "r2": 1 - sse / sst if sst else float("nan"),
        "f": ((sst - sse) / q) / (sse / free) if free > 0 and sse > 0 else float("inf"),
        "aic": n * math.log(sse / n) + 2 * len(w) if sse > 0 else float("-inf"),
    }


def point_state(spec: ModelSpec, values, y) -> LinearState:
    """State of one point given as exact decimals (or integers) in column order."""
    cols = spec.columns() + [spec.target]
    v = [1] * int(spec.intercept) + list(values) + [y]
    v = [int(round(x * c.unit)) for x, c in zip(v, cols)]
    return LinearState(spec.spec_id, 1, [v[i] * v[j] for i in range(len(v)) for j in range(i, len(v))], v, tuple(c.unit for c in cols))


def linreg_add(state: LinearState, spec: ModelSpec, values, y) -> LinearState:
    return state.combine(point_state(spec, values, y))


def linreg_remove(state: LinearState, spec: ModelSpec, values, y) -> LinearState:
    return state.combine(point_state(spec, values, y), -1)

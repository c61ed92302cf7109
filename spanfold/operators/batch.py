"""Many ranges in one pass: elementary cells, prefix states, differences."""

from __future__ import annotations

from bisect import bisect_left, bisect_right

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spanfold.functions import bayes, linear
from spanfold.operators.combine import empty
from spanfold.plans.ranges import Range, union
from spanfold.sources.points import ModelSpec, PointSource, in_cells


def cut_points(ranges) -> list[int]:
    return sorted({x for r in ranges for x in (r.lo, r.hi)})


def cell_states(source: PointSource, spec: ModelSpec, cuts: list[int], needed=None) -> DataFrame:
    """One row of sums for each elementary cell (and class): cell is the number of cuts passed.

    `needed` names the cells to read, all by default. Few cuts travel inside the plan; beyond, a
    cell comes from a join by buckets of keys with a table of the needed cells (20 bytes each).
    """
    needed = range(len(cuts) - 1) if needed is None else needed
    if not needed:
        needed = [0]
    source = source.prepared(spec, linear.project if spec.kind == "linreg" else bayes.project)
    rows = source.scan_range(cuts[needed[0]], cuts[needed[-1] + 1])
    if len(cuts) <= 64:
        key, cell = F.col(source.key), F.lit(None).cast("int")
        for i in needed:
            cell = F.when((key >= cuts[i]) & (key < cuts[i + 1]), i).otherwise(cell)
        rows = rows.withColumn("cell", cell).where("cell is not null")
    else:
        rows = in_cells(rows, source.key, [(cuts[i], cuts[i + 1], i) for i in needed], "cell int")
    return linear.sums(rows, spec, ["cell"], points=source.most_points) if spec.kind == "linreg" else bayes.sums(rows, spec, ["cell"])


def range_states(source: PointSource, spec: ModelSpec, ranges: list[Range]) -> list:
    """Exact states of many ranges from one job: each is the difference of two prefix states. Cells
    below no range are not read."""
    cuts = cut_points(ranges)
    if len(cuts) < 2:
        return [empty(spec) for _ in ranges]
    source.stats["jobs"] += 1
    needed, at = [], 0
    for r in union(ranges):
        at = bisect_left(cuts, r.lo)
        needed += range(at, bisect_left(cuts, r.hi))
        source.stats["points"] += r.hi - r.lo
    by: dict[int, list] = {}
    for r in cell_states(source, spec, cuts, needed).collect():  # one row a cell and class
        by.setdefault(r["cell"], []).append(r)
    prefix = [empty(spec)]
    for i in range(len(cuts) - 1):
        rows = by.get(i, [])
        own = empty(spec) if not rows else linear.state_from_row(rows[0], spec) if spec.kind == "linreg" else bayes.state_from_rows(rows, spec)
        prefix.append(prefix[-1].combine(own) if rows else prefix[-1])
    at = {c: i for i, c in enumerate(cuts)}
    return [prefix[at[r.hi]].combine(prefix[at[r.lo]], -1) for r in ranges]


def prefix_states(cells: DataFrame, by: list[str], columns: list[str]) -> DataFrame:
    """Running sums of cell states in cell order, inside Spark (one row a cell and group)."""
    order = Window.partitionBy(*by).orderBy("cell").rowsBetween(Window.unboundedPreceding, 0)
    return cells.select("cell", *by, *[F.sum(c).over(order).alias(c) for c in columns])


def sliding_states(cells: DataFrame, by: list[str], columns: list[str], width: int) -> DataFrame:
    """State of the last `width` cells at each cell: the newest comes in, the expired goes out."""
    order = Window.partitionBy(*by).orderBy("cell").rangeBetween(-(width - 1), 0)
    return cells.select("cell", *by, *[F.sum(c).over(order).alias(c) for c in columns])


def covered_cells(cuts: list[int], models) -> list[Range]:
    """Elementary cells below at least one model, for set operations on coverage."""
    out = []
    for a, b in zip(cuts, cuts[1:]):
        if any(m.lo <= a and b <= m.hi for m in models):
            out.append(Range(a, b))
    return out


def cell_of(cuts: list[int], key: int) -> int:
    return bisect_right(cuts, key) - 1

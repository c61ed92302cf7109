"""Combining, subtracting and adjusting additive models over ranges."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.functions import bayes, linear
from spanfold.plans.planner import Segment
from spanfold.plans.ranges import Range, contains, hull, meet, minus, overlaps
from spanfold.sources.local import MOST_POINTS
from spanfold.sources.points import ModelSpec, PointSource


@dataclass
class RangeModel:
    """A state and the range of points it speaks of."""

    range: Range
    state: object

    @property
    def n(self) -> int:
        return self.state.n


def scan_state(source: PointSource, spec: ModelSpec, segments):
    """Signed state of scan segments: from a read on the driver where the source's features were
    written out and the points are few, else in one job. Nothing to scan runs no job."""
    segments = [s for s in segments if s.hi > s.lo]
    if not segments:
        return empty(spec)
    points = sum(s.hi - s.lo for s in segments)
    source.stats["points"] += points
    ready = source.prepared(spec, linear.project if spec.kind == "linreg" else bayes.project)
    if ready.reader is not None and points <= MOST_POINTS:
        out = empty(spec)
        of = linear.state_of_table if spec.kind == "linreg" else bayes.state_of_table
        for s in segments:
            out = out.combine(of(ready.reader.read(s.lo, s.hi), spec), s.sign)
        return out
    source.stats["jobs"] += 1
    plain = len(segments) == 1 and segments[0].sign == 1
    rows = ready.scan_range(segments[0].lo, segments[0].hi) if plain else ready.scan_segments(segments)
    sign = None if plain else "sign"
    if spec.kind == "linreg":
        return linear.state_from_row(linear.sums(rows, spec, sign=sign, points=source.most_points).collect()[0], spec)
    return bayes.state_from_rows(bayes.sums(rows, spec, sign=sign).collect(), spec)  # one row a class


def empty(spec: ModelSpec):
    if spec.kind == "linreg":
        return linear.empty_state(spec)
    return bayes.BayesState(spec.spec_id, tuple(f.unit for f in spec.features))


def build(source: PointSource, spec: ModelSpec, lo: int, hi: int) -> RangeModel:
    return RangeModel(Range(lo, hi), scan_state(source, spec, [Segment(1, "scan", lo, hi)]))


def _scan(source, spec, parts) -> object:
    return scan_state(source, spec, [Segment(1, "scan", r.lo, r.hi) for r in parts])


def combine(a: RangeModel, b: RangeModel, source: PointSource | None = None, spec: ModelSpec | None = None, via: str = "auto") -> RangeModel:
    """One model over the points of both. Overlapping points count once, in one of three ways:
    minus_intersection, first_plus_rest, second_plus_rest; auto takes the smallest scan."""
    if not overlaps(a.range, b.range):
        if a.range.hi != b.range.lo and b.range.hi != a.range.lo:
            raise ValueError("ranges with a gap between them make no range")
        return RangeModel(hull(a.range, b.range), a.state.combine(b.state))
    options = {"minus_intersection": [meet(a.range, b.range)], "first_plus_rest": minus(b.range, a.range), "second_plus_rest": minus(a.range, b.range)}
    if via == "auto":
        count = source.directory.count if source.directory is not None else lambda lo, hi: hi - lo
        via = min(options, key=lambda k: sum(count(r.lo, r.hi) for r in options[k]))
    part = _scan(source, spec, options[via])
    if via == "minus_intersection":
        state = a.state.combine(b.state).combine(part, -1)
    else:
        state = (a if via == "first_plus_rest" else b).state.combine(part)
    return RangeModel(hull(a.range, b.range), state)


def subtract(big: RangeModel, small: RangeModel) -> RangeModel:
    """The big model without a contained one at either end."""
    if not contains(big.range, small.range) or (small.range.lo != big.range.lo and small.range.hi != big.range.hi):
        raise ValueError("only a range at one end of the model can be taken off")
    rest = minus(big.range, small.range)
    return RangeModel(rest[0] if rest else Range(big.range.lo, big.range.lo), big.state.combine(small.state, -1))


def adjust(model: RangeModel, lo: int, hi: int, source: PointSource, spec: ModelSpec) -> RangeModel:
    """The model moved to [lo, hi): points at the ends are added or removed, in one job."""
    segments = []
    for old, new, at_start in ((model.range.lo, lo, True), (model.range.hi, hi, False)):
        if old != new:
            grows = (new < old) == at_start
            segments.append(Segment(1 if grows else -1, "scan", min(old, new), max(old, new)))
    return RangeModel(Range(lo, hi), model.state.combine(scan_state(source, spec, segments)))


def merge_signed(states: DataFrame, spec_col: str = "spec_id", sign: str = "sign", values: str = "values") -> DataFrame:
    """(spec_id, i, v): signed sums of stored state vectors, inside Spark."""
    each = states.select(spec_col, F.col(sign).alias("s_"), F.posexplode(values).alias("i", "v"))
    return each.groupBy(spec_col, "i").agg(F.sum(F.col("s_") * F.col("v")).alias("v"))

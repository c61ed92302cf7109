"""Which kept models can matter to a request."""

from __future__ import annotations

from bisect import bisect_left, bisect_right, insort
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spanfold.plans.ranges import Range, contains, overlaps


@dataclass(frozen=True, order=True)
class Kept:
    """A kept model's descriptor; `cost` overrides the cost model's constant."""

    lo: int
    hi: int
    model_id: str
    cost: float | None = None
    n_chunks: int = 1

    @property
    def range(self) -> Range:
        return Range(self.lo, self.hi)


def relevant_by_closure(models, request: Range) -> set:
    """By definition: models that overlap the request, then those that overlap relevant ones."""
    found = {m for m in models if overlaps(m.range, request)}
    edge = set(found)
    while edge:
        edge = {m for m in models if m not in found and any(overlaps(m.range, r.range) for r in edge)}
        found |= edge
    return found


def relevant_contained(models, request: Range) -> set:
    """For models that cannot be subtracted: only those inside the request."""
    return {m for m in models if contains(request, m.range)}


def group_models(models) -> list[tuple[Range, list]]:
    """Maximal chains of overlapping descriptors, by one ascending sweep."""
    groups: list = []
    for m in sorted(models):
        if groups and m.lo < groups[-1][0].hi:
            span, members = groups[-1]
            groups[-1] = (Range(span.lo, max(span.hi, m.hi)), members + [m])
        else:
            groups.append((m.range, [m]))
    return groups


class DescriptorIndex:
    """Groups kept up to date on the driver: sorted group starts, bisection to query."""

    def __init__(self, models=()):
        self._starts: list[int] = []
        self._groups: dict[int, tuple[int, list]] = {}
        for span, members in group_models(models):
            self._put(span, members)

    def _put(self, span: Range, members: list) -> None:
        insort(self._starts, span.lo)
        self._groups[span.lo] = (span.hi, members)

    def _touched(self, r: Range) -> list[int]:
        at = bisect_left(self._starts, r.lo)
        if at and self._groups[self._starts[at - 1]][0] > r.lo:
            at -= 1
        return self._starts[at : bisect_left(self._starts, r.hi)] if not r.empty else []

    def add(self, model: Kept) -> None:
        met = self._touched(model.range)
        members, lo, hi = [model], model.lo, model.hi
        for s in met:
            end, own = self._groups.pop(s)
            self._starts.remove(s)
            members += own
            lo, hi = min(lo, s), max(hi, end)
        self._put(Range(lo, hi), sorted(members))

    def remove(self, model: Kept) -> None:
        at = self._starts[bisect_right(self._starts, model.lo) - 1]
        _, members = self._groups.pop(at)
        self._starts.remove(at)
        for span, own in group_models(m for m in members if m != model):
            self._put(span, own)

    def groups(self) -> list[tuple[Range, list]]:
        return [(Range(s, self._groups[s][0]), self._groups[s][1]) for s in self._starts]

    def query(self, request: Range) -> list:
        """Models of every group that overlaps the request."""
        return [m for s in self._touched(request) for m in self._groups[s][1]]

    def models(self) -> list:
        return [m for s in self._starts for m in self._groups[s][1]]


def group_descriptors(models: DataFrame) -> DataFrame:
    """(model_id, lo, hi) rows to (glo, ghi, n_models, model_ids): the sweep as window functions.

    The window has no key: descriptors are 24 bytes each and as few as the models kept.
    """
    order = Window.orderBy("lo", "hi", "model_id")
    reach = F.max("hi").over(order.rowsBetween(Window.unboundedPreceding, -1))
    opens = F.when(reach.isNull() | (F.col("lo") >= reach), 1).otherwise(0)
    marked = models.where("lo < hi").withColumn("opens", opens).withColumn("island", F.sum("opens").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return marked.groupBy("island").agg(
        F.min("lo").alias("glo"), F.max("hi").alias("ghi"), F.count("*").alias("n_models"), F.array_join(F.array_sort(F.collect_list("model_id")), ",").alias("model_ids")
    ).drop("island")

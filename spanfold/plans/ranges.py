"""Half-open ranges [lo, hi) on an ordering key. Touching ranges do not overlap."""

from __future__ import annotations

from typing import NamedTuple


class Range(NamedTuple):
    lo: int
    hi: int

    @property
    def empty(self) -> bool:
        return self.hi <= self.lo

    def __contains__(self, key: int) -> bool:  # type: ignore[override]
        return self.lo <= key < self.hi


def overlaps(a: Range, b: Range) -> bool:
    return max(a.lo, b.lo) < min(a.hi, b.hi)


def contains(outer: Range, inner: Range) -> bool:
    return inner.empty or (outer.lo <= inner.lo and inner.hi <= outer.hi)


def meet(a: Range, b: Range) -> Range:
    """The common part; an empty range at the higher start where there is none."""
    lo = max(a.lo, b.lo)
    return Range(lo, max(lo, min(a.hi, b.hi)))


def hull(a: Range, b: Range) -> Range:
    return Range(min(a.lo, b.lo), max(a.hi, b.hi))


def minus(a: Range, b: Range) -> list[Range]:
    """What a has beyond b: none, one or two ranges."""
    if not overlaps(a, b):
        return [] if a.empty else [a]
    return [r for r in (Range(a.lo, b.lo), Range(b.hi, a.hi)) if not r.empty]


def union(ranges) -> list[Range]:
    """Disjoint, ascending cover of the same points; touching ranges become one."""
    out: list[Range] = []
    for r in sorted(r for r in ranges if not r.empty):
        if out and r.lo <= out[-1].hi:
            out[-1] = hull(out[-1], r)
        else:
            out.append(r)
    return out


def gaps(within: Range, ranges) -> list[Range]:
    """Parts of `within` that no range covers."""
    out, at = [], within.lo
    for r in union(meet(within, r) for r in ranges):
        if r.lo > at:
            out.append(Range(at, r.lo))
        at = r.hi
    return out + ([Range(at, within.hi)] if at < within.hi else [])

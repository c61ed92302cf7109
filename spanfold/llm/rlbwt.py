"""Run-length Burrows-Wheeler index of a set of byte strings, with sampled run ends.

The index keeps runs of the transform (head symbol, start row), symbol counts before each run, and
the text positions at both ends of each run. Patterns are streamed from right to left, many at a
time: inside a run the row steps backward by the run's counts; at a foreign symbol the stream jumps
to the nearer-matching run end above or below. Lengths are cut at `width`, all that is asked for.
"""

from __future__ import annotations

import numpy as np

from spanfold.llm.common import ship

_PACK = 7  # symbols of 9 bits in one first sorting key


def layout(pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Symbols 1 to 256 with a 0 after each piece, and the position of each piece's 0."""
    joined = np.frombuffer(b"\0".join(pieces) + b"\0", dtype=np.uint8).astype(np.int16) + 1
    ends = np.cumsum([len(p) + 1 for p in pieces]) - 1
    joined[ends] = 0
    return joined, ends


class RunLengthIndex:
    def __init__(self, pieces: list[bytes], width: int):
        self.width = width
        self.text, self.ends = layout(pieces)
        n = len(self.text)
        self.piece = np.repeat(np.arange(len(pieces), dtype=np.int32), np.diff(np.concatenate(([-1], self.ends))))
        order, mid_rank, mid = self._sort()
        bwt = self.text[order - 1]
        head = np.empty(n, dtype=bool)
        head[0] = True
        np.not_equal(bwt[1:], bwt[:-1], out=head[1:])
        self.run_start = np.flatnonzero(head)
        self.run_symbol = bwt[self.run_start].astype(np.int64)
        last = np.append(self.run_start[1:], n) - 1
        self.at_first, self.at_last, self.run_last = order[self.run_start], order[last], last
        length = last - self.run_start + 1
        by_symbol = np.argsort(self.run_symbol, kind="stable")
        before = np.cumsum(length[by_symbol]) - length[by_symbol]
        # rows below a symbol plus its rows in earlier runs: where a run's first row steps back to
        self.step_base = np.empty(len(length), dtype=np.int64)
        self.step_base[by_symbol] = before
        self.run_key = np.sort(self.run_symbol * len(length) + np.arange(len(length)))
        # rows that share their first `width` symbols
        shift = order + (width - mid)
        shift = np.minimum(shift, n - 1)
        apart = np.empty(n, dtype=bool)
        apart[0] = True
        a, b = mid_rank[order], mid_rank[shift]
        apart[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1]) | (self.ends[self.piece[order]] - order < width)[1:]
        self.class_start = np.flatnonzero(apart)
        self.order = order  # dropped by seal()

    def _sort(self):
        text, n, width = self.text, len(self.text), self.width
        end = self.ends[self.piece]
        where = np.arange(n)
        key = np.zeros(n, dtype=np.int64)
        alive = np.ones(n, dtype=bool)
        for j in range(_PACK):
            symbol = np.zeros(n, dtype=np.int64)
            symbol[: n - j] = text[j:]
            symbol[~alive] = 0
            key = (key << 9) | symbol
            alive &= symbol != 0
        depth, mid_rank, mid = _PACK, None, 0
        longest = int((end - where).max()) + 1
        while True:
            order = np.argsort(key)
            sorted_key = key[order]
            new = np.empty(n, dtype=bool)
            new[0] = False
            np.not_equal(sorted_key[1:], sorted_key[:-1], out=new[1:])
            rank = np.empty(n, dtype=np.int64)
            rank[order] = np.cumsum(new)
            if depth <= width:
                mid_rank, mid = rank, depth
            if depth >= longest and depth * 2 > width:
                break
            ahead = np.minimum(where + depth, n - 1)
            key = rank * (n + 1) + np.where(where + depth <= end, rank[ahead] + 1, 0)
            depth *= 2
        order = np.argsort(rank * n + where)  # equal up to their 0: by piece
        return order, mid_rank, mid

    def seal(self, owner: np.ndarray) -> "RunLengthIndex":
        """Keep the smallest owner of each class of equal windows, drop the full suffix order."""
        self.least = np.minimum.reduceat(owner[self.piece[self.order]], self.class_start)
        del self.order
        return self

    @property
    def runs(self) -> int:
        return len(self.run_start)

    def _common(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Length of the common start of two text positions, up to width and the piece's end."""
        span = np.arange(self.width)
        n = len(self.text) - 1
        a = self.text[np.minimum(x[:, None] + span, n)]
        same = (a == self.text[np.minimum(y[:, None] + span, n)]) & (a != 0)
        return np.where(same.all(axis=1), self.width, same.argmin(axis=1))

    def stream(self, symbols: np.ndarray, ends: np.ndarray):
        """Matching statistics of patterns in `layout` form: for each symbol position the length
        (up to width) of the longest match that starts there, and a row of the index it starts at."""
        starts = np.concatenate(([0], ends[:-1] + 1))
        length = np.zeros(len(symbols), dtype=np.int64)
        rows = np.zeros(len(symbols), dtype=np.int64)
        todo = np.argsort(starts - ends, kind="stable")  # longest patterns first
        sizes = (ends - starts)[todo]
        row = np.zeros(len(todo), dtype=np.int64)
        pos = np.full(len(todo), self.at_first[0], dtype=np.int64)
        ln = np.zeros(len(todo), dtype=np.int64)
        runs = len(self.run_start)
        for step in range(1, int(sizes.max(initial=0)) + 1):
            live = int(np.searchsorted(-sizes, -step, side="right"))
            at = ends[todo[:live]] - step
            c = symbols[at].astype(np.int64)
            i, p, m = row[:live], pos[:live], ln[:live]
            run = np.searchsorted(self.run_start, i, side="right") - 1
            foreign = np.flatnonzero(self.run_symbol[run] != c)
            if len(foreign):
                cf, rf, pf, mf = c[foreign], run[foreign], p[foreign], m[foreign]
                slot = np.searchsorted(self.run_key, cf * runs + rf)
                best = np.full(len(foreign), -1, dtype=np.int64)
                to_run, to_row, to_pos = rf.copy(), i[foreign], pf.copy()
                for side in (0, 1):
                    s = np.clip(slot - 1 + side, 0, runs - 1)
                    r = self.run_key[s] % runs
                    ok = np.flatnonzero((self.run_key[s] // runs == cf) & ((slot > 0) if side == 0 else (slot < runs)))
                    rr = r[ok]
                    there = self.at_last[rr] if side == 0 else self.at_first[rr]
                    common = np.minimum(self._common(there, pf[ok]), mf[ok])
                    win = common > best[ok]
                    w = ok[win]
                    best[w], to_run[w], to_pos[w] = common[win], rr[win], there[win]
                    to_row[w] = (self.run_last if side == 0 else self.run_start)[rr[win]]
                lost = best < 0  # the symbol is nowhere in the index
                m[foreign] = best
                run[foreign], i[foreign], p[foreign] = to_run, to_row, to_pos
            i[:] = self.step_base[run] + i - self.run_start[run]
            p -= 1
            m += 1
            if len(foreign) and lost.any():
                f = foreign[lost]
                i[f], p[f], m[f] = 0, self.at_first[0], 0
            np.minimum(m, self.width, out=m)
            length[at], rows[at] = m, i
        return length, rows

    def least_owner(self, rows: np.ndarray) -> np.ndarray:
        return self.least[np.searchsorted(self.class_start, rows, side="right") - 1]


ship(__name__)

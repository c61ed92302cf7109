"""Content-defined parse of symbol sequences into phrases, and what repeats among them.

Every window of `width` symbols is led by its smallest k-gram (by a mixed rolling hash, leftmost
on ties). Consecutive windows led by the same occurrence form one phrase. Equal windows have equal
leaders, so all occurrences of a window meet under one leader hash:

* equal phrases are one dictionary entry; only the entry's smallest document keeps it undecided,
* a leader with a single entry is decided by the dictionary alone,
* entries that share a leader but differ ("conflicts") are compared window by window by the caller
  (rolling window counts for words, a run-length index for bytes).

Nothing is dropped: the parse only decides which documents have to meet.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.llm.common import lean, ship, written

U = np.uint64
_BASE = 0x9E3779B97F4A7C15
_SPAN = 1 << 20  # symbols handled at once; also the room for positions in a packed key
_tables: dict = {}


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> U(29))
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(32)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(29)
    return x


def powers(n: int, base: int = _BASE) -> tuple[np.ndarray, np.ndarray]:
    """base^i and base^-i modulo 2^64 for i < n."""
    have = _tables.get(base)
    if have is None or len(have[0]) < n:
        size = max(n, 1 << 17)
        both = []
        for b in (base, pow(base, -1, 1 << 64)):
            p = np.full(size, b, dtype=np.uint64)
            p[0] = 1
            both.append(np.multiply.accumulate(p))
        have = _tables[base] = tuple(both)
    return have[0][:n], have[1][:n]


def prefix_hashes(codes: np.ndarray, base: int = _BASE) -> np.ndarray:
    """Running sums from which the rolling hash of any stretch follows by one subtraction."""
    out = np.zeros(len(codes) + 1, dtype=np.uint64)
    np.cumsum(codes * powers(len(codes), base)[1], out=out[1:])
    return out


def stretch_hash(sums: np.ndarray, start, length, base: int = _BASE) -> np.ndarray:
    return (sums[start + length] - sums[start]) * powers(len(sums), base)[0][start]


def window_hashes(codes: np.ndarray, width: int, base: int = _BASE) -> np.ndarray:
    """Rabin-Karp hash of each run of `width` symbols (all starts)."""
    n = len(codes) - width + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    sums = prefix_hashes(codes, base)
    return (sums[width:] - sums[:n]) * powers(len(sums), base)[0][:n]


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    span = 1
    while span * 2 <= w:
        x = np.minimum(x[:-span], x[span:])
        span *= 2
    return np.minimum(x[: len(x) - (w - span)], x[w - span :]) if span < w else x


def parse(codes: np.ndarray, ends: np.ndarray, width: int, k: int):
    """Phrases of documents laid end to end: (leader hash, phrase hash, first window, windows).

    `ends` are the ascending document ends within `codes`; windows never cross them.
    """
    n = len(codes)
    if n < width:
        return None
    sums = prefix_hashes(codes)
    grams = mix((sums[k:] - sums[: n - k + 1]) * powers(n + 1)[0][: n - k + 1])
    low = U(_SPAN * 2 - 1)
    packed = (grams & ~low) | np.arange(len(grams), dtype=np.uint64)
    lead = (sliding_min(packed, width - k + 1) & low).astype(np.int64)
    inside = np.ones(n, dtype=bool)
    for e in ends:
        inside[max(0, e - width + 1) : e] = False
    inside = inside[: len(lead)]
    change = np.empty(len(lead), dtype=bool)
    change[0] = True
    np.not_equal(lead[1:], lead[:-1], out=change[1:])
    change[1:] |= inside[1:] != inside[:-1]
    first = np.flatnonzero(change)
    count = np.diff(np.append(first, len(lead)))
    keep = inside[first]
    first, count = first[keep], count[keep]
    if not len(first):
        return None
    whole = mix(stretch_hash(sums, first, count + width - 1) + count.astype(np.uint64) * U(_BASE))
    return grams[lead[first]], whole, first, count


def parse_documents(docs, width: int, k: int):
    """docs: iterable of (doc id, codes). Yields (leader, phrase, doc, place) arrays.

    A place packs first window << 24 | windows.
    """
    part, ids, offs, total = [], [], [], 0

    def flush():
        codes = np.concatenate(part)
        ends = np.cumsum([len(c) for c in part])
        got = parse(codes, ends, width, k)
        if got is None:
            return None
        lead, whole, first, count = got
        which = np.searchsorted(ends, first, side="right")
        starts = first - np.concatenate(([0], ends[:-1]))[which] + np.array(offs, dtype=np.int64)[which]
        return lead.view(np.int64), whole.view(np.int64), np.array(ids, dtype=np.int64)[which], (starts << 24) | count

    for doc, codes in docs:
        for at in range(0, max(1, len(codes) - width + 1), _SPAN - width):
            piece = codes[at : at + _SPAN - 1]
            if len(piece) < width:
                continue
            if total + len(piece) > (1 << 17) and part:
                if (out := flush()) is not None:
                    yield out
                part, ids, offs, total = [], [], [], 0
            part.append(piece)
            ids.append(doc)
            offs.append(at)
            total += len(piece)
    if part and (out := flush()) is not None:
        yield out


#: Rows of the shuffle, in the order that packs best: the document and the high bytes of the place
#: repeat from row to row (places are byte-swapped; their low bits tell stretches that are decided
#: and entries that stay open because their leader is hot).
PHRASES = pa.schema([("d", pa.int64()), ("p", pa.int64()), ("a", pa.int64()), ("s", pa.int64())])
MARKS = pa.schema([("open", pa.bool_()), ("d", pa.int64()), ("p", pa.int64())])
SHAPE = "d long, p long, a long, s long"


def combined(found, hot: np.ndarray, room: int = 1 << 19):
    """Combined batches of parsed arrays, each of about `room` phrases."""
    held, size = [], 0
    for arrays in found:
        held.append(arrays)
        size += len(arrays[0])
        if size >= room:
            yield combine(held, hot)
            held, size = [], 0
    if held:
        yield combine(held, hot)


def combine(arrays, hot: np.ndarray) -> pa.RecordBatch:
    """Combine before the shuffle: of equal phrases in a batch, those of later documents are decided
    at once and joined into stretches; these travel under a scattered key, so a phrase that fills
    the corpus makes no hot key. Phrases of a hot leader travel under a key of their own each, and
    stay open, as if they had met another phrase of their leader."""
    a, s, d, p = (np.concatenate(x) for x in zip(*arrays))
    order = np.argsort(s)
    ordered, owner = s[order], d[order]
    head = np.empty(len(s), dtype=bool)
    head[0] = True
    np.not_equal(ordered[1:], ordered[:-1], out=head[1:])
    least = np.minimum.reduceat(owner, np.flatnonzero(head))
    done = np.empty(len(s), dtype=bool)
    done[order] = owner > least[np.cumsum(head) - 1]
    p_done, d_done = p[done], d[done]
    a, s, d, p = a[~done], s[~done], d[~done], p[~done] << 2
    if len(hot):
        crowded = np.isin(a, hot)
        a = np.where(crowded, mix((a ^ s).view(np.uint64)).view(np.int64), a)
        p |= crowded.astype(np.int64) << 1
    if len(p_done):
        start, count = p_done >> 24, p_done & 0xFFFFFF
        new = np.ones(len(start), dtype=bool)
        new[1:] = (d_done[1:] != d_done[:-1]) | (start[1:] != start[:-1] + count[:-1])
        at = np.flatnonzero(new)
        total = np.add.reduceat(count, at)
        d_done, start = d_done[at], start[at]
        key = mix((d_done ^ (start << 32)).view(np.uint64)).view(np.int64)
        a, s, d = np.concatenate((a, key)), np.concatenate((s, key)), np.concatenate((d, d_done))
        p = np.concatenate((p, (((start << 24) | total) << 2) | 1))
    return pa.record_batch([d, p.byteswap(), a, s], schema=PHRASES)


def resolve(batches):
    """Batches sorted by (a, s, d): marks for decided phrases, open entries for conflicting ones."""

    def settle(d, p, a, s):
        p = p.byteswap()
        done, stays, p = (p & 1) == 1, (p & 2) == 2, p >> 2
        ready = pa.record_batch([np.zeros(done.sum(), bool), d[done], p[done]], schema=MARKS)
        a, s, d, p, stays = a[~done], s[~done], d[~done], p[~done], stays[~done]
        if not len(a):
            return [ready]
        new_a = np.empty(len(a), dtype=bool)
        new_a[0] = True
        np.not_equal(a[1:], a[:-1], out=new_a[1:])
        new_s = new_a.copy()
        new_s[1:] |= s[1:] != s[:-1]
        heads = np.flatnonzero(new_s)
        later = d > d[heads][np.cumsum(new_s) - 1]
        tops = np.flatnonzero(new_a)
        entries = np.add.reduceat(new_s.astype(np.int64), tops)
        mixed = (entries > 1) & (np.minimum.reduceat(d, tops) < np.maximum.reduceat(d, tops))
        clash = ~later & (mixed[np.cumsum(new_a) - 1] | stays)
        return [
            ready,
            pa.record_batch([np.zeros(later.sum(), bool), d[later], p[later]], schema=MARKS),
            pa.record_batch([np.ones(clash.sum(), bool), d[clash], p[clash]], schema=MARKS),
        ]

    held = None
    for batch in batches:
        cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(4)]
        if not len(cols[0]):
            continue
        if held is not None:
            cols = [np.concatenate(x) for x in zip(held, cols)]
        cut = int(np.searchsorted(cols[2], cols[2][-1]))  # the last leader may go on
        if cut:
            yield from settle(*(c[:cut] for c in cols))
        held = [c[cut:].copy() for c in cols]
    if held is not None:
        yield from settle(*held)


HOT_SAMPLE = 64  # one document in so many is parsed first, to find hot leaders
HOT_SHARE = 0.01  # of the sampled documents, and 16 of them at least


def hot_leaders(texts: DataFrame, phrases) -> np.ndarray:
    """Leaders found in a hundredth of the documents or more, told from a hashed sample.

    Only how rows are dealt depends on them. A document has some hundred leaders, so no more than
    some ten thousand can be this frequent; the driver gets their hashes.
    """

    def leaders(batches):
        for found in phrases(batches, np.zeros(0, dtype=np.int64)):
            d, p, a = (found.column(i).to_numpy() for i in range(3))
            real = (p.byteswap() & 1) == 0
            pairs = np.unique(np.stack([a[real], d[real]]), axis=1)
            yield pa.record_batch([pairs[0]], names=["a"])

    sample = texts.where(F.pmod(F.xxhash64("doc_id"), F.lit(HOT_SAMPLE)) == 0)
    least = max(16, int(sample.count() * HOT_SHARE))
    rows = sample.mapInArrow(lean(leaders), "a long").groupBy("a").count().where(F.col("count") >= least).select("a").collect()
    return np.array(sorted(r.a for r in rows), dtype=np.int64)


def repeated_phrases(parsed: DataFrame) -> DataFrame:
    """(d, p, a, s) rows to (open, d, p): stretches to remove, and entries still open."""
    return parsed.repartition("a").sortWithinPartitions("a", "s", "d").mapInArrow(lean(resolve), "open boolean, d long, p long")


def merge_marks(marks, n: int, width: int) -> np.ndarray:
    """Covered symbols of a document of n symbols from packed places."""
    edge = np.zeros(n + 2, dtype=np.int64)
    marks = np.asarray(marks, dtype=np.int64)
    start, count = marks >> 24, marks & 0xFFFFFF
    np.add.at(edge, np.minimum(start, n), 1)
    np.add.at(edge, np.minimum(start + count + width - 1, n), -1)
    return np.cumsum(edge)[:n] > 0


def count_windows(open_windows: DataFrame) -> DataFrame:
    """Windows (h1, h2, d, w) that an earlier document has too, as (d, p) marks.

    The aggregate combines before its shuffle and the join reads two written tables, so a window
    that fills the corpus is split among tasks.
    """
    open_windows = written(open_windows, "windows")
    counted = open_windows.groupBy("h1", "h2").agg(F.min("d").alias("first_doc"), F.max("d").alias("last_doc")).where("first_doc < last_doc")
    counted = written(counted.drop("last_doc"), "window-counts")
    return open_windows.join(counted, ["h1", "h2"]).where("d > first_doc").select("d", F.expr("shiftleft(w, 24) | 1L").alias("p"))


def packed(docs: DataFrame) -> DataFrame:
    """doc_id and the compressed body (and the columns after them): what is shuffled where
    documents meet their marks."""

    def run(batches):
        press = zstandard.ZstdCompressor(level=3)
        for batch in batches:
            body = [press.compress(b.as_buffer()) if b.is_valid else None for b in batch.column(1)]
            cols = batch.columns
            yield pa.record_batch([cols[0], pa.array(body, pa.binary()), *cols[2:]], names=batch.schema.names)

    return docs.mapInArrow(lean(run), docs.schema)


def unpacked(body) -> bytes:
    return zstandard.decompress(body.as_buffer()) if body.is_valid else b""


def marks_by_document(marks: DataFrame) -> DataFrame:
    return marks.groupBy("d").agg(F.collect_list("p").alias("ps"))


ship(__name__)

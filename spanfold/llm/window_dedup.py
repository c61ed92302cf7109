"""Substring dedup over words: Rabin-Karp windows counted in Spark, merged into removal intervals."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.llm.common import lean, ship, written
from spanfold.llm.phrases import marks_by_document, merge_marks, mix, packed, parse_documents, unpacked, window_hashes

LEAD_WORDS = 10
_SECOND = 0xD1342543DE82EF95
_ROOM = 1 << 19  # phrases, and windows, that are combined before a shuffle

#: What a row of the leader count says: a place to be told, a place told already, a leader told already.
_ASKED, _PLACE, _LEADER = 0, 1, 2
_MEETINGS = pa.schema([("d", pa.int64()), ("p", pa.int64()), ("a", pa.int64())])
_PLACES = pa.schema([("d", pa.int64()), ("p", pa.int64())])
_WINDOWS = pa.schema([("h1", pa.int64()), ("h2", pa.int32()), ("d", pa.int64()), ("p", pa.int64())])


class WordCodes(dict):
    """64-bit codes of words, kept for the frequent ones."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 100_000:
            self.clear()
        self[word] = code = xxhash.xxh3_64_intdigest(word)
        return code


def word_codes(words: list[bytes], cache: WordCodes) -> np.ndarray:
    return np.fromiter(map(cache.__getitem__, words), dtype=np.uint64, count=len(words))


def stretches(d: np.ndarray, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places in reading order, those that follow on each other in a document joined into one, but
    not across multiples of 2^23 words, so that counts keep to their 24 bits."""
    start, count = p >> 24, p & 0xFFFFFF
    new = np.ones(len(p), dtype=bool)
    new[1:] = (d[1:] != d[:-1]) | (start[1:] != start[:-1] + count[:-1]) | (start[1:] >> 23 != start[:-1] >> 23)
    at = np.flatnonzero(new)
    return d[at], (start[at] << 24) | (np.add.reduceat(count, at) if len(at) else count)


def group_heads(*sorted_keys: np.ndarray) -> np.ndarray:
    head = np.zeros(len(sorted_keys[0]), dtype=bool)
    head[:1] = True
    for key in sorted_keys:
        head[1:] |= key[1:] != key[:-1]
    return head


def meet_in_batch(held: list) -> pa.RecordBatch:
    """Count leaders before the shuffle. A leader that two documents of the batch have is told at
    once: its places travel under scattered keys, one row tells other batches, so a leader that
    fills the corpus sends a row a batch. Other leaders send the places of their one document."""
    a, _, d, p = (np.concatenate(x) for x in zip(*held))
    order = np.argsort(a)
    head = group_heads(a[order])
    tops, group = np.flatnonzero(head), np.cumsum(head) - 1
    two = np.minimum.reduceat(d[order], tops) < np.maximum.reduceat(d[order], tops)
    told = np.empty(len(a), dtype=bool)
    told[order] = two[group]
    d_told, p_told = stretches(d[told], p[told])
    scattered = mix((d_told ^ (p_told << 8)).view(np.uint64)).view(np.int64)
    leaders = a[order][tops[two]]
    none = np.zeros(len(leaders), dtype=np.int64)
    kinds = ((d[~told], p[~told], a[~told], _ASKED), (d_told, p_told, scattered, _PLACE), (none, none, leaders, _LEADER))
    d, p, a = (np.concatenate(x) for x in zip(*((d, (p << 2) | kind, a) for d, p, a, kind in kinds)))
    # the low bytes of a place differ most; swapped, the like ones lie side by side
    return pa.record_batch([d, p.byteswap(), a], schema=_MEETINGS)


def shared_places(batches):
    """Batches sorted by leader: the places whose leader two documents have."""

    def settle(d, p, a):
        p = p.byteswap()
        kind, p = p & 3, p >> 2
        head = group_heads(a)
        tops = np.flatnonzero(head)
        asked = kind == _ASKED
        low = np.minimum.reduceat(np.where(asked, d, np.iinfo(np.int64).max), tops)
        high = np.maximum.reduceat(np.where(asked, d, np.iinfo(np.int64).min), tops)
        shared = (low < high) | np.logical_or.reduceat(kind == _LEADER, tops)
        out = (kind == _PLACE) | (asked & shared[np.cumsum(head) - 1])
        return pa.record_batch([d[out], p[out]], schema=_PLACES)

    held = None
    for batch in batches:
        cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(3)]
        if not len(cols[0]):
            continue
        if held is not None:
            cols = [np.concatenate(x) for x in zip(held, cols)]
        cut = int(np.searchsorted(cols[2], cols[2][-1]))  # the last leader may go on
        if cut:
            yield settle(*(c[:cut] for c in cols))
        held = [c[cut:].copy() for c in cols]
    if held is not None:
        yield settle(*held)


def count_in_batch(held: list) -> pa.RecordBatch:
    """Count windows before the shuffle: those that a smaller document of the batch has too are
    told at once and leave as stretches without hashes."""
    h1, h2, d, w = (np.concatenate(x) for x in zip(*held))
    order = np.argsort(h1)
    head = group_heads(h1[order], h2[order])
    least = np.minimum.reduceat(d[order], np.flatnonzero(head))
    told = np.empty(len(d), dtype=bool)
    told[order] = d[order] > least[np.cumsum(head) - 1]
    d_told, p_told = stretches(d[told], (w[told] << 24) | 1)
    blank = np.zeros(len(d_told), dtype=np.int64)
    no_hash = np.arange(int((~told).sum()) + len(blank)) >= int((~told).sum())
    hashes = [pa.array(np.concatenate((h[~told], blank.astype(h.dtype))), mask=no_hash) for h in (h1, h2)]
    return pa.record_batch([*hashes, np.concatenate((d[~told], d_told)), np.concatenate(((w[~told] << 24) | 1, p_told))], schema=_WINDOWS)


def in_batches(found, combine):
    """Combined batches of about _ROOM rows of the arrays found."""
    held, size = [], 0
    for arrays in found:
        held.append(arrays)
        size += len(arrays[0])
        if size >= _ROOM:
            yield combine(held)
            held, size = [], 0
    if size:
        yield combine(held)


def remove_repeated_windows(docs: DataFrame, width: int = 50, with_text: bool = False) -> DataFrame:
    """One row per input row: doc_id, n_words, n_removed, kept_sha256, n_spans (and kept_text).

    A word goes if a `width`-word window covers it whose words also start in a row of smaller
    doc_id. Only doc_id and text are read, so other columns cannot clash. Null text has no words;
    texts shorter than a window keep all. Rows with a null doc_id are kept whole and make no other
    row lose words. Rows that share a doc_id pool their marks, clipped to each row's length.

    Plan: every window is led by the smallest rolling hash of its ten-word stretches, so equal
    windows have equal leaders, and a window whose leader only one document has is seen once: this
    first count, a row a run of windows, sets those aside. Of all other windows two rolling hashes
    (96 bits: among 10^13 windows two differing ones would meet with probability 0.001) are counted
    in Spark, with the smallest document of each; partial counts are made before the shuffle.
    Windows that a smaller document has too merge into maximal intervals.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("body"))

    def leaders(batches):
        cache = WordCodes()

        def pieces():
            for batch in batches:
                for doc, body in zip(batch.column(0).to_pylist(), batch.column(1)):
                    words = (body.as_py() or b"").split()
                    if doc is not None and len(words) >= width:
                        yield doc, word_codes(words, cache)

        yield from in_batches(parse_documents(pieces(), width, LEAD_WORDS), meet_in_batch)

    def windows(batches):
        cache = WordCodes()

        def found():
            for batch in batches:
                for doc, body, ps in zip(*(batch.column(i) for i in range(3))):
                    codes = word_codes(unpacked(body).split(), cache)
                    one, two = window_hashes(codes, width), window_hashes(codes, width, _SECOND)
                    p = np.asarray(ps.values, dtype=np.int64)
                    asked = np.zeros(len(one) + 1, dtype=np.int64)
                    np.add.at(asked, np.minimum(p >> 24, len(one)), 1)
                    np.add.at(asked, np.minimum((p >> 24) + (p & 0xFFFFFF), len(one)), -1)
                    spots = np.flatnonzero(np.cumsum(asked[:-1]) > 0)
                    yield one[spots].view(np.int64), (two[spots] >> np.uint64(32)).astype(np.uint32).view(np.int32), np.full(len(spots), doc.as_py()), spots

        yield from in_batches(found(), count_in_batch)

    def finish(batches):
        for batch in batches:
            out = []
            for doc, body, ps in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2)):
                words = unpacked(body).split()
                n_removed = n_spans = 0
                if ps.is_valid:
                    gone = merge_marks(np.asarray(ps.values), len(words), width)
                    n_removed = int(gone.sum())
                    n_spans = int(np.count_nonzero(np.diff(np.concatenate(([0], gone.view(np.int8)))) == 1))
                    kept = b" ".join([words[i] for i in np.flatnonzero(~gone)])
                else:
                    kept = b" ".join(words)
                out.append((doc, len(words), n_removed, hashlib.sha256(kept).hexdigest(), n_spans, kept.decode("utf-8", "replace") if with_text else None))
            if out:
                yield pa.record_batch(
                    [pa.array(x, t) for x, t in zip(zip(*out), (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string()))],
                    names=["doc_id", "n_words", "n_removed", "kept_sha256", "n_spans", "kept_text"],
                )

    bodies = packed(texts)
    met = texts.mapInArrow(lean(leaders), "d long, p long, a long").repartition("a").sortWithinPartitions("a")
    places = marks_by_document(met.mapInArrow(lean(shared_places), "d long, p long"))
    asked = bodies.join(places, bodies.doc_id == places.d).select("doc_id", "body", "ps").mapInArrow(lean(windows), "h1 long, h2 int, d long, p long")
    asked = written(asked, "windows")
    hashed = asked.where("h1 is not null")
    counts = hashed.groupBy("h1", "h2").agg(F.min("d").alias("first_doc"), F.max("d").alias("last_doc")).where("first_doc < last_doc")
    counts = written(counts.drop("last_doc"), "window-counts")
    later = hashed.join(counts, ["h1", "h2"]).where("d > first_doc").select("d", "p")
    ranges = marks_by_document(asked.where("h1 is null").select("d", "p").unionByName(later))
    out = bodies.join(ranges, bodies.doc_id == ranges.d, "left").select("doc_id", "body", "ps")
    out = out.mapInArrow(lean(finish), "doc_id long, n_words long, n_removed long, kept_sha256 string, n_spans long, kept_text string")
    return out if with_text else out.drop("kept_text")


ship(__name__)

"""Byte-level dedup with a run-length index: repeated strings of 50 bytes are cut from later documents."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from spanfold.llm.common import lean, ship, written
from spanfold.llm.phrases import (
    SHAPE, combined, count_windows, hot_leaders, marks_by_document, merge_marks, mix, packed, parse_documents, prefix_hashes, repeated_phrases, stretch_hash, unpacked, window_hashes,
)
from spanfold.llm.rlbwt import RunLengthIndex

LEAD_BYTES = 20
BLOCK = 1 << 20  # symbols in one index
HOT = 4096  # pieces under one key beyond which their windows are counted instead
SECOND = 0xD1342543DE82EF95  # base of the second rolling hash


def byte_codes(body: bytes) -> np.ndarray:
    return mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))[np.frombuffer(body, dtype=np.uint8)]


def piece_batch(rows: list) -> pa.RecordBatch:
    return pa.record_batch([pa.array(x, t) for x, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.binary()))], names=["k", "d", "q", "piece"])


def index_pieces(docs: np.ndarray, starts: np.ndarray, pieces: list[bytes], width: int):
    """Windows of the pieces that also occur in a piece of a smaller document, as packed marks."""
    index = RunLengthIndex(pieces, width).seal(docs)
    length, rows = index.stream(index.text, index.ends)
    hit = np.flatnonzero(length >= width)
    hit = hit[index.least_owner(rows[hit]) < docs[index.piece[hit]]]
    piece = index.piece[hit]
    first = np.concatenate(([0], index.ends[:-1] + 1))[piece]
    return docs[piece], ((starts[piece] + hit - first) << 24) | 1


def remove_repeated_bytes(docs: DataFrame, width: int = 50, with_text: bool = False, carry: tuple[str, ...] = ()) -> DataFrame:
    """One row per input row: doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and kept_text).

    A byte goes if a `width`-byte string covers it that also starts in a row of smaller doc_id;
    strings are judged on the input. Only doc_id and text are read. Null text is empty; texts
    shorter than a string are kept whole. Rows with a null doc_id are kept whole and cost others
    nothing; rows that share a doc_id pool their marks, clipped to each row's length. kept_text is
    the kept bytes; a character that lost some of its bytes goes with them. Columns named in `carry`
    come along unchanged.

    Plan: a content-defined parse makes a dictionary of phrases (equal phrases are one entry, the
    prefix-free way of building the transform of a repetitive corpus). Entries that share a leader
    but differ give their texts to blocks, each of which gets a run-length index; every entry's
    text is streamed through the index for its matching statistics, and matches of full width
    whose smallest owner is an earlier document are marked. Keys with more than HOT pieces would make
    a block of their own that grows with the corpus: these few have the rolling hashes of their
    windows counted in Spark instead, which is exact as well.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("body"), *([F.struct(*carry).alias("rest")] if carry else []))
    side = (width - LEAD_BYTES) // 2

    def phrases(batches, hot):
        for batch in batches:
            ids, body = batch.column(0).to_pylist(), batch.column(1)
            table = byte_codes(bytes(range(256)))

            def pieces():
                for i, doc in enumerate(ids):
                    b = body[i]
                    if doc is not None and b.is_valid and len(b.as_buffer()) >= width:
                        yield doc, table[np.frombuffer(b.as_buffer(), dtype=np.uint8)]

            yield from combined(parse_documents(pieces(), width, LEAD_BYTES), hot)

    def entries(batches):
        """Texts of open entries. The windows left and right of the leader's middle go apart, each
        under a key of their common bytes, longer than the leader."""
        for batch in batches:
            out = []
            for doc, body, ps in zip(*(batch.column(i) for i in range(3))):
                doc, body = doc.as_py(), unpacked(body)
                p = np.unique(np.asarray(ps.values, dtype=np.int64))
                q, count = p >> 24, p & 0xFFFFFF
                inside = q + count + width - 1 <= len(body)
                q, count = q[inside], count[inside]
                sums = prefix_hashes(byte_codes(body))
                # the leader is the smallest k-gram of those that all the entry's windows share
                span = np.arange(width - LEAD_BYTES + 1)
                at = np.minimum((q + count - 1)[:, None] + span, (q + width - LEAD_BYTES)[:, None])
                grams = mix(stretch_hash(sums, at, LEAD_BYTES)) >> np.uint64(21)
                lead = at[np.arange(len(at)), grams.argmin(axis=1)] if len(at) else q
                cut = np.clip(lead - side + 1, q, q + count)
                for lo, hi, key_at in ((q, cut, lead - side), (cut, q + count, lead)):
                    ok = np.flatnonzero(hi > lo)
                    keys = mix(stretch_hash(sums, key_at[ok], LEAD_BYTES + side)).view(np.int64)
                    out += [(int(k), doc, int(a), body[a : b + width - 1]) for k, a, b in zip(keys, lo[ok], hi[ok])]
                if len(out) >= 1 << 16:
                    yield piece_batch(out)
                    out = []
            if out:
                yield piece_batch(out)

    def indexed(batches):
        def settle(k, d, q, piece):
            head = np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1])))
            met = (np.minimum.reduceat(d, head) < np.maximum.reduceat(d, head)).repeat(np.diff(np.append(head, len(k))))
            where = np.flatnonzero(met)
            if len(where):
                doc, p = index_pieces(d[where], q[where], [piece[i] for i in where], width)
                yield pa.record_batch([doc, p], names=["d", "p"])

        held = None
        for batch in batches:
            cols = [batch.column(i).to_numpy() for i in range(3)] + [np.array(batch.column(3).to_pylist(), dtype=object)]
            if not len(cols[0]):
                continue
            held = cols if held is None else [np.concatenate(x) for x in zip(held, cols)]
            while len(held[0]):
                sizes = np.cumsum([len(x) + 1 for x in held[3]])
                if sizes[-1] <= BLOCK:
                    break
                over = int(np.searchsorted(sizes, BLOCK))
                cut = int(np.searchsorted(held[0], held[0][over]))  # whole keys only
                if cut:
                    yield from settle(*(c[:cut] for c in held))
                else:
                    cut = int(np.searchsorted(held[0], held[0][0], side="right"))
                    if cut == len(held[0]):
                        break
                    yield from settle(*(c[:cut] for c in held))
                held = [c[cut:] for c in held]
        if held is not None and len(held[0]):
            yield from settle(*held)

    def windows(batches):
        for batch in batches:
            found = []
            for d, q, piece in zip(*(batch.column(i).to_pylist() for i in range(3))):
                codes = byte_codes(piece)
                one = window_hashes(codes, width)
                found.append((one.view(np.int64), window_hashes(codes, width, SECOND).view(np.int64), np.full(len(one), d), q + np.arange(len(one))))
            if found:
                yield pa.record_batch([np.concatenate(x) for x in zip(*found)], names=["h1", "h2", "d", "w"])

    def finish(batches):
        for batch in batches:
            out = []
            for doc, body, ps in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2)):
                kept = unpacked(body)
                n, n_removed, n_spans = len(kept), 0, 0
                if ps.is_valid:
                    gone = merge_marks(np.asarray(ps.values), n, width)
                    n_removed = int(gone.sum())
                    n_spans = int(np.count_nonzero(np.diff(np.concatenate(([0], gone.view(np.int8)))) == 1))
                    kept = np.frombuffer(kept, dtype=np.uint8)[~gone].tobytes()
                out.append((doc, n, n_removed, n_spans, hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "ignore") if with_text else None))
            if out:
                cols = [pa.array(x, t) for x, t in zip(zip(*out), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string()))]
                names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept_text"]
                yield pa.record_batch(cols + [batch.column(i) for i in range(3, batch.num_columns)], names=names + ["rest"] * (batch.num_columns - 3))

    bodies = packed(texts)
    hot = hot_leaders(texts.select("doc_id", "body"), phrases)
    marks = written(repeated_phrases(texts.select("doc_id", "body").mapInArrow(lean(lambda batches: phrases(batches, hot)), SHAPE)), "byte-phrases")
    open_docs = marks_by_document(marks.where("open"))
    pieces = bodies.join(open_docs, bodies.doc_id == open_docs.d).select("doc_id", "body", "ps").mapInArrow(lean(entries), "k long, d long, q long, piece binary")
    pieces = written(pieces, "pieces")
    crowd = written(pieces.groupBy("k").count().where(F.col("count") > HOT).select("k", F.lit(True).alias("crowded")), "crowded-keys")
    dealt = pieces.join(crowd, "k", "left")
    calm = dealt.where("crowded is null").select("k", "d", "q", "piece").repartition("k").sortWithinPartitions("k", "d")
    matched = calm.mapInArrow(lean(indexed), "d long, p long")
    counted = count_windows(dealt.where("crowded").select("d", "q", "piece").mapInArrow(lean(windows), "h1 long, h2 long, d long, w long"))
    ranges = marks_by_document(marks.where("not open").select("d", "p").unionByName(matched).unionByName(counted))
    out = bodies.join(ranges, bodies.doc_id == ranges.d, "left").select("doc_id", "body", "ps", *(["rest"] if carry else []))
    shape = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept_text string"
    shape = StructType(StructType.fromDDL(shape).fields + [f for f in texts.schema.fields if f.name == "rest"])
    out = out.mapInArrow(lean(finish), shape)
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", *(["kept_text"] if with_text else []), *(["rest.*"] if carry else []))


ship(__name__)

"""SimHash near-duplicates: exact Hamming links by tiles of exclusive-or and bit counts."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.llm.common import lean, ship, written
from spanfold.llm.components import components

TILE = 1024
HOT = 4096  # rows agreeing on one block beyond which they are dealt by a second block


def block_masks(radius: int) -> list[int]:
    """radius + 1 disjoint bit blocks: fingerprints within the radius agree on one of them."""
    cuts = [round(64 * i / (radius + 1)) for i in range(radius + 2)]
    return [((1 << b) - (1 << a)) for a, b in zip(cuts, cuts[1:])]


def _sub_masks(mask: int, radius: int) -> list[int]:
    bits = [b for b in range(64) if not mask >> b & 1]
    cuts = [round(len(bits) * i / (radius + 1)) for i in range(radius + 2)]
    return [mask | sum(1 << b for b in bits[a:c]) for a, c in zip(cuts, cuts[1:])]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def fingerprint(words: list[bytes], size: int) -> int:
    """Majority of each bit over the shingles' hashes; no words: zero."""
    if not words:
        return 0
    line = b" ".join(words)
    if len(words) <= size:
        digests = xxhash.xxh64_digest(line, seed=42)
    else:
        ends = np.cumsum([len(w) + 1 for w in words]).tolist()
        starts = [0, *ends]
        hash_of = xxhash.xxh64_digest
        digests = b"".join([hash_of(line[a : b - 1], 42) for a, b in zip(starts, ends[size - 1 :])])
    rows = np.frombuffer(digests, dtype=np.uint8).reshape(-1, 8)
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(rows), 1 << 15):
        ones += np.unpackbits(rows[at : at + (1 << 15)], axis=1).sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(ones * 2 > len(rows)).tobytes(), "big")


def fingerprints(docs: DataFrame, size: int = 3) -> DataFrame:
    """doc_id, fp (signed 64-bit) of every row; A-Z lower-cased, null text has no words."""

    def run(batches):
        for batch in batches:
            body = batch.column(1)
            fps = [fingerprint((body[i].as_py() or b"").lower().split(), size) for i in range(len(body))]
            yield pa.record_batch([batch.column(0), pa.array(np.array(fps, dtype=np.uint64).view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("binary")).mapInArrow(lean(run), "doc_id long, fp long")


def _roots(label: np.ndarray) -> np.ndarray:
    while True:
        up = label[label]
        if (up == label).all():
            return label
        label = up


def link_group(fps: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning links among a group's fingerprints: tiles in bit-count order, distant tiles skipped."""
    weight = np.bitwise_count(fps)
    order = np.argsort(weight, kind="stable")
    fps, weight = fps[order], weight[order].astype(np.int16)
    label = np.arange(len(fps))
    for i in range(0, len(fps), TILE):
        for j in range(i, len(fps), TILE):
            if weight[j] - weight[min(i + TILE, len(fps)) - 1] > radius:
                break
            near = np.bitwise_count(fps[i : i + TILE, None] ^ fps[None, j : j + TILE]) <= radius
            x, y = np.nonzero(near)
            x, y = x + i, y + j
            while True:
                a, b = label[x], label[y]
                apart = a != b
                if not apart.any():
                    break
                x, y, a, b = x[apart], y[apart], a[apart], b[apart]
                np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
                label = _roots(label)
    moved = np.flatnonzero(label != np.arange(len(fps)))
    return fps[moved], fps[label[moved]]


def _link_sorted(radius: int):
    def run(batches):
        def settle(kid, key, fps):
            head = np.empty(len(fps), dtype=bool)
            head[0] = True
            head[1:] = (kid[1:] != kid[:-1]) | (key[1:] != key[:-1])
            starts = np.flatnonzero(head)
            sizes = np.diff(np.append(starts, len(fps)))
            us, vs = [], []
            group = np.cumsum(head)
            small = int(min(sizes.max(), 32))
            for step in range(1, small):  # groups of up to 32 rows: shifted comparison, all at once
                ok = (group[step:] == group[:-step]) & (sizes[group[step:] - 1] <= 32)
                at = np.flatnonzero(ok)
                hit = at[np.bitwise_count(fps[at] ^ fps[at + step]) <= radius]
                us.append(fps[hit])
                vs.append(fps[hit + step])
            for g in np.flatnonzero(sizes > 32):
                u, v = link_group(fps[starts[g] : starts[g] + sizes[g]], radius)
                us.append(u)
                vs.append(v)
            if us:
                yield pa.record_batch([np.concatenate(us).view(np.int64), np.concatenate(vs).view(np.int64)], names=["u", "v"])

        held = None
        for batch in batches:
            cols = [batch.column(i).to_numpy() for i in range(3)]
            if not len(cols[0]):
                continue
            cols[2] = cols[2].view(np.uint64)
            if held is not None:
                cols = [np.concatenate(x) for x in zip(held, cols)]
            last = np.flatnonzero((cols[0] != cols[0][-1]) | (cols[1] != cols[1][-1]))
            cut = int(last[-1]) + 1 if len(last) else 0
            if cut:
                yield from settle(*(c[:cut] for c in cols))
            held = [c[cut:].copy() for c in cols]
        if held is not None:
            yield from settle(*held)

    return run


def _keys(masks: list[tuple[int, int]]):
    return F.explode(F.array(*[F.struct(F.lit(i).alias("kid"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("key")) for i, m in masks])).alias("at")


def links(distinct_fps: DataFrame, radius: int = 2) -> DataFrame:
    """Links (u, v) that connect all fingerprints within the radius, without listing every pair.

    Fingerprints meet in groups that agree on one of radius + 1 bit blocks. A group of more than
    HOT rows is dealt again by a second block of its other bits (again lossless), so its rows
    spread over many keys; inside a group, tiles are compared exactly.
    """
    first = block_masks(radius)
    keyed = distinct_fps.select("fp", _keys(list(enumerate(first)))).select("fp", "at.*")
    hot = written(keyed.groupBy("kid", "key").count().where(F.col("count") > HOT).select("kid", "key", F.lit(True).alias("hot")), "hot-blocks")
    keyed = keyed.join(hot, ["kid", "key"], "left")
    calm = keyed.where("hot is null").select("kid", "key", "fp")
    split = None
    for i, m in enumerate(first):
        subs = [(len(first) * (i + 1) + s, sub) for s, sub in enumerate(_sub_masks(m, radius))]
        part = keyed.where(F.col("hot") & (F.col("kid") == i)).select("fp", _keys(subs)).select("at.kid", "at.key", "fp")
        split = part if split is None else split.unionByName(part)
    every = calm.unionByName(split)
    return every.repartition("kid", "key").sortWithinPartitions("kid", "key").mapInArrow(lean(_link_sorted(radius)), "u long, v long")


def near_duplicates(docs: DataFrame, size: int = 3, radius: int = 2) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id of every row.

    Rows link if their fingerprints differ in at most `radius` bits; component_id is the smallest
    doc_id of the linked rows. Null and empty texts have fingerprint zero and link like any other.
    A null doc_id keeps its row and never names a component unless it is alone (then null). Equal
    fingerprints are one node, so copies cost one row each. Only doc_id and text are read.
    """
    fps = written(fingerprints(docs, size), "fingerprints")
    nodes = fps.groupBy("fp").agg(F.min("doc_id").alias("least"))
    linked = components(links(nodes.select("fp"), radius))
    named = written(nodes.join(linked, nodes.fp == linked.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root")), "roots")
    least = named.groupBy("root").agg(F.min("least").alias("component_id"))
    labels = written(named.join(least, "root").select("fp", "component_id"), "labels")
    return fps.join(labels, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


ship(__name__)

"""Near copies of the pipeline: SimHash tiles find candidates, exact shingle sets confirm them."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.llm.common import lean, ship, written
from spanfold.llm.components import components

SHINGLE = 5  # words
LEAST = 0.8  # Jaccard similarity of two documents' shingle sets
FIRST, BOTH = 19, 32  # bits that may differ in the first 64 and in all 128; 10 and 19 are expected at 0.8
TILE = 256
SMALL = 32  # rows of a group up to which groups are compared all at once
PART_ROWS, PART_SHINGLES = 16_384, 1 << 22  # of one part of a cluster
#: Sets this alike differ in size by less than STEP, so they lie in one band of sizes or in neighbouring
#: ones; sets of fewer than SMALLEST shingles are alike only if equal, as five of a union must agree.
STEP, SMALLEST = 1.26, 4


def shingles(text: bytes | None) -> np.ndarray:
    """Sorted hashes of the distinct runs of five words; a shorter text is one run."""
    words = (text or b"").lower().split()
    if not words:
        return np.zeros(0, dtype=np.uint64)
    line = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]).tolist()
    starts = [0, *ends]
    digest = xxhash.xxh3_64_intdigest
    return np.unique(np.array([digest(line[a : b - 1]) for a, b in zip(starts, ends[min(SHINGLE, len(words)) - 1 :])], dtype=np.uint64))


def _majority(hashes: np.ndarray) -> int:
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), 1 << 15):
        ones += np.unpackbits(hashes[at : at + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(ones * 2 > len(hashes)).tobytes(), "big")


def _scatter(hashes: np.ndarray) -> np.ndarray:
    x = hashes * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def _prints(batches):
    for batch in batches:
        rows = []
        for text in batch.column(2):
            s = shingles(text.as_py())
            rows.append((xxhash.xxh3_64_intdigest(s.tobytes()), len(s), _majority(s), _majority(_scatter(s))))
        if rows:
            columns = np.array(rows, dtype=np.uint64).T.copy().view(np.int64)
            yield pa.record_batch([batch.column(0), batch.column(1), *map(pa.array, columns)], names=["row", "doc_id", "sig", "size", "f1", "f2"])


def _alike(f1, f2, size, a, b) -> np.ndarray:
    """Whether fingerprints and sizes of rows a and b allow the similarity."""
    ok = np.bitwise_count(f1[a] ^ f1[b]) <= FIRST
    ok &= np.bitwise_count(f1[a] ^ f1[b]).astype(np.int16) + np.bitwise_count(f2[a] ^ f2[b]) <= BOTH
    return ok & (np.minimum(size[a], size[b]) >= LEAST * np.maximum(size[a], size[b]))


def _candidates(f1, f2, size, left, right, same: bool):
    """Pairs (x, y) of one tile after another, rows in order of their size: every pair of fingerprints
    is compared, but for tiles whose sizes lie too far apart."""
    different, bits, near = (np.empty((TILE, TILE), dtype=t) for t in (np.uint64, np.uint8, bool))  # used again by each tile
    left = left[np.argsort(size[left], kind="stable")]
    right = left if same else right[np.argsort(size[right], kind="stable")]
    for i in range(0, len(left), TILE):
        x = left[i : i + TILE]
        for j in range(i if same else 0, len(right), TILE):
            y = right[j : j + TILE]
            if size[x[-1]] < LEAST * size[y[0]]:
                break
            if size[y[-1]] < LEAST * size[x[0]]:
                continue
            full = len(x) == len(y) == TILE
            d, n, ok = (different, bits, near) if full else (m[: len(x), : len(y)] for m in (different, bits, near))
            np.bitwise_xor(f1[x, None], f1[None, y], out=d)
            np.less_equal(np.bitwise_count(d, out=n), FIRST, out=ok)
            a, b = np.divmod(np.flatnonzero(ok), len(y))
            if same and i == j:
                a, b = a[a < b], b[a < b]
            a, b = x[a], y[b]
            ok = _alike(f1, f2, size, a, b)
            yield a[ok], b[ok]


def _span(label: np.ndarray, pairs):
    """Links that join what pairs join, each of them needed."""
    us, vs = [], []
    for x, y in pairs:
        while True:
            a, b = label[x], label[y]
            apart = a != b
            if not apart.any():
                break
            x, y, a, b = x[apart], y[apart], a[apart], b[apart]
            top, first = np.unique(np.maximum(a, b), return_index=True)
            us.append(x[first])
            vs.append(y[first])
            label[top] = np.minimum(a, b)[first]
            while not (label[label] == label).all():
                label[:] = label[label]
    none = np.zeros(0, dtype=np.int64)
    return np.concatenate([none, *us]), np.concatenate([none, *vs])


def _group_links(k, p, q, side, sig, size, f1, f2):
    """Candidate links of whole groups, sorted by (k, p, q)."""
    head = np.flatnonzero(np.concatenate(([True], (k[1:] != k[:-1]) | (p[1:] != p[:-1]) | (q[1:] != q[:-1]))))
    count = np.diff(np.append(head, len(k)))
    group = np.repeat(np.arange(len(head)), count)
    us, vs = [], []
    for step in range(1, min(SMALL, int(count.max()))):
        at = np.flatnonzero((group[step:] == group[:-step]) & (count[group[step:]] <= SMALL) & (p[step:] == q[step:]))
        hit = at[_alike(f1, f2, size, at, at + step)]
        us.append(hit)
        vs.append(hit + step)
    for g in np.flatnonzero((count > SMALL) | (p[head] != q[head])):
        own = np.arange(head[g], head[g] + count[g])
        same = p[head[g]] == q[head[g]]
        left, right = (own, own) if same else (own[side[own] == 0], own[side[own] == 1])
        label = np.arange(count[g])
        pairs = ((a - head[g], b - head[g]) for a, b in _candidates(f1, f2, size, left, right, same))
        u, v = _span(label, pairs)
        us.append(u + head[g])
        vs.append(v + head[g])
    none = np.zeros(0, dtype=np.int64)
    u, v = np.concatenate([none, *us]), np.concatenate([none, *vs])
    return pa.record_batch([sig[u], sig[v]], names=["u", "v"])


def _links(batches):
    """Sorted rows (k, p, q, side, sig, size, f1, f2) to links; a group may go on in the next batch,
    and groups hold two parts of a band at most."""
    held = None
    for batch in batches:
        cols = [c.to_numpy() for c in batch.columns]
        if not len(cols[0]):
            continue
        cols = cols if held is None else [np.concatenate(x) for x in zip(held, cols)]
        last = np.flatnonzero((cols[0] != cols[0][-1]) | (cols[1] != cols[1][-1]) | (cols[2] != cols[2][-1]))
        cut = int(last[-1]) + 1 if len(last) else 0
        if cut:
            k, p, q, side, sig, size, f1, f2 = (c[:cut] for c in cols)
            yield _group_links(k, p, q, side, sig, size, f1.view(np.uint64), f2.view(np.uint64))
        held = [c[cut:].copy() for c in cols]
    if held is not None:
        k, p, q, side, sig, size, f1, f2 = held
        yield _group_links(k, p, q, side, sig, size, f1.view(np.uint64), f2.view(np.uint64))


def _confirm(table: pa.Table) -> pa.Table:
    """Links of a task whose exact similarity suffices; pairs joined already are not read again."""
    f1, f2 = (table.column(c).to_numpy().view(np.uint64) for c in ("f1", "f2"))
    size, side, sig = (table.column(c).to_numpy() for c in ("size", "side", "sig"))
    place = table.column("task")[0].as_py()
    same = place["p"] == place["q"]
    left = np.arange(len(side)) if same else np.flatnonzero(side == 0)
    right = left if same else np.flatnonzero(side == 1)
    sets: dict = {}

    def of(x):
        if x not in sets:
            sets[x] = shingles(table.column("text")[int(x)].as_py())
        return sets[x]

    label = np.arange(len(side))
    us, vs = [], []
    for a, b in _candidates(f1, f2, size, left, right, same):
        order = np.argsort(a, kind="stable")
        a, b = a[order], b[order]
        for x, y in zip(a.tolist(), b.tolist()) if len(a) < 4096 else _unjoined(a, b, label):
            if label[x] == label[y]:
                continue
            both = len(np.intersect1d(of(x), of(y), assume_unique=True))
            if both >= LEAST * (len(of(x)) + len(of(y)) - both):
                label[label == label[y]] = label[x]
                us.append(x)
                vs.append(y)
    return pa.table([pa.array(sig[np.array(us, dtype=np.int64)]), pa.array(sig[np.array(vs, dtype=np.int64)])], names=["u", "v"])


def _unjoined(a, b, label):
    """Pairs by first row, without those joined by the time the row's turn comes."""
    for row in np.split(np.arange(len(a)), np.flatnonzero(np.diff(a)) + 1):
        x, y = int(a[row[0]]), b[row]
        while len(y := y[label[y] != label[x]]):
            yield x, int(y[0])
            y = y[1:]


def _dealt(rows: DataFrame, by: list[str], parts) -> DataFrame:
    """Rows of groups with a number of parts (`parts`, a column) to every task they take part in: a
    pair of parts (p, q), p <= q, of their group; side tells the part."""
    own = F.pmod(F.xxhash64("sig"), F.col(parts).cast("long")).cast("int")
    rows = rows.withColumn("own_", own)
    others = F.filter(F.sequence(F.lit(0), F.col(parts).cast("int")), lambda i: i < F.col(parts))
    task = F.transform(others, lambda i: F.struct(F.least("own_", i).alias("p"), F.greatest("own_", i).alias("q"), F.when(F.col("own_") > i, 1).otherwise(0).alias("side")))
    return rows.withColumn("t_", F.explode(task)).select("*", "t_.*").drop("own_", "t_", parts)


def _candidate_links(nodes: DataFrame) -> DataFrame:
    """(u, v) of nodes whose fingerprints allow the similarity: what all such pairs join, by few
    links. Nodes are dealt by bands of sizes; each band is cut into parts by hash, and every pair of
    parts of a band, or of two neighbouring bands, is a group whose fingerprints are compared."""
    nodes = nodes.where(F.col("size") >= SMALLEST).withColumn("band", F.floor(F.log(F.col("size")) / float(np.log(STEP))).cast("int"))
    count = {r.band: r["count"] for r in nodes.groupBy("band").count().collect()}  # a row a band
    parts = {b: -(-n // min(4 * PART_ROWS, max(PART_ROWS // 16, n // 8))) for b, n in count.items()}
    table = F.create_map(*[F.lit(v) for b in sorted(parts) for v in (b, parts[b])]) if parts else F.create_map(F.lit(0), F.lit(0))
    of = lambda b: F.coalesce(F.element_at(table, b), F.lit(0))
    upto = lambda n: F.filter(F.sequence(F.lit(0), n), lambda i: i < n)
    task = lambda k, p, q, side: F.struct(k.alias("k"), p.alias("p"), q.alias("q"), side.alias("side"))
    rows = nodes.withColumn("parts_", of(F.col("band"))).withColumn("above_", of(F.col("band") + 1)).withColumn("below_", of(F.col("band") - 1))
    rows = rows.withColumn("own_", F.pmod(F.xxhash64("sig"), F.col("parts_").cast("long")).cast("int"))
    own, band = F.col("own_"), F.col("band")
    inside = F.transform(upto(F.col("parts_")), lambda i: task(2 * band, F.least(own, i), F.greatest(own, i), F.when(own > i, 1).otherwise(0)))
    above = F.transform(upto(F.col("above_")), lambda i: task(2 * band + 1, own, -1 - i, F.lit(0)))  # q < 0: two bands
    below = F.transform(upto(F.col("below_")), lambda i: task(2 * band - 1, i, -1 - own, F.lit(1)))
    dealt = rows.select(F.explode(F.concat(inside, above, below)).alias("t_"), "sig", "size", "f1", "f2").select("t_.*", "sig", "size", "f1", "f2")
    return dealt.repartition("k", "p", "q").sortWithinPartitions("k", "p", "q").mapInArrow(lean(_links), "u long, v long").distinct()


def losers(rows: DataFrame) -> DataFrame:
    """row of each near copy to drop, of (row, doc_id, text) with distinct row.

    Documents link if their sets of five-word shingles have a Jaccard similarity of 0.8 or more;
    of each connected group the smallest (doc_id, row) stays. Texts without words are copies of
    one another. Rows without doc_id take no part.

    Plan: equal sets are one node. The 128-bit SimHash fingerprints of all nodes whose sizes allow
    the similarity are compared in tiles, in tasks of bounded parts; no other key has to agree. So no
    pair within the bits allowed is missed, and the comparisons (some nanoseconds each) grow with the
    square of the nodes. What candidates join is a cluster; a cluster's texts are sent together once
    (by bounded parts, if it is large) and compared exactly.
    """
    rows = rows.where("doc_id is not null").select(F.col("row").cast("long"), F.col("doc_id").cast("long"), F.col("text").cast("binary").alias("text"))
    prints = written(rows.mapInArrow(lean(_prints), "row long, doc_id long, sig long, size long, f1 long, f2 long"), "prints")
    nodes = written(prints.groupBy("sig").agg(F.first("size").alias("size"), F.first("f1").alias("f1"), F.first("f2").alias("f2"), F.min("row").alias("row")), "nodes")
    clusters = written(components(_candidate_links(nodes)), "clusters")
    light = nodes.select("sig", "size", "f1", "f2", "row")
    members = clusters.select(F.col("node").alias("sig"), "root").unionByName(clusters.select(F.col("root").alias("sig"), "root").distinct()).join(light, "sig")
    members = written(members, "members")
    load = members.groupBy("root").agg(F.greatest(F.ceil(F.sum("size") / PART_SHINGLES), F.ceil(F.count("*") / PART_ROWS)).alias("parts_"))
    dealt = _dealt(members.join(load, "root"), ["root"], "parts_").select(F.struct("root", "p", "q").alias("task"), "side", "sig", "size", "f1", "f2", "row")
    links = dealt.join(rows.select("row", "text"), "row").groupBy("task").applyInArrow(_confirm, "u long, v long")
    named = prints.select("row", "doc_id", "sig").join(components(links), F.col("sig") == F.col("node"), "left").select("row", "doc_id", F.coalesce("root", "sig").alias("root"))
    named = written(named, "groups")
    best = named.groupBy("root").agg(F.min(F.struct("doc_id", "row")).alias("best")).select("best.row")
    return named.join(best, "row", "left_anti").select("row")  # by row: a large group stays spread


ship(__name__)

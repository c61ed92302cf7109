"""Toxicity: a convolutional text classifier over hashed word embeddings, trained here in numpy."""

from __future__ import annotations

import pickle
import re
import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.llm.common import crc_mod, lean, ship

BUCKETS = 1 << 15
TABLES = 4  # hashed twice by the word, and by its first four and first five letters
DIMS = 6  # of each table
WIDTHS = (1, 2, 3)
FILTERS = 8  # of each width
SAMPLE = 4000  # labelled rows of each class used for training at most
LETTERS = 128
STEP = 1024  # rows scored at once where documents are dropped


def _word_ids(text: str, cache: dict) -> np.ndarray:
    """Buckets of each lower-cased word of letters, shape (words, TABLES): two by the whole word, so
    that a chance collision shows in one only, and two by its start, for inflected words."""
    out = []
    for w in re.findall(r"[^\W\d_]+", text.lower()):
        ids = cache.get(w)
        if ids is None:
            if len(cache) > 100_000:
                cache.clear()
            b = w.encode()
            ids = cache[w] = tuple(zlib.crc32(x) % BUCKETS for x in (b, b"#" + b, b"4" + w[:4].encode(), b"5" + w[:5].encode()))
        out.append(ids)
    return np.array(out, dtype=np.int32).reshape(-1, TABLES)


def _letter_profile(text: str) -> np.ndarray:
    codes = np.frombuffer(text.lower().encode("utf-32-le", "replace"), dtype=np.uint32)
    codes = codes[codes > 64]
    counts = np.bincount(codes % LETTERS, minlength=LETTERS).astype(np.float64)
    return counts / max(1.0, np.sqrt((counts**2).sum()))


@dataclass
class Network:
    tables: list
    kernels: dict  # width -> (width, TABLES * DIMS, FILTERS)
    biases: dict
    out: np.ndarray
    out_bias: float
    langs: list = field(default_factory=list)
    profiles: np.ndarray | None = None
    cuts: np.ndarray | None = None

    @staticmethod
    def fresh(seed: int) -> "Network":
        rng = np.random.default_rng(seed)
        tables = [np.vstack([rng.normal(0, 0.1, (BUCKETS, DIMS)), np.zeros((1, DIMS))]).astype(np.float32) for _ in range(TABLES)]
        kernels = {w: rng.normal(0, 0.4, (w, TABLES * DIMS, FILTERS)).astype(np.float32) for w in WIDTHS}
        return Network(tables, kernels, {w: np.zeros(FILTERS, np.float32) for w in WIDTHS}, rng.normal(0, 0.3, FILTERS * len(WIDTHS)).astype(np.float32), 0.0)

    def activations(self, ids: np.ndarray) -> tuple[np.ndarray, dict]:
        """ids end every document with padding; returns the input rows and one map for each width."""
        x = np.hstack([t[ids[:, j]] for j, t in enumerate(self.tables)])
        maps = {}
        for w, k in self.kernels.items():
            y = x @ k[0]
            for j in range(1, w):
                y[:-j] += x[j:] @ k[j]
            maps[w] = y
        return x, maps

    def logits(self, docs: list[np.ndarray]) -> np.ndarray:
        out = np.empty(len(docs), dtype=np.float64)
        for at, chunk in _chunks(docs):
            ids, starts = _lay(chunk)
            _, maps = self.activations(ids)
            pooled = np.hstack([np.maximum(np.maximum.reduceat(m, starts, axis=0) + self.biases[w], 0) for w, m in maps.items()])
            out[at : at + len(chunk)] = pooled @ self.out + self.out_bias
        return out


def _chunks(docs, room: int = 60_000):
    start, size = 0, 0
    for i, d in enumerate(docs):
        if size + len(d) > room and i > start:
            yield start, docs[start:i]
            start, size = i, 0
        size += len(d)
    if start < len(docs):
        yield start, docs[start:]


def _lay(docs):
    """Documents end to end, each followed by as much padding as the widest filter needs."""
    pad = np.full((max(WIDTHS), TABLES), BUCKETS, dtype=np.int32)
    parts = [x for d in docs for x in (d, pad)]
    sizes = [len(d) + len(pad) for d in docs]
    return np.concatenate(parts), np.concatenate(([0], np.cumsum(sizes)[:-1])).astype(np.int64)


def train(docs: list[np.ndarray], labels: np.ndarray, epochs: int = 14, rate: float = 0.01, seed: int = 7) -> Network:
    """Adam on the logistic loss. The pooled maximum passes its gradient to one place of each filter,
    so only those words' rows of the tables change."""
    net = Network.fresh(seed)
    rng = np.random.default_rng(seed)
    weight = np.where(labels > 0, len(labels) / max(1, 2 * labels.sum()), len(labels) / max(1, 2 * (1 - labels).sum()))
    dense = [net.out, *net.kernels.values(), *net.biases.values()]
    state = [(np.zeros_like(p), np.zeros_like(p)) for p in dense]
    sparse = [np.zeros_like(t) for t in net.tables]
    step = 0
    for epoch in range(epochs):
        order = rng.permutation(len(docs))
        lr = rate * (1 - epoch / epochs) + 0.001
        for at in range(0, len(docs), 32):
            pick = order[at : at + 32]
            ids, starts = _lay([docs[i] for i in pick])
            ends = np.append(starts[1:], len(ids))
            x, maps = net.activations(ids)
            pooled, where = [], []
            for w, m in maps.items():
                best = np.stack([m[a:b].argmax(axis=0) + a for a, b in zip(starts, ends)])
                where.append(best)
                pooled.append(np.take_along_axis(m, best, axis=0) + net.biases[w])
            z = np.hstack(pooled)
            h = np.maximum(z, 0)
            logit = h @ net.out + net.out_bias
            err = ((1 / (1 + np.exp(-logit)) - labels[pick]) * weight[pick] / len(pick)).astype(np.float32)
            back = (err[:, None] * net.out[None, :]) * (z > 0)
            grads = [h.T @ err]
            table_ids, table_grads = [], []
            for n, w in enumerate(WIDTHS):
                g = back[:, n * FILTERS : (n + 1) * FILTERS]
                gk = np.zeros_like(net.kernels[w])
                for j in range(w):
                    rows = np.minimum(where[n] + j, len(ids) - 1)
                    gk[j] = np.einsum("bfd,bf->df", x[rows], g)
                    table_ids.append(ids[rows].reshape(-1, TABLES))
                    table_grads.append((g[:, :, None] * net.kernels[w][j].T[None]).reshape(-1, TABLES * DIMS))
                grads.append(gk)
            grads += [back[:, n * FILTERS : (n + 1) * FILTERS].sum(axis=0) for n in range(len(WIDTHS))]
            step += 1
            for p, g, (m1, m2) in zip(dense, grads, state):
                m1 += 0.1 * (g - m1)
                m2 += 0.001 * (g * g - m2)
                p -= lr * (m1 / (1 - 0.9**step)) / (np.sqrt(m2 / (1 - 0.999**step)) + 1e-8)
            net.out_bias -= lr * float(err.sum())
            touched, moved = np.concatenate(table_ids), np.concatenate(table_grads)
            for t in range(TABLES):
                rows, inverse = np.unique(touched[:, t], return_inverse=True)
                g = np.zeros((len(rows), DIMS), dtype=np.float32)
                np.add.at(g, inverse, moved[:, t * DIMS : (t + 1) * DIMS])
                sparse[t][rows] += g * g
                net.tables[t][rows] -= 5 * lr * g / (np.sqrt(sparse[t][rows]) + 1e-6)
                net.tables[t][BUCKETS] = 0
    return net


def _best_cut(logits: np.ndarray, labels: np.ndarray) -> float:
    """The cut with the fewest errors; the middle of the widest gap among equals."""
    order = np.argsort(logits)
    z, y = logits[order], labels[order]
    wrong = np.concatenate(([0], np.cumsum(y))) + np.concatenate((np.cumsum((1 - y)[::-1])[::-1], [0]))
    edges = np.concatenate(([z[0] - 2], z, [z[-1] + 2]))
    best = np.flatnonzero(wrong == wrong.min())
    i = best[np.argmax(edges[best + 1] - edges[best])]
    return float((edges[i] + edges[i + 1]) / 2)


def calibrate(net: Network, docs, texts, labels, langs, least: int = 30) -> Network:
    """Cuts for each language, told from the text by its letter profile; those with few labels of
    either class keep the cut of all languages."""
    z = net.logits(docs)
    shared = _best_cut(z, labels)
    profile = np.stack([_letter_profile(t) for t in texts])
    net.langs = sorted({x for x in langs if x is not None})
    langs = np.array([x or "" for x in langs])
    if not net.langs:
        net.langs, net.profiles = [""], np.zeros((1, LETTERS))
    else:
        net.profiles = np.stack([profile[langs == x].mean(axis=0) for x in net.langs])
    guess = (profile @ net.profiles.T).argmax(axis=1)
    net.cuts = np.full(len(net.langs), shared)
    for i in range(len(net.langs)):
        own = guess == i
        if min(labels[own].sum(), (1 - labels[own]).sum()) >= least:
            net.cuts[i] = _best_cut(z[own], labels[own])
    return net


def fit(docs: DataFrame, labels: DataFrame, train_rows, sample: int = SAMPLE) -> Network | None:
    """Train on at most `sample` labelled rows of each class, those of smallest hashed doc_id.

    `train_rows` is a condition on doc_id. A document labelled both ways counts as toxic; repeated
    labels count once. Of rows that share a doc_id the smallest text (then language) is learned from.
    Without labelled rows of both classes: None. Whole texts are read, however long.
    """
    good = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where(train_rows).where("toxic in (0, 1)").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    picks = [good.where(F.col("toxic") == c).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample) for c in (0, 1)]
    picked = picks[0].unionByName(picks[1])
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("lang").cast("string").alias("lang") if "lang" in docs.columns else F.lit(None).cast("string").alias("lang"))
    texts = texts.join(F.broadcast(picked), "doc_id").groupBy("doc_id", "toxic").agg(F.min(F.struct("text", "lang")).alias("r"))
    # two classes of `sample` rows at most; they are learned from where they are, the driver gets the network
    learned = texts.select("doc_id", "toxic", "r.*").coalesce(1).mapInArrow(lean(_learn), "net binary").collect()
    return Network(**pickle.loads(learned[0].net)) if learned else None


def _learn(batches):
    """The fields of the network learned from all batches' rows (doc_id, toxic, text, lang); nothing
    without both classes."""
    rows = sorted((r for batch in batches for r in zip(*(c.to_pylist() for c in batch.columns))), key=lambda r: (r[0], r[2] or ""))
    y = np.array([toxic for _, toxic, _, _ in rows], dtype=np.float32)
    if not len(y) or y.min() == y.max():
        return
    cache: dict = {}
    words = [_word_ids(text or "", cache) for _, _, text, _ in rows]
    held = np.array([zlib.crc32(f"{doc}/check".encode()) % 5 == 0 for doc, _, _, _ in rows])
    if held.all() or not held.any() or y[~held].min() == y[~held].max():
        held[:] = False
    net = train([w for w, h in zip(words, held) if not h], y[~held])
    use = held if held.any() and y[held].min() < y[held].max() else ~held
    pick = np.flatnonzero(use)
    net = calibrate(net, [words[i] for i in pick], [rows[i][2] or "" for i in pick], y[pick], [rows[i][3] for i in pick])
    yield pa.record_batch([pa.array([pickle.dumps(vars(net))], pa.binary())], names=["net"])


def probabilities(net: Network | None, texts: list, cache: dict) -> np.ndarray:
    """Score of each text; a text without words, and any text without a network, has score 0."""
    if net is None:
        return np.zeros(len(texts))
    words = [_word_ids(t, cache) for t in texts]
    guess = [int((net.profiles @ _letter_profile(t)).argmax()) for t in texts]
    p = 1 / (1 + np.exp(-np.clip(net.logits(words) - net.cuts[guess], -40, 40)))
    return np.where([len(w) > 0 for w in words], p, 0.0)


def score(docs: DataFrame, net: Network | None) -> DataFrame:
    """doc_id, score (0 to 1) of every row's whole text; only doc_id and text are read.

    Texts without words (null and empty ones too) have score 0, as has every text without a network.
    """

    def run(batches):
        cache: dict = {}
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            p = probabilities(net, texts, cache)
            yield pa.record_batch([batch.column(0), pa.array(p, pa.float64())], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(lean(run), "doc_id long, score double")


def drop_toxic(docs: DataFrame, net: Network | None, cut: float = 0.5) -> DataFrame:
    """The rows of docs, all columns, whose score is below the cut; one pass without a shuffle."""
    at = docs.columns.index("text")

    def run(batches):
        cache: dict = {}
        for whole in batches:
            for batch in (whole.slice(i, STEP) for i in range(0, whole.num_rows, STEP)):
                texts = [t or "" for t in batch.column(at).to_pylist()]
                yield batch.filter(pa.array(probabilities(net, texts, cache) < cut))

    return docs if net is None else docs.mapInArrow(lean(run), docs.schema)


def classify(docs: DataFrame, labels: DataFrame, folds: int = 5) -> DataFrame:
    """doc_id, held_out, score, predicted. Labels are learned from documents outside the held-out
    fold (crc32 of the doc_id text, remainder 0); a null doc_id is not held out and not learned."""
    net = fit(docs, labels, crc_mod("doc_id", folds) != 0)
    held = F.coalesce(crc_mod("doc_id", folds) == 0, F.lit(False))
    return score(docs, net).select("doc_id", held.alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))


ship(__name__)

"""Language identification by hyperdimensional profiles."""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.llm.common import crc_mod, lean, ship

DIMS = 1024
SLOTS = 256  # letters share hashed slots; slot 0 stands for everything that is no letter
_made: dict = {}


def _letter_slots() -> np.ndarray:
    """Slot of every code point: 0 for non-letters."""
    if "slots" not in _made:
        out = np.zeros(sys.maxunicode + 1, dtype=np.int32)
        for c in range(sys.maxunicode + 1):
            if chr(c).isalpha():
                out[c] = 1 + (c if c < 128 else c * 2654435761 % (1 << 32) >> 7) % (SLOTS - 1)
        _made["slots"] = out
    return _made["slots"]


def _letter_vectors(dims: int) -> list[np.ndarray]:
    """Random vectors of +1 and -1 for each slot, permuted (rotated) once more for each earlier place."""
    if dims not in _made:
        base = np.random.default_rng(20).choice(np.array([-1, 1], dtype=np.int8), size=(SLOTS, dims))
        _made[dims] = [np.roll(base, shift, axis=1) for shift in (2, 1, 0)]
    return _made[dims]


def _grams(text: str) -> np.ndarray | None:
    """Codes of the letter trigrams of a text, runs of other characters as one blank; None: no letters."""
    slots = _letter_slots()[np.frombuffer(f" {text.lower()} ".encode("utf-32-le", "replace"), dtype=np.uint32)]
    if not slots.any():
        return None
    keep = np.ones(len(slots), dtype=bool)
    keep[1:] = (slots[1:] != 0) | (slots[:-1] != 0)
    slots = slots[keep]
    return (slots[:-2] * SLOTS + slots[1:-1]) * SLOTS + slots[2:] if len(slots) > 2 else np.zeros(0, dtype=np.int32)


def bundle(codes: np.ndarray, counts: np.ndarray, dims: int) -> np.ndarray:
    """Sum of the bound trigram vectors, each as often as it occurs."""
    one, two, three = _letter_vectors(dims)
    out = np.zeros(dims, dtype=np.float64)
    for at in range(0, len(codes), 2048):
        c = codes[at : at + 2048]
        bound = one[c // (SLOTS * SLOTS)] * two[c // SLOTS % SLOTS] * three[c % SLOTS]
        out += counts[at : at + 2048].astype(np.float32) @ bound.astype(np.float32)
    return out


def prototypes(docs: DataFrame, train_rows, dims: int = DIMS) -> tuple[list[str], np.ndarray]:
    """Bundles of all training texts of each language: one vector a language reaches the driver."""

    def run(batches):
        sums: dict[str, np.ndarray] = {}
        for batch in batches:
            by: dict[str, list] = {}
            for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if (g := _grams(text or "")) is not None:
                    by.setdefault(lang, []).append(g)
            for lang, found in by.items():
                v = bundle(*np.unique(np.concatenate(found), return_counts=True), dims)
                sums[lang] = sums[lang] + v if lang in sums else v
        for lang, v in sums.items():
            yield pa.record_batch([pa.array([lang] * dims), pa.array(range(dims), pa.int32()), pa.array(v)], names=["lang", "i", "x"])

    rows = docs.where(train_rows).where("lang is not null").select(F.col("text").cast("string"), F.col("lang").cast("string"))
    got = rows.mapInArrow(lean(run), "lang string, i int, x double").groupBy("lang", "i").agg(F.sum("x").alias("x")).collect()
    langs = sorted({r.lang for r in got})
    out = np.zeros((len(langs), dims))
    for r in got:
        out[langs.index(r.lang), r.i] = r.x
    return langs, out / np.maximum(1e-12, np.linalg.norm(out, axis=1, keepdims=True))


def identify(docs: DataFrame, folds: int = 3, held: int = 1, dims: int = DIMS) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every row.

    Prototypes come from rows outside the held-out fold with a language; the prediction reads the
    text alone. A text that is null or without letters is `und` with score 0, and so is every text
    when there is nothing to learn from. score: cosine with the nearest prototype, at least 0.
    A null doc_id is neither learned from nor held out. Ties go to the smaller language name.
    """
    langs, protos = prototypes(docs, crc_mod("doc_id", folds) != held, dims)

    def run(batches):
        for batch in batches:
            pred, scores = [], []
            for text in batch.column(1).to_pylist():
                g = _grams(text or "") if langs else None
                if g is None:
                    pred.append("und")
                    scores.append(0.0)
                    continue
                v = bundle(*np.unique(g, return_counts=True), dims)
                near = protos @ v / max(1e-12, float(np.sqrt(v @ v)))
                best = int(near.argmax())
                pred.append(langs[best])
                scores.append(min(1.0, max(0.0, float(near[best]))))
            yield pa.record_batch([batch.column(0), pa.array(pred, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "lang_pred", "score"])

    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(lean(run), "doc_id long, lang_pred string, score double")
    return out.select("doc_id", F.coalesce(crc_mod("doc_id", folds) == held, F.lit(False)).alias("held_out"), "lang_pred", "score")


ship(__name__)

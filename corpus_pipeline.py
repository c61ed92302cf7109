"""Corpus pipeline: toxicity, near-duplicates, repeated passages, benchmark leaks, source mix."""

from __future__ import annotations

import uuid

from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from spanfold.llm.common import load, shared_dir, written
from spanfold.llm.decontam import contaminated
from spanfold.llm.mixing import mixed_sizes
from spanfold.llm.resemblance import losers
from spanfold.llm.suffix_dedup import remove_repeated_bytes
from spanfold.llm.toxicity import drop_toxic, fit

PLACE_BITS = 38  # of a row's place in its file; the bits above number the files


def toxicity(spark, docs, sf_dir):
    """Documents that the classifier does not call toxic; it learns from all labelled documents."""
    net = fit(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"), F.lit(True))
    return drop_toxic(docs, net)


def _with_rows(docs):
    """The documents under a key of their own, and its name. Rows of plain Parquet files have a key
    that holds already, file and place, so they are not copied; others are written once."""
    row = "row_"
    while any(c.lower().startswith(row) for c in docs.columns):
        row += "_"
    file = row + "file"
    try:
        if not docs._jdf.queryExecution().analyzed().children().isEmpty():
            raise AnalysisException("not plain files")
        meta = docs.metadataColumn("_metadata")
        placed = docs.select("*", meta["file_path"].alias(file), meta["row_index"].alias(row))
    except AnalysisException:
        return written(docs.withColumn(row, F.monotonically_increasing_id()), "rows"), row
    number = row + "number"
    files = written(placed.select(file).distinct().coalesce(1).withColumn(number, F.monotonically_increasing_id()), "files")
    key = F.shiftleft(number, PLACE_BITS) + F.col(row)
    return placed.join(F.broadcast(files), file).select(*(F.col(f"`{c}`") for c in docs.columns), key.alias(row)), row


def near_dedup(spark, docs, sf_dir):
    """One row of each group of near copies: the smallest doc_id; a row without doc_id stays."""
    keyed, row = _with_rows(docs)
    gone = losers(keyed.select(F.col(row).alias("row"), "doc_id", "text")).select(F.col("row").alias(row))
    return keyed.join(gone, row, "left_anti").select(*docs.columns)


def suffix_dedup(spark, docs, sf_dir):
    """Every document without the passages that an earlier one has; n_chars is counted anew."""
    rest = tuple(c for c in docs.columns if c not in ("doc_id", "text"))
    out = remove_repeated_bytes(docs, with_text=True, carry=rest).withColumnRenamed("kept_text", "text")
    if "n_chars" in rest:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def decontamination(spark, docs, sf_dir):
    """Documents without a benchmark item's template."""
    keyed, row = _with_rows(docs)
    leaks = contaminated(keyed.select(F.col(row).alias("doc_id"), "text"), load(spark, sf_dir, "benchmark")).select(F.col("doc_id").alias(row)).distinct()
    return keyed.join(leaks, row, "left_anti").select(*docs.columns)


def mixing(spark, docs, sf_dir):
    """How many words of each document the mix takes."""
    return mixed_sizes(docs)


STAGES = [
    ("toxicity", toxicity),
    ("simhash near-dedup", near_dedup),
    ("suffix-array dedup", suffix_dedup),
    ("benchmark decontamination", decontamination),
    ("source mixing", mixing),
]

#: A trained network, components and a run-length index are beyond SQL.
ORACLE_SQL = None


def run(spark, sf_dir):
    """The stages applied to documents, each written as Parquet and read again by the next."""
    docs = load(spark, sf_dir, "documents")
    for n, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if n == len(STAGES) - 1:
            return out
        path = f"{shared_dir(spark)}/tables/stage-{n}-{uuid.uuid4().hex}"
        out.write.parquet(path)
        docs = spark.read.parquet(path)

"""Streams of points: closed windows become kept models; late points change exact ones."""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanfold.functions import bayes, linear
from spanfold.operators.batch import range_states
from spanfold.operators.combine import empty
from spanfold.plans.ranges import Range, union
from spanfold.sources.points import ModelSpec, PointSource
from spanfold.sources.store import ModelStore, pack_state, unpack_state


def event_stream(spark: SparkSession, path: str, schema, files: int = 1) -> DataFrame:
    """A file stream with a fixed schema and an event time Spark can put a watermark on."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    return rows.withColumn("at", F.col("ts").cast("timestamp"))


def window_states(rows: DataFrame, spec: ModelSpec, width: str, slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """(w_start, w_end, class, key_lo, key_hi, n, s0…, q0…) of tumbling or sliding windows.

    The same expression serves batches and streams, so a stream's closed windows equal the batch's.
    """
    if watermark:
        rows = rows.withWatermark("at", watermark)
    w = F.window("at", width, slide) if slide else F.window("at", width)
    cols = [f.integer().alias(f"v{i}") for i, f in enumerate(spec.features)]
    flat = rows.select(w.alias("w"), F.expr(spec.label).cast("string").alias("class"), F.col(spec.key).alias("key_"), *cols)
    sums = [F.sum(f"v{i}").alias(f"s{i}") for i in range(len(cols))]
    squares = [F.sum(F.col(f"v{i}") * F.col(f"v{i}")).alias(f"q{i}") for i in range(len(cols))] if spec.kind == "gnb" else []
    out = flat.groupBy("w", "class").agg(F.min("key_").alias("key_lo"), (F.max("key_") + 1).alias("key_hi"), F.count("*").alias("n"), *sums, *squares)
    return out.select(F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), *[c for c in out.columns if c != "w"])


def session_states(rows: DataFrame, spec: ModelSpec, gap: str, by: str) -> DataFrame:
    """One state a session of `by`: count and sums between pauses longer than the gap."""
    cols = [f.integer().alias(f"v{i}") for i, f in enumerate(spec.features)]
    flat = rows.select("at", F.col(by), *cols)
    out = flat.groupBy(F.session_window("at", gap).alias("w"), by).agg(F.count("*").alias("n"), *[F.sum(f"v{i}").alias(f"s{i}") for i in range(len(cols))])
    return out.select(F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), *[c for c in out.columns if c != "w"])


def keep_windows(store: ModelStore, spec: ModelSpec, closed: DataFrame, batch_id: str) -> int:
    """Closed windows into the store; a replayed batch adds nothing."""
    by: dict = {}
    for r in closed.collect():  # one row a window and class
        by.setdefault(r.w_start, []).append(r)
    new = 0
    for rows in by.values():
        r = Range(min(x.key_lo for x in rows), max(x.key_hi for x in rows))
        new += store.put(spec, r, bayes.state_from_rows(rows, spec), batch_id=batch_id) is not None
    return new


def stream_to_store(rows: DataFrame, store: ModelStore, spec: ModelSpec, width: str, watermark: str, checkpoint: str):
    """Run a stream to its end: each closed tumbling window becomes a kept model."""
    closed = window_states(rows, spec, width, watermark=watermark)
    sink = closed.writeStream.outputMode("append").option("checkpointLocation", checkpoint).trigger(availableNow=True)
    query = sink.foreachBatch(lambda df, i: keep_windows(store, spec, df, f"stream-{i}") and None).start()
    query.awaitTermination()
    return query


RUNNING = "batch long, state string"


class RunningState:
    """A running exact state whose every step is a row in the shared folder.

    The row of batch b holds the state of all batches up to b. A batch that is replayed after a
    failure starts from the row before it and writes the same row again, so it counts once, and a
    new session goes on from the rows, in step with Spark's own checkpoint.
    """

    def __init__(self, spark: SparkSession, spec: ModelSpec, path: str):
        self.spark, self.spec, self.path = spark, spec, path
        self.batches: list[int] = []
        self.state = self.upto(None)

    def upto(self, before: int | None):
        """State of the batches below `before` (of all, if None)."""
        try:
            rows = self.spark.read.schema(RUNNING).parquet(self.path)
        except AnalysisException as missing:
            if missing.getCondition() != "PATH_NOT_FOUND":
                raise
            return empty(self.spec)
        rows = rows.where(F.col("batch") < before) if before is not None else rows
        last = rows.agg(F.max_by(F.struct("batch", "state"), "batch").alias("r")).first().r
        return empty(self.spec) if last is None else unpack_state(self.spec.kind, self.spec.spec_id, last.state)

    def fold(self, df: DataFrame, batch: int) -> None:
        if self.batches and batch != self.batches[-1] + 1 or not self.batches:
            self.state = self.upto(batch)
        of = linear.linreg_state if self.spec.kind == "linreg" else bayes.bayes_state
        self.state = self.state.combine(of(df, self.spec))
        row = self.spark.createDataFrame([(batch, pack_state(self.state))], RUNNING)
        row.coalesce(1).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("batch").parquet(self.path)
        self.batches.append(batch)


def running_state(rows: DataFrame, spec: ModelSpec, checkpoint: str):
    """Merge every micro-batch into one running exact state; (RunningState, query). Stopped and
    started again on the same checkpoint, it goes on where it was."""
    held = RunningState(rows.sparkSession, spec, f"{checkpoint}-states")
    query = rows.writeStream.foreachBatch(held.fold).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return held, query


def running_counts(rows: DataFrame, key: str, value: str) -> DataFrame:
    """Stateful form: per class running count, sum and sum of squares, one update a trigger."""
    import pandas as pd

    def step(k, batches, state):
        n, s, q = state.get if state.exists else (0, 0.0, 0.0)
        for pdf in batches:
            n, s, q = n + len(pdf), s + float(pdf[value].sum()), q + float((pdf[value] ** 2).sum())
        state.update((n, s, q))
        yield pd.DataFrame({"class": [k[0]], "n": [n], "s": [s], "q": [q]})

    return rows.groupBy(key).applyInPandasWithState(step, "class string, n long, s double, q double", "n long, s double, q double", "update", "NoTimeout")


def insert_late(store: ModelStore, spec: ModelSpec, late: DataFrame) -> dict:
    """Points after the watermark: folded into the kept exact models that cover their keys, each
    point counted once, and counted as unplaced where none does. One job gives what every model
    gains; changed models are written again. Closed logistic chunks refuse them."""
    if spec.kind == "logit":
        raise ValueError("closed chunks of a logistic model take no late points")
    models = store.models(spec)
    total = late.count()
    done = 0
    if models:
        covered = union(m.range for m in models)
        states = range_states(PointSource(late, spec.key), spec, [m.range for m in models] + covered)
        done = sum(s.n for s in states[len(models) :])
        gained = {m.model_id: s for m, s in zip(models, states) if s.n}
        for m, old in store.fetch(list(gained)).items():
            store.replace(m, old.combine(gained[m]))
        store.flush()
    return {"inserted": done, "unplaced": total - done}

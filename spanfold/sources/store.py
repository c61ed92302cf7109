"""Kept models: rows in Parquet, descriptors and hot states on the driver."""

from __future__ import annotations

import json
from collections import OrderedDict

import numpy as np
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanfold.functions.bayes import BayesState
from spanfold.functions.linear import LinearState
from spanfold.functions.logistic import LogisticState
from spanfold.plans.ranges import Range
from spanfold.plans.relevance import DescriptorIndex, Kept
from spanfold.sources.points import ModelSpec

SCHEMA = (
    "model_id string, spec_id string, kind string, source_version string, lo long, hi long, n long, n_chunks int, "
    "state string, params array<double>, nbytes long, seq long, batch_id string"
)


def pack_state(state) -> str:
    """State as JSON: exact integers have no fixed width."""
    if isinstance(state, LinearState):
        return json.dumps({"n": state.n, "cross": state.cross, "total": state.total, "units": state.units})
    if isinstance(state, LogisticState):
        return json.dumps({"n": state.n, "w": list(map(float, state.w)), "n_chunks": state.n_chunks})
    return json.dumps({"units": state.units, "classes": state.classes})


def unpack_state(kind: str, spec_id: str, text: str):
    x = json.loads(text)
    if kind == "linreg":
        return LinearState(spec_id, x["n"], x["cross"], x["total"], tuple(x["units"]))
    if kind == "logit":
        return LogisticState(spec_id, x["n"], np.array(x["w"]), x["n_chunks"])
    return BayesState(spec_id, tuple(x["units"]), x["classes"])


DROPPED = "model_id string, seq long"
HEAD = ("model_id", "spec_id", "kind", "source_version", "lo", "hi", "n", "n_chunks", "nbytes", "seq", "batch_id")


class ModelStore:
    """Models by spec. New and changed ones are appended in one file a flush, dropped ones named in
    another; of rows of one model the latest counts. `compact` rewrites what is left into a new
    folder. Descriptors (24 bytes each) are held, and at most `hot` states, the least used leave
    first."""

    def __init__(self, spark: SparkSession, path: str | None = None, hot: int = 100_000):
        self.spark, self.path, self.hot = spark, path, hot
        self.index: dict[str, DescriptorIndex] = {}
        self.states: OrderedDict = OrderedDict()
        self.rows: dict[str, dict] = {}
        self.pending: list[str] = []
        self.gone: list[tuple[str, int]] = []
        self.batches: set = set()
        self.seq = 0

    def put(self, spec: ModelSpec, r: Range, state, source_version: str = "0", cost: float | None = None, batch_id: str | None = None) -> str | None:
        """Keep a model; a replayed batch is not kept twice."""
        if batch_id is not None:
            mark = (spec.spec_id, r.lo, r.hi, batch_id)
            if mark in self.batches:
                return None
            self.batches.add(mark)
        self.seq += 1
        model_id = f"{spec.kind}-{self.seq:08d}"
        chunks = getattr(state, "n_chunks", 1)
        self.rows[model_id] = {
            "model_id": model_id, "spec_id": spec.spec_id, "kind": spec.kind, "source_version": source_version, "lo": r.lo, "hi": r.hi,
            "n": state.n, "n_chunks": chunks, "nbytes": state.nbytes, "seq": self.seq, "batch_id": batch_id,
        }
        self.index.setdefault(spec.spec_id, DescriptorIndex()).add(Kept(r.lo, r.hi, model_id, cost, chunks))
        self._hold(model_id, state)
        return model_id

    def _hold(self, model_id: str, state) -> None:
        self.states[model_id] = state
        self.states.move_to_end(model_id)
        self.pending.append(model_id)
        if self.path and len(self.states) > self.hot:
            self.flush()
            self._cool()

    def _cool(self) -> None:
        while self.path and len(self.states) > self.hot:
            self.states.popitem(last=False)

    def replace(self, model_id: str, state) -> None:
        """Another state for a kept model, as when late points came in."""
        self.seq += 1
        self.rows[model_id] |= {"n": state.n, "nbytes": state.nbytes, "seq": self.seq}
        self._hold(model_id, state)

    def drop(self, spec: ModelSpec, model: Kept) -> None:
        self.index[spec.spec_id].remove(model)
        self.states.pop(model.model_id, None)
        self.rows.pop(model.model_id, None)
        self.pending = [m for m in self.pending if m != model.model_id]
        self.seq += 1
        self.gone.append((model.model_id, self.seq))

    def relevant(self, spec: ModelSpec, request: Range, contained: bool = False, source_version: str | None = None) -> list[Kept]:
        """Models that can matter to a request; those of another version of the data cannot."""
        found = self.index.get(spec.spec_id, DescriptorIndex()).query(request)
        if source_version is not None:
            found = [m for m in found if self.rows[m.model_id]["source_version"] == source_version]
        return [m for m in found if request.lo <= m.lo and m.hi <= request.hi] if contained else found

    def models(self, spec: ModelSpec) -> list[Kept]:
        return self.index.get(spec.spec_id, DescriptorIndex()).models()

    def fetch(self, model_ids, source_version: str | None = None) -> dict:
        """States of models; those not in memory come from one pruned read."""
        for m in model_ids:
            if source_version is not None and self.rows[m]["source_version"] != source_version:
                raise ValueError(f"{m} was built on another version of the data")
        out = {m: self.states[m] for m in model_ids if m in self.states}
        cold = [m for m in model_ids if m not in out]
        if cold:
            kinds = {self.rows[m]["spec_id"] for m in cold}
            latest: dict = {}
            for r in self._stored().where(F.col("spec_id").isin(*kinds) & F.col("model_id").isin(*cold)).collect():
                if r.model_id not in latest or latest[r.model_id].seq < r.seq:
                    latest[r.model_id] = r
            for m, r in latest.items():
                out[m] = self.states[m] = unpack_state(r.kind, r.spec_id, r.state)
        for m in out:
            self.states.move_to_end(m)
        self._cool()
        return {m: out[m] for m in model_ids}

    def flush(self) -> None:
        """Append what is new, what changed, and the names of what went."""
        if not self.path:
            return
        if self.pending:
            rows = [self._row(m) for m in dict.fromkeys(self.pending)]
            self.spark.createDataFrame(rows, SCHEMA).coalesce(1).write.mode("append").partitionBy("kind", "spec_id").parquet(f"{self.path}/current")
            self.pending = []
        if self.gone:
            self.spark.createDataFrame(self.gone, DROPPED).coalesce(1).write.mode("append").parquet(f"{self.path}/dropped")
            self.gone = []

    def _row(self, m: str) -> tuple:
        r, s = self.rows[m], self.states[m]
        w = list(map(float, s.w)) if isinstance(s, LogisticState) else None
        return (m, r["spec_id"], r["kind"], r["source_version"], r["lo"], r["hi"], r["n"], r["n_chunks"], pack_state(s), w, r["nbytes"], r["seq"], r["batch_id"])

    def _read(self, name: str, schema: str) -> DataFrame:
        try:
            return self.spark.read.schema(schema).parquet(f"{self.path}/{name}")
        except AnalysisException as missing:
            if missing.getCondition() != "PATH_NOT_FOUND":
                raise
            return self.spark.createDataFrame([], schema)

    def _stored(self) -> DataFrame:
        """Rows as written, of all ages."""
        if not self.path:
            return self.spark.createDataFrame([self._row(m) for m in self.states], SCHEMA)
        self.flush()
        return self._read("current", SCHEMA).select(*[f.split()[0] for f in SCHEMA.split(", ")])

    def _latest(self, columns=None) -> DataFrame:
        """One row a kept model: its latest, unless it was dropped since. Only `columns` are read."""
        rows = self._stored()
        rows = rows if columns is None else rows.select(*columns)
        if not self.path:
            return rows
        last = rows.groupBy("model_id").agg(F.max_by(F.struct(*rows.columns), "seq").alias("r")).select("r.*")
        gone = self._read("dropped", DROPPED).select("model_id").distinct()
        return last.join(gone, "model_id", "left_anti").select(*rows.columns)

    def frame(self) -> DataFrame:
        """All models as a table."""
        return self._latest()

    def descriptors(self, spec: ModelSpec) -> DataFrame:
        rows = [(m.model_id, m.lo, m.hi, int(self.rows[m.model_id]["nbytes"])) for m in self.models(spec)]
        return self.spark.createDataFrame(rows, "model_id string, lo long, hi long, nbytes long")

    def compact(self, target: str) -> "ModelStore":
        """Rewrite what is left, sorted by range in files of neighbouring ranges, in a new folder; the
        old one stays until dropped."""
        rows = self._latest().repartitionByRange("kind", "spec_id", "lo").sortWithinPartitions("kind", "spec_id", "lo")
        rows.write.mode("overwrite").partitionBy("kind", "spec_id").parquet(f"{target}/current")
        self.path = target
        return self

    @classmethod
    def open(cls, spark: SparkSession, path: str, hot: int = 100_000) -> "ModelStore":
        """The kept models' descriptors; states are read when first fetched."""
        store = cls(spark, path, hot)
        for r in store._latest(HEAD).orderBy("seq").collect():  # a row a model, without its state
            store.rows[r.model_id] = r.asDict()
            store.index.setdefault(r.spec_id, DescriptorIndex()).add(Kept(r.lo, r.hi, r.model_id, None, r.n_chunks))
            if r.batch_id is not None:
                store.batches.add((r.spec_id, r.lo, r.hi, r.batch_id))
        ends = [df.agg(F.max("seq")).first()[0] for df in (store._stored(), store._read("dropped", DROPPED))]
        store.seq = max([0, *(s for s in ends if s is not None)])
        return store

    def evict(self, spec: ModelSpec, max_bytes: int) -> list[str]:
        """Drop the models least used lately until the rest fit."""
        own = {m.model_id: m for m in self.models(spec)}
        size = sum(self.rows[m]["nbytes"] for m in own)
        gone = []
        cold = [m for m in own if m not in self.states]  # not used since the store was opened
        for m in cold + [m for m in self.states if m in own]:
            if size <= max_bytes:
                break
            size -= self.rows[m]["nbytes"]
            self.drop(spec, own[m])
            gone.append(m)
        self.flush()
        return gone

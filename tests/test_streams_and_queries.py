"""Streams against batches, and every registered query against its SQL."""

import math
from decimal import Decimal

import duckdb
import pytest
from pyspark.sql import functions as F

from spanfold import queries as Q
from spanfold.functions import bayes
from spanfold.operators.measures import state_distance
from spanfold.sources.points import GNB_EVENTS, TABLES, load
from spanfold.sources.store import ModelStore
from spanfold.streaming import states as S


def stream_files(spark, tiny, path, late=False):
    events = load(spark, tiny, "events")
    events.repartitionByRange(5, "event_id").write.parquet(path)
    return events, S.event_stream(spark, path, events.schema)


def test_running_state_equals_batch(spark, tiny, tmp_path):
    events, rows = stream_files(spark, tiny, f"file://{tmp_path}/in")
    held, _ = S.running_state(rows, GNB_EVENTS, f"file://{tmp_path}/ck")
    assert state_distance(held.state, bayes.bayes_state(events, GNB_EVENTS)) == 0 and len(held.batches) > 1
    # a new session goes on from what was written; a batch that comes again counts once
    events.write.mode("append").parquet(f"file://{tmp_path}/in")
    again, _ = S.running_state(S.event_stream(spark, f"file://{tmp_path}/in", events.schema), GNB_EVENTS, f"file://{tmp_path}/ck")
    twice = bayes.bayes_state(events.unionByName(events), GNB_EVENTS)
    assert state_distance(again.state, twice) == 0 and again.batches[0] > held.batches[-1]
    replayed = S.RunningState(spark, GNB_EVENTS, f"file://{tmp_path}/ck-states")
    replayed.fold(events.where("event_id < 0"), again.batches[-1] + 1)
    replayed.fold(events.where("event_id < 0"), again.batches[-1] + 1)
    assert state_distance(replayed.state, twice) == 0


def test_closed_windows_become_models(spark, tiny, tmp_path):
    events, rows = stream_files(spark, tiny, f"file://{tmp_path}/in")
    store = ModelStore(spark)
    S.stream_to_store(rows, store, GNB_EVENTS, "5 days", "1 hour", f"file://{tmp_path}/ck")
    models = store.models(GNB_EVENTS)
    assert len(models) >= 4
    for m in models:
        assert state_distance(store.states[m.model_id], bayes.bayes_state(events.where((F.col("event_id") >= m.lo) & (F.col("event_id") < m.hi)), GNB_EVENTS)) == 0
    before = len(models)
    batch = S.window_states(events.withColumn("at", F.col("ts").cast("timestamp")), GNB_EVENTS, "5 days")
    assert S.keep_windows(store, GNB_EVENTS, batch, "again") > 0 and S.keep_windows(store, GNB_EVENTS, batch, "again") == 0
    assert len(store.models(GNB_EVENTS)) > before


def test_stateful_counts(spark, tiny, tmp_path):
    events, rows = stream_files(spark, tiny, f"file://{tmp_path}/in")
    name = "running_counts_test"
    S.running_counts(rows.select("event_type", "value"), "event_type", "value").writeStream.outputMode("update").format("memory").queryName(name).option(
        "checkpointLocation", f"file://{tmp_path}/ck"
    ).trigger(availableNow=True).start().awaitTermination()
    got = {r["class"]: r.n for r in spark.table(name).groupBy("class").agg(F.max("n").alias("n")).collect()}
    assert got == {r.event_type: r["count"] for r in events.groupBy("event_type").count().collect()}


def test_late_points(spark, tiny):
    from dataclasses import replace

    from spanfold.sources.points import LOGIT

    store = ModelStore(spark)
    events = load(spark, tiny, "events").where("event_id < 20")
    assert S.insert_late(store, GNB_EVENTS, events) == {"inserted": 0, "unplaced": 20}
    with pytest.raises(ValueError):
        S.insert_late(store, replace(LOGIT), events)


def canon(rows, cols):
    def one(v):
        if isinstance(v, Decimal):
            v = float(v)
        if isinstance(v, float):
            return None if math.isnan(v) else float(f"{v:.10g}")
        return v

    order = sorted(range(len(cols)), key=lambda i: cols[i])
    return sorted([tuple(one(r[i]) for i in order) for r in rows], key=repr)


@pytest.fixture(scope="module")
def duck(tiny):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(Q.queries()))
def test_query(spark, tiny, duck, name):
    df = Q.queries()[name](spark, tiny)
    rows = [tuple(r) for r in df.collect()]
    sql = Q.oracle_sql().get(name)
    if sql is None:
        assert rows
        return
    got = duck.execute(sql)
    cols = [c[0] for c in got.description]
    assert sorted(cols) == sorted(df.columns)
    assert canon(rows, df.columns) == canon(got.fetchall(), cols)


def test_flagship(spark, tiny):
    rows = Q.flagship(spark, tiny).collect()
    assert {r.part for r in rows} == {"segment", "weight"} and sum(r.part == "weight" for r in rows) == 11


def test_entry_module(spark):
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries()) and entry.entry(spark).count() > 0

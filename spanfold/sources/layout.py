"""Dense positions, range-clustered files and the block directory."""

from __future__ import annotations

import hashlib
import json
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanfold.plans.costs import Directory
from spanfold.sources.local import LocalReader
from spanfold.sources.points import LINEITEM_KEY, PointSource, load


def work_dir(spark: SparkSession) -> str:
    """The shared folder the session names. Only a session whose tasks all run in this process may
    go without: it gets a temporary one."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        import tempfile

        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")

        found = "file://" + tempfile.mkdtemp(prefix="spanfold-")
        spark.conf.set("spark.checkpoint.dir", found)
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def assign_position(df: DataFrame, order: list[str], name: str = "pid") -> DataFrame:
    """A dense 0-based position in the given order, without a one-task sort.

    Rows are range-partitioned and sorted; a row's number within its task and the counts of the
    tasks before it make its position. The sorted rows are written once, as range sampling may cut
    otherwise on a second run; one number a task reaches the driver.
    """
    spark = df.sparkSession
    path = f"{work_dir(spark)}/positions/{uuid.uuid4().hex}"
    row = F.monotonically_increasing_id()
    ranged = df.repartitionByRange(*order).sortWithinPartitions(*order)
    ranged.withColumn("part_", F.shiftright(row, 33)).withColumn("row_", row.bitwiseAND(F.lit((1 << 33) - 1))).write.parquet(path)
    rows = spark.read.parquet(path)
    counts = sorted(tuple(r) for r in rows.groupBy("part_").count().collect())
    before, total = [], 0
    for part, n in counts:
        before.append((part, total))
        total += n
    offsets = F.broadcast(spark.createDataFrame(before, "part_ long, base_ long"))  # one row a task
    return rows.join(offsets, "part_").withColumn(name, F.col("base_") + F.col("row_")).drop("part_", "row_", "base_")


def version_of(df: DataFrame) -> str:
    """A name for the files behind a table: the same in any session while they stay as they are,
    another once one is rewritten. Few files are asked of the file system; of many, their metadata
    is gathered by a job that reads no column."""
    spark = df.sparkSession
    names = df.inputFiles()
    if len(names) <= 64:
        conf, path = spark._jsc.hadoopConfiguration(), spark._jvm.org.apache.hadoop.fs.Path
        found = [(p := path(n)).getFileSystem(conf).getFileStatus(p) for n in sorted(names)]
        text = json.dumps([(f.getPath().getName(), f.getLen(), f.getModificationTime()) for f in found])
        return f"{len(names)}-{hashlib.sha256(text.encode()).hexdigest()[:16]}"
    files = df.select("_metadata.file_name", "_metadata.file_size", "_metadata.file_modification_time").distinct()
    r = files.agg(F.count("*").alias("n"), F.sum(F.xxhash64(*files.columns).cast("decimal(38,0)")).alias("h")).first()
    return f"{r.n}-{int(r.h or 0) & (1 << 64) - 1:016x}"


def write_clustered(df: DataFrame, key: str, path: str, bucket_width: int, version: str | None = None, ranged: bool = False) -> PointSource:
    """Range-cluster rows by key into bucket folders sorted by key, and read them back. `ranged`:
    files behind the rows hold ranges of keys already, so rows are sorted where they are read."""
    spark = df.sparkSession
    dealt = df.withColumn("bucket", F.floor(F.col(key) / bucket_width).cast("int"))
    dealt = dealt if ranged else dealt.repartitionByRange(key)
    dealt.sortWithinPartitions("bucket", key).write.partitionBy("bucket").parquet(path)
    rows = spark.read.parquet(path)
    source = PointSource(rows, key, version or version_of(rows), bucket_width)
    source.directory = directory_of(build_directory(rows, key, bucket_width))
    return source


def materialize(source: PointSource, spec, project=None) -> PointSource:
    """Write a clustered source's features for a spec as numbers, once; its later scans read only
    those columns and compute nothing but sums. The source's files hold ranges of keys, so rows are
    sorted where they are read. Row groups are small, so that a reader can pick short ranges."""
    from spanfold.functions import bayes, linear, logistic

    project = project or {"linreg": linear.project, "logit": logistic.project}.get(spec.kind, bayes.project)
    spark = source.df.sparkSession
    rows = source.prepared(spec, project)
    path = f"{work_dir(spark)}/features/{uuid.uuid4().hex}"
    ranged = rows.df.sortWithinPartitions("bucket", source.key)
    ranged.write.option("parquet.block.size", 1 << 19).partitionBy("bucket").parquet(path)
    kept = PointSource(spark.read.parquet(path), source.key, source.version, source.bucket_width, source.directory)
    try:
        kept.reader = LocalReader(path, source.key, source.bucket_width)
    except (pa.ArrowInvalid, pa.ArrowNotImplementedError):  # a store that only Spark reads: every scan is a job
        kept.reader = None
    source.projected[spec.shape_id] = kept
    return kept


def build_directory(df: DataFrame, key: str, bucket_width: int) -> DataFrame:
    """bucket, min_key, max_key, n, cum_n: one row a block, counts run in key order. The running
    sum is one task's, over 32 bytes a block: blocks are chosen so wide that they number thousands."""
    from pyspark.sql import Window

    per = df.groupBy(F.floor(F.col(key) / bucket_width).cast("long").alias("bucket")).agg(F.min(key).alias("min_key"), F.max(key).alias("max_key"), F.count("*").alias("n"))
    order = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)  # one row a block
    return per.withColumn("cum_n", F.sum("n").over(order))


def directory_of(blocks: DataFrame) -> Directory:
    rows = sorted(tuple(r) for r in blocks.select("min_key", "max_key", "n").collect())
    return Directory([r[0] for r in rows], [r[2] for r in rows], [r[1] + 1 for r in rows])


_laid: dict = {}


def lineitem_source(spark: SparkSession, sf_dir: str) -> PointSource:
    """lineitem with a dense `pid`, clustered once a session and kept for later requests. Its
    version is that of the given files, since positions follow from them alone."""
    rows = load(spark, sf_dir, "lineitem")
    at = (spark.sparkContext.applicationId, sf_dir)
    if at not in _laid:
        path = f"{work_dir(spark)}/lineitem/{uuid.uuid4().hex}"
        width = max(1, rows.count() // 24)
        _laid[at] = write_clustered(assign_position(rows, LINEITEM_KEY), "pid", path, width, version_of(rows), ranged=True)
    return _laid[at]


def event_source(spark: SparkSession, sf_dir: str) -> PointSource:
    """events by event_id, which is dense and rises with ts: already in key order as given."""
    rows = load(spark, sf_dir, "events")
    n = rows.agg(F.max("event_id")).first()[0]
    return PointSource(rows, "event_id", version_of(rows), directory=Directory.dense((n if n is not None else -1) + 1))

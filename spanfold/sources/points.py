"""Data sets of points: ordered key, target, features; and what makes two models comparable."""

from __future__ import annotations

import hashlib
import json
from dataclasses import asdict, dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SPARSE = 256
MOST_CELLS = 1 << 20  # cells up to which their table is broadcast

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """Rows of a file too small to be split, dealt to all cores where each row takes long."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if len(df.inputFiles()) < cores and df.rdd.getNumPartitions() < cores else df


def load_as(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """CSV, JSON or ORC files under an explicit schema (no inference pass)."""
    reader = spark.read.schema(schema)
    return {"csv": reader.option("header", True).csv, "json": reader.json, "orc": reader.orc, "parquet": reader.parquet}[kind](path)


@dataclass(frozen=True)
class Feature:
    """A feature as SQL, held exactly as an integer of `scale` decimal digits; |value| <= bound."""

    name: str
    expr: str
    scale: int = 0
    bound: float = 1e6

    def integer(self) -> Column:
        if not self.scale:
            return F.expr(f"cast({self.expr} as bigint)")
        return F.expr(f"cast(cast({self.expr} as decimal(18,{self.scale})) * {10**self.scale} as bigint)")

    def real(self) -> Column:
        return F.expr(f"cast({self.expr} as double)")

    @property
    def unit(self) -> int:
        return 10**self.scale

    @property
    def limit(self) -> int:
        return int(self.bound * self.unit) + 1


@dataclass(frozen=True)
class ModelSpec:
    """What a model is of. Only models of one spec combine; solving parameters (ridge, smoothing)
    are no part of it, since the kept state does not depend on them."""

    kind: str  # linreg | gnb | mnb | logit
    source_id: str
    key: str
    features: tuple[Feature, ...]
    label: str  # SQL of the class, or of the target where `target` is not given
    target: Feature | None = None
    classes: tuple[str, ...] = ()
    intercept: bool = False
    scales: tuple[float, ...] = ()  # fixed divisors of logistic features, never taken from the data
    chunk: int = 0
    step_size: float = 0.0
    l2: float = 0.0
    trainer: str = "sgd"
    steps: int = 1
    null_policy: str = "fail"

    @property
    def spec_id(self) -> str:
        return hashlib.sha256(json.dumps(asdict(self), sort_keys=True, default=str).encode()).hexdigest()[:16]

    @property
    def shape_id(self) -> str:
        """What a spec's points look like; specs that differ in training only share it."""
        return json.dumps([self.kind, self.key, [asdict(f) for f in self.features], self.label, asdict(self.target) if self.target else None, self.intercept, self.scales, self.null_policy], default=str)

    def columns(self) -> list[Feature]:
        """Features with the constant in front where the model has one."""
        return ([Feature("one", "1", 0, 1)] if self.intercept else []) + list(self.features)


@dataclass
class PointSource:
    """A DataFrame bound to its key; layout knows about buckets when the rows were clustered."""

    df: DataFrame
    key: str
    version: str = "0"
    bucket_width: int | None = None
    directory: object = None
    stats: dict = field(default_factory=lambda: {"points": 0.0, "jobs": 0})
    projected: dict = field(default_factory=dict)
    reader: object = None  # of clustered features, for scans too small for a job

    @property
    def most_points(self) -> float:
        """Points of the whole source at most, for bounds of sums."""
        return float(self.directory.running[-1]) if self.directory is not None else float(1 << 31)

    def prepared(self, spec: "ModelSpec", project) -> "PointSource":
        """This source with only what a spec needs, analysed once; filters still reach the scan."""
        if spec.shape_id not in self.projected:
            keep = [self.key] + (["bucket"] if self.bucket_width else [])
            self.projected[spec.shape_id] = PointSource(project(self.df, spec, keep=keep), self.key, self.version, self.bucket_width, self.directory)
        return self.projected[spec.shape_id]

    def scan_range(self, lo: int, hi: int) -> DataFrame:
        """Points of [lo, hi): partitions are pruned by bucket, row groups by key."""
        out = self.df.where((F.col(self.key) >= lo) & (F.col(self.key) < hi))
        if self.bucket_width:
            out = out.where(F.col("bucket").between(lo // self.bucket_width, max(lo, hi - 1) // self.bucket_width))
        return out

    def scan_segments(self, segments) -> DataFrame:
        """Points of all scan segments with a net sign, in one job.

        The segments' ends cut the key line into cells, so each point falls into one cell; cells
        that cancel are not read. Few cells become one filter, many a join by buckets of keys over
        the part of the line they span.
        """
        from spanfold.plans.planner import net_coverage

        cells = net_coverage(segments)
        if len(cells) <= 64:
            where, sign = F.lit(False), F.lit(None).cast("int")
            for r, n in cells:
                hit = (F.col(self.key) >= r.lo) & (F.col(self.key) < r.hi)
                if self.bucket_width:
                    hit = hit & F.col("bucket").between(r.lo // self.bucket_width, (r.hi - 1) // self.bucket_width)
                where = where | hit
                sign = F.when((F.col(self.key) >= r.lo) & (F.col(self.key) < r.hi), n).otherwise(sign)
            return self.df.where(where).withColumn("sign", sign)
        rows = self.scan_range(cells[0][0].lo, cells[-1][0].hi)
        return in_cells(rows, self.key, [(r.lo, r.hi, n) for r, n in cells], "sign int").drop("cell_lo", "cell_hi")


def in_cells(rows: DataFrame, key: str, cells: list[tuple], extra: str) -> DataFrame:
    """Rows joined to the one of many disjoint cells (lo, hi, …) that holds their key.

    Cells are listed under every coarse bucket of keys they meet, so rows meet few cells by an
    equality join and the exact range decides. The table is broadcast: cells are few thousands, 20
    bytes each, and a cell of a 1,024th of the line has two buckets on average.
    """
    table = rows.sparkSession.createDataFrame(cells, f"cell_lo long, cell_hi long, {extra}")
    width = max(1, (cells[-1][1] - cells[0][0]) // 1024)
    dealt = table.withColumn("kb_", F.explode(F.sequence(F.floor(F.col("cell_lo") / width), F.floor((F.col("cell_hi") - 1) / width))))
    dealt = F.broadcast(dealt) if len(cells) <= MOST_CELLS else dealt
    k = F.col(key)
    return rows.withColumn("kb_", F.floor(k / width)).join(dealt, "kb_").where((k >= F.col("cell_lo")) & (k < F.col("cell_hi"))).drop("kb_")


def check_rows(df: DataFrame, spec: ModelSpec) -> DataFrame:
    """Apply the null policy to the columns a spec uses: fail at run time, or drop such points."""
    used = [f.real() for f in spec.features] + ([spec.target.real()] if spec.target else [F.expr(spec.label)])
    bad = F.lit(False)
    for c in used:
        bad = bad | c.isNull()
    if spec.null_policy == "drop":
        return df.where(~bad)
    return df.where(F.when(bad, F.raise_error(F.lit("null in a feature or target"))).otherwise(F.lit(True)))


def validate_key(df: DataFrame, key: str) -> DataFrame:
    """One row: points, distinct keys, null keys, lowest, highest, valid.

    Where one key in SPARSE or more of the line is taken, keys are marked in bitmaps of 32,768
    neighbours, built inside the scan: no key is shuffled, an eighth of a byte a key is. On a
    sparser line keys are counted one by one.
    """
    k = F.col(key).cast("long")
    facts = df.agg(F.count("*").alias("n"), F.count(k).alias("m"), F.min(k).alias("lo"), F.max(k).alias("hi"))
    seen = facts.first()
    if seen.m and seen.hi - seen.lo < SPARSE * seen.m:
        maps = df.where(k.isNotNull()).groupBy(F.bitmap_bucket_number(k).alias("b")).agg(F.bitmap_count(F.bitmap_construct_agg(F.bitmap_bit_position(k))).alias("c"))
    else:
        maps = df.where(k.isNotNull()).groupBy(k.alias("b")).agg(F.lit(1).cast("long").alias("c"))
    out = maps.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("distinct_keys"))
    lit = lambda x: F.lit(x).cast("long")
    return out.select(
        lit(seen.n).alias("n"), "distinct_keys", lit(seen.n - seen.m).alias("null_keys"), lit(seen.lo).alias("min_key"), lit(seen.hi).alias("max_key"),
        ((F.col("distinct_keys") == seen.m) & F.lit(seen.n - seen.m <= 1)).alias("valid"),
    )


def time_range_keys(df: DataFrame, key: str, ts: str, start: str, end: str) -> DataFrame:
    """Key range [lo, hi) of the points of a time range, for data whose key rises with time."""
    return time_ranges_keys(df, key, ts, [(start, end)]).select("lo", "hi", "n")


def time_ranges_keys(df: DataFrame, key: str, ts: str, spans: list[tuple[str, str]]) -> DataFrame:
    """(seq, lo, hi, n) of several time ranges in one scan of two columns; the hull of the ranges
    reaches the scan as a filter."""
    at = F.col(ts).cast("timestamp")
    first, last = min(a for a, _ in spans), max(b for _, b in spans)
    rows = df.where((at >= F.lit(first).cast("timestamp")) & (at < F.lit(last).cast("timestamp")))
    parts = []
    for i, (a, b) in enumerate(spans):
        inside = F.when((at >= F.lit(a).cast("timestamp")) & (at < F.lit(b).cast("timestamp")), F.col(key))
        parts.append(F.struct(F.lit(i).alias("seq"), F.min(inside).alias("lo"), (F.max(inside) + 1).alias("hi"), F.count(inside).alias("n")))
    return rows.agg(F.array(*parts).alias("all")).select(F.inline("all"))


# The ten-feature design over lineitem, its noise and planted targets.
LINEITEM_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate"]
NOISE = "((l_orderkey * 7919 + l_partkey * 104729 + l_suppkey * 1299709 + l_linenumber * 15485863) % 1000)"
DESIGN = (
    Feature("x1", "l_quantity", 2, 50),
    Feature("x2", "l_extendedprice", 2, 105000),
    Feature("x3", "l_discount", 2, 1),
    Feature("x4", "l_tax", 2, 1),
    Feature("x5", "l_linenumber", 0, 7),
    Feature("x6", "l_partkey % 10", 0, 10),
    Feature("x7", "l_suppkey % 7", 0, 7),
    Feature("x8", "month(l_shipdate)", 0, 12),
    Feature("x9", "day(l_shipdate)", 0, 31),
    Feature("x10", "case when l_returnflag = 'R' then 1 else 0 end", 0, 1),
)
DESIGN_SCALES = (50.0, 105000.0, 0.1, 0.08, 7.0, 10.0, 7.0, 12.0, 31.0, 1.0)
DEC = "cast({} as decimal(12,2))"
TARGET = Feature("y", f"3 * {DEC.format('l_quantity')} - 20 * {DEC.format('l_discount')} + l_linenumber + cast({NOISE} as decimal(12,2)) / 50 - 10", 2, 1000)
SCORE = f"(5600 * {DEC.format('l_quantity')} + 2100000 * {DEC.format('l_discount')} - 1750000 * {DEC.format('l_tax')} + {DEC.format('l_extendedprice')} + 140 * {NOISE} - 297500)"
CLASS2 = f"case when {SCORE} > 0 then 1 else 0 end"
CLASS3 = f"case when {SCORE} <= -60000 then 'low' when {SCORE} > 60000 then 'high' else 'middle' end"

LINREG = ModelSpec("linreg", "lineitem", "pid", DESIGN, "y", TARGET, intercept=True)
GNB_LINES = ModelSpec("gnb", "lineitem", "pid", DESIGN, CLASS3, classes=("high", "low", "middle"))
LOGIT = ModelSpec("logit", "lineitem", "pid", DESIGN, CLASS2, intercept=True, scales=DESIGN_SCALES, chunk=600, step_size=0.5, l2=0.0, trainer="sgd")
EVENT_VALUE = Feature("value", "value", 2, 1000)
EVENT_K = Feature("k", "cast(get_json_object(props, '$.k') as int)", 0, 100)
EVENT_HOUR = Feature("hour", "hour(ts)", 0, 24)
EVENT_USER = Feature("user10", "user_id % 10", 0, 10)
GNB_EVENTS = ModelSpec("gnb", "events", "event_id", (EVENT_VALUE, EVENT_K, EVENT_HOUR, EVENT_USER), "event_type", classes=("click", "error", "purchase", "signup", "view"))

"""Mixing sources to target weights, in DataFrame functions only."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spanfold.llm.common import WORD, shuffle_parts, written

BLOCK_WORDS = 64
SHARD_SLOTS = 1024
ROUNDS = 12


def source_targets(sizes: DataFrame, cap: float = 3.0) -> DataFrame:
    """(source, size) rows to one row a source: source, source_size, target.

    Sources in code point order, null last, weigh 1, 2, 3 in turn and share the sum of all sizes.
    No target exceeds cap times its source's size; what is cut off goes to the others by weight.
    That is one level: each target is the smaller of the cap and level times weight, and the level
    follows from the sources sorted by the level at which they are full.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").asc_nulls_last())  # one row a source
    per = per.withColumn("weight", (F.pmod(F.row_number().over(order) - 1, F.lit(3)) + 1).cast("double"))
    full = F.col("source_size") * F.lit(cap)
    per = per.withColumn("full", full).withColumn("fill", full / F.col("weight"))
    by_fill = Window.orderBy("fill", F.col("source").asc_nulls_last())
    everyone = Window.partitionBy()
    per = per.withColumn("total", F.sum("source_size").over(everyone)).withColumn("weights", F.sum("weight").over(everyone))
    before = by_fill.rowsBetween(Window.unboundedPreceding, -1)
    per = per.withColumn("spent", F.coalesce(F.sum("full").over(before), F.lit(0.0))).withColumn("taken", F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    level_here = (F.col("total") - F.col("spent")) / (F.col("weights") - F.col("taken"))
    # the level is set by the first source that it does not fill
    per = per.withColumn("level_at", F.struct(F.row_number().over(by_fill).alias("at"), level_here.alias("level"))).withColumn("holds", level_here <= F.col("fill"))
    level = F.min(F.when(F.col("holds"), F.col("level_at"))).over(everyone)["level"]
    return per.select("source", "source_size", F.least("full", F.coalesce(level, F.lit(0.0)) * F.col("weight")).alias("target"))


def _uniform(*parts):
    """A repeatable number in [0, 1) from the given columns."""
    return F.shiftrightunsigned(F.xxhash64(*parts), 11).cast("double") / F.lit(float(1 << 53))


def shuffled_index(index, size, *seed):
    """A pseudorandom permutation of 0 … size - 1 for any size: rounds of swap-or-not.

    Each round pairs x with (key - x) modulo size and swaps the pair by a coin both share.
    """
    key = lambda r: F.pmod(F.xxhash64(r, F.lit("key"), *seed), size)

    def turn(x, r):
        other = F.pmod(key(r) - x, size)
        coin = F.pmod(F.xxhash64(r, F.greatest(x, other), *seed), F.lit(2)) == 1
        return F.when(coin, other).otherwise(x)

    return F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), index, turn)


def _offsets(rows: DataFrame, key: list, order: list, size: str, out: str, groups: int) -> DataFrame:
    """Running sums of `size` before each row within `key`, in two levels so that no task gets all
    rows of a key: sums inside hashed groups, then sums over the groups (both near the square root
    of the number of rows)."""
    rows = rows.withColumn("g_", F.pmod(F.xxhash64(*order), F.lit(groups)))
    inner = Window.partitionBy(*key, "g_").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("in_", F.coalesce(F.sum(size).over(inner), F.lit(0).cast("long")))
    heads = rows.groupBy(*key, "g_").agg(F.sum(size).alias("all_"))
    outer = Window.partitionBy(*key).orderBy("g_").rowsBetween(Window.unboundedPreceding, -1)
    heads = heads.withColumn("base_", F.coalesce(F.sum("all_").over(outer), F.lit(0).cast("long"))).drop("all_")
    return rows.join(heads, [*key, "g_"]).withColumn(out, F.col("base_") + F.col("in_")).drop("g_", "in_", "base_")


def mix(docs: DataFrame, block: int = BLOCK_WORDS, shard_slots: int = SHARD_SLOTS, seed: int = 1) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The plan of a mix: (spans, documents, sources).

    Words of a source, documents in a hashed order, are packed into blocks of `block` words (the
    last one may be short). The output is dealt in shards of slots. A shard's source counts are the
    whole parts of its expected counts and a multinomial draw for the rest. A source's n-th slot
    takes the block at the n-th place of a pseudorandom permutation of its blocks, a new one each
    time round, so blocks are used evenly and no block more than three times.

    spans: shard, slot, source_key, block, doc_id, row, pos (in its source), first_word, n_words, one row for each
    stretch of a document in a slot's block. documents: row, doc_id, source_key, size. sources:
    source_key, source, source_size, target. A null text has no words, a null source is a source
    of its own (the last), a null doc_id and repeated rows are documents like others. Only doc_id,
    text and source are read.
    """
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col("source").cast("string").alias("source"),
        F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
        F.xxhash64("text", F.col("doc_id").cast("long")).alias("row"),
    )
    rows = written(rows.withColumn("source_key", F.sha2(F.concat(F.when(F.col("source").isNull(), "n").otherwise("s"), F.coalesce("source", F.lit(""))), 256)), "mix-documents")
    # rows that repeat each other are told apart by their number among equals
    twin = Window.partitionBy("source_key", "doc_id", "row").orderBy("size")
    docs_ = rows.withColumn("twin", F.row_number().over(twin)) if rows.groupBy("doc_id", "row").count().where("count > 1").limit(1).count() else rows.withColumn("twin", F.lit(1))
    total = max(1, rows.count())
    sources = source_targets(rows.select("source", "size"))
    sources = sources.withColumn("source_key", F.sha2(F.concat(F.when(F.col("source").isNull(), "n").otherwise("s"), F.coalesce("source", F.lit(""))), 256))
    sources = sources.withColumn("blocks", F.ceil(F.col("source_size") / F.lit(block)).cast("long"))
    sources = sources.withColumn("want", F.when(F.col("source_size") > 0, F.col("target") * F.col("blocks") / F.col("source_size")).otherwise(0.0))
    sources = written(sources, "mix-sources")
    slots = math.ceil(sources.agg(F.sum("want")).first()[0] or 0)
    shards = math.ceil(slots / shard_slots)

    # expected counts of a shard, as numbers of slots; the last shard may be short
    side = max(1, math.isqrt(shards))
    grid = sources.where("want > 0").select("source_key", "blocks", (F.col("want") / F.lit(float(max(slots, 1)))).alias("share"), F.explode(F.sequence(F.lit(0), F.lit((shards - 1) // side if shards else 0))).alias("g"))
    lo = F.col("g").cast("long") * side
    grid = grid.repartition("source_key", "g").select("source_key", "blocks", "share", F.explode(F.sequence(lo, F.least(lo + side, F.lit(shards).cast("long")) - 1)).alias("shard"))
    room = F.least(F.lit(shard_slots).cast("long"), F.lit(slots) - F.col("shard") * shard_slots)
    expected = grid.withColumn("mean", F.col("share") * room)
    expected = expected.withColumn("whole", F.floor("mean")).withColumn("part", F.col("mean") - F.floor("mean"))
    edge = Window.partitionBy("shard").orderBy("source_key")
    expected = expected.withColumn("upto", F.sum("part").over(edge)).withColumn("rest", F.sum("part").over(Window.partitionBy("shard")))
    expected = written(expected, "mix-expected")
    # what the whole parts leave is a number of slots: each is drawn by the sources' remaining parts
    draws = expected.groupBy("shard").agg(F.max("rest").alias("rest")).where("round(rest) >= 1")
    draws = draws.select("shard", "rest", F.explode(F.sequence(F.lit(1), F.round("rest").cast("int"))).alias("draw")).withColumn("u", _uniform(F.lit(seed), F.col("shard"), F.col("draw")) * F.col("rest"))
    hits = draws.alias("d").join(expected.alias("e"), "shard").where((F.col("d.u") < F.col("upto")) & (F.col("d.u") >= F.col("upto") - F.col("part")))
    drawn = hits.groupBy("shard", "source_key").agg(F.count("*").alias("more"))
    counts = expected.join(drawn, ["shard", "source_key"], "left").select("shard", "source_key", "blocks", (F.col("whole") + F.coalesce("more", F.lit(0))).alias("slots"))
    counts = _offsets(counts, ["source_key"], ["shard"], "slots", "before", max(1, math.isqrt(shards)))
    # few rows become many slots: they are spread before, by a number that is not merged again
    counts = counts.where("slots > 0").repartition(shuffle_parts(docs.sparkSession), "shard", "source_key")
    chosen = counts.select("shard", "source_key", "blocks", F.explode(F.sequence(F.col("before"), F.col("before") + F.col("slots") - 1)).alias("n"))
    cycle = F.floor(F.col("n") / F.col("blocks"))
    place = shuffled_index(F.pmod("n", "blocks"), F.col("blocks"), F.lit(seed), F.col("source_key"), cycle)
    chosen = chosen.where(cycle < 3).select("shard", "source_key", F.col("n").alias("slot"), place.alias("block"))

    placed = _offsets(docs_.where("size > 0"), ["source_key"], ["row", "doc_id", "twin"], "size", "at", max(1, math.isqrt(total)))
    first = F.floor(F.col("at") / block)
    last = F.floor((F.col("at") + F.col("size") - 1) / block)
    spans = placed.select("source_key", "doc_id", "row", "twin", "at", "size", F.explode(F.sequence(first, last)).alias("block"))
    lo = F.greatest(F.col("at"), F.col("block") * block)
    hi = F.least(F.col("at") + F.col("size"), (F.col("block") + 1) * block)
    spans = spans.select("source_key", "block", "doc_id", "row", "twin", lo.alias("pos"), (lo - F.col("at")).alias("first_word"), (hi - lo).alias("n_words"))
    return spans.join(chosen, ["source_key", "block"]), docs_, sources


def mixed_sizes(docs: DataFrame, **options) -> DataFrame:
    """doc_id, size, source_size, target, taken for every row; see `mix`."""
    spans, rows, sources = mix(docs, **options)
    taken = spans.groupBy(F.col("doc_id").alias("doc_"), F.col("row").alias("row_"), F.col("twin").alias("twin_")).agg(F.sum("n_words").alias("words_"))
    same = F.col("doc_id").eqNullSafe(F.col("doc_")) & (F.col("row") == F.col("row_")) & (F.col("twin") == F.col("twin_"))
    out = rows.join(taken, same, "left").select("doc_id", "size", F.col("source_key").alias("of_"), F.coalesce("words_", F.lit(0)).cast("long").alias("taken"))
    per = sources.select("source_key", F.col("source_size").cast("long").alias("source_size"), "target")
    if sources.count() <= 10_000:
        per = F.broadcast(per)  # 100 bytes a source
    return out.join(per, F.col("of_") == F.col("source_key")).select("doc_id", "size", "source_size", "target", "taken")


def mixed_blocks(docs: DataFrame, block: int = BLOCK_WORDS, **options) -> DataFrame:
    """The mix itself: shard, slot, source, text: one row a slot, its block's words joined by blanks."""
    spans, _, sources = mix(docs, block=block, **options)
    words = F.regexp_extract_all(F.col("text"), F.lit(WORD), F.lit(0))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text", F.col("doc_id").cast("long")).alias("row"), words.alias("words")).dropDuplicates(["doc_id", "row"])
    same = [spans.row == texts.row, spans.doc_id.eqNullSafe(texts.doc_id)]
    parts = spans.join(texts, same).select("shard", "slot", "source_key", spans.doc_id, spans.row, "pos", F.slice("words", F.col("first_word").cast("int") + 1, F.col("n_words").cast("int")).alias("part"))
    # a block holds at most `block` stretches
    whole = parts.groupBy("shard", "slot", "source_key").agg(F.array_sort(F.collect_list(F.struct("pos", "part"))).alias("parts"))
    return whole.join(sources.select("source_key", "source"), "source_key").select("shard", "slot", "source", F.array_join(F.flatten("parts.part"), " ").alias("text"))

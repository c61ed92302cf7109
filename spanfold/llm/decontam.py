"""Benchmark decontamination by template windows, in DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spanfold.llm.common import written

WINDOW = 8
LEAST_COVER = 0.5
BROADCAST_ROWS = 1_000_000  # windows of the benchmark (20 bytes each) up to which they are broadcast

# Units of measure, as written after numbers.
UNITS = "kilometers|kilometres|kilometer|meters|metres|meter|miles|mile|feet|foot|inches|inch|kilograms|kilogram|grams|gram|pounds|pound|ounces|tons|liters|litres|liter|gallons|hours|hour|minutes|minute|seconds|second|days|day|weeks|week|months|month|years|year|dollars|dollar|cents|euros|euro|degrees|percent|mph|kmh|km|cm|mm|kg|mg|ml|lb|oz|ft|hr|min|sec|°C|°F|%|€|\\$|£|m|g|l|h|s"
# Words that open sentences with a capital and are no names.
OPENERS = "a after all also an and are as at before but by can did do does each every find for from given has have he her his how i if in is it its let many most my no of on one or our she some that the their then there these they this those to two was we were what when where which while who whose why will with you your"
NUM, UNIT, NAME = "\u0001", "\u0002", "\u0003"
# Repeats of groups are possessive: what follows cannot match within them, and giving back, they
# would take a frame of the stack each, which long runs of names or numbers overflow.
# A number does not begin inside a list of numbers, or a long list would be read from each of its places.
_NUMBER = r"(?<![\p{L}\p{N}])(?<!\p{N}[.,:/])[-+]?\p{Sc}?\p{N}++(?:[.,:/]\p{N}++)*+"
_MEASURE = _NUMBER + r"\s?(?:" + UNITS + r")(?![\p{L}\p{N}])"
_TOKEN = r"[\p{L}\p{N}]+|[\x01-\x03]"


def _name_pattern() -> str:
    """Runs of capitalised words, at the start of a text or sentence too, that do not begin with an
    opener. The capital is matched first, since most places have none."""
    rest: dict[str, list[str]] = {}
    for w in OPENERS.split():
        rest.setdefault(w[0].upper(), []).append(w[1:])
    openers = "|".join(f"(?<={c})(?:{'|'.join(sorted(tails, key=len, reverse=True))})" for c, tails in sorted(rest.items()))
    return r"\p{Lu}(?<=(?:^|[\p{L}\p{N},;.!?]\s)\p{Lu})(?!(?:" + openers + r")(?!\p{L}))\p{L}*+(?: \p{Lu}\p{L}*+)*+"


_NAME = _name_pattern()


def template(text: Column) -> Column:
    """Tokens of a text: numbers, units and names (capitalised words but openers) become
    placeholders; other words are lower-cased, and marks between them do not count."""
    clean = F.translate(text, NUM + UNIT + NAME, "   ")
    named = F.regexp_replace(clean, _NAME, NAME)
    typed = F.regexp_replace(F.regexp_replace(named, _MEASURE, f" {NUM} {UNIT} "), _NUMBER, f" {NUM} ")
    typed = F.when(F.regexp_like(clean, F.lit(r"\p{N}")), typed).otherwise(named)
    return F.regexp_extract_all(F.lower(typed), F.lit(_TOKEN), F.lit(0))


def slots(text: Column) -> Column:
    """What the placeholders of `template` stand for, in order: names, then numbers with units."""
    clean = F.translate(text, NUM + UNIT + NAME, "   ")
    return F.regexp_extract_all(clean, F.lit(f"{_NAME}|{_MEASURE}|{_NUMBER}"), F.lit(0))


def kind(slot: Column) -> Column:
    """The placeholder type of a slot's text: name, number, or number with a unit."""
    return F.when(F.regexp_like(slot, F.lit(r"^\p{L}")), "name").when(F.regexp_like(slot, F.lit(r"[^\p{N}]$")), "measure").otherwise("number")


def _before(tokens: Column, at: Column) -> Column:
    """Slots among the tokens before a 0-based place; a unit belongs to its number."""
    return F.size(F.filter(F.slice(tokens, F.lit(1), at), lambda t: t.isin(NUM, NAME)))


def _windows(tokens: Column, size: int) -> Column:
    """Hash of each run of `size` tokens; a shorter text is one window of all its tokens."""
    starts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.size(tokens) - size + 1))
    hashes = F.transform(starts, lambda i: F.xxhash64(F.slice(tokens, i, size)))
    return F.when(F.size(tokens) > 0, hashes).otherwise(F.array().cast("array<bigint>"))


def _all_windows(tokens: Column, size: int, short: list[int]) -> Column:
    """Windows of `size` tokens, and those of each shorter length that a benchmark item has."""
    full = _windows(tokens, size)
    if not short:
        return full
    more = [F.when(F.size(tokens) > n, _windows(tokens, n)).otherwise(F.array().cast("array<bigint>")) for n in short]
    return F.array_distinct(F.concat(full, *more))


def contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, least: float = LEAST_COVER) -> DataFrame:
    """(doc_id, item_id, n_windows, coverage, n_slots, slot_match, same_slots): one row for each
    document and benchmark item whose template windows it holds to the share `least`. An item
    shorter than a window is one window of its own length, looked for in documents of any length.

    Templates are compared, so an item whose numbers, units or names were changed matches as well.
    For such pairs the document's stretch is read again: a matching window's place tells which of
    the document's slots stand for the item's. slot_match is the share of pairs of values, item's
    and document's, in which the item's value keeps to one value of its type (1 when there are no
    slots), the best of the stretches where the item was found; a pair whose slots contradict each
    other (below one half) is dropped. same_slots: no slot value changed; an item without a word beside its slots matches only so, since its template would
    match any number or name. Null and empty texts match nothing, null doc_id or item_id rows
    are skipped, repeated rows count once; only doc_id, text and item_id, text are read. Whole texts
    are read, however long; an empty table of either kind gives no row.

    Plan: windows are hashed inside the scan; the benchmark's windows are broadcast when counted
    below a bound and joined by hash otherwise; equal windows of a document combine first.
    """
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("item_text")).where("item_id is not null")
    bench = items.select("item_id", template(F.col("item_text")).alias("tokens"))
    held = F.struct(F.size("tokens").alias("n"), F.exists("tokens", lambda t: ~t.isin(NUM, UNIT, NAME)).alias("worded"))
    bench = bench.select("item_id", held.alias("held"), F.explode(F.array_distinct(_windows(F.col("tokens"), window))).alias("h")).select("item_id", "held.*", "h").distinct()
    sizes = bench.groupBy("item_id").agg(F.count("*").alias("of"))
    bench = written(bench.join(sizes, "item_id"), "benchmark-windows")
    small = bench.count() <= BROADCAST_ROWS
    short = sorted(r.n for r in bench.where(F.col("n") < window).select("n").distinct().collect())  # window - 1 lengths at most
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("doc_id is not null and text is not null")
    # tokens are a column of their own: inside the window function they would be made anew each time
    seen = texts.select("doc_id", template(F.col("text")).alias("tokens")).select("doc_id", F.explode(_all_windows(F.col("tokens"), window, short)).alias("h"))
    keys = bench.select("h").distinct()
    hits = seen.join(F.broadcast(keys) if small else keys, "h").distinct()
    hits = written(hits, "window-hits")
    # a window common to many documents and items meets the items in parts of its documents
    pairs = hits.join(F.broadcast(bench) if small else bench, "h").groupBy("doc_id", "item_id").agg(F.count("*").alias("n_windows"), (F.count("*") / F.max("of")).alias("coverage"), F.max("worded").alias("worded"))
    pairs = written(pairs.where(F.col("coverage") >= least), "leaks")
    # where in the document an item's windows lie says which slots of the document stand for its own
    asked = items.select("item_id", template(F.col("item_text")).alias("item_tokens"), slots(F.col("item_text")).alias("item_slots")).where("size(item_slots) > 0").distinct()
    doubtful = pairs.join(asked.select("item_id").distinct(), "item_id").select("doc_id", "item_id")
    there = texts.join(doubtful.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", template(F.col("text")).alias("tokens"), slots(F.col("text")).alias("doc_slots")).distinct()
    there = written(there, "leaking-texts")

    def spots(rows, tokens, name):
        """Windows of every size in use, each with its place."""
        parts = [rows.where(F.size(tokens) >= n).select("*", F.posexplode(_windows(F.col(tokens), n)).alias(name, "h")) for n in [window, *short]]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out

    mine = spots(asked, "item_tokens", "wi").where(F.size("item_tokens") >= 1).select("item_id", "wi", "h", _before(F.col("item_tokens"), F.col("wi")).alias("bi"))
    mine = mine.join(bench.select("item_id", "h").distinct(), ["item_id", "h"])
    yours = spots(there.select(F.xxhash64("tokens").alias("tk"), "doc_id", "tokens"), "tokens", "wd").select("doc_id", "tk", "wd", "h")
    met = yours.join(doubtful, "doc_id").join(mine, ["item_id", "h"])
    # one place of each alignment is enough: all its windows say the same
    met = met.groupBy("doc_id", "tk", "item_id", (F.col("wd") - F.col("wi")).alias("off")).agg(F.min(F.struct("wd", "bi")).alias("m"))
    placed = met.join(there.withColumn("tk", F.xxhash64("tokens")), ["doc_id", "tk"]).join(asked, "item_id")
    shift = _before(F.col("tokens"), F.col("m.wd")) - F.col("m.bi")
    n_item = F.size("item_slots")
    placed = placed.withColumn("shift", shift).withColumn("here", F.slice("item_slots", F.greatest(F.lit(0), -F.col("shift")) + 1, n_item)).withColumn("part", F.slice("doc_slots", F.greatest(F.lit(0), F.col("shift")) + 1, F.size("here")))
    both = F.arrays_zip(F.slice("here", F.lit(1), F.size("part")).alias("i"), F.col("part").alias("d"))
    placed = placed.withColumn("both", F.array_distinct(F.transform(both, lambda x: F.struct(x["i"].alias("i"), x["d"].alias("d"), (kind(x["i"]) == kind(x["d"])).alias("typed")))))
    # an item's value should stand for one value of its type wherever it recurs
    agreed = F.size(F.array_distinct(F.transform(F.filter("both", lambda x: x["typed"]), lambda x: x["i"])))
    match = F.when(F.size("both") > 0, agreed / F.size("both")).otherwise(F.lit(0.0))
    same = F.col("part") == F.col("item_slots")
    checked = placed.groupBy("doc_id", "item_id").agg(F.max(n_item).alias("n_slots"), F.max(match).alias("slot_match"), F.max(same).alias("same"))
    out = pairs.join(checked, ["doc_id", "item_id"], "left").select(
        "doc_id", "item_id", "n_windows", "coverage",
        F.coalesce("n_slots", F.lit(0)).alias("n_slots"), F.coalesce("slot_match", F.lit(1.0)).alias("slot_match"),
        F.coalesce("same", F.lit(True)).alias("same_slots"), "worded",
    )
    return out.where("slot_match >= 0.5 and (worded or same_slots)").drop("worded")

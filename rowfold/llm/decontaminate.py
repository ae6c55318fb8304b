"""Benchmark decontamination by spaced seeds, in DataFrame operations only.

Fixed masks of ones and zeros slide over the tokens; only tokens under a one are
hashed, so a changed token under a zero does not hide an overlap. Hashes of all
masks at all places of the test items are joined with those of the documents; at
the first hit of each stretch the two token runs are laid side by side and the
matching tokens counted, whatever the tokens that differ.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Masks: 1 is hashed, 0 may differ. All start and end with 1.
MASKS = ("11101", "1100101", "101100011")
#: Beside them for items of five or six tokens, where one changed token may lie under every one of the masks above.
SHORT_MASKS, SHORT = ("1101", "1011"), 6
WINDOW, SHARE = 16, 0.8


def tokens(text: Column) -> Column:
    """Lower-case runs of letters and digits, in order; one empty token for a text without any."""
    return F.split(F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+", " ")), " ")


def _seed(toks: Column, at: Column, mask: str) -> Column:
    """Hash of the mask's tokens from place `at`; null where the mask runs over the end (or before the start)."""
    picked = [F.get(toks, at + i) for i, c in enumerate(mask) if c == "1"]
    whole = reduce(lambda a, b: a & b, (p.isNotNull() for p in (picked[0], picked[-1])))
    return F.when(whole, F.xxhash64(F.lit(mask), *picked))


def item_tokens(benchmark: DataFrame) -> DataFrame:
    """(item_id, item_key, item_tokens) of the items that have tokens, without repeats; item_key tells texts of one id apart."""
    items = benchmark.filter("item_id is not null").select("item_id", tokens(F.col("text")).alias("item_tokens"))
    return items.filter(F.get("item_tokens", F.lit(0)) != "").withColumn("item_key", F.xxhash64("item_tokens")).dropDuplicates(["item_id", "item_key"])


def masks_for(sizes: list[int]) -> tuple[str, ...]:
    """The masks that items of these numbers of tokens need; those of fewer than five tokens match as a whole."""
    least = min(map(len, MASKS))
    return MASKS + (SHORT_MASKS if any(least <= n <= SHORT for n in sizes) else ()) + tuple("1" * n for n in sizes if n < least)


def item_seeds(items: DataFrame, masks: tuple[str, ...]) -> DataFrame:
    """(seed, mask, item_id, item_key, bpos, prev): prev is the same mask's hash one place to the left."""
    at = items.select("item_id", "item_key", "item_tokens", F.posexplode("item_tokens").alias("bpos", "t")).drop("t")
    every = F.array(*[
        F.struct(F.lit(k).alias("mask"), _seed(F.col("item_tokens"), F.col("bpos"), m).alias("seed"), F.when(F.col("bpos") > 0, _seed(F.col("item_tokens"), F.col("bpos") - 1, m)).alias("prev"))
        for k, m in enumerate(masks)
    ])
    rows = at.select("item_id", "item_key", F.size("item_tokens").alias("n"), "bpos", F.explode(every).alias("s")).select("item_id", "item_key", "n", "bpos", "s.*").filter("seed is not null")
    least = min(map(len, MASKS))
    own = F.lit(False)
    for k, m in enumerate(masks):
        fits = F.col("n") >= least if m in MASKS else F.col("n").between(least, SHORT) if m in SHORT_MASKS else F.col("n") == len(m)
        own = own | ((F.col("mask") == k) & fits)
    return rows.filter(own).select("seed", "mask", "item_id", "item_key", "bpos", "prev")


def best_window(places: Column, width: Column) -> Column:
    """The most of the sorted places that lie in any window of `width`."""
    return F.array_max(F.transform(places, lambda p, i: F.size(F.filter(F.slice(places, i + 1, width), lambda q: q < p + width))))


def contaminated(docs: DataFrame, benchmark: DataFrame, most_broadcast: int = 2_000_000, most_bytes: int = 64 << 20) -> DataFrame:
    """(doc_id, item_id, matched, width): documents that overlap an item, and the best window of each pair.

    An overlap has at least ceil(0.8 * width) equal tokens in some window of width = min(16, item tokens) places, and
    is found where a mask lies on equal tokens of it. Items with fewer than five tokens must occur whole. Null and
    empty texts and items overlap nothing; null doc_ids and item_ids are left out; further columns are ignored; empty
    tables give no rows. A document overlaps an item if one of the texts under its id overlaps one of the texts under
    the item's: rows that share an id but not a text are held apart, and the pair gets the best of them. Item
    seeds are broadcast up to `most_broadcast` rows and `most_bytes` bytes of items; beyond, hits are found by a shuffled
    join, whose hot seeds the engine splits, and the documents with hits are read again to be verified.

    Places are exploded and hashed within generated code, where a row's token array is only referred to; nothing
    that copies a row may stand between the two, so verification has no higher-order functions before it has left
    the tokens behind.
    """
    items = item_tokens(benchmark)
    sizes = [r["n"] for r in items.select(F.size("item_tokens").alias("n")).filter(F.col("n") <= SHORT).distinct().orderBy("n").collect()]  # at most six numbers
    masks = masks_for(sizes)
    seeds = item_seeds(items, masks)
    size = items.agg(F.coalesce(F.sum(F.octet_length(F.concat_ws(" ", "item_tokens"))), F.lit(0)).alias("b")).first()["b"]
    small = size <= most_bytes and seeds.count() <= most_broadcast
    texts = docs.filter("doc_id is not null").select("doc_id", tokens(F.col("text")).alias("toks"))
    every = F.array(*[F.struct(F.lit(k).alias("mask"), _seed(F.col("toks"), F.col("pos"), m).alias("seed")) for k, m in enumerate(masks)])
    shift = (F.col("pos") - F.col("bpos")).alias("shift")
    key = ["doc_id", "text_key", "item_id", "item_key", "shift"]
    if small:
        at = texts.select("doc_id", "toks", F.posexplode("toks").alias("pos", "t")).drop("t")
        hits = at.select("doc_id", "toks", "pos", F.explode(every).alias("s")).select("doc_id", "toks", "pos", "s.mask", "s.seed").join(F.broadcast(seeds), ["seed", "mask"])
        before = F.when(F.lit(False), F.lit(0).cast("long"))
        for k, m in enumerate(masks):
            before = before.when((F.col("mask") == k) & (F.col("pos") > 0), _seed(F.col("toks"), F.col("pos") - 1, m))
        first = hits.filter(F.col("prev").isNull() | before.isNull() | (before != F.col("prev")))  # of a stretch of hits
        laid = first.select("doc_id", F.xxhash64("toks").alias("text_key"), "item_id", "item_key", "toks", shift).join(F.broadcast(items), ["item_id", "item_key"])
    else:
        texts = texts.withColumn("text_key", F.xxhash64("toks"))
        at = texts.select("doc_id", "text_key", "toks", F.posexplode("toks").alias("pos", "t")).drop("t")
        hits = at.select("doc_id", "text_key", "pos", F.explode(every).alias("s")).select("doc_id", "text_key", "pos", "s.mask", "s.seed").filter("seed is not null").join(seeds.drop("prev"), ["seed", "mask"])
        laid = hits.select("doc_id", "text_key", "item_id", "item_key", shift).distinct().join(texts.dropDuplicates(["doc_id", "text_key"]), ["doc_id", "text_key"]).join(items, ["item_id", "item_key"])
    each = laid.select(*key, "toks", "item_tokens", F.posexplode("item_tokens").alias("i", "want"))
    equal = each.filter(F.get("toks", F.col("shift") + F.col("i")) == F.col("want")).select(*key, "i", F.size("item_tokens").alias("n"))
    runs = equal.groupBy(*key).agg(F.sort_array(F.collect_set("i")).alias("places"), F.max("n").alias("n"))  # at most an item's tokens
    width = F.least(F.lit(WINDOW), F.col("n"))
    found = runs.select("doc_id", "item_id", best_window(F.col("places"), width).cast("long").alias("matched"), width.cast("long").alias("width"))
    found = found.filter(F.col("matched") >= F.when(F.col("width") < min(map(len, MASKS)), F.col("width")).otherwise(F.ceil(F.lit(SHARE) * F.col("width"))))
    return found.groupBy("doc_id", "item_id").agg(F.max("matched").alias("matched"), F.max("width").alias("width"))

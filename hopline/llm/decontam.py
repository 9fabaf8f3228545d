"""Benchmark items inside long documents: size-partitioned MinHash containment search, then exact containment.

Items and documents are sets of distinct five-word shingles (words as in near-duplicate search). An item counts as
contained when at least ``NUMERATOR / DENOMINATOR`` of its shingles occur in the document.

1. Items are partitioned by size (powers of two). One hash orders all shingles, and an item's sketch holds its smallest
   values: floor(0.2 u) + 1 + ``EXTRA`` for the largest size u of its partition. A contained item of n shingles lacks
   at most floor(0.2 n) of them, so at least (sketch length - floor(0.2 n)) >= 1 sketch values occur in the document.
2. A bitmap of all partitions' sketch values (16 bits a value within ``BITS``, so its size is bounded; a fuller one only
   prunes less) tests each shingle of a document inside its row, so only shingles that may be sketch values leave it.
   No second pass over long texts is needed.
3. These meet the sketches in a join. The share of an item's sketch that a document holds estimates the containment;
   pairs whose estimate lies below what step 1 proves go, and no contained item is missed.
4. For the documents that remain all shingles are compared exactly, as text.

Everything is built-in DataFrame functions. Sketches and item shingles are broadcast when they are at most
``BROADCAST_ROWS`` rows and ``BROADCAST_BYTES`` bytes, else joined by shuffle. Hot documents or items need no grouping
wider than (document, item): counts are pre-aggregated within each task.

Defined cases: null or blank texts hold nothing and match nothing; fewer than five words make one shingle of the
whole sequence, which only matches a document with the same whole sequence; rows that share a doc_id (null included)
are judged as one document that holds all their shingles; an item is a pair of item_id (null included) and text, so
repeated items count once; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hopline.session import cut, small_enough

WIDTH, NUMERATOR, DENOMINATOR = 5, 4, 5
BROADCAST_ROWS, BROADCAST_BYTES = 500_000, 64 << 20
EXTRA, BITS = 4, (1 << 12, 1 << 20)
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_BLANKS = r"[ \t\n\x0B\f\r]+"


def words(text: Column) -> Column:
    lowered = F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER)
    return F.filter(F.split(lowered, _BLANKS), lambda w: w != "")


def _per_shingle(w: Column, make) -> Column:
    """``make(words of one shingle)`` for each shingle of the word array ``w``."""
    last = F.greatest(F.size(w) - WIDTH + 1, F.lit(1))
    full = F.transform(F.sequence(F.lit(0), last - 1), lambda k: make([F.get(w, k + j) for j in range(WIDTH)]))
    return F.when(F.size(w) > 0, full).otherwise(F.array().cast(full_type(make)))


def full_type(make) -> str:
    return {hashed: "array<bigint>", spelled: "array<string>"}.get(make, "array<struct<s:string,h:bigint>>")


def hashed(parts: list[Column]) -> Column:
    return F.xxhash64(*parts)


def spelled(parts: list[Column]) -> Column:
    return F.concat_ws(" ", *parts)


def both_ways(parts: list[Column]) -> Column:
    return F.struct(spelled(parts).alias("s"), hashed(parts).alias("h"))


class Bitmap:
    """Which sketch values there are, as a literal array of longs that every row reads; false hits only cost time."""

    def __init__(self, sketch: DataFrame):
        count = sketch.limit(BITS[1]).count()
        self.bits = min(BITS[1], max(BITS[0], 1 << (16 * count).bit_length()))
        word, bit = self.place(F.col("h"))
        one = F.call_function("shiftleft", F.lit(1).cast("long"), "bit")
        filled = sketch.select(word.alias("word"), bit.alias("bit")).groupBy("word").agg(F.bit_or(one).alias("bits"))
        held = {r.word: r.bits for r in filled.collect()}  # at most BITS[1] / 64 rows
        self.words = F.split(F.lit(",".join(str(held.get(k, 0)) for k in range(self.bits // 64))), ",").cast("array<bigint>")

    def place(self, h: Column) -> tuple[Column, Column]:
        at = h.bitwiseAND(F.lit(self.bits - 1))
        return F.shiftright(at, 6).cast("int"), at.bitwiseAND(F.lit(63)).cast("int")

    def holds(self, h: Column) -> Column:
        word, bit = self.place(h)
        return F.call_function("shiftright", F.get(self.words, word), bit).bitwiseAND(1) == 1


def _side(df: DataFrame, size: Column | None = None) -> DataFrame:
    """``df`` marked for broadcasting if it is small in rows and, by ``size``, in bytes."""
    if not small_enough(df, BROADCAST_ROWS):
        return df
    return F.broadcast(df) if size is None or (df.agg(F.sum(size)).first()[0] or 0) <= BROADCAST_BYTES else df


def sketches(sets: DataFrame) -> DataFrame:
    """(item, h, sketched, needed): the sketch values of items (item, hashes), the sketch's length, and how many of its
    values a document that contains the item holds at least."""
    n = F.size("hashes")
    upper = F.pow(F.lit(2), F.ceil(F.log2(n.cast("double"))))
    lacks = lambda x: F.floor(x * (DENOMINATOR - NUMERATOR) / DENOMINATOR).cast("int")
    sized = sets.withColumn("sketched", F.least(lacks(upper) + 1 + EXTRA, n)).withColumn("needed", F.col("sketched") - lacks(n))
    return sized.select("item", "sketched", "needed", F.explode(F.slice(F.array_sort("hashes"), F.lit(1), F.col("sketched"))).alias("h"))


def candidates(docs: DataFrame, sketch: DataFrame) -> DataFrame:
    """(doc_id, item, estimate): pairs whose share of common sketch values allows containment."""
    known = Bitmap(sketch)
    row = docs.select("doc_id", words(F.col("text")).alias("w"))
    low = F.array_distinct(F.filter(_per_shingle(F.col("w"), hashed), known.holds))
    hits = row.select("doc_id", F.explode(low).alias("h")).join(_side(sketch), "h").select("doc_id", "item", "h", "sketched", "needed").distinct()
    share = hits.groupBy("doc_id", "item").agg(F.count("*").alias("hits"), F.min("sketched").alias("sketched"), F.min("needed").alias("needed"))
    return share.where("hits >= needed").select("doc_id", "item", (F.col("hits") / F.col("sketched")).alias("estimate"))


def contained_items(docs: DataFrame, items: DataFrame) -> DataFrame:
    """doc_id, item_id, n_item, n_common, containment for every contained item."""
    spark = docs.sparkSession
    key = F.md5(F.concat_ws("\0", F.coalesce(F.col("item_id").cast("string"), F.lit("")), F.coalesce("text", F.lit(""))))
    item = items.select("item_id", key.alias("item"), words(F.col("text")).alias("w")).dropDuplicates(["item"])
    sets = item.withColumn("x", F.array_distinct(_per_shingle(F.col("w"), both_ways))).where("size(x) > 0")
    sets = cut(sets.select("item_id", "item", "x", F.size("x").cast("long").alias("n_item")), "items")
    sketch = cut(sketches(sets.select("item", F.array_distinct("x.h").alias("hashes"))), "sketch")
    if sketch.isEmpty():
        return spark.createDataFrame([], "doc_id long, item_id long, n_item long, n_common long, containment double")
    found = cut(candidates(docs, sketch), "candidates")
    chosen = found.select(F.col("doc_id").alias("_doc")).distinct()
    held = docs.select("doc_id", "text").join(chosen, F.col("doc_id").eqNullSafe(F.col("_doc")), "left_semi").select("doc_id", words(F.col("text")).alias("w"))
    whole = held.select("doc_id", F.explode(F.array_distinct(_per_shingle(F.col("w"), spelled))).alias("s"))
    parts = sets.select("item", F.explode("x.s").alias("s"))
    named = found.select(F.col("doc_id").alias("_doc"), F.col("item").alias("_item"))
    same = F.col("doc_id").eqNullSafe(F.col("_doc")) & (F.col("item") == F.col("_item"))
    both = whole.join(_side(parts, F.octet_length("s") + 48), "s").join(named, same, "left_semi").select("doc_id", "item", "s").distinct()
    counted = both.groupBy("doc_id", "item").agg(F.count("*").alias("n_common")).join(_side(sets.select("item", "item_id", "n_item")), "item")
    near = counted.where(F.col("n_common") * DENOMINATOR >= F.col("n_item") * NUMERATOR)
    return near.select("doc_id", "item_id", "n_item", "n_common", F.round(F.col("n_common") / F.col("n_item"), 6).alias("containment"))


def keep_clean(docs: DataFrame, items: DataFrame) -> DataFrame:
    """Documents that contain no item. Without a doc_id a row is judged by its own text, not with all others that
    have none."""
    flagged = contained_items(docs.where("doc_id is not null"), items).select(F.col("doc_id").alias("_doc")).distinct()
    nameless = docs.where("doc_id is null")
    if nameless.isEmpty():
        return docs.join(flagged, docs.doc_id == flagged["_doc"], "left_anti")
    key = F.xxhash64("text")
    dirty = contained_items(nameless.select(key.alias("doc_id"), "text"), items).select(F.col("doc_id").alias("_doc")).distinct()
    clean = nameless.join(dirty, key == F.col("_doc"), "left_anti")
    return docs.where("doc_id is not null").join(flagged, F.col("doc_id") == F.col("_doc"), "left_anti").unionByName(clean)

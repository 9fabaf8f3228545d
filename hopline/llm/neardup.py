"""Near duplicates: banded MinHash candidates, sequential Bayesian verification, exact confirmation.

1. Each text becomes its set of distinct five-word shingles. Texts with equal sets form a *class*; from here on one
   row stands for a class, so copies are never paired with each other.
2. Each class gets ``ROWS * BANDS`` MinHash values; classes that agree in a whole band meet in a bucket. At
   similarity 0.85 a pair misses all bands with probability (1 - 0.85^6)^24 < 2e-5, at 0.8 with less than 7e-4.
3. Every bucket first proposes a star (its members against its smallest member), which is linear in its size.
   Proposals go through a sequential test: signatures are compared batch by batch, and a pair is dropped as soon as
   the posterior probability that its similarity reaches the threshold falls below ``MISS``. Survivors are confirmed
   on full shingle sets.
4. What a star can't decide is decided between components only: buckets whose members lie in several components
   compare the members outside the bucket's largest component with all members. Small buckets do so by an equi-join;
   large ones are cut into blocks of at most ``BLOCK`` x ``BLOCK`` members (fewer where their sets exceed
   ``BLOCK_BYTES``) that are compared with numpy, first with each member's best partner only (which joins most
   components and ships signatures alone), then with all surviving partners, confirmed on the spot so that only links
   leave the block: survivors that are no links can number the square of a bucket. For that pass sets come along, each
   as often as a bucket has blocks. No bucket is capped and no pair within a component is compared.
5. Links are closed to components by minimum-label propagation with pointer jumping.

The thin query links at 85/100, the contract of its SQL; the pipeline's stage passes 80/100.

Defined cases: null or blank texts have no shingles, link with nothing and are kept, each its own component; a null
``doc_id`` is never the smallest one; repeated rows share class and component; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hopline.llm.textvec import WordReader, shingle_set
from hopline.operators.components import connected_labels
from hopline.session import cut

BANDS, ROWS, BATCH = 24, 6, 24
HASHES = BANDS * ROWS
WIDTH = 5
NUMERATOR, DENOMINATOR = 85, 100
MISS = 1e-4
LINK = "a binary, b binary"  # classes are named by the 128-bit digest of their set
BLOCK, BLOCK_BYTES, SMALL = 512, 48 << 20, 24
_FACTORS = np.random.default_rng(20240607).integers(1, 2**63, HASHES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def signature(items: np.ndarray) -> np.ndarray:
    """MinHash values (high 32 bits of the least product) of a set of mixed 64-bit fingerprints."""
    low = np.full(HASHES, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(items), 2048):
        np.minimum(low, (items[None, at : at + 2048] * _FACTORS[:, None]).min(axis=1), out=low)
    return (low >> np.uint64(32)).astype(np.uint32)


def least_matches(threshold: float, miss: float = MISS) -> list[int]:
    """For 24, 48, ... compared values: the fewest matches at which P(similarity >= threshold) is still >= miss.

    With a uniform prior the posterior is Beta(m + 1, n - m + 1), whose upper tail is a binomial sum.
    """
    out = []
    for n in range(BATCH, HASHES + 1, BATCH):
        tail = 0.0
        for m in range(n + 1):
            tail += math.comb(n + 1, m) * threshold**m * (1 - threshold) ** (n + 1 - m)
            if tail >= miss:
                out.append(m)
                break
    return out


def survivors(left: np.ndarray, right: np.ndarray, least: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Rows of two aligned signature matrices that pass every batch, and their match counts."""
    alive, count = np.arange(len(left)), np.zeros(len(left), np.int64)
    for k, bound in enumerate(least):
        part = slice(k * BATCH, (k + 1) * BATCH)
        count = count + (left[alive, part] == right[alive, part]).sum(axis=1)
        ok = count >= bound
        alive, count = alive[ok], count[ok]
    return alive, count


def _sketches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    reader = WordReader()
    for batch in batches:
        size, cls, sig, keys = [], [], [], []
        for _, words in reader.texts(batch.column("text")):
            items = shingle_set(words, WIDTH)
            size.append(len(items))
            if len(items) == 0:
                cls.append(None), sig.append(None), keys.append(None)
                continue
            values = signature(items)
            cls.append(hashlib.blake2b(items.tobytes(), digest_size=16).digest())
            sig.append(values.tobytes())
            bands = values.reshape(BANDS, ROWS).tobytes()
            step = ROWS * 4
            keys.append([int.from_bytes(hashlib.blake2b(bands[k * step : (k + 1) * step], digest_size=8, salt=bytes([k])).digest(), "little", signed=True) for k in range(BANDS)])
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), batch.column("text_key"), pa.array(size, pa.int64()), pa.array(cls, pa.binary()), pa.array(sig, pa.binary()), pa.array(keys, pa.list_(pa.int64()))],
            names=["doc_id", "text_key", "n_shingles", "digest", "sig", "bands"],
        )


def _full_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    reader = WordReader()
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            sets = [shingle_set(words, WIDTH).tobytes() for _, words in reader.texts(part.column("text"))]
            yield pa.RecordBatch.from_arrays([part.column("cls"), pa.array(sets, pa.large_binary())], names=["cls", "items"])


def _sequential(threshold: float):
    least = least_matches(threshold)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows == 0:
                continue
            left, right = (np.stack([np.frombuffer(x, np.uint32) for x in batch.column(c).to_pylist()]) for c in ("sig_a", "sig_b"))
            keep, _ = survivors(left, right, least)
            yield pa.RecordBatch.from_arrays([batch.column(c).take(pa.array(keep)) for c in ("a", "b")], names=["a", "b"])

    return run


def _confirm(num: int, den: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            left, right = batch.column("items_a"), batch.column("items_b")
            for k in range(batch.num_rows):
                if _is_link(*(np.frombuffer(side[k].as_buffer(), np.uint64) for side in (left, right)), num, den):
                    keep.append(k)
            index = pa.array(keep, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("a").take(index), batch.column("b").take(index)], names=["a", "b"])

    return run


def _is_link(x: np.ndarray, y: np.ndarray, num: int, den: int) -> bool:
    if len(x) > len(y):
        x, y = y, x
    at = np.searchsorted(y, x)
    at[at == len(y)] = 0
    both = int((y[at] == x).sum()) if len(y) else 0
    return den * both >= num * (len(x) + len(y) - both)


def _blocks(threshold: float, num: int, den: int, best_only: bool):
    """Compares the members outside the largest component (role 0) with a block of members (role 1): each one's best
    partner, or all partners that survive and are confirmed on the full sets, which then come along."""
    least, bands = least_matches(threshold), BANDS

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        first, second = rows[rows.role == 0], rows[rows.role == 1]
        found: list[pd.DataFrame] = []
        if len(first) and len(second):
            matrix = np.stack([np.frombuffer(x, np.uint32) for x in second.sig])
            band = int(second.band.iloc[0])
            grid = matrix.reshape(len(matrix), bands, -1)
            sets = None if best_only else second["items"].to_numpy()
            ids, sizes = second.cls.tolist(), second.n.to_numpy()
            codes = pd.factorize(pd.concat([first.comp, second.comp]))[0]
            mine_in, comps = codes[: len(first)], codes[len(first) :]
            for own_comp, x in zip(mine_in, first.itertuples(index=False), strict=True):
                other = np.flatnonzero((comps != own_comp) & (np.minimum(sizes, x.n) >= threshold * np.maximum(sizes, x.n)))
                if not len(other):
                    continue
                mine = np.frombuffer(x.sig, np.uint32)
                keep, count = survivors(np.broadcast_to(mine, (len(other), len(mine))), matrix[other], least)
                other = other[keep]
                if len(other) and best_only:
                    other = other[[int(np.argmax(count))]]
                elif len(other):  # each pair only in the first band that it shares
                    shared = (grid[other] == mine.reshape(1, bands, -1)).all(axis=2)
                    own = np.frombuffer(x.items, np.uint64)
                    other = other[shared.argmax(axis=1) == band]
                    other = other[[_is_link(own, np.frombuffer(sets[k], np.uint64), num, den) for k in other]] if len(other) else other
                if len(other):
                    found.append(pd.DataFrame([sorted((ids[k], x.cls)) for k in other], columns=["a", "b"]))
        return pd.concat(found) if found else pd.DataFrame({"a": [], "b": []}, dtype=object)

    return run


def text_key(text: Column) -> Column:
    return F.xxhash64(F.coalesce(text, F.lit("\0null")))


class NearDuplicates:
    """One run over a table of documents; see the module's text for the method."""

    def __init__(self, docs: DataFrame, num: int = NUMERATOR, den: int = DENOMINATOR):
        self.num, self.den, self.threshold = num, den, num / den
        self.docs = docs.select("doc_id", "text", text_key(F.col("text")).alias("text_key"))
        sketch = self.docs.mapInArrow(_sketches, "doc_id long, text_key long, n_shingles long, digest binary, sig binary, bands array<long>")
        self.sketch = cut(sketch.withColumnRenamed("digest", "cls"), "sketch")
        filled = self.sketch.where("n_shingles > 0")
        self.classes = cut(filled.groupBy("cls").agg(F.first("n_shingles").alias("n"), F.first("sig").alias("sig"), F.first("bands").alias("bands"), F.min(F.struct("doc_id", "text_key")).alias("doc")), "classes")

    def _buckets(self) -> DataFrame:
        """(bucket, band, cls, n, size, hub) for buckets with several classes."""
        rows = self.classes.select("cls", "n", F.posexplode("bands").alias("band", "bucket"))
        many = rows.groupBy("bucket", "band").agg(F.count("*").alias("size"), F.min("cls").alias("hub")).where("size > 1")
        return cut(rows.join(many, ["bucket", "band"]), "buckets")

    def _links(self, pairs: DataFrame, tested: bool = False) -> DataFrame:
        if not tested:
            sig = self.classes.select("cls", "sig", "n")
            a, b = (sig.select(F.col("cls").alias(c), F.col("sig").alias(f"sig_{c}"), F.col("n").alias(f"n_{c}")) for c in "ab")
            near = pairs.join(a, "a").join(b, "b").where(F.least("n_a", "n_b") * self.den >= F.greatest("n_a", "n_b") * self.num)
            pairs = near.select("a", "b", "sig_a", "sig_b").mapInArrow(_sequential(self.threshold), LINK)
        a, b = (self.items.select(F.col("cls").alias(c), F.col("items").alias(f"items_{c}")) for c in "ab")
        return cut(pairs.join(a, "a").join(b, "b").mapInArrow(_confirm(self.num, self.den), LINK), "links")

    def _mixed(self, buckets: DataFrame, labels: DataFrame) -> tuple[DataFrame, DataFrame]:
        """Members of buckets that hold several components: small buckets, large buckets."""
        member = buckets.select("bucket", "band", "cls", "n", "size").join(labels, "cls", "left").withColumn("comp", F.coalesce("comp", "cls"))
        per = member.groupBy("bucket", "band", "comp").agg(F.count("*").alias("rows"), F.sum("n").alias("items"))
        mixed = per.groupBy("bucket", "band").agg(F.max_by("comp", F.struct("rows", "comp")).alias("main"), F.max("rows").alias("most"), F.sum("rows").alias("all"), F.sum("items").alias("items_all"), F.count("*").alias("comps")).where("comps > 1")
        member = cut(member.join(mixed, ["bucket", "band"]), "mixed")
        return member.where(F.col("size") <= SMALL), member.where(F.col("size") > SMALL)

    def _across(self, large: DataFrame, best_only: bool) -> DataFrame:
        """By blocks of large buckets: the best pair of each member outside, or all confirmed links."""
        row = large.join(self.classes.select("cls", "sig"), "cls")
        row = row if best_only else row.join(self.items, "cls")
        per_row = F.lit(0) if best_only else F.col("items_all") * 8 / F.col("all") / BLOCK_BYTES  # blocks by the bytes of the sets
        rows = F.greatest(F.col("all") - F.col("most"), F.lit(1))
        outside = F.greatest(F.ceil(rows / BLOCK), F.ceil(rows * per_row)).cast("int")
        inside = F.greatest(F.ceil(F.col("all") / BLOCK), F.ceil(F.col("all") * per_row)).cast("int")
        keep = ["bucket", "band", "cls", "comp", "sig", "n", *([] if best_only else ["items"])]
        first = row.where("comp <> main").select(*keep, F.lit(0).alias("role"), F.pmod(F.xxhash64("cls", F.lit(1)), outside).alias("i"), F.explode(F.sequence(F.lit(0), inside - 1)).alias("j"))
        second = row.select(*keep, F.lit(1).alias("role"), F.explode(F.sequence(F.lit(0), outside - 1)).alias("i"), F.pmod(F.xxhash64("cls", F.lit(2)), inside).alias("j"))
        both = first.select(second.columns).unionByName(second).select(*keep, "role", F.col("i").cast("long"), F.col("j").cast("long"))
        return both.groupBy("bucket", "band", "i", "j").applyInPandas(_blocks(self.threshold, self.num, self.den, best_only), LINK).distinct()

    def labels(self) -> DataFrame:
        """(cls, comp) for classes that are linked with another class."""
        buckets = self._buckets()
        wanted = buckets.select("cls").distinct()
        rep = self.classes.join(wanted, "cls", "left_semi").select("cls", F.col("doc.doc_id").alias("doc_id"), "doc.text_key")
        rep = rep.withColumnRenamed("doc_id", "rep_id").withColumnRenamed("text_key", "rep_key")
        docs = self.docs.join(rep, self.docs.doc_id.eqNullSafe(rep.rep_id) & (self.docs.text_key == rep.rep_key))
        self.items = cut(docs.select("cls", "text").mapInArrow(_full_sets, "cls binary, items binary").dropDuplicates(["cls"]), "sets")
        star = buckets.where("cls <> hub").select(F.col("hub").alias("a"), F.col("cls").alias("b")).distinct()
        links = self._links(star)
        labels = connected_labels(links)
        small, large = self._mixed(buckets, labels)
        if hot := not large.isEmpty():
            links = links.unionByName(self._links(self._across(large, best_only=True), tested=True))
            small, large = self._mixed(buckets, connected_labels(links))
        x, y = (small.select("bucket", "band", F.col("cls").alias(c), F.col("comp").alias(f"comp_{c}")) for c in "ab")
        tried = star.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
        pairs = x.join(y, ["bucket", "band"]).where("a < b and comp_a <> comp_b").select("a", "b").distinct().join(tried, ["a", "b"], "left_anti")
        links = links.unionByName(self._links(pairs))
        if hot:
            links = links.unionByName(cut(self._across(large, best_only=False), "links"))
        return connected_labels(links)

    def result(self) -> DataFrame:
        """doc_id, text_key, n_shingles, component_id, kept for every row of the input."""
        labels = self.labels()
        comps = self.classes.select("cls", F.col("doc.doc_id").alias("least")).join(labels, "cls", "left").withColumn("comp", F.coalesce("comp", "cls"))
        least = comps.groupBy("comp").agg(F.min("least").alias("component_id"))
        per = comps.select("cls", "comp").join(least, "comp").select("cls", "component_id")
        out = self.sketch.select("doc_id", "text_key", "n_shingles", "cls").join(per, "cls", "left")
        component = F.when(F.col("n_shingles") == 0, F.col("doc_id")).otherwise(F.col("component_id"))
        return out.select("doc_id", "text_key", "n_shingles", component.alias("component_id")).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def near_duplicates(docs: DataFrame, num: int = NUMERATOR, den: int = DENOMINATOR) -> DataFrame:
    """doc_id, n_shingles, component_id, kept; documents link at ``den * |A and B| >= num * |A or B|``."""
    return NearDuplicates(docs, num, den).result().drop("text_key")


def keep_one(docs: DataFrame, num: int = NUMERATOR, den: int = DENOMINATOR) -> DataFrame:
    """The documents that stay: the smallest id of each component, once; links as in :func:`near_duplicates`."""
    # One exchange of the texts serves both the numbering of repeated rows and the join: the same three plain keys.
    keys = ["id", "no_id", "text_key"]
    named = [F.coalesce("doc_id", F.lit(0)).alias("id"), F.col("doc_id").isNull().alias("no_id")]
    rule = NearDuplicates(docs, num, den).result().where("kept").select(*named, "text_key").distinct()
    keyed = docs.select(F.struct("*").alias("row"), *named, text_key(F.col("text")).alias("text_key"))
    order = Window.partitionBy(*keys).orderBy(F.lit(1))
    return keyed.withColumn("copy", F.row_number().over(order)).where("copy = 1").join(rule, keys, "left_semi").select("row.*")

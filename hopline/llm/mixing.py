"""Temperature mixing of sources: exponentiated token shares, a bisected exponent, budgeted block permutations.

Weights are w_s = T_s^a / sum T^a, where T_s counts a source's tokens (white-space words). The exponent a in [0, 1] is
bisected to meet a target entropy of the weights (nats), or to be the smallest one (the flattest mix) under which no
source repeats more than ``repetition`` times. Each evaluation is one aggregate over the sources for a whole grid of
exponents, so any number of sources works and only sums reach the driver.

The budget of tokens is given, or ``None`` for the least budget under which every document appears (no source is cut
short). Source s gets w_s x budget tokens: whole passes over its documents, then part of one. A pass permutes blocks
of about ``BLOCK_ROWS`` documents (at most ``BLOCKS`` a source, then larger ones, so that the order of a source's blocks
fits one task) by a seeded hash and documents within a block by another; the last pass ends within
one block, at the document that reaches the budget. Only that block's rows are ranked, so a hot source never meets in
one task.

Defined cases: a null source is a source of its own; documents without words carry no tokens and go along with their
block; sources without tokens get weight 0 and one pass; repeated rows (same id and text) share their order value, so they
lie in one block and the last pass takes all or none of them; an empty table gives an empty result; extra columns are carried along by :func:`mix` and ignored by :func:`plan`.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hopline.session import cut

BLOCK_ROWS, BLOCKS, SEED = 1000, 20_000, 20
REPETITION = 2.0
GRID, ROUNDS = 33, 5


def tokens(text: Column) -> Column:
    blank = r"[ \t\n\x0B\f\r]+"
    body = F.regexp_replace(F.coalesce(text, F.lit("")), r"^[ \t\n\x0B\f\r]+|[ \t\n\x0B\f\r]+$", "")
    return F.when(body == "", 0).otherwise(F.size(F.split(body, blank))).cast("long")


def _sums(sources: DataFrame, exponents: list[float]) -> list[tuple[float, float]]:
    """(sum T^a, sum T^a ln T) for each exponent."""
    log = F.log(F.col("tokens").cast("double"))
    row = sources.where("tokens > 0").agg(*[f(F.exp(log * a)) if f is F.sum else F.sum(F.exp(log * a) * log) for a in exponents for f in (F.sum, None)]).first()
    return [(row[2 * k], row[2 * k + 1]) for k in range(len(exponents))]


def solve(sources: DataFrame, repetition: float | None = REPETITION, entropy: float | None = None, budget: float | None = None) -> tuple[float, float]:
    """(exponent, budget). Exactly one of ``repetition`` and ``entropy`` is the target."""
    if (repetition is None) == (entropy is None):
        raise ValueError("give either a repetition limit or a target entropy")
    ends = sources.where("tokens > 0").agg(F.min("tokens"), F.max("tokens"), F.sum("tokens")).first()
    if ends[0] is None:
        return 1.0, 0.0
    low_t, high_t, _ = ends

    def needed(a: float, total: float) -> float:  # least budget with all documents
        return total * high_t ** (1 - a) if budget is None else budget

    def good(a: float, sums: tuple[float, float]) -> bool:  # true from some exponent on
        if entropy is not None:
            return math.log(sums[0]) - a * sums[1] / sums[0] <= entropy
        return needed(a, sums[0]) * low_t ** (a - 1) / sums[0] <= repetition

    lo, hi = 0.0, 1.0
    for _ in range(ROUNDS):
        grid = [lo + (hi - lo) * k / (GRID - 1) for k in range(GRID)]
        first = next((k for k, s in enumerate(_sums(sources, grid)) if good(grid[k], s)), GRID - 1)
        lo, hi = grid[max(first - 1, 0)], grid[first]
        if first == 0:
            break
    return hi, needed(hi, _sums(sources, [hi])[0][0])


def _hash(*columns: str | Column) -> Column:
    return F.xxhash64(*columns, F.lit(SEED))


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.withColumn("_tokens", tokens(F.col("text"))).withColumn("_order", _hash(F.col("doc_id"), F.coalesce("text", F.lit("\0"))))


def _blocks(thin: DataFrame, repetition: float | None, entropy: float | None, budget: float | None) -> DataFrame:
    """(_source, _blocks, _block, passes, cutoff, weight): a row of a block appears ``passes`` times, and once more if
    its order value is at most ``cutoff``."""
    sources = cut(thin.groupBy("_source").agg(F.sum("_tokens").alias("tokens"), F.count("*").alias("rows")), "sources")
    exponent, total = solve(sources, repetition, entropy, budget)
    norm = _sums(sources, [exponent])[0][0] or 1.0
    share = F.when(F.col("tokens") > 0, F.exp(F.log(F.col("tokens").cast("double")) * exponent) / norm).otherwise(F.lit(0.0))
    goal = sources.withColumn("weight", share).withColumn("goal", F.col("weight") * total)
    # Rounded to whole tokens, so that an exact number of passes stays one.
    goal = goal.withColumn("goal", F.round("goal")).withColumn("passes", F.when(F.col("tokens") > 0, F.floor(F.col("goal") / F.col("tokens"))).otherwise(1).cast("int"))
    goal = goal.withColumn("rest", F.col("goal") - F.col("passes") * F.col("tokens")).withColumn("_blocks", F.least(F.ceil(F.col("rows") / BLOCK_ROWS), F.lit(BLOCKS)).cast("int"))
    goal = cut(goal.select("_source", "_blocks", "weight", "passes", "rest"), "goals")
    dealt = thin.join(goal.select("_source", "_blocks"), "_source").withColumn("_block", F.pmod(F.hash("_order"), "_blocks"))
    sums = dealt.groupBy("_source", "_block").agg(F.sum("_tokens").alias("held")).join(goal, "_source")
    turn = Window.partitionBy("_source").orderBy(_hash("_source", "_block", "passes"), "_block")
    ranked = sums.withColumn("before", F.sum("held").over(turn.rowsBetween(Window.unboundedPreceding, -1))).withColumn("before", F.coalesce("before", F.lit(0)))
    ranked = cut(ranked.withColumn("left", F.col("rest") - F.col("before")), "blocks")
    ends = ranked.where("left > 0 and left < held").select("_source", "_block", "left")
    inner = Window.partitionBy("_source", "_block").orderBy("_order").rowsBetween(Window.unboundedPreceding, -1)
    last = dealt.join(ends, ["_source", "_block"]).withColumn("before", F.coalesce(F.sum("_tokens").over(inner), F.lit(0))).where(F.col("before") < F.col("left"))
    edge = last.groupBy("_source", "_block").agg(F.max("_order").alias("edge"))
    whole = F.when((F.col("left") > 0) & (F.col("left") >= F.col("held")), F.lit(2**63 - 1))
    return ranked.join(edge, ["_source", "_block"], "left").select("_source", "_block", "_blocks", "weight", "passes", F.coalesce(whole, "edge").alias("cutoff"))


def _emit(rows: DataFrame, blocks: DataFrame) -> DataFrame:
    """Every row once for each pass that takes it."""
    counts = blocks.select("_source", "_blocks").distinct()
    dealt = rows.join(counts, "_source").withColumn("_block", F.pmod(F.hash("_order"), "_blocks")).drop("_blocks")
    joined = dealt.join(blocks.drop("_blocks"), ["_source", "_block"])
    times = F.col("passes") + F.coalesce((F.col("_order") <= F.col("cutoff")).cast("int"), F.lit(0))
    return joined.withColumn("_times", times).where("_times > 0").withColumn("_pass", F.explode(F.sequence(F.lit(0), F.col("_times") - 1)))


def _with_source(docs: DataFrame) -> DataFrame:
    return docs.withColumn("_source", F.coalesce(F.concat(F.lit("="), "source"), F.lit("")))


def plan(docs: DataFrame, repetition: float | None = REPETITION, entropy: float | None = None, budget: float | None = None) -> DataFrame:
    """doc_id, source, n_tokens, weight, pass, block, turn for every appearance; a source's passes are read in the
    order of (pass, turn)."""
    thin = cut(_with_source(_keyed(docs)).select("doc_id", "source", "_source", "_tokens", "_order"), "thin")
    out = _emit(thin, _blocks(thin, repetition, entropy, budget))
    turn = F.struct(_hash("_source", "_block", "_pass").alias("block_turn"), _hash("_order", "_pass").alias("row_turn"))
    return out.select("doc_id", "source", F.col("_tokens").alias("n_tokens"), F.round("weight", 9).alias("weight"), F.col("_pass").alias("pass"), F.col("_block").alias("block"), turn.block_turn.alias("block_turn"), turn.row_turn.alias("row_turn"))


def mix(docs: DataFrame, repetition: float | None = REPETITION, entropy: float | None = None, budget: float | None = None) -> DataFrame:
    """The documents with all their columns, each as often as the mix asks for."""
    keyed = _with_source(_keyed(docs.select(F.struct("*").alias("row"), "doc_id", "text", "source"))).select("row", "_source", "_tokens", "_order")
    thin = cut(keyed.drop("row"), "thin")
    return _emit(keyed, _blocks(thin, repetition, entropy, budget)).select("row.*")

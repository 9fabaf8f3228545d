"""Balanced label propagation: linked documents move towards their neighbours' shards, counts stay within one row.

Links. Documents with equal texts are linked and form a *unit* that moves as one. Units are linked when they share a
line of at least ``LEAST_LINE`` characters. A line that c units share links all their pairs; each pair weighs
1 / (c - 1), so a common line doesn't drown a rare one. Pairs are never made: a line holds its weight in each shard.

Start. Units of several documents are seated whole: large ones (above 1/64 of a shard, ``LARGE`` a shard at most)
exactly, largest first, the others in turns under the room that is left. Only a unit that no shard can hold whole is
cut, shard after shard. All other documents are dealt by hash into the room that remains.

Rounds. Every line counts its units' weight by shard, every unit adds up the counts of its lines, and wishes for the
shard that gains most over its own. Wishes are admitted per flow (from, to), best gain first, under two quotas: the
documents of units of several must fit into the shard's size, and a shard may exceed its size by ``SLACK`` at most,
counting what leaves it in the same round. Who isn't admitted votes again in the next round. :func:`shard_report`
gives the cut before each round and at the end.

End. Shards above their size (the law ``rows``: counts at most one apart) hand on what exceeds it to shards below
theirs: documents without links first, then single linked ones.

Skew. Lines that many units share are counted with partial aggregates and joined by broadcast (``HOT`` at most), as
are large units; the rest meets by shuffle. Global ranks come from counts per small bucket, running sums over these
counts, and a rank within each bucket. What reaches the driver is bounded: counts per shard, per flow and slice, large
units, and the last ``TAIL`` open units.

Defined cases: null texts equal each other, have size 1 and no lines; repeated rows are rows like any other and take a
slot each; an empty table gives an empty result; extra columns are ignored by :func:`assign` and kept by :func:`shard`.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hopline.session import cut, small_enough

SHARDS, BUCKET = 8, 1500
LARGE, SLICES, TAIL = 64, 1024, 4096
ROUNDS, SLACK = 4, 0.01
LEAST_LINE, HOT, HOT_LEAST, UNIT = 20, 10_000, 500, 1 << 20
COPIES = 1000
LAW = "rows"


def thin_rows(docs: DataFrame) -> DataFrame:
    raw = F.encode("text", "UTF-8")
    lines = F.filter(F.split(F.coalesce("text", F.lit("")), "\n"), lambda x: F.length(x) >= LEAST_LINE)
    keys = F.array_distinct(F.transform(lines, lambda x: F.xxhash64(x)))
    return docs.select("doc_id", (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"), F.crc32(F.coalesce(raw, F.encode(F.lit(""), "UTF-8"))).alias("text_crc32"), F.coalesce(F.md5(raw), F.lit("")).alias("g"), keys.alias("lines"))


def _ranks(rows: DataFrame, key: str, first: str, spread: str, total: int) -> DataFrame:
    """Adds ``rank``: gapless from 0 within ``key``, ordered by ``first``, then by buckets of ``spread``."""
    buckets = max(1, total // BUCKET)
    row = rows.withColumn("_b", F.pmod(F.xxhash64(spread, F.lit(9)), F.lit(buckets)).cast("int"))
    counts = row.groupBy(key, first, "_b").agg(F.count("*").alias("_n"))
    run = Window.partitionBy(key).orderBy(first, "_b").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("_before", F.coalesce(F.sum("_n").over(run), F.lit(0))).drop("_n")
    within = Window.partitionBy(key, first, "_b").orderBy(spread, "u")
    return row.join(counts, [key, first, "_b"]).withColumn("rank", F.col("_before") + F.row_number().over(within) - 1).drop("_b", "_before")


def shard_sizes(total: int, shards: int) -> list[int]:
    return [total // shards + (s < total % shards) for s in range(shards)]


def seat(units: list[tuple[str, int]], room: list[int]) -> list[tuple[str, int, int, int]]:
    """(g, first, last, shard): pieces of units (g, n), largest first; takes from ``room``."""
    pieces = []
    for g, n in sorted(units, key=lambda x: (-x[1], x[0])):
        order = sorted(range(len(room)), key=lambda s: (-room[s], s))
        order = order[:1] if room[order[0]] >= n else order
        at = 0
        for s in order:
            if take := min(room[s], n - at):
                pieces.append((g, at, at + take, s))
                room[s] -= take
                at += take
    return pieces


def settle(units: DataFrame, shards: int, total: int) -> tuple[list[tuple[str, int, int, int]], list[DataFrame], list[int]]:
    """Pieces of the units (g, n > 1) seated on the driver, tables (g, n, shard) of those that found room in turns, and the
    room that is left."""
    room, placed, turn = shard_sizes(total, shards), [], 0
    large = F.col("n") > total / (shards * LARGE)
    plain = lambda rows: [(r.g, r.n) for r in rows.collect()]
    pieces, open_ = seat(plain(units.where(large)), room), units.where(~large)
    while not (last := small_enough(open_, TAIL)):
        choice = [F.when(F.col("n") <= room[s], F.struct(F.xxhash64("g", F.lit(s)).alias("draw"), F.lit(s).alias("s"))) for s in range(shards)]
        goal = F.array_max(F.filter(F.array(*choice), lambda c: c.isNotNull()))["s"]
        wish = cut(open_.withColumn("goal", goal).withColumn("slice", F.pmod(F.xxhash64("g", F.lit(100 + turn)), F.lit(SLICES)).cast("int")), "wishes")
        upto = [0] * shards
        for r in wish.where("goal is not null").groupBy("goal", "slice").agg(F.sum("n").alias("n")).orderBy("goal", "slice").collect():
            if upto[r.goal] >= 0 and r.n <= room[r.goal]:
                room[r.goal] -= r.n
                upto[r.goal] = r.slice + 1
            elif upto[r.goal] >= 0:
                upto[r.goal] = -1 - upto[r.goal]  # closed for this turn
        bound = F.get(F.array(*[F.lit(x if x >= 0 else -1 - x) for x in upto]), F.col("goal"))
        admitted = F.coalesce(F.col("slice") < bound, F.lit(False))
        placed.append(wish.where(admitted).select("g", "n", F.col("goal").alias("shard")))
        open_, turn = wish.where(~admitted).select("g", "n"), turn + 1
        if not any(upto[s] not in (0, -1) for s in range(shards)):  # nobody moved: the largest are seated exactly
            seated = plain(open_.orderBy(F.desc("n"), "g").limit(TAIL))
            pieces += seat(seated, room)
            open_ = cut(open_.join(F.broadcast(open_.sparkSession.createDataFrame([(g,) for g, _ in seated], "g string")), "g", "left_anti"), "open")
    return pieces + (seat(plain(open_), room) if last else []), placed, room


def dealt(room: list[int]) -> Column:
    """A shard for each ``g`` by hash, in proportion to the room."""
    total = max(1, sum(room))
    draw, out = F.pmod(F.xxhash64("g", F.lit(3)), F.lit(1 << 32)), F.lit(len(room) - 1)
    for s in range(len(room) - 2, -1, -1):
        upto = sum(room[: s + 1])
        out = F.when(draw < (upto << 32) // total, F.lit(s)).otherwise(out)
    return out.cast("int")


class Links:
    """(g, n, key): units and the lines that they share with other units; lines of many units apart."""

    def __init__(self, units: DataFrame):
        held = cut(units.select("g", "n", F.explode("lines").alias("key")), "lines")
        shared = cut(held.groupBy("key").agg(F.count("*").alias("c")).where("c > 1"), "shared")
        most = max(HOT_LEAST, (shared.agg(F.sum("c")).first()[0] or 0) // HOT)
        hot = F.broadcast(shared.where(F.col("c") > most))
        weight = F.floor(UNIT / (F.col("c") - 1)).cast("long").alias("weight")
        self.hot = cut(held.join(hot, "key").select("g", "n", "key", weight), "hot")
        cold = held.join(hot.select("key"), "key", "left_anti").join(shared.where(F.col("c") <= most), "key")
        self.cold = cut(cold.select("g", "n", "key", weight), "cold")

    def units(self) -> DataFrame:
        return self.hot.select("g").unionByName(self.cold.select("g")).distinct()

    def labelled(self, state: DataFrame) -> tuple[DataFrame, DataFrame]:
        """Links with each unit's shard: those of lines of many units, the others."""
        return tuple(cut(rows.join(state.select("g", "shard", "movable"), "g"), "labelled") for rows in (self.hot, self.cold))


def counted(labelled: DataFrame, shards: int) -> DataFrame:
    """(key, held): the documents of a line in each shard."""
    held = F.array(*[F.sum(F.when(F.col("shard") == s, F.col("n")).otherwise(0)) for s in range(shards)])
    return labelled.groupBy("key", "weight").agg(held.alias("held"))


def cut_weight(counts: DataFrame) -> tuple[float, float]:
    """Weight of all pairs of documents that share a line, and of those in different shards."""
    all_ = F.aggregate("held", F.lit(0).cast("long"), lambda a, x: a + x).cast("double")
    same = F.aggregate("held", F.lit(0.0), lambda a, x: a + x.cast("double") * x)
    inside = F.aggregate("held", F.lit(0.0), lambda a, x: a + x)
    row = counts.agg(F.sum((all_ * all_ - inside) * F.col("weight")), F.sum((all_ * all_ - same) * F.col("weight"))).first()
    return (row[0] or 0.0) / (2 * UNIT), (row[1] or 0.0) / (2 * UNIT)


def wishes(labelled: tuple[DataFrame, DataFrame], counts: list[DataFrame], shards: int) -> DataFrame:
    """(g, n, shard, goal, gain): the shard whose neighbours outweigh those of the unit's own shard most."""
    sides = [rows.join(F.broadcast(c) if k == 0 else c, ["key", "weight"]) for k, (rows, c) in enumerate(zip(labelled, counts, strict=True))]
    both = sides[0].unionByName(sides[1])
    pull = [F.sum(F.col("weight") * (F.get("held", F.lit(s)) - F.when(F.col("shard") == s, F.col("n")).otherwise(0))).alias(f"pull{s}") for s in range(shards)]
    sums = both.where("movable").groupBy("g", "n", "shard").agg(*pull)
    best = F.array_max(F.array(*[F.struct(F.col(f"pull{s}").alias("pull"), F.xxhash64("g", F.lit(s)).alias("tie"), F.lit(s).alias("s")) for s in range(shards)]))
    own = F.get(F.array(*[F.col(f"pull{s}") for s in range(shards)]), F.col("shard"))
    return sums.select("g", "n", "shard", best.alias("best"), own.alias("own")).select("g", "n", "shard", F.col("best.s").alias("goal"), (F.col("best.pull") - F.col("own")).alias("gain")).where("gain > 0 and goal <> shard")


def admit(flows: dict[tuple, list[tuple[int, int]]], total: list[int], grouped: list[int], size: list[int]) -> dict[tuple, int]:
    """How many leading slices (place, documents) of each flow (from, to, several) move; updates both counts by shard.

    A slice moves alone while its goal has room, else together with the next slice of an opposite flow.
    """
    done = dict.fromkeys(flows, 0)

    def moves(picked: tuple) -> bool:
        change, change_grouped = [0] * len(size), [0] * len(size)
        for f in picked:
            n = flows[f][done[f]][1]
            for s, x in ((f[0], -n), (f[1], n)):
                change[s] += x
                change_grouped[s] += x * f[2]
        ok = all(x <= 0 or total[s] + x <= size[s] * (1 + SLACK) + 1 for s, x in enumerate(change))
        if not ok or not all(x <= 0 or grouped[s] + x <= size[s] for s, x in enumerate(change_grouped)):
            return False
        for s in range(len(size)):
            total[s] += change[s]
            grouped[s] += change_grouped[s]
        for f in picked:
            done[f] += 1
        return True

    while True:
        open_ = sorted((f for f in flows if done[f] < len(flows[f])), key=lambda f: (flows[f][done[f]][0], f))
        if any([done[f] < len(flows[f]) and moves((f,)) for f in open_]):
            continue
        back = [(f, (f[1], f[0], k)) for f in open_ for k in (False, True) if (f[1], f[0], k) in flows]
        if not any([all(done[x] < len(flows[x]) for x in pair) and moves(pair) for pair in back]):
            return done


def propagate(units: DataFrame, state: DataFrame, links: Links, totals: list[int], shards: int, total: int, rounds: int = ROUNDS) -> tuple[DataFrame, list[tuple]]:
    """The state (g, n, shard, movable) after the rounds, and (round, pairs, cut, moved) of each."""
    report, size = [], shard_sizes(total, shards)
    grouped = [0] * shards
    for r in state.where("n > 1").groupBy("shard").agg(F.sum("n").alias("n")).collect():
        grouped[r.shard] = r.n
    for turn in range(rounds + 1):
        labelled = links.labelled(state)
        counts = [cut(counted(rows, shards), "counts") for rows in labelled]
        pairs, torn = cut_weight(counts[0].unionByName(counts[1]))
        if turn == rounds or not torn:
            return state, [*report, (turn, pairs, torn, 0)]
        # Best gain a document first, in powers of two, then by hash: a slice moves whole or not at all.
        place = (F.lit(64) - F.floor(F.log2(F.col("gain") / F.col("n") + 1)).cast("int")) * 16 + F.pmod(F.xxhash64("g", F.lit(200 + turn)), F.lit(16)).cast("int")
        asked = cut(wishes(labelled, counts, shards).select("g", "n", "shard", "goal", (F.col("n") > 1).alias("several"), place.alias("place")), "asked")
        flows: dict[tuple, list] = {}
        for r in asked.groupBy("shard", "goal", "several", "place").agg(F.sum("n").alias("n")).orderBy("place").collect():
            flows.setdefault((r.shard, r.goal, r.several), []).append((r.place, r.n))
        done = admit(flows, totals, grouped, size)
        bounds = [(*f, flows[f][k - 1][0]) for f, k in done.items() if k]
        moved = sum(n for f, k in done.items() for _, n in flows[f][:k])
        report.append((turn, pairs, torn, moved))
        if not moved:
            return state, report
        table = units.sparkSession.createDataFrame(bounds, "shard int, goal int, several boolean, upto int")
        going = asked.join(F.broadcast(table), ["shard", "goal", "several"]).where("place <= upto").select("g", "goal")
        state = cut(state.join(going, "g", "left").withColumn("shard", F.coalesce("goal", "shard")).drop("goal"), "state")
    return state, report


def place_units(rows: DataFrame, shards: int, total: int) -> tuple[DataFrame, list[tuple]]:
    """Adds shard, single (0: document of a unit of several, 1: linked, 2: neither) and spread, which keeps the pieces of a
    text together in ranks; and the report of the rounds."""
    spark = rows.sparkSession
    units = cut(rows.groupBy("g").agg(F.count("*").alias("n"), F.any_value("lines").alias("lines")), "units")
    pieces, placed, room = settle(units.where("n > 1").select("g", "n"), shards, total)
    parts: dict[str, list] = {}
    for g, _, last, s in pieces:
        parts.setdefault(g, []).append((last, s))
    torn = {g: p for g, p in parts.items() if len(p) > 1}
    # A cut unit votes for the shard of its first piece, which is the largest, and doesn't move.
    seated = spark.createDataFrame([(g, p[-1][0], p[0][1], g not in torn) for g, p in parts.items()], "g string, n long, shard int, movable boolean")
    links = Links(units)
    single = links.units().join(units.where("n = 1").select("g", "n"), "g").select("g", "n", dealt(room).alias("shard"), F.lit(True).alias("movable"))
    state = reduce(DataFrame.unionByName, [p.withColumn("movable", F.lit(True)) for p in placed], seated.unionByName(single))
    state = cut(state, "state")
    totals = [size - left for size, left in zip(shard_sizes(total, shards), room, strict=True)]
    loose = units.where("n = 1").groupBy(dealt(room).alias("s")).count().collect()
    for r in loose:
        totals[r.s] += r["count"]
    state, report = propagate(units, state, links, totals, shards, total)
    large = state.join(F.broadcast(seated.select("g")), "g", "left_semi").select("g", F.col("n").alias("seated"), F.when(F.col("movable"), F.col("shard")).otherwise(-1).alias("home"))
    row = rows.drop("lines").join(F.broadcast(large), "g", "left")
    others = state.join(F.broadcast(seated.select("g")), "g", "left_anti").select("g", F.col("n").alias("several"), F.col("shard").alias("goal"))
    # Rows of large units are placed by the broadcast alone, so that no large text meets in one task.
    small = row.where("seated is null").join(others, "g", "left")
    row = small.unionByName(row.where("seated is not null").select("*", F.lit(None).cast("long").alias("several"), F.lit(None).cast("int").alias("goal")))
    n = F.coalesce("seated", "several", F.lit(1))
    row = row.withColumn("single", F.when(n > 1, 0).when(F.col("several").isNotNull(), 1).otherwise(2))
    fine = F.xxhash64("g", F.pmod(F.xxhash64("u"), F.ceil(n / BUCKET)))
    row = row.withColumn("spread", F.when(F.col("single") > 0, F.col("u")).otherwise(fine))
    out = cut(row.withColumn("shard", F.coalesce("home", "goal", dealt(room))).drop("home", "goal", "several", "seated"), "shards")
    if not torn:
        return out, report
    ends = spark.createDataFrame([(g, [x for x, _ in p], [s for _, s in p]) for g, p in torn.items()], "g string, ends array<long>, homes array<int>")
    ranked = _ranks(out.where("shard < 0"), "g", "single", "u", total).join(F.broadcast(ends), "g")
    home = F.get("homes", F.size(F.filter("ends", lambda x: x <= F.col("rank"))))
    rest = ranked.withColumn("shard", home).select(out.columns)
    return cut(out.where("shard >= 0").unionByName(rest), "shards"), report


def assign(rows: DataFrame, shards: int = SHARDS) -> tuple[DataFrame, list[tuple]]:
    """Adds shard and slot to thin rows, whose shard counts then differ by one at most; and the report of the rounds."""
    total = rows.count()
    state, report = place_units(rows.withColumn("u", F.xxhash64("doc_id", "g")), shards, total)
    have = {r.shard: r["count"] for r in state.groupBy("shard").count().collect()}
    size = dict(enumerate(shard_sizes(total, shards)))
    over, gaps, offset = {}, [], 0
    for s in range(shards):
        over[s] = offset
        offset += max(0, have.get(s, 0) - size[s])
    start = 0
    for s in range(shards):
        if (lack := size[s] - have.get(s, 0)) > 0:
            gaps.append((start, s))
            start += lack
    ranked = _ranks(state, "shard", "single", "spread", max(1, total // shards))
    table = lambda values: F.create_map(*[F.lit(x) for s in range(shards) for x in (s, values[s])])[F.col("shard")]
    extra = F.col("rank") - table(size) + table(over)
    moved = F.lit(None).cast("int")
    for first, s in gaps:  # the last gap that begins at or before
        moved = F.when(extra >= first, F.lit(s)).otherwise(moved)
    placed = cut(ranked.withColumn("shard", F.when(F.col("rank") < table(size), F.col("shard")).otherwise(moved).cast("int")).drop("rank"), "placed")
    return _ranks(placed, "shard", "single", "spread", max(1, total // shards)).withColumnRenamed("rank", "slot").drop("single", "spread", "u"), report


def document_shards(docs: DataFrame) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard."""
    out, _ = assign(cut(thin_rows(docs), "rows"))
    return out.select("doc_id", "size", "text_crc32", F.lit(LAW).alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def shard_report(docs: DataFrame) -> DataFrame:
    """(round, pairs, cut, moved): weight of linked pairs, of those across shards before the round, documents it moved."""
    _, report = assign(cut(thin_rows(docs), "rows"))
    return docs.sparkSession.createDataFrame([(t, float(p), float(c), m) for t, p, c, m in report], "round int, pairs double, cut double, moved long")


def shard(docs: DataFrame) -> DataFrame:
    """All columns of the documents, with shard and slot.

    Equal rows are collapsed to one row and a count before texts move, so copies of one row never meet in a task; their
    slots are runs, which are dealt out again in pieces of ``COPIES``.
    """
    keys = ["id", "no_id", "g"]
    named = [F.coalesce("doc_id", F.lit(0)).alias("id"), F.col("doc_id").isNull().alias("no_id")]
    placed, _ = assign(cut(thin_rows(docs), "rows"))
    runs = placed.select(*named, "g", "shard", F.col("slot").cast("long").alias("slot")).groupBy(*keys, "shard").agg(F.min("slot").alias("first"), F.count("*").alias("many"))
    before = Window.partitionBy(*keys).orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    runs = cut(runs.withColumn("lo", F.coalesce(F.sum("many").over(before), F.lit(0))), "runs")
    row = F.struct(*[c for c in docs.columns if c not in ("shard", "slot")])
    digest = F.coalesce(F.md5(F.encode("text", "UTF-8")), F.lit(""))
    same = docs.select(row.alias("row"), *named, digest.alias("g")).groupBy("row", *keys).agg(F.count("*").alias("copies"))
    earlier = Window.partitionBy(*keys).orderBy(F.xxhash64("row"), "row").rowsBetween(Window.unboundedPreceding, -1)
    same = same.withColumn("at", F.coalesce(F.sum("copies").over(earlier), F.lit(0)))
    begin, end = F.greatest("at", "lo"), F.least(F.col("at") + F.col("copies"), F.col("lo") + F.col("many"))
    both = same.join(runs, keys).where(end > begin).select("row", "shard", (F.col("first") + begin - F.col("lo")).alias("slot"), (end - begin).alias("n"))
    each = F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("k")
    out = both.where(F.col("n") <= COPIES)
    if not runs.where(F.col("many") > COPIES).isEmpty():
        piece = F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"(n - 1) div {COPIES}")))
        pieces = both.where(F.col("n") > COPIES).withColumn("piece", piece).withColumn("slot", F.col("slot") + F.col("piece") * COPIES)
        pieces = pieces.withColumn("n", F.least(F.lit(COPIES).cast("long"), F.col("n") - F.col("piece") * COPIES))
        out = out.unionByName(pieces.repartition("slot").drop("piece"))
    return out.select("row", "shard", "slot", each).select("row.*", "shard", (F.col("slot") + F.col("k")).alias("slot"))

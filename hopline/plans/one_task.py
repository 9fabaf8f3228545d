"""Searches and partitions of graphs that fit one task: the same synchronous rounds on arrays.

A round of the distributed form costs a job, whatever the graph's size. Where the arcs and the widest state fit one
task (``ARCS`` and ``CELLS``, checked before), all rounds run in that task, round for round and tie for tie as in the
distributed form, so that results and ledgers are the same. Larger graphs never come here.

Searches that need no ledger are dealt over tasks by their sources (``dealt``), partitions by their repetitions: every
task holds the edges, so only these have to fit (``DEALT`` arcs), and takes so many sources at a time that their state has
at most ``BATCH`` cells. Edges are packed before they are copied (``packed``): a copy then costs bytes and not rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hopline.plans.rounds import Ledger

ARCS, CELLS = 1_000_000, 32_000_000
DEALT, COPIES = 16_000_000, 10_000_000
BATCH, STEP = 2_000_000, 4_000_000
PULL = 32  # an offer that is sent costs as much as so many that are taken in a round of all arcs
PACK = 100_000
NEVER = np.iinfo(np.int64).max


def fits(arcs: int, cells: int) -> bool:
    return arcs <= ARCS and cells <= CELLS


def deals(arcs: int) -> bool:
    """Whether a task may hold the arcs of a search that is dealt over tasks."""
    return arcs <= DEALT


def _tasks(spark: SparkSession, parts: int, edges: int) -> int:
    """Tasks for so many parts of the work, each with a copy of the edges; more copies than cores only of small tables."""
    asked = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return max(1, min(parts, asked, max(spark.sparkContext.defaultParallelism, COPIES // max(1, edges))))


def _together(left: DataFrame, right: DataFrame, run, schema: str) -> DataFrame:
    """Both tables in one task."""
    a, b = (df.withColumn("_task", F.lit(0)).groupBy("_task") for df in (left, right))
    return a.cogroup(b).applyInArrow(run, schema)


def _settled(out: DataFrame, phase: str, ledger: Ledger | None) -> DataFrame:
    """Materialises the rows; rows without a node carry the ledger."""
    out = out.checkpoint()
    if ledger is not None:
        per = out.where("_round is not null").groupBy("_round").agg(F.max("_state"), F.sum("_improved").alias("improved"), F.sum("_offers")).where("improved > 0")
        for r in sorted(per.collect()):
            ledger.note(phase, r[0], r[1], r[2], r[3], 0.0)
    return out.where("_round is null").drop("_round", "_state", "_improved", "_offers")


LEDGER = "_round int, _state long, _improved long, _offers long"


def _ledger_columns(rows: list[tuple], n: int) -> list[pa.Array]:
    """Four columns: null for n rows of results, then one row a round."""
    return [pa.array([None] * n + [r[k] for r in rows], pa.int32() if k == 0 else pa.int64()) for k in range(4)]


def _narrow(t: pa.Table) -> pa.Table:
    """Whole numbers in 32 bits where all of a column fit."""
    for i, name in enumerate(t.column_names):
        if t.schema.types[i] == pa.int64():
            ends = pc.min_max(t[name])
            if t[name].null_count == len(t) or (ends["min"].as_py() >= -(2**31) and ends["max"].as_py() < 2**31):
                t = t.set_column(i, name, t[name].cast(pa.int32()))
    return t


def packed(rows: DataFrame) -> DataFrame:
    """(_rows binary): the rows of whole numbers as they are, up to about PACK of them in a value."""

    def pack(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        t, sink = _narrow(pa.Table.from_batches(parts)).combine_chunks(), pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, t.schema) as out:
            out.write_table(t)
        return pa.RecordBatch.from_pydict({"_rows": pa.array([sink.getvalue().to_pybytes()], pa.binary())})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, many = [], 0
        for b in batches:
            if b.num_rows:
                held, many = [*held, b], many + b.num_rows
            if many >= PACK:
                yield pack(held)
                held, many = [], 0
        if held:
            yield pack(held)

    return rows.mapInArrow(run, "_rows binary")


def _unpacked(values: pa.Array) -> Iterator[pa.Table]:
    for x in values:
        if x.is_valid:
            yield pa.ipc.open_stream(x.as_buffer()).read_all()


def _spread(first: np.ndarray, many: np.ndarray) -> np.ndarray:
    """first, first + 1, ... first + many - 1 for each pair, one after another."""
    if not len(many) or not many.sum():
        return np.zeros(0, np.int64)
    return np.repeat(first - np.concatenate([[0], np.cumsum(many)[:-1]]), many) + np.arange(many.sum())


def search(arcs: DataFrame, seeds: DataFrame, keys: list[str], arc_keys: list[str], hops: int | None, bits: int, phase: str, ledger: Ledger | None) -> DataFrame:
    """``arcs``: arc_keys, u, v, w, _cap (offers to v must lie below, null: none). ``seeds``: keys, v, _radius (null: none).
    Returns keys, v, d, hops."""
    own = [k for k in keys if k not in arc_keys]
    types = {k: seeds.schema[k].dataType.simpleString() for k in keys}

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        a, s = left.to_pandas(), right.to_pandas()
        ends = pd.concat([a[[*arc_keys, "u"]].rename(columns={"u": "x"}), a[[*arc_keys, "v"]].rename(columns={"v": "x"}), s[[*arc_keys, "v"]].rename(columns={"v": "x"})], ignore_index=True)
        node = ends.groupby([*arc_keys, "x"], sort=False).ngroup().to_numpy() if len(ends) else np.zeros(0, np.int64)
        places = ends.assign(node=node).drop_duplicates("node").sort_values("node")
        total, m = len(places), len(a)
        order = np.argsort(node[:m], kind="stable")
        u, v = node[:m][order], node[m : 2 * m][order]
        w, cap = a["w"].to_numpy(np.int64)[order], a["_cap"].fillna(NEVER).to_numpy(np.int64)[order] if a["_cap"].notna().any() else None
        begin = np.searchsorted(u, np.arange(total + 1))
        line = s.groupby(own, sort=False).ngroup().to_numpy() if own and len(s) else np.zeros(len(s), np.int64)
        lines = s.assign(line=line).drop_duplicates("line").sort_values("line")
        radius = lines["_radius"].fillna(NEVER).to_numpy(np.int64) if lines["_radius"].notna().any() else None
        state = np.full(len(lines) * total, NEVER, np.int64)
        fresh = np.unique(line * total + node[2 * m :])
        state[fresh] = 0
        count, log, round_ = len(fresh), [], 0
        while len(fresh) and (hops is None or round_ < hops):
            round_ += 1
            at, key = fresh % total, fresh // total
            many = begin[at + 1] - begin[at]
            arc = _spread(begin[at], many)
            near, base = np.repeat(key, many), np.repeat(state[fresh], many)
            if len(arc) and (w[arc] >= (NEVER - base) >> bits).any():
                raise OverflowError("a distance exceeds the packed state")
            offer = base + (w[arc] << bits) + 1
            ok = np.ones(len(arc), bool)
            if radius is not None:
                ok &= (offer >> bits) <= radius[near]
            if cap is not None:
                ok &= (offer >> bits) < cap[arc]
            goal, offer = (near * total + v[arc])[ok], offer[ok]
            touched = np.unique(goal)
            before = state[touched]
            np.minimum.at(state, goal, offer)
            better = state[touched] < before
            count += int((before[better] == NEVER).sum())
            fresh = touched[better]
            if len(fresh):
                log.append((round_, count, len(fresh), len(goal)))
        held = np.flatnonzero(state != NEVER)
        columns = [lines[k].to_numpy()[held // total] if k in own else places[k].to_numpy()[held % total] for k in keys]
        columns += [places["x"].to_numpy()[held % total], state[held] >> bits, (state[held] & ((1 << bits) - 1)).astype(np.int32)]
        filler = [pa.array([*c.tolist(), *[None] * len(log)]) for c in columns]
        fields = [*keys, "v", "d", "hops"]
        return pa.table(dict(zip([*fields, "_round", "_state", "_improved", "_offers"], [*filler, *_ledger_columns(log, len(held))], strict=True))).cast(_schema(types, keys))

    schema = ", ".join(f"`{k}` {types[k]}" for k in keys) + f", v long, d long, hops int, {LEDGER}"
    return _settled(_together(arcs.select(*arc_keys, "u", "v", "w", "_cap"), seeds.select(*keys, "v", "_radius"), run, schema), phase, ledger)


class Near:
    """The graph's arcs by their tail, as arrays; ``cap`` has what offers to a node must lie below."""

    def __init__(self, u: np.ndarray, v: np.ndarray, w: np.ndarray, others: np.ndarray, bits: int):
        self.ids = np.unique(np.concatenate([u, v, others]))
        a, b = (np.searchsorted(self.ids, x).astype(np.int32) for x in (u, v))
        tail = np.concatenate([a, b])
        order = np.argsort(tail, kind="stable").astype(np.int32)
        self.begin = np.searchsorted(tail, np.arange(len(self.ids) + 1), sorter=order)
        self.most, self.cap, self.bits = int(w.max()) if len(w) else 0, None, bits
        small = w.astype(np.int32) if self.most < 2**31 else w
        self.v, self.w = np.concatenate([b, a])[order], np.concatenate([small, small])[order]
        self.mean = int(w.mean()) + 1 if len(w) else 1
        self.never, self.state, self._long = NEVER, np.zeros(0, np.int64), (None, None)
        self.wide = np.argsort(self.begin[:-1] - self.begin[1:], kind="stable")  # nodes by falling degree

    def batch(self, farthest: int | None = None) -> int:
        """Sources of a batch: twice as many where a cell has two bytes."""
        cells = BATCH if farthest is None or self._kind(farthest)[1] != np.uint16 else 2 * BATCH
        return max(1, cells // max(1, len(self.ids)))

    def _kind(self, farthest: int | None) -> tuple[int, type]:
        """What stands for no value, and a type that holds it and all that count."""
        if farthest is None or (2 * farthest + 2 + min(self.most, farthest + 1)) << self.bits >= 2**32:
            return NEVER, np.int64
        never = (farthest + 1) << self.bits
        return never, np.uint16 if never + (min(self.most, farthest + 1) << self.bits) + 1 < 2**16 else np.uint32

    def _room(self, lines: int, farthest: int | None) -> np.ndarray:
        """A state in which every cell is NEVER or a value beyond all that count, in as few bytes as hold them."""
        never, kind = self._kind(farthest)
        if never != self.never or len(self.state) < lines * len(self.ids) or self.state.dtype != kind:
            self.never, self.state = never, np.full(lines * len(self.ids), never, kind)
        return self.state

    def _pull(self, state: np.ndarray, lines: int, limit: np.ndarray | None, only: np.ndarray | None = None) -> np.ndarray:
        """A round in which every node takes the least of all its neighbours' values; the improved cells. All nodes take their
        j-th neighbour at once. ``only``: which nodes take any."""
        rows = state[: lines * len(self.ids)].reshape(-1, lines)
        wide = self.wide if only is None else self.wide[only[self.wide]]
        best, degree = rows.copy(), np.diff(self.begin)[wide]
        far = (self.never - 1) >> self.bits
        if self._long[0] != (far, self.bits, state.dtype):
            self._long = (far, self.bits, state.dtype), (np.minimum(self.w, far + 1).astype(np.int64) << self.bits).astype(state.dtype) + state.dtype.type(1)
        length = self._long[1]
        got, first = np.full((len(wide), lines), self.never, state.dtype), self.begin[:-1][wide]
        step = max(1, 250_000 // lines)
        offers = np.empty((step, lines), state.dtype)
        for x in range(0, len(wide), step):
            top = degree[x] if len(degree) else 0
            part = got[x : x + step]
            for j, k in enumerate(np.searchsorted(-degree[x : x + step], -np.arange(top))):
                arc = first[x : x + k] + j
                sent = np.take(rows, self.v[arc], axis=0, out=offers[:k], mode="clip")
                sent += length[arc][:, None]
                np.minimum(part[:k], sent, out=part[:k])
        if limit is not None:
            got[got > limit] = self.never
        got[got > self.never] = self.never
        best[wide] = np.minimum(best[wide], got)
        fresh = np.flatnonzero(best.reshape(-1) < state[: best.size])
        state[: best.size] = best.reshape(-1)
        return fresh

    def search(self, starts: np.ndarray, radius: np.ndarray | None, hops: int | None, names: np.ndarray | None = None, wanted: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place of the start, node, packed value) of all that the starts reach in synchronous rounds, of the nodes ``wanted``
        only where given.

        With ``names`` all starts share one line, and the low bits hold the name of the start instead of the hops. Without
        a hop limit the least values of any order are the same, so rows wait until those nearer by a mean weight have gone."""
        total, bits, hop = len(self.ids), self.bits, int(names is None)
        lines = len(starts) if names is None else 1
        whole = hops is not None and self.cap is None and names is None
        reach = [x for x in (int(radius.max()) if radius is not None else None, hops * self.most if hops is not None else None) if x is not None]
        state, never = self._room(lines, min(reach) if whole else None), self.never
        limit = None
        if radius is not None and whole and never != NEVER:
            limit = ((np.minimum(radius, never >> bits).astype(np.int64) << bits) | ((1 << bits) - 1)).clip(max=never).astype(state.dtype)[None, :]
        whole = whole and never != NEVER
        fresh = starts * lines + np.arange(len(starts)) if names is None else starts
        state[fresh] = 0 if names is None else names
        seen, round_, waiting, rest = [fresh], 0, np.unique(fresh), fresh[:0]
        while len(waiting) and (hops is None or round_ < hops):
            round_, fresh = round_ + 1, waiting
            if hops is None:
                value = state[waiting]
                now = value - value.min() < min(self.mean << bits, NEVER)
                fresh, rest = waiting[now], waiting[~now]
            at = fresh // lines
            many = self.begin[at + 1] - self.begin[at]
            upto = np.cumsum(many)
            if whole and upto[-1] > len(self.v) * lines // PULL:
                waiting, seen = self._pull(state, lines, limit, wanted if round_ == hops else None), None
                continue
            held, values, improved = fresh, state[fresh].astype(np.int64), [rest]
            for piece in np.split(np.arange(len(fresh)), np.searchsorted(upto, np.arange(STEP, upto[-1], STEP), "right")):
                if not len(piece) or not many[piece].sum():
                    continue
                arc = _spread(self.begin[at[piece]], many[piece])
                near, base = np.repeat(held[piece] % lines, many[piece]), np.repeat(values[piece], many[piece])
                if self.most >= (NEVER - int(base.max())) >> bits:
                    raise OverflowError("a distance exceeds the packed state")
                head = self.v[arc].astype(np.int64)
                offer, goal = base + (self.w[arc].astype(np.int64) << bits) + hop, head * lines + near
                ok = offer < state[goal]
                if radius is not None:
                    ok &= (offer >> bits) <= radius[near]
                if self.cap is not None:
                    ok &= (offer >> bits) < self.cap[head]
                goal, offer = goal[ok], offer[ok]
                new = state[goal] == never
                np.minimum.at(state, goal, offer.astype(state.dtype))
                improved.append(np.unique(goal))
                if seen is not None:
                    seen.append(np.unique(goal[new]))
            waiting = np.unique(np.concatenate(improved))
        held = np.sort(np.concatenate(seen)) if seen is not None else np.flatnonzero(state[: lines * total] != never)
        values = state[held].astype(np.int64)
        state[held] = never
        if wanted is not None:
            mine = wanted[held // lines]
            held, values = held[mine], values[mine]
        return held % lines, held // lines, values

    def nearest(self, starts: np.ndarray, hops: int | None, radius: int | None) -> tuple[np.ndarray, np.ndarray]:
        """For each node the distance to the nearest of ``starts``, which rise (none: NEVER), and the first such start."""
        hop_bits, self.bits = self.bits, max(1, len(starts).bit_length())
        _, node, value = self.search(starts, None if radius is None else np.array([radius]), hops, np.arange(len(starts)))
        cap, pivot = np.full(len(self.ids), NEVER, np.int64), np.full(len(self.ids), -1, np.int64)
        cap[node], pivot[node] = value >> self.bits, starts[value & ((1 << self.bits) - 1)]
        self.bits = hop_bits
        return cap, pivot


class Chains:
    """A graph without its nodes of two arcs, which lie on chains between the nodes kept: a chain is one edge of ``core``, and
    what its nodes get comes over one of its ends. Rounds then are as many as kept nodes lie on a path."""

    def __init__(self, g: Near, starts: np.ndarray):
        degree = np.diff(g.begin)
        inner = degree == 2
        inner[starts] = False
        at = np.flatnonzero(inner)
        at = at[g.v[g.begin[at]] != g.v[g.begin[at] + 1]]
        inner[:] = False
        inner[at] = True
        self.g, self.inner, self.kept = g, at, np.flatnonzero(~inner)
        self.pays = 2 * len(at) >= len(g.ids) and g.w.sum(dtype=np.float64) * 2.0**g.bits < 2.0**60
        if not self.pays:
            return
        # Every arc's way to the next kept node: ways are joined two by two, so that each round doubles them.
        length, last = (g.w.astype(np.int64) << g.bits) + 1, np.arange(len(g.v), dtype=np.int32)
        onward = np.full(len(g.v), -1, np.int32)
        going = np.flatnonzero(inner[g.v])
        first = g.begin[g.v[going]]
        onward[going] = first + (g.v[first] == np.repeat(np.arange(len(g.ids), dtype=np.int32), degree)[going])
        for _ in range(len(g.v).bit_length()):  # rings without a kept node have no end, and no start reaches them
            if not len(going):
                break
            j = onward[going]
            longer, end, then = length[going] + length[j], last[j], onward[j]
            length[going], last[going], onward[going] = longer, end, then
            going = going[then >= 0]
        end = np.full(len(g.ids), 0, np.int64)
        end[self.kept] = np.arange(len(self.kept))
        lost = np.zeros(len(g.v), bool)
        lost[going] = True
        at = at[~lost[g.begin[at]]]
        self.inner, one, two = at, g.begin[at], g.begin[at] + 1
        self.ends = [(end[g.v[last[x]]], length[x]) for x in (one, two)]
        out = _spread(g.begin[self.kept], degree[self.kept])
        a, b, w = np.repeat(np.arange(len(self.kept)), degree[self.kept]), end[g.v[last[out]]], length[out]
        up = np.flatnonzero(a < b)
        up = up[np.lexsort((w[up], b[up], a[up]))]
        up = up[np.concatenate([[True], (a[up][1:] != a[up][:-1]) | (b[up][1:] != b[up][:-1])])] if len(up) else up
        self.core = Near(a[up], b[up], w[up] - 1, np.arange(len(self.kept)), 0)  # a round adds the one

    def search(self, starts: np.ndarray, wanted: np.ndarray | None) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(place of the start, nodes, packed values) for one start after another; all starts are kept nodes."""
        far, ends, inner = 2**62, self.ends, self.inner
        if wanted is not None:
            mine = wanted[inner]
            inner, ends = inner[mine], [(x[mine], y[mine]) for x, y in ends]
        of = np.searchsorted(self.kept, starts)
        for i in range(0, len(of), self.core.batch()):
            line, node, value = self.core.search(of[i : i + self.core.batch()], None, None)
            order = np.argsort(line, kind="stable")
            line, node, value = line[order], node[order], value[order]
            upto = np.searchsorted(line, np.arange(len(of[i : i + self.core.batch()]) + 1))
            best = np.full(len(self.kept), far, np.int64)
            for j, (a, b) in enumerate(zip(upto[:-1], upto[1:], strict=True)):
                near, own = node[a:b], value[a:b]
                best[near] = own
                between = np.minimum(*(best[x] + y for x, y in ends))
                met = between < far
                best[near] = far
                if wanted is not None:
                    near, own = near[keep := wanted[self.kept[near]]], own[keep]
                yield i + j, np.concatenate([self.kept[near], inner[met]]), np.concatenate([own, between[met]])


def _copied(every: DataFrame, own: DataFrame, tasks: int) -> DataFrame:
    """``every``: _kind, u, v, w, for every task. ``own``: u, w, each for the task of its u."""
    none = [F.lit(None).cast("long").alias(x) for x in "uw"]
    copies = packed(every).select("_rows", *none, F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("_task"))
    mine = own.select(F.lit(None).cast("binary").alias("_rows"), "u", "w", F.pmod(F.xxhash64("u"), F.lit(tasks)).cast("int").alias("_task"))
    return copies.unionByName(mine).repartitionById(tasks, "_task")


def _received(batches: Iterator[pa.RecordBatch]) -> list[np.ndarray]:
    """Kind (3: the task's own), u, v, w of what :func:`_copied` sent, once; nothing where nothing came."""
    least, held, parts = None, [], []
    for t in batches:
        if not t.num_rows:
            continue
        mine = t.filter(t["_rows"].is_null())
        parts.append((np.full(len(mine), 3, np.int8), mine["u"].to_numpy(), np.full(len(mine), -1), mine["w"].fill_null(NEVER).to_numpy()))
        first = pc.min(t["_task"]).as_py()
        if least is None or first < least:  # more than one copy where two tasks' rows came together
            least, held = first, []
        some = t.filter(pc.and_(pc.equal(t["_task"], least), t["_rows"].is_valid()))
        for x in _unpacked(some["_rows"]):
            held.append((x["_kind"].to_numpy().astype(np.int8), *(x[c].to_numpy() if not x[c].null_count else x[c].cast(pa.int64()).fill_null(-1 if c == "v" else NEVER).to_numpy() for c in "uvw")))
    return [np.concatenate(x) for x in zip(*parts, *held, strict=True)]


def dealt(edges: DataFrame, seeds: DataFrame, count: int, hops: int | None, bits: int, prune: DataFrame | None = None, members: DataFrame | None = None, ends: DataFrame | None = None, many: int = 0) -> DataFrame:
    """``edges``: u, v, w. ``seeds``: src, _radius (null: none), ``count`` of them. ``prune``: (v, cap): offers to v must lie
    below the cap. Returns src, v, d, hops, of ``ends`` (v) only where given; with ``members`` (rep, center, v) instead
    (rep, center, far): of each source the greatest distance to a member of its cluster. ``many``: how many edges, if known."""
    clustered, ended = members is not None, ends is not None
    nothing = lambda *names: [F.lit(None).cast("long").alias(x) for x in names]
    every = edges.select(F.lit(0).alias("_kind"), "u", "v", "w")
    if prune is not None:
        every = every.unionByName(prune.select(F.lit(1).alias("_kind"), F.col("v").alias("u"), *nothing("v"), F.col("cap").alias("w")))
    if clustered:
        every = every.unionByName(members.select(F.lit(2).alias("_kind"), F.col("v").alias("u"), F.col("center").alias("v"), F.col("rep").cast("long").alias("w")))
    if ends is not None:
        every = every.unionByName(ends.select(F.lit(4).alias("_kind"), F.col("v").alias("u"), *nothing("v", "w")))
    tasks = _tasks(edges.sparkSession, min(count, max(8, ceil(count / 16))), many)
    rows = _copied(every, seeds.select(F.col("src").alias("u"), F.col("_radius").alias("w")), tasks)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not (got := _received(batches)):
            return
        kind, u, v, w = got
        e, p, c, s, f = (np.flatnonzero(kind == k) for k in range(5))
        g = Near(u[e], v[e], w[e], np.concatenate([u[s], u[p], u[c], u[f]]), bits)
        wanted = None
        if ended:
            wanted = np.zeros(len(g.ids), bool)
            wanted[np.searchsorted(g.ids, u[f])] = True
        if len(p):
            g.cap = np.full(len(g.ids), NEVER, np.int64)
            g.cap[np.searchsorted(g.ids, u[p])] = w[p]
        source, first = np.unique(u[s], return_index=True)
        radius = w[s][first] if (w[s] != NEVER).any() else None
        home = {}
        for rep in np.unique(w[c]):
            home[rep] = np.full(len(g.ids), -1, np.int64)
            mine = c[w[c] == rep]
            home[rep][np.searchsorted(g.ids, u[mine])] = v[mine]
        if hops is None and radius is None and g.cap is None and not clustered:
            chains = Chains(g, starts := np.searchsorted(g.ids, source))
            if chains.pays:
                for i, node, value in chains.search(starts, wanted):
                    yield from _batches(pa.table({"src": np.full(len(node), source[i]), "v": g.ids[node], "d": value >> bits, "hops": (value & ((1 << bits) - 1)).astype(np.int32)}))
                return
            del chains
        step = g.batch(int(radius.max()) if radius is not None and hops is not None and g.cap is None else None)
        for i in range(0, len(source), step):
            starts = np.searchsorted(g.ids, source[i : i + step])
            line, node, value = g.search(starts, radius[i : i + step] if radius is not None else None, hops, wanted=wanted)
            d = value >> bits
            if not clustered:
                yield from _batches(pa.table({"src": source[i + line], "v": g.ids[node], "d": d, "hops": (value & ((1 << bits) - 1)).astype(np.int32)}))
                continue
            for rep, of in home.items():
                far = np.full(len(starts), -1, np.int64)
                same = (of[node] == of[starts][line]) & (of[node] >= 0)
                np.maximum.at(far, line[same], d[same])
                in_one = far >= 0
                yield from _batches(pa.table({"rep": np.full(in_one.sum(), rep, np.int32), "center": of[starts][in_one], "far": far[in_one]}))

    return rows.mapInArrow(run, "rep int, center long, far long" if clustered else "src long, v long, d long, hops int")


def levels(edges: DataFrame, nodes: DataFrame, count: int, many: int, hops: int | None, bits: int, radius: int | None) -> DataFrame:
    """``edges``: u, v, w, ``many`` of them. ``nodes``: id, level, ``count`` of them. (a, b, d, kind): of each node below the top
    level those of its level or above that are nearer than the nearest node above it, and that node; of the top level all pairs.

    One job: a task has all edges and levels, finds each level's nearest nodes above and then searches from its own nodes."""
    tasks = _tasks(edges.sparkSession, min(count, max(8, ceil(count / 16))), many)
    every = edges.select(F.lit(0).alias("_kind"), "u", "v", "w").unionByName(nodes.select(F.lit(1).alias("_kind"), F.col("id").alias("u"), F.lit(None).cast("long").alias("v"), F.col("level").alias("w")))
    rows = _copied(every, nodes.select(F.col("id").alias("u"), F.col("level").alias("w")), tasks)

    def found(g: Near, a: np.ndarray, b: np.ndarray, d: np.ndarray, kind: str) -> list[pa.RecordBatch]:
        return _batches(pa.table({"a": g.ids[a], "b": g.ids[b], "d": d, "kind": pa.array(np.repeat(kind, len(a)), pa.string())}))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not (got := _received(batches)):
            return
        kind, u, v, w = got
        e, p, s = (np.flatnonzero(kind == k) for k in (0, 1, 3))
        g = Near(u[e], v[e], w[e], u[p], bits)
        level = np.zeros(len(g.ids), np.int64)
        level[np.searchsorted(g.ids, u[p])] = w[p]
        own, top = np.searchsorted(g.ids, np.unique(u[s])), level.max(initial=0)
        del got, kind, u, v, w, e, p, s
        for i in np.unique(level[own]):
            mine, wanted, below = own[level[own] == i], level >= i, None
            if i < top:
                cap, pivot = g.nearest(np.flatnonzero(level > i), hops, radius)
                met = mine[cap[mine] != NEVER]
                yield from found(g, met, pivot[met], cap[met], "pivot")
                # Whoever lies on a path to a nearer node is nearer still, so searching below the start's cap loses none.
                below = np.minimum(cap[mine], 2**40 if radius is None else radius + 1) - 1
            elif radius is not None:
                below = np.full(len(mine), radius, np.int64)
            step = g.batch(int(below.max()) if i == top and below is not None and hops is not None else None)
            for x in range(0, len(mine), step):
                starts = mine[x : x + step]
                line, node, value = g.search(starts, below[x : x + step] if below is not None else None, hops, wanted=wanted)
                far = starts[line] != node
                yield from found(g, starts[line[far]], node[far], value[far] >> bits, "top" if i == top else "bunch")

    return rows.mapInArrow(run, "a long, b long, d long, kind string")


def nearest(edges: DataFrame, sources: DataFrame, hops: int | None, radius: int | None) -> DataFrame:
    """(v, cap, pivot): the distance to the nearest of ``sources`` (id) and the smallest such, for all nodes that one reaches:
    one search of all sources, whose offers carry their source."""
    rows = edges.select("u", "v", "w").unionByName(sources.select(F.col("id").alias("u"), F.lit(None).cast("long").alias("v"), F.lit(None).cast("long").alias("w")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [b for b in batches if b.num_rows]
        if not parts:
            return
        t = pa.Table.from_batches(parts)
        source = np.unique(t.filter(t["w"].is_null())["u"].to_numpy()).astype(np.int64)
        u, v, w = (t.filter(t["w"].is_valid())[x].to_numpy().astype(np.int64) for x in "uvw")
        g = Near(u, v, w, source, 1)
        cap, pivot = g.nearest(np.searchsorted(g.ids, source), hops, radius)
        met = np.flatnonzero(cap != NEVER)
        yield from _batches(pa.table({"v": g.ids[met], "cap": cap[met], "pivot": g.ids[pivot[met]]}))

    return rows.repartition(1).mapInArrow(run, "v long, cap long, pivot long")


def labels(edges: DataFrame) -> DataFrame:
    """(id, comp): for every end of ``edges`` the smallest end that it reaches. Trees hang on their smallest node; each round
    hangs the greater root of an edge on the smaller one and flattens all trees."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [b for b in batches if b.num_rows]
        if not parts:
            return
        t = pa.Table.from_batches(parts)
        ids, place = np.unique(np.concatenate([t[x].to_numpy() for x in "uv"]), return_inverse=True)
        a, b = place[: len(t)], place[len(t) :]
        comp = np.arange(len(ids))
        while len(a):
            np.minimum.at(comp, np.maximum(a, b), np.minimum(a, b))
            while not np.array_equal(comp, up := comp[comp]):
                comp = up
            a, b = comp[a], comp[b]
            a, b = a[a != b], b[a != b]
        yield from _batches(pa.table({"id": ids, "comp": ids[comp]}))

    return edges.select("u", "v").repartition(1).mapInArrow(run, "id long, comp long")


def widths(own: DataFrame, bits: int) -> DataFrame:
    """``own``: rep, center, u, v, w, the edges inside clusters. (rep, center, strong): the greatest distance of two members by
    paths inside the cluster; a cluster is a task's work, its members the sources."""

    def run(table: pa.Table) -> pa.Table:
        u, v, w = (table[x].to_numpy().astype(np.int64) for x in "uvw")
        g, most = Near(u, v, w, u[:0], bits), 0
        for i in range(0, len(g.ids), g.batch()):
            _, _, value = g.search(np.arange(i, min(len(g.ids), i + g.batch())), None, None)
            most = max(most, int(value.max() >> bits))
        return pa.table({"rep": table["rep"].slice(0, 1), "center": table["center"].slice(0, 1), "strong": pa.array([most], pa.int64())})

    return own.groupBy("rep", "center").applyInArrow(run, "rep int, center long, strong long")


def spans(edges: DataFrame, members: DataFrame, count: int, bits: int, many: int) -> DataFrame:
    """``edges``: u, v, w, ``many`` of them. ``members``: rep, center, v, strong (none of its cluster's pairs is further apart),
    ``count`` of them. (rep, center, weak): the greatest distance of two members by any path. A way between two members is
    nowhere further than half the width from both, so a cluster's searches keep to the nodes that near."""
    tasks = _tasks(edges.sparkSession, max(8, ceil(count / 10_000)), many)
    none = [F.lit(None).cast("long").alias(x) for x in ("rep", "center", "v", "strong")]
    every = packed(edges.select("u", "v", "w")).select("_rows", *none, F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("_task"))
    own = members.select(F.lit(None).cast("binary").alias("_rows"), F.col("rep").cast("long").alias("rep"), "center", "v", "strong", F.pmod(F.xxhash64("rep", "center"), F.lit(tasks)).cast("int").alias("_task"))
    rows = every.unionByName(own).repartitionById(tasks, "_task")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        least, held, parts = None, [(np.zeros(0, np.int64),) * 3], []
        for t in batches:
            if not t.num_rows:
                continue
            mine = t.filter(t["_rows"].is_null())
            parts.append([mine[x].to_numpy() for x in ("rep", "center", "v", "strong")])
            first = pc.min(t["_task"]).as_py()
            if least is None or first < least:
                least, held = first, held[:1]
            for x in _unpacked(t.filter(pc.and_(pc.equal(t["_task"], least), t["_rows"].is_valid()))["_rows"]):
                held.append(tuple(x[c].to_numpy() for c in "uvw"))
        if not parts:
            return
        rep, center, v, strong = (np.concatenate(x) for x in zip(*parts, strict=True))
        g = Near(*(np.concatenate(x) for x in zip(*held, strict=True)), v, bits)
        del held, parts
        order = np.lexsort((v, center, rep))
        rep, center, strong, node = rep[order], center[order], strong[order], np.searchsorted(g.ids, v[order])
        new = np.flatnonzero(np.concatenate([[True], (rep[1:] != rep[:-1]) | (center[1:] != center[:-1])])) if len(rep) else np.zeros(0, np.int64)
        place, weak = np.full(len(g.ids), -1, np.int64), np.zeros(len(new), np.int64)
        for k, (a, b) in enumerate(zip(new, [*new[1:], len(rep)][: len(new)], strict=True)):
            if strong[a] == 0:
                continue
            _, region, _ = g.search(node[a:b], np.array([strong[a] // 2]), None, np.zeros(b - a, np.int64))
            place[region] = np.arange(len(region))
            degree = g.begin[region + 1] - g.begin[region]
            arc, tail = _spread(g.begin[region], degree), np.repeat(np.arange(len(region)), degree)
            head = place[g.v[arc]]
            once, members = head > tail, place[node[a:b]]
            near = Near(tail[once], head[once], g.w[arc][once], np.arange(len(region)), bits)
            place[region] = -1
            wanted = np.zeros(len(region), bool)
            wanted[members] = True
            for i in range(0, len(members), near.batch()):
                starts = members[i : i + near.batch()]
                _, _, value = near.search(starts, np.full(len(starts), strong[a]), None, wanted=wanted)
                weak[k] = max(weak[k], int(value.max() >> bits))
        yield from _batches(pa.table({"rep": rep[new].astype(np.int32), "center": center[new], "weak": weak}))

    return rows.mapInArrow(run, "rep int, center long, weak long")


def _batches(table: pa.Table) -> list[pa.RecordBatch]:
    return table.to_batches(max_chunksize=100_000)


def _schema(types: dict[str, str], keys: list[str]) -> pa.Schema:
    kinds = {"bigint": pa.int64(), "int": pa.int32(), "string": pa.string()}
    rows = [(k, kinds[types[k]]) for k in keys]
    return pa.schema([*rows, ("v", pa.int64()), ("d", pa.int64()), ("hops", pa.int32()), ("_round", pa.int32()), ("_state", pa.int64()), ("_improved", pa.int64()), ("_offers", pa.int64())])


def partition(arcs: DataFrame, start: DataFrame, reps: int, nodes: int, many: int, fraction: int, phase: str, ledger: Ledger | None) -> DataFrame:
    """``arcs``: from, to, w, what. ``start``: rep, v, key (shift below zero). ``many``: how many edges. Returns rep, v, center,
    dhat, dtree. Repetitions know nothing of each other and are dealt over tasks."""
    tasks = _tasks(arcs.sparkSession, reps, many)
    none = [F.lit(None).cast("long").alias(x) for x in ("rep", "v", "key")]
    every = packed(arcs.select("from", "to", "w", "what")).select("_rows", *none, F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("_task"))
    own = start.select(F.lit(None).cast("binary").alias("_rows"), "rep", "v", "key", F.pmod(F.col("rep"), F.lit(tasks)).cast("int").alias("_task"))
    rows = every.unionByName(own).repartitionById(tasks, "_task")
    cells = reps * nodes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        least, held, parts = None, [(np.zeros(0, np.int32),) * 4], []
        for t in batches:
            if not t.num_rows:
                continue
            mine = t.filter(t["_rows"].is_null())
            parts.append([mine[x].to_numpy() for x in ("rep", "v", "key")])
            first = pc.min(t["_task"]).as_py()
            if least is None or first < least:
                least, held = first, held[:1]
            for x in _unpacked(t.filter(pc.and_(pc.equal(t["_task"], least), t["_rows"].is_valid()))["_rows"]):
                held.append(tuple(x[c].to_numpy() for c in ("from", "to", "w", "what")))
        if not parts:
            return
        rep, at, key = (np.concatenate(x) for x in zip(*parts, strict=True))
        if not len(rep):
            return
        ids = np.unique(at)
        total = len(ids)
        u, v = (np.concatenate([np.searchsorted(ids, x[c]).astype(np.int32) for x in held]) for c in (0, 1))
        w, what = (np.concatenate([x[c] for x in held]) for c in (2, 3))
        del held, parts
        order = np.argsort(u, kind="stable").astype(np.int32)
        begin = np.concatenate([[0], np.cumsum(np.bincount(u, minlength=total))])
        v, w, what = v[order], w[order], what[order]
        del u, order
        for r in np.unique(rep):
            best = np.zeros((4, total), np.int64)  # key, centre, dhat, dtree
            mine = np.searchsorted(ids, at[rep == r])
            best[0, mine], best[1] = key[rep == r], ids
            fresh, log, round_ = np.sort(mine), [], 0
            while len(fresh):
                round_ += 1
                count = begin[fresh + 1] - begin[fresh]
                out, back = _spread(begin[fresh], count), np.repeat(fresh, count)
                units = what[out].astype(np.int64)
                first = best[0, back] + (units << fraction)
                ok = first <= 0
                sent = int(ok.sum())
                ok &= first <= best[0, v[out]]  # others win nowhere
                out, back, units, first = out[ok], back[ok], units[ok], first[ok]
                offer, goal = np.stack([first, best[1, back], best[2, back] + units, best[3, back] + w[out]]), v[out]
                order = np.lexsort((offer[3], offer[2], offer[1], offer[0], goal))
                offer, goal = offer[:, order], goal[order]
                first = np.flatnonzero(np.concatenate([[True], goal[1:] != goal[:-1]])) if len(goal) else np.zeros(0, np.int64)
                offer, goal = offer[:, first], goal[first]
                less, same = np.zeros(len(goal), bool), np.ones(len(goal), bool)
                for k in range(4):
                    less |= same & (offer[k] < best[k, goal])
                    same &= offer[k] == best[k, goal]
                fresh = goal[less]
                best[:, fresh] = offer[:, less]
                log.append((round_, cells, len(fresh), sent))
            none = [pa.nulls(total, pa.int32())] + [pa.nulls(total, pa.int64())] * 3
            names = ["rep", "v", "center", "dhat", "dtree", "_round", "_state", "_improved", "_offers"]
            yield from _batches(pa.table(dict(zip(names, [np.full(total, r), ids, *best[1:], *none], strict=True))))
            if log:
                yield from _batches(pa.table(dict(zip(names, [pa.nulls(len(log), pa.int64())] * 5 + _ledger_columns(log, 0), strict=True))))

    return _settled(rows.mapInArrow(run, f"rep long, v long, center long, dhat long, dtree long, {LEDGER}"), phase, ledger)

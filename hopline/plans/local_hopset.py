"""The sparse hopset inside one small cluster, in two forms that give the same rows.

Nodes are sampled level by level: of a cluster of s nodes, A_{i+1} keeps each node of A_i with probability
s^(-2^i / k). A node of level i gets edges to all nodes of A_i nearer than its nearest node of A_{i+1} (bunch) and to
that node (pivot); the last level becomes a clique (top). Weights are exact distances in the cluster. An empty
sample makes the rest of its level the top.
"""

from __future__ import annotations

import hashlib
import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopline.functions.params import levels
from hopline.functions.rand import u32
from hopline.plans.relax import search

SCHEMA = "rep int, center long, u long, v long, w long, kind string"
ROW = pa.schema([("rep", pa.int32()), ("center", pa.int64()), ("u", pa.int64()), ("v", pa.int64()), ("w", pa.int64()), ("kind", pa.string())])


def _draw(seed: int, level: int, rep: int, center: int, node: int) -> int:
    return int(hashlib.md5(f"{seed}:level{level}:{center}.{rep}:{node}".encode()).hexdigest()[:8], 16)


def _lengths(near: dict[int, list[tuple[int, int]]], start: int) -> dict[int, int]:
    best, heap = {}, [(0, start)]
    while heap:
        d, x = heapq.heappop(heap)
        if x not in best:
            best[x] = d
            for y, w in near.get(x, ()):
                if y not in best:
                    heapq.heappush(heap, (d + w, y))
    return best


def cluster_edges(edges: list[tuple[int, int, int]], rep: int, center: int, k: float, seed: int, clique: bool = False) -> list[tuple[int, int, int, str]]:
    """Shortcut edges (u < v, w, kind) of one cluster given by its induced edges."""
    near: dict[int, list[tuple[int, int]]] = {}
    for u, v, w in edges:
        near.setdefault(u, []).append((v, w))
        near.setdefault(v, []).append((u, w))
    dist = {x: _lengths(near, x) for x in near}
    size, level, out = len(near), sorted(near), {}

    def add(a: int, b: int, kind: str) -> None:
        if a != b and b in dist[a]:
            e = (min(a, b), max(a, b))
            out[e] = min(out.get(e, (dist[a][b], kind)), (dist[a][b], kind))

    for i in range(0 if clique else levels(k)):
        bound = size ** (-(2**i) / k) * 2**32
        upper = [x for x in level if _draw(seed, i, rep, center, x) < int(bound)]
        if not upper:
            break
        for u in set(level).difference(upper):
            pivot = min(((dist[u][x], x) for x in upper if x in dist[u]), default=None)
            for v in level:
                if v in dist[u] and (pivot is None or dist[u][v] < pivot[0]):
                    add(u, v, "bunch")
            if pivot:
                add(u, pivot[1], "pivot")
        level = upper
    for i, a in enumerate(level):
        for b in level[i + 1 :]:
            add(a, b, "clique" if clique else "top")
    return [(u, v, w, kind) for (u, v), (w, kind) in sorted(out.items())]


def recursive_edges(edges: list[tuple[int, int, int]], rep: int, center: int, k: float, seed: int, clique: bool = False, least: int = 6) -> list[tuple[int, int, int, str]]:
    """Shortcut edges of one cluster by recursion: about sqrt s hubs, a clique of hubs, a star in each hub's part, then the
    parts themselves; parts of at most ``least`` nodes become cliques."""
    near: dict[int, list[tuple[int, int]]] = {}
    for u, v, w in edges:
        near.setdefault(u, []).append((v, w))
        near.setdefault(v, []).append((u, w))
    out: dict[tuple[int, int], tuple[int, str]] = {}

    def add(a: int, b: int, d: int, kind: str) -> None:
        e = (min(a, b), max(a, b))
        out[e] = min(out.get(e, (d, kind)), (d, kind))

    def split(nodes: list[int], level: int) -> None:
        inside = set(nodes)
        own = {x: [(y, w) for y, w in near.get(x, ()) if y in inside] for x in nodes}
        hubs = [x for x in nodes if _draw(seed, level, rep, center, x) < 2**32 / len(nodes) ** 0.5]
        if len(nodes) <= least or len(hubs) < 2 or len(hubs) == len(nodes):
            hubs = nodes
        lengths = {h: _lengths(own, h) for h in hubs}
        kind = "inner" if hubs is nodes else "outer"
        for i, a in enumerate(hubs):
            for b in hubs[i + 1 :]:
                if b in lengths[a]:
                    add(a, b, lengths[a][b], kind)
        if hubs is nodes:
            return
        parts: dict[int, list[int]] = {}
        for x in nodes:
            home = min(((lengths[h][x], h) for h in hubs if x in lengths[h]), default=None)
            if home is None:  # cut off from every hub
                continue
            parts.setdefault(home[1], []).append(x)
            if x != home[1]:
                add(x, home[1], home[0], "hub")
        for part in parts.values():
            if 1 < len(part) < len(nodes):
                split(part, level + 1)

    split(sorted(near), 0)
    return [(u, v, w, kind) for (u, v), (w, kind) in sorted(out.items())]


def at_centers(induced: DataFrame, k: float, seed: int, clique: bool = False, make=cluster_edges) -> DataFrame:
    """One task computes a whole small cluster: the paper's shipping of a cluster to its centre is one exchange. Clusters are
    dealt over as many tasks as the session asks for, however few bytes they have, and come to a task as one sorted stream."""
    tasks = int(induced.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def made(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        """The shortcut edges of the whole clusters that the batches hold, in their order."""
        rep, center, u, v, w = (np.concatenate([p[x].to_numpy() for p in parts]) for x in ("rep", "center", "u", "v", "w"))
        first = np.flatnonzero(np.concatenate([[True], (rep[1:] != rep[:-1]) | (center[1:] != center[:-1])]))
        out = []
        for a, b in zip(first.tolist(), [*first[1:].tolist(), len(rep)], strict=True):
            r, c = int(rep[a]), int(center[a])
            edges = list(zip(u[a:b].tolist(), v[a:b].tolist(), w[a:b].tolist(), strict=True))
            out += [(r, c, *e) for e in make(edges, r, c, k, seed, clique)]
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True) if out else [()] * 6, ROW.types, strict=True)], schema=ROW)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for b in batches:
            if not b.num_rows:
                continue
            rep, center = b["rep"].to_numpy(), b["center"].to_numpy()
            last = int(np.flatnonzero((rep != rep[-1]) | (center != center[-1])).max(initial=-1)) + 1  # where its last cluster begins
            if last:
                yield made([*held, b.slice(0, last)])
                held = [b.slice(last)]
            elif held and (held[-1]["rep"][0].as_py(), held[-1]["center"][0].as_py()) != (int(rep[0]), int(center[0])):
                yield made(held)
                held = [b]
            else:
                held.append(b)
        if held:
            yield made(held)

    rows = induced.select("rep", "center", "u", "v", "w").repartition(tasks, "rep", "center").sortWithinPartitions("rep", "center")
    return rows.mapInArrow(run, SCHEMA)


def by_keys(induced: DataFrame, k: float, seed: int, partitions: int, clique: bool = False) -> DataFrame:
    """The same for all clusters at once, as DataFrame operations with (rep, center) as key columns; the way for
    clusters too large for one task."""
    both = induced.select("rep", "center", "u", "v", "w").unionByName(induced.select("rep", "center", F.col("v").alias("u"), F.col("u").alias("v"), "w"))
    both = both.repartition(partitions, "u").persist()
    nodes = both.select("rep", "center", F.col("u").alias("src")).distinct()
    keys = ["rep", "center", "src"]
    started = nodes.withColumn("v", F.col("src"))
    arcs = both.select("rep", "center", "u", "v", "w")
    dist = search(arcs, started, keys, None, partitions, arc_keys=("rep", "center")).select(*keys, "v", "d").checkpoint()
    both.unpersist()
    size = nodes.groupBy("rep", "center").agg(F.count("*").alias("s"))
    level = nodes.join(size, ["rep", "center"]).withColumnRenamed("src", "x").withColumn("i", F.lit(0))
    made, top = [], []
    for i in range(0 if clique else levels(k)):
        draw = u32(seed, f"level{i}", F.concat_ws(".", "center", "rep"), F.col("x"))
        marked = level.withColumn("up", draw < F.floor(F.pow(F.col("s").cast("double"), F.lit(-(2**i) / k)) * F.lit(float(2**32))))
        alive = marked.groupBy("rep", "center").agg(F.max("up").alias("any"))
        marked = marked.join(alive, ["rep", "center"]).checkpoint()
        top.append(marked.where("not any").select("rep", "center", "x"))
        upper, lower = marked.where("up"), marked.where("any and not up")
        to_upper = dist.join(upper.select("rep", "center", F.col("x").alias("v")), ["rep", "center", "v"])
        pivot = to_upper.groupBy(*keys).agg(F.min(F.struct("d", "v")).alias("pivot"))
        low = lower.select("rep", "center", F.col("x").alias("src")).join(pivot, keys, "left")
        same = marked.where("any").select("rep", "center", F.col("x").alias("v"))
        bunch = dist.join(same, ["rep", "center", "v"]).join(low, keys).where("src <> v and (pivot is null or d < pivot.d)")
        made.append(bunch.select("rep", "center", "src", "v", "d", F.lit("bunch").alias("kind")))
        made.append(low.where("pivot is not null").select("rep", "center", "src", F.col("pivot.v").alias("v"), F.col("pivot.d").alias("d"), F.lit("pivot").alias("kind")))
        level = upper.select("rep", "center", "x", "s", "i")
    top.append(level.select("rep", "center", "x"))
    last = top[0]
    for t in top[1:]:
        last = last.unionByName(t)
    ends = last.select("rep", "center", F.col("x").alias("src")).join(dist, keys).join(last.select("rep", "center", F.col("x").alias("v")), ["rep", "center", "v"]).where("src < v")
    made.append(ends.select("rep", "center", "src", "v", "d", F.lit("clique" if clique else "top").alias("kind")))
    rows = made[0]
    for x in made[1:]:
        rows = rows.unionByName(x)
    best = rows.groupBy("rep", "center", F.least("src", "v").alias("u"), F.greatest("src", "v").alias("v")).agg(F.min(F.struct("d", "kind")).alias("best"))
    return best.select("rep", "center", "u", "v", F.col("best.d").alias("w"), "best.kind")

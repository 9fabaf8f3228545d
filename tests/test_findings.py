"""Cases that a review found."""

import random

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as contract
from hopline import model
from hopline.plans import baselines, cover, local_hopset, one_task, relax, verify
from hopline.plans.rounds import Ledger
from hopline.sources import graphs
from tests.test_graph import lengths


def test_range_join_at_powers_of_two(spark, tmp_path):
    prices = [1024.0, 1024.01, 2047.99, 2048.0, 2.0**15, 2.0**19 - 0.01, 2.0**20, 2.0**20 + 0.01, None]
    spark.createDataFrame(list(enumerate(prices)), "o_orderkey long, o_totalprice double").write.parquet(f"{tmp_path}/orders.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW orders AS SELECT * FROM '{tmp_path}/orders.parquet/*.parquet'")
    want = con.execute(contract.oracle_sql()["op_join_range"]).fetchall()
    got = contract.queries()["op_join_range"](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == sorted(want) and len(want) == 6


def _ladder(spark, n=40):
    rows = [(i, i + 1, 1 + i * 7 % 5) for i in range(n)] + [(i, i + 5, 3 + i * 3 % 11) for i in range(n - 4)]
    return rows, model.from_edges(spark.createDataFrame(rows, "u long, v long, w long"))


def _no_rounds(*_, **__):
    raise AssertionError("a job for every round")


def test_searches_dealt_by_source_need_no_round_of_jobs(spark, monkeypatch):
    rows, g = _ladder(spark)
    src = g.nodes.select(F.col("id").alias("src"))
    limited = sorted(map(tuple, relax.hop_limited(g, src, 3).collect()))
    monkeypatch.setattr(one_task, "CELLS", 10)  # the whole state fits no task, some sources at a time do
    monkeypatch.setattr(one_task, "BATCH", 100)
    monkeypatch.setattr(relax, "loop", _no_rounds)
    got = {(r.src, r.v): r.d for r in relax.exact(g.compact(), src).collect()}
    assert got == {(a, b): d for a in range(41) for b, d in lengths(rows, a).items()}
    assert sorted(map(tuple, relax.hop_limited(g.compact(), src, 3).collect())) == limited
    near = relax.ball(g.compact(), src, 6).collect()
    assert {(r.src, r.v): r.d for r in near} == {k: d for k, d in got.items() if d <= 6}


def test_diameters_need_no_round_of_jobs(spark, monkeypatch):
    # A ring of six: the path 0..3 is 3 long inside and in the graph 3; the path 4..0 with weight 9 is nearer outside.
    g = model.from_edges(spark.createDataFrame([(0, 1, 1), (1, 2, 1), (2, 3, 1), (3, 4, 1), (4, 5, 9), (5, 0, 1)], "u long, v long, w long"))
    members = spark.createDataFrame([(0, 0, x) for x in (0, 1, 2, 3)] + [(0, 4, 4), (0, 4, 5), (1, 2, 2)], "rep int, center long, v long")
    monkeypatch.setattr(one_task, "CELLS", 0)
    monkeypatch.setattr(relax, "loop", _no_rounds)
    got = {(r.rep, r.center): (r.strong, r.weak) for r in verify.true_diameters(g.compact(), members).collect()}
    assert got == {(0, 0): (3, 3), (0, 4): (9, 5), (1, 2): (0, 0)}


def test_pipelined_cover_computes_each_repetition_once(spark, monkeypatch):
    _, g = _ladder(spark)
    drawn = []
    real = cover.partition

    def counted(*args, **kwargs):
        out = real(*args, **kwargs)
        drawn.append(out.select("rep").distinct().count())
        return out

    monkeypatch.setattr(cover, "partition", counted)
    one = cover.limited_pairwise(g, 8, 4, reps=3, batch=1).select("rep", "v", "center", "dhat")
    assert drawn == [1, 1, 1]
    assert one.exceptAll(cover.limited_pairwise(g, 8, 4, reps=3).select(one.columns)).isEmpty() and one.count() == 3 * 41


def test_nearest_sources_in_one_search(spark, monkeypatch):
    _, g = _ladder(spark)
    upper = g.nodes.where("id % 7 = 3")
    want = [sorted(map(tuple, baselines._nearest_upper(g, upper, *how).collect())) for how in ((None,), (2,), (None, 5))]
    monkeypatch.setattr(one_task, "CELLS", 0)
    monkeypatch.setattr(relax, "loop", _no_rounds)
    got = [sorted(map(tuple, baselines._nearest_upper(g.compact(), upper, *how).collect())) for how in ((None,), (2,), (None, 5))]
    assert got == want


def test_bucket_sum_reads_part(spark, sf):
    from hopline import queries

    queries.graph(spark, sf, "part_mesh")  # a held graph must not take the table's place
    out = contract.queries()["bucket_sum"](spark, sf)
    assert [f for f in out.inputFiles() if f.endswith("part.parquet")] and out.count() == 3


def test_nearest_vectors_block_by_block(spark, tmp_path, monkeypatch):
    draw = random.Random(3)
    vectors = [[draw.gauss(0, 1) for _ in range(8)] for _ in range(60)]
    rows = [(3 * i, vectors[i % 47 if i < 80 else 5], 0) for i in range(110)]  # pairs of copies and a large group
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    want = con.execute(contract.oracle_sql()["graph_edges_embed_knn"]).fetchall()

    def all_in_one(_):
        raise AssertionError("the whole table in every task")

    monkeypatch.setattr(graphs.F, "broadcast", all_in_one)
    for block in (16_384, 20):
        assert sorted(map(tuple, graphs.embed_knn(spark, str(tmp_path), block=block).edges.collect())) == sorted(want)


def test_nearest_vectors_of_few_and_of_none(spark):
    table = lambda *rows: spark.createDataFrame(list(rows), "vec_id long, e array<double>, norm double")
    assert graphs.nearest_vectors(table((1, [1.0, 0.0], 1.0)), 5).count() == 0
    assert sorted(map(tuple, graphs.nearest_vectors(table((1, [3.0, 4.0], 5.0), (2, [4.0, 3.0], 5.0)), 5).collect())) == [(1, 2, 0.96), (2, 1, 0.96)]
    with pytest.raises(Exception, match="not zero"):
        graphs.nearest_vectors(table((1, [0.0, 0.0], 0.0), (2, [1.0, 0.0], 1.0)), 5).count()


def test_dense_rounds_are_those_of_the_distributed_form(spark, monkeypatch):
    draw = random.Random(5)
    rows = [(a, b, draw.randint(1, 40)) for a in range(30) for b in range(a) if draw.random() < 0.6]
    g = model.from_edges(spark.createDataFrame(rows, "u long, v long, w long"))
    src, some = g.nodes.select(F.col("id").alias("src")), g.nodes.where("id % 4 = 1").select(F.col("id").alias("v"))
    hows = [{"hops": 3}, {"hops": 4, "radius": 25}, {"hops": 3, "ends": some}, {"hops": None, "ends": some}]
    want = [sorted(map(tuple, relax.hop_limited(g, src, **how).collect())) for how in hows]
    monkeypatch.setattr(one_task, "ARCS", 10)  # more arcs than a search with a ledger may have
    monkeypatch.setattr(one_task, "STEP", 50)
    monkeypatch.setattr(relax, "loop", _no_rounds)
    assert [sorted(map(tuple, relax.hop_limited(g.compact(), src, **how).collect())) for how in hows] == want


def test_components_in_one_task(spark, monkeypatch):
    def loops(_):
        raise AssertionError("a job for every round")

    rows = [(i, i + 1 + i % 3, 1) for i in range(0, 90, 3)] + [(200 - i, 201 - i, 1) for i in range(50)] + [(150, 40, 1), (7, 7, 1)]
    g = model.from_edges(spark.createDataFrame(rows, "u long, v long, w long"))
    want = sorted(map(tuple, model.components(g).collect()))
    monkeypatch.setattr(model, "connected_labels", loops)
    assert sorted(map(tuple, model.components(g.compact()).collect())) == want


def test_repetitions_of_a_partition_are_dealt_over_tasks(spark, monkeypatch):
    _, g = _ladder(spark)
    a, b = Ledger(), Ledger()
    want = sorted(map(tuple, cover.partition(g, 0.2, 3, 5, ledger=a).collect()))
    monkeypatch.setattr(one_task, "ARCS", 10)
    monkeypatch.setattr(cover, "loop", _no_rounds)
    assert sorted(map(tuple, cover.partition(g.compact(), 0.2, 3, 5, ledger=b).collect())) == want
    strip = lambda x: [r[:-1] for r in x.rows]
    assert strip(a) == strip(b) and a.rounds() > 1


def test_copies_of_edges_are_packed(spark, monkeypatch):
    _, g = _ladder(spark)
    far = model.from_edges(g.edges.unionByName(spark.createDataFrame([(0, 900, 2**40)], "u long, v long, w long")))  # beyond 32 bits
    src, some = far.nodes.select(F.col("id").alias("src")), far.nodes.where("id % 4 = 1 or id = 900").select(F.col("id").alias("v"))
    hows = [{"hops": 3}, {"hops": None, "radius": 9}, {"hops": None, "ends": some}]
    want = [sorted(map(tuple, relax.hop_limited(far, src, **how).collect())) for how in hows]
    real, moved = one_task.packed, []

    def counted(rows):
        out = real(rows)
        moved.append((rows.count(), out.count(), rows.rdd.getNumPartitions()))
        return out

    monkeypatch.setattr(one_task, "packed", counted)
    for pack in (one_task.PACK, 7):
        monkeypatch.setattr(one_task, "PACK", pack)
        assert [sorted(map(tuple, relax.hop_limited(far.compact(), src, **how).collect())) for how in hows] == want
    assert len(moved) == 6 and all(out <= parts for _, out, parts in moved[:3]) and all(rows > 40 for rows, _, _ in moved)


def test_clusters_come_to_tasks_as_a_stream(spark, monkeypatch):
    from pyspark.sql.group import GroupedData

    def a_group_each(*_):
        raise AssertionError("a call for every cluster")

    monkeypatch.setattr(GroupedData, "applyInPandas", a_group_each)
    draw = random.Random(8)
    clusters = {(r, c): sorted((a, b, draw.randint(1, 9)) for a in range(2 + c % 7) for b in range(a) if a == b + 1 or draw.random() < 0.3) for r in range(2) for c in range(60)}
    rows = [(r, c, b, a, w) for (r, c), es in clusters.items() for a, b, w in es]
    draw.shuffle(rows)
    own = spark.createDataFrame(rows, "rep int, center long, u long, v long, w long")
    for most in ("3", "10000"):  # clusters cut by batches, and many clusters in a batch
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", most)
        for make in (local_hopset.cluster_edges, local_hopset.recursive_edges):
            got = local_hopset.at_centers(own, 2, 42, make=make)
            assert got.rdd.getNumPartitions() == 4
            want = [(r, c, *e) for (r, c), es in clusters.items() for e in make([(b, a, w) for a, b, w in es], r, c, 2, 42, False)]
            assert sorted(map(tuple, got.collect())) == sorted(want)
    spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_approximate_clique_asks_for_centres_only(spark, monkeypatch):
    from hopline.plans import hopset, mssp

    _, g = _ladder(spark)
    big = g.nodes.where("id % 5 = 2").select(F.lit(0).alias("rep"), F.col("id").alias("center"))
    far = {(r.src, r.v): r.d for r in mssp.approx(g.compact(), big.select(F.col("center").alias("src")), 0.5, allow_many=True, hops=9).collect()}
    want = sorted((a, b, d) for (a, b), d in far.items() if a < b and b % 5 == 2)
    real, asked = mssp.hop_limited, []

    def seen(*args, **kwargs):
        asked.append(kwargs.get("ends"))
        return real(*args, **kwargs)

    monkeypatch.setattr(mssp, "hop_limited", seen)
    got = hopset.center_clique(g.compact(), big, 9, weights="approx", eps=0.5)
    assert sorted(map(tuple, got.collect())) == want and len(want) > 3
    assert sorted(r.v for r in asked[0].collect()) == sorted(r.center for r in big.collect())


def test_levels_of_a_hierarchy_in_one_job(spark, monkeypatch):
    draw = random.Random(9)
    rows = [(a, b, draw.randint(1, 30)) for a in range(45) for b in range(a) if draw.random() < 0.12] + [(100, 101, 4), (101, 102, 9)]
    g = model.from_edges(spark.createDataFrame(rows, "u long, v long, w long"), nodes=spark.createDataFrame([(500,)], "id long"))

    def shortcuts(on):
        return [sorted(map(tuple, baselines._edges(baselines._by_levels(on, k, rho, 42, 0, *how)).collect())) for k, rho in ((3, 0.5), (7, 0.5), (7, 0.05)) for how in ((None,), (4, 40))]

    want = shortcuts(g)
    assert {x[4] for x in want[2]} == {"bunch", "pivot", "top"}

    def apart(*_, **__):
        raise AssertionError("a job for every part of a level")

    monkeypatch.setattr(relax, "loop", _no_rounds)
    for name in ("dealt", "nearest"):
        monkeypatch.setattr(one_task, name, apart)
    for pull in (1, 10_000):  # rounds of all arcs throughout, and none
        monkeypatch.setattr(one_task, "PULL", pull, raising=False)
        assert shortcuts(g.compact()) == want


def test_rounds_of_all_arcs_begin_early_and_end_at_wanted_nodes(monkeypatch):
    draw = random.Random(4)
    u, v, w = (np.array(x) for x in zip(*[(a, b, draw.randint(1, 20)) for a in range(80) for b in range(a) if draw.random() < 0.08], strict=True))
    g, wanted, pulled = one_task.Near(u, v, w, np.arange(80), 3), np.arange(80) % 5 == 0, []
    starts, radius = np.array([1]), np.array([60])
    monkeypatch.setattr(one_task, "PULL", 10**-9, raising=False)
    line, node, value = g.search(starts, radius, 4)  # rows sent one by one
    monkeypatch.setattr(one_task, "PULL", 32, raising=False)
    real = g._pull
    monkeypatch.setattr(g, "_pull", lambda *args: pulled.append(args[3]) or real(*args))
    got = g.search(starts, radius, 4, wanted=wanted)
    keep = wanted[node]
    assert [x.tolist() for x in got] == [x[keep].tolist() for x in (line, node, value)] and keep.sum() > 5
    assert len(pulled) >= 3 and pulled[0] is None and pulled[-1] is wanted


def test_scales_join_only_edges_made_since_the_last(spark, monkeypatch):
    _, g = _ladder(spark)
    real, joined = baselines.augment, []

    def seen(graph, made):
        joined.append((graph.m, made.count()))
        return real(graph, made)

    monkeypatch.setattr(baselines, "augment", seen)
    scales, last = baselines.Scales(g.compact(), 0.5, 4), None
    for kappa, rounded, radius, unit in scales:
        row = spark.createDataFrame([(0, 20 + kappa, 10**6, "top")], "a long, b long, d long, kind string")
        scales.add(row, kappa, unit)
        last = rounded.m
    assert len(joined) >= 2 and [x for _, x in joined] == [1] * len(joined)
    assert [m for m, _ in joined] == [g.m + i for i in range(len(joined))] and last >= g.m


def test_sweeps_measure_all_pairs_and_the_widest_hop_limit(spark, sf, monkeypatch):
    from hopline import queries
    from hopline.plans.hopset import HopsetResult
    from hopline.plans.rounds import Ledger

    g, asked = queries.graph(spark, sf, queries.SMALL), []
    none = spark.createDataFrame([], model.HOPSET_SCHEMA)
    monkeypatch.setattr(queries, "built", lambda s, d, name, p: HopsetResult(none, p, p.beta, g, Ledger()))
    monkeypatch.setattr(queries.verify, "effective_hopbound", lambda on, edges, src, eps, t: asked.append((src.distinct().count(), t.count())) or 1)
    rows = queries.QUERIES["hopset_beta_sweep"](spark, sf).collect()
    pairs = model.components(g).groupBy("comp").count().agg(F.sum(F.col("count") * F.col("count"))).first()[0]
    assert [r.value for r in rows] == [4.0, 8.0, 16.0, 32.0]
    assert asked == [(g.n, pairs)] * 4 and pairs > g.n


def test_chains_give_what_rounds_along_them_give():
    for seed in range(60):
        draw = random.Random(seed)
        n = draw.randint(2, 60)
        edges = {(i, i + 1): draw.randint(1, 9) for i in range(n - 1) if draw.random() < 0.9} | {(100, 101): 2, (101, 102): 2, (100, 102): 2}
        edges |= {tuple(sorted(draw.sample(range(n), 2))): draw.randint(1, 20) for _ in range(draw.randint(0, 4))}
        u, v, w = (np.array(x) for x in zip(*[(a, b, c) for (a, b), c in edges.items()], strict=True))
        g = one_task.Near(u, v, w, np.arange(n), 8)
        starts = np.array(sorted(draw.sample(range(n), draw.randint(1, min(4, n)))))
        wanted = np.array([draw.random() < 0.5 for _ in g.ids]) if seed % 2 else None
        want = sorted(zip(*(x.tolist() for x in g.search(starts, None, None, wanted=wanted)), strict=True))
        chains = one_task.Chains(g, starts)
        if chains.pays:
            assert sorted((i, a, b) for i, node, value in chains.search(starts, wanted) for a, b in zip(node.tolist(), value.tolist(), strict=True)) == want
            assert len(chains.kept) + len(chains.inner) + 3 >= len(g.ids)


def test_rounds_on_a_long_path_follow_its_sources(spark, monkeypatch):
    rows = [(i, i + 1, 1 + i % 7) for i in range(300)]
    g = model.from_edges(spark.createDataFrame(rows, "u long, v long, w long")).compact()
    real = one_task._spread

    def few(first, many):
        if len(first) == 1 and many[0] == 2:
            raise AssertionError("a round for every node of the path")
        return real(first, many)

    monkeypatch.setattr(one_task, "_spread", few)
    sources = spark.createDataFrame([(0,), (100,)], "src long")
    got = {(r.src, r.v): (r.d, r.hops) for r in relax.exact(g, sources).collect()}
    upto = np.concatenate([[0], np.cumsum([w for _, _, w in rows])])
    assert got == {(s, v): (abs(int(upto[v] - upto[s])), abs(v - s)) for s in (0, 100) for v in range(301)}


def test_pipelined_repetitions_run_in_tasks(spark, monkeypatch):
    _, g = _ladder(spark)
    want = cover.limited_pairwise(g, 8, 3, 1.0, 3, 42, 1.0)
    want = sorted(map(tuple, want.collect()))
    monkeypatch.setattr(cover, "loop", _no_rounds)
    for batch in (1, 2, None):
        assert sorted(map(tuple, cover.limited_pairwise(g.compact(), 8, 3, 1.0, 3, 42, 1.0, batch=batch).collect())) == want
    assert len({x[1] for x in want}) == 3 and len({x[2] for x in want}) > 3


def test_diameters_of_a_graph_beyond_one_task(spark, monkeypatch):
    _, g = _ladder(spark, 60)
    members = g.nodes.select(F.lit(0).alias("rep"), F.expr("id div 6 * 6").alias("center"), F.col("id").alias("v"))
    want = sorted(map(tuple, verify.true_diameters(g.compact(), members).collect()))
    monkeypatch.setattr(verify, "search", _no_rounds)
    monkeypatch.setattr(one_task, "ARCS", 60)
    assert sorted(map(tuple, verify.true_diameters(g.compact(), members).collect())) == want and len(want) > 8

"""Hand examples, edge cases, and the invariants that stand in for proofs."""

import heapq
import math

import pytest
from pyspark.sql import functions as F

from hopline import model
from hopline.functions.params import Budget, HopsetParams, bounds, check_gamma, check_rho, levels, padding_bound
from hopline.plans import baselines, cover, hopset, local_hopset, mssp, relax, verify
from hopline.plans.rounds import Ledger
from hopline.session import setting
from hopline.streaming.edges import maintain

TOY = [(1, 2, 5), (2, 3, 1), (1, 3, 9), (3, 4, 2)]


def make(spark, rows, nodes=()):
    extra = spark.createDataFrame([(x,) for x in nodes], "id long") if nodes else None
    return model.from_edges(spark.createDataFrame(list(rows), "u long, v long, w long"), nodes=extra)


def sources(spark, *ids):
    return spark.createDataFrame([(i,) for i in ids], "src long")


def lengths(rows, start):
    near = {}
    for u, v, w in rows:
        near.setdefault(u, []).append((v, w)), near.setdefault(v, []).append((u, w))
    best, heap = {}, [(0, start)]
    while heap:
        d, x = heapq.heappop(heap)
        if x not in best:
            best[x] = d
            for y, w in near.get(x, ()):
                heapq.heappush(heap, (d + w, y))
    return best


def grid(side, seed=3):
    import random

    r = random.Random(seed)
    return [(i * side + j, i * side + j + k, r.randint(1, 20)) for i in range(side) for j in range(side) for k in ((1,) if j < side - 1 else ()) + ((side,) if i < side - 1 else ())]


def table(df):
    return {(r.src, r.v): r.d for r in df.collect()}


def test_canonical_form(spark):
    g = make(spark, [(1, 1, 3), (2, 1, 7), (1, 2, 4), (5, 6, 1)], nodes=[9])
    assert sorted(map(tuple, g.edges.collect())) == [(1, 2, 4), (5, 6, 1)]
    assert {r.id for r in g.nodes.collect()} == {1, 2, 5, 6, 9}


def test_bad_weights(spark):
    for w in (0, -1, None):
        with pytest.raises(ValueError):
            make(spark, [(1, 2, w)])


def test_toy_distances(spark):
    g = make(spark, TOY)
    assert {v: d for (_, v), d in table(relax.exact(g, sources(spark, 1))).items()} == {1: 0, 2: 5, 3: 6, 4: 8}
    assert {v: d for (_, v), d in table(relax.hop_limited(g, sources(spark, 1), 1)).items()} == {1: 0, 2: 5, 3: 9}


@pytest.mark.parametrize("rows,nodes", [([], [1]), ([(1, 2, 1)], []), ([(1, 2, 3), (7, 8, 2)], [])])
def test_small_graphs(spark, rows, nodes):
    g = make(spark, rows, nodes)
    assert table(relax.exact(g, sources(spark, 1))) == {(1, v): d for v, d in ({1: 0} | lengths(rows, 1)).items()}
    assert {r.id: r.comp for r in model.components(g).collect()}[1] == 1
    b = hopset.build(g, HopsetParams(beta=1, reps=1, segments=4, ell=3))
    assert verify.sound(g, b.edges).isEmpty()


def test_star_and_path(spark):
    star = [(0, i, i) for i in range(1, 51)]
    path = [(i, i + 1, 1 if i % 2 else 1000) for i in range(64)]
    for rows in (star, path):
        g = make(spark, rows)
        assert table(relax.exact(g, sources(spark, 0))) == {(0, v): d for v, d in lengths(rows, 0).items()}


def test_hops_never_run_into_distances(spark, monkeypatch):
    monkeypatch.setattr(relax, "HOP_BITS", 4)  # stands for a path longer than the field
    rows = [(i, i + 1, 1) for i in range(40)]
    g, start = make(spark, rows), sources(spark, 0)
    assert sorted((r.v, r.d, r.hops) for r in relax.exact(g, start).collect()) == [(i, i, i) for i in range(41)]
    assert table(relax.hop_limited(g, start, 5000)) == {(0, i): i for i in range(41)}
    with pytest.raises(OverflowError):
        relax.search(g.arcs, relax.seeds(start), ["src"], None, g.partitions)
    assert verify.effective_hopbound(g, None, start, 0.0) == 40
    for far in (make(spark, [(1, 2, 2**62)]), make(spark, [(1, 2, 2**62)]).compact()):
        with pytest.raises(Exception, match="exceeds the packed state"):
            relax.exact(far, sources(spark, 1)).collect()


def test_more_rounds_than_twelve_bits_hold(spark):
    g = make(spark, [(i, i + 1, 1) for i in range(5000)]).compact()
    assert sorted((r.v, r.d, r.hops) for r in relax.exact(g, sources(spark, 0)).collect()) == [(i, i, i) for i in range(5001)]


def test_ledger_counts_rounds_and_offers(spark):
    edge, path, star = make(spark, [(1, 2, 3)]), make(spark, [(i, i + 1, 1) for i in range(20)]), make(spark, [(0, i, i) for i in range(1, 6)])
    for g, start, rounds, improved, offers in ((edge, 1, 1, 1, 1), (path, 0, 20, 20, 39), (star, 0, 1, 5, 5)):
        for h in (g, g.compact()):
            ledger = Ledger()
            relax.exact(h, sources(spark, start), ledger)
            assert (ledger.rounds(), sum(r[4] for r in ledger.rows), ledger.messages()) == (rounds, improved, offers)


def test_one_task_equals_rounds(spark):
    g = make(spark, grid(6))
    a, b = Ledger(), Ledger()
    x, y = cover.partition(g, 0.1, 5, 2, ledger=a), cover.partition(g.compact(), 0.1, 5, 2, ledger=b)
    assert x.exceptAll(y).isEmpty() and y.exceptAll(x).isEmpty() and [r[:6] for r in a.rows] == [r[:6] for r in b.rows]
    p = HopsetParams(beta=2, reps=1, segments=4, ell=3, rate=1.0)
    x, y = (hopset.build(g, p.but(in_task=t), max_scale=2) for t in (False, True))
    assert x.edges.exceptAll(y.edges).isEmpty() and y.edges.exceptAll(x.edges).isEmpty()
    assert [r[:6] for r in x.ledger.rows] == [r[:6] for r in y.ledger.rows]


def test_hubs_are_cut_into_slices(spark, monkeypatch):
    monkeypatch.setattr(relax, "HUB", 10)
    monkeypatch.setattr(model, "MOST_PER_PARTITION", 20)
    rows = [(0, i, i % 7 + 1) for i in range(1, 61)] + [(i, i + 1, 1) for i in range(1, 60)]
    g = make(spark, rows)
    assert table(relax.exact(g, sources(spark, 5, 40))) == {(s, v): d for s in (5, 40) for v, d in lengths(rows, s).items()}
    hubs = relax.hubs_of(g)
    arcs = relax.Arcs(g.arcs_in(4), hubs, 4)
    assert arcs.leaving.groupBy("u", "slice").count().agg(F.max("count")).first()[0] <= 20 and arcs.plain.where("u = 0 or v = 0").isEmpty()


def test_no_hopbound_within_the_limit(spark):
    g, start = make(spark, [(i, i + 1, 1) for i in range(9)]), sources(spark, 0)
    assert verify.effective_hopbound(g, None, start, 0.0, most=5) is None and verify.effective_hopbound(g, None, start, 0.0) == 9


def test_default_parameters_build(spark):
    g = make(spark, grid(8))
    b = hopset.build(g, HopsetParams())
    assert b.beta > 0 and verify.sound(g, b.edges).isEmpty()


def test_competitors_keep_their_stretch(spark):
    rows = grid(7)
    g, src = make(spark, rows).compact(), sources(spark, 0, 24)
    truth = {(s, v): d for s in (0, 24) for v, d in lengths(rows, s).items()}
    for edges in (baselines.dense_two_level(g, 0.5, hops=3), baselines.hierarchy_global(g, 3, 0.5, hops=4), baselines.hierarchy_global(g, 3, 0.5, hops=4, drop_scales=True)):
        assert verify.sound(g, edges).isEmpty()
        got = table(relax.hop_limited(model.augment(g, edges), src, 9))
        assert all(d <= got[k] <= 1.5 * d for k, d in truth.items())


def test_delta_equals_full_and_partitions_do_not_matter(spark):
    g = make(spark, grid(8))
    a = table(relax.hop_limited(g, sources(spark, 0, 9), 5))
    assert a == table(relax.hop_limited(g, sources(spark, 0, 9), 5, delta=False))
    with setting(spark, spark__sql__shuffle__partitions="1"):
        h = make(spark, grid(8))
        assert a == table(relax.hop_limited(h, sources(spark, 0, 9), 5))


def test_normalise_and_aspect(spark):
    g, factor = model.normalize_weights(make(spark, [(1, 2, 7), (2, 3, 15)]))
    assert factor == 7 and {r.w for r in g.edges.collect()} == {1, 3}
    r = model.reduce_aspect(make(spark, [(1, 2, 1), (2, 3, 100), (3, 4, 5000)]), 0.5, [100]).collect()
    assert [(x.u, x.v, x.w) for x in r] == [(1, 3, 100)]


def test_partition_is_the_argmin(spark):
    rows = grid(7)
    g = make(spark, rows)
    got = {(r.rep, r.v): (r.center, r.dhat) for r in cover.partition(g, 0.1, 5, 2).collect()}
    from hopline.functions.rand import shifts

    radius = {(r.rep, r.id): r.shift_fp for r in shifts(g.nodes, 0.1, 5, 2).collect()}
    dist = {x: lengths(rows, x) for x in range(49)}
    for (rep, v), (center, dhat) in got.items():
        key, best = min((dist[x][v] * 2**20 - radius[rep, x], x) for x in range(49))
        assert (center, dhat) == (best, dist[best][v])
    assert len(got) == 98


def test_cover_properties(spark):
    g = make(spark, grid(9))
    members = cover.limited_pairwise(g, 16, 4, 1.0, 3, 1, 1.0)
    assert {r["count"] for r in members.groupBy("rep").count().collect()} == {81}
    assert verify.connected_members(g, members).where("pieces <> 1").isEmpty()
    stray = spark.createDataFrame([(0, 0, 0, 0), (0, 0, 0, 1), (0, 0, 0, 40), (0, 0, 0, 41)], "scale int, rep int, center long, v long")
    assert [r.pieces for r in verify.connected_members(g, stray).collect()] == [2]
    assert members.where("dtree < 0 or (v = center and dtree <> 0)").isEmpty()


def test_rounding(spark):
    g = make(spark, grid(6))
    unit = cover.eta(10, 7, 0.3)
    assert verify.rounding_inflation(cover.round_weights(g, 10, 7, 0.3), unit.numerator, unit.denominator).isEmpty()


def test_padding(spark):
    g = make(spark, grid(8))
    parts = cover.partition(g, 0.02, 4, 12)
    row = verify.padding_rate(parts, relax.ball(g, g.nodes.select(F.col("id").alias("src")), 5), 5, 0.02).first()
    assert row.rate >= row.bound - 0.1


@pytest.mark.parametrize("k", [2, 3, 4, 7])
def test_local_hopset_forms_agree(spark, k):
    rows = [(0, 10 + c, u + 100 * c, v + 100 * c, w) for c in range(3) for u, v, w in grid(4 + c, c)]
    own = spark.createDataFrame(rows, "rep int, center long, u long, v long, w long")
    a, b = local_hopset.at_centers(own, k, 3), local_hopset.by_keys(own, k, 3, 2)
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty() and not a.isEmpty()
    exact = {c: {x: lengths([e[2:] for e in rows if e[1] == c], x) for x in {e[2] for e in rows if e[1] == c}} for c in (10, 11, 12)}
    assert all(r.w == exact[r.center][r.u][r.v] for r in a.collect() if r.u in exact[r.center])


@pytest.mark.parametrize("small", ["hierarchy", "clique", "recursive"])
def test_hopset_is_sound_and_shortens(spark, small):
    g = make(spark, grid(10))
    p = HopsetParams(k=2, eps=0.5, beta=4, reps=2, segments=4, ell=3, rate=1.0, small=small)
    b = hopset.build(g, p)
    assert verify.sound(g, b.edges).isEmpty()
    src = sources(spark, 0, 9, 55)
    truth = relax.exact(g, src)
    assert verify.effective_hopbound(g, b.edges, src, 0.5) < verify.effective_hopbound(g, None, src, 0.5)
    got = verify.stretch(truth, mssp.many(g, b.edges, src, 40), 0.5).first()
    assert got.too_short == 0 and got.max_stretch == 1.0
    assert {r.kind for r in b.edges.select("kind").distinct().collect()} & {"bunch", "clique", "inner", "hub", "star"}


def test_same_seed_same_rows(spark):
    g = make(spark, grid(7))
    p = HopsetParams(beta=2, reps=1, segments=4, ell=3, rate=1.0)
    a, b = (hopset.build(g, p).edges for _ in range(2))
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def test_heavy_clusters_take_the_key_column_way(spark):
    g = make(spark, grid(7))
    p = HopsetParams(beta=2, reps=1, segments=4, ell=3, rate=1.0)
    a, b = hopset.build(g, p, max_scale=2).edges, hopset.build(g, p.but(local_edge_cap=3), max_scale=2).edges
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def test_baselines_are_sound(spark):
    rows = grid(7)
    g, src = make(spark, rows), sources(spark, 0, 24)
    truth = {(s, v): d for s in (0, 24) for v, d in lengths(rows, s).items()}
    for edges in (baselines.dense_two_level(g), baselines.hierarchy_global(g, 3)):
        assert table(relax.exact(model.augment(g, edges), src)) == truth
    thin = model.Graph(g.nodes, baselines.spanner(g, 2))
    assert all(truth[k] <= d <= 3 * truth[k] for k, d in table(relax.exact(thin, src)).items())
    bunches, pivots = baselines.bunch_oracle(g, 3)
    pairs = spark.createDataFrame([k for k in truth if k[0] != k[1]], "src long, v long")
    got = table(baselines.oracle_query(bunches, pivots, pairs, 3))
    assert set(got) == {k for k in truth if k[0] != k[1]} and all(truth[k] <= d <= 5 * truth[k] for k, d in got.items())
    members = baselines.ball_growing_cover(g, 8, 6)
    assert members.count() == 49 and members.select("v").distinct().count() == 49


def test_guards(spark):
    for bad in ({"eps": 0}, {"eps": 1.5}, {"k": 1}, {"mu": 1}, {"small": "x"}):
        with pytest.raises(ValueError):
            HopsetParams(**bad)
    for f, x in ((check_gamma, 0), (check_gamma, 1.1), (check_rho, 0.6)):
        with pytest.raises(ValueError):
            f(x)
    g = make(spark, grid(4))
    with pytest.raises(ValueError):
        mssp.source_detection(g, g.nodes.select(F.col("id").alias("src")), 2)
    with pytest.raises(ValueError):
        Budget(10).search(5, 5)


def test_bounds():
    assert levels(2) == levels(3) == 1 and levels(4) == levels(7) == 2
    assert math.isclose(bounds("main_hopbound", n=1500, k=2, eps=1), 442, rel_tol=0.02)
    assert math.isclose(bounds("restated_hopbound", n=15000, k=4, eps=1), 561, rel_tol=0.02)
    assert math.isclose(padding_bound(0, 1), 1)


def test_maintain(spark):
    g = make(spark, TOY + [(10, 11, 1)])
    h = spark.createDataFrame([(1, 4, 8), (10, 11, 1)], "u long, v long, w long")
    after, kept = maintain(g, h, spark.createDataFrame([(4, 5, 1)], "u long, v long, w long"), spark.createDataFrame([(2, 3)], "u long, v long"))
    assert after.m == 5 and [tuple(r) for r in kept.collect()] == [(10, 11, 1)]

"""The hand-checked network: four vertices, four edges, four snapshots, three paths."""

import numpy as np
import pytest

from roadsnap.operators import candidates, clustering, distances, edgevec, evaluate, hotspots, matching, paths, reach, routing, snapshots, temporal

W = [[10, 10, 10, 30], [10, 12, 10, 30], [20, 30, 20, 30], [22, 30, 20, 33]]
A, B, C, D = 0, 1, 2, 3


@pytest.fixture(scope="module")
def toy(spark):
    edges = spark.createDataFrame([(0, A, B, 1000), (1, B, C, 1000), (2, C, D, 1000), (3, A, C, 1000)], "eid bigint, src bigint, dst bigint, length_m bigint")
    weights = spark.createDataFrame([(s, e, 1000 * w) for s, row in enumerate(W) for e, w in enumerate(row)], "snap int, eid bigint, w_ms bigint")
    ways = spark.createDataFrame([(p, i, e) for p, way in enumerate(([0, 1, 2], [3, 2], [1, 2])) for i, e in enumerate(way)], "pid bigint, seq int, eid bigint")
    vertices = spark.createDataFrame([(A, 0, 0), (B, 1, 0), (C, 1, 1), (D, 0, 1)], "vid bigint, x bigint, y bigint")
    return edges.cache(), weights.cache(), ways.cache(), vertices.cache()


@pytest.fixture(scope="module")
def matrix(toy):
    _, weights, ways, _ = toy
    return temporal.matrix(evaluate.error_matrix(paths.cost_rows(paths.cost(ways, weights)), 4), 4)


def test_costs(toy):
    _, weights, ways, _ = toy
    got = {(r["snap"], r["pid"]): r["d_ms"] // 1000 for r in paths.cost(ways, weights).collect()}
    assert [[got[s, p] for p in range(3)] for s in range(4)] == [[30, 40, 20], [32, 40, 22], [70, 50, 50], [72, 53, 50]]
    packed = {r["pid"]: r["d"] for r in paths.cost_packed(ways, snapshots.packed(weights)).collect()}
    assert packed == {p: [1000 * x for x in d] for p, d in {0: [30, 32, 70, 72], 1: [40, 40, 50, 53], 2: [20, 22, 50, 50]}.items()}


def test_errors(toy, matrix, spark):
    want = [[0, 0.051136, 0.457143, 0.476205], [0.055556, 0, 0.434286, 0.453613], [1.027778, 0.903409, 0, 0.028127], [1.075, 0.949242, 0.029524, 0]]
    assert np.allclose(matrix, want, atol=1e-6)
    _, weights, ways, _ = toy
    costs = paths.cost(ways, weights)
    pairs = spark.createDataFrame([(t, a) for t in range(4) for a in range(4)], "typ int, act int")
    assert np.allclose(temporal.matrix(evaluate.pair_error(costs, pairs), 4), matrix, atol=1e-9)
    band = {(r["typ"], r["act"]) for r in evaluate.error_matrix(paths.cost_rows(costs), 4, 1).collect()}
    assert band == {(t, a) for t in range(4) for a in range(4) if abs(t - a) <= 1}


@pytest.mark.parametrize("eps, want", [(0.05, [(0, 0, 0), (1, 1, 1), (2, 3, 2)]), (0.1, [(0, 1, 0), (2, 3, 2)]), (0.4, [(0, 1, 0), (2, 3, 2)]), (9, [(0, 3, 1)]), (0, [(0, 0, 0), (1, 1, 1), (2, 2, 2), (3, 3, 3)])])
def test_windows(toy, matrix, eps, want):
    found = temporal.windows(matrix, eps)
    if eps == 9:
        assert len(found) == 1 and found[0][:2] == (0, 3)
    else:
        assert [f[:3] for f in found] == want
    assert all(f[3] <= eps for f in found)
    _, weights, ways, _ = toy
    rows = paths.cost_rows(paths.cost(ways, weights))
    assert [tuple(r)[:3] for r in temporal.nonuniform_banded(rows, 4, eps, 1).collect()] == [f[:3] for f in found]


def test_windows_are_maximal():
    rng = np.random.default_rng(0)
    m = rng.random((20, 20))
    np.fill_diagonal(m, 0)
    for eps in (0.3, 0.6, 0.9):
        found = temporal.windows(m, eps)
        assert [x for lo, hi, _, _ in found for x in range(lo, hi + 1)] == list(range(20))
        for lo, hi, typ, worst in found:
            assert max(m[typ, lo : hi + 1]) == worst <= eps
            if hi < 19:
                assert all(m[j, lo : hi + 2].max() > eps for j in range(lo, hi + 2))
    assert temporal.windows(np.zeros((1, 1)), 0.0) == [(0, 0, 0, 0.0)]


def test_uniform(spark):
    s = spark.range(12).selectExpr("cast(id as int) as snap")
    ids = lambda df: sorted(r["typ"] for r in df.collect())
    assert ids(temporal.uniform(s, 4, 1)) == [1, 5, 9] and ids(temporal.uniform(s, 1)) == list(range(12)) and ids(temporal.uniform(s, 20, 11)) == [11]
    near = {r["snap"]: r["typ"] for r in temporal.assign(s, temporal.uniform(s, 4, 1)).collect()}
    assert near == {0: 1, 1: 1, 2: 1, 3: 1, 4: 5, 5: 5, 6: 5, 7: 5, 8: 9, 9: 9, 10: 9, 11: 9}
    before = {r["snap"]: r["typ"] for r in temporal.assign(s, temporal.uniform(s, 4, 1), "previous").collect()}
    assert before[0] == 1 and before[4] == 1 and before[11] == 9


def test_cv_and_pca(toy):
    _, weights, _, _ = toy
    got = {r["eid"]: r["cv"] for r in edgevec.cv(weights).collect()}
    assert [round(got[e], 6) for e in range(4)] == [0.357759, 0.464697, 0.333333, 0.042245]
    assert {r["eid"] for r in edgevec.cv_filter(edgevec.cv(weights), top_share=0.5).collect()} == {0, 1}
    raw = {(r["i"], r["j"]): r["dist"] for r in distances.euclidean(edgevec.weights(weights)).collect()}
    for rep in (edgevec.pca(edgevec.weights(weights), 4, 4), edgevec.pca(edgevec.delta(weights), 4, 4), edgevec.pca_ml(edgevec.weights(weights), 4, 4)):
        assert all(abs(raw[r["i"], r["j"]] - r["dist"]) < 1e-3 for r in distances.euclidean(rep).collect())


def test_reach(toy):
    edges, weights, _, vertices = toy
    for engine in ("loop", "block"):
        rows = reach.bounded(edges, weights, vertices.select("vid"), 25_000, engine, vertices).collect()
        got = {}
        for r in rows:
            got.setdefault((r["origin"], r["snap"]), set()).add(r["reached"])
        assert [got[A, s] for s in range(4)] == [{A, B, C}, {A, B, C}, {A, B}, {A, B}]
        assert [got[B, s] for s in range(4)] == [{B, C, D}, {B, C, D}, {B}, {B}]
        assert all(got[C, s] == {C, D} and got[D, s] == {D} for s in range(4))
    size = hotspots.sizes(reach.bounded(edges, weights, vertices.select("vid"), 25_000))
    block = hotspots.block_coef(size)
    b = {(r["vid"], r["snap"]): r["b"] for r in block.collect()}
    assert [b[A, s] for s in range(4)] == [1, 1, 1.5, 1.5] and [b[B, s] for s in range(4)] == [1, 1, 3, 3]
    f = {r["vid"]: r["f"] for r in hotspots.fluctuation(block).collect()}
    assert f == {A: 0.2, B: 0.5, C: 0.0, D: 0.0}


def test_set_distance_and_matching(toy, spark):
    edges, weights, _, vertices = toy
    typical = spark.createDataFrame([(A,), (B,)], "vid bigint")
    rep = matching.represent_vertices(edges, weights, typical, 25_000)
    got = {(r["i"], r["j"]): r["dist"] for r in distances.sets(rep).collect()}
    # A: {A,B,C} against {A,B}: 1/3; B: {B,C,D} against {B}: 2/3
    assert got == {(0, 1): 0.0, (2, 3): 0.0, (0, 2): 0.5, (0, 3): 0.5, (1, 2): 0.5, (1, 3): 0.5}
    near = {r["snap"]: (r["typ"], r["dist"]) for r in matching.nearest_sets(rep, rep.filter("snap in (0, 2)")).collect()}
    assert near == {0: (0, 0.0), 1: (0, 0.0), 2: (2, 0.0), 3: (2, 0.0)}
    smooth = spark.createDataFrame([(9, A, 4)], "snap int, vid bigint, size bigint")
    top = spark.createDataFrame([(A, 3)], "vid bigint, top bigint")
    assert hotspots.block_coef(smooth, top).first()["b"] == 0.75 and hotspots.block_coef(smooth, top, True).first()["b"] == 1.0


def test_selection_of_vertices(spark):
    f = spark.createDataFrame([(v, 1.0 - v / 10) for v in range(6)], "vid bigint, f double")
    near = {0: {0, 1}, 1: {1}, 2: {2, 3}, 3: {3, 4}, 4: {4}, 5: {5, 2}}
    cover = lambda ids: spark.createDataFrame([(r["vid"], v) for r in ids.collect() for v in near[r["vid"]]], "origin bigint, reached bigint")
    pick = lambda rule, q: [r["vid"] for r in hotspots.select(f, q, cover, rule).collect()]
    assert pick("in_2r", 3) == [0, 2, 4] and pick("none", 3) == [0, 1, 2] and pick("disjoint_r", 3) == [0, 2, 4]
    with pytest.warns(UserWarning):
        assert pick("in_2r", 6) == [0, 2, 4, 5]


def test_routing(toy, spark):
    edges, weights, _, vertices = toy
    asked = spark.createDataFrame([(A, D), (B, D), (D, A), (C, C)], "s bigint, t bigint")
    plain = {(r["snap"], r["s"], r["t"]): r["dist"] for r in routing.distances(edges, weights, asked).collect()}
    assert plain[0, A, D] == 30_000 and plain[2, A, D] == 50_000 and plain[0, D, A] is None and plain[1, C, C] == 0
    labels = routing.hub_labels(edges, weights)
    q = weights.selectExpr("snap as typ").distinct().crossJoin(asked)
    assert {(r["typ"], r["s"], r["t"]): r["dist"] for r in routing.answer(q, labels).collect()} == plain
    ways = routing.shortest_paths(edges, weights, asked).collect()
    assert {(r["snap"], r["s"], r["t"]): r["dist"] for r in ways} == plain
    assert next(r["edges"] for r in ways if (r["snap"], r["s"], r["t"]) == (2, A, D)) == [3, 2]
    typ = spark.createDataFrame([(s, s) for s in range(4)], "snap int, typ int")
    act = routing.distances(edges, weights, asked)
    same = routing.regret(routing.shortest_paths(edges, weights, asked), typ, weights, act).collect()
    assert all(r["regret"] == 0 for r in same)
    moved = routing.regret(routing.shortest_paths(edges, weights, asked), spark.createDataFrame([(0, 2), (2, 0)], "snap int, typ int"), weights, act).collect()
    assert all(r["regret"] >= 0 for r in moved) and max(r["regret"] for r in moved) > 0


def test_clustering(spark):
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(c, 0.1, (10, 2)) for c in (0, 5, 9)])
    rep = spark.createDataFrame([(i, d, float(x[i, d])) for i in range(30) for d in range(2)], "snap int, dim bigint, val double")
    dist = distances.euclidean(rep).cache()
    truth = [i // 10 for i in range(30)]
    same = lambda labels: len({(a, b) for a, b in zip(labels, truth)}) == 3
    col = lambda df: [r["cluster"] for r in df.orderBy("snap").collect()]
    assert same(col(clustering.kmeans(rep, 3)))
    tau = 1.0
    grown = clustering.adaptive_kmeans(rep, tau).toPandas()
    assert grown["dist"].max() <= tau and grown["cluster"].nunique() == 3
    for linkage in ("complete", "average", "single"):
        assert same(col(clustering.agglomerative(dist, linkage, k=3))) and same(col(clustering.agglomerative(dist, linkage, tau=2.0)))
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    cut = clustering.agglomerate(d, "complete", tau=0.2)
    assert all(d[np.ix_(cut == c, cut == c)].max() <= 0.2 for c in set(cut))
    pairs = dist.filter("dist <= 2")
    ids = spark.range(30).selectExpr("cast(id as int) as snap")
    assert same(col(clustering.components(pairs, ids)))
    whole = clustering.agglomerative(dist, k=3).toPandas()
    assert set(whole["typ"]) == {r["typ"] for r in clustering.representatives(distances.symmetric(dist), clustering.agglomerative(dist, k=3)).collect()}
    assert all(whole.set_index("snap").loc[t, "cluster"] == c for t, c in zip(whole["typ"], whole["cluster"]))


def test_replay_order_matters(spark):
    dist = spark.createDataFrame([(0, 1, 1.0), (0, 2, 2.0), (1, 2, 1.0)], "i int, j int, dist double")
    rows = matching.replay(dist, 1.0).collect()
    assert [(r["typ"], r["is_new"]) for r in rows] == [(0, True), (0, False), (2, True)]
    assert [(r["typ"], r["is_new"]) for r in matching.replay(dist, 1.0, (1,)).collect()] == [(1, False), (1, False), (1, False)]


def test_model_store(spark, tmp_path):
    rep = spark.createDataFrame([(0, 1, 2.0)], "snap int, dim bigint, val double")
    matching.save_model(spark, str(tmp_path), 3, rep, r_ms=60000)
    back, params = matching.load_model(spark, str(tmp_path), 3)
    assert back.collect() == rep.collect() and params == {"r_ms": 60000}
    level, slope = matching.linear_fit([1, 2, 3], [1.5, 2.5, 3.5])
    assert level == pytest.approx(0.5) and slope == pytest.approx(1.0)


def test_stream_decisions_do_not_depend_on_the_batch_size(spark):
    from roadsnap.streaming import traffic

    level = [0, 10, 10, 20, 11, 20, 0, 31, 30, 10]
    rep = spark.createDataFrame([(i, d, float(v)) for i, v in enumerate(level) for d in (0, 1)], "snap int, dim bigint, val double")
    pairs = distances.euclidean(rep)
    want = sorted(map(tuple, matching.replay(pairs, 5.0, (0,)).collect()))
    assert sum(r[3] for r in want) == 3
    for size in (1, 3, 7, 10):
        matcher = traffic.SnapshotMatcher(rep.filter("snap = 0"), 5.0)
        for number, lo in enumerate(range(0, len(level), size)):
            matcher.batch(rep.filter(f"snap >= {lo} and snap < {lo + size}"), number)
        assert sorted(tuple(r) for d in matcher.decisions.values() for r in d.collect()) == want, size

"""Operators and queries that SQL does not express, against plain loops; and the corners where earlier versions failed."""

import hashlib
import heapq
import random
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from roadsnap.functions.shared import cut
from roadsnap.operators import candidates, clustering, distances, edgevec, evaluate, hotspots, matching, paths, reach, regions, routing, snapshots, temporal
from roadsnap.plans import methods, queries, queries_ops  # noqa: F401 - the import fills the registry
from roadsnap.sources import nets


def rows_of(df):
    return sorted(tuple(r) for r in df.collect())


# ---------------------------------------------------------------- reach


def random_graph(spark, seed, n=60, m=220, snaps=3, low=0, high=400, spread=40):
    r = random.Random(seed)
    place = [(v, r.randint(-spread, spread), r.randint(-spread, spread)) for v in range(n)]
    arcs = [(e, r.randrange(n), r.randrange(n), 100) for e in range(m)]
    w = [(s, e, r.randint(low, high)) for s in range(snaps) for e in range(m)]
    return (
        spark.createDataFrame(place, "vid bigint, x bigint, y bigint"), spark.createDataFrame(arcs, "eid bigint, src bigint, dst bigint, length_m bigint"),
        spark.createDataFrame(w, "snap int, eid bigint, w_ms bigint"), place, arcs, w,
    )


def dijkstra(arcs, w, s):
    out = {}
    for e, a, b, _ in arcs:
        out.setdefault(a, []).append((b, w[e], e))
    dist, via, heap = {s: 0}, {}, [(0, s)]
    while heap:
        d, v = heapq.heappop(heap)
        if d > dist[v]:
            continue
        for u, x, e in out.get(v, ()):
            if d + x < dist.get(u, 1 << 60):
                dist[u], via[u] = d + x, (v, e)
                heapq.heappush(heap, (d + x, u))
    return dist, via


@pytest.mark.parametrize("seed, low, spread", [(1, 0, 40), (2, 1, 200), (3, 150, 3), (4, 120, 12)])
def test_reach_engines_on_any_graph(spark, seed, low, spread):
    """Long edges, negative coordinates, weights of 0 and 1: all engines give what a heap search gives."""
    v, e, w, place, arcs, rows = random_graph(spark, seed, low=low, spread=spread)
    weight = {}
    for s, eid, x in rows:
        weight.setdefault(s, {})[eid] = x
    r = 260
    want = sorted((s, o, t, d) for s in weight for o, _, _ in place for t, d in dijkstra(arcs, weight[s], o)[0].items() if d <= r)
    assert rows_of(reach.bounded(e, w, v, r, "block", v, 8)) == want
    if seed == 1:
        assert rows_of(reach.bounded(e, w, v, r)) == want
    size = {}
    for s, o, _, _ in want:
        size[s, o] = size.get((s, o), 0) + 1
    assert {(a, b): c for a, b, c in rows_of(reach.sizes(e, w, v, r, v, 8))} == size


def test_reach_leaves_the_block(spark):
    v = spark.createDataFrame([(0, 0, 0), (1, 200, 0), (2, 201, 0), (3, 202, 0)], "vid bigint, x bigint, y bigint")
    e = spark.createDataFrame([(0, 0, 1, 1), (1, 1, 2, 1), (2, 2, 3, 1)], "eid bigint, src bigint, dst bigint, length_m bigint")
    w = spark.createDataFrame([(0, i, 1000) for i in range(3)], "snap int, eid bigint, w_ms bigint")
    got = rows_of(reach.bounded(e, w, v.limit(1), 3000, "block", v))
    assert [(o, t) for _, o, t, _ in got if o == 0] == [(0, 0), (0, 1), (0, 2), (0, 3)]


def test_new_snapshots_on_a_neighbourhood(spark):
    v, e, w, *_ = random_graph(spark, 5, low=100)
    hot = v.filter("vid in (3, 17, 40)").select("vid")
    near = cut(reach.neighbourhood(e, w, hot, 260))
    faster = w.withColumn("w_ms", F.expr("cast(w_ms * 0.6 as bigint)"))
    assert rows_of(reach.around(near, faster, hot, 260)) == rows_of(reach.bounded(e, faster, hot, 260))
    a = matching.represent_vertices(e, faster, hot, 260, near=near)
    assert rows_of(a) == rows_of(matching.represent_vertices(e, faster, hot, 260))
    with pytest.raises(Exception, match="below the bound"):
        reach.around(near, w.withColumn("w_ms", F.lit(1).cast("bigint")), hot, 260).collect()


# ---------------------------------------------------------------- vectors and distances


def test_cv_of_long_travel_times(spark):
    w = spark.createDataFrame([(s, 0, 12_000_000_000 + s % 2 * 3_000_000_000) for s in range(288)], "snap int, eid bigint, w_ms bigint")
    assert edgevec.cv(w).first()["cv"] == pytest.approx(1.5 / 13.5, abs=1e-9)
    x = [12_000_000_000 + s % 2 * 3_000_000_000 for s in range(288)]
    assert edgevec.cv(w, 1).first()["cv"] == pytest.approx(np.std(x, ddof=1) / np.mean(x), abs=1e-9)


def test_principal_components_of_reduced_rank(spark, sf):
    w = cut(nets.trade_net(spark, sf).weights)
    table = w.toPandas().pivot(index="snap", columns="eid", values="w_ms").to_numpy(float)
    centred = table - table.mean(0)
    u, s, _ = np.linalg.svd(centred, full_matrices=False)
    for dims in (2, 5):
        x = u[:, :dims] * s[:dims]
        for rep in (edgevec.weights(w), edgevec.delta(w)):
            got = {(r["i"], r["j"]): r["dist"] for r in distances.euclidean(edgevec.pca(rep, 28, dims)).collect()}
            assert all(got[i, j] == pytest.approx(np.linalg.norm(x[i] - x[j]), rel=1e-6) for i, j in combinations(range(28), 2))


def test_close_sets(spark):
    r = random.Random(3)
    sets = {i: set(r.sample(range(30), r.randint(0, 14))) for i in range(80)}
    for i in range(0, 80, 4):
        sets[i + 1] = set(sets[i]) ^ {r.randrange(30)}
    df = spark.createDataFrame([(i, "ab"[i % 3 == 0], [str(x) for x in s]) for i, s in sets.items()], "id bigint, kind string, members array<string>")
    for limit in (0.2, 0.5):
        want = {(a, b): round(1 - len(sets[a] & sets[b]) / len(sets[a] | sets[b]), 6) for a, b in combinations(sets, 2) if (a % 3 == 0) == (b % 3 == 0) and sets[a] and sets[b]}
        want = {p: d for p, d in want.items() if d <= limit}
        assert want and {(x["a"], x["b"]): x["dist"] for x in distances.close_sets(df, limit).collect()} == want


def test_set_distance_kernel(spark):
    r = random.Random(4)
    rep = [(s, v, x) for s in range(9) for v in range(5) for x in {v, *r.sample(range(20), r.randint(0, 9))}]
    df = spark.createDataFrame(rep, "snap int, vid bigint, reached bigint")
    assert rows_of(distances.sets_packed(df, 9)) == rows_of(distances.sets(df))


# ---------------------------------------------------------------- clustering


def naive_agglomerate(d, linkage, tau=None, k=None):
    groups = [[i] for i in range(len(d))]
    link = {"complete": max, "single": min, "average": lambda x: sum(x) / len(x)}[linkage]
    while len(groups) > max(1, k or 1):
        best = min(((round(link([d[i][j] for i in a for j in b]), 9), a[0], b[0], x, y) for (x, a), (y, b) in combinations(enumerate(groups), 2)))
        if not np.isfinite(best[0]) or tau is not None and best[0] > tau:
            break
        x, y = best[3:]
        groups[x] = sorted(groups[x] + groups.pop(y))
        groups.sort()
    label = [0] * len(d)
    for g, each in enumerate(groups):
        for i in each:
            label[i] = g
    return label


@pytest.mark.parametrize("linkage", ["complete", "average", "single"])
def test_agglomeration_equals_a_naive_one(linkage):
    rng = np.random.default_rng(7)
    x = rng.normal(size=(24, 3))
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    for kw in ({"k": 5}, {"tau": 1.4}, {"tau": 0.0}, {"k": 1}):
        assert clustering.agglomerate(d, linkage, **kw).tolist() == naive_agglomerate(d, linkage, **kw)


@pytest.mark.parametrize("linkage", ["complete", "average", "single"])
def test_agglomeration_by_rounds(spark, linkage):
    x = np.random.default_rng(8).normal(size=(18, 2))
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    dist = spark.createDataFrame([(i, j, float(d[i, j])) for i, j in combinations(range(18), 2)], "i int, j int, dist double")
    got = dict(rows_of(clustering.agglomerative_rounds(dist, spark.range(20).selectExpr("cast(id as int) as snap"), 0.9, linkage)))
    want = naive_agglomerate(d, linkage, tau=0.9)
    assert len(set(want)) < 18 and all((got[i] == got[j]) == (want[i] == want[j]) for i, j in combinations(range(18), 2)) and got[18] == 18 and got[19] == 19


def test_agglomeration_of_one_snapshot_and_missing_pairs(spark):
    none = spark.createDataFrame([], "i int, j int, dist double")
    one = spark.createDataFrame([(7,)], "snap int")
    assert rows_of(clustering.agglomerative(none, k=1, snaps=one)) == [(7, 0, 7, 0.0)]
    assert rows_of(matching.replay(none, 1.0, snaps=one)) == [(7, 7, None, True)]
    part = spark.createDataFrame([(0, 1, 5.0), (1, 2, 1.0)], "i int, j int, dist double")
    label = {s: c for s, c, _, _ in rows_of(clustering.agglomerative(part, tau=6.0))}
    assert label[1] == label[2] != label[0]  # nothing says that 0 and 2 are close
    many = spark.range(clustering.MAX_N + 1).selectExpr("cast(id as int) as i", "cast(id + 1 as int) as j", "1.0D as dist")
    with pytest.raises(ValueError, match="driver kernels take"):
        clustering.agglomerative(many, k=2)


def naive_kmeans(x, centres):
    label = None
    for _ in range(50):
        new = [min(range(len(centres)), key=lambda c: (sum((a - b) ** 2 for a, b in zip(p, centres[c])), c)) for p in x]
        if new == label:
            break
        label = new
        for c in range(len(centres)):
            mine = [p for p, y in zip(x, label) if y == c]
            if mine:
                centres[c] = [sum(v) / len(mine) for v in zip(*mine)]
    return label, centres


def test_kmeans_equals_a_naive_one(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(40, 2)).tolist()
    gap = lambda p, q: sum((a - b) ** 2 for a, b in zip(p, q))
    mean = [sum(v) / 40 for v in zip(*x)]
    start = [min(range(40), key=lambda i: gap(x[i], mean))]
    while len(start) < 5:
        start.append(max(range(40), key=lambda i: min(gap(x[i], x[c]) for c in start)))
    label, centres = naive_kmeans(x, [list(x[c]) for c in start])
    got, c = clustering.kmeans_kernel(np.array(x), 5)
    assert got.tolist() == label and np.allclose(c, centres)
    rep = spark.createDataFrame([(i, d, x[i][d]) for i in range(40) for d in range(2)], "snap int, dim bigint, val double")
    tau, label, centres = 0.8, *naive_kmeans(x, [list(x[start[0]])])
    while max(gap(p, centres[y]) ** 0.5 for p, y in zip(x, label)) > tau:
        worst = max(range(40), key=lambda i: gap(x[i], centres[label[i]]))
        label, centres = naive_kmeans(x, [*centres, list(x[worst])])
    rows = clustering.adaptive_kmeans(rep, tau).orderBy("snap").collect()
    assert len({r["cluster"] for r in rows}) == len(set(label)) and {(a, r["cluster"]) for a, r in zip(label, rows)} == set(zip(label, [r["cluster"] for r in rows]))
    assert all((rows[i]["cluster"] == rows[j]["cluster"]) == (label[i] == label[j]) for i, j in combinations(range(40), 2))


def test_library_kmeans_on_clear_groups(spark, sf):
    rep = spark.createDataFrame([(i, d, float(100 * (i // 5) + i % 5)) for i in range(20) for d in range(2)], "snap int, dim bigint, val double")
    got = {r["snap"]: r["cluster"] for r in clustering.kmeans_ml(rep, 4).collect()}
    assert len(set(got.values())) == 4 and all(got[i] == got[i // 5 * 5] for i in range(20))
    assert queries.QUERIES["kmeans_ml"](spark, sf).count() == 28


def test_adjusted_rand_by_pairs(spark):
    r = random.Random(1)
    a, b = [r.randrange(4) for _ in range(60)], [r.randrange(3) for _ in range(60)]
    b = [x if r.random() < 0.4 else y % 3 for x, y in zip(b, a)]
    same = [(a[i] == a[j], b[i] == b[j]) for i, j in combinations(range(60), 2)]
    n, i, x, y = len(same), sum(p and q for p, q in same), sum(p for p, _ in same), sum(q for _, q in same)
    want = (i - x * y / n) / ((x + y) / 2 - x * y / n)
    sel = spark.createDataFrame([(k, v) for k, v in enumerate(a)], "snap int, cluster int")
    truth = spark.createDataFrame([(k, str(v)) for k, v in enumerate(b)], "snap int, regime string")
    assert evaluate.adjusted_rand(sel, truth).first()["ari"] == pytest.approx(want, abs=1e-6)
    most = sum(max(sum(1 for p, q in zip(a, b) if p == c and q == l) for l in range(3)) for c in range(4))
    assert evaluate.purity(sel, truth).first()["purity"] == pytest.approx(most / 60, abs=1e-6)


def test_crossover(spark):
    c = spark.createDataFrame([("m", 2, 0.5), ("m", 4, 0.3), ("m", 8, 0.1), ("n", 2, 0.9), ("n", 4, 0.9), ("n", 8, 0.9)], "method string, k int, mean_err double")
    base = spark.createDataFrame([(2, 0.4), (4, 0.35), (8, 0.2)], "k int, mean_err double")
    assert {(r["method"], r["k"]): (r["better"], r["first_k"]) for r in evaluate.crossover(c, base).collect()} == {
        ("m", 2): (False, 4), ("m", 4): (True, 4), ("m", 8): (True, 4), ("n", 2): (False, None), ("n", 4): (False, None), ("n", 8): (False, None)}


# ---------------------------------------------------------------- windows and their sweeps


def naive_windows(m, eps, pick):
    n, lo, out = len(m), 0, []
    while lo < n:
        chosen = None
        for hi in range(lo, n):
            members = range(lo, hi + 1)
            worst = {j: max((m[j][i] for i in members if i != j), default=0.0) for j in members}
            j = {"minimax": min(members, key=lambda x: (worst[x], x)), "first": lo, "last": hi, "middle": lo + (hi - lo) // 2}[pick]
            if worst[j] > eps:
                break
            chosen = (lo, hi, j, worst[j])
        out.append(chosen)
        lo = chosen[1] + 1
    return out


@pytest.mark.parametrize("pick", ["minimax", "first", "middle", "last"])
def test_windows_equal_naive_ones(pick):
    m = np.random.default_rng(3).random((25, 25)) * np.abs(np.subtract.outer(np.arange(25), np.arange(25))) / 12
    for eps in (0.0, 0.1, 0.3, 0.7, 2.0):
        assert [tuple(w) for w in temporal.windows(m, eps, pick)] == [pytest.approx(w) for w in naive_windows(m.tolist(), eps, pick)]


def test_window_queries(spark, sf):
    _, err = queries.trade_errors(spark, sf)
    m = temporal.matrix(err, 28)
    mean = lambda w: round(float(sum(m[t, lo : hi + 1].sum() for lo, hi, t, _ in w) / 28), 6)
    for r in queries.QUERIES["nonuniform_picks"](spark, sf).collect():
        w = naive_windows(m.tolist(), queries.EPS, r["pick"])
        assert (r["k"], r["mean_err"]) == (len(w), pytest.approx(mean(w), abs=2e-6))
    for r in queries.QUERIES["eps_sweep"](spark, sf).collect():
        w = naive_windows(m.tolist(), r["eps"] + 5e-10, "minimax")
        assert (r["k"], r["mean_err"], r["worst"]) == (len(w), pytest.approx(mean(w), abs=2e-6), pytest.approx(max(x[3] for x in w), abs=2e-6))


# ---------------------------------------------------------------- paths and routes


def test_kept_paths(spark, sf):
    rows = cut(queries.grown_paths(spark, sf, "random")).orderBy("cand").collect()
    quota = {r["region"]: r["quota"] for r in regions.quota(regions.grid(nets.grid_net(spark, sf).vertices), 64).collect()}
    kept = {}
    for r in rows:
        mine, e = kept.setdefault(r["region"], []), set(r["edges"])
        if len(mine) < quota[r["region"]] and all(round(len(e & s) / len(e | s), 6) <= 0.3 for _, s in mine):
            mine.append((r["cand"], e))
    want = sorted(c for x in kept.values() for c, _ in x)
    assert sorted(r["cand"] for r in queries.QUERIES["typical_paths_kept"](spark, sf).collect()) == want


def test_further_draws_fill_quotas(spark, sf):
    net = nets.grid_net(spark, sf)
    placed, edges = cut(regions.grid(net.vertices)), cut(net.edges)
    quota = regions.quota(placed, 16)
    first = candidates.dedup(candidates.valid(candidates.grow(edges, candidates.starts(edges, placed, quota, 42, 1), 42)), quota, 0.1).count()
    more = candidates.select("random", edges, placed, 16, None, 42, max_jaccard=0.1)
    assert first < more.count() <= 16
    walk = candidates.grow(edges, candidates.starts(edges, placed, quota, 42), 42, no_uturn=True).collect()
    ends = {r["eid"]: (r["src"], r["dst"]) for r in edges.collect()}
    assert all(ends[a] != ends[b][::-1] for r in walk for a, b in zip(r["edges"], r["edges"][1:]))


def test_regret_and_ways(spark, sf):
    net = nets.trade_net(spark, sf)
    w = cut(net.weights)
    arcs = [(r["eid"], r["src"], r["dst"], 0) for r in net.edges.collect()]
    weight = {}
    for r in w.collect():
        weight.setdefault(r["snap"], {})[r["eid"]] = r["w_ms"]
    asked = [(r["s"], r["t"]) for r in queries._trade_queries(spark, sf).collect()]
    best = {(s, o): dijkstra(arcs, weight[s], o) for s in weight for o in {a for a, _ in asked}}

    def way(s, o, t):
        out, v = [], t
        while v != o:
            v, e = best[s, o][1][v]
            out.append(e)
        return out

    typ = {r["snap"]: r["typ"] for r in queries._match(spark, sf).collect()}
    for r in queries.QUERIES["regret"](spark, sf).collect():
        s = r["snap"]
        parts = [(sum(weight[s][e] for e in way(typ[s], o, t)) - best[s, o][0][t]) * 10**9 // best[s, o][0][t] for o, t in asked]
        assert r["queries"] == len(asked) and r["regret"] == pytest.approx(sum(parts) / len(parts) / 1e9, abs=2e-6)
    for r in routing.shortest_paths(net.edges, w.filter("snap = 3"), queries._trade_queries(spark, sf)).collect():
        assert r["edges"] == way(3, r["s"], r["t"])[::-1] and r["dist"] == best[3, r["s"]][0][r["t"]]


def test_index_sizes(spark, sf):
    rows = queries.QUERIES["index_sizes"](spark, sf).collect()
    net = nets.trade_net(spark, sf)
    labels = routing.hub_labels(net.edges, net.weights).groupBy("typ").count().collect()
    count = {r["typ"]: r["count"] for r in labels}
    assert {(r["plan"], r["typ"]): (r["rows"], r["bytes"]) for r in rows} == {**{("every", t): (n, 25 * n) for t, n in count.items()}, **{("typical", t): (n, 25 * n) for t, n in count.items() if t % 6 == 0}}


def test_path_function(spark):
    rows = [tuple(r) for r in queries.QUERIES["udtf_grow_path"](spark, None).collect()]
    at, used = 8, set()
    for seq, eid, head in rows:
        x, y = at % 6, at // 6
        free = [(at * 4 + d, at + dx + 6 * dy) for d, dx, dy in ((0, 1, 0), (1, -1, 0), (2, 0, 1), (3, 0, -1)) if 0 <= x + dx < 6 and 0 <= y + dy < 5]
        free = [a for a in free if a[0] not in used]
        assert (eid, head) == min(free, key=lambda a: hashlib.md5(f"42|8|{seq}|{a[0]}".encode()).hexdigest())
        used.add(eid)
        at = head
    assert len(rows) == 12


def test_regional_passes(spark, sf):
    got = queries.QUERIES["w11_regional_passes"](spark, sf).collect()
    by = {}
    for r in got:
        by.setdefault(r["region"], []).append((r["snap"], r["cluster"]))
    t = {n: spark.read.parquet(f"{sf}/{n}.parquet").toPandas() for n in ("orders", "customer", "nation", "region")}
    flat = t["orders"].merge(t["customer"], left_on="o_custkey", right_on="c_custkey").merge(t["nation"], left_on="c_nationkey", right_on="n_nationkey").merge(t["region"], left_on="n_regionkey", right_on="r_regionkey")
    flat["q"] = flat["o_orderdate"].dt.to_period("Q")
    for region, part in flat.groupby("r_name"):
        x = part.groupby(["q", "n_nationkey"]).size().unstack(fill_value=0).to_numpy(float)
        assert sorted(by[region]) == list(enumerate(clustering.kmeans_kernel(x, 4)[0].tolist()))
    assert len(by) == flat["r_name"].nunique()


# ---------------------------------------------------------------- matching as a stream


def events_table(spark, tmp_path, snaps=10, seed=6):
    r, rows = random.Random(seed), []
    for s in range(snaps):
        for i in range(40):
            rows.append((s, r.randrange(5), len(rows), s * 1000 + i, r.randrange(4), 1000 * (1 + s // 3 % 2 * 5) + r.randrange(50)))
    schema = "snap int, user_id bigint, event_id bigint, ts bigint, bucket bigint, obs_ms bigint"
    df = spark.createDataFrame(rows, schema)
    df.coalesce(1).write.mode("overwrite").parquet(f"{tmp_path}/placed")
    return rows, schema


def test_answers_do_not_depend_on_batches_nor_on_a_restart(spark, tmp_path):
    from roadsnap.sources.replay import ReplaySource
    from roadsnap.streaming import traffic

    rows, schema = events_table(spark, tmp_path)
    last, moves = {}, []
    for s, u, _, _, b, obs in sorted(rows, key=lambda x: (x[1], x[3])):
        if last.get(u, b) != b:
            moves.append((u, last[u] * 10 + b, obs, s))
        last[u] = b
    moves = cut(spark.createDataFrame(moves, "pid bigint, eid bigint, obs_ms bigint, snap int"))
    edges = moves.select("eid").distinct().selectExpr("eid", "eid div 10 as src", "eid % 10 as dst", "100 as length_m")
    of_edge, of_net = moves.groupBy("eid").agg(F.expr("sum(obs_ms) div count(*)").alias("edge_ms")), moves.agg(F.expr("sum(obs_ms) div count(*)").alias("net_ms"))
    weights = cut(snapshots.fill(snapshots.profile(moves), edges, moves.select("snap").distinct(), of_edge, of_net))
    net, tau = nets.Network(None, edges, None, weights), 5000.0
    # the rule in order, and all distances of the snapshots that stay typical
    order = [(r[0], r[1]) for r in rows_of(matching.replay(distances.euclidean(edgevec.weights(weights)), tau, (0,)))]
    typ = dict(order)
    assert 1 < len(set(typ.values())) < 10
    arcs = [(r["eid"], r["src"], r["dst"], 0) for r in edges.collect()]
    w = {}
    for r in weights.collect():
        w.setdefault(r["snap"], {})[r["eid"]] = r["w_ms"]
    want = sorted({(s, typ[s], s != 0 and typ[s] == s, e // 10, e % 10, dijkstra(arcs, w[typ[s]], e // 10)[0][e % 10]) for _, e, _, s in moves.collect()})
    spark.dataSource.register(ReplaySource)
    for size in (1, 4, 7):
        stream = spark.readStream.format("snapshot_replay").option("path", f"{tmp_path}/placed").option("per_batch", size).option("columns", schema).load()
        assert rows_of(traffic.answer_stream(stream, net, of_edge, of_net, tau)) == want, size
    # a second driver finds the model, runs the last batch of the first one again, and goes on
    rep, asked = cut(edgevec.weights(weights)), moves.selectExpr("snap", "eid div 10 as s", "eid % 10 as t").distinct()
    start = weights.filter("snap = 0")
    for number, lo in enumerate((0, 4, 8)):
        for _ in range(2):
            m = traffic.SnapshotMatcher(edgevec.weights(start), tau, edges, start, f"file://{tmp_path}/model")
            part = f"snap >= {lo} and snap < {lo + 4}"
            m.batch(rep.filter(part), number, weights.filter(part), asked.filter(part))
    assert rows_of(m.answers()) == want
    assert sorted(m.decisions) == [0, 1, 2]


# ---------------------------------------------------------------- methods


def test_methods_under_thresholds_and_rules(spark, sf):
    net = nets.grid_net(spark, sf)
    study = methods.Study(net, 28, 60_000, 5, 16)
    dist = methods.distance_of(study, "edge_raw")
    tau = float(dist.agg(F.percentile("dist", F.lit(0.3))).first()[0])
    near = {(r["i"], r["j"]): r["dist"] for r in dist.collect()}
    label = {r["snap"]: r["cluster"] for r in methods.select_typical(study, "edge_raw", tau=tau).collect()}
    assert all(near[i, j] <= tau for i, j in near if label[i] == label[j]) and 1 < len(set(label.values())) < 28
    far = [r["dist"] for r in methods.select_typical(study, "vertex_bc_kmeans", tau=0.2).collect()]
    assert max(far) <= 0.2
    hot = [r["vid"] for r in study.typical_vertices(3, "disjoint_r").orderBy("rank").collect()]
    cover = {}
    for r in reach.bounded(study.edges, study.weights, study.net.vertices, 60_000).select("origin", "reached").distinct().collect():
        cover.setdefault(r["origin"], set()).add(r["reached"])
    assert all(cover[a].isdisjoint(cover[b]) for a, b in combinations(hot, 2))
    c = methods.curve(study, ("uniform", "vertex_set"), (4, 14), rule="disjoint_r").collect()
    assert all(r["k_found"] == r["k"] and r["mean_err"] <= r["p95_err"] <= r["max_err"] for r in c)

"""Networks, invariants of the methods on them, and the shape of plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from roadsnap.functions.shared import cut
from roadsnap.operators import candidates, edgevec, evaluate, hotspots, paths, reach, regions, snapshots, temporal
from roadsnap.plans import inspect, methods
from roadsnap.sources import nets, tables


@pytest.fixture(scope="module")
def grid(spark, sf):
    net = nets.grid_net(spark, sf)
    return nets.Network(net.vertices, cut(net.edges), net.snapshots, cut(net.weights), cut(net.paths))


def test_golden_weights(spark):
    w = nets.grid_net(spark, "/root/testdata/sf0.01").weights.agg(F.count("*"), F.sum("w_ms"), F.min("w_ms"), F.max("w_ms")).first()
    assert tuple(w) == (218960, 8932930529, 4000, 289961)


def test_sizes(spark, grid, sf):
    assert grid.edges.count() == 742 and grid.vertices.count() == 200 and grid.snapshots.count() == 28
    assert snapshots.missing_cells(grid.weights, grid.edges, grid.snapshots).isEmpty() and snapshots.unknown_edges(grid.weights, grid.edges).isEmpty()
    event = nets.event_net(spark, sf)
    assert snapshots.missing_cells(event.weights, event.edges, event.snapshots).isEmpty()


def test_routes_are_connected(grid):
    e = {r["eid"]: (r["src"], r["dst"]) for r in grid.edges.collect()}
    ways = {}
    for r in grid.paths.orderBy("pid", "seq").collect():
        ways.setdefault(r["pid"], []).append(r["eid"])
    assert ways and all(e[a][1] == e[b][0] for w in ways.values() for a, b in zip(w, w[1:]))


def test_packing_of_weights(grid):
    back = snapshots.unpacked(snapshots.packed(grid.weights))
    assert back.exceptAll(grid.weights.select("snap", "eid", "w_ms")).isEmpty()


@pytest.mark.parametrize("kind", ["random", "constrained", "greedy"])
def test_typical_paths(grid, kind):
    placed = cut(regions.grid(grid.vertices))
    cvs = cut(edgevec.cv(grid.weights))
    e = {r["eid"]: r for r in grid.edges.collect()}
    rows = candidates.select(kind, grid.edges, placed, 32, cvs).collect()
    quota = {r["region"]: r["quota"] for r in regions.quota(placed, 32).collect()}
    assert sum(quota.values()) == 32
    high = {r["eid"] for r in edgevec.cv_filter(cvs, top_share=0.3).collect()}
    cv = {r["eid"]: r["cv"] for r in cvs.collect()}
    for r in rows:
        way = r["edges"]
        assert len(set(way)) == len(way) and all(e[a]["dst"] == e[b]["src"] for a, b in zip(way, way[1:]))
        assert r["length"] == sum(e[x]["length_m"] for x in way) and 2000 <= r["length"] <= 3000
        if kind == "constrained":
            assert set(way) <= high
        if kind == "greedy":
            for i, (a, b) in enumerate(zip(way, way[1:])):
                free = [x for x in e if e[x]["src"] == e[a]["dst"] and x not in way[: i + 1]]
                assert cv[b] == max(cv[x] for x in free)
    for region in quota:
        mine = [set(r["edges"]) for r in rows if r["region"] == region]
        assert len(mine) <= quota[region]
        assert all(len(a & b) / len(a | b) <= 0.3 for i, a in enumerate(mine) for b in mine[:i])


def test_reach_engines_and_nesting(grid):
    a = cut(reach.bounded(grid.edges, grid.weights, grid.vertices, 60_000))
    b = cut(reach.bounded(grid.edges, grid.weights, grid.vertices, 60_000, "block", grid.vertices, 4))
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()
    wide = cut(reach.bounded(grid.edges, grid.weights, grid.vertices, 120_000, "block", grid.vertices))
    assert a.join(wide, ["snap", "origin", "reached", "dist_ms"], "left_anti").isEmpty()
    slow = grid.weights.withColumn("w_ms", F.col("w_ms") + 1000)
    less = cut(reach.bounded(grid.edges, slow, grid.vertices, 60_000, "block", grid.vertices))
    assert less.join(a, ["snap", "origin", "reached"], "left_anti").isEmpty()
    assert hotspots.block_coef(hotspots.sizes(a)).filter("b < 1").isEmpty()


def test_hot_vertices_lie_apart(spark, grid):
    study = methods.Study(grid, 28, 60_000, 5)
    f = hotspots.fluctuation(study.block)
    hot = [r["vid"] for r in study.typical_vertices().orderBy("rank").collect()]
    value = {r["vid"]: r["f"] for r in f.collect()}
    assert [value[v] for v in hot] == sorted((value[v] for v in hot), reverse=True)
    wide = reach.bounded(grid.edges, grid.weights, grid.vertices, 120_000, "block", grid.vertices)
    cover = {}
    for r in wide.filter(F.col("origin").isin(hot)).select("origin", "reached").distinct().collect():
        cover.setdefault(r["origin"], set()).add(r["reached"])
    for i, v in enumerate(hot):
        assert not any(v in cover[u] for u in hot[:i])


def test_every_method_selects(grid):
    study = methods.Study(grid, 28, 60_000, 5, 16)
    for m in methods.METHODS:
        rows = methods.select_typical(study, m, 5).collect()
        assert sorted(r["snap"] for r in rows) == list(range(28)), m
        by = {r["snap"]: r for r in rows}
        assert all(by[r["typ"]]["typ"] == r["typ"] for r in rows), m
    curve = methods.curve(study, ("uniform", "vertex_set"), (28,)).collect()
    assert all(r["mean_err"] == 0 for r in curve)


def test_planted_day_ranks_methods(spark):
    """Uniform steps err most; at as many clusters as regimes, edge vectors find the regimes."""
    net = nets.planted_net(spark, "/root/testdata/sf0.001")
    study = methods.Study(net, 288, 60_000, 8, 32)
    c = {(r["method"], r["k"]): r["mean_err"] for r in methods.curve(study, ("uniform", "nonuniform", "edge_raw"), (4, 7, 12, 24)).collect()}
    for k in (7, 12, 24):
        assert c["uniform", k] > c["nonuniform", k] and c["uniform", k] > c["edge_raw", k]
    assert evaluate.purity(methods.select_typical(study, "edge_raw", 7), net.snapshots).first()["purity"] > 0.9


# ---------------------------------------------------------------- sources, streams, plans


def test_sources(spark, grid, tmp_path):
    for fmt in ("csv", "json", "orc", "parquet"):
        tables.save(grid.edges, f"{tmp_path}/{fmt}", fmt) if fmt != "csv" else grid.edges.write.option("header", True).csv(f"{tmp_path}/csv")
        assert tables.edge_list(spark, f"{tmp_path}/{fmt}", fmt).exceptAll(grid.edges.select("eid", "src", "dst", "length_m")).isEmpty()
    tables.save(grid.weights, f"{tmp_path}/w", by=["snap"])
    one = spark.read.parquet(f"{tmp_path}/w").filter("snap = 3")
    assert "PartitionFilters: [isnotnull(snap" in inspect.physical(one) and one.count() == 742


def test_late_rows_are_dropped(spark, tmp_path):
    from roadsnap.streaming import traffic

    schema = tables.SCHEMAS["events"]
    rows = lambda xs: spark.createDataFrame([(i, __import__("datetime").datetime(2024, 1, 1, h, m), 1, "x", 1.0, '{"k": 1}') for i, h, m in xs], schema)
    src = f"{tmp_path}/events"
    import os
    import time

    for n, part in enumerate(([(1, 0, 1), (2, 5, 0)], [(3, 6, 0)], [(4, 0, 2), (5, 6, 1)])):
        rows(part).coalesce(1).write.mode("append").parquet(src)
        time.sleep(1.1)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(src).withColumn("ts", F.col("ts").cast("timestamp"))
    out = traffic.run(traffic.tumbling(stream), "append").collect()
    assert sum(r["n"] for r in out) == 2  # events 1 and 2: 4 comes too late, 3 and 5 are still open
    assert os.path.isdir(src)


def test_functions_and_views_for_sql(spark, grid):
    from roadsnap.functions import udx

    udx.register(spark)
    udx.views(grid)
    assert spark.sql("SELECT l2(array(0D, 0D), array(3D, 4D)) AS d").first()["d"] == 5.0
    assert spark.sql("SELECT count(*) AS n FROM network_weights w JOIN network_edges e USING (eid) JOIN network_snapshots s USING (snap)").first()["n"] == 28 * 742


def test_plans(spark, sf, grid):
    lines = tables.table(spark, sf, "lineitem").filter("l_quantity > 45").select("l_orderkey")
    assert "GreaterThan(l_quantity,45.0)" in inspect.pushed_filters(lines)
    assert inspect.read_columns(lines) == ["l_orderkey:bigint,l_quantity:double"]
    assert inspect.exchanges(edgevec.cv(grid.weights)) == 1
    assert inspect.exchanges(paths.cost(grid.paths.hint("merge"), grid.weights)) == 3  # one on each side of the join, one for the sums
    assert inspect.exchanges(edgevec.weights(grid.weights)) == 0
    kernel = evaluate.error_matrix(spark.createDataFrame([(0, [1, 2])], "pid bigint, d array<bigint>"), 2)
    assert inspect.exchanges(kernel) == 1

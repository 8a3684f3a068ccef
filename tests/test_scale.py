"""Queries that were right on small tables only, or formed more rows than a larger table allows."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from roadsnap.functions.shared import cut
from roadsnap.operators import distances, edgevec, evaluate, hotspots, paths, reach, snapshots
from roadsnap.plans import methods, queries, queries_ops  # noqa: F401 - the import fills the registry
from roadsnap.sources import nets


def test_theta_sketch_beyond_its_nominal_size(spark, tmp_path):
    """150,000 customers in one year and half of them in the next; one order without a customer in each."""
    ids = spark.range(150_000).selectExpr("id", "id as o_custkey", "1995 as y").union(spark.range(0, 150_000, 2).selectExpr("id + 150000", "id", "1996"))
    ids = ids.union(spark.createDataFrame([(-1, None, 1995), (-2, None, 1996)], "id bigint, c bigint, y int"))
    orders = ids.selectExpr("id as o_orderkey", "o_custkey", "'O' as o_orderstatus", "1D as o_totalprice", "cast(make_date(y, 5, 1) as timestamp_ntz) as o_orderdate", "'5-LOW' as o_orderpriority")
    orders.write.parquet(f"{tmp_path}/orders.parquet")
    found = queries.QUERIES["op_theta_sketch"](spark, str(tmp_path)).collect()
    assert {tuple(r) for r in found} == {(1995, 150_001, 0), (1996, 75_001, 75_000)}


def test_costs_by_runs_equal_those_by_edges(spark):
    """Chains with gaps and doubled edges, long weights, paths of one run, without any edge, and with a missing id."""
    r = random.Random(6)
    edges = [(e, c, p, [r.choice((r.randrange(100), r.randrange(1 << 40))) for _ in range(3)]) for e, (c, p) in enumerate([(c, p) for c in range(5) for p in range(30) if r.random() < 0.7] + [(0, 3), (4, 9)])]
    legs = [(i, r.randrange(-1, 3), *sorted(r.sample(range(35), 2)), r.randrange(2, 6) if i % 9 else -2, *sorted(r.sample(range(35), 2))) for i in range(300)] + [(None, 1, 2, 2, 4, 9, 12)]
    want = {}
    for pid, *runs in legs:
        on = [w for c, lo, hi in (runs[:3], runs[3:]) for _, d, p, w in edges if d == c and lo <= p <= hi]
        if on:
            want[pid] = [sum(x) for x in zip(*on)]
    w = paths.coded(np.array([e[3] for e in edges])).to_pylist()
    places = spark.createDataFrame([(e, c, p, x) for (e, c, p, _), x in zip(edges, w)], "eid bigint, chain bigint, pos bigint, w binary")
    got = paths.cost_legs(spark.createDataFrame(legs, "pid bigint, c1 bigint, lo1 bigint, hi1 bigint, c2 bigint, lo2 bigint, hi2 bigint"), places).collect()
    assert len(got) == len(want) < len(legs) and {x["pid"]: x["d"] for x in got} == want
    assert {x["eid"]: x["w"] for x in paths.opened(places).collect()} == {e: x for e, _, _, x in edges}


def test_coded_rows_of_either_width():
    small, large = np.array([[1, -5], [2**31 - 1, 0]]), np.array([[2**31, 2**31 + 7]])
    both = pa.concat_arrays([paths.coded(small), paths.coded(large)])
    assert paths.decoded(both).tolist() == [*small.tolist(), *large.tolist()] and paths.decoded(both.slice(1, 2)).tolist() == [small[1].tolist(), large[0].tolist()]
    assert len(paths.coded(large)[0].as_py()) == 9 and len(paths.coded(large - 2**31)[0].as_py()) == 3


@pytest.mark.parametrize("name", ["path_costs_grid", "error_band_grid"])
def test_grid_costs_send_no_row_per_edge_of_a_path(spark, sf, name):
    """A path's edges are not listed, so nothing grows with their number."""
    plan = queries.QUERIES[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "explode(sequence" not in plan and "FlatMapCoGroupsInArrow" in plan


def test_shares_of_errors(spark):
    """Sums in doubles are those in integers, whatever the costs' size."""
    r = np.random.default_rng(8)
    for most in (2, 1000, 10**7, 9 * 10**9):
        d = r.integers(1, most, (500, 6))
        want = {(t, a): sum(abs(int(x[t]) - int(x[a])) * 10**9 // int(x[a]) for x in d) for t in range(6) for a in range(6)}
        got = evaluate.error_sums(spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(d)], "pid bigint, d array<bigint>"), 6).collect()
        assert {(x["typ"], x["act"]): x["s"] for x in got} == want


def test_pair_error_forms_no_row_per_pair_and_path(spark, sf):
    """No costs in long form: pairs are formed in the tasks that hold the paths."""
    plan = queries.QUERIES["pair_error_trade"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("MapInArrow") == 3  # edges' weights are added, then across batches, then errors


def test_studies_in_coded_form_equal_those_in_long_form(spark, sf):
    """Of the planted day: variation and inner products exactly, errors by edges and by runs; no weight by snapshot is written."""
    net = nets.planted_net(spark, sf)
    study = methods.Study(net, 288)
    methods.curve(study, ("edge_cv_pca",), (4,))
    assert "weights" not in study.held
    w = cut(net.weights)
    plain = methods.Study(nets.Network(net.vertices, net.edges, net.snapshots, w, net.paths), 288)
    both = lambda make: [sorted(map(tuple, make(s).collect())) for s in (study, plain)]
    assert len(set(map(str, both(lambda s: s.cvs)))) == 1
    assert len(set(map(str, both(lambda s: s.errors)))) == 1
    for delta in (False, True):
        a, b = (edgevec._matrix(s.edge_gram(delta, True), 288) for s in (study, plain))
        assert np.allclose(a, b, rtol=1e-12)


@pytest.mark.parametrize("fast", [0, 1])
def test_searches_in_coded_form_equal_those_in_long_form(spark, fast):
    """A map with a few long edges and one without outgoing arcs; weights of 0 and beyond the radius; few origins and all."""
    r, side, n, most = random.Random(4), 9, 5, 400
    at = [(v, v % side, v // side) for v in range(side * side)]
    ends = [(a, b) for a, x, y in at[:-1] for b, u, v in at if abs(x - u) + abs(y - v) == 1] + [(r.randrange(80), r.randrange(81)) for _ in range(6 if fast else 0)]
    w = [[r.choice((0, r.randrange(50, 300), 1 << 40)) if fast else r.randrange(60, 500) for _ in range(n)] for _ in ends]
    edges = spark.createDataFrame([(i, a, b, 1) for i, (a, b) in enumerate(ends)], "eid bigint, src bigint, dst bigint, length_m bigint")
    places = spark.createDataFrame([(i, 0, i, x) for i, x in enumerate(paths.coded(np.array(w)).to_pylist())], "eid bigint, chain bigint, pos bigint, w binary")
    v, rows = spark.createDataFrame(at, "vid bigint, x bigint, y bigint"), lambda df: sorted(map(tuple, df.collect()))

    def reached(s, o):
        best, todo = {o: 0}, [o]
        for x in todo:  # grows
            for (a, b), c in zip(ends, w):
                if a == x and best[x] + c[s] <= min(most, best.get(b, most + 1) - 1):
                    best[b] = best[x] + c[s]
                    todo.append(b)
        return best

    origins = range(len(at)) if not fast else (0, 40, 80)
    want = sorted((s, o, b, d) for s in range(n) for o in origins for b, d in reached(s, o).items())
    found = lambda emit: reach.bounded_coded(edges, places, v.filter(F.col("vid").isin(*origins)), most, v, n, emit, cell=4)
    assert rows(found("sets")) == want
    assert rows(found("ever")) == sorted({x[1:3] for x in want})
    size, sets = cut(found("sizes")), spark.createDataFrame(want, "snap int, origin bigint, reached bigint, dist_ms bigint")
    assert rows(hotspots.sizes_of_coded(size)) == rows(hotspots.sizes(sets).select("snap", "vid", "size"))
    assert rows(hotspots.fluctuation_coded(size)) == rows(hotspots.fluctuation(hotspots.block_coef(hotspots.sizes(sets))))


def test_vertex_studies_write_no_weight_by_snapshot(spark, sf):
    """Errors at each k are those of the selections by name, and no weights in long form are read."""
    study, kinds = queries.planted_study(spark, sf, 6), ("vertex_set", "vertex_bc_hier", "vertex_bc_kmeans")
    got = [tuple(x) for x in methods.curve(study, kinds, (4, 9), 5).collect()]
    assert "weights" not in study.held
    assert got == [methods.measured(study, m, methods.select_typical(study, m, k, 5), k, 5) for m in kinds for k in (4, 9)]


def test_close_classes_lose_no_link_and_expand_no_copies(spark, monkeypatch):
    """Many copies, sizes over several blocks and bands: links of all pairs follow from classes; each other copy has one row."""
    monkeypatch.setattr(distances, "BLOCK", 200)
    r = random.Random(3)
    pool = [r.sample(range(r.choice((6, 40))), r.randrange(1, 6)) if r.random() < 0.6 else r.sample(range(60), r.randrange(10, 45)) for _ in range(80)]
    data = [(i, r.choice("ab"), r.sample(p, len(p))) for i, p in enumerate(r.choices(pool, k=160))] + [(500, "a", []), (501, None, [1]), (502, "a", None), *((i, "a", [1, 2]) for i in range(600, 700))]
    sets = {i: (k, frozenset(m)) for i, k, m in data if k and m}
    least = {}
    for i in sorted(sets):
        least.setdefault(sets[i], i)
    jaccard = lambda x, y: round(1 - len(x & y) / len(x | y), 6)
    want = {(a, b): jaccard(sets[a][1], sets[b][1]) for a in least.values() for b in least.values() if a < b and sets[a][0] == sets[b][0] and 2 * len(sets[a][1] & sets[b][1]) >= len(sets[a][1] | sets[b][1])}
    want |= {(least[x], i): 0.0 for i, x in sets.items() if least[x] != i}
    got = distances.close_classes(spark.createDataFrame(data, "id bigint, kind string, members array<int>"), 0.5).collect()
    assert len(got) == len(want) and {(x["a"], x["b"]): x["dist"] for x in got} == want


def test_replayed_events_do_not_pass_through_the_driver(spark, sf, monkeypatch):
    """A source's rows are formed on the driver: it tells a row per snapshot, and executors read the events."""
    seen = []
    monkeypatch.setattr(queries.traffic, "answer_stream", lambda places, *_: seen.append(places))
    queries.stream_to_answer(spark, sf, 28)
    source = [x for x in seen[0]._jdf.queryExecution().analyzed().toString().splitlines() if "Streaming" in x]
    assert seen[0].isStreaming and len(source) == 1 and "snap" in source[0] and "obs_ms" not in source[0] and "event_id" not in source[0]


def test_matching_time_reads_no_weight_by_snapshot(spark, sf, monkeypatch):
    """Paths, sets and the new snapshot come from weights in coded form; networks have no others here."""
    monkeypatch.setattr(nets, "_weights", lambda places: None)
    rows = [tuple(x) for x in queries.QUERIES["w5_matching_time"](spark, sf).collect()]
    assert [x[:2] for x in rows if x[1] >= 10] == [(f, k) for f in ("edge", "vertex") for k in (10, 20, 40, 80)]


def test_one_snapshot_of_coded_weights(spark, sf):
    net = nets.planted_net(spark, sf)
    places = cut(net.places)
    rows = lambda df: sorted(map(tuple, df.select("snap", "eid", "w_ms").collect()))
    assert rows(snapshots.at(places, 100)) == rows(nets._weights(places).filter("snap = 100"))
    assert rows(reach.least_coded(places)) == rows(reach.least(nets._weights(places)))

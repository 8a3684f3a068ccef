"""Shortest paths on a snapshot, indexes of typical snapshots, and answers from the matched index."""

from __future__ import annotations

import heapq

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.shared import cut
from . import reach

FAR = 1 << 60


def distances(edges: DataFrame, weights: DataFrame, queries: DataFrame) -> DataFrame:
    """(snap, s, t, dist) without an index: label-correcting rounds from the distinct sources; null if unreachable."""
    sources = queries.select(F.col("s").alias("vid")).distinct()
    found = reach.bounded(edges, weights, sources, FAR).select("snap", F.col("origin").alias("s"), F.col("reached").alias("t"), F.col("dist_ms").alias("dist"))
    asked = weights.select("snap").distinct().crossJoin(queries.select("s", "t").distinct())
    return asked.join(found, ["snap", "s", "t"], "left")


def all_pairs(edges: DataFrame, weights: DataFrame, vertices: DataFrame) -> DataFrame:
    """(typ, s, t, dist): the complete table, for small networks."""
    found = reach.bounded(edges, weights, vertices, FAR)
    return found.select(F.col("snap").alias("typ"), F.col("origin").alias("s"), F.col("reached").alias("t"), F.col("dist_ms").alias("dist"))


def _graphs(table):
    out, back = {}, {}
    for e, s, d, w in zip(*(table.column(c).to_pylist() for c in ("eid", "src", "dst", "w_ms"))):
        out.setdefault(s, []).append((d, w, e))
        back.setdefault(d, []).append((s, w, e))
    return out, back


def _labels(key, table):
    """Two-hop labels by pruned searches from vertices in order of degree; one task per snapshot."""
    out, back = _graphs(table)
    vertices = sorted(out.keys() | back.keys(), key=lambda v: (-(len(out.get(v, ())) + len(back.get(v, ()))), v))
    to_hub, from_hub = {v: {} for v in vertices}, {v: {} for v in vertices}
    for hub in vertices:
        for graph, mine, theirs in ((out, from_hub, to_hub), (back, to_hub, from_hub)):
            # distances from the hub (to the hub on the reversed graph)
            own, done, heap = theirs[hub], set(), [(0, hub)]
            while heap:
                d, v = heapq.heappop(heap)
                if v in done:
                    continue
                done.add(v)
                label = mine[v]
                if any(h in own and own[h] + x <= d for h, x in label.items()):
                    continue
                label[hub] = d
                for u, w, _ in graph.get(v, ()):
                    if u not in done:
                        heapq.heappush(heap, (d + w, u))
    rows = [(v, h, d, side) for side, labels in (("out", to_hub), ("in", from_hub)) for v, each in labels.items() for h, d in each.items()]
    v, h, d, side = zip(*rows) if rows else ((), (), (), ())
    return pa.table([pa.array([key[0].as_py()] * len(v), pa.int32()), pa.array(v, pa.int64()), pa.array(h, pa.int64()), pa.array(d, pa.int64()), pa.array(side, pa.string())], names=["typ", "v", "hub", "dist", "side"])


def hub_labels(edges: DataFrame, weights: DataFrame) -> DataFrame:
    """(typ, v, hub, dist, side): side 'out' is from v to the hub, 'in' from the hub to v."""
    arcs = weights.join(edges.select("eid", "src", "dst"), "eid").select(F.col("snap").alias("typ"), "eid", "src", "dst", "w_ms")
    return arcs.groupBy("typ").applyInArrow(_labels, "typ int, v bigint, hub bigint, dist bigint, side string")


def answer(queries: DataFrame, labels: DataFrame) -> DataFrame:
    """(typ, s, t, dist) of queries (typ, s, t): least sum over common hubs; null if there is none."""
    a = labels.filter("side = 'out'").select("typ", F.col("v").alias("s"), "hub", F.col("dist").alias("x"))
    b = labels.filter("side = 'in'").select("typ", F.col("v").alias("t"), "hub", F.col("dist").alias("y"))
    best = queries.select("typ", "s", "t").distinct().join(a, ["typ", "s"]).join(b, ["typ", "t", "hub"]).groupBy("typ", "s", "t").agg(F.min(F.col("x") + F.col("y")).alias("dist"))
    return queries.select("typ", "s", "t").join(best, ["typ", "s", "t"], "left")


def shortest_paths(edges: DataFrame, weights: DataFrame, queries: DataFrame, places: DataFrame | None = None, blocks: int = 4) -> DataFrame:
    """(snap, s, t, dist, edges): the ways themselves, by heap searches in one task per snapshot and block of sources.

    `queries` (s, t) are asked of every snapshot; they are dealt to blocks by their sources, and each block's task gets the
    snapshot's graph.  With `places` (vid, x, y) the search is guided by the grid distance times the least
    weight per step, which never exceeds the rest of the way; the answers are the same.
    """
    arcs = weights.join(edges.select("eid", "src", "dst"), "eid").select("snap", "eid", "src", "dst", "w_ms")
    if places is not None:
        a, b = places.selectExpr("vid as src", "x as xa", "y as ya"), places.selectExpr("vid as dst", "x as xb", "y as yb")
        arcs = arcs.join(a, "src").join(b, "dst")
    spark = edges.sparkSession
    graph = arcs.crossJoin(F.broadcast(spark.range(blocks).select(F.col("id").cast("int").alias("block"))))
    asked = queries.select("s", "t").distinct().withColumn("block", F.pmod(F.xxhash64("s"), F.lit(blocks)).cast("int"))
    snaps = weights.select(F.col("snap").alias("of")).distinct()  # a row per snapshot
    asked = asked.select("s", "t", F.col("block").alias("part")).crossJoin(F.broadcast(snaps))

    def run(key, table, wanted):
        out, _ = _graphs(table)
        at = {}
        if "xa" in table.column_names:
            cols = {c: table.column(c).to_pylist() for c in ("src", "xa", "ya", "dst", "xb", "yb")}
            at = {**dict(zip(cols["src"], zip(cols["xa"], cols["ya"]))), **dict(zip(cols["dst"], zip(cols["xb"], cols["yb"])))}
        least = min((w for vs in out.values() for _, w, _ in vs), default=0)
        rows = []
        for s, t in sorted(zip(wanted.column("s").to_pylist(), wanted.column("t").to_pylist())):
            guide = (lambda v: 0) if t not in at else (lambda v: least * (abs(at[v][0] - at[t][0]) + abs(at[v][1] - at[t][1])))
            dist, via, done, heap = {s: 0}, {}, set(), [(guide(s) if s in at else 0, s)]
            while heap:
                _, v = heapq.heappop(heap)
                if v == t:
                    break
                if v in done:
                    continue
                done.add(v)
                for u, w, e in out.get(v, ()):
                    d = dist[v] + w
                    if d < dist.get(u, FAR):
                        dist[u], via[u] = d, (v, e)
                        heapq.heappush(heap, (d + guide(u), u))
            way, v = [], t
            while v != s and v in via:
                v, e = via[v]
                way.append(e)
            rows.append((s, t, dist.get(t), way[::-1] if t in dist else None))
        s, t, d, way = zip(*rows) if rows else ((), (), (), ())
        snap = (wanted.column("of") if wanted.num_rows else table.column("snap"))[0].as_py()
        return pa.table([pa.array([snap] * len(s), pa.int32()), pa.array(s, pa.int64()), pa.array(t, pa.int64()), pa.array(d, pa.int64()), pa.array(way, pa.list_(pa.int64()))], names=["snap", "s", "t", "dist", "edges"])

    return graph.groupBy("snap", "block").cogroup(asked.groupBy("of", "part")).applyInArrow(run, "snap int, s bigint, t bigint, dist bigint, edges array<bigint>")


def regret(ways: DataFrame, typical: DataFrame, weights: DataFrame, actual: DataFrame) -> DataFrame:
    """(snap, queries, regret): cost under actual weights of the typical snapshot's ways over the optimum, less 1, on average.

    `ways` are (snap = typical, s, t, edges); `typical` is (snap, typ); `actual` is (snap, s, t, dist).
    """
    step = typical.join(ways.select(F.col("snap").alias("typ"), "s", "t", F.explode("edges").alias("eid")), "typ")
    paid = step.join(weights, ["snap", "eid"]).groupBy("snap", "s", "t").agg(F.sum("w_ms").alias("paid"))
    both = paid.join(actual.select("snap", "s", "t", "dist"), ["snap", "s", "t"]).filter("dist > 0")
    return both.groupBy("snap").agg(F.count("*").alias("queries"), F.round(F.sum(F.expr("(paid - dist) * 1000000000 div dist")) / F.count("*") / 1e9, 6).alias("regret"))


def index_size(labels: DataFrame) -> DataFrame:
    """(typ, rows, bytes): entries of each index and what they take as three 8-byte numbers and a side mark."""
    return labels.groupBy("typ").agg(F.count("*").alias("rows"), (F.count("*") * 25).alias("bytes"))

"""Vertices that can be reached from chosen origins within a travel time, in every snapshot."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from ..functions.shared import cut, drop
from .paths import coded, decoded

FAR = np.iinfo(np.int64).max


def arcs(edges: DataFrame, weights: DataFrame) -> DataFrame:
    return weights.join(edges.select("eid", "src", "dst"), "eid").select("snap", "src", "dst", "w_ms")


def bounded(edges: DataFrame, weights: DataFrame, origins: DataFrame, r_ms: int, engine: str = "loop", vertices: DataFrame | None = None, cell: int = 16) -> DataFrame:
    """(snap, origin, reached, dist_ms) with dist_ms <= r_ms; every origin reaches itself.

    loop: rounds of one join and one aggregate on (snap, at).  block: vertices are cut to cells of the map, and one exchange
    brings each cell what its origins can ever reach, to be searched in one kernel.  Both hold for any graph with
    weights of 0 or more and give the same rows.
    """
    if engine == "block":
        return _blocks(edges, weights, origins, r_ms, vertices, cell)
    front = weights.select("snap").distinct().crossJoin(origins.select(F.col("vid").alias("origin"))).select("snap", "origin", F.col("origin").alias("reached"), F.lit(0).cast("bigint").alias("dist_ms"))
    arc = cut(arcs(edges, weights))
    best = _rounds(front, arc, ["snap", "origin"], ["snap"], r_ms)
    drop(arc)
    return best


def sizes(edges: DataFrame, weights: DataFrame, origins: DataFrame, r_ms: int, vertices: DataFrame, cell: int = 16) -> DataFrame:
    """(snap, vid, size): how many vertices each origin reaches. The sets stay in the kernels; only counts are written."""
    return _blocks(edges, weights, origins, r_ms, vertices, cell, "sizes")


def _rounds(front, arc, keys, on, r_ms):
    """Label correcting: (keys, reached, dist_ms) from a front of such rows and arcs (on, src, dst, w_ms)."""
    arc = arc.withColumnRenamed("src", "reached")
    best = front = cut(front)
    while True:
        step = front.join(arc, [*on, "reached"]).select(*keys, F.col("dst").alias("reached"), (F.col("dist_ms") + F.col("w_ms")).alias("dist_ms"))
        step = step.filter(F.col("dist_ms") <= r_ms).groupBy(*keys, "reached").agg(F.min("dist_ms").alias("dist_ms"))
        known = best.withColumnRenamed("dist_ms", "had")
        new = cut(step.join(known, [*keys, "reached"], "left").filter("had is null or dist_ms < had").drop("had"))
        if new.isEmpty():
            drop(new)
            return best
        better = cut(best.unionByName(new).groupBy(*keys, "reached").agg(F.min("dist_ms").alias("dist_ms")))
        drop(*({id(x): x for x in (best, front)}.values()))
        best, front = better, new


def hops(edges: DataFrame, origins: DataFrame, n: int) -> DataFrame:
    """(origin, reached, hop): a search by number of edges, as a contrast; all weights are one."""
    unit = edges.select("eid", F.lit(0).alias("snap"), F.lit(1).cast("bigint").alias("w_ms"))
    return bounded(edges, unit, origins, n).select("origin", "reached", F.col("dist_ms").alias("hop"))


def least(weights: DataFrame) -> DataFrame:
    """(snap = 0, eid, w_ms): each edge's least weight over all snapshots, below which no search can be faster."""
    return weights.groupBy("eid").agg(F.min("w_ms").alias("w_ms")).select(F.lit(0).alias("snap"), "eid", "w_ms")


#: A halo of so many cells at most is cut out by coordinates; what reaches further is searched for cell by cell.
WIDE = 4


def _blocks(edges, weights, origins, r_ms, vertices, cell, emit="sets"):
    """Two passes: on each edge's least weight, what a cell's origins can ever reach; then every snapshot on just that."""
    near, mine = _reachable(edges, cut(least(weights)), origins, r_ms, vertices, cell)
    return _search(arcs(edges, weights), near, mine, weights.select("snap").distinct(), r_ms, emit)


def _reachable(edges, floor, origins, r_ms, vertices, cell):
    """(src, cx, cy) of vertices whose outgoing arcs a cell needs, and (cx, cy, src) of its origins, from edges' least weights.

    No way of travel time r leads further than r over the least travel time per step of the map (an edge's
    least weight over the larger of its two coordinate differences).  Where that halo is narrow it is cut out by
    coordinates; where some edge is long or fast, rounds over whole cells tell the same.
    """
    at = vertices.select("vid", "x", "y")
    slow = arcs(edges, floor)
    a, b = at.selectExpr("vid as src", "x as xa", "y as ya"), at.selectExpr("vid as dst", "x as xb", "y as yb")
    step = F.greatest(F.abs(F.col("xa") - F.col("xb")), F.abs(F.col("ya") - F.col("yb")))
    rate = slow.join(a, "src").join(b, "dst").select("w_ms", step.alias("step")).filter("step > 0 and w_ms <= " + str(int(r_ms))).agg(F.min(F.col("w_ms") / F.col("step"))).first()[0]
    halo = 0 if rate is None else None if rate <= 0 or r_ms / rate > WIDE * cell else int(r_ms / rate) + 1
    place = lambda c: F.floor(F.col(c) / cell).cast("bigint")
    mine = cut(origins.select("vid").distinct().join(at, "vid").select(place("x").alias("cx"), place("y").alias("cy"), F.col("vid").alias("src")))
    if halo is None:
        start = mine.select("cx", "cy", F.col("src").alias("reached"), F.lit(0).cast("bigint").alias("dist_ms"))
        near = _rounds(start, cut(slow.drop("snap")), ["cx", "cy"], [], r_ms).select(F.col("reached").alias("src"), "cx", "cy")
    else:
        span = lambda c: F.explode(F.sequence(F.floor((F.col(c) - halo) / cell).cast("bigint"), F.floor((F.col(c) + halo) / cell).cast("bigint")))
        near = at.select(F.col("vid").alias("src"), span("x").alias("cx"), "y").select("src", "cx", span("y").alias("cy"))
        near = near.join(mine.select("cx", "cy").distinct(), ["cx", "cy"], "left_semi").select("src", "cx", "cy")
        ever = _search(slow, near, mine, floor.select("snap").distinct(), r_ms)
        near = cut(ever.join(mine.withColumnRenamed("src", "origin"), "origin").select(F.col("reached").alias("src"), "cx", "cy").distinct())
    return near, mine


def neighbourhood(edges: DataFrame, weights: DataFrame, origins: DataFrame, r_ms: int, slack: float = 0.5) -> DataFrame:
    """(eid, src, dst, lower): the edges that any origin can use within r_ms, for searches in snapshots still to come.

    They may be faster than all of `weights`, but not below `lower`, the least weight times `slack`.
    """
    floor = least(weights).select("eid", F.floor(F.col("w_ms") * slack).cast("bigint").alias("lower"))
    arc = cut(edges.select("eid", "src", "dst").join(floor, "eid"))
    start = origins.select(F.lit(0).alias("all"), F.col("vid").alias("reached"), F.lit(0).cast("bigint").alias("dist_ms"))
    ever = _rounds(start, arc.select("src", "dst", F.col("lower").alias("w_ms")), ["all"], [], r_ms)
    return arc.join(ever.select(F.col("reached").alias("src")), "src", "left_semi")


def around(near: DataFrame, weights: DataFrame, origins: DataFrame, r_ms: int) -> DataFrame:
    """(snap, origin, reached, dist_ms) of few origins in new snapshots, on their neighbourhood(): one task per snapshot.

    A weight below the neighbourhood's bound raises an error, as the search might then leave it.
    """
    below = F.raise_error("a weight is below the bound of the neighbourhood: build it anew").cast("bigint")
    few = weights.join(F.broadcast(near), "eid")  # q vertices and what is around them
    rows = few.select("snap", F.lit(0).alias("cx"), F.lit(0).alias("cy"), "src", "dst", F.when(F.col("w_ms") < F.col("lower"), below).otherwise(F.col("w_ms")).alias("w_ms"))
    mine = origins.select(F.lit(0).alias("cx"), F.lit(0).alias("cy"), F.col("vid").alias("src"))
    return _kernel(rows, mine, weights.select("snap").distinct(), r_ms, "sets")


def _search(spread, near, mine, snaps, r_ms, emit="sets"):
    """One task for each snapshot and cell: `near` tells whose outgoing arcs a cell needs, `mine` its origins."""
    return _kernel(spread.join(near, "src").select("snap", "cx", "cy", "src", "dst", "w_ms"), mine, snaps, r_ms, emit)


#: Cells of the dense (origin, vertex) table that are worked on at once.
DENSE = 1 << 22


def _kernel(rows, mine, snaps, r_ms, emit):
    null = F.lit(None).cast("bigint")
    wanted = mine.crossJoin(snaps).select("snap", "cx", "cy", "src", null.alias("dst"), null.alias("w_ms"))

    def search(key, table):
        """Origins of a cell together: a dense (origin, vertex) table and rounds over what just improved."""
        src, w = table.column("src").to_numpy(), table.column("w_ms").to_numpy()
        dst = table.column("dst").to_numpy()
        own = np.asarray(table.column("dst").is_null())
        ids = np.unique(np.concatenate([src, dst[~own].astype(np.int64)]))
        tail, head = np.searchsorted(ids, src[~own]), np.searchsorted(ids, dst[~own].astype(np.int64))
        order = np.argsort(tail, kind="stable")
        head, cost = head[order], w[~own][order].astype(np.int64)
        first = np.searchsorted(tail[order], np.arange(len(ids) + 1))
        m, every = len(ids), np.unique(np.searchsorted(ids, src[own]))
        out, some = [], max(1, DENSE // max(1, m))
        for lo in range(0, len(every), some):
            at = every[lo : lo + some]
            best = np.full(len(at) * m, FAR, np.int64)
            front = np.arange(len(at)) * m + at
            best[front] = 0
            while len(front):
                v = front % m
                deg = first[v + 1] - first[v]
                arc = np.arange(deg.sum()) + np.repeat(first[v] - np.concatenate([[0], np.cumsum(deg)[:-1]]), deg)
                reach_ = np.repeat(best[front], deg) + cost[arc]
                to = np.repeat(front - v, deg) + head[arc]
                better = (reach_ <= r_ms) & (reach_ < best[to])
                to, reach_ = to[better], reach_[better]
                np.minimum.at(best, to, reach_)
                front = np.unique(to)
            if emit == "sizes":
                out.append((ids[at], (best.reshape(len(at), m) < FAR).sum(1)))
            else:
                hit = np.flatnonzero(best < FAR)
                out.append((ids[at[hit // m]], ids[hit % m], best[hit]))
        cols = [np.concatenate(c) for c in zip(*out)] if out else [np.empty(0, np.int64)] * (2 if emit == "sizes" else 3)
        snap = pa.array(np.full(len(cols[0]), key[0].as_py()), pa.int32())
        return pa.table([snap, *(pa.array(c, pa.int64()) for c in cols)], names=names)

    names = ["snap", "vid", "size"] if emit == "sizes" else ["snap", "origin", "reached", "dist_ms"]
    return rows.unionByName(wanted).groupBy("snap", "cx", "cy").applyInArrow(search, ", ".join(f"{n} {'int' if n == 'snap' else 'bigint'}" for n in names))


# ---------------------------------------------------------------- weights in coded form


def least_coded(places: DataFrame) -> DataFrame:
    """least() of weights in coded form."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array(np.zeros(b.num_rows, np.int32)), b.column("eid"), pa.array(decoded(b.column("w")).min(1))], names=["snap", "eid", "w_ms"])

    return places.select("eid", "w").mapInArrow(run, "snap int, eid bigint, w_ms bigint")


def bounded_coded(edges: DataFrame, places: DataFrame, origins: DataFrame, r_ms: int, vertices: DataFrame, n: int, emit: str = "sets", floor: DataFrame | None = None, cell: int = 32) -> DataFrame:
    """bounded() and sizes() from weights of n snapshots in coded form: a task searches all snapshots of a cell at once.

    sets: (snap, origin, reached, dist_ms); ever: (origin, reached) of what is reached in any snapshot; sizes: (vid, w), numbers of reached
    vertices in snapshot order, coded.  A row per edge and cell travels; `floor`, edges' least weights, is made once where several searches need it.
    """
    near, mine = _reachable(edges, cut(least_coded(places)) if floor is None else floor, origins, r_ms, vertices, cell)
    arc = places.select("eid", "w").join(edges.select("eid", "src", "dst"), "eid").join(near.select("src").distinct(), "src", "left_semi")

    def clip(batches):
        """What is longer than r is of no use, and takes fewer bytes when it is cut to r + 1."""
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column("src"), b.column("dst"), coded(np.minimum(decoded(b.column("w")), r_ms + 1))], names=["src", "dst", "w"])

    rows = arc.select("src", "dst", "w").mapInArrow(clip, "src bigint, dst bigint, w binary").join(near, "src").select("cx", "cy", "src", "dst", "w")
    wanted = mine.select("cx", "cy", "src", F.lit(None).cast("bigint").alias("dst"), F.lit(None).cast("binary").alias("w"))
    form = {"sets": "snap int, origin bigint, reached bigint, dist_ms bigint", "ever": "origin bigint, reached bigint", "sizes": "vid bigint, w binary"}[emit]
    return rows.unionByName(wanted).groupBy("cx", "cy").applyInArrow(lambda table: _all_snapshots(table, r_ms, n, emit), form)


#: Travel times, of arcs times snapshots, that are added at once.
AT_ONCE = 1 << 20


def _all_snapshots(table: pa.Table, r_ms: int, n: int, emit: str) -> pa.Table:
    """Origins of a cell together: a row of n travel times for each vertex that an origin reaches in any snapshot."""
    table = table.combine_chunks()
    own = table.filter(pc.is_null(table.column("dst"))).column("src").to_numpy()
    table = table.filter(pc.is_valid(table.column("dst")))
    src, dst = table.column("src").to_numpy(), table.column("dst").to_numpy()
    kind = np.int32 if r_ms < 1 << 29 else np.int64
    far = r_ms + 1  # also where a sum is larger
    ids = np.unique(np.concatenate([src, dst, own]))
    tail, head = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    order = np.argsort(tail, kind="stable")
    head, cost = head[order], (decoded(table.column("w"))[order] if len(src) else np.zeros((0, n))).astype(kind)
    first = np.searchsorted(tail[order], np.arange(len(ids) + 1))
    m, every, out = len(ids), np.unique(np.searchsorted(ids, own)), []
    some = max(1, min(64, DENSE // max(1, m)))
    for lo in range(0, len(every), some):
        at = every[lo : lo + some]
        row_of = np.full(len(at) * m, -1, np.int64)  # of an (origin, vertex) its row in best
        state = np.arange(len(at)) * m + at  # and back
        best = np.zeros((len(at), n), kind)
        row_of[state] = np.arange(len(at))
        front = np.arange(len(at))
        while len(front):
            deg = first[state[front] % m + 1] - first[state[front] % m]
            improved = []
            for part in np.array_split(front, max(1, int(deg.sum()) * n // AT_ONCE)):
                v = state[part] % m
                deg = first[v + 1] - first[v]
                arc = np.arange(deg.sum()) + np.repeat(first[v] - np.cumsum(deg) + deg, deg)
                to = np.repeat(state[part] - v, deg) + head[arc]
                order = np.argsort(to, kind="stable")
                to, begin = np.unique(to[order], return_index=True)
                if not len(to):
                    continue
                took = best[np.repeat(part, deg)[order]] + cost[arc[order]]
                took = np.minimum(np.minimum.reduceat(took, begin, 0), far)
                row = row_of[to]
                had = best[row]
                had[row < 0] = far
                better = (took < had).any(1)
                to, row, took = to[better], row[better], np.minimum(took, had)[better]
                new = np.flatnonzero(row < 0)
                row[new] = len(state) + np.arange(len(new))
                row_of[to[new]] = row[new]
                state = np.concatenate([state, to[new]])
                if len(state) > len(best):
                    best = np.concatenate([best, np.empty((max(len(best), len(state) - len(best)), n), kind)])
                best[row] = took
                improved.append(row)
            front = np.unique(np.concatenate(improved)) if improved else front[:0]
        origin, within = state // m, best[: len(state)]
        if emit == "sizes":
            order = np.argsort(origin, kind="stable")
            out.append((ids[at], np.add.reduceat(within[order] <= r_ms, np.searchsorted(origin[order], np.arange(len(at))), 0, dtype=np.int64)))
        elif emit == "ever":
            out.append((ids[at[origin]], ids[state % m]))
        else:
            row, snap = np.nonzero(within <= r_ms)
            out.append((snap.astype(np.int32), ids[at[origin[row]]], ids[state[row] % m], within[row, snap].astype(np.int64)))
    cols = [np.concatenate(c) for c in zip(*out)]
    if emit == "sizes":
        return pa.table([pa.array(cols[0]), coded(cols[1])], names=["vid", "w"]) if out else pa.table([pa.array([], pa.int64()), pa.array([], pa.binary())], names=["vid", "w"])
    kinds = [pa.int32()] * (emit == "sets") + [pa.int64()] * (3 if emit == "sets" else 2)
    names = ["snap", "origin", "reached", "dist_ms"] if emit == "sets" else ["origin", "reached"]
    return pa.table([pa.array(c, k) for c, k in zip(cols or [[]] * len(kinds), kinds)], names=names)

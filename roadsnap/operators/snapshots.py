"""Cutting observations to snapshots, speed profiles, filling of unseen cells, and the topology check."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F


def slot(ts: Column, minutes: int) -> Column:
    """Ordinal of the time-of-day slot that a timestamp lies in."""
    return ((F.hour(ts) * 60 + F.minute(ts)) / minutes).cast("int")


def profile(moves: DataFrame, stat: str = "mean") -> DataFrame:
    """Observations (snap, eid, obs_ms) to travel times (snap, eid, w_ms); stat: mean, median or trimmed mean."""
    if stat == "mean":
        value = F.expr("sum(obs_ms) div count(*)")
    elif stat == "median":
        value = F.floor(F.percentile("obs_ms", F.lit(0.5))).cast("bigint")
    elif stat == "trimmed":
        ordered, cut = F.array_sort(F.collect_list("obs_ms")), F.expr("cast(count(*) div 10 as int)")
        inner = F.slice(ordered, cut + 1, F.count("*").cast("int") - 2 * cut)
        value = F.floor(F.aggregate(inner, F.lit(0).cast("bigint"), lambda a, x: a + x) / F.size(inner)).cast("bigint")
    else:
        raise ValueError(f"unknown statistic {stat!r}")
    return moves.groupBy("snap", "eid").agg(value.alias("w_ms"))


def fill(seen: DataFrame, edges: DataFrame, snapshots: DataFrame, of_edge: DataFrame, of_net: DataFrame) -> DataFrame:
    """Weights for every snapshot and edge: as seen, else the edge's value over all time, else the network's."""
    skeleton = edges.select("eid").crossJoin(F.broadcast(snapshots.select("snap")))
    full = skeleton.join(seen, ["snap", "eid"], "left").join(of_edge, "eid", "left").crossJoin(F.broadcast(of_net))
    return full.select("snap", "eid", F.coalesce("w_ms", "edge_ms", "net_ms").cast("bigint").alias("w_ms"))


def unknown_edges(weights: DataFrame, edges: DataFrame) -> DataFrame:
    """Weights of edges that the topology lacks."""
    return weights.join(edges.select("eid"), "eid", "left_anti")


def missing_cells(weights: DataFrame, edges: DataFrame, snapshots: DataFrame) -> DataFrame:
    """(snap, eid) that have no weight."""
    return snapshots.select("snap").crossJoin(edges.select("eid")).join(weights, ["snap", "eid"], "left_anti")


def packed(weights: DataFrame) -> DataFrame:
    """Storage form (eid, w): one row per edge with its weights in snapshot order."""
    pairs = F.array_sort(F.collect_list(F.struct("snap", "w_ms")))
    return weights.groupBy("eid").agg(F.transform(pairs, lambda p: p["w_ms"]).alias("w"))


def unpacked(rows: DataFrame) -> DataFrame:
    return rows.select("eid", F.posexplode("w").alias("snap", "w_ms")).select("snap", "eid", "w_ms")


def at(places: DataFrame, snap: int) -> DataFrame:
    """(snap, eid, w_ms) of one snapshot, of weights in coded form."""
    import numpy as np
    import pyarrow as pa

    from .paths import decoded

    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array(np.full(b.num_rows, snap, np.int32)), b.column("eid"), pa.array(decoded(b.column("w"))[:, snap])], names=["snap", "eid", "w_ms"])

    return places.select("eid", "w").mapInArrow(run, "snap int, eid bigint, w_ms bigint")

"""Matching a new snapshot to the typical ones, and opening a new typical one where none is close."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, functions as F

from . import distances, hotspots, paths, reach


def represent_edges(typical_paths: DataFrame, weights: DataFrame) -> DataFrame:
    """Edge form of new snapshots: travel times of the typical paths."""
    return paths.represent(typical_paths, weights)


def represent_vertices(edges: DataFrame, weights: DataFrame, typical: DataFrame, r_ms: int, largest: DataFrame | None = None, kind: str = "set", near: DataFrame | None = None) -> DataFrame:
    """Vertex form of new snapshots: as many bounded searches as there are typical vertices.

    `near`, the typical vertices' reach.neighbourhood(), is made once with the model; with it all searches of a snapshot
    run in one kernel over the few edges that they can use, and without it they run on the whole network.
    """
    if near is None:
        reached = reach.bounded(edges, weights, typical.select("vid"), r_ms)
    else:
        reached = reach.around(near, weights, typical.select("vid"), r_ms)
    if kind == "set":
        return hotspots.rep_set(reached, typical)
    return hotspots.rep_bc(hotspots.block_coef(hotspots.sizes(reached), largest), typical)


def nearest(new: DataFrame, typical: DataFrame) -> DataFrame:
    """(snap, typ, dist): the closest typical vector of each new one; ties to the smaller id."""
    far = distances.euclidean(new, typical)
    return far.groupBy(F.col("i").alias("snap")).agg(F.min(F.struct("dist", F.col("j").alias("typ"))).alias("best")).select("snap", "best.typ", "best.dist")


def nearest_sets(new: DataFrame, typical: DataFrame) -> DataFrame:
    """(snap, typ, dist): the closest typical set family, by the mean Jaccard distance."""
    size = lambda rep, s, n: rep.groupBy(F.col("snap").alias(s), "vid").agg(F.count("*").alias(n))
    a, b = new.select(F.col("snap").alias("i"), "vid", "reached"), typical.select(F.col("snap").alias("j"), "vid", "reached")
    both = a.join(b, ["vid", "reached"]).groupBy("i", "j", "vid").agg(F.count("*").alias("both"))
    cell = both.join(size(new, "i", "ni"), ["i", "vid"]).join(size(typical, "j", "nj"), ["j", "vid"])
    far = cell.groupBy("i", "j").agg(F.round(1 - F.sum(F.expr("both * 1000000000 div (ni + nj - both)")) / F.count("*") / 1e9, 6).alias("dist"))
    return far.groupBy(F.col("i").alias("snap")).agg(F.min(F.struct("dist", F.col("j").alias("typ"))).alias("best")).select("snap", "best.typ", "best.dist")


def decide(matched: DataFrame, tau: float) -> DataFrame:
    """Adds is_new: nothing typical lies within tau, so the snapshot becomes typical itself."""
    new = F.col("dist") > tau
    return matched.select("snap", F.when(new, F.col("snap")).otherwise(F.col("typ")).alias("typ"), "dist", new.alias("is_new"))


def decide_in_order(rep: DataFrame, typical: DataFrame, tau: float) -> DataFrame:
    """decide() for the snapshots of `rep` one after the other, each against `typical` and those opened before it.

    Collects the closest typical snapshot of each of `rep`, and the distances among them.
    """
    known = {r["snap"]: (r["dist"], r["typ"]) for r in nearest(rep, typical).collect()}
    among = {(r["i"], r["j"]): r["dist"] for r in distances.euclidean(rep).collect()}
    opened, rows = [], []
    for s in sorted(r["snap"] for r in rep.select("snap").distinct().collect()):
        near = [(among[t, s], t) for t in opened if (t, s) in among]
        dist, typ = min(near + ([known[s]] if s in known else []), default=(None, None))
        if dist is None or dist > tau:
            opened.append(s)
            rows.append((s, s, dist, True))
        else:
            rows.append((s, typ, dist, False))
    return rep.sparkSession.createDataFrame(rows, "snap int, typ int, dist double, is_new boolean")


def replay(dist: DataFrame, tau: float, initial: tuple[int, ...] = (), snaps: DataFrame | None = None) -> DataFrame:
    """(snap, typ, dist, is_new) in time order: every snapshot meets only what became typical before it."""
    from .clustering import collect_distances

    ids, d = collect_distances(dist, snaps)
    place = {int(s): i for i, s in enumerate(ids)}
    typical, rows = [place[s] for s in initial], []
    for i, s in enumerate(ids):
        best = min(typical, key=lambda t: (d[i, t], t), default=None)
        if best is None or d[i, best] > tau:
            rows.append((int(s), int(s), None if best is None or np.isinf(d[i, best]) else float(d[i, best]), True))
            typical.append(i)
        else:
            rows.append((int(s), int(ids[best]), float(d[i, best]), False))
    return dist.sparkSession.createDataFrame(rows, "snap int, typ int, dist double, is_new boolean")


# ---------------------------------------------------------------- the stored model


def save_model(spark, folder: str, version: int, reps: DataFrame, largest: DataFrame | None = None, **params) -> None:
    """Representations of the typical snapshots, stored maxima and parameters, under a version number."""
    reps.write.mode("overwrite").parquet(f"{folder}/version={version}/reps")
    if largest is not None:
        largest.write.mode("overwrite").parquet(f"{folder}/version={version}/largest")
    spark.createDataFrame([(version, json.dumps(params, sort_keys=True))], "version int, params string").coalesce(1).write.mode("overwrite").json(f"{folder}/version={version}/manifest")


def load_model(spark, folder: str, version: int) -> tuple[DataFrame, dict]:
    manifest = spark.read.schema("version int, params string").json(f"{folder}/version={version}/manifest").first()
    return spark.read.parquet(f"{folder}/version={version}/reps"), json.loads(manifest["params"])


def linear_fit(k: list[int], seconds: list[float]) -> tuple[float, float]:
    """(conversion time, time of one similarity): least squares of seconds = t_r + k * t_sim."""
    slope, level = np.polyfit(k, seconds, 1)
    return float(level), float(slope)

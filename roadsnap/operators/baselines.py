"""What the methods are held against."""

from __future__ import annotations

from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, functions as F

from . import routing


def index_every(edges: DataFrame, weights: DataFrame) -> DataFrame:
    """An index for each snapshot: most space, no error."""
    return routing.hub_labels(edges, weights)


def time_profile(edges: DataFrame, weights: DataFrame, vertices: DataFrame) -> DataFrame:
    """(s, t, d): one index over all time - for every pair the distances of all snapshots."""
    pairs = F.array_sort(F.collect_list(F.struct("typ", "dist")))
    return routing.all_pairs(edges, weights, vertices).groupBy("s", "t").agg(F.transform(pairs, lambda p: p["dist"]).alias("d"))


def path_cache(queries: DataFrame, distances: DataFrame) -> DataFrame:
    """(snap, s, t, dist, age): the first answer to (s, t), served again however traffic changed since."""
    first = distances.groupBy("s", "t").agg(F.min_by("dist", "snap").alias("dist"), F.min("snap").alias("since"))
    return queries.join(first, ["s", "t"]).select("snap", "s", "t", "dist", (F.col("snap") - F.col("since")).alias("age"))


def random_k(snapshots: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """(typ): k snapshots in the order of a repeatable draw."""
    return snapshots.orderBy(F.md5(F.concat_ws("|", F.lit(seed), "snap").cast("binary"))).limit(k).select(F.col("snap").alias("typ"))


def exact_k(errors: np.ndarray, k: int) -> tuple[tuple[int, ...], float]:
    """The k typical snapshots of least mean error, by trying all sets: for small n only."""
    n = len(errors)
    best = min(combinations(range(n), k), key=lambda c: errors[list(c)].min(0).sum())
    return best, float(errors[list(best)].min(0).mean())

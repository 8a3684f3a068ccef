"""Functions for SQL users; each has a built-in twin that the operators use instead."""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructField, StructType


@pandas_udf(DoubleType())
def jaccard_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    """Similarity of two arrays taken as sets; null where either is null, 1 for two empty ones."""

    def one(x, y):
        if x is None or y is None:
            return None
        u = np.union1d(x, y)
        return 1.0 if not len(u) else round(len(np.intersect1d(x, y)) / len(u), 6)

    return pd.Series([one(x, y) for x, y in zip(a, b)], dtype="object").astype("float64")


@pandas_udf(DoubleType())
def l2_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    """Euclidean distance of two vectors of one length."""
    x, y = np.stack(a.to_numpy()).astype(float), np.stack(b.to_numpy()).astype(float)
    return pd.Series(np.round(np.sqrt(((x - y) ** 2).sum(1)), 6))


@pandas_udf(ArrayType(LongType()))
def vec_sum(v: pd.Series) -> list:
    """Grouped sum of vectors of one length."""
    return np.stack(v.to_numpy()).astype(np.int64).sum(0).tolist()


@udtf(returnType=StructType([StructField(n, LongType()) for n in ("eid", "src", "dst")]))
class GridEdges:
    """Edges of a full grid of w x h vertices."""

    def eval(self, w: int, h: int):
        for v in range(w * h):
            x, y = v % w, v // w
            for d, dx, dy in ((0, 1, 0), (1, -1, 0), (2, 0, 1), (3, 0, -1)):
                if 0 <= x + dx < w and 0 <= y + dy < h:
                    yield v * 4 + d, v, v + dx + dy * w


def _grid_arcs(w, h, v):
    x, y = v % w, v // w
    return [(v * 4 + d, v + dx + dy * w) for d, dx, dy in ((0, 1, 0), (1, -1, 0), (2, 0, 1), (3, 0, -1)) if 0 <= x + dx < w and 0 <= y + dy < h]


@udtf(returnType=StructType([StructField(n, LongType()) for n in ("reached", "dist_ms")]))
class ReachFrom:
    """Vertices of a full grid of w x h that are reached from `origin` within r_ms, each edge taking w_ms."""

    def eval(self, w: int, h: int, origin: int, r_ms: int, w_ms: int):
        found, front, dist = {origin: 0}, [origin], 0
        while front and dist + w_ms <= r_ms:
            dist += w_ms
            front = sorted({u for v in front for _, u in _grid_arcs(w, h, v)} - found.keys())
            found.update(dict.fromkeys(front, dist))
        yield from found.items()


@udtf(returnType=StructType([StructField(n, LongType()) for n in ("seq", "eid", "head")]))
class GrowPath:
    """A random path of at most `steps` edges over a full grid from `origin` on, by the draws of candidates.grow."""

    def eval(self, w: int, h: int, origin: int, steps: int, seed: int):
        at, used = origin, set()
        for step in range(steps):
            free = [a for a in _grid_arcs(w, h, at) if a[0] not in used]
            if not free:
                return
            eid, at = min(free, key=lambda a: hashlib.md5(f"{seed}|{origin}|{step}|{a[0]}".encode()).hexdigest())
            used.add(eid)
            yield step, eid, at


def register(spark: SparkSession) -> None:
    """Make the functions callable from SQL."""
    spark.udf.register("set_jaccard", jaccard_udf)
    spark.udf.register("l2", l2_udf)
    spark.udf.register("vec_sum", vec_sum)
    spark.udtf.register("grid_edges", GridEdges)
    spark.udtf.register("reach_from", ReachFrom)
    spark.udtf.register("grow_path", GrowPath)


def views(net, prefix: str = "network") -> None:
    """A network's frames as temporary views for SQL users."""
    for name in ("vertices", "edges", "snapshots", "weights"):
        getattr(net, name).createOrReplaceTempView(f"{prefix}_{name}")

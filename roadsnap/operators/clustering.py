"""Clusterings under a distance threshold, and a typical member of each cluster.

What is clustered are snapshots: n of them, each a row of a small representation or of an n x n distance table.
The kernels below hold exactly that on the driver and refuse more than MAX_N snapshots; the relational forms
(`lloyd`, `components`) have no such limit.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, functions as F

from ..functions.shared import cut, drop

MAX_N = 5000


def _check(n: int) -> None:
    if n > MAX_N:
        raise ValueError(f"{n} snapshots; the driver kernels take {MAX_N}: select within days first, then among the daily ones")


def collect_vectors(rep: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(snapshot ids, matrix) of a reduced representation."""
    rows = rep.groupBy("snap").agg(F.array_sort(F.collect_list(F.struct("dim", "val"))).alias("c")).select("snap", F.transform("c", lambda c: c["val"]).alias("x")).orderBy("snap").limit(MAX_N + 1).collect()
    _check(len(rows))
    return np.array([r["snap"] for r in rows]), np.array([r["x"] for r in rows], float).reshape(len(rows), -1)


def collect_distances(dist: DataFrame, snaps: DataFrame | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(snapshot ids, symmetric matrix) of rows (i, j, dist), i < j.

    `snaps` (snap) names all snapshots, as one without any pair is in no row of `dist`; a pair that `dist` lacks is
    infinitely far apart.  Both are counted before anything is collected.
    """
    every = dist.select("i").union(dist.select("j")).distinct() if snaps is None else snaps.select("snap").distinct()
    ids = np.array(sorted(r[0] for r in every.limit(MAX_N + 1).collect()), np.int64)
    _check(len(ids))
    table = dist.select("i", "j", "dist").toArrow()
    i, j, d = (table.column(c).to_numpy() for c in ("i", "j", "dist"))
    out = np.full((len(ids), len(ids)), np.inf)
    np.fill_diagonal(out, 0)
    a, b = np.searchsorted(ids, i), np.searchsorted(ids, j)
    out[a, b] = out[b, a] = d
    return ids, out


def _frame(spark, ids, labels, typical, dist) -> DataFrame:
    rows = [(int(s), int(c), int(t), float(d)) for s, c, t, d in zip(ids, labels, typical, dist)]
    return spark.createDataFrame(rows, "snap int, cluster int, typ int, dist double")


# ---------------------------------------------------------------- K-means


def kmeans_kernel(x: np.ndarray, k: int, iters: int = 50) -> tuple[np.ndarray, np.ndarray]:
    """(labels, centres): Lloyd from farthest-first centres, starting at the row nearest to the mean."""
    first = int(((x - x.mean(0)) ** 2).sum(1).argmin())
    centres, gap = [first], ((x - x[first]) ** 2).sum(1)
    while len(centres) < min(k, len(x)):
        centres.append(int(gap.argmax()))
        gap = np.minimum(gap, ((x - x[centres[-1]]) ** 2).sum(1))
    return _lloyd(x, x[centres].copy(), iters)


def _lloyd(x, c, iters):
    label = None
    for _ in range(iters):
        d = ((x[:, None, :] - c[None, :, :]) ** 2).sum(2)
        new = d.argmin(1)
        if label is not None and (new == label).all():
            break
        label = new
        for j in range(len(c)):
            if (label == j).any():
                c[j] = x[label == j].mean(0)
    return label, c


def kmeans(rep: DataFrame, k: int, iters: int = 50) -> DataFrame:
    """(snap, cluster, typ, dist): typ is the member nearest to the centre, dist the distance to the centre."""
    ids, x = collect_vectors(rep)
    return _frame(rep.sparkSession, ids, *kmeans_members(ids, x, k, iters))


def kmeans_members(ids: np.ndarray, x: np.ndarray, k: int, iters: int = 50) -> tuple:
    """kmeans() of collected vectors: (cluster, typ, dist) in the order of ids."""
    return _nearest(ids, x, *kmeans_kernel(x, k, iters))


def _nearest(ids, x, label, c):
    d = np.sqrt(((x - c[label]) ** 2).sum(1))
    typ = np.empty(len(ids), int)
    for j in np.unique(label):
        at = np.flatnonzero(label == j)
        typ[at] = ids[at[d[at].argmin()]]
    return np.unique(label, return_inverse=True)[1], typ, np.round(d, 6)


def adaptive_kmeans(rep: DataFrame, tau: float, k0: int = 1, kmax: int | None = None) -> DataFrame:
    """K-means that gains a centre, at the worst member, until all members lie within `tau` of their centre."""
    ids, x = collect_vectors(rep)
    label, c = kmeans_kernel(x, k0)
    while len(c) < (kmax or len(x)):
        d = np.sqrt(((x - c[label]) ** 2).sum(1))
        if d.max(initial=0.0) <= tau:
            break
        label, c = _lloyd(x, np.vstack([c, x[d.argmax()]]), 50)
    return _frame(rep.sparkSession, ids, *_nearest(ids, x, label, c))


def kmeans_ml(rep: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """The library's K-means; (snap, cluster)."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    wide = rep.groupBy("snap").agg(F.array_sort(F.collect_list(F.struct("dim", "val"))).alias("c")).select("snap", array_to_vector(F.transform("c", lambda c: c["val"])).alias("features"))
    return KMeans(k=k, seed=seed).fit(wide).transform(wide).select("snap", F.col("prediction").alias("cluster"))


def lloyd(rep: DataFrame, centres: DataFrame, rounds: int, digits: int = 9) -> DataFrame:
    """(snap, cluster, d2) after relational rounds from centres (cluster, dim, val): k x dims rows are broadcast."""
    for turn in range(rounds):
        gap = rep.join(F.broadcast(centres.select("cluster", "dim", F.col("val").alias("c"))), "dim")
        far = gap.groupBy("snap", "cluster").agg(F.round(F.sum((F.col("val") - F.col("c")) * (F.col("val") - F.col("c"))), 6).alias("d2"))
        label = far.groupBy("snap").agg(F.min(F.struct("d2", "cluster")).alias("best")).select("snap", "best.cluster", "best.d2")
        if turn + 1 < rounds:
            centres = cut(rep.join(label, "snap").groupBy("cluster", "dim").agg(F.round(F.avg("val"), digits).alias("val")))
    return label


# ---------------------------------------------------------------- agglomeration


def agglomerate(d: np.ndarray, linkage: str = "complete", tau: float | None = None, k: int | None = None) -> np.ndarray:
    """Labels after merging closest clusters (ties: smallest ids) while they are within tau, or until k are left."""
    n = len(d)
    d = d.astype(float).copy()
    np.fill_diagonal(d, np.inf)
    size, label, left = np.ones(n), np.arange(n), n
    while left > max(1, k or 1):
        a, b = divmod(int(d.argmin()), n)
        if tau is not None and d[a, b] > tau or not np.isfinite(d[a, b]):
            break
        a, b = min(a, b), max(a, b)
        if linkage == "complete":
            new = np.maximum(d[a], d[b])
        elif linkage == "single":
            new = np.minimum(d[a], d[b])
        elif linkage == "average":
            new = (size[a] * d[a] + size[b] * d[b]) / (size[a] + size[b])
        else:
            raise ValueError(f"unknown linkage {linkage!r}")
        new[[a, b]] = np.inf
        d[a], d[:, a] = new, new
        d[b], d[:, b] = np.inf, np.inf
        size[a] += size[b]
        label[label == label[b]] = label[a]
        left -= 1
    return np.unique(label, return_inverse=True)[1]


def medoids(ids: np.ndarray, d: np.ndarray, label: np.ndarray, rule: str = "max") -> tuple[np.ndarray, np.ndarray]:
    """(typ, dist to it) per snapshot; rule: least worst distance in the cluster, or least sum."""
    typ, far = np.empty(len(ids), int), np.empty(len(ids))
    for c in np.unique(label):
        at = np.flatnonzero(label == c)
        inner = d[np.ix_(at, at)]
        best = int((inner.max(1) if rule == "max" else inner.sum(1)).argmin())
        typ[at], far[at] = ids[at[best]], inner[best]
    return typ, far


def agglomerative(dist: DataFrame, linkage: str = "complete", tau: float | None = None, k: int | None = None, rule: str = "max", snaps: DataFrame | None = None) -> DataFrame:
    """(snap, cluster, typ, dist) of rows (i, j, dist); `snaps` (snap) adds those that are in no row."""
    ids, d = collect_distances(dist, snaps)
    return _frame(dist.sparkSession, ids, *merged_members(ids, d, linkage, tau, k, rule))


def merged_members(ids: np.ndarray, d: np.ndarray, linkage: str = "complete", tau: float | None = None, k: int | None = None, rule: str = "max") -> tuple:
    """agglomerative() of collected distances: (cluster, typ, dist) in the order of ids."""
    label = agglomerate(d, linkage, tau, k)
    return label, *medoids(ids, d, label, rule)


def agglomerative_rounds(dist: DataFrame, snaps: DataFrame, tau: float, linkage: str = "complete") -> DataFrame:
    """(snap, cluster) for any number of snapshots: each round merges all clusters that are nearest to each other.

    dist: (i, j, dist), i < j.  These linkages never bring a merged cluster closer than its parts were, so merging all mutual
    pairs at once gives the clusters of merging the closest pair at a time, unless distances tie.  A pair
    without a distance is infinitely far apart: complete and average linkage do not merge across it.
    """
    how = {"complete": F.max("d"), "single": F.min("d"), "average": F.sum(F.col("d") * F.col("c")) / F.sum("c")}[linkage]
    label = cut(snaps.select("snap", F.col("snap").alias("cluster")))
    pairs = dist.select("i", "j", F.col("dist").alias("d"), F.lit(1).cast("bigint").alias("c"))
    pairs = cut(pairs.unionByName(pairs.select(F.col("j").alias("i"), F.col("i").alias("j"), "d", "c")))
    while True:
        near = pairs.filter(F.col("d") <= tau).groupBy("i").agg(F.min(F.struct("d", "j")).alias("n")).select("i", F.col("n.j").alias("j"))
        back = near.select(F.col("j").alias("i"), F.col("i").alias("j"))
        moved = cut(near.join(back, ["i", "j"]).filter("i < j").select(F.col("j").alias("old"), F.col("i").alias("new")))
        if moved.isEmpty():
            return label
        now = lambda c, to: F.coalesce(to, F.col(c))
        a, b = moved.selectExpr("old as i", "new as ni"), moved.selectExpr("old as j", "new as nj")
        both = pairs.join(a, "i", "left").join(b, "j", "left").select(now("i", F.col("ni")).alias("i"), now("j", F.col("nj")).alias("j"), "d", "c").filter("i <> j")
        merged = both.groupBy("i", "j").agg(how.alias("d"), F.sum("c").alias("c"))
        size = label.join(moved.withColumnRenamed("old", "cluster"), "cluster", "left").select("snap", F.coalesce("new", "cluster").alias("cluster"))
        new = cut(size)
        if linkage != "single":  # pairs that miss some distance go
            n = new.groupBy("cluster").agg(F.count("*").alias("n"))
            merged = merged.join(n.selectExpr("cluster as i", "n as na"), "i").join(n.selectExpr("cluster as j", "n as nb"), "j").filter("c = na * nb").select("i", "j", "d", "c")
        next_ = cut(merged)
        drop(label, pairs, moved)
        label, pairs = new, next_


def components(pairs: DataFrame, ids: DataFrame) -> DataFrame:
    """(snap, cluster): connected components of pairs (i, j), which is single linkage cut at their threshold."""
    both = cut(pairs.select("i", "j").union(pairs.select(F.col("j").alias("i"), F.col("i").alias("j"))))
    label = cut(ids.select("snap", F.col("snap").alias("cluster")))
    while True:
        near = both.join(label.withColumnRenamed("snap", "j"), "j").groupBy(F.col("i").alias("snap")).agg(F.min("cluster").alias("near"))
        new = cut(label.join(near, "snap", "left").select("snap", F.least("cluster", F.coalesce("near", "cluster")).alias("cluster"), F.col("cluster").alias("old")))
        if new.filter("cluster <> old").isEmpty():
            return new.select("snap", "cluster")
        label = new.select("snap", "cluster")


def representatives(dist: DataFrame, clusters: DataFrame, rule: str = "max") -> DataFrame:
    """(cluster, typ): medoids from both-way distances (i, j, dist), ties to the smaller id."""
    a, b = clusters.select(F.col("snap").alias("i"), "cluster"), clusters.select(F.col("snap").alias("j"), F.col("cluster").alias("cj"))
    inner = dist.join(a, "i").join(b, "j").filter("cluster = cj")
    cost = F.max("dist") if rule == "max" else F.round(F.sum("dist"), 6)
    return inner.groupBy("cluster", "i").agg(cost.alias("cost")).groupBy("cluster").agg(F.min(F.struct("cost", "i")).alias("best")).select("cluster", F.col("best.i").alias("typ"))


def density(dist: DataFrame, ids: DataFrame, eps: float, min_pts: int) -> DataFrame:
    """(snap, core, cluster): density clusters, for contrast only - their members may be far from each other."""
    near = dist.filter(F.col("dist") <= eps)
    core = near.groupBy(F.col("i").alias("snap")).agg(F.count("*").alias("n")).filter(F.col("n") >= min_pts).select("snap")
    links = near.filter("i < j").join(core.withColumnRenamed("snap", "i"), "i", "left_semi").join(core.withColumnRenamed("snap", "j"), "j", "left_semi")
    label = components(links, core)
    edge = near.join(label.withColumnRenamed("snap", "j"), "j").groupBy(F.col("i").alias("snap")).agg(F.min("cluster").alias("near"))
    return ids.select("snap").join(label, "snap", "left").join(edge, "snap", "left").select("snap", F.col("cluster").isNotNull().alias("core"), F.coalesce("cluster", "near").alias("cluster"))

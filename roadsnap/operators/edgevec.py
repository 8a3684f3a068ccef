"""Snapshots as vectors of edge weights, and their reduction."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .paths import decoded


def weights(w: DataFrame) -> DataFrame:
    """(snap, dim, val)."""
    return w.select("snap", F.col("eid").alias("dim"), F.col("w_ms").cast("double").alias("val"))


def delta(w: DataFrame, ref: int = 0) -> DataFrame:
    """(snap, dim, val): weights less those of one reference snapshot."""
    base = w.filter(F.col("snap") == ref).select("eid", F.col("w_ms").alias("base"))
    return w.join(base, "eid").select("snap", F.col("eid").alias("dim"), (F.col("w_ms") - F.col("base")).cast("double").alias("val"))


def cv(w: DataFrame, ddof: int = 0) -> DataFrame:
    """(eid, cv): standard deviation over mean of an edge's weights, from exact integer sums."""
    w_ms = F.col("w_ms").cast("decimal(19,0)")  # squares of long travel times leave 64 bits
    s, q, n = F.sum("w_ms").cast("decimal(38,0)"), F.sum((w_ms * w_ms).cast("decimal(38,0)")), F.count("*").cast("decimal(10,0)")
    sums = w.groupBy("eid").agg(s.alias("s"), q.alias("q"), n.alias("n"))
    spread = F.sqrt(((F.col("n") * F.col("q")).cast("decimal(38,0)") - (F.col("s") * F.col("s")).cast("decimal(38,0)")).cast("double") * (F.lit(1.0) if ddof == 0 else F.col("n").cast("double") / F.nullif(F.col("n") - 1, F.lit(0))))
    return sums.select("eid", F.round(spread / F.col("s").cast("double"), 9).alias("cv"))


def cv_filter(cvs: DataFrame, min_cv: float | None = None, top_share: float | None = None) -> DataFrame:
    """(eid, cv) of edges whose variability is at least a threshold, given or as the share of edges to keep."""
    if top_share is not None:
        cut = cvs.agg(F.percentile("cv", F.lit(1 - top_share)).alias("cut"))
        return cvs.crossJoin(F.broadcast(cut)).filter("cv >= cut").select("eid", "cv")
    return cvs.filter(F.col("cv") >= min_cv)


def keep_edges(w: DataFrame, kept: DataFrame) -> DataFrame:
    return w.join(kept.select("eid"), "eid", "left_semi")


def gram(rep: DataFrame, n: int) -> DataFrame:
    """(i, j, dot) for all pairs of snapshots: tasks add outer products of dimensions, n x n numbers travel."""
    rows = rep.groupBy("dim").agg(F.collect_list(F.struct("snap", "val")).alias("cells"))

    def run(batches):
        total = np.zeros((n, n))
        for b in batches:
            if not b.num_rows:
                continue
            cells = b.column("cells")
            flat = cells.flatten()
            dim = np.repeat(np.arange(b.num_rows), np.diff(cells.offsets.to_numpy()))
            m = np.zeros((b.num_rows, n))
            m[dim, flat.field("snap").to_numpy()] = flat.field("val").to_numpy()
            total += m.T @ m
        i, j = np.indices((n, n))
        yield pa.RecordBatch.from_arrays([pa.array(i.ravel(), pa.int32()), pa.array(j.ravel(), pa.int32()), pa.array(total.ravel())], names=["i", "j", "dot"])

    return rows.select("cells").mapInArrow(run, "i int, j int, dot double").groupBy("i", "j").agg(F.sum("dot").alias("dot"))


def gram_coded(places: DataFrame, n: int, ref: int | None = None) -> DataFrame:
    """gram() of weights in coded form, less those of snapshot `ref`, where edges' rows lie: no weight travels."""

    def run(batches):
        total = np.zeros((n, n))
        for b in batches:
            if b.num_rows:
                m = decoded(b.column("w"))
                m = (m if ref is None else m - m[:, ref : ref + 1]).astype(float)
                total += m.T @ m
        i, j = np.indices((n, n))
        yield pa.RecordBatch.from_arrays([pa.array(i.ravel(), pa.int32()), pa.array(j.ravel(), pa.int32()), pa.array(total.ravel())], names=["i", "j", "dot"])

    return places.select("w").mapInArrow(run, "i int, j int, dot double").groupBy("i", "j").agg(F.sum("dot").alias("dot"))


def cv_coded(places: DataFrame) -> DataFrame:
    """cv() of weights in coded form, by the same exact sums; an edge has one row."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                w = decoded(b.column("w"))
                n = w.shape[1]
                if n * int(np.abs(w).max(initial=0)) >= 1 << 31:  # squares of sums leave 63 bits
                    w = w.astype(object)
                s, q = w.sum(1), (w * w).sum(1)
                spread = np.sqrt((n * q - s * s).astype(float))
                yield pa.RecordBatch.from_arrays([b.column("eid"), pa.array(spread), pa.array(s.astype(float))], names=["eid", "spread", "s"])

    return places.select("eid", "w").mapInArrow(run, "eid bigint, spread double, s double").select("eid", F.round(F.col("spread") / F.col("s"), 9).alias("cv"))


def _matrix(g: DataFrame, n: int) -> np.ndarray:
    out = np.zeros((n, n))
    for i, j, v in g.toLocalIterator():
        out[i, j] = v
    return out


def gram_matrix(rep: DataFrame, n: int) -> np.ndarray:
    return _matrix(gram(rep, n), n)


def pca_from_gram(g: np.ndarray, dims: int) -> np.ndarray:
    """Coordinates (n, dims) of the principal components, from the n x n Gram matrix alone."""
    n = len(g)
    centre = np.eye(n) - 1.0 / n
    value, vector = np.linalg.eigh(centre @ g @ centre)
    top = np.argsort(-value)[:dims]
    return vector[:, top] * np.sqrt(np.maximum(value[top], 0))


def pca(rep: DataFrame, n: int, dims: int) -> DataFrame:
    """(snap, dim, val) on principal components. The state is n x n, so the number of edges does not matter."""
    return pca_of(gram(rep, n), n, dims)


def pca_of(g: DataFrame, n: int, dims: int) -> DataFrame:
    """pca() from the Gram matrix (i, j, dot)."""
    x = pca_from_gram(_matrix(g, n), dims)
    rows = [(int(i), int(j), float(x[i, j])) for i in range(n) for j in range(x.shape[1])]
    return g.sparkSession.createDataFrame(rows, "snap int, dim bigint, val double")


def pca_ml(rep: DataFrame, n: int, dims: int) -> DataFrame:
    """The same through the library's covariance PCA, for representations of few dimensions."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector, vector_to_array

    wide = rep.groupBy("snap").agg(F.array_sort(F.collect_list(F.struct("dim", "val"))).alias("c")).select("snap", array_to_vector(F.transform("c", lambda c: c["val"])).alias("x"))
    done = PCA(k=dims, inputCol="x", outputCol="y").fit(wide).transform(wide)
    return done.select("snap", F.posexplode(vector_to_array("y")).alias("dim", "val")).select("snap", F.col("dim").cast("bigint"), "val")

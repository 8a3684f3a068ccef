"""Typical vertices: where traffic fluctuates most, and snapshots represented around them."""

from __future__ import annotations

import warnings

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from .paths import decoded, opened
from .snapshots import unpacked

MICRO = 1_000_000


def sizes(reached: DataFrame) -> DataFrame:
    """(snap, vid, size): counts only; the sets themselves need not move."""
    return reached.groupBy("snap", F.col("origin").alias("vid")).agg(F.count("*").alias("size"))


def block_coef(size: DataFrame, largest: DataFrame | None = None, clamp: bool = False) -> DataFrame:
    """(snap, vid, b): the vertex's largest size over its size. With stored `largest` (vid, top), new snapshots may be below 1."""
    if largest is None:
        top = size.withColumn("top", F.max("size").over(Window.partitionBy("vid")))
    else:
        top = size.join(largest, "vid")
    b = F.expr(f"top * {MICRO} div size") / MICRO
    return top.select("snap", "vid", (F.greatest(b, F.lit(1.0)) if clamp else b).alias("b"))


def fluctuation(block: DataFrame) -> DataFrame:
    """(vid, f): deviation over mean of the block coefficient, from whole numbers of 1e-6."""
    m = F.round(F.col("b") * MICRO).cast("decimal(20,0)")
    sums = block.groupBy("vid").agg(F.sum(m).alias("s"), F.sum(m * m).alias("q"), F.count("*").alias("n"))
    return sums.select("vid", F.round(F.sqrt((F.col("n") * F.col("q") - F.col("s") * F.col("s")).cast("double")) / F.col("s").cast("double"), 6).alias("f"))


def fluctuation_coded(size: DataFrame) -> DataFrame:
    """fluctuation() of (vid, w), all sizes of a vertex in one coded row, by the same whole numbers."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                w = decoded(batch.column("w"))
                m = w.max(1)[:, None] * MICRO // w
                n, over = w.shape[1], m - MICRO  # a shift leaves the deviation as it is
                if n * int(over.max(initial=0)) >= 1 << 31:  # squares of sums leave 63 bits
                    over = over.astype(object)
                s, q = over.sum(1), (over * over).sum(1)
                yield pa.RecordBatch.from_arrays([batch.column("vid"), pa.array(np.sqrt((n * q - s * s).astype(float))), pa.array(m.sum(1).astype(float))], names=["vid", "spread", "s"])

    return size.select("vid", "w").mapInArrow(run, "vid bigint, spread double, s double").select("vid", F.round(F.col("spread") / F.col("s"), 6).alias("f"))


def sizes_of_coded(size: DataFrame) -> DataFrame:
    """(snap, vid, size) of (vid, w)."""
    return unpacked(opened(size.withColumnRenamed("vid", "eid"))).select("snap", F.col("eid").alias("vid"), F.col("w_ms").alias("size"))


def cover_radius(rule: str, r_ms: int) -> int:
    """How wide the covers are that `select` needs: twice the radius to keep vertices out of them, once to keep them apart."""
    return r_ms if rule == "disjoint_r" else 2 * r_ms


def select(f: DataFrame, q: int, cover=None, rule: str = "in_2r", first: int | None = None) -> DataFrame:
    """(rank, vid, f): most fluctuating vertices first, without those too close to a chosen one.

    `cover(vids)` gives (origin, reached) of a batch of candidates over all snapshots (see cover_radius), so the wide
    search runs for candidates only.  in_2r: a vertex inside a chosen one's cover is left out; disjoint_r: covers must
    not meet; none: no exclusion.  Batches double from `first` on (4q unless told; the result is the same), so an exhausted pool of N vertices takes log N searches, and each
    starts where the one before it ended in the order.  Fewer than q come back, with a warning, when no vertex is left.
    """
    spark = f.sparkSession
    if rule == "none":
        rows = [(i, r["vid"], r["f"]) for i, r in enumerate(f.orderBy(F.desc("f"), "vid").limit(q).collect())]
        return spark.createDataFrame(rows, "rank int, vid bigint, f double")
    chosen, taken, after, size = [], set(), None, first or 4 * q
    while len(chosen) < q:
        rest = f if after is None else f.filter((F.col("f") < after["f"]) | ((F.col("f") == after["f"]) & (F.col("vid") > after["vid"])))
        batch = rest.orderBy(F.desc("f"), "vid").limit(size).collect()
        if not batch:
            warnings.warn(f"only {len(chosen)} of {q} vertices are far enough from each other", stacklevel=2)
            break
        after, size = batch[-1], 2 * size
        open_ = [r for r in batch if r["vid"] not in taken] if rule == "in_2r" else batch
        if not open_:
            continue
        covers: dict[int, set] = {}
        ids = spark.createDataFrame([(r["vid"],) for r in open_], "vid bigint")
        for part in cover(ids).select("origin", "reached").distinct().groupBy("origin").agg(F.collect_list("reached").alias("own")).toLocalIterator():
            covers[part["origin"]] = set(part["own"])
        for r in open_:
            own = covers.get(r["vid"], {r["vid"]})
            if len(chosen) < q and (r["vid"] not in taken if rule == "in_2r" else taken.isdisjoint(own)):
                chosen.append((len(chosen), r["vid"], r["f"]))
                taken |= own
    return spark.createDataFrame(chosen, "rank int, vid bigint, f double")


def rep_bc(block: DataFrame, typical: DataFrame) -> DataFrame:
    """(snap, dim, val): block coefficients at the typical vertices."""
    return block.join(F.broadcast(typical.select("vid")), "vid").select("snap", F.col("vid").alias("dim"), F.col("b").alias("val"))


def rep_set(reached: DataFrame, typical: DataFrame) -> DataFrame:
    """(snap, vid, reached): members of the sets around the typical vertices."""
    return reached.join(F.broadcast(typical.select(F.col("vid").alias("origin"))), "origin").select("snap", F.col("origin").alias("vid"), "reached")

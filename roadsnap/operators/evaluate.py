"""Accuracy and cost measures.

A path's relative error is kept as a whole number of 1e-9, so that sums over paths are exact whatever the
partitioning; means are formed once, at the end.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

SCALE = 1_000_000_000
#: Costs below it, in ms, have all products of _shares() below 2**53.
EXACT = (1 << 53) // 32_000


def pair_error(costs: DataFrame, pairs: DataFrame) -> DataFrame:
    """(typ, act, err) for the asked (typ, act): mean over paths of |typical - actual| / actual."""
    typ = costs.select(F.col("snap").alias("typ"), "pid", F.col("d_ms").alias("dt"))
    act = costs.select(F.col("snap").alias("act"), "pid", F.col("d_ms").alias("da"))
    both = pairs.select("typ", "act").join(act, "act").join(typ, ["typ", "pid"])
    micro = F.expr(f"abs(dt - da) * {SCALE} div da")
    return both.groupBy("typ", "act").agg(F.sum(micro).alias("s"), F.count("*").alias("c")).select("typ", "act", F.round(F.col("s") / F.col("c") / SCALE, 9).alias("err"))


def _shares(gap: np.ndarray, act: np.ndarray) -> np.ndarray:
    """Sums over rows of gap * SCALE div act, of whole numbers in doubles: a quarter of the time that integers take.

    The quotient is formed in two steps, whose products and quotients stay below 2**53: then a quotient that is rounded to a double has the right floor.
    """
    gap *= 32_000
    high = np.floor(gap / act)
    gap -= high * act
    gap *= SCALE // 32_000
    gap /= act
    np.floor(gap, out=gap)
    return high.sum(0).astype(np.int64) * (SCALE // 32_000) + gap.sum(0).astype(np.int64)


def error_matrix(cost_rows: DataFrame, n: int, band: int | None = None) -> DataFrame:
    """(typ, act, err) for all pairs at most `band` apart: the means of error_sums()."""
    part = error_sums(cost_rows, n, band)
    return part.select("typ", "act", F.round(F.col("s") / F.col("c") / SCALE, 9).alias("err"))


def error_sums(cost_rows: DataFrame, n: int, band: int | None = None) -> DataFrame:
    """(typ, act, s, c): sums and numbers of path errors for pairs at most `band` apart, from one row of n costs per path.

    Every task adds its rows to an n x n table and emits it once: what travels is tasks x n x band
    numbers, however many paths there are.
    """
    width = n if band is None else band

    def run(batches):
        total, count = np.zeros((n, n), np.int64), 0
        for b in batches:
            if not b.num_rows:
                continue
            d = b.column("d").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, n)
            lines = max(64, 16_384 // max(1, min(n, 2 * width + 1)))  # a block stays in the cache
            for lo in range(0, len(d), lines):
                block = d[lo : lo + lines]
                least, most = block.min(initial=EXACT), block.max(initial=1)
                plain = 0 < least and most < EXACT and most < least << 24  # sums over a block stay below 2**53 too
                whole = block.astype(np.float64) if plain else block
                for t in range(n):
                    a0, a1 = max(0, t - width), min(n, t + width + 1)
                    act = whole[:, a0:a1]
                    gap = np.abs(whole[:, t : t + 1] - act)
                    total[t, a0:a1] += _shares(gap, act) if plain else (gap * SCALE // act).sum(0)
            count += b.num_rows
        if count:
            t, a = np.nonzero(np.abs(np.subtract.outer(np.arange(n), np.arange(n))) <= width)
            yield pa.RecordBatch.from_arrays([pa.array(t, pa.int32()), pa.array(a, pa.int32()), pa.array(total[t, a]), pa.array(np.full(len(t), count, np.int64))], names=["typ", "act", "s", "c"])

    part = cost_rows.select("d").mapInArrow(run, "typ int, act int, s bigint, c bigint")
    return part.groupBy("typ", "act").agg(F.sum("s").alias("s"), F.sum("c").alias("c"))


def assigned_error(selection: DataFrame, errors: DataFrame) -> DataFrame:
    """(snap, typ, err): every snapshot's error to the typical one that serves it."""
    e = errors.select("typ", F.col("act").alias("snap"), "err")
    return selection.select("snap", "typ").join(e, ["snap", "typ"])


def selection_error(selection: DataFrame, errors: DataFrame) -> DataFrame:
    """One row: k, mean, 95 % quantile and worst of the errors over all snapshots, and the mean over those that are not typical."""
    each = assigned_error(selection, errors)
    scaled = F.round(F.col("err") * SCALE).cast("bigint")
    return each.agg(
        F.countDistinct("typ").alias("k"),
        F.round(F.sum(scaled) / F.count("*") / SCALE, 6).alias("mean_err"),
        F.round(F.percentile("err", F.lit(0.95)), 6).alias("p95_err"),
        F.round(F.max("err"), 6).alias("max_err"),
        F.round(F.sum(F.when(F.col("snap") != F.col("typ"), scaled)) / F.nullif(F.count_if(F.col("snap") != F.col("typ")), F.lit(0)) / SCALE, 6).alias("mean_err_others"),
    )


def worst_per_window(selection: DataFrame, errors: DataFrame) -> DataFrame:
    """(typ, members, worst): the worst error within each window or cluster."""
    return assigned_error(selection, errors).groupBy("typ").agg(F.count("*").alias("members"), F.max("err").alias("worst"))


def relative_distance_error(typical: DataFrame, actual: DataFrame) -> DataFrame:
    """Of shortest-path distances (s, t, dist): |typical - actual| / actual per query, and its mean, as one row."""
    both = typical.select("s", "t", F.col("dist").alias("dt")).join(actual.select("s", "t", F.col("dist").alias("da")), ["s", "t"]).filter("da > 0")
    return both.agg(F.count("*").alias("queries"), F.round(F.sum(F.expr(f"abs(dt - da) * {SCALE} div da")) / F.count("*") / SCALE, 6).alias("mean_err"))


def purity(selection: DataFrame, truth: DataFrame, cluster: str = "cluster", label: str = "regime") -> DataFrame:
    """One row: share of snapshots that carry their cluster's most frequent label."""
    table = selection.join(truth, "snap").groupBy(cluster, label).agg(F.count("*").alias("n"))
    best = table.groupBy(cluster).agg(F.max("n").alias("most"), F.sum("n").alias("all"))
    return best.agg(F.count("*").alias("clusters"), F.round(F.sum("most") / F.sum("all"), 6).alias("purity"))


def adjusted_rand(selection: DataFrame, truth: DataFrame, cluster: str = "cluster", label: str = "regime") -> DataFrame:
    """One row: adjusted Rand index of a clustering against labels."""
    cell = selection.join(truth, "snap").groupBy(cluster, label).agg(F.count("*").alias("n"))
    choose = lambda c: F.col(c) * (F.col(c) - 1) / 2
    a = cell.groupBy(cluster).agg(F.sum("n").alias("n")).agg(F.sum(choose("n")).alias("a"))
    b = cell.groupBy(label).agg(F.sum("n").alias("n")).agg(F.sum(choose("n")).alias("b"))
    both = cell.agg(F.sum(choose("n")).alias("index"), (F.sum("n") * (F.sum("n") - 1) / 2).alias("all")).crossJoin(a).crossJoin(b)
    expected = F.col("a") * F.col("b") / F.col("all")
    return both.select(F.round((F.col("index") - expected) / F.nullif((F.col("a") + F.col("b")) / 2 - expected, F.lit(0.0)), 6).alias("ari"))


def crossover(curve: DataFrame, baseline: DataFrame) -> DataFrame:
    """(method, k, better): does a method's error at k lie below the baseline's; and the least such k over all."""
    both = curve.join(baseline.select("k", F.col("mean_err").alias("base_err")), "k")
    return both.select("method", "k", (F.col("mean_err") < F.col("base_err")).alias("better")).withColumn("first_k", F.min(F.when(F.col("better"), F.col("k"))).over(Window.partitionBy("method")))

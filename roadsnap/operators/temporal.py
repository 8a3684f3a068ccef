"""Selection by time alone: a fixed step, and windows that grow while their error stays bounded."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window, functions as F


def uniform(snapshots: DataFrame, step: int, start: int = 0) -> DataFrame:
    """(typ): snapshots whose ordinal is `start` modulo `step`."""
    return snapshots.filter((F.col("snap") - start) % step == 0).filter(F.col("snap") >= start).select(F.col("snap").alias("typ"))


def uniform_k(snapshots: DataFrame, n: int, k: int) -> DataFrame:
    return uniform(snapshots, max(1, n // k))


def uniform_starts(snapshots: DataFrame, step: int) -> DataFrame:
    """(start, typ) for every possible start of one step."""
    return snapshots.select((F.col("snap") % step).alias("start"), F.col("snap").alias("typ"))


def assign(snapshots: DataFrame, typical: DataFrame, mode: str = "nearest_time", errors: DataFrame | None = None) -> DataFrame:
    """(snap, typ): who serves a snapshot; ties go to the earlier typical one.

    previous: the last typical one at or before (else the first after); nearest_time; min_error: the
    typical one with the least error, read off `errors`.
    """
    if mode == "min_error":
        e = errors.join(F.broadcast(typical), "typ")  # k rows
        return e.groupBy(F.col("act").alias("snap")).agg(F.min_by("typ", F.struct("err", "typ")).alias("typ")).join(snapshots.select("snap"), "snap", "left_semi")
    marked = snapshots.select("snap").join(typical.withColumn("snap", F.col("typ")), "snap", "left")
    back = Window.orderBy("snap").rowsBetween(Window.unboundedPreceding, 0)  # a row per snapshot
    ahead = Window.orderBy("snap").rowsBetween(0, Window.unboundedFollowing)
    near = marked.select("snap", F.last("typ", True).over(back).alias("before"), F.first("typ", True).over(ahead).alias("after"))
    if mode == "previous":
        return near.select("snap", F.coalesce("before", "after").alias("typ"))
    if mode == "nearest_time":
        later = F.col("before").isNull() | (F.col("after") - F.col("snap") < F.col("snap") - F.col("before"))
        return near.select("snap", F.when(later, F.col("after")).otherwise(F.col("before")).alias("typ"))
    raise ValueError(f"unknown mode {mode!r}")


def windows(errors: np.ndarray, eps: float, pick: str = "minimax") -> list[tuple[int, int, int, float]]:
    """(first, last, typical, worst) of every window, from the directed matrix errors[typical, actual].

    A window takes the next snapshot while some member errs by at most `eps` against all others; the first
    snapshot that breaks this opens the next window. pick: minimax, or first, last, middle for comparison.
    """
    n, out, lo = len(errors), [], 0
    worst, chosen = np.zeros(0), (0, 0.0)
    for i in range(n + 1):
        if i < n:
            members = np.arange(lo, i)
            grown = np.append(np.maximum(worst, errors[members, i]), errors[i, members].max(initial=0.0))
            best = _pick(grown, pick)
            if i == lo or grown[best] <= eps:
                worst, chosen = grown, (lo + best, float(grown[best]))
                continue
        if i > lo:
            out.append((lo, i - 1, *chosen))
        if i < n:
            lo, worst, chosen = i, np.zeros(1), (i, 0.0)
    return out


def _pick(worst, rule):
    return {"minimax": int(np.argmin(worst)), "first": 0, "last": len(worst) - 1, "middle": (len(worst) - 1) // 2}[rule]


def matrix(errors: DataFrame, n: int) -> np.ndarray:
    """Collect a directed error table: n x band numbers by design."""
    out = np.full((n, n), np.inf)
    for t, a, e in errors.select("typ", "act", "err").toLocalIterator():
        out[t, a] = e
    return out


def nonuniform(errors: DataFrame, n: int, eps: float, pick: str = "minimax") -> DataFrame:
    """(lo, hi, typ, worst): windows under `eps` in time order."""
    found = windows(matrix(errors, n), eps, pick)
    return errors.sparkSession.createDataFrame(found, "lo int, hi int, typ int, worst double")


def nonuniform_banded(cost_rows: DataFrame, n: int, eps: float, band: int = 8) -> DataFrame:
    """The same from a band of the matrix, doubled while some window would leave it."""
    from .evaluate import error_matrix

    while True:
        m = matrix(error_matrix(cost_rows, n, band), n)
        found = windows(m, eps)
        if band >= n or all(hi - lo < band for lo, hi, _, _ in found):
            return cost_rows.sparkSession.createDataFrame(found, "lo int, hi int, typ int, worst double")
        band *= 2


def members(found: DataFrame) -> DataFrame:
    """(snap, typ) from windows."""
    return found.select(F.explode(F.sequence("lo", "hi")).alias("snap"), "typ")


def eps_for_k(errors: np.ndarray, k: int, pick: str = "minimax") -> float:
    """A threshold that gives at most k windows, by bisection over the matrix's own values."""
    values = np.unique(errors[np.isfinite(errors)])
    lo, hi = 0, len(values) - 1
    while lo < hi:
        mid = (lo + hi) // 2
        if len(windows(errors, values[mid], pick)) <= k:
            hi = mid
        else:
            lo = mid + 1
    return float(values[lo])

"""Travel times of edge sequences."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F


def cost(paths: DataFrame, weights: DataFrame) -> DataFrame:
    """(snap, pid, d_ms): one exchange by edge for the join, one by (snap, pid) for the sums."""
    return paths.select("pid", "eid").join(weights, "eid").groupBy("snap", "pid").agg(F.sum("w_ms").alias("d_ms"))


def represent(typical_paths: DataFrame, weights: DataFrame) -> DataFrame:
    """(snap, dim, val): a snapshot as the travel times of typical paths, whose edges are few by design."""
    return cost(typical_paths, weights).select("snap", F.col("pid").alias("dim"), F.col("d_ms").cast("double").alias("val"))


def cost_rows(costs: DataFrame) -> DataFrame:
    """(pid, d): one row per path with its costs in snapshot order."""
    pairs = F.array_sort(F.collect_list(F.struct("snap", "d_ms")))
    return costs.groupBy("pid").agg(F.transform(pairs, lambda p: p["d_ms"]).alias("d"))


def cost_packed(paths: DataFrame, packed_weights: DataFrame) -> DataFrame:
    """(pid, d) from weights in storage form: edges' arrays are added in Arrow batches, then across them."""

    def summed(pid, rows):
        order = np.argsort(pid, kind="stable")
        pid, rows = pid[order], rows[order]
        first = np.flatnonzero(np.concatenate([[True], pid[1:] != pid[:-1]]))
        return pid[first], np.add.reduceat(rows, first)

    def opened(b):
        return b.column("pid").to_numpy(), b.column("w").flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(b.num_rows, -1)

    def batch(pid, rows, name):
        offsets = pa.array(np.arange(len(pid) + 1) * rows.shape[1], pa.int32())
        return pa.RecordBatch.from_arrays([pa.array(pid), pa.ListArray.from_arrays(offsets, pa.array(rows.ravel()))], names=["pid", name])

    def add(batches):
        for b in batches:
            if b.num_rows:
                yield batch(*summed(*opened(b)), "w")

    joined = paths.select("pid", "eid").join(packed_weights, "eid").select("pid", "w")
    partial = joined.mapInArrow(add, "pid bigint, w array<bigint>").repartition("pid").sortWithinPartitions("pid")

    def finish(batches):
        held = None  # the last path of a batch may go on in the next one
        for b in batches:
            if not b.num_rows:
                continue
            pid, rows = opened(b)
            if held is not None:
                pid, rows = np.concatenate([held[0], pid]), np.concatenate([held[1], rows])
            pid, rows = summed(pid, rows)
            held = (pid[-1:], rows[-1:])
            if len(pid) > 1:
                yield batch(pid[:-1], rows[:-1], "d")
        if held is not None:
            yield batch(*held, "d")

    return partial.mapInArrow(finish, "pid bigint, d array<bigint>")


# ---------------------------------------------------------------- runs along chains of edges


def coded(rows: np.ndarray) -> pa.Array:
    """Rows of whole numbers as bytes, of as few each as all of a batch need; the last byte tells how many."""
    width = 8 if rows.size and rows.min() < 0 else max(1, (int(rows.max(initial=0)).bit_length() + 7) // 8)
    body = np.ascontiguousarray(rows, "<i8").view(np.uint8).reshape(len(rows), rows.shape[1], 8)[:, :, :width].reshape(len(rows), rows.shape[1] * width)
    data = np.concatenate([body, np.full((len(rows), 1), width, np.uint8)], 1)
    offsets = np.arange(len(rows) + 1, dtype=np.int64) * data.shape[1]
    if offsets[-1] < 1 << 31:
        return pa.Array.from_buffers(pa.binary(), len(rows), [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(data.tobytes())])
    return pa.Array.from_buffers(pa.large_binary(), len(rows), [None, pa.py_buffer(offsets), pa.py_buffer(data.tobytes())])


def decoded(column) -> np.ndarray:
    """Of coded() without nulls; its rows may be of any widths."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros((0, 0), np.int64)
    data, wide = np.frombuffer(column.buffers()[2], np.uint8), pa.types.is_large_binary(column.type)
    offsets = np.frombuffer(column.buffers()[1], np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    widths = data[offsets[1:] - 1].astype(np.int64)
    n = int((offsets[1] - offsets[0] - 1) // widths[0])
    out = np.zeros((len(column), n, 8), np.uint8)
    for width in np.unique(widths):
        at = np.flatnonzero(widths == width)
        body = data[offsets[0] : offsets[-1]].reshape(len(at), -1)[:, :-1] if len(at) == len(column) else data[offsets[at][:, None] + np.arange(n * width)]
        out[at, :, :width] = body.reshape(len(at), n, width)
    return out.view("<i8").reshape(len(column), n)


def opened(places: DataFrame) -> DataFrame:
    """Coded rows (eid, chain, pos, w) as (eid, w) with arrays."""

    def run(batches):
        for b in batches:
            rows = decoded(b.column("w"))
            offsets = pa.array(np.arange(b.num_rows + 1) * rows.shape[1], pa.int32())
            yield pa.RecordBatch.from_arrays([b.column("eid"), pa.ListArray.from_arrays(offsets, pa.array(rows.ravel()))], names=["eid", "w"])

    return places.select("eid", "w").mapInArrow(run, "eid bigint, w array<bigint>")


def cost_legs(legs: DataFrame, places: DataFrame) -> DataFrame:
    """(pid, d): costs of paths that are two runs along chains of edges, from edges' weights in coded form.

    A leg (pid, c1, lo1, hi1, c2, lo2, hi2) takes a chain's edges at positions lo to hi; edges that are lacking cost nothing,
    and a path without any has no row. A chain's weights are summed once along it, so a run costs two of these sums whatever
    its length, and one row of costs per path travels, between its first run and its second.
    """
    chains = places.select("chain", "pos", "w")
    first = legs.groupBy("c1").cogroup(chains.groupBy("chain")).applyInArrow(_along("1", ["pid", "c2", "lo2", "hi2"]), "pid bigint, c2 bigint, lo2 bigint, hi2 bigint, k bigint, d binary")
    rows = first.groupBy("c2").cogroup(chains.groupBy("chain")).applyInArrow(_along("2", ["pid"]), "pid bigint, k bigint, d binary")

    def arrays(batches):
        for b in batches:
            if b.num_rows:
                d = decoded(b.column("d"))
                offsets = pa.array(np.arange(b.num_rows + 1) * d.shape[1], pa.int32())
                yield pa.RecordBatch.from_arrays([b.column("pid"), pa.ListArray.from_arrays(offsets, pa.array(d.ravel()))], names=["pid", "d"])

    return rows.filter("k > 0").select("pid", "d").mapInArrow(arrays, "pid bigint, d array<bigint>")


def _along(leg: str, keep: list[str]):
    """Adds a chain's runs to the costs d that paths bring along, of k edges so far; both are null or lacking before the first."""

    def add(rows, chain):
        pos = chain.column("pos").to_numpy()
        order = np.argsort(pos, kind="stable")
        pos, w = pos[order], decoded(chain.column("w"))[order]
        upto = np.concatenate([np.zeros((1, w.shape[1]), np.int64), np.cumsum(w, 0)])
        out = []
        for at in range(0, max(1, rows.num_rows), 4096):
            part = rows.slice(at, 4096).combine_chunks()
            i, j = np.searchsorted(pos, part.column(f"lo{leg}").to_numpy(), "left"), np.searchsorted(pos, part.column(f"hi{leg}").to_numpy(), "right")
            k, d = j - i, upto[j] - upto[i]
            if "d" in part.column_names:
                k, before = k + part.column("k").to_numpy(), part.column("d").combine_chunks()
                had = np.flatnonzero(before.is_valid().to_numpy(zero_copy_only=False))
                if len(had):
                    old = decoded(before.take(pa.array(had)))
                    d = d if d.shape[1] else np.zeros((len(d), old.shape[1]), np.int64)  # no edge of the chain exists
                    d[had] += old
            d = coded(d) if d.shape[1] else pa.nulls(len(d), pa.binary())
            out.append(pa.table([*(part.column(c) for c in keep), pa.array(k, pa.int64()), d], names=[*keep, "k", "d"]))
        return pa.concat_tables(out)

    return add

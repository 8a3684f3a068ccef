"""Near-duplicate groups by ProbMinHash signatures, banding, verification and connected components.

Every distinct shingle (`k` words) of a text starts a Poisson process whose rate is the number of times it
occurs; each arrival picks a register, and a register keeps the shingle of its first arrival.  Processes
are seeded by the shingle alone, so two texts agree in a register with a probability equal to their
probability Jaccard similarity.  A text's processes stop once their next arrival is later than all of its
registers.  Registers are cut to bands; texts that agree in a band are candidates, and a candidate pair
counts when its exact probability Jaccard is at least `threshold`.

Every pair of a band bucket is compared, unless its two texts are connected already.  It is done in rounds: in
each, a bucket's least doc_ids (1, 4, 16, ...) are its hubs, which meet all other members that are not in their
component; then hubs leave the bucket, and a bucket whose members are all in one component is done.  Texts
with equal shingle counts are one node throughout.  Of every connected group the least doc_id stays.

Defined results: a null or empty text has no shingle and stays; a text of fewer than `k` words is one
shingle; rows that share a doc_id stay or go together, and one of their texts is verified; a row with a null
doc_id stays; texts of any length are read whole; extra columns may have any name and come back as they are.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from . import text as tk
from .store import drop, keep

K, REGISTERS, ROWS, THRESHOLD = 3, 144, 4, 0.5
#: Each round a bucket has so many times the hubs of the round before.
GROWTH = 4


def weighted_shingles(data, offsets, k, hasher):
    """Distinct shingles of a batch with their counts: (48-bit hash, row, count), sorted by row and hash."""
    starts, ends, rows = tk.words(data, offsets)
    h, r = tk.shingles(hasher(data, starts, ends), rows, len(offsets) - 1, k)
    key = (r.astype(np.uint64) << np.uint64(48)) | (h >> np.uint64(16))
    key.sort()
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.empty(0, np.int64)
    count = np.diff(np.append(first, len(key)))
    key = key[first]
    return key & np.uint64((1 << 48) - 1), (key >> np.uint64(48)).astype(np.int64), count


def signatures(elements, rows, weights, n_rows, m=REGISTERS):
    """ProbMinHash registers, (n_rows, m) of element hashes; rows without elements stay 0."""
    arrival = np.full(n_rows * m, np.inf)
    winner = np.zeros(n_rows * m, np.uint64)
    seed = tk.mix(elements + tk.BASE)
    element, row, rate, now = elements, rows, weights.astype(float), np.zeros(len(elements))
    drawn, block = 0, 1
    while len(element):
        step = np.arange(drawn, drawn + block, dtype=np.uint64) * tk.BASE
        x = tk.mix(seed[:, None] + step[None, :])
        gap = -np.log(((x >> np.uint64(24)).astype(float) + 0.5) / (1 << 40)) / rate[:, None]
        gap[:, 0] += now
        when = np.cumsum(gap, 1) if block > 1 else gap
        at = row[:, None] * m + ((x & np.uint64((1 << 24) - 1)) % np.uint64(m)).astype(np.int64)
        now = when[:, -1]
        better = when < arrival[at]
        w, a = when[better], at[better]
        np.minimum.at(arrival, a, w)
        won = arrival[a] == w
        winner[a[won]] = np.broadcast_to(element[:, None], when.shape)[better][won]
        drawn += block
        block = 1 if drawn < 3 else min(64, 4 * block)
        some = np.unique(row)
        last = np.full(n_rows, -1.0)
        last[some] = arrival.reshape(n_rows, m)[some].max(1)
        live = now < last[row]
        element, row, rate, now, seed = element[live], row[live], rate[live], now[live], seed[live]
    return winner.reshape(n_rows, m)


def probability_jaccard(x_key, x_count, y_key, y_count):
    """Exact similarity of two weighted sets (sorted distinct keys with counts)."""
    if not len(x_key) or not len(y_key):
        return 0.0
    keys = np.union1d(x_key, y_key)
    x, y = np.zeros(len(keys)), np.zeros(len(keys))
    x[np.searchsorted(keys, x_key)] = x_count
    y[np.searchsorted(keys, y_key)] = y_count
    ratio = np.full(len(keys), np.inf)
    np.divide(y, x, out=ratio, where=x > 0)
    order = np.argsort(ratio, kind="stable")
    x, y, ratio = x[order], y[order], ratio[order]
    both = (x > 0) & (y > 0)
    upto = np.searchsorted(ratio, ratio[both], "right")
    below, above = np.concatenate([[0], np.cumsum(x)])[upto], y.sum() - np.concatenate([[0], np.cumsum(y)])[upto]
    return float((1 / (below / x[both] + above / y[both])).sum())


def sketch(docs: DataFrame, k: int = K, m: int = REGISTERS, rows: int = ROWS) -> DataFrame:
    """(doc_id, whole: hash of all shingles and counts, bands: array of band hashes)."""

    def run(batches):
        hasher = tk.SpanHash(1)
        for b in batches:
            for lo, hi, data, offsets in tk.pieces(*tk.utf8(b.column("text"))):
                e, r, c = weighted_shingles(data, offsets, k, hasher)
                n = hi - lo
                sig = signatures(e, r, c, n, m)
                part = np.zeros((n, m // rows), np.uint64)
                for j in range(rows):
                    part = part * tk.BASE + tk.mix(sig[:, j :: rows][:, : m // rows])
                part = tk.mix(part + np.arange(m // rows, dtype=np.uint64)[None, :]).view(np.int64)
                each = tk.mix(e * tk.BASE + c.astype(np.uint64))
                whole = np.zeros((2, n), np.uint64)
                np.add.at(whole[0], r, each)
                np.add.at(whole[1], r, tk.mix(each + np.uint64(1)))
                some = np.flatnonzero(np.bincount(r, minlength=n) > 0)
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id").slice(lo, n).take(pa.array(some)), pa.array(whole[0][some].view(np.int64)), pa.array(whole[1][some].view(np.int64)), tk.list_array(part[some].ravel(), np.arange(len(some) + 1) * (m // rows), pa.int64())],
                    names=["doc_id", "whole", "whole2", "bands"],
                )

    return docs.filter("doc_id is not null").select("doc_id", "text").mapInArrow(run, "doc_id long, whole long, whole2 long, bands array<long>")


def shingle_sets(docs: DataFrame, k: int = K) -> DataFrame:
    """(doc_id, sh: sorted shingle hashes of 48 bits, each as often as it occurs)."""

    def run(batches):
        hasher = tk.SpanHash(1)
        for b in batches:
            for lo, hi, data, offsets in tk.pieces(*tk.utf8(b.column("text"))):
                e, r, c = weighted_shingles(data, offsets, k, hasher)
                e, r = np.repeat(e, c), np.repeat(r, c)
                off = np.searchsorted(r, np.arange(hi - lo + 1))
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(lo, hi - lo), tk.list_array(e.view(np.int64), off, pa.int64())], names=["doc_id", "sh"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, sh array<long>")


def _similar(batches):
    for b in batches:
        sets = []
        for name in ("x", "y"):
            col = b.column(name)
            sets.append((col.flatten().to_numpy(zero_copy_only=False), col.offsets.to_numpy() - col.offsets[0].as_py()))
        (xv, xo), (yv, yo) = sets
        out = []
        for i in range(b.num_rows):
            x, y = np.unique(xv[xo[i] : xo[i + 1]], return_counts=True), np.unique(yv[yo[i] : yo[i + 1]], return_counts=True)
            out.append(probability_jaccard(*x, *y))
        yield pa.RecordBatch.from_arrays([b.column("a"), b.column("b"), pa.array(out, pa.float64())], names=["a", "b", "similarity"])


def verify(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """(a, b, similarity) of pairs of doc_ids."""
    both = pairs.join(sets.select(F.col("doc_id").alias("a"), F.col("sh").alias("x")), "a").join(sets.select(F.col("doc_id").alias("b"), F.col("sh").alias("y")), "b")
    return both.select("a", "b", "x", "y").mapInArrow(_similar, "a long, b long, similarity double")


def pairs(docs: DataFrame, threshold: float = THRESHOLD, k: int = K, m: int = REGISTERS, rows: int = ROWS) -> DataFrame:
    """Verified edges (a < b): enough of them to connect every group that the bands find."""
    sk = keep(sketch(docs, k, m, rows), "bands")
    node = F.min("doc_id").alias("node")
    same = sk.groupBy("whole", "whole2").agg(node, F.min_by("bands", "doc_id").alias("bands"), F.count("*").alias("n"))
    same = keep(same, "nodes")
    twins = sk.select("doc_id", "whole", "whole2").join(same.filter("n > 1").select("whole", "whole2", "node"), ["whole", "whole2"]).filter("doc_id != node")
    edges = [keep(twins.select(F.col("node").alias("a"), F.col("doc_id").alias("b")).distinct(), "edges")]
    drop(sk)
    members = same.select(F.explode("bands").alias("h"), F.col("node").alias("id"))
    full = members.groupBy("h").agg(F.min("id").alias("hub"), F.max("id").alias("last")).filter("hub < last")
    members = keep(members.join(full.select("h"), "h").select("h", "id", F.col("id").alias("root")), "buckets")
    drop(same)
    if not members.isEmpty():
        wanted = members.select(F.col("id").alias("doc_id")).distinct()
        sets = keep(shingle_sets(docs.select("doc_id", "text").join(wanted, "doc_id", "left_semi").dropDuplicates(["doc_id"]), k), "sets")
    failed, hubs = None, 1
    while not members.isEmpty():
        ranked = keep(members.withColumn("turn", F.row_number().over(Window.partitionBy("h").orderBy("id"))), "ranked")
        drop(members)
        hub = ranked.filter(F.col("turn") <= hubs).select("h", F.col("id").alias("a"), F.col("root").alias("a_root"), F.col("turn").alias("a_turn"))
        star = ranked.withColumnRenamed("id", "b").join(hub, "h").filter("turn > a_turn and root != a_root").select("a", "b", "a_root", "root").distinct()
        star = keep(star if failed is None else star.join(failed, ["a", "b"], "left_anti"), "star")
        known = keep(verify(star.select("a", "b"), sets), "verified")
        linked, parted = known.filter(F.col("similarity") >= threshold).select("a", "b"), known.filter(F.col("similarity") < threshold).select("a", "b")
        edges.append(linked)
        failed = parted if failed is None else failed.unionByName(parted)
        moved = components(star.join(linked, ["a", "b"], "left_semi").select(F.col("a_root").alias("a"), F.col("root").alias("b")).distinct())
        # a hub has met all others of its bucket, so it leaves; a bucket of one component has nothing to tell any more
        rest = ranked.filter(F.col("turn") > hubs).join(moved.select(F.col("doc_id").alias("root"), F.col("root").alias("to")), "root", "left")
        rest = keep(rest.select("h", "id", F.coalesce("to", "root").alias("root")), "rest")
        open_ = rest.groupBy("h").agg(F.min("root").alias("low"), F.max("root").alias("high")).filter("low != high")
        members = keep(rest.join(open_.select("h"), "h"), "buckets")
        drop(ranked, star, rest, moved)
        hubs *= GROWTH
    out = edges[0]
    for e in edges[1:]:
        out = out.unionByName(e)
    return keep(out.distinct(), "pairs")


def components(edges: DataFrame) -> DataFrame:
    """(doc_id, root): least id of each connected group, by neighbours' minima and pointer jumping."""
    both = keep(edges.select("a", "b").union(edges.select("b", "a")).distinct(), "both")
    label = keep(both.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("least")).select("id", F.least("id", "least").alias("root")), "label")
    while True:
        near = both.join(label.withColumnRenamed("id", "b"), "b").groupBy(F.col("a").alias("id")).agg(F.min("root").alias("near"))
        step = label.join(near, "id").select("id", F.least("root", "near").alias("next"), F.col("root").alias("old"))
        jump = label.select(F.col("id").alias("next"), F.col("root").alias("over"))
        new = keep(step.join(jump, "next", "left").select("id", F.least("next", F.coalesce("over", "next")).alias("root"), "old"), "label")
        changed = not new.filter("root != old").isEmpty()
        drop(label)
        label = new.select("id", "root")
        if not changed:
            return label.withColumnRenamed("id", "doc_id")


def dedup(docs: DataFrame, threshold: float = THRESHOLD, k: int = K, m: int = REGISTERS, rows: int = ROWS) -> DataFrame:
    """The rows of `docs` that stay: all without a near copy, and one doc_id of each group."""
    found = components(pairs(docs, threshold, k, m, rows))
    (key,) = tk.fresh(docs, "id")
    gone = keep(found.filter("doc_id != root").select(F.col("doc_id").alias(key)), "gone")
    return docs.join(gone, docs["doc_id"] == gone[key], "left_anti")

"""Exact dedup against a minimal perfect hash over the distinct digests of a history.

The history's distinct SHA-256 digests are cut to shards by their hash.  Each shard becomes one row
of an index table: the bit arrays of a levelled perfect hash (every level keeps the keys that meet no
other in it; the rank of a key's bit is its slot) and, by slot, the full digest and the locator (doc_id)
of the winner, which is the least doc_id that has the text.  A look-up goes to one slot and compares all
bytes of the digest, so a text that the history lacks is never taken for a member.  Texts that are no
members are grouped by digest among themselves.

With a history, every row whose text it has goes, whatever its doc_id; of the others one row of the least doc_id
stays.  Without one, a table is its own history, and its winners stay.

Defined results: a null text has no digest and its row is kept; empty texts equal each other; of rows
that repeat both doc_id and text one is kept (any one, where other columns differ); a null doc_id loses to any
other; an empty history removes nothing; extra columns may have any name and come back as they are.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from . import text as tk
from .store import drop, keep

KEYS_PER_SHARD = 100_000
INDEX = "shard int, n long, sizes array<int>, bits binary, digests binary, winners array<long>"


def _matrix(column):
    """Digests as rows of 32 bytes."""
    return tk.utf8(column)[0].reshape(-1, 32)


def _halves(rows):
    """The first 16 bytes of every digest as two numbers."""
    return np.ascontiguousarray(rows[:, :8]).view("<u8").ravel(), np.ascontiguousarray(rows[:, 8:16]).view("<u8").ravel()


def _place(a, b, level, size):
    return (tk.mix(a ^ tk.mix(b + np.uint64((level + 1) * int(tk.BASE) % (1 << 64)))) % np.uint64(size)).astype(np.int64)


def build(a, b, gamma=1.5):
    """Perfect hash of distinct keys: (level sizes, bit per place)."""
    sizes, bits = [], []
    while len(a):
        size = max(8, int(gamma * len(a)))
        at = _place(a, b, len(sizes), size)
        count = np.bincount(at, minlength=size)
        bits.append(count == 1)
        sizes.append(size)
        rest = count[at] > 1
        a, b = a[rest], b[rest]
    return np.array(sizes, np.int64), np.concatenate(bits) if bits else np.empty(0, bool)


def slots(a, b, sizes, bits):
    """Slot of every key; a key that was not built in gets -1 or some slot of another."""
    rank = np.cumsum(bits) - 1
    slot = np.full(len(a), -1, np.int64)
    open_, base = np.arange(len(a)), 0
    for level, size in enumerate(sizes):
        at = base + _place(a[open_], b[open_], level, size)
        hit = bits[at]
        slot[open_[hit]] = rank[at[hit]]
        open_, base = open_[~hit], base + int(size)
    return slot


def _build_shard(key, table):
    rows = _matrix(table.column("digest"))
    a, b = _halves(rows)
    sizes, bits = build(a, b)
    order = np.argsort(slots(a, b, sizes, bits))
    winners = table.column("winner").combine_chunks().take(pa.array(order))
    return pa.table(
        [[key[0].as_py()], [len(rows)], [sizes.tolist()], [np.packbits(bits).tobytes()], [rows[order].tobytes()], [winners.to_pylist()]],
        schema=pa.schema([("shard", pa.int32()), ("n", pa.int64()), ("sizes", pa.list_(pa.int32())), ("bits", pa.binary()), ("digests", pa.binary()), ("winners", pa.list_(pa.int64()))]),
    )


FOUND = "doc_id long, digest binary, copies long, winner long, member boolean"


def _look_up(key, asked, index):
    rows = _matrix(asked.column("digest"))
    member, winner = np.zeros(len(rows), bool), pa.nulls(len(rows), pa.int64())
    if len(rows) and index.num_rows:
        sizes = np.array(index.column("sizes")[0].as_py(), np.int64)
        bits = np.unpackbits(np.frombuffer(index.column("bits")[0].as_py(), np.uint8))[: sizes.sum()].astype(bool)
        held = np.frombuffer(index.column("digests")[0].as_py(), np.uint8).reshape(-1, 32)
        at = slots(*_halves(rows), sizes, bits)
        member = (at >= 0) & (held[np.maximum(at, 0)] == rows).all(1)
        winner = index.column("winners").combine_chunks().flatten().take(pa.array(np.maximum(at, 0), mask=~member))
    return pa.table([*(asked.column(c).combine_chunks() for c in ("doc_id", "digest", "copies")), winner, pa.array(member)], names=["doc_id", "digest", "copies", "winner", "member"])


def digest_of(text) -> Column:
    return F.unhex(F.sha2(F.col(text).cast("binary"), 256))


def digests(docs: DataFrame, shards: int) -> DataFrame:
    """(doc_id, digest, shard, copies) of the texts that are not null, a row for each doc_id and digest."""
    return (
        docs.filter("text is not null").select("doc_id", digest_of("text").alias("digest")).groupBy("doc_id", "digest").agg(F.count("*").alias("copies"))
        .withColumn("shard", F.pmod(F.xxhash64("digest"), F.lit(shards)).cast("int"))
    )


def index(history: DataFrame, shards: int) -> DataFrame:
    """One row per shard: the perfect hash, and the slots' digests and winners. Takes rows of digests()."""
    return history.groupBy("shard", "digest").agg(F.min("doc_id").alias("winner")).groupBy("shard").applyInArrow(_build_shard, INDEX)


def repeats(docs: DataFrame, history: DataFrame | None = None, keys_per_shard: int = KEYS_PER_SHARD) -> DataFrame:
    """(doc_id, digest, copies, stays): doc_ids and texts of which some row goes.

    `stays` tells whether one row of them is left: the case of a winner that has several rows.  The number of
    shards follows the history's size; what is found does not depend on it.
    """
    known_by = docs if history is None else history
    shards = max(1, -(-known_by.count() // keys_per_shard))  # of Parquet, this reads footers only
    mine = keep(digests(docs, shards), "digests")
    known = keep(index(mine if history is None else digests(history, shards), shards), "mph")
    found = mine.groupBy("shard").cogroup(known.groupBy("shard")).applyInArrow(_look_up, FOUND)
    if history is None:  # every text is a member
        named = found.select("doc_id", "digest", "copies", F.col("doc_id").eqNullSafe(F.col("winner")).alias("stays"))
        out = keep(named.filter("not stays or copies > 1"), "repeats")
    else:
        found = keep(found.drop("winner"), "found")
        old = found.filter("member").select("doc_id", "digest", "copies", F.lit(False).alias("stays"))
        new = found.filter("not member")
        grouped = new.groupBy("digest").agg(F.min("doc_id").alias("winner"), F.count("*").alias("rows"), F.max("copies").alias("most")).filter("rows > 1 or most > 1")
        new = new.join(grouped, "digest").select("doc_id", "digest", "copies", F.col("doc_id").eqNullSafe(F.col("winner")).alias("stays"))
        out = keep(old.unionByName(new.filter("not stays or copies > 1")), "repeats")
        drop(found)
    drop(mine, known)
    return out


def dedup(docs: DataFrame, history: DataFrame | None = None, keys_per_shard: int = KEYS_PER_SHARD) -> DataFrame:
    """The rows of `docs` that stay, with their columns; see the module for what a history changes."""
    gone = repeats(docs, history, keys_per_shard)
    names, (key, mark) = docs.columns, tk.fresh(docs, "key", "mark")
    parts = lambda stays: gone.filter(f"stays = {stays}").select(F.col("doc_id").alias(key), F.col("digest").alias(mark))
    same = lambda left, right: left["doc_id"].eqNullSafe(right[key]) & (F.unhex(F.sha2(left["text"].cast("binary"), 256)) == right[mark])
    # the list of repeats grows with the corpus, so its join is the same at every size
    lost, many = parts("false").hint("shuffle_hash"), parts("true")
    left = docs.join(lost, same(docs, lost), "left_anti").select([docs[f"`{c}`"] for c in names])
    if many.isEmpty():
        return left
    single, several = left.join(many, same(left, many), "left_anti"), left.join(many, same(left, many), "left_semi")
    return single.unionByName(several.dropDuplicates(["doc_id", "text"]))


def dedup_by_history(docs: DataFrame, old: str, keys_per_shard: int = KEYS_PER_SHARD) -> DataFrame:
    """One row of each text of `docs`, of which the rows that meet the condition `old` came first.

    These are freed of repeats by themselves; the others lose what the first have, and repeats among themselves.
    Where the condition is null it counts as not met.
    """
    is_old = F.coalesce(F.expr(old), F.lit(False))
    first, later = docs.filter(is_old), docs.filter(~is_old)
    return dedup(first, None, keys_per_shard).unionByName(dedup(later, first, keys_per_shard))

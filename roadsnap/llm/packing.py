"""Sum-of-squares online packing of token sequences into windows of a fixed length.

A level array counts the partly filled windows by fill level.  Every arriving piece goes to the level
(0: a new window) for which the sum of squared counts after placing it is least; a window that becomes
full leaves the array.  Ties go to the fuller level, of one level's windows to the one that came to it first.
A text longer than a window fills whole windows and arrives with its rest.

Texts are dealt to shards of consecutive doc_ids (`per_shard` of them), so where a text goes depends neither on the
number of rows nor on texts of other shards, and a table that grows keeps its packing but for its last shard.  Where
doc_ids are sparse, `shards` deals by their hash instead, to a number that the caller fixes.  A shard is packed
in doc_id order; what it loses are its last partly filled windows.

A row of the result is a piece of a text with its ids, so `windows` only has to put pieces together.

Defined results: a text without tokens (null, empty) has one row with window null, no ids and 0 tokens; rows that
share a doc_id are packed one after the other, the shorter first; a null doc_id comes first; a text of any length
is cut to as many windows as it fills; only doc_id and text are read, so other columns do not matter.
"""

from __future__ import annotations

from collections import defaultdict, deque

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, functions as F

from . import text as tk, tokens as tok

WINDOW = 2048
PER_SHARD = 10_000


class Packer:
    def __init__(self, window: int = WINDOW):
        self.window = window
        self.level = np.zeros(window, np.int64)  # windows by fill; place 0 is for new ones
        self.open = defaultdict(deque)
        self.next = 0

    def place(self, size: int) -> tuple[int, int]:
        """(window, offset) for a piece of 1 <= size <= window tokens."""
        b, n = self.window, self.level
        top = b - size  # the fullest level that it fits in
        best, cost = 0, (2 * n[size] + 1 if size < b else 0)
        if top >= 1:
            grow = np.empty(top, np.int64)  # for levels 1..top
            grow[: top - 1] = 2 * (n[size + 1 : b] - n[1:top]) + 2
            grow[top - 1] = 1 - 2 * n[top]
            grow[n[1 : top + 1] == 0] = np.iinfo(np.int64).max
            at = top - 1 - int(np.argmin(grow[::-1]))
            if grow[at] <= cost and n[at + 1]:
                best = at + 1
        if best == 0:
            window, self.next = self.next, self.next + 1
        else:
            window = self.open[best].popleft()
            n[best] -= 1
        fill = best + size
        if fill < b:
            n[fill] += 1
            self.open[fill].append(window)
        return window, best

    def add(self, size: int) -> list[tuple[int, int, int]]:
        """(window, offset, tokens) for every piece of a text."""
        out = []
        while size > self.window:
            out.append((self.next, 0, self.window))
            self.next, size = self.next + 1, size - self.window
        if size:
            out.append((*self.place(size), size))
        return out


SCHEMA = "doc_id long, piece int, shard long, window int, position int, n_tokens int, ids array<int>"


def place_all(sizes, packer: Packer) -> np.ndarray:
    """(text, piece, window, position, tokens) of texts of these sizes in order, as arrays; window -1: no tokens."""
    cells = []
    for i, size in enumerate(sizes):
        cells += [(i, j, *g) for j, g in enumerate(packer.add(size) or [(-1, -1, 0)])]
    return np.array(cells, np.int64).reshape(-1, 5).T


def _pack_sorted(window):
    def run(batches):
        """Rows come shard by shard, in order; the pieces of a batch leave with it, so no shard is held."""
        packer, now = None, None
        for b in batches:
            shard = b.column("shard").to_numpy()
            edge = np.concatenate([[0], np.flatnonzero(shard[1:] != shard[:-1]) + 1, [len(shard)]]) if len(shard) else [0]
            for lo, hi in zip(edge[:-1], edge[1:]):
                if packer is None or shard[lo] != now:
                    packer, now = Packer(window), shard[lo]
                part = b.slice(lo, hi - lo)
                text, piece, at, position, size = place_all(part.column("n_tokens").to_pylist(), packer)
                none = at < 0
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id").take(pa.array(text)), pa.array(piece, pa.int32()), part.column("shard").take(pa.array(text)),
                     pa.array(at.astype(np.int32), pa.int32(), mask=none), pa.array(position.astype(np.int32), pa.int32(), mask=none), pa.array(size, pa.int32()),
                     pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(size)), pa.int32()), part.column("ids").flatten())],
                    names=["doc_id", "piece", "shard", "window", "position", "n_tokens", "ids"],
                )

    return run


def pack_ids(coded: DataFrame, window: int = WINDOW, per_shard: int = PER_SHARD, shards: int | None = None) -> DataFrame:
    """Pack rows of (doc_id, n_tokens, ids)."""
    parts = int(coded.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    by = F.expr(f"floor(doc_id / {per_shard})") if shards is None else F.pmod(F.xxhash64("doc_id"), F.lit(shards))
    dealt = coded.select("doc_id", "n_tokens", "ids", F.coalesce(by.cast("long"), F.lit(-1)).alias("shard"))
    # shards are heavy, so they are dealt evenly by number; a hash would leave some tasks without and give others several
    placed = dealt.repartitionById(parts, F.pmod("shard", F.lit(parts)).cast("int")).sortWithinPartitions("shard", F.asc_nulls_first("doc_id"), "n_tokens")
    return placed.mapInArrow(_pack_sorted(window), SCHEMA)


def pack(docs: DataFrame, window: int = WINDOW, folder: str = tok.TOKENIZERS, per_shard: int = PER_SHARD, shards: int | None = None) -> DataFrame:
    """Windows of the texts' byte-level BPE ids: a row for each piece of a text, with its ids."""
    return pack_ids(tok.token_ids(docs, folder), window, per_shard, shards)


def windows(pieces: DataFrame) -> DataFrame:
    """(shard, window, doc_ids, ids): the windows themselves, each with the texts it holds in order."""
    part = F.sort_array(F.collect_list(F.struct("position", "doc_id", "ids")))
    held = pieces.filter("window is not null").groupBy("shard", "window").agg(part.alias("p"))
    return held.select("shard", "window", F.transform("p", lambda p: p["doc_id"]).alias("doc_ids"), F.flatten(F.transform("p", lambda p: p["ids"])).alias("ids"))

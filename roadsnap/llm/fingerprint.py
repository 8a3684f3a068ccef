"""Document fingerprints: the `k` least hashes of a text's distinct word shingles.

Two sketches of the same shingle length merge to the sketch of the union, so a corpus, a source or a text
kept in parts is sketched by merging.  From sketches alone follow estimates of the distinct shingle count,
of resemblance (Jaccard) and of containment; they are exact while a sketch holds all of the shingles.
against() compares documents with benchmark items by all of their shingles, so it is exact at every size.

Hashes have 52 bits.  Defined results: a null or empty text has an empty sketch, count 0, resemblance
and containment 0; a text shorter than a shingle is one shingle.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from . import text as tk
from .store import keep

K, SHINGLE = 128, 5
SPACE = 1 << 52
#: Bits of the benchmark's bitmap and of one block of it; fixed, so the bitmap can be broadcast.
MAP_BITS, BLOCK_BITS = 27, 15


def hashes(data, offsets, shingle, hasher):
    """Distinct shingle hashes of every row, sorted, ragged. Handles at most 4096 rows."""
    starts, ends, rows = tk.words(data, offsets)
    h, r = tk.shingles(hasher(data, starts, ends, fold=True), rows, len(offsets) - 1, shingle)
    key = (r.astype(np.uint64) << np.uint64(52)) | (h >> np.uint64(12))
    key.sort()
    if len(key):
        key = key[np.concatenate([[True], key[1:] != key[:-1]])]
    r = (key >> np.uint64(52)).astype(np.int64)
    return (key & np.uint64(SPACE - 1)).astype(np.int64), np.searchsorted(r, np.arange(len(offsets)))


def cut_rows(h, off, kept):
    """The hashes that are kept, with their offsets."""
    return h[kept], np.concatenate([[0], np.cumsum(kept)])[off]


def bottom(h, off, k):
    """Bottom-k hashes of every row."""
    row = np.repeat(np.arange(len(off) - 1), np.diff(off))
    return cut_rows(h, off, np.arange(len(h)) - off[row] < k)


def distinct(sketch: np.ndarray, k: int) -> float:
    return float(len(sketch)) if len(sketch) < k else (k - 1) * SPACE / (int(sketch[k - 1]) + 1)


def merge(a: np.ndarray, b: np.ndarray, k: int) -> np.ndarray:
    return np.union1d(a, b)[:k]


def compare(a: np.ndarray, ka: int, b: np.ndarray, kb: int) -> tuple[float, float]:
    """(resemblance, containment of a in b): counted below the bound to which both sketches are complete."""
    if not len(a) or not len(b):
        return 0.0, 0.0
    bound = min(int(a[-1]) if len(a) >= ka else SPACE, int(b[-1]) if len(b) >= kb else SPACE)
    x, y = a[: np.searchsorted(a, bound, "right")], b[: np.searchsorted(b, bound, "right")]
    both = int(np.isin(x, y, assume_unique=True).sum())
    union = len(x) + len(y) - both
    return (both / union if union else 0.0), (both / len(x) if len(x) else 0.0)


def _hashed(column, shingle, hasher):
    """(first row, last row, hashes, offsets) of the pieces of a batch."""
    for first, last, data, offsets in tk.pieces(*tk.utf8(column)):
        for lo in range(0, last - first, 4096):
            hi = min(lo + 4096, last - first)
            yield first + lo, first + hi, *hashes(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo], shingle, hasher)


def sketch(docs: DataFrame, k: int = K, shingle: int = SHINGLE, key: str = "doc_id") -> DataFrame:
    """(key, n_shingles, sketch) of every row."""
    kind = {f.name: f.dataType.simpleString() for f in docs.schema}[key]

    def run(batches):
        hasher = tk.SpanHash(21)
        for b in batches:
            for lo, hi, h, off in _hashed(b.column("text"), shingle, hasher):
                h, off = bottom(h, off, k)
                n = pa.array([distinct(h[s:e], k) for s, e in zip(off[:-1], off[1:])], pa.float64())
                yield pa.RecordBatch.from_arrays([b.column(key).slice(lo, hi - lo), n, tk.list_array(h, off, pa.int64())], names=[key, "n_shingles", "sketch"])

    return docs.select(key, "text").mapInArrow(run, f"{key} {kind}, n_shingles double, sketch array<long>")


def item_hashes(items: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """(item_id, h, item_n): all distinct shingle hashes of every item, and their number."""
    kind = {f.name: f.dataType.simpleString() for f in items.schema}["item_id"]

    def run(batches):
        hasher = tk.SpanHash(21)
        for b in batches:
            for lo, hi, h, off in _hashed(b.column("text"), shingle, hasher):
                yield pa.RecordBatch.from_arrays([b.column("item_id").slice(lo, hi - lo).take(pa.array(np.repeat(np.arange(hi - lo), np.diff(off)))), pa.array(h)], names=["item_id", "h"])

    every = items.select("item_id", "text").mapInArrow(run, f"item_id {kind}, h long").distinct()
    return every.withColumn("item_n", F.count("*").over(Window.partitionBy("item_id")))


def bitmap(every: DataFrame) -> np.ndarray:
    """Bytes in which the bit of each hash `h` is set; of MAP_BITS bits, however many hashes there are."""
    size = 1 << (BLOCK_BITS - 3)

    def run(batches):
        held = {}
        for b in batches:
            block, place = b.column("block").to_numpy(), b.column("place").to_numpy()
            for x in np.unique(block):
                at = place[block == x]
                np.bitwise_or.at(held.setdefault(int(x), np.zeros(size, np.uint8)), at >> 3, (1 << (at & 7)).astype(np.uint8))
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int64()), pa.array([x.tobytes() for x in held.values()], pa.binary())], names=["block", "bits"])

    low = F.col("h").bitwiseAND((1 << MAP_BITS) - 1)
    places = every.select(F.shiftright(low, BLOCK_BITS).alias("block"), low.bitwiseAND((1 << BLOCK_BITS) - 1).alias("place")).repartition("block")
    out = np.zeros(1 << (MAP_BITS - 3), np.uint8)
    for r in places.mapInArrow(run, "block long, bits binary").collect():
        out[r["block"] * size : (r["block"] + 1) * size] = np.frombuffer(r["bits"], np.uint8)
    return out


def against(docs: DataFrame, benchmark: DataFrame, k: int = K, shingle: int = SHINGLE) -> DataFrame:
    """sketch() of `docs`, with the exact resemblance and containment in the benchmark as one set, and `items`.

    items: of each item with a common shingle its item_id, the common shingles, the resemblance, the part of the
    item that is in the document (containment) and the part of the document that is in the item.  The bitmap only
    keeps hashes from the join that no item has; what passes it by chance finds no item there.
    """
    spark = docs.sparkSession
    every = keep(item_hashes(benchmark, shingle), "items")
    total = every.select("h").distinct().count()
    bits = spark.sparkContext.broadcast(bitmap(every))
    kind = {f.name: f.dataType.simpleString() for f in docs.schema}["doc_id"]

    def run(batches):
        hasher = tk.SpanHash(21)
        for b in batches:
            for lo, hi, h, off in _hashed(b.column("text"), shingle, hasher):
                at = h & ((1 << MAP_BITS) - 1)
                hits, hit_off = cut_rows(h, off, (bits.value[at >> 3] >> (at & 7)) & 1 > 0)
                s, s_off = bottom(h, off, k)
                n = pa.array([distinct(s[x:y], k) for x, y in zip(s_off[:-1], s_off[1:])], pa.float64())
                cols = [b.column(c).slice(lo, hi - lo) for c in ("__row", "doc_id")] + [n, tk.list_array(s, s_off, pa.int64()), pa.array(np.diff(off).astype(np.int64)), tk.list_array(hits, hit_off, pa.int64())]
                yield pa.RecordBatch.from_arrays(cols, names=["__row", "doc_id", "n_shingles", "sketch", "n", "hits"])

    part = docs.select(F.monotonically_increasing_id().alias("__row"), "doc_id", "text").mapInArrow(run, f"__row long, doc_id {kind}, n_shingles double, sketch array<long>, n long, hits array<long>")
    part = keep(part, "hits")
    found = part.select("__row", "n", F.explode("hits").alias("h")).join(every, "h")
    pairs = found.groupBy("__row", "n", "item_id", "item_n").agg(F.count("*").alias("common"))
    item = F.struct("item_id", "common", (F.col("common") / (F.col("n") + F.col("item_n") - F.col("common"))).alias("resemblance"), (F.col("common") / F.col("item_n")).alias("containment"), (F.col("common") / F.col("n")).alias("of_document"))
    items = pairs.groupBy("__row").agg(F.sort_array(F.collect_list(item)).alias("items"))
    union = found.groupBy("__row").agg(F.countDistinct("h").alias("any"))
    some = part.filter(F.size("hits") > 0).drop("hits").join(items.join(union, "__row").hint("shuffle_hash"), "__row", "left")
    none = part.filter(F.size("hits") == 0).drop("hits").select("*", F.lit(None).cast(items.schema["items"].dataType).alias("items"), F.lit(None).cast("long").alias("any"))
    both = F.coalesce("any", F.lit(0))
    resembles = F.when(both > 0, both / (F.col("n") + F.lit(total) - both)).otherwise(0.0)
    contained = F.when(both > 0, both / F.col("n")).otherwise(0.0)
    return some.unionByName(none).select("doc_id", "n_shingles", "sketch", resembles.alias("reference_resemblance"), contained.alias("reference_containment"), F.coalesce("items", F.array().cast(items.schema["items"].dataType)).alias("items"))


def merged(sketched: DataFrame, by: str, k: int = K) -> DataFrame:
    """(by, sketch): sketches merged within each partition first, so that few rows travel."""
    kind = {f.name: f.dataType.simpleString() for f in sketched.schema}[by]
    schema = f"{by} {kind}, sketch array<long>"

    def partial(batches):
        held = {}
        for b in batches:
            for name, s in zip(b.column(by).to_pylist(), b.column("sketch")):
                s = np.asarray(s.values.to_numpy() if s.is_valid else [], np.int64)
                held[name] = merge(held[name], s, k) if name in held else s[:k]
        yield pa.RecordBatch.from_arrays([pa.array(list(held), b_type), pa.array([x.tolist() for x in held.values()], pa.list_(pa.int64()))], names=[by, "sketch"])

    from pyspark.sql.pandas.types import to_arrow_type

    b_type = to_arrow_type(sketched.schema[by].dataType)

    def final(batches):
        yield from partial(batches)

    part = sketched.select(by, "sketch").mapInArrow(partial, schema)
    return part.repartition(F.col(by)).mapInArrow(final, schema)


# ---------------------------------------------------------------- the same estimates as Spark columns


def resemblance(a: Column, b: Column, k: int = K) -> Column:
    union = F.slice(F.array_sort(F.array_union(a, b)), 1, k)
    return F.when(F.size(union) > 0, F.size(F.array_intersect(F.array_intersect(union, a), b)) / F.size(union)).otherwise(0.0)

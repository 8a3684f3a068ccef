"""Vectorised text kernels shared by the operators: every function works on one Arrow batch in numpy.

A *word* is a maximal run of bytes above 0x20, so ASCII blanks and control characters separate words;
other Unicode blanks count as letters.  Null texts behave as empty ones and have no words.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BASE = np.uint64(0x9E3779B97F4A7C15)
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
CHUNK = 1 << 21  # bytes of text handled at once, bounds the memory of a kernel


def mix(x):
    """Finaliser of splitmix64: spreads every input bit over all 64 output bits."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= _M1
    x ^= x >> np.uint64(27)
    x *= _M2
    x ^= x >> np.uint64(31)
    return x


def utf8(column):
    """Bytes and row offsets of an Arrow string column, whatever its slice or offset width."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_binary()), b"")
    offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    raw = column.buffers()[2]
    data = np.frombuffer(raw, np.uint8) if raw is not None else np.empty(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def pieces(data, offsets, limit=CHUNK):
    """Cut a batch to (first row, last row, bytes, offsets) of at most `limit` bytes, a row at least."""
    first, n = 0, len(offsets) - 1
    while first < n:
        last = max(first + 1, int(np.searchsorted(offsets, offsets[first] + limit, "right")) - 1)
        last = min(last, n)
        yield first, last, data[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first]
        first = last


def runs(kind, offsets):
    """Start, end and row of every maximal run of one non-zero kind of byte within a row."""
    n = len(kind)
    if n == 0:
        return (np.empty(0, np.int64),) * 3
    edge = np.empty(n + 1, bool)
    edge[0] = edge[n] = True
    np.not_equal(kind[1:], kind[:-1], out=edge[1:n])
    edge[offsets] = True
    cuts = np.flatnonzero(edge)
    starts, ends = cuts[:-1], cuts[1:]
    keep = kind[starts] != 0
    starts, ends = starts[keep], ends[keep]
    return starts, ends, np.searchsorted(offsets, starts, "right") - 1


def words(data, offsets):
    return runs((data > 32).view(np.uint8), offsets)


class SpanHash:
    """64-bit hashes of byte spans from prefix sums: the cost is a few passes, however many spans."""

    def __init__(self, seed=1):
        self.table = mix(np.arange(256, dtype=np.uint64) + np.uint64(256 * seed))
        self.power = self.inverse = np.empty(0, np.uint64)

    def _grow(self, n):
        if len(self.power) < n:
            n = max(n, CHUNK)
            base, inv = int(BASE) | 1, pow(int(BASE) | 1, -1, 1 << 64)
            for name, b in (("power", base), ("inverse", inv)):
                x = np.full(n + 1, b, np.uint64)
                x[0] = 1
                setattr(self, name, np.multiply.accumulate(x))

    def __call__(self, data, starts, ends, fold=False):
        self._grow(len(data) + 1)
        table = self.table
        if fold:  # ASCII letters compare without case
            table = table.copy()
            table[65:91] = table[97:123]
        prefix = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(table[data] * self.power[: len(data)], out=prefix[1:])
        h = (prefix[ends] - prefix[starts]) * self.inverse[starts]
        return mix(h + (ends - starts).astype(np.uint64) * _M2)


def grams(hashes, rows, k):
    """Hash of every window of k consecutive items of a row: (hash, row, index of its first item)."""
    n = len(hashes) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64)
    h = hashes[:n].copy()
    for j in range(1, k):
        h = h * BASE + hashes[j : n + j]
    inside = np.flatnonzero(rows[:n] == rows[k - 1 :])
    return mix(h[inside]), rows[inside], inside


def shingles(hashes, rows, n_rows, k):
    """Windows of k words; a row with fewer words, but one at least, is one window of what it has."""
    h, r, first = grams(hashes, rows, k)
    count = np.bincount(rows, minlength=n_rows)
    short = np.flatnonzero((count > 0) & (count < k))
    if len(short):
        begin = np.searchsorted(rows, short)
        extra = np.zeros(len(short), np.uint64)
        for j in range(k - 1):
            has = count[short] > j
            extra[has] = extra[has] * BASE + hashes[begin[has] + j]
        h, r = np.concatenate([h, mix(extra + np.uint64(k))]), np.concatenate([r, short])
        order = np.argsort(r, kind="stable")
        h, r = h[order], r[order]
    return h, r


def gather(values, offsets, pick):
    """Concatenate the ragged rows `pick` of (values, offsets): (values, offsets)."""
    size = (offsets[1:] - offsets[:-1])[pick]
    out = np.zeros(len(pick) + 1, np.int64)
    np.cumsum(size, out=out[1:])
    at = np.arange(out[-1]) - np.repeat(out[:-1] - offsets[:-1][pick], size)
    return values[at], out


def list_array(values, offsets, kind):
    return pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(values, kind))


def drop_columns(df, names):
    """A frame without the columns (in any case) that an operator adds itself."""
    low = {n.lower() for n in names}
    return df.select([df[f"`{c}`"] for c in df.columns if c.lower() not in low])


def fresh(df, *names):
    """The given names, each with underscores in front until no column of `df` has it (in any case)."""
    taken, out = {c.lower() for c in df.columns}, []
    for n in names:
        while n.lower() in taken:
            n = "_" + n
        taken.add(n.lower())
        out.append(n)
    return out


def with_fields(df, **extra):
    """Schema of a frame and further fields, each given by the name of its type."""
    from pyspark.sql.types import StructField, StructType, _parse_datatype_string

    return StructType([*df.schema.fields, *(StructField(n, _parse_datatype_string(t)) for n, t in extra.items())])


def ship(spark, value):
    """Broadcast an object of this package by value; open it on a worker with opened()."""
    from pyspark import cloudpickle

    return spark.sparkContext.broadcast(cloudpickle.dumps(value))


def opened(shared):
    import pickle

    return pickle.loads(shared.value)


def map_arrow(df, kernel, schema):
    """mapInArrow for frames whose columns may have any name, dots included."""
    names, result = df.columns, [f.name for f in schema]
    from pyspark.sql.types import StructField, StructType

    def run(batches):
        named = (pa.RecordBatch.from_arrays(b.columns, names=names) for b in batches)
        for out in kernel(named):
            yield pa.RecordBatch.from_arrays(out.columns, names=[f"c{i}" for i in range(len(result))])

    plain = df.toDF(*[f"c{i}" for i in range(len(names))])
    return plain.mapInArrow(run, StructType([StructField(f"c{i}", f.dataType) for i, f in enumerate(schema)])).toDF(*result)

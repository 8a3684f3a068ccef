"""Quality classifier: logistic regression on hashed word n-grams, fitted by FTRL-proximal updates.

Features are the distinct unigrams and bigrams of a text's tokens (runs of letters and digits, runs of
punctuation; ASCII letters without case), hashed to `2**bits` columns with value 1, plus a constant.
Two heads share the features: quality and toxicity.  A text is kept where quality is at least
`min_quality` and toxicity at most `max_toxic`.

Defined results: a null or empty text has only the constant; a text with a null label is not used for
fitting, and of several labels of a doc_id the greatest counts; rows without a doc_id or that share one are scored as all
others; with no labelled rows at all every probability is 0.5 and every text is kept; texts of any length are read whole;
extra columns may have any name, but p_quality and p_toxic are replaced.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import text as tk

BITS = 20
#: Rows used for fitting, at most about this many: a hash sample of the labelled documents.
MAX_ROWS = 20_000
EPOCHS = 4  # FTRL constants are set so that a column needs about ten labelled texts to gain a weight


def tokens(data, offsets, hasher):
    """Hash and row of every token of a batch."""
    kind = np.full(256, 1, np.uint8)
    kind[:33] = 0
    for lo, hi in ((33, 48), (58, 65), (91, 97), (123, 128)):
        kind[lo:hi] = 2
    starts, ends, rows = tk.runs(kind[data], offsets)
    return hasher(data, starts, ends, fold=True), rows


def features(data, offsets, bits, hasher):
    """Distinct hashed n-gram columns of every row, sorted: (columns, row offsets). Column 0 is the constant."""
    n = len(offsets) - 1
    h, rows = tokens(data, offsets, hasher)
    pair, pair_rows, _ = tk.grams(h, rows, 2)
    shift = np.uint64(64 - bits)
    column = np.concatenate([tk.mix(h) >> shift, tk.mix(pair + np.uint64(7)) >> shift]).astype(np.int64)
    column[column == 0] = 1
    key = (np.concatenate([rows, pair_rows]) << bits) | column
    key = np.concatenate([key, np.arange(n, dtype=np.int64) << bits])
    key.sort()
    key = key[np.concatenate([[True], key[1:] != key[:-1]])] if len(key) else key
    offsets = np.searchsorted(key >> bits, np.arange(n + 1))
    return key & ((1 << bits) - 1), offsets


class Ftrl:
    """Per-coordinate FTRL-proximal for several logistic heads over the same binary features."""

    def __init__(self, bits=BITS, heads=2, alpha=1.0, beta=1.0, l1=6.0, l2=0.0):
        self.bits, self.alpha, self.beta, self.l1, self.l2 = bits, alpha, beta, l1, l2
        self.z = np.zeros((heads, 1 << bits))
        self.n = np.zeros((heads, 1 << bits))

    def _weights(self, z, n):
        w = (np.sign(z) * self.l1 - z) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2)
        return np.where(np.abs(z) <= self.l1, 0.0, w)

    def update(self, columns, labels):
        z, n = self.z[:, columns], self.n[:, columns]
        w = self._weights(z, n)
        p = 1 / (1 + np.exp(-np.clip(w.sum(1), -35, 35)))
        g = (p - labels)[:, None]
        sigma = (np.sqrt(n + g * g) - np.sqrt(n)) / self.alpha
        self.z[:, columns] = z + g - sigma * w
        self.n[:, columns] = n + g * g
        return p

    def weights(self):
        return self._weights(self.z, self.n).astype(np.float32)


def fit(columns, offsets, labels, bits=BITS, epochs=EPOCHS, seed=7, **kw):
    """Weights (heads, 2**bits) from ragged features and a label matrix (rows, heads)."""
    model = Ftrl(bits, labels.shape[1], **kw)
    for epoch in range(epochs):
        for i in np.random.default_rng(seed + epoch).permutation(len(labels)):
            model.update(columns[offsets[i] : offsets[i + 1]], labels[i])
    return model.weights()


def probabilities(columns, offsets, weights):
    """Sparse dot products: one row of the result per head."""
    rows = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    total = [np.bincount(rows, weights=w[columns], minlength=len(offsets) - 1) for w in weights]
    return 1 / (1 + np.exp(-np.clip(total, -35, 35)))


def sample(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS) -> DataFrame:
    """Labelled texts for fitting: all, or a hash sample of about `max_rows` where there are more."""
    good = labels.select("doc_id", "quality", "toxic").dropna().groupBy("doc_id").agg(F.max("quality").alias("quality"), F.max("toxic").alias("toxic"))
    count = labels.count()
    share = 1 << 30 if count <= max_rows else int((1 << 30) * max_rows / count)
    good = good.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < share)
    # at most about max_rows small rows, so this side is broadcast
    return docs.select("doc_id", "text").join(F.broadcast(good), "doc_id")


def train(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS, bits: int = BITS, **kw) -> np.ndarray:
    """Fit on `docs` joined with `labels` (doc_id, quality, toxic); features are built on the executors."""

    def featurise(batches):
        hasher = tk.SpanHash(3)
        for b in batches:
            for lo, hi, data, offsets in tk.pieces(*tk.utf8(b.column("text"))):
                col, off = features(data, offsets, bits, hasher)
                yield pa.RecordBatch.from_arrays(
                    [b.column(n).slice(lo, hi - lo) for n in ("doc_id", "quality", "toxic")] + [tk.list_array(col.astype(np.int32), off, pa.int32())],
                    names=["doc_id", "quality", "toxic", "col"],
                )

    rows = (
        sample(docs, labels, max_rows)
        .select("doc_id", "text", F.col("quality").cast("int").alias("quality"), F.col("toxic").cast("int").alias("toxic"))
        .mapInArrow(featurise, "doc_id long, quality int, toxic int, col array<int>")
        .toArrow()
        .sort_by("doc_id")
    )
    if rows.num_rows == 0:
        return np.zeros((2, 1 << bits), np.float32)
    lists = rows.column("col").combine_chunks()
    offsets = np.concatenate([[0], np.cumsum(np.diff(lists.offsets.to_numpy()))])
    y = np.stack([rows.column(c).to_numpy().astype(float) for c in ("quality", "toxic")], 1)
    return fit(lists.flatten().to_numpy(), offsets, y, bits, **kw)


def score(docs: DataFrame, weights: np.ndarray) -> DataFrame:
    """All columns of `docs`, and p_quality and p_toxic (which replace columns of these names)."""
    spark = docs.sparkSession
    docs = tk.drop_columns(docs, ["p_quality", "p_toxic"])
    used = np.flatnonzero(np.any(weights != 0, 0))  # most are 0: only the others travel
    model = spark.sparkContext.broadcast((used, weights[:, used], weights.shape[1]))
    bits = int(weights.shape[1]).bit_length() - 1

    def run(batches):
        at, values, width = model.value
        w = np.zeros((len(values), width), np.float32)
        w[:, at] = values
        hasher = tk.SpanHash(3)
        for b in batches:
            p = [probabilities(*features(data, offsets, bits, hasher), w) for _, _, data, offsets in tk.pieces(*tk.utf8(b.column("text")))]
            p = np.concatenate(p, 1) if p else np.empty((2, 0))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(p[0]), pa.array(p[1])], names=[*b.schema.names, "p_quality", "p_toxic"])

    return tk.map_arrow(docs, run, tk.with_fields(docs, p_quality="double", p_toxic="double"))


def classify(docs: DataFrame, labels: DataFrame, min_quality: float = 0.5, max_toxic: float = 0.5, max_rows: int = MAX_ROWS) -> DataFrame:
    """The texts that pass, with their two probabilities."""
    scored = score(docs, train(docs, labels, max_rows))
    return scored.filter(f"p_quality >= {min_quality} and p_toxic <= {max_toxic}")

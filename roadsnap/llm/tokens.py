"""Byte-level BPE ids of whole texts, and directly addressable codes for them.

Tokenising: a text is cut before every blank that follows a non-blank, where no pre-token of the public
pattern can cross; each distinct unit of a task is encoded once and the ids are gathered.

Codes: an id is cut to chunks of `bits` bits.  Level 0 holds the lowest chunk of every id with a bitmap that
says whether the id goes on; level 1 holds the next chunk of those that do, and so on.  A directory of
set-bit counts before every 512 bits gives the place in the next level, so the i-th id of a text is
read from one place per level, without decoding anything else.

Defined results: a null or empty text has no ids and a blob with no level; every row has one row in the result,
with its doc_id as it is, null and repeated ones too; a text of any length is read whole; other columns are not read.
"""

from __future__ import annotations

import base64

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import text as tk

TOKENIZERS = "/opt/tokenizers"
CHUNK_BITS = 8
BLOCK = 512
#: Pre-token pattern of the public byte-level vocabulary.
PATTERN = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def load_bpe(folder: str = TOKENIZERS, name: str = "byte_bpe_50k.tiktoken"):
    """The vocabulary's ranks; the file is public and stays where it is."""
    with open(f"{folder}/{name}", "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class Tokenizer:
    """Encodes batches; what it has seen is kept for the task, at most `limit` units."""

    def __init__(self, ranks, pattern: str = PATTERN, limit: int = 1_000_000):
        import tiktoken

        self.bpe = tiktoken.Encoding("bpe", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.hasher, self.limit = tk.SpanHash(5), limit
        self.blank = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
        # a byte pair that may end a blank beyond ASCII: no cut behind it
        self.lead = np.isin(np.arange(256), [0xC2, 0x80, 0x81, 0x9A])
        self.trail = np.isin(np.arange(256), [*range(0x80, 0x8B), 0x85, 0x9F, 0xA0, 0xA8, 0xA9, 0xAF])
        self._forget()

    def _forget(self):
        self.seen = np.empty(0, np.uint64)
        self.row = np.empty(0, np.int64)
        self.ids, self.offsets = [np.empty(0, np.int32)], np.zeros(1, np.int64)

    def units(self, data, offsets):
        blank = self.blank[data]
        cut = np.zeros(len(data) + 1, bool)
        if len(data) > 1:
            cut[1:-1] = blank[1:] & ~blank[:-1]
            wide = np.flatnonzero(cut[2:-1] & self.trail[data[1:-1]] & self.lead[data[:-2]]) + 2 if len(data) > 2 else []
            cut[wide] = False
        cut[offsets] = True
        at = np.flatnonzero(cut)
        return at[:-1], at[1:]

    def encode(self, data, offsets):
        """Ids of all rows, ragged: (ids, row offsets)."""
        if not len(data):
            return np.empty(0, np.int32), np.zeros(len(offsets), np.int64)
        starts, ends = self.units(data, offsets)
        distinct, first, which = np.unique(self.hasher(data, starts, ends), return_index=True, return_inverse=True)
        at = np.searchsorted(self.seen, distinct)
        known = np.zeros(len(distinct), bool)
        inside = at < len(self.seen)
        known[inside] = self.seen[at[inside]] == distinct[inside]
        row = np.empty(len(distinct), np.int64)
        row[known] = self.row[at[known]]
        new = np.flatnonzero(~known)
        if len(new):
            if len(self.seen) + len(new) > self.limit and len(self.seen):
                self._forget()
                return self.encode(data, offsets)
            whole = data.tobytes()
            encoded = [self.bpe.encode_ordinary(whole[s:e].decode("utf-8", "replace")) for s, e in zip(starts[first[new]].tolist(), ends[first[new]].tolist())]
            size = np.fromiter(map(len, encoded), np.int64, len(encoded))
            base = len(self.offsets) - 1
            row[new] = base + np.arange(len(new))
            self.ids.append(np.fromiter((i for e in encoded for i in e), np.int32, int(size.sum())))
            self.offsets = np.concatenate([self.offsets, self.offsets[-1] + np.cumsum(size)])
            self.ids = [np.concatenate(self.ids)]
            place = at[new] + np.arange(len(new))
            seen, rows = np.empty(len(self.seen) + len(new), np.uint64), np.empty(len(self.seen) + len(new), np.int64)
            old = np.ones(len(seen), bool)
            old[place] = False
            seen[place], seen[old] = distinct[new], self.seen
            rows[place], rows[old] = row[new], self.row
            self.seen, self.row = seen, rows
        ids, unit = tk.gather(self.ids[0], self.offsets, row[which])
        return ids, unit[np.searchsorted(starts, offsets)]


# ---------------------------------------------------------------- directly addressable codes


def encode_ids(ids: np.ndarray, bits: int = CHUNK_BITS) -> bytes:
    """One text's blob: level count, chunk width, count of ids; per level its size, chunks, bitmap, directory."""
    left, levels = np.asarray(ids, np.uint64), []
    mask, n = np.uint64((1 << bits) - 1), len(ids)
    kind = np.uint8 if bits <= 8 else np.uint16
    while len(left):
        chunk, more = (left & mask).astype(kind), (left >> np.uint64(bits)) > 0
        padded = np.zeros(-(-len(left) // BLOCK) * BLOCK, bool)
        padded[: len(left)] = more
        before = np.zeros(len(padded) // BLOCK, np.uint32)
        np.cumsum(padded.reshape(-1, BLOCK).sum(1)[:-1], out=before[1:])
        levels.append(np.uint32(len(left)).tobytes() + before.tobytes() + np.packbits(more, bitorder="little").tobytes() + chunk.tobytes())
        left = left[more] >> np.uint64(bits)
    return bytes([len(levels), bits]) + np.uint32(n).tobytes() + b"".join(levels)


class Codes:
    """A blob opened for reading: `codes[i]` touches one chunk, one bit and one directory entry per level."""

    def __init__(self, blob: bytes):
        self.count = int.from_bytes(blob[2:6], "little")
        bits, at, self.levels = blob[1], 6, []
        self.bits, width = bits, 1 if bits <= 8 else 2
        for _ in range(blob[0]):
            n = int.from_bytes(blob[at : at + 4], "little")
            directory = at + 4
            bitmap = directory + 4 * -(-n // BLOCK)
            chunks = bitmap + -(-n // 8)
            self.levels.append((n, directory, bitmap, chunks))
            at = chunks + width * n
        self.blob, self.width = blob, width

    def __len__(self):
        return self.count

    def __getitem__(self, i: int) -> int:
        if not 0 <= i < self.count:
            raise IndexError(i)
        value, shift = 0, 0
        for _, directory, bitmap, chunks in self.levels:
            value |= int.from_bytes(self.blob[chunks + i * self.width : chunks + (i + 1) * self.width], "little") << shift
            if not self.blob[bitmap + i // 8] >> i % 8 & 1:
                return value
            block = i // BLOCK
            words = self.blob[bitmap + block * BLOCK // 8 : bitmap + i // 8 + 1]
            inside = int.from_bytes(words, "little") & ((1 << i % BLOCK) - 1)
            i = int.from_bytes(self.blob[directory + 4 * block : directory + 4 * block + 4], "little") + inside.bit_count()
            shift += self.bits
        return value

    def all(self) -> np.ndarray:
        out, live, shift = np.zeros(self.count, np.int64), np.arange(self.count), 0
        for n, _, bitmap, chunks in self.levels:
            chunk = np.frombuffer(self.blob, np.uint8 if self.width == 1 else np.uint16, n, chunks)
            out[live] |= chunk.astype(np.int64) << shift
            more = np.unpackbits(np.frombuffer(self.blob, np.uint8, -(-n // 8), bitmap), bitorder="little")[:n].astype(bool)
            live, shift = live[more], shift + self.bits
        return out


def write_codes(docs: DataFrame, folder: str = TOKENIZERS, bits: int = CHUNK_BITS) -> DataFrame:
    """(doc_id, n_tokens, codes) of every row."""
    ranks = docs.sparkSession.sparkContext.broadcast(load_bpe(folder))  # a vocabulary: its size is fixed

    def run(batches):
        tokenizer = Tokenizer(ranks.value)
        for b in batches:
            for lo, hi, data, offsets in tk.pieces(*tk.utf8(b.column("text"))):
                ids, off = tokenizer.encode(data, offsets)
                blobs = [encode_ids(ids[s:e], bits) for s, e in zip(off[:-1], off[1:])]
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(lo, hi - lo), pa.array(np.diff(off), pa.int32()), pa.array(blobs, pa.binary())], names=["doc_id", "n_tokens", "codes"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens int, codes binary")


def token_ids(docs: DataFrame, folder: str = TOKENIZERS) -> DataFrame:
    """(doc_id, n_tokens, ids) of every row."""
    ranks = docs.sparkSession.sparkContext.broadcast(load_bpe(folder))

    def run(batches):
        tokenizer = Tokenizer(ranks.value)
        for b in batches:
            for lo, hi, data, offsets in tk.pieces(*tk.utf8(b.column("text"))):
                ids, off = tokenizer.encode(data, offsets)
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(lo, hi - lo), pa.array(np.diff(off), pa.int32()), tk.list_array(ids, off, pa.int32())], names=["doc_id", "n_tokens", "ids"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens int, ids array<int>")

"""SentencePiece encoding and decoding as a relational lattice over distinct words.

A text is normalised as the model says (a blank becomes the mark U+2581, one is put in front) and cut to words:
before a mark that follows another character, and around line ends.  No piece crosses these cuts, so words are
independent.  The words that are frequent in the corpus are encoded in Spark: bounded-length substrings are
exploded, equi-joined to the piece table, the edges found are grouped by word, and a fold with the higher-order
`aggregate` chooses among them: Viterbi for a unigram model (best sum of scores), merges in order of score
for a BPE model, where Viterbi would give other ids than the model defines.  A character without a piece becomes
its bytes' pieces.

The table of encoded words has at most `MAX_WORDS` rows, so it can be broadcast; each task gathers the ids
of its texts from it.  Words that it lacks get the same fold in numpy, once a task.  Results do not
depend on which words the table holds.

Defined results: a null or empty text has no ids; decode(encode(t)) is t for every text that is valid and does
not itself contain the mark; every row has one row in the result, null and repeated doc_ids too; texts of any length are
read whole; only doc_id and text are read, so other columns do not matter.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, functions as F

from . import text as tk

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁"
MAX_WORDS = 1 << 17
#: Words of fewer occurrences within a batch are not offered for the table.
MIN_COUNT = 3


class Model:
    """Pieces and scores of a model file; `kind` is 'bpe' or 'unigram'."""

    def __init__(self, proto: bytes, kind: str | None = None):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_proto=proto)
        n = sp.get_piece_size()
        self.pieces = [sp.id_to_piece(i) for i in range(n)]
        self.scores = [sp.get_score(i) for i in range(n)]
        self.byte = [next(i for i in range(n) if sp.is_byte(i) and self.pieces[i] == f"<0x{b:02X}>") for b in range(256)]
        odd = {i for i in range(n) if sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i)}
        self.normal = [i for i in range(n) if i not in odd]
        self.longest = max(len(self.pieces[i]) for i in self.normal)
        self.kind = kind or {1: "unigram", 2: "bpe"}[_model_type(proto)]
        raw = [self.pieces[i].replace(MARK, " ").encode() for i in range(n)]
        for b, i in enumerate(self.byte):
            raw[i] = bytes([b])
        for i in odd - set(self.byte):
            raw[i] = b""
        self.raw = np.frombuffer(b"".join(raw), np.uint8)
        self.raw_offsets = np.concatenate([[0], np.cumsum([len(r) for r in raw])])
        self.unknown = min(self.scores[i] for i in self.normal) - 10.0
        self.id_of = {self.pieces[i]: i for i in self.normal}

    def frame(self, spark) -> DataFrame:
        """(piece, id, score) of the pieces that a text can contain."""
        table = pa.table({"piece": [self.pieces[i] for i in self.normal], "id": pa.array(self.normal, pa.int32()), "score": pa.array([float(self.scores[i]) for i in self.normal])})
        return spark.createDataFrame(table)


def _varint(b, i):
    x = s = 0
    while True:
        x |= (b[i] & 127) << s
        s, i = s + 7, i + 1
        if not b[i - 1] & 128:
            return x, i


def _fields(b):
    i = 0
    while i < len(b):
        key, i = _varint(b, i)
        at = i
        if key & 7 == 0:
            _, i = _varint(b, i)
        elif key & 7 == 2:
            n, at = _varint(b, i)
            i = at + n
        else:
            i += 8 if key & 7 == 1 else 4
        yield key >> 3, at, i


def _model_type(proto: bytes) -> int:
    """trainer_spec (2) . model_type (3); unigram (1) is the format's default."""
    for f, s, e in _fields(proto):
        if f == 2:
            for g, a, _ in _fields(proto[s:e]):
                if g == 3:
                    return _varint(proto, s + a)[0]
    return 1


# ---------------------------------------------------------------- the lattice in Spark


def lattice(words: DataFrame, pieces: DataFrame, longest: int) -> DataFrame:
    """(word, n, edges): edges are (s, e, score, id), the substrings [s, e) that are pieces."""
    n = F.char_length("word")
    start = words.select("word", n.alias("n"), F.explode(F.sequence(F.lit(0), n - 1)).alias("s"))
    sub = start.select("word", "n", "s", F.explode(F.sequence(F.col("s") + 1, F.least("n", F.col("s") + longest))).alias("e"))
    sub = sub.withColumn("piece", F.substring(F.col("word"), F.col("s") + 1, F.col("e") - F.col("s")))
    # the vocabulary has a fixed size; a word without any piece keeps an empty row
    hit = sub.join(F.broadcast(pieces), "piece").select("word", F.struct("s", "e", "score", "id").alias("edge"))
    some = hit.groupBy("word").agg(F.collect_list("edge").alias("edges"))
    none = F.array().cast("array<struct<s:int,e:int,score:double,id:int>>")
    return words.join(some, "word", "left").select("word", n.alias("n"), F.coalesce("edges", none).alias("edges"))


def _char_ids(at: str, byte: str) -> str:
    """Byte pieces of the character at place `at` of the word."""
    return f"transform(regexp_extract_all(hex(encode(substring(word, {at} + 1, 1), 'utf-8')), '(..)', 1), x -> {byte}[cast(conv(x, 16, 10) as int)])"


def fold_merges(table: DataFrame, byte_ids: list[int]) -> DataFrame:
    """(word, ids): join the two neighbours whose joined piece scores best, leftmost first, until none joins."""
    byte = "array(" + ",".join(map(str, byte_ids)) + ")"
    inner = "array_position(cuts, g.s)"
    cuts = f"""aggregate(sequence(1, greatest(n - 1, 1)), sequence(0, n), (cuts, _) ->
        array_remove(cuts, coalesce(array_max(transform(
            filter(edges, g -> {inner} > 0 and coalesce(try_element_at(cuts, cast({inner} as int) + 2), -1) = g.e),
            g -> struct(g.score as a, -g.s as b, element_at(cuts, cast({inner} as int) + 1) as cut))).cut, -1)))"""
    ids = f"""flatten(transform(slice(cuts, 1, size(cuts) - 1), (s, i) ->
        if(exists(edges, g -> g.s = s and g.e = cuts[i + 1]), transform(filter(edges, g -> g.s = s and g.e = cuts[i + 1]), g -> g.id), {_char_ids('s', byte)})))"""
    return table.withColumn("cuts", F.expr(cuts)).select("word", F.expr(ids).alias("ids"))


def fold_viterbi(table: DataFrame, byte_ids: list[int], unknown: float) -> DataFrame:
    """(word, ids): the path of the best sum of scores; a character without a piece costs `unknown`."""
    byte = "array(" + ",".join(map(str, byte_ids)) + ")"
    # the state at place e: (best sum, start of its last edge, id); -1 as id stands for bytes
    step = f"""aggregate(sequence(1, n), array(struct(cast(0 as double) as sum, -1 as s, -1 as id)), (best, e) -> array_append(best, array_max(
        concat(transform(filter(edges, g -> g.e = e), g -> struct(best[g.s].sum + g.score as sum, g.s as s, g.id as id)),
               if(exists(edges, g -> g.e = e and g.s = e - 1), array(), array(struct(best[e - 1].sum + {unknown}D as sum, e - 1 as s, -1 as id)))))))"""
    back = f"""aggregate(sequence(1, n), struct(n as at, cast(array() as array<int>) as ids), (acc, _) -> if(acc.at <= 0, acc,
        struct(best[acc.at].s as at, concat(if(best[acc.at].id >= 0, array(best[acc.at].id), {_char_ids('best[acc.at].s', byte)}), acc.ids) as ids))).ids"""
    return table.withColumn("best", F.expr(step)).select("word", F.expr(back).alias("ids"))


def encode_words(words: DataFrame, model: Model) -> DataFrame:
    """(word, ids) of distinct, non-empty words in which blanks are marks."""
    table = lattice(words, model.frame(words.sparkSession), model.longest)
    if model.kind == "bpe":
        return fold_merges(table, model.byte)
    return fold_viterbi(table, model.byte, model.unknown)


# ---------------------------------------------------------------- texts


def cut_words(data, offsets):
    """Bytes with a blank put in front of every text that has any, and start and end of its words."""
    size = np.diff(offsets)
    lead = (size > 0).astype(np.int64)
    new = np.concatenate([[0], np.cumsum(size + lead)])
    out = np.full(new[-1], 32, np.uint8)
    out[np.arange(len(data)) + np.repeat(new[:-1] - offsets[:-1] + lead, size)] = data
    cut = np.zeros(len(out) + 1, bool)
    blank, end = out == 32, out == 10
    cut[1:-1] = (blank[1:] & ~blank[:-1]) | end[1:] | end[:-1]
    cut[new] = True
    at = np.flatnonzero(cut)
    return out, new, at[:-1], at[1:]


class LocalFold:
    """The folds for the words of one task that the table lacks."""

    def __init__(self, model: Model):
        self.model = model
        if model.kind == "bpe":
            left, right, out = [], [], []
            for i in model.normal:
                p = model.pieces[i]
                for c in range(1, len(p)):
                    a, b = model.id_of.get(p[:c]), model.id_of.get(p[c:])
                    if a is not None and b is not None:
                        left.append(a)
                        right.append(b)
                        out.append(i)
            key = np.array(left, np.int64) << 20 | np.array(right, np.int64)
            order = np.argsort(key)
            self.key, self.out = key[order], np.array(out, np.int32)[order]
            scores = np.array(model.scores)
            self.rank = np.empty(len(scores), np.int32)  # 0 is the best score
            self.rank[np.argsort(-scores, kind="stable")] = np.arange(len(scores))
        self.single = {c: i for c, i in model.id_of.items() if len(c) == 1}

    def __call__(self, words: list[str]) -> list[np.ndarray]:
        return self._merges(words) if self.model.kind == "bpe" else [self._viterbi(w) for w in words]

    def _symbols(self, word):
        """Piece of each character; one without a piece is -1 - its code point."""
        return [self.single.get(c, -1 - ord(c)) for c in word]

    def _spell(self, ids):
        out = []
        for i in ids:
            out += [i] if i >= 0 else [self.model.byte[b] for b in chr(-1 - i).encode("utf-8", "replace")]
        return np.array(out, np.int32)

    def _merges(self, words):
        out = [None] * len(words)
        by_size = {}
        for i, w in enumerate(words):
            by_size.setdefault(min(1 << (len(w) - 1).bit_length(), len(w)) if len(w) > 64 else -(-len(w) // 4) * 4, []).append(i)
        none = np.int32(np.iinfo(np.int32).max)
        for width, group in by_size.items():
            for lo in range(0, len(group), 8192):
                part = group[lo : lo + 8192]
                longest = max(len(words[i]) for i in part)
                sym = np.full((len(part), longest + 1), np.iinfo(np.int64).min, np.int64)
                for row, i in enumerate(part):
                    s = self._symbols(words[i])
                    sym[row, : len(s)] = s
                size = np.array([len(words[i]) for i in part])
                live = np.flatnonzero(size > 1)
                while len(live):
                    s = sym[live]
                    a, b = s[:, :-1], s[:, 1:]
                    good = (a >= 0) & (b >= 0)
                    key = np.where(good, a << 20 | np.maximum(b, 0), -1)
                    at = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
                    hit = self.key[at] == key
                    rank = np.where(hit, self.rank[self.out[at]], none)
                    best = rank.argmin(1)
                    r = np.arange(len(live))
                    can = rank[r, best] < none
                    live, s, best, at = live[can], s[can], best[can], at[can]
                    if not len(live):
                        break
                    r = np.arange(len(live))
                    merged = self.out[at[r, best]]
                    col = np.arange(s.shape[1] - 1)
                    s[:, :-1] = np.where(col[None, :] > best[:, None], s[:, 1:], s[:, :-1])
                    s[:, -1] = np.iinfo(np.int64).min
                    s[r, best] = merged
                    sym[live] = s
                for row, i in enumerate(part):
                    ids = sym[row][sym[row] != np.iinfo(np.int64).min]
                    out[i] = ids.astype(np.int32) if (ids >= 0).all() else self._spell(ids.tolist())
        return out

    def _viterbi(self, word):
        m = self.model
        best = [(0.0, -1, -1)]
        for e in range(1, len(word) + 1):
            options = [(best[s][0] + m.scores[i], s, i) for s in range(max(0, e - m.longest), e) if (i := m.id_of.get(word[s:e])) is not None]
            if not any(s == e - 1 for _, s, _ in options):
                options.append((best[e - 1][0] + m.unknown, e - 1, -1 - ord(word[e - 1])))
            best.append(max(options))
        ids, at = [], len(word)
        while at > 0:
            ids.append(best[at][2])
            at = best[at][1]
        return self._spell(ids[::-1])


def frequent_words(docs: DataFrame, max_words: int = MAX_WORDS, min_count: int = MIN_COUNT) -> DataFrame:
    """The words for the table: the most frequent ones, by counts within batches."""

    def run(batches):
        hasher = tk.SpanHash(41)
        for b in batches:
            for _, _, data, offsets in tk.pieces(*tk.utf8(b.column("text")), limit=4 * tk.CHUNK):
                out, _, starts, ends = cut_words(data, offsets)
                if len(starts):
                    _, first, count = np.unique(hasher(out, starts, ends), return_index=True, return_counts=True)
                    often = count >= min_count
                    whole = out.tobytes()
                    found = [whole[s:e].decode("utf-8", "replace").replace(" ", MARK) for s, e in zip(starts[first[often]].tolist(), ends[first[often]].tolist())]
                    yield pa.RecordBatch.from_arrays([pa.array(found, pa.string()), pa.array(count[often], pa.int64())], names=["word", "n"])

    counted = docs.select("text").mapInArrow(run, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return counted.filter(F.char_length("word") <= 64).orderBy(F.desc("n"), "word").limit(max_words).select("word")


def encode(docs: DataFrame, model_file: str = MODEL, kind: str | None = None, max_words: int = MAX_WORDS) -> DataFrame:
    """(doc_id, n_pieces, ids, round_trip) of every row; round_trip: decoding the ids gave the text."""
    spark = docs.sparkSession
    with open(model_file, "rb") as f:
        model = Model(f.read(), kind)
    coded = encode_words(frequent_words(docs, max_words), model).toArrow()
    lists = coded.column("ids").combine_chunks()
    words = [w.replace(MARK, " ").encode() for w in coded.column("word").to_pylist()]
    ends = np.cumsum([0, *map(len, words)])
    h = tk.SpanHash(41)(np.frombuffer(b"".join(words), np.uint8), ends[:-1], ends[1:]) if words else np.empty(0, np.uint64)
    order = np.argsort(h)
    ids, offsets = tk.gather(lists.flatten().to_numpy(), lists.offsets.to_numpy().astype(np.int64), order) if words else (np.empty(0, np.int32), np.zeros(1, np.int64))
    shared = tk.ship(spark, (model, h[order], ids.astype(np.int32), offsets))  # at most max_words words

    def run(batches):
        model, seen, ids, offsets = tk.opened(shared)
        fold, hasher = LocalFold(model), tk.SpanHash(41)
        row = np.arange(len(seen))
        start = (seen, row, ids, offsets)
        for b in batches:
            for lo, hi, data, at in tk.pieces(*tk.utf8(b.column("text"))):
                out, new, starts, ends = cut_words(data, at)
                if len(seen) > 1_500_000:
                    seen, row, ids, offsets = start
                distinct, first, which = np.unique(hasher(out, starts, ends), return_index=True, return_inverse=True)
                place = np.searchsorted(seen, distinct)
                known = np.zeros(len(distinct), bool)
                known[place < len(seen)] = seen[place[place < len(seen)]] == distinct[place < len(seen)]
                of = np.empty(len(distinct), np.int64)
                of[known] = row[place[known]]
                fresh = np.flatnonzero(~known)
                if len(fresh):
                    whole = out.tobytes()
                    coded = fold([whole[s:e].decode("utf-8", "replace").replace(" ", MARK) for s, e in zip(starts[first[fresh]].tolist(), ends[first[fresh]].tolist())])
                    of[fresh] = len(offsets) - 1 + np.arange(len(fresh))
                    ids = np.concatenate([ids, *coded])
                    offsets = np.concatenate([offsets, offsets[-1] + np.cumsum([len(c) for c in coded])])
                    spot = place[fresh] + np.arange(len(fresh))
                    old = np.ones(len(seen) + len(fresh), bool)
                    old[spot] = False
                    both = [np.empty(len(old), seen.dtype), np.empty(len(old), np.int64)]
                    for x, was, now in zip(both, (seen, row), (distinct[fresh], of[fresh])):
                        x[old], x[spot] = was, now
                    seen, row = both
                got, unit = tk.gather(ids, offsets, of[which])
                off = unit[np.searchsorted(starts, new)]
                text, toff = decode_ids(got, off, model)
                size = np.diff(at)
                equal = np.diff(toff) == size
                if len(text) == len(data):
                    differ = np.concatenate([[0], np.cumsum(text != data)])
                    equal &= differ[at[1:]] == differ[at[:-1]]
                else:
                    for i in np.flatnonzero(equal):
                        equal[i] = bool(np.array_equal(text[toff[i] : toff[i + 1]], data[at[i] : at[i + 1]]))
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(lo, hi - lo), pa.array(np.diff(off), pa.int32()), tk.list_array(got, off, pa.int32()), pa.array(equal)], names=["doc_id", "n_pieces", "ids", "round_trip"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_pieces int, ids array<int>, round_trip boolean")


def decode_ids(ids, offsets, model: Model):
    """Bytes and row offsets of the texts: pieces put together, and the blank in front taken away."""
    data, piece = tk.gather(model.raw, model.raw_offsets, ids)
    at = piece[offsets]
    lead = (np.diff(at) > 0) & (data[np.minimum(at[:-1], max(len(data) - 1, 0))] == 32) if len(data) else np.zeros(len(at) - 1, bool)
    keep = np.ones(len(data), bool)
    keep[at[:-1][lead]] = False
    return data[keep], at - np.concatenate([[0], np.cumsum(lead)])


def decode(encoded: DataFrame, model_file: str = MODEL) -> DataFrame:
    """(doc_id, text) from (doc_id, ids)."""
    with open(model_file, "rb") as f:
        shared = tk.ship(encoded.sparkSession, Model(f.read()))

    def run(batches):
        model = tk.opened(shared)
        for b in batches:
            col = pa.compute.fill_null(b.column("ids"), pa.scalar([], pa.list_(pa.int32())))
            offsets = col.offsets.to_numpy().astype(np.int64)
            data, at = decode_ids(col.flatten().to_numpy(), offsets - offsets[0], model)
            whole = data.tobytes()
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([whole[s:e].decode("utf-8", "replace") for s, e in zip(at[:-1], at[1:])], pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")

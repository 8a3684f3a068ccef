"""Private data: a linear-chain conditional random field over word-shape features.

A text is cut to lines and these to tokens (runs of letters, digits and ``.@-_+()/:=``; runs of other
punctuation).  A token's features are its shape (runs of capitals, small letters and digits, with what stands between
them), the shapes and letters of its ends, counts of its digits and marks, its classes of characters, whether its numbers
are small and its digits' checksum; none of them tells a kind by itself.  The field sees those of the two tokens on either
side too, and learns from a small labelled table (a DataFrame, or the one that `labelled_table` draws from templates) how
they combine, by gradient ascent on its likelihood.  Texts are decoded by Viterbi for all lines of a batch at once.  Found
spans are trimmed of outer punctuation and masked as ``[EMAIL]``, ``[PHONE]``, ``[CARD]``, ``[IP]`` or ``[SECRET]``.

Defined results: a null text stays null and has no spans; an empty text stays empty; texts of any length are read
whole; every row has one row in the result, null and repeated doc_ids too; n_chars, where the table has it, is the length of
the masked text for texts that changed; extra columns may have any name, but `spans` is replaced.
"""

from __future__ import annotations

import random
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame

from . import text as tk

LABELS = ("O", "EMAIL", "PHONE", "CARD", "IP", "SECRET")
PHONE = LABELS.index("PHONE")  # the only kind that may take several tokens
KEYWORDS = ("token", "password", "passwd", "secret", "key", "api_key", "apikey", "pwd", "=", "version", "bearer")
_KEYS = frozenset(k.encode() for k in KEYWORDS)
WINDOW = (-2, -1, 0, 1, 2)
_TOKEN = re.compile(rb"[0-9A-Za-z\x80-\xff.@\-_+()/:=]+|[!-'*,;<>?\[\\\]^`{|}~]+")
_TRIM = {"EMAIL": b"._-+()/:=@", "PHONE": b"._-)/:=@", "CARD": b"._-+()/:=@", "IP": b"._-+()/:=@", "SECRET": b".()/:"}


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        v = int(c) * (1 + i % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


_CLASS = bytes(ord("9") if 48 <= c < 58 else ord("X") if 65 <= c < 91 else ord("x") if 97 <= c < 123 or c >= 128 else c for c in range(256))
_RUN = re.compile(rb"([9Xx])\1+")
_KINDS = ((re.compile(rb"[0-9]+"), "digits only"), (re.compile(rb"[0-9a-f]+"), "hex"), (re.compile(rb"[0-9A-F]+"), "HEX"), (re.compile(rb"[A-Z0-9]+"), "capitals"), (re.compile(rb"[a-z0-9]+"), "small"), (re.compile(rb"[A-Za-z0-9]+"), "letters and digits"))


def special_features(token: bytes) -> tuple:
    """Features of a token that has a digit, '@' or '=', or is a run of punctuation."""
    core = token.strip(b"._-+()/:=")
    shape, numbers = token.translate(_CLASS), re.findall(rb"[0-9]+", token)
    bare = core.translate(_CLASS)
    digits = sum(map(len, numbers))
    out = [
        "shape " + _RUN.sub(rb"\1", shape).decode(), "inner " + _RUN.sub(rb"\1", bare).decode(), "begins " + bare[:3].decode(), "ends " + bare[-4:].decode(),
        f"digits {digits if digits < 20 else '20+'}", f"length {min(len(core), 60) // 4}", f"numbers {min(len(numbers), 5)}",
    ]
    out += [f"{chr(c)} {min(token.count(c), 4)}" for c in b"@.-=+(" if c in token]
    kind = next((name for form, name in _KINDS if form.fullmatch(core)), "mixed")
    out.append("class " + kind)
    out.append(f"class and length {kind} {len(core) if len(core) < 24 else len(core) // 8 * 8}")
    letters = re.match(rb"[A-Za-z_]{3,}", core)
    if letters:
        out.append("word " + letters.group()[:4].lower().decode())
    if numbers:
        out.append("small numbers" if all(len(x) < 4 and int(x) < 256 for x in numbers) else "a large number")
    if digits == len(core) >= 12:
        out.append("checksum " + str(luhn(core.decode())))
    if token.lower() in _KEYS:
        out.append("key " + token.lower().decode())
    return tuple(out)


def features(token: bytes) -> tuple:
    s = token.lower()
    if s in _KEYS:
        return ("key " + s.decode(),)
    if re.search(rb"[0-9@=]", token) or not re.search(rb"[0-9A-Za-z\x80-\xff]", token) or re.fullmatch(rb"[A-Z]{16,}[^a-z]*", token):
        return special_features(token)
    return (f"plain {_plain(token)}",)


def _plain(token: bytes) -> int:
    letters = re.sub(rb"[^A-Za-z\x80-\xff]", b"", token)
    upper = sum(65 <= c <= 90 for c in letters)
    return (0 if upper == 0 else 1 if upper < len(letters) else 2) + 3 * (len(letters) != len(token))


# ---------------------------------------------------------------- the labelled table


def labelled_table(n: int = 500, seed: int = 5) -> list[tuple[list[str], list[int]]]:
    """Token sequences with their labels, from templates: the small table that the field learns from."""
    r = random.Random(seed)
    word = lambda: "".join(r.choice(("an", "er", "th", "in", "lo", "mé", "qu", "sch", "ó", "ti", "ba", "ou")) for _ in range(r.randint(1, 4)))
    num = lambda k: "".join(r.choice("0123456789") for _ in range(k))
    hexa = lambda k: "".join(r.choice("0123456789abcdef") for _ in range(k))

    def card(ok):
        while True:
            c = r.choice("3456") + num(r.choice((15, 15, 15, 14, 12)))
            if r.random() < 0.3:
                c = str(r.randint(1, 9)) + c[1:]
            if luhn(c) == ok:
                return c

    def filler():
        w = word()
        if r.random() < 0.04:
            w = "".join(word() for _ in range(r.randint(3, 5))).upper()
        w = r.choice((w, w, w, w.capitalize(), w.upper()))
        return r.choice((w, w, w, w + ".", "(" + w + ")", w + "-" + word()))

    def email():
        return f"{word()}{r.choice(('.', '_', ''))}{r.choice((num(2), word(), ''))}@{r.choice(('mail', '', 'x'))}{word()}{r.choice((num(1), ''))}.{r.choice(('com', 'org', 'example.com', 'net', 'de'))}".replace("é", "e").replace("ó", "o")

    def key(k, alphabet="ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"):
        return "AKIA" + "".join(r.choice(alphabet) for _ in range(k))

    def entity():
        kind = r.randrange(17)
        if kind < 2:
            return [email()], [1]
        if kind < 4:
            return ["+" + str(r.randint(1, 99)), f"({num(3)})", f"{num(3)}-{num(4)}"], [2, 2, 2]
        if kind == 4:
            return r.choice(([f"({num(3)})", f"{num(3)}-{num(4)}"], ["+1", num(3), f"{num(3)}-{num(4)}"])), None
        if kind < 7:
            return [card(True)], [3]
        if kind < 9:
            return [".".join(str(r.randint(0, 255)) for _ in range(4))], [4]
        if kind == 9:
            return [r.choice(("token", "key", "secret", "api_key")), "=", '"', hexa(r.choice((32, 40, 64))), '"'], [0, 0, 0, 5, 0]
        if kind == 10:
            return [r.choice(("password", "passwd", "secret", "api_key")) + "=" + hexa(r.randint(8, 24))], [5]
        if kind == 11:
            return [key(16, "ABCDEFGHIJKLMNOPQRSTUVWXYZ") if r.random() < 0.3 else key(16)], [5]
        if kind == 12:
            return [card(False)], [0]
        if kind == 13:
            return r.choice(([num(4)], [f"{num(1)}.{num(1)}"], ["version", num(1) + "."], [f"{num(4)}-{num(2)}-{num(2)}"], [num(2) + ":" + num(2)], ["x=" + num(2)], [num(3)], [num(r.randint(5, 12))])), None
        if kind == 14:
            return [word() + num(2)], [0]
        if kind == 15:
            return [r.choice((hexa(40).upper(), "".join(word() for _ in range(6)).upper()))], [0]
        return [".".join(str(r.randint(256, 999)) for _ in range(4))], [0]

    table = []
    for _ in range(n):
        tokens, labels = [], []
        for _ in range(r.randint(1, 4)):
            for _ in range(r.randint(0, 4)):
                tokens.append(filler())
                labels.append(0)
                if r.random() < 0.25:
                    tokens.append(r.choice((",", "!!", "###", "%%%", "|", "$$$", "***", "&&&", ";")))
                    labels.append(0)
            t, lab = entity()
            if lab is None:
                lab = [2] * len(t) if len(t) > 1 and t[-1][3:4] == "-" else [0] * len(t)
            for j, (x, y) in enumerate(zip(t, lab)):
                last = j == len(t) - 1
                tokens.append(x + ("." if last and y in (1, 2, 3, 4) and r.random() < 0.15 else ""))
                labels.append(y)
                if r.random() < 0.06 or last and r.random() < 0.2:
                    tokens.append(r.choice((",", "!!", "###", "%%%", "$$$", "***", "&&&", "!", '"')))
                    labels.append(y if not last and y == 2 else 0)
        if tokens:
            table.append((tokens, labels))
    return table


# ---------------------------------------------------------------- fitting


class Field:
    """Weights: per window position a (feature, label) table, and a transition table."""

    def __init__(self, vocabulary, emission, transition):
        self.vocabulary, self.emission, self.transition = vocabulary, emission, transition

    def rows(self, feats) -> np.ndarray:
        """What a token with these features adds to the label scores at each window position."""
        at = [self.vocabulary[f] for f in feats if f in self.vocabulary]
        return self.emission[:, at].sum(1) if at else np.zeros((len(WINDOW), len(LABELS)))


def _log_sum(x, axis):
    m = x.max(axis, keepdims=True)
    return (m + np.log(np.exp(x - m).sum(axis, keepdims=True))).squeeze(axis)


class Sequences:
    """A labelled table as arrays: feature ids by place, labels and mask; `likelihood` is what fit() climbs."""

    def __init__(self, table):
        n, longest = len(table), max(len(t) for t, _ in table)
        self.vocabulary: dict[str, int] = {"edge": 0}
        feats = [[features(t.encode()) for t in tokens] for tokens, _ in table]
        for f in (f for each in feats for token in each for f in token):
            self.vocabulary.setdefault(f, len(self.vocabulary))
        self.none, self.pad, self.longest = len(self.vocabulary), max(abs(w) for w in WINDOW), longest
        width = max((len(t) for each in feats for t in each), default=1)
        self.ids = np.full((n, longest + 2 * self.pad, width), self.none)
        gold = np.zeros((n, longest), int)
        self.mask = np.zeros((n, longest), bool)
        self.ids[:, :, 0] = 0
        for i, (each, (_, labels)) in enumerate(zip(feats, table)):
            for j, t in enumerate(each):
                f = [self.vocabulary[x] for x in t]
                self.ids[i, self.pad + j] = self.none
                self.ids[i, self.pad + j, : len(f)] = f
            gold[i, : len(labels)], self.mask[i, : len(labels)] = labels, True
        self.gold = np.eye(len(LABELS))[gold] * self.mask[:, :, None]

    def likelihood(self, emission, transition):
        """(log likelihood, its gradients by emission and transition), from forward and backward sums of all sequences at once."""
        ids, mask, gold, longest, pad = self.ids, self.mask, self.gold, self.longest, self.pad
        n, size = len(ids), len(LABELS)
        score = sum(emission[w][ids[:, pad + o : pad + o + longest]].sum(2) for w, o in enumerate(WINDOW))
        alpha, beta = np.zeros((n, longest, size)), np.zeros((n, longest, size))
        alpha[:, 0] = score[:, 0]
        for t in range(1, longest):
            a = _log_sum(alpha[:, t - 1, :, None] + transition, 1) + score[:, t]
            alpha[:, t] = np.where(mask[:, t, None], a, alpha[:, t - 1])
        for t in range(longest - 2, -1, -1):
            b = _log_sum(transition + (score[:, t + 1] + beta[:, t + 1])[:, None, :], 2)
            beta[:, t] = np.where(mask[:, t + 1, None], b, 0)
        z = _log_sum(alpha[:, -1], 1)
        p = np.exp(alpha + beta - z[:, None, None]) * mask[:, :, None]
        both = (mask[:, 1:] & mask[:, :-1])[:, :, None, None]
        pair = np.exp(alpha[:, :-1, :, None] + transition + (score[:, 1:] + beta[:, 1:])[:, :, None, :] - z[:, None, None, None]) * both
        pairs = gold[:, :-1, :, None] * gold[:, 1:, None, :]
        g_emission, diff = np.zeros_like(emission), gold - p
        for w, o in enumerate(WINDOW):
            at = ids[:, pad + o : pad + o + longest]
            for y in range(size):
                spread = np.broadcast_to(diff[:, :, y, None], at.shape)
                g_emission[w, :, y] = np.bincount(at.ravel(), spread.ravel(), self.none + 1)
        value = (gold * score).sum() + (pairs * transition).sum() - z.sum()
        return value, g_emission, (pairs - pair).sum((0, 1))


def fit(table, steps: int = 60, rate: float = 0.2, l2: float = 1e-3) -> Field:
    """Adam on the penalised likelihood of (tokens, label numbers) sequences; with none, every token stays."""
    if not table:
        return Field({"edge": 0}, np.zeros((len(WINDOW), 1, len(LABELS))), np.zeros((len(LABELS), len(LABELS))))
    seq, size = Sequences(table), len(LABELS)
    emission, transition = np.zeros((len(WINDOW), seq.none + 1, size)), np.zeros((size, size))
    slots = [(e, np.zeros_like(e), np.zeros_like(e)) for e in (emission, transition)]
    for step in range(1, steps + 1):
        _, *gradients = seq.likelihood(emission, transition)
        for (value, m, v), g in zip(slots, gradients):
            g = g / len(table) - l2 * value
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            value += rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        emission[:, seq.none] = 0
    return Field(seq.vocabulary, emission[:, : seq.none], transition)


def from_frame(labelled: DataFrame) -> list:
    """Sequences for fit() from a small DataFrame (tokens array<string>, labels array<string>)."""
    number = {name: i for i, name in enumerate(LABELS)}
    return [(r["tokens"], [number[x] for x in r["labels"]]) for r in labelled.select("tokens", "labels").dropna().orderBy("tokens").collect() if r["tokens"]]


def by_kind(found, truth) -> dict[str, tuple[float, float]]:
    """(precision, recall) of each kind, from sets of (text, start, end, kind)."""
    out = {}
    for kind in LABELS[1:]:
        a, b = {x for x in found if x[-1] == kind}, {x for x in truth if x[-1] == kind}
        out[kind] = (len(a & b) / len(a) if a else 1.0, len(a & b) / len(b) if b else 1.0)
    return out


# ---------------------------------------------------------------- decoding


def viterbi(score, starts, lengths, transition):
    """Best label of every token; sequences are the token ranges [start, start + length)."""
    best = np.zeros(len(score), np.int8)
    keep_ = lengths > 0
    order = np.argsort(-lengths[keep_], kind="stable")
    starts, lengths = starts[keep_][order], lengths[keep_][order]
    if not len(starts):
        return best
    back = np.zeros(score.shape, np.int8)
    total = score[starts]
    final = np.empty((len(starts), score.shape[1]))
    turned = transition.T.copy()  # (to, from)
    live = np.searchsorted(-lengths, -np.arange(1, lengths[0] + 1), "right")  # sequences of at least t + 1 tokens
    for t in range(1, lengths[0]):
        a = live[t]
        if a < len(total):
            final[a : len(total)] = total[a:]
        step = total[:a, None, :] + turned
        at = starts[:a] + t
        choice = step.argmax(2)
        back[at] = choice
        total = np.take_along_axis(step, choice[:, :, None], 2)[:, :, 0] + score[at]
    final[: len(total)] = total
    label = np.empty(len(starts), np.int64)
    for t in range(lengths[0] - 1, -1, -1):
        a = live[t]
        ending = lengths[:a] == t + 1
        label[:a][ending] = final[:a][ending].argmax(1)
        at = starts[:a] + t
        best[at] = label[:a]
        label[:a] = back[at, label[:a]]
    return best


class Decoder:
    def __init__(self, field: Field):
        self.field = field
        kind = np.zeros(256, np.uint8)
        for c in range(33, 127):
            kind[c] = 2
        for c in b"0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz.@-_+()/:=":
            kind[c] = 1
        kind[128:] = 1
        self.kind = kind
        self.digit = np.isin(np.arange(256), np.frombuffer(b"0123456789@=", np.uint8))
        self.upper = (np.arange(256) >= 65) & (np.arange(256) <= 90)
        self.letter = self.upper | ((np.arange(256) >= 97) & (np.arange(256) <= 122)) | (np.arange(256) >= 128)
        self.hasher = tk.SpanHash(11)
        kinds = [("edge",), *[(f"plain {i}",) for i in range(6)], *[("key " + k,) for k in KEYWORDS]]
        self.table = [field.rows(k) for k in kinds]
        self.known = {k: i for i, k in enumerate(kinds)}
        joined = np.frombuffer("".join(KEYWORDS).encode(), np.uint8)
        ends = np.cumsum([len(k) for k in KEYWORDS])
        h = self.hasher(joined, ends - [len(k) for k in KEYWORDS], ends, fold=True)
        self.key_order = np.argsort(h)
        self.key_hash = h[self.key_order]

    def spans(self, data, offsets):
        """(row, start byte, end byte, label) of all found spans, in order."""
        starts, ends, rows = tk.runs(self.kind[data], offsets)
        if not len(starts):
            return []
        count = lambda table: np.concatenate([[0], np.cumsum(table[data], dtype=np.int32)])
        letters, upper, digit = (c[ends] - c[starts] for c in map(count, (self.letter, self.upper, self.digit)))
        size = ends - starts
        token = 1 + np.where(upper == 0, 0, np.where(upper < letters, 1, 2)) + 3 * (letters != size)
        h = self.hasher(data, starts, ends, fold=True)
        at = np.minimum(np.searchsorted(self.key_hash, h), len(self.key_hash) - 1)
        is_key = self.key_hash[at] == h
        token[is_key] = 7 + self.key_order[at[is_key]]
        special = np.flatnonzero(((digit > 0) | (letters == 0) | ((upper >= 16) & (letters == upper))) & ~is_key)
        whole = data.tobytes()
        cache: dict[bytes, int] = {}
        for i in special:
            word = whole[starts[i] : ends[i]]
            k = cache.get(word)
            if k is None:
                f = features(word)
                k = self.known.get(f)
                if k is None:
                    k = self.known[f] = len(self.table)
                    self.table.append(self.field.rows(f))
                cache[word] = k
            token[i] = k
        table = np.stack(self.table)  # (token kind, window position, label)
        lines = np.flatnonzero(data == 10)
        line = np.searchsorted(lines, starts) + rows  # grows at line ends and at row ends
        first = np.flatnonzero(np.concatenate([[True], line[1:] != line[:-1]]))
        length = np.diff(np.append(first, len(line)))
        score = table[token, WINDOW.index(0)]
        for w, o in enumerate(WINDOW):
            if o:
                beside = np.zeros(len(token), np.int64)  # the edge
                if o > 0:
                    beside[:-o] = np.where(line[o:] == line[:-o], token[o:], 0)
                else:
                    beside[-o:] = np.where(line[:o] == line[-o:], token[:o], 0)
                score += table[beside, w]
        best = viterbi(score, first, length, self.field.transition)
        hits = np.flatnonzero(best)
        out = []
        for i in hits:
            if out and out[-1][3] == best[i] == PHONE and out[-1][4] == i - 1 and line[i] == line[i - 1]:
                out[-1][2], out[-1][4] = ends[i], i
            else:
                out.append([rows[i], starts[i], ends[i], best[i], i])
        found = []
        for row, s, e, label, _ in out:
            core, name = whole[s:e], LABELS[label]
            if name == "SECRET" and b"=" in core:
                s += core.rindex(b"=", 0, max(core.rindex(b"="), 1) + 1) + 1
                core = whole[s:e]
            if name == "PHONE":
                core = core.rstrip(b"!\"#$%&'*,;<>?[\\]^`{|}~ ")
                e = s + len(core)
            left = core.lstrip(_TRIM[name].replace(b"(", b"").replace(b"+", b"") if name == "PHONE" else _TRIM[name])
            s += len(core) - len(left)
            e -= len(left) - len(left.rstrip(_TRIM[name]))
            if e > s:
                found.append((int(row), int(s), int(e), name))
        return found


SPANS = "array<struct<kind:string,start:int,end:int>>"


def redact(docs: DataFrame, field: Field | None = None, labelled: DataFrame | None = None) -> DataFrame:
    """All columns of `docs`; text masked; spans: what was found, by characters of the text as it came.

    The field is the given one, or fitted to `labelled` (see from_frame), or to the table drawn from templates.
    """
    docs = tk.drop_columns(docs, ["spans"])
    field = field or fit(labelled_table() if labelled is None else from_frame(labelled))
    model = tk.ship(docs.sparkSession, field)
    names = docs.columns
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))

    def run(batches):
        decoder = Decoder(tk.opened(model))
        for b in batches:
            texts, found = b.column("text"), [[] for _ in range(b.num_rows)]
            for lo, hi, data, offsets in tk.pieces(*tk.utf8(texts)):
                for row, s, e, name in decoder.spans(data, offsets):
                    found[lo + row].append((int(s - offsets[row]), int(e - offsets[row]), name))
            changed, spans, size = {}, [], {}
            for i, each in enumerate(found):
                out = []
                if each:
                    raw, at, parts, chars = texts[i].as_py().encode(), 0, [], 0
                    for s, e, name in each:
                        gap, body = raw[at:s].decode(), raw[s:e].decode()
                        out.append({"kind": name, "start": chars + len(gap), "end": chars + len(gap) + len(body)})
                        chars += len(gap) + len(body)
                        parts += [gap, f"[{name}]"]
                        at = e
                    changed[i] = "".join(parts) + raw[at:].decode()
                    size[i] = len(changed[i])
                spans.append(out)
            columns = []
            for name, column in zip(names, b.columns):
                if changed and name == "text":
                    mask = np.zeros(b.num_rows, bool)
                    mask[list(changed)] = True
                    column = pa.compute.replace_with_mask(column, pa.array(mask), pa.array([changed[i] for i in sorted(changed)], column.type))
                elif changed and name == "n_chars":
                    mask = np.zeros(b.num_rows, bool)
                    mask[list(changed)] = True
                    column = pa.compute.replace_with_mask(column, pa.array(mask), pa.array([size[i] for i in sorted(changed)], column.type))
                columns.append(column)
            yield pa.RecordBatch.from_arrays([*columns, pa.array(spans, kind)], names=[*names, "spans"])

    return tk.map_arrow(docs, run, tk.with_fields(docs, spans=SPANS))

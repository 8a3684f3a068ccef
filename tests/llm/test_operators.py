"""Every operator against brute force, and on nulls, empty, very long and repeated rows, ties, no rows, clashing columns."""

import random
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
import pytest

from roadsnap.llm import exact, fingerprint, lattice, linedup, nearcopy, packing, private, quality, substrings, text as tk, tokens

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def frame(spark, texts, ids=None, **extra):
    rows = [(i, t, "en", "s", None if t is None else len(t)) for i, t in zip(ids or range(len(texts)), texts)]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def documents(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def texts(documents):
    return {r["doc_id"]: r["text"] for r in documents.collect()}


ODD = [None, "", "word", "a\nb", "a\nb", "x " * 30000, "é ü ñ 日本 🎉", "\n\n\n", " lead and  double ", "same text here", "same text here"]


def all_operators(docs, labels):
    return {
        "pack": packing.pack(docs), "lines": linedup.dedup(docs), "quality": quality.classify(docs, labels), "sketch": fingerprint.sketch(docs), "pieces": lattice.encode(docs, max_words=50),
        "exact": exact.dedup(docs), "passages": substrings.dedup(docs), "near": nearcopy.dedup(docs), "codes": tokens.write_codes(docs), "private": private.redact(docs, FIELD()),
    }


_field = []


def FIELD():
    if not _field:
        _field.append(private.fit(private.labelled_table(200), steps=30))
    return _field[0]


def labels_frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id bigint, quality int, toxic int")


def test_empty_tables(spark):
    docs = frame(spark, [])
    for name, df in all_operators(docs, labels_frame(spark, [])).items():
        assert df.count() == 0, name


def test_odd_rows(spark):
    docs = frame(spark, ODD)
    n = len(ODD)
    got = {k: v.collect() for k, v in all_operators(docs, labels_frame(spark, [(0, 1, 0), (1, None, 0)])).items()}
    for name in ("lines", "quality", "sketch", "pieces", "passages", "codes", "private"):
        assert len(got[name]) == n, name
    assert sorted(r["doc_id"] for r in got["exact"]) == [0, 1, 2, 3, 5, 6, 7, 8, 9]
    near = {r["doc_id"] for r in got["near"]}
    assert {0, 1, 2, 7} <= near and len(near & {9, 10}) == 1
    assert {r["doc_id"] for r in got["pack"]} == set(range(n))
    assert [r["n_tokens"] for r in got["pack"] if r["doc_id"] in (0, 1)] == [0, 0]
    assert all(r["round_trip"] for r in got["pieces"])
    assert next(r["text"] for r in got["lines"] if r["doc_id"] == 4) == "" and next(r["text"] for r in got["lines"] if r["doc_id"] == 0) is None


def test_clashing_and_extra_columns(spark):
    docs = frame(spark, ["one two three", "one two three", None])
    from pyspark.sql import functions as F

    for c in ("p_quality", "spans", "removed_lines", "removed_words", "copied_from", "digest", "node", "my.column", "key", "mark", "did", "rid", "gaps", "end", "ln", "id", "__id", "__digest", "__gone", "__from", "__spans", "_key", "shard", "ids"):
        docs = docs.withColumn(c, F.lit("mine"))
    assert set(exact.dedup(docs).columns) == set(docs.columns) and exact.dedup(docs).count() == 2
    assert nearcopy.dedup(docs).columns == docs.columns and nearcopy.dedup(docs).count() == 2
    assert quality.classify(docs, labels_frame(spark, [])).filter("`my.column` = 'mine'").count() == 3
    assert private.redact(docs, FIELD()).filter("`my.column` = 'mine'").count() == 3
    assert substrings.dedup(docs).filter("digest = 'mine' and removed_words = 0").count() == 3
    assert linedup.dedup(docs).filter("node = 'mine'").count() == 3
    for df in (packing.pack(docs), tokens.write_codes(docs), fingerprint.sketch(docs), lattice.encode(docs, max_words=5)):
        assert df.count() == 3


def test_null_and_repeated_ids(spark):
    docs = frame(spark, ["t u", "t u", "t u", "v w", None], [7, 7, None, None, None])
    got = exact.dedup(docs).collect()
    assert sorted((r["doc_id"] or -1, r["text"] or "") for r in got) == [(-1, ""), (-1, "v w"), (7, "t u")]
    assert nearcopy.dedup(docs).count() == 5
    for df in all_operators(docs, labels_frame(spark, [])).values():
        df.collect()


# ---------------------------------------------------------------- 1 packing


def test_packing_follows_sum_of_squares():
    rng = random.Random(3)
    b, packer, level, fills = 12, packing.Packer(12), defaultdict(int), {}
    for _ in range(400):
        s = rng.randint(1, b)
        def cost(h):
            n = Counter(level)
            if h:
                n[h] -= 1
            if h + s < b:
                n[h + s] += 1
            return sum(v * v for v in n.values())
        options = {h: cost(h) for h in [0, *[h for h in level if level[h] and h + s <= b]]}
        window, offset = packer.place(s)
        assert options[offset] == min(options.values())
        assert fills.get(window, 0) == offset
        fills[window] = offset + s
        if offset:
            level[offset] -= 1
        if offset + s < b:
            level[offset + s] += 1


def test_packing_keeps_all_tokens(spark, documents):
    rows = packing.pack(documents).toPandas()
    ids = {r["doc_id"]: r["ids"] for r in tokens.token_ids(documents).collect()}
    whole = defaultdict(list)
    for r in rows.sort_values(["doc_id", "piece"]).itertuples():
        whole[r.doc_id] += list(r.ids)
        assert len(r.ids) == r.n_tokens
    assert whole == ids
    used = rows.dropna().groupby(["shard", "window"])
    for _, w in used:
        w = w.sort_values("position")
        assert w["n_tokens"].sum() <= packing.WINDOW and (w["position"].to_numpy() == np.concatenate([[0], w["n_tokens"].cumsum()[:-1]])).all()
    assert rows["n_tokens"].sum() / (len(used) * packing.WINDOW) > 0.9
    made = packing.windows(packing.pack(documents)).collect()
    assert len(made) == len(used) and sum(len(r["ids"]) for r in made) == rows["n_tokens"].sum() and max(len(r["ids"]) for r in made) <= packing.WINDOW


def plain_packing(sizes, b):
    """(window, offset, tokens) by trying every level for every piece; ties: fuller level, then the window that came to it first."""
    level, since, out, fresh = {}, {}, [], 0
    for size in sizes:
        mine = []
        while size > b:
            mine.append((fresh, 0, b))
            fresh, size = fresh + 1, size - b
        if size:
            count = Counter(level.values())
            def cost(h):
                n = Counter(count)
                n[h] -= h > 0
                if h + size < b:
                    n[h + size] += 1
                return sum(v * v for v in n.values())
            best = min([0, *{h for h in count if h + size <= b}], key=lambda h: (cost(h), -h))
            window = min((w for w, h in level.items() if h == best), key=lambda w: since[w]) if best else fresh
            fresh += best == 0
            mine.append((window, best, size))
            level.pop(window, None)
            if best + size < b:
                level[window] = best + size
                since[window] = len(out)
        out.append(mine)
    return out


def test_packing_equals_plain_packing(spark):
    rng, b = random.Random(11), 9
    sizes = [rng.randint(0, 25) if rng.random() < 0.2 else rng.randint(1, 9) for _ in range(300)]
    packer = packing.Packer(b)
    got = [packer.add(x) for x in sizes]
    assert got == plain_packing(sizes, b)
    rows = [(i, x, list(range(x))) for i, x in enumerate(sizes)]
    coded = spark.createDataFrame(rows[::-1], "doc_id bigint, n_tokens int, ids array<int>")
    out = packing.pack_ids(coded, b).collect()
    assert sorted((r["doc_id"], r["piece"], r["window"], r["position"], r["n_tokens"]) for r in out if r["n_tokens"]) == [(i, j, *g) for i, each in enumerate(got) for j, g in enumerate(each)]


def test_packing_does_not_depend_on_other_shards(spark):
    few = spark.createDataFrame([(i, 3, [1, 2, 3]) for i in range(40)], "doc_id bigint, n_tokens int, ids array<int>")
    many = few.unionAll(spark.createDataFrame([(i, 2, [7, 8]) for i in range(40, 90)], "doc_id bigint, n_tokens int, ids array<int>"))
    place = lambda df: {tuple(r) for r in packing.pack_ids(df, 7, per_shard=20).select("doc_id", "shard", "window", "position").collect()}
    assert place(few) < place(many)
    assert len(place(few.withColumn("doc_id", few.doc_id * 1_000_003))) == 40
    assert {r["shard"] for r in packing.pack_ids(few, 7, shards=3).collect()} == {0, 1, 2}


# ---------------------------------------------------------------- 2 and 7 repeats


@pytest.mark.parametrize("m", [1, 2, 3, 4, 5])
def test_line_runs(spark, m):
    rng = random.Random(m)
    docs = ["\n".join(rng.choice("abcdefgh") for _ in range(rng.randint(0, 25))) for _ in range(30)]
    first, gone = {}, defaultdict(set)
    for d, t in enumerate(docs):
        lines = t.split("\n")
        for p in range(len(lines) - m + 1):
            k = tuple(lines[p : p + m])
            e, q = first.setdefault(k, (d, p))
            if (e, q) != (d, p) and (e != d or p >= q + m):
                gone[d].update(range(p, p + m))
    got = {r["doc_id"]: r["text"] for r in linedup.dedup(frame(spark, docs), m).collect()}
    for d, t in enumerate(docs):
        assert got[d] == "\n".join(x for i, x in enumerate(t.split("\n")) if i not in gone[d])


@pytest.mark.parametrize("letters", ["ab", "abcdefgh"])
def test_array_of_line_suffixes(spark, letters):
    """The order of all suffixes and their common prefixes; several texts end alike, and one repeats a line only."""
    rng = random.Random(len(letters))
    docs = ["\n".join(rng.choice(letters) for _ in range(rng.randint(0, 18))) for _ in range(12)] + ["\n".join(x) for x in ("qqabcdefabc", "zabcdefabc", "zzbcdefabc", "a" * 17)]
    lines = [d.split("\n") for d in docs]
    name = {lines[r["did"]][r["ln"]]: (r["h1"], r["h2"]) for r in linedup.line_ids(frame(spark, docs)).collect()}
    count = Counter(x for t in lines for x in t)
    want = sorted(([name[x] for x in t[p:]], d, p) for d, t in enumerate(lines) for p in range(len(t)) if count[t[p]] > 1)
    got = {(r["doc_id"], r["ln"]): (r["rank"], r["lcp"]) for r in linedup.suffix_array(frame(spark, docs)).collect()}
    assert len(got) == len(want)
    for i, (s, d, p) in enumerate(want):
        before, h = want[i - 1][0] if i else [], 0
        while h < min(len(before), len(s)) and before[h] == s[h]:
            h += 1
        assert got[d, p] == (i, h)


def test_maximal_line_runs(spark):
    """A run is as long as what it shares with its source, and names it; one long line is a run by itself."""
    long = " ".join(f"w{i}" for i in range(50))
    docs = ["a\nb\nc\nd\ne", "x\nb\nc\nd\ny", f"p\n{long}\nq", f"r\n{long}\ns", "c\nd\nq", f"{long[:-4]}", f"u\n{long[:-4]}"]
    runs = {(r["did"], r["ln"], r["lines"], r["fdid"], r["fln"]) for r in linedup.repeated_runs(frame(spark, docs)).collect()}
    assert runs == {(1, 1, 3, 0, 1), (3, 1, 1, 2, 1), (4, 0, 2, 0, 2)}
    got = {r["doc_id"]: r for r in linedup.dedup(frame(spark, docs)).collect()}
    assert [got[i]["text"] for i in (1, 3, 4, 6)] == ["x\ny", "r\ns", "q", docs[6]] and got[3]["copied_from"] == [2] and got[1]["removed_lines"] == 3
    assert linedup.dedup(frame(spark, docs), min_words=None).filter("doc_id = 3").first()["removed_lines"] == 0


def test_line_runs_of_rows_that_share_an_id(spark):
    docs = ["a\nb\nc", "a\nb\nd", "a\nb\nc", "z\nb\nc", None, "q\na\nb"]
    got = linedup.dedup(frame(spark, docs, [5, 5, 5, None, None, 9])).collect()
    text = sorted((r["doc_id"] or -1, r["removed_lines"]) for r in got)
    assert len(got) == 6 and [n for d, n in text if d == 9] == [2] and [n for d, n in text if d == -1] == [0, 0]  # null doc_ids come first
    same = [r["text"] for r in got if r["doc_id"] == 5]
    assert len(set(same)) == 2  # rows that repeat id and text lose the same lines; the other text loses its own
    many = "\n".join(["x", "y"] * 20000)
    big = {r["doc_id"]: r for r in linedup.dedup(frame(spark, [many, "x\ny\n" + many])).collect()}
    assert big[0]["text"] == "x\ny" and big[0]["removed_lines"] == 39998 and big[1]["text"] == ""


@pytest.mark.parametrize("alphabet", [1, 2, 6, 50])
def test_suffix_array(alphabet):
    rng = random.Random(alphabet)
    for _ in range(60):
        s = [rng.randrange(alphabet) for _ in range(rng.randint(0, 60))]
        sa = substrings.suffix_array(s)
        assert list(sa) == sorted(range(len(s)), key=lambda i: s[i:])
        p = substrings.permuted_lcp(s, sa)
        for i in range(1, len(s)):
            a, b, h = s[sa[i - 1] :], s[sa[i] :], 0
            while h < min(len(a), len(b)) and a[h] == b[h]:
                h += 1
            assert p[sa[i]] == h


def passages(texts, length):
    first, gone = {}, defaultdict(set)
    for d in sorted(texts):
        w = (texts[d] or "").split()
        for p in range(len(w) - length + 1):
            e, q = first.setdefault(tuple(w[p : p + length]), (d, p))
            if (e, q) != (d, p) and (e != d or p >= q + length):
                gone[d].update(range(p, p + length))
    return gone


def test_passages_on_the_table(documents, texts):
    gone = passages(texts, substrings.LENGTH)
    for r in substrings.dedup(documents).collect():
        want = [x for i, x in enumerate(texts[r["doc_id"]].split()) if i not in gone[r["doc_id"]]]
        assert r["text"].split() == want and r["removed_words"] == len(gone[r["doc_id"]])


def test_passages_small_alphabet(spark):
    rng = random.Random(9)
    docs = {d: " ".join(rng.choice("abc") for _ in range(rng.randint(0, 60))) for d in range(25)}
    docs[25] = "a " * 80
    gone = passages(docs, 12)
    for per_shard in (substrings.SEGMENTS_PER_SHARD, 3):  # with 3, most anchors are split
        for r in substrings.dedup(frame(spark, [docs[d] for d in range(26)]), 12, 3, per_shard).collect():
            assert r["text"].split() == [x for i, x in enumerate(docs[r["doc_id"]].split()) if i not in gone[r["doc_id"]]], r["doc_id"]


def test_passages_in_very_many_surroundings(spark):
    """One line in 300 texts that share nothing else: its anchors are split, and nothing but it goes."""
    rng = random.Random(12)
    line = " ".join(f"l{i}" for i in range(60))
    docs = [" ".join(f"x{rng.random()}" for _ in range(40)) + f" {line} " + " ".join(f"y{rng.random()}" for _ in range(40)) for _ in range(300)]
    for r in substrings.dedup(frame(spark, docs), per_shard=50).collect():
        want = docs[0] if r["doc_id"] == 0 else docs[r["doc_id"]].replace(line + " ", "")
        assert r["text"] == want and bool(r["copied_from"]) == (r["doc_id"] > 0) and all(c < r["doc_id"] for c in r["copied_from"])


def test_passages_of_rows_that_share_an_id(spark):
    x, y = " ".join(f"w{i}" for i in range(80)), " ".join(f"v{i}" for i in range(80))
    got = substrings.dedup(frame(spark, [x, x, y, None, "", y + " end"], [7, 7, 7, None, 3, 9])).collect()
    assert sorted((r["doc_id"] or -1, r["removed_words"]) for r in got) == [(-1, 0), (3, 0), (7, 0), (7, 0), (7, 0), (9, 80)]


def test_passages_by_sql(documents):
    import duckdb

    from roadsnap.llm import queries

    con = duckdb.connect()
    con.execute("CREATE VIEW documents AS SELECT * FROM '/root/testdata/sf0.001/documents.parquet'")
    want = dict(con.execute(queries.OP7_REMOVED_SQL).fetchall())
    assert {r["doc_id"]: r["removed_words"] for r in substrings.dedup(documents).filter("removed_words > 0").collect()} == want


# ---------------------------------------------------------------- 3 quality


def test_quality_on_held_out(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    weights = quality.train(docs, labels.filter("doc_id % 5 <> 0"))
    held = quality.score(docs, weights).drop("text").join(labels.filter("doc_id % 5 = 0"), "doc_id").toPandas()
    clean = held[(held.quality == 1) & (held.toxic == 0)]
    assert ((clean.p_quality >= 0.5) & (clean.p_toxic <= 0.5)).mean() > 0.98
    assert (held[held.quality == 0].p_quality < 0.5).mean() > 0.8
    assert (held[held.toxic == 1].p_toxic > 0.5).mean() > 0.75


def test_sparse_scores_match_dense():
    data, offsets = tk.utf8(__import__("pyarrow").array(["good good words", None, "bad!! words"]))
    col, off = quality.features(data, offsets, 12, tk.SpanHash(3))
    w = np.random.default_rng(0).normal(size=(2, 1 << 12))
    p = quality.probabilities(col, off, w)
    for i in range(3):
        c = col[off[i] : off[i + 1]]
        assert len(set(c)) == len(c) and c[0] == 0
        assert np.allclose(p[:, i], 1 / (1 + np.exp(-w[:, c].sum(1))))


def test_follow_the_leader_by_a_plain_loop():
    """Every update by the per-coordinate rule, one number at a time."""
    from math import exp, sqrt

    rng = random.Random(6)
    rows = [sorted({0, *(rng.randrange(1, 32) for _ in range(rng.randint(1, 9)))}) for _ in range(60)]
    labels = [[rng.random() < (0.8 if 3 in r else 0.2), rng.random() < (0.9 if 5 in r else 0.1)] for r in rows]
    alpha, beta, l1, l2 = 0.7, 1.0, 0.4, 0.05
    off = np.concatenate([[0], np.cumsum([len(r) for r in rows])])
    got = quality.fit(np.array([c for r in rows for c in r]), off, np.array(labels, float), bits=5, epochs=3, seed=2, alpha=alpha, beta=beta, l1=l1, l2=l2)
    z, n = [[0.0] * 32 for _ in range(2)], [[0.0] * 32 for _ in range(2)]
    weight = lambda h, c: 0.0 if abs(z[h][c]) <= l1 else ((1 if z[h][c] > 0 else -1) * l1 - z[h][c]) / ((beta + sqrt(n[h][c])) / alpha + l2)
    for epoch in range(3):
        for i in np.random.default_rng(2 + epoch).permutation(60):
            for h in range(2):
                w = {c: weight(h, c) for c in rows[i]}
                g = 1 / (1 + exp(-sum(w.values()))) - labels[i][h]
                for c in rows[i]:
                    s = (sqrt(n[h][c] + g * g) - sqrt(n[h][c])) / alpha
                    z[h][c] += g - s * w[c]
                    n[h][c] += g * g
    assert np.allclose(got, [[weight(h, c) for c in range(32)] for h in range(2)], atol=1e-5) and np.count_nonzero(got) > 10


# ---------------------------------------------------------------- 4 fingerprints


def test_fingerprints(spark, documents, texts):
    def shingle_set(t):
        w = t.lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    rows = {r["doc_id"]: r for r in fingerprint.sketch(documents).collect()}
    sets = {d: shingle_set(t) for d, t in texts.items()}
    for d, r in rows.items():
        n = len(sets[d])
        assert abs(r["n_shingles"] - n) <= (0 if n < fingerprint.K else 0.4 * n), d
    ids, errors = sorted(sets), []
    for a in ids[:60]:
        for b in ids:
            want = len(sets[a] & sets[b]) / len(sets[a] | sets[b])
            x, y = np.array(rows[a]["sketch"]), np.array(rows[b]["sketch"])
            errors.append(abs(fingerprint.compare(x, fingerprint.K, y, fingerprint.K)[0] - want))
    assert max(errors) < 0.25 and np.mean(errors) < 0.005


def test_resemblance_as_a_column(spark, documents):
    from pyspark.sql import functions as F

    rows = fingerprint.sketch(documents).limit(30)
    a, b = rows.select(F.col("doc_id").alias("i"), F.col("sketch").alias("x")), rows.select(F.col("doc_id").alias("j"), F.col("sketch").alias("y"))
    for r in a.crossJoin(b).select("x", "y", fingerprint.resemblance(F.col("x"), F.col("y")).alias("r")).collect():
        x, y = np.array(r["x"], np.int64), np.array(r["y"], np.int64)
        union = np.union1d(x, y)[: fingerprint.K]
        want = np.isin(union, np.intersect1d(x, y)).mean() if len(union) else 0.0
        assert r["r"] == pytest.approx(want)


def test_merged_sketch_is_that_of_the_union(spark, documents):
    parts = fingerprint.sketch(documents.select("lang", "text"), key="lang")
    whole = {r["lang"]: r["sketch"] for r in fingerprint.merged(parts, "lang").collect()}
    for r in whole:
        every = np.unique(np.concatenate([np.array(x["sketch"], np.int64) for x in parts.filter(parts.lang == r).collect()]))[: fingerprint.K]
        assert whole[r] == every.tolist()


def test_documents_against_a_large_benchmark(spark, tmp_path):
    rng = random.Random(5)
    items = [" ".join(f"w{rng.randrange(10**6)}" for _ in range(35)) for _ in range(2500)]
    long = " ".join(f"x{i}" for i in range(3000))
    docs = [items[7], f"{long} {items[8]} {long}", " ".join(items[9].split()[:20] + items[10].split()[:12]), "nothing of it is in there at all", "", None, f"a b {items[2499]}"]
    frame(spark, docs).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(list(enumerate(items)), "item_id bigint, text string").write.parquet(f"{tmp_path}/benchmark.parquet")

    def shingle_set(t):
        w = (t or "").split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    from roadsnap.llm import queries

    sets, whole = [shingle_set(t) for t in items], set().union(*map(shingle_set, items))
    got = {r["doc_id"]: r for r in queries.op4_fingerprints(spark, str(tmp_path)).collect()}
    assert len(whole) > 65_536 and len(got) == len(docs)
    for d, t in enumerate(docs):
        mine = shingle_set(t)
        assert got[d]["reference_containment"] == pytest.approx(len(mine & whole) / len(mine) if mine else 0)
        assert got[d]["reference_resemblance"] == pytest.approx(len(mine & whole) / len(mine | whole))
        want = [(i, len(mine & s), len(mine & s) / len(mine | s), len(mine & s) / len(s), len(mine & s) / len(mine)) for i, s in enumerate(sets) if mine & s]
        assert len(got[d]["items"]) == len(want) and all(tuple(x) == pytest.approx(y) for x, y in zip(got[d]["items"], want))


# ---------------------------------------------------------------- 5 sentencepiece


def unigram_proto(proto):
    p = bytearray(proto)
    for f, s, e in lattice._fields(proto):
        if f == 2:
            for g, a, _ in lattice._fields(proto[s:e]):
                if g == 3:
                    p[s + a] = 1
    return bytes(p)


def test_pieces_equal_the_library(spark, documents, texts):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=lattice.MODEL)
    for r in lattice.encode(documents, max_words=500).collect():
        assert r["ids"] == sp.encode(texts[r["doc_id"]]) and r["round_trip"]
    odd = [t for t in ODD if t is not None]
    for r in lattice.encode(frame(spark, odd), max_words=2).collect():
        assert r["ids"] == sp.encode(odd[r["doc_id"]]), odd[r["doc_id"]][:20]


def test_spark_and_local_folds_agree(spark, texts):
    proto = open(lattice.MODEL, "rb").read()
    words = sorted({w for t in list(texts.values())[:40] for w in t.split()})[:400] + ["日本é", "🎉x"]
    words = ["▁" + w for w in words]
    for kind in ("bpe", "unigram"):
        model = lattice.Model(proto, kind)
        got = {r["word"]: r["ids"] for r in lattice.encode_words(spark.createDataFrame([(w,) for w in words], "word string"), model).collect()}
        local = lattice.LocalFold(model)(words)
        if kind == "bpe":
            assert all(got[w] == x.tolist() for w, x in zip(words, local))
            continue
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_proto=unigram_proto(proto))
        score = lambda ids: sum(model.scores[i] if i not in model.byte else model.unknown for i in ids)
        for w, x in zip(words[:-2], local):
            best = score(sp.encode(w[1:]))  # ties may be cut differently; the best sum is the same
            assert score(got[w]) == pytest.approx(best) and score(x.tolist()) == pytest.approx(best)


def test_decode(spark, documents, texts):
    for r in lattice.decode(lattice.encode(documents, max_words=500)).collect():
        assert r["text"] == texts[r["doc_id"]]


# ---------------------------------------------------------------- 6 exact


def test_perfect_hash():
    rng = np.random.default_rng(1)
    a, b = rng.integers(0, 1 << 63, 5000).astype(np.uint64), rng.integers(0, 1 << 63, 5000).astype(np.uint64)
    sizes, bits = exact.build(a, b)
    assert sorted(exact.slots(a, b, sizes, bits)) == list(range(5000)) and bits.sum() == 5000
    other = exact.slots(a + np.uint64(1), b, sizes, bits)
    assert ((other >= -1) & (other < 5000)).all()
    assert len(exact.build(a[:0], b[:0])[1]) == 0


def test_exact_dedup_and_history(spark, documents, texts):
    first = {}
    for d in sorted(texts):
        first.setdefault(texts[d], d)
    assert sorted(r["doc_id"] for r in exact.dedup(documents).select("doc_id").collect()) == sorted(first.values())
    new = frame(spark, ["old one", "new", "new", None, "old two"], [10, 11, 12, 13, 14])
    old = frame(spark, ["old one", "old two", None], [1, 2, 3])
    assert sorted(r["doc_id"] for r in exact.dedup(new, old).collect()) == [11, 13]
    # a new text that stands in two rows of one doc_id leaves one; what the history has goes whatever its doc_id
    again = exact.dedup(frame(spark, ["fresh", "fresh", "old five", "old five"], [11, 11, 5, 6]), frame(spark, ["old five"], [5])).collect()
    assert [(r["doc_id"], r["text"]) for r in again] == [(11, "fresh")]


@pytest.mark.parametrize("seed", range(4))
def test_exact_dedup_with_random_histories(spark, seed):
    """Few texts and ids, so that rows repeat both, tie on either and miss one."""
    rng = random.Random(seed)
    make = lambda n: [(rng.choice([None, *range(6)]), rng.choice([None, "", *"abcde"]), rng.choice("st")) for _ in range(n)]
    new, old = make(40), make(seed * 4)
    schema = "doc_id bigint, text string, source string"
    key = lambda i: (i is None, i or 0)

    def plain(rows, known):
        best = {}
        for i, t, _ in rows:
            if t is not None and t not in known:
                best[t] = min(best.get(t, i), i, key=key)
        return sorted([(repr(i), repr(t)) for t, i in best.items()] + [(repr(i), repr(t)) for i, t, _ in rows if t is None])

    shown = lambda df: sorted((repr(r["doc_id"]), repr(r["text"])) for r in df.collect())
    docs, history = spark.createDataFrame(new, schema), spark.createDataFrame(old, schema)
    assert shown(exact.dedup(docs, history, 3)) == plain(new, {t for _, t, _ in old})
    assert shown(exact.dedup(docs)) == plain(new, ())
    first, later = [r for r in new if r[2] == "s"], [r for r in new if r[2] != "s"]
    assert shown(exact.dedup_by_history(docs, "source = 's'")) == sorted(plain(first, ()) + plain(later, {t for _, t, _ in first}))


# ---------------------------------------------------------------- 8 near copies


def weighted(t, k=nearcopy.K):
    w = t.split()
    return Counter(tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))) if w else Counter()


def brute_probability_jaccard(x, y):
    out = 0.0
    for d in x.keys() & y.keys():
        out += 1 / sum(max(x[e] / x[d], y[e] / y[d]) for e in x.keys() | y.keys())
    return out


def test_probability_jaccard_and_signatures():
    rng = random.Random(4)
    x = Counter({i: rng.randint(1, 5) for i in range(60)})
    y = Counter({i: rng.randint(1, 5) for i in range(20, 90)})
    want = brute_probability_jaccard(x, y)
    arr = lambda c: (np.array(sorted(c)), np.array([c[k] for k in sorted(c)]))
    assert nearcopy.probability_jaccard(*arr(x), *arr(y)) == pytest.approx(want)
    m = 20000
    key = tk.mix(np.array([*sorted(x), *sorted(y)], np.uint64))
    sig = nearcopy.signatures(key, np.repeat([0, 1], [len(x), len(y)]), np.array([x[k] for k in sorted(x)] + [y[k] for k in sorted(y)]), 2, m)
    assert (sig[0] == sig[1]).mean() == pytest.approx(want, abs=0.015)


def test_near_copies_recall(documents, texts):
    w = {d: weighted(t) for d, t in texts.items()}
    near = []
    for a in w:
        for b in w:
            if a < b and 2 * len(w[a].keys() & w[b].keys()) > 0.5 * min(len(w[a]), len(w[b])):
                s = brute_probability_jaccard(w[a], w[b])
                if s >= nearcopy.THRESHOLD:
                    near.append((a, b))
    root = {r["doc_id"]: r["root"] for r in nearcopy.components(nearcopy.pairs(documents)).collect()}
    hit = sum(a in root and root[a] == root.get(b) for a, b in near)
    assert near and hit >= 0.9 * len(near)
    left = Counter(root.values())
    linked = {x for p in near for x in p}
    assert set(root) <= linked and min(left.values()) > 1  # nothing else is touched


@pytest.mark.parametrize("low, high", [(0.05, 0.2), (0.08, 0.12)])
def test_drifting_hot_group_equals_brute_force(spark, low, high):
    rng = random.Random(8)
    base = [f"w{i}" for i in range(60)]
    docs = [" ".join(f"e{rng.random()}" if rng.random() < share else x for x in base) for share in (rng.uniform(low, high) for _ in range(90))]
    df = frame(spark, docs)
    buckets = defaultdict(list)
    for r in nearcopy.sketch(df).collect():
        for h in r["bands"]:
            buckets[h].append(r["doc_id"])
    met = {(min(a, b), max(a, b)) for ids in buckets.values() for a in ids for b in ids if a != b}
    w = [weighted(t) for t in docs]
    root = list(range(len(docs)))
    for a, b in met:
        if brute_probability_jaccard(w[a], w[b]) >= nearcopy.THRESHOLD:
            x, y = sorted((root[a], root[b]))
            root = [x if r == y else r for r in root]
    got = {r["doc_id"]: r["root"] for r in nearcopy.components(nearcopy.pairs(df)).collect()}
    assert max(map(len, buckets.values())) > 10 and [got.get(d, d) for d in range(len(docs))] == root


def test_hot_group_of_near_copies(spark):
    base = [f"w{i}" for i in range(200)]
    rng = random.Random(2)
    docs = []
    for i in range(150):
        t = list(base)
        t[rng.randrange(200)] = f"x{i}"
        docs.append(" ".join(t))
    docs += [" ".join(f"u{i}_{j}" for j in range(100)) for i in range(5)]
    assert sorted(r["doc_id"] for r in nearcopy.dedup(frame(spark, docs)).collect()) == [0, *range(150, 155)]


# ---------------------------------------------------------------- 9 codes


@pytest.mark.parametrize("bits", [4, 8, 12])
def test_codes(bits):
    rng = np.random.default_rng(bits)
    for n in (0, 1, 7, 511, 512, 513, 5000):
        ids = np.concatenate([rng.integers(0, 50257, n // 2), rng.integers(0, 20, n - n // 2)])
        c = tokens.Codes(tokens.encode_ids(ids, bits))
        assert len(c) == n and (c.all() == ids).all()
        assert all(c[int(i)] == ids[i] for i in rng.integers(0, max(n, 1), 50) if n)
    with pytest.raises(IndexError):
        c[n]


def test_token_ids_equal_the_library(spark, documents, texts):
    import tiktoken

    bpe = tiktoken.Encoding("x", pat_str=tokens.PATTERN, mergeable_ranks=tokens.load_bpe(), special_tokens={})
    rows = [(r, texts[r["doc_id"]]) for r in tokens.write_codes(documents).collect()]
    odd = ["a  b\n\n c\t\td ", "x  y   z　　 w", "", "é  è\r\n"]
    rows += [(r, odd[r["doc_id"]]) for r in tokens.write_codes(frame(spark, odd)).collect()]
    for r, t in rows:
        assert tokens.Codes(r["codes"]).all().tolist() == bpe.encode_ordinary(t) and r["n_tokens"] == len(bpe.encode_ordinary(t))


# ---------------------------------------------------------------- 10 private data


def test_viterbi_is_the_best_path():
    from itertools import product

    rng = np.random.default_rng(5)
    score, trans = rng.normal(size=(9, 3)), rng.normal(size=(3, 3))
    got = private.viterbi(score, np.array([0, 4, 4, 9]), np.array([4, 0, 5, 0]), trans)
    for lo, hi in ((0, 4), (4, 9)):
        value = lambda p: sum(score[lo + i, y] for i, y in enumerate(p)) + sum(trans[a, b] for a, b in zip(p, p[1:]))
        assert tuple(got[lo:hi]) == max(product(range(3), repeat=hi - lo), key=value)


def test_gradient_fit_and_held_out():
    field = private.fit(private.labelled_table())
    right = total = 0
    edge = field.rows(("edge",))
    for toks, labels in private.labelled_table(200, 77):
        rows = [field.rows(private.features(t.encode())) for t in toks]
        score = np.array([sum((rows[i + o] if 0 <= i + o < len(rows) else edge)[w] for w, o in enumerate(private.WINDOW)) for i in range(len(rows))])
        right += (private.viterbi(score, np.array([0]), np.array([len(rows)]), field.transition) == labels).sum()
        total += len(labels)
    assert right / total > 0.99


def test_likelihood_gradient_by_differences():
    seq, rng = private.Sequences(private.labelled_table(25)), np.random.default_rng(3)
    emission, transition = rng.normal(0, 0.3, (5, seq.none + 1, 6)), rng.normal(0, 0.3, (6, 6))
    emission[:, seq.none] = 0
    _, by_emission, by_transition = seq.likelihood(emission, transition)
    for values, gradient, limit in ((emission, by_emission, seq.none), (transition, by_transition, 6)):
        for _ in range(12):
            at = tuple(rng.integers(0, n) for n in values.shape[:-2]) + (rng.integers(0, limit), rng.integers(0, 6))
            was, d = values[at], 1e-5
            values[at] = was + d
            up = seq.likelihood(emission, transition)[0]
            values[at] = was - d
            down = seq.likelihood(emission, transition)[0]
            values[at] = was
            assert gradient[at] == pytest.approx((up - down) / (2 * d), abs=1e-4)


SPANS = {
    "EMAIL": r"[A-Za-z0-9][A-Za-z0-9._+-]*@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[a-z]{2,}", "PHONE": r"\+\d{1,3} \(\d{3}\) \d{3}-\d{4}", "CARD": r"(?<!\d)\d{13,19}(?!\d)",
    "IP": r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\d]|\.\d)", "SECRET": r"AKIA[A-Z0-9]{16}|(?<== \")(?:[0-9a-f]{32,}|[0-9A-F]{32,})(?=\")",
}


def test_kinds_on_real_texts():
    """Precision and recall of each kind on the documents of sf0.1, against patterns that are written by themselves."""
    import re

    import pyarrow as pa

    texts = pd.read_parquet("/root/testdata/sf0.1/documents.parquet", columns=["text"])["text"].tolist()
    decoder, found, truth = private.Decoder(private.fit(private.labelled_table())), set(), set()
    for lo in range(0, len(texts), 1000):
        for a, _, data, off in tk.pieces(*tk.utf8(pa.array(texts[lo : lo + 1000]))):
            found |= {(lo + a + row, int(s - off[row]), int(e - off[row]), kind) for row, s, e, kind in decoder.spans(data, off)}
    for i, t in enumerate(texts):
        for kind, form in SPANS.items():
            truth |= {(i, m.start(), m.end(), kind) for m in re.finditer(form.encode(), t.encode()) if kind != "CARD" or private.luhn(m.group().decode())}
    for kind, (precision, recall) in private.by_kind(found, truth).items():
        assert precision > 0.9 and recall > 0.95, kind


def test_field_from_a_table(spark):
    rows = [(t, [private.LABELS[y] for y in labels]) for t, labels in private.labelled_table(200)]
    labelled = spark.createDataFrame(rows, "tokens array<string>, labels array<string>")
    got = private.redact(frame(spark, ["mail to jane.12@mail.example.com, now"]), labelled=labelled).first()
    assert got["text"] == "mail to [EMAIL], now"
    none = private.redact(frame(spark, ["mail to jane.12@mail.example.com"]), labelled=labelled.limit(0)).first()
    assert none["text"] == "mail to jane.12@mail.example.com" and none["spans"] == []


def test_masks_private_data(spark):
    field = private.fit(private.labelled_table())
    docs = ["mail to jane.12@mail.example.com, now", "call +1 (415) 555-1234. Thanks", "card 4111111111111111 here", "from 10.20.30.40!! ok", 'token = "0123456789abcdef0123456789abcdef01234567" end', "number 4111111111111112 stays", "Version 2.0. in 2024", None]
    got = {r["doc_id"]: r for r in private.redact(frame(spark, docs), field).collect()}
    assert [got[i]["text"] for i in range(8)] == ["mail to [EMAIL], now", "call [PHONE]. Thanks", "card [CARD] here", "from [IP]!! ok", 'token = "[SECRET]" end', docs[5], docs[6], None]
    assert got[0]["n_chars"] == len("mail to [EMAIL], now") and docs[0][got[0]["spans"][0]["start"] : got[0]["spans"][0]["end"]] == "jane.12@mail.example.com"

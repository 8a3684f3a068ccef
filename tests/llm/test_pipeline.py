"""Each stage of the pipeline against what its operator must do, on its own input."""

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")


def test_stages_in_order(spark, sf):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality classifier", "exact dedup", "MinHash near-dedup", "PII", "packing"]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, sizes = docs.columns, [docs.count()]
    from roadsnap.llm import store

    for i, (_, stage) in enumerate(corpus_pipeline.STAGES):
        docs = store.keep(stage(spark, docs, sf), "test")
        if i < 4:
            assert docs.columns == columns
        sizes.append(docs.count())
        if i == 1:
            assert docs.select("text").distinct().count() == docs.count()
        if i == 3:
            assert docs.filter("text rlike '[a-z]@[a-z0-9]+[.]example[.]com'").count() == 0
            kept = {r["doc_id"] for r in docs.collect()}
    assert sizes[0] > sizes[1] > sizes[2] > sizes[3] == sizes[4]
    assert {r["doc_id"] for r in docs.collect()} == kept


def test_stages_equal_plain_ones(spark, sf):
    """Classifier, near-dedup and packing against loops, each on the input that the stage before it wrote."""
    import numpy as np
    import pyarrow as pa

    from roadsnap.llm import nearcopy, packing, quality, store, text as tk, tokens

    from test_operators import plain_packing, weighted

    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    stages = [f for _, f in corpus_pipeline.STAGES]
    # 1: sums of the weights of a text's distinct columns, one by one
    w = quality.train(docs, labels)
    keep, hasher = set(), tk.SpanHash(3)
    for r in docs.collect():
        col, off = quality.features(*tk.utf8(pa.array([r["text"]])), quality.BITS, hasher)
        p = [1 / (1 + np.exp(-np.clip(sum(float(h[c]) for c in set(col.tolist())), -35, 35))) for h in w]
        if p[0] >= 0.5 and p[1] <= 0.5:
            keep.add(r["doc_id"])
    first = store.keep(stages[0](spark, docs, sf), "test")
    assert {r["doc_id"] for r in first.collect()} == keep
    # 3: all pairs that share a band and are similar enough, joined to groups
    second = store.keep(stages[1](spark, first, sf), "test")
    bands = {r["doc_id"]: set(r["bands"]) for r in nearcopy.sketch(second).collect()}
    shingles = {r["doc_id"]: weighted(r["text"]) for r in second.collect()}
    root = {d: d for d in bands}
    ids = sorted(bands)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if bands[a] & bands[b]:
                x, y = shingles[a], shingles[b]
                keys = sorted(x.keys() | y.keys())
                if sum(1 / sum(max(x[e] / x[k], y[e] / y[k]) for e in keys) for k in x.keys() & y.keys()) >= nearcopy.THRESHOLD:
                    lo, hi = sorted((root[a], root[b]))
                    root = {d: lo if r == hi else r for d, r in root.items()}
    third = store.keep(stages[2](spark, second, sf), "test")
    assert {r["doc_id"] for r in third.collect()} == {d for d in shingles if root.get(d, d) == d}
    # 5: pieces in the order of doc_id
    fourth = store.keep(stages[3](spark, third, sf), "test")
    ids = {r["doc_id"]: r["ids"] for r in tokens.token_ids(fourth).collect()}
    want = plain_packing([len(ids[d]) for d in sorted(ids)], packing.WINDOW)
    got = {(r["doc_id"], r["piece"]): r for r in stages[4](spark, fourth, sf).collect()}
    for d, each in zip(sorted(ids), want):
        at = 0
        for j, (window, position, n) in enumerate(each):
            r = got.pop((d, j))
            assert (r["window"], r["position"], r["n_tokens"]) == (window, position, n) and r["ids"] == ids[d][at : at + n]
            at += n
        if not each:
            assert got.pop((d, 0))["n_tokens"] == 0
    assert not got


def test_empty_documents(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    docs.limit(0).write.parquet(f"{tmp_path}/documents.parquet")
    spark.read.parquet(f"{sf}/labels.parquet").write.parquet(f"{tmp_path}/labels.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_registry(spark, sf):
    import __spark_entry__ as entry

    names = [n for n in entry.queries() if n.startswith("op") and n[2].isdigit()]
    assert len(names) == 10 and "pipeline" in entry.queries()
    assert all(n in entry.queries() for n in entry.oracle_sql())

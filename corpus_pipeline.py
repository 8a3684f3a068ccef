"""Cleaning pipeline over `documents`: each stage reads what the one before it wrote."""

from __future__ import annotations

from roadsnap.llm import exact, nearcopy, packing, private, quality, queries, store


def classify(spark, docs, sf_dir):
    """Texts that the quality classifier, fitted on `labels`, keeps; columns of documents.

    A null or empty text has only the classifier's constant and is judged by it; rows without a doc_id are judged too.
    """
    labels = queries.table(spark, sf_dir, "labels")
    return quality.classify(docs, labels).select(docs.columns)


def exact_dedup(spark, docs, sf_dir):
    """One row of each distinct text: that of the least doc_id (a null one only where there is no other). Null texts stay."""
    return exact.dedup(docs)


def near_dedup(spark, docs, sf_dir):
    """One document of each group of near copies: that of the least doc_id. Texts without words and rows without a doc_id stay."""
    return nearcopy.dedup(docs)


def mask_private(spark, docs, sf_dir):
    """All rows, with private data masked in their texts; null and empty texts stay as they are."""
    return private.redact(docs).select(docs.columns)


def pack(spark, docs, sf_dir):
    """Windows of tokens: a row for each piece of a text, with its ids; a text without tokens has one row without a window."""
    return packing.pack(docs)


STAGES = [
    ("quality classifier", classify),
    ("exact dedup", exact_dedup),
    ("MinHash near-dedup", near_dedup),
    ("PII", mask_private),
    ("packing", pack),
]

#: A fitted classifier, MinHash and a sequential packing are beyond SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark, sf_dir):
    """All stages over documents; every stage's rows are written as Parquet to the shared folder and read again."""
    docs = queries.table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = store.keep(docs, "stage")
    return docs

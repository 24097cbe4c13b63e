"""A corpus pipeline of five stages over ``documents``: quality, exact and near duplicates, secrets, packing."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from progenrich.llm import fingerprint_dedup, ngram_join, nnls_packing, pairwise_quality, secret_scan
from progenrich.llm.common import Workspace, kept_of, table, without


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier does not reject.

    Null texts are scored as empty ones; null and repeated ids pass through like any row; an empty table gives no rows.
    """
    model = pairwise_quality.learn(docs, table(spark, sf_dir, "labels"))
    return pairwise_quality.filter_documents(docs, model)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts.

    Null texts equal empty ones; rows with a null id stay; of rows that repeat an id and its text one stays; an empty
    table gives no rows.
    """
    classes = Workspace(spark, "classes").write(fingerprint_dedup.duplicate_classes(spark, docs), "classes")
    left = without(docs, classes.where("not kept").select("doc_id"))
    again = classes.where("kept and doc_id is not null").groupBy("doc_id").count().where("count > 1").select("doc_id")
    if again.isEmpty():
        return left
    return without(left, again).unionByName(kept_of(left, again).dropDuplicates(["doc_id"]))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of least id of each component of near duplicates (five words, similarity 0.8).

    Null and empty texts and null ids are near to nothing and stay; rows that repeat the id that stays all stay; an
    empty table gives no rows.
    """
    found = ngram_join.near_duplicate_components(spark, docs, n=5, percent=80)
    return without(docs, found.where("component_id <> doc_id").select("doc_id"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with secrets in their text replaced by a mark. Null texts and ids and repeated rows pass through."""
    return secret_scan.redact_documents(docs)


def pack_windows(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their place in sequences of 4096 tokens.

    A null text counts as empty; null and repeated ids are packed row by row; an empty table gives no rows.
    """
    return nnls_packing.pack(spark, docs, public_tokenizers.path("word_bpe_49k.json"), window=4096, end_id=2, entries=200_000)


STAGES = [
    ("quality classifier", keep_good),
    ("exact dedup", drop_exact_copies),
    ("n-gram jaccard join", drop_near_copies),
    ("secret scan", redact_secrets),
    ("packing", pack_windows),
]

#: Stages tokenise and learn; SQL cannot express them. tests/llm holds a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each result is stored and read again."""
    work, docs = Workspace(spark, "pipeline"), table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = work.write(docs, f"stage{i}")
    return docs

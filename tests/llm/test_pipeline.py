"""The pipeline against plain Python, stage by stage."""

import collections

import corpus_pipeline
from test_group_operators import brute_dedup, brute_join

from progenrich.llm import pairwise_quality as pq
from progenrich.llm import secret_scan
from progenrich.llm.common import table

SMALL = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = table(spark, SMALL, "documents")
    rows = {r["doc_id"]: r["text"] for r in docs.collect()}
    stages = dict(corpus_pipeline.STAGES)
    model = pq.learn(docs, table(spark, SMALL, "labels"))
    good = stages["quality classifier"](spark, docs, SMALL)
    want = {i for i, t in rows.items() if model.score(pq.features([t or ""]))[0] >= model.decision}
    assert good.columns == docs.columns and {r["doc_id"] for r in good.collect()} == want
    once = stages["exact dedup"](spark, good, SMALL)
    want = {i for i, v in brute_dedup([(i, rows[i]) for i in want]).items() if v[2]}
    assert once.columns == docs.columns and {r["doc_id"] for r in once.collect()} == want
    near = stages["n-gram jaccard join"](spark, once, SMALL)
    want = {i for i, (_, c) in brute_join([(i, rows[i]) for i in want], 5, 80).items() if c == i}
    assert near.columns == docs.columns and {r["doc_id"] for r in near.collect()} == want
    clean = stages["secret scan"](spark, near, SMALL)
    got = {r["doc_id"]: r["text"] for r in clean.collect()}
    assert clean.columns == docs.columns and got == {i: secret_scan.redact(rows[i], secret_scan.spans_of(rows[i])) for i in want}
    assert all(not secret_scan.base_spans(t) for t in got.values())
    packed = stages["packing"](spark, clean, SMALL).collect()
    assert {r["doc_id"] for r in packed} == want
    seqs = collections.Counter()
    for r in packed:
        seqs[r["sequence_id"]] += r["length"]
    assert max(seqs.values()) <= 4096 and sum(seqs.values()) / (4096 * len(seqs)) > 0.9
    assert corpus_pipeline.run(spark, SMALL).count() == len(packed)


def test_empty(spark):
    docs = table(spark, SMALL, "documents").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SMALL)
    assert docs.count() == 0


def test_nulls_and_repeated_rows(spark, docs):
    """Null texts and ids pass; rows that repeat an id and its text leave one; extra columns stay."""
    good = "The quick brown fox jumps over the lazy dog while many people watch from the garden wall. "
    rows = [(1, good), (1, good), (2, good), (3, None), (4, ""), (None, good), (None, None), (5, good + "Then it rests in the shade for some time.")]
    frame = docs(rows)
    stages = dict(corpus_pipeline.STAGES)
    once = stages["exact dedup"](spark, frame, SMALL)
    assert once.columns == frame.columns
    assert sorted((str(r["doc_id"]), str(r["text"])) for r in once.collect()) == sorted([("1", good), ("3", "None"), ("None", good), ("None", "None"), ("5", rows[-1][1])])
    assert [r["doc_id"] for r in once.collect()].count(1) == 1
    near = stages["n-gram jaccard join"](spark, once, SMALL)
    assert {str(r["doc_id"]) for r in near.collect()} == {"1", "3", "5", "None"}
    clean = stages["secret scan"](spark, near, SMALL)
    assert clean.count() == near.count()
    assert {str(r["doc_id"]) for r in stages["packing"](spark, clean, SMALL).collect()} == {"1", "3", "5", "None"}
    assert stages["quality classifier"](spark, frame, SMALL).columns == frame.columns


def test_oracles(spark, con):
    from harness import differences

    from progenrich.llm.queries import ORACLES, QUERIES

    for name, sql in ORACLES.items():
        assert differences(spark, name, QUERIES[name], sql, con) == ""

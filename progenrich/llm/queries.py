"""One registered query for each operator of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann_block_join, crf_extract, extendible_shards, fingerprint_dedup, ngram_join, nnls_packing, pairwise_quality, piece_codec, secret_scan, token_counts
from .common import table

#: Bytes of text in a shard.
SHARD_BYTES = 64 << 20
#: A small limit under which even the test tables split.
SMALL_SHARD_BYTES = 64 << 10


def op1_int8_block_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings")
    return ann_block_join.nearest(spark, rows, rows.where(F.col("vec_id") % 100 == 0), k=10)


def op2_pretoken_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), limit=512)


def op3_nnls_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nnls_packing.pack(spark, table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), window=4096, end_id=2)


def op4_assignment_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(table(spark, sf_dir, "documents"))


def op5_piece_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_codec.round_trip_digests(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op6_extendible_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extendible_shards.shards(spark, table(spark, sf_dir, "documents"), SHARD_BYTES)


def small_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extendible_shards.shards(spark, table(spark, sf_dir, "documents"), SMALL_SHARD_BYTES)


def op7_pairwise_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return pairwise_quality.score(docs, pairwise_quality.learn(docs, table(spark, sf_dir, "labels")))


def op8_fingerprint_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint_dedup.duplicate_classes(spark, table(spark, sf_dir, "documents"))


def op9_crf_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return crf_extract.extract(table(spark, sf_dir, "pages"))


def op10_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.near_duplicate_components(spark, table(spark, sf_dir, "documents"), n=4, percent=85)


def op10_ngram_jaccard_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.near_duplicate_links(spark, table(spark, sf_dir, "documents"), n=4, percent=85)


QUERIES = {f.__name__: f for f in (op1_int8_block_search, op2_pretoken_counts, op3_nnls_packing, op4_assignment_secrets, op5_piece_round_trip, op6_extendible_shards, small_shards, op7_pairwise_quality, op8_fingerprint_dedup, op9_crf_main_text, op10_ngram_jaccard_join, op10_ngram_jaccard_links)}

_WHITE = "[\\x20\\x09-\\x0D]"


def _shards_sql(limit: int) -> str:
    return f"""
    WITH rows AS (
      SELECT doc_id, octet_length(encode(coalesce(text, ''))) AS n_bytes,
             CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), 'null') || ':' || md5(coalesce(text, ''))), 1, 15) AS BIGINT) AS h
      FROM documents),
    sums AS (
      SELECT d.depth, h >> (60 - d.depth) AS prefix, sum(n_bytes) AS bytes, count(DISTINCT h) AS n
      FROM rows, (SELECT unnest(range(0, 61)) AS depth) d GROUP BY 1, 2),
    leaf AS (
      SELECT r.doc_id, r.h, r.n_bytes, min(s.depth) AS depth
      FROM rows r JOIN sums s ON r.h >> (60 - s.depth) = s.prefix WHERE s.bytes <= {limit} OR s.n = 1
      GROUP BY r.doc_id, r.h, r.n_bytes),
    copies AS (SELECT doc_id, h, n_bytes, row_number() OVER (PARTITION BY h ORDER BY doc_id) AS k, count(*) OVER (PARTITION BY h) AS c FROM rows)
    SELECT l.doc_id, CAST(l.n_bytes AS BIGINT) AS n_bytes, l.h >> (60 - l.depth) AS shard_prefix, CAST(l.depth AS INTEGER) AS shard_depth,
           CAST(CASE WHEN c.c * c.n_bytes <= {limit} THEN 0 ELSE (c.k - 1) // greatest(1, {limit} // greatest(c.n_bytes, 1)) END AS BIGINT) AS page
    FROM leaf l JOIN copies c ON l.h = c.h AND l.doc_id = c.doc_id"""


ORACLES = {
    "op1_int8_block_search": """
    WITH v AS (
      SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings
      WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
    d AS (SELECT q.vec_id AS query_id, c.vec_id, list_distance(q.e, c.e) AS score FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e) WHERE q.vec_id % 100 = 0),
    r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score, vec_id) AS INTEGER) AS rank, vec_id, score FROM d)
    SELECT * FROM r WHERE rank <= 10""",
    "op6_extendible_shards": _shards_sql(SHARD_BYTES),
    "small_shards": _shards_sql(SMALL_SHARD_BYTES),
    "op8_fingerprint_dedup": f"""
    WITH n AS (SELECT doc_id, length(coalesce(text, '')) AS points, regexp_replace(coalesce(text, ''), '{_WHITE}', '', 'g') AS body FROM documents),
    k AS (SELECT *, first_value(doc_id) OVER (PARTITION BY body ORDER BY points DESC, doc_id) AS keep_id, count(*) OVER (PARTITION BY body) AS group_size FROM n)
    SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(body) AS text_sha256 FROM k""",
    "op10_ngram_jaccard_join": """
    WITH RECURSIVE w AS (
      SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS ws FROM documents),
    s AS (
      SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 4 THEN [array_to_string(ws, ' ')]
        ELSE list_transform(range(1, len(ws) - 2), lambda i: array_to_string(ws[i:i+3], ' ')) END) AS g FROM w),
    z AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
    p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
    link AS (SELECT x, y FROM p JOIN z u ON u.doc_id = x JOIN z v ON v.doc_id = y WHERE 100 * k >= 85 * (u.n + v.n - k)),
    reach(x, y) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.x, l.y FROM reach r JOIN link l ON l.x = r.y)
    SELECT d.doc_id, CAST(coalesce(z.n, 0) AS BIGINT) AS n_shingles, c.component_id
    FROM documents d LEFT JOIN z ON z.doc_id = d.doc_id JOIN (SELECT x, min(y) AS component_id FROM reach GROUP BY x) c ON c.x = d.doc_id""",
}

_LINKED, _COMPONENTS = ORACLES["op10_ngram_jaccard_join"].split("    reach(x, y) AS")
ORACLES["op10_ngram_jaccard_links"] = f"""{_LINKED}    reach(x, y) AS{_COMPONENTS.split("    SELECT d.doc_id")[0].rstrip()},
    same AS (SELECT x, least(x, min(y)) AS c FROM p JOIN z u ON u.doc_id = x JOIN z v ON v.doc_id = y WHERE k = u.n AND k = v.n GROUP BY x),
    cls AS (SELECT doc_id, coalesce(c, doc_id) AS c FROM documents LEFT JOIN same ON x = doc_id),
    degree AS (SELECT x, count(DISTINCT b.c) AS links FROM link JOIN cls a ON a.doc_id = x JOIN cls b ON b.doc_id = y WHERE a.c <> b.c GROUP BY x)
    SELECT q.*, coalesce(g.links, 0) AS links FROM (SELECT d.doc_id{_COMPONENTS.split("    SELECT d.doc_id")[1]}) q LEFT JOIN degree g ON g.x = q.doc_id"""

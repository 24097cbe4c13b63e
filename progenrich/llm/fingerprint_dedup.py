"""Exact deduplication by composable polynomial fingerprints.

The normalised text is cut into chunks, each chunk is hashed by itself (a polynomial in fixed bases modulo
several primes), and chunk hashes join by shifting the left one by the length of the right one. Texts of
equal fingerprint and length are then compared chunk by chunk with the row that would stay: only texts
with a partner are cut into rows again, and each comparison streams over chunks, so that neither a huge
text nor a huge group meets in one place. Members that differ from their row (a collision) form groups
of their own in further rounds.
"""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, map_slices, may_hold, sieve, texts_of, with_totals

#: Primes below 2**31 (fixed values of the fingerprint), each with a base.
PRIMES = (2147483647, 2147483629, 2147483587, 2147483579)
BASES = (911382323, 972663749, 1500450271, 1812433253)
CHUNK = 1 << 16
#: Members that share one copy of the row they are compared with.
SHARE = 64
_DROP = bytes([0x20, *range(0x09, 0x0E)])


def normalise(text: str) -> bytes:
    """UTF-8 of the text without the six white-space characters of ASCII."""
    return text.encode("utf-8", "surrogatepass").translate(None, _DROP)


@lru_cache(maxsize=8)
def _powers(base: int, prime: int, n: int) -> np.ndarray:
    """base**(n-1) .. base**0, by doubling."""
    out = np.ones(1, np.uint64)
    p, b = np.uint64(prime), base % prime
    while len(out) < n:
        shift = np.uint64(pow(b, len(out), prime))
        out = np.concatenate([out * shift % p, out])
    return np.ascontiguousarray(out[-n:])


def chunk_hash(chunk: bytes, primes=PRIMES, bases=BASES, size: int = CHUNK) -> tuple[int, ...]:
    buf = np.frombuffer(chunk, np.uint8).astype(np.uint64) + np.uint64(1)
    return tuple(int(np.dot(buf, _powers(b, p, size)[size - len(buf) :]) % np.uint64(p)) for p, b in zip(primes, bases))


def combine(left: tuple[int, ...], right: tuple[int, ...], right_size: int, primes=PRIMES, bases=BASES) -> tuple[int, ...]:
    """Hash of a concatenation from the hashes of its parts."""
    return tuple((x * pow(b, right_size, p) + y) % p for x, y, p, b in zip(left, right, primes, bases))


def fingerprint(data: bytes, primes=PRIMES, bases=BASES, size: int = CHUNK) -> tuple[int, ...]:
    out = (0,) * len(primes)
    for at in range(0, len(data), size):
        part = data[at : at + size]
        out = combine(out, chunk_hash(part, primes, bases, size), len(part), primes, bases)
    return out


def fingerprints(docs: DataFrame, primes=PRIMES, bases=BASES) -> DataFrame:
    """``doc_id, f1, f2, size, points, text_sha256`` of each row; ``points`` are code points of the original."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        cols: list[list] = [[], [], [], [], []]
        for t in batch["text"].to_pylist():
            data = normalise(t)
            h = (*fingerprint(data, primes, bases), 0, 0, 0)
            for c, v in zip(cols, ((h[0] << 31) + h[1], (h[2] << 31) + h[3], len(data), len(t), hashlib.sha256(data).hexdigest())):
                c.append(v)
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string())
        return pa.RecordBatch.from_arrays([batch["doc_id"], *(pa.array(c, k) for c, k in zip(cols, kinds))], names=["doc_id", "f1", "f2", "size", "points", "text_sha256"])

    return map_slices(docs, run, "doc_id long, f1 long, f2 long, size long, points long, text_sha256 string")


def _chunks(texts: DataFrame, size: int) -> DataFrame:
    """Rows of a text's normalised chunks; an empty text has one empty chunk."""

    def run(batches):
        for b in batches:
            for r in range(b.num_rows):
                data = normalise(b["text"][r].as_py())
                parts = [data[at : at + size] for at in range(0, len(data), size)] or [b""]
                keep = {c: pa.repeat(b[c][r], len(parts)) for c in b.schema.names if c != "text"}
                yield pa.RecordBatch.from_pydict({**keep, "part": pa.array(range(len(parts)), pa.int32()), "bytes": pa.array(parts, pa.binary())})

    kept = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in texts.schema.fields if f.name != "text")
    return texts.mapInArrow(run, f"{kept}, part int, bytes binary")


def duplicate_classes(spark: SparkSession, docs: DataFrame, key: str = "doc_id", text: str = "text", primes=PRIMES, bases=BASES, chunk: int = CHUNK) -> DataFrame:
    """One row per document: ``doc_id, keep_id, group_size, kept, text_sha256``.

    Of equal normalised texts the one with most code points in the original, then the smallest id,
    stays. Null texts count as empty, and so equal each other and texts of white space alone. Keys are
    expected to be unique: repeated rows have the same ``keep_id``, and those of the row that stays all
    count as kept. Rows with a null key stay, each on its own. An empty table gives no rows; other columns
    are not read.
    """
    work = Workspace(spark, "exact-dedup")
    texts = texts_of(docs, key, text)
    prints = work.write(fingerprints(texts, primes, bases), "prints")
    by, open_, settled, round_ = ["f1", "f2", "size"], prints.where("doc_id is not null").select("doc_id", "f1", "f2", "size", "points"), [], 0
    # of a group: its size and the row that would stay
    first = [F.count("*").alias("n"), F.max(F.struct(F.col("points"), (-F.col("doc_id")).alias("low"))).alias("best")]
    second = [F.sum("n").alias("n"), (-F.max("best")["low"]).alias("keep_id")]
    while True:
        members = work.write(with_totals(open_, by, "doc_id", first, second, "n > 1").select("doc_id", "keep_id", "n"), f"members{round_}")
        # a member, and for each share of a group one copy of the row that stays
        share = F.pmod(F.xxhash64("doc_id"), F.ceil(F.col("n") / SHARE).cast("long"))
        wanted = members.where("doc_id <> keep_id").withColumn("share", share)
        copies = wanted.select(F.col("keep_id").alias("doc_id"), "keep_id", "share", F.lit(True).alias("stays")).distinct()
        # a sieve lets through the texts that may have a partner; they alone are shuffled, stored and cut
        partners = wanted.select("doc_id", "keep_id", "share", F.lit(False).alias("stays")).unionByName(copies)
        near = may_hold(texts, sieve(members))
        bodies = work.write(near.join(partners.hint("merge"), "doc_id"), f"bodies{round_}")
        left = _chunks(bodies.where("not stays").drop("stays"), chunk)
        right = _chunks(bodies.where("stays").drop("stays", "doc_id"), chunk).withColumnRenamed("bytes", "other").dropDuplicates(["keep_id", "share", "part"])
        same = left.join(right.hint("merge"), ["keep_id", "share", "part"], "left").groupBy("doc_id", "keep_id").agg(F.min(F.coalesce(F.col("bytes") == F.col("other"), F.lit(False))).alias("same"))
        same = work.write(same, f"same{round_}")
        work.drop(f"bodies{round_}", f"members{round_}")
        settled.append(same.where("same").select("doc_id", "keep_id"))
        differ = same.where(~F.col("same")).select("doc_id").distinct()
        if differ.isEmpty():
            break
        open_ = work.write(open_.join(differ, "doc_id", "left_semi"), f"open{round_}")
        round_ += 1
    links = settled[0]
    for more in settled[1:]:
        links = links.unionByName(more)
    links = links.groupBy("doc_id").agg(F.min("keep_id").alias("to"))
    named = prints.select("doc_id", "text_sha256").join(links, "doc_id", "left").withColumn("keep_id", F.coalesce("to", "doc_id"))
    # sizes: rows of a group, dealt to many tasks as one group may hold a great share of all rows
    sized = with_totals(named.where("keep_id is not null"), ["keep_id"], "doc_id", [F.count("to").alias("n")], [(F.sum("n") + 1).alias("group_size")])
    lone = named.where("keep_id is null").withColumn("group_size", F.lit(1).cast("long"))
    out = sized.unionByName(lone.select(*sized.columns))
    return out.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")

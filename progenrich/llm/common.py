"""Shared pieces: reading tables, a work folder that every executor sees, Arrow maps over whole texts."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows handled at once inside a Python worker, so that Python objects of few texts live together.
SLICE = 256


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Workspace:
    """A folder of Parquet tables below ``spark.checkpoint.dir``.

    Tables cut lineage and survive the loss of executors, as the folder is shared. Where the setting
    is unset (local tests), the context's checkpoint folder is used, or a local one is set.
    """

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
        if not base:
            base = spark.sparkContext._jsc.sc().getCheckpointDir()
            base = base.get() if base.isDefined() else None
        if not base:
            base = "/tmp/checkpoints"
            spark.sparkContext.setCheckpointDir(base)
        self.root = f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def write(self, df: DataFrame, name: str) -> DataFrame:
        """Store the rows and return a DataFrame that reads them back."""
        df.write.mode("overwrite").parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def drop(self, *names: str) -> None:
        """Delete stored tables which nothing reads any more."""
        jvm = self.spark.sparkContext._jvm
        conf = self.spark.sparkContext._jsc.hadoopConfiguration()
        for name in names:
            p = jvm.org.apache.hadoop.fs.Path(self.path(name))
            p.getFileSystem(conf).delete(p, True)


#: Most rows and bytes of an Arrow batch that goes to a Python worker: texts can be long.
BATCH = {"spark.sql.execution.arrow.maxRecordsPerBatch": 1000, "spark.sql.execution.arrow.maxBytesPerBatch": 16 << 20}


def bound_batches(spark: SparkSession) -> None:
    """Lower the session's limits on Arrow batches to ``BATCH``; both are settings of a running session."""
    for key, most in BATCH.items():
        now = spark.conf.get(key).rstrip("b")
        if not now.isdigit() or not 0 < int(now) <= most:
            spark.conf.set(key, str(most))


def texts_of(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The key and text alone; a null text counts as empty."""
    bound_batches(docs.sparkSession)
    return docs.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))


def slices(batches: Iterator[pa.RecordBatch], rows: int = SLICE) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def map_slices(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch], schema: str, rows: int = SLICE) -> DataFrame:
    """Map record batches of few rows; ``fn`` may build its state lazily, once in each worker."""

    bound_batches(df.sparkSession)

    def run(batches):
        for part in slices(batches, rows):
            yield fn(part)

    return df.mapInArrow(run, schema)


#: Cells of a sieve: with eight words of 64 bits each, 16 MiB whatever the number of ids.
SIEVE_CELLS = 1 << 18
#: The column that tells whether an id may be in a sieve; its name clashes with no column of a table.
HIT = "__hit"
_WORDS = tuple(f"w{j}" for j in range(8))


def _cell(key: str) -> F.Column:
    return F.pmod(F.xxhash64(F.lit(17), F.col(key)), F.lit(SIEVE_CELLS)).cast("int")


def _bit(key: str, j: int) -> F.Column:
    """The bit of word ``j`` that an id sets."""
    return F.shiftrightunsigned(F.xxhash64(F.col(key)), 6 * j).bitwiseAND(F.lit(63)).cast("int")


def sieve(ids: DataFrame, key: str = "doc_id") -> DataFrame:
    """A split-block Bloom filter of the ids: ``cell, w0 .. w7``, at most ``SIEVE_CELLS`` rows whatever the input."""
    words = [F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), _bit(key, j))).alias(w) for j, w in enumerate(_WORDS)]
    return ids.where(F.col(key).isNotNull()).groupBy(_cell(key).alias("cell")).agg(*words)


def sifted(rows: DataFrame, cells: DataFrame, key: str = "doc_id") -> DataFrame:
    """``rows`` with the boolean column ``HIT``: false only where the id is surely not in the sieve.

    The sieve is broadcast: its size is bounded. As it fills up, more rows hit that need not; results that
    follow with an exact join stay the same, at every size by the same plan.
    """
    held = F.lit(True)
    for j, w in enumerate(_WORDS):
        held = held & (F.call_function("shiftright", F.col(f"__sieve.{w}"), _bit(key, j)).bitwiseAND(F.lit(1).cast("long")) == 1)
    keep = [F.col(f"`{c}`") for c in rows.columns]
    packed = cells.select(F.col("cell").alias("__cell"), F.struct(*_WORDS).alias("__sieve"))
    both = rows.withColumn("__cell", _cell(key)).join(F.broadcast(packed), "__cell", "left")
    return both.select(*keep, F.coalesce(held, F.lit(False)).alias(HIT))


def may_hold(rows: DataFrame, cells: DataFrame, key: str = "doc_id") -> DataFrame:
    """Rows whose id may be in the sieve."""
    return sifted(rows, cells, key).where(HIT).drop(HIT)


def kept_of(rows: DataFrame, ids: DataFrame, key: str = "doc_id") -> DataFrame:
    """Rows whose id is among ``ids`` (a table of distinct ids): a sieve first, so that few others are shuffled."""
    near = may_hold(rows, sieve(ids, key), key)
    return near.join(ids.select(key).hint("merge"), key, "left_semi").select(*rows.columns)


def without(rows: DataFrame, ids: DataFrame, key: str = "doc_id") -> DataFrame:
    """Rows whose id is not among ``ids``; rows that miss the sieve never move."""
    marked = sifted(rows, sieve(ids, key), key)
    near = marked.where(HIT).drop(HIT).join(ids.select(key).hint("merge"), key, "left_anti")
    return marked.where(f"not {HIT}").drop(HIT).unionByName(near.select(*rows.columns))


def salts(spark: SparkSession) -> int:
    """Parts into which rows of one key are dealt."""
    return max(32, int(spark.conf.get("spark.sql.shuffle.partitions")))


def with_totals(rows: DataFrame, by: list[str], salt: str, first: list, second: list, where: str = "true") -> DataFrame:
    """``rows`` with aggregates of their group, no task of which sees all rows of a large group.

    ``first`` aggregates rows by group and salt, ``second`` those results by group; groups that fail
    ``where`` are dropped with their rows. Rows meet the results by group and salt. Null keys are dropped.
    """
    dealt = rows.withColumn("__salt", F.pmod(F.xxhash64(F.lit(3), F.col(salt)), F.lit(salts(rows.sparkSession))).cast("int"))
    cells = dealt.groupBy(*by, "__salt").agg(*first)
    totals = cells.groupBy(*by).agg(*second).where(where)
    named = cells.select(*by, "__salt").join(totals.hint("merge"), by)
    return dealt.join(named.hint("merge"), [*by, "__salt"]).drop("__salt")


def with_lookup(rows: DataFrame, by: list[str], salt: str, found: DataFrame) -> DataFrame:
    """``rows`` left joined with ``found`` (one row for each ``by``), rows of one key spread over many tasks."""
    dealt = rows.withColumn("__salt", F.pmod(F.xxhash64(F.lit(3), F.col(salt)), F.lit(salts(rows.sparkSession))).cast("int"))
    named = dealt.select(*by, "__salt").distinct().join(found.hint("merge"), by, "left")
    return dealt.join(named.hint("merge"), [*by, "__salt"]).drop("__salt")


#: Longer words are computed each time they are met, so that entries bound the bytes of a dictionary as well.
WORD_BYTES = 64


class Generations(dict):
    """A bounded dictionary that computes what it lacks: when full, all but the entries met since then go.

    Two generations of ``entries`` each: a new one starts when the present one is full, and entries of the
    old one move over when they are met again, so frequent entries are never computed twice. Keys of more than
    ``WORD_BYTES`` characters are never stored. ``many`` computes a list of keys at once.
    """

    def __init__(self, make: Callable, entries: int, many: Callable | None = None):
        super().__init__()
        self.make, self.entries, self.old = make, entries, {}
        self.many = many or (lambda keys: [make(k) for k in keys])

    def __missing__(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        if len(key) <= WORD_BYTES:
            if len(self) >= self.entries:
                self.old = dict(self)
                self.clear()
            self[key] = value
        return value

    def all(self, keys: list) -> list:
        """Values of the keys, those that are new computed together."""
        if len(self) + len(keys) > self.entries:
            self.old = dict(self)
            self.clear()
        out = list(map(self.get, keys))
        miss = [i for i, v in enumerate(out) if v is None]
        fresh = []
        for i in miss:
            value = self.old.get(keys[i])
            if value is None:
                fresh.append(i)
            else:
                out[i] = self[keys[i]] = value
        for i, value in zip(fresh, self.many([keys[i] for i in fresh]) if fresh else ()):
            out[i] = value
            if len(keys[i]) <= WORD_BYTES:
                self[keys[i]] = value
        return out


def distinct_words(texts: pa.Array, white: bool = False) -> tuple[np.ndarray, np.ndarray, pa.Array]:
    """Words of a slice of texts, each distinct word once: (bounds by text, code of each word, distinct words).

    Texts are cut at every single space (so words may be empty), or with ``white`` at runs of ASCII white space
    (no word is empty).
    """
    lists = (pc.ascii_split_whitespace if white else lambda t: pc.split_pattern(t, " "))(texts)
    bounds = lists.offsets.to_numpy().astype(np.int64)
    flat = lists.values.slice(bounds[0], bounds[-1] - bounds[0])
    bounds -= bounds[0]
    if white:
        full = pc.not_equal(pc.binary_length(flat), 0)
        kept = full.to_numpy(zero_copy_only=False)
        bounds = np.concatenate([[0], np.cumsum(kept)])[bounds]
        flat = flat.filter(full)
    coded = flat.dictionary_encode()
    return bounds, coded.indices.to_numpy(), coded.dictionary


def as_list(words: pa.Array) -> list[str]:
    """Words without spaces as Python strings: one join and one split are far cheaper than an object from each Arrow value."""
    n = len(words)
    return pc.binary_join(pa.ListArray.from_arrays(pa.array([0, n], pa.int32()), words), " ")[0].as_py().split(" ") if n else []


@lru_cache(maxsize=1)
def _byte_marks() -> dict[int, str]:
    """How byte-level vocabularies write bytes that are not visible characters: the next ones from 256 on."""
    seen = [*range(33, 127), *range(161, 173), *range(174, 256)]
    return {b: chr(256 + i) for i, b in enumerate(b for b in range(256) if b not in seen)}


def byte_level(text: str) -> str:
    return text.encode().decode("latin-1").translate(_byte_marks())


def gather(parts: list[bytes], codes: np.ndarray, kind: str) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of ``parts`` (packed as ``kind``) laid out in the order of ``codes``, and the bounds by code."""
    flat = np.frombuffer(b"".join(parts), kind)
    sizes = np.fromiter(map(len, parts), np.int64, len(parts)) // np.dtype(kind).itemsize
    starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    each = sizes[codes]
    ends = np.cumsum(each)
    at = np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts[codes] - (ends - each), each)
    return flat[at], np.concatenate([[0], ends])

"""Jaccard join on word n-grams: rare-first prefixes with length, positional and suffix filters.

1. A pass over the texts gives each document the size and a 128-bit digest of its set of n-grams, and adds
   every n-gram of every document to a sketch of counts of fixed size.
2. Documents of equal sets form a class with one representative. The sketch orders n-grams rare first
   (ties by hash: any total order is right, a rare-first one is cheap). Each set gives the n-grams of its
   prefix with their positions.
3. N-grams that lie in one set only are dropped, the rest are postings. For the join, every pair of
   representatives that passes the filters is verified. Components alone need less: links join components, and
   pairs in one component need no more work; so representatives are first compared with one promising partner
   each (in one round, or more), and every pair over different components that passes the filters is
   verified after that, exactly once. Postings of an n-gram that lie in one component make no pairs at all.
4. Verified links give the components and, in the join, the number of links.

N-grams are 64-bit hashes from here on. One plan serves all sizes: texts of a pair are found through a sieve of
fixed size, and the rows of hot n-grams, as the sketch tells them, are dealt to several tasks.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, as_list, distinct_words, may_hold, sieve, slices, texts_of, with_lookup, with_totals
from .components import components

SKETCH_BITS = 20
SEGMENT = 4096
#: Bits of a set's bitmap: sets differ in at least as many n-grams as their bitmaps in bits (the suffix filter).
BITMAP = 1024
#: An n-gram is hot, and its rows go to several tasks, from this many rows and this multiple of the mean on.
HOT_ROWS = 2000
HOT_SHARE = 8
_MIX = tuple(np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xFF51AFD7ED558CCD))


class Shingler:
    """Sorted distinct hashes of the word n-grams of texts; each distinct word of a slice is hashed once."""

    def __init__(self, n: int):
        self.n = n

    def _mixed(self, h: np.ndarray, size: int) -> np.ndarray:
        out = np.full(len(h) - size + 1, np.uint64(size), np.uint64)
        with np.errstate(over="ignore"):
            for i in range(size):
                out = (out * _MIX[0] + h[i : len(h) - size + 1 + i]) * _MIX[1]
                out ^= out >> np.uint64(29)
        return out

    def sets(self, texts: pa.Array) -> list[np.ndarray]:
        bounds, codes, words = distinct_words(pc.ascii_lower(texts), white=True)
        each = np.fromiter(map(xxhash.xxh64_intdigest, as_list(words)), np.uint64, len(words))
        h, n = each[codes], self.n
        every = self._mixed(h, n) if len(h) >= n else h[:0]
        bounds, out = bounds.tolist(), []
        for lo, hi in zip(bounds, bounds[1:]):
            if hi - lo >= n:
                grams = np.sort(every[lo : hi - n + 1])
                new = np.empty(len(grams), bool)
                new[0] = True
                np.not_equal(grams[1:], grams[:-1], out=new[1:])
                out.append(grams[new])
            else:
                out.append(self._mixed(h[lo:hi], hi - lo) if hi > lo else h[:0])
        return out

    def of(self, text: str) -> np.ndarray:
        return self.sets(pa.array([text]))[0]


def needed(size, percent: int):
    """Least overlap of a partner with a set of ``size``."""
    return -(-percent * size // 100)


def prefix_size(size: int, percent: int) -> int:
    return size - needed(size, percent) + 1


def _digest(grams: np.ndarray) -> tuple[int, int]:
    return struct.unpack("<qq", xxhash.xxh3_128_digest(grams.tobytes()))


def _bitmap(grams: np.ndarray) -> list[int]:
    bits = np.zeros(BITMAP, np.uint8)
    bits[(grams >> np.uint64(64 - BITMAP.bit_length() + 1)).astype(np.int64)] = 1
    return np.packbits(bits).view("<i8").tolist()


def _profiles(texts: DataFrame, n: int) -> DataFrame:
    """Rows (doc_id, n, s1, s2, bits) of documents and rows (segment, counts) of the partition's sketch."""

    def run(batches):
        sh, sketch = Shingler(n), np.zeros(1 << SKETCH_BITS, np.uint32)
        for b in slices(batches, 1000):
            size, s1, s2, bits, pending = [], [], [], [], []
            for g in sh.sets(b["text"]):
                d = _digest(g)
                size.append(len(g))
                s1.append(d[0])
                s2.append(d[1])
                bits.append(_bitmap(g))
                pending.append(g)
            each = np.concatenate(pending) >> np.uint64(64 - SKETCH_BITS)
            sketch += np.bincount(each.astype(np.int64), minlength=len(sketch)).astype(np.uint32) if len(each) > len(sketch) // 64 else 0
            if len(each) <= len(sketch) // 64:
                np.add.at(sketch, each.astype(np.int64), 1)
            m = b.num_rows
            yield pa.RecordBatch.from_arrays([b["doc_id"], pa.array(size, pa.int64()), pa.array(s1, pa.int64()), pa.array(s2, pa.int64()), pa.array(bits, pa.list_(pa.int64())), pa.nulls(m, pa.int32()), pa.nulls(m, pa.binary())], names=names)
        live = [(i, sketch[at : at + SEGMENT]) for i, at in enumerate(range(0, len(sketch), SEGMENT))]
        live = [(i, zlib.compress(c.tobytes(), 1)) for i, c in live if c.any()]
        m = len(live)
        if m:
            none = pa.nulls(m, pa.int64())
            yield pa.RecordBatch.from_arrays([none, none, none, none, pa.nulls(m, pa.list_(pa.int64())), pa.array([i for i, _ in live], pa.int32()), pa.array([c for _, c in live], pa.binary())], names=names)

    names = ["doc_id", "n", "s1", "s2", "bits", "segment", "counts"]
    return texts.mapInArrow(run, "doc_id long, n long, s1 long, s2 long, bits array<long>, segment int, counts binary")


def _merged_sketch(parts: DataFrame) -> np.ndarray:
    """Sum of the partitions' sketches; the result has a fixed size whatever the input."""

    def run(batches):
        sums: dict[int, np.ndarray] = {}
        for b in batches:
            for i, c in zip(b["segment"].to_pylist(), b["counts"].to_pylist()):
                got = np.frombuffer(zlib.decompress(c), np.uint32).astype(np.int64)
                sums[i] = sums[i] + got if i in sums else got
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([v.tobytes() for v in sums.values()], pa.binary())], names=["segment", "counts"])

    out = np.zeros(1 << SKETCH_BITS, np.int64)
    for r in parts.repartition("segment").mapInArrow(run, "segment int, counts binary").collect():
        out[r["segment"] * SEGMENT : (r["segment"] + 1) * SEGMENT] = np.frombuffer(r["counts"], np.int64)
    return out


def _prefixes(spark: SparkSession, texts: DataFrame, n: int, percent: int, sketch: np.ndarray) -> DataFrame:
    """Rows (gram, s1, n, pos, parts) of the prefixes; ``parts`` is how many tasks share the rows of a hot n-gram.

    A hot one has several times the mean count of a cell of the sketch, so few cells are hot at any size.
    """
    shared = spark.sparkContext.broadcast(sketch)
    hot = max(HOT_ROWS, HOT_SHARE * float(sketch.mean()))

    def run(batches):
        sh, count, seen = Shingler(n), shared.value, set()
        for b in slices(batches, 1000):
            cols: list[list] = [[], [], [], [], []]
            for g in sh.sets(b["text"]):
                if not len(g):
                    continue
                d = _digest(g)
                if d in seen:  # an equal set of this partition has given these rows
                    continue
                seen.add(d)
                p = prefix_size(len(g), percent)
                c = count[(g >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)]
                if p < len(g) // 2:
                    few = np.flatnonzero(c <= np.partition(c, p - 1)[p - 1])
                    few = few[np.argsort(c[few], kind="stable")][:p]
                else:
                    few = np.argsort(c, kind="stable")[:p]
                cols[0].append(g[few].view(np.int64))
                cols[1].append(np.full(p, d[0], np.int64))
                cols[2].append(np.full(p, len(g), np.int32))
                cols[3].append(np.arange(p, dtype=np.int32))
                cols[4].append(np.ceil(np.maximum(c[few] / hot, 1)).astype(np.int32))
            if cols[0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in cols], names=["gram", "s1", "n", "pos", "parts"])

    return texts.mapInArrow(run, "gram long, s1 long, n int, pos int, parts int")


def _sets(texts: DataFrame, n: int) -> DataFrame:
    """``doc_id, grams``: the sorted hashes as bytes."""

    def run(batches):
        sh = Shingler(n)
        for b in slices(batches, 1000):
            yield pa.RecordBatch.from_arrays([b["doc_id"], pa.array([g.tobytes() for g in sh.sets(b["text"])], pa.binary())], names=["doc_id", "grams"])

    return texts.mapInArrow(run, "doc_id long, grams binary")


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """``a, b, linked`` of each pair by its exact overlap."""
    left = sets.select(F.col("doc_id").alias("a"), F.col("grams").alias("ga"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("grams").alias("gb"))

    def run(batches):
        for b in slices(batches, 64):
            out = []
            for x, y in zip(b["ga"].to_pylist(), b["gb"].to_pylist()):
                u, v = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                small, large = (u, v) if len(u) <= len(v) else (v, u)
                hit = int((large[np.minimum(np.searchsorted(large, small), len(large) - 1)] == small).sum())
                out.append(100 * hit >= percent * (len(u) + len(v) - hit))
            yield pa.RecordBatch.from_arrays([b["a"], b["b"], pa.array(out, pa.bool_())], names=["a", "b", "linked"])

    # sorted merges: AQE deals the pairs of an id that is in very many of them to several tasks
    both = pairs.hint("merge").join(left, "a").hint("merge").join(right, "b")
    return both.select("a", "b", "ga", "gb").mapInArrow(run, "a long, b long, linked boolean").groupBy("a", "b").agg(F.max("linked").alias("linked"))


def _can_match(percent: int, a: str = "", b: str = "o_") -> F.Column:
    """Length and positional filters on two postings of one n-gram."""
    na, nb, pa_, pb = (F.col(x) for x in (f"{a}n", f"{b}n", f"{a}pos", f"{b}pos"))
    size = 100 * F.least(na, nb) >= percent * F.greatest(na, nb)
    room = F.least(na - pa_, nb - pb)
    return size & ((100 + percent) * room.cast("long") >= percent * (na + nb).cast("long"))


def _can_overlap(percent: int, a: str = "bits", b: str = "o_bits") -> F.Column:
    """Suffix filter: the bits in which two bitmaps differ leave room for the overlap that is needed."""
    differ = sum((F.bit_count(F.col(a)[i].bitwiseXOR(F.col(b)[i])) for i in range(BITMAP // 64)), F.lit(0))
    both = (F.col("n") + F.col("o_n")).cast("long")
    return (100 + percent) * (both - differ) >= 2 * percent * both


def _slots(rows: DataFrame) -> DataFrame:
    """A copy of each row for every part of its n-gram."""
    return rows.withColumn("slot", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))


def near_duplicate_components(spark: SparkSession, docs: DataFrame, n: int = 5, percent: int = 80, rounds: int = 1, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document: ``doc_id, n_shingles, component_id``; links within a component are not looked for.

    ``component_id`` is the least id reachable over pairs with a Jaccard similarity of at least
    ``percent`` / 100 on sets of distinct ``n``-word shingles (words by ASCII white space, A-Z lowered).
    Fewer words than ``n`` make one shingle of the whole; without words (null or empty text) a document
    has size 0 and its own component. A null id has a row with its size and no component, and links nothing. A
    repeated id with equal texts has equal rows; one with different texts has a row for each, and where it stands
    for a class, any of its texts may link the class. Shingles are compared as 64-bit hashes: a similarity is exact
    unless two different shingles of one pair share a hash. An empty table gives no rows; other columns are not read.
    """
    return _joined(spark, docs, n, percent, rounds, key, text, False)


def near_duplicate_links(spark: SparkSession, docs: DataFrame, n: int = 5, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``near_duplicate_components`` with ``links``: in how many other classes (documents of equal sets) the
    document has partners. All pairs of classes count, so the work grows with the number of links."""
    return _joined(spark, docs, n, percent, 0, key, text, True)


def _joined(spark: SparkSession, docs: DataFrame, n: int, percent: int, rounds: int, key: str, text: str, every: bool) -> DataFrame:
    work = Workspace(spark, "ngram-join")
    texts = texts_of(docs, key, text)
    profiles = work.write(_profiles(texts, n), "profiles")
    sketch = _merged_sketch(profiles.where("segment is not null").select("segment", "counts"))
    prints = profiles.where("segment is null").select("doc_id", "n", "s1", "s2", "bits")
    # classes of equal sets, each named by its least id, which alone keeps the bitmap
    lo = F.min("rep").alias("rep")
    named = with_totals(prints.where("n > 0 and doc_id is not null"), ["s1", "s2"], "doc_id", [F.min("doc_id").alias("rep")], [lo])
    named = work.write(named.select("doc_id", "n", "s1", "rep", F.when(F.col("doc_id") == F.col("rep"), F.col("bits")).alias("bits")), "named")
    lone = work.write(prints.where("n = 0 or doc_id is null").select("doc_id", "n"), "lone")
    work.drop("profiles")  # with it go the sketches of all partitions
    classes = named.where("doc_id = rep").select("s1", "rep", "bits").dropDuplicates(["s1", "rep"])
    prefixes = work.write(_prefixes(spark, texts.where("doc_id is not null"), n, percent, sketch), "prefixes")
    # an n-gram matters if two different sets have it in their prefixes; a hot one is taken to
    cold, warm = prefixes.where("parts = 1").repartition("gram"), prefixes.where("parts > 1")
    # the aggregate reads every column, so that it and the join below share one exchange of the prefixes
    live = cold.groupBy("gram").agg(F.min("s1").alias("lo"), F.max("s1").alias("hi"), F.max(F.col("n") + F.col("pos") + F.col("parts")).alias("most")).where("lo < hi and most > 0").select("gram")
    each = [F.max(c).alias(c) for c in ("n", "pos", "parts")]
    # partitions by n-gram serve the join and this aggregate alike
    shared = cold.join(live.hint("merge"), "gram").groupBy("gram", "s1").agg(*each).unionByName(warm.groupBy("gram", "s1").agg(*each))
    shared = work.write(shared, "shared")
    work.drop("prefixes")
    # half of the digest names the set here: where two sets share it, both get the posting, and verification tells;
    # w: how many n-grams of its prefix a set shares
    named_sets = shared.groupBy("s1").agg(F.count("*").alias("w")).join(classes.select("s1", "rep"), "s1").select("s1", "rep", "w")
    slot = F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int").alias("slot")
    postings = work.write(shared.join(named_sets, "s1").select("gram", "rep", "n", "pos", "w", "parts", slot), "postings")
    work.drop("shared")
    sets, links, comp, tried = None, None, None, None

    def verify(pairs: DataFrame, label: str) -> DataFrame:
        nonlocal sets
        ids = pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct()
        new = ids if sets is None else ids.join(sets.select("doc_id"), "doc_id", "left_anti")
        # texts that pass the sieve give their sets where they are; the join of the pairs drops the few too many
        more = work.write(_sets(may_hold(texts, sieve(new)), n), f"sets-{label}")
        sets = more if sets is None else sets.unionByName(more)
        return work.write(_verified(pairs, may_hold(sets, sieve(ids)), percent), f"verified-{label}")

    def joined(label: str) -> DataFrame:
        return work.write(components(links, work, f"cc-{label}"), f"comp-{label}")

    def with_components() -> DataFrame:
        rows = postings if comp is None else postings.join(comp.withColumnRenamed("node", "rep"), "rep", "left")
        return rows.withColumn("c", F.col("rep") if comp is None else F.coalesce("component", "rep")).select("gram", "rep", "n", "pos", "w", "c", "parts", "slot")

    for r in range(rounds):
        # one partner for each n-gram and class of size (within which sizes can match): the set with most shared
        # n-grams in its prefix, as it has least of its own; with classes shifted in the next round, then any set
        step = F.floor(F.log(F.col("n").cast("double")) / float(np.log(100 / percent)) + 0.5 * (r % 2)).cast("int") if percent < 100 else F.col("n")
        rows = with_components().withColumn("size", step)
        order = F.col("w") if r < 2 else F.xxhash64(F.col("rep"), F.lit(r))
        centre = rows.groupBy("gram", "size").agg(
            F.max(F.struct(order.cast("long").alias("o"), F.col("rep").alias("o_rep"), F.col("n").alias("o_n"), F.col("pos").alias("o_pos"), F.col("c").alias("o_c"))).alias("m"),
            F.min("c").alias("lo"), F.max("c").alias("hi"), F.max("parts").alias("parts"),
        ).where("lo < hi").select("gram", "size", "m.*", "parts")
        near = rows.drop("parts").join(_slots(centre), ["gram", "size", "slot"]).where(F.col("c") != F.col("o_c")).where(_can_match(percent))
        best = near.groupBy("rep", "o_rep").agg(F.count("*").alias("k")).groupBy("rep").agg(F.max(F.struct("k", "o_rep")).alias("m"))
        pairs = best.select(F.least("rep", "m.o_rep").alias("a"), F.greatest("rep", "m.o_rep").alias("b")).distinct()
        pairs = work.write(pairs if tried is None else pairs.join(tried, ["a", "b"], "left_anti"), f"pairs-{r}")
        if pairs.isEmpty():
            break
        done = verify(pairs, str(r))
        good = done.where("linked").select("a", "b")
        links = good if links is None else links.unionByName(good)
        tried = done.select("a", "b") if tried is None else tried.unionByName(done.select("a", "b"))
        comp = joined(str(r))
    # every pair, or every pair over different components, that the filters let through; for a hot n-gram one side
    # is copied to all parts, so its pairs are made in as many tasks
    rows, bits = with_components().drop("w"), classes.select("rep", "bits").dropDuplicates(["rep"])
    if every:
        rows = work.write(rows.join(bits, "rep"), "mixed")
        other = _slots(rows.select("gram", "parts", *[F.col(x).alias(f"o_{x}") for x in ("rep", "n", "pos", "bits")])).drop("parts")
        cross = rows.join(other, ["gram", "slot"]).where((F.col("rep") < F.col("o_rep")) & _can_match(percent) & _can_overlap(percent))
    else:
        mixed = rows.groupBy("gram", "c").agg(F.count("*").alias("k"), F.max("parts").alias("parts")).groupBy("gram").agg(F.max(F.struct("k", "c")).alias("m"), F.count("*").alias("kinds"), F.max("parts").alias("parts"))
        mixed = _slots(mixed.where("kinds > 1")).select("gram", "slot", F.col("m.c").alias("main"))
        rows = work.write(rows.join(mixed, ["gram", "slot"]).join(bits, "rep"), "mixed")
        minor = _slots(rows.where("c <> main").select("gram", "parts", *[F.col(x).alias(f"o_{x}") for x in ("rep", "n", "pos", "c", "bits")])).drop("parts")
        cross = rows.join(minor, ["gram", "slot"]).where((F.col("c") != F.col("o_c")) & ((F.col("c") == F.col("main")) | (F.col("rep") < F.col("o_rep"))) & _can_match(percent) & _can_overlap(percent))
    pairs = cross.select(F.least("rep", "o_rep").alias("a"), F.greatest("rep", "o_rep").alias("b")).distinct()
    pairs = work.write(pairs if tried is None else pairs.join(tried, ["a", "b"], "left_anti"), "pairs-rest")
    work.drop("postings", "mixed")
    if not pairs.isEmpty():
        good = verify(pairs, "rest").where("linked").select("a", "b")
        links = good if links is None else links.unionByName(good)
        comp = joined("rest")
    work.drop("sets-rest", *[f"sets-{r}" for r in range(rounds)])
    size, alone = F.col("n").alias("n_shingles"), lone.select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    none = [F.lit(0).cast("long").alias("links")] if every else []
    if comp is None:
        return named.select("doc_id", size, F.col("rep").alias("component_id"), *none).unionByName(alone.select("*", *none))
    found = comp.withColumnRenamed("node", "rep")
    if every:
        degree = links.select(F.col("a").alias("rep")).union(links.select("b")).groupBy("rep").agg(F.count("*").alias("links"))
        found = found.join(degree, "rep", "left")
    out = with_lookup(named.select("doc_id", "n", "rep"), ["rep"], "doc_id", found)
    out = out.select("doc_id", size, F.coalesce("component", "rep").alias("component_id"), *([F.coalesce("links", F.lit(0)).cast("long").alias("links")] if every else []))
    return out.unionByName(alone.select("*", *none))

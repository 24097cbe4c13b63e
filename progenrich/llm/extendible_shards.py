"""Byte-bounded shards by extendible hashing, in DataFrame operations only.

A document's key is hashed to 60 bits. A directory entry is a prefix of those bits; only a bucket over
the byte limit is split, on its next bit, until every bucket fits. The sums of all prefixes come from one
pass over cells (prefixes of a chosen depth) and from few, ever deeper passes over the cells that are
still too large. Rows that no bit can part (equal in all columns hashed) go to overflow pages of their
bucket, numbered from their count alone, so no such group is gathered.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Workspace

BITS = 60
#: Bits by which a pass looks deeper.
STEP = 12
#: Parts in which equal rows are counted.
PARTS = 64
#: Most equal rows that one task writes out of a counted run.
RUN = 100_000


def hashed(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, n_bytes, h``: h from the id and the digest of the text, so that only equal rows share it."""
    body = F.coalesce(F.col(text).cast("string"), F.lit(""))
    label = F.concat_ws(":", F.coalesce(F.col(key).cast("string"), F.lit("null")), F.md5(body.cast("binary")))
    h = F.conv(F.substring(F.md5(label.cast("binary")), 1, 15), 16, 10).cast("long")
    return docs.select(F.col(key).cast("long").alias("doc_id"), F.octet_length(body).cast("long").alias("n_bytes"), h.alias("h"))


def _prefix(h, depth):
    return F.shiftright(h, F.lit(BITS) - depth)


def directory(rows: DataFrame, limit: int, work: Workspace) -> DataFrame:
    """``prefix, depth, bytes`` of the leaves, from rows ``h, n_bytes`` with distinct h.

    Depth 0 is the one bucket of a table that fits; a lone h is never split.
    """
    leaves, depth = None, 0
    cells = rows
    while True:
        deep = min(depth + STEP, BITS)
        sums = cells.groupBy(F.expr(f"shiftright(h, {BITS - deep})").alias("cell")).agg(F.sum("n_bytes").alias("bytes"), F.count("*").alias("n"))
        levels = sums.select("bytes", "n", "cell", F.explode(F.sequence(F.lit(depth), F.lit(deep))).alias("depth"))
        per = levels.groupBy("depth", F.expr(f"shiftright(cell, {deep} - depth)").alias("prefix")).agg(F.sum("bytes").alias("bytes"), F.sum("n").alias("n"))
        per = work.write(per, f"level{deep}")
        split = (F.col("bytes") > limit) & (F.col("n") > 1)
        full = per.where(split).select((F.col("depth") + 1).alias("depth"), F.col("prefix").alias("up"))
        fits = per.where(~split)
        # a leaf fits while its parent does not; the first level of a deeper pass was found too large before
        child = fits.where(F.col("depth") > depth).withColumn("up", F.shiftright("prefix", 1)).join(full, ["depth", "up"]).select("prefix", "depth", "bytes")
        if depth == 0:
            child = child.unionByName(fits.where("depth = 0").select("prefix", "depth", "bytes"))
        leaves = child if leaves is None else leaves.unionByName(child)
        if deep == BITS:
            return leaves
        over = per.where((F.col("depth") == deep) & split).select("prefix")
        if over.isEmpty():
            return leaves
        cells = work.write(cells.join(over, F.expr(f"shiftright(h, {BITS - deep})") == F.col("prefix"), "left_semi"), f"cells{deep}")
        depth = deep


def shards(spark: SparkSession, docs: DataFrame, limit: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, n_bytes, shard_prefix, shard_depth, page`` of each row.

    A shard is (prefix, depth, page); its bytes stay within ``limit`` unless one row alone exceeds it.
    Pages above 0 exist only for rows that are equal in id and text. Null texts count as empty, null ids
    hash as such; an empty table gives no rows; other columns are not read.
    """
    work = Workspace(spark, "shards")
    rows = work.write(hashed(docs, key, text), "hashed")
    leaves = work.write(directory(rows.groupBy("h").agg(F.sum("n_bytes").alias("n_bytes")), limit, work), "leaves")
    depths = [r["depth"] for r in leaves.select("depth").distinct().collect()]  # at most 61 values
    # equal rows are counted by parts and numbered within them, so that no task sees or makes all of them
    dealt = rows.withColumn("part", F.pmod(F.monotonically_increasing_id(), F.lit(PARTS)).cast("int"))
    same = work.write(dealt.groupBy("h", "doc_id", "n_bytes", "part").agg(F.count("*").alias("copies")), "same")
    order = W.partitionBy("h", "doc_id", "n_bytes").orderBy("part")
    same = same.withColumn("before", F.sum("copies").over(order) - F.col("copies")).withColumn("all", F.sum("copies").over(W.partitionBy("h", "doc_id", "n_bytes")))
    tries = F.array(*[F.struct(F.lit(d).alias("depth"), F.expr(f"shiftright(h, {BITS - d})").alias("prefix")) for d in sorted(depths)]) if depths else F.array(F.struct(F.lit(0).alias("depth"), F.lit(0).cast("long").alias("prefix")))
    placed = same.select("*", F.inline(tries)).join(leaves.select("prefix", "depth"), ["depth", "prefix"])
    # a run of copies is written out in two steps: runs of at most RUN, dealt to other tasks, then rows
    runs = placed.withColumn("first", F.explode(F.sequence(F.lit(0).cast("long"), F.col("copies") - 1, F.lit(RUN).cast("long"))))
    runs = runs.where("copies <= " + str(RUN)).unionByName(runs.where("copies > " + str(RUN)).repartition("h", "first"))
    many = F.least(F.col("copies") - F.col("first"), F.lit(RUN))
    each = runs.withColumn("step", F.explode(F.sequence(F.lit(0).cast("long"), many - 1)))
    copy = F.col("before") + F.col("first") + F.col("step")
    per_page = F.greatest(F.lit(1), F.floor(F.lit(limit) / F.greatest(F.col("n_bytes"), F.lit(1))))
    page = F.when(F.col("all") * F.col("n_bytes") <= limit, 0).otherwise(F.floor(copy / per_page))
    return each.select("doc_id", "n_bytes", F.col("prefix").alias("shard_prefix"), F.col("depth").alias("shard_depth"), page.cast("long").alias("page"))

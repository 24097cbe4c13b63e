"""Object collections: a key, exact attributes, and hidden truth columns ``t_<type>``.

Scorers and measures alone may read the truth; planning never does.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Catalog, TagType
from ..operators.scorers import simulated_catalog
from .tables import table

# Fixed domains of the tables.
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")


@dataclass(frozen=True)
class Collection:
    name: str
    types: tuple[TagType, ...]

    def catalog(self) -> Catalog:
        return simulated_catalog(self.types)


COLLECTIONS = {
    "orders": Collection("orders", (TagType("Status", ("F", "O", "P"), "t_status"), TagType("Priority", PRIORITIES, "t_priority"), TagType("Segment", SEGMENTS, "t_segment"))),
    "lineitem": Collection("lineitem", (TagType("ReturnFlag", ("A", "N", "R"), "t_returnflag"), TagType("LineStatus", ("F", "O"), "t_linestatus"))),
    "events": Collection("events", (TagType("Kind", ("view", "signup", "purchase", "error", "click"), "t_kind"),)),
    "docs": Collection("docs", (TagType("Quality", (0, 1), "t_quality"), TagType("Toxic", (0, 1), "t_toxic"), TagType("Lang", ("de", "en", "es", "fr"), "t_lang"))),
    "turns": Collection("turns", (TagType("Role", ("user", "assistant", "system"), "t_role"),)),
    "vectors": Collection("vectors", (TagType("Cluster", tuple(range(10)), "t_cluster"),)),
}


def objects(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The collection as ``object_id``, exact attributes, truth columns. Dimensions join by broadcast only
    where Spark finds them small enough."""
    t = lambda n, *c: table(spark, sf_dir, n, *c)
    if name == "orders":
        dims = t("customer", "c_custkey", "c_nationkey", "c_mktsegment").join(t("nation", "n_nationkey", "n_name", "n_regionkey"), F.col("c_nationkey") == F.col("n_nationkey"))
        o = t("orders", "o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")
        return o.join(dims, F.col("o_custkey") == F.col("c_custkey")).select(
            F.col("o_orderkey").cast("long").alias("object_id"), "o_orderdate", "o_custkey", "o_totalprice", "c_nationkey", "n_name", "n_regionkey",
            F.col("o_orderstatus").alias("t_status"), F.col("o_orderpriority").alias("t_priority"), F.col("c_mktsegment").alias("t_segment"),
        )
    if name == "lineitem":
        key = _folded(*_line_factors(spark, sf_dir))
        return t("lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_discount", "l_returnflag", "l_linestatus").select(
            key.alias("object_id"), "l_shipdate", "l_quantity", "l_discount", F.col("l_returnflag").alias("t_returnflag"), F.col("l_linestatus").alias("t_linestatus")
        )
    if name == "events":
        return t("events", "event_id", "ts", "user_id", "event_type", "props").select(
            F.col("event_id").cast("long").alias("object_id"), "ts", "user_id", F.get_json_object("props", "$.k").cast("int").alias("location"), F.col("event_type").alias("t_kind")
        )
    if name == "docs":
        return t("documents", "doc_id", "text", "lang", "source", "n_chars").join(t("labels", "doc_id", "quality", "toxic"), "doc_id").select(
            F.col("doc_id").cast("long").alias("object_id"), "source", "n_chars", "text", F.col("quality").alias("t_quality"), F.col("toxic").alias("t_toxic"), F.col("lang").alias("t_lang")
        )
    if name == "turns":
        return t("conversations").select((F.col("conv_id") * 1000 + F.col("turn")).cast("long").alias("object_id"), "conv_id", "turn", "text", F.col("role").alias("t_role"))
    if name == "vectors":
        return t("embeddings").select(F.col("vec_id").cast("long").alias("object_id"), "embedding", F.col("label").alias("t_cluster"))
    raise ValueError(f"no collection {name!r}")


#: Factors by which the columns of a line's key fold into a long, and the multiple of a key that must still fit.
LINE_FACTORS = (8, 20011, 1009)
KEY_ROOM = 16
_FACTORS: dict[tuple[str, str], tuple[int, int, int]] = {}


def _folded(lines: int, parts: int, supps: int):
    """The four columns of a line's key as one number."""
    return (((F.col("l_orderkey").cast("long") * lines + F.col("l_linenumber")) * parts + F.col("l_partkey")) * supps + F.col("l_suppkey")).cast("long")


def _fold_apart(lines: DataFrame, key) -> bool:
    """Whether different keys of lines fold to different numbers. Rows that repeat a key do not count against it."""
    ids = lines.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", key.alias("k"))
    twice = ids.groupBy("k").count().where("count > 1").select("k")
    return ids.join(twice, "k", "left_semi").distinct().groupBy("k").count().where("count > 1").isEmpty()


def _line_factors(spark: SparkSession, sf_dir: str) -> tuple[int, int, int]:
    """Factors with which no two keys of lines fold alike; the four columns together are a key.

    The fixed factors (those of the SQL) serve where the columns stay below them, or else where a count by folded key
    finds none twice; otherwise factors above the greatest values do. Refused where the folded key would not fit into a long.
    """
    name = (spark.sparkContext.applicationId, sf_dir)
    if name not in _FACTORS:
        cols = ("l_linenumber", "l_partkey", "l_suppkey", "l_orderkey")
        lines = table(spark, sf_dir, "lineitem", *cols)
        top = {c: int(v or 0) for c, v in lines.agg(*[F.max(c).alias(c) for c in cols]).first().asDict().items()}

        def fits(factors) -> bool:
            return max(top["l_orderkey"] + 1, 1) * factors[0] * factors[1] * factors[2] * KEY_ROOM < 1 << 63

        found = LINE_FACTORS
        if any(top[c] >= f for c, f in zip(cols, LINE_FACTORS)) and not (fits(found) and _fold_apart(lines, _folded(*found))):
            found = tuple(max(f, top[c] + 1) for f, c in zip(LINE_FACTORS, cols))
        if not fits(found):
            raise ValueError("the key of a line does not fit into a long; number the lines first (objects with a bigint key)")
        _FACTORS[name] = found
    return _FACTORS[name]


def split_part(key=None):
    """0..9 from the key: parts 0 and 1 are for validation, the rest for queries."""
    return F.pmod(F.pmod(F.col(key or "object_id"), F.lit(10)) * 7919, F.lit(10))

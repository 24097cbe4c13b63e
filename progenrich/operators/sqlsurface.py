"""SQL face: one call that runs the operator from a text, functions for SQL users, and a table function."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.tagexpr import parse_tag_expr
from ..model import Catalog
from .enrich import EnrichmentRun
from .planning import NextScorer
from .state import Query

_FORM = re.compile(r"^\s*ENRICH\s+(?P<table>\w+)\s+SATISFYING\s+(?P<expr>.+?)(?:\s+WHERE\s+(?P<where>.+?))?\s+BUDGET\s+(?P<budget>[\d.]+)(?:\s+EPOCHS\s+(?P<epochs>\d+))?\s*$", re.I | re.S)


def enrich_sql(spark: SparkSession, text: str, catalog: Catalog, table: NextScorer | None = None, calibration=None) -> DataFrame:
    """Run ``ENRICH <view> SATISFYING <tag expression> [WHERE <exact condition>] BUDGET <cost> [EPOCHS <n>]``.

    Gives the members of the last answer. The WHERE part filters the view before anything is scored.
    """
    m = _FORM.match(text)
    if not m:
        raise ValueError("expected ENRICH view SATISFYING expression [WHERE condition] BUDGET cost [EPOCHS n]")
    objects = spark.table(m["table"])
    if m["where"]:
        objects = objects.where(m["where"])
    e = parse_tag_expr(m["expr"])
    query = Query(e, catalog, calibration) if calibration else Query(e, catalog)
    last = None
    for last in EnrichmentRun(objects, query, float(m["budget"]), table).epochs(int(m["epochs"] or 1)):
        pass
    return last.members()


def register_functions(spark: SparkSession) -> None:
    """``entropy_bits(p)`` and ``relative_benefit(p, est, cost)`` as SQL functions: plain expressions, no Python."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION entropy_bits(p DOUBLE) RETURNS DOUBLE RETURN CASE WHEN p <= 0 OR p >= 1 THEN 0 ELSE -p * log2(p) - (1 - p) * log2(1 - p) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION relative_benefit(p DOUBLE, est DOUBLE, cost DOUBLE) RETURNS DOUBLE RETURN p * est / cost")


def register_item_function(spark: SparkSession) -> None:
    """``enrich_items(TABLE(t))``: for rows (object_id, p, cost) the benefit of raising p to certainty; a
    partition-local step, as a table function cannot see the global cutoff."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="object_id: bigint, benefit: double")
    class EnrichItems:
        def eval(self, row):
            yield row["object_id"], float(row["p"]) / float(row["cost"])

    spark.udtf.register("enrich_items", EnrichItems)


def expected_by(state: DataFrame, by: str, value: str | None = None) -> DataFrame:
    """Group-by over an uncertain answer: expected count, and expected sum of a column."""
    cols = [F.sum("match_p").alias("expected_count")]
    if value:
        cols.append(F.sum(F.col("match_p") * F.col(value)).alias("expected_sum"))
    return state.groupBy(by).agg(*cols)

"""Connected components of links between integer ids, by alternating star contractions.

Each round maps links to links, so lineage is cut by a stored table; what a node keeps is the least
label it has seen. No list of neighbours is gathered anywhere: all steps are aggregates and joins, in which the
edges of a hub are dealt to many tasks.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace, with_totals


def components(links: DataFrame, work: Workspace, label: str = "cc") -> DataFrame:
    """``node, component`` (least node of its component) for every node of ``links(a, b)``.

    Repeated links, self links and links in either direction are fine; no links give no rows.
    """
    edges = work.write(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), f"{label}-0")
    done, i = edges.isEmpty(), 0
    while not done:
        i += 1
        # large star: larger neighbours (and the node) point to the least of the neighbourhood
        both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = with_totals(both, ["u"], "v", [F.min("v").alias("m")], [F.least(F.min("m"), F.first("u")).alias("m")])
        large = large.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = work.write(large, f"{label}-{i}l")
        # small star: a node and its lesser neighbours point to the least of them
        low = large.groupBy("u").agg(F.min("v").alias("m")).select("u", F.col("m").alias("v"))
        near = with_totals(large, ["u"], "v", [F.min("v").alias("m")], [F.min("m").alias("m")])
        small = near.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").unionByName(low).distinct()
        nxt = work.write(small, f"{label}-{i}")
        # stars only: no node is both an end and a centre, and each has one centre
        done = nxt.join(nxt.select(F.col("v").alias("u")).distinct(), "u", "left_semi").isEmpty() and nxt.groupBy("u").count().where("count > 1").isEmpty()
        work.drop(f"{label}-{i - 1}", f"{label}-{i}l")
        edges = nxt
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())

"""Connected components of an edge table by alternating large-star and small-star steps.

Every step is a shuffle by node with the minimum taken map-side; each round is a
stored table, so lineage stays short.  A node with many neighbours is never
collected: its edges are joined to its minimum, and that join can be split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.llm.common import staged


def components(spark: SparkSession, edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): for every node of an edge the smallest node reachable; loops and repeats do no harm."""
    e = staged(spark, edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(), "edges")
    while not _stars(e):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        # a node that is its own minimum keeps its edge to it only through its larger neighbours
        down = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        m = down.groupBy("u").agg(F.min("v").alias("m"))
        small = down.join(m, "u").select(F.col("v").alias("x"), "m").where("x <> m").unionByName(m.select(F.col("u").alias("x"), "m"))
        e = staged(spark, small.select(F.greatest("x", "m").alias("u"), F.least("x", "m").alias("v")).distinct(), "edges")
    return e.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def _stars(e: DataFrame) -> bool:
    """Whether every larger end has one edge and is no other edge's smaller end: then the smaller ends are the components."""
    ends = e.select(F.col("u").alias("x"), F.lit(1).alias("up"), F.lit(0).alias("down")).unionByName(e.select(F.col("v").alias("x"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    bad = ends.groupBy("x").agg(F.sum("up").alias("up"), F.max("down").alias("down")).where("up > 1 or (up = 1 and down = 1)")
    return bad.agg(F.count(F.lit(1))).first()[0] == 0

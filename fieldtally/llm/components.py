"""Connected components over an edge table, by alternating large and small stars.

Each round rewires every node's neighbours to the smallest node it knows; rounds end when
no edge changes.  Edges stay distributed throughout and each round's edges are written to
the shared folder, so lineage stays short and a lost executor costs one round at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import scratch


def _large(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    out = down.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return out.unionByName(least.select("u", F.col("m").alias("v")))


def components(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """edges (u, v) of longs -> (node, component): the smallest node reachable, for every node with an edge to another."""
    now = scratch(spark, edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    mark = None
    while True:
        state = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if (state["n"], state["h"]) == mark or not state["n"]:
            return now.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("component"))
        mark = (state["n"], state["h"])
        now = scratch(spark, _small(_large(now).where("u <> v").distinct()).where("u <> v").distinct(), "edges")

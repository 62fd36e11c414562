"""Connected components of an edge table, by rounds of large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hand_over, release


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """Hang neighbours on the least one. ``edges``: distinct (u, v) with u > v."""
    if large:
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        out = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        least = edges.groupBy("u").agg(F.min("v").alias("m"))
        hung = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        out = hung.union(least.select("u", F.col("m").alias("v")))
    return out.where("u > v").distinct()


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(u, v) pairs of longs -> (node, root): the least node reachable. Nodes without an edge are left out."""
    pairs = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u > v").distinct()
    pairs = hand_over(pairs, "edges")
    before = None
    for _ in range(rounds):
        former, pairs = pairs, hand_over(_stars(_stars(pairs, True), False), "stars")
        release(former)
        sign = pairs.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if (sign["n"], sign["h"]) == before:
            roots = pairs.select(F.col("u").alias("node"), F.col("v").alias("root"))
            return roots.union(roots.select(F.col("root").alias("node"), "root").distinct())
        before = (sign["n"], sign["h"])
    raise RuntimeError("components did not settle")

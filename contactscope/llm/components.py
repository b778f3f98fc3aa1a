"""Connected components of an edge table by alternating large-star and small-star steps, each written to the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from contactscope.llm.common import stored


def _least_neighbour(edges: DataFrame) -> DataFrame:
    return edges.groupBy("u").agg(F.min("v").alias("m"))


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = _least_neighbour(both).select("u", F.least("u", "m").alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    joined = down.join(_least_neighbour(down), "u")
    own = joined.select("u", F.col("m").alias("v"))
    others = joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return own.unionByName(others).distinct()


def _settled(edges: DataFrame) -> bool:
    """True if every u has one v and no v has one of its own: stars that touch no other."""
    both = edges.select(F.col("u").alias("x"), F.lit(1).alias("out"), F.lit(0).alias("into")).unionByName(edges.select(F.col("v").alias("x"), F.lit(0).alias("out"), F.lit(1).alias("into")))
    per = both.groupBy("x").agg(F.sum("out").alias("out"), F.max("into").alias("into"))
    return per.where((F.col("out") > 1) | ((F.col("out") > 0) & (F.col("into") > 0))).isEmpty()


def stars(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Edges (u, v) of longs, a written table, to rows (u, v): v is the least vertex of u's component; roots have no row."""
    most = 2 * edges.count()
    now = stored(_small_star(edges.where("u <> v")), "edges", most)
    for _ in range(max_rounds):
        if _settled(now):
            return now
        now = stored(_small_star(_large_star(now)), "edges", most)
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")

"""Test tracks derived from the given tables by plain arithmetic (FIXTURES.md)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from contactscope.sources.readers import micros, read_table

DAY_US = 86_400_000_000


def venue_fixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event is a short visit of its user to one of 25 venues; a track is a user's day."""
    return visits_of(read_table(spark, sf_dir, "events"))


def visits_of(e: DataFrame) -> DataFrame:
    """The fixes of an events table, batch or streaming."""
    v = F.get_json_object("props", "$.k").cast("int") % 25
    # the place is parsed once a visit: beside the explode it would be once a fix
    visits = e.select("event_id", "user_id", micros(F.col("ts")).alias("t0"), v.alias("v")).select("*", F.explode(F.sequence(F.lit(0), (3 + F.col("event_id") % 31).cast("int"))).alias("i"))
    day = ((F.col("t0") - F.pmod("t0", F.lit(DAY_US))) / F.lit(DAY_US)).cast("long") - 19723
    return visits.select(
        (F.col("user_id") * 100000 + day).alias("track_id"),
        (F.col("event_id") * 64 + F.col("i")).alias("fix_id"),
        (F.col("t0") + F.col("i") * 30_000_000).alias("t_us"),
        (500.0 * (F.col("v") % 5) + (F.col("user_id") * 37 % 41 - 20) + 3 * (F.col("i") % 5)).alias("x"),
        (500.0 * F.floor(F.col("v") / 5) + (F.col("user_id") * 53 % 41 - 20) + 2 * (F.col("i") % 7)).alias("y"),
        F.col("user_id").alias("owner_id"),
    )


def venue_fixes_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As venue_fixes, a track being all of a user's days."""
    return venue_fixes(spark, sf_dir).withColumn("track_id", F.col("owner_id"))


def geo_fixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """venue_fixes as longitude and latitude, by a linear map to a place in the northern temperate zone."""
    return venue_fixes(spark, sf_dir).withColumns({"x": 116.0 + F.col("x") / 80000.0, "y": 39.0 + F.col("y") / 111000.0})


def scale_copies(fixes: DataFrame, copies: int, dx: float = 7.0, dy: float = -5.0, dt_us: int = 20_000_000) -> DataFrame:
    """Fixes repeated with offsets; copy j has track ids from j * 10^9 on. A map-side explode, no join."""
    j = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(copies - 1).cast("long"))).alias("copy")
    rows = fixes.select("*", j)
    return rows.withColumns({"track_id": F.col("track_id") + F.col("copy") * 1_000_000_000, "x": F.col("x") + F.col("copy") * dx, "y": F.col("y") + F.col("copy") * dy, "t_us": F.col("t_us") + F.col("copy") * dt_us})


def downsample(fixes: DataFrame, every: int = 3, keep: int = 1, jitter: bool = True) -> DataFrame:
    """Every third fix of each track as a labelled query track: case_id is disjoint from track ids, true_track_id names the
    source, places are moved by up to 5 m times a factor that grows with track_id mod 4."""
    rank = F.row_number().over(Window.partitionBy("track_id").orderBy("t_us", "fix_id")) - 1
    rows = fixes.withColumn("r", rank).where(F.col("r") % every == keep)
    grow = 1 + 6 * (F.col("track_id") % 4)
    x = F.col("x") + (F.col("fix_id") * 7 % 11 - 5) * grow if jitter else F.col("x")
    y = F.col("y") + (F.col("fix_id") * 3 % 11 - 5) * grow if jitter else F.col("y")
    return rows.select((-F.col("track_id") - 1).alias("track_id"), "fix_id", "t_us", x.cast("double").alias("x"), y.cast("double").alias("y"), F.col("track_id").alias("true_track_id"))


def case_fixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return venue_fixes(spark, sf_dir).where("owner_id % 10 = 0")


def labelled_cases(spark: SparkSession, sf_dir: str) -> DataFrame:
    return downsample(case_fixes(spark, sf_dir))


def query_fraction(cases: DataFrame, percent: int, id_col: str = "track_id") -> DataFrame:
    """A deterministic share of the query tracks."""
    return cases.where(F.pmod(F.abs(F.col(id_col)), F.lit(10)) * 10 < percent)


def shipment_fixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supplier tracks on a coarse calendar; rows equal in all columns are interchangeable."""
    li = read_table(spark, sf_dir, "lineitem")
    order = [F.col(c) for c in li.columns]
    rows = li.withColumn("fix_id", F.row_number().over(Window.partitionBy("l_suppkey").orderBy(*order)).cast("long"))
    return rows.select(F.col("l_suppkey").alias("track_id"), "fix_id", micros(F.col("l_shipdate")).alias("t_us"), (100.0 * (F.col("l_partkey") % 40)).alias("x"), (100.0 * (F.floor(F.col("l_partkey") / 40) % 40)).alias("y"))


def vector_fixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first two elements of each vector as a place, its label as a track."""
    e = read_table(spark, sf_dir, "embeddings")
    return e.select(F.col("label").cast("long").alias("track_id"), F.col("vec_id").alias("fix_id"), (F.col("vec_id") * 1_000_000).alias("t_us"), (F.col("embedding")[0].cast("double") * 100).alias("x"), (F.col("embedding")[1].cast("double") * 100).alias("y"))

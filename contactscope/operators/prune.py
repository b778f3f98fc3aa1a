"""Lossless bounds on a pair's rate. All compare products with thresholds (no division) and lean by EPS towards keeping.

Inputs: hits (case_id, seg_no, track_id, weight): segments whose extended box the track meets. rates: hits with seg_rate,
segments without any partner in reach counting as rate 0."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from contactscope.operators.exposure import segment_sums
from contactscope.schema import EPS

PAIR = ["case_id", "track_id"]


def prune_weight(hits: DataFrame, theta: float) -> DataFrame:
    """Pairs that may still pass by the weights of the segments met (first bound). hits must be distinct segments."""
    return hits.groupBy(*PAIR).agg(F.sum("weight").alias("met")).where(F.col("met") >= theta - EPS)


def slack_single(theta: float) -> Column:
    """Second bound, a segment alone: negative slack kills the pair."""
    return F.col("weight") * F.col("seg_rate") - (theta - 1 + F.col("weight"))


def _met() -> Column:
    return F.sum("weight").over(Window.partitionBy(*PAIR))


def slack_hit(theta: float) -> Column:
    """Third bound: the other segments met may count fully."""
    return F.col("weight") * F.col("seg_rate") - (theta - (_met() - F.col("weight")))


def slack_running(theta: float, order: str = "time") -> Column:
    """Fourth bound: earlier segments count with their rates, later ones fully."""
    by = [F.col("seg_no")] if order == "time" else [F.col("weight").desc(), F.col("seg_no")]
    w = Window.partitionBy(*PAIR).orderBy(*by)
    before = F.coalesce(F.sum(F.col("weight") * F.col("seg_rate")).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    after = F.coalesce(F.sum("weight").over(w.rowsBetween(1, Window.unboundedFollowing)), F.lit(0.0))
    return F.col("weight") * F.col("seg_rate") - (theta - before - after)


def mandatory(weights: DataFrame, theta: float) -> DataFrame:
    """Case segments without which no pair can pass: weight above 1 - theta."""
    return weights.where(F.col("weight") > 1 - theta + EPS).select("case_id", "seg_no")


def prune_mandatory(pairs: DataFrame, hits: DataFrame, weights: DataFrame, theta: float) -> DataFrame:
    """Pairs that meet every mandatory segment of their case."""
    need = mandatory(weights, theta)
    wanted = need.groupBy("case_id").agg(F.count("*").alias("need"))
    got = hits.join(need, ["case_id", "seg_no"], "left_semi").groupBy(*PAIR).agg(F.count("*").alias("got"))
    kept = pairs.join(wanted, "case_id", "left").join(got, PAIR, "left")
    return kept.where(F.coalesce("got", F.lit(0)) >= F.coalesce("need", F.lit(0))).select(*pairs.columns)


def dropped(rates: DataFrame, theta: float, bound: str, order: str = "time") -> DataFrame:
    """Distinct pairs that a bound (single, hit or running) drops."""
    slack = {"single": slack_single(theta), "hit": slack_hit(theta), "running": slack_running(theta, order)}[bound]
    return rates.withColumn("slack", slack).where(F.col("slack") < -EPS).select(*PAIR).distinct()


def fused(rates: DataFrame, theta: float) -> DataFrame:
    """Sum and second bound in one aggregation: case_id, track_id, rate, without the pairs that the bound drops."""
    out = rates.groupBy(*PAIR).agg(F.sum(F.col("weight") * F.col("seg_rate")).alias("rate"), F.min(slack_single(theta)).alias("slack"))
    return out.where(F.col("slack") >= -EPS).select(*PAIR, "rate")


def prune_audits(rates: DataFrame, thetas: list[float]) -> DataFrame:
    """theta, case_id, track_id, rate and for each of the four bounds whether it drops the pair, for several theta from one pass: a slack falls by just as much as theta rises."""
    marked = rates.withColumns({"s2": slack_single(0.0), "s3": slack_hit(0.0), "s4": slack_running(0.0)})
    pairs = marked.groupBy(*PAIR).agg(F.sum(F.col("weight") * F.col("seg_rate")).alias("rate"), F.sum("weight").alias("met"), *(F.min(s).alias(s) for s in ("s2", "s3", "s4")))
    each = pairs.withColumn("theta", F.explode(F.array(*(F.lit(float(t)) for t in thetas))))
    drops = {"by_weight": "met", "by_single": "s2", "by_hit": "s3", "by_running": "s4"}
    return each.select("theta", *PAIR, "rate", *((F.col(c) - F.col("theta") < -EPS).alias(name) for name, c in drops.items()))


def prune_audit(rates: DataFrame, theta: float) -> DataFrame:
    """case_id, track_id, rate and for each of the four bounds whether it drops the pair."""
    return prune_audits(rates, [theta]).drop("theta")


def cover_bound(correlation: DataFrame, weights: DataFrame) -> DataFrame:
    """case_id, track_id, low, high: bounds of the rate from the mere existence of partners in reach. A fix with a partner correlates
    by at most 1 and, at the very edge of the reach, by at least 1/e."""
    covered = segment_sums(correlation, weights, k=F.count("*"))
    share = covered.groupBy(*PAIR).agg(F.sum(F.col("weight") * F.col("k") / F.col("n")).alias("high"))
    return share.select(*PAIR, (F.col("high") * F.exp(F.lit(-1.0))).alias("low"), "high")

"""Accuracy and cost measures, and the experiment workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from contactscope.operators import exposure
from contactscope.operators.leafindex import build_leaves, leaf_fetch, placed
from contactscope.plans.query import direct_rates, prepare_cases, rate_grid
from contactscope.schema import Extent, Params
from contactscope.sources.tracks import query_fraction, scale_copies
from contactscope.workspace import stored


def labels_of(cases: DataFrame) -> DataFrame:
    """case_id, true_track_id of labelled query tracks."""
    return cases.groupBy(F.col("track_id").alias("case_id")).agg(F.first("true_track_id").alias("true_track_id"))


def quality(answers: DataFrame, labels: DataFrame, by: list[str] | None = None) -> DataFrame:
    """queries, pairs, accuracy (correct pairs of all pairs), recall (queries with an answer), true_hit (queries that found their source).

    answers may hold several runs told apart by `by`; a run without any answer has no row."""
    by = by or []
    per_case = answers.join(labels, "case_id").groupBy(*by, "case_id").agg(F.count("*").alias("pairs"), F.count_if(F.col("track_id") == F.col("true_track_id")).alias("right"))
    n = labels.agg(F.count("*").alias("queries"))
    sums = per_case.groupBy(*by).agg(F.sum("pairs").alias("pairs"), F.sum("right").alias("right"), F.count("*").alias("answered"), F.count_if(F.col("right") > 0).alias("hit"))
    out = sums.join(F.broadcast(n))
    return out.select(*by, "queries", "pairs", (F.col("right") / F.col("pairs")).alias("accuracy"), (F.col("answered") / F.col("queries")).alias("recall"), (F.col("hit") / F.col("queries")).alias("true_hit"))


def sweep(cases: DataFrame, fixes: DataFrame, param: str, values: list[float], p: Params = Params()) -> DataFrame:
    """param, value, queries, pairs, accuracy, recall for values of lam, theta, theta_d or theta_t, all from one pass."""
    if param == "theta":
        rates = rate_grid(cases, fixes, [(p.lam, p.theta_d, p.theta_t)], p)
        runs = rates.select("case_id", "track_id", "rate", F.explode(F.array(*(F.lit(float(v)) for v in values))).alias("value")).where("rate > value")
    else:
        point = lambda v: tuple(v if k == param else getattr(p, k) for k in ("lam", "theta_d", "theta_t"))
        runs = rate_grid(cases, fixes, [point(float(v)) for v in values], p).where(F.col("rate") > p.theta).withColumn("value", F.col(param))
    out = quality(runs, labels_of(cases), ["value"])
    return out.select(F.lit(param).alias("param"), "value", "queries", "pairs", F.round("accuracy", 6).alias("accuracy"), F.round("recall", 6).alias("recall"))


def sweep_query_size(cases: DataFrame, fixes: DataFrame, percents: list[int], p: Params = Params()) -> DataFrame:
    """value (percent), queries, pairs, accuracy, recall for shares of the query set."""
    answers = stored(exposure.above(exposure.track_rate(direct_rates(cases, fixes, p)), p), "answers")
    labels, out = stored(labels_of(cases), "labels"), None
    for v in percents:
        some = query_fraction(labels, v, "case_id")
        one = quality(answers, some).withColumn("value", F.lit(float(v)))
        out = one if out is None else out.unionByName(one)
    return out.select(F.lit("query_size").alias("param"), "value", "queries", "pairs", F.round("accuracy", 6).alias("accuracy"), F.round("recall", 6).alias("recall"))


def sweep_resolution(case_fixes: DataFrame, store: DataFrame, resolutions: list[int | None], p: Params = Params(), extent: Extent = Extent()) -> DataFrame:
    """resolution (-1: a leaf per segment), accesses (leaves), largest (segments in a leaf), fetched and distinct_fetched segments."""
    cases, out = prepare_cases(case_fixes, p), None
    for r in resolutions:
        leaves = build_leaves(placed(cases.segments, r, extent))
        got = leaf_fetch(leaves, store, p)
        load = leaves.agg(F.count("*").alias("accesses"), F.max("n").alias("largest"))
        fetched = got.agg(F.count("*").alias("fetched"), F.count_distinct("track_id", "store_seg").alias("distinct_fetched"))
        one = load.join(F.broadcast(fetched)).withColumn("resolution", F.lit(-1 if r is None else r))
        out = one if out is None else out.unionByName(one)
    return out


def sweep_data_size(cases: DataFrame, fixes: DataFrame, copies: list[int], p: Params = Params()) -> DataFrame:
    """copies, fixes, tracks, pairs (answers) and answered (cases with an answer) on the data repeated with offsets."""
    cases, out = stored(cases, "cases"), None
    for c in copies:
        data = scale_copies(fixes, c)
        answers = exposure.above(exposure.track_rate(direct_rates(cases, data, p)), p).agg(F.count("*").alias("pairs"), F.count_distinct("case_id").alias("answered"))
        size = data.agg(F.count("*").alias("fixes"), F.count_distinct("track_id").alias("tracks"))
        one = size.join(F.broadcast(answers)).withColumn("copies", F.lit(c))
        out = one if out is None else out.unionByName(one)
    return out


def dataset_stats(fixes: DataFrame, segmented: DataFrame) -> DataFrame:
    """fixes, tracks, segments, fixes per track."""
    per_track = segmented.groupBy("track_id").agg(F.count("*").alias("n"), F.count_distinct("seg_no").alias("s"))
    return per_track.agg(F.sum("n").alias("fixes"), F.count("*").alias("tracks"), F.sum("s").alias("segments"), F.round(F.avg("n"), 6).alias("fixes_per_track"))


def calibrate(cases: DataFrame, fixes: DataFrame, grid: list[tuple[float, float, float]], thetas: list[float], p: Params = Params()) -> DataFrame:
    """Accuracy and recall for every (lam, theta_d, theta_t) and theta; `choose` picks one."""
    rates = rate_grid(cases, fixes, grid, p)
    runs = rates.select("*", F.explode(F.array(*(F.lit(float(t)) for t in thetas))).alias("theta")).where("rate > theta")
    return quality(runs, labels_of(cases), ["lam", "theta_d", "theta_t", "theta"])


def choose(grid: DataFrame) -> DataFrame:
    """The point of a calibrated grid (lam, theta_d, theta_t, theta, accuracy, recall) with the best product of accuracy and recall; ties go to the smallest values."""
    score = F.round("accuracy", 6) * F.round("recall", 6)
    return grid.orderBy(score.desc(), "lam", "theta_d", "theta_t", "theta").limit(1)

"""What a query or join would do, in counts: an explain view beside Spark's own."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from contactscope.operators.candidates import segment_candidates
from contactscope.operators.leafindex import build_leaves, placed
from contactscope.operators.prune import mandatory, prune_weight
from contactscope.plans.query import hits_of, prepare_cases, relevant
from contactscope.schema import Params
from contactscope.workspace import stored


def plan_report(store: DataFrame, case_fixes: DataFrame, p: Params = Params(), leaf_resolution: int = 3) -> dict:
    """Counts for the choice of a method: case segments (store accesses of the query), leaves (those of the join), segments without which no pair can
    pass, candidate segment pairs and pairs, pairs that the weight bound keeps, and whether each small side would be broadcast."""
    cases = prepare_cases(case_fixes, p)
    part = relevant(store, cases, p)
    found = stored(segment_candidates(cases.segments, part, p, p.broadcast_rows), "report")
    hits = hits_of(found, cases.weights)
    segments, fixes = cases.segments.count(), cases.fixes.count()
    pairs = found.select("case_id", "track_id").distinct().count()
    wanted = found.select("track_id", "store_seg").distinct().count()
    return {
        "case_segments": segments,
        "leaves": build_leaves(placed(cases.segments, leaf_resolution, p.extent)).count(),
        "mandatory_segments": mandatory(cases.weights, p.theta).count(),
        "candidate_segment_pairs": found.count(),
        "candidate_pairs": pairs,
        "pairs_kept_by_weight": prune_weight(hits, p.theta).count(),
        "stored_segments_fetched": wanted,
        "case_cells": 27 * fixes,
        "broadcast_segments": wanted <= p.broadcast_rows,
        "broadcast_boxes": segments <= p.broadcast_rows,
    }


def uses(df: DataFrame, operator: str) -> int:
    """How often an operator's name stands in the physical plan."""
    return df._jdf.queryExecution().executedPlan().toString().count(operator)


def input_files(df: DataFrame, column: str = "bin") -> DataFrame:
    """Files and rows that a scan still reads after pruning, by partition."""
    rows = df.select(column, F.input_file_name().alias("file"))
    return rows.groupBy(column, "file").agg(F.count("*").alias("rows")).groupBy(column).agg(F.sum("rows").alias("rows"), F.count("*").alias("files"))


class Meter:
    """What the work inside a with block shuffled, read, spilled to disk and held at most, over all executors: from Spark's own status store."""

    def __init__(self, spark: SparkSession):
        self.spark, self.work = spark, {}

    def _totals(self) -> dict[str, int]:
        out = {"shuffle_read": 0, "shuffle_written": 0, "input": 0, "spilled": 0, "peak_heap": 0, "peak_execution": 0}
        sc = self.spark.sparkContext._jsc.sc()
        executors = sc.statusStore().executorList(False)
        for i in range(executors.size()):
            e = executors.apply(i)
            out["shuffle_read"] += e.totalShuffleRead()
            out["shuffle_written"] += e.totalShuffleWrite()
            out["input"] += e.totalInputBytes()
            peak = e.peakMemoryMetrics()
            if peak.isDefined():
                out["peak_heap"] = max(out["peak_heap"], peak.get().getMetricValue("JVMHeapMemory"))
                out["peak_execution"] = max(out["peak_execution"], peak.get().getMetricValue("OnHeapExecutionMemory"))
        jvm, gateway = self.spark._jvm, self.spark.sparkContext._gateway
        stages = sc.statusStore().stageList(None, False, False, gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
        for i in range(stages.size()):
            out["spilled"] += stages.apply(i).diskBytesSpilled()
        return out

    def __enter__(self) -> Meter:
        self._before = self._totals()
        return self

    def __exit__(self, *_) -> None:
        after = self._totals()
        self.work = {k: v if k.startswith("peak") else max(0, v - self._before[k]) for k, v in after.items()}

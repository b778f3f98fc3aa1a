"""Reading tables and fixes, and mapping any table to fixes."""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from contactscope.functions.udfs import register_sql_functions
from contactscope.schema import FIX

_L, _I, _D, _S, _TS = T.LongType(), T.IntegerType(), T.DoubleType(), T.StringType(), T.TimestampNTZType()
SCHEMAS = {
    "events": {"event_id": _L, "ts": _TS, "user_id": _L, "event_type": _S, "value": _D, "props": _S},
    "lineitem": {"l_orderkey": _L, "l_partkey": _L, "l_suppkey": _L, "l_linenumber": _I, "l_quantity": _D, "l_extendedprice": _D, "l_discount": _D, "l_tax": _D, "l_returnflag": _S, "l_linestatus": _S, "l_shipdate": _TS},
    "orders": {"o_orderkey": _L, "o_custkey": _L, "o_orderstatus": _S, "o_totalprice": _D, "o_orderdate": _TS, "o_orderpriority": _S},
    "customer": {"c_custkey": _L, "c_name": _S, "c_nationkey": _I, "c_acctbal": _D, "c_mktsegment": _S},
    "nation": {"n_nationkey": _I, "n_name": _S, "n_regionkey": _I},
    "region": {"r_regionkey": _I, "r_name": _S},
    "embeddings": {"vec_id": _L, "embedding": T.ArrayType(T.FloatType()), "label": _I},
}


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, with its fixed schema where one is known (no footer inference)."""
    reader = spark.read
    if name in SCHEMAS:
        reader = reader.schema(T.StructType([T.StructField(k, v) for k, v in SCHEMAS[name].items()]))
    return reader.parquet(f"{sf_dir}/{name}.parquet")


def micros(ts: Column) -> Column:
    """Microseconds since 1970 of a zone-free timestamp, whatever the session's zone."""
    return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), ts)


@dataclass(frozen=True)
class TrackMapping:
    """Which expressions of a table are track, fix, time (timestamp or microseconds) and place; `keep` adds columns."""

    track_id: str
    fix_id: str
    time: str
    x: str
    y: str
    time_is_micros: bool = False
    keep: Mapping[str, str] = field(default_factory=dict)


def to_fixes(df: DataFrame, m: TrackMapping) -> DataFrame:
    t = F.expr(m.time).cast("long") if m.time_is_micros else micros(F.expr(m.time).cast("timestamp_ntz"))
    return df.select(F.expr(m.track_id).cast("long").alias("track_id"), F.expr(m.fix_id).cast("long").alias("fix_id"), t.alias("t_us"), F.expr(m.x).cast("double").alias("x"), F.expr(m.y).cast("double").alias("y"), *(F.expr(v).alias(k) for k, v in m.keep.items()))


def read_fixes(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Fixes of the fixed schema from Parquet, ORC, CSV (with header) or JSON files."""
    if fmt not in ("parquet", "orc", "csv", "json"):
        raise ValueError("fmt is parquet, orc, csv or json")
    reader = spark.read.schema(FIX)
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.format(fmt).load(path)


def register_store(store: DataFrame, name: str = "segments") -> None:
    """The store as a view, and the SQL functions that Catalyst inlines."""
    store.createOrReplaceTempView(name)
    register_sql_functions(store.sparkSession)

"""Working tables in the folder that driver and executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def work_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; where that is unset, one of our own in local mode, else the warehouse."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master.split("[")[0] == "local":
            base = tempfile.mkdtemp(prefix="contactscope-")
            atexit.register(shutil.rmtree, base, True)
        else:
            base = spark.conf.get("spark.sql.warehouse.dir")
        spark.conf.set("spark.checkpoint.dir", base)
    return base.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{work_dir(spark)}/work/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """df written as Parquet and read back: lineage is cut, its size is known to the planner."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Bytes of rows that a broadcast may have: the driver holds them several times over (collected, as a relation, as blocks).
BROADCAST_BYTES = 16 << 20


def fits_broadcast(df: DataFrame, rows: int, most_rows: int) -> bool:
    """Whether that many rows of df's columns may be broadcast: at most most_rows, and BROADCAST_BYTES at 8 bytes a column (32 for those without a fixed width) and 24 a row."""
    width = 24 + sum(32 if isinstance(f.dataType, (T.StringType, T.BinaryType, T.ArrayType, T.MapType, T.StructType)) else 8 for f in df.schema)
    return rows <= most_rows and rows * width <= BROADCAST_BYTES


def shuffled(df: DataFrame) -> DataFrame:
    """df with a hint that keeps it from being broadcast: Spark goes by the size of the files beneath, which says nothing about rows made by an explode or packed tightly."""
    return df.hint("merge")


def maybe_broadcast(df: DataFrame, most_rows: int) -> DataFrame:
    """df, which must be cheap to count, to be broadcast if it has at most most_rows rows and fits the driver, and shuffled otherwise."""
    return F.broadcast(df) if fits_broadcast(df, df.count(), most_rows) else shuffled(df)

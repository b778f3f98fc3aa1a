"""Shared helpers of the training-data operators: working tables, id-based filters, text pieces."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Most rows of an id list that is broadcast; longer lists are joined by shuffle.
MAX_BROADCAST_IDS = 500_000


def work_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share: the one in spark.checkpoint.dir, or one of our own where that is unset."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
            base = tempfile.mkdtemp(prefix="contactscope-")
            atexit.register(shutil.rmtree, base, True)
        else:
            base = spark.conf.get("spark.sql.warehouse.dir")
        spark.conf.set("spark.checkpoint.dir", base)
    return base


#: Rows in one file of a written table whose size is known.
FILE_ROWS = 500_000


def stored(df: DataFrame, name: str, rows: int | None = None, per_file: int = FILE_ROWS) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: lineage is cut and lost executors cost no rework. rows: an upper bound
    of df's rows where one is known; the table then has a file for each per_file of them, not for each shuffle partition: its rows are dealt
    anew, so that the work above keeps its own tasks."""
    spark = df.sparkSession
    if rows is not None:
        df = df.repartition(rows // per_file + 1)
    path = f"{work_dir(spark).rstrip('/')}/llm/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    table_ = spark.read.schema(df.schema).parquet(path)
    table_.stored_at = path
    return table_


def forget(*tables: DataFrame) -> None:
    """Delete tables that `stored` wrote and no later plan reads."""
    for t in tables:
        jvm = t.sparkSession._jvm
        path = jvm.org.apache.hadoop.fs.Path(t.stored_at)
        path.getFileSystem(t.sparkSession._jsc.hadoopConfiguration()).delete(path, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bounded(df: DataFrame, most: int = MAX_BROADCAST_IDS) -> DataFrame:
    """df, a written table of narrow rows, to be broadcast if it has at most `most` rows; beyond, joins shuffle it."""
    return F.broadcast(df) if df.count() <= most else df


def without_ids(docs: DataFrame, dropped: DataFrame, key: str = "doc_id", rows: int | None = None) -> DataFrame:
    """Rows of docs whose key isn't in dropped (the same name). The list is broadcast only after its
    length was counted and found small; otherwise it is a shuffled anti join. Rows with a null key stay. rows: most rows of dropped, if known."""
    dropped = stored(dropped.select(key).where(F.col(key).isNotNull()), "dropped", rows)
    return docs.join(bounded(dropped), key, "left_anti").select(*docs.columns)


BLANK = re.compile(rb"[ \n\t\r\x0b\x0c]")


def pieces(data: bytes, size: int = 1 << 20) -> Iterator[bytes]:
    """data in pieces of about size bytes, cut behind white space; a longer run without any stays whole."""
    at = 0
    while len(data) - at > size:
        cut = BLANK.search(data, at + size - 1)
        end = cut.end() if cut else len(data)
        yield data[at:end]
        at = end
    yield data[at:] if at else data

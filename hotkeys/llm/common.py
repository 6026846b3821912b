"""Shared helpers of the training-data operators."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed value: the six ASCII white-space characters, space and \x09 to \x0D.
WHITE = " \t\n\x0b\f\r"
#: Fixed value: a run of them, as a Java and RE2 pattern.
WHITE_RUN = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_of(column: str = "text") -> Column:
    """The text column, null read as empty."""
    return F.coalesce(F.col(column).cast("string"), F.lit(""))


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Evaluate value once and hand it to body: a lambda variable is never inlined or recomputed."""
    return F.transform(F.array(value), body)[0]


def words_of(text: Column) -> Column:
    """Array of the maximal runs of characters other than ASCII white space."""
    return F.array_remove(F.split(text, WHITE_RUN), "")


def shared_folder(spark: SparkSession) -> str:
    """Folder that driver and executors share: the cluster's spark.checkpoint.dir.

    Only where it is unset is another one taken: a temporary folder in local mode, else a
    folder under the warehouse, which a cluster shares as well.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder
    if spark.sparkContext.master.startswith("local") and not spark.sparkContext.master.startswith("local-cluster"):
        folder = "file://" + tempfile.mkdtemp(prefix="hotkeys-shared-")
    else:
        folder = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_hotkeys_scratch"
    spark.conf.set("spark.checkpoint.dir", folder)
    return folder


_WRITTEN: list[str] = []


def written(spark: SparkSession, frame: DataFrame, name: str) -> DataFrame:
    """Cut the lineage of frame with a table in the shared folder; a lost executor can't lose it.

    The table stays until `clear`, since results are read from it when they are asked for.
    """
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    frame.write.parquet(path)
    _WRITTEN.append(path)
    return spark.read.schema(frame.schema).parquet(path)


def clear(spark: SparkSession) -> int:
    """Delete all tables that this driver has written, once their results are read; how many there were."""
    jvm = spark.sparkContext._jvm
    gone = 0
    while _WRITTEN:
        path = jvm.org.apache.hadoop.fs.Path(_WRITTEN.pop())
        gone += path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    return gone


def sized_broadcast(frame: DataFrame, rows: int, most_rows: int) -> DataFrame:
    """Hint a broadcast where the counted rows are few, else leave the join to the optimizer."""
    return F.broadcast(frame) if rows <= most_rows else frame

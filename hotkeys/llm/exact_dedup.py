"""Exact dedup: an extendible-hash index of normalised texts on shared files, in DataFrame form.

A directory maps the first bits of a text's hash to a bucket. It doubles as long as some bucket holds more
than BUCKET_KEYS hashes: only the overfull buckets are split, so a crowded prefix is cut by more bits than a
sparse one and several cells of the directory share one bucket. Every row is routed through the
directory to its bucket, and the owner task of a bucket sorts its rows by hash and text: rows of one hash
chain behind one another, and their whole texts are compared byte by byte. What it finds (bucket, depth, hash,
place in the chain, digest, the row that stays, the group's size) is the index on shared files; the answers are read from it.

A hash with HOT_ROWS rows or more would burden its owner, and no split can part it. The rows of such hashes
are combined into their distinct texts before any shuffle and then looked up in these by whole text.

The directory travels to every task, so it stops at 2**MAX_DEPTH cells; buckets beyond hold more keys, which are
sorted with spilling all the same. Defined results: null text counts as empty; empty texts are copies of one another; a null id sorts
after all others; repeated rows (id and text equal) are copies, of which `op6` marks every one
with the smallest id as kept and `kept_rows` keeps one; columns of the input are not touched.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from hotkeys.llm.common import WHITE_RUN, table, text_of, written

MAX_DEPTH = 20
BUCKET_KEYS = 500
HOT_ROWS = 1_000
#: Bytes of the hot hashes' texts that may travel to every task.
MOST_BROADCAST_BYTES = 8_000_000


def normalised(text: Column) -> Column:
    return F.regexp_replace(text, WHITE_RUN, " ")


def cell_of(h64: Column, depth: int) -> Column:
    """The first bits of the hash, as a number."""
    return F.shiftrightunsigned(h64, 64 - depth).cast("int") if depth else F.lit(0)


def hash_counts(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """(h64, n): rows of each hash, written to the shared folder."""
    hashes = docs.select(F.xxhash64(normalised(text_of(text_col))).alias("h64"))
    return written(docs.sparkSession, hashes.groupBy("h64").agg(F.count("*").alias("n")), "hash-counts")


def depth_for(keys: int, capacity: int) -> int:
    """Bits of the directory: three more than even buckets need, so that uneven ones can be split."""
    return min(MAX_DEPTH, max(0, math.ceil(math.log2(max(1, keys) / capacity)) + 3))


def directory(counts: DataFrame, depth: int, capacity: int = BUCKET_KEYS) -> DataFrame:
    """(cell, depth, bucket) of all 2**depth cells: a bucket is the first cell of those that share it.

    A prefix of d bits is split if it holds more hashes than the capacity, so a cell's local depth is the
    number of its prefixes, the shorter first, that are overfull.
    """
    spark = counts.sparkSession
    held = counts.groupBy(cell_of(F.col("h64"), depth).alias("cell")).agg(F.count("*").alias("keys"))
    prefix = lambda cell, bits: F.expr(f"shiftright({cell}, {depth} - {bits})")
    levels = held.select("keys", "cell", F.explode(F.sequence(F.lit(0), F.lit(max(0, depth - 1)))).alias("bits")).select("bits", prefix("cell", "bits").alias("prefix"), "keys")
    overfull = levels.groupBy("bits", "prefix").agg(F.sum("keys").alias("keys")).filter(F.col("keys") > capacity).select("bits", "prefix")
    cells = spark.range(1 << depth).select(F.col("id").cast("int").alias("cell"))
    walked = cells.select("cell", F.explode(F.sequence(F.lit(0), F.lit(max(0, depth - 1)))).alias("bits")).select("cell", "bits", prefix("cell", "bits").alias("prefix"))
    split = walked.join(overfull, ["bits", "prefix"]).groupBy("cell").agg(F.count("*").alias("depth")) if depth else cells.withColumn("depth", F.lit(0)).limit(0)
    local = cells.join(split, "cell", "left").select("cell", F.coalesce("depth", F.lit(0)).cast("int").alias("depth"))
    first = F.expr(f"shiftleft(shiftright(cell, {depth} - depth), {depth} - depth)")
    return written(spark, local.select("cell", "depth", first.alias("bucket")), "exact-directory")


def _routed(rows: DataFrame, counts: DataFrame, capacity: int, cells: DataFrame | None = None, depth: int | None = None) -> DataFrame:
    """rows (with norm's hash h64) with bucket and depth of the directory; at most 2**MAX_DEPTH cells travel."""
    if cells is None:
        depth = depth_for(counts.count(), capacity)
        cells = directory(counts, depth, capacity)
    return rows.withColumn("cell", cell_of(F.col("h64"), depth)).join(F.broadcast(cells), "cell").drop("cell")


def _hot(counts: DataFrame) -> tuple[DataFrame, int]:
    """Hashes of HOT_ROWS rows and more: at most one for each HOT_ROWS rows."""
    hot = counts.filter(F.col("n") >= HOT_ROWS).select("h64")
    return hot, hot.count()


def _hot_classes(hot_rows: DataFrame) -> DataFrame:
    """A row for each distinct text of the hot hashes, copies combined before the shuffle."""
    classes = hot_rows.groupBy("h64", "bucket", "depth", "norm").agg(F.min("id").alias("keep_id"), F.count("*").alias("group_size"))
    chain = F.row_number().over(W.partitionBy("h64").orderBy("norm"))
    return written(hot_rows.sparkSession, classes.withColumn("chain", chain).withColumn("sha", F.unhex(F.sha2("norm", 256))), "exact-hot")


def _looked_up(hot_rows: DataFrame, classes: DataFrame) -> DataFrame:
    """Hot rows with their class, found by whole text, or by hash and digest where the texts are too many to travel."""
    size = classes.agg(F.coalesce(F.sum(F.octet_length("norm")), F.lit(0))).first()[0]
    known = classes.drop("bucket", "depth")
    if size <= MOST_BROADCAST_BYTES:
        return hot_rows.join(F.broadcast(known), ["h64", "norm"])
    return hot_rows.withColumn("sha", F.unhex(F.sha2("norm", 256))).join(known.drop("norm"), ["h64", "sha"])


INDEX = ["id", "bucket", "depth", "h64", "chain", "sha", "keep_id", "group_size"]


def build_index(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = BUCKET_KEYS, cells: DataFrame | None = None, depth: int | None = None) -> DataFrame:
    """The index on shared files, an entry for each row: its bucket, place in the chain, digest and group.

    cells and depth give a directory to use instead of the one that the hashes call for.
    """
    spark = docs.sparkSession
    counts = hash_counts(docs, text_col)
    hot, n_hot = _hot(counts)
    rows = docs.select(F.col(f"`{id_col}`").alias("id"), normalised(text_of(text_col)).alias("norm")).withColumn("h64", F.xxhash64("norm"))
    routed = _routed(rows, counts, capacity, cells, depth)
    cold = routed.join(F.broadcast(hot), "h64", "left_anti") if n_hot else routed
    same = W.partitionBy("bucket", "h64", "norm")
    owned = cold.repartition("bucket").select("id", "bucket", "depth", "h64", F.dense_rank().over(W.partitionBy("bucket", "h64").orderBy("norm")).alias("chain"), "norm", F.min("id").over(same).alias("keep_id"), F.count("*").over(same).alias("group_size"))
    index = owned.withColumn("sha", F.unhex(F.sha2("norm", 256))).select(*INDEX)
    if n_hot:
        hot_rows = routed.join(F.broadcast(hot), "h64", "left_semi")
        index = index.unionByName(_looked_up(hot_rows, _hot_classes(hot_rows)).select(*INDEX))
    return written(spark, index, "exact-index")


def classes_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row for each input row: id, h64, sha, keep_id, group_size, bucket, depth and chain position."""
    return build_index(docs, id_col, text_col)


def kept_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = BUCKET_KEYS) -> DataFrame:
    """One row of docs for each distinct normalised text, with the columns of docs."""
    counts = hash_counts(docs, text_col)
    hot, n_hot = _hot(counts)
    # the input's row stays apart from the columns that are added, whatever its names are
    norm = normalised(text_of(f"row.`{text_col}`"))
    rows = docs.select(F.struct("*").alias("row")).select("row", F.col(f"row.`{id_col}`").alias("id"), F.xxhash64(norm).alias("h64"))
    routed = _routed(rows, counts, capacity)
    cold = routed.join(F.broadcast(hot), "h64", "left_anti") if n_hot else routed
    first = F.row_number().over(W.partitionBy("bucket", "h64", "norm").orderBy(F.asc_nulls_last("id")))
    kept = cold.repartition("bucket").withColumn("norm", norm).withColumn("turn", first).filter("turn = 1").select("row")
    if n_hot:
        hot_rows = routed.join(F.broadcast(hot), "h64", "left_semi").withColumn("norm", norm)
        found = _looked_up(hot_rows, _hot_classes(hot_rows)).filter(F.col("id").eqNullSafe(F.col("keep_id")))
        # rows of one id and text: any one of them stands for the others
        kept = kept.unionByName(found.groupBy("h64", "sha").agg(F.first("row").alias("row")).select("row"))
    return kept.select(*[F.col(f"row.`{c}`") for c in docs.columns])


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = build_index(table(spark, sf_dir, "documents"))
    kept = F.col("id").eqNullSafe(F.col("keep_id"))
    return found.select(F.col("id").alias("doc_id"), "keep_id", "group_size", kept.alias("kept"), F.lower(F.hex("sha")).alias("text_sha256"))

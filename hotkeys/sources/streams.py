"""Element streams: DataFrames (e, w, ...) made from tables, files and generators."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hotkeys.frames import keep

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: What splits a text into words: runs of anything but letters and digits.
NOT_WORD = r"[^\p{L}\p{N}]+"
#: Ranks whose weights the Zipf generator tabulates; those behind it are drawn from the smooth tail.
HEAD_RANKS = 1_000_000


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_files(spark: SparkSession, path: str, kind: str, schema: str | T.StructType) -> DataFrame:
    """A user's csv, json, orc, parquet or text files with a given schema; nothing is inferred."""
    if kind not in ("csv", "json", "orc", "parquet", "text"):
        raise ValueError(f"no source of kind {kind}")
    return spark.read.schema(schema).format(kind).load(path)


def canonical(e: Column, data_type: T.DataType) -> Column:
    """The element as it is counted: -0.0 and 0.0 are one, and so are all NaN; maps and arrays are refused."""
    if isinstance(data_type, (T.MapType, T.ArrayType)):
        raise TypeError("explode maps and arrays: they are no elements")
    if isinstance(data_type, (T.DoubleType, T.FloatType)):
        return F.when(F.isnan(e), F.lit(float("nan")).cast(data_type)).when(e == 0, F.lit(0.0).cast(data_type)).otherwise(e)
    return e


def element_stream(df: DataFrame, e: Column | str, w: Column | str | None = None, order: list[str] | None = None) -> DataFrame:
    """(e, w) and the order columns; null elements are absent and not counted."""
    e = F.col(e) if isinstance(e, str) else e
    weight = F.lit(1).cast("long") if w is None else (F.col(w) if isinstance(w, str) else w).cast("long")
    out = df.select(e.alias("e"), weight.alias("w"), *(order or []))
    out = out.withColumn("e", canonical(F.col("e"), out.schema["e"].dataType))
    return out.filter(F.col("e").isNotNull())


def words(df: DataFrame, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """A row for each word of each text: (e, w) and the columns kept."""
    parts = F.explode(F.split(F.lower(F.trim(text)), NOT_WORD)).alias("e")
    return df.select(*(keep or []), parts).filter("e <> ''").withColumn("w", F.lit(1).cast("long"))


def word_list(text: str) -> Column:
    """The words of a text in order."""
    return F.array_remove(F.split(F.lower(F.trim(text)), NOT_WORD), "")


def documents_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return words(read(spark, sf_dir, "documents"))


def conversations_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return words(read(spark, sf_dir, "conversations"))


def documents_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return element_stream(read(spark, sf_dir, "documents"), F.explode(F.split("text", "\n")))


def page_hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    host = F.regexp_extract("url", "^[a-z]+://([^/?#]*)", 1)
    return element_stream(read(spark, sf_dir, "pages"), host)


def page_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    tags = F.regexp_extract_all("html", F.lit("<([a-zA-Z][a-zA-Z0-9]*)"), F.lit(1))
    return element_stream(read(spark, sf_dir, "pages"), F.explode(F.transform(tags, F.lower)))


def flows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five-field keys, as network flows have."""
    key = F.struct("l_suppkey", "l_partkey", "l_returnflag", "l_linestatus", "l_linenumber")
    return element_stream(read(spark, sf_dir, "lineitem"), key)


def zipf_stream(spark: SparkSession, n: int, u: int, a: float, seed: int = 42, partitions: int | None = None) -> DataFrame:
    """n draws of ranks 1..u with probabilities in proportion to rank**-a: (ord, e, w).

    A draw depends on its number and the seed only, whatever the partitions.
    """
    base = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    drawn = base.select(F.col("id").alias("ord"), (F.shiftrightunsigned(F.xxhash64("id", F.lit(seed)), 11) / F.lit(float(1 << 53))).alias("x"))

    def run(batches):
        ranks = _ranker(u, a)
        for batch in batches:
            rank = ranks(batch.column("x").to_numpy())
            yield pa.RecordBatch.from_arrays([batch.column("ord"), pa.array(rank), pa.array(np.ones(len(rank), np.int64))], ["ord", "e", "w"])

    return drawn.mapInArrow(run, "ord long, e long, w long")


def _ranker(u: int, a: float):
    """What gives the ranks of numbers drawn evenly from 0 to 1."""
    head = min(u, HEAD_RANKS)

    def smooth(lo: float, hi: float) -> float:
        return float(np.log(hi / lo)) if a == 1 else float((hi ** (1 - a) - lo ** (1 - a)) / (1 - a))

    sums = np.cumsum(np.arange(1, head + 1, dtype=np.float64) ** -a)
    tail = smooth(head + 0.5, u + 0.5) if u > head else 0.0

    def ranks(x: np.ndarray) -> np.ndarray:
        at = x * (sums[-1] + tail)
        rank = np.searchsorted(sums, at, side="right").astype(np.int64) + 1
        far = rank > head
        if far.any():
            if tail:
                rest = at[far] - sums[-1]
                reach = (head + 0.5) * np.exp(rest) if a == 1 else ((head + 0.5) ** (1 - a) + rest * (1 - a)) ** (1 / (1 - a))
                rank[far] = np.clip(np.rint(reach), head + 1, u).astype(np.int64)
            else:
                rank[far] = head
        return rank

    return ranks


def _xxhash64(ids: np.ndarray, last: int) -> np.ndarray:
    """Spark's xxhash64 of a long and an int that is not negative."""
    p1, p2, p3, p4, p5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    turned = lambda x, k: (x << np.uint64(k)) | (x >> np.uint64(64 - k))

    def ended(h: np.ndarray) -> np.ndarray:
        h = (h ^ (h >> np.uint64(33))) * p2
        h = (h ^ (h >> np.uint64(29))) * p3
        return h ^ (h >> np.uint64(32))

    h = np.full(len(ids), 42 + int(p5) + 8, np.uint64) ^ turned(ids.astype(np.uint64) * p2, 31) * p1
    h = ended(turned(h, 27) * p1 + p4)
    h = (h + p5 + np.uint64(4)) ^ np.uint64(last * int(p1) % (1 << 64))
    return ended(turned(h, 23) * p2 + p3)


def zipf_ranks(n: int, u: int, a: float, size: int, seed: int = 42) -> Iterator[np.ndarray]:
    """The same draws in order without Spark, in arrays of size ranks."""
    ranks = _ranker(u, a)
    for at in range(0, n, size):
        drawn = _xxhash64(np.arange(at, min(at + size, n), dtype=np.int64), seed) >> np.uint64(11)
        yield ranks(drawn.astype(np.float64) / float(1 << 53))


def sampled_by(stream: DataFrame, by: str, shares: dict, seed: int = 42) -> DataFrame:
    """Arrivals sampled by a column's values, each with its own share."""
    return stream.sampleBy(by, shares, seed)


def prefix(stream: DataFrame, order: str, k: int) -> DataFrame:
    """The first k arrivals of a stream whose order column counts from 0 without gaps."""
    return stream.filter(F.col(order) < k)


def reordered(stream: DataFrame, how: str) -> DataFrame:
    """The same arrivals in an adverse order, as a new ord column that starts at 0.

    how: ascending or descending by count, round_robin, tail_first (rare elements, then the rest).
    """
    from pyspark.sql import Window as W

    counts = stream.groupBy("e").agg(F.count("*").alias("f"))
    turn = F.row_number().over(W.partitionBy("e").orderBy("ord"))
    both = stream.join(counts, "e").withColumn("turn", turn)
    keys = {"ascending": ["f", "e", "turn"], "descending": [F.desc("f"), "e", "turn"], "round_robin": ["turn", "e"], "tail_first": [F.col("f") > 1, "turn", "e"]}[how]
    return numbered(both, keys).select("ord", "e", "w")


def numbered(rows: DataFrame, keys: list) -> DataFrame:
    """rows with ord, from 0 in the order of the keys: sorted in ranges, each of which starts where those before it end."""
    placed = keep(rows.repartitionByRange(*keys).sortWithinPartitions(*keys).select(*rows.columns, F.spark_partition_id().alias("part"), F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("inside")))
    sizes = {r["part"]: r["n"] for r in placed.groupBy("part").agg(F.count("*").alias("n")).collect()}  # a row for each partition
    starts, at = [], 0
    for part in sorted(sizes):
        starts += [F.lit(part), F.lit(at).cast("long")]
        at += sizes[part]
    first = F.element_at(F.create_map(*starts), F.col("part")) if starts else F.lit(0).cast("long")
    return placed.withColumn("ord", first + F.col("inside")).drop("part", "inside")


def stream_files(spark: SparkSession, path: str, name_glob: str, schema: T.StructType, files_per_trigger: int = 1) -> DataFrame:
    """A folder of parquet files as a live stream."""
    return spark.readStream.schema(schema).option("pathGlobFilter", name_glob).option("maxFilesPerTrigger", files_per_trigger).parquet(path)

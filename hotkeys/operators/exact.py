"""Exact counts and exact frequent elements: the ground truth, and a baseline of its own."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotkeys.spec import exact


def exact_counts(stream: DataFrame) -> DataFrame:
    """(e, f) of a stream (e, w)."""
    return stream.groupBy("e").agg(F.sum("w").alias("f"))


def over_threshold(count: str, n: str, phi, inclusive: bool = False):
    """count > phi * n as an exact comparison of integers."""
    phi = exact(phi)
    left = F.col(count).cast("decimal(38,0)") * F.lit(phi.denominator)
    right = F.col(n).cast("decimal(38,0)") * F.lit(phi.numerator)
    return left >= right if inclusive else left > right


def exact_frequent(stream: DataFrame, phi, inclusive: bool = False) -> DataFrame:
    """(e, f) of the elements whose share exceeds phi; N is one broadcast row of the same counts."""
    counts = exact_counts(stream)
    n = counts.agg(F.coalesce(F.sum("f"), F.lit(0)).alias("n"))
    return counts.crossJoin(F.broadcast(n)).filter(over_threshold("f", "n", phi, inclusive)).select("e", "f")


def stream_block(stream: DataFrame, owner_column: str, owner: int) -> DataFrame:
    """The stream restricted to one owner's elements; the others' places stay, as nulls."""
    return stream.withColumn("e", F.when(F.col(owner_column) == owner, F.col("e")))


def block_sizes(block: DataFrame) -> DataFrame:
    """n_present and n_deleted of a stream block."""
    return block.agg(F.count("e").alias("n_present"), F.count_if(F.col("e").isNull()).alias("n_deleted"))

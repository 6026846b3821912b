"""The engine in SQL: an aggregate over a column, and a table function over a table."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hotkeys.kernels.minmax import MinMaxSummary
from hotkeys.spec import exact


def frequent_agg(phi, eps):
    """A grouped aggregate: the frequent elements of a text column, as text 'element=estimate'."""

    @F.pandas_udf(T.ArrayType(T.StringType()))
    def agg(e: pd.Series) -> list:
        own = MinMaxSummary.from_eps(eps)
        for x, w in e.dropna().value_counts(sort=False).items():
            own.update(x, int(w))
        return sorted(f"{x}={c}" for x, c in own.query(phi))

    return agg


def estimate_udf(rows: list[tuple], m: int):
    """A scalar: the upper bound of each element's count by a given (small) summary."""
    own = MinMaxSummary.from_rows(m, rows)

    @F.pandas_udf(T.LongType())
    def upper(e: pd.Series) -> pd.Series:
        return e.map(own.estimate).astype("int64")

    return upper


@F.udtf(returnType="e string, est bigint")
class FrequentElements:
    """frequent_elements(TABLE(t) PARTITION BY ..., phi, eps): t's column e."""

    def __init__(self):
        self.own = None
        self.phi = None

    def eval(self, row, phi: float, eps: float):
        if self.own is None:
            self.own, self.phi = MinMaxSummary.from_eps(exact(eps)), exact(phi)
        if row["e"] is not None:
            self.own.update(str(row["e"]))

    def terminate(self):
        if self.own is not None:
            for e, c in self.own.query(self.phi):
                yield e, c


def register(spark: SparkSession) -> None:
    spark.udtf.register("frequent_elements", FrequentElements)

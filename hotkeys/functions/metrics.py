"""Measures of answers: precision, recall, relative error, and broken guarantees."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotkeys.operators.exact import over_threshold
from hotkeys.spec import exact


def joined(answer: DataFrame, counts: DataFrame, phi) -> DataFrame:
    """(e, f, est, truly, reported, n) of every element that is frequent or reported."""
    n = counts.agg(F.coalesce(F.sum("f"), F.lit(0)).alias("n"))
    both = counts.join(answer.select("e", "est", "lower", "upper"), "e", "full_outer").crossJoin(F.broadcast(n))
    marked = both.select("e", F.coalesce("f", F.lit(0)).alias("f"), "est", "lower", "upper", "n", F.col("est").isNotNull().alias("reported"))
    return marked.withColumn("truly", over_threshold("f", "n", phi)).filter("truly OR reported")


def accuracy(answer: DataFrame, counts: DataFrame, phi, over: str = "both") -> DataFrame:
    """One row: n_true, n_reported, precision, recall and are (average relative error).

    The error is averaged over elements that are reported and true (both), reported, or true, where an
    unreported one counts as estimated 0. Of two empty sets precision and recall are 1.
    """
    rows = joined(answer, counts, phi)
    among = {"both": F.col("truly") & F.col("reported"), "reported": F.col("reported"), "true": F.col("truly")}[over]
    error = F.abs(F.coalesce("est", F.lit(0)) - F.col("f")) / F.col("f")
    sums = rows.agg(
        F.count_if("truly").alias("n_true"),
        F.count_if("reported").alias("n_reported"),
        F.count_if(F.col("truly") & F.col("reported")).alias("hits"),
        F.avg(F.when(among & (F.col("f") > 0), error)).alias("are"),
    )
    share = lambda part: F.when(F.col(part) > 0, F.col("hits") / F.col(part)).when((F.col("n_true") == 0) & (F.col("n_reported") == 0), F.lit(1.0)).otherwise(F.lit(0.0))
    return sums.select("n_true", "n_reported", share("n_reported").alias("precision"), share("n_true").alias("recall"), F.coalesce("are", F.lit(0.0)).alias("are"))


def violations(answer: DataFrame, counts: DataFrame, phi, eps) -> DataFrame:
    """One row of how often each guarantee is broken.

    missed: f > phi n, unreported; spurious: f < (phi - eps) n, reported; low: est < f; high: est > f + eps n;
    bounds: f outside [lower, upper].
    """
    phi, eps = exact(phi), exact(eps)
    rows = joined(answer, counts, phi)
    big = lambda c: F.col(c).cast("decimal(38,0)")
    below = big("f") * (phi - eps).denominator < big("n") * (phi - eps).numerator
    high = (big("est") - big("f")) * eps.denominator > big("n") * eps.numerator
    n = counts.agg(F.coalesce(F.sum("f"), F.lit(0)).alias("n"))
    broken = rows.agg(
        F.count_if("truly").alias("n_true"),
        F.count_if(F.col("truly") & ~F.col("reported")).alias("missed"),
        F.count_if(F.col("reported") & below).alias("spurious"),
        F.count_if(F.col("reported") & (F.col("est") < F.col("f"))).alias("low"),
        F.count_if(F.col("reported") & high).alias("high"),
        F.count_if(F.col("reported") & ((F.col("f") < F.col("lower")) | (F.col("f") > F.col("upper")))).alias("bounds"),
    )
    return n.crossJoin(broken)


def owner_balance(summary: DataFrame, eps) -> DataFrame:
    """One row: how far the fullest owner is above the mean, and the greatest f_min over eps * n."""
    sums = summary.agg(F.max("n_seen").alias("most"), F.avg("n_seen").alias("mean"), F.max("f_min").alias("f_min"), F.sum("n_seen").alias("n"), F.count("*").alias("owners"))
    return sums.select("owners", "n", (F.col("most") / F.col("mean")).alias("imbalance"), (F.col("f_min") / (F.col("n") * float(exact(eps)))).alias("fmin_share"))


def frequent_count(counts: DataFrame, phis: list[str]) -> DataFrame:
    """(phi, n_frequent): how many elements exceed each support."""
    n = counts.agg(F.sum("f").alias("n"))
    both = counts.crossJoin(F.broadcast(n))
    sums = both.agg(*[F.count_if(over_threshold("f", "n", p)).alias(f"p{i}") for i, p in enumerate(phis)])
    return sums.select(F.explode(F.array(*[F.struct(F.lit(p).alias("phi"), F.col(f"p{i}").alias("n_frequent")) for i, p in enumerate(phis)])).alias("x")).select("x.*")


def rank_curve(counts: DataFrame, k: int) -> DataFrame:
    """(rank, e, f, share) of the k greatest counts; the top k is taken before ranks are given."""
    from pyspark.sql import Window as W

    n = counts.agg(F.sum("f").alias("n"))
    top = counts.orderBy(F.desc("f"), "e").limit(k).crossJoin(F.broadcast(n))
    return top.select(F.row_number().over(W.orderBy(F.desc("f"), "e")).cast("long").alias("rank"), "e", "f", (F.col("f") / F.col("n")).alias("share"))


def fitted_skew(counts: DataFrame, k: int = 200) -> DataFrame:
    """One row: the slope of log f against log rank over the top k, its sign turned."""
    curve = rank_curve(counts, k)
    return curve.agg((-F.regr_slope(F.log("f"), F.log("rank"))).alias("skew"))


def state_bytes(summary: DataFrame) -> DataFrame:
    """One row: counters held, their bytes in the memory model, and the bytes of the state as JSON."""
    from hotkeys.plans.sizing import SLOT_BYTES

    return summary.agg(F.sum(F.size("slots")).alias("counters"), (F.sum(F.size("slots")) * SLOT_BYTES).alias("model_bytes"), F.sum(F.octet_length(F.to_json("slots"))).alias("json_bytes"))

"""Choices made before a run: exact or approximate, owners or local merge, and the counters."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hotkeys.functions.metrics import fitted_skew
from hotkeys.operators import owner_split as engine
from hotkeys.operators.exact import exact_counts, exact_frequent
from hotkeys.spec import SupportSpec

#: With fewer distinct elements than this the exact aggregate is small enough.
FEW_DISTINCT = 1_000_000


@dataclass(frozen=True)
class Plan:
    strategy: str
    spec: SupportSpec
    distinct: int
    skew: float


def choose(stream: DataFrame, spec: SupportSpec, fraction: float = 0.01, seed: int = 42) -> Plan:
    """Distinct elements by a sketch over all rows; skew by a fit on a sample.

    The smaller size for Zipf streams is taken only where the fitted exponent exceeds 1, and the
    certificate of the run decides whether it was enough.
    """
    distinct = stream.agg(F.approx_count_distinct("e").alias("d")).first()["d"]
    skew = fitted_skew(exact_counts(stream.sample(fraction, seed))).first()["skew"] or 0.0
    if distinct <= min(FEW_DISTINCT, 1 / spec.eps):
        return Plan("exact", spec, distinct, skew)
    sized = replace(spec, dist="zipf", skew=skew) if skew > 1 else spec
    tail_heavy = distinct * spec.owners > 64 / spec.eps and skew < 0.2
    return Plan("local_merge" if tail_heavy else "owner_split", sized, distinct, skew)


def run(stream: DataFrame, plan: Plan) -> tuple[DataFrame, str]:
    """The answer (e, est, lower, upper) and the level that is proved for it."""
    if plan.strategy == "exact":
        found = exact_frequent(stream, plan.spec.phi)
        return found.select("e", F.col("f").alias("est"), F.col("f").alias("lower"), F.col("f").alias("upper")), "full"
    if plan.strategy == "local_merge":
        from hotkeys.operators.baselines import local_merge

        return local_merge(stream, plan.spec), "full"
    return engine.frequent_certified(stream, plan.spec)

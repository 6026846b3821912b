"""Headline timings at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

ROOT = Path(__file__).resolve().parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"


def main() -> None:
    from pyspark.sql import SparkSession

    from hotkeys import mixed, timing
    from hotkeys.functions.metrics import violations
    from hotkeys.operators import owner_split as engine
    from hotkeys.operators.exact import exact_counts, exact_frequent
    from hotkeys.sources import streams
    from hotkeys.spec import SupportSpec

    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", "8"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(cpus))
        .config("spark.sql.files.maxPartitionBytes", "4m")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "12g")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    spec = SupportSpec("0.0001", owners=cpus, every=1_000_000, slots=1 << 16)  # a batch run: nothing asks before the end
    small = SupportSpec("0.0001", owners=cpus, every=1_000, slots=32)
    words = streams.documents_words(spark, sf).repartition(cpus).persist()
    n = words.count()
    zipf = streams.zipf_stream(spark, 2_000_000, 2_000_000, 1.0, partitions=cpus).persist()
    zipf.count()
    timing.seconds(engine.frequent(words.limit(10_000), spec))  # code is compiled, workers are up

    q: dict[str, float] = {"exact_words": timing.seconds(exact_frequent(words, spec.phi))}
    q |= {f"{name}_words": s for name, s in timing.throughput(words, spec).items()}
    q |= {f"{name}_zipf_1": s for name, s in timing.throughput(zipf, spec, ["owner_split", "single_summary", "merge_collector", "cell_majority"], 1).items()}
    q["owner_split_small_buffers_words"] = timing.throughput(words, small, ["owner_split"], 1)["owner_split"]
    q |= {f"owner_split_words_{t}_owners": s for t, s in timing.scaling(words, spec).items()}
    q["verified_words"] = timing.seconds(engine.verify_exact(words, engine.frequent(words, spec), spec.phi))
    summary = engine.build_summary(words, spec)
    q["query_of_summary"] = timing.query_seconds(summary, "0.0001")
    row = violations(engine.query(summary, spec.phi), exact_counts(words), spec.phi, spec.eps).first()
    looped = timing.looped(words, spec, 10.0)

    # logical workers: what falls to the busiest of 24, without and with queries
    arrivals = timing.zipf_list(300_000, 1.0)
    mixes = [mixed.Mix("zipf_1", m, 24, p, share) for m in mixed.METHODS for p in ("0.001", "0.0001") for share in (0.0, 0.0001, 0.0002)]
    by = {(r["method"], r["phi"], r["share"]): r for r in mixed.run_all(iter(arrivals), mixes, [len(arrivals)])}
    speed_up = {f"{m}_{p}_{share:g}": round(by["single_summary", p, share]["critical"] / by[m, p, share]["critical"], 3) for m, p, share in by if m != "single_summary"}
    # one owner of 24 at support 1e-4, and a single summary at 1e-3: a query every 10,000 updates
    inner = {f"zipf_{a:g}_m{m}": timing.inner_timing(timing.zipf_list(200_000, a), m, p, owners=t) for a in (0.5, 0.75, 1.0, 1.25, 2.0, 3.0) for m, p, t in ((4_167, "0.0001", 24), (10_000, "0.001", 1))}
    ratio = lambda a, b: round(a / b, 2)
    out = {
        "metric": "owner_split_words_seconds",
        "value": round(q["owner_split_words"], 3),
        "unit": "sec",
        "queries": {k: round(v, 3) for k, v in q.items()},
        "sf": sf,
        "arrivals": n,
        "ratios": {
            "owner_split_over_single_words": ratio(q["single_summary_words"], q["owner_split_words"]),
            "owner_split_over_single_zipf_1": ratio(q["single_summary_zipf_1"], q["owner_split_zipf_1"]),
            "owner_split_over_cell_majority_words": ratio(q["cell_majority_words"], q["owner_split_words"]),
            "owner_split_over_merge_collector_words": ratio(q["merge_collector_words"], q["owner_split_words"]),
            "owner_split_8_over_1_owners": ratio(q["owner_split_words_1_owners"], q["owner_split_words_8_owners"]),
            "million_arrivals_per_s_words": round(n / q["owner_split_words"] / 1e6, 3),
            "million_arrivals_per_s_looped": round(looped / 1e6, 3),
        },
        "speed_up_of_24_workers_in_steps": speed_up,
        "inner_minmax_over_minheap": {k: {"query": ratio(v["minheap"]["query_us"], max(v["minmax"]["query_us"], 1e-3)), "comparisons": ratio(v["minheap"]["comparisons"], v["minmax"]["comparisons"]), "operations": ratio(v["minmax"]["operations_per_s"], v["minheap"]["operations_per_s"])} for k, v in inner.items()},
        "guarantees_broken": sum(row[c] for c in ("missed", "spurious", "low", "high", "bounds")),
        "at": time.strftime("%Y-%m-%d"),
    }
    print(json.dumps(out), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()

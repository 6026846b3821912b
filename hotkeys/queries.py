"""The engine's queries by name, and the SQL that each is held against."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotkeys import mixed, workloads
from hotkeys.frames import keep
from hotkeys.functions import metrics
from hotkeys.kernels.minmax import padded
from hotkeys.operators import baselines, sketches
from hotkeys.operators import owner_split as engine
from hotkeys.operators.exact import block_sizes, exact_counts, exact_frequent, stream_block
from hotkeys.plans import sizing
from hotkeys.sources import streams
from hotkeys.spec import SupportSpec
from hotkeys.streaming import live

Query = Callable[[SparkSession, str], DataFrame]
OWNERS = 8
_words: Query = streams.documents_words

QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


# --- streams and their SQL ---


def _table(name: str, e: str, w: str | None = None) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf: streams.element_stream(streams.read(spark, sf, name), F.expr(e), F.expr(w) if w else None)


STREAMS = {
    "words": streams.documents_words,
    "conversations": streams.conversations_words,
    "lines": streams.documents_lines,
    "partkey": _table("lineitem", "l_partkey"),
    "suppkey": _table("lineitem", "l_suppkey"),
    "props": _table("events", "props"),
    "user": _table("events", "user_id"),
    "cust": _table("orders", "o_custkey"),
}
_SPLIT = r"SELECT e, 1 AS w FROM (SELECT unnest(regexp_split_to_array(lower(trim(text)), '[^\p{L}\p{N}]+')) AS e FROM %s) WHERE e <> ''"
STREAM_SQL = {
    "words": _SPLIT % "documents",
    "conversations": _SPLIT % "conversations",
    "lines": "SELECT unnest(string_split(text, chr(10))) AS e, 1 AS w FROM documents",
    "partkey": "SELECT l_partkey AS e, 1 AS w FROM lineitem",
    "suppkey": "SELECT l_suppkey AS e, 1 AS w FROM lineitem",
    "suppkey_weighted": "SELECT l_suppkey AS e, CAST(l_quantity AS BIGINT) AS w FROM lineitem",
    "props": "SELECT props AS e, 1 AS w FROM events",
    "user": "SELECT user_id AS e, 1 AS w FROM events",
    "cust": "SELECT o_custkey AS e, 1 AS w FROM orders",
    "flow": "SELECT (l_suppkey, l_partkey, l_returnflag, l_linestatus, l_linenumber) AS e, 1 AS w FROM lineitem",
    "user_type": "SELECT user_id, event_type, 1 AS w FROM events",
    "hosts": "SELECT regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS e, 1 AS w FROM pages",
    "tags": "SELECT lower(unnest(regexp_extract_all(html, '<([a-zA-Z][a-zA-Z0-9]*)', 1))) AS e, 1 AS w FROM pages",
    "json": "SELECT CAST(json_extract(props, '$.k') AS VARCHAR) AS e, 1 AS w FROM events",
}


def _counts(stream: str) -> str:
    return f"s AS ({STREAM_SQL[stream]}), c AS (SELECT e, CAST(sum(w) AS BIGINT) AS f FROM s WHERE e IS NOT NULL GROUP BY e), t AS (SELECT CAST(coalesce(sum(f), 0) AS BIGINT) AS n FROM c)"


def _over(phi: str, f: str = "f") -> str:
    p = sizing.exact(phi)
    return f"CAST({f} AS HUGEINT) * {p.denominator} > CAST(n AS HUGEINT) * {p.numerator}"


def _frequent_sql(stream: str, phi: str, columns: str = "e, f") -> str:
    return f"WITH {_counts(stream)} SELECT {columns} FROM c, t WHERE {_over(phi)}"


def _verdict_sql(stream: str, phi: str, zeros: list[str]) -> str:
    return f"WITH {_counts(stream)} SELECT max(n) AS n, CAST(count(*) FILTER (WHERE {_over(phi)}) AS BIGINT) AS n_true, " + ", ".join(f"CAST(0 AS BIGINT) AS {z}" for z in zeros) + " FROM c, t"


# --- exact truth ---

for _name, _stream, _phi in (("words", "words", "0.001"), ("partkey", "partkey", "0.0001"), ("props_boundary", "props", "0.01"), ("customers", "cust", "0.001")):
    add(f"exact_frequent_{_name}", lambda spark, sf, s=_stream, p=_phi: exact_frequent(STREAMS[s](spark, sf), p), _frequent_sql(_stream, _phi))
add("exact_frequent_flow_empty", lambda spark, sf: exact_frequent(streams.flows(spark, sf), "0.001").select("e.*", "f"), f"WITH s AS (SELECT l_suppkey, l_partkey, l_returnflag, l_linestatus, l_linenumber, count(*) AS f FROM lineitem GROUP BY ALL) SELECT * FROM s WHERE f * 1000 > (SELECT sum(f) FROM s)")
add("exact_frequent_props_inclusive", lambda spark, sf: exact_frequent(STREAMS["props"](spark, sf), "0.01", inclusive=True), f"WITH {_counts('props')} SELECT e, f FROM c, t WHERE f * 100 >= n")

# --- the engine with a counter for every element: estimates equal counts ---


def _enough(stream: DataFrame, by: list[str] | None = None) -> int:
    """Counters with which no owner has to replace any: as many as there are elements, in a group or in all."""
    if by:
        return stream.select(*by, "e").distinct().groupBy(*by).agg(F.count("*").alias("n")).agg(F.coalesce(F.max("n"), F.lit(1))).first()[0]
    return max(1, stream.select("e").distinct().count())


def _ample(stream: DataFrame, phi: str, **options) -> DataFrame:
    return engine.frequent(stream, SupportSpec(phi, owners=OWNERS, counters=_enough(stream)), **options).select("e", "est", "lower", "upper")


def _verified(stream: DataFrame, phi: str) -> DataFrame:
    """The frequent elements by a summary sized by support and error, their counts by a second pass: (e, est)."""
    answer, _ = engine.frequent_certified(stream, SupportSpec(phi, owners=OWNERS))
    return engine.verify_exact(stream, answer, phi).select("e", F.col("f").alias("est"))


_EXACT_COLUMNS = "e, f AS est, f AS lower, f AS upper"
add("owner_split_exact_props", lambda spark, sf: _ample(STREAMS["props"](spark, sf), "0.01"), _frequent_sql("props", "0.01", _EXACT_COLUMNS))
add("owner_split_rowwise_props", lambda spark, sf: engine.frequent(STREAMS["props"](spark, sf), SupportSpec("0.01", owners=OWNERS, counters=_enough(STREAMS["props"](spark, sf)), slots=8, every=100), mode="rows"), _frequent_sql("props", "0.01", _EXACT_COLUMNS))
add("owner_split_suppkey_weighted", lambda spark, sf: _ample(streams.element_stream(streams.read(spark, sf, "lineitem"), "l_suppkey", F.col("l_quantity").cast("long")), "0.01"), _frequent_sql("suppkey_weighted", "0.01", _EXACT_COLUMNS))
add(
    "owner_split_user_type",
    lambda spark, sf: _ample(streams.element_stream(streams.read(spark, sf, "events"), F.struct("user_id", "event_type")), "0.001").select("e.user_id", "e.event_type", "est"),
    "WITH c AS (SELECT user_id, event_type, count(*) AS est FROM events GROUP BY ALL) SELECT * FROM c WHERE est * 1000 > (SELECT count(*) FROM events)",
)
add("owner_split_verified_words", lambda spark, sf: engine.verify_exact(streams.documents_words(spark, sf), engine.frequent(streams.documents_words(spark, sf), SupportSpec("0.001", owners=OWNERS)), "0.001"), _frequent_sql("words", "0.001"))
add("owner_split_combined_props", lambda spark, sf: _combined(spark, sf), f"WITH {_counts('props')} SELECT e, 2 * f AS est FROM c, t WHERE {_over('0.01')}")


def _combined(spark: SparkSession, sf: str) -> DataFrame:
    stream = STREAMS["props"](spark, sf)
    summary = engine.build_summary(stream, SupportSpec("0.01", owners=OWNERS, counters=_enough(stream)))
    return engine.query(engine.combine(summary, summary), "0.01").select("e", "est")




def _counted_pending(spark: SparkSession, sf: str) -> DataFrame:
    stream = STREAMS["props"](spark, sf)
    summary, pending = engine.build_with_pending(stream, SupportSpec("0.01", owners=OWNERS, counters=_enough(stream), every=700, slots=50))
    return engine.query(summary, "0.01", pending=pending).select("e", "est", "lower", "upper")


add("owner_split_pending_counted_props", _counted_pending, _frequent_sql("props", "0.01", "e, f AS est, f AS lower, f AS upper"))


def _drift(spark: SparkSession, sf: str) -> DataFrame:
    """Estimates of event types in the first and the second half of the users."""
    events = streams.element_stream(streams.read(spark, sf, "events"), "event_type", order=["user_id"])
    spec = SupportSpec("0.01", owners=3, counters=63)
    return engine.drift(engine.build_summary(events.filter("user_id % 2 = 0"), spec), engine.build_summary(events.filter("user_id % 2 = 1"), spec)).select("e", "before", "after")


add("drift_types", _drift, "SELECT event_type AS e, count(*) FILTER (WHERE user_id % 2 = 0) AS before, count(*) FILTER (WHERE user_id % 2 = 1) AS after FROM events GROUP BY 1")
add("worker_totals_words", lambda spark, sf: engine.worker_totals(engine.handover(_words(spark, sf), SupportSpec("0.001", owners=OWNERS, every=1_000, slots=32))).agg(F.sum("n").alias("n")), f"WITH {_counts('words')} SELECT n FROM t")
add("top_words", lambda spark, sf: engine.top_k(engine.build_summary(streams.documents_words(spark, sf), SupportSpec("0.001", owners=OWNERS, counters=_enough(streams.documents_words(spark, sf)))), 10).select("e", "est"), f"WITH {_counts('words')} SELECT e, f AS est FROM c ORDER BY f DESC, e LIMIT 10")

# --- guarantees ---

_ALL = ["missed", "spurious", "low", "high", "bounds"]


def _verdict(stream: Query, answer: Callable[[DataFrame], DataFrame], phi: str, keep: list[str], eps: str | None = None) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        own = stream(spark, sf)
        spec = SupportSpec(phi, eps or 0, owners=OWNERS)
        return metrics.violations(answer(own), exact_counts(own), phi, spec.eps).select("n", "n_true", *keep)

    return run


def _evicting(stream: Query, spec: SupportSpec) -> Query:
    """Broken guarantees, and whether the summaries had to replace elements at all: else nothing could break."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        own = stream(spark, sf)
        summary = engine.build_summary(own, spec)
        evicted = summary.agg((F.coalesce(F.max("f_min"), F.lit(0)) > 0).alias("evicted"))
        broken = metrics.violations(engine.query(summary, spec.phi), exact_counts(own), spec.phi, spec.eps)
        return broken.select("n", "n_true", *_ALL).crossJoin(F.broadcast(evicted))

    return run


#: Support, error and owners of each stream: fewer counters than elements, hand-overs each 1,000 arrivals or 32 elements.
GUARANTEES = {"words": ("0.001", "0.0001", 8), "conversations": ("0.001", "0.0001", 8), "lines": ("0.01", "0.001", 8), "partkey": ("0.0007", "0.0006", 8), "suppkey": ("0.03", "0.02", 2), "user": ("0.008", "0.0078", 2)}


def _evicting_sql(stream: str, spec: SupportSpec, phi: str) -> str:
    """Something is replaced where there are more elements than slots."""
    return _verdict_sql(stream, phi, _ALL).replace(" FROM c, t", f", count(*) > {spec.owners * padded(spec.per_owner())} AS evicted FROM c, t")


for _stream, (_phi, _eps, _owners) in GUARANTEES.items():
    _spec = SupportSpec(_phi, _eps, owners=_owners, slots=32, every=1_000)
    add(f"owner_split_guarantee_{_stream}", _evicting(STREAMS[_stream], _spec), _evicting_sql(_stream, _spec, _phi))
_words, _phi = STREAMS["words"], "0.001"


def _method(name: str, answer: Callable[[DataFrame, SupportSpec], DataFrame], keep: list[str]) -> None:
    add(name, _verdict(_words, lambda s: answer(s, SupportSpec(_phi, owners=OWNERS)), _phi, keep), _verdict_sql("words", _phi, keep))


_method("single_summary_guarantee_words", lambda s, p: engine.query(baselines.single_summary(s, p, bulk=True), p.phi), _ALL)
_method("minheap_guarantee_words", lambda s, p: engine.frequent(s, p, inner="minheap"), _ALL)
_method("bucketlist_guarantee_words", lambda s, p: engine.frequent(s, p, inner="bucketlist"), _ALL)
_method("global_cooperative_guarantee_words", lambda s, p: engine.query(baselines.global_cooperative([s], p), p.phi), _ALL)
_method("local_merge_guarantee_words", lambda s, p: baselines.local_merge(s, p), ["missed", "low"])
_method("merge_collector_guarantee_words", lambda s, p: baselines.merge_collector(s, p), ["spurious"])
_method("cell_majority_words", lambda s, p: baselines.cell_majority(s, p), ["spurious"])
# where nothing has to be thrown out, or withheld, every baseline is exact
_SURE = f"WITH {_counts('props')} SELECT e, f AS est FROM c, t WHERE CAST(f AS HUGEINT) * 1000 > CAST(n AS HUGEINT) * 9"
add("merge_collector_exact_props", lambda spark, sf: baselines.merge_collector(STREAMS["props"](spark, sf), SupportSpec("0.01"), beta="0.0000001").select("e", "est"), _SURE)
add("cell_majority_exact_props", lambda spark, sf: baselines.cell_majority(STREAMS["props"](spark, sf), SupportSpec("0.01"), cells=1_000_003).select("e", "est"), _SURE)
add("frequent_unit_exact_props", lambda spark, sf: baselines.frequent_unit(STREAMS["props"](spark, sf), SupportSpec("0.01")).select("e", "est"), _SURE)
add("lossy_counting_bounds_props", lambda spark, sf: baselines.lossy_counting(STREAMS["props"](spark, sf), SupportSpec("0.01")).agg(F.count("*").alias("reported")), _SURE.replace("SELECT e, f AS est", "SELECT count(*) AS reported"))
add("count_min_exact_props", lambda spark, sf: sketches.count_min(STREAMS["props"](spark, sf), SupportSpec("0.01"), width=1 << 18).select("e", "est"), _frequent_sql("props", "0.01", "e, f AS est"))
add("count_sketch_exact_props", lambda spark, sf: sketches.count_sketch(STREAMS["props"](spark, sf), SupportSpec("0.01"), 1 << 18).select("e", "est"), _frequent_sql("props", "0.01", "e, f AS est"))
_method("frequent_unit_words", lambda s, p: baselines.frequent_unit(s, p), ["missed", "spurious", "bounds"])
_method("lossy_counting_words", lambda s, p: baselines.lossy_counting(s, p), ["missed", "spurious", "bounds"])
_method("count_min_words", lambda s, p: sketches.count_min(s, p), ["missed", "low"])
add(
    "global_cooperative_two_streams",
    lambda spark, sf: engine.query(baselines.global_cooperative([streams.documents_words(spark, sf), streams.conversations_words(spark, sf)], SupportSpec("0.001", counters=_enough(streams.documents_words(spark, sf).unionByName(streams.conversations_words(spark, sf))))), "0.001").select("e", "est"),
    f"WITH s AS ({STREAM_SQL['words']} UNION ALL {STREAM_SQL['conversations']}), c AS (SELECT e, count(*) AS f FROM s GROUP BY e), t AS (SELECT sum(f) AS n FROM c) SELECT e, f AS est FROM c, t WHERE {_over('0.001')}",
)
add("count_sketch_words", lambda spark, sf: _sketch_recall(spark, sf), f"WITH {_counts('words')} SELECT CAST(count(*) AS BIGINT) AS n_true, true AS recall_ok FROM c, t WHERE {_over(_phi)}")


def _sketch_recall(spark: SparkSession, sf: str) -> DataFrame:
    stream = _words(spark, sf)
    found = sketches.count_sketch(stream, SupportSpec(_phi))
    return metrics.accuracy(found, exact_counts(stream), _phi).select("n_true", (F.col("recall") >= 0.95).alias("recall_ok"))


add("sketch_topk_words", lambda spark, sf: sketches.sketch_topk(_words(spark, sf), 5, 1 << 18, 5).select("e"), f"WITH {_counts('words')} SELECT e FROM c ORDER BY f DESC, e LIMIT 5")
add("builtin_topk_merged_types", lambda spark, sf: sketches.builtin_topk_merged(streams.element_stream(streams.read(spark, sf, "events"), "event_type", order=["user_id"]).withColumn("part", F.pmod("user_id", F.lit(7))), "part", 5), "SELECT event_type AS e, count(*) AS est FROM events GROUP BY 1")
add("builtin_count_min_bytes_words", lambda spark, sf: sketches.builtin_count_min_bytes(_words(spark, sf), SupportSpec(_phi)))
add("builtin_topk_types", lambda spark, sf: sketches.builtin_topk(streams.element_stream(streams.read(spark, sf, "events"), "event_type"), 5), "SELECT event_type AS e, count(*) AS est FROM events GROUP BY 1")

# --- checks of the structure ---


def _agreement(spark: SparkSession, sf: str) -> DataFrame:
    """Labelled counts above f_min are the same in all three forms of Space-Saving."""
    stream = STREAMS["conversations"](spark, sf).coalesce(1)
    spec = SupportSpec("0.001", owners=OWNERS)
    above = []
    for inner in engine.KERNELS:
        summary = engine.build_summary(stream, spec, inner, deterministic=True, mode="direct")
        above.append(engine.slots(summary).filter("est > f_min").select("owner", "e", "est"))
    apart = above[0].exceptAll(above[1]).unionAll(above[1].exceptAll(above[0])).unionAll(above[0].exceptAll(above[2])).unionAll(above[2].exceptAll(above[0]))
    n = stream.agg(F.sum("w").alias("n"))
    return n.crossJoin(apart.agg(F.count("*").alias("differences")))


add("inner_agreement_conversations", _agreement, f"WITH {_counts('conversations')} SELECT n, CAST(0 AS BIGINT) AS differences FROM t")
add("minmax_query_cost_words", lambda spark, sf: workloads.inner_costs(_words(spark, sf), SupportSpec(_phi, owners=OWNERS)).agg(F.sum("answers").alias("answers"), F.count_if(F.col("comparisons") > F.col("bound")).alias("over_bound"), F.count_if(F.col("comparisons") > F.col("scan")).alias("over_scan")).select("over_bound", "over_scan"), "SELECT CAST(0 AS BIGINT) AS over_bound, CAST(0 AS BIGINT) AS over_scan")
add("explicit_owners_types", lambda spark, sf: _explicit(spark, sf), "SELECT CASE event_type WHEN 'click' THEN 0 WHEN 'view' THEN 1 ELSE 2 END AS owner, CAST(count(*) AS BIGINT) AS n_seen FROM events WHERE event_type IN ('click', 'view') GROUP BY 1")


def _explicit(spark: SparkSession, sf: str) -> DataFrame:
    """Owners by a given map of elements."""
    events = streams.element_stream(streams.read(spark, sf, "events"), "event_type").filter("e IN ('click', 'view')")
    summary = engine.build_summary(events, SupportSpec("0.01", owners=3), how="map", bounds=[("click", 0), ("view", 1)])
    return summary.select("owner", "n_seen")


add("sum_invariant_words", lambda spark, sf: _sums(spark, sf), f"WITH {_counts('words')} SELECT n, CAST(0 AS BIGINT) AS broken, CAST(0 AS BIGINT) AS fmin_over FROM t")


def _sums(spark: SparkSession, sf: str) -> DataFrame:
    spec = SupportSpec(_phi, owners=OWNERS)
    summary = engine.build_summary(_words(spark, sf), spec)
    total = F.aggregate("slots", F.lit(0).cast("long"), lambda a, s: a + s["est"])
    rows = summary.select("n_seen", "f_min", total.alias("total"))
    sums = rows.agg(F.sum("n_seen").alias("n"), F.count_if(F.col("total") != F.col("n_seen")).alias("broken"), F.max("f_min").alias("f_min"))
    return sums.select("n", "broken", (F.col("f_min") * spec.eps.denominator > F.col("n") * spec.eps.numerator).cast("long").alias("fmin_over"))


add("owner_balance_words", lambda spark, sf: metrics.owner_balance(engine.build_summary(_words(spark, sf), SupportSpec(_phi, owners=OWNERS)), SupportSpec(_phi).eps).select("owners", "n", (F.col("imbalance") < 2).alias("balanced")), f"WITH {_counts('words')} SELECT CAST({OWNERS} AS BIGINT) AS owners, n, true AS balanced FROM t")
add("certificate_words", lambda spark, sf: engine.certify(engine.build_summary(_words(spark, sf), SupportSpec(_phi, owners=OWNERS)), SupportSpec(_phi)).select("n", "level"), f"WITH {_counts('words')} SELECT n, 'full' AS level FROM t")
add("certificate_unbalanced_flow", lambda spark, sf: engine.certify(engine.build_summary(streams.flows(spark, sf), SupportSpec("0.01", owners=4), how="one"), SupportSpec("0.01")).select("n", "level"), "SELECT count(*) AS n, 'recall' AS level FROM lineitem")
add("stream_block_events", lambda spark, sf: block_sizes(stream_block(streams.element_stream(streams.read(spark, sf, "events"), "user_id").withColumn("owner", F.pmod("e", F.lit(4))), "owner", 1)), "SELECT count(*) FILTER (WHERE user_id % 4 = 1) AS n_present, count(*) FILTER (WHERE user_id % 4 <> 1) AS n_deleted FROM events")

# --- measures and tables ---

add("table2_counts_words", lambda spark, sf: metrics.frequent_count(exact_counts(_words(spark, sf)), list(workloads.SCALED)), f"WITH {_counts('words')} " + " UNION ALL ".join(f"SELECT '{p}' AS phi, count(*) FILTER (WHERE {_over(p)}) AS n_frequent FROM c, t" for p in workloads.SCALED))
add("rank_curve_words", lambda spark, sf: metrics.rank_curve(exact_counts(_words(spark, sf)), 50), f"WITH {_counts('words')}, k AS (SELECT row_number() OVER (ORDER BY f DESC, e) AS rank, e, f, f / n AS share FROM c, t) SELECT * FROM k WHERE rank <= 50")
add(
    "zipf_table2",
    lambda spark, sf: workloads.zipf_counts(_words(spark, sf)),
    # shares of a Zipf distribution over as many ranks as the table has elements
    f"WITH {_counts('words')}, k AS (SELECT unnest(range(1, 1 + (SELECT count(*) FROM c))) AS r), a AS (SELECT * FROM (VALUES (1.25::DOUBLE), (2), (3)) AS v(skew)), h AS (SELECT skew, sum(pow(r, -skew)) AS total FROM k, a GROUP BY 1), p AS (SELECT * FROM (VALUES "
    + ", ".join(f"('{x}', {x}::DOUBLE)" for x in workloads.SUPPORTS)
    + ") AS v(phi, share)) SELECT skew, phi, (SELECT count(*) FROM c) AS elements, count(*) FILTER (WHERE pow(r, -skew) / total > share) AS n FROM k, h, p GROUP BY 1, 2",
)


def _memory_sql(threads: tuple[int, ...]) -> str:
    """The memory model's formulas with no more counters than the words of documents can fill; matrices are laid out whole."""
    return (
        f"WITH {_counts('words')}, u AS (SELECT CAST(count(*) AS DOUBLE) AS u FROM c) SELECT method, phi, threads, CAST(round(CASE method WHEN 'owner_split' THEN 32 * least(10 / p, u) + threads * threads * 167 WHEN 'merge_collector' THEN 2 * (threads + 1) * least(1 / (p / 100), u) * 32 ELSE 4 * threads * 10 / p * 32 END) AS BIGINT) AS bytes "
        f"FROM u, (VALUES {', '.join(f"('{x}', {x}::DOUBLE)" for x in workloads.SUPPORTS)}) AS v(phi, p), (VALUES ('owner_split'), ('merge_collector'), ('cell_majority')) AS m(method), (VALUES {', '.join(f'({t}::INTEGER)' for t in threads)}) AS x(threads)"
    )


add("memory_model_450", lambda spark, sf: workloads.memory_model(_words(spark, sf), (450,)).select("method", "phi", F.round("bytes").cast("long").alias("bytes")), f"SELECT method, phi, bytes FROM ({_memory_sql((450,))})")
add("accuracy_report_words", lambda spark, sf: workloads.accuracy_report(_words(spark, sf), SupportSpec(_phi, owners=OWNERS)))
add("accuracy_owner_split_words", lambda spark, sf: workloads.accuracy_report(_words(spark, sf), SupportSpec(_phi, owners=OWNERS), ["owner_split"]).select("method", "n_true", "recall"), f"WITH {_counts('words')} SELECT 'owner_split' AS method, count(*) AS n_true, 1.0::DOUBLE AS recall FROM c, t WHERE {_over(_phi)}")

# --- overlap of queries and updates ---


def _overlap(spark: SparkSession, sf: str, stream=workloads.word_arrays) -> DataFrame:
    rows = workloads.overlap_runs(spark, sf, stream=stream)
    return rows.groupBy("run_id").agg(F.max("n_end").alias("n"), *[F.sum(c).alias(c) for c in ("missed", "spurious", "outside", "pending_over")])


add("overlap_bounds_words", _overlap, f"WITH {_counts('words')} SELECT CAST(r AS INTEGER) AS run_id, n, 0::BIGINT AS missed, 0::BIGINT AS spurious, 0::BIGINT AS outside, 0::BIGINT AS pending_over FROM t, range(4) AS v(r)")
add("overlap_records_sim", workloads.overlap_runs)
add("enhancement_ab_words", workloads.enhancement_ab)
add(
    "enhancement_ab_conversations",
    lambda spark, sf: workloads.verdicts(mixed.run_grid(spark, {"conversations": workloads.ordered_texts(spark, sf, "conversations")}, workloads.enhancement_grid("conversations"))).select("method", "arrivals", "queries", "missed", "low", "spurious"),
    f"WITH {_counts('conversations')} SELECT method, n AS arrivals, n // 10 AS queries, 0::BIGINT AS missed, 0::BIGINT AS low, 0::BIGINT AS spurious FROM t, (VALUES ('owner_split'), ('owner_split_counting')) AS m(method)",
)

# --- groups and windows ---

add(
    "frequent_by_lang",
    lambda spark, sf: engine.frequent_by(streams.words(streams.read(spark, sf, "documents"), keep=["lang"]), ["lang"], "0.005", _enough(streams.words(streams.read(spark, sf, "documents"), keep=["lang"]), ["lang"])).select("lang", "e", "est"),
    rf"WITH s AS (SELECT lang, unnest(regexp_split_to_array(lower(trim(text)), '[^\p{{L}}\p{{N}}]+')) AS e FROM documents), c AS (SELECT lang, e, count(*) AS f FROM s WHERE e <> '' GROUP BY ALL), g AS (SELECT *, sum(f) OVER (PARTITION BY lang) AS n FROM c) SELECT lang, e, f AS est FROM g WHERE {_over('0.005')}",
)


def _events(spark: SparkSession, sf: str) -> DataFrame:
    return streams.element_stream(streams.read(spark, sf, "events"), "event_type", order=["ts", "user_id"])


def _start():
    return F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start")


_WINDOW_SQL = "WITH x AS (%s), c AS (SELECT d, e, count(*) AS f FROM x GROUP BY ALL), g AS (SELECT *, sum(f) OVER (PARTITION BY d) AS n FROM c) SELECT strftime(d, '%%Y-%%m-%%d %%H:%%M:%%S') AS start, e, f AS est FROM g WHERE " + _over("0.2")
add("frequent_tumbling_events", lambda spark, sf: live.frequent_windowed(_events(spark, sf), "ts", "0.2", "1 day", m=63).select(_start(), "e", "est"), _WINDOW_SQL % "SELECT date_trunc('day', ts) AS d, event_type AS e FROM events")
add("frequent_sliding_events", lambda spark, sf: live.frequent_windowed(_events(spark, sf), "ts", "0.2", "2 days", "1 day", m=63).select(_start(), "e", "est"), _WINDOW_SQL % "SELECT CAST(date_trunc('day', ts) - to_days(CAST(k AS INTEGER)) AS TIMESTAMP) AS d, event_type AS e FROM events, range(2) AS r(k)")
add(
    "frequent_session_events",
    lambda spark, sf: live.frequent_sessions(_events(spark, sf), "ts", "user_id", "12 hours", "0.5").select("user_id", _start(), "e", F.col("est").alias("f")),
    "WITH a AS (SELECT user_id, ts, event_type AS e, CASE WHEN ts - lag(ts) OVER w < INTERVAL 12 HOURS THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), b AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM a), s AS (SELECT user_id, k, min(ts) AS st, count(*) AS n FROM b GROUP BY ALL), c AS (SELECT user_id, k, e, count(*) AS f FROM b GROUP BY ALL) SELECT user_id, strftime(st, '%Y-%m-%d %H:%M:%S') AS start, e, f FROM c JOIN s USING (user_id, k) WHERE 2 * f > n",
)

# --- uses, joins and reports ---

add(
    "frequent_parts_enriched",
    lambda spark, sf: _verified(STREAMS["partkey"](spark, sf), "0.0007").join(streams.read(spark, sf, "part"), F.col("e") == F.col("p_partkey")).select("p_partkey", "p_name", "p_brand", "est"),
    f"WITH {_counts('partkey')} SELECT p_partkey, p_name, p_brand, f AS est FROM c, t, part WHERE e = p_partkey AND {_over('0.0007')}",
)


def _regions(spark: SparkSession, sf: str) -> DataFrame:
    found = _verified(STREAMS["cust"](spark, sf), "0.001").select(F.col("e").alias("c_custkey"), "est")
    read = lambda n: streams.read(spark, sf, n)
    placed = found.join(read("customer"), "c_custkey").join(read("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(read("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return placed.groupBy("r_name").agg(F.count("*").alias("customers"), F.sum("est").alias("orders"))


add("frequent_customers_by_region", _regions, f"WITH {_counts('cust')}, q AS (SELECT e, f FROM c, t WHERE {_over('0.001')}) SELECT r_name, count(*) AS customers, CAST(sum(f) AS BIGINT) AS orders FROM q JOIN customer ON e = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
add("active_users", lambda spark, sf: _verified(STREAMS["user"](spark, sf), "0.007").select("e", "est"), _frequent_sql("user", "0.007", "e, f AS est"))
add("popular_hosts", lambda spark, sf: _verified(streams.page_hosts(spark, sf), "0.01").select("e", "est"), _frequent_sql("hosts", "0.01", "e, f AS est"))
add("popular_tags", lambda spark, sf: _verified(streams.page_tags(spark, sf), "0.01").select("e", "est"), _frequent_sql("tags", "0.01", "e, f AS est"))
add("json_keys", lambda spark, sf: _verified(streams.element_stream(streams.read(spark, sf, "events"), F.get_json_object("props", "$.k")), "0.01").select("e", "est"), _frequent_sql("json", "0.01", "e, f AS est"))


def _cube(spark: SparkSession, sf: str) -> DataFrame:
    found = _verified(STREAMS["suppkey"](spark, sf), "0.01").select(F.col("e").alias("l_suppkey"))
    lines = streams.read(spark, sf, "lineitem").select("l_suppkey", "l_returnflag", "l_linestatus")
    kept = lines.join(F.broadcast(found), "l_suppkey", "left_semi")  # at most 1 / phi suppliers
    cells = keep(kept.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("lines")))
    parts = cells.cube("l_returnflag", "l_linestatus").agg(F.sum("lines").alias("lines"), F.grouping_id().alias("level")).filter("level < 3")
    # the grand total is a row in SQL even where no supplier is frequent; a cube of nothing has none
    whole = cells.agg(F.coalesce(F.sum("lines"), F.lit(0)).alias("lines")).select(*[F.lit(None).cast(cells.schema[c].dataType).alias(c) for c in ("l_returnflag", "l_linestatus")], "lines", F.lit(3).cast("long").alias("level"))
    return parts.unionByName(whole)


add("cube_report", _cube, f"WITH {_counts('suppkey')}, q AS (SELECT e FROM c, t WHERE {_over('0.01')}) SELECT l_returnflag, l_linestatus, count(*) AS lines, CAST(grouping(l_returnflag) * 2 + grouping(l_linestatus) AS BIGINT) AS level FROM lineitem WHERE l_suppkey IN (SELECT e FROM q) GROUP BY CUBE (l_returnflag, l_linestatus)")


def _method_overlap(spark: SparkSession, sf: str) -> DataFrame:
    stream = _words(spark, sf)
    truth = exact_frequent(stream, _phi).select("e")
    found = engine.frequent(stream, SupportSpec(_phi, owners=OWNERS)).select("e")
    return truth.agg(F.count("*").alias("n_true")).crossJoin(truth.intersect(found).agg(F.count("*").alias("common"))).crossJoin(truth.subtract(found).agg(F.count("*").alias("missing")))


add("method_overlap", _method_overlap, f"WITH {_counts('words')} SELECT count(*) AS n_true, count(*) AS common, 0::BIGINT AS missing FROM c, t WHERE {_over(_phi)}")

def _counts_by_stream(spark: SparkSession, sf: str) -> DataFrame:
    """Frequent elements of three streams, a column for each support."""
    parts = [metrics.frequent_count(exact_counts(STREAMS[s](spark, sf)), list(workloads.SCALED)).withColumn("source", F.lit(s)) for s in ("words", "conversations", "lines")]
    whole = parts[0].unionByName(parts[1]).unionByName(parts[2])
    return whole.groupBy("source").pivot("phi", list(workloads.SCALED)).agg(F.sum("n_frequent")).select("source", *[F.col(f"`{p}`").alias(f"over_{p.replace('.', '_')}") for p in workloads.SCALED])


def _counts_by_stream_sql() -> str:
    columns = ", ".join(f"CAST(count(*) FILTER (WHERE {_over(p)}) AS BIGINT) AS over_{p.replace('.', '_')}" for p in workloads.SCALED)
    return " UNION ALL ".join(f"SELECT * FROM (WITH {_counts(s)} SELECT '{s}' AS source, {columns} FROM c, t)" for s in ("words", "conversations", "lines"))


add("frequent_counts_pivot", _counts_by_stream, _counts_by_stream_sql())


def _adverse(spark: SparkSession, sf: str) -> DataFrame:
    """Guarantees under adverse orders of the same arrivals, with few counters and small hand-overs."""
    given = streams.element_stream(streams.read(spark, sf, "events"), "user_id", order=["event_id"]).withColumnRenamed("event_id", "ord")
    spec = SupportSpec("0.008", "0.0078", owners=2, slots=8, every=50)
    parts = []
    for how in ("ascending", "descending", "round_robin", "tail_first"):
        summary = engine.build_summary(streams.reordered(given, how), spec, deterministic=True)
        broken = metrics.violations(engine.query(summary, spec.phi), exact_counts(given), spec.phi, spec.eps).select(F.lit(how).alias("how"), "n", "n_true", *_ALL)
        parts.append(broken.crossJoin(F.broadcast(summary.agg((F.max("f_min") > 0).alias("evicted")))))
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


add("adverse_orders_users", _adverse, f"SELECT how, v.* FROM ({_evicting_sql('user', SupportSpec('0.008', '0.0078', owners=2), '0.008')}) AS v, (VALUES ('ascending'), ('descending'), ('round_robin'), ('tail_first')) AS h(how)")
add("builtin_items_types", lambda spark, sf: sketches.builtin_frequent_items(streams.element_stream(streams.read(spark, sf, "events"), "event_type"), 0.1), "SELECT DISTINCT event_type AS e FROM events")
add("state_bytes_words", lambda spark, sf: metrics.state_bytes(engine.build_summary(_words(spark, sf), SupportSpec(_phi, owners=OWNERS))))


def _as_of(spark: SparkSession, sf: str) -> DataFrame:
    """Each purchase with the user's latest event before it: an as-of join as one window."""
    from pyspark.sql import Window as W

    events = streams.read(spark, sf, "events")
    before = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    seen = events.withColumn("last_type", F.last("event_type", ignorenulls=True).over(before))
    return seen.filter("event_type = 'purchase'").groupBy("last_type").agg(F.count("*").alias("purchases"))


add("as_of_purchases", _as_of, "WITH a AS (SELECT event_type, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS last_type FROM events) SELECT last_type, count(*) AS purchases FROM a WHERE event_type = 'purchase' GROUP BY 1")

# --- updates and queries mixed: the comparison of the methods ---


def _mixed_sql(arrivals: str, labels: list[str], owners: tuple[int, ...]) -> str:
    """What must hold of every run: its queries, what merging takes of a matrix per worker, and no broken guarantee."""
    sets = {"label": labels, "method": mixed.METHODS, "phi": workloads.SCALED}
    given = ", ".join(f"(VALUES {', '.join(f"('{x}')" for x in xs)}) AS v_{k}({k})" for k, xs in sets.items())
    shares = ", ".join(f"({x}::DOUBLE, {round(1 / x) if x else 0})" for x in workloads.QUERY_SHARES)
    merged = "CASE WHEN method LIKE 'cell_majority%' THEN owners * 4 * CAST(round(10 / CAST(phi AS DOUBLE)) AS BIGINT) * (CASE WHEN gap > 0 THEN n // gap ELSE 0 END) ELSE 0 END"
    return (
        f"WITH n AS ({arrivals}) SELECT label, method, owners, phi, share, n AS arrivals, CASE WHEN gap > 0 THEN n // gap ELSE 0 END AS queries, {merged} AS merged, "
        f"0::BIGINT AS missed, 0::BIGINT AS low, 0::BIGINT AS spurious, 0::BIGINT AS over_bound FROM n, {given}, (VALUES {', '.join(f'({t}::INTEGER)' for t in owners)}) AS o(owners), (VALUES {shares}) AS q(share, gap)"
    )


add("mixed_verdicts_by_skew", lambda spark, sf: workloads.verdicts(workloads.mixed_by_skew(spark, sf)), _mixed_sql("SELECT count(*) AS n FROM lineitem", [workloads.zipf_label(a) for a in workloads.SKEWS], (24,)))
add("mixed_verdicts_by_threads", lambda spark, sf: workloads.verdicts(workloads.mixed_by_threads(spark, sf)), _mixed_sql(f"SELECT count(*) AS n FROM ({STREAM_SQL['words']}) AS s", ["words"], workloads.THREADS))
add("throughput_by_skew", lambda spark, sf: workloads.speeds(workloads.mixed_by_skew(spark, sf)))
add("throughput_by_threads", lambda spark, sf: workloads.speeds(workloads.mixed_by_threads(spark, sf)))
add("latency_by_skew", workloads.mixed_latency)
add("latency_by_threads", lambda spark, sf: workloads.mixed_latency(spark, sf, "threads"))


def _handed_over(spark: SparkSession, sf: str) -> DataFrame:
    """What 8 workers hand over of all words, by age alone and with a summary that replaces many."""
    mix = mixed.Mix("words", "owner_split", 8, "0.001", 0.0, 1_000, 1_001)
    return mixed.run_grid(spark, {"words": workloads.word_arrays(spark, sf)}, [mix]).select("arrivals", "handovers", "pairs", "n_true", "hits")


add(
    "handed_over_words",
    _handed_over,
    rf"WITH d AS (SELECT doc_id, regexp_split_to_array(lower(trim(text)), '[^\p{{L}}\p{{N}}]+') AS es FROM documents), w AS (SELECT doc_id, unnest(es) AS e, generate_subscripts(es, 1) AS i FROM d), k AS (SELECT e, row_number() OVER (ORDER BY doc_id, i) - 1 AS k FROM w WHERE e <> ''), b AS (SELECT e, k % 8 AS j, k // 8 // 1000 AS block FROM k), c AS (SELECT e, count(*) AS f FROM k GROUP BY 1), t AS (SELECT sum(f) AS n FROM c), x AS (SELECT count(*) AS n_true FROM c, t WHERE {_over('0.001')}) SELECT CAST((SELECT n FROM t) AS BIGINT) AS arrivals, (SELECT count(*) FROM (SELECT DISTINCT j, block FROM b)) AS handovers, (SELECT count(*) FROM (SELECT DISTINCT j, block, e FROM b)) AS pairs, n_true, n_true AS hits FROM x",
)
add(
    "error_by_owners_words",
    lambda spark, sf: workloads.accuracies(mixed.run_grid(spark, {"words": workloads.word_arrays(spark, sf)}, workloads.grid_by_threads("words", ["owner_split"], shares=(0.0,)))).select("owners", "phi", "length", "n_true", "recall"),
    f"WITH {_counts('words')} SELECT * FROM (" + " UNION ALL ".join(f"SELECT owners, '{p}' AS phi, max(n) AS length, CAST(count(*) FILTER (WHERE {_over(p)}) AS BIGINT) AS n_true, 1.0::DOUBLE AS recall FROM c, t, (VALUES {', '.join(f'({x}::INTEGER)' for x in workloads.THREADS)}) AS o(owners) GROUP BY owners" for p in workloads.SCALED) + ")",
)
add("memory_by_threads", lambda spark, sf: workloads.memory_by_threads(_words(spark, sf)).select("method", "phi", "threads", F.round("bytes").cast("long").alias("bytes")), _memory_sql((1, 2, 4, 8, 16, 24, 50, 100, 200, 300, 450)))

# --- experiments without an SQL form ---

add("accuracy_by_skew", workloads.accuracy_by_skew)
add("error_by_owners", workloads.error_by_owners)
add("staleness_by_length", workloads.staleness_by_length)
add("equal_bytes_words", workloads.equal_bytes)
add("frequent_counts_by_skew", workloads.frequent_counts_by_skew)
add("shuffled_pairs", workloads.shuffled_pairs)
add("qualitative_report", workloads.qualitative)

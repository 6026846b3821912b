"""The owner-split engine: buffered hand-over, one shuffle, one summary per owner, union of answers.

Every element has one owner. Map tasks combine arrivals in bounded buffers and hand them over as
weighted pairs; the exchange puts owner i's pairs in partition i; there one task feeds owner i's
summary. Domains are disjoint, so a query filters the summaries' slots and merges nothing.
What is shuffled is what doesn't combine within `every` arrivals; what is kept is 1 / eps counters,
whatever the stream's length.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hotkeys.frames import drop, keep
from hotkeys.kernels.buffers import HandoverBuffers
from hotkeys.kernels.minmax import MinMaxSummary
from hotkeys.kernels.others import BucketListSummary, MinHeapSummary
from hotkeys.operators.exact import over_threshold
from hotkeys.spec import SupportSpec

KERNELS = {"minmax": MinMaxSummary, "minheap": MinHeapSummary, "bucketlist": BucketListSummary}


def owner_of(columns: list[str], owners: int, seed: int, how: str = "hash", bounds: list | None = None):
    """Owner of an element: by hash, by range (bounds are the upper ends of all but the last), all to 0, or by a given
    map (bounds are pairs of element and owner, others go by hash)."""
    if how == "hash":
        return F.pmod(F.xxhash64(*columns, F.lit(seed)), F.lit(owners)).cast("int")
    if how == "range":
        return sum((F.col(columns[0]) > b).cast("int") for b in bounds) if bounds else F.lit(0)
    if how == "one":
        return F.lit(0)
    if how == "map":
        return F.coalesce(F.element_at(F.create_map(*[x for e, o in bounds for x in (F.lit(e), F.lit(o))]), F.col(columns[0])), owner_of(columns, owners, seed)).cast("int")
    raise ValueError(f"no owner function {how}")


def with_owner(stream: DataFrame, spec: SupportSpec, how: str = "hash", bounds: list | None = None) -> DataFrame:
    return stream.withColumn("owner", owner_of(["e"], spec.owners, spec.seed, how, bounds))


def keys(column: pa.Array) -> list[Any]:
    """Elements as hashable Python values; a struct becomes the tuple of its fields."""
    values = column.to_pylist()
    return [tuple(v.values()) for v in values] if pa.types.is_struct(column.type) else values


def restored(elements: list[Any], arrow_type: pa.DataType) -> pa.Array:
    if pa.types.is_struct(arrow_type):
        names = [arrow_type.field(i).name for i in range(arrow_type.num_fields)]
        elements = [dict(zip(names, e, strict=True)) for e in elements]
    return pa.array(elements, arrow_type)


def pair_schema(stream: DataFrame) -> T.StructType:
    return T.StructType([T.StructField("owner", T.IntegerType()), T.StructField("src", T.IntegerType()), T.StructField("seq", T.LongType()), stream.schema["e"], T.StructField("w", T.LongType())])


#: Pairs that an owner combines before its summary takes them.
ABSORB_ROWS = 200_000


def gathered(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of at least so many, the last one but for what is left."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
        if sum(b.num_rows for b in held) >= rows:
            yield from pa.Table.from_batches(held).combine_chunks().to_batches()
            held = []
    if held:
        yield from pa.Table.from_batches(held).combine_chunks().to_batches()


def sum_pairs(batch: pa.RecordBatch) -> pa.Table:
    """(owner, e, w) of a batch, one row for each owner and element."""
    table = pa.Table.from_batches([batch])
    kind = table.schema.field("e").type
    if not pa.types.is_struct(kind):
        got = table.group_by(["owner", "e"]).aggregate([("w", "sum")])
        return got.select(["owner", "e", "w_sum"]).rename_columns(["owner", "e", "w"])
    fields = table.column("e").combine_chunks().flatten()
    names = [f"e{i}" for i in range(len(fields))]
    flat = pa.table([table.column("owner"), table.column("w"), *fields], ["owner", "w", *names])
    got = flat.group_by(["owner", *names]).aggregate([("w", "sum")])
    e = pa.StructArray.from_arrays([got.column(n).combine_chunks() for n in names], fields=list(kind))
    return pa.table([got.column("owner"), e, got.column("w_sum")], ["owner", "e", "w"])


def summed(batch: pa.RecordBatch) -> list[pa.Table]:
    """sum_pairs of a batch, a table for each owner in it."""
    whole = sum_pairs(batch)
    owners = pc.unique(whole.column("owner"))
    return [whole] if len(owners) == 1 else [whole.filter(pc.equal(whole.column("owner"), o)) for o in owners]


def _combined(batch: pa.RecordBatch, slots: int) -> Iterator[pa.Table]:
    """The batch as weighted pairs; halved until no owner has more distinct elements than slots."""
    todo = [batch]
    while todo:
        part = todo.pop()
        pairs = sum_pairs(part)
        most = pc.max(pc.value_counts(pairs.column("owner").combine_chunks()).field("counts")).as_py() or 0
        if most > slots and part.num_rows > 1:
            half = part.num_rows // 2
            todo += [part.slice(half), part.slice(0, half)]
        else:
            yield pairs


def handover(stream: DataFrame, spec: SupportSpec, mode: str = "batch", how: str = "hash", bounds: list | None = None, mark_rest: bool = False) -> DataFrame:
    """Weighted pairs (owner, src, seq, e, w) as the buffers hand them over, the rest at the end.

    With mark_rest what no trigger has handed over, but only the end, has seq -1.

    mode 'batch' combines up to `every` arrivals at a time in Arrow and keeps to `slots` by halving;
    mode 'rows' inserts arrivals one by one, with both triggers exactly where they fall.
    """
    given = with_owner(stream, spec, how, bounds).select("owner", F.spark_partition_id().alias("src"), "e", F.col("w").cast("long").alias("w"))
    owners, slots, every = spec.owners, spec.slots, spec.every

    def checked(batch: pa.RecordBatch) -> None:
        if batch.num_rows and pc.min(batch.column("w")).as_py() <= 0:
            raise ValueError("weights are positive: deletions are not supported")

    def by_batch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seq = 0
        held: list[pa.RecordBatch] = []
        rows = 0

        def out(last: bool = False) -> Iterator[pa.RecordBatch]:
            nonlocal seq, rows
            whole = pa.Table.from_batches(held).combine_chunks()
            src = whole.column("src")[0]
            for part in whole.to_batches():
                for pairs in _combined(part, slots):
                    n = pairs.num_rows
                    yield from pa.table([pairs.column("owner"), pa.repeat(src, n), pa.repeat(pa.scalar(-1 if last and mark_rest else seq, pa.int64()), n), pairs.column("e"), pairs.column("w")], ["owner", "src", "seq", "e", "w"]).combine_chunks().to_batches()
                    seq += 1
            held.clear()
            rows = 0

        for batch in batches:
            checked(batch)
            while batch.num_rows:
                part = batch.slice(0, every - rows)
                batch = batch.slice(part.num_rows)
                held.append(part)
                rows += part.num_rows
                if rows >= every:
                    yield from out()
        if rows:
            yield from out(True)

    def by_row(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        buffers = HandoverBuffers(owners, slots, every)
        seq, kind, src = 0, None, 0

        def out(flushed, last: bool = False) -> pa.RecordBatch:
            nonlocal seq
            rows = [(i, e, w) for i, held in flushed for e, w in held.items()]
            seq += 1
            n = len(rows)
            return pa.RecordBatch.from_arrays(
                [pa.array([r[0] for r in rows], pa.int32()), pa.array([src] * n, pa.int32()), pa.array([-1 if last and mark_rest else seq - 1] * n, pa.int64()), restored([r[1] for r in rows], kind), pa.array([r[2] for r in rows], pa.int64())], ["owner", "src", "seq", "e", "w"]
            )

        for batch in batches:
            checked(batch)
            kind = batch.column("e").type
            if batch.num_rows:
                src = batch.column("src")[0].as_py()
            for o, e, w in zip(batch.column("owner").to_pylist(), keys(batch.column("e")), batch.column("w").to_pylist(), strict=True):
                if flushed := buffers.insert(o, e, w):
                    yield out(flushed)
        if rest := buffers.flush():
            yield out(rest, True)

    return given.mapInArrow(by_row if mode == "rows" else by_batch, pair_schema(stream))


def route(pairs: DataFrame, owners: int, deterministic: bool = False) -> DataFrame:
    """Owner i's pairs to partition i; in order of source and hand-over if asked."""
    dealt = pairs.repartitionById(owners, "owner")
    return dealt.sortWithinPartitions("owner", "src", "seq", "e") if deterministic else dealt


def summary_schema(stream: DataFrame) -> T.StructType:
    slot = T.StructType([stream.schema["e"], T.StructField("est", T.LongType()), T.StructField("over", T.LongType())])
    return T.StructType(
        [
            T.StructField("owner", T.IntegerType()),
            T.StructField("m", T.IntegerType()),
            T.StructField("n_seen", T.LongType()),
            T.StructField("f_min", T.LongType()),
            T.StructField("f_max", T.LongType()),
            T.StructField("slots", T.ArrayType(slot)),
        ]
    )


def summary_batch(kept: dict[int, Any], kind: pa.DataType) -> pa.RecordBatch:
    """Summaries by owner as rows, each one's slots by descending estimate."""
    rows = {o: sorted(k.to_rows(), key=lambda r: -r[1]) for o, k in kept.items()}
    slot = pa.struct([("e", kind), ("est", pa.int64()), ("over", pa.int64())])
    flat = [r for o in kept for r in rows[o]]
    values = pa.StructArray.from_arrays([restored([r[0] for r in flat], kind), pa.array([r[1] for r in flat], pa.int64()), pa.array([r[2] for r in flat], pa.int64())], fields=list(slot))
    offsets = [0]
    for o in kept:
        offsets.append(offsets[-1] + len(rows[o]))
    return pa.RecordBatch.from_arrays(
        [
            pa.array(list(kept), pa.int32()),
            pa.array([k.m for k in kept.values()], pa.int32()),
            pa.array([k.n for k in kept.values()], pa.int64()),
            pa.array([k.f_min for k in kept.values()], pa.int64()),
            pa.array([rows[o][0][1] if rows[o] else 0 for o in kept], pa.int64()),
            pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), values),
        ],
        ["owner", "m", "n_seen", "f_min", "f_max", "slots"],
    )


def absorb(routed: DataFrame, stream: DataFrame, m: int, inner: str = "minmax", bulk: bool = True) -> DataFrame:
    """One summary row for each owner that got pairs; the kernel streams over its partition.

    With bulk a kernel takes each batch of pairs at once, combined per element; else in the order in which they come.
    """
    kernel: Callable[[int], Any] = KERNELS[inner]
    weighted = kernel.weighted

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict[int, Any] = {}
        kind = None
        for batch in gathered(batches, ABSORB_ROWS) if bulk and weighted else batches:
            kind = batch.column("e").type
            if bulk and weighted:
                for part in summed(batch):
                    o = part.column("owner")[0].as_py()
                    if o not in kept:
                        kept[o] = kernel(m)
                    kept[o].update_batch(keys(part.column("e").combine_chunks()), part.column("w").to_pylist())
                continue
            for o, e, w in zip(batch.column("owner").to_pylist(), keys(batch.column("e")), batch.column("w").to_pylist(), strict=True):
                own = kept.get(o)
                if own is None:
                    own = kept[o] = kernel(m)
                if weighted:
                    own.update(e, w)
                else:
                    for _ in range(w):
                        own.update(e)
        if kept:
            yield summary_batch(kept, kind)

    return routed.mapInArrow(run, summary_schema(stream))


def build_summary(stream: DataFrame, spec: SupportSpec, inner: str = "minmax", how: str = "hash", bounds: list | None = None, deterministic: bool = False, mode: str = "batch") -> DataFrame:
    """The stream's summary: (owner, m, n_seen, f_min, f_max, slots), at most 1 / eps slots in all.

    mode 'direct' leaves the buffers out: arrivals go to their owners as they are. The bucket list,
    which takes no weights, gets them in no other way. The summary is kept, for it is small and
    every query reads it; lost parts are computed again.
    """
    if mode == "direct" or not KERNELS[inner].weighted:
        pairs = with_owner(stream, spec, how, bounds).select("owner", F.spark_partition_id().alias("src"), F.lit(0).cast("long").alias("seq"), "e", "w")
    else:
        pairs = handover(stream, spec, mode, how, bounds)
    # without buffers nothing is combined: the kernels see arrivals as they come
    return keep(absorb(route(pairs, spec.owners, deterministic), stream, spec.per_owner(), inner, bulk=mode != "direct" and not deterministic))


def build_with_pending(stream: DataFrame, spec: SupportSpec, inner: str = "minmax", mode: str = "batch") -> tuple[DataFrame, DataFrame]:
    """The summary of what was handed over by a trigger, and the pairs (e, w) that still wait: `query` takes both."""
    pairs = keep(handover(stream, spec, mode, mark_rest=True))
    summary = keep(absorb(route(pairs.filter("seq >= 0"), spec.owners), stream, spec.per_owner(), inner))
    return summary, pairs.filter("seq < 0").select("e", "w")


def worker_totals(pairs: DataFrame) -> DataFrame:
    """(src, n, handovers): arrivals and hand-overs of each worker, from its pairs."""
    return pairs.groupBy("src").agg(F.sum("w").alias("n"), F.countDistinct("seq").alias("handovers"))


def drift(left: DataFrame, right: DataFrame) -> DataFrame:
    """(owner, e, before, after): estimates of each element in two summaries with the same owners, null where it has no slot."""
    kind = left.schema["slots"].dataType.elementType["e"].dataType
    schema = T.StructType([T.StructField("owner", T.IntegerType()), T.StructField("e", kind), T.StructField("before", T.LongType()), T.StructField("after", T.LongType())])

    def run(key: tuple, a: pa.Table, b: pa.Table) -> pa.Table:
        rows = [{s["e"]: s["est"] for x in side.column("slots").to_pylist() for s in x} for side in (a, b)]
        elements = list(dict.fromkeys([*rows[0], *rows[1]]))
        return pa.table([pa.repeat(key[0], len(elements)), pa.array(elements), pa.array([rows[0].get(e) for e in elements], pa.int64()), pa.array([rows[1].get(e) for e in elements], pa.int64())], ["owner", "e", "before", "after"])

    slim = lambda x: x.select("owner", "slots").groupBy("owner")
    return slim(left).cogroup(slim(right)).applyInArrow(run, schema)


def stream_length(summary: DataFrame) -> DataFrame:
    return summary.agg(F.coalesce(F.sum("n_seen"), F.lit(0)).alias("n"))


def slots(summary: DataFrame) -> DataFrame:
    return summary.select("owner", "f_min", F.explode("slots").alias("s")).select("owner", "f_min", "s.e", "s.est", "s.over")


def query(summary: DataFrame, phi, n: int | None = None, inclusive: bool = False, pending: DataFrame | None = None) -> DataFrame:
    """(e, est, lower, upper) of the slots above phi * N: a filter and a union, no merge.

    Owners whose greatest count doesn't pass are left out before their slots are read. pending, pairs (e, w)
    still in buffers, is counted in where given: the form without the query enhancement.
    """
    total = summary.sparkSession.range(1).select(F.lit(n).cast("long").alias("n")) if n is not None else stream_length(summary)
    if pending is not None:
        waiting = pending.groupBy("e").agg(F.sum("w").alias("waiting"))
        total = total.crossJoin(pending.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("more"))).select((F.col("n") + F.col("more")).alias("n")) if n is None else total
        found = slots(summary).join(waiting, "e", "full_outer").select("e", (F.coalesce("est", F.lit(0)) + F.coalesce("waiting", F.lit(0))).alias("est"), F.coalesce("over", F.lit(0)).alias("over"))
        kept = found.crossJoin(F.broadcast(total))
    else:
        reach = summary.crossJoin(F.broadcast(total)).filter(over_threshold("f_max", "n", phi, inclusive))
        kept = reach.select("n", F.explode("slots").alias("s")).select("n", "s.e", "s.est", "s.over")
    return kept.filter(over_threshold("est", "n", phi, inclusive)).select("e", "est", (F.col("est") - F.col("over")).alias("lower"), F.col("est").alias("upper"))


def frequent(stream: DataFrame, spec: SupportSpec, **options) -> DataFrame:
    """The approximate frequent elements of a stream (e, w)."""
    return query(build_summary(stream, spec, **options), spec.phi)


def top_k(summary: DataFrame, k: int) -> DataFrame:
    return slots(summary).select("e", "est", (F.col("est") - F.col("over")).alias("lower")).orderBy(F.desc("est"), "e").limit(k)


def estimate(summary: DataFrame, elements: DataFrame, spec: SupportSpec) -> DataFrame:
    """(e, lower, upper) of given elements; one without a slot has at most its owner's least count."""
    asked = with_owner(elements.select("e").distinct(), spec)
    least = summary.select("owner", "f_min")
    held = slots(summary).select("e", "est", "over")
    return asked.join(held, "e", "left").join(F.broadcast(least), "owner", "left").select("e", F.coalesce(F.col("est") - F.col("over"), F.lit(0)).alias("lower"), F.coalesce("est", "f_min", F.lit(0)).alias("upper"))


def certify(summary: DataFrame, spec: SupportSpec) -> DataFrame:
    """One row: n, the greatest f_min, and what it proves.

    'full': within floor(eps * N), so estimates and answers have their bounds. 'recall': within phi * N,
    so nothing frequent is missed, but some below (phi - eps) * N may be reported. Else 'none'.
    """
    eps, phi = spec.eps, spec.phi
    one = summary.agg(F.coalesce(F.sum("n_seen"), F.lit(0)).alias("n"), F.coalesce(F.max("f_min"), F.lit(0)).alias("f_min"))
    within = lambda x: F.col("f_min").cast("decimal(38,0)") * x.denominator <= F.col("n").cast("decimal(38,0)") * x.numerator
    return one.withColumn("level", F.when(within(eps), "full").when(within(phi), "recall").otherwise("none"))


def frequent_certified(stream: DataFrame, spec: SupportSpec, doublings: int | None = None, **options) -> tuple[DataFrame, str]:
    """The answer with the level that its summary proves, counters being doubled until that is full.

    It is full at the latest when an owner has a counter for each of its elements; doublings is a caller's own limit.
    """
    from dataclasses import replace

    while True:
        summary = build_summary(stream, spec, **options)
        level = certify(summary, spec).first()["level"]
        if level == "full" or doublings == 0:
            break
        drop(summary)
        doublings = None if doublings is None else doublings - 1
        spec = replace(spec, counters=2 * spec.per_owner())
    return query(summary, spec.phi), level


def verify_exact(stream: DataFrame, answer: DataFrame, phi, n_rows: int | None = None, most_broadcast: int = 1_000_000) -> DataFrame:
    """(e, f) of the answer's elements that are truly frequent, by a second pass over the stream.

    An answer has at most 1 / (phi - eps) elements. It is broadcast where the caller gives that bound or a count and it
    is small; else the size that the run finds decides.
    """
    few = answer.select("e")
    if n_rows is not None and n_rows <= most_broadcast:
        few = F.broadcast(few)
    counts = stream.join(few, "e", "left_semi").groupBy("e").agg(F.sum("w").alias("f"))
    n = stream.agg(F.sum("w").alias("n"))
    return counts.crossJoin(F.broadcast(n)).filter(over_threshold("f", "n", phi)).select("e", "f")


def combine(left: DataFrame, right: DataFrame) -> DataFrame:
    """One summary of two made with the same owners and size: estimates add up, an absent side adds its f_min."""
    sides = []
    for k, side in enumerate((left, right)):
        sides.append(slots(side).select("owner", "e", F.col("est").alias(f"est{k}"), F.col("over").alias(f"over{k}")))
    least = left.select("owner", "m", F.col("n_seen").alias("n0"), F.col("f_min").alias("least0")).join(right.select("owner", F.col("m").alias("m1"), F.col("n_seen").alias("n1"), F.col("f_min").alias("least1")), "owner", "full_outer")
    both = sides[0].join(sides[1], ["owner", "e"], "full_outer").join(F.broadcast(least), "owner")
    value = lambda name, k: F.coalesce(f"{name}{k}", f"least{k}", F.lit(0))
    rows = both.select("owner", F.coalesce("m", "m1").alias("m"), (F.coalesce("n0", F.lit(0)) + F.coalesce("n1", F.lit(0))).alias("n_seen"), (F.coalesce("least0", F.lit(0)) + F.coalesce("least1", F.lit(0))).alias("floor"), F.struct((value("est", 0) + value("est", 1)).alias("est"), "e", (value("over", 0) + value("over", 1)).alias("over")).alias("s"))
    grouped = rows.groupBy("owner", "m", "n_seen", "floor").agg(F.sort_array(F.collect_list("s"), asc=False).alias("all"))
    top = F.transform(F.slice("all", F.lit(1), F.col("m")), lambda s: F.struct(s["e"].alias("e"), s["est"].alias("est"), s["over"].alias("over")))
    thrown = F.when(F.size("all") > F.col("m"), F.col("all")[F.col("m")]["est"]).otherwise(F.lit(0))
    return grouped.select("owner", "m", "n_seen", F.greatest(F.col("floor"), thrown).alias("f_min"), F.col("all")[0]["est"].alias("f_max"), top.alias("slots"))


def frequent_by(stream: DataFrame, by: list[str], phi, m: int, inner: str = "minmax", owners: int = 8, slots: int = 4096, every: int = 100_000) -> DataFrame:
    """Frequent elements within each group of the columns by: (by..., e, est, lower).

    A group is split among owners as a whole stream is: its elements are combined in bounded buffers and handed over to
    summaries of m counters for each (group, owner), so that a group that holds most arrivals isn't one task. What a
    group's owners have above phi of the group's arrivals is its answer.
    """
    spec = SupportSpec(phi, owners=owners, slots=slots, every=every)
    parts = [f"e.`{f.name}`" for f in stream.schema["e"].dataType.fields] if isinstance(stream.schema["e"].dataType, T.StructType) else ["e"]
    keyed = stream.select(F.struct(*[F.col(b).alias(f"by{i}") for i, b in enumerate(by)], *[F.col(p).alias(f"e{i}") for i, p in enumerate(parts)]).alias("e"), "w")
    element = F.col("e.e0") if parts == ["e"] else F.struct(*[F.col(f"e.e{i}").alias(f.name) for i, f in enumerate(stream.schema["e"].dataType.fields)])
    pairs = handover(keyed, spec).select(*[F.col(f"e.by{i}").alias(f"by{i}") for i in range(len(by))], "owner", element.alias("e"), "w")
    groups = [f"by{i}" for i in range(len(by))]
    slot = T.StructType([T.StructField("e", stream.schema["e"].dataType), T.StructField("est", T.LongType()), T.StructField("over", T.LongType())])
    schema = T.StructType([*[T.StructField(g, stream.schema[b].dataType) for g, b in zip(groups, by, strict=True)], T.StructField("n_seen", T.LongType()), T.StructField("slots", T.ArrayType(slot))])
    kernel = KERNELS[inner]

    def run(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, kind = kernel(m), None
        for batch in gathered(batches, ABSORB_ROWS):
            kind = batch.column("e").type
            for part in summed(batch):
                own.update_batch(keys(part.column("e").combine_chunks()), part.column("w").to_pylist())
        made = summary_batch({0: own}, kind)
        yield pa.RecordBatch.from_arrays([*[pa.repeat(k, 1) for k in key[: len(groups)]], made.column("n_seen"), made.column("slots")], [f.name for f in schema.fields])

    summaries = keep(pairs.groupBy(*groups, "owner").applyInArrow(run, schema))
    totals = summaries.groupBy(*groups).agg(F.sum("n_seen").alias("n")).select(*[F.col(g).alias(f"t_{g}") for g in groups], "n")
    on = [F.col(g).eqNullSafe(F.col(f"t_{g}")) for g in groups]
    held = summaries.join(totals, on).select(*[F.col(g).alias(b) for g, b in zip(groups, by, strict=True)], "n", F.explode("slots").alias("s"))
    return held.select(*by, "n", "s.e", "s.est", (F.col("s.est") - F.col("s.over")).alias("lower")).filter(over_threshold("est", "n", phi)).drop("n")

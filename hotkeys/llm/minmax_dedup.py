"""Near-dedup by min-max hashing over word shingles, with every link confirmed on the full sets.

Each hash function gives two signature values, the least and the greatest hash of a set: 126
functions make 252 values, cut into 42 bands of 6. Two sets at the threshold of 0.8 share no band
with a chance under 4e-6. Texts with the same shingle set are one class from the start and only
its smallest id goes on, so groups of copies add no work.

In a band's bucket every class is compared with the bucket's smallest id (partial aggregates find
it, so a crowded bucket is no hot key). Links join classes to components; then only the buckets
that still hold several components matter. There all pairs across components are weighed on byte
signatures, in blocks of bounded size, and the likely ones confirmed until their components are
joined. So no link between buckets' members is lost and no group is expanded into all of its pairs.

Sets are 64-bit shingle hashes. Defined results: null or wordless text has an empty set, links with
nothing and is its own component; fewer words than a shingle make one shingle; rows with a null
id are not compared: they are linked with nothing, have a null component and are kept; rows that repeat an
id share its fate; other columns are not touched.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotkeys.llm.common import sized_broadcast, table, text_of, written
from hotkeys.llm.components import components

FUNCTIONS, BANDS, ROWS = 126, 42, 6
#: Least share of equal signature bytes with which a pair is worth confirming. A pair at the threshold has fewer
#: with a chance of 2e-13 (binomial), far under that of sharing no band.
LIKELY = 0.6
#: Rows of one shingle set from which on its class travels to the rows instead of the rows to one task.
HOT_ROWS = 1_000
BLOCK = 1_500
MAX_KNOWN = 100_000
_RANDOM = np.random.Generator(np.random.PCG64(20240917))
_FACTORS = _RANDOM.integers(0, 1 << 64, 2 * FUNCTIONS, np.uint64, endpoint=False) | np.uint64(1)
_WORD_FACTORS = _RANDOM.integers(0, 1 << 64, 64, np.uint64, endpoint=False) | np.uint64(1)
_BAND_FACTORS = _RANDOM.integers(0, 1 << 64, ROWS, np.uint64, endpoint=False) | np.uint64(1)
#: Multipliers of a public 64-bit mixing function.
_MIX = (np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _MIX[0]
    x = (x ^ (x >> np.uint64(27))) * _MIX[1]
    return x ^ (x >> np.uint64(31))


class _Words(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > MAX_KNOWN:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


def shingle_sets(texts: list[str], k: int, known: _Words) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of the k-word shingles of each text; known is a task's table of word hashes."""
    words = [t.encode("utf-8", "surrogatepass").lower().split() for t in texts]  # of bytes: A-Z and ASCII white space only
    out = []
    for ws in words:
        n = len(ws)
        if not n:
            out.append(np.empty(0, np.uint64))
            continue
        h = np.fromiter(map(known.__getitem__, ws), np.uint64, n)
        if n < k:
            k_own = n
            h = h + np.uint64(n)
        else:
            k_own = k
        s = h[: n - k_own + 1] * _WORD_FACTORS[0]
        for j in range(1, k_own):
            s = s + h[j : n - k_own + 1 + j] * _WORD_FACTORS[j]
        out.append(np.unique(mixed(s)))
    return out


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """Least and greatest value of every hash function over each (nonempty) set."""
    out = np.empty((len(sets), 2 * FUNCTIONS), np.uint64)
    at = 0
    while at < len(sets):
        end, size = at, 0
        while end < len(sets) and (size < 32_768 or end == at):
            size += len(sets[end])
            end += 1
        flat = np.concatenate(sets[at:end])
        starts = np.cumsum([0, *map(len, sets[at : end - 1])])
        value = np.empty_like(flat)
        for f in range(FUNCTIONS):
            np.multiply(flat, _FACTORS[f], out=value)
            value ^= value >> np.uint64(32)
            value *= _FACTORS[FUNCTIONS + f]
            out[at:end, f] = np.minimum.reduceat(value, starts)
            out[at:end, FUNCTIONS + f] = np.maximum.reduceat(value, starts)
        at = end
    return out


def band_keys(found: np.ndarray) -> np.ndarray:
    """A 64-bit key for each band of each signature; the band's number is part of it."""
    rows = found.reshape(len(found), BANDS, ROWS)
    key = (rows * _BAND_FACTORS).sum(axis=2, dtype=np.uint64) + np.arange(1, BANDS + 1, dtype=np.uint64) * _MIX[0]
    return mixed(key).view(np.int64)


def signature_bytes(found: np.ndarray) -> np.ndarray:
    return (mixed(found) & np.uint64(0xFF)).astype(np.uint8)


def sketches(docs: DataFrame, k: int, id_col: str, text_col: str) -> DataFrame:
    """id, n (set size), set_hi and set_lo (128-bit digest of the set), bands and sig."""
    asked = docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), text_of(text_col).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = _Words()
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                sets = shingle_sets(part.column("text").to_pylist(), k, words)
                full = [i for i, s in enumerate(sets) if len(s)]
                digests = np.zeros((len(sets), 2), np.int64)
                bands: list[np.ndarray | None] = [None] * len(sets)
                sig: list[bytes | None] = [None] * len(sets)
                if full:
                    found = signatures([sets[i] for i in full])
                    keys, low = band_keys(found), signature_bytes(found)
                    for row, i in enumerate(full):
                        digests[i] = np.frombuffer(xxhash.xxh3_128_digest(sets[i].tobytes()), np.int64)
                        bands[i], sig[i] = keys[row], low[row].tobytes()
                yield pa.RecordBatch.from_arrays(
                    [part.column("id"), pa.array([len(s) for s in sets], pa.int64()), pa.array(digests[:, 0]), pa.array(digests[:, 1]), pa.array(bands, pa.list_(pa.int64())), pa.array(sig, pa.binary())],
                    ["id", "n", "set_hi", "set_lo", "bands", "sig"],
                )

    return asked.mapInArrow(run, "id long, n long, set_hi long, set_lo long, bands array<long>, sig binary")


def _fits(a: str, b: str, percent: int) -> str:
    """Sets of these sizes can reach the similarity at all."""
    return f"100 * least({a}, {b}) >= {percent} * greatest({a}, {b})"


def confirmed(pairs: DataFrame, texts: DataFrame, k: int, percent: int) -> DataFrame:
    """Of the pairs (a, b) those whose full sets reach the similarity, as links (u, v)."""
    second = pairs.join(texts.select(F.col("id").alias("b"), F.col("text").alias("text_b")), "b")
    both = second.join(texts.select(F.col("id").alias("a"), F.col("text").alias("text_a")), "a").select("a", "b", "text_a", "text_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict[int, np.ndarray] = {}
        words = _Words()
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                a, b = part.column("a").to_pylist(), part.column("b").to_pylist()
                if len(kept) > 2_000:
                    kept = {}
                for ids, column in ((a, "text_a"), (b, "text_b")):
                    new = {i: row for row, i in enumerate(ids) if i not in kept}
                    column_texts = part.column(column)
                    kept.update(zip(new, shingle_sets([column_texts[row].as_py() for row in new.values()], k, words), strict=True))
                u, v = [], []
                for x, y in zip(a, b, strict=True):
                    s, t = kept[x], kept[y]
                    common = len(s) + len(t) - len(np.union1d(s, t))
                    if 100 * common >= percent * (len(s) + len(t) - common) and common:
                        u.append(x)
                        v.append(y)
                yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

    return both.mapInArrow(run, "u long, v long")


def full_sets(texts: DataFrame, k: int) -> DataFrame:
    """(id, members): the sorted shingle hashes of each text, packed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = _Words()
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                sets = shingle_sets(part.column("text").to_pylist(), k, words)
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array([s.tobytes() for s in sets], pa.binary())], ["id", "members"])

    return texts.mapInArrow(run, "id long, members binary")


def links_across(crowded: DataFrame, percent: int) -> DataFrame:
    """Links (u, v) between components that meet in a bucket, confirmed on the full sets.

    crowded: key, band, id, component, n, sig, bands, members. A bucket is cut into blocks by a hash
    of the id, and each pair of blocks is one group, so a group never holds more than about two
    blocks. A pair is weighed in the first band that it shares, and confirmed, the most alike first,
    unless links found before it have already joined its components.
    """
    sizes = crowded.groupBy("key").agg(F.count("*").alias("k"))
    blocks = F.ceil(F.col("k") / BLOCK).cast("int")
    placed = crowded.join(sizes, "key").withColumn("blocks", blocks).withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    spread = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    grouped = spread.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "band", "own", "id", "component", "n", "sig", "bands", "members")

    def run(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(list(batches))
        i, j, band = key[1].as_py(), key[2].as_py(), rows.column("band")[0].as_py()
        own, ids, component, n = (rows.column(c).to_numpy() for c in ("own", "id", "component", "n"))
        sig = np.frombuffer(b"".join(rows.column("sig").to_pylist()), np.uint8).reshape(len(ids), 2 * FUNCTIONS)
        before = np.stack(rows.column("bands").to_numpy(zero_copy_only=False))[:, :band]
        members = rows.column("members").to_pylist()
        right = np.flatnonzero(own == j)
        left_side, right_side, alike = [], [], []
        for x in np.flatnonzero(own == i):
            rest = right[(component[right] != component[x]) & (100 * np.minimum(n[right], n[x]) >= percent * np.maximum(n[right], n[x])) & ((ids[right] > ids[x]) if i == j else True)]
            if len(rest):
                rest = rest[~(before[rest] == before[x]).any(axis=1)]
                same = (sig[rest] == sig[x]).sum(axis=1)
                hit = same >= LIKELY * 2 * FUNCTIONS
                if hit.any():
                    left_side.append(np.full(int(hit.sum()), x))
                    right_side.append(rest[hit])
                    alike.append(same[hit])
        if not alike:
            return
        x, y, same = np.concatenate(left_side), np.concatenate(right_side), np.concatenate(alike)
        joined: dict[int, int] = {}

        def root(c: int) -> int:
            while c in joined:
                c = joined[c]
            return c

        u, v = [], []
        for at in np.argsort(-same, kind="stable"):
            a, b = root(int(component[x[at]])), root(int(component[y[at]]))
            if a != b:
                s, t = np.frombuffer(members[x[at]], np.uint64), np.frombuffer(members[y[at]], np.uint64)
                common = len(np.intersect1d(s, t, assume_unique=True))
                if 100 * common >= percent * (len(s) + len(t) - common):
                    joined[max(a, b)] = min(a, b)
                    u.append(int(ids[x[at]]))
                    v.append(int(ids[y[at]]))
        if u:
            yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

    return grouped.groupBy("key", "i", "j").applyInArrow(run, "u long, v long").distinct()


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_shingles and component of every row; needs no order among rows."""
    spark = docs.sparkSession
    rows = written(spark, sketches(docs, k, id_col, text_col), "sketches")
    made = rows.filter("n > 0 AND id IS NOT NULL")
    classes = written(spark, made.groupBy("set_hi", "set_lo").agg(F.min("id").alias("rep"), F.count("*").alias("size")), "set-classes")
    reps = made.join(classes.select(F.col("rep").alias("id")), "id", "left_semi").select("id", "n", "bands", "sig")
    banded = reps.select("id", "n", F.posexplode("bands").alias("band", "key"))
    leaders = banded.groupBy("key").agg(F.min(F.struct("id", "n")).alias("lead"), F.count("*").alias("k")).filter("k > 1")
    shared = written(spark, banded.join(leaders, "key").select("key", "band", "id", "n", "k", F.col("lead.id").alias("lead"), F.col("lead.n").alias("lead_n")), "shared-bands")
    pairs = written(spark, shared.filter("id <> lead AND " + _fits("n", "lead_n", percent)).select(F.col("lead").alias("a"), F.col("id").alias("b")).distinct(), "leader-pairs")
    own = docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), text_of(text_col).alias("text")).filter("id IS NOT NULL")

    def texts_of(ids: DataFrame) -> DataFrame:
        return own.join(sized_broadcast(ids, ids.count(), 500_000), "id", "left_semi")

    involved = written(spark, pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct(), "involved")
    links = written(spark, confirmed(pairs, texts_of(involved), k, percent), "links")
    first = written(spark, components(spark, links), "components")
    labelled = shared.filter("k > 2").join(first, "id", "left").select("key", "band", "id", "n", F.coalesce("component", "id").alias("component"))
    several = labelled.groupBy("key").agg(F.min("component").alias("low"), F.max("component").alias("high")).filter("low <> high").select("key")
    crowded = written(spark, labelled.join(several, "key"), "crowded")
    rest = written(spark, crowded.select("id").distinct(), "crowded-ids")
    known = made.select("id", "sig", "bands").dropDuplicates(["id"]).join(full_sets(texts_of(rest).dropDuplicates(["id"]), k), "id")
    more = written(spark, links_across(crowded.join(known, "id"), percent), "more-links")
    final = first if more.isEmpty() else written(spark, components(spark, links.union(more)), "components")
    digest = ["set_hi", "set_lo"]
    by_class = classes.join(final.withColumnRenamed("id", "rep"), "rep", "left").select(*digest, "size", F.coalesce("component", "rep").alias("component"))
    hot = written(spark, by_class.filter(F.col("size") >= HOT_ROWS), "hot-classes")  # at most one for each HOT_ROWS rows
    n_hot = hot.count()
    slim = made.select("id", "n", *digest)
    if n_hot:
        few = sized_broadcast(hot, n_hot, 500_000)
        cold = slim.join(few.select(*digest), digest, "left_anti").join(by_class.filter(F.col("size") < HOT_ROWS), digest)
        joined = slim.join(few, digest).select("id", "n", "component").unionByName(cold.select("id", "n", "component"))
    else:
        joined = slim.join(by_class, digest).select("id", "n", "component")
    alone = rows.filter("n = 0 OR id IS NULL").select("id", "n", F.col("id").alias("component"))
    return joined.unionByName(alone).select("id", F.col("n").alias("n_shingles"), "component")


def kept_rows(docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each component, with the columns of docs."""
    spark = docs.sparkSession
    gone = written(spark, near_duplicates(docs, k, percent, id_col, text_col).filter("id <> component").select(F.col("id").alias("gone")).distinct(), "near-copies")
    # the input's row stays apart, whatever its names are
    rows = docs.select(F.struct("*").alias("row"))
    left = rows.join(sized_broadcast(gone, gone.count(), 500_000), F.col(f"row.`{id_col}`").cast("long") == F.col("gone"), "left_anti")
    return left.select(*[F.col(f"row.`{c}`") for c in docs.columns])


def op9_minmax_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"), k=4)
    return found.select(F.col("id").alias("doc_id"), "n_shingles", F.col("component").alias("component_id"), F.col("id").eqNullSafe(F.col("component")).alias("kept"))

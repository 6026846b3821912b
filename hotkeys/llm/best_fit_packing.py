"""Best-fit packing by bin completion.

Documents become pieces of at most `capacity` tokens. How pieces are packed depends on nothing but
how many there are of each length, and there are at most `capacity` lengths: the driver solves that
histogram, whatever the corpus' size. Bin completion takes the longest piece left, enumerates the
undominated fillings of what it leaves free, and branches over them, least waste first; a branch is
cut once its waste so far exceeds what would still beat the incumbent, which starts as the best-fit
solution. A filling is laid as often as the counts allow, so the plan has few patterns. Pieces then
get ranks within their length (salted, so that a common length is no hot key), and a rank names
the sequence and the place there.

Defined results: null counts as empty and gives one piece, the end id alone; ties between pieces
of a length are broken by doc_id, piece and ids; repeated rows are packed each; an empty table gives
an empty table; other columns are not read.
"""

from __future__ import annotations

import os
import zlib
from array import array
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from hotkeys.llm.common import table, text_of, written

CAPACITY = 4096
MAX_KNOWN = 700_000
#: Steps of the search after which the incumbent is the answer; `packed` tells whether it is proved best, and with
#: None for this and BRANCHES searches on until it is.
SEARCH_STEPS = 20_000
#: Fillings branched over for one piece, the least waste first.
BRANCHES = 4
SALT_ROWS = 20_000
Pattern = tuple[tuple[int, ...], int]


def _spaced(text: str) -> str:
    """text with a space for every other ASCII white-space character."""
    for white in "\n\t\r\x0b\x0c":
        text = text.replace(white, " ")
    return text


class WordIds(dict):
    """Ids of texts by a tokenizer whose tokens never cross white space; known words are kept.

    A new word is first brought to the form that it shares with others: Latin-1 words to lower case, as the
    tokenizer does, and without the one comma or full stop behind a letter, which is a token of its own.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        super().__init__()
        self.tokenizer = Tokenizer.from_file(path)
        self[""] = b""

    def _encoded(self, word: str) -> bytes:
        return array("I", self.tokenizer.encode(word, add_special_tokens=False).ids).tobytes()

    def __missing__(self, word: str) -> bytes:
        plain = (word.isascii() or max(word) <= "\xff") and "<|" not in word
        base = word.lower() if plain else word
        tail = ""
        if plain and len(base) > 1 and base[-1] in ".," and "a" <= base[-2] <= "z":
            base, tail = base[:-1], base[-1]
        found = self.get(base)
        new = found is None
        if new:
            found = self._encoded(base)
            if len(self) > MAX_KNOWN:
                self.clear()
                self[""] = b""
            self[base] = found
        if tail:
            found += self[tail]
        if not new:  # forms of a word that came before are worth keeping, those of most words aren't
            self[word] = found
        return found

    def packed(self, texts: list[str]) -> list[bytes]:
        """Native (little-endian) unsigned 32-bit ids of each text."""
        get = self.__getitem__
        return [b"".join(map(get, _spaced(t).split(" "))) for t in texts]


_WORDS: dict[str, WordIds] = {}


def word_ids(path: str) -> WordIds:
    if path not in _WORDS:
        _WORDS[path] = WordIds(path)
    return _WORDS[path]


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, piece, start, length and ids_crc32 of every piece; no shuffle."""
    asked = docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text"))
    id_type = asked.schema["id"].dataType.simpleString()
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = word_ids(tokenizer)
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                rows, number, start, length, crc = [], [], [], [], []
                for row, ids in enumerate(own.packed(part.column("text").to_pylist())):
                    ids += end
                    for k, lo in enumerate(range(0, len(ids), 4 * capacity)):
                        cut = ids[lo : lo + 4 * capacity]
                        rows.append(row)
                        number.append(k)
                        start.append(lo // 4)
                        length.append(len(cut) // 4)
                        crc.append(zlib.crc32(cut))
                long = lambda x: pa.array(x, pa.int64())
                yield pa.RecordBatch.from_arrays([part.column("id").take(pa.array(rows, pa.int32())), pa.array(number, pa.int32()), long(start), long(length), long(crc)], ["id", "piece", "start", "length", "ids_crc32"])

    return asked.mapInArrow(run, f"id {id_type}, piece int, start long, length long, ids_crc32 long")


def best_fit(counts: dict[int, int], capacity: int) -> list[Pattern]:
    """Best-fit decreasing over counts: each bin is opened by the longest piece left and filled greedily."""
    left = Counter({k: n for k, n in counts.items() if n > 0})
    lengths = sorted(left)
    out: list[Pattern] = []
    while lengths:
        filling, free = [], capacity
        used: Counter[int] = Counter()
        at = len(lengths) - 1
        while at >= 0:
            length = lengths[at]
            if length <= free and used[length] < left[length]:
                take = min(free // length, left[length] - used[length])
                filling += [length] * take
                used[length] += take
                free -= take * length
            at = min(at - 1, bisect_right(lengths, free) - 1)
        times = min(left[k] // n for k, n in used.items())
        out.append((tuple(filling), times))
        for k, n in used.items():
            left[k] -= n * times
        lengths = [k for k in lengths if left[k] > 0]
    return out


def fillings(left: dict[int, int], lengths: list[int], free: int, limit: int | None) -> tuple[list[tuple[int, tuple[int, ...]]], bool]:
    """Undominated fillings of free, least waste first, as (waste, lengths), and whether these are all.

    Only fillings into which nothing left fits are kept, and of these the ones in which no single
    piece could give way to a longer one; a filling without waste ends the search. With a limit that many are
    returned, from the first that are met, and each level tries that many lengths.
    """
    found: dict[tuple[int, ...], int] = {}
    steps, whole = 0, True

    def dominated(filling: tuple[int, ...], waste: int) -> bool:
        used = Counter(filling)
        for length in used:
            better = bisect_right(lengths, length + waste) - 1
            while better >= 0 and lengths[better] > length:
                if left[lengths[better]] > used[lengths[better]]:
                    return True
                better -= 1
        return False

    def search(at: int, room: int, filling: tuple[int, ...], used: Counter[int]) -> bool:
        """True when the search may stop."""
        nonlocal steps, whole
        steps += 1
        at = min(at, bisect_right(lengths, room) - 1)
        tries = 0
        for i in range(at, -1, -1):
            length = lengths[i]
            if left[length] - used[length] <= 0:
                continue
            if limit is not None and (tries >= limit or steps > 60 * limit and tries):
                whole = False
                break
            used[length] += 1
            stop = search(i, room - length, (*filling, length), used)
            used[length] -= 1
            tries += 1
            if stop:
                return True
        # in descending order a shorter piece may still fit where it was passed over: then nothing is full
        if not any(length <= room and left[length] > used[length] for length in lengths[: bisect_right(lengths, room)]):
            if not dominated(filling, room):
                found[filling] = room
            if limit is None:
                return False
            if len(found) >= 8 * limit:
                whole = False
            return room == 0 or len(found) >= 8 * limit
        return False

    search(len(lengths) - 1, free, (), Counter())
    best = sorted((waste, filling) for filling, waste in found.items())
    if best and not best[0][0] and limit is not None:
        whole = whole and len(best) <= limit
    return (best, whole) if limit is None else (best[:limit], whole and len(best) <= limit)


@dataclass(frozen=True)
class Packing:
    """A plan, its bins, the least number that any plan needs, and whether the plan is known to have the fewest."""

    plan: list[Pattern]
    bins: int
    least: int
    proved: bool


def packed(counts: dict[int, int], capacity: int = CAPACITY, steps: int | None = SEARCH_STEPS, branches: int | None = BRANCHES) -> Packing:
    """Patterns (lengths, how often) that use every piece once, in as few bins as the search finds.

    With steps and branches None the search is exact: every undominated filling of every bin, laid once at a
    time. Otherwise fillings are laid as often as the counts allow, and what is cut off shows in `proved`.
    """
    counts = {k: n for k, n in counts.items() if n > 0}
    if not counts:
        return Packing([], 0, 0, True)
    best = best_fit(counts, capacity)
    best_bins = sum(n for _, n in best)
    total = sum(k * n for k, n in counts.items())
    least = max(-(-total // capacity), sum(n for k, n in counts.items() if 2 * k > capacity))
    whole, exact = True, steps is None and branches is None
    seen: dict[tuple, int] = {}
    stack: list[tuple[dict[int, int], list[int], int, int, list[Pattern]]] = [(counts, sorted(counts), 0, 0, [])]
    while stack and best_bins > least:
        if steps is not None and steps <= 0:
            whole = False
            break
        left, lengths, waste, bins, plan = stack.pop()
        if not lengths:
            if bins < best_bins:
                best, best_bins = plan, bins
            continue
        if waste > (best_bins - 1) * capacity - total:
            continue
        if exact:
            state = tuple((k, left[k]) for k in lengths)
            if seen.get(state, best_bins) <= bins:
                continue
            seen[state] = bins
        longest = lengths[-1]
        rest = dict(left)
        rest[longest] -= 1
        options, all_of_them = fillings(rest, lengths, capacity - longest, branches)
        whole = whole and all_of_them
        for lost, filling in reversed(options or [(capacity - longest, ())]):  # the least waste is popped first
            used = Counter((longest, *filling))
            times = 1 if exact else min(left[k] // n for k, n in used.items())
            whole = whole and (times == 1)
            after = dict(left)
            for k, n in used.items():
                after[k] -= n * times
            steps = None if steps is None else steps - 1
            stack.append((after, [k for k in lengths if after[k] > 0], waste + lost * times, bins + times, [*plan, ((longest, *filling), times)]))
    return Packing(best, best_bins, least, best_bins == least or whole)


def pack(counts: dict[int, int], capacity: int = CAPACITY, steps: int | None = SEARCH_STEPS) -> list[Pattern]:
    return packed(counts, capacity, steps).plan


def slots(plan: list[Pattern]) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, end rank, first sequence, offset): which ranks of a length go where."""
    out, taken, base = [], Counter(), 0
    for filling, times in plan:
        offset = 0
        for length in filling:
            out.append((length, taken[length], taken[length] + times, base, offset))
            taken[length] += times
            offset += length
        base += times
    return out


def ranked(made: DataFrame) -> DataFrame:
    """Pieces with their rank, from 0, among those of the same length, without one task for a length."""
    salts = max(8, made.count() // SALT_ROWS)
    salted = made.withColumn("salt", F.pmod(F.xxhash64("id", "piece", "ids_crc32"), F.lit(salts)).cast("int"))
    sums = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    before = sums.select("length", "salt", (F.sum("n").over(W.partitionBy("length").orderBy("salt")) - F.col("n")).alias("before"))
    inner = F.row_number().over(W.partitionBy("length", "salt").orderBy("id", "piece", "ids_crc32")) - 1
    return salted.withColumn("inner", inner).join(before, ["length", "salt"]).withColumn("rank", F.col("before") + F.col("inner")).drop("salt", "inner", "before")


def pack_documents(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row for each piece with its sequence_id and offset."""
    spark = docs.sparkSession
    made = written(spark, pieces(docs, tokenizer, capacity, end_id, id_col, text_col), "pieces")
    counts = {r["length"]: r["n"] for r in made.groupBy("length").agg(F.count("*").alias("n")).collect()}  # capacity rows at most
    placed = sorted(slots(pack(counts, capacity)))
    asked = ranked(made).select("id", "piece", "start", "length", "ids_crc32", "rank")
    id_type = asked.schema["id"].dataType.simpleString()
    columns = np.array(placed, np.int64).reshape(-1, 5).T

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        length, first, _, base, offset = columns
        span = int(columns[2].max(initial=0)) + 1
        keys = length * span + first
        for batch in batches:
            rank = batch.column("rank").to_numpy()
            at = np.searchsorted(keys, batch.column("length").to_numpy() * span + rank, side="right") - 1
            where = [pa.array(base[at] + rank - first[at]), pa.array(offset[at])]
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], *where], ["id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return asked.mapInArrow(run, f"id {id_type}, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long").withColumnRenamed("id", id_col)


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))

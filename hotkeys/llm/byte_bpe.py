"""Byte-level BPE: a lazily determinised transducer encodes, an incremental UTF-8 machine decodes.

Encoding. Any prefix of a merge result is itself a merge result, and a token sequence is one
exactly if each adjacent pair is (two tokens are compatible if merging their joined bytes gives
back the two). So the last token of every prefix is known as soon as the prefix is read, and the
prefixes that a longer text can still build on are those from which the read bytes start some
token. Their chains share a first part; it can't change any more and is emitted. What is left,
the last emitted token and the pending bytes, which some token limits, is the state. States and
moves are made when first met and kept, so later texts only follow table entries.

Decoding. Ids become bytes, and a byte automaton for UTF-8 holds back an unfinished character at
the end of a chunk, so a stream of ids gives whole characters.

The work is per row in Arrow batches without a shuffle; both tables are emptied at a bound.
Defined results: null counts as empty; an empty text has no tokens and the digest of no bytes;
repeated rows are encoded each; other columns are not read.
"""

from __future__ import annotations

import base64
import gc
import re
from array import array
from bisect import insort
from collections.abc import Iterable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotkeys.llm.common import table, text_of

MAX_STATES = 350_000
MAX_KNOWN = 400_000
#: Stands for the end of a pre-token among the bytes.
_END = 256


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in lines if line.strip())}


@contextmanager
def uncollected() -> Iterator[None]:
    """No search for reference cycles meanwhile, nor later in what was made: the tables have none, and are large to go through."""
    was = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        gc.freeze()
        if was:
            gc.enable()


class Merges:
    """Ranks, the strings that tokens start and end with, and which pairs of tokens are compatible.

    A token's id is its rank.
    """

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.by_id = {i: t for t, i in ranks.items()}
        self.size = {i: len(t) for t, i in ranks.items()}
        self.starts = {t[:k] for t in ranks for k in range(1, len(t))}
        #: Ends of tokens: -1, or for a whole token its id, less than -1 until it is proven.
        self.ends = {t[k:]: -1 for t in ranks for k in range(1, len(t))} | {t: -2 - i for t, i in ranks.items()}
        self.pairs: dict[int, bool] = {}
        self.made_of: dict[bytes, tuple[bytes, bytes]] = {}

    def merge(self, data: bytes, least: int = 1) -> list[bytes]:
        """Plain merging until `least` parts, lowest rank first and leftmost among equals."""
        parts = [data[i : i + 1] for i in range(len(data))]
        while len(parts) > least:
            rank, at = min((self.ranks.get(parts[i] + parts[i + 1], 1 << 40), i) for i in range(len(parts) - 1))
            if rank == 1 << 40:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def proven(self, token: bytes) -> int:
        """The token's id if merging its bytes gives the token, else -1; kept in ends."""
        known = self.ends[token] = self.ranks[token] if self.merge(token) == [token] else -1
        return known

    def halves(self, token: bytes) -> tuple[bytes, bytes]:
        """The two tokens whose merge made this one; a single byte has none and gives itself."""
        known = self.made_of.get(token)
        if known is None:
            known = (token, token) if len(token) == 1 else self.merge(token, 2)
            self.made_of[token] = known
        return known

    def compatible(self, left_id: int, right_id: int) -> bool:
        """Whether no merge crosses the seam, looked up along the seam's sides of both merge trees.

        Of the two tokens at the seam the one made later is undone first; a crossing merge
        wins if it ranks before the merge that was undone last.
        """
        if len(self.pairs) > MAX_KNOWN:
            self.pairs.clear()
        ranks, bound, fits = self.ranks, 1 << 40, True
        left, right = self.by_id[left_id], self.by_id[right_id]
        while True:
            if ranks.get(left + right, 1 << 40) < bound:
                fits = False
                break
            if len(left) == 1 and len(right) == 1:
                break
            if len(right) == 1 or len(left) > 1 and ranks[left] > ranks[right]:
                bound, left = ranks[left], self.halves(left)[1]
            else:
                bound, right = ranks[right] + 1, self.halves(right)[0]
        self.pairs[left_id << 32 | right_id] = fits
        return fits


class Transducer:
    """States are (last emitted token, pending bytes); moves give the next state and its output."""

    def __init__(self, merges: Merges):
        self.merges = merges
        self.bytes = [bytes((b,)) for b in range(256)]
        self.clear()

    def clear(self) -> None:
        """States are numbered in steps of 512, so that state + byte is the key of a move.

        chains[k][j] is state k's last token of the first j pending bytes, at 0 the one emitted or -1.
        """
        self.states: dict[tuple[int, bytes], int] = {(-1, b""): 0}
        self.pending: list[bytes] = [b""]
        self.chains: list[list[int | None]] = [[-1]]
        self.moves: dict[int, tuple[int, tuple[int, ...]]] = {}

    def _extend(self, tokens: list[int | None], pending: bytes) -> None:
        """Append to tokens the last token of each longer prefix of pending, given those of the shorter.

        None for a dead prefix: its tokens don't go through the last emitted one, and no longer
        text uses it.
        """
        m = self.merges
        ends, pairs = m.ends, m.pairs
        for end in range(len(tokens), len(pending) + 1):
            found = None
            for start in range(end - 1, -1, -1):
                token = ends.get(pending[start:end])
                if token is None:
                    break
                if token < -1:
                    token = m.proven(pending[start:end])
                left = tokens[start]
                if token < 0 or left is None:
                    continue
                if left >= 0:
                    fits = pairs.get(left << 32 | token)
                    if not (m.compatible(left, token) if fits is None else fits):
                        continue
                found = token
                break
            tokens.append(found)

    def _path(self, tokens: list[int | None], end: int, start: int = 0) -> list[int]:
        """The tokens between `start` and the first `end` pending bytes, in order."""
        size, out = self.merges.size, []
        while end > start:
            out.append(tokens[end])
            end -= size[tokens[end]]
        return out[::-1]

    def _make(self, state: int, byte: int) -> tuple[int, tuple[int, ...]]:
        """The move from a state by a byte or the end, and the state that it leads to if that is new.

        A state's chain is worked out when a move has to emit something, not before.
        """
        pending, tokens = self.pending[state >> 9], self.chains[state >> 9]
        if byte == _END:
            self._extend(tokens, pending)
            return 0, tuple(self._path(tokens, len(pending)))
        pending += self.bytes[byte]
        starts = self.merges.starts
        if pending in starts:  # one token may yet cover all that is pending
            return self._state(pending, tokens), ()
        tokens = list(tokens)
        self._extend(tokens, pending)
        n, size = len(pending), self.merges.size
        live = [k for k in range(1, n + 1) if tokens[k] is not None and (k == n or pending[k:] in starts)]
        cut = live.pop()
        while live:  # the last place that the tokens of all live prefixes share
            cut -= size[tokens[cut]]
            if cut == live[-1]:
                live.pop()
            elif cut < live[-1]:
                live[-1], cut = cut, live[-1]
                if len(live) > 1 and live[-1] <= live[-2]:
                    low = live.pop()
                    if low != live[-1]:
                        insort(live, low)
            if not cut:
                break
        if not cut:
            return self._state(pending, tokens), ()
        chain = [tokens[cut]]
        for k in range(cut + 1, n + 1):
            token = tokens[k]
            at = k - cut - size[token] if token is not None else -1
            chain.append(token if at >= 0 and chain[at] is not None else None)
        return self._state(pending[cut:], chain), tuple(self._path(tokens, cut))

    def _state(self, pending: bytes, chain: list[int | None]) -> int:
        name = (chain[0], pending)
        number = self.states.get(name)
        if number is None:
            number = self.states[name] = len(self.pending) << 9
            self.pending.append(pending)
            self.chains.append(list(chain))
        return number

    def _finish(self, state: int, rest: bytes) -> list[int]:
        """What a state and all bytes behind it still give, without states between."""
        pending, tokens = self.pending[state >> 9] + rest, list(self.chains[state >> 9])
        self._extend(tokens, pending)
        return self._path(tokens, len(pending))

    def encode(self, data: bytes) -> list[int]:
        """Ids of one pre-token: a move for each byte and one for the end.

        The first move that is missing is made and kept. If another one is, the state's chain goes on to the end at once: it is the
        same run without names for its states, which get theirs, one with each visit, as far as texts come back to them.
        """
        if len(self.pending) > MAX_STATES:
            self.clear()
        out: list[int] = []
        state, moves, made = 0, self.moves, False
        for at, byte in enumerate(data):
            move = moves.get(state + byte)
            if move is None:
                if made:
                    return out + self._finish(state, data[at:])
                move = moves[state + byte] = self._make(state, byte)
                made = True
            state = move[0]
            if move[1]:
                out += move[1]
        move = moves.get(state + _END)
        if move is None:
            move = moves[state + _END] = self._make(state, _END)
        out += move[1]
        return out


class Encoder:
    """Splits by the pattern and encodes each match; a table keeps the ids of known matches."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.find_any = regex.compile(pattern).findall
        # in ASCII text letters, digits and white space are these, and the plain engine is faster
        plain = pattern.replace(r"\s\p{L}\p{N}", r"\t-\r A-Za-z0-9").replace(r"\p{L}", "[A-Za-z]").replace(r"\p{N}", "[0-9]").replace(r"\s", r"[\t-\r ]").replace(r"\S", r"[^\t-\r ]")
        self.find_ascii = None if "\\p" in plain else re.compile(plain).findall
        self.ranks = ranks
        self.transducer = Transducer(Merges(ranks))
        encoder = self

        class Known(dict):
            def __missing__(self, piece: str) -> bytes:
                data = piece.encode()
                whole = encoder.ranks.get(data)
                ids = [whole] if whole is not None else encoder.transducer.encode(data)
                packed = array("I", ids).tobytes()
                if len(self) > MAX_KNOWN:
                    self.clear()
                self[piece] = packed
                return packed

        self.known = Known()

    def encode_packed(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        return b"".join(map(self.known.__getitem__, self.find(text)))

    def find(self, text: str) -> list[str]:
        return self.find_ascii(text) if self.find_ascii and text.isascii() else self.find_any(text)

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_packed(text), "<u4").tolist()


class Utf8Machine:
    """Byte automaton of UTF-8: a state is (bytes still due, least and most of the next one)."""

    START = (0, 0, 0)

    @staticmethod
    def step(state: tuple[int, int, int], byte: int) -> tuple[int, int, int] | None:
        """The next state, or None where no UTF-8 text goes on so."""
        due, low, high = state
        if due:
            if not low <= byte <= high:
                return None
            return (due - 1, 0x80, 0xBF) if due > 1 else Utf8Machine.START
        if byte < 0x80:
            return Utf8Machine.START
        if 0xC2 <= byte <= 0xDF:
            return 1, 0x80, 0xBF
        if 0xE0 <= byte <= 0xEF:
            return 2, 0xA0 if byte == 0xE0 else 0x80, 0x9F if byte == 0xED else 0xBF
        if 0xF0 <= byte <= 0xF4:
            return 3, 0x90 if byte == 0xF0 else 0x80, 0x8F if byte == 0xF4 else 0xBF
        return None


class StreamDecoder:
    """Ids in, whole characters out; an unfinished character waits for the next call."""

    def __init__(self, by_id: dict[int, bytes]):
        self.by_id = by_id
        self.held = b""

    def feed(self, ids: Iterable[int]) -> str:
        data = self.held + b"".join(map(self.by_id.__getitem__, ids))
        keep = len(data)
        for back in range(1, min(3, len(data)) + 1):  # an unfinished character has at most three bytes
            if data[-back] >= 0xC0:
                state: tuple[int, int, int] | None = Utf8Machine.START
                for byte in data[-back:]:
                    state = state and Utf8Machine.step(state, byte)
                if state and state[0]:
                    keep = len(data) - back
                break
        self.held = data[keep:]
        return data[:keep].decode("utf-8", "replace")

    def close(self) -> str:
        rest, self.held = self.held, b""
        return rest.decode("utf-8", "replace")


_ENCODERS: dict[tuple[str, str], Encoder] = {}


def encoder(ranks_path: str, pattern: str) -> Encoder:
    """One encoder per worker process, kept between tasks."""
    key = (ranks_path, pattern)
    if key not in _ENCODERS:
        _ENCODERS[key] = Encoder(read_ranks(ranks_path), pattern)
    return _ENCODERS[key]


def encode_documents(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, ids (packed, little-endian unsigned 32-bit) and n_tokens of every row."""
    asked = docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text"))
    id_type = asked.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(ranks_path, pattern)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                with uncollected():
                    packed = [own.encode_packed(t) for t in part.column("text").to_pylist()]
                n = pa.array([len(p) // 4 for p in packed], pa.int64())
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(packed, pa.binary()), n], ["id", "ids", "n_tokens"])

    return asked.mapInArrow(run, f"id {id_type}, ids binary, n_tokens long").withColumnRenamed("id", id_col)


def _decoded(by_id: dict[int, bytes], packed: bytes, chunk: int) -> str:
    """The text of packed ids, decoded as a stream of chunks."""
    ids, stream = np.frombuffer(packed, "<u4").tolist(), StreamDecoder(by_id)
    return "".join([stream.feed(ids[at : at + chunk]) for at in range(0, len(ids), chunk)]) + stream.close()


def decode_documents(encoded: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", chunk: int = 4096) -> DataFrame:
    """id and the text that the ids decode to."""
    asked = encoded.select(F.col(id_col).alias("id"), "ids")
    id_type = asked.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by_id = encoder(ranks_path, pattern).transducer.merges.by_id
        for batch in batches:
            texts = [_decoded(by_id, p, chunk) for p in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(texts, pa.string())], ["id", "decoded"])

    return asked.mapInArrow(run, f"id {id_type}, decoded string").withColumnRenamed("id", id_col)


def round_trip(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", chunk: int = 4096) -> DataFrame:
    """id, ids, n_tokens and decoded, both ways by one worker, which then holds one set of tables."""
    asked = docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text"))
    id_type = asked.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(ranks_path, pattern)
        by_id = own.transducer.merges.by_id
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                with uncollected():
                    packed = [own.encode_packed(t) for t in part.column("text").to_pylist()]
                decoded = [_decoded(by_id, p, chunk) for p in packed]
                n = pa.array([len(p) // 4 for p in packed], pa.int64())
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(packed, pa.binary()), n, pa.array(decoded, pa.string())], ["id", "ids", "n_tokens", "decoded"])

    return asked.mapInArrow(run, f"id {id_type}, ids binary, n_tokens long, decoded string").withColumnRenamed("id", id_col)


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    found = round_trip(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    return found.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))

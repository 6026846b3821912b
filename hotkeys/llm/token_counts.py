"""Token counts: pieces are counted once per distinct pre-token and joined to the frequencies.

A pre-token is a run of spaces and what follows up to the next space. No piece of the vocabulary
holds a space behind another character, which is checked when the model is loaded, so no merge
crosses a pre-token's start and a text's count is the sum over its pre-tokens; the mark that the model
writes for a space splits like one. A batch of texts becomes a table of frequencies (text, pre-token, times); its
distinct pre-tokens are looked up in the worker's table of counts, which counts each missing one
once; the two are joined and summed by text, and ids are never built. The join is local to a batch, since over the corpus it would
shuffle a row for each distinct word of each document; so there is no hot key and nothing to
gather. The table is emptied when it holds MAX_KNOWN pre-tokens.

Defined results: null counts as empty; an empty text has 0 tokens; repeated rows are counted
each; other columns are not read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import sentencepiece
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotkeys.llm.common import table, text_of

MAX_KNOWN = 1_000_000
#: Texts whose frequencies are held at once.
ROWS = 2_000
#: Fixed value: the model's mark for a space.
MARK = "▁"
_RUN = re.compile(" +[^ ]*")


class PieceCounter:
    """Counts of a sentencepiece BPE model with identity normaliser and dummy prefix."""

    def __init__(self, model: str):
        self.model = sentencepiece.SentencePieceProcessor(model_file=model)
        pieces = [self.model.id_to_piece(i) for i in range(self.model.get_piece_size())]
        self.splits = not any(re.search(f"[^{MARK}]{MARK}", p) for p in pieces)
        self.known: dict[str, int] = {}

    def whole(self, text: str) -> int:
        return len(self.model.encode(text, num_threads=1))

    def learn(self, pre_tokens: list[str]) -> None:
        """Count those not known yet; "" stands for a lone space at a text's end."""
        new = [p for p in pre_tokens if p not in self.known]
        for at in range(0, len(new), 20_000):
            part = new[at : at + 20_000]
            self.known.update(zip(part, map(len, self.model.encode(part, num_threads=1)), strict=True))
        self.known[""] = 1

    def frequencies(self, texts: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray, np.ndarray]:
        """The batch's distinct pre-tokens, and a table of text, pre-token (as its place among them) and how often."""
        spaced = pc.replace_substring(texts, MARK, " ")  # to the model the two are one
        runs = pc.or_(pc.match_substring(spaced, "  "), pc.starts_with(spaced, " ")).to_numpy(zero_copy_only=False)
        empty = pc.equal(pc.binary_length(spaced), 0).to_numpy(zero_copy_only=False)
        plain = np.flatnonzero(~(runs | empty))
        lists = pc.split_pattern(spaced.take(pa.array(plain)), " ")
        found, where = [lists.flatten()], [np.repeat(plain, np.diff(np.asarray(lists.offsets)))]
        for i in np.flatnonzero(runs):
            parts = [m[1:] for m in _RUN.findall(" " + spaced[int(i)].as_py())]
            found.append(pa.array(parts, pa.string()))
            where.append(np.full(len(parts), i))
        codes = pa.concat_arrays(found).dictionary_encode()
        distinct = codes.dictionary.to_pylist()
        key, times = np.unique(np.concatenate(where) * max(1, len(distinct)) + np.asarray(codes.indices), return_counts=True)
        return distinct, key // max(1, len(distinct)), key % max(1, len(distinct)), times

    def count(self, texts: pa.Array) -> np.ndarray:
        """Tokens of each text of a batch: frequencies joined to the counts of distinct pre-tokens, and summed."""
        if len(self.known) > MAX_KNOWN:
            self.known.clear()
        if not self.splits:
            return np.array([self.whole(t) for t in texts.to_pylist()], np.int64)
        distinct, text, code, times = self.frequencies(texts)
        self.learn(distinct)
        of_code = np.fromiter(map(self.known.__getitem__, distinct), np.int64, len(distinct))
        out = np.zeros(len(texts), np.int64)
        np.add.at(out, text, of_code[code] * times)
        return out


_COUNTERS: dict[str, PieceCounter] = {}


def counter(model: str) -> PieceCounter:
    """One counter per worker process and model, kept between tasks."""
    if model not in _COUNTERS:
        _COUNTERS[model] = PieceCounter(model)
    return _COUNTERS[model]


def token_counts(docs: DataFrame, model: str, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_bytes, n_tokens and over_limit of every row."""
    asked = docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text"))
    id_type = asked.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = counter(model)
        for batch in batches:
            for at in range(0, batch.num_rows, ROWS):
                part = batch.slice(at, ROWS)
                texts = part.column("text")
                n = own.count(texts)
                n_bytes = pc.cast(pc.binary_length(texts), pa.int64())
                yield pa.RecordBatch.from_arrays([part.column("id"), n_bytes, pa.array(n), pa.array(n > limit)], ["id", "n_bytes", "n_tokens", "over_limit"])

    return asked.mapInArrow(run, f"id {id_type}, n_bytes long, n_tokens long, over_limit boolean").withColumnRenamed("id", id_col)


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))

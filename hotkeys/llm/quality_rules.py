"""Quality rules: a threshold table compiled into one Spark projection.

Each rule names a measure, the side on which it fails and a threshold. `compile_rules` turns the
whole table into one boolean column over the measures; nothing but built-in expressions runs.

Defined results: a null or empty text has no words, measures of 0, ratios of 0, and fails the
base rule; repeated rows are judged each on its own; an empty table gives an empty table; columns
of the input other than the id and the text are not read by `judge`, and `kept_rows` returns
them untouched whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hotkeys.llm.common import WHITE, let, table, text_of, words_of

#: Very frequent function words of the four corpus languages.
STOP_WORDS = {
    "en": "the be to of and that have with in is it for on as are this by from or at an was".split(),
    "fr": "le la les de des du et un une en est que qui dans pour par sur avec au ou pas ce".split(),
    "de": "der die das und in zu den von mit ist ein eine nicht auf für im dem des sich es auch als".split(),
    "es": "el la los las de del y en que un una es por con para se su no al lo como más".split(),
}


@dataclass(frozen=True)
class Rule:
    """The row of the table: a text fails if its measure is below `least` or above `most`."""

    name: str
    measure: str
    least: float | None = None
    most: float | None = None


#: Thresholds of the usual heuristic web-text filters, over the measures of `measures`.
RULES = (
    Rule("length", "n_words", least=50, most=1_000_000),
    Rule("repeated_words", "repeat_ratio", most=0.5),
    Rule("word_length", "mean_word_chars", least=2, most=14),
    Rule("symbols", "symbol_ratio", most=0.1),
    Rule("letters", "letter_word_ratio", least=0.7),
    Rule("stop_words", "n_stop_words", least=2),
    Rule("stop_word_share", "stop_word_ratio", least=0.03),
    Rule("repeated_lines", "dup_line_ratio", most=0.5),
    Rule("bullets", "bullet_line_ratio", most=0.9),
    Rule("ellipses", "ellipsis_line_ratio", most=0.3),
)

SYMBOLS = "#*$%&|<>"


def _repeated_words(words: Column) -> Column:
    """Words inside three-word windows that occur at least twice.

    A text whose windows all have different 64-bit hashes has none. Any other has its windows
    sorted by hash, and neighbours of one hash are compared word by word.
    """
    none = F.lit(0).cast("long")

    def starts(s: Column) -> Column:
        def same(e: Column, j: Column) -> Column:
            other = F.get(s, j)
            word = lambda x, k: F.get(words, x["i"] + k)
            return (other["h"] == e["h"]) & (word(other, 0) == word(e, 0)) & (word(other, 1) == word(e, 1)) & (word(other, 2) == word(e, 2))

        hit = F.filter(s, lambda e, j: F.coalesce(same(e, j - 1), F.lit(False)) | F.coalesce(same(e, j + 1), F.lit(False)))
        return F.array_sort(F.transform(hit, lambda e: e["i"]))

    def covered(p: Column) -> Column:
        gaps = F.transform(p, lambda x, k: F.least(F.lit(3), F.coalesce(F.get(p, k + 1) - x, F.lit(3))))
        return F.aggregate(gaps, none, lambda a, g: a + g)

    def by_hash(hashes: Column) -> Column:
        pairs = F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i")))
        return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), none).otherwise(let(F.sort_array(pairs), lambda s: let(starts(s), covered)))

    hashes = F.transform(words, lambda x, i: F.xxhash64(x, F.get(words, i + 1), F.get(words, i + 2)))
    return F.when(F.size(words) < 4, none).otherwise(let(F.slice(hashes, 1, F.size(words) - 2), by_hash))


def _ratio(part: Column, whole: Column) -> Column:
    return F.when(whole > 0, part / whole).otherwise(F.lit(0.0))


def measures(text: Column) -> Column:
    """Struct of the counts of one text; every array is bound once, so nothing is computed twice."""
    stops = sorted({w for words in STOP_WORDS.values() for w in words})

    def count(n: Column) -> Column:
        return n.cast("long")

    def of_text(t: Column) -> Column:
        lines = F.filter(F.split(t, "\n", -1), lambda x: F.translate(x, WHITE, "") != "")
        by_words = let(
            words_of(t),
            lambda w: F.struct(
                count(F.size(w)).alias("n_words"),
                count(_repeated_words(w)).alias("n_repeat_words"),
                count(F.size(F.filter(w, lambda x: x.rlike(r"\p{L}")))).alias("n_letter_words"),
                count(F.size(F.filter(w, lambda x: F.lower(x).isin(stops)))).alias("n_stop_words"),
            ),
        )
        by_lines = let(
            lines,
            lambda ls: F.struct(
                count(F.size(ls)).alias("n_lines"),
                count(F.size(ls) - F.size(F.array_distinct(ls))).alias("n_dup_lines"),
                count(F.size(F.filter(ls, lambda x: F.ltrim(x).rlike(r"^[-*•]\s")))).alias("n_bullet_lines"),
                count(F.size(F.filter(ls, lambda x: F.rtrim(x).rlike(r"(\.\.\.|…)$")))).alias("n_ellipsis_lines"),
            ),
        )
        return F.struct(
            by_words.alias("words"),
            by_lines.alias("lines"),
            count(F.length(F.translate(t, WHITE, ""))).alias("word_chars"),
            count(F.length(t) - F.length(F.translate(t, SYMBOLS, ""))).alias("n_symbols"),
        )

    return let(text, of_text)


def compile_rules(rules: tuple[Rule, ...] = RULES) -> dict[str, Column]:
    """A boolean column for each rule of the table: true where a text passes."""
    out = {}
    for rule in rules:
        ok = F.lit(True)
        if rule.least is not None:
            ok = ok & (F.col(rule.measure) >= rule.least)
        if rule.most is not None:
            ok = ok & (F.col(rule.measure) <= rule.most)
        out[rule.name] = ok
    return out


def _measured(docs: DataFrame, carried: Column, text_col: str) -> DataFrame:
    """carried, as column `carried`, beside every measure and ratio that a rule may name."""
    m = docs.select(carried.alias("carried"), measures(text_of(text_col)).alias("m"))
    flat = m.select("carried", "m.words.*", "m.lines.*", "m.word_chars", "m.n_symbols")
    return flat.withColumns(
        {
            "repeat_ratio": _ratio(F.col("n_repeat_words"), F.col("n_words")),
            "mean_word_chars": _ratio(F.col("word_chars"), F.col("n_words")),
            "symbol_ratio": _ratio(F.col("n_symbols"), F.col("n_words")),
            "letter_word_ratio": _ratio(F.col("n_letter_words"), F.col("n_words")),
            "stop_word_ratio": _ratio(F.col("n_stop_words"), F.col("n_words")),
            "dup_line_ratio": _ratio(F.col("n_dup_lines"), F.col("n_lines")),
            "bullet_line_ratio": _ratio(F.col("n_bullet_lines"), F.col("n_lines")),
            "ellipsis_line_ratio": _ratio(F.col("n_ellipsis_lines"), F.col("n_lines")),
        }
    )


def _verdict(rules: tuple[Rule, ...]) -> dict[str, Column]:
    passes = compile_rules(rules)
    base_failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    kept = ~base_failed
    for ok in passes.values():
        kept = kept & ok
    failed = F.array_compact(F.array(*[F.when(~ok, F.lit(name)) for name, ok in passes.items()]))
    return {"base_failed": base_failed, "failed_rules": failed, "kept": kept}


def judge(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row for each input row: its measures, the rules that it fails, and whether it is kept."""
    out = _measured(docs, F.col(id_col), text_col).withColumns(_verdict(rules))
    return out.withColumnRenamed("carried", id_col)


def kept_rows(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text") -> DataFrame:
    """The rows of docs that pass every rule, with their own columns; one pass, no shuffle."""
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    return _measured(docs, row, text_col).withColumns(_verdict(rules)).filter("kept").select("carried.*")


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")

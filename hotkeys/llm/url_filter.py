"""URL filters: pattern rules indexed by their rarest literal token.

Every rule is a regular expression over the host and a prefix of the path, with the literal tokens
(runs of a-z and 0-9) that any match must hold as whole tokens of the URL. Of these the one found in the fewest URLs of the corpus keys the rule.
A URL's tokens fetch the candidate rules, and only those run their expressions. Of the address
rules that fit the longest wins; where none fits, a pattern rule that fits blocks, unless another one allows. Rules
come as a table of addresses and patterns; the tokens are read off the patterns.

Defined results: a null url, or one without ://, has an empty host and path, no rule and verdict
allow; repeated rows are judged each; the rule list travels to every task, so its length is
checked (MAX_RULES); rules without a literal token are tried on every URL.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from re._constants import ASSERT_NOT, AT, AT_BEGINNING, AT_BEGINNING_STRING, AT_END, AT_END_STRING, LITERAL
from re._parser import parse

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hotkeys.llm.common import table

MAX_RULES = 100_000
_TOKEN = re.compile(r"[a-z0-9]+")


@dataclass(frozen=True)
class UrlRule:
    """name: what is reported; rank: length of an address rule, 0 for patterns."""

    name: str
    action: str
    host_pattern: str
    path_prefix: str = ""
    tokens: tuple[str, ...] = field(default=())
    rank: int = 0


def address_rule(action: str, address: str) -> UrlRule:
    """A rule like example.net/en/: that host and its subdomains, paths that start so."""
    host, slash, path = address.partition("/")
    # the last token of a path that doesn't end it may be the start of a longer one
    whole = path if not path or not re.search(r"[a-z0-9]$", path) else re.sub(r"[a-z0-9]+$", "", path)
    return UrlRule(address, action, r"\A(?:.*\.)?" + re.escape(host) + r"\Z", slash + path, tuple(_TOKEN.findall(host) + _TOKEN.findall(whole)), len(address))


def literal_tokens(pattern: str) -> tuple[str, ...]:
    """Tokens that every match of a pattern holds whole: literal runs of a-z and 0-9 that no such character can adjoin.

    Only what stands outside of groups, choices and repeats is certain. A run is whole between other literals, the
    ends of the text, and assertions that no token character is there.
    """
    out: list[str] = []
    run, whole = "", False

    def ended(closed: bool) -> None:
        nonlocal run, whole
        if run and whole and closed:
            out.append(run)
        run, whole = "", closed

    for op, value in parse(pattern):
        if op is LITERAL and _TOKEN.fullmatch(chr(value)):
            run += chr(value)
        elif op is LITERAL and chr(value).lower() == chr(value):
            ended(True)
        elif op is AT and value in (AT_BEGINNING, AT_BEGINNING_STRING, AT_END, AT_END_STRING):
            ended(True)
        elif op is ASSERT_NOT and list(value[1]) == list(parse("[a-z0-9]")):
            ended(True)
        else:
            ended(False)
    ended(False)
    return tuple(dict.fromkeys(out))


def pattern_rule(name: str, action: str, host_pattern: str, path_prefix: str = "") -> UrlRule:
    """A regular expression over the host, found anywhere in it, and a start of the path."""
    return UrlRule(name, action, host_pattern, path_prefix, literal_tokens(host_pattern))


def word_rule(word: str) -> UrlRule:
    """Blocks hosts with word, which may hold hyphens, as a whole hyphen-or-dot-bounded part."""
    return pattern_rule(word, "block", rf"(?<![a-z0-9]){re.escape(word)}(?![a-z0-9])")


def rules_of(table: DataFrame) -> tuple[UrlRule, ...]:
    """Rules from a table (name, action, address, host_pattern, path_prefix): an address, or else a pattern.

    At most MAX_RULES rows may come; a longer table is refused, for the rules travel to every task.
    """
    rows = table.select("name", "action", "address", "host_pattern", "path_prefix").orderBy("name", "action").take(MAX_RULES + 1)
    if len(rows) > MAX_RULES:
        raise ValueError(f"more than {MAX_RULES} rules")
    return tuple([address_rule(r["action"], r["address"]) if r["address"] else pattern_rule(r["name"], r["action"], r["host_pattern"], r["path_prefix"] or "") for r in rows])


#: The address rules of the op4 contract.
ADDRESS_RULES = (address_rule("block", "net/"), address_rule("allow", "example.net/en/"), address_rule("block", "example.com/de/"), address_rule("allow", "org/fr/"))
#: Words of hosts that mark advertising, gambling, adult and spam sites.
BLOCK_WORDS = ("ads", "adserver", "adult", "bets", "betting", "casino", "doubleclick", "pills", "poker", "porn", "spam", "viagra", "xxx")
RULES = ADDRESS_RULES + tuple(word_rule(w) for w in BLOCK_WORDS)


def host_and_path(url: str | None) -> tuple[str, str]:
    """Host, its A-Z lower-cased, and path of an absolute URL; both empty if there is no ://."""
    _, found, rest = (url or "").partition("://")
    if not found:
        return "", ""
    host = re.match(r"[^/?#]*", rest)[0]
    path = re.match(r"[^?#]*", rest[len(host) :])[0]
    return host.translate(_LOWER), path


_LOWER = {c: c + 32 for c in range(65, 91)}


def tokens_column(url: Column) -> Column:
    return F.array_distinct(F.array_remove(F.split(F.lower(F.coalesce(url, F.lit(""))), "[^a-z0-9]+"), ""))


def token_counts(pages: DataFrame, rules: tuple[UrlRule, ...], url_col: str = "url") -> dict[str, int]:
    """URLs that hold each rule token, over the whole table; as many rows as the rules have tokens."""
    known = sorted({t for r in rules for t in r.tokens})
    if not known:
        return {}
    wanted = F.array_intersect(tokens_column(F.col(url_col)), F.lit(known))
    found = pages.select(F.explode(wanted).alias("token")).groupBy("token").agg(F.count("*").alias("n"))
    return {r["token"]: r["n"] for r in found.collect()}


class RuleIndex:
    """Rules by rarest token, with the rules that have none beside them."""

    def __init__(self, rules: tuple[UrlRule, ...], counts: dict[str, int]):
        if len(rules) > MAX_RULES:
            raise ValueError(f"{len(rules)} rules; at most {MAX_RULES} may travel to every task")
        self.by_token: dict[str, list[tuple[UrlRule, re.Pattern]]] = {}
        self.always: list[tuple[UrlRule, re.Pattern]] = []
        for rule in rules:
            compiled = (rule, re.compile(rule.host_pattern, re.DOTALL))
            if rule.tokens:
                self.by_token.setdefault(min(rule.tokens, key=lambda t: (counts.get(t, 0), t)), []).append(compiled)
            else:
                self.always.append(compiled)

    def judge(self, host: str, path: str) -> tuple[str | None, str, int]:
        """Address rule that wins or None, verdict, and how many expressions ran."""
        tokens = set(_TOKEN.findall(host)) | set(_TOKEN.findall(path))
        candidates = [c for t in tokens if t in self.by_token for c in self.by_token[t]] + self.always
        fits = [rule for rule, pattern in candidates if path.startswith(rule.path_prefix) and pattern.search(host)]
        address = max((r for r in fits if r.rank), key=lambda r: (r.rank, r.name), default=None)
        if address:
            return address.name, address.action, len(candidates)
        # of pattern rules one that allows outweighs those that block
        return None, "block" if fits and all(r.action == "block" for r in fits) else "allow", len(candidates)


def judge_urls(pages: DataFrame, rules: tuple[UrlRule, ...] | DataFrame = RULES, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """id, host, path, rule, verdict and the number of candidates tried, for each row; no shuffle.

    rules: a tuple, or a table as `rules_of` takes it.
    """
    rules = rules if isinstance(rules, tuple) else rules_of(rules)
    counts = token_counts(pages, rules, url_col)
    asked = pages.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url"))
    id_type = asked.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = RuleIndex(rules, counts)
        for batch in batches:
            parts = [host_and_path(u) for u in batch.column("url").to_pylist()]
            verdicts = [index.judge(*p) for p in parts]
            text = lambda xs: pa.array(xs, pa.string())
            yield pa.RecordBatch.from_arrays(
                [batch.column("id"), text([p[0] for p in parts]), text([p[1] for p in parts]), text([v[0] for v in verdicts]), text([v[1] for v in verdicts]), pa.array([v[2] for v in verdicts], pa.int64())],
                ["id", "host", "path", "rule", "verdict", "n_candidates"],
            )

    return asked.mapInArrow(run, f"id {id_type}, host string, path string, rule string, verdict string, n_candidates long").withColumnRenamed("id", id_col)


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")

"""PII by information-theoretic sanitisation, in DataFrame form.

Protected entities are the e-mail addresses, IP addresses, card and phone numbers that patterns and
checks find. The corpus then tells which other terms reveal them: for an entity c and a term t of its documents,
PMI(c, t) = log(N * df(c, t) / (df(c) * df(t))) is held against ALPHA times the information content
of c, log(N / df(c)). A term that reaches it in at least MIN_CONTEXTS different contexts of c
discloses c and is generalised, where a given taxonomy has a broader term whose own PMI stays under the
threshold for every entity that t discloses, or else removed. Document frequencies, those of c and t together
too, are counted over whole documents of the whole corpus. A context is the text of CONTEXT_CHARS characters on
each side of a mention of c: a term has those of the mentions that it is near, and one for each document
that it shares with c.

Match places come from splitting a text at its matches, so no user function runs. The patterns
start only where a run of their characters starts, or where the last match ended, and possessive
repeats don't backtrack: time is linear in the text and the matches stay the leftmost ones.

Defined results: null counts as empty and has no spans; repeated rows are searched each; matches
of different kinds may overlap and are all reported, but a term span that touches one is dropped; a document is
a pair of id (null is one as well) and text, so rows that share an id have each their own spans and rows that
repeat both count once; other columns are not touched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hotkeys.llm.common import let, sized_broadcast, table, text_of, written

#: Kinds as listed, and the patterns of what each kind may look like.
KINDS = ("email", "ip", "card", "phone", "term")
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
CARD = r"[0-9](?:[\x20-]?[0-9])++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
_BYTE = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"

#: Share of an entity's information content that a term must give away to count as disclosing it.
ALPHA = 0.9
#: Different contexts of the entity that must hold the term: what one text or its copies hold is no evidence.
MIN_CONTEXTS = 2
#: Characters on each side of a mention that make its context.
CONTEXT_CHARS = 80
#: Words of texts that can be terms.
TERM = r"\p{L}[\p{L}\p{M}]*"
MOST_BROADCAST = 200_000

SPAN = "struct<start:int,rank:int,end:int,kind:string,value:string>"


def _luhn(digits: Column) -> Column:
    """Whether 12 to 19 digits pass the Luhn check."""
    padded = F.lpad(digits, 20, "0")

    def worth(i: Column) -> Column:
        x = padded.substr(i, F.lit(1)).cast("int")
        return F.when(i % 2 == 1, 2 * x - F.when(x > 4, 9).otherwise(0)).otherwise(x)

    total = F.aggregate(F.sequence(F.lit(1), F.lit(20)), F.lit(0), lambda a, i: a + worth(i))
    return F.length(digits).between(12, 19) & (F.when(F.length(digits) <= 19, total).otherwise(1) % 10 == 0)


def _valid(kind: str, hit: Column) -> Column:
    digits = F.regexp_replace(hit, "[^0-9]", "")
    return {
        "email": F.lit(True),
        "ip": hit.rlike(rf"\A{_BYTE}(?:\.{_BYTE}){{3}}\z"),
        "card": _luhn(digits),
        "phone": F.length(digits).between(9, 15),
        "term": F.lit(True),
    }[kind]


def _matches(text: Column, pattern: str, kind: str, valid) -> Column:
    """Spans of all matches of pattern in text that are valid, in order; code points, end exclusive."""
    empty = F.from_json(F.lit("[]"), f"array<{SPAN}>")

    def placed(hits: Column) -> Column:
        gaps = F.split(text, pattern, -1)
        both = F.zip_with(hits, gaps, lambda h, g: F.struct(h.alias("h"), F.length(g).alias("g")))
        start = F.struct(F.lit(0).alias("at"), empty.alias("spans"))

        def step(acc: Column, x: Column) -> Column:
            here = acc["at"] + x["g"]
            end = here + F.length(x["h"])
            span = F.struct(here.alias("start"), F.lit(KINDS.index(kind)).alias("rank"), end.alias("end"), F.lit(kind).alias("kind"), x["h"].alias("value"))
            return F.struct(end.alias("at"), F.when(valid(x["h"]), F.concat(acc["spans"], F.array(span))).otherwise(acc["spans"]).alias("spans"))

        return F.aggregate(F.filter(both, lambda x: x["h"].isNotNull()), start.cast(f"struct<at:int,spans:array<{SPAN}>>"), lambda a, x: step(a, x).cast(f"struct<at:int,spans:array<{SPAN}>>"), lambda a: a["spans"])

    return let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda hits: F.when(F.exists(hits, valid), placed(hits)).otherwise(empty))


def base_spans(text: Column) -> Column:
    """All entity spans of a text, by start and then kind."""
    empty = F.from_json(F.lit("[]"), f"array<{SPAN}>")
    found = lambda kind, pattern: _matches(text, pattern, kind, lambda h: _valid(kind, h))
    email = F.when(text.contains("@"), found("email", EMAIL)).otherwise(empty)
    phone = F.when(text.contains("+"), found("phone", PHONE)).otherwise(empty)
    return F.array_sort(F.concat(email, found("ip", IP), found("card", CARD), phone))


def _terms(context: Column) -> Column:
    return F.array_distinct(F.regexp_extract_all(F.lower(context), F.lit(TERM), F.lit(0)))


def _contexts(text: Column, spans: Column) -> Column:
    """For each span the entity and the whole terms around it, the entity itself left out."""

    def of(s: Column) -> Column:
        low = F.greatest(s["start"] - CONTEXT_CHARS, F.lit(0))
        left = F.when(low == 0, text.substr(F.lit(1), s["start"])).otherwise(F.regexp_replace(text.substr(low + 1, s["start"] - low), r"\A\S*", ""))
        cut = text.substr(s["end"] + 1, F.lit(CONTEXT_CHARS))
        right = F.when(F.length(cut) < CONTEXT_CHARS, cut).otherwise(F.regexp_replace(cut, r"\S*\z", ""))
        around = F.concat(F.regexp_replace(left, r"\S*\z", ""), F.lit(" "), F.regexp_replace(right, r"\A\S*", ""))
        return F.struct(F.lower(F.concat(s["kind"], F.lit(":"), s["value"])).alias("entity"), F.xxhash64(around).alias("context"), _terms(around).alias("terms"))

    return F.transform(spans, of)


def entities(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, h (hash of the text), spans and contexts of every row, and all terms of those with spans."""
    own = docs.select(F.col(f"`{id_col}`").alias("id"), text_of(text_col).alias("text"))
    return own.select("id", F.xxhash64("text").alias("h"), let(F.col("text"), lambda t: let(base_spans(t), lambda s: F.struct(s.alias("spans"), _contexts(t, s).alias("contexts"), F.when(F.size(s) > 0, _terms(t)).alias("terms")))).alias("x")).select("id", "h", "x.spans", "x.contexts", "x.terms")


def _documents_with(rows: DataFrame, by: list[str], name: str) -> DataFrame:
    """Distinct documents for each value of by, in two plain aggregates: a common one is combined before the shuffle."""
    return rows.groupBy(*by, "id", "h").agg(F.lit(1).alias("one")).groupBy(*by).agg(F.count("*").alias(name))


def _hits(docs: DataFrame, terms: DataFrame, n_terms: int, id_col: str, text_col: str) -> DataFrame:
    """(id, h, term): which documents hold which of the terms."""
    own = docs.select(F.col(f"`{id_col}`").alias("id"), text_of(text_col).alias("text"))
    words = own.select("id", F.xxhash64("text").alias("h"), F.explode(_terms(F.col("text"))).alias("term"))
    return words.join(sized_broadcast(terms, n_terms, MOST_BROADCAST), "term", "left_semi").select("id", "h", "term")


def _discloses(pmi: Column, information: Column, alpha: float) -> Column:
    return (information > 0) & (pmi >= alpha * information - 1e-9)


def disclosing_terms(docs: DataFrame, found: DataFrame, id_col: str = "doc_id", text_col: str = "text", alpha: float = ALPHA) -> DataFrame:
    """(term, entity, df_c, pmi, information) of the terms that reveal an entity, from the whole corpus."""
    spark = docs.sparkSession
    mentions = found.select("id", "h", F.explode("contexts").alias("c")).select("id", "h", "c.entity", "c.context")
    holds = _documents_with(mentions, ["entity"], "df_c")
    met = mentions.groupBy("entity", "context").agg(F.lit(1).alias("one")).groupBy("entity").agg(F.count("*").alias("n")).filter(F.col("n") >= MIN_CONTEXTS)
    # entities with fewer contexts than a term needs drop out before any term is looked at
    able = written(spark, holds.join(met, "entity").select("entity", "df_c"), "able-entities")
    known = sized_broadcast(able.select("entity"), able.count(), MOST_BROADCAST)
    least = F.array_min(F.transform(F.filter("contexts", lambda c: c["entity"] == F.col("entity")), lambda c: c["context"]))
    held = found.filter(F.size("spans") > 0).withColumn("entity", F.explode(F.array_distinct(F.transform("contexts", lambda c: c["entity"])))).join(known, "entity", "left_semi")
    shared = held.select("id", "h", "entity", least.alias("context"), "terms")
    close = found.select("id", "h", F.explode("contexts").alias("c")).select("id", "h", "c.entity", "c.context", "c.terms").join(known, "entity", "left_semi")
    with_terms = shared.unionByName(close).select("entity", "context", F.explode("terms").alias("term"))
    contexts = with_terms.groupBy("entity", "term", "context").agg(F.lit(1).alias("one")).groupBy("entity", "term").agg(F.count("*").alias("n_contexts")).filter(F.col("n_contexts") >= MIN_CONTEXTS)
    both = _documents_with(shared.select("id", "h", "entity", F.explode("terms").alias("term")), ["entity", "term"], "df_ct")
    total = found.select("id", "h").distinct().count()
    # a term is in at least as many documents as it shares with some entity: common words drop out here
    at_least = _documents_with(found.filter(F.size("spans") > 0).select("id", "h", F.explode("terms").alias("term")), ["term"], "df_least")
    most = F.col("df_ct") * F.pow(F.lit(float(total)) / F.col("df_c"), F.lit(1.0 - alpha))
    scored = contexts.join(both, ["entity", "term"]).join(able, "entity").join(at_least, "term").filter(F.col("df_least") <= most + 1e-6)
    pairs = written(spark, scored, "term-pairs")
    candidates = written(spark, pairs.select("term").distinct(), "candidate-terms")
    few = candidates.count()
    if not few:
        counts = candidates.withColumn("df_t", F.lit(0).cast("long"))
    else:
        counts = _documents_with(_hits(docs, candidates, few, id_col, text_col), ["term"], "df_t")
    pmi = F.log2(F.lit(float(total)) * F.col("df_ct") / (F.col("df_c") * F.col("df_t")))
    information = F.log2(F.lit(float(total)) / F.col("df_c"))
    scored = pairs.join(counts, "term").select("term", "entity", "df_c", pmi.alias("pmi"), information.alias("information"))
    return written(spark, scored.filter(_discloses(F.col("pmi"), F.col("information"), alpha)), "disclosing-terms")


def broader_terms(docs: DataFrame, found: DataFrame, terms: DataFrame, taxonomy: DataFrame, id_col: str = "doc_id", text_col: str = "text", alpha: float = ALPHA, levels: int = 4) -> DataFrame:
    """(term, label): for a disclosing term the nearest broader one that discloses none of the term's entities.

    taxonomy: (term, broader). A broader term is in every document that holds it or a term under it; its
    PMI with an entity, counted so, is held against the same threshold. Terms without a safe one are absent.
    """
    spark = docs.sparkSession
    given = taxonomy.select(F.lower("term").alias("term"), F.lower("broader").alias("broader")).filter("term <> broader").distinct()
    step = given.select("term", F.col("broader").alias("above"), F.lit(1).alias("level"))
    above = step
    for level in range(2, levels + 1):
        step = step.join(given.select(F.col("term").alias("above"), "broader"), "above").select("term", F.col("broader").alias("above"), F.lit(level).alias("level"))
        above = above.unionByName(step)
    asked = terms.select("term", "entity", "df_c", "information").join(above, "term")
    wanted = asked.select("above").distinct()
    under = written(spark, above.join(wanted, "above", "left_semi").select("term", "above").union(wanted.select(F.col("above").alias("term"), "above")).distinct(), "narrower-terms")
    members = under.select("term").distinct()
    hits = written(spark, _hits(docs, members, members.count(), id_col, text_col).join(under, "term").select("id", "h", "above").distinct(), "broader-hits")
    own = found.select("id", "h", F.explode("contexts").alias("c")).select("id", "h", "c.entity").join(terms.select("entity").distinct(), "entity", "left_semi").distinct()
    df_b = hits.groupBy("above").agg(F.count("*").alias("df_b"))
    df_cb = own.join(hits, [own["id"].eqNullSafe(hits["id"]), own["h"] == hits["h"]]).groupBy("entity", "above").agg(F.count("*").alias("df_cb"))
    total = found.select("id", "h").distinct().count()
    weighed = asked.join(df_b, "above").join(df_cb, ["entity", "above"], "left")
    pmi = F.log2(F.lit(float(total)) * F.col("df_cb") / (F.col("df_c") * F.col("df_b")))
    safe = F.col("df_cb").isNull() | ~_discloses(pmi, F.col("information"), alpha)
    judged = weighed.groupBy("term", "above").agg(F.min("level").alias("level"), F.bool_and(safe).alias("safe"))
    return written(spark, judged.filter("safe").groupBy("term").agg(F.min_by("above", F.struct("level", "above")).alias("label")), "broader-terms")


def all_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", alpha: float = ALPHA, taxonomy: DataFrame | None = None) -> DataFrame:
    """id, h (hash of the text), base (entity spans), spans (those and the spans of disclosing terms) and labels of every row.

    labels maps the row's terms that a taxonomy generalises to what stands for them.
    """
    spark = docs.sparkSession
    found = written(spark, entities(docs, id_col, text_col), "entities")
    pairs = disclosing_terms(docs, found, id_col, text_col, alpha)
    terms = pairs.select("term").distinct()
    n_terms = terms.count()
    base = found.select("id", "h", F.col("spans").alias("base"))
    none = F.from_json(F.lit("{}"), "map<string,string>")
    if not n_terms:
        return base.withColumn("spans", F.col("base")).withColumn("labels", none)
    labelled = terms.withColumn("label", F.lit(None).cast("string")) if taxonomy is None else terms.join(broader_terms(docs, found, pairs, taxonomy, id_col, text_col, alpha), "term", "left")
    hits = _hits(docs, terms, n_terms, id_col, text_col).join(sized_broadcast(labelled, n_terms, MOST_BROADCAST), "term")
    of_doc = written(spark, hits.groupBy("id", "h").agg(F.sort_array(F.collect_set(F.struct("term", "label"))).alias("known")), "terms-of-documents")
    weight = of_doc.agg(F.coalesce(F.sum(F.size("known")), F.lit(0))).first()[0]  # a row's array counts by its length
    own = docs.select(F.col(f"`{id_col}`").alias("id"), text_of(text_col).alias("text")).withColumn("h", F.xxhash64("text"))
    few = sized_broadcast(of_doc.select(F.col("id").alias("doc"), F.col("h").alias("hash"), "known"), weight, MOST_BROADCAST)
    texts = own.join(few, F.col("id").eqNullSafe(F.col("doc")) & (F.col("h") == F.col("hash")))
    listed = F.transform("known", lambda k: k["term"])
    more = texts.select(F.col("id").alias("doc"), F.col("h").alias("hash"), _matches(F.col("text"), TERM, "term", lambda t: F.array_contains(listed, F.lower(t))).alias("more"), F.map_from_entries(F.filter("known", lambda k: k["label"].isNotNull())).alias("labels"))
    more = written(spark, more.dropDuplicates(["doc", "hash"]), "term-spans")
    touches = lambda s, b: (s["start"] < b["end"]) & (b["start"] < s["end"])
    free = F.filter(F.coalesce("more", F.from_json(F.lit("[]"), f"array<{SPAN}>")), lambda s: ~F.exists("base", lambda b: touches(s, b)))
    both = base.join(sized_broadcast(more, weight, MOST_BROADCAST), F.col("id").eqNullSafe(F.col("doc")) & (F.col("h") == F.col("hash")), "left")
    return both.select("id", "h", "base", F.array_sort(F.concat("base", free)).alias("spans"), F.coalesce("labels", none).alias("labels"))


def spans_text(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def redacted(text: Column, spans: Column, labels: Column | None = None) -> Column:
    """text with every span generalised: entities to their kind, terms to the label that the map has for them or nothing.

    spans in order; overlapping ones are replaced together, by the label of the first.
    """

    def label(s: Column) -> Column:
        known = F.try_element_at(labels, F.lower(s["value"])) if labels is not None else F.lit(None).cast("string")
        return F.when(s["kind"] == "term", F.coalesce(known, F.lit("[REMOVED]"))).otherwise(F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]")))

    merged_type = "struct<done:array<struct<start:int,end:int,label:string>>>"

    def merge(acc: Column, s: Column) -> Column:
        done = acc["done"]
        last = F.element_at(done, -1)
        own = F.array(F.struct(s["start"].alias("start"), s["end"].alias("end"), label(s).alias("label")))
        wider = F.array(F.struct(last["start"].alias("start"), F.greatest(last["end"], s["end"]).alias("end"), last["label"].alias("label")))
        grown = F.when((F.size(done) > 0) & (s["start"] < F.try_element_at(done, F.lit(-1))["end"]), F.concat(F.slice(done, 1, F.size(done) - 1), wider)).otherwise(F.concat(done, own))
        return F.struct(grown.alias("done")).cast(merged_type)

    def built(done: Column) -> Column:
        before = lambda i: F.coalesce(F.get(done, i - 1)["end"], F.lit(0))
        parts = F.transform(done, lambda d, i: F.concat(text.substr(before(i) + 1, d["start"] - before(i)), d["label"]))
        tail = text.substr(F.element_at(done, -1)["end"] + 1, F.length(text))
        return F.concat(F.array_join(parts, ""), tail)

    start = F.from_json(F.lit('{"done": []}'), merged_type)
    return F.when(F.size(spans) == 0, text).otherwise(let(F.aggregate(spans, start, merge)["done"], built))


def sanitised(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", alpha: float = ALPHA, taxonomy: DataFrame | None = None) -> DataFrame:
    """The rows of docs with spans redacted in the text, and its length in n_chars if there is one.

    Only texts with spans change. A row's term spans are found by its id and its text together, so rows that
    share an id get their own. With a taxonomy (term, broader), terms are generalised where a broader term is safe.
    """
    spark = docs.sparkSession
    spans = all_spans(docs, id_col, text_col, alpha, taxonomy)
    term_spans = F.filter("spans", lambda s: s["kind"] == "term")
    with_terms = written(spark, spans.filter(F.size(term_spans) > 0).select(F.col("id").alias("doc"), F.col("h").alias("hash"), term_spans.alias("terms"), "labels").dropDuplicates(["doc", "hash"]), "spans-to-redact")
    weight = with_terms.agg(F.coalesce(F.sum(F.size("terms")), F.lit(0))).first()[0]
    # the input's row stays apart from the columns that are added, whatever its names are
    rows = docs.select(F.struct("*").alias("row"), text_of(text_col).alias("own"))
    if weight:
        on = F.col(f"row.`{id_col}`").eqNullSafe(F.col("doc")) & (F.xxhash64("own") == F.col("hash"))
        rows = rows.join(sized_broadcast(with_terms, weight, MOST_BROADCAST), on, "left")
        own = F.array_sort(F.concat(base_spans(F.col("own")), F.coalesce("terms", F.from_json(F.lit("[]"), f"array<{SPAN}>"))))
        labels = F.coalesce("labels", F.from_json(F.lit("{}"), "map<string,string>"))
    else:
        own, labels = base_spans(F.col("own")), None
    changed = rows.withColumn("new", let(F.col("own"), lambda t: let(own, lambda s: redacted(t, s, labels))))
    given = F.col(f"row.`{text_col}`").isNotNull()
    columns = {text_col: F.when(given, F.col("new"))}
    if "n_chars" in docs.columns:
        columns["n_chars"] = F.when(given & (F.col("new") != F.col("own")), F.length("new").cast("long")).otherwise(F.col("row.n_chars"))
    return changed.select(*[columns[c].alias(c) if c in columns else F.col(f"row.`{c}`") for c in docs.columns])


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = all_spans(table(spark, sf_dir, "documents"))
    count = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select(F.col("id").alias("doc_id"), *[count(k) for k in KINDS[:4]], F.sha2(spans_text(F.col("base")), 256).alias("base_sha256"), spans_text(F.col("spans")).alias("spans"))

r"""Personal data: base patterns and information-theoretic sanitisation, in native expressions only.

Base spans are the leftmost non-overlapping matches of four patterns; failing candidates
are dropped without a retry.  The patterns below are the base ones with possessive
quantifiers and look-arounds that change no match but keep every scan linear.

The method: protected entities are the values found.  Documents count once per content, so that
copies of one prove nothing.  A term (a word of three letters or more) occurs with an entity if the
same document has both, anywhere in its whole text; n(e, t), n(e) and n(t) documents give the
pointwise mutual information, and a term discloses an entity when that reaches the
entity's information content minus ``slack`` bits, i.e. when at least 2^-slack of the documents
with the term have the entity.  At least ``support`` documents must have both, and
n(e, t) times the mutual information must reach ``evidence`` bits, so that chance in many rare words proves
nothing either.  Every occurrence of such a term, in any document, becomes a ``term`` span that
``sanitise`` generalises like the base spans.

By those thresholds a term counts only for entities of ``support`` documents or more, and only if it
has no more than 2^slack times the documents of some entity; pairs are formed for these alone.
Nothing is collected per entity or term; counts are map-side combined, so an entity or
term in a third of all documents is harmless.  Sides of joins are broadcast only when their
counted rows are few enough; beyond that the join shuffles.  Texts are never shuffled otherwise.

Defined results: null text is empty and has no spans; repeated rows count as documents of
their own and get the same spans; an empty table gives an empty table; offsets are code
points, ends exclusive; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rotagrad.llm.common import broadcast_if_small, checkpointed, text_or_empty

KINDS = ("email", "ip", "card", "phone")
PATTERNS = {
    # A local part starts where its run of characters starts, or just after a match.
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    # Whole maximal runs of digits with single separators, 13 to 19 digits long.
    "card": r"(?<![0-9])(?<![0-9][ -])[0-9](?:[ -]?[0-9]){12,18}+(?![ -]?[0-9])",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
#: A character without which a kind cannot match.
NEEDS = {"email": "@", "ip": ".", "card": None, "phone": "+"}
#: Words up to which a list of them is broadcast.
BROADCAST_TERMS = 200_000
SPAN = "array<struct<kind:string,start:int,end:int,value:string>>"


def digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def luhn(value: Column) -> Column:
    d = F.reverse(digits(value))

    def add(total: Column, i: Column) -> Column:
        x = F.substring(d, i, F.lit(1)).cast("int") * F.when(i % 2 == 0, 2).otherwise(1)
        return total + x - F.when(x > 9, 9).otherwise(0)

    return F.aggregate(F.sequence(F.lit(1), F.length(d)), F.lit(0), add) % 10 == 0


def valid(kind: str, value: Column) -> Column:
    if kind == "ip":
        return value.rlike(r"^(?:0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])(?:\.|$)){4}$")
    if kind == "card":
        return luhn(value)
    if kind == "phone":
        return F.length(digits(value)).between(9, 15)
    return F.lit(True)


def located(text: Column, pattern: str, kind: str, keep) -> Column:
    """Spans of all matches that ``keep`` (a function of the matched text) accepts."""
    parts = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hit"))
    none = F.array().cast(SPAN)
    start = F.struct(F.lit(0).alias("at"), none.alias("out"))

    def step(acc: Column, p: Column) -> Column:
        a = acc["at"] + F.length(p["gap"])
        b = a + F.coalesce(F.length(p["hit"]), F.lit(0))
        span = F.struct(F.lit(kind).alias("kind"), a.cast("int").alias("start"), b.cast("int").alias("end"), p["hit"].alias("value"))
        found = p["hit"].isNotNull() & keep(p["hit"])
        return F.struct(b.cast("int").alias("at"), F.when(found, F.concat(acc["out"], F.array(span))).otherwise(acc["out"]).alias("out"))

    return F.when(F.regexp_instr(text, F.lit(pattern)) > 0, F.aggregate(parts, start, step, lambda acc: acc["out"])).otherwise(none)


def base_spans(text: Column) -> Column:
    """All base spans by kind, then start."""
    found = []
    for k in KINDS:
        spans = located(text, PATTERNS[k], k, lambda v, k=k: valid(k, v))
        found.append(F.when(text.contains(NEEDS[k]), spans).otherwise(F.array().cast(SPAN)) if NEEDS[k] else spans)
    return F.concat(*found)


def terms(text: Column) -> Column:
    """Different lower-cased words of three letters or more."""
    return F.filter(F.array_distinct(F.split(F.lower(text), r"[^\p{L}]+")), lambda w: F.length(w) >= 3)


def disclosing(base: DataFrame, docs: DataFrame, support: int = 3, slack: float = 1.0, evidence: float = 20.0) -> DataFrame:
    """Rows (term, entity, pmi, ic) of the terms above the thresholds; counts run over all documents.

    base: h, spans; docs: h, text; h is the hash of the text.
    """
    copies = checkpointed(base.groupBy("h").agg(F.count(F.lit(1)).alias("n")))
    n = F.lit(float(max(1, copies.count())))
    found = base.filter(F.size("spans") > 0).select("h", F.explode(F.array_distinct(F.transform("spans", lambda s: F.lower(s["value"])))).alias("e")).distinct()
    entity = checkpointed(found.groupBy("e").agg(F.count(F.lit(1)).alias("n_e")).filter(F.col("n_e") >= support))
    most = entity.agg(F.max("n_e")).first()[0]
    if most is None:
        return docs.sparkSession.createDataFrame([], "term string, entity string, pmi double, ic double")
    entities = checkpointed(found.join(broadcast_if_small(entity, BROADCAST_TERMS), "e"))
    # A copy of a text that stands n times weighs 1/n.
    again = checkpointed(copies.filter("n > 1"))
    weighted = docs.join(broadcast_if_small(again), "h", "left").select((1 / F.coalesce("n", F.lit(1))).alias("w"), F.explode(terms(F.col("text"))).alias("t"))
    term = weighted.groupBy("t").agg(F.round(F.sum("w")).alias("n_t")).filter(F.col("n_t").between(support, most * 2.0**slack))
    term = checkpointed(term)
    own = checkpointed(entities.select("h").distinct())
    beside = docs.join(broadcast_if_small(own), "h", "left_semi").select("h", F.explode(terms(F.col("text"))).alias("t"))
    pairs = beside.join(broadcast_if_small(term, BROADCAST_TERMS), "t").distinct().join(entities, "h")
    pairs = pairs.groupBy("e", "t").agg(F.count(F.lit(1)).cast("double").alias("n_et"), F.max("n_e").alias("n_e"), F.max("n_t").alias("n_t"))
    pmi, ic = F.log2(F.col("n_et") * n / (F.col("n_t") * F.col("n_e"))), -F.log2(F.col("n_e") / n)
    known = pairs.filter(F.col("n_et") >= support).select(F.col("t").alias("term"), F.col("e").alias("entity"), pmi.alias("pmi"), ic.alias("ic"), "n_et")
    return known.filter((F.col("pmi") >= F.col("ic") - slack) & (F.col("n_et") * F.col("pmi") >= evidence)).drop("n_et")


def term_spans(docs: DataFrame, found: DataFrame) -> DataFrame:
    """(hit_id, hit_h, more): spans of disclosing terms for the documents that have any."""
    words = docs.select("doc_id", "h", F.explode(terms(F.col("text"))).alias("term"))
    hits = words.join(broadcast_if_small(found, BROADCAST_TERMS), "term").groupBy(F.col("doc_id").alias("hit_id"), F.col("h").alias("hit_h")).agg(F.collect_set("term").alias("terms"))
    text = F.col("text")
    more = located(text, r"\p{L}+", "term", lambda w: F.array_contains(F.col("terms"), F.lower(w)))
    marked = docs.join(broadcast_if_small(checkpointed(hits), BROADCAST_TERMS), same_row("hit_id", "hit_h")).select("hit_id", "hit_h", more.alias("more"))
    return marked.dropDuplicates(["hit_id", "hit_h"])


def same_row(doc_id: str, h: str) -> Column:
    """Rows are told apart by id and content, so that repeated ids with other texts keep their own spans."""
    return (F.col("h") == F.col(h)) & F.col("doc_id").eqNullSafe(F.col(doc_id))


def find(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", **thresholds) -> DataFrame:
    """One row per input row: doc_id, base (spans), more (spans of disclosing terms); thresholds as for ``disclosing``."""
    docs = df.select(F.col(id_col).alias("doc_id"), text_or_empty(F.col(text_col)).alias("text")).withColumn("h", F.unhex(F.md5("text")))
    base = checkpointed(docs.select("doc_id", "h", base_spans(F.col("text")).alias("spans")))
    found = checkpointed(disclosing(base, docs, **thresholds).select("term").distinct())
    out = base
    if found.isEmpty():
        out = base.withColumn("more", F.array().cast(SPAN))
    else:
        out = base.join(term_spans(docs, found), same_row("hit_id", "hit_h"), "left")
    return out.select("doc_id", "h", F.col("spans").alias("base"), F.coalesce("more", F.array().cast(SPAN)).alias("more"))


def written(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))


def sanitise(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """doc_id and the text with every span generalised to its kind in brackets."""
    docs = df.select(F.col(id_col).alias("doc_id"), text_or_empty(F.col(text_col)).alias("text")).withColumn("h", F.unhex(F.md5("text")))
    spans = find(df, id_col, text_col, **options).dropDuplicates(["doc_id", "h"])
    spans = spans.select(F.col("doc_id").alias("hit_id"), F.col("h").alias("hit_h"), F.concat("base", "more").alias("spans"))
    both = docs.join(spans, same_row("hit_id", "hit_h")).select("doc_id", "text", "spans")
    ordered = F.array_sort(F.transform("spans", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))
    text = F.col("text")

    def step(acc: Column, s: Column) -> Column:
        piece = F.when(s["start"] >= acc["at"], F.concat(F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), F.lit("["), F.upper(s["kind"]), F.lit("]"))).otherwise(F.lit(""))
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.concat(acc["out"], F.array(piece)).alias("out"))

    begin = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out"))
    whole = F.aggregate(ordered, begin, step, lambda acc: F.concat(F.concat_ws("", acc["out"]), F.substring(text, acc["at"] + 1, F.length(text))))
    return both.select("doc_id", whole.alias("text"))

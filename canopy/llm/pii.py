"""Information-theoretic sanitisation, in DataFrame expressions only.

Values of fixed form (mail, network address, card, telephone) are found by pattern and test. The rest is
judged by the corpus: a term that stands near a value, however seldom, reveals it as far as their co-occurrence
exceeds chance. The disclosed share is PMI(term, value) / IC(value), both estimated from counts over all
documents. A term at or above the threshold is a span of its own and removed with the values.
A key or token has no corpus to be judged by: it is a secret if its own characters carry enough information. Values
and secrets are generalised to their kind's mark.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from canopy.llm.common import cut, small_enough, temporary

KINDS = ("email", "ip", "card", "phone")
TERM, SECRET = "term", "secret"
#: Patterns in possessive form: a start inside a run that has failed would fail too, so each run is read once.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must hold for the pattern to have a chance.
NEEDS = {"email": "@", "ip": r"[0-9]\.[0-9]", "card": r"[0-9][\x20-]?[0-9]", "phone": r"\+[0-9]"}
SPANS = "array<struct<s:int,k:int,e:int,v:string>>"
BYTE = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9]{2}|[0-9]{1,2})"
#: A secret: one unbroken run with letters and digits, of at least so many bits in all and for each character.
SECRET_PATTERN = r"(?<![A-Za-z0-9_+/=-])[A-Za-z0-9_+/=-]{20,}+"
SECRET_BITS, SECRET_BITS_EACH = 64, 3
#: Words on each side of a value that count as near it.
NEAR = 6
THRESHOLD = 0.5
TERM_PATTERN = r"[\p{L}]{4,}"
#: Characters first read beside a value; more, tenfold each time, where they don't hold NEAR whole words.
REACH = (120, 1200, 12_000)


def digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def luhn(m: Column) -> Column:
    """The weighted digit sum is a multiple of ten; every second digit from the right counts double."""
    d = F.reverse(digits(m))
    cells = F.transform(F.sequence(F.lit(1), F.length(d)), lambda i: F.substring(d, i, F.lit(1)).cast("int") * (2 - i % 2))
    return F.aggregate(cells, F.lit(0), lambda a, x: a + x - F.when(x > 9, 9).otherwise(0)) % 10 == 0


def holds(kind: str, m: Column) -> Column:
    n = F.length(digits(m))
    if kind == "ip":
        return m.rlike(f"^{BYTE}(?:\\.{BYTE}){{3}}$")
    if kind == "card":
        return F.when(n.between(14, 19), luhn(m)).otherwise(False)
    if kind == "phone":
        return n.between(10, 15)
    return F.lit(True)


def information(v: Column) -> Column:
    """Bits of v by its own character frequencies."""
    n = F.length(v)
    each = lambda c: n - F.length(F.replace(v, c, F.lit("")))
    return F.aggregate(F.array_distinct(F.split(v, "")), F.lit(0.0), lambda a, c: a + F.when(c == "", 0.0).otherwise(each(c) * F.log2(n / each(c))))


def secrets(text: Column, base: Column) -> Column:
    """(s, k, e, v) of secrets that overlap no base span."""
    free = lambda x: ~F.exists(base, lambda p: (p["s"] < x["e"]) & (x["s"] < p["e"]))
    rich = lambda v: v.rlike("[A-Za-z]") & v.rlike("[0-9]") & (information(v) >= F.greatest(F.lit(SECRET_BITS), SECRET_BITS_EACH * F.length(v)))
    hits = F.filter(walked(text, SECRET_PATTERN, len(KINDS) + 1), lambda x: rich(x["v"]) & free(x))
    return F.when(text.rlike("[A-Za-z0-9_+/=-]{20}"), hits).otherwise(F.array().cast(SPANS))


def walked(text: Column, pattern: str, k: int, wanted=lambda v: F.lit(True)) -> Column:
    """Array of (start, kind number, end, value) of the pattern's matches that are wanted, in code points.

    split() gives what stands between matches and regexp_extract_all() the matches; their lengths in
    turn give the places.
    """
    gaps, hits = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    span = lambda a, x: F.struct((a["at"] + x["g"]).alias("s"), F.lit(k).alias("k"), (a["at"] + x["g"] + F.length(x["h"])).alias("e"), x["h"].alias("v"))
    return F.aggregate(
        F.arrays_zip(F.transform(gaps, F.length).alias("g"), hits.alias("h")),
        F.struct(F.lit(0).alias("at"), F.array().cast(SPANS).alias("out")),
        lambda a, x: F.struct(
            (a["at"] + x["g"] + F.coalesce(F.length(x["h"]), F.lit(0))).alias("at"),
            F.when(x["h"].isNotNull() & wanted(x["h"]), F.concat(a["out"], F.array(span(a, x)))).otherwise(a["out"]).alias("out"),
        ),
    )["out"]


def found(text: Column, kind: str) -> Column:
    """The kind's valid matches."""
    need = F.contains(text, F.lit("@")) if kind == "email" else text.rlike(NEEDS[kind])
    return F.when(need, walked(text, PATTERNS[kind], KINDS.index(kind), lambda v: holds(kind, v))).otherwise(F.array().cast(SPANS))


def base_spans(docs: DataFrame) -> DataFrame:
    """docs with ``pii``: the sorted base spans of the whole text; none for a null text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    any_need = F.contains(text, F.lit("@")) | text.rlike("[0-9]")
    return docs.withColumn("pii", F.when(any_need, F.array_sort(F.concat(*(found(text, k) for k in KINDS)))).otherwise(F.array().cast(SPANS)))


def words(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(TERM_PATTERN), F.lit(0))


def beside(text: Column, p: Column) -> Column:
    """The NEAR words before a value and the NEAR after it.

    A piece of the text is read on each side. Its outermost word may be cut, so it must hold one word more than
    is wanted; else a longer piece is read, at last the whole side.
    """

    def side(piece, whole, order) -> Column:
        out = order(words(whole))
        for n in reversed(REACH):
            got = words(piece(n))
            out = F.when(F.size(got) > NEAR, order(got)).otherwise(out)
        return F.slice(out, 1, NEAR)

    left = side(lambda n: F.substring(text, F.greatest(p["s"] - n, F.lit(0)) + 1, F.least(p["s"], F.lit(n))), F.substring(text, F.lit(1), p["s"]), F.reverse)
    right = side(lambda n: F.substring(text, p["e"] + 1, F.lit(n)), F.substring(text, p["e"] + 1, F.length(text)), lambda x: x)
    return F.concat(left, right)


def revealing_terms(marked: DataFrame, docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(value, term): terms whose disclosed share of a value reaches the threshold, for values of any number of sightings.

    p(value), p(term) and p(both) are shares of documents; for both, the term stands near the value. All documents
    count, copies too, on both sides: a term found only beside one value reveals all of it, be it in one document or in fifty copies.
    The corpus becomes its vocabulary with counts before anything is joined.
    """
    held = marked.where(F.size("pii") > 0).select("text", "pii")
    # no value holds a tab; distinct strings are found by hash, distinct structs pair by pair
    pairs = F.array_distinct(F.flatten(F.transform("pii", lambda p: F.transform(beside(F.col("text"), p), lambda t: F.concat_ws("\t", p["v"], t)))))
    values = held.select(F.explode(F.array_distinct(F.transform("pii", lambda p: p["v"]))).alias("value")).groupBy("value").agg(F.count("*").alias("n_value"))
    seen = held.select(F.explode(pairs).alias("x")).select(F.split("x", "\t").alias("x")).select(F.col("x")[0].alias("value"), F.col("x")[1].alias("term"))
    both = cut(seen.groupBy("value", "term").agg(F.count("*").alias("n_both")).join(values, "value"), "pii-pairs")
    if not both.take(1):
        return both.select("value", "term")
    vocabulary = docs.where(F.col("text").isNotNull()).select(F.explode(F.array_distinct(words(F.col("text")))).alias("term")).groupBy("term").agg(F.count("*").alias("n_term"))
    total = F.lit(float(max(docs.count(), 1)))
    pmi = F.log2(F.col("n_both") * total / (F.col("n_value") * F.col("n_term")))
    share = pmi / F.greatest(F.log2(total / F.col("n_value")), F.lit(1e-9))
    return both.join(vocabulary, "term").where(share >= threshold).select("value", "term")


def terms_held(hit: DataFrame, terms: DataFrame) -> DataFrame:
    """Per distinct (doc_id, mark): the terms that stand anywhere in the text and reveal a value it holds."""
    small = small_enough(terms)
    known = terms.select("term").distinct()
    held = hit.select("doc_id", "mark", F.array_distinct(F.transform("pii", lambda x: x["v"])).alias("values"), F.explode(F.array_distinct(words(F.col("text")))).alias("term"))
    each = held.join(F.broadcast(known) if small else known, "term", "left_semi").select("doc_id", "mark", "term", F.explode("values").alias("value"))
    return each.join(F.broadcast(terms) if small else terms, ["value", "term"]).groupBy("doc_id", "mark").agg(F.collect_set("term").alias("terms"))


def term_spans(text: Column, terms: Column) -> Column:
    return walked(text, TERM_PATTERN, len(KINDS), lambda v: F.array_contains(terms, F.lower(v)))


def find(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """docs with ``pii`` (base spans) and ``spans`` (base, secrets and revealing terms, by start, then kind).

    Null and empty texts have none. Repeated rows have equal spans. An empty table gives no rows.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    with temporary() as kept:
        marked = cut(base_spans(docs).withColumn("spans", F.array_sort(F.concat("pii", secrets(text, F.col("pii"))))), "pii-base")
        terms = cut(revealing_terms(marked, docs, threshold), "pii-terms")
        kept += [marked, terms]
    if not terms.take(1):
        return marked
    rest = marked.where(F.size("pii") == 0)
    hit = marked.where(F.size("pii") > 0).withColumn("mark", F.sha2("text", 256))
    extra = terms_held(hit, terms).withColumnRenamed("doc_id", "x_id").withColumnRenamed("mark", "x_mark")
    both = hit.join(extra, F.col("doc_id").eqNullSafe(F.col("x_id")) & (F.col("mark") == F.col("x_mark")), "left")
    spans = F.when(F.col("terms").isNull(), F.col("spans")).otherwise(F.array_sort(F.concat("spans", term_spans(F.col("text"), F.col("terms")))))
    return rest.unionByName(both.withColumn("spans", spans).drop("x_id", "x_mark", "terms", "mark"))


def said(spans: Column) -> Column:
    """kind:start:end, joined by commas."""
    names = F.array(*map(F.lit, [*KINDS, TERM, SECRET]))
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(names, x["k"] + 1), x["s"].cast("string"), x["e"].cast("string"))), ",")


def report(docs: DataFrame) -> DataFrame:
    """The digest of find(): counts by base kind, hash of the base spans, all spans and their number."""
    n = lambda k: F.size(F.filter("pii", lambda x: x["k"] == KINDS.index(k))).cast("long").alias(f"n_{k}")
    got = find(docs.select("doc_id", "text"))
    return got.select("doc_id", *map(n, KINDS), F.sha2(said(F.col("pii")), 256).alias("base_sha256"), said(F.col("spans")).alias("spans"), F.size("spans").cast("long").alias("n_spans"))


def sanitised(text: Column, spans: Column) -> Column:
    """The text with each span replaced by its kind's mark (values) or dropped (terms); of overlapping spans the first stands for all."""
    marks = F.array(*(F.lit(f"[{k.upper()}]") for k in KINDS), F.lit(""), F.lit("[SECRET]"))
    walked = F.aggregate(
        spans,
        F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out")),
        lambda a, x: F.struct(
            F.greatest(a["at"], x["e"]).alias("at"),
            F.when(x["s"] >= a["at"], F.concat(a["out"], F.array(F.substring(text, a["at"] + 1, x["s"] - a["at"]), F.element_at(marks, x["k"] + 1)))).otherwise(a["out"]).alias("out"),
        ),
    )
    tail = F.struct(walked.alias("w"))["w"]
    return F.when(F.size(spans) == 0, text).otherwise(F.concat(F.array_join(tail["out"], ""), F.substring(text, tail["at"] + 1, F.length(text))))


def sanitise(docs: DataFrame) -> DataFrame:
    """docs with the same columns, found spans replaced in the text. Null texts stay null."""
    held = docs.select("doc_id", "text", F.struct(*docs.columns).alias("row"))
    got = find(held).select(F.col("row").withField("text", sanitised(F.col("text"), F.col("spans"))).alias("row"))
    return got.select("row.*")

"""Personal data: fixed patterns, and terms whose company in the corpus gives protected entities away. DataFrame functions only.

Every value that the patterns find is a protected entity, and so is each kind of value, which lets values that occur once count together.
Whole words within a window on either side of a mention are weighed by what the corpus says: in how many different windows of the
entity the term stands, how many windows the entity has, and how many documents the term occurs in. Pointwise mutual
information, as a part of the entity's own information content, and shrunk by n / (n + 1) for n joint windows, is how strongly the term
reveals the entity. Terms that reveal more than the disclosure threshold become spans of kind ``term``; ``sanitise`` puts a general
word in place of the spans of every kind. Windows of equal text count once, so copies of a document are no further evidence.

Term counts come map-side first; mentions cost a fixed number of rows each, so no pairs are formed within a document or group.

Defined cases: null text is the empty text, without spans; an empty table gives no rows; rows repeated under one id, or without one, are
searched and sanitised each by itself; offsets are code points, end exclusive; terms that overlap a pattern's span are no terms.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import joined_spans, spans_of, staged

# The patterns asked for. Repetition is possessive where it cannot change what matches, and a run of
# characters is entered at its beginning only, so long runs cost linear time.
EMAIL = r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}"
CARD = r"[0-9](?:[\x20-]?[0-9])++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
OCTETS = r"^0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]?[0-9])(?:\.0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]?[0-9])){3}$"
KINDS = ("email", "ip", "card", "phone")

#: This many characters on either side of a mention are its window; terms are words of at least three letters that lie within it.
WINDOW = 128
TERM_BEFORE, TERM_AFTER = r"(?<=\P{L})\p{L}{3,}+", r"(?<!\p{L})\p{L}{3,}+(?=\P{L})"
#: Part of an entity's information that a term may reveal, and least joint windows for values and for kinds.
THRESHOLD, LEAST_VALUE, LEAST_KIND = 0.6, 2, 3


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the check digit test."""
    values = F.transform(F.reverse(F.split(digits, "")), lambda d: d.cast("int"))
    weighed = F.transform(values, lambda d, i: F.when(i % 2 == 0, d).otherwise(F.when(d > 4, 2 * d - 9).otherwise(2 * d)))
    return F.aggregate(weighed, F.lit(0), lambda a, d: a + d) % 10 == 0


def base_spans(text: Column) -> Column:
    """array<struct<kind,start,end,value>>, by kind as listed and start. A pattern runs only on texts with its marks."""

    def digits(value: Column) -> Column:
        return F.regexp_replace(value, "[^0-9]", "")

    def card(value: Column) -> Column:
        bare = digits(value)
        return F.length(bare).between(16, 19) & luhn(F.when(F.length(bare) <= 19, bare).otherwise(F.lit("1")))

    rules = {
        "email": (EMAIL, F.contains(text, F.lit("@")), lambda v: F.lit(True)),
        "ip": (IP, text.rlike(r"[0-9]\.[0-9]"), lambda v: v.rlike(OCTETS)),
        "card": (CARD, text.rlike(r"[0-9](?:[\x20-]?[0-9]){15}"), card),
        "phone": (PHONE, text.rlike(r"\+[0-9]"), lambda v: F.length(digits(v)).between(8, 15)),
    }

    def named(kind: str, pattern: str, marks: Column, passes: Callable[[Column], Column]) -> Column:
        found = F.filter(spans_of(text, pattern), lambda s: passes(s["value"]))
        spans = F.transform(found, lambda s: F.struct(F.lit(kind).alias("kind"), s["start"].alias("start"), s["end"].alias("end"), s["value"].alias("value")))
        return F.when(marks, spans).otherwise(F.array().cast("array<struct<kind:string,start:int,end:int,value:string>>"))

    return F.concat(*[named(kind, *rule) for kind, rule in rules.items()])


def _windows(text: Column) -> Column:
    """For each base span its entity and what stands around it, with one character more on the outer sides, a blank at the text's ends.

    A term is whole if a character that is no letter lies between it and the outer edge."""

    def window(s: Column) -> Column:
        begin = F.greatest(s["start"] - WINDOW, F.lit(0))
        before = F.concat(F.when(begin == 0, F.lit(" ")).otherwise(F.substring(text, begin, F.lit(1))), F.substring(text, begin + 1, s["start"] - begin))
        after = F.concat(F.substring(text, s["end"] + 1, F.lit(WINDOW + 1)), F.when(F.length(text) <= s["end"] + WINDOW, F.lit(" ")).otherwise(F.lit("")))
        return F.struct(s["kind"].alias("kind"), F.xxhash64(s["kind"], F.lower(s["value"])).alias("entity"), F.xxhash64(before, s["value"], after).alias("context"), (begin - 1).alias("from"), before.alias("before"), s["end"].alias("to"), after.alias("after"))

    return F.transform("base", window)


def find_personal_data(docs: DataFrame, threshold: float = THRESHOLD, least_value: int = LEAST_VALUE, least_kind: int = LEAST_KIND, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, ``base`` and ``terms``, arrays of (kind, start, end, value)."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    found = docs.select(F.col(id_col).alias("id"), base_spans(text).alias("base"), text.alias("text"))
    # What stands around each mention is kept with it, so texts are not needed again.
    found = found.select("id", "base", F.when(F.size("base") > 0, _windows(F.col("text"))).alias("around"))
    found = staged(found.withColumn("rid", F.monotonically_increasing_id()), "pii-base")
    mentions = found.where(F.size("base") > 0).select("rid", "base", F.explode("around").alias("m"))
    terms = F.concat(spans_of(F.col("m.before"), TERM_BEFORE, F.col("m.from")), spans_of(F.col("m.after"), TERM_AFTER, F.col("m.to")))
    near = mentions.select("rid", "base", "m.kind", "m.entity", "m.context", F.explode(terms).alias("t"))
    near = near.where(~F.exists("base", lambda s: (s["start"] < F.col("t.end")) & (s["end"] > F.col("t.start"))))
    near = staged(near.select("rid", "kind", "entity", "context", F.lower("t.value").alias("term"), F.col("t.start").alias("start"), F.col("t.end").alias("end"), F.col("t.value").alias("value")), "pii-near")

    # A window's terms are the text's own words, folded one by one, so a term is in at least as many documents as its windows are.
    words = F.transform(F.array_distinct(F.split(F.coalesce(F.col(text_col), F.lit("")), r"[^\p{L}]+")), F.lower)
    occurring = docs.select(F.explode(F.array_distinct(words)).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("n_term"))
    total = F.lit(max(1, found.count())).cast("double")
    contexts = found.where(F.size("base") > 0).select(F.explode("around").alias("m")).select("m.kind", "m.entity", "m.context").distinct()

    def revealing(entity: str, least: int) -> DataFrame:
        joint = near.select(entity, "term", "context").distinct().groupBy(entity, "term").agg(F.count(F.lit(1)).alias("both")).where(F.col("both") >= least)
        known = contexts.select(entity, "context").distinct().groupBy(entity).agg(F.count(F.lit(1)).alias("n_entity"))
        information = F.log2(total / F.col("n_entity"))
        # Several mentions in one document are several windows, so a rate above one is cut to it.
        mutual = F.log2(total * F.least(F.col("both"), F.col("n_term")) / (F.col("n_entity") * F.col("n_term")))
        weighed = joint.join(known, entity).join(occurring, "term").where((information > 0) & (mutual * F.col("both") / (F.col("both") + 1) >= threshold * information))
        return staged(weighed.select(entity, "term"), f"pii-revealing-{entity}")

    hits = near.join(revealing("entity", least_value), ["entity", "term"], "left_semi").unionByName(near.join(revealing("kind", least_kind), ["kind", "term"], "left_semi"))
    spans = hits.select("rid", F.struct(F.lit("term").alias("kind"), "start", "end", "value").alias("span"))
    spans = spans.groupBy("rid").agg(F.sort_array(F.collect_set("span")).alias("terms"))
    empty = F.array().cast("array<struct<kind:string,start:int,end:int,value:string>>")
    return found.join(spans, "rid", "left").select(F.col("id").alias(id_col), "base", F.coalesce("terms", empty).alias("terms"))


def of_kind(spans: str, kind: str) -> Column:
    return F.filter(spans, lambda s: s["kind"] == kind)


def digest(found: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Counts, checksum and text of the spans."""
    counts = [F.size(of_kind("base", kind)).cast("long").alias(f"n_{kind}") for kind in KINDS]
    everything = F.concat("base", F.sort_array("terms"))
    return found.select(id_col, *counts, F.sha2(joined_spans(F.col("base")), 256).alias("base_sha256"), joined_spans(everything).alias("spans"))


def sanitised(text: Column, spans: Column) -> Column:
    """``text`` with each span of array<struct<kind,start,end,..>> replaced by its kind in brackets; overlapping spans by the first."""
    ordered = F.array_sort(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))

    def step(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        piece = F.concat(acc["out"], F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), F.lit("["), s["kind"], F.lit("]"))
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(fresh, piece).otherwise(acc["out"]).alias("out"))

    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    return F.aggregate(ordered, start, step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.length(text))))


def sanitise(docs: DataFrame, threshold: float = THRESHOLD, least_value: int = LEAST_VALUE, least_kind: int = LEAST_KIND, text_col: str = "text") -> DataFrame:
    """``docs``, row by row, with personal data and revealing terms generalised; a null text stays null.

    Rows are numbered and written down first, so ids may repeat or be null."""
    numbered = staged(docs.withColumn("__rid", F.monotonically_increasing_id()), "pii-rows")
    spans = find_personal_data(numbered, threshold, least_value, least_kind, "__rid", text_col)
    spans = spans.select(F.col("__rid").alias("__id"), F.concat("base", "terms").alias("__spans")).where(F.size("__spans") > 0)
    joined = numbered.join(spans, F.col("__rid") == F.col("__id"), "left")
    changed = F.when(F.col("__spans").isNull(), F.col(text_col)).otherwise(sanitised(F.col(text_col), F.col("__spans")))
    return joined.withColumn(text_col, changed).select(*docs.columns)

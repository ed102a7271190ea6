"""Personal data by pattern, and terms that give protected values away by corpus co-occurrence. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import join_small, store

# The patterns match exactly what the plain ones do:
#   email [A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+      ip [0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)
#   card [0-9]([\x20-]?[0-9])+                                   phone \+[0-9][\x20().0-9-]+[0-9]
# but in time linear in a run's length: a run is tried from its start (or from the end of the match before) alone, since
# a later start can only match if that does, and repeated groups are single characters with a look behind.
EMAIL = r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++\.[A-Za-z0-9-](?:[A-Za-z0-9.-](?<!\.\.))*(?<!\.)"
IP = r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
CARD = r"[0-9](?:[0-9 \-](?<![ \-]{2}))+(?<=[0-9])"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
_PART = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"

#: A secret: a long run of key characters with a letter and a digit. It tells so much by itself that no count is needed.
SECRET = r"[A-Za-z0-9+/_-]{20,}+"

KINDS = ("email", "ip", "card", "phone", "term", "secret")
SPAN = "struct<start:long,rank:int,end:long,kind:string,value:string>"
_EMPTY = f"array<{SPAN}>"

#: A term: a run of at least three letters, in lower case. Its class, what it is generalised to, is its first three
#: letters and a star: all terms that begin alike.
TERM = r"\p{L}{3,}"
CLASS = 3


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _count(value: Column) -> Column:
    return F.length(_digits(value))


VALID = {
    "email": lambda v: F.lit(True),
    "ip": lambda v: v.rlike(rf"^{_PART}(?:\.{_PART}){{3}}$"),
    "card": lambda v: _count(v).between(14, 19) & F.call_function("luhn_check", _digits(v)),
    "phone": lambda v: _count(v).between(10, 15),
    "secret": lambda v: v.rlike("[0-9]") & v.rlike("[A-Za-z]"),
}
PATTERNS = {"email": EMAIL, "ip": IP, "card": CARD, "phone": PHONE}
#: Cheap tests that every text with such a match passes.
HINTS = {
    "email": lambda t: t.contains("@"),
    "ip": lambda t: t.rlike(r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]"),
    "card": lambda t: t.rlike(r"[0-9](?:[ \-]?[0-9]){13}"),
    "phone": lambda t: t.contains("+"),
    "secret": lambda t: t.rlike(r"[A-Za-z0-9+/_-]{20}"),
}


def located(text: Column, pattern: str, kind: str, keep) -> Column:
    """Spans of all matches that `keep` accepts: the text split at matches and the matches give their places."""
    parts = F.zip_with(F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda p, h: F.struct(p.alias("p"), h.alias("h")))

    def step(acc, x):
        start = acc["at"] + F.length(x["p"])
        end = start + F.length(x["h"])
        span = F.struct(start.cast("long").alias("start"), F.lit(KINDS.index(kind)).alias("rank"), end.cast("long").alias("end"), F.lit(kind).alias("kind"), x["h"].alias("value"))
        out = F.when(x["h"].isNotNull() & keep(x["h"]), F.array_append(acc["out"], span)).otherwise(acc["out"])
        return F.struct(F.coalesce(end, start).cast("long").alias("at"), out.cast(_EMPTY).alias("out"))

    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast(_EMPTY).alias("out"))
    return F.aggregate(parts, start, step, lambda acc: acc["out"])


def base_spans(text: Column) -> Column:
    """Spans of the four kinds by start, then kind."""
    none = F.array().cast(_EMPTY)
    found = [F.when(HINTS[k](text), located(text, PATTERNS[k], k, VALID[k])).otherwise(none) for k in PATTERNS]
    return F.array_sort(F.concat(*found))


def _apart(spans: Column, others: Column) -> Column:
    """spans that touch none of others."""
    return F.filter(spans, lambda s: ~F.exists(others, lambda b: (b["start"] < s["end"]) & (b["end"] > s["start"])))


def secret_spans(text: Column, base: Column) -> Column:
    """Spans of secrets that touch no base span."""
    return F.when(HINTS["secret"](text), _apart(located(text, SECRET, "secret", VALID["secret"]), base)).otherwise(F.array().cast(_EMPTY))


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def _marks(text: Column) -> Column:
    """The distinct terms of a text and their classes."""
    terms = F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit(TERM), F.lit(0)))
    return F.concat(terms, F.array_distinct(F.transform(terms, _class_of)))


def _class_of(term: Column) -> Column:
    return F.concat(F.substring(term, 1, CLASS), F.lit("*"))


def disclosing_marks(found: DataFrame, docs: DataFrame, doubt: float, most: float, small: int) -> DataFrame:
    """_key, _marks: for each text that holds a span, the terms and classes that give a value of it away.

    Every span's value is protected, however rare. How far a mark gives it away is their pointwise mutual information
    over documents, as a share of the value's information content: log2(c n_both D / (n_mark n_value)) /
    log2(D / n_value), 1 at most. Counts are over all documents; c is t / (t + doubt) for the t distinct texts that hold
    both, so few texts, or many copies of one, weigh less than many.

    Values that stand in the same texts have the same counts, so they are taken together: a text with many values of its
    own costs its terms once.
    """
    held = found.filter("_key is not null")
    spans = F.concat("_spans", "_secrets")
    values = held.select("_key", F.explode(F.array_distinct(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], F.lower(s["value"]))))).alias("value"))
    per_text = store(values.groupBy("_key", "value").agg(F.count("*").alias("n")), "values")
    digest = lambda seed: F.sum(F.xxhash64("_key", F.lit(seed)).cast("decimal(20,0)"))
    protected = store(per_text.groupBy("value").agg(F.unhex(F.md5(F.concat_ws(":", F.count("*"), digest(1), digest(2)))).alias("group"), F.sum("n").alias("n_value")), "protected")
    shared = join_small(per_text, protected, "value", "inner", protected.count(), small).groupBy("_key", "group").agg(F.first("n").alias("n"), F.first("n_value").alias("n_value"))
    shared = store(shared, "shared")

    # Counted with map-side sums: what moves grows with tasks and vocabulary, not with words.
    all_marks = docs.select(F.explode(_marks(F.coalesce(F.col("text").cast("string"), F.lit("")))).alias("mark"))
    known = store(all_marks.groupBy("mark").agg(F.count("*").alias("n_mark")), "marks")
    total = float(found.count())
    # As n_both <= n_value and c < 1, only marks this rare can pass; all others go before anything is joined by text.
    rare = lambda n_value: F.pow(F.lit(total), 1 - most) * F.pow(n_value, most) * 1.000001
    largest = shared.agg(F.max("n_value")).first()[0] or 0
    common = known.filter(F.col("n_mark") > rare(F.lit(float(largest)))).select("mark")
    texts = held.groupBy("_key").agg(F.any_value("_text").alias("_text"))
    marks = texts.select("_key", F.explode(_marks(F.col("_text"))).alias("mark"))
    marks = join_small(marks, common, "mark", "left_anti", common.count(), small).join(known, "mark")
    pairs = store(marks.join(shared, "_key").filter(F.col("n_mark") <= rare(F.col("n_value"))), "pairs")

    both = pairs.groupBy("group", "mark").agg(F.sum("n").alias("n_both"), F.count("*").alias("texts"), F.first("n_value").alias("n_value"), F.first("n_mark").alias("n_mark"))
    certain = F.col("texts") / (F.col("texts") + F.lit(float(doubt)))
    share = F.log2(certain * F.col("n_both") * total / (F.col("n_mark") * F.col("n_value"))) / F.log2(total / F.col("n_value"))
    flagged = store(both.filter(F.when(F.lit(total) > F.col("n_value"), F.round(share, 9) >= most)).select("group", "mark"), "flagged")
    at = join_small(pairs, flagged, ["group", "mark"], "left_semi", flagged.count(), small)
    return store(at.groupBy("_key").agg(F.array_sort(F.collect_set("mark")).alias("_marks")), "disclosing")


def _with_base(docs: DataFrame) -> DataFrame:
    """_row (all columns of docs), doc_id, _text (null is empty; of texts with a span only), _spans, _secrets and _key."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.struct(*docs.columns).alias("_row"), "doc_id", text.alias("_text")).withColumn("_spans", base_spans(F.col("_text")))
    rows = rows.withColumn("_secrets", secret_spans(F.col("_text"), F.col("_spans")))
    some = (F.size("_spans") > 0) | (F.size("_secrets") > 0)
    return rows.select("_row", "doc_id", F.when(some, F.col("_text")).alias("_text"), "_spans", "_secrets", F.when(some, F.unhex(F.md5("_text"))).alias("_key"))


def find(docs: DataFrame, keep_columns: bool = False, doubt: float = 0.5, most: float = 0.9, small: int = 1_000_000) -> DataFrame:
    """doc_id, _text, _spans (the four kinds), _all (with secrets and terms), _marks; with keep_columns also _row, docs' columns.

    Null text is empty. Places are code points, end exclusive. Spans of secrets and terms touch no base span. Repeated
    rows each give a row; null doc_ids stay null; other columns of docs, whatever their names, don't matter; an empty
    table gives an empty one. Rows without a span skip the join, so only texts with one are ever shuffled.
    """
    rows = _with_base(docs)
    found = store(rows if keep_columns else rows.drop("_row"), "found")
    told = disclosing_marks(found, docs, doubt, most, small)
    held = join_small(found.filter("_key is not null"), told, "_key", "left", told.count(), small)
    none = F.lit(None).cast("array<string>")
    out = held.unionByName(found.filter("_key is null").withColumn("_marks", none))
    terms = located(F.col("_text"), TERM, "term", lambda h: F.array_contains("_marks", F.lower(h)))
    extra = F.when(F.col("_marks").isNotNull(), _apart(terms, F.concat("_spans", "_secrets"))).otherwise(F.array().cast(_EMPTY))
    return out.withColumn("_all", F.array_sort(F.concat("_spans", "_secrets", extra)))


def detect(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_terms, n_secrets and n_spans, of find()'s rows."""
    out = find(docs, **options)
    count = lambda spans, kind: F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long")
    counts = [count(F.col("_spans"), k).alias(f"n_{k}") for k in PATTERNS]
    more = [count(F.col("_all"), "term").alias("n_terms"), F.size("_secrets").cast("long").alias("n_secrets"), F.size("_all").cast("long").alias("n_spans")]
    return out.select(F.col("doc_id").cast("long").alias("doc_id"), *counts, F.sha2(_listed(F.col("_spans")), 256).alias("base_sha256"), _listed(F.col("_all")).alias("spans"), *more)


def sanitise(docs: DataFrame, **options) -> DataFrame:
    """docs with text made safe: base spans become [EMAIL], [IP], [CARD] or [PHONE], secrets [SECRET]. A disclosing term
    is generalised to its class (its first letters and a star, which many terms share), or, where the class gives a
    value of the text away too, removed ([...]). Where spans overlap the first stands. n_chars, if there, is counted
    again; null stays null."""
    out = find(docs, keep_columns=True, **options)
    class_ = lambda s: _class_of(F.lower(s["value"]))
    put = lambda s: F.when(s["kind"] != "term", F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]"))).when(F.array_contains("_marks", class_(s)), F.lit("[...]")).otherwise(class_(s))
    text = F.col("_text")

    def step(acc, s):
        cut = F.concat(acc["out"], F.substr(text, (acc["at"] + 1).cast("int"), (s["start"] - acc["at"]).cast("int")), put(s))
        return F.when(s["start"] >= acc["at"], F.struct(s["end"].alias("at"), cut.alias("out"))).otherwise(F.struct(F.greatest(acc["at"], s["end"]).alias("at"), acc["out"].alias("out")))

    start = F.struct(F.lit(0).cast("long").alias("at"), F.lit("").alias("out"))
    safe = F.aggregate("_all", start, step, lambda acc: F.concat(acc["out"], F.substr(text, (acc["at"] + 1).cast("int"))))
    out = out.withColumn("_safe", F.when(F.size("_all") > 0, safe).otherwise(F.col("_row")["text"]))
    cols = [F.col("_safe").alias(c) if c == "text" else F.when(F.size("_all") > 0, F.length("_safe").cast(docs.schema[c].dataType)).otherwise(F.col("_row")[c]).alias(c) if c == "n_chars" else F.col("_row")[c].alias(c) for c in docs.columns]
    return out.select(*cols)


def _sql_spans(kind: str, pattern: str, valid: str) -> str:
    """Matches (value) of a plain pattern with their places: what stands between matches and the matches give them."""
    rank = KINDS.index(kind)
    return f"""
SELECT doc_id, '{kind}' AS kind, {rank} AS rank, value, place::BIGINT AS "start", (place + length(value))::BIGINT AS "end" FROM (
  SELECT doc_id, found[i] AS value, list_sum(list_transform(parts[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(found[1:i - 1], lambda x: length(x))), 0) AS place
  FROM (SELECT doc_id, found, parts, unnest(range(1, len(found) + 1)) AS i FROM (
    SELECT doc_id, regexp_extract_all(text, '{pattern}') AS found, string_split_regex(text, '{pattern}') AS parts FROM docs)))
WHERE {valid}"""


_SQL_DIGITS = "regexp_replace(value, '[^0-9]', '', 'g')"
_SQL_DOUBLED = f"list_transform(range(1, length({_SQL_DIGITS}) + 1), lambda i: ({_SQL_DIGITS})[-i]::INT * (2 - i % 2))"
_SQL_PLAIN = {
    "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", "true"),
    "ip": (r"[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)", "len(list_filter(string_split(value, '.'), lambda x: length(ltrim(x, '0')) > 3 OR x::HUGEINT > 255)) = 0"),
    "card": (r"[0-9](?:[\x20-]?[0-9])+", f"length({_SQL_DIGITS}) BETWEEN 14 AND 19 AND list_sum(list_transform({_SQL_DOUBLED}, lambda d: d // 10 + d % 10)) % 10 = 0"),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", f"length({_SQL_DIGITS}) BETWEEN 10 AND 15"),
}
_SQL_SECRET = (SECRET.rstrip("+"), "regexp_matches(value, '[0-9]') AND regexp_matches(value, '[A-Za-z]')")


def _sql_listed(rows: str) -> str:
    return f"""coalesce(string_agg(kind || ':' || "start" || ':' || "end", ',' ORDER BY "start", rank) FILTER ({rows}), '')"""


def _sql_apart(x: str, others: str) -> str:
    return f"""NOT EXISTS (SELECT 1 FROM {others} b WHERE b.doc_id = {x}.doc_id AND b."start" < {x}."end" AND b."end" > {x}."start")"""


#: The rows of detect(documents) with plain patterns, for doc_ids that differ.
ORACLE = f"""
WITH docs AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
base AS MATERIALIZED ({" UNION ALL ".join(_sql_spans(k, *v) for k, v in _SQL_PLAIN.items())}),
secret AS MATERIALIZED (SELECT * FROM ({_sql_spans("secret", *_SQL_SECRET)}) x WHERE {_sql_apart("x", "base")}),
sure AS MATERIALIZED (SELECT * FROM base UNION ALL SELECT * FROM secret),
words AS MATERIALIZED ({_sql_spans("term", TERM, "true")}),
held AS (SELECT DISTINCT doc_id, text, kind || ':' || lower(value) AS value FROM sure JOIN docs USING (doc_id)),
protected AS (SELECT value, count(*) AS n_value FROM held GROUP BY value),
marks AS MATERIALIZED (SELECT doc_id, lower(value) AS mark FROM words UNION SELECT doc_id, lower(value)[:{CLASS}] || '*' FROM words),
known AS (SELECT mark, count(*) AS n_mark FROM marks GROUP BY mark),
together AS (SELECT value, mark, count(*) AS n_both, count(DISTINCT text) AS texts FROM held JOIN marks USING (doc_id) GROUP BY value, mark),
size AS (SELECT count(*)::DOUBLE AS total FROM docs),
flagged AS (
  SELECT value, mark FROM together JOIN protected USING (value) JOIN known USING (mark), size
  WHERE total > n_value AND round(log2(texts / (texts + 0.5) * n_both * total / (n_mark * n_value)) / log2(total / n_value), 9) >= 0.9),
told AS (SELECT DISTINCT doc_id, mark FROM held JOIN flagged USING (value)),
extra AS (SELECT w.* FROM words w JOIN told ON w.doc_id = told.doc_id AND lower(w.value) = told.mark WHERE {_sql_apart("w", "sure")}),
listed AS (
  SELECT doc_id, {", ".join(f"count(*) FILTER (kind = '{k}') AS n_{k}" for k in PATTERNS)}, {_sql_listed("rank < 4")} AS base,
    {_sql_listed("true")} AS spans, count(*) FILTER (kind = 'term') AS n_terms, count(*) FILTER (kind = 'secret') AS n_secrets, count(*) AS n_spans
  FROM (SELECT * FROM sure UNION ALL SELECT * FROM extra) GROUP BY doc_id)
SELECT doc_id, {", ".join(f"coalesce(n_{k}, 0) AS n_{k}" for k in PATTERNS)}, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans,
  coalesce(n_terms, 0) AS n_terms, coalesce(n_secrets, 0) AS n_secrets, coalesce(n_spans, 0) AS n_spans
FROM docs LEFT JOIN listed USING (doc_id)
"""

"""Licence scan by canonical digests: whole texts, and each line as a text of its own, looked up by hash. Native."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import store
from .licence_texts import KNOWN

# Equivalent spellings, as pairs of a pattern on lower-case text and its canonical form.
SPELLINGS = [
    ("licence", "license"),
    ("licenced", "licensed"),
    ("sub-license", "sublicense"),
    ("non-infringement", "noninfringement"),
    ("merchantibility", "merchantability"),
    ("organisation", "organization"),
    ("authorised", "authorized"),
    ("favour", "favor"),
    ("judgement", "judgment"),
    ("acknowledgement", "acknowledgment"),
    ("&", " and "),
    ("https", "http"),
]

#: A line that only says who holds the copyright, on lower-case text.
COPYRIGHT = r"(?m)^[^a-z0-9\n]*(copyright|\(c\)|©)[^\n]*$"


def canonical_lines(text: Column) -> Column:
    """Lower case (A-Z), copyright lines out, spellings made one, runs of anything but a-z, 0-9 and line ends made a blank.

    No step reaches over a line end, so the lines of this are those of text, each normalised by itself but for outer blanks.
    """
    out = F.regexp_replace(F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), COPYRIGHT, " ")
    for a, b in SPELLINGS:
        out = F.replace(out, F.lit(a), F.lit(b))
    return F.regexp_replace(out, "[^a-z0-9\n]+", " ")


def joined_lines(lines: Column) -> Column:
    """One canonical text of canonical lines: single blanks and no line ends."""
    return F.trim(F.regexp_replace(lines, "[ \n]+", " "))


def canonical(text: Column) -> Column:
    """Lower case (A-Z), copyright lines out, spellings made one, everything but a-z and 0-9 made single blanks."""
    return joined_lines(canonical_lines(text))


def digest(text: Column) -> Column:
    return F.sha2(canonical(text), 256)


def known_digests(spark, known=None) -> DataFrame:
    """licence, digest: one row a known text, the first id in order where texts are the same once normalised."""
    rows = spark.createDataFrame(list(known if known is not None else KNOWN), "licence string, _text string")
    rows = rows.select("licence", canonical(F.col("_text")).alias("_text")).filter("_text <> ''")
    return rows.groupBy(F.sha2("_text", 256).alias("digest")).agg(F.min("licence").alias("licence"))


#: Known texts up to which they are broadcast, as a table and as a map; beyond, lines become rows and both joins are shuffled.
MOST_KNOWN = 20_000


def scan(docs: DataFrame, known=None, most_known: int = MOST_KNOWN) -> DataFrame:
    """doc_id, digest, whole_licence, n_licence_lines, licences.

    digest is of the whole canonical text; whole_licence its licence, or null; n_licence_lines counts lines that are
    known notices; licences are the distinct ids of both, sorted and comma-joined. Null text: null digest, no licence.
    Text with nothing left after normalisation matches nothing. Repeated rows each give a row; null doc_ids stay null;
    other columns are ignored, whatever their names; an empty table gives an empty one. Texts of any length are read whole.
    """
    spark = docs.sparkSession
    known = list(known if known is not None else KNOWN)
    table = known_digests(spark, known)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), canonical_lines(F.col("text")).alias("_text"))
    lines = F.transform(F.split(F.coalesce(F.col("_text"), F.lit("")), "\n"), lambda x: F.trim(x))
    if len(known) > most_known:
        return _scan_joined(rows.withColumn("_lines", lines), table)
    sizes = spark.createDataFrame(known or [("", "")], "licence string, _text string").select(F.length(canonical(F.col("_text"))).alias("size")).filter("size > 0")
    sizes = F.broadcast(sizes.agg(F.collect_set("size").alias("_sizes")))
    lookup = F.broadcast(table.agg(F.map_from_entries(F.collect_list(F.struct("digest", "licence"))).alias("_map")))
    # A canonical line can only be a known text if it has the length of one: the rest skip hashing.
    rows = rows.join(sizes, F.lit(True), "left")
    hashes = F.transform(F.filter(lines, lambda x: F.array_contains(F.col("_sizes"), F.length(x))), lambda x: F.sha2(x, 256))
    rows = rows.select("doc_id", F.sha2(joined_lines(F.col("_text")), 256).alias("digest"), hashes.alias("_lines"))
    # The known table is joined to whole texts by hash, and to lines through the same table as a map.
    joined = rows.join(F.broadcast(table), "digest", "left").join(lookup, F.lit(True), "left")
    return _described(joined.withColumn("_found", F.filter(F.transform("_lines", lambda x: F.element_at(F.col("_map"), x)), lambda x: x.isNotNull())))


def _described(rows: DataFrame) -> DataFrame:
    """scan()'s columns of doc_id, digest, licence (of the whole text) and _found (of each known line)."""
    whole = F.when(F.col("licence").isNotNull(), F.array("licence")).otherwise(F.array().cast("array<string>"))
    return rows.select(
        "doc_id",
        "digest",
        F.col("licence").alias("whole_licence"),
        F.size("_found").cast("long").alias("n_licence_lines"),
        F.array_join(F.array_sort(F.array_distinct(F.concat("_found", whole))), ",").alias("licences"),
    )


def _scan_joined(rows: DataFrame, table: DataFrame) -> DataFrame:
    """The same by shuffled hash joins, for any number of known texts. Only distinct digests of lines meet the table."""
    rows = rows.select(F.monotonically_increasing_id().alias("_row"), "doc_id", F.sha2(joined_lines(F.col("_text")), 256).alias("digest"), F.transform(F.filter("_lines", lambda x: x != ""), lambda x: F.sha2(x, 256)).alias("_lines"))
    rows = store(rows, "licence-lines")
    lines = rows.select("_row", F.explode("_lines").alias("digest")).groupBy("_row", "digest").agg(F.count("*").alias("n"))
    hits = lines.join(table, "digest").select("_row", F.explode(F.array_repeat("licence", F.col("n").cast("int"))).alias("_hit"))
    hits = hits.groupBy("_row").agg(F.collect_list("_hit").alias("_found"))
    out = rows.join(table, "digest", "left").join(hits, "_row", "left")
    return _described(out.withColumn("_found", F.coalesce("_found", F.array().cast("array<string>"))))


def _sql_canonical(x: str) -> str:
    out = f"regexp_replace(translate({x}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{COPYRIGHT}', ' ', 'g')"
    for a, b in SPELLINGS:
        out = f"replace({out}, '{a}', '{b}')"
    return f"trim(regexp_replace({out}, '[^a-z0-9]+', ' ', 'g'))"


def _values() -> str:
    return ", ".join("('{}', '{}')".format(i, t.replace("'", "''")) for i, t in KNOWN)


ORACLE = f"""
WITH known AS (SELECT sha256({_sql_canonical('t')}) AS digest, min(licence) AS licence FROM (VALUES {_values()}) v(licence, t) GROUP BY 1),
docs AS (SELECT row_number() OVER () AS r, doc_id, text, sha256({_sql_canonical('text')}) AS digest FROM documents),
lines AS (SELECT r, sha256({_sql_canonical('line')}) AS digest FROM (SELECT r, unnest(string_split(text, chr(10))) AS line FROM docs)),
hits AS (SELECT r, licence FROM lines JOIN known USING (digest)),
both_ AS (SELECT r, licence FROM hits UNION SELECT r, licence FROM docs JOIN known USING (digest)),
lined AS (SELECT r, count(*) AS n FROM hits GROUP BY r),
named AS (SELECT r, string_agg(licence, ',' ORDER BY licence) AS ids FROM both_ GROUP BY r)
SELECT doc_id, d.digest, k.licence AS whole_licence, coalesce(n, 0) AS n_licence_lines, coalesce(ids, '') AS licences
FROM docs d LEFT JOIN known k USING (digest) LEFT JOIN lined USING (r) LEFT JOIN named USING (r)
"""

"""Licence scans by canonical digest lookup, in DataFrame functions only.

A text is lower-cased, loses its copyright lines, gets one spelling for equivalent ones, and keeps only letters and digits
between single blanks; its SHA-256 is joined to those of known licences. Entire texts are looked up, and each line as a text of its own,
since notices stand alone on a line. The known texts are broadcast while they are at most `MAX_KNOWN`, and shuffled beyond.

Defined results: null text counts as empty; an empty canonical text matches nothing; a licence known by several texts is named
once; lines are cut at line feeds; each row of docs gives one row; empty tables give an empty result, or no licences. Other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .license_texts import KNOWN, KNOWN_DIGESTS

MAX_KNOWN = 100_000
#: Patterns that go, then spellings that are one.
DROPPED = (r"(?m)^[^a-z0-9\n]*(copyright[\x20\t]*(\(c\)|©|[0-9])|\(c\)[\x20\t]*[0-9]|©)[^\n]*$", r"(?m)^[^a-z0-9\n]*all rights reserved[^a-z0-9\n]*$")
SPELLINGS = (("licence", "license"), ("acknowledgement", "acknowledgment"), ("organisation", "organization"), ("favour", "favor"), ("http:", "https:"), ("non-infringement", "noninfringement"), ("&", " and "), ("version 2.0", "version 2"), ("-2.0", "-2"))
GAPS = r"[^\p{L}\p{N}]+"


def canonical(text: Column) -> Column:
    out = F.lower(text)
    for p in DROPPED:
        out = F.regexp_replace(out, p, "")
    for a, b in SPELLINGS:
        out = F.replace(out, F.lit(a), F.lit(b))
    return F.trim(F.regexp_replace(out, GAPS, " "))


def known_digests(spark, known=KNOWN, digests=KNOWN_DIGESTS) -> DataFrame:
    """(known_digest, license) of known texts, and of those known by their digest alone."""
    rows = spark.createDataFrame([(n, t) for n, t in known], "license string, t string")
    told = spark.createDataFrame([(d, n) for n, d in digests], "known_digest string, license string")
    return rows.select(F.sha2(canonical(F.col("t")), 256).alias("known_digest"), "license").union(told).dropDuplicates(["known_digest"])


def scan_licenses(docs: DataFrame, known: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, digest, license, notices): license of the entire text or null; notices is the sorted set of licences of its lines."""
    known = known_digests(docs.sparkSession) if known is None else known
    known = F.broadcast(known) if known.limit(MAX_KNOWN + 1).count() <= MAX_KNOWN else known
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.monotonically_increasing_id().alias("row"), text.alias("t"))
    units = rows.select("id", "row", F.posexplode(F.concat(F.array("t"), F.split("t", "\n", -1))).alias("unit", "u"))
    digests = units.select("id", "row", "unit", F.sha2(canonical(F.col("u")), 256).alias("digest"))
    found = digests.join(known, F.col("digest") == F.col("known_digest"), "left").where("unit = 0 or license is not null")
    whole, line = F.col("unit") == 0, F.col("unit") > 0
    by_row = found.groupBy("row", "id").agg(
        F.max(F.when(whole, F.col("digest"))).alias("digest"), F.max(F.when(whole, F.col("license"))).alias("license"),
        F.array_sort(F.collect_set(F.when(line, F.col("license")))).alias("notices"),
    )
    return by_row.select("id", "digest", "license", "notices")


def op1(docs: DataFrame) -> DataFrame:
    s = scan_licenses(docs)
    return s.select(F.col("id").alias("doc_id"), "digest", "license", F.array_join("notices", ",").alias("notices"))


def sql() -> str:
    """DuckDB."""
    quote = lambda s: "'" + s.replace("'", "''") + "'"

    def canon(x):
        x = f"lower({x})"
        for p in DROPPED:
            x = f"regexp_replace({x}, {quote(p)}, '', 'g')"
        for a, b in SPELLINGS:
            x = f"replace({x}, {quote(a)}, {quote(b)})"
        return f"trim(regexp_replace({x}, {quote(GAPS)}, ' ', 'g'), ' ')"

    known = ", ".join(f"({quote(n)}, {quote(t)})" for n, t in KNOWN)
    digests = ", ".join(f"({quote(n)}, {quote(d)})" for n, d in KNOWN_DIGESTS)
    return f"""WITH k AS (SELECT DISTINCT license, sha256({canon('t')}) AS h FROM (VALUES {known}) v(license, t) UNION SELECT * FROM (VALUES {digests})),
    d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
    line AS (SELECT r, sha256({canon('u')}) AS h FROM (SELECT r, unnest(string_split(t, chr(10))) AS u FROM d)),
    n AS (SELECT r, string_agg(DISTINCT license, ',' ORDER BY license) AS notices FROM line JOIN k USING (h) GROUP BY r),
    w AS (SELECT r, doc_id, sha256({canon('t')}) AS digest FROM d)
    SELECT doc_id, digest, license, coalesce(notices, '') AS notices FROM w LEFT JOIN n USING (r) LEFT JOIN k ON k.h = w.digest"""

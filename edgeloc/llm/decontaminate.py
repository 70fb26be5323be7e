"""Benchmark decontamination: a prefix-filtered set join on word shingles, in DataFrame functions only.

A window is `window_words` consecutive words of an item, or all words of a shorter one. A document that holds a window
holds all its shingles, so one of them, the rarest over all documents, is a sufficient prefix: windows join
documents on that shingle alone. The shingle's offset in the window gives the one place where the window can lie (positional bound), which must be
inside the document (length bound); the words there are then compared exactly.

The windows' prefix table is broadcast if it has at most `broadcast_rows` rows and `broadcast_bytes` bytes, else document shingles are shuffled to
it with the words around them; equal rows (id and text, told by 128 bits of hash) are then looked at as one and given back as many. Document shingles are made in one pass and never stored.

Defined results: null text, or one without words, has no words and is never hit; items without words have no windows; windows of
items with a null id hit words but name no item; repeated rows and equal items count as they stand; a document's
row stays one row; empty tables give an empty result, or no hits. Other columns are not read, and pass drop_contaminated untouched, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, fresh, text_key

#: Fixed value: what separates words, after A-Z are lower-cased.
GAPS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    """Split at the gaps; a gap at either end leaves an empty word, which is cut off."""
    parts = F.split(F.concat(ascii_lower(F.coalesce(text.cast("string"), F.lit(""))), F.lit(" ")), GAPS)
    lead = (F.element_at(parts, 1) == "").cast("int")
    return F.slice(parts, lead + 1, F.size(parts) - 1 - lead)


def _shingle(words: Column, at: Column, n: int) -> Column:
    """Hash of n words from the 0-based place at; null beyond the end."""
    return F.when(at + n <= F.size(words), F.xxhash64(F.lit(n), *(F.get(words, at + k) for k in range(n))))


def benchmark_windows(benchmark: DataFrame, item_col: str, text_col: str, window_words: int, shingle_words: int) -> DataFrame:
    """(win, items, len, words, shingles): distinct windows, the items that hold them, and (size, at, h) of each shingle."""
    w = benchmark.select(F.col(item_col).cast("string").alias("item"), words_of(F.col(text_col)).alias("all")).where("size(all) > 0")
    starts = F.sequence(F.lit(0), F.greatest(F.size("all") - window_words, F.lit(0)))
    w = w.select("item", "all", F.explode(starts).alias("s")).select("item", F.slice("all", F.col("s") + 1, window_words).alias("words"))
    w = w.groupBy("words").agg(F.collect_set("item").alias("items"))
    at = lambda n: F.transform(F.sequence(F.lit(0), F.size("words") - n), lambda i: F.struct(F.lit(n).alias("size"), i.alias("at"), _shingle(F.col("words"), i, n).alias("h")))
    cases = F.when(F.size("words") >= shingle_words, at(shingle_words))
    for n in range(1, shingle_words):
        cases = cases.when(F.size("words") == n, at(n))
    return w.select(F.xxhash64("words").alias("win"), "items", F.size("words").alias("len"), "words", cases.alias("shingles"))


def _placed(docs: DataFrame, text_col: str, sizes: list[int], row: Column, ident: Column) -> DataFrame:
    """A row for each place of each document, with the hashes of the shingles that start there."""
    base = docs.select(ident.alias("id"), words_of(F.col(text_col)).alias("w"), row.alias("row"))
    places = base.select("row", "id", "w", F.posexplode_outer("w").alias("pos", "word"))
    hashes = [_shingle(F.col("w"), F.col("pos"), n) for n in sizes]
    if len(hashes) == 1:
        return places.withColumn("h", hashes[0]).drop("word")
    return places.withColumn("h", F.explode(F.array(*hashes))).drop("word")


def find_windows(docs: DataFrame, benchmark: DataFrame, window_words: int = 10, shingle_words: int = 5, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", broadcast_rows: int = 200_000, broadcast_bytes: int = 64 << 20, id_type: str | None = "long") -> DataFrame:
    """(id, n_words, hits, items): hits is an array of (start, len) of windows found; one row for each row of docs."""
    windows = benchmark_windows(benchmark, item_col, item_text_col, window_words, shingle_words)
    windows = windows.select("*", F.explode("shingles").alias("g")).select("win", "items", "len", "words", "g.*")
    sizes = sorted(r[0] for r in windows.select("size").distinct().collect()) or [shingle_words]  # at most shingle_words values
    held = F.octet_length(F.concat_ws(" ", "words")) + F.octet_length(F.concat_ws(" ", "items")) + 16 * (F.size("words") + F.size("items"))
    told = windows.agg(F.count("*").alias("n"), F.coalesce(F.sum(held), F.lit(0)).alias("bytes")).first()
    small = told.n <= broadcast_rows and told.bytes <= broadcast_bytes
    fits = (lambda df: F.broadcast(df)) if small else (lambda df: df)
    own = F.struct(*(k.alias(n) for k, n in zip(text_key(F.coalesce(F.col(text_col).cast("string"), F.lit(""))), "ab")))
    ident = F.col(id_col).cast(id_type) if id_type else F.col(id_col)
    placed = _placed(docs, text_col, sizes, F.monotonically_increasing_id() if small else own, ident)  # read twice on the way of shuffles, where a number given in passing may change
    seen = placed.select("h").join(fits(windows.select("h").distinct()), "h").groupBy("h").agg(F.count("*").alias("n"))
    ranked = windows.join(fits(seen), "h", "left").groupBy("win", "words", "items", "len").agg(F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "at", "h")).alias("p"))
    prefix = ranked.select(F.col("p.h").alias("h"), F.col("p.at").alias("at"), F.col("len").alias("wlen"), F.col("words").alias("wwords"), "items")
    start = F.col("pos") - F.col("at")
    inside = (start >= 0) & (start + F.col("wlen") <= F.size("w"))
    if small:
        joined = placed.join(F.broadcast(prefix), "h", "left")
        same = F.col("at").isNotNull() & inside & (F.slice("w", F.greatest(start, F.lit(0)) + 1, F.col("wlen")) == F.col("wwords"))
        rows = joined.select("row", "id", F.size("w").alias("n_words"), F.coalesce("pos", F.lit(0)).alias("pos"), F.when(same, F.struct(start.alias("start"), F.col("wlen").alias("len"))).alias("hit"), F.when(same, F.col("items")).alias("found"))
        rows = rows.where("hit is not null or pos = 0")  # a document's first place keeps its row
    else:
        reach = window_words - 1
        lead = F.least(F.col("pos"), F.lit(reach))
        near = placed.where("h is not null").select("row", "id", F.size("w").alias("n_words"), "pos", lead.alias("lead"), F.slice("w", F.col("pos") - lead + 1, 2 * reach + 1).alias("ctx"), "h")
        same = (start >= 0) & (start + F.col("wlen") <= F.col("n_words")) & (F.slice("ctx", F.greatest(F.col("lead") - F.col("at"), F.lit(0)) + 1, F.col("wlen")) == F.col("wwords"))
        hits = near.join(prefix, "h").where(same).select("row", "id", "n_words", "pos", F.struct(start.alias("start"), F.col("wlen").alias("len")).alias("hit"), F.col("items").alias("found"))
        none = [F.lit(None).cast("struct<start:int,len:int>").alias("hit"), F.lit(None).cast("array<string>").alias("found")]
        each = docs.select(own.alias("row"), ident.alias("id"), F.size(words_of(F.col(text_col))).alias("n_words"))
        each = each.groupBy("row", "id", "n_words").agg(F.count("*").alias("copies")).select("row", "id", "n_words", F.lit(0).alias("pos"), *none, "copies")
        rows = each.union(hits.withColumn("copies", F.lit(0)))
    by_row = rows.groupBy("row", "id", "n_words").agg(F.collect_set("hit").alias("hits"), F.collect_set("found").alias("found"), (F.lit(1) if small else F.max("copies")).alias("copies"))
    by_row = by_row if small else by_row.withColumn("copies", F.explode(F.sequence(F.lit(1).cast("long"), "copies")))
    return by_row.select("id", "n_words", "hits", F.array_sort(F.array_distinct(F.flatten("found"))).alias("items"))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", **options) -> DataFrame:
    """docs without the rows whose text holds a window; what a text holds depends on the text only, so texts are told by 128 bits of hash."""
    (key,) = fresh(docs, "key")
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    keyed = docs.withColumn(key, F.struct(*(k.alias(n) for k, n in zip(text_key(text), "ab"))))
    hit = find_windows(keyed, benchmark, id_col=key, id_type=None, text_col=text_col, **options).where("size(hits) > 0").select(F.col("id").alias(key)).distinct()
    return keyed.join(hit, key, "left_anti").select(docs.columns)


def hit_words(hits: Column) -> Column:
    """0-based places of the words inside any hit."""
    return F.array_distinct(F.flatten(F.transform(hits, lambda h: F.sequence(h["start"], h["start"] + h["len"] - 1))))


def op8(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    f = find_windows(docs, benchmark)
    n_hit = F.size(hit_words(F.col("hits"))).cast("long")
    return f.select(
        F.col("id").alias("doc_id"), F.col("n_words").cast("long").alias("n_words"), n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"),
    )


#: DuckDB: every document place is compared with every window by its words.
SQL = r"""
WITH d AS (SELECT doc_id, row_number() OVER () AS r, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark),
win AS (SELECT DISTINCT item, array_to_string(w[s + 1 : s + 10], ' ') AS k, least(len(w), 10) AS n FROM (SELECT item, w, unnest(range(0, greatest(len(w) - 9, 1))) AS s FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM win),
place AS (SELECT r, w, n, unnest(range(0, len(w) - n + 1)) AS s FROM d, sizes WHERE len(w) >= n),
hit AS (SELECT r, s, p.n, item FROM place p JOIN win ON win.n = p.n AND win.k = array_to_string(w[s + 1 : s + p.n], ' ')),
cover AS (SELECT r, count(DISTINCT s + o) AS n_hit FROM (SELECT r, s, unnest(range(0, n)) AS o FROM hit) GROUP BY r),
named AS (SELECT r, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS items FROM hit GROUP BY r)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN cover USING (r) LEFT JOIN named USING (r)
"""

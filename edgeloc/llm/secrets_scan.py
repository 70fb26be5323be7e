"""Secret scans by a trigram inverted index, in DataFrame functions only.

From each rule's regular expression a Boolean trigram query is derived: alternatives, each a set of trigrams that
any match must hold. The index, stored once, maps the trigrams that rules ask for to texts, known by 128 bits of hash; postings are
intersected by counting, for each text and alternative, how many of its trigrams are there. Candidates come from the index alone, and only they are
verified with the expression itself, on a second and last pass. A rule with an alternative that has no mandatory trigram scans all documents.

Postings are rows, never a list held in one task. The candidates are broadcast if they are at most `broadcast_rows`, else the texts are shuffled to
them. Matches are leftmost and non-overlapping for each rule; positions are code points, end exclusive.

Defined results: null text counts as empty and has no spans (redact leaves it null); a null id is scanned like any other; repeated rows stay
repeated; an empty table gives an empty one; other columns pass by untouched, whatever their names.
"""

from __future__ import annotations

import re._parser as sre
from dataclasses import dataclass
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, fresh, text_key


@dataclass(frozen=True)
class Rule:
    """find: what matches are cut out; a match stays if the group's length in code points is at least `least`."""

    kind: str
    find: str
    group: int = 0
    least: int = 1
    base: bool = False


#: Base rules in the order that breaks ties, then the added ones. Where only whole runs of a length stay,
#: the length stands in the expression: a shorter run can't hold a longer match.
RULES = (
    Rule("assign", r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 12, True),
    Rule("access", r"AKIA[A-Z0-9]{14,}", base=True),
    Rule("hex", r"[0-9a-f]{16,}", base=True),
    Rule("pem", r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----"),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("webkey", r"AIza[A-Za-z0-9_-]{35}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
)


def trigram_query(pattern: str) -> list[frozenset[str]] | None:
    """Alternatives of lower-case trigrams, one of which every match holds in whole; None if some match needs none.

    Literals are joined into runs across groups and branches; anything else ends a run. Lower-casing loosens the
    query for rules that regard case, so it never loses a match.
    """

    def grow(items, states):
        for op, arg in items:
            name = str(op)
            if name == "LITERAL":
                states = {(done, run + chr(arg).lower()) for done, run in states}
            elif name == "IN" and len(arg) <= 8 and all(str(o) == "LITERAL" for o, _ in arg):  # a small class is a branch
                states = {(done, run + chr(c).lower()) for done, run in states for _, c in arg}
            elif name == "SUBPATTERN":
                states = grow(arg[-1], states)
            elif name == "BRANCH":
                states = set().union(*(grow(b, states) for b in arg[1]))
            elif name in ("MAX_REPEAT", "MIN_REPEAT", "POSSESSIVE_REPEAT"):
                low, high, body = arg
                if (low, high) == (0, 1):
                    states = states | grow(body, states)
                else:
                    for _ in range(min(low, 3)):
                        states = grow(body, states)
                    if low != high or low > 3:
                        states = ended(states)
            elif name != "AT":
                states = ended(states)
            if len(states) > 256:
                states = {(frozenset(), "")}
        return states

    def ended(states):
        return {(done | {run[i : i + 3] for i in range(len(run) - 2)}, "") for done, run in states}

    found = {done for done, _ in ended(grow(sre.parse(pattern), {(frozenset(), "")}))}
    return None if frozenset() in found else sorted((a for a in found if not any(b < a for b in found)), key=sorted)


def trigram_index(docs: DataFrame, trigrams: list[str], text_col: str = "text") -> DataFrame:
    """(k1, k2, trigram): the stored index of texts over the given trigrams, lower-cased."""
    keyed = docs.select(*(k.alias(n) for k, n in zip(text_key(_text(text_col)), ("k1", "k2"))), F.lower(_text(text_col)).alias("low"))
    there = F.array(*(F.when(F.contains("low", F.lit(g)), F.lit(g)) for g in trigrams))
    return checkpointed(keyed.select("k1", "k2", F.explode(F.array_compact(there)).alias("trigram")))


def candidates(index: DataFrame, rules) -> DataFrame:
    """(k1, k2, kinds): texts that satisfy the trigram queries of rules, by the index alone. Rules without a query are not in it."""
    parts = [(r.kind, n, g, len(alt)) for r in rules for n, alt in enumerate(trigram_query(r.find) or ()) for g in sorted(alt)]
    asked = index.sparkSession.createDataFrame(parts, "kind string, alternative int, trigram string, need int")  # as many as the rules have trigrams
    met = index.distinct().join(F.broadcast(asked), "trigram").groupBy("k1", "k2", "kind", "alternative", "need").agg(F.count("*").alias("n"))
    return met.where("n = need").groupBy("k1", "k2").agg(F.collect_set("kind").alias("kinds"))


def _text(text_col: str) -> Column:
    return F.coalesce(F.col(text_col).cast("string"), F.lit(""))


def rule_spans(text: Column, rule: Rule, order: int) -> Column:
    """Array of (at, ord, until, kind) for a rule's matches; the text between matches gives their places."""
    find = F.lit(rule.find)
    found = F.regexp_extract_all(text, find, F.lit(0))
    kept = F.regexp_extract_all(text, find, F.lit(rule.group)) if rule.group else found
    zipped = F.arrays_zip(F.split(text, rule.find, -1).alias("gap"), found.alias("hit"), kept.alias("kept"))
    zero = F.struct(F.lit(0).alias("pos"), F.array().cast("array<struct<at:int,ord:int,until:int,kind:string>>").alias("out"))

    def step(state, x):
        at = state["pos"] + F.char_length(x["gap"])
        until = at + F.char_length(x["hit"])
        span = F.struct(at.alias("at"), F.lit(order).alias("ord"), until.alias("until"), F.lit(rule.kind).alias("kind"))
        stays = x["hit"].isNotNull() & (F.char_length(x["kept"]) >= rule.least)
        return F.struct(F.coalesce(until, at).alias("pos"), F.when(stays, F.concat(state["out"], F.array(span))).otherwise(state["out"]).alias("out"))

    none = F.array().cast("array<struct<at:int,ord:int,until:int,kind:string>>")
    return F.when(F.rlike(text, find), F.aggregate(zipped, zero, step, lambda s: s["out"])).otherwise(none)


_SPANS = "array<struct<at:int,ord:int,until:int,kind:string>>"


def with_spans(docs: DataFrame, out_col: str, rules=RULES, text_col: str = "text", broadcast_rows: int = 1_000_000) -> DataFrame:
    """docs and, in out_col, which must be a new name, the spans of all rules sorted by start, then by the rules' order."""
    k1, k2, kinds = fresh(docs, "k1", "k2", "kinds")
    text, none = _text(text_col), F.array().cast(_SPANS)
    queried = [r for r in rules if trigram_query(r.find) is not None]
    scanned = [rule_spans(text, r, n) for n, r in enumerate(rules) if r not in queried]
    if not queried:
        return docs.withColumn(out_col, F.array_sort(F.concat(none, *scanned)))
    index = trigram_index(docs, sorted({g for r in queried for alt in trigram_query(r.find) for g in alt}), text_col)
    found = checkpointed(candidates(index, queried).toDF(k1, k2, kinds))  # read twice: counted, then joined
    found = F.broadcast(found) if found.count() <= broadcast_rows else found
    checks = [F.when(F.array_contains(kinds, r.kind), rule_spans(text, r, n)).otherwise(none) for n, r in enumerate(rules) if r in queried]
    keyed = docs.withColumns(dict(zip((k1, k2), text_key(text))))
    return keyed.join(found, [k1, k2], "left").withColumn(out_col, F.array_sort(F.concat(none, *scanned, *checks))).select(*docs.columns, out_col)


def find_secrets(docs: DataFrame, rules=RULES, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """(id, spans): one row for each row of docs."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("t"))
    return with_spans(rows, "spans", rules, "t", **options).select("id", "spans")


def redact(docs: DataFrame, rules=RULES, text_col: str = "text", mask: str = "[SECRET]", **options) -> DataFrame:
    """docs with the spans of all rules masked in text_col, overlapping ones together; rows and other columns stay as they are."""
    (spans,) = fresh(docs, "spans")
    text, found = F.col(text_col), F.col(spans)
    zero = F.struct(F.lit(0).alias("pos"), F.lit("").alias("out"))

    def step(state, x):
        new = F.concat(state["out"], F.substring(text, state["pos"] + 1, x["at"] - state["pos"]), F.lit(mask))
        return F.struct(F.greatest(state["pos"], x["until"]).alias("pos"), F.when(x["at"] >= state["pos"], new).otherwise(state["out"]).alias("out"))

    masked = F.aggregate(found, zero, step, lambda s: F.concat(s["out"], F.substring(text, s["pos"] + 1, F.char_length(text))))
    out = with_spans(docs, spans, rules, text_col, **options)
    return out.withColumn(text_col, F.when(F.size(found) > 0, masked).otherwise(text)).select(docs.columns)


def joined_spans(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["at"], s["until"])), ",")


def op3(docs: DataFrame) -> DataFrame:
    found = find_secrets(docs)
    n = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    base = [r.kind for r in RULES if r.base]
    digest = F.sha2(joined_spans(F.filter("spans", lambda s: s["kind"].isin(base))), 256)
    return found.select(F.col("id").alias("doc_id"), *(n(k) for k in base), digest.alias("base_sha256"), joined_spans(F.col("spans")).alias("spans"))


def _sql_spans(n: int, r: Rule) -> str:
    find = r.find.replace("'", "''")
    keep = f"length(k[i]) >= {r.least}"
    return f"""list_transform(list_filter(range(1, len(h{n}) + 1), lambda i: {keep.replace('k[i]', f'k{n}[i]')}),
      lambda i: {{'at': p{n}[i], 'ord': {n}, 'until': p{n}[i] + length(h{n}[i]), 'kind': '{r.kind}'}})""", f"""
      regexp_extract_all(t, '{find}') AS h{n}, regexp_extract_all(t, '{find}', {r.group}) AS k{n}, string_split_regex(t, '{find}') AS g{n},
      list_transform(range(1, len(h{n}) + 1), lambda i: list_sum(list_transform(g{n}[:i], lambda x: length(x))) + coalesce(list_sum(list_transform(h{n}[:i-1], lambda x: length(x))), 0)) AS p{n}"""


def sql() -> str:
    """DuckDB."""
    spans, cols = zip(*(_sql_spans(n, r) for n, r in enumerate(RULES)))
    base = ", ".join(f"'{r.kind}'" for r in RULES if r.base)
    told = "list_transform({0}, lambda q: q.kind || ':' || CAST(q.at AS BIGINT) || ':' || CAST(q.until AS BIGINT))"
    counts = ", ".join(f"len(list_filter(s, lambda x: x.kind = '{r.kind}')) AS n_{r.kind}" for r in RULES if r.base)
    return f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents), m AS (SELECT doc_id, {','.join(cols)} FROM d),
    a AS (SELECT doc_id, list_sort(list_concat({','.join(spans)})) AS s FROM m)
    SELECT doc_id, {counts}, sha256(array_to_string({told.format(f"list_filter(s, lambda x: x.kind IN ({base}))")}, ',')) AS base_sha256,
    array_to_string({told.format('s')}, ',') AS spans FROM a"""

"""Toxicity by a weighted lexicon: Aho-Corasick over folded text, normalised by length, with exception phrases.

Folding lower-cases, maps look-alike letters of other scripts and undoes digit and sign substitutions. Entries are whole words or
word beginnings, matched at a word's start. A hit inside an exception phrase doesn't count. The score is a logistic function of the
hits' summed weight, of that sum divided by the logarithm of the text's length, and of whether there is a hit.

Entries, weights and the function are learned from labelled rows: in expectation at most `max_rows` of them, chosen by a
hash of the id. That bound is a parameter; scoring covers every text in whole.

Defined results: null text counts as empty and gets the score of a text without hits; null labels and null ids teach nothing; without enough labels
the seed entries and prior weights stand; repeated rows stay; an empty table gives an empty one. Labels, language, source and id are never inputs of a score.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, released

#: Seed entries (whole words), look-alikes, and phrases in which an entry is harmless.
SEEDS = ("idiot", "moron", "loser", "pathetic", "scum", "worthless", "trash", "clown", "disgusting", "stupid")
FOLD = str.maketrans("аеорсухіјѕԁɡοαεικντυ0134579", "aeopcyxijsdgoaeikvtuoieastg")
SIGNS = {"@": "a", "$": "s", "!": "i", "|": "i"}
EXCEPTIONS = ("trash can", "trash bin", "trash bag", "pond scum", "soap scum", "clown fish", "clownfish", "class clown", "idiot proof")
WORD = re.compile(r"[^\W\d_]+")
_SIGN = re.compile(r"[@$!|](?=[^\W_])")  # before a letter or digit only: at a word's end it is punctuation


def fold(text: str | None) -> str:
    t = (text or "").lower()
    return _SIGN.sub(lambda m: SIGNS[m.group()], t).translate(FOLD)


@dataclass
class Model:
    entries: dict[str, float]  # a final blank marks a whole word
    bias: tuple[float, float, float, float] = (-4.0, 3.0, 1.0, 1.0)
    threshold: float = 0.3


class Matcher:
    def __init__(self, model: Model):
        self.model = model
        self.automaton = ahocorasick.Automaton()
        for e, w in model.entries.items():
            self.automaton.add_word(e.rstrip(), (len(e.rstrip()), e[-1] == " ", w))
        for e in EXCEPTIONS:
            self.automaton.add_word(fold(e), (len(e), True, None))
        self.automaton.make_automaton()

    def features(self, text: str | None) -> tuple[float, float, float]:
        t = fold(text)
        hits, exempt, n = [], [], len(t)
        for end, (size, whole, weight) in self.automaton.iter(t):
            start = end - size + 1
            if (start == 0 or not t[start - 1].isalpha()) and not (whole and end + 1 < n and t[end + 1].isalpha()):
                (exempt if weight is None else hits).append((start, end, weight))
        best = {}
        for start, end, weight in hits:
            if not any(a <= start and end <= b for a, b, _ in exempt):
                best[start] = max(weight, best.get(start, 0.0))
        total = sum(best.values())
        return total, total / math.log2(4 + n / 6), float(bool(best))

    def score(self, text: str | None) -> float:
        return float(score_of(np.array([self.features(text)]), self.model)[0])


def score_of(x: np.ndarray, model: Model) -> np.ndarray:
    bias, any_hit, total, dense = model.bias
    return 1 / (1 + np.exp(-np.clip(bias + any_hit * x[:, 2] + total * np.log1p(x[:, 0]) + dense * np.log1p(x[:, 1]), -30, 30)))


def held_out(id_col: Column) -> Column:
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def _terms(text: str | None) -> set[str]:
    """Words (with a final blank) and their beginnings of 4 to 8 letters."""
    out = set()
    for w in set(WORD.findall(fold(text))):
        if 3 < len(w) < 40:
            out.add(w + " ")
            out.update(w[:k] for k in range(4, min(8, len(w)) + 1))
    return out


def _counts(rows: DataFrame) -> DataFrame:
    """(term, p, q): in how many rows of label 1 and of label 0 each term is."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n: Counter = Counter()

        def out():
            return pa.RecordBatch.from_arrays([pa.array([t for t, _ in n], type=pa.string()), pa.array([y for _, y in n], type=pa.int32()), pa.array(list(n.values()), type=pa.int64())], names=["term", "y", "n"])

        for b in batches:
            for y, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                n.update((term, y) for term in _terms(t))
                if len(n) > 500_000:
                    yield out()
                    n.clear()
        yield out()

    of = lambda y: F.sum(F.when(F.col("y") == y, F.col("n")).otherwise(0))
    return rows.select("y", "t").mapInArrow(released(run), "term string, y int, n long").groupBy("term").agg(of(1).alias("p"), of(0).alias("q"))


def beyond_chance(n_pos: int, n_neg: int, precision: float, chance: float) -> Column:
    """Terms in p rows of label 1 and q of label 0 whose precision suffices and which rows drawn at random would hardly give (a bound on the binomial tail)."""
    share = min(max(n_pos, 1) / max(n_pos + n_neg, 2), 0.5)
    n = F.col("p") + F.col("q")
    a = F.col("p") / n
    far = a * F.log(a / share) + F.when(a < 1, (1 - a) * F.log((1 - a) / (1 - share))).otherwise(0.0)
    return (F.col("p") >= 3) & (a >= precision) & (a > share) & (n * far >= -math.log(chance))


def choose(counts: dict[str, tuple[int, int]], n_pos: int, n_neg: int) -> dict[str, float]:
    """Of terms that pass, the most general of a chain that lose nothing, with log odds as weights."""
    longer: dict[str, int] = {}
    for t, (p, _) in counts.items():
        above = t.rstrip() if t[-1] == " " else t[:-1]
        longer[above] = max(longer.get(above, 0), p)
    kept = {t: pq for t, pq in counts.items() if pq[0] > longer.get(t, 0)}  # a longer entry that finds as much is more specific
    out = {}
    for t in sorted(kept, key=lambda t: (len(t.rstrip()), t[-1] == " ")):
        if not any(t[:k] in out for k in range(4, len(t))):
            p, q = kept[t]
            out[t] = math.log((p + 0.5) / (n_pos + 1)) - math.log((q + 0.5) / (n_neg + 1))
    return out


def _fit(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2) -> tuple[float, float, float, float]:
    """Logistic regression by Newton steps."""
    a = np.column_stack((np.ones(len(y)), x[:, 2], np.log1p(x[:, 0]), np.log1p(x[:, 1])))
    w, keep = np.zeros(4), np.diag([1e-6, ridge, ridge, ridge]) * len(y)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve(a.T @ (a * (p * (1 - p))[:, None]) + keep + 1e-9 * np.eye(4), a.T @ (p - y) + keep @ w)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return tuple(float(v) for v in w)


def learn(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", max_rows: int = 20_000, precision: float = 0.4, chance: float = 1e-6) -> Model:
    """Learns from labelled rows that aren't held out. One scan of docs joins the sample, which is kept; terms are counted and the function fitted on that.

    A term becomes an entry by its support and precision alone: no number of terms is cut off.
    """
    known = labels.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("int").alias("y")).where(~held_out(F.col("id")) & F.col("id").isNotNull() & F.col("y").isin(0, 1))
    n = known.count()
    part = min(1.0, max_rows / max(n, 1))
    known = known.where(F.pmod(F.xxhash64("id"), F.lit(1_000_000)) < int(part * 1_000_000)) if part < 1 else known
    rows = checkpointed(docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("t")).join(F.broadcast(known), "id").select("y", "t"))
    model = Model({s + " ": 5.0 for s in SEEDS})
    sizes = {r.y: r["count"] for r in rows.groupBy("y").count().collect()}
    passed = _counts(rows).where(beyond_chance(sizes.get(1, 0), sizes.get(0, 0), precision, chance))
    model.entries |= choose({r.term: (r.p, r.q) for r in passed.collect()}, sizes.get(1, 0), sizes.get(0, 0))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = Matcher(model)
        for b in batches:
            x = [m.features(t) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array([v[k] for v in x], type=pa.float64()) for k in range(3))], names=["y", "a", "b", "c"])

    if min(sizes.get(0, 0), sizes.get(1, 0)) >= 10:
        got = rows.select("y", "t").mapInArrow(released(run), "y int, a double, b double, c double").toPandas().to_numpy(dtype=float)
        model.bias = _fit(got[:, 1:], got[:, 0])
    return model


def score(docs: DataFrame, model: Model, text_col: str = "text", out_col: str = "score") -> DataFrame:
    """docs with a score in [0, 1]; all columns pass through, one named like the result is replaced."""
    from pyspark.sql import types as T

    names, at = [c for c in docs.columns if c != out_col], docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = Matcher(model)
        for b in batches:
            x = np.array([m.features(t) for t in b.column(at).to_pylist()], dtype=float).reshape(-1, 3)
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in names), pa.array(score_of(x, m.model))], names=[*names, out_col])

    kind = T.StructType([f for f in docs.schema.fields if f.name != out_col] + [T.StructField(out_col, T.DoubleType())])
    return docs.mapInArrow(released(run), kind)


def op6(docs: DataFrame, labels: DataFrame) -> DataFrame:
    model = learn(docs, labels)
    rows = score(docs.select(F.col("doc_id"), F.col("text").cast("string").alias("text")), model)
    return rows.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= model.threshold).cast("int").alias("predicted"))

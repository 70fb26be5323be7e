"""Every stage of the corpus pipeline, and the whole, against plain Python on a small corpus."""

import random
import re

import pytest

import corpus_pipeline
from edgeloc.llm import piece_codec, toxicity

RNG = random.Random(3)
WORDS = [f"w{k}" for k in range(900)]
text = lambda n: " ".join(RNG.choice(WORDS) for _ in range(n))


@pytest.fixture(scope="module")
def corpus(spark, tmp_path_factory):
    """documents with toxic rows, near copies, benchmark passages and secrets; also rows with nulls in every column."""
    item = text(30)
    rows = []
    for k in range(120):
        t = text(80)
        if k % 4 == 0:
            t += " you idiot and moron"
        elif k % 10 == 1:
            t += " " + item
        elif k % 10 == 3:
            t += ' token = "abcdefghijklmnop"'
        rows.append((k, t, "en", "web", len(t)))
    copies = [(200 + k, rows[k][1].replace("w1 ", "w2 ", 1), "en", "copy", 0) for k in range(1, 20, 2)]
    odd = [(None, text(50), None, None, None), (300, None, None, None, None), (301, "", "de", "", 0), (301, text(20), "de", "", 0)]
    d = str(tmp_path_factory.mktemp("corpus"))
    kind = "doc_id long, text string, lang string, source string, n_chars int"
    spark.createDataFrame(rows + copies + odd, kind).write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame([(k, 1, int(k % 4 == 0)) for k in range(120)] + [(None, None, None)], "doc_id long, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
    spark.createDataFrame([(1, item), (None, None)], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    return d


def test_stages_and_whole(spark, corpus):
    docs = spark.read.parquet(f"{corpus}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["toxicity", "simhash", "decontamination", "secrets", "pieces"]
    item = spark.read.parquet(f"{corpus}/benchmark.parquet").where("item_id = 1").first().text.split()

    rows = [tuple(r) for r in docs.collect()]
    model = toxicity.learn(docs, spark.read.parquet(f"{corpus}/labels.parquet"))
    matcher = toxicity.Matcher(model)
    rows = [r for r in rows if matcher.score(r[1]) < model.threshold]
    assert not any("idiot" in (r[1] or "") for r in rows) and len(rows) > 80
    state = stages["toxicity"](spark, docs, corpus)
    order = lambda r: str(r)
    assert state.columns == docs.columns and sorted(map(tuple, state.collect()), key=order) == sorted(rows, key=order)

    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0d]+", (t or "").lower())
        return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}

    named = [r for r in rows if r[0] is not None]
    sets, root = [shingles(r[1]) for r in named], list(range(len(named)))
    for i in range(len(named)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                a, b = root[i], root[j]
                root = [min(a, b) if x in (a, b) else x for x in root]
    kept = {min(named[k][0] for k, x in enumerate(root) if x == own) for own in root}
    state = stages["simhash"](spark, state, corpus)
    got = sorted(map(tuple, state.collect()), key=order)
    assert sorted(r[0] for r in got if r[0] is not None) == sorted(kept) and sum(r[0] is None for r in got) == 1 and set(got) <= set(rows)
    assert [r[1] for r in got if r[0] == 301] == [r[1] for r in rows if r[0] == 301 and r[1]]  # the empty row of that id is a copy of row 300

    has = lambda t: any(w[k : k + 10] == item[a : a + 10] for w in [(t or "").split()] for k in range(len(w) - 9) for a in range(len(item) - 9))
    rows = [r for r in got if not has(r[1])]
    assert len(rows) < len(got)
    state = stages["decontamination"](spark, state, corpus)
    assert sorted(map(tuple, state.collect()), key=order) == sorted(rows, key=order)

    def masked(r):
        t = r[1] if r[1] is None else r[1].replace('token = "abcdefghijklmnop', "[SECRET]")
        return r if t == r[1] else (r[0], t, *r[2:4], len(t))

    rows = [masked(r) for r in rows]
    state = stages["secrets"](spark, state, corpus)
    assert sorted(map(tuple, state.collect()), key=order) == sorted(rows, key=order) and "[SECRET]" in str(rows)

    import sentencepiece as sp

    library = sp.SentencePieceProcessor(model_file=piece_codec.default_model_path())
    want = sorted((str((*r, None if r[1] is None else library.encode(r[1]))) for r in rows))
    assert sorted(str(tuple(x)[:6]) for x in stages["pieces"](spark, state, corpus).collect()) == want
    assert sorted(str(tuple(x)[:6]) for x in corpus_pipeline.run(spark, corpus).collect()) == want


def test_empty_and_clashing_columns(spark, corpus):
    docs = spark.read.parquet(f"{corpus}/documents.parquet").limit(6)
    clash = docs.selectExpr("*", "'a' AS score", "'b' AS masked", "'c' AS spans", "'d' AS key", "'e' AS k1", "'f' AS copies", "'g' AS id", "'h' AS component")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, clash, corpus)
        assert out.columns == clash.columns and all((r.score, r.masked, r.spans, r.key, r.k1, r.copies, r.id, r.component) == tuple("abcdefgh") for r in out.collect()), name
        assert stage(spark, clash.where("1 = 0"), corpus).count() == 0

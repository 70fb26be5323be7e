import random

import corpus_pipeline
from edgeloc.llm import near_copies


def jaccard(a, b):
    """In plain Python, over the words themselves."""
    def sets(t):
        w = (t or "").lower().split()
        return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}

    return len(sets(a) & sets(b)) / len(sets(a) | sets(b))


def kept(texts):
    """Smallest ids of the groups, by brute force."""
    root = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if jaccard(texts[i], texts[j]) >= 0.8:
                root = [root[j] if r == root[i] else r for r in root]
    return {min(k for k, r in enumerate(root) if r == own) for own in root}


def texts():
    rng, out = random.Random(1), [None, "", "one two", "ONE  two", "three"]
    for _ in range(25):
        base = [f"v{rng.randrange(5000)}" for _ in range(rng.randrange(60, 300))]
        out.append(" ".join(base))
        for share in (0.005, 0.01, 0.02, 0.03, 0.05):
            out.append(" ".join(rng.choice(["new", "other"]) + str(rng.randrange(999)) if rng.random() < share else w for w in base))
    return out


def test_near_copies_equal_brute_force(spark):
    t = texts()
    docs = spark.createDataFrame(list(enumerate(t)), "doc_id long, text string")
    want = kept(t)
    for tile_rows in (512, 2):
        assert {r.id for r in near_copies.near_copies(docs, tile_rows=tile_rows).collect() if r.id == r.component} == want
    assert {r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, "").collect()} == want


def test_rows_without_an_id_stay_and_empty_tables_are_taken(spark):
    docs = spark.createDataFrame([(1, "a b c"), (2, "a b c"), (None, "a b c"), (1, "a b c")], "doc_id long, text string")
    assert sorted(str(r.doc_id) for r in corpus_pipeline.drop_near_copies(spark, docs, "").collect()) == ["1", "None"]
    shared = spark.createDataFrame([(1, "a b c"), (1, "d e f"), (2, "d e f")], "doc_id long, text string")  # two groups whose smallest id is the same
    assert sorted(tuple(r) for r in corpus_pipeline.drop_near_copies(spark, shared, "").collect()) == [(1, "a b c"), (1, "d e f")]
    assert corpus_pipeline.drop_near_copies(spark, docs.where("1 = 0"), "").count() == 0

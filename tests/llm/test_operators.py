import hashlib

import pytest

from edgeloc.llm import decontaminate, license_scan, media, pii, piece_codec, secrets_scan, simhash, substring, toxicity, url_filter

WORDS = [f"w{k}" for k in range(60)]
TEXTS = [None, "", "a", " ".join(WORDS[:30]), " ".join(["x", *WORDS[5:25], "y"]), " ".join(WORDS[:30]), 'token = "abcdef0123456789abcdef"', "é " * 3000]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(k, t, "en") for k, t in enumerate(TEXTS)] + [(None, "lost", "en"), (3, TEXTS[3], "en")], "doc_id long, text string, id string")


def test_every_operator_keeps_rows_and_takes_empty_tables(spark, docs):
    bench = spark.createDataFrame([(1, " ".join(WORDS[8:20])), (2, None)], "item_id long, text string")
    labels = spark.createDataFrame([(1, 1), (2, 0), (None, None)], "doc_id long, toxic int")
    for f in (license_scan.op1, simhash.op2, secrets_scan.op3, substring.op4, piece_codec.op5, pii.op9, media.op10, lambda d: decontaminate.op8(d, bench), lambda d: toxicity.op6(d, labels)):
        assert f(docs).count() == docs.count()
        assert f(docs.where("1 = 0")).count() == 0


def test_copies_share_a_component(docs):
    c = {r.doc_id: r.component_id for r in simhash.op2(docs).collect() if r.doc_id is not None}
    assert c[3] == c[5] == 3 and c[0] == c[1] == 0


def test_repeats_go_from_larger_ids(docs):
    r = {x.doc_id: x for x in substring.op4(docs).collect()}
    assert (r[3].n_removed, r[5].n_removed, r[4].n_removed) == (0, 30, 20)
    assert r[4].kept_sha256 == hashlib.sha256(b"x y").hexdigest()


def test_windows_hit(spark, docs):
    bench = spark.createDataFrame([(1, " ".join(WORDS[8:20])), (2, None)], "item_id long, text string")
    for rows in (1000, 0):
        f = {x.id: x for x in decontaminate.find_windows(docs, bench, broadcast_rows=rows).collect()}
        assert len(f[3].hits) == 3 and f[3]["items"] == ["1"] and not f[2].hits


def test_secret_spans_and_masks(docs):
    r = {x.doc_id: x for x in secrets_scan.op3(docs).collect()}[6]
    assert (r.n_assign, r.n_hex) == (1, 1)
    assert "abcdef" not in {x.doc_id: x.text for x in secrets_scan.redact(docs).collect()}[6]


def test_pieces_equal_the_library():
    import sentencepiece as sp

    path = piece_codec.default_model_path()
    texts = ["  a  b   c", "aaaa aaaaaaaaaaaaa", "日本語 \x00 x", "def  foo():\n\treturn 1", "x      ", " "]
    assert piece_codec.Encoder(piece_codec.PieceModel(path)).encode(texts).to_pylist() == sp.SentencePieceProcessor(model_file=path).encode(texts)


def test_pseudonyms_are_valid_linked_and_reversible():
    f = pii.Feistel(b"k")
    text = "card 4539 5787 6362 1486 on 2024-02-29 mail bob.x1@example.com ip 10.0.0.1 bad 1234567812345678"
    new, spans = pii.replace_pii(text, f)
    assert [k for k, _, _ in spans] == ["card", "date", "email", "ip"] and new.endswith("bad 1234567812345678") and new != text
    assert pii.replace_pii(new, f, back=True)[0] == text


def test_longest_rule_wins():
    t = url_filter.Trie(url_filter.RULES)
    assert t.find("a.example.net", "/en/1") == ("allow", "example.net/en/") and t.find("a.example.net", "/de/") == ("block", "net/")
    assert t.find("net", "") is None and url_filter.split_url(None) == ("", "")


def test_samples_come_back():
    for raw in (b"", b"abc", bytes(range(256)) * 3):
        back = media.from_wav(media.to_wav(raw))
        assert back.startswith(raw) and len(back) % 64 == 0 and len(back) >= 64

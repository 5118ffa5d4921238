"""Long, deep and odd inputs, clashing columns and empty tables, and plain recomputations of each operator's rows."""

import hashlib
import random
import re
import time
import zlib

import numpy as np
import pytest
import zstandard

from quillon.llm import bpe, embedding_dedup, flac, html_extract, jaccard_join, language_id, mixing, secrets, textkernel, toxicity, url_filter

NAMES = "id long, n long, sig string, vec string, rank int, score string, held_out string, copy int, size long, mark string, start int, block int, embedding2 string, html2 string, host string, path string, rule string"
MORE = (7, 7, "s", "v", 7, "x", "h", 7, 7, "m", 7, 7, "e", "h", "o", "p", "r")


def clashing(spark, rows, columns):
    taken = {c.split()[0] for c in columns.split(",")}
    keep = [k for k, c in enumerate(NAMES.split(", ")) if c.split()[0] not in taken]
    return spark.createDataFrame([(*r, *(MORE[k] for k in keep)) for r in rows], columns + ", " + ", ".join(NAMES.split(", ")[k] for k in keep))


DOCS = [(1, None, "en", "a"), (2, "", None, None), (3, "Some words, and password = hunter2x9 here.", "en", "a"), (3, "Some words, and password = hunter2x9 here.", "en", "a"), (None, "no id", "en", "b")]
OPERATORS = {
    "op2": lambda spark, d: jaccard_join.jaccard_components(d),
    "op3": lambda spark, d: secrets.find_secrets(d),
    "op4": lambda spark, d: bpe.bpe_digests(d),
    "op5": lambda spark, d: flac.media_digests(d),
    "op6": lambda spark, d: language_id.language_predictions(d),
    "op8": lambda spark, d: toxicity.toxicity_scores(d, spark.createDataFrame([(1, 1, 0), (3, 0, 1), (None, 1, 1), (3, None, None)], "doc_id long, toxic int, quality int")),
    "op9": lambda spark, d: mixing.mixture(d),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_documents_with_clashing_columns_and_empty_tables(spark, name):
    docs = clashing(spark, DOCS, "doc_id long, text string, lang string, source string")
    rows = OPERATORS[name](spark, docs).collect()
    assert len(rows) == len(DOCS) and sorted(str(r.doc_id) for r in rows) == sorted(str(r[0]) for r in DOCS)
    assert len({str(r) for r in rows if r.doc_id == 3}) == 1  # repeated rows alike
    assert OPERATORS[name](spark, docs.where("false")).count() == 0


def test_pages_and_vectors_with_clashing_columns_and_empty_tables(spark):
    pages = clashing(spark, [(1, "http://x.org/a", "<p>Text one is here.</p>"), (1, "http://x.org/a", "<p>Text one is here.</p>"), (2, None, None)], "page_id long, url string, html string")
    assert len({str(r) for r in html_extract.extract_pages(pages).where("page_id = 1").collect()}) == 1
    assert html_extract.extract_pages(pages.where("false")).count() == url_filter.url_verdicts(pages.where("false")).count() == 0
    got = {(r.page_id, r.host, r.path, r.rule, r.verdict) for r in url_filter.url_verdicts(pages).collect()}
    assert got == {(1, "x.org", "/a", "org/", "allow"), (2, "", "", None, "allow")}
    vectors = clashing(spark, [(1, [1.0, 0.0], 1), (2, [1.0, 0.01], 1), (None, [1.0, 0.0], 1)], "vec_id long, embedding array<float>, label int")
    assert embedding_dedup.embedding_links(vectors).count() == 3


def test_secrets_in_long_lines_take_linear_time():
    plain = "passage of words without any sign " * 150_000
    began = time.monotonic()
    assert secrets.lexed_spans(plain) == [] and len(plain) > 5_000_000
    for bad in ("token " + "a+b+" * 200_000, "token" + "--a" * 200_000, 'token \\"' + '\\"' * 200_000, "token " + "a:" * 200_000 + "(", "token " + "a:b= " * 100_000, 'token="abc123"\n' + "token=token+token\n" * 20_000):
        secrets.lexed_spans(bad)
    assert time.monotonic() - began < 60
    long = "x = 1; " * 100_000 + "db_password = 'Zx81kkQ2'"
    assert [long[a:b] for _, a, b in secrets.lexed_spans(long)] == ["Zx81kkQ2"]


def test_secrets_over_lines_and_types():
    text = 'secret_key =\n   "multi99line"\npassword: str = "Abc12399"\nx --api-key=ab12cd34 postgres://u:pw99xx@h/\npassphrase: "correct horse battery staple"\nnote: "token of thanks"\nK = "q1w2e3r4"\nauth_token = K + "t5y6"\n'
    found = {text[a:b] for _, a, b in secrets.lexed_spans(text)}
    assert found == {"multi99line", "Abc12399", "ab12cd34", "pw99xx", "correct horse battery staple", "q1w2e3r4", "t5y6"}


def test_deep_pages_take_linear_time():
    began = time.monotonic()
    deep = html_extract.leaf_blocks("<div>a" * 100_000)
    assert len(deep) == 100_000 and deep[-1].tags == {"div"}
    for bad in ("<h1>x" * 50_000, "<b>" * 50_000 + "<p>a</p>c" * 5_000, "<b>" * 50_000 + "</i>" * 50_000, "<!" * 100_000, "<script></script " * 30_000, '<a "' * 50_000):
        html_extract.leaf_blocks(bad)
    assert time.monotonic() - began < 60
    assert html_extract.main_text("<p>", html_extract.trained_field()) == ""


def test_chain_labels_equal_those_of_all_sequences():
    rng = np.random.default_rng(6)
    field = html_extract.ChainField()
    field.index, field.weights = {"a": 0, "b": 1, "c": 2}, np.array([1.0, -0.7, 0.1])
    for _ in range(50):
        field.steps = rng.normal(size=(2, 2))
        names = [[str(rng.choice(["a", "b", "c"]))] for _ in range(6)]
        score = lambda y: sum(field.weights[field.index[f[0]]] for f, v in zip(names, y) if v) + sum(field.steps[u, v] for u, v in zip(y, y[1:]))
        every = [[k >> j & 1 for j in range(6)] for k in range(64)]
        assert score(field.decode(names)) == pytest.approx(max(map(score, every)))
    field.steps = np.array([[1.5, 0.0], [0.0, 1.5]])
    assert field.decode([["a"], ["b"], ["a"], ["a"]]) == [1, 1, 1, 1]  # neighbours decide; alone the second is 0
    assert field.decode([["b"]]) == [0]


def test_languages_equal_plain_compression(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    model = language_id.learn_dictionaries(docs.where(~language_id.crc_held_out()))
    judge = language_id.Compressors(model)
    for r in docs.where("n_chars > 2000").limit(12).collect():
        text = re.sub(r"[^a-zà-öø-ÿœ]+", " ", r.text.lower()).strip() if r.lang in ("en", "de", "fr", "es") and re.fullmatch(r"[\x00-\xffœŒ–—’‘“”…]*", r.text) else language_id.letters(r.text).decode()
        data = text.encode()
        size = {}
        for name, content in model:
            d = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            c = zstandard.ZstdCompressor(level=language_id.LEVEL, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False)
            size[name] = sum(len(c.compress(data[k : k + language_id.WINDOW_BYTES])) for k in range(0, len(data), language_id.WINDOW_BYTES))
        assert judge.judge(r.text)[0] == min(size, key=lambda k: size[k])
    long = docs.where("lang = 'en'").orderBy("n_chars", ascending=False).first().text * 300
    assert judge.judge(long)[0] == "en" and b"".join(language_id.windows(long)) == language_id.letters(long)
    same = docs.limit(3).selectExpr("1L AS doc_id", "text", "lang")
    assert len(language_id.learn_dictionaries(same.union(same))) >= 1  # repeated ids


def test_machine_equals_the_sum_over_pairs():
    rng = np.random.default_rng(2)
    m = toxicity.Machine(np.arange(6), 0.3, rng.normal(size=6), rng.normal(size=(6, 4)))
    for d in ([], [2], [0, 3, 5], [0, 1, 2, 3, 4, 5]):
        want = 0.3 + sum(m.weights[i] for i in d) + sum(m.factors[i] @ m.factors[j] for i in d for j in d if i < j)
        assert m.raw(np.zeros(len(d), int), np.array(d, int), 1)[0] == pytest.approx(want)


def test_media_of_long_texts(spark):
    rng = random.Random(1)
    text = " ".join("".join(rng.choices("abcdefgh", k=6)) for _ in range(300_000))
    [r] = flac.media_digests(spark.createDataFrame([(1, text)], "doc_id long, text string")).collect()
    raw = text.encode()
    padded = raw + b"\xff" * (-len(raw) % 576)
    assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-32:]))
    x = np.frombuffer(padded, np.uint8).astype(int) - 128
    assert r.feature == f"energy={(x * x).sum()};crossings={((x[1:] < 0) != (x[:-1] < 0)).sum()};peak={abs(x).max()};steps={abs(np.diff(x)).sum()}"


def test_tree_of_halves_equals_the_library():
    rng = random.Random(4)
    alphabets = ["ab c's'll 12!.\n", "a", " \n\t", "аб в,г 9'", "汉字，。 x", "'stREll  d", "ab ԱՙՠჅ꟎ ̃x\u0085 \x1c'", "aé☃𝒳 !'s"]
    for leaf in (2, 3, 7, 32):
        own = bpe.TreeEncoder(bpe.default_vocabulary(), leaf_chars=leaf)
        for _ in range(150):
            text = "".join(rng.choices(rng.choice(alphabets), k=rng.randint(0, 90)))
            assert own.encode(text) == own.tokenizer.encode(text, add_special_tokens=False).ids, (leaf, text)
    own = bpe.TreeEncoder(bpe.default_vocabulary(), threads=2)
    text = "the cat's 12 hats, " * 500 + "z" * 5000 + " " * 3000 + "end"
    assert own.encode(text) == own.tokenizer.encode(text, add_special_tokens=False).ids and own.longer == 1


def test_most_documents_go_through_the_tree(spark):
    own = bpe.TreeEncoder(bpe.default_vocabulary())
    for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").collect():
        own.encode(r.text or "")
    assert own.longer / own.texts > 0.5


def test_shingles_equal_plain_sets_in_any_packing(monkeypatch):
    rng = random.Random(3)
    lower = {c: c + 32 for c in range(65, 91)}

    def hashed(texts):
        raw = [t.encode() for t in texts]
        at = np.cumsum([0, *map(len, raw)])
        return textkernel.shingle_sets(np.frombuffer(b"".join(raw), np.uint8), at)

    for piece in (7, 16, 1 << 16):
        monkeypatch.setattr(textkernel, "PIECE_BYTES", piece)
        for _ in range(60):
            texts = ["".join(rng.choices("aAb \n", k=rng.choice([0, 1, 3, 30, 200]))) for _ in range(rng.randint(1, 5))]
            got = hashed(texts)
            for t, s in zip(texts, got):
                w = re.findall(r"[^\x20\x09-\x0D]+", t.translate(lower))
                assert len(s) == (0 if not w else 1 if len(w) < 5 else len({tuple(w[i : i + 5]) for i in range(len(w) - 4)}))
                assert np.array_equal(hashed([t])[0], s)
    assert np.array_equal(*(textkernel.word_hashes(np.frombuffer(w, np.uint8), np.array([0, len(w)]))[0] for w in ((b"Ab" * 90_000), b"ab" * 90_000)))


def test_url_rules_of_one_length_and_globs():
    auto = url_filter.ShiftAnd([url_filter.glob("a*c"), url_filter.glob("*b*"), url_filter.glob("abc")])
    raw = [b"abc", b"ac", b"axxc", b"b", b"", b"abcd"]
    at = np.cumsum([0, *map(len, raw)])
    import fnmatch

    want = [[fnmatch.fnmatchcase(x.decode(), p) for p in ("a*c", "*b*", "abc")] for x in raw]
    assert auto.run(np.frombuffer(b"".join(raw), np.uint8), at).tolist() == want

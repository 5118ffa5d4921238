"""The training-data operators against brute force, exact round trips, and edge cases."""

import hashlib
import re

import duckdb
import numpy as np
import pytest

from quillon.llm import bpe, flac, html_extract, language_id, secrets, toxicity, url_filter
from quillon.llm.components import components, local_roots
from quillon.llm.embedding_dedup import embedding_links, tile_links
from quillon.llm import jaccard_join
from quillon.llm.jaccard_join import jaccard_components, overlap, tree_links
from quillon.llm.mixing import mixture, source_targets

SF = "/root/testdata/sf0.001"
EDGE = [(1, None), (2, ""), (3, " \n"), (4, "one two"), (4, "one two"), (5, "Straße ☃ 𝒳 \x00 x"), (6, "w " * 30000), (7, "y" * 5000)]


def edge(spark, extra="lang string, source string, text2 string"):
    rows = [(i, t, "en", "a" if i % 2 else None, "x") for i, t in EDGE]
    return spark.createDataFrame(rows, f"doc_id long, text string, {extra}")


def test_tile_links_are_exact():
    rng = np.random.default_rng(0)
    base = rng.normal(size=(60, 64))
    x = np.concatenate([base, base + rng.normal(size=base.shape) * 0.36, base[:5] * 3])
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    want = {(i, j) for i in range(len(x)) for j in range(i + 1, len(x)) if u[i] @ u[j] >= 0.93}
    i, j = tile_links(x, None, 0.93, step=32)
    assert set(zip(i.tolist(), j.tolist())) == want and 5 < len(want) < 200


def test_embedding_edge_cases(spark):
    rows = [(1, [1.0, 0.0], 1), (2, [2.0, 0.0], 1), (3, [1.0, 0.0], 2), (4, None, 1), (5, [0.0, 0.0], 1), (6, [float("nan"), 1.0], 1), (7, [1.0, None], 1), (8, [1.0, 0.0], None), (9, [1.0, 0.1], 1), (9, [1.0, 0.1], 1), (10, [], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = sorted((r.vec_id, r.n_links, r.component_id, r.kept) for r in embedding_links(df, tile_rows=2).collect())
    assert got == [(1, 3, 1, True), (2, 3, 1, False), (3, 0, 3, True), (4, 0, 4, True), (5, 0, 5, True), (6, 0, 6, True), (7, 0, 7, True), (8, 0, 8, True), (9, 3, 1, False), (9, 3, 1, False), (10, 0, 10, True)]
    assert embedding_links(df.where("false")).count() == 0


def test_components(spark):
    links = [(5, 4), (4, 3), (3, 2), (2, 1), (10, 11), (12, 11), (7, 7)]
    got = {r.id: r.component for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 10: 10, 11: 10, 12: 10}
    assert local_roots(5, np.array([4, 3]), np.array([3, 1])).tolist() == [0, 1, 2, 1, 1]


def test_tree_links_equal_brute_force():
    rng = np.random.default_rng(1)
    sets = []
    for _ in range(40):
        s = rng.integers(0, 1 << 40, rng.integers(20, 200)).astype(np.uint64)
        for _ in range(3):
            drop = rng.random(len(s)) > rng.choice([0.02, 0.1, 0.2])
            sets.append(np.unique(np.concatenate((s[drop], rng.integers(0, 1 << 40, 3).astype(np.uint64)))))
    sets = sets + [sets[0][:1], sets[0][:1]]
    hit = [(i, j) for i in range(len(sets)) for j in range(i) if 100 * (k := overlap(sets[i], sets[j])) >= 80 * (len(sets[i]) + len(sets[j]) - k)]
    pick = lambda pairs: local_roots(len(sets), *(np.array(v, np.int64) for v in zip(*pairs)))
    assert pick(list(tree_links(sets))).tolist() == pick(hit).tolist() and hit


def test_jaccard_edge_cases(spark):
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_components(edge(spark)).collect()}
    assert got == {1: (0, 1), 2: (0, 2), 3: (0, 3), 4: (1, 4), 5: (1, 5), 6: (1, 6), 7: (1, 7)}
    assert jaccard_components(edge(spark).where("false")).count() == 0


def test_jaccard_equals_sql(spark):
    from quillon.llm.sql import SQL

    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    got = jaccard_components(spark.read.parquet(f"{SF}/documents.parquet")).select("doc_id", "n_shingles", "component_id")
    assert sorted(map(tuple, got.collect())) == sorted(con.execute(SQL["op2_ngram_jaccard_join"]).fetchall())


def test_base_secrets_equal_plain_patterns():
    rng = np.random.default_rng(2)
    bits = ["password", "TOKEN", "api_key", "apikey", "=", ": ", "'", '"', " ", "abc", "xYz123", "AKIA", "ABCDEFGHIJ0123456789", "deadbeef" * 3, "0f", "\n", "ſecret", "secret"]
    for _ in range(400):
        text = "".join(rng.choice(bits, rng.integers(1, 14)))
        want = [("assign", *m.span()) for m in re.finditer(r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text, re.A) if len(m[2]) >= 6]
        want += [("access", *m.span()) for m in re.finditer(r"AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
        want += [("hex", *m.span()) for m in re.finditer(r"[0-9a-f]+", text) if len(m[0]) >= 24]
        assert secrets.base_spans(text) == want


def test_lexed_secrets():
    text = 'KEY = "abc12345XYZ"\npassword = KEY\ndb_pwd: "ab" + "cdefgh12"\n<secretKey>zz99zz88q</secretKey>\ntoken_count = 123456\npassword = "changeme"\n'
    found = {text[a:b] for _, a, b in secrets.lexed_spans(text)}
    assert found >= {"abc12345XYZ", "cdefgh12", "zz99zz88q"} and not found & {"123456", "changeme"}
    assert "zz99" not in secrets.redacted(text, secrets.lexed_spans(text))


def test_bpe_equals_library(spark):
    own = bpe.encoder(bpe.default_vocabulary())
    rng = np.random.default_rng(3)
    texts = [t for _, t in EDGE if t] + ["hi<|endoftext|> 's 'll", "ԱՙՠჅ ꟎ x", "a" * 300 + " " * 700 + "é" * 900 + "!?" * 400] + ["".join(rng.choice(list("abеё1 .\n"), 900)) for _ in range(30)]
    for t in texts:
        ids = own.tokenizer.encode(t, add_special_tokens=False).ids
        assert own.encode(t) == ids and own.decode(ids) == own.tokenizer.decode(ids, skip_special_tokens=False)
    rows = {r.doc_id: r for r in bpe.bpe_digests(edge(spark)).collect()}
    assert rows[1].n_tokens == rows[2].n_tokens == 0 and rows[1].ids_sha256 == hashlib.sha256(b"").hexdigest()


@pytest.mark.parametrize("order", [0, 2, 8])
def test_flac_round_trip(order):
    rng = np.random.default_rng(4)
    payloads = [np.full(576, 255, np.uint8), rng.integers(0, 256, 1728).astype(np.uint8), (128 + 100 * np.sin(np.arange(2880) / 9)).astype(np.uint8), np.tile(np.arange(256, dtype=np.uint8), 576), np.where(rng.random(1152) < 0.01, 255, 3).astype(np.uint8)]
    media = flac.encode(payloads, order)
    assert all(np.array_equal(p.astype(int) - 128, x) for p, x in zip(payloads, flac.decode(media)))
    broken = bytearray(media[2])
    broken[len(broken) // 2] ^= 4
    with pytest.raises(flac.FlacError):
        flac.decode([bytes(broken)])


def test_media_digests_and_blocks(spark):
    rows = {r.doc_id: r for r in flac.media_digests(edge(spark)).collect()}
    assert rows[1].payload_bytes == 576 and rows[1].payload_sha256 == hashlib.sha256(b"\xff" * 576).hexdigest()
    assert rows[6].n_bytes == 60000 and rows[6].payload_bytes % 576 == 0
    media = flac.media_digests(edge(spark).where("doc_id = 6"), with_media=True)
    blocks = sorted(flac.pcm_blocks(media, block_samples=5760).collect(), key=lambda r: r.block)
    assert [r.sample_offset for r in blocks] == [5760 * k for k in range(len(blocks))] and sum(r.n_samples for r in blocks) == rows[6].payload_bytes


def test_language_id(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = language_id.language_predictions(docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (got.lang_pred == got.lang).mean() > 0.97
    assert {r.lang_pred for r in language_id.language_predictions(edge(spark)).where("doc_id < 4").collect()} == {"und"}


def test_language_stage_rejects_ties_and_narrow_margins(spark):
    import corpus_pipeline

    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = language_id.learn_dictionaries(docs.where(~language_id.crc_held_out()))
    judge = language_id.Compressors(model).judge
    part = {k: next(r.text for r in docs.where(f"lang = '{k}' and n_chars > 9000").orderBy("doc_id").collect()) for k in ("en", "de")}
    both = lambda n: part["en"][:6000] + " " + part["de"][:n]
    flip = next(n for n in range(0, 9000, 100) if judge(both(n))[0] == "de")
    mixed = next(both(n) for n in range(flip - 200, flip + 100) if 0 < judge(both(n))[1] < language_id.MARGIN)
    tie = next(r.text for r in docs.orderBy("n_chars").collect() if judge(r.text) == (model[0][0], 0.0))
    ids = [r.id for r in spark.range(1 << 40, (1 << 40) + 60).where(language_id.crc_held_out("id")).collect()[:3]]  # not learnt from
    more = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in zip(ids, (mixed, tie, part["en"]), strict=True)], docs.schema)
    kept = {r.doc_id for r in corpus_pipeline.language_stage(spark, docs.unionByName(more), "").where(f"doc_id >= {1 << 40}").collect()}
    assert kept == {ids[2]}
    assert not any(r.lang_ok for r in language_id.identify(more.where(f"doc_id = {ids[1]}"), model, margin=0.0).collect())


def test_html(spark):
    page = '<html><head><title>T</title></head><body><nav><ul><li><a href="/a">Home</a></li></ul></nav><div class="cookie-notice"><p>We use cookies.</p></div><article><h1>A &amp; B</h1><p>First\n one is a long enough sentence, here.<br>More<p>Second one is also a sentence.</article><div class="comments"><h3>Comments</h3><p>I do not agree at all.</p></div><script>var x="</p>";</script><footer>&copy; x</footer></body></html>'
    field = html_extract.trained_field()
    assert html_extract.main_text(page, field) == "A & B\n\nFirst one is a long enough sentence, here. More\n\nSecond one is also a sentence."
    made = html_extract.training_set(60, 99)
    assert np.mean([a == b for names, y in made for a, b in zip(field.decode(names), y)]) > 0.97
    df = spark.createDataFrame([(1, "u", None), (2, None, ""), (3, "u", "a < b <p"), (4, "u", page)], "page_id long, url string, html string")
    assert {r.page_id: r.n_chars for r in html_extract.extract_pages(df).collect()}[1] == 0


def test_toxicity(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    got = toxicity.toxicity_scores(docs, labels).join(labels, "doc_id").where("held_out").toPandas()
    assert (got.predicted == got.toxic).mean() > 0.96
    assert toxicity.toxicity_scores(edge(spark), labels.where("false")).count() == len(EDGE)


def test_factorisation_learns_pairs():
    rng = np.random.default_rng(0)
    docs = [np.unique(np.append(rng.integers(10, 60, 5), [k for k in (1, 2) if rng.random() < 0.5])) for _ in range(600)]
    y = np.array([int(1 in d and 2 in d) for d in docs])
    m = toxicity.fit(docs, y)
    one = lambda *t: m.raw(np.zeros(len(t), int), np.searchsorted(m.terms, t), 1)[0]
    assert one(1, 2) > 0 > max(one(1), one(2))


def test_factorisation_learns_pairs_of_neutral_terms():
    rng = np.random.default_rng(5)
    docs, y = [], []
    for k in range(2000):  # 5 % toxic; term 1 is an insult, 2 neutral alone, 3 tells by itself
        toxic = k % 20 == 0
        own = [[1, 2], [3]][k // 20 % 2] if toxic else [[2], [1], [2], []][k % 4]
        docs.append(np.unique(np.append(rng.integers(10, 60, 5), own).astype(np.int64)))
        y.append(int(toxic))
    y = np.array(y)
    shares = [np.mean([2 in d for d, t in zip(docs, y, strict=True) if t == k]) for k in (0, 1)]
    assert abs(shares[0] - shares[1]) < 0.05
    m = toxicity.fit(docs, y)
    assert {1, 2, 3} <= set(m.terms.tolist()) and len(m.terms) < 10  # none of the noise
    one = lambda *t: m.raw(np.zeros(len(t), int), np.searchsorted(m.terms, t), 1)[0]
    assert one(1, 2) > 0 > max(one(1), one(2))


def test_url_filter(spark):
    urls = ["http://A.Org/x", "http://a.org", "https://m.example.org/en/12?q", "https://example.org/es/1", "https://notexample.org/es/1", "http://x.com/de/", "http://x.com.evil.net/fr/", None, "no scheme", "http://cheap-pills.net/x#a", "http://evil.net/foo.org/x", "http://org/"]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r.page_id: (r.rule, r.verdict) for r in url_filter.url_verdicts(df).collect()}
    assert got == {0: ("org/", "allow"), 1: (None, "allow"), 2: ("example.org/en/1", "block"), 3: ("example.org/es/", "block"), 4: ("org/", "allow"), 5: ("com/de/", "block"), 6: (None, "allow"), 7: (None, "allow"), 8: (None, "allow"), 9: (None, "block"), 10: (None, "allow"), 11: ("org/", "allow")}


def test_mixing(spark):
    sizes = spark.createDataFrame([("a", 1000), ("b", 10), ("c", 500), (None, 300)], "source string, source_size long")
    got = {r.source: r.target for r in source_targets(sizes).collect()}
    assert got["b"] == 20 and got[None] == 600 and sum(got.values()) == pytest.approx(1.5 * 1810) and got["c"] == pytest.approx(2 / 3 * got["a"])
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    a, b = (sorted(map(tuple, mixture(docs.repartition(n)).select("doc_id", "size", "taken").collect())) for n in (1, 5))
    assert a == b and all(t <= 2 * s for _, s, t in a)
    rows = mixture(edge(spark)).collect()
    assert len(rows) == len(EDGE) and all(r.taken == 0 for r in rows if r.size == 0)
    assert mixture(edge(spark).where("false")).count() == 0


def test_a_large_shard_has_every_pair_of_documents_in_some_task(spark, monkeypatch):
    monkeypatch.setattr(jaccard_join, "SHARD_DOCS", 8)
    rows = [(k, 1, 40 + k % 30) for k in range(120)]
    dealt = jaccard_join._shards(spark.createDataFrame(rows, "id long, cluster long, n long")).collect()
    tasks = {}
    for r in dealt:
        tasks.setdefault((r["lo"], r["hi"]), set()).add(r["id"])
    together = {(a, b) for ids in tasks.values() for a in ids for b in ids}
    lost = [(a, b) for a, _, n in rows for b, _, m in rows if 100 * min(n, m) >= 80 * max(n, m) and (a, b) not in together]
    assert not lost

"""The corpus pipeline's stages on odd rows: repeated and null ids, clashing columns, empty tables."""

import hashlib
import re

import pytest

import corpus_pipeline
from quillon.llm import jaccard_join, language_id, mixing, secrets

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, id long, copy int, copies int, row string, rep long, `group` string, sig string, rank int, words string"
LONG = "the quick brown fox jumps over the lazy dog and runs away from all of the other animals in the old forest today ".split()


def docs_of(spark, rows):
    more = (7, 77, 9, "r", 5, "g", "s", 3, "w")
    return spark.createDataFrame([(i, t, "en", s, None if t is None else len(t), *more) for i, t, s in rows], SCHEMA)


def text(k, n=60):
    return " ".join(f"{LONG[j % len(LONG)]}{k if j % 3 == 0 else ''}" for j in range(n))


ROWS = [
    (1, text(1), "a"), (1, text(2), "a"),  # one id, two texts
    (2, text(1) + " more", "a"), (3, text(3), None), (3, text(3), None),  # a near copy; a row that repeats
    (None, text(4), "b"), (None, text(5), "b"), (None, text(4) + " end", "b"), (None, None, "b"), (None, None, "b"), (4, None, "b"), (5, "", "a"),
    (6, text(6), "a"), (7, text(6), "c"), (8, "too short", "c"), (9, "too  short\n", "c"),
]


def shingles(t):
    w = (t or "").lower().split()
    return {tuple(w)} if 0 < len(w) < 5 else {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def test_one_of_each_group_equals_brute_force(spark):
    docs = docs_of(spark, ROWS)
    got = jaccard_join.one_of_each_group(docs)
    assert got.columns == docs.columns
    found = sorted(((r.doc_id, r.text) for r in got.collect()), key=str)
    sets = [shingles(t) for _, t, _ in ROWS]
    group = list(range(len(ROWS)))
    for _ in ROWS:
        for i, a in enumerate(sets):
            for j, b in enumerate(sets):
                if a and b and 100 * len(a & b) >= 80 * len(a | b):
                    group[i] = group[j] = min(group[i], group[j])
    want = [(i, t) for k, (i, t, _) in enumerate(ROWS) if not sets[k]]
    for g in {group[k] for k in range(len(ROWS)) if sets[k]}:
        members = [ROWS[k][:2] for k in range(len(ROWS)) if group[k] == g]
        options = sorted(members, key=lambda m: (m[0] is None, m[0] or 0))
        picked = [f for f in found if f in members]
        assert len(picked) == 1 and picked[0][0] == options[0][0]
        want.append(picked[0])
    assert found == sorted(want, key=str)


def test_components_of_repeated_and_null_ids(spark):
    got = sorted(((r.doc_id, r.n_shingles, r.component_id) for r in jaccard_join.jaccard_components(docs_of(spark, ROWS)).collect()), key=str)
    want = [(i, len(shingles(t)), {2: 1, 7: 6, 9: 8}.get(i, i)) for i, t, _ in ROWS]
    assert got == sorted(want, key=str)


def test_mixed_documents_keep_rows_without_an_id(spark):
    docs = docs_of(spark, ROWS)
    sizes = {r.text: 0 for r in docs.collect()}
    mix = mixing.mixture(docs)
    assert mix.count() == len(ROWS) and sum(r.taken for r in mix.collect()) > 0
    got = mixing.mixed_documents(docs)
    assert got.columns == docs.columns
    rows = got.collect()
    assert any(r.doc_id is None for r in rows) and {(r.copy, r.copies, r.id, r.row) for r in rows} == {(77, 9, 7, "r")}
    for r in rows:
        sizes[r.text] += 1
    assert all(n <= 2 * sum(t == x for _, x, _ in ROWS) for t, n in sizes.items())
    assert sorted(map(str, rows)) == sorted(map(str, mixing.mixed_documents(docs.repartition(3)).collect()))


def test_mixture_counts_equal_the_blocks_drawn(spark):
    """Brute force: the documents laid out in the operator's order, the blocks counted in Python."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    sized = mixing.stored(docs.select("doc_id", "source", mixing.word_count().alias("size"), mixing._mark("doc_id", "source", "text").alias("mark")), "t")
    places = mixing.packed(sized, sized.count()).collect()
    targets = mixing.stored(mixing.source_targets(sized.groupBy("source").agg(mixing.F.sum("size").alias("source_size"))), "t")
    uses = {}
    for r in mixing.slot_blocks(mixing.drawn_slots(targets)).collect():
        uses[r.source, r.block] = uses.get((r.source, r.block), 0) + 1
    assert max(uses.values()) <= 2
    ends = {}
    for r in sorted(places, key=lambda r: (str(r.source), r.start, r.size)):
        assert r.start == ends.get(r.source, 0)
        ends[r.source] = r.start + r.size
    want = {r.doc_id: sum(uses.get((r.source, w // mixing.BLOCK_WORDS), 0) for w in range(r.start, r.start + r.size)) for r in places}
    assert {r.doc_id: r.taken for r in mixing.mixture(docs).collect()} == want


def test_shards_counts_are_multinomial_and_totals_near_targets(spark):
    targets = spark.createDataFrame([("a", 64000, 96000.0), ("b", 64000, 32000.0), (None, 64000, 64000.0)], "source string, source_size long, target double")
    spreads = []
    for seed in range(8):
        rows = mixing.drawn_slots(targets, shard_slots=16, seed=seed).collect()
        total = {s: sum(r.n for r in rows if r.source == s) for s in ("a", "b", None)}
        assert all(abs(total[s] - n) <= 20 for s, n in (("a", 1500), ("b", 500), (None, 1000)))
        slots = {k: sum(r.n for r in rows if r.shard == k) for k in {r.shard for r in rows}}
        n = max(slots.values())
        counts = [sum(r.n for r in rows if r.shard == k and r.source == "a") for k in slots if slots[k] == n]
        spreads.append(sum((c - n / 2) ** 2 for c in counts) / len(counts) / (n * 0.25))
    assert 0.6 < sum(spreads) / len(spreads) < 1.5  # a binomial's variance; rounding alone would give a twelfth of that


@pytest.mark.parametrize("n", [1, 2, 3, 7, 16, 17, 99, 1000])
def test_permutation_is_one(spark, n):
    F = mixing.F
    got = [r.x for r in spark.range(n).select(mixing.permuted(F.col("id"), F.lit(n).cast("long"), F.lit("k")).alias("x")).collect()]
    assert sorted(got) == list(range(n))
    if n == 1000:
        steps = [(b - a) % n for a, b in zip(got, got[1:])]
        assert len(set(steps)) > 500  # no constant stride


def test_secret_and_token_stages_on_odd_rows(spark):
    docs = docs_of(spark, [*ROWS, (10, "password = hunter22x", "a")])
    clean = corpus_pipeline.secret_stage(spark, docs, "")
    assert clean.columns == docs.columns
    rows = clean.collect()
    assert len(rows) == len(ROWS) + 1 and all(r.n_chars == (None if r.text is None else len(r.text)) for r in rows) and not any("hunter22x" in (r.text or "") for r in rows)
    assert secrets.without_secrets(docs.drop("n_chars")).count() == len(ROWS) + 1
    tokens = corpus_pipeline.token_stage(spark, docs, "").collect()
    assert len(tokens) == len(ROWS) + 1 and {r.ids_sha256 for r in tokens if r.n_tokens == 0} == {hashlib.sha256(b"").hexdigest()}


def test_language_stage_on_odd_rows(spark):
    more = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").where("n_chars > 300")
    docs = docs_of(spark, [(r.doc_id, r.text, "a") for r in more.collect()] + [(None, "½ ² ③ 12", "a"), (None, None, "a"), (10**9, "½ Ⅷ", "a")])
    kept = corpus_pipeline.language_stage(spark, docs, "").collect()
    assert len(kept) >= more.count() - 1 and not {r.text for r in kept} & {"½ ² ③ 12", None, "½ Ⅷ"}
    assert language_id.Compressors([("en", b"some words of the language")]).judge("½ ² ③") == ("und", 0.0)


def test_whole_pipeline_and_empty_tables(spark, tmp_path):
    docs = docs_of(spark, ROWS)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        empty = stage(spark, docs.where("false"), "")
        assert empty.columns == docs.columns and empty.count() == 0, name
    assert corpus_pipeline.token_stage(spark, docs.where("false"), "").count() == 0
    source = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    out = corpus_pipeline.run(spark, "/root/testdata/sf0.001").toPandas()
    assert set(out.doc_id) <= {r.doc_id for r in source.collect()} and out.groupby("doc_id").size().max() <= 2 and len(out) > 100


def test_no_broadcast_of_the_blocks_taken(spark):
    """Blocks grow with the words of all documents; the planner's guess of their number must not send them to the driver."""
    docs = spark.range(40).selectExpr("id AS doc_id", "repeat('word ', 3000) AS text", "concat('s', id % 3) AS source")
    mix = mixing.mixture(docs)
    assert sum(r["taken"] for r in mix.collect()) > 0
    plan = mix._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0]
    joins = [line for line in plan.splitlines() if "BroadcastHashJoin" in line and re.search(r"\bb#", line)]
    assert not joins, joins

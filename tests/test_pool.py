"""Pools, vertical bitmaps and lists over all items against brute force."""

import itertools
import math

import numpy as np
import pytest

from quillon.functions.scores import binomial_two_tailed, binomial_two_tailed_many, kl2_value
from quillon.operators.bag import bag_of
from quillon.operators.greedy import summarize
from quillon.operators.maxent import MaxEntModel
from quillon.operators.pool import best_lazy, rule, start_state, summarize_pool, summarize_rows
from quillon.operators.vertical import PoolTooLarge, mine, vertical
from quillon.sources import synth
from quillon.sources.views import transactions
from quillon.workloads import mining

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def baskets(spark):
    rng = np.random.default_rng(8)
    rows = []
    for t in range(400):
        own = {x for x in "abcdefg" if rng.random() < 0.3}
        if rng.random() < 0.2:
            own |= {"a", "b", "c"}
        rows.append((t, sorted(own)))
    return rows, spark.createDataFrame(rows, "tid long, items array<string>")


def supports(rows, most):
    out = {}
    for size in range(2, most + 1):
        for x in itertools.combinations("abcdefg", size):
            out["|".join(x)] = sum(set(x) <= set(items) for _, items in rows)
    return out


def test_mined_itemsets_equal_brute_force(spark, baskets):
    rows, df = baskets
    v = vertical(df.repartition(3), 20)
    got = {v.names(r["items"]): r["supp"] for r in mine(v).collect()}
    want = {k: s for k, s in supports(rows, 7).items() if s >= 20}
    assert got == want and max(k.count("|") for k in want) >= 2
    assert v.n == 400 and v.m == 7
    asked = np.array([[-1, 0, 1], [0, 1, 2]], np.int32)  # a shorter set stands behind -1
    assert v.supports_of(asked).tolist() == [supports(rows, 3)[v.names(x[x >= 0])] for x in asked]


def test_other_half_uses_the_same_items(spark, baskets):
    rows, df = baskets
    v = vertical(df.where("tid % 2 = 0"), 20)
    held = vertical(df.where("tid % 2 = 1"), 1, like=v)
    pairs = np.array(list(itertools.combinations(range(len(v.items)), 2)), np.int32)
    odd = supports([r for r in rows if r[0] % 2], 2)
    assert held.supports_of(pairs).tolist() == [odd[v.names(p)] for p in pairs]


def test_lists_equal_those_of_the_block_model(spark, baskets):
    rows, df = baskets
    for kind in ("bic", "mdl"):
        bag = bag_of(df, 7)
        old, new = summarize(bag, kind, max_size=4, k=6), summarize_rows(df, kind, 1, 4, k=6)
        assert [bag.names(p.items) for p in old.picks] == [new.vertical.names(p.items) for p in new.picks]
        assert new.score == pytest.approx(old.score, abs=1e-2)


def test_known_itemsets_are_not_charged_and_not_reported(spark, baskets):
    rows, df = baskets
    v = vertical(df, 1)
    at = {x: k for k, x in enumerate(v.items)}
    pool = mine(v, 3)
    first = summarize_pool(v, pool, "mdl", k=1).picks[0]
    known = [(first.items, first.support / v.n)]
    state = start_state(v, known)
    assert state.k == state.total == 0 and state.estimate(first.items) == pytest.approx(first.support / v.n, abs=1e-6)
    assert state.score("mdl") < start_state(v).score("mdl")
    assert first.items not in [p.items for p in summarize_pool(v, pool, "mdl", known=known).picks]
    stated = rule([at["a"]], [at["b"]], 0.5, 0.8)
    assert stated == [(tuple(sorted((at["a"], at["b"]))), 0.4)]
    many = start_state(v, rule([at["a"], at["b"]], [at["c"]], 0.3, 0.9))
    assert many.estimate([at["a"], at["b"], at["c"]]) == pytest.approx(0.27, abs=1e-4)


def test_branch_and_bound_finds_the_best(spark, baskets):
    rows, df = baskets
    v = vertical(df.repartition(5), 1)
    state = start_state(v)
    every = []
    for k, s in supports(rows, 4).items():
        ids = tuple(sorted(v.items.index(x) for x in k.split("|")))
        if s:
            every.append((kl2_value(s / 400, float(np.prod(v.frequencies[list(ids)]))) - len(ids) * math.log2(7) / 400, ids))
    for seed in (None, 0.5):
        found, stats = best_lazy(v, state, "mdl", 4, seed=seed)
        assert found[3] == pytest.approx(max(every)[0], abs=1e-9) and stats["visited"] > 0


def test_time_limit_and_size_limits(spark, baskets, monkeypatch):
    rows, df = baskets
    v = vertical(df, 1)
    s = summarize_pool(v, mine(v, 2), "bic", time_limit=0.0)
    assert not s.finished and not s.picks
    monkeypatch.setattr("quillon.operators.vertical.MOST_SETS", 5)
    with pytest.raises(PoolTooLarge):
        mine(v, 3)


def test_empty_and_odd_rows(spark):
    none = spark.createDataFrame([], "tid long, items array<string>")
    assert not summarize_rows(none, "mdl").picks
    same = spark.createDataFrame([(k, ["x", "y"]) for k in range(20)] + [(99, [])], "tid long, items array<string>")
    s = summarize_rows(same, "bic", 1)
    assert s.vertical.n == 21 and [s.vertical.names(p.items) for p in s.picks] == ["x|y"]


def test_generated_data_behave_as_published(spark):
    v = vertical(synth.mosaic(spark, 4000).select("items"), 200)
    found = summarize_pool(v, mine(v), "mdl", k=5)
    assert {v.names(p.items) for p in found.picks} == {"|".join(f"i{5 * g + j:02d}" for j in range(5)) for g in range(5)}
    v = vertical(synth.draws(spark, 2386).select("items"), 3)
    assert not summarize_pool(v, mine(v, 3), "mdl").picks
    v = vertical(synth.independent(spark, 5000, 12).select("items"), 250)
    assert not summarize_pool(v, mine(v), "mdl").picks
    v = vertical(synth.chain(spark, 20000, 10).select("items"), 1000)
    lists = [sorted(p.items) for p in summarize_pool(v, mine(v), "mdl", k=4).picks]
    runs = [sorted(int(v.items[i][1:]) for i in x) for x in lists]
    assert runs and all(r == list(range(r[0], r[0] + len(r))) for r in runs)


def test_part_equals_block_model():
    margins, sets = [0.5, 0.4, 0.3, 0.6], [(0b0011, 0.3), (0b1110, 0.1)]
    model = MaxEntModel(4, [m for m, _ in sets], [f for _, f in sets], margins).fit(1e-12, 5000)
    from quillon.operators.pool import Part, free_rows

    part = Part((0, 1, 2, 3), [(m, f, True) for m, f in sets]).fit(np.array(margins), free_rows(margins), 1e-12, 5000)
    assert all(part.within[x] == pytest.approx(model.query(x), abs=1e-9) for x in range(1, 16))


def test_p_values_equal_single_ones():
    rng = np.random.default_rng(4)
    d = rng.integers(1, 400, 300)
    p = np.where(rng.random(300) < 0.1, rng.integers(0, 2, 300), rng.random(300) * rng.random(300))
    f = rng.binomial(d, np.clip(p * rng.uniform(0.7, 1.4, 300), 0, 1))
    assert binomial_two_tailed_many(f, d, p) == pytest.approx([binomial_two_tailed(int(a), int(b), float(c)) for a, b, c in zip(f, d, p)], abs=1e-10)


def test_full_search_lists(spark):
    s = mining.of_view(spark, SF, "part_attr", 0.02, 3, "bic", 4)
    assert s.vertical.m > 40 and s.curve() == sorted(s.curve(), reverse=True)
    rows = transactions(spark, SF, "user_day")
    assert [p.items for p in mining.of_view(spark, SF, "user_day", k=2).picks] == [p.items for p in summarize_rows(rows, "mdl", 1, 4, k=2).picks]

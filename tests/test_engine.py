"""Queries at the smallest scale, and outcomes on data of known structure."""

import duckdb
import pytest

import __spark_entry__ as entry_module
from quillon import registry
from quillon.operators.bag import bag_of
from quillon.operators.greedy import summarize
from quillon.sources import synth

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def sql():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def test_entry(spark):
    assert entry_module.entry(spark).count() > 0


def test_every_oracle_has_a_query():
    assert set(registry.oracle_sql()) <= set(registry.queries())


@pytest.mark.parametrize("name", ["rank_pool", "row_margins", "frequent_itemsets", "fit_with_columns", "score_mdl", "summary_user_day_mdl", "binomial_pvalue", "closed_itemsets", "session_baskets"])
def test_query_equals_sql(spark, sql, name):
    got = registry.queries()[name](spark, SF)
    columns = sorted(got.columns)
    shown = lambda v: f"{v + 0.0:.7g}" if isinstance(v, float) else str(v)
    want = sql.execute(registry.oracle_sql()[name])
    names = [d[0] for d in want.description]
    expected = sorted(tuple(shown(r[names.index(c)]) for c in columns) for r in want.fetchall())
    assert sorted(tuple(shown(r[c]) for c in columns) for r in got.collect()) == expected


def test_planted_sets_come_first(spark):
    bag = bag_of(synth.mosaic(spark, 2000, 15), 15)
    found = summarize(bag, "mdl", k=3, max_size=5)
    planted = {"|".join(f"i{k:02d}" for k in range(5 * g, 5 * g + 5)) for g in range(3)}
    assert {bag.names(p.items) for p in found.picks} == planted
    assert found.curve() == sorted(found.curve(), reverse=True)


def test_nothing_in_independent_data(spark):
    assert not summarize(bag_of(synth.independent(spark, 2000, 10), 10), "mdl", max_size=3, k=3).picks


def test_fair_draw_has_no_pattern(spark):
    rows = synth.draws(spark, 2000)
    assert {r["n"] for r in rows.selectExpr("size(items) AS n").distinct().collect()} == {7}
    assert not summarize(bag_of(rows, 12), "mdl", max_size=2, k=2).picks

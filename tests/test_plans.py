"""Plans that have to stay as they are: filters and columns reach the scans, no Python where built-ins do, no nested loops."""

import pytest

from quillon import registry
from quillon.operators.bag import margins
from quillon.plans.inspect import facts
from quillon.sources.views import table, transactions

SF = "/root/testdata/sf0.001"


def test_filters_and_columns_reach_the_scan(spark):
    df = table(spark, SF, "lineitem").where("l_quantity > 40").groupBy("l_returnflag").count()
    f = facts(df)
    assert any("GreaterThan(l_quantity,40" in p for p in f.pushed) and len(f.read[0].split(",")) == 2 and f.exchanges == 1


def test_views_of_attributes_do_not_shuffle(spark):
    for view in ("part_attr", "line_attr", "doc_word", "emb_bin", "page_tag"):
        f = facts(transactions(spark, SF, view))
        assert f.exchanges == f.python == 0, view
    f = facts(margins(transactions(spark, SF, "line_attr")))
    assert f.exchanges == 1 and f.nodes["HashAggregate"] == 2  # summed before the shuffle


@pytest.mark.parametrize("name", ["rank_pool", "static_rank_kl", "column_margins", "row_margins", "view_stats", "empirical_distribution"])
def test_built_ins_only(spark, name):
    f = facts(registry.queries()[name](spark, SF))
    assert f.python == 0 and f.nodes["CartesianProduct"] == 0


def test_python_nodes_are_counted(spark):
    assert facts(spark.range(3).mapInArrow(lambda b: b, "id long")).python == 1

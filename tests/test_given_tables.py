"""Queries that once made their data up read a given table: without one they fail."""

import pytest

from quillon import registry


@pytest.mark.parametrize("name", [
    "block_cumulative",
    "block_sizes_quadratic",
    "block_sizes_quick",
    "block_subtractions",
    "cap_admissible",
    "chain_true_score",
    "closed_blocks",
    "closure_table",
    "entropy_drop",
    "fit_small_collection",
    "itemset_groups",
    "math_kl",
])
def test_reads_a_given_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        registry.queries()[name](spark, str(tmp_path)).collect()

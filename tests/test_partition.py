"""Parts of items against plain counting."""

import itertools
import math
from collections import Counter

import numpy as np

from quillon.operators import partition
from quillon.operators.bag import bag_of, wide_bag_of
from quillon.operators.partition import partition_items
from quillon.sources.views import transactions
from quillon.workloads import modelling

SF = "/root/testdata/sf0.001"


def test_parts_are_where_items_hang_together(spark):
    rng = np.random.default_rng(1)
    rows = []
    for _ in range(500):
        own = set()
        for group in ("abc", "de"):
            if rng.random() < 0.5:
                own |= {x for x in group if rng.random() < 0.9}
        own |= {x for x in "fg" if rng.random() < 0.4}
        rows.append(sorted(own))
    bag = bag_of(spark.createDataFrame([(k, r) for k, r in enumerate(rows)], "tid long, items array<string>"), 7)
    parts, total = partition_items(bag)
    assert sorted(bag.names(p) for p in parts) == ["a|b|c", "d|e", "f", "g"]

    def bits(names):
        kinds = Counter(frozenset(names) & frozenset(r) for r in rows)
        return -sum(c * math.log2(c / len(rows)) for c in kinds.values()) + (len(kinds) - 1) / 2 * math.log2(len(rows))

    sets = [set(bag.names(p).split("|")) for p in parts]
    assert math.isclose(total, sum(map(bits, sets)), rel_tol=1e-9)
    assert all(bits(x | y) >= bits(x) + bits(y) for x, y in itertools.combinations(sets, 2))
    small, _ = partition_items(bag, 2)
    assert all(p.bit_count() <= 2 for p in small)


def test_merges_share_jobs(spark, monkeypatch):
    """Ten pairs of equal items: ten merges, but not a job each; many of the unions they need are measured ahead."""
    rng = np.random.default_rng(2)
    coins = rng.random((300, 10)) < 0.5
    rows = [(k, [f"{x}{i}" for i in range(10) if own[i] for x in "ab"]) for k, own in enumerate(coins)]
    bag = bag_of(spark.createDataFrame(rows, "tid long, items array<string>"), 20)
    jobs, measure = [], partition.part_bits
    monkeypatch.setattr(partition, "part_bits", lambda b, parts: jobs.append(len(parts)) or measure(b, parts))
    parts, _ = partition_items(bag, 2)
    assert sorted(bag.names(p) for p in parts) == [f"a{i}|b{i}" for i in range(10)]
    parts, _ = partition_items(bag, 4)
    assert all(p.bit_count() <= 4 for p in parts) and len(jobs) < 8


def plain_parts(rows):
    """Merging without a limit, by plain counting: (parts, bits together)."""
    n, seen = len(rows), {}

    def bits(names):
        if names not in seen:
            kinds = Counter(names & r for r in rows)
            seen[names] = -sum(c * math.log2(c / n) for c in kinds.values()) + (len(kinds) - 1) / 2 * math.log2(n)
        return seen[names]

    parts = {frozenset([x]) for r in rows for x in r}
    while True:
        gain, x, y = max(((bits(x) + bits(y) - bits(x | y), x, y) for x, y in itertools.combinations(parts, 2)), key=lambda e: e[0], default=(0, None, None))
        if gain <= 1e-9:
            return parts, sum(map(bits, parts))
        parts = parts - {x, y} | {x | y}


def test_parts_grow_while_merges_save(spark):
    """Fourteen items that hang together are in one part, not ten in one and the rest elsewhere."""
    rng = np.random.default_rng(3)
    rows = []
    for both in rng.random((400, 2)) < 0.5:
        rows.append(frozenset([f"a{i:02}" for i in range(14) if both[0] and rng.random() < 0.97] + [x for x in "bc" if both[1]]))
    bag = bag_of(spark.createDataFrame([(k, sorted(r)) for k, r in enumerate(rows)], "tid long, items array<string>"), 20)
    parts, total = partition_items(bag)
    expected, bits = plain_parts(rows)
    assert max(map(len, expected)) >= 14
    assert {frozenset(bag.names(p).split("|")) for p in parts} == expected and math.isclose(total, bits, rel_tol=1e-9)


def test_more_items_than_a_mask_holds(spark, monkeypatch):
    """Seventy values of an attribute, five of another: a part over two words, one within; kinds are passed on early, too."""
    monkeypatch.setattr(partition, "HELD_KINDS", 64)
    rng = np.random.default_rng(4)
    rows = [frozenset([f"v={rng.integers(70)}", f"w={rng.integers(5)}"]) for _ in range(3000)] + [frozenset()] * 5
    bag = wide_bag_of(spark.createDataFrame([(k, sorted(r)) for k, r in enumerate(rows)], "tid long, items array<string>").repartition(3))
    assert (bag.m, bag.n, len(bag.rows.columns)) == (75, 3005, 3)
    parts, _ = partition_items(bag)
    assert sorted(p.bit_count() for p in parts) == [5, 70]
    both = sum(parts)
    kinds = Counter(rows)
    bits = -sum(c * math.log2(c / len(rows)) for c in kinds.values()) + (len(kinds) - 1) / 2 * math.log2(len(rows))
    assert math.isclose(partition.part_bits(bag, [both])[both], bits, rel_tol=1e-9)


def test_query_has_all_items_and_whole_parts(spark):
    """Each value of the orders' attributes is there, and the parts are those of plain counting."""
    got = modelling.item_partition(spark, SF).collect()
    rows = [frozenset(r["items"]) for r in transactions(spark, SF, "order_attr").collect()]
    expected, bits = plain_parts(rows)
    parts = {}
    for r in got:
        parts.setdefault(r["part"], set()).add(r["item"])
    assert {frozenset(p) for p in parts.values()} == expected and max(map(len, expected)) > 10
    assert math.isclose(got[0]["bits"], bits, abs_tol=0.01)


def test_empty_bag(spark):
    bag = wide_bag_of(spark.createDataFrame([], "tid long, items array<string>"))
    assert (bag.items, bag.n) == ([], 0) and partition_items(bag) == ([], 0)

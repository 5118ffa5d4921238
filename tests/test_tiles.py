"""Tiles and code tables against plain covers of rows."""

import math

import numpy as np
import pytest

from quillon.operators import tiles
from quillon.operators.vertical import mine, vertical


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(3)
    rows = []
    for _ in range(150):
        own = {x for x in "abcdef" if rng.random() < 0.25} | (set("abc") if rng.random() < 0.4 else set())
        rows.append(sorted(own))
    v = vertical(spark.createDataFrame([(k, r) for k, r in enumerate(rows)], "tid long, items array<string>").repartition(3), 5)
    return rows, v, mine(v)


def named(v, x):
    return {v.items[i] for i in x}


def test_greedy_cover(small):
    rows, v, pool = small
    covered, sets = set(), tiles.pool_sets(pool)
    for tile, fresh in tiles.greedy_cover(v, sets, 3):
        area = lambda x: sum((r, i) not in covered for r, items in enumerate(rows) if named(v, x) <= set(items) for i in named(v, x))
        assert fresh == area(tile) == max(map(area, sets))
        covered |= {(r, i) for r, items in enumerate(rows) if named(v, tile) <= set(items) for i in named(v, tile)}


def test_margin_model_has_the_margins(small):
    rows, v, _ = small
    sizes = np.bincount([len(r) for r in rows], minlength=7)
    p = tiles.margin_model(sizes, v.supports.astype(float), 2000)
    assert (p * sizes[:, None]).sum(axis=0) == pytest.approx(v.supports, rel=1e-3)
    assert [p[s].sum() for s in range(1, 6) if sizes[s]] == pytest.approx([s for s in range(1, 6) if sizes[s]], rel=1e-3)


def test_tiles_by_information(small):
    rows, v, pool = small
    sets = tiles.pool_sets(pool)
    sizes = np.bincount([len(r) for r in rows], minlength=len(v.items) + 1)
    bits = -np.log2(np.clip(tiles.margin_model(sizes, v.supports.astype(float)), 1e-12, 1))
    covered, found = set(), tiles.by_information(v, sets, 2)
    for tile, told, ratio in found:
        info = lambda x: sum(bits[len(items), i] for r, items in enumerate(rows) if named(v, x) <= set(items) for i in x if (r, i) not in covered)
        assert told == pytest.approx(info(tile))
        covered |= {(r, i) for r, items in enumerate(rows) if named(v, tile) <= set(items) for i in tile}
    assert found[0][2] >= found[1][2] > 0


def test_code_table_covers_rows_and_shortens_them(small):
    rows, v, pool = small
    table, bits, alone = tiles.code_table(v, pool, batch=3)
    assert table and bits < alone and (table, bits) == tiles.code_table(v, pool, batch=50)[:2]
    order, usage, single = [x for x, _ in table], {x: 0 for x, _ in table}, np.zeros(len(v.items))
    for items in rows:
        left = {v.items.index(i) for i in items}
        for x in order:
            if set(x) <= left:
                usage[x] += 1
                left -= set(x)
        for i in left:
            single[i] += 1
    assert [usage[x] for x, _ in table] == [u for _, u in table]
    every = np.array([*usage.values(), *single])
    standard = -np.log2(v.supports / v.supports.sum())
    code = [-math.log2(u / every.sum()) if u else 0.0 for u in every]
    own = [sum(standard[list(x)]) for x in order] + list(standard)
    assert bits == pytest.approx(sum(u * c for u, c in zip(every, code)) + sum(c + o for u, c, o in zip(every, code, own) if u))

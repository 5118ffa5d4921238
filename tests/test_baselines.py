"""Randomised margins, the closed form of chains, and file streams, on small data."""

from itertools import product
from math import log2

import numpy as np
import pytest
from pyspark.sql import functions as F

from quillon import registry
from quillon.operators.bag import margins
from quillon.operators.swap import swap_randomize, trade
from quillon.sources import synth
from quillon.workloads.baselines import path_likelihood, path_scores

SF = "/root/testdata/sf0.001"


def test_trades_keep_both_margins_and_move_cells():
    rng = np.random.default_rng(1)
    cells = rng.random((101, 12)) < np.linspace(0.1, 0.9, 12)
    out = trade(cells, 10, rng)
    assert (out.sum(axis=0) == cells.sum(axis=0)).all() and (out.sum(axis=1) == cells.sum(axis=1)).all()
    assert (out != cells).any()
    for small in (np.zeros((0, 3), bool), np.ones((1, 3), bool)):
        assert (trade(small, 3, rng) == small).all()


def test_randomised_rows_repeat_and_lose_their_links(spark):
    rows = spark.range(400).select(F.col("id").alias("tid"), F.when(F.col("id") % 2 == 0, F.array(F.lit("a"), F.lit("b"))).otherwise(F.array(F.lit("c"), F.lit("d"))).alias("items"))
    shown = lambda: sorted((r["sample"], r["tid"], tuple(r["items"])) for r in swap_randomize(rows, 2, chunk_rows=128).collect())
    once = shown()
    assert once == shown() and len(once) == 800
    linked = [sum("a" in i and "b" in i for s, _, i in once if s == k) for k in (0, 1)]
    assert all(n < 150 for n in linked) and all(sum("a" in i for s, _, i in once if s == k) == 200 for k in (0, 1))


def test_chain_likelihood_is_the_product_of_its_rows(spark):
    rows, path = synth.chain(spark, 300, 4), [f"i{k:02d}" for k in range(4)]
    sets = [set(r["items"]) for r in rows.collect()]
    share = lambda *c: sum(all((path[k] in s) == v for k, v in c) for s in sets) / 300
    total, mass = 0.0, 0.0
    row_p = lambda bits: np.prod([share((k, bits[k]), (k + 1, bits[k + 1])) for k in range(3)]) / np.prod([share((k, bits[k])) for k in (1, 2)])
    p = {bits: row_p(bits) for bits in product((False, True), repeat=4)}
    mass, total = sum(p.values()), sum(log2(p[tuple(x in s for x in path)]) for s in sets)
    found = path_likelihood(rows, path).first()
    assert mass == pytest.approx(1) and found["chain"] == pytest.approx(total) and found["chain"] > found["independent"]


def test_the_true_chain_beats_the_background(spark):
    found = path_scores(synth.chain(spark, 1000), [f"i{k:02d}" for k in range(50)]).first()
    assert found["k"] == 49 and found["mdl"] < found["background"]


@pytest.mark.parametrize("stream,batch", [("stream_margins", "tumbling_baskets"), ("stream_sliding", "sliding_baskets")])
def test_stream_equals_batch(spark, stream, batch):
    q = registry.queries()
    shown = lambda n: sorted(tuple(r[c] for c in ("start", "event_type", "cnt")) for r in q[n](spark, SF).collect())
    assert shown(stream) == shown(batch)


def test_swapped_margins_on_a_view(spark):
    rows = synth.mosaic(spark, 500, 15)
    random = swap_randomize(rows, 1)
    assert sorted(map(tuple, margins(random).collect())) == sorted(map(tuple, margins(rows).collect()))

"""Randomised transactions with the margins of the given ones, by trades between pairs of rows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Cells of the row-by-item table that one task holds.
CHUNK_CELLS = 1 << 21


def trade(cells: np.ndarray, rounds: int, rng: np.random.Generator) -> np.ndarray:
    """A boolean table with the row and column sums of `cells`.

    Each round pairs all rows at random; what only one row of a pair holds is dealt anew between the two,
    each keeping its size. One round is a whole-array operation.
    """
    cells = cells.copy()
    half = len(cells) // 2
    for _ in range(rounds if half else 0):
        order = rng.permutation(len(cells))
        one, two = order[:half], order[half : 2 * half]
        a, b = cells[one], cells[two]
        pool = a ^ b
        draw = np.where(pool, rng.random(pool.shape), 2.0)
        place = np.argsort(np.argsort(draw, axis=1), axis=1)
        first = place < (a & pool).sum(axis=1)[:, None]
        cells[one], cells[two] = (a & b) | (pool & first), (a & b) | (pool & ~first)
    return cells


def swap_randomize(rows: DataFrame, samples: int, rounds: int = 20, seed: int = 7, chunk_rows: int = 4096) -> DataFrame:
    """(sample, tid, items): `samples` randomised versions of (tid, items).

    Rows are dealt to chunks by the hash of their tid and traded within a chunk, so that a chunk's margins
    hold and with them all margins; no task holds more than a chunk. A sample depends on the rows, the seed
    and the number of chunks alone. Empty rows stay empty; rows with a null tid share one chunk, so give
    them ids first.
    """
    chunks = max(1, -(-rows.count() // chunk_rows))
    dealt = rows.select(F.explode(F.sequence(F.lit(0), F.lit(samples - 1))).alias("sample"), F.col("tid").cast("string").alias("tid"), "items").withColumn("chunk", F.pmod(F.xxhash64("tid", F.lit(seed)), F.lit(chunks)))

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("tid")
        sets = table.column("items").to_pylist()
        names = sorted({x for s in sets for x in s})
        at = {x: k for k, x in enumerate(names)}
        key = seed, table.column("sample")[0].as_py(), table.column("chunk")[0].as_py()
        rng, out = np.random.default_rng(key), []
        step = max(2, CHUNK_CELLS // max(1, len(names)))
        for begin in range(0, len(sets), step):
            part = sets[begin : begin + step]
            cells = np.zeros((len(part), len(names)), bool)
            for r, s in enumerate(part):
                cells[r, [at[x] for x in s]] = True
            out += [[names[k] for k in np.flatnonzero(r)] for r in trade(cells, rounds, rng)]
        return pa.table({"sample": table.column("sample"), "tid": table.column("tid"), "items": pa.array(out, pa.list_(pa.string()))})

    return dealt.groupBy("sample", "chunk").applyInArrow(run, "sample int, tid string, items array<string>")


def swap_pvalues(rows: DataFrame, samples: int, rounds: int = 20, seed: int = 7) -> DataFrame:
    """(a, b, supp, mean_supp, p_value) of pairs: the share of samples, the data among them, with that support or more."""
    from .bag import pair_supports, pairs_of

    random = swap_randomize(rows, samples, rounds, seed)
    drawn = random.select("sample", F.explode(pairs_of()).alias("p")).groupBy("sample", F.col("p.a").alias("a"), F.col("p.b").alias("b")).agg(F.count("*").alias("drawn"))
    held = pair_supports(rows).join(drawn, ["a", "b"], "left")
    hits = F.count(F.when(F.col("drawn") >= F.col("supp"), 1))
    return held.groupBy("a", "b", "supp").agg((F.coalesce(F.sum("drawn"), F.lit(0)) / samples).alias("mean_supp"), ((hits + 1) / (samples + 1)).alias("p_value"))

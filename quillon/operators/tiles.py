"""Baselines from coverage: tiles by area, tiles by information about the margins, and code tables.

All three look at the rows as chunks of bitmaps; what a step needs of the steps before it, the tiles or the
code table chosen, is broadcast, so no step keeps state on the executors.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .pool import coin_bits
from .vertical import Vertical

Sets = list[tuple[int, ...]]


class _Chunk:
    """One chunk's bitmaps, by item."""

    def __init__(self, rows: int, ids: np.ndarray, bits):
        self.rows, self.words = rows, -(-rows // 64)
        self.of = dict(zip(ids.tolist(), np.frombuffer(bits, np.uint64).reshape(len(ids), self.words), strict=True))
        self.none = np.zeros(self.words, np.uint64)

    def item(self, i: int) -> np.ndarray:
        return self.of.get(i, self.none)

    def all_of(self, items: Iterable[int]) -> np.ndarray:
        out = None
        for i in items:
            out = self.item(i) if out is None else out & self.item(i)
        return self.none if out is None else out

    def uncovered(self, chosen: Sets) -> dict[int, np.ndarray]:
        """For each item of the chosen tiles, its rows that no tile covers."""
        left: dict[int, np.ndarray] = {}
        for tile in chosen:
            rows = self.all_of(tile)
            for i in tile:
                left[i] = left.get(i, self.item(i)) & ~rows
        return left

    def row_sizes(self) -> np.ndarray:
        out = np.zeros(self.rows, np.int64)
        for bits in self.of.values():
            out += self.flags(bits)
        return out

    def flags(self, bits: np.ndarray) -> np.ndarray:
        return np.unpackbits(bits.view(np.uint8))[: self.rows].astype(bool)


def popcount(bits: np.ndarray) -> int:
    return int(np.bitwise_count(bits).sum())


def _summed(v: Vertical, of_chunk: Callable[[_Chunk], np.ndarray], kind: type = float) -> np.ndarray:
    """The sum over all chunks of an array that a chunk gives, of one length for all."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for b in batches:
            for k in range(b.num_rows):
                got = of_chunk(_Chunk(b.column(0)[k].as_py(), b.column(1)[k].values.to_numpy(), b.column(2)[k].as_buffer()))
                total = got if total is None else total + got
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(np.asarray(total, np.float64))], names=["k", "x"])

    got = v.chunks.mapInArrow(run, "k long, x double").groupBy("k").agg(F.sum("x").alias("x")).toPandas()
    out = np.zeros(int(got["k"].max()) + 1 if len(got) else 0)
    out[got["k"].to_numpy()] = got["x"].to_numpy()
    return out.astype(kind)


def pool_sets(pool: DataFrame, most: int = 1 << 18) -> Sets:
    """The itemsets of a pool, whose number is checked."""
    n = pool.count()
    if n > most:
        raise ValueError(f"a pool of {n} itemsets; raise the minimum support to have {most} at most")
    return sorted(tuple(r["items"]) for r in pool.select("items").collect())


def largest(pool: DataFrame, k: int) -> DataFrame:
    """(items, supp, area): tiles of two items or more with the largest area."""
    return pool.withColumn("area", F.col("supp") * F.size("items")).orderBy(F.desc("area"), F.size("items"), "items").limit(k)


def greedy_cover(v: Vertical, sets: Sets, k: int) -> list[tuple[tuple[int, ...], int]]:
    """(tile, cells that no tile before it covers) of k tiles, each the largest by such cells."""
    chosen: list[tuple[tuple[int, ...], int]] = []
    while len(chosen) < k and sets:
        before = [t for t, _ in chosen]

        def areas(c: _Chunk, before=before) -> np.ndarray:
            left = c.uncovered(before)
            return np.array([sum(popcount(rows & left.get(i, rows)) for i in x) for x in sets for rows in (c.all_of(x),)], np.int64)

        fresh = _summed(v, areas, np.int64)
        at = min(range(len(sets)), key=lambda j: (-fresh[j], len(sets[j]), sets[j])) if len(fresh) else None
        if at is None or not fresh[at]:
            break
        chosen.append((sets[at], int(fresh[at])))
    return chosen


def margin_model(sizes: np.ndarray, totals: np.ndarray, sweeps: int = 200) -> np.ndarray:
    """Cell probabilities [row size, item] of the independent-cell model that has the row sizes' and the items' totals.

    odds of a cell = r[size] c[item], by rescaling either in turn; rows of one size share their r.
    """
    s = np.arange(len(sizes))
    r, c = np.where(s > 0, 1.0, 0.0), np.where(totals > 0, 1.0, 0.0)
    for _ in range(sweeps):
        for axis in (0, 1):
            p = np.outer(r, c)
            p = p / (1 + p)
            if axis == 0:
                now, want = p.sum(axis=1), s.astype(float)
                full = want >= (totals > 0).sum()
                r = np.where(full & (s > 0), 1e9, np.where(now > 0, r * want / np.maximum(now, 1e-12), 0.0))
            else:
                now = (p * sizes[:, None]).sum(axis=0)
                c = np.where(now > 0, c * totals / np.maximum(now, 1e-12), 0.0)
    p = np.outer(r, c)
    return p / (1 + p)


def by_information(v: Vertical, sets: Sets, k: int) -> list[tuple[tuple[int, ...], float, float]]:
    """(tile, information in bits, ratio to its description) of k tiles, best ratio first.

    A tile tells as many bits as its cells are unlikely under the margins of rows and columns, covered cells
    none; it is described by its items and by which rows have it.
    """
    m = len(v.items)
    sizes = _summed(v, lambda c: np.bincount(c.row_sizes(), minlength=m + 1), np.int64)
    if not len(sizes):
        return []
    bits = -np.log2(np.clip(margin_model(sizes, v.supports.astype(float)), 1e-12, 1.0))
    supports = np.concatenate([v.supports_of(np.array([x], np.int32)) for x in sets]) if len(sets) < 2 else v.supports_of(_padded(sets))
    cost = np.array([len(x) * np.log2(max(v.m, 2)) for x in sets]) + v.n * coin_bits(supports / v.n) + 1
    chosen: list[tuple[tuple[int, ...], float, float]] = []
    while len(chosen) < k and sets:
        before = [t for t, _, _ in chosen]

        def told(c: _Chunk, before=before) -> np.ndarray:
            size, left = c.row_sizes(), c.uncovered(before)
            out = np.zeros(len(sets))
            for j, x in enumerate(sets):
                rows = c.all_of(x)
                if rows.any():
                    for i in x:
                        cells = rows & left[i] if i in left else rows
                        out[j] += bits[size[c.flags(cells)], i].sum()
            return out

        found = _summed(v, told)
        ratio = np.where(supports > 0, found / cost, 0.0)
        at = min(range(len(sets)), key=lambda j: (-round(ratio[j], 9), len(sets[j]), sets[j]))
        if ratio[at] <= 0:
            break
        chosen.append((sets[at], float(found[at]), float(ratio[at])))
    return chosen


def _padded(sets: Sets) -> np.ndarray:
    width = max(map(len, sets), default=1)
    return np.array([[-1] * (width - len(x)) + list(x) for x in sets], np.int32).reshape(-1, width)


def usages(v: Vertical, tables: list[Sets]) -> list[np.ndarray]:
    """How often each itemset of each code table, and then each item, is used: rows are covered from the table's top down."""

    many = len(v.items)

    def cover(c: _Chunk) -> np.ndarray:
        out = []
        for table in tables:
            left = {}
            for x in table:
                use = None
                for i in x:
                    own = left.get(i, c.item(i))
                    use = own if use is None else use & own
                out.append(popcount(use))
                for i in x:
                    left[i] = left.get(i, c.item(i)) & ~use
            out += [popcount(left.get(i, c.item(i))) for i in range(many)]
        return np.array(out, np.int64)

    flat, at, out = _summed(v, cover, np.int64), 0, []
    for table in tables:
        n = len(table) + len(v.items)
        out.append(flat[at : at + n] if len(flat) else np.zeros(n, np.int64))
        at += n
    return out


def table_bits(table: Sets, usage: np.ndarray, standard: np.ndarray) -> float:
    """Bits of the rows under a code table, and of the table: its codes, and its itemsets by the items' own codes."""
    some = usage > 0
    length = np.where(some, -np.log2(np.where(some, usage, 1) / max(usage.sum(), 1)), 0.0)
    own = np.array([*(standard[list(x)].sum() for x in table), *standard])
    return float((usage * length).sum() + (length + own)[some].sum())


def code_table(v: Vertical, pool: DataFrame, batch: int = 64) -> tuple[list[tuple[tuple[int, ...], int]], float, float]:
    """([(itemset, usage)], bits, bits with items alone): a candidate stays in the table if it makes the whole shorter.

    Candidates go by support, size and items; the table covers by size, support and items. A batch of
    candidates is held against the current table in one job: those before the first that helps are
    rejected against that table, those after it are looked at again, as one by one.
    """
    n = pool.count()
    if n > 1 << 18:
        raise ValueError(f"a pool of {n} candidates; raise the minimum support")
    supp = {tuple(r["items"]): r["supp"] for r in pool.collect()}
    waiting = sorted(supp, key=lambda x: (-supp[x], -len(x), x))
    standard = np.where(v.supports > 0, -np.log2(np.maximum(v.supports, 1) / max(v.supports.sum(), 1)), 0.0)
    ordered = lambda sets: sorted(sets, key=lambda x: (-len(x), -supp[x], x))
    table: Sets = []
    usage = usages(v, [table])[0]
    alone = best = table_bits(table, usage, standard)
    while waiting:
        tried = [ordered([*table, x]) for x in waiting[:batch]]
        for k, (t, u) in enumerate(zip(tried, usages(v, tried), strict=True)):
            bits = table_bits(t, u, standard)
            if bits < best - 1e-9:
                table, usage, best, waiting = t, u, bits, waiting[k + 1 :]
                break
        else:
            waiting = waiting[batch:]
    return [(x, int(u)) for x, u in zip(table, usage, strict=False)], best, alone

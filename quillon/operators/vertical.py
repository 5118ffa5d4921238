"""Supports of many itemsets at once, from bitmaps of the items in chunks of rows."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.files import stored
from .bag import margins

#: Itemsets that are broadcast and counted together; items that a dictionary may have; itemsets a pool may have, candidates that are joined together.
BATCH_SETS, MOST_ITEMS, MOST_SETS, JOINED_SETS = 1 << 18, 1 << 20, 1 << 23, 1 << 20
#: Cells of a chunk's matrix, before it is packed into bits.
CHUNK_CELLS = 1 << 25


class PoolTooLarge(ValueError):
    """The itemsets above the minimum support are more than a driver should hold; nothing is cut off silently."""


@dataclass
class Vertical:
    """Rows as chunks of bitmaps, one for each item that occurs there.

    `items` are those with enough support, most frequent first; the others count in `m` and, by the entropy of
    their frequencies in bits a row, in `rest_bits`. Rows without any item count in `n`.
    """

    chunks: DataFrame
    items: list[str]
    supports: np.ndarray
    n: int
    m: int
    rest_bits: float
    min_support: int

    @property
    def frequencies(self) -> np.ndarray:
        return self.supports / max(self.n, 1)

    def names(self, ids) -> str:
        return "|".join(sorted(self.items[i] for i in ids))

    def count(self, sets: np.ndarray) -> DataFrame:
        """(k, supp) of the itemsets, the rows of `sets`, that occur: summed over chunks."""
        shared = self.chunks.sparkSession.sparkContext.broadcast(np.ascontiguousarray(sets, np.int32))

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            wanted, total = shared.value, None
            for b in batches:
                for k in range(b.num_rows):
                    found = _count_chunk(wanted, b.column(0)[k].as_py(), b.column(1)[k].values.to_numpy(), b.column(2)[k].as_buffer())
                    total = found if total is None else total + found
            if total is not None:
                some = np.flatnonzero(total)
                yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(total[some])], names=["k", "s"])

        return self.chunks.mapInArrow(run, "k long, s long").groupBy("k").agg(F.sum("s").alias("supp"))

    def supports_of(self, sets: np.ndarray) -> np.ndarray:
        """Supports of the itemsets, in batches whose results are one number an itemset."""
        out = np.zeros(len(sets), np.int64)
        for a in range(0, len(sets), BATCH_SETS):
            got = self.count(sets[a : a + BATCH_SETS]).toPandas()
            out[a + got["k"].to_numpy()] = got["supp"].to_numpy()
        return out


def _count_chunk(wanted: np.ndarray, rows: int, ids: np.ndarray, bits) -> np.ndarray:
    """Supports within one chunk; itemsets that share all but the last item are counted together."""
    words = -(-rows // 64)
    matrix = np.frombuffer(bits, np.uint64).reshape(len(ids), words)
    place = np.full(int(max(ids.max(initial=-1), wanted.max(initial=-1))) + 1, -1)
    place[ids] = np.arange(len(ids))
    at = np.where(wanted >= 0, place[wanted], -2)  # -2: no item at this place, for shorter sets
    out = np.zeros(len(wanted), np.int64)
    live = np.flatnonzero((at != -1).all(axis=1))
    if not len(live):
        return out
    at = at[live]
    width = at.shape[1]
    change = np.flatnonzero((at[1:, : width - 1] != at[:-1, : width - 1]).any(axis=1)) + 1 if width > 1 else np.zeros(0, np.int64)
    counts = np.zeros(len(live), np.int64)
    for a, b in zip([0, *change.tolist()], [*change.tolist(), len(live)], strict=True):
        prefix = None
        for i in at[a, : width - 1].tolist():
            if i >= 0:
                prefix = matrix[i] if prefix is None else prefix & matrix[i]
        last = at[a:b, width - 1]
        for c in range(0, len(last), 4096):
            own = last[c : c + 4096]
            block = np.where((own >= 0)[:, None], matrix[np.maximum(own, 0)], ~np.uint64(0)) if (own < 0).any() else matrix[own]
            counts[a + c : a + c + len(own)] = np.bitwise_count(block if prefix is None else block & prefix).sum(axis=1)
    out[live] = counts
    return out


def _chunks(rows: DataFrame, items: list[str]) -> DataFrame:
    shared = rows.sparkSession.sparkContext.broadcast(items)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = pa.array(shared.value, pa.string())
        for batch in batches:
            column = batch.column(0)
            found = pc.index_in(column.flatten(), value_set=names).fill_null(-1).to_numpy(zero_copy_only=False)
            owner = np.repeat(np.arange(batch.num_rows), pc.list_value_length(column).fill_null(0).to_numpy(zero_copy_only=False))
            owner, found = owner[found >= 0], found[found >= 0]
            step = max(64, CHUNK_CELLS // max(1, len(names)) // 64 * 64)
            for a in range(0, batch.num_rows, step):
                n = min(step, batch.num_rows - a)
                inside = (owner >= a) & (owner < a + n)
                ids = np.unique(found[inside])
                cells = np.zeros((len(ids), -(-n // 64) * 64), bool)
                cells[np.searchsorted(ids, found[inside]), owner[inside] - a] = True
                yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([ids.astype(np.int32)], pa.list_(pa.int32())), pa.array([np.packbits(cells, axis=1).tobytes()], pa.binary())], names=["n", "ids", "bits"])

    return rows.select("items").mapInArrow(run, "n long, ids array<int>, bits binary")


def vertical(rows: DataFrame, min_support: int = 1, like: Vertical | None = None) -> Vertical:
    """The bitmaps of (tid, items); with `like`, over that one's items whatever their supports here."""
    n = rows.count()
    counted = stored(margins(rows), "margins")
    share = F.col("supp") / max(n, 1)
    bits = -(share * F.log2(share) + F.when(share < 1, (1 - share) * F.log2(1 - share)).otherwise(0.0))
    if like is None:
        kept = counted.where(F.col("supp") >= min_support)
        if kept.count() > MOST_ITEMS:
            raise PoolTooLarge(f"more than {MOST_ITEMS} items have the minimum support {min_support}")
        got = kept.orderBy(F.desc("supp"), "item").toPandas()
        items, supports = got["item"].tolist(), got["supp"].to_numpy(np.int64)
    else:
        items = like.items
        own = {r["item"]: r["supp"] for r in counted.join(F.broadcast(rows.sparkSession.createDataFrame([(x,) for x in items], "item string")), "item", "left_semi").collect()} if items else {}
        supports = np.array([own.get(x, 0) for x in items], np.int64)
    of = counted.agg(F.count("*").alias("m"), F.sum(F.when(F.col("supp") < min_support, bits).otherwise(0.0)).alias("rest")).first()
    return Vertical(stored(_chunks(rows, items), "chunks"), items, supports, n, of["m"], of["rest"] or 0.0, min_support)


def _partners(level: np.ndarray) -> np.ndarray:
    """For each of the sorted sets, how many after it share all but the last item."""
    fresh = np.ones(len(level), bool)
    fresh[1:] = (level[1:, :-1] != level[:-1, :-1]).any(axis=1)
    starts = np.flatnonzero(fresh)
    ends = np.append(starts[1:], len(level))
    return np.repeat(ends, ends - starts) - np.arange(len(level)) - 1


def _joined(level: np.ndarray) -> Iterator[np.ndarray]:
    """Sets of one item more, from pairs of sorted sets that share all but the last item, JOINED_SETS or so at a time."""
    partners = _partners(level) if len(level) else np.zeros(0, np.int64)
    total = np.cumsum(partners)
    a = 0
    while a < len(level):
        b = max(a + 1, int(np.searchsorted(total, (total[a - 1] if a else 0) + JOINED_SETS, side="right")))
        own = partners[a:b]
        left = np.repeat(np.arange(a, b), own)
        right = left + 1 + np.arange(len(left)) - np.repeat(np.cumsum(own) - own, own)
        if len(left):
            yield np.concatenate((level[left], level[right, -1:]), axis=1)
        a = b


def _all_parts_frequent(sets: np.ndarray, level: np.ndarray, items: int) -> np.ndarray:
    """Which sets have only frequent subsets of one item less."""
    if sets.shape[1] < 3 or not len(sets) or items ** (sets.shape[1] - 1) >= 1 << 62:
        return np.ones(len(sets), bool)
    weigh = np.int64(items) ** np.arange(level.shape[1] - 1, -1, -1, dtype=np.int64)
    known, ok = level.astype(np.int64) @ weigh, np.ones(len(sets), bool)
    known.sort()
    for drop in range(sets.shape[1] - 2):
        part = np.delete(sets, drop, axis=1).astype(np.int64) @ weigh
        at = np.minimum(np.searchsorted(known, part), len(known) - 1)
        ok &= known[at] == part
    return ok


def frequent_sets(v: Vertical, max_size: int | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(itemsets of one size, supports) from size 2 on, level by level: joined from the level before, counted on the executors.

    Every itemset with the minimum support is there. More than MOST_SETS of them raise PoolTooLarge.
    """
    level, size, found = np.arange(len(v.items), dtype=np.int32)[:, None], 1, 0
    while len(level) > 1 and (max_size is None or size < max_size):
        kept, counts = [np.zeros((0, size + 1), np.int32)], [np.zeros(0, np.int64)]
        for sets in _joined(level):
            sets = sets[_all_parts_frequent(sets, level, len(v.items))]
            supports = v.supports_of(sets)
            keep = supports >= max(v.min_support, 1)
            kept.append(sets[keep])
            counts.append(supports[keep])
            found += int(keep.sum())
            if found > MOST_SETS:
                raise PoolTooLarge(f"more than {MOST_SETS} itemsets have the minimum support {v.min_support}; raise it, or limit their size")
        level, size = np.concatenate(kept), size + 1
        if len(level):
            yield level, np.concatenate(counts)


def mine(v: Vertical, max_size: int | None = None) -> DataFrame:
    """(items array<int>, supp): all itemsets of two items or more with the minimum support, stored."""
    spark, parts = v.chunks.sparkSession, []
    for sets, supports in frequent_sets(v, max_size):
        for a in range(0, len(sets), 1 << 20):
            part = sets[a : a + (1 << 20)]
            flat = pa.ListArray.from_arrays(pa.array(np.arange(len(part) + 1, dtype=np.int32) * part.shape[1]), pa.array(part.ravel()))
            parts.append(pa.table({"items": flat, "supp": pa.array(supports[a : a + (1 << 20)])}))
    if not parts:
        return spark.createDataFrame([], "items array<int>, supp long")
    return stored(spark.createDataFrame(pa.concat_tables(parts)), "pool")

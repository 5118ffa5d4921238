"""Bags of transactions over the items kept, counted with DataFrame aggregations and Arrow batches."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Items that fit a row's bit mask.
MASK_ITEMS = 62
#: Distinct rows of a wide bag that a task may have before there are more tasks than cores.
TASK_ROWS = 1 << 17


def margins(rows: DataFrame) -> DataFrame:
    """(item, supp) of (tid, items)."""
    return rows.select(F.explode("items").alias("item")).groupBy("item").agg(F.count("*").alias("supp"))


def pairs_of(items: str = "items") -> Column:
    """All pairs (a, b) of an array of sorted items, in the order of their places."""
    inner = lambda x, i: F.transform(F.slice(items, i + 2, F.size(items)), lambda y: F.struct(x.alias("a"), y.alias("b")))
    return F.flatten(F.transform(items, inner))


def pair_supports(rows: DataFrame) -> DataFrame:
    """(a, b, supp) of all pairs that occur: made within rows and summed before the shuffle, without a self-join."""
    return rows.select(F.explode(pairs_of()).alias("p")).groupBy(F.col("p.a").alias("a"), F.col("p.b").alias("b")).agg(F.count("*").alias("supp"))


def triple_supports(rows: DataFrame) -> DataFrame:
    """(a, b, c, supp) of all triples that occur."""
    third = lambda p: F.transform(F.filter("items", lambda z: z > p["b"]), lambda z: F.struct(p["a"].alias("a"), p["b"].alias("b"), z.alias("c")))
    exploded = rows.select(F.explode(F.flatten(F.transform(pairs_of(), third))).alias("p"))
    return exploded.groupBy(*(F.col(f"p.{k}").alias(k) for k in "abc")).agg(F.count("*").alias("supp"))


@dataclass
class Bag:
    """Distinct rows as bit masks over `items` (most frequent first), with counts."""

    rows: DataFrame
    items: list[str]
    supports: list[int]
    n: int

    @property
    def m(self) -> int:
        return len(self.items)

    @property
    def margins(self) -> list[float]:
        return [s / self.n for s in self.supports]

    def mask(self, *names: str) -> int:
        return sum(1 << self.items.index(x) for x in names)

    def names(self, mask: int) -> str:
        return "|".join(sorted(self.items[i] for i in range(self.m) if mask >> i & 1))

    def row_sizes(self) -> list[float]:
        got = {r["k"]: r["c"] for r in self.rows.groupBy(F.bit_count("mask").alias("k")).agg(F.sum("cnt").alias("c")).collect()}  # at most m + 1 rows
        return [got.get(j, 0) / self.n for j in range(self.m + 1)]

    def supports_of(self, sets: list[int]) -> dict[int, int]:
        """Supports of many itemsets in one pass: each Arrow batch of rows is held against all of them at once."""
        if not sets:
            return {}
        wanted = np.array(sets, np.int64)

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros(len(wanted), np.int64)
            for b in batches:
                mask, cnt = b.column(0).to_numpy(), b.column(1).to_numpy()
                for k in range(0, len(wanted), 256):
                    w = wanted[k : k + 256]
                    total[k : k + 256] += (((mask[:, None] & w) == w) * cnt[:, None]).sum(axis=0)
            some = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(total[some])], names=["k", "s"])

        got = self.rows.mapInArrow(run, "k long, s long").groupBy("k").agg(F.sum("s").alias("s")).collect()  # one row an itemset asked for
        found = {int(wanted[r["k"]]): r["s"] for r in got}
        return {x: found.get(x, 0) for x in sets}


def bag_of(rows: DataFrame, top: int = MASK_ITEMS, min_support: int = 1) -> Bag:
    """The bag of (tid, items) over its `top` most frequent items; rows without any of them count, too."""
    if top > MASK_ITEMS:
        raise ValueError(f"a bit mask holds {MASK_ITEMS} items")
    kept = margins(rows).where(F.col("supp") >= min_support).orderBy(F.desc("supp"), "item").limit(top).collect()  # at most 62 rows
    names = [r["item"] for r in kept]
    place = F.create_map(*(x for k, v in enumerate(names) for x in (F.lit(v), F.lit(1 << k).cast("long")))) if names else None
    mask = F.aggregate("items", F.lit(0).cast("long"), lambda acc, x: acc.bitwiseOR(F.coalesce(place[x], F.lit(0).cast("long")))) if names else F.lit(0).cast("long")
    bag = rows.select(mask.alias("mask")).groupBy("mask").agg(F.count("*").alias("cnt")).cache()
    n = bag.agg(F.sum("cnt")).first()[0] or 0
    return Bag(bag, names, [r["supp"] for r in kept], n)


@dataclass
class WideBag:
    """Distinct rows over any number of items (most frequent first): words of MASK_ITEMS bits each, with counts."""

    rows: DataFrame
    items: list[str]
    n: int

    @property
    def m(self) -> int:
        return len(self.items)

    def names(self, mask: int) -> str:
        return "|".join(sorted(self.items[i] for i in range(self.m) if mask >> i & 1))


def wide_bag_of(rows: DataFrame) -> WideBag:
    """The bag of (tid, items) over all items; rows without any item count, too. Rows are grouped before they are encoded."""
    items = F.coalesce("items", F.array().cast("array<string>"))
    kinds = rows.groupBy(items.alias("items")).agg(F.count("*").alias("cnt")).cache()
    # a null beside each row's items counts the rows in the same job
    cells = kinds.select(F.explode(F.concat(F.array_compact("items"), F.array(F.lit(None).cast("string")))).alias("item"), "cnt")
    got = {r["item"]: r for r in cells.groupBy("item").agg(F.sum("cnt").alias("supp"), F.count("*").alias("kinds")).collect()}  # a row an item
    distinct, n = (got[None]["kinds"], got.pop(None)["supp"]) if got else (0, 0)
    names = sorted(got, key=lambda x: (-got[x]["supp"], x))
    context = rows.sparkSession.sparkContext
    shared, words = context.broadcast(names), max(-(-len(names) // MASK_ITEMS), 1)
    columns = [*(f"w{j}" for j in range(words)), "cnt"]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = pa.array(shared.value, pa.string())
        for b in batches:
            at = pc.index_in(b.column(0).flatten(), value_set=known)
            own = at.is_valid().to_numpy(zero_copy_only=False)
            row = np.repeat(np.arange(b.num_rows), pc.list_value_length(b.column(0)).to_numpy())[own]
            at = at.fill_null(0).to_numpy()[own].astype(np.int64)
            out = np.zeros((words, b.num_rows), np.int64)
            np.bitwise_or.at(out, (at // MASK_ITEMS, row), np.int64(1) << at % MASK_ITEMS)
            yield pa.RecordBatch.from_arrays([*map(pa.array, out), b.column(1)], names=columns)

    tasks = max(context.defaultParallelism, -(-distinct // TASK_ROWS))
    encoded = kinds.coalesce(tasks).mapInArrow(run, ", ".join(f"{c} long" for c in columns)).cache()
    encoded.count()  # stored from now on
    kinds.unpersist()
    return WideBag(encoded, names, n)

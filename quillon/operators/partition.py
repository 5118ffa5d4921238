"""Items put into near-independent parts, so that a model can treat the parts one by one."""

from __future__ import annotations

import heapq
import itertools
from collections import defaultdict
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from .bag import MASK_ITEMS, Bag, WideBag


#: Items of a part up to which its kinds of rows are counted in an array, and the cells that all arrays of a task may have.
DENSE_ITEMS, DENSE_CELLS = 12, 1 << 22
#: Kinds of other parts that a task holds before it passes them on.
HELD_KINDS = 1 << 19
#: Merges whose unions are measured before it is their turn.
AHEAD = 16


def grouped(words: list[np.ndarray], cnt: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """The distinct rows of some words, with their counts."""
    order = np.lexsort(words)
    words = [w[order] for w in words]
    new = np.ones(len(order), bool)
    if len(order):
        new[1:] = np.any([w[1:] != w[:-1] for w in words], axis=0)
    at = np.flatnonzero(new)
    return [w[at] for w in words], np.add.reduceat(cnt[order], at) if len(at) else cnt[:0]


def record(k: int, words: list[np.ndarray], counts: np.ndarray) -> pa.RecordBatch:
    """A kind is the bytes of its words."""
    data, ends = np.stack(words, axis=1), np.arange(len(counts) + 1, dtype=np.int32) * (8 * len(words))
    kinds = pa.Array.from_buffers(pa.binary(), len(counts), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(data))])
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(counts), k)), kinds, pa.array(counts)], names=["k", "kind", "c"])


def part_bits(bag: Bag | WideBag, parts: list[int]) -> dict[int, float]:
    """Bits of the rows' items in each part (a bit mask): those of the rows, coded by their own frequencies, and
    half a logarithm of n for each kind of row beyond the first. One job for all parts; one number a part comes back.
    """
    if not parts:
        return {}
    items = [[i for i in range(w.bit_length()) if w >> i & 1] for w in parts]
    cells = np.cumsum([1 << len(x) if len(x) <= DENSE_ITEMS else 0 for x in items])
    in_array = {k for k, x in enumerate(items) if len(x) <= DENSE_ITEMS and cells[k] <= DENSE_CELLS}
    in_words = {k: [(j, x) for j in range(-(-w.bit_length() // MASK_ITEMS)) if (x := w >> j * MASK_ITEMS & (1 << MASK_ITEMS) - 1)] for k, w in enumerate(parts) if k not in in_array}

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dense = {k: np.zeros(1 << len(items[k]), np.int64) for k in in_array}
        sparse, held_kinds = defaultdict(list), 0

        def together() -> dict[int, tuple[list[np.ndarray], np.ndarray]]:
            return {k: grouped([np.concatenate(c) for c in zip(*(w for w, _ in got), strict=True)], np.concatenate([c for _, c in got])) for k, got in sparse.items()}

        for b in batches:
            *words, cnt = (c.to_numpy() for c in b.columns)
            held: dict[int, np.ndarray] = {}
            for k, total in dense.items():
                kind = np.zeros(len(cnt), np.int16)
                for place, i in enumerate(items[k]):
                    if i not in held:
                        held[i] = (words[i // MASK_ITEMS] >> i % MASK_ITEMS & 1).astype(np.int16)
                    kind += held[i] << place
                total += np.bincount(kind, cnt, len(total)).astype(np.int64)
            for k, masks in in_words.items():
                got = grouped([words[j] & x for j, x in masks], cnt)
                sparse[k].append(got)
                held_kinds += len(got[1])
                if held_kinds > HELD_KINDS:
                    merged = together()
                    held_kinds = sum(len(c) for _, c in merged.values())
                    sparse = defaultdict(list, {k: [x] for k, x in merged.items()})
                    if held_kinds > HELD_KINDS // 2:
                        yield from (record(k, *x) for k, x in merged.items())
                        sparse, held_kinds = defaultdict(list), 0
        yield from (record(k, *x) for k, x in together().items())
        for k, total in dense.items():
            some = np.flatnonzero(total)
            yield record(k, [some], total[some])

    # a part may have as many kinds as there are rows, so they are dealt by kind; decimals have the same sum in any order
    kinds = bag.rows.mapInArrow(run, "k long, kind binary, c long").groupBy("k", "kind").agg(F.sum("c").alias("c"))
    coded = (F.col("c") * F.log2(F.col("c") / bag.n)).cast("decimal(28,9)")
    got = kinds.groupBy("k").agg(F.sum(coded).cast("double").alias("s"), F.count("*").alias("kinds")).collect()  # a row a part
    return {parts[r["k"]]: -r["s"] + (r["kinds"] - 1) / 2 * float(np.log2(max(bag.n, 2))) for r in got}


def likely_unions(parts: list[int], bits: dict[int, float], cap: int | None) -> set[int]:
    """Unions that later steps need if the next AHEAD merges go as guessed; measured ahead they save jobs.

    A guess: what a union made meanwhile saves with a part is what its two parts save with it, together.
    """
    gains = {frozenset((a, b)): bits[a] + bits[b] - bits[a | b] for a, b in itertools.combinations(parts, 2) if a | b in bits}
    left, merged = set(parts), []
    while gains and len(merged) < AHEAD:
        best = max(gains, key=gains.__getitem__)
        if gains[best] <= 1e-9:
            break
        a, b = best
        left -= best
        for y in left:
            both = [gains.pop(frozenset((x, y)), 0.0) for x in best]
            if cap is None or (a | b | y).bit_count() <= cap:
                gains[frozenset((a | b, y))] = sum(both)
        del gains[best]
        left.add(a | b)
        merged.append(a | b)
    unions = {x | y for x in merged for y in [*parts, *merged] if not x & y and (cap is None or (x | y).bit_count() <= cap)}
    return unions - set(bits)


def partition_items(bag: Bag | WideBag, cap: int | None = None) -> tuple[list[int], float]:
    """(parts as bit masks, bits together): the two parts whose union saves most are merged, while any saves.

    A part may grow to all items; only a caller that gives a `cap` has parts of `cap` items at most. All unions of a
    step that were not looked at before are measured in one job, with those that the next steps likely need.
    """
    parts = [1 << i for i in range(bag.m)]
    bits = part_bits(bag, parts)
    saving: list[tuple[float, int, int]] = []  # a heap, with pairs of parts that are gone
    new = list(itertools.combinations(parts, 2))
    while True:
        new = [(a, b) for a, b in new if cap is None or (a | b).bit_count() <= cap]
        missing = {a | b for a, b in new} - set(bits)
        if missing:
            bits |= part_bits(bag, sorted(missing | likely_unions(parts, bits, cap)))
        for a, b in new:
            if (gain := bits[a] + bits[b] - bits[a | b]) > 1e-9:
                heapq.heappush(saving, (-gain, a, b))
        left = set(parts)
        while saving and not left.issuperset(saving[0][1:]):
            heapq.heappop(saving)
        if not saving:
            return sorted(parts), sum(bits[p] for p in parts)
        _, a, b = heapq.heappop(saving)
        parts = [p for p in parts if p not in (a, b)]
        new = [(p, a | b) for p in parts]
        parts.append(a | b)

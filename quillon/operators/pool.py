"""Greedy summaries from pools of any size: candidates are scored on the executors, the model is broadcast.

Column margins are known, so parts of the model without common items are independent, and each part has at
most `cap` items: every one of its 2^cap kinds of row is a block of its own, and the model is one vector a part.
"""

from __future__ import annotations

import time
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scores import penalty, score
from .vertical import Vertical, mine, vertical

CAP = 10


def entropy(p: np.ndarray) -> float:
    p = p[p > 0]
    return float(-(p * np.log2(p)).sum())


def coin_bits(f: np.ndarray) -> np.ndarray:
    """Entropy in bits of coins of these frequencies."""
    f = np.asarray(f, float)
    out = np.zeros_like(f)
    for x in (f, 1 - f):
        out -= np.where(x > 0, x * np.log2(np.where(x > 0, x, 1)), 0)
    return out


@dataclass
class Part:
    """The model of a few items: `rows` has the probability of each subset being exactly the row's, `within` of being in it."""

    items: tuple[int, ...]
    members: list[tuple[int, float, bool]]  # (mask over items, frequency, penalised)
    rows: np.ndarray = field(default=None)
    within: np.ndarray = field(default=None)
    sweeps: int = 0

    def fit(self, margins: np.ndarray, start: np.ndarray, tolerance: float = 1e-9, most_sweeps: int = 1000) -> "Part":
        """Cyclic rescaling of the rows: each constraint is met exactly in its turn, until all are within `tolerance`."""
        kinds = np.arange(1 << len(self.items))
        limits = [(m, f) for m, f, _ in self.members] + [(1 << k, float(margins[i])) for k, i in enumerate(self.items)]
        inside = [np.flatnonzero((kinds & m) == m) for m, _ in limits]
        p = start.copy()
        for self.sweeps in range(1, most_sweeps + 1):
            worst = 0.0
            for has, (_, fr) in zip(inside, limits, strict=True):
                now = float(p[has].sum())
                worst = max(worst, abs(now - fr))
                own = p[has] * (fr / now if now > 0 else 0.0)
                p *= (1 - fr) / (1 - now) if now < 1 else 0.0
                p[has] = own
            if worst <= tolerance:
                break
        self.rows = p / p.sum()
        self.within = self.rows.copy()
        for k in range(len(self.items)):
            at = self.within.reshape(-1, 2, 1 << k)
            at[:, 0] += at[:, 1]
        return self


def free_rows(probabilities) -> np.ndarray:
    """Probabilities of all subsets of independent items."""
    p = np.ones(1)
    for f in probabilities:
        p = np.concatenate((p * (1 - f), p * f))
    return p


@dataclass
class State:
    """The model of all items of a pool: parts, and free items with their frequencies."""

    n: int
    m: int
    margins: np.ndarray
    rest_bits: float
    parts: list[Part] = field(default_factory=list)
    k: int = 0
    total: int = 0
    sweeps: int = 0

    def part_of(self) -> tuple[np.ndarray, np.ndarray]:
        """For each item its part (-1: free) and its place there."""
        part, place = np.full(len(self.margins), -1, np.int32), np.zeros(len(self.margins), np.int64)
        for g, p in enumerate(self.parts):
            part[list(p.items)], place[list(p.items)] = g, np.arange(len(p.items))
        return part, place

    def bits(self) -> float:
        """Entropy of a row; the log-likelihood of the data is -n times it, as the model meets their frequencies."""
        touched = [i for p in self.parts for i in p.items]
        free = np.delete(self.margins, touched)
        return float(self.rest_bits + coin_bits(free).sum() + sum(entropy(p.rows) for p in self.parts))

    def score(self, kind: str) -> float:
        return score(kind, -self.n * self.bits(), self.k, self.total, self.n, self.m)

    def admissible(self, items, cap: int) -> bool:
        touched = [p for p in self.parts if set(p.items) & set(items)]
        return len(set(items).union(*(p.items for p in touched))) <= cap

    def with_set(self, items, frequency: float, penalised: bool = True, shift: float = 0.0) -> "State":
        """With one more itemset, fitted: its part and those it touches become one.

        `shift` mixes the frequency with that of rows drawn evenly, which keeps it off 0 and 1.
        """
        items = tuple(sorted(int(i) for i in items))
        frequency = (1 - shift) * frequency + shift * 2.0 ** -len(items)
        touched = [p for p in self.parts if set(p.items) & set(items)]
        fresh = sorted(set(items).difference(*(p.items for p in touched)))
        order = [i for p in touched for i in p.items] + fresh
        start = np.ones(1)
        for p in touched:
            start = np.outer(p.rows, start).ravel()
        start = np.outer(free_rows(self.margins[fresh]), start).ravel()
        where = {i: k for k, i in enumerate(order)}
        code = lambda ids: sum(1 << where[i] for i in ids)
        members = [(code(i for k, i in enumerate(p.items) if m >> k & 1), f, c) for p in touched for m, f, c in p.members]
        new = Part(tuple(order), [*members, (code(items), frequency, penalised)]).fit(self.margins, start)
        rest = [p for p in self.parts if not set(p.items) & set(items)]
        return State(self.n, self.m, self.margins, self.rest_bits, [*rest, new], self.k + penalised, self.total + len(items) * penalised, self.sweeps + new.sweeps)

    def estimates(self, values: np.ndarray, offsets: np.ndarray, cap: int = CAP) -> tuple[np.ndarray, np.ndarray]:
        """Probabilities of itemsets (values[offsets[k] : offsets[k + 1]]), and which may be added."""
        part, place = self.part_of()
        sizes, starts = np.diff(offsets), offsets[:-1]
        owner = part[values]
        est = np.multiply.reduceat(np.where(owner < 0, self.margins[values], 1.0), starts)
        union, known = sizes.astype(np.int64), np.zeros(len(sizes), bool)
        bit = np.left_shift(1, place[values])
        for g in np.unique(owner[owner >= 0]).tolist():
            code = np.add.reduceat(np.where(owner == g, bit, 0), starts)
            own = self.parts[g]
            est *= own.within[code]
            count = np.bitwise_count(code)
            union += np.where(code > 0, len(own.items) - count, 0)
            known |= (count == sizes) & np.isin(code, [m for m, _, _ in own.members])
        return est, (union <= cap) & ~known

    def estimate(self, items) -> float:
        ids = np.array(sorted(items), np.int64)
        return float(self.estimates(ids, np.array([0, len(ids)]))[0][0])


def kl2_array(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Divergence in bits of coins of frequencies x from coins of probabilities y."""
    out = np.zeros(len(x))
    with np.errstate(divide="ignore", invalid="ignore"):
        for a, b in ((x, y), (1 - x, 1 - y)):
            out += np.where(a > 0, a * np.log2(np.where(a > 0, a, 1) / np.maximum(b, 0)), 0)
    return out


def start_state(v: Vertical, known: Iterable[tuple[Iterable[int], float]] = ()) -> State:
    """Column margins, and any itemsets that are known besides: in the model, not in the score's penalty."""
    state = State(v.n, v.m, v.frequencies, v.rest_bits)
    for items, frequency in known:
        state = state.with_set(items, frequency, penalised=False)
    return state


def rule(items_if: Iterable[int], items_then: Iterable[int], support_if: float, confidence: float) -> list[tuple[tuple[int, ...], float]]:
    """A known rule as the two itemsets whose frequencies state it."""
    both = tuple(sorted({*items_if, *items_then}))
    left = tuple(sorted(items_if))
    return [*([(left, support_if)] if len(left) > 1 else []), (both, support_if * confidence)]


BEST = "key double, size int, items array<int>, supp long, est double, h double"


def scored(pool: DataFrame, state: State, kind: str, cap: int = CAP) -> DataFrame:
    """(items, supp, est, h) of all candidates of a pool, scored on the executors."""
    shared = pool.sparkSession.sparkContext.broadcast(state)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                est, h, _ = _judged(b, shared.value, kind, cap)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(est), pa.array(h)], names=["items", "supp", "est", "h"])

    return pool.select("items", "supp").mapInArrow(run, "items array<int>, supp long, est double, h double")


def _judged(b: pa.RecordBatch, state: State, kind: str, cap: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    column = b.column(0)
    values, sizes = column.flatten().to_numpy(), column.value_lengths().to_numpy()
    est, ok = state.estimates(values, np.concatenate(([0], np.cumsum(sizes))), cap)
    cost = np.array([penalty(kind, s, state.n, state.m) for s in range(int(sizes.max()) + 1)])
    return est, kl2_array(b.column(1).to_numpy() / state.n, est) - cost[sizes], ok


def best_of(pool: DataFrame, state: State, kind: str, cap: int = CAP) -> tuple[tuple[int, ...], int, float, float] | None:
    """(items, support, estimate, h) of the candidate with the largest h above 0; ties by fewer, then smaller items.

    Every batch gives its own best, so that the last sort has one row a batch.
    """
    shared = pool.sparkSession.sparkContext.broadcast(state)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = None
        for b in batches:
            if not b.num_rows:
                continue
            est, h, ok = _judged(b, shared.value, kind, cap)
            key = np.where(ok, np.round(h, 12), -np.inf)
            top = float(key.max())
            if top > 0:
                for k in np.flatnonzero(key == top).tolist():
                    items = b.column(0)[k].as_py()
                    rank = (-top, len(items), items)
                    if best is None or rank < best[0]:
                        best = (rank, b.column(1)[k].as_py(), float(est[k]), float(h[k]))
        if best:
            (key, size, items), supp, est, h = best
            yield pa.RecordBatch.from_pylist([{"key": -key, "size": size, "items": items, "supp": supp, "est": est, "h": h}], schema=pa.schema([("key", pa.float64()), ("size", pa.int32()), ("items", pa.list_(pa.int32())), ("supp", pa.int64()), ("est", pa.float64()), ("h", pa.float64())]))

    got = pool.select("items", "supp").mapInArrow(run, BEST).orderBy(F.desc("key"), "size", "items").limit(1).collect()
    shared.unpersist()
    return (tuple(got[0]["items"]), got[0]["supp"], got[0]["est"], got[0]["h"]) if got else None


@dataclass
class PoolPick:
    items: tuple[int, ...]
    support: int
    estimate: float
    surprise: float
    score: float
    seconds: float


@dataclass
class PoolSummary:
    vertical: Vertical
    state: State
    kind: str
    background_score: float
    picks: list[PoolPick] = field(default_factory=list)
    finished: bool = True
    seconds: float = 0.0

    @property
    def score(self) -> float:
        return self.picks[-1].score if self.picks else self.background_score

    def curve(self) -> list[float]:
        return [self.background_score, *(p.score for p in self.picks)]


def summarize_pool(v: Vertical, pool: DataFrame, kind: str = "mdl", k: int | None = None, cap: int = CAP, known=(), time_limit: float | None = None, shift: float = 0.0) -> PoolSummary:
    """The greedy list over a pool (items, supp): best h, refit, while the score falls, there are fewer than `k`
    and `time_limit` seconds are not over; past it the list so far comes back, not finished.
    """
    began, state = time.monotonic(), start_state(v, known)
    out = PoolSummary(v, state, kind, state.score(kind))
    while k is None or len(out.picks) < k:
        if time_limit is not None and time.monotonic() - began > time_limit:
            out.finished = False
            break
        found = best_of(pool, state, kind, cap)
        if not found:
            break
        items, supp, est, h = found
        new = state.with_set(items, supp / v.n, shift=shift)
        value = new.score(kind)
        if value >= out.score:
            break
        state = new
        out.picks.append(PoolPick(items, supp, est, h, value, time.monotonic() - began))
    out.state, out.seconds = state, time.monotonic() - began
    return out


def summarize_rows(rows: DataFrame, kind: str = "mdl", min_support: int = 1, max_size: int | None = None, **more) -> PoolSummary:
    """Mines all itemsets of (tid, items) above a support and makes the list from them."""
    v = vertical(rows, min_support)
    return summarize_pool(v, mine(v, max_size), kind, **more)


def best_lazy(v: Vertical, state: State, kind: str = "mdl", max_size: int = 4, cap: int = CAP, seed: float | None = 1 / 8) -> tuple[tuple | None, dict]:
    """The most surprising itemset by branch and bound in rounds; supports are counted only for what is visited.

    A round has the itemsets of one size: their children and, for the bound, each child with all that may still
    come to it, are counted in one job over the chunks; children are scored on the executors against the best
    found in all rounds before, and those whose bound stays below it go. The frontier is a stored table. With
    `seed`, the best pair of that share of the chunks, counted exactly, is the first one to beat.
    """
    from ..sources.files import stored

    spark, stats = v.chunks.sparkSession, {"visited": 0, "pruned": 0, "rounds": 0}
    best = None

    def better(found):
        nonlocal best
        if found and (best is None or (-round(found[3], 12), len(found[0]), found[0]) < (-round(best[3], 12), len(best[0]), best[0])):
            best = found

    def table(sets: np.ndarray, supports: np.ndarray) -> DataFrame:
        flat = pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1, dtype=np.int32) * sets.shape[1]), pa.array(sets.ravel().astype(np.int32)))
        return spark.createDataFrame(pa.table({"items": flat, "supp": pa.array(supports)}))

    many = len(v.items)
    i, j = np.triu_indices(many, 1)
    pairs = np.stack((i, j), axis=1).astype(np.int32)
    if seed and len(pairs):
        part = Vertical(v.chunks.where(F.pmod(F.xxhash64("bits"), F.lit(max(1, round(1 / seed)))) == 0), v.items, v.supports, v.n, v.m, v.rest_bits, 1)
        counts = part.supports_of(pairs)
        size = part.chunks.agg(F.sum("n")).first()[0] or 0
        if size:
            rough = State(size, v.m, v.frequencies, v.rest_bits, state.parts)
            first = best_of(table(pairs, counts), rough, kind, cap)
            if first:
                exact = v.supports_of(np.array([first[0]], np.int32))
                if exact[0] >= v.min_support:
                    better(best_of(table(np.array([first[0]], np.int32), exact), state, kind, cap))
    frontier = stored(spark.createDataFrame(pa.table({"items": pa.array([[k] for k in range(many)], pa.list_(pa.int32()))})), "frontier") if many else None
    for size in range(2, max_size + 1):
        if frontier is None or frontier.isEmpty():
            break
        stats["rounds"] += 1
        children = frontier.withColumn("j", F.explode(F.sequence(F.element_at("items", -1) + 1, F.lit(many)))).where(F.col("j") < many).select(F.concat("items", F.array(F.col("j").cast("int"))).alias("items"))
        next_level = []
        sets = children.orderBy("items").toArrow().column("items").combine_chunks()
        sets = sets.flatten().to_numpy().reshape(-1, size) if len(sets) else np.zeros((0, size), np.int32)
        supports = v.supports_of(sets)
        keep = supports >= max(v.min_support, 1)
        sets, supports = sets[keep], supports[keep]
        stats["visited"] += len(keep)
        if not len(sets):
            break
        better(best_of(table(sets, supports), state, kind, cap))
        if size == max_size:
            break
        shared = spark.sparkContext.broadcast((state, best[3] if best else 0.0))
        order = np.arange(many)

        def bound(batches, shared=shared, order=order, kind=kind):
            from ..functions.scores import kl2_value

            for b in batches:
                own, bar = shared.value
                out = []
                for items, supp in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    tail = order[items[-1] + 1 :].tolist()
                    full = own.estimate([*items, *tail]) if tail else own.estimate(items)
                    fr, est = supp / own.n, own.estimate(items)
                    # no superset is rarer than 0 rows, nor likelier than this one
                    top = max(kl2_value(fr, full), kl2_value(0.0, est)) - penalty(kind, len(items), own.n, own.m)
                    if tail and top + 1e-12 >= bar:
                        out.append(items)
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.list_(pa.int32()))], names=["items"])

        frontier = stored(table(sets, supports).mapInArrow(bound, "items array<int>"), "frontier")
        stats["pruned"] += len(sets) - frontier.count()
    return best, stats

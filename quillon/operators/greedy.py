"""Greedy summaries: the most surprising itemset, again and again, while the score falls."""

from __future__ import annotations

import itertools
import time
from dataclasses import dataclass, field

from ..functions.scores import branch_bound, kl2_value, penalty, score
from .bag import Bag
from .blocks import admissible
from .maxent import MaxEntModel


@dataclass
class Pick:
    items: int
    frequency: float
    estimate: float
    surprise: float
    score: float


@dataclass
class Summary:
    bag: Bag
    model: MaxEntModel
    kind: str
    background_score: float
    picks: list[Pick] = field(default_factory=list)
    finished: bool = True
    nodes: int = 0
    pruned: int = 0
    counted: int = 0
    sweeps: int = 0

    @property
    def score(self) -> float:
        return self.picks[-1].score if self.picks else self.background_score

    def curve(self) -> list[float]:
        return [self.background_score, *(p.score for p in self.picks)]


def model_score(bag: Bag, model: MaxEntModel, kind: str) -> float:
    total = sum(x.bit_count() for x in model.members)
    return score(kind, model.log_likelihood(bag.n), len(model.members), total, bag.n, bag.m)


def order_key(h: float, items: int) -> tuple:
    """Larger h first, then fewer items, then lower item places; h to 12 places, so that rounding does not decide."""
    return (-round(h, 12), items.bit_count(), [i for i in range(items.bit_length()) if items >> i & 1])


def small_sets(m: int, size: int) -> list[int]:
    return [sum(1 << i for i in c) for k in range(2, size + 1) for c in itertools.combinations(range(m), k)]


def background(bag: Bag, kind: str = "columns") -> MaxEntModel:
    """Model of what is known beforehand: none, columns, rows, or rows and columns."""
    return MaxEntModel(bag.m, margins=bag.margins if "columns" in kind else None, row_sizes=bag.row_sizes() if "rows" in kind else None).fit()


def best_of_pool(model: MaxEntModel, pool: dict[int, float], kind: str, n: float, cap: int) -> tuple[int, float, float] | None:
    """(itemset, estimate, h) with the largest h = surprise less penalty of a pool with known frequencies."""
    best = None
    for x, fr in pool.items():
        if x in model.members or not admissible(model.members, x, cap):
            continue
        est = model.query(x)
        h = kl2_value(fr, est) - penalty(kind, x.bit_count(), n, model.m)
        if best is None or order_key(h, x) < best[0]:
            best = (order_key(h, x), x, est, h)
    return None if best is None or best[3] <= 0 else best[1:]


def best_by_gain(bag: Bag, model: MaxEntModel, pool: dict[int, float], kind: str, cap: int) -> tuple[int, float, float] | None:
    """The same by the exact gain: one refit a candidate."""
    best, now = None, model_score(bag, model, kind)
    for x, fr in pool.items():
        if x in model.members or not admissible(model.members, x, cap):
            continue
        gain = (now - model_score(bag, model.with_set(x, fr), kind)) / bag.n
        if best is None or order_key(gain, x) < best[0]:
            best = (order_key(gain, x), x, model.query(x), gain)
    return None if best is None or best[3] <= 0 else best[1:]


def find_best(bag: Bag, model: MaxEntModel, kind: str, cap: int, max_size: int, min_support: int, memo: dict[int, int], stats: Summary | None = None, root: int = 0) -> tuple[int, float, float] | None:
    """Branch and bound over all itemsets, in rounds: each counts the supports of a whole frontier in one job.

    A node is an itemset and the items that may still come to it, rarest first. Its subtree is cut if no
    frequency between that of the node and that of the node with all its items, with any estimate between
    theirs, is as surprising as the best found. Supports are kept in `memo`, as they never change.
    """
    best: tuple | None = None
    order = sorted(range(bag.m), key=lambda i: (bag.supports[i], -i))
    frontier = [(root, [i for i in order if not root >> i & 1])]
    while frontier:
        children = []
        for x, tail in frontier:
            for k, i in enumerate(tail):
                new = x | 1 << i
                if new.bit_count() <= max_size and admissible(model.members, new, cap):
                    children.append((new, [j for j in tail[k + 1 :] if admissible(model.members, new | 1 << j, cap)]))
        full = {x: x | sum(1 << j for j in tail) for x, tail in children}
        missing = [s for s in dict.fromkeys([*full, *full.values()]) if s not in memo]
        memo |= bag.supports_of(missing)
        if stats:
            stats.nodes += len(children)
            stats.counted += len(missing)
        scored = []
        for x, tail in children:
            if memo[x] < min_support:
                continue
            fr, est = memo[x] / bag.n, model.query(x)
            r = penalty(kind, x.bit_count(), bag.n, bag.m)
            if x.bit_count() >= 2 and x not in model.members:
                h = kl2_value(fr, est) - r
                if best is None or order_key(h, x) < best[0]:
                    best = (order_key(h, x), x, est, h)
            scored.append((x, tail, fr, est, r))
        frontier = []
        for x, tail, fr, est, r in scored:
            if not tail or x.bit_count() >= max_size:
                continue
            bound = branch_bound(fr, est, memo[full[x]] / bag.n, model.query(full[x])) - r
            if best is None or bound + 1e-12 >= best[3]:
                frontier.append((x, tail))
            elif stats:
                stats.pruned += 1
    return None if best is None or best[3] <= 0 else best[1:]


def summarize(bag: Bag, kind: str = "mdl", known: str = "columns", k: int | None = None, max_size: int = 4, min_support: int = 1, cap: int = 10, supports: str = "cached", pick: str = "heuristic", pool: dict[int, int] | None = None, time_limit: float | None = None, start: MaxEntModel | None = None) -> Summary:
    """A list of itemsets that with what is known tells most of the bag.

    supports: `cached` counts all itemsets of up to `max_size` (or takes `pool`) once and scores the pool in
    each step; `lazy` counts what the branch-and-bound search visits. pick: `heuristic` or `exact` gain. The
    last itemset is taken back if it did not lower the score. At `time_limit` seconds the list so far is given,
    not finished.
    """
    began, model = time.monotonic(), start or background(bag, known)
    out = Summary(bag, model, kind, model_score(bag, model, kind))
    memo: dict[int, int] = {}
    if supports == "cached":
        counts = pool if pool is not None else bag.supports_of(small_sets(bag.m, max_size))
        frequencies = {x: c / bag.n for x, c in counts.items() if c >= min_support}
        out.counted = len(counts)
    while k is None or len(out.picks) < k:
        if time_limit is not None and time.monotonic() - began > time_limit:
            out.finished = False
            break
        if supports == "lazy":
            found = find_best(bag, out.model, kind, cap, max_size, min_support, memo, out)
            frequencies = {found[0]: memo[found[0]] / bag.n} if found else {}
        elif pick == "exact":
            found = best_by_gain(bag, out.model, frequencies, kind, cap)
        else:
            found = best_of_pool(out.model, frequencies, kind, bag.n, cap)
        if not found:
            break
        x, est, h = found
        new = out.model.with_set(x, frequencies[x])
        out.sweeps += new.sweeps
        value = model_score(bag, new, kind)
        if value >= out.score:
            break
        out.model = new
        out.picks.append(Pick(x, frequencies[x], est, h, value))
    return out


def optimal_subset(bag: Bag, pool: dict[int, float], kind: str, known: str = "columns", cap: int = 10) -> tuple[float, list[int]]:
    """The best subset of a tiny pool by trying all of them: what greedy lists are held against."""
    best = None
    for size in range(len(pool) + 1):
        for chosen in itertools.combinations(pool, size):
            members: list[int] = []
            if all(admissible(members, x, cap) and not members.append(x) for x in chosen):
                start = background(bag, known)
                model = MaxEntModel(bag.m, list(chosen), [pool[x] for x in chosen], start.margins, start.row_sizes).fit()
                value = model_score(bag, model, kind)
                if best is None or value < best[0] - 1e-9:
                    best = (value, list(chosen))
    return best


class Session:
    """Interactive use: add, remove, extend; supports already counted are kept."""

    def __init__(self, bag: Bag, kind: str = "mdl", known: str = "columns", max_size: int = 4):
        self.bag, self.kind, self.max_size, self.memo = bag, kind, max_size, {}
        self.model = background(bag, known)

    def score(self) -> float:
        return model_score(self.bag, self.model, self.kind)

    def add(self, items: int) -> float:
        self.memo |= self.bag.supports_of([items]) if items not in self.memo else {}
        self.model = self.model.with_set(items, self.memo[items] / self.bag.n)
        return self.score()

    def remove(self, items: int) -> float:
        self.model = self.model.without_set(items)
        return self.score()

    def extend(self, k: int = 1, cap: int = 10) -> list[int]:
        added = []
        for _ in range(k):
            found = find_best(self.bag, self.model, self.kind, cap, self.max_size, 1, self.memo)
            if not found:
                break
            self.add(found[0])
            added.append(found[0])
        return added

    def specialize(self, items: int, cap: int = 10) -> tuple[int, float, float] | None:
        """The most surprising superset of an itemset."""
        return find_best(self.bag, self.model, self.kind, cap, self.max_size, 1, self.memo, root=items)

"""Maximum-entropy model of a collection of itemsets with frequencies, and what is known besides.

The model's size follows the collection, not the rows: the driver holds it, executors get it by broadcast.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from .blocks import Mass, closed_blocks, groups, independent_mass, quick_sizes
from .sizes import size_distribution


class _Plan:
    """Blocks of a collection as arrays, with the subtractions that make their masses exact; see blocks.quick_sizes."""

    def __init__(self, members: list[int]):
        unions = np.zeros(1, np.int64)
        for x in members:
            unions = np.unique(np.concatenate((unions, unions | x)))
        sets = np.array(members, np.int64)
        powers = 1 << np.arange(len(members), dtype=np.int64)
        sign = lambda u: ((u[:, None] & sets) == sets) @ powers
        self.blocks, first = np.unique(sign(unions), return_index=True)
        self.unions = unions[first]
        self.inside = (self.blocks[:, None] & powers) != 0
        self.steps = []
        for k, x in enumerate(members):
            rest = np.flatnonzero(~self.inside[:, k])
            to = sign(self.unions[rest] | x)
            ok = (to ^ self.blocks[rest]) & (powers[k] - 1) == 0
            self.steps.append((rest[ok], np.searchsorted(self.blocks, to[ok])))

    def exact(self, cumulative: np.ndarray) -> np.ndarray:
        sizes = cumulative.copy()
        for rest, to in self.steps:
            sizes[rest] -= sizes[to]
        return sizes


@dataclass
class _Part:
    """One item-disjoint part of the collection, with the plans of the collection and of its queries."""

    which: list[int]
    members: list[int]
    items: int
    plans: dict[int, _Plan] = field(default_factory=dict)

    def plan(self, query: int) -> _Plan:
        query = 0 if query in self.members else query
        if query not in self.plans:
            if len(self.plans) > 4096:
                self.plans.clear()
            self.plans[query] = _Plan([*self.members, query] if query else self.members)
        return self.plans[query]


class MaxEntModel:
    """p(row) = norm * product of multipliers of the itemsets inside it * product of odds of its items * weight of its size.

    `margins`: item frequencies, or None if nothing is known of single items. `row_sizes`: frequencies
    of 0 to m items in a row, or None; with `bins`, the bin of each size, only those of the bins are known, and a
    weight belongs to a bin. Frequencies of 0 and 1 are limits and are met exactly.
    """

    def __init__(self, m: int, members: list[int] | None = None, frequencies: list[float] | None = None, margins: list[float] | None = None, row_sizes: list[float] | None = None, bins: list[int] | None = None):
        self.m = m
        self.members = list(members or [])
        self.frequencies = list(frequencies or [])
        self.margins = None if margins is None else list(margins)
        self.row_sizes = None if row_sizes is None else np.asarray(row_sizes, float)
        self.bins = None if bins is None or row_sizes is None else np.asarray(bins, np.int64)
        self.mult = [1.0] * len(self.members)
        self.probability = [0.5] * m if margins is None else list(margins)  # of the independent part
        self.weights = np.ones(m + 1)
        self.sweeps = 0
        self._split()

    def _split(self) -> None:
        self.parts = [_Part(ks, [self.members[k] for k in ks], _union(self.members[k] for k in ks)) for ks in groups(self.members)]
        self.touched = _union(self.members)

    # masses: arrays over the number of items if row sizes are known, else of length 1

    def _mass(self, items: int) -> Mass:
        """Of the items of one part: mass by number of items of its rows that contain given ones."""
        own = _bits(items)

        def mass(inside: int) -> np.ndarray:
            out = np.ones(1)
            for i in own:
                p = self.probability[i]
                out = np.append(0.0, out * p) if inside >> i & 1 else np.append(out * (1 - p), 0.0) + np.append(0.0, out * p)
            return out

        return mass

    def _part_mass(self, part: _Part, query: int = 0) -> np.ndarray:
        """Weighted mass of the part's rows that contain `query` (items of the part)."""
        plan = part.plan(query)
        if self.row_sizes is None:
            own = _bits(part.items)
            has = (plan.unions[:, None] >> np.array(own)) & 1 == 1
            cumulative = np.where(has, np.array([self.probability[i] for i in own]), 1.0).prod(axis=1)[:, None]
        else:
            mass = self._mass(part.items)
            cumulative = np.stack([mass(int(u)) for u in plan.unions])
        sizes = plan.exact(cumulative)
        k = len(part.members)
        weight = np.where(plan.inside[:, :k], np.array([self.mult[j] for j in part.which]), 1.0).prod(axis=1)
        if query:
            at = part.members.index(query) if query in part.members else k
            weight = weight * plan.inside[:, at]
        return (weight[:, None] * sizes).sum(axis=0)

    def _free_mass(self, query: int) -> np.ndarray:
        free = [i for i in range(self.m) if not self.touched >> i & 1]
        if self.row_sizes is None:
            return np.array([np.prod([self.probability[i] for i in free if query >> i & 1])])
        out = size_distribution([self.probability[i] for i in free if not query >> i & 1])
        for i in free:
            if query >> i & 1:
                out = np.append(0.0, out * self.probability[i])
        return out

    def query(self, items: int) -> float:
        """Probability that a row contains the items."""
        if self.row_sizes is None:
            out = float(self._free_mass(items)[0])
            for part in self.parts:
                if part.items & items:
                    out *= float(self._part_mass(part, part.items & items)[0] / self._part_mass(part)[0])
            return out
        inside, every = self._free_mass(items), self._free_mass(0)
        for part in self.parts:
            inside = np.convolve(inside, self._part_mass(part, part.items & items))
            every = np.convolve(every, self._part_mass(part))
        return float((inside * self.weights).sum() / (every * self.weights).sum())

    def size_probabilities(self) -> np.ndarray:
        every = self._free_mass(0)
        for part in self.parts:
            every = np.convolve(every, self._part_mass(part))
        every = every * self.weights
        return every / every.sum()

    def total(self) -> float:
        """What the weights of all rows, under the independent part, add up to; 1 / norm."""
        every = self._free_mass(0)
        for part in self.parts:
            every = np.convolve(every, self._part_mass(part))
        return float((every * self.weights).sum() if self.row_sizes is not None else every[0])

    def fit(self, tolerance: float = 1e-10, most_sweeps: int = 2000) -> "MaxEntModel":
        """Cyclic rescaling: one constraint at a time is met exactly, until all are within `tolerance`."""
        for sweep in range(1, most_sweeps + 1):
            worst = 0.0
            for k, (x, fr) in enumerate(zip(self.members, self.frequencies, strict=True)):
                now = self.query(x)
                worst = max(worst, abs(now - fr))
                self.mult[k] *= _ratio(fr, now)
            if self.margins is not None:
                for i in range(self.m):
                    if self.row_sizes is None and not self.touched >> i & 1:
                        continue  # free items keep their frequency
                    now, fr = self.query(1 << i), self.margins[i]
                    worst = max(worst, abs(now - fr))
                    p = self.probability[i]
                    if 0 < p < 1:
                        odds = p / (1 - p) * _ratio(fr, now)
                        self.probability[i] = odds / (1 + odds)
            if self.row_sizes is not None:
                now, want = self.size_probabilities(), self.row_sizes
                if self.bins is not None:
                    now, want = (np.bincount(self.bins, x)[self.bins] for x in (now, want))
                worst = max(worst, float(np.abs(now - want).max()))
                self.weights = np.where(now > 0, self.weights * want / np.where(now > 0, now, 1), 0.0)
            self.sweeps = sweep
            if worst <= tolerance or not self.members and self.row_sizes is None:
                break
        return self

    def row_probability(self, row: int) -> float:
        out = self.weights[row.bit_count()] / self.total()
        for i, p in enumerate(self.probability):
            out *= p if row >> i & 1 else 1 - p
        for x, u in zip(self.members, self.mult, strict=True):
            if row & x == x:
                out *= u
        return float(out)

    def log_likelihood(self, n: float) -> float:
        """Bits of n rows whose frequencies are the model's own, from the parameters alone."""
        out = -np.log2(self.total())
        for fr, u in zip(self.frequencies, self.mult, strict=True):
            out += fr * np.log2(u) if fr > 0 else 0.0
        for i, p in enumerate(self.probability):
            fr = 0.5 if self.margins is None else self.margins[i]
            if self.margins is None:
                out -= 1.0  # p = 1/2 for either value
            else:
                out += (fr * np.log2(p) if fr > 0 else 0.0) + ((1 - fr) * np.log2(1 - p) if fr < 1 else 0.0)
        if self.row_sizes is not None:
            out += float(sum(q * np.log2(w) for q, w in zip(self.row_sizes, self.weights, strict=True) if q > 0))
        return float(n * out)

    def entropy(self) -> float:
        """Bits; equal to minus the log-likelihood of one row with the model's own frequencies."""
        return -self.log_likelihood(1)

    def with_set(self, items: int, frequency: float) -> "MaxEntModel":
        """A fitted model with one more itemset, started from this one's parameters."""
        new = MaxEntModel(self.m, [*self.members, items], [*self.frequencies, frequency], self.margins, self.row_sizes, self.bins)
        new.mult, new.probability, new.weights = [*self.mult, 1.0], list(self.probability), self.weights.copy()
        return new.fit()

    def without_set(self, items: int) -> "MaxEntModel":
        keep = [k for k, x in enumerate(self.members) if x != items]
        return MaxEntModel(self.m, [self.members[k] for k in keep], [self.frequencies[k] for k in keep], self.margins, self.row_sizes, self.bins).fit()

    def blocks(self) -> list[tuple[int, int, float]]:
        """(part, block over the part's members, probability) of all blocks of each part, without row sizes."""
        out = []
        for g, part in enumerate(self.parts):
            found, mass = closed_blocks(part.members), independent_mass(self.probability)
            sizes, _ = quick_sizes(part.members, found, {b: mass(u) for b, u in found.items()})
            total = self._part_mass(part)[0]
            out += [(g, b, float(s[0] * np.prod([self.mult[k] for j, k in enumerate(part.which) if b >> j & 1]) / total)) for b, s in sorted(sizes.items())]
        return out


def _ratio(fr: float, now: float) -> float:
    """What to scale a weight by so that its event gets frequency `fr` instead of `now`."""
    if fr <= 0:
        return 0.0
    if fr >= 1 or now <= 0 or now >= 1:
        return 1.0 if now >= 1 or now <= 0 else fr * (1 - now) / (now * max(1 - fr, 1e-15))
    return fr * (1 - now) / (now * (1 - fr))


def _union(sets) -> int:
    out = 0
    for x in sets:
        out |= x
    return out


def _bits(x: int) -> list[int]:
    return [i for i in range(x.bit_length()) if x >> i & 1]


def shift(frequency: float, size: int, eps: float) -> float:
    """The frequency mixed with that of rows drawn evenly, which keeps it off 0 and 1."""
    return (1 - eps) * frequency + eps * 2.0**-size

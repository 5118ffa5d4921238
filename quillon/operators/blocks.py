"""Blocks: rows that contain the same members of a collection of itemsets, and how much mass each has.

Itemsets and rows are bit masks over items; a block is a bit mask over the collection's members. All
sizes are masses under independent items (2^-m a row if nothing is known), so no count overflows.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

Mass = Callable[[int], np.ndarray]


def signature(row: int, members: list[int]) -> int:
    """Which members the row contains."""
    return sum(1 << k for k, x in enumerate(members) if row & x == x)


def closed_blocks(members: list[int]) -> dict[int, int]:
    """Nonempty blocks as {block: union of its members}; each is the set of all members inside a union of some."""
    unions = {0}
    for x in members:
        unions |= {u | x for u in unions}
    return {signature(u, members): u for u in unions}


def closure(block: int, members: list[int]) -> int:
    """All members inside the union of the block's members."""
    return signature(union(block, members), members)


def closure_after(block: int, members: list[int], j: int) -> int:
    """The block, and the members from place `j` on that lie inside the union of its members."""
    return block | closure(block, members) >> j << j


def union(block: int, members: list[int]) -> int:
    out = 0
    for k, x in enumerate(members):
        if block >> k & 1:
            out |= x
    return out


def independent_mass(probabilities: list[float]) -> Mass:
    """Mass of all rows that contain the given items, items independent."""

    def mass(items: int) -> np.ndarray:
        return np.array([np.prod([p for i, p in enumerate(probabilities) if items >> i & 1])])

    return mass


def cumulative(blocks: dict[int, int], mass: Mass) -> dict[int, np.ndarray]:
    """Mass of the rows that contain a block's members, whatever else they contain."""
    return {b: mass(u) for b, u in blocks.items()}


def quick_sizes(members: list[int], blocks: dict[int, int], sizes: dict[int, np.ndarray]) -> tuple[dict[int, np.ndarray], int]:
    """Exact masses, and how many subtractions that took.

    After step k a block's mass is that of the rows with exactly its members among the first k and at
    least its other ones. A step takes from each block without member k the block that adding it leads
    to, if that adds no earlier member: then no such row exists.
    """
    sizes, steps = dict(sizes), 0
    for k, x in enumerate(members):
        early = (1 << k) - 1
        for b, u in blocks.items():
            if not b >> k & 1:
                to = signature(u | x, members)
                if to & early == b & early:
                    sizes[b] = sizes[b] - sizes[to]
                    steps += 1
    return sizes, steps


def quadratic_sizes(blocks: dict[int, int], sizes: dict[int, np.ndarray]) -> tuple[dict[int, np.ndarray], int]:
    """The same by taking from each block all larger ones, largest first."""
    out: dict[int, np.ndarray] = {}
    steps = 0
    for b in sorted(blocks, key=lambda b: -b.bit_count()):
        out[b] = sizes[b]
        for c in out:
            if c != b and c & b == b:
                out[b] = out[b] - out[c]
                steps += 1
    return out, steps


def groups(members: list[int]) -> list[list[int]]:
    """Positions of the members, split into parts that share no item."""
    parts: list[tuple[int, list[int]]] = []
    for k, x in enumerate(members):
        items, own, rest = x, [k], []
        for used, ks in parts:
            if used & items:
                items, own = items | used, ks + own
            else:
                rest.append((used, ks))
        parts = [*rest, (items, sorted(own))]
    return sorted(ks for _, ks in parts)


def admissible(members: list[int], new: int, cap: int, most_members: int = 60) -> bool:
    """Whether `new` and all parts that it touches have `cap` items and fewer than `most_members` members together at most."""
    total, count = new, 0
    for part in groups(members):
        items = 0
        for k in part:
            items |= members[k]
        if items & new:
            total, count = total | items, count + len(part)
    return total.bit_count() <= cap and count < most_members

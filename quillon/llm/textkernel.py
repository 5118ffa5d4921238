"""Vectorised hashing of the words of many texts at once, in pieces that fit a processor's cache."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np

U = np.uint64
#: Odd multiplier of the rolling hash, and its inverse modulo 2^64.
_R = 0x9E3779B97F4A7C15
_R_INV = pow(_R, -1, 1 << 64)
#: Odd multipliers for the words of a shingle.
_MULS = np.array([0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3], U)
#: Bytes that are hashed together.
PIECE_BYTES = 1 << 16
#: Bytes of a word up to which the rolling hash is used; longer ones get a cryptographic hash, as words that
#: collide under a rolling hash can be built once they are long.
ROLLING_BYTES = 64

#: True for the white space that ends a word: 0x20 and 0x09-0x0D.
SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
#: True for what ends a term: ASCII other than letters and digits.
NOT_TERM = np.ones(256, bool)
NOT_TERM[128:] = False
for _a, _b in (("a", "z"), ("A", "Z"), ("0", "9")):
    NOT_TERM[ord(_a) : ord(_b) + 1] = False


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words in which each input bit moves each output bit."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def _byte_values() -> np.ndarray:
    values = mix(np.arange(1, 257, dtype=U) * U(_R))
    values[ord("A") : ord("Z") + 1] = values[ord("a") : ord("z") + 1]
    return values


_BYTES = _byte_values()


def _powers(base: int) -> np.ndarray:
    steps = np.full(PIECE_BYTES + 1, base, U)
    steps[0] = 1
    return np.multiply.accumulate(steps)


_UP, _DOWN = _powers(_R), _powers(_R_INV)
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))


def _long_word(data: np.ndarray) -> int:
    return int.from_bytes(hashlib.blake2b(data.tobytes().translate(_LOWER), digest_size=8).digest(), "little")


def _piece(data: np.ndarray, bounds: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes and starts of the words of a piece; words also end at `bounds`."""
    n = len(data)
    inside = ~ends[data]
    first = np.ones(n, bool)
    first[1:] = ~inside[:-1]
    first[bounds] = True
    starts = np.flatnonzero(inside & first)
    last = np.ones(n, bool)
    last[:-1] = first[1:] | ~inside[1:]
    stops = np.flatnonzero(inside & last) + 1
    if n > PIECE_BYTES:  # a word that no piece can hold
        return np.array([_long_word(data[x:y]) for x, y in zip(starts.tolist(), stops.tolist(), strict=True)], U), starts
    total = np.zeros(n + 1, U)
    np.cumsum(_BYTES[data] * _UP[:n], out=total[1:])
    hashes = mix((total[stops] - total[starts]) * _DOWN[starts])
    for k in np.flatnonzero(stops - starts > ROLLING_BYTES).tolist():
        hashes[k] = _long_word(data[starts[k] : stops[k]])
    return hashes, starts


def word_pieces(data: np.ndarray, offsets: np.ndarray, ends: np.ndarray = SPACE) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Hashes and starts of the words of many texts (A-Z as a-z), in order, a piece of the bytes at a time."""
    at, n = 0, len(data)
    while at < n:
        stop = min(n, at + PIECE_BYTES)
        if stop < n:  # back to the last place where a word ends, or on to the next one
            outside = np.flatnonzero(ends[data[at:stop]])
            k = int(np.searchsorted(offsets, stop, side="right")) - 1
            cut = max(at + int(outside[-1]) + 1 if len(outside) else at, int(offsets[k]))
            while cut <= at or cut > n:
                later = np.flatnonzero(ends[data[stop : stop + PIECE_BYTES]])
                following = int(offsets[np.searchsorted(offsets, stop, side="left")])
                cut = min(stop + int(later[0]) + 1 if len(later) else n + 1, following if following <= stop + PIECE_BYTES else n + 1)
                stop += PIECE_BYTES
                cut = n if cut > n and stop >= n else cut
            stop = cut
        lo, hi = np.searchsorted(offsets, (at, stop))
        hashes, starts = _piece(data[at:stop], offsets[lo:hi] - at, ends)
        yield hashes, starts + at
        at = stop


def word_hashes(data: np.ndarray, offsets: np.ndarray, ends: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all words (A-Z as a-z) in order, and the n + 1 bounds of each text's words."""
    found = list(word_pieces(data, offsets, ends))
    if not found:
        return np.zeros(0, U), np.zeros(len(offsets), np.int64)
    return np.concatenate([h for h, _ in found]), np.searchsorted(np.concatenate([x for _, x in found]), offsets)


def _grams(words: np.ndarray, width: int) -> np.ndarray:
    """Hashes of the runs of `width` words."""
    n = max(0, len(words) - width + 1)
    grams = words[:n] * _MULS[0]
    for k in range(1, width):
        grams += words[k : k + n] * _MULS[k]
    return mix(grams)


def _distinct(values: np.ndarray) -> np.ndarray:
    """The distinct values, sorted; `values` is sorted in place."""
    values.sort()
    if len(values) < 2:
        return values
    fresh = np.ones(len(values), bool)
    np.not_equal(values[1:], values[:-1], out=fresh[1:])
    return values if fresh.all() else values[fresh]


def _few(words: np.ndarray) -> np.ndarray:
    """The one shingle of a text with fewer words than a shingle has."""
    return mix((words * _MULS[: len(words)]).sum(keepdims=True) + U(len(words))) if len(words) else words


def long_set(data: np.ndarray, width: int = 5) -> np.ndarray:
    """The shingle set of one text of any length, with some 16 bytes of memory for each of its words."""
    kept, carried = [], np.zeros(0, U)
    for hashes, _ in word_pieces(data, np.array([0, len(data)])):
        words = np.concatenate((carried, hashes))
        kept.append(_distinct(_grams(words, width)))
        carried = words[len(words) - min(width - 1, len(words)) :]
    if not any(map(len, kept)):
        return _few(carried)
    values = np.concatenate(kept)
    kept.clear()
    return _distinct(values)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, width: int = 5) -> list[np.ndarray]:
    """For each text the sorted distinct hashes of its `width`-word shingles; a shorter text is one shingle.

    Two different shingles have one hash with a chance of 2^-64; sets of n and m shingles are told wrong by it
    with a chance below (n + m)^2 / 2^65.
    """
    if len(offsets) == 2 and len(data) > 8 * PIECE_BYTES:
        return [long_set(data, width)]
    words, at = word_hashes(data, offsets)
    grams = _grams(words, width)
    return [_distinct(grams[a : b - width + 1].copy()) if b - a >= width else _few(words[a:b]) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]

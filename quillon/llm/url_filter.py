"""URL filters: glob rules as one bit-parallel automaton over canonical URLs."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, utf8

# The rules (host, path) and their verdicts.
RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))
#: The method's own globs, for urls that no rule fits; any fit blocks. `*` stands for any bytes.
BLOCK_GLOBS = ("*spam*", "*cheap-pills*", "*casino*", "*porn*", "*malware*")
#: Stands before the host, so that a rule's host is preceded by it or by a dot.
START = b"\x01"


class ShiftAnd:
    """Glob patterns over bytes, all simulated at once: a bit a pattern position, in 64-bit words.

    A pattern is a list of elements: a byte, or a set of bytes that may repeat any number of times
    (a wildcard). A wildcard is a loop on the position before it. A pattern fits if it covers the
    whole input: it is anchored on both sides, unless it begins or ends with a wildcard.
    """

    def __init__(self, patterns: list[list[int | frozenset]]):
        self.accept: list[int] = []
        loops: list[frozenset] = []
        letters: list[int] = []
        first: list[int] = []
        for p in patterns:
            first.append(len(letters))
            letters.append(-1)  # before the first byte
            loops.append(frozenset())
            for e in p:
                if isinstance(e, frozenset):
                    loops[-1] |= e
                else:
                    letters.append(e)
                    loops.append(frozenset())
            self.accept.append(len(letters) - 1)
        self.words = max(1, -(-len(letters) // 64))
        pack = lambda bits: np.array([sum(1 << (b - 64 * w) for b in bits if w == b // 64) for w in range(self.words)], np.uint64)
        self.start = pack(first)
        self.step = np.stack([pack([k for k, c in enumerate(letters) if c == b]) for b in range(256)])
        self.loop = np.stack([pack([k for k, s in enumerate(loops) if b in s]) for b in range(256)])

    def run(self, data: np.ndarray, at: np.ndarray) -> np.ndarray:
        """[input, pattern] -> fits. Inputs are data[at[k] : at[k + 1]]; all move one byte in a step."""
        n, lengths = len(at) - 1, np.diff(at)
        order = np.argsort(-lengths, kind="stable")
        state = np.tile(self.start, (n, 1))
        starts, live = at[:-1][order], np.searchsorted(-lengths[order], -np.arange(int(lengths.max(initial=0))), side="left")
        one, top = np.uint64(1), np.uint64(63)
        for k, m in enumerate(live.tolist()):  # the m inputs that have a byte k
            s, b = state[:m], data[starts[:m] + k]
            moved = s << one
            moved[:, 1:] |= s[:, :-1] >> top
            state[:m] = (moved & self.step[b]) | (s & self.loop[b])
        out = np.zeros((n, len(self.accept)), bool)
        for j, a in enumerate(self.accept):
            out[order, j] = (state[:, a // 64] >> np.uint64(a % 64)) & one != 0
        return out


ANY = frozenset(range(256))
IN_HOST = frozenset(set(range(256)) - set(b"/"))


def glob(pattern: str) -> list[int | frozenset]:
    """`*` any bytes, everything else itself."""
    return [ANY if c == ord("*") else c for c in pattern.encode()]


def rule(host: str, path: str) -> list[list[int | frozenset]]:
    """A host, or its subdomains, with all paths that start with `path`."""
    tail = [*host.encode(), *path.encode(), ANY]
    return [[*START, *tail], [*START, IN_HOST, ord("."), *tail]]


def url_verdicts(pages: DataFrame, rules: Iterable[tuple[str, str, str]] = RULES, globs: Iterable[str] = BLOCK_GLOBS, key: str = "page_id", url: str = "url") -> DataFrame:
    """Per row: key, host, path, rule, verdict.

    Host: after the first `://` up to `/`, `?`, `#` or the end, A-Z lower-cased; path: from there up to
    `?`, `#` or the end; both empty without `://` or for a null url. Of the rules that fit, the longest
    wins, a block before an allow of one length. Without one, the verdict is block if a glob fits
    what follows `://`, query and fragment included, A-Z lower-cased, else allow; a glob is anchored where it has
    no `*`. Repeated rows are treated alike; an empty table gives an empty result; other columns, whatever
    their names, are ignored.
    """
    rules = sorted(rules, key=lambda r: (-len(r[0] + r[1]), r[2] != "block", r[0] + r[1]))
    compiled = [p for host, path, _ in rules for p in rule(host, path)]
    own = [glob(g) for g in globs]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton, words = ShiftAnd(compiled), ShiftAnd(own)
        names = np.array([h + p for h, p, _ in rules] + [None], object)
        verdicts = np.array([v for _, _, v in rules], object)
        for batch in batches:
            for a in range(0, batch.num_rows, 8192):
                rows = batch.slice(a, 8192)
                fits = automaton.run(*utf8(rows.column(3)))
                of = fits.reshape(len(fits), len(rules), 2).any(axis=2) if rules else np.zeros((len(fits), 0), bool)
                best = np.where(of.any(axis=1), of.argmax(axis=1), len(rules)) if rules else np.zeros(len(fits), np.int64)
                blocked = np.where(words.run(*utf8(rows.column(4))).any(axis=1), "block", "allow").astype(object)
                verdict = np.where(best < len(rules), np.append(verdicts, "")[best], blocked)
                yield pa.RecordBatch.from_arrays([*rows.columns[:3], pa.array(names[best], pa.string()), pa.array(verdict, pa.string())], names=["id", "host", "path", "rule", "verdict"])

    place = F.instr(url, "://")
    rest = F.when(place > 0, F.expr(f"substring(`{url}`, instr(`{url}`, '://') + 3)")).otherwise("")
    low = lambda c: F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    host = low(F.regexp_extract(F.coalesce(rest, F.lit("")), r"\A([^/?#]*)", 1))
    path = F.regexp_extract(F.coalesce(rest, F.lit("")), r"\A[^/?#]*([^?#]*)", 1)
    source = pages.select(F.col(key).alias("id"), host.alias("host"), path.alias("path"), low(F.coalesce(rest, F.lit(""))).alias("whole"))
    source = source.select("id", "host", "path", F.concat(F.lit(START.decode()), "host", "path").alias("canonical"), "whole")
    schema = f"id {source.schema['id'].dataType.simpleString()}, host string, path string, rule string, verdict string"
    return map_batches(source, run, schema).withColumnRenamed("id", key)

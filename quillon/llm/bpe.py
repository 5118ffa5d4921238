"""Byte-level BPE: exact encoding by tree concatenation, and decoding from ids."""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterable, Iterator

import public_tokenizers
import pyarrow as pa
import regex
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from .common import map_batches, row_slices

#: Characters of a text up to which it is encoded at once; a longer one is cut in halves, again and again.
LEAF_CHARS = 1024
#: Characters on both sides of a seam in the first window that is encoded again.
SEAM_CHARS = 12
#: Characters that all libraries class alike, for places where a piece ends in whatever text they stand.
_BLANK = r" \t-\r\u0085\u00a0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
_LETTER = r"A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f\u0400-\u0481\u048a-\u052f\u3041-\u3096\u30a1-\u30fa\u4e00-\u9fa5\uac00-\ud7a3"
_MARK, _DIGIT = r"!-&(-/:-@\[-`{-~\u3001-\u3003\u3008-\u3011\uff01-\uff0f\uff1a-\uff20", "0-9"
#: Those places: before white space that follows another character, before the last white space of a run that another
#: character ends, and between letters, digits and marks, but for a letter after an apostrophe.
FIRM = re.compile(rf"(?<=\S)(?=[{_BLANK}])|(?<=[{_BLANK}])(?=[{_BLANK}]\S)|(?<=[{_LETTER}])(?=[{_MARK}'{_DIGIT}])|(?<=[{_DIGIT}])(?=[{_MARK}'{_LETTER}])|(?<=[{_MARK}])(?=[{_LETTER}{_DIGIT}])|(?<=')(?=[{_DIGIT}])")
#: Characters outside these ranges may be classed otherwise by another library's Unicode tables.
UNSURE = re.compile("[^\x00-\u052f\u05d0-\u05ea\u0620-\u06d3\u0904-\u0939\u2000-\u2064\u20a0-\u20bd\u2100-\u218b\u2190-\u23fe\u2500-\u2b73\u3000-\u303f\u3041-\u3096\u30a0-\u30ff\u4e00-\u9fa5\uac00-\ud7a3\uff01-\uffbe\U0001f300-\U0001f64f]")

_encoders: dict[str, "TreeEncoder"] = {}


def byte_letters() -> dict[int, str]:
    """The letter that stands for each byte in a byte-level vocabulary: printable bytes for themselves, the others from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(others)}


def default_vocabulary() -> str:
    return public_tokenizers.path("byte_bpe_50k.json")


class _Gaps:
    """Finds the firm places around a seam; remembers stretches without any, so that none is searched twice."""

    def __init__(self, near: int):
        self.near, self.before, self.after = near, {}, {}

    @staticmethod
    def _firm(text: str, x: int, y: int) -> list[int]:
        """Firm places from x to y."""
        base = max(x - 1, 0)
        return [k for m in FIRM.finditer(text[base : y + 2]) if x <= (k := m.start() + base) <= y]

    def _left(self, text: str, a: int, x: int) -> int:
        """The last firm place before x, or a."""
        end, step = x, SEAM_CHARS
        while True:
            x = self.before.get(x, x)
            if x <= a or x != end and self._firm(text, x, x):
                break
            y = max(a, x - step)
            if found := [k for k in self._firm(text, y, x - 1) if k > a]:
                x = found[-1]
                break
            x, step = y, 2 * step
        self.before[end] = x = max(a, x)
        return x

    def _right(self, text: str, x: int, b: int) -> int:
        """The first firm place after x, or b."""
        start, step = x, SEAM_CHARS
        while True:
            x = self.after.get(x, x)
            if x >= b or x != start and self._firm(text, x, x):
                break
            y = min(b, x + step)
            if found := [k for k in self._firm(text, x + 1, y) if k < b]:
                x = found[0]
                break
            x, step = y, 2 * step
        self.after[start] = x = min(b, x)
        return x

    def around(self, text: str, a: int, seam: int, b: int, skip: int) -> tuple[list[int], list[int]]:
        """Outwards from the seam, after `skip` others: one or two firm places, or the part's end, on each side.

        A second place is left out if it is far from the first one. The last white space of a run does not
        count right before the seam, as the part that ends there does not see what follows.
        """
        here = bool(self._firm(text, seam, seam))
        x = seam if here else self._left(text, a, seam)
        if x == seam - 1 and x > a and text[x].isspace() and text[x - 1].isspace():
            x = self._left(text, a, x)
        y = seam if here else self._right(text, seam, b)
        for _ in range(skip):
            x, y = (self._left(text, a, x) if x > a else a), (self._right(text, y, b) if y < b else b)
        if not here and not skip:  # nothing firm lies between x and y but the seam's neighbours
            if y == b:
                self.before.setdefault(b, x)
            if x == a:
                self.after.setdefault(a, y)
        before, after = [x], [y]
        if x > a and x - (z := self._left(text, a, x)) <= self.near:
            before.append(z)
        if y < b and (z := self._right(text, y, b)) - y <= self.near:
            after.append(z)
        return before, after


class TreeEncoder:
    """Encodes as the tokenizers library does with the same file, special tokens not added.

    A text is cut at special tokens. A stretch of more than `leaf_chars` is cut in halves, wherever the middle
    falls, down to leaves; these are encoded as one batch (by `threads` threads); then neighbours are joined, see
    `join`. Leaves and windows are encoded by ranks or, if a text has characters that libraries may class
    differently, by the tokenizers library itself. `longer` counts the texts that were cut, `texts` all.
    """

    def __init__(self, path: str, leaf_chars: int = LEAF_CHARS, threads: int = 1):
        with open(path, encoding="utf-8") as f:
            stored = json.load(f)
        self.path, self.leaf_chars, self.threads, self._library = path, leaf_chars, threads, None
        self.texts = self.longer = 0
        self.special = {t["content"]: t["id"] for t in stored["added_tokens"]}
        self.marks = re.compile("|".join(map(re.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        to_byte = {c: b for b, c in byte_letters().items()}
        tokens = {bytes(to_byte[c] for c in t): i for t, i in stored["model"]["vocab"].items() if t not in self.special}
        del stored
        self.pieces = regex.compile(public_tokenizers.PATTERN)
        self.ranks = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=tokens, special_tokens={})  # ids are in the order of the merges
        self.bytes: list[bytes] = [b""] * (1 + max([*tokens.values(), *self.special.values()]))
        for t, i in [*tokens.items(), *((x.encode(), i) for x, i in self.special.items())]:
            self.bytes[i] = t
        self.names = [str(i) for i in range(len(self.bytes))]

    @property
    def tokenizer(self) -> Tokenizer:
        if self._library is None:
            self._library = Tokenizer.from_file(self.path)
            self._library.no_truncation()
            self._library.no_padding()
        return self._library

    def leaves(self, texts: list[str], sure: bool) -> list[list[int]]:
        """The encodings of short texts."""
        if not sure:
            return [e.ids for e in self.tokenizer.encode_batch(texts, add_special_tokens=False)]
        if self.threads > 1:
            return self.ranks.encode_ordinary_batch(texts, num_threads=self.threads)
        return [self.ranks.encode_ordinary(t) for t in texts]

    def _tail(self, ids: list[int], size: int) -> int | None:
        """The place from which the tokens have `size` bytes; None if no token starts there."""
        k = len(ids)
        while size > 0:
            k -= 1
            size -= len(self.bytes[ids[k]])
        return k if size == 0 else None

    def _head(self, ids: list[int], size: int) -> int | None:
        k = 0
        while size > 0:
            size -= len(self.bytes[ids[k]])
            k += 1
        return k if size == 0 else None

    def join(self, text: str, a: int, seam: int, b: int, left: list[int], right: list[int], sure: bool, gaps: "_Gaps") -> list[int]:
        """The encoding of text[a:b] from those of text[a:seam] and text[seam:b].

        A window around the seam reaches, on either side, to the second place where a piece ends whatever stands
        around it, or to the end of the part; it is the smallest such window. It is encoded again and must begin
        with the left part's tokens between its first two such places and end with the right part's between the
        last two; else it grows to the next places. Pieces before such a place are those of the left part, pieces
        after it those of the right part, so the joined ids are exact. A seam within one long piece is joined by
        its tokens, see `merge`.
        """
        skip = 0
        while True:
            before, after = gaps.around(text, a, seam, b, skip)
            if after[0] - before[0] > self.leaf_chars and (found := self._within(text, before[0], seam, after[0], left, right, sure)):
                return found
            first, last = before[-1], after[-1]
            if first == a and last == b:
                return self.leaves([text[a:b]], sure)[0]
            [ids] = self.leaves([text[first:last]], sure)
            size = lambda x, y: len(text[x:y].encode())
            i, j = self._tail(left, size(first, seam)), self._head(right, size(seam, last))
            if i is not None and j is not None:
                m, n = self._head(left[i:], size(first, before[0])), self._head(right[:j][::-1], size(after[0], last))
                if m is not None and n is not None and ids[:m] == left[i : i + m] and ids[len(ids) - n :] == right[j - n : j]:
                    return left[:i] + ids + right[j:]
            skip += 1

    def _within(self, text: str, first: int, seam: int, last: int, left: list[int], right: list[int], sure: bool) -> list[int] | None:
        """The joined ids if the seam lies within one long piece text[first:last]; else None."""
        one = lambda x, y: x == y or (m := self.pieces.match(text, x, y)) is not None and m.end() == y
        if not (first < seam < last and one(first, last) and one(first, seam) and one(seam, last)):
            return None
        i, j = self._tail(left, len(text[first:seam].encode())), self._head(right, len(text[seam:last].encode()))
        return None if i is None or j is None else left[:i] + self.merge(left[i:], right[:j], sure) + right[j:]

    def merge(self, left: list[int], right: list[int], sure: bool) -> list[int]:
        """The encoding of one piece from those of two parts of it.

        Windows of 2, 4, 8, ... tokens on both sides of the seam are encoded again until the first token
        equals the left part's there and the last one the right part's, or a side is used up. Then every
        pair of neighbours in the result also stands together in an encoding, which makes it the encoding.
        """
        k = 2
        while True:
            a, b = left[-k:], right[:k]
            try:
                text = b"".join([self.bytes[i] for i in a + b]).decode()
            except UnicodeDecodeError:  # the window ends within a character
                text = None
            if text is not None:
                [ids] = self.leaves([text], sure)
                if (k >= len(left) or ids[0] == a[0]) and (k >= len(right) or ids[-1] == b[-1]):
                    return left[:-k] + ids + right[k:]
            k *= 2

    def tree(self, text: str, sure: bool) -> list[int]:
        """The encoding of a text of any length without special tokens, from those of its halves."""
        cuts: list[str] = []

        def cut(a: int, b: int) -> None:
            if b - a <= self.leaf_chars:
                cuts.append(text[a:b])
            else:
                cut(a, (a + b) // 2)
                cut((a + b) // 2, b)

        cut(0, len(text))
        leaves, gaps = iter(self.leaves(cuts, sure)), _Gaps(self.leaf_chars)

        def build(a: int, b: int) -> list[int]:
            if b - a <= self.leaf_chars:
                return next(leaves)
            seam = (a + b) // 2
            left = build(a, seam)
            return self.join(text, a, seam, b, left, build(seam, b), sure, gaps)

        return build(0, len(text))

    def encode(self, text: str) -> list[int]:
        sure = text.isascii() or not UNSURE.search(text)
        out, at = [], 0
        for m in self.marks.finditer(text) if self.marks else ():
            out += [*self.tree(text[at : m.start()], sure), self.special[m[0]]]
            at = m.end()
        self.texts += 1
        self.longer += len(text) > self.leaf_chars
        return out + self.tree(text[at:], sure) if at else self.tree(text, sure)

    def joined(self, ids: list[int]) -> str:
        """Decimal ids joined by commas."""
        return ",".join(map(self.names.__getitem__, ids))

    def decode(self, ids: Iterable[int]) -> str:
        """The text of ids; bytes that are no UTF-8 give the replacement character."""
        return b"".join(map(self.bytes.__getitem__, ids)).decode("utf-8", "replace")


def encoder(path: str) -> TreeEncoder:
    """The encoder of a vocabulary file, one for each Python worker."""
    if path not in _encoders:
        _encoders[path] = TreeEncoder(path)
    return _encoders[path]


def bpe_digests(docs: DataFrame, vocabulary: str | None = None, key: str = "doc_id", text: str = "text", with_ids: bool = False) -> DataFrame:
    """Per row: key, n_tokens, ids_sha256, decoded_sha256; `with_ids` adds the ids and the decoded text.

    Null and empty texts have no tokens. Texts are encoded whole. Repeated rows are treated alike; other
    columns, whatever their names, are ignored; an empty table gives an empty result. `vocabulary` is a file
    that every executor can read.
    """
    path = vocabulary or default_vocabulary()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(path)
        sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
        for rows in row_slices(batches):
            n, ids, back, whole = [], [], [], []
            for t in rows.column(1).to_pylist():
                found = own.encode(t or "")
                text_back = own.decode(found)
                n.append(len(found))
                ids.append(sha(own.joined(found)))
                back.append(sha(text_back))
                if with_ids:
                    whole.append((found, text_back))
            columns = [rows.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(back, pa.string())]
            if with_ids:
                columns += [pa.array([i for i, _ in whole], pa.list_(pa.int32())), pa.array([t for _, t in whole], pa.string())]
            yield pa.RecordBatch.from_arrays(columns, names=["id", "n_tokens", "ids_sha256", "decoded_sha256", "ids", "decoded"][: len(columns)])

    source = docs.select(F.col(key).alias("id"), F.col(text).alias("text"))
    schema = f"id {source.schema['id'].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded string" * with_ids
    return map_batches(source, run, schema).withColumnRenamed("id", key)

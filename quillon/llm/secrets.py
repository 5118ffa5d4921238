"""Secret scans: fixed patterns, and assignment-aware lexing of name-literal pairs."""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, row_slices

# The base patterns, and the lengths from which a match counts.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")  # a run of that class is one match, so a shorter one fails whole
ASSIGN_VALUE, ACCESS_LENGTH = 6, 20
ASSIGN_STEMS = ("password", "passwd", "secret", "token", "apikey", "api_key")

KINDS = ("assign", "access", "hex", "lexed")
Span = tuple[str, int, int]

#: Parts of a name that make it sensitive, with their scores; pairs count if both parts are there.
SENSITIVE = {
    "password": 4, "passwd": 4, "passphrase": 4, "pwd": 4, "pass": 3, "secret": 4, "secrets": 4, "token": 3, "apikey": 4,
    "credential": 4, "credentials": 4, "bearer": 3, "authorization": 3, "api key": 4, "private key": 4, "access key": 4,
    "auth key": 4, "signing key": 4, "encryption key": 4, "client key": 3, "account key": 4, "auth token": 4, "connection string": 4,
}
#: Parts that say the value is about a secret and not one.
HARMLESS = {"length", "len", "count", "min", "max", "size", "type", "name", "field", "label", "hint", "url", "uri", "path", "file", "ttl", "expiry", "expires", "policy", "regex", "id", "limit", "prompt", "placeholder", "header"}
#: Values that stand for a secret and are none.
STAND_IN = re.compile(r"(?i)(?:change_?me|your[-_ ].*|example.*|placeholder|redacted|none|null|undefined|true|false|todo|test|dummy|x{3,}|\*{3,}|\.{3,}|<.*>|\$\{.*|\{\{.*|%\(.*|\$\w+|os\.environ.*|process\.env.*|getenv.*)\Z")
STEMS = ("pass", "pwd", "secret", "token", "key", "credential", "bearer", "authorization", "connection")
LEAST_SCORE, LEAST_LITERAL = 5, 6

#: One token at a place; quoted strings are read apart. What may start far from where it fails cannot start
#: again within what it failed on, so that reading a text takes time in proportion to its length.
LEX = re.compile(
    r"(?P<xml><(?P<tag>[A-Za-z_][\w.-]*+)>(?P<body>[^<>]*+)</(?P=tag)>)"
    r"|(?P<flag>(?<![\w-])--?(?P<option>[A-Za-z][\w-]*+)[ =](?P<argument>[^\s\"']++))"
    r"|(?P<url>(?<![A-Za-z0-9+.-])[a-z][a-z0-9+.-]*+://[^\s/:@]++:(?P<login>[^\s/@]++)@)"
    r"|(?P<name>[A-Za-z_$][\w$]*+(?:[.-][\w$]++)*+)|(?P<op>:=|=>|->|==|!=|<=|>=|[=:+,;(){}\[\]])|(?P<number>\d[\w.]*+)|(?P<other>\S)",
    re.ASCII,
)
SPACE, LINE_SPACE = re.compile(r"\s*+"), re.compile(r"[^\S\n]*+")
#: Quoted strings by what opens them: within a line, or over lines for three quotes and back quotes.
STRINGS = {
    '"""': re.compile(r'"""((?:[^"\\]|\\.|"(?!""))*+)"""', re.S), "'''": re.compile(r"'''((?:[^'\\]|\\.|'(?!''))*+)'''", re.S),
    '"': re.compile(r'"((?:[^"\\\n]|\\.)*+)"'), "'": re.compile(r"'((?:[^'\\\n]|\\.)*+)'"), "`": re.compile(r"`([^`]*+)`"),
}
BARE = re.compile(r"[^\s\"'`,;(){}\[\]<>]++")
ASSIGNS, TAKES_OVER = frozenset(("=", ":=", "=>", ":", "->")), frozenset(("=", ":=", "=>", "->", "(", "["))
#: Characters of a joined literal that its look is judged by; its spans are whole.
LOOK_CHARS = 512
PARTS = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|\d+")


def base_spans(text: str) -> list[Span]:
    """Spans of the fixed patterns, leftmost and not overlapping within a kind."""
    spans: list[Span] = []
    low = text.lower()
    if any(stem in low for stem in ASSIGN_STEMS):
        spans += [("assign", *m.span()) for m in ASSIGN.finditer(text) if len(m[2]) >= ASSIGN_VALUE]
    if "AKIA" in text:
        spans += [("access", *m.span()) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LENGTH]
    spans += [("hex", *m.span()) for m in HEX.finditer(text)]
    return spans


def name_score(name: str) -> int:
    """How sensitive a target's name is: the best of its parts and neighbouring parts, less the harmless ones."""
    parts = [p.lower() for p in PARTS.findall(name)]
    best = max([SENSITIVE.get(p, 0) for p in [*parts, "".join(parts), *(f"{a} {b}" for a, b in zip(parts, parts[1:], strict=False))]], default=0)
    return best - 3 * bool(HARMLESS & set(parts[-1:])) if best else 0


def literal_score(value: str, strong: bool = False) -> int:
    """How much a literal looks like a secret: length, kinds of characters, variety; 0 if it stands in for one.

    Of literals with white space only those of three words or more count, and only under a `strong` name.
    """
    if len(value) < LEAST_LITERAL or STAND_IN.match(value):
        return 0
    words = len(value.split())
    if words > 1 or value != value.strip():
        return int(strong and words >= 3 and value[-1] not in ".:?!…")
    kinds = sum(any(f(c) for c in value) for f in (str.islower, str.isupper, str.isdigit, lambda c: not c.isalnum()))
    varied = len(set(value)) >= 5
    return 1 + (kinds >= 2) + (len(value) >= 12 and varied) if varied or kinds > 1 else 1


@dataclass
class Literal:
    """A literal: how it begins, the spans it has itself, and the literals it takes over by name."""

    look: str
    spans: list[tuple[int, int]] = field(default_factory=list)
    parts: list["Literal"] = field(default_factory=list)


class _Reader:
    """Reads one text from left to right; holds one token at a time."""

    def __init__(self, text: str):
        self.text, self.dead, self.run_end, self.run_after = text, {}, -1, None

    def string(self, at: int) -> re.Match | None:
        """The quoted string that starts at `at`. After one without an end, no other within it has one."""
        for opener in (self.text[at] * 3, self.text[at]):
            if opener in STRINGS and self.text.startswith(opener, at) and at >= self.dead.get(opener, 0):
                if m := STRINGS[opener].match(self.text, at):
                    return m
                end = self.text.find("\n", at) if len(opener) == 1 and opener != "`" else -1
                self.dead[opener] = len(self.text) if end < 0 else end
        return None

    def token(self, at: int) -> tuple[str, re.Match] | None:
        """Kind and match of the token at or after `at`."""
        at = SPACE.match(self.text, at).end()
        if at >= len(self.text):
            return None
        if self.text[at] in "\"'`" and (m := self.string(at)):
            return "string", m
        m = LEX.match(self.text, at)
        return m.lastgroup, m

    def op(self, at: int) -> tuple[str, int]:
        """The operator at or after `at`, within the line, and where it ends."""
        m = LEX.match(self.text, LINE_SPACE.match(self.text, at).end())
        return (m[0], m.end()) if m and m["op"] else ("", at)

    def bare(self, at: int) -> tuple[int, str]:
        """End of the unquoted run at `at`, and the operator after it; found once for each run."""
        if at >= self.run_end:
            m = BARE.match(self.text, at)
            self.run_end = m.end() if m else at
            self.run_after = self.op(self.run_end)[0]
        return self.run_end, self.run_after

    def value(self, at: int, known: dict[str, Literal]) -> tuple[Literal | None, int]:
        """The literal at or after `at`, and where reading goes on."""
        out, first = Literal(""), True
        while True:
            start = SPACE.match(self.text, at).end()
            if start >= len(self.text):
                break
            same_line = LINE_SPACE.match(self.text, at).end() == start
            got = self.token(start)
            kind, m = got
            if kind == "string":
                out.spans.append(m.span(1))
                out.look = (out.look + m[1][:LOOK_CHARS])[:LOOK_CHARS]
                at = m.end()
            elif kind == "name" and m[0] in known and same_line and (not first or self.bare(start)[0] == m.end()):
                out.parts.append(known[m[0]])
                out.look = (out.look + known[m[0]].look)[:LOOK_CHARS]
                at = m.end()
            elif first and same_line and (end := self.bare(start))[0] > start:
                if end[1] in TAKES_OVER:
                    return None, start  # a type, another target or a call
                return Literal(self.text[start : min(end[0], start + LOOK_CHARS)], [(start, end[0])]), end[0]
            else:
                return (None, at) if first else (out, at)
            first = False
            op, after = self.op(at)
            if op == "+":
                at = after
            else:
                spot = LINE_SPACE.match(self.text, at).end()
                if self.text[spot : spot + 1] not in ("'", '"') or not self.string(spot):
                    break
        return (out if out.spans or out.parts else None), at


def pairs(text: str) -> Iterator[tuple[str, Literal]]:
    """Name-literal pairs of source and configuration syntax, in the order of the text.

    Reads assignments (= := => : ->), keyword and dictionary entries, elements, options and logins in
    URLs; joins literals that + puts together or that stand side by side; takes for a name on the right the
    literal that the same text gave it before. A quoted literal, or an element's body, may stand on later
    lines than its name; an unquoted one stands on the name's own line. Takes time and memory in proportion
    to the text.
    """
    known: dict[str, Literal] = {}
    read, at = _Reader(text), 0
    while got := read.token(at):
        kind, t = got
        at = t.end()
        if kind in ("name", "string"):
            op, after = read.op(at)
            if op in ASSIGNS:
                target = t[0] if kind == "name" else t[1]
                value, at = read.value(after, known)
                if not value and op == ":" and read.run_end > at and read.run_after == "=":  # the run is the name's type
                    value, at = read.value(read.op(read.run_end)[1], known)
                if value:
                    known[target] = value
                    yield target, value
        elif kind == "xml":
            yield t["tag"], Literal(t["body"][:LOOK_CHARS], [t.span("body")])
        elif kind == "flag":
            yield t["option"], Literal(t["argument"][:LOOK_CHARS], [t.span("argument")])
        elif kind == "url":
            yield "password", Literal(t["login"][:LOOK_CHARS], [t.span("login")])


def lexed_spans(text: str) -> list[Span]:
    """Spans of literals whose targets' names and own looks score LEAST_SCORE or more."""
    low = text.lower()
    if not any(stem in low for stem in STEMS) and "://" not in low:
        return []
    found: set[tuple[int, int]] = set()
    seen: dict[int, Literal] = {}
    secret: list[Literal] = []
    for name, value in pairs(text):
        worth = name_score(name) if len(name) <= LOOK_CHARS else 0
        if worth > 0 and (own := literal_score(value.look, worth >= 4)) and worth + own >= LEAST_SCORE:
            secret.append(value)
            while secret:  # each literal is gone through once, however many names take it over
                x = secret.pop()
                if id(x) not in seen:
                    seen[id(x)] = x
                    found.update(x.spans)
                    secret += x.parts
    return [("lexed", a, b) for a, b in found if b > a]


def _joined(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda s: (s[1], KINDS.index(s[0]), s[2])))


def redacted(text: str, spans: Iterable[Span], mark: str = "[secret]") -> str:
    """The text with the union of the spans replaced by `mark`."""
    out, at = [], 0
    for a, b in sorted((a, b) for _, a, b in spans):
        if a >= at:
            out += [text[at:a], mark]
        at = max(at, b)
    return "".join([*out, text[at:]])


def find_secrets(docs: DataFrame, key: str = "doc_id", text: str = "text", with_text: bool = False) -> DataFrame:
    """Per row: key, n_assign, n_access, n_hex, base_sha256, spans; `with_text` adds the text without its secrets.

    Null and empty texts have no spans (and stay as they are). Texts are read whole. Repeated rows are
    treated alike; other columns are ignored.
    """

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in row_slices(batches):
            out: list[list] = [[] for _ in range(6 if with_text else 5)]
            for t in rows.column(1).to_pylist():
                base = base_spans(t or "")
                spans = base + lexed_spans(t or "")
                n = Counter(k for k, _, _ in base)
                row = [n["assign"], n["access"], n["hex"], hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(spans)]
                for column, v in zip(out, [*row, redacted(t, spans) if t else t] if with_text else row, strict=True):
                    column.append(v)
            kinds = [pa.int64()] * 3 + [pa.string()] * (len(out) - 3)
            names = ["id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "clean"][: len(out) + 1]
            yield pa.RecordBatch.from_arrays([rows.column(0), *(pa.array(c, k) for c, k in zip(out, kinds, strict=True))], names=names)

    source = docs.select(F.col(key).alias("id"), F.col(text).alias("text"))
    schema = f"id {source.schema['id'].dataType.simpleString()}, n_assign long, n_access long, n_hex long, base_sha256 string, spans string" + ", clean string" * with_text
    return map_batches(source, run, schema).withColumnRenamed("id", key)


def without_secrets(docs: DataFrame, text: str = "text") -> DataFrame:
    """All rows and columns, with the secrets in `text` replaced; a column n_chars follows the new text."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in row_slices(batches, text):
            at = rows.schema.get_field_index(text)
            new = [redacted(t, base_spans(t) + lexed_spans(t)) if t else t for t in rows.column(at).to_pylist()]
            yield rows.set_column(at, rows.schema.field(at), pa.array(new, rows.schema.field(at).type))

    out = map_batches(docs, run, docs.schema)
    return out.withColumn("n_chars", F.length(text).cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out

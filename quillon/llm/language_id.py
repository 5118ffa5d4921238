"""Language identification by compression: the language whose dictionary compresses a text best."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
import regex
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import crc_held_out, map_batches, row_slices

UNDETERMINED = "und"
#: Letters are the characters of Unicode's category L; numerals such as one half or the Roman twelve are none.
LETTER, NOT_LETTERS = regex.compile(r"\p{L}"), regex.compile(r"\P{L}++")
#: Bytes of text in a language's dictionary, and of one text that may go into it.
DICTIONARY_BYTES, EXCERPT_BYTES = 112 << 10, 2 << 10
#: Labelled texts of a language that are looked at for its dictionary, about.
SAMPLE_ROWS = 400
#: Bytes that are compressed by themselves, so that a long text's own past does not stand in for the dictionary.
WINDOW_BYTES = 2 << 10
#: Characters of a long text that are looked at together.
PIECE_CHARS = 1 << 18
#: Level for all texts; level for a second look at texts within SHORT_BYTES whose margin is within SECOND_LOOK.
LEVEL, CLOSE_LEVEL = 6, 12
SHORT_BYTES, SECOND_LOOK = 512, 0.03
#: Share of the second best size by which the best must be smaller; else the text is rejected.
MARGIN = 0.002

Model = list[tuple[str, bytes]]


def letters(text: str) -> bytes:
    """The text in lower case, with one space for each run of anything but letters."""
    return NOT_LETTERS.sub(" ", text.lower()).strip().encode()


def windows(text: str) -> Iterator[bytes]:
    """The letters of a text of any length in windows of WINDOW_BYTES, a piece of it in memory at a time."""
    held = b""
    for a in range(0, len(text), PIECE_CHARS):
        piece = NOT_LETTERS.sub(" ", text[a : a + PIECE_CHARS].lower()).encode()
        held += piece[1:] if piece[:1] == b" " and (held[-1:] == b" " or not held and not a) else piece
        whole = max(0, len(held) - 1) // WINDOW_BYTES * WINDOW_BYTES  # the last byte stays: it tells whether a space goes on
        for k in range(0, whole, WINDOW_BYTES):
            yield held[k : k + WINDOW_BYTES]
        held = held[whole:]
    held = held.rstrip(b" ")
    if held:
        yield held


def learn_dictionaries(labelled: DataFrame, text: str = "text", lang: str = "lang", key: str = "doc_id", sample_rows: int = SAMPLE_ROWS, dictionary_bytes: int = DICTIONARY_BYTES) -> Model:
    """A raw-content dictionary for each language, from a bounded sample of its texts.

    The sample is the texts whose hash (of id and text) lies below a bound set from the language's count (about
    `sample_rows` of them, equal rows once, and never more than four times as many of all languages together), in
    order of that hash; of a longer text, the EXCERPT_BYTES characters at a place that the hash gives. The dictionary
    is cut at `dictionary_bytes`. The languages stand in order of their counts. Rows with a null text or language are
    left out; rows with null or repeated ids are not.
    """
    rows = labelled.where(F.col(text).isNotNull() & F.col(lang).isNotNull()).select(F.col(key).alias("id"), F.col(text).alias("text"), F.col(lang).alias("lang"))
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # a row a language
    if not counts:
        return []
    bound = F.create_map(*(x for k, n in counts.items() for x in (F.lit(k), F.lit(int(min(1.0, sample_rows / n) * (1 << 30)) + 1))))
    place = F.pmod(F.shiftright("rank", 30), F.greatest(F.length("text") - EXCERPT_BYTES, F.lit(0)) + 1) + 1
    some = rows.withColumn("rank", F.xxhash64("id", "text", F.lit(23))).where(F.pmod("rank", F.lit(1 << 30)) < bound[F.col("lang")])
    some = some.groupBy("lang", "rank").agg(F.min(F.substr("text", place, F.lit(EXCERPT_BYTES))).alias("text"))
    texts: dict[str, list[bytes]] = {k: [] for k in counts}
    for r in some.orderBy("rank", "lang").limit(4 * sample_rows * len(counts)).collect():
        texts[r["lang"]].append(letters(r["text"]))
    order = sorted(texts, key=lambda k: (-counts[k], k))
    return [(k, b"\n".join(dict.fromkeys(texts[k]))[:dictionary_bytes]) for k in order if any(texts[k])]


class Compressors:
    """Compressors for each language."""

    def __init__(self, model: Model):
        self.names = [k for k, _ in model]
        self.levels = {level: [self._with(content, level) for _, content in model] for level in (LEVEL, CLOSE_LEVEL)}

    @staticmethod
    def _with(content: bytes, level: int) -> zstandard.ZstdCompressor:
        d = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        d.precompute_compress(level=level)
        return zstandard.ZstdCompressor(level=level, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False)

    def _sizes(self, parts: Iterable[bytes], level: int) -> tuple[int, float]:
        sizes = [0] * len(self.names)
        for w in parts:
            for k, c in enumerate(self.levels[level]):
                sizes[k] += len(c.compress(w))
        best = min(range(len(sizes)), key=lambda k: (sizes[k], k))
        second = min((s for k, s in enumerate(sizes) if k != best), default=0)
        return best, (second - sizes[best]) / second if second else 1.0

    def judge(self, text: str | None) -> tuple[str, float]:
        """(language, margin): how much smaller the best size is, as a share of the second best. Ties go to the commoner language."""
        if not self.names or not text or not LETTER.search(text):
            return UNDETERMINED, 0.0
        best, margin = self._sizes(windows(text), LEVEL)
        if margin <= SECOND_LOOK and len(text) <= SHORT_BYTES and len(data := letters(text)) <= SHORT_BYTES:
            best, margin = self._sizes([data], CLOSE_LEVEL)
        return self.names[best], margin


def identify(docs: DataFrame, model: Model, text: str = "text", margin: float = MARGIN, names: tuple[str, str, str] = ("lang_pred", "score", "lang_ok")) -> DataFrame:
    """All rows and columns of `docs`, with three more: language, score (the margin) and whether it is accepted.

    A column of `docs` that has one of these names is left out.
    Texts are compressed whole, in windows whose sizes are summed. Null texts and texts without a letter get
    `und`, score 0, and are not accepted; so do all if there is no model. Acceptance also needs `margin`; a tie
    is never accepted.
    """

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        compressors = Compressors(model)
        for rows in row_slices(batches, text):
            found = [compressors.judge(t) for t in rows.column(rows.schema.get_field_index(text)).to_pylist()]
            new = [pa.array([k for k, _ in found], pa.string()), pa.array([s for _, s in found], pa.float64()), pa.array([k != UNDETERMINED and s > 0 and s >= margin for k, s in found], pa.bool_())]
            yield pa.RecordBatch.from_arrays([*rows.columns, *new], names=[*rows.schema.names, *names])

    docs = docs.drop(*names)
    kinds = (T.StringType(), T.DoubleType(), T.BooleanType())
    return map_batches(docs, run, T.StructType([*docs.schema.fields, *(T.StructField(n, k) for n, k in zip(names, kinds, strict=True))]))


def language_predictions(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score: learnt from the rows that are not held out, for all rows."""
    model = learn_dictionaries(docs.where(~crc_held_out()))
    found = identify(docs.select("doc_id", "text"), model)
    return found.select("doc_id", crc_held_out().alias("held_out"), "lang_pred", "score", "lang_ok")

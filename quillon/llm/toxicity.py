"""Toxicity by a factorisation machine over hashed terms."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_held_out, map_batches, text_slices
from .textkernel import NOT_TERM, PIECE_BYTES, U, word_hashes, word_pieces

BUCKETS = 1 << 20
#: Labelled documents that the model is fitted on, about.
SAMPLE_ROWS = 8192
#: A term must be in so many of them, and its share among toxic and other documents differ by so many standard errors;
LEAST_DOCS, LEAST_Z, MOST_TERMS = 5, 6.0, 4096
#: or it is in a pair whose toxic share differs so clearly (root of twice the log-likelihood ratio) from what its two
#: terms let expect. Terms whose pairs are counted against each other at a time.
LEAST_PAIR_G, PAIR_TILE = 6.0, 512
RANK, ROUNDS, RATE, DECAY = 8, 300, 0.05, 1e-3


@dataclass
class Machine:
    """score = sigmoid(bias + sum w x + sum over pairs <v_i, v_j> x_i x_j), x the presence of a term."""

    terms: np.ndarray
    bias: float
    weights: np.ndarray
    factors: np.ndarray

    def raw(self, rows: np.ndarray, columns: np.ndarray, n: int) -> np.ndarray:
        """Scores before the sigmoid of n documents; (rows, columns) are their distinct terms."""
        out = np.full(n, self.bias)
        np.add.at(out, rows, self.weights[columns])
        total = np.zeros((n, self.factors.shape[1]))
        np.add.at(total, rows, self.factors[columns])
        own = np.zeros(n)
        np.add.at(own, rows, (self.factors[columns] ** 2).sum(axis=1))
        return out + 0.5 * ((total**2).sum(axis=1) - own)


def terms_of(data: np.ndarray, at: np.ndarray, buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray]:
    """(text, bucket) of the terms of many texts; a term is a run of letters, digits and bytes over 127, A-Z as a-z.

    Of one long text, each bucket once, with a bit of memory a bucket.
    """
    if len(at) == 2 and len(data) > 8 * PIECE_BYTES:
        seen = np.zeros(buckets, bool)
        for hashes, _ in word_pieces(data, at, NOT_TERM):
            seen[(hashes & U(buckets - 1)).astype(np.int64)] = True
        found = np.flatnonzero(seen)
        return np.zeros(len(found), np.int64), found
    words, bounds = word_hashes(data, at, NOT_TERM)
    return np.repeat(np.arange(len(at) - 1), np.diff(bounds)), (words & U(buckets - 1)).astype(np.int64)


def pair_terms(rows: np.ndarray, columns: np.ndarray, labels: np.ndarray, m: int) -> np.ndarray:
    """The columns of all pairs of terms that tell the labels together beyond what each tells alone.

    (rows, columns) are the distinct terms of the documents. A pair's toxic share is held against the sum of
    its terms' effects where the other is missing; this expectation, uncertain at its ends, is widened to half
    the base rates, and the rarest of the three groups limits the evidence. All pairs are looked at, except
    those of a term too rare for any label to reach the bound. Repeated documents count once.
    """
    order = np.lexsort((columns, rows))
    rows, columns = rows[order], columns[order]
    cuts = np.searchsorted(rows, np.arange(len(labels) + 1))
    first = list({columns[a:b].tobytes(): k for k, (a, b) in enumerate(zip(cuts, cuts[1:]))}.values())
    again = np.full(len(labels), -1)
    again[first] = np.arange(len(first))
    keep = again[rows] >= 0
    rows, columns, labels = again[rows[keep]], columns[keep], labels[first].astype(np.float32)
    n, toxic = len(labels), float(labels.sum())
    share = toxic / n
    if not 0 < share < 1:
        return np.zeros(0, np.int64)
    among, with_ = np.bincount(columns, labels[rows], minlength=m), np.bincount(columns, minlength=m).astype(float)
    may = np.flatnonzero(2 * np.maximum(among * np.log(1 / share), (with_ - among) * np.log(1 / (1 - share))) >= LEAST_PAIR_G**2)
    place = np.full(m, -1)
    place[may] = np.arange(len(may))
    order = np.argsort(place[columns], kind="stable")
    rows, columns = rows[order], place[columns][order]
    among, with_ = among[may], with_[may]

    def tile(lo: int) -> np.ndarray:
        a, b = np.searchsorted(columns, (lo, lo + PAIR_TILE))
        out = np.zeros((n, min(PAIR_TILE, len(may) - lo)), np.float32)
        out[rows[a:b], columns[a:b] - lo] = 1
        return out

    smooth = lambda t, k: (t + share) / (k + 1)
    found = np.zeros(len(may), bool)
    for lo in range(0, len(may), PAIR_TILE):
        left = tile(lo)
        left_toxic = left[labels > 0]
        a = slice(lo, lo + left.shape[1])
        for other in range(lo, len(may), PAIR_TILE):
            right = tile(other)
            b = slice(other, other + right.shape[1])
            both, both_toxic = (left.T @ right).astype(float), (left_toxic.T @ right[labels > 0]).astype(float)
            one, one_toxic = with_[a, None] - both, among[a, None] - both_toxic
            two, two_toxic = with_[None, b] - both, among[None, b] - both_toxic
            neither = smooth(toxic - one_toxic - two_toxic - both_toxic, n - one - two - both)
            expected = smooth(one_toxic, one) + smooth(two_toxic, two) - neither
            wide = np.clip(expected, share / 2, (1 + share) / 2)
            p = both_toxic / np.maximum(both, 1)
            q = np.clip(np.clip(p, np.minimum(expected, wide), np.maximum(expected, wide)), 1e-9, 1 - 1e-9)
            apart = p * np.log(np.maximum(p, 1e-12) / q) + (1 - p) * np.log(np.maximum(1 - p, 1e-12) / (1 - q))
            evidence = 1 / (1 / np.maximum(both, 1e-9) + 1 / np.maximum(one, 1e-9) + 1 / np.maximum(two, 1e-9))
            hit = (2 * evidence * apart >= LEAST_PAIR_G**2) & (both >= LEAST_DOCS)
            if other == lo:
                np.fill_diagonal(hit, False)
            found[a] |= hit.any(axis=1)
            found[b] |= hit.any(axis=0)
    return may[found]


def fit(documents: list[np.ndarray], labels: np.ndarray, rank: int = RANK, rounds: int = ROUNDS) -> Machine:
    """A machine from documents (arrays of distinct buckets) and 0/1 labels, by Adam on the whole sample.

    Keeps the terms whose share differs most clearly between the labels, and those of `pair_terms`. Without documents, or of one
    label only, the score is that label's smoothed share everywhere.
    """
    n, toxic = len(labels), int(labels.sum())
    share = (toxic + 0.5) / (n + 1)
    empty = Machine(np.zeros(0, np.int64), float(np.log(share / (1 - share))), np.zeros(0), np.zeros((0, rank)))
    if not 0 < toxic < n:
        return empty
    rows = np.repeat(np.arange(n), [len(d) for d in documents])
    buckets = np.concatenate(documents)
    terms, columns = np.unique(buckets, return_inverse=True)
    with_ = np.bincount(columns, minlength=len(terms))
    among = np.bincount(columns, labels[rows], minlength=len(terms))
    p = with_ / n
    z = np.abs(among / toxic - (with_ - among) / (n - toxic)) / np.sqrt(np.maximum(p * (1 - p), 1e-12) * (1 / toxic + 1 / (n - toxic)))
    z[with_ < LEAST_DOCS] = 0
    chosen = np.sort(np.lexsort((terms, -z))[:MOST_TERMS])
    chosen = np.union1d(chosen[z[chosen] >= LEAST_Z], pair_terms(rows, columns, labels, len(terms)))
    if not len(chosen):
        return empty
    place = np.full(len(terms), -1)
    place[chosen] = np.arange(len(chosen))
    keep = place[columns] >= 0
    rows, columns = rows[keep], place[columns][keep]
    rng = np.random.default_rng(17)
    machine = Machine(terms[chosen], empty.bias, np.zeros(len(chosen)), rng.normal(0, 0.05, (len(chosen), rank)))
    balance = np.where(labels == 1, 0.5 / toxic, 0.5 / (n - toxic)) ** 0.5
    balance /= balance.sum()
    flat = np.concatenate(([machine.bias], machine.weights, machine.factors.ravel()))
    first, second = np.zeros_like(flat), np.zeros_like(flat)
    m = len(chosen)
    for t in range(1, rounds + 1):
        machine.bias, machine.weights, machine.factors = float(flat[0]), flat[1 : m + 1], flat[m + 1 :].reshape(m, rank)
        error = (1 / (1 + np.exp(-machine.raw(rows, columns, n))) - labels) * balance
        total = np.zeros((n, rank))
        np.add.at(total, rows, machine.factors[columns])
        weights = np.bincount(columns, error[rows], minlength=m)
        factors = np.zeros((m, rank))
        np.add.at(factors, columns, error[rows, None] * (total[rows] - machine.factors[columns]))
        slope = np.concatenate(([error.sum()], weights + DECAY / m * machine.weights, (factors + DECAY * machine.factors).ravel()))
        first, second = 0.9 * first + 0.1 * slope, 0.999 * second + 0.001 * slope**2
        flat = flat - RATE * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-9)
    machine.bias, machine.weights, machine.factors = float(flat[0]), flat[1 : m + 1].copy(), flat[m + 1 :].reshape(m, rank).copy()
    return machine


def learn(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> Machine:
    """A machine from a bounded sample of the labelled documents: those whose hash (of id and text) lies below a bound.

    The bound is set from the number of labelled rows, so that about `sample_rows` pass; equal rows count once,
    and never more than four times as many are taken. Rows with a null text, label or id are left out; of rows
    with one id, the sample's texts each count.
    """
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("id"), F.col("toxic").cast("int").alias("toxic")).distinct()
    texts = docs.where(F.col("text").isNotNull()).select(F.col("doc_id").alias("id"), "text")
    n = texts.select("id").join(known, "id").count()
    bound = int(min(1.0, sample_rows / max(n, 1)) * (1 << 30))

    def terms(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, data, at in text_slices(batches):
            row, bucket = terms_of(data, at)
            distinct = np.unique(row * BUCKETS + bucket)
            cuts = np.searchsorted(distinct, np.arange(rows.num_rows + 1) * BUCKETS)
            values = pa.ListArray.from_arrays(pa.array(cuts, pa.int32()), pa.array((distinct % BUCKETS).astype(np.int32)))
            yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(2), values], names=["id", "toxic", "terms"])

    some = texts.where(F.pmod(F.xxhash64("id", "text", F.lit(29)), F.lit(1 << 30)) < bound).dropDuplicates(["id", "text"])
    some = some.join(known, "id").select("id", "text", "toxic")
    sample = map_batches(some, terms, f"id {texts.schema['id'].dataType.simpleString()}, toxic int, terms array<int>").limit(4 * sample_rows)
    got = sample.toPandas().sort_values("id", kind="stable")
    got = got.assign(size=got["terms"].map(len)).sort_values(["id", "toxic", "size"], kind="stable")
    return fit([np.asarray(t, np.int64) for t in got["terms"]], got["toxic"].to_numpy(np.int64))


def score(docs: DataFrame, machine: Machine, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row: key, score, predicted. Texts are read whole; null and empty texts score by the bias alone."""
    shared = docs.sparkSession.sparkContext.broadcast(machine)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        place = np.full(BUCKETS, -1, np.int32)
        place[own.terms] = np.arange(len(own.terms))
        most = max(len(own.terms), 1)
        for rows, data, at in text_slices(batches):
            row, bucket = terms_of(data, at)
            column = place[bucket]
            keep = column >= 0
            distinct = np.unique(row[keep] * most + column[keep])
            value = 1 / (1 + np.exp(-np.clip(own.raw(distinct // most, distinct % most, rows.num_rows), -500, 500)))
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(value), pa.array((value >= 0.5).astype(np.int32))], names=["id", "score", "predicted"])

    source = docs.select(F.col(key).alias("id"), F.col(text).alias("text"))
    return map_batches(source, run, f"id {source.schema['id'].dataType.simpleString()}, score double, predicted int").withColumnRenamed("id", key)


def toxicity_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted: learnt from the labels of rows that are not held out, for all rows."""
    machine = learn(docs, labels.where(~crc_held_out()))
    return score(docs, machine).withColumn("held_out", crc_held_out()).select("doc_id", "held_out", "score", "predicted")

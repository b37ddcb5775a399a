"""Quality classification by nearest-neighbour voting over latent-semantic vectors.

A text's terms are its words (lower-cased in A-Z), its byte trigrams and the pairs of adjacent byte classes, each kind
hashed or counted into a fixed number of places, and words equal to the word before. Term frequencies of
labelled texts are weighted by inverse document frequency and reduced by a truncated singular value
decomposition; the labelled texts' unit vectors are broadcast. Every text is projected likewise, its cosines to
all labelled vectors are taken exactly, in blocks, and its nearest neighbours vote with their similarity as
weight.

The classifier is fitted on a bounded sample of the labelled rows (``MOST_LABELLED``, those with the
smallest hashed key), so what is broadcast has a fixed size. Scores are functions of the text alone.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import pick, table
from .memory import release

MOST_LABELLED = 4096
DIMENSIONS = 48
#: Places of word and of trigram terms, and the weights of the three kinds.
WORD_PLACES, TRIGRAM_PLACES = 1 << 13, 1 << 12
WORD_WEIGHT, TRIGRAM_WEIGHT, CLASS_WEIGHT = 0.6, 0.6, 1.0
#: Columns of the labelled texts' matrix that are made dense at once, and rounds of the subspace iteration.
COLUMNS, ROUNDS = 1024, 8
NEIGHBOURS = 5
#: Votes that the share of good labels counts besides the neighbours'.
PRIOR_VOTES = 0.5
THRESHOLD = 0.7
BLOCK = 512
#: Rows with this remainder of crc32(key as text) by FOLDS are held out.
FOLDS, HELD_OUT = 4, 2


def _byte_classes() -> np.ndarray:
    """A class for each byte: vowels and other letters by case, digits, white space, each kind of punctuation, lead and tail bytes of longer characters."""
    out = np.zeros(256, np.uint8)
    groups = ["aeiou", "bcdfghjklmnpqrstvwxyz", "AEIOU", "BCDFGHJKLMNPQRSTVWXYZ", "0123456789", " ", "\n", "\t\r\v\f", ".", ",", "!?", ";:", "'\"`", "()[]{}", "<>", "|", "-_", "/\\", "*", "#", "$%&@", "+=~^"]
    for i, g in enumerate(groups, 1):
        out[[ord(c) for c in g]] = i
    out[128:192] = len(groups) + 1
    out[192:] = len(groups) + 2
    return out


CLASSES = _byte_classes()
KINDS = int(CLASSES.max()) + 1
CLASS_TERMS = KINDS * KINDS + 1
TERMS = WORD_PLACES + TRIGRAM_PLACES + CLASS_TERMS
#: Letter values by byte and place in the word, whose sum is a word's hash.
_LETTERS = np.random.Generator(np.random.PCG64(41)).integers(1, 1 << 63, (16, 256)).astype(np.uint64)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


def term_counts(text: str | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Counts of word places, of trigram places, and of byte class pairs with, last, words equal to the word before, eight times."""
    words, trigrams, pairs = np.zeros(WORD_PLACES, np.float32), np.zeros(TRIGRAM_PLACES, np.float32), np.zeros(CLASS_TERMS, np.float32)
    data = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8) if text else np.empty(0, np.uint8)
    if len(data) > 1:
        kinds = CLASSES[data].astype(np.int16)
        pairs[:-1] = np.bincount(kinds[:-1] * KINDS + kinds[1:], minlength=CLASS_TERMS - 1)
        low = _LOWER[data]
        if len(low) > 2:
            three = low[:-2].astype(np.uint32) | low[1:-1].astype(np.uint32) << np.uint32(8) | low[2:].astype(np.uint32) << np.uint32(16)
            three *= np.uint32(2654435761)
            trigrams[:] = np.bincount(three >> np.uint32(32 - TRIGRAM_PLACES.bit_length() + 1), minlength=TRIGRAM_PLACES)
        at = np.flatnonzero(~_SPACE[low])
        if len(at):
            first = np.flatnonzero(np.concatenate([[True], np.diff(at) > 1]))
            size = np.diff(np.concatenate([first, [len(at)]]))
            place = np.arange(len(at)) - np.repeat(first, size)
            code = np.add.reduceat(_LETTERS[place & 15, low[at]] * (place // 16 * 2 + 1).astype(np.uint64), first)
            words[:] = np.bincount((code * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - WORD_PLACES.bit_length() + 1), minlength=WORD_PLACES)
            pairs[-1] = 8 * np.count_nonzero(code[1:] == code[:-1])
    return words, trigrams, pairs


def _frequencies(texts: list) -> np.ndarray:
    """Square roots of each kind's term frequencies, by weight, a row for each text; rows of texts without terms are zero."""
    out = np.zeros((len(texts), TERMS), np.float32)
    for row, text in zip(out, texts, strict=True):
        at = 0
        for counts, weight in zip(term_counts(text), (WORD_WEIGHT, TRIGRAM_WEIGHT, CLASS_WEIGHT), strict=True):
            total = counts.sum()
            if total:
                np.sqrt(counts / total, out=row[at : at + len(counts)])
                row[at : at + len(counts)] *= weight
            at += len(counts)
    return out


@dataclass
class Voter:
    axes: np.ndarray  # terms x dimensions, with the terms' weights
    vectors: np.ndarray  # labelled texts x dimensions, of unit length
    labels: np.ndarray
    prior: float

    def project(self, frequencies: np.ndarray) -> np.ndarray:
        z = frequencies @ self.axes
        return z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-9)

    def scores(self, texts: list) -> np.ndarray:
        out = np.full(len(texts), self.prior)
        k = min(NEIGHBOURS, len(self.labels))
        if not k:
            return out
        for i in range(0, len(texts), BLOCK):
            cosines = self.project(_frequencies(texts[i : i + BLOCK])) @ self.vectors.T
            near = np.argpartition(-cosines, k - 1, axis=1)[:, :k]
            weight = np.maximum(np.take_along_axis(cosines, near, axis=1), 0).astype(np.float64)
            votes = (weight * self.labels[near]).sum(axis=1) + PRIOR_VOTES * self.prior
            out[i : i + BLOCK] = votes / (weight.sum(axis=1) + PRIOR_VOTES)
        return np.clip(out, 0, 1)


def fit_voter(rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, dimensions: int = DIMENSIONS) -> Voter:
    """The voter of labelled texts' frequencies (places, values of each); without any, every score is one half.

    The leading singular vectors come from a subspace iteration on the texts' products, which are summed over
    blocks of terms, so the whole matrix is never dense.
    """
    n = len(rows)
    if not n:
        return Voter(np.zeros((TERMS, 1), np.float32), np.zeros((0, 1), np.float32), labels, 0.5)
    places, values = np.concatenate([p for p, _ in rows]), np.concatenate([v for _, v in rows])
    text = np.repeat(np.arange(n, dtype=np.int32), [len(p) for p, _ in rows])
    weights = (np.log((1 + n) / (1 + np.bincount(places, minlength=TERMS))) + 1).astype(np.float32)
    values = values * weights[places]
    order = np.argsort(places, kind="stable").astype(np.uint32)
    places, values, text = places[order], values[order], text[order]
    del order

    def block(at: int) -> np.ndarray:
        i, j = np.searchsorted(places, np.array([at, at + COLUMNS], places.dtype))
        out = np.zeros((n, min(COLUMNS, TERMS - at)), np.float32)
        out[text[i:j], places[i:j] - at] = values[i:j]
        return out

    gram = np.zeros((n, n), np.float32)
    for at in range(0, TERMS, COLUMNS):
        x = block(at)
        for i in range(0, n, BLOCK):  # some rows at a time, so that one such matrix is held and not two
            gram[i : i + BLOCK] += x[i : i + BLOCK] @ x.T
    k = min(n, dimensions)
    base = np.random.Generator(np.random.PCG64(3)).standard_normal((n, min(n, k + 16))).astype(np.float32)
    for _ in range(ROUNDS):
        base = np.linalg.qr(gram @ base)[0]
    small, turn = np.linalg.eigh((base.T @ gram @ base).astype(np.float64))
    lead = np.argsort(-small)[:k]
    left = (base @ turn[:, lead]).astype(np.float32) / np.sqrt(np.maximum(small[lead], 1e-9)).astype(np.float32)
    axes = np.concatenate([block(at).T @ left for at in range(0, TERMS, COLUMNS)])
    vectors = gram @ left
    vectors /= np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-9)
    return Voter(np.ascontiguousarray(axes * weights[:, None]), vectors, labels.astype(np.float64), float(labels.mean()))


def is_held_out(key: Column) -> Column:
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % FOLDS == HELD_OUT, F.lit(False))


def _with_frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i in range(0, batch.num_rows, BLOCK):
            part = batch.slice(i, BLOCK)
            rows = _frequencies(part.column("text").to_pylist())
            places = [np.flatnonzero(x) for x in rows]
            packed = [p.astype("<u2").tobytes() for p in places], [x[p].astype("<f4").tobytes() for x, p in zip(rows, places, strict=True)]
            yield pa.RecordBatch.from_arrays([part.column("label"), *(pa.array(c, pa.binary()) for c in packed)], names=["label", "places", "frequencies"])


def quality_scorer(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "quality", most: int = MOST_LABELLED) -> Callable[[Column], Column]:
    """A function from a text column to its score column (0 to 1; higher: label 1 likelier).

    Learns from rows of labels that are not held out and have a document; of more than ``most`` of
    them, those with the smallest hashed key. Null labels and keys are left out. A key with several labels counts with
    their mean, a key with several texts with the least of them. Null and empty texts, and all texts where there
    are no labels, score the prior.
    """
    learn = pick(labels, key, label).toDF("key", "label").filter("key is not null and label is not null").filter(~is_held_out(F.col("key")))
    rows = pick(docs, key, text).toDF("key", "text")
    known = learn.join(rows.select("key").distinct(), "key", "left_semi").groupBy("key").agg(F.avg("label").alias("label"))
    sample = known.orderBy(F.xxhash64("key"), "key").limit(most)
    texts = rows.join(F.broadcast(sample), "key").groupBy("key").agg(F.max("label").cast("double").alias("label"), F.min("text").alias("text"))
    found = texts.select("label", "text").mapInArrow(_with_frequencies, "label double, places binary, frequencies binary").collect()  # bounded by most
    found.sort(key=lambda r: (r["label"], bytes(r["places"]), bytes(r["frequencies"])))
    rows = [(np.frombuffer(r["places"], "<u2"), np.frombuffer(r["frequencies"], "<f4")) for r in found]
    fitted = fit_voter(rows, np.array([r["label"] for r in found]))
    del rows, found
    release()  # what fitting took is not kept from the driver's other work
    voter = docs.sparkSession.sparkContext.broadcast(fitted)

    @F.pandas_udf("double")
    def score(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        try:
            for batch in texts:
                yield pd.Series(voter.value.scores(batch.tolist()), dtype="float64")
        finally:
            release()

    return score


def scored_documents(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "quality", threshold: float = THRESHOLD) -> DataFrame:
    """key, held_out, score, predicted for each row of docs; see quality_scorer for what is learnt.

    Repeated rows and null keys are kept (null keys are not held out), extra columns are ignored, an empty table
    gives an empty result. Equal texts have equal scores.
    """
    score = quality_scorer(docs, labels, key, text, label)
    rows = pick(docs, key, text).toDF("key", "text")
    out = rows.select(F.col("key").alias(key), is_held_out(F.col("key")).alias("held_out"), score("text").alias("score"))
    return out.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def op4_latent_neighbour_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))

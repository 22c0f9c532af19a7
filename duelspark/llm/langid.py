"""Language identification: multinomial naive Bayes over hashed character n-grams.

Characters are lower-cased; all that isn't a letter counts as a space. N-grams of one to three characters that hold a letter are
hashed to `buckets` features. Training sums counts per language and feature with an ordinary aggregation, over at most about
`max_training` documents (a documented bound, met by a hash of doc_id); the log-probability matrix, buckets x languages, is
broadcast: its size does not grow with the data. Scoring gathers each document's rows of the matrix in numpy, in pieces of
`piece` characters.

Defined results: a null text, or one without a letter, is `und` with score 0; without any labelled document every text is
`und`. The language is that of the largest posterior; the score is its posterior with the evidence of a text counted as `evidence` n-grams at most
(n-grams are not independent, so raw posteriors would all be 0 or 1). Ties go to the language that sorts first.
Repeated rows are judged alike, an empty table gives an empty result, and other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import slices

UNKNOWN = "und"
SCHEMA = "doc_id long, held_out boolean, lang_pred string, score double"


@dataclass(frozen=True)
class Model:
    languages: tuple[str, ...]
    prior: np.ndarray
    #: languages x (buckets + 1); the last column, for n-grams without a letter, is zero
    weights: np.ndarray


@cache
def letters() -> np.ndarray:
    """For each code point whether it is a letter."""
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


def grams(lowered: list[str], buckets: int, over: list[int] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Feature of every n-gram of all texts (buckets where it has no letter, or where it begins in the overlap at a text's end), as an array of three orders, the offset of each text, and whether it has a letter."""
    lengths = np.fromiter((len(t) + 2 for t in lowered), np.int64, len(lowered))
    points = np.frombuffer("".join(t + "  " for t in lowered).encode("utf-32-le", "surrogatepass"), np.uint32)
    offsets = np.concatenate(([0], np.cumsum(lengths)[:-1]))
    alpha = letters()[points]
    c = np.where(alpha, points, 32).astype(np.uint32)
    after = np.concatenate((c[1:], np.full(2, 32, np.uint32)))
    is_after = np.concatenate((alpha[1:], np.zeros(2, bool)))
    shift = np.uint32(32 - (buckets.bit_length() - 1))
    a, b, d = np.uint32(2654435761), np.uint32(2246822519), np.uint32(3266489917)
    one = c * a
    two = one + after[:-1] * b + np.uint32(374761393)
    three = two + after[1:] * d + np.uint32(668265263)
    has2 = alpha | is_after[:-1]
    ids = np.empty((3, len(c)), np.int32)
    for row, mixed, has in zip(ids, (one, two, three), (alpha, has2, has2 | is_after[1:]), strict=True):
        mixed = (mixed ^ (mixed >> np.uint32(15))) * np.uint32(2246822519)
        row[:] = np.where(has, mixed >> shift, buckets)
    ends = offsets + lengths
    ids[:, np.concatenate((ends - 2, ends - 1))] = buckets  # what begins in the padding would reach into the next text
    for end, more in zip(ends, over or [], strict=False):
        if more:
            ids[:, end - 2 - more : end] = buckets
    return ids, offsets, np.add.reduceat(alpha, offsets, dtype=np.int64) > 0


def pieces(texts: list[str | None], size: int) -> Iterator[tuple[list[int], list[str], list[int]]]:
    """Positions, lower-cased texts and overlaps in groups of about `size` characters.

    A longer text is cut; a part holds two characters of the next one, whose n-grams count there, so none is lost or comes twice.
    """
    group: list[str] = []
    at: list[int] = []
    over: list[int] = []
    total = 0
    for i, text in enumerate(texts):
        if not text:
            continue
        for k in range(0, len(text), size):
            part, more = text[k : k + size].lower(), text[k + size : k + size + 2].lower()
            group.append(part + more)
            at.append(i)
            over.append(len(more))
            total += len(part)
            if total >= size:
                yield at, group, over
                group, at, over, total = [], [], [], 0
    if group:
        yield at, group, over


def held_out() -> Column:
    return F.crc32(F.col("doc_id").cast("string")) % 4 == 2


def train(documents: DataFrame, buckets: int = 1 << 14, max_training: int = 20_000, smoothing: float = 0.5, piece: int = 500_000) -> Model:
    """Counts n-grams of labelled documents that are not held out."""
    labelled = documents.select("doc_id", F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.coalesce(~held_out(), F.lit(False)))
    there = labelled.drop("text").count() if "text" in labelled.columns else 0
    share = min(1.0, max_training / max(1, there))
    sample = labelled.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_003)) < int(share * 1_000_003) + 1) if share < 1 else labelled

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        docs: dict[str, int] = {}
        for batch in slices(batches):
            langs = batch.column(1).to_pylist()
            for lang in langs:
                docs[lang] = docs.get(lang, 0) + 1
            for at, group, over in pieces(batch.column(0).to_pylist(), piece):
                ids, offsets, _ = grams(group, buckets, over)
                ends = np.append(offsets[1:], ids.shape[1])
                for i, start, end in zip(at, offsets, ends, strict=True):
                    got = np.bincount(ids[:, start:end].ravel(), minlength=buckets + 1)
                    sums[langs[i]] = sums.get(langs[i], 0) + got
        for lang, got in sums.items():
            got[buckets] = docs[lang]
            at = np.flatnonzero(got)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at)), pa.array(at, pa.int32()), pa.array(got[at], pa.int64())], names=["lang", "feature", "n"])

    summed = sample.select("text", "lang").mapInArrow(count, "lang string, feature int, n long").groupBy("lang", "feature").agg(F.sum("n").alias("n"))
    found = summed.toPandas()  # buckets x languages rows at most
    languages = tuple(sorted(found["lang"].unique()))
    if not languages:
        return Model((), np.zeros(0), np.zeros((0, buckets + 1)))
    counts = np.zeros((len(languages), buckets + 1))
    counts[found["lang"].map({x: i for i, x in enumerate(languages)}), found["feature"]] = found["n"]
    prior = np.log(counts[:, buckets] / counts[:, buckets].sum())
    counts = counts[:, :buckets] + smoothing
    weights = np.log(counts / counts.sum(axis=1, keepdims=True))
    return Model(languages, prior, np.hstack((weights, np.zeros((len(languages), 1)))))


def predict(texts: list[str | None], model: Model, evidence: int = 64, piece: int = 500_000) -> tuple[list[str], list[float]]:
    """Language and score of each text."""
    n = len(texts)
    sums, used, lettered = np.zeros((n, len(model.languages))), np.zeros(n), np.zeros(n, bool)
    buckets = model.weights.shape[1] - 1
    for at, group, over in pieces(texts, piece):
        ids, offsets, has = grams(group, buckets, over)
        at = np.asarray(at)
        np.logical_or.at(lettered, at, has)
        np.add.at(used, at, np.add.reduceat((ids != buckets).sum(axis=0), offsets))
        for k, row in enumerate(model.weights):
            got = row[ids[0]]
            got += row[ids[1]]
            got += row[ids[2]]
            np.add.at(sums[:, k], at, np.add.reduceat(got, offsets))
    if not model.languages:
        return [UNKNOWN] * n, [0.0] * n
    best = (sums + model.prior).argmax(axis=1)
    z = sums * np.minimum(1, evidence / np.maximum(1, used))[:, None] + model.prior
    p = np.exp(z - z.max(axis=1, keepdims=True))
    score = np.round(p[np.arange(n), best] / p.sum(axis=1), 6)
    return [model.languages[b] if h else UNKNOWN for b, h in zip(best, lettered, strict=True)], [float(s) if h else 0.0 for s, h in zip(score, lettered, strict=True)]


def identify(documents: DataFrame, model: Model, keep: DataFrame | None = None) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every document; the model is broadcast."""
    shared = documents.sparkSession.sparkContext.broadcast(model)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            langs, scores = predict(batch.column(2).to_pylist(), shared.value)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=[x.split()[0] for x in SCHEMA.split(", ")])

    wanted = documents.select(F.col("doc_id").cast("long"), F.coalesce(held_out(), F.lit(False)).alias("held_out"), F.col("text").cast("string"))
    return wanted.mapInArrow(judge, SCHEMA)


def accepted(documents: DataFrame, model: Model, least: float | None = None) -> DataFrame:
    """The documents, all columns, that have a language by at least this score, by default that of an even guess; `und` goes. Works on each row by itself, so repeated or null ids are no matter."""
    shared = documents.sparkSession.sparkContext.broadcast(model)
    names, least = documents.columns, 1 / max(1, len(model.languages)) if least is None else least

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            langs, scores = predict(batch.column(names.index("text")).cast(pa.string()).to_pylist(), shared.value)
            yield batch.filter(pa.array([x != UNKNOWN and s >= least for x, s in zip(langs, scores, strict=True)], pa.bool_()))

    return documents.mapInArrow(judge, documents.schema)

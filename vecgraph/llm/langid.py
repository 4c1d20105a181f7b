"""Language identification by string kernels with Nystroem landmarks.

The kernel of two texts is a blended spectrum: the number of character n-grams
(n from 1 to 3, of the lower-cased text, hashed to 2**18 bins) that both contain,
over the geometric mean of the numbers each contains. A few training texts of
each language are landmarks; kernel values with them, whitened by the landmarks'
own kernel matrix, are the features of a one-versus-rest kernel ridge
regression. A batch of texts is scored as the product of its presence matrix
with (landmark presence x coefficients), which is formed once.

Training reads a bounded sample for each language (a parameter). Ids, sources and
given languages are no inputs of a prediction.

Cases: a null text or one without a letter is ``und`` with score 0, as is every
text when there was nothing to train on. Repeated rows each get a row; an id
that repeats with several languages trains each of them; a null doc_id is in
fold 0; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from .common import checkpoint, fold, map_texts, read_table

FOLDS, HELD_OUT = 3, 1
UNKNOWN = "und"
TRAIN_PER_LANGUAGE = 300
#: Languages whose limits are broadcast; a table of more is joined by a shuffle.
MOST_LANGUAGES = 10_000
LANDMARKS_PER_LANGUAGE = 24
BINS = 18
RIDGE = 1e-2
#: Steepness of the score.
SCALE = 6.0
_LETTER = re.compile(r"[^\W\d_]")
_MIX = np.uint64(0x9E3779B97F4A7C15)
_STEPS = [np.uint64(x) for x in (0x2545F4914F6CDD1D, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD)]


def presence(text: str, bins: np.ndarray) -> None:
    """Mark the bins of the text's n-grams in ``bins`` (uint8, cleared by the caller)."""
    codes = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.uint64)
    shift = np.uint64(64 - BINS)
    gram = (codes + np.uint64(1)) * _STEPS[0]
    bins[(gram * _MIX) >> shift] = 1
    for n in (1, 2):
        if len(codes) <= n:
            break
        gram = (gram[:-1] ^ (gram[:-1] >> np.uint64(29))) * _STEPS[n] + codes[n:] + np.uint64(1)
        bins[(gram * _MIX) >> shift] = 1


class Model:
    """Languages, the bins that landmarks use, and their weights."""

    def __init__(self, languages: list[str], used: np.ndarray, weights: np.ndarray):
        self.languages, self.used, self.weights = languages, used, weights

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        names, scores = [UNKNOWN] * len(texts), [0.0] * len(texts)
        if not self.languages:
            return names, scores
        rows = [k for k, t in enumerate(texts) if t is not None and _LETTER.search(t)]
        bins = np.zeros(1 << BINS, dtype=np.uint8)
        for first in range(0, len(rows), 64):
            block = rows[first : first + 64]
            x = np.empty((len(block), len(self.used)), dtype=np.float32)
            sizes = np.empty(len(block))
            for i, k in enumerate(block):
                bins[:] = 0
                presence(texts[k], bins)
                x[i] = bins[self.used]
                sizes[i] = bins.sum(dtype=np.int64)
            s = (x @ self.weights) / np.sqrt(sizes)[:, None]
            e = np.exp(SCALE * (s - s.max(axis=1, keepdims=True)))
            best = s.argmax(axis=1)
            for i, k in enumerate(block):
                names[k], scores[k] = self.languages[best[i]], float(e[i, best[i]] / e[i].sum())
        return names, scores


def grams(text: str | None) -> np.ndarray:
    """The bins of the text's n-grams, in order; none without a letter."""
    if text is None or not _LETTER.search(text):
        return np.zeros(0, dtype=np.int32)
    bins = np.zeros(1 << BINS, dtype=np.uint8)
    presence(text, bins)
    return np.flatnonzero(bins).astype(np.int32)


def train(texts: list[str], labels: list[str], landmarks_each: int = LANDMARKS_PER_LANGUAGE, ridge: float = RIDGE) -> Model:
    return train_grams([grams(t) for t in texts], labels, landmarks_each, ridge)


def train_grams(rows: list[np.ndarray], labels: list[str], landmarks_each: int = LANDMARKS_PER_LANGUAGE, ridge: float = RIDGE) -> Model:
    """The model of texts given by their bins; the first of each language are its landmarks."""
    labels = [g for x, g in zip(rows, labels) if len(x)]
    rows = [x for x in rows if len(x)]
    counts = Counter(labels)
    languages = sorted(counts)
    if not languages:
        return Model([], np.zeros(0, dtype=np.int64), np.zeros((0, 0), dtype=np.float32))
    marks, taken = [], Counter()
    for x, g in zip(rows, labels):
        if taken[g] < landmarks_each:
            taken[g] += 1
            marks.append(x)
    used = np.unique(np.concatenate(marks))
    land = np.zeros((len(marks), len(used)), dtype=np.float32)
    for i, m in enumerate(marks):
        land[i, np.searchsorted(used, m)] = 1.0
    land /= np.sqrt([len(m) for m in marks])[:, None]
    kernel = np.empty((len(rows), len(marks)))
    bins = np.zeros(1 << BINS, dtype=np.float32)
    for i, x in enumerate(rows):
        bins[x] = 1
        kernel[i] = land @ bins[used] / np.sqrt(len(x))
        bins[x] = 0
    # Nystroem: features are kernel values whitened by the landmarks' own kernel.
    values, vectors = np.linalg.eigh((land @ land.T).astype(np.float64))
    white = vectors / np.sqrt(np.maximum(values, 1e-6))
    features = kernel @ white
    y = np.array([[1.0 if g == h else -1.0 for h in languages] for g in labels])
    # Every language weighs the same, however many rows it has.
    each = np.array([1.0 / counts[g] for g in labels])[:, None]
    gram = features.T @ (each * features)
    coefficients = np.linalg.solve(gram + ridge * np.eye(len(gram)) / len(rows), features.T @ (each * y))
    return Model(languages, used, (land.T.astype(np.float64) @ (white @ coefficients)).astype(np.float32))


def training_rows(docs: DataFrame, per_language: int) -> DataFrame:
    """(lang, h, bins): about ``2 * per_language`` (id, language) pairs at most of each language, those with the least hashes, with the bins of one of their texts.

    Hashes below a limit for each language choose the rows, so no language's rows
    meet in one task; a pair that repeats has the text with the least hash.
    """
    ids = docs.select("doc_id", "lang", "text").where("doc_id is not null and lang is not null").where(fold("doc_id", FOLDS) != HELD_OUT)
    h = F.shiftrightunsigned(F.xxhash64(F.lit(7), "doc_id", "lang"), 1)
    ids = ids.withColumn("h", h)
    sizes = ids.groupBy("lang").agg(F.approx_count_distinct("h", 0.02).alias("n"))
    limit = F.least(F.lit(1.0), 1.6 * per_language / F.col("n")) * F.lit(float(1 << 62)) * 2
    limits = checkpoint(sizes.select("lang", limit.alias("limit")))
    if limits.count() <= MOST_LANGUAGES:
        limits = F.broadcast(limits)
    near = ids.join(limits, "lang").where(F.col("h") <= F.col("limit"))
    one = near.groupBy("lang", "h").agg(F.min_by("text", F.xxhash64("text")).alias("text"))

    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([grams(t) for t in batch.column(2).to_pylist()], type=pa.list_(pa.int32()))], ["lang", "h", "bins"])

    return map_texts(one, ["lang", "h", "text"], work, "lang string, h bigint, bins array<int>")


def fit(docs: DataFrame, per_language: int = TRAIN_PER_LANGUAGE) -> Model:
    """Train on at most ``per_language`` ids of each language outside the held-out fold, those with the least hashes.

    The driver gets bins, at most 2**18 for a text however long it is.
    """
    kept: dict[str, list[tuple[int, list[int]]]] = {}
    for r in training_rows(docs, per_language).toLocalIterator():
        kept.setdefault(r.lang, []).append((r.h, r.bins))
        if len(kept[r.lang]) > 4 * per_language:
            kept[r.lang] = sorted(kept[r.lang])[:per_language]
    rows = sorted((h, g, bins) for g, own in kept.items() for h, bins in sorted(own)[:per_language])
    return train_grams([np.array(bins, dtype=np.int32) for _, _, bins in rows], [g for _, g, _ in rows])


def language_report(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, lang_pred, score: one row for each row of ``docs``."""

    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        names, scores = model.predict(batch.column(1).to_pylist())
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, type=pa.string()), pa.array(scores, type=pa.float64())], ["doc_id", "lang_pred", "score"])

    found = map_texts(docs, ["doc_id", "text"], work, "doc_id bigint, lang_pred string, score double")
    return found.select("doc_id", (fold("doc_id", FOLDS) == HELD_OUT).alias("held_out"), "lang_pred", "score")


def identify(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return language_report(docs, fit(docs))

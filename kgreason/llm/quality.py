"""Quality rules: counted rules, then a logistic regression over hashed word and character n-grams.

The regression is trained on labelled rows (good: of high quality and not toxic; at most ``max_rows`` of them and ``max_cells``
features in all), a quarter of which is held back to calibrate its probability (Platt's two parameters); documents
are scored in Arrow batches against fixed thresholds.

Defined results: null text has no words and fails the rules; repeated labels of a document are merged (lowest
quality, highest toxicity); without labels of both kinds, and a feature that stands in enough labelled rows, the regression keeps what the rules keep; repeated rows
are each scored; an empty table gives an empty table; further columns are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow, mix64, slices, table
from .features import Rows, Scorer, evidence, learnable, scaled
from .ordinal import MAX_CELLS, _sigmoid, collect_rows, graded_labels, labelled_sample

MAX_ROWS = 12_000
MIN_WORDS, MAX_REPEAT_PERCENT, WINDOW = 20, 30, 8
MIN_PROBABILITY = 0.5

_SYMBOL = re.compile(r"[#*$%&|<>]")
_WORD = re.compile(r"[^\x20\x09-\x0D]")


def rule_counts(text: str | None, window: int = WINDOW) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    text = text or ""
    words = text.encode("utf-8", "surrogatepass").split()
    chars = len(text) - sum(text.count(c) for c in " \t\n\x0b\x0c\r")
    seen: set[str] = set()
    dup = 0
    lines = text.split("\n")
    if len(lines) > 1:
        for line in lines:
            if line in seen:
                dup += bool(_WORD.search(line))
            else:
                seen.add(line)
    repeat = 0
    if len(words) > window:
        h = mix64(np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words)))
        n = len(words) - window + 1
        own = np.zeros(n, np.uint64)
        for j in range(window):
            own = own * np.uint64(0x9E3779B97F4A7C15) + h[j : j + n]
            own ^= own >> np.uint64(29)
        order = np.argsort(own)
        same = own[order][1:] == own[order][:-1]
        if same.any():
            twice = np.zeros(n, bool)
            twice[order[1:][same]] = True
            twice[order[:-1][same]] = True
            edge = np.zeros(len(words) + 1, np.int64)
            at = np.flatnonzero(twice)
            np.add.at(edge, at, 1)
            np.add.at(edge, at + window, -1)
            repeat = int((np.cumsum(edge) > 0).sum())
    return len(words), chars, len(_SYMBOL.findall(text)), dup, repeat


def base_failed(n_words: int, n_repeat: int) -> bool:
    return n_words < MIN_WORDS or 100 * n_repeat > MAX_REPEAT_PERCENT * n_words


@dataclass
class Logistic:
    scorer: Scorer
    slope: float  # calibrated probability: sigmoid(slope * score + shift)
    shift: float

    def probability(self, scores: np.ndarray) -> np.ndarray:
        return _sigmoid(self.slope * np.asarray(scores, dtype=np.float64) + self.shift)


def _weights(rows: Rows, good: np.ndarray, size: int, rng: np.random.Generator, epochs: int, batch: int, rate: float, decay: float) -> tuple[np.ndarray, float]:
    """Weights and bias by minibatch steps scaled by past gradients."""
    w, gw, bias, gb = np.zeros(size), np.full(size, 1e-8), 0.0, 1e-8
    for _ in range(epochs):
        own = rng.permutation(len(good))
        for i in range(0, len(own), batch):
            at = own[i : i + batch]
            part = rows.take(at)
            err = good[at] - _sigmoid(part.dot(w) + bias)
            g = part.back(err, size) / len(at) - decay * w
            gw += g * g
            w += rate * g / np.sqrt(gw)
            gb += err.mean() ** 2
            bias += 0.1 * err.mean() / np.sqrt(gb)
    return w, bias


def calibrate(scores: np.ndarray, good: np.ndarray) -> tuple[float, float]:
    """Platt's slope and shift by Newton steps; targets a little inside 0 and 1 keep the slope finite."""
    hi, lo = (good.sum() + 1) / (good.sum() + 2), 1 / (len(good) - good.sum() + 2)
    t, ab = np.where(good > 0, hi, lo), np.array([1.0, 0.0])
    x = np.stack((scores, np.ones(len(scores))), axis=1)
    for _ in range(50 if len(good) else 0):
        p = _sigmoid(x @ ab)
        grad, hess = x.T @ (t - p), (x * (p * (1 - p))[:, None]).T @ x + 1e-6 * np.eye(2)
        step = np.linalg.solve(hess, grad)
        ab = ab + np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return (float(ab[0]), float(ab[1])) if ab[0] > 0 else (1.0, 0.0)  # too few held rows to tell


def fit_logistic(rows: Rows, good: np.ndarray, epochs: int = 30, batch: int = 128, rate: float = 0.5, decay: float = 1e-5, seed: int = 1) -> Logistic:
    """Fits three quarters of the rows and calibrates on the rest, then fits all rows for the weights that the calibration is applied to."""
    rng = np.random.default_rng(seed)

    def fitted(own: Rows, y: np.ndarray) -> tuple[Scorer, float]:
        scale = evidence(own, y.astype(np.int64), 2)
        own, features = scaled(own, scale)
        w, bias = _weights(own, y, len(features), rng, epochs, batch, rate, decay)
        return Scorer.of(w, features, scale), bias

    order = rng.permutation(len(good))
    held, rest = order[: len(order) // 4], order[len(order) // 4 :]
    part, bias = fitted(rows.take(rest), good[rest])
    own = rows.take(held)
    value = own.value * part.scale[own.index]
    owner = np.repeat(np.arange(len(held)), own.sizes())
    length = np.sqrt(np.bincount(owner, weights=value * value, minlength=len(held)))
    score = np.bincount(owner, weights=value * part.weights[own.index], minlength=len(held)) / np.where(length > 0, length, 1)
    slope, shift = calibrate(score + bias, good[held])
    whole, bias = fitted(rows, good)
    return Logistic(whole, slope, slope * bias + shift)


def train(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS, max_cells: int = MAX_CELLS) -> Logistic | None:
    rows, grades = collect_rows(labelled_sample(docs, graded_labels(labels), max_rows, max_cells))
    good = (grades == 2).astype(np.float64)
    return fit_logistic(rows, good) if 0 < good.sum() < len(good) and learnable(rows) else None


def apply_rules(docs: DataFrame, model: Logistic | None, min_probability: float = MIN_PROBABILITY) -> DataFrame:
    """doc_id, the counts, base_failed, kept and the calibrated probability of every row."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]

    def scan(batches):
        model = sent.value
        for batch in batches:
            for part in slices(batch):
                texts = part.column(1).to_pylist()
                counts = [rule_counts(t) for t in texts]
                failed = np.array([base_failed(c[0], c[4]) for c in counts], bool)
                p = np.ones(len(texts))
                if model is not None:
                    p = model.probability(model.scorer.scores(texts))
                cols = [pa.array([c[j] for c in counts], pa.int64()) for j in range(5)]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), *cols, pa.array(failed), pa.array(~failed & (p >= min_probability)), pa.array(p)], ["doc_id", *names, "base_failed", "kept", "probability"]
                )

    schema = "doc_id bigint, " + ", ".join(f"{n} bigint" for n in names) + ", base_failed boolean, kept boolean, probability double"
    return arrow(docs.select(F.col("doc_id").cast("bigint"), "text"), scan, schema)


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return apply_rules(docs, train(docs, table(spark, sf_dir, "labels")))

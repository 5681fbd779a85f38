"""Quality classifier: ordinal cumulative-link regression on graded ratings.

P(grade <= k) = sigmoid(threshold_k - w.x): one weight vector over hashed text for all grades, and ordered
thresholds.  Grades are made of the labelled rows: 0 toxic, 1 of low quality, 2 good.  The model is fitted on
a bounded sample of the labelled rows (``max_rows`` documents and ``max_cells`` features in all, by hash of the id, the same at
every size); all documents are scored in Arrow batches.

Defined results: null and empty texts have no features, score by the thresholds alone; repeated labels of a
document are merged (lowest quality, highest toxicity); labels that are null are left out; of rows repeating a
doc_id one trains the model, each is scored; without labels of two grades, and a feature that stands in enough labelled rows, there is
no model and everything is kept with the top grade; an empty table gives an empty table; further columns pass through, one that has the name of an added
column as ``input_<name>``.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow, materialize, slices, spare, table
from .features import Rows, Scorer, evidence, hashed, learnable, scaled

MAX_ROWS = 12_000
MAX_CELLS = 10_000_000  # features of all training rows together, 8 bytes each on the driver
GRADES = 3
MIN_TAIL = 0.5  # P(top grade) from which a document is kept


def graded_labels(labels: DataFrame) -> DataFrame:
    """(doc_id, grade) of (doc_id, quality, toxic)."""
    own = labels.where("doc_id is not null and (quality is not null or toxic is not null)").groupBy("doc_id").agg(F.min("quality").alias("q"), F.max("toxic").alias("t"))
    return own.select("doc_id", F.when(F.coalesce("t", F.lit(0)) >= 1, 0).when(F.coalesce("q", F.lit(1)) < 1, 1).otherwise(2).alias("grade"))


def labelled_sample(docs: DataFrame, graded: DataFrame, max_rows: int = MAX_ROWS, max_cells: int = MAX_CELLS) -> DataFrame:
    """(doc_id, y, index, value) of labelled documents, those of the smallest hashes: at most max_rows of them, and as many as have max_cells features together.

    Only the ids and sizes of those rows, max_rows at most, come to the driver to find where the second bound lies.
    """
    chosen = graded.select(F.col("doc_id").cast("bigint").alias("id"), F.col("grade").cast("int").alias("y"))
    chosen = chosen.withColumn("place", F.xxhash64("id")).orderBy("place", "id").limit(max_rows)
    rows = docs.select(F.col("doc_id").cast("bigint").alias("id"), "text").where("text is not null").join(F.broadcast(chosen), "id")
    one = rows.groupBy("id", "y", "place").agg(F.min_by("text", F.xxhash64("text")).alias("text"))

    def scan(batches):
        for batch in batches:
            for part in slices(batch):
                if part.num_rows:
                    own = [hashed(t) for t in part.column(3).to_pylist()]
                    yield pa.RecordBatch.from_arrays(
                        [part.column(0), part.column(1), part.column(2), pa.array([len(i) for i, _ in own], pa.int64()), pa.array([i for i, _ in own], pa.list_(pa.int32())), pa.array([v for _, v in own], pa.list_(pa.float32()))],
                        ["doc_id", "y", "place", "cells", "index", "value"],
                    )

    found = materialize(arrow(one.select("id", "y", "place", "text"), scan, "doc_id bigint, y int, place bigint, cells bigint, index array<int>, value array<float>"), "labelled")
    sizes = sorted((r["place"], r["doc_id"], r["cells"]) for r in found.select("place", "doc_id", "cells").collect())
    total = np.cumsum([c for _, _, c in sizes])
    fit = int((total <= max_cells).sum()) if len(sizes) else 0
    if fit < len(sizes):
        place, doc_id, _ = sizes[fit]
        found = found.where((F.col("place") < place) | ((F.col("place") == place) & (F.col("doc_id") < doc_id)))
    return found.select("doc_id", "y", "index", "value")


#: Parts in which training rows come to the driver, so that few of them are there twice at a time.
PARTS = 8


def collect_rows(sample: DataFrame) -> tuple[Rows, np.ndarray]:
    """The rows of a labelled sample, by doc_id, and their grades; part by part into arrays of the final size."""
    got = sample.select("doc_id", "y", F.size("index").alias("n")).toArrow()
    if not got.num_rows:
        return Rows.of([]), np.zeros(0, np.int64)
    order = np.argsort(got["doc_id"].to_numpy(), kind="stable")
    ids, y, ends = got["doc_id"].to_numpy()[order], got["y"].to_numpy()[order], np.cumsum(got["n"].to_numpy()[order].astype(np.int64))
    index, value = np.empty(int(ends[-1]), np.int32), np.empty(int(ends[-1]), np.float32)
    for part in range(PARTS):
        got = sample.where(F.pmod(F.xxhash64("doc_id"), F.lit(PARTS)) == part).select("doc_id", "index", "value").toArrow()
        for batch in got.to_batches():
            at = np.searchsorted(ids, batch.column(0).to_numpy())
            for name, target in ((1, index), (2, value)):
                flat, cuts = batch.column(name).values.to_numpy(), batch.column(name).offsets.to_numpy()
                for k, a, b in zip(at, cuts, cuts[1:], strict=False):
                    target[ends[k] - (b - a) : ends[k]] = flat[a:b]
        del got
        pa.default_memory_pool().release_unused()
    return Rows(index, value, ends), y


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -35, 35)))


@dataclass
class Ordinal:
    scorer: Scorer
    thresholds: np.ndarray  # ascending, one fewer than grades

    def tails(self, scores: np.ndarray) -> np.ndarray:
        """P(grade > k), one column for each threshold."""
        return _sigmoid(np.asarray(scores)[:, None] - self.thresholds[None, :])


def grade_terms(scores: np.ndarray, grades: np.ndarray, thresholds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(p, up, low): probability of each row's grade, and the derivatives of its logarithm by its upper and its lower threshold (the latter negated)."""
    edge = np.concatenate(([-np.inf], thresholds, [np.inf]))
    above, below = _sigmoid(edge[grades + 1] - scores), _sigmoid(edge[grades] - scores)
    above, below = np.where(grades == len(thresholds), 1.0, above), np.where(grades == 0, 0.0, below)
    p = np.maximum(above - below, 1e-9)
    return p, above * (1 - above) / p, below * (1 - below) / p


def fit_ordinal(rows: Rows, grades: np.ndarray, n_grades: int = GRADES, epochs: int = 30, batch: int = 128, rate: float = 0.5, decay: float = 1e-5, seed: int = 1) -> Ordinal:
    """Minibatch gradient ascent of the likelihood, with steps scaled by past gradients; gaps between thresholds stay positive as exponentials."""
    scale = evidence(rows, grades, n_grades)
    rows, features = scaled(rows, scale)
    rng, size = np.random.default_rng(seed), len(features)
    w, gw = np.zeros(size), np.full(size, 1e-8)
    share = np.cumsum(np.bincount(grades, minlength=n_grades) + 1.0)[:-1] / (len(grades) + n_grades)
    cut = np.log(share / (1 - share))
    first, gaps = cut[0], np.log(np.maximum(np.diff(cut), 1e-2))
    gt = np.full(n_grades - 1, 1e-8)
    for _ in range(epochs):
        order = rng.permutation(len(grades))
        for i in range(0, len(order), batch):
            at = order[i : i + batch]
            part, y = rows.take(at), grades[at]
            theta = first + np.concatenate(([0.0], np.cumsum(np.exp(gaps))))
            _, up, low = grade_terms(part.dot(w), y, theta)
            g = part.back(low - up, size) / len(at) - decay * w
            gw += g * g
            w += rate * g / np.sqrt(gw)
            by_threshold = np.array([(up[y == k].sum() - low[y == k + 1].sum()) / len(at) for k in range(n_grades - 1)])
            d = np.concatenate(([by_threshold.sum()], [by_threshold[k + 1 :].sum() * np.exp(gaps[k]) for k in range(n_grades - 2)]))
            gt += d * d
            step = 0.1 * d / np.sqrt(gt)
            first, gaps = first + step[0], gaps + step[1:]
    return Ordinal(Scorer.of(w, features, scale), first + np.concatenate(([0.0], np.cumsum(np.exp(gaps)))))


def train(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS, max_cells: int = MAX_CELLS) -> Ordinal | None:
    rows, grades = collect_rows(labelled_sample(docs, graded_labels(labels), max_rows, max_cells))
    if len(set(grades.tolist())) < 2 or not learnable(rows):
        return None
    own = [rows]
    del rows  # so that the fit can let go of them
    return fit_ordinal(own.pop(), grades)


ADDED = ("expected_grade", "tail_probability", "quality_kept")


def score(docs: DataFrame, model: Ordinal | None, min_tail: float = MIN_TAIL) -> DataFrame:
    """docs with expected_grade, tail_probability (of the top grade) and quality_kept added."""
    docs = spare(docs, ADDED)
    schema = docs.withColumns({"expected_grade": F.lit(0.0), "tail_probability": F.lit(0.0), "quality_kept": F.lit(True)}).schema
    for f in schema.fields:
        f.nullable = True
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def scan(batches):
        model = sent.value
        for batch in batches:
            for part in slices(batch):
                names = part.schema.names
                texts = part.column(names.index("text")).to_pylist()
                tails = np.ones((len(texts), GRADES - 1)) if model is None else model.tails(model.scorer.scores(texts))
                arrays = [part.column(i) for i in range(len(names))]
                arrays += [pa.array(tails.sum(axis=1)), pa.array(tails[:, -1]), pa.array(tails[:, -1] >= min_tail)]
                yield pa.RecordBatch.from_arrays(arrays, [*names, *ADDED])

    return arrow(docs, scan, schema)


def op7_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs, table(spark, sf_dir, "labels"))
    return score(docs, model).select("doc_id", "expected_grade", "tail_probability", F.col("quality_kept").alias("kept"))

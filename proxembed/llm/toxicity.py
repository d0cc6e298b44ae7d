"""Toxicity by cumulative-link ordinal regression on sparse text features.

P(grade <= k) = sigmoid(theta_k - w . x): one weight vector for all thresholds, thetas in order (theta_k is the one before
plus an exponential). The expected severity is the sum over k of P(grade > k). Features are hashed lower-case words of
the whole text and the first six bytes of longer ones, present or not; those whose log-odds of the labels are more than two
standard errors from zero, over five rows or more, are used.

The labels say toxic or not; severity grades come from them by cross-fitting: 0 for non-toxic texts, and 1 to 3 for toxic
ones by the third of the toxic texts' log-odds that a two-grade model gives them which was fitted on the other half of the
rows. No row's grade thus rests on a model that saw its label.

The point of rejection is set on a quarter of the fitting rows that a first fit does not see.

The fit uses at most `fit_rows` labelled documents, those with the smallest hash of doc_id: a documented bound, so fitting
costs the same at any size. Words are hashed and counted by class in the executors; the driver sees the features chosen and,
for each fitting row, which of them it holds. Scoring reads every text whole.

Defined cases: null and empty texts have no features and get the base rate; rows without doc_id are scored, never used to
fit; null labels are not used, of several labels of a document the largest counts, and of several texts of one id that with
the largest features; repeated rows are scored alike; with no labelled toxic rows every severity is 0; an empty table gives an
empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from proxembed.llm.common import forget, spread, store, table
from proxembed.llm.textkernel import letter_table, string_chunks, word_hashes

FIT_ROWS = 12_000
PREFIX_BYTES = 6
BUCKET_BITS = 20
GRADES = 4


@dataclass
class OrdinalModel:
    """buckets: the features, sorted; weights: theirs; thetas: rising thresholds; texts with P(grade > 0) >= reject are rejected."""

    buckets: np.ndarray
    weights: np.ndarray
    thetas: np.ndarray
    reject: float = 0.5

    def _table(self) -> np.ndarray:
        full = np.zeros(1 << BUCKET_BITS)
        full[self.buckets] = self.weights
        return full

    def scores(self, column: pa.Array) -> np.ndarray:
        """w . x of each text."""
        full = self._table()
        known = full != 0
        return np.array([float(full[f].sum()) for _, f in features_of(column, known)])

    def sums(self, rows: list[np.ndarray], buckets: np.ndarray) -> np.ndarray:
        """w . x of rows given as places in `buckets`."""
        full = self._table()[buckets]
        return np.array([full[r].sum() for r in rows])

    def severity(self, score: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(expected grade, P(grade > 0)) of w . x values."""
        above = 1 / (1 + np.exp(np.clip(self.thetas[None, :] - score[:, None], -50, 50)))
        return above.sum(axis=1), above[:, 0]


def features_of(column: pa.Array, known: np.ndarray | None = None) -> Iterator[tuple[int, np.ndarray]]:
    """(row, sorted distinct word buckets); `known` leaves only buckets it marks."""
    letters = letter_table()
    for first, data, offsets in string_chunks(column):
        words, at = word_hashes(data, offsets, letters, PREFIX_BYTES)
        at = at - at[0]
        row = np.repeat(np.arange(len(at) - 1), np.diff(at))
        headed = words[1] != 0
        buckets = (np.concatenate((words[0], words[1][headed])) >> np.uint64(64 - BUCKET_BITS)).astype(np.int64)
        row = np.concatenate((row, row[headed]))
        if known is not None:
            keep = known[buckets]
            buckets, row = buckets[keep], row[keep]
        both = np.unique((row << BUCKET_BITS) | buckets)
        cut = np.searchsorted(both >> BUCKET_BITS, np.arange(len(at)))
        both &= (1 << BUCKET_BITS) - 1
        for k in range(len(at) - 1):
            yield first + k, both[cut[k] : cut[k + 1]]


def fit_ordinal(rows: list[np.ndarray], grade: np.ndarray, columns: int, rounds: int = 300, ridge: float = 1e-3, rate: float = 0.1) -> tuple[np.ndarray, np.ndarray]:
    """Maximum likelihood with a ridge, by full-batch Adam from zero weights; deterministic."""
    flat = np.concatenate(rows) if rows else np.zeros(0, dtype=np.int64)
    owner = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
    levels = int(grade.max()) if len(grade) else 0
    share = np.array([(grade <= k).mean() for k in range(levels)]).clip(1e-4, 1 - 1e-4)
    start = np.log(share / (1 - share))
    raw = np.concatenate((start[:1], np.log(np.maximum(np.diff(start), 1e-2))))
    p = np.concatenate((np.zeros(columns), raw))
    m, v = np.zeros_like(p), np.zeros_like(p)
    upto = (grade[:, None] <= np.arange(levels)[None, :]).astype(float)
    for t in range(1, rounds + 1):
        w, r = p[:columns], p[columns:]
        theta = np.cumsum(np.concatenate((r[:1], np.exp(r[1:]))))
        score = np.bincount(owner, weights=w[flat], minlength=len(rows))
        cum = 1 / (1 + np.exp(-np.clip(theta[None, :] - score[:, None], -30, 30)))
        full = np.concatenate((np.zeros((len(rows), 1)), cum, np.ones((len(rows), 1))), axis=1)
        own = np.maximum(np.take_along_axis(full, grade[:, None] + 1, 1) - np.take_along_axis(full, grade[:, None], 1), 1e-12)[:, 0]
        slope = cum * (1 - cum)
        hi = np.arange(levels)[None, :] == grade[:, None]
        lo = np.arange(levels)[None, :] == grade[:, None] - 1
        d_theta = slope * (hi.astype(float) - lo) / own[:, None]
        g_theta = -d_theta.mean(axis=0)
        g_score = d_theta.sum(axis=1) / len(rows)
        g_w = np.bincount(flat, weights=g_score[owner], minlength=columns) + ridge * w
        tail = np.cumsum(g_theta[::-1])[::-1]
        g = np.concatenate((g_w, tail[:1], tail[1:] * np.exp(r[1:])))
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        p = p - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    r = p[columns:]
    return p[:columns], np.cumsum(np.concatenate((r[:1], np.exp(r[1:]))))


#: Counts of a feature: rows that hold it, by label and by whether the row is held back.
COUNTS = "bucket long, clean long, toxic long, clean_held long, toxic_held long"


def labelled_words(docs: DataFrame, labels: DataFrame, fit_rows: int) -> DataFrame:
    """(doc_id, toxic, buckets) of at most `fit_rows` labelled documents; buckets are packed 32-bit word ids."""
    picked = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    picked = picked.orderBy(F.xxhash64("doc_id"), "doc_id").limit(fit_rows)
    texts = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").select("doc_id", "toxic", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [f.astype("<i4").tobytes() for _, f in features_of(batch.column(2))]
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), batch.column(1).cast(pa.int32()), pa.array(found, pa.binary())], names=["doc_id", "toxic", "buckets"])

    words = texts.mapInArrow(run, "doc_id long, toxic int, buckets binary")
    return words.groupBy("doc_id").agg(F.max(F.struct("toxic", "buckets")).alias("w")).select("doc_id", "w.*")


def feature_counts(rows: DataFrame) -> DataFrame:
    """(toxic, held, buckets) -> COUNTS, summed inside a task before they are shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((4, 1 << BUCKET_BITS), dtype=np.int64)
        for batch in batches:
            for toxic, held, buckets in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                counts[(toxic != 0) + 2 * held, np.frombuffer(buckets, dtype="<i4")] += 1
        seen = np.flatnonzero(counts.any(axis=0))
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (seen, *counts[:, seen])], names=[c.split()[0] for c in COUNTS.split(", ")])

    found = rows.select("toxic", "held", "buckets").mapInArrow(run, COUNTS)
    return found.groupBy("bucket").agg(*[F.sum(c).alias(c) for c in ("clean", "toxic", "clean_held", "toxic_held")])


def _stands_out(toxic: Column, clean: Column, toxics: int, cleans: int, least_rows: int = 5) -> Column:
    """Whether the log-odds of a feature are more than two standard errors from zero."""
    a, b = toxic + F.lit(0.5), clean + F.lit(0.5)
    odds = F.log(a / F.greatest(F.lit(0.5), F.lit(toxics + 1) - a)) - F.log(b / F.greatest(F.lit(0.5), F.lit(cleans + 1) - b))
    return (toxic + clean >= least_rows) & (F.abs(odds) > 2 * F.sqrt(1 / a + 1 / b))


def fit_toxicity(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS) -> OrdinalModel:
    """Fit on at most `fit_rows` labelled documents."""
    held = F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(4)) == 0
    words = store(labelled_words(docs, labels, fit_rows).withColumn("held", held), "labelled-words")
    n = {(bool(r["toxic"]), r["held"]): r["count"] for r in words.select((F.col("toxic") != 0).alias("toxic"), "held").groupBy("toxic", "held").count().collect()}  # 4 rows
    count = lambda toxic, *holds: sum(n.get((toxic, h), 0) for h in holds)
    if not count(True, True, False):
        forget(words)
        return OrdinalModel(np.zeros(0, dtype=np.int64), np.zeros(0), np.full(GRADES - 1, 50.0))
    # With no toxic row on one side of the split, all rows fit and the point of rejection is even odds.
    split = bool(count(True, True) and count(True, False))
    first = _stands_out(F.col("toxic"), F.col("clean"), count(True, False), count(False, False))
    whole = _stands_out(F.col("toxic") + F.col("toxic_held"), F.col("clean") + F.col("clean_held"), count(True, True, False), count(False, True, False))
    chosen = feature_counts(words).select("bucket", first.alias("first"), whole.alias("whole")).where("first or whole").orderBy("bucket").toPandas()
    buckets, in_first, in_whole = (chosen[c].to_numpy() for c in ("bucket", "first", "whole"))
    def narrow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = np.full(1 << BUCKET_BITS, -1, dtype=np.int32)
        place[buckets] = np.arange(len(buckets))
        for batch in batches:
            found = [(x[x >= 0]).astype("<i4").tobytes() for x in (place[np.frombuffer(b, dtype="<i4")] for b in batch.column(3).to_pylist())]
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(3)), pa.array(found, pa.binary())], names=["doc_id", "toxic", "held", "features"])

    got = words.select("doc_id", "toxic", "held", "buckets").mapInArrow(narrow, "doc_id long, toxic int, held boolean, features binary").orderBy("doc_id").toPandas()  # fit_rows rows of chosen features
    forget(words)
    rows = [np.frombuffer(f, dtype="<i4") for f in got["features"]]
    toxic, held_back = got["toxic"].to_numpy() != 0, got["held"].to_numpy()
    grade = severity_grades(rows, toxic, len(buckets))
    reject = 0.5
    if split:
        model = _fit(rows, grade, ~held_back, buckets, in_first)
        p = model.severity(model.sums([r for r, h in zip(rows, held_back, strict=True) if h], buckets))[1]
        reject = reject_point(p, toxic[held_back])
    model = _fit(rows, grade, np.ones(len(rows), dtype=bool), buckets, in_whole)
    return OrdinalModel(model.buckets, model.weights, model.thetas, reject)


def severity_grades(rows: list[np.ndarray], toxic: np.ndarray, columns: int) -> np.ndarray:
    """0 for clean rows; 1 to 3 for toxic ones by thirds of the log-odds that the model of the other half of the rows gives them."""
    half = np.arange(len(rows)) % 2
    odds = np.zeros(len(rows))
    for k in (0, 1):
        fit, seen = np.flatnonzero(half != k), np.flatnonzero(half == k)
        if toxic[fit].any() and not toxic[fit].all():
            weights, _ = fit_ordinal([rows[i] for i in fit], toxic[fit].astype(np.int64), columns, rounds=100)
            odds[seen] = [weights[rows[i]].sum() for i in seen]
    order = np.argsort(np.argsort(odds[toxic], kind="stable"), kind="stable")
    grade = np.zeros(len(rows), dtype=np.int64)
    grade[toxic] = 1 + order * (GRADES - 1) // max(1, int(toxic.sum()))
    return grade


def reject_point(p: np.ndarray, toxic: np.ndarray, beta: float = 0.5) -> float:
    """The largest of some probabilities with the best F-measure, precision counting twice as much as recall."""
    best, at = -1.0, 0.5
    for x in (0.5, 0.4, 0.3, 0.25, 0.2, 0.15, 0.1):
        said = p >= x
        hit = int((said & toxic).sum())
        f = (1 + beta**2) * hit / max(1e-9, beta**2 * int(toxic.sum()) + int(said.sum()))
        if f > best + 1e-9:
            best, at = f, x
    return at


def _fit(rows: list[np.ndarray], grade: np.ndarray, use: np.ndarray, buckets: np.ndarray, chosen: np.ndarray) -> OrdinalModel:
    """The model of the rows and features used."""
    index = np.where(chosen, np.cumsum(chosen) - 1, -1)
    own = [x[x >= 0] for x in (index[r] for r, u in zip(rows, use, strict=True) if u)]
    weights, thetas = fit_ordinal(own, grade[use], int(chosen.sum()))
    return OrdinalModel(buckets[chosen], weights, thetas)


def score_toxicity(docs: DataFrame, model: OrdinalModel) -> DataFrame:
    """(doc_id, text) -> (doc_id, severity, p_toxic) for every row."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = model.scores(batch.column(1))
            severity, p = model.severity(score) if len(score) else (score, score)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(severity, pa.float64()), pa.array(p, pa.float64())], names=["doc_id", "severity", "p_toxic"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, severity double, p_toxic double")


def op8_ordinal_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = fit_toxicity(docs, table(spark, sf_dir, "labels"))
    return score_toxicity(spread(docs), model).withColumn("rejected", F.col("p_toxic") >= F.lit(model.reject))


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with P(grade > 0) at the model's point of rejection or above go; the score is a column of the row, so texts are not joined."""
    model = fit_toxicity(docs, table(spark, sf_dir, "labels"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = model.scores(batch.column(batch.schema.get_field_index("text")))
            yield batch.filter(pa.array(model.severity(score)[1] < model.reject)) if batch.num_rows else batch

    return docs.mapInArrow(run, docs.schema)

"""Quality: one-vs-rest logistic regression on embeddings, Micro- and Macro-F1."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxembed.functions.rng import SPAN, SPLIT, draw


def confusion(rows: DataFrame, label: str = "label", prediction: str = "prediction") -> DataFrame:
    return rows.groupBy(F.col(label).cast("int").alias("label"), F.col(prediction).cast("int").alias("prediction")).agg(F.count("*").alias("n"))


def f1(counts: DataFrame) -> DataFrame:
    """(micro, macro) of a confusion table; a class without true positives scores 0."""
    sides = counts.select(F.explode(F.array(
        F.struct(F.col("label").alias("k"), F.when(F.col("label") == F.col("prediction"), F.col("n")).otherwise(0).alias("tp"), F.col("n").alias("rows"), F.lit(0).cast("long").alias("said")),
        F.struct(F.col("prediction").alias("k"), F.lit(0).cast("long").alias("tp"), F.lit(0).cast("long").alias("rows"), F.col("n").alias("said")),
    )).alias("s")).select("s.*")
    per = sides.groupBy("k").agg(F.sum("tp").alias("tp"), F.sum("rows").alias("rows"), F.sum("said").alias("said"))
    score = 2.0 * F.col("tp") / (F.col("rows") + F.col("said"))
    return per.agg(F.round(F.sum("tp") / F.sum("rows"), 6).alias("micro"), F.round(F.avg(score), 6).alias("macro"))


def split(rows: DataFrame, train_fraction: float, seed: int) -> tuple[DataFrame, DataFrame]:
    """Deterministic by vertex; never randomSplit."""
    if not 0 < train_fraction < 1:
        raise ValueError("train_fraction must lie between 0 and 1")
    d = draw(seed, SPLIT, "vid") < F.lit(int(train_fraction * SPAN))
    return rows.where(d), rows.where(~d)


def features(vectors: DataFrame, which: str = "u") -> DataFrame:
    """(vid, x): U, C or both, scaled to length 1."""
    raw = {"u": F.col("u"), "c": F.col("c"), "both": F.concat("u", "c")}[which].cast("array<double>")
    norm = F.sqrt(F.aggregate(raw, F.lit(0.0), lambda s, x: s + x * x))
    return vectors.select("vid", F.transform(raw, lambda x: F.when(norm > 0, x / norm).otherwise(0.0)).alias("x"))


def classify(vectors: DataFrame, labels: DataFrame, train_fraction: float = 0.1, seeds: tuple[int, ...] = (7,), which: str = "u", iterations: int = 30) -> DataFrame:
    """(seed, micro, macro) of one-vs-rest logistic regression; labels (vid, label) with label 0, 1, ..."""
    from pyspark.ml.classification import LogisticRegression, OneVsRest
    from pyspark.ml.functions import array_to_vector

    rows = features(vectors, which).join(labels, "vid").select("vid", F.col("label").cast("double").alias("label"), array_to_vector("x").alias("features")).persist()
    out = None
    for seed in seeds:
        fit, test = split(rows, train_fraction, seed)
        model = OneVsRest(classifier=LogisticRegression(maxIter=iterations, regParam=1e-4)).fit(fit)
        row = f1(confusion(model.transform(test))).select(F.lit(seed).alias("seed"), "micro", "macro")
        out = row if out is None else out.unionByName(row)
    return out


def gain(f1_rows: DataFrame, method: str, value: str, ours: str) -> DataFrame:
    """Relative gain in percent of `ours` over every other method."""
    own = f1_rows.where(F.col(method) == ours).agg(F.max(value).alias("own"))
    return f1_rows.where(F.col(method) != ours).crossJoin(F.broadcast(own)).select(method, F.round(100 * (F.col("own") / F.col(value) - 1), 6).alias("gain_percent"))  # one row

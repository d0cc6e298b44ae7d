"""Queries without SQL: training, baselines, classification, profiles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxembed.operators import baselines, evaluate, measure, partition, sampling
from proxembed.operators.graph import Graph
from proxembed.operators.storage import store
from proxembed.operators.train import TrainConfig, embedding, initial_frame, loss, signed, train, train_dataflow
from proxembed.operators.variants import Sample, SampleConfig, Variant, sample
from proxembed.plans.exact import P, graph
from proxembed.sources import builders

CONFIG = TrainConfig(dim=16, lr=0.05)
BATCHES = 4
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_HASHED: dict[tuple, Graph] = {}


def run(f: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    QUERIES[f.__name__] = f
    return f


def hashed(spark: SparkSession, d: str, name: str, parts: int = P) -> Graph:
    """A graph cut by hash, stored: ids of a kind are consecutive, so a two-sided graph cut by ranges has no inner edges."""
    key = (spark.sparkContext.applicationId, d, name, parts)
    if key not in _HASHED:
        _HASHED[key] = partition.stored(partition.cut_by_hash(graph(spark, d, name), parts))
    return _HASHED[key]


def drawn(spark: SparkSession, d: str, variant: Variant, name: str = "geography") -> tuple[Graph, Sample]:
    """A sample of two pairs a vertex and batch, so that nearly every vertex is met."""
    g = hashed(spark, d, name)
    size = max(64, 2 * g.n // g.parts)
    return g, sample(g, variant, SampleConfig(batch_size=size, batches=BATCHES, length=20, rounds=max(4, size // 16)))


def _signs(spark: SparkSession, d: str, variant: Variant, scope: str = "global") -> tuple[Graph, DataFrame]:
    g, s = drawn(spark, d, variant)
    return g, store(signed(s.pairs, sampling.negatives(s.pairs, g, 1, scope=scope)), "signed")


@run
def train_blocked(spark: SparkSession, d: str) -> DataFrame:
    g, rows = _signs(spark, d, Variant("all", "fresh"))
    return embedding(train(g, rows, CONFIG, BATCHES), CONFIG.dim)


@run
def train_dataflow_batches(spark: SparkSession, d: str) -> DataFrame:
    g, rows = _signs(spark, d, Variant("all", "fresh"))
    return train_dataflow(initial_frame(g, CONFIG), rows, CONFIG, BATCHES)


def _exchange(kind: str) -> None:
    def f(spark: SparkSession, d: str) -> DataFrame:
        from dataclasses import replace

        g, rows = _signs(spark, d, Variant("all", "pair"), "adjacent" if kind == "neighbors" else "global")
        if kind == "neighbors":  # pairs of pairs may join parts that share no edge
            links = partition.part_links(g).select("part", F.col("other").alias("v_part"))
            rows = rows.where("part = v_part").unionByName(rows.where("part <> v_part").join(links, ["part", "v_part"], "left_semi"))
        return embedding(train(g, rows, replace(CONFIG, exchange=kind), 1), CONFIG.dim)

    QUERIES[f"train_{kind}"] = f


for _kind in ("neighbors", "onesided_get", "onesided_atomic"):
    _exchange(_kind)


@run
def training_loss(spark: SparkSession, d: str) -> DataFrame:
    """Mean loss by batch, of the vectors before and after training."""
    g, rows = _signs(spark, d, Variant("all", "fresh"))
    before = loss(baselines.initial(g, CONFIG), rows).withColumn("trained", F.lit(False))
    return before.unionByName(loss(embedding(train(g, rows, CONFIG, BATCHES), CONFIG.dim), rows).withColumn("trained", F.lit(True)))


@run
def sampling_only(spark: SparkSession, d: str) -> DataFrame:
    g = hashed(spark, d, "geography")
    return baselines.sampling_only(g, Variant("all", "reuse"), SampleConfig(batch_size=64, batches=2, length=20))


@run
def alias_negatives(spark: SparkSession, d: str) -> DataFrame:
    g, s = drawn(spark, d, Variant("any", "fresh"))
    return sampling.alias_negatives(s.pairs, g, 2)


@run
def fit_edge_sgd(spark: SparkSession, d: str) -> DataFrame:
    return baselines.fit_edge_sgd(graph(spark, d, "geography"), CONFIG, 20_000)


@run
def fit_biased_walk(spark: SparkSession, d: str) -> DataFrame:
    return baselines.fit_biased_walk(graph(spark, d, "geography"), CONFIG, 200, 6, 3, 0.5, 2.0)


@run
def fit_uniform_walk(spark: SparkSession, d: str) -> DataFrame:
    return baselines.fit_uniform_walk(graph(spark, d, "geography"), CONFIG, 400, 20, 3)


@run
def fit_pooled(spark: SparkSession, d: str) -> DataFrame:
    return baselines.fit_pooled(graph(spark, d, "geography"), CONFIG, 400, 20, 2)


@run
def fit_bucketed(spark: SparkSession, d: str) -> DataFrame:
    return baselines.fit_bucketed(graph(spark, d, "geography"), CONFIG, 20_000, 2)


@run
def fit_spectral(spark: SparkSession, d: str) -> DataFrame:
    return baselines.fit_spectral_small(graph(spark, d, "geography"), 8)


@run
def classify_nodes(spark: SparkSession, d: str) -> DataFrame:
    """Micro- and Macro-F1 of region labels after edge sampling on the geography graph."""
    g = graph(spark, d, "geography")
    vectors = baselines.fit_edge_sgd(g, TrainConfig(dim=16, lr=0.1), 300_000)
    return evaluate.classify(vectors, builders.labelled(g, builders.labels(spark, d, "geography")))


@run
def comm_volume(spark: SparkSession, d: str) -> DataFrame:
    _, rows = _signs(spark, d, Variant("all", "fresh"))
    return measure.comm_volume(rows.withColumn("part", F.col("part").cast("int")), CONFIG.dim)


def _profiled(spark: SparkSession, d: str) -> DataFrame:
    """Tasks of one sampled and trained run, by phase."""
    before, took = measure.last_stage(spark), {}
    g = hashed(spark, d, "geography")
    with measure.timed(took, "sampling", spark):
        _, rows = _signs(spark, d, Variant("any", "refresh"))
    with measure.timed(took, "training", spark):
        train(g, rows, CONFIG, BATCHES)
    return measure.task_profile(spark, before)


@run
def stage_profile(spark: SparkSession, d: str) -> DataFrame:
    return measure.routine_profile(_profiled(spark, d))


@run
def measured_traffic(spark: SparkSession, d: str) -> DataFrame:
    return measure.traffic(_profiled(spark, d))


@run
def process_memory(spark: SparkSession, d: str) -> DataFrame:
    """Peak memory by process beside the state that a part's owner holds."""
    g = hashed(spark, d, "geography")
    state = measure.memory_report(g, CONFIG.dim).agg(F.max("bytes").alias("largest_block"))
    return measure.process_memory(spark).crossJoin(F.broadcast(state))  # one row


def _embed_10k(kind: str) -> None:
    def f(spark: SparkSession, d: str) -> DataFrame:
        """Two batches of 10,000 pairs a part from walks of 100 steps, with negatives, trained on the co-purchase graph cut by hash."""
        g = hashed(spark, d, "copurchase")
        s = sample(g, Variant("any", kind), SampleConfig(batch_size=10_000, batches=2, length=100, rounds=25_000 if kind == "local" else 128))
        rows = store(signed(s.pairs, sampling.negatives(s.pairs, g, 1)), "signed")
        return embedding(train(g, rows, CONFIG, 2), CONFIG.dim)

    QUERIES[f"embed_{kind}_10k"] = f


for _kind in ("local", "fresh"):
    _embed_10k(_kind)

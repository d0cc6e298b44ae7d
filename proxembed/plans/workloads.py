"""The experiments, re-expressed on the given tables. `python -m proxembed.plans.workloads NAME SF_DIR [FILE]` prints one.

Every experiment yields a row for each configuration, one after another: a driver loop over `measured` and `baseline` runs. With
FILE, each row is appended there as a line of JSON once it is known. Calls, handed-over steps and exchanged contexts don't
depend on the machine; seconds do, and only their ratios compare.
"""

from __future__ import annotations

import json
import sys
from collections.abc import Callable, Iterable, Iterator
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxembed.operators import baselines, evaluate, measure, partition
from proxembed.operators.graph import Graph
from proxembed.operators.sampling import negatives
from proxembed.operators.storage import store
from proxembed.operators.train import TrainConfig, embedding, signed, train
from proxembed.operators.variants import GRID, SampleConfig, Variant, sample
from proxembed.plans.exact import graph
from proxembed.sources import builders

RESULT = "method string, graph string, parts int, setting string, sampling_s double, training_s double, calls long, handed long, contexts long, least long, most long, zero_parts long, false_share double, remote_share double, micro double, macro double"
FIELDS = [c.split()[0] for c in RESULT.split(", ")]
S = SampleConfig(batch_size=256, batches=4, length=10, rounds=64)
T = TrainConfig(dim=16, lr=0.1)
Rows = Iterator[dict]
EXPERIMENTS: dict[str, Callable[[SparkSession, str], Rows]] = {}


def experiment(f: Callable[[SparkSession, str], Rows]) -> Callable[[SparkSession, str], Rows]:
    EXPERIMENTS[f.__name__] = f
    return f


def frame(spark: SparkSession, found: Iterable[dict]) -> DataFrame:
    """Rows of an experiment as RESULT."""
    return spark.createDataFrame([tuple(r.get(k) for k in FIELDS) for r in found], RESULT)


def embed(g: Graph, variant: Variant, s: SampleConfig = S, t: TrainConfig = T, k: int = 1, epochs: int = 1, scope: str = "global") -> tuple[DataFrame, dict]:
    """Sample, draw negatives, train: (vid, part, u, c), and what the run cost. Every epoch has batches of its own, drawn in one dataflow."""
    took: dict[str, float] = {}
    s = replace(s, batches=s.batches * epochs)
    with measure.timed(took, "sampling", g.edges.sparkSession):
        drawn = sample(g, variant, s)
        signs = store(signed(drawn.pairs, negatives(drawn.pairs, g, k, seed=s.seed, scope=scope)), "signed")
    with measure.timed(took, "training", g.edges.sparkSession):
        vectors = store(embedding(train(g, signs, t, s.batches), t.dim), "embedding")
    spread = measure.sample_spread(drawn.pairs, g.parts, s.batches).first()
    remote = {r["sign"]: r["share"] for r in measure.remote_share(signs).collect()}
    cost = {"method": str(variant), "parts": g.parts, "sampling_s": took["sampling"], "training_s": took["training"], "calls": drawn.calls, "handed": drawn.handed,
            "contexts": signs.where("v_part <> part").select("batch", "part", "v").distinct().count(), "least": spread["least"], "most": spread["most"], "zero_parts": spread["zero_parts"],
            "false_share": measure.false_positive_share(drawn.pairs, g).first()["share"], "remote_share": remote.get(1)}
    return vectors, cost


def quality(vectors: DataFrame, labels: DataFrame | None, fraction: float = 0.1) -> dict:
    if labels is None:
        return {}
    r = evaluate.classify(vectors, labels, fraction).first()
    return {"micro": r["micro"], "macro": r["macro"]}


def measured(g: Graph, labels: DataFrame | None, variant: Variant, name: str, s: SampleConfig = S, t: TrainConfig = T, setting: str = "", **more) -> dict:
    vectors, cost = embed(g, variant, s, t, **more)
    return cost | {"graph": name, "setting": setting} | quality(vectors, labels)


def baseline(g: Graph, labels: DataFrame | None, method: str, name: str, t: TrainConfig = T, samples: int = 4 * 256 * 4, setting: str = "", buckets: int = 2) -> dict:
    """A single-owner method, or the edge buckets, on about as many positives as the variants get."""
    took: dict[str, float] = {}
    fits = {"edge_sgd": lambda: baselines.fit_edge_sgd(g, t, samples), "biased_walk": lambda: baselines.fit_biased_walk(g, t, max(1, samples // 18), 8, 3), "uniform_walk": lambda: baselines.fit_uniform_walk(g, t, max(1, samples // 19), 10, 2),
            "pooled": lambda: baselines.fit_pooled(g, t, max(1, samples // 10), 10, 2), "bucketed": lambda: baselines.fit_bucketed(g, t, samples, buckets), "untrained": lambda: baselines.initial(g, t)}
    with measure.timed(took, "all"):
        vectors = store(fits[method](), "embedding")
    return {"method": method, "graph": name, "parts": buckets if method == "bucketed" else 1, "setting": setting, "training_s": took["all"]} | quality(vectors, labels)


def load(spark: SparkSession, d: str, name: str, parts: int = 4) -> tuple[Graph, DataFrame | None]:
    """A graph and its labels. Parts are by hash: keys of a kind are consecutive ids, and two-sided graphs cut by ranges have no inner edges."""
    labelled = {"doc_quality": ("doc_term", "doc_quality")}.get(name, (name, name))
    g = partition.stored(partition.cut_by_hash(graph(spark, d, labelled[0]), parts))
    if labelled[1] not in LABELLED:
        return g, None
    return g, store(builders.labelled(g, builders.labels(spark, d, labelled[1])), "labels")


LABELLED = ("geography", "doc_term", "near_doc", "doc_quality", "vector_knn", "copurchase")
LOCAL, PAIR, FRESH, REUSE, REFRESH = Variant("any", "local"), Variant("all", "pair"), Variant("all", "fresh"), Variant("all", "reuse"), Variant("any", "refresh")


@experiment
def x01_single_node(spark: SparkSession, d: str) -> Rows:
    """End to end against single-owner baselines on as many positives."""
    for name in ("doc_term", "copurchase", "customer_part"):
        g, _ = load(spark, d, name)
        for v in (LOCAL, PAIR):
            yield measured(g, None, v, name)
        for m in ("edge_sgd", "biased_walk"):
            yield baseline(g, None, m, name)


@experiment
def x02_edge_buckets(spark: SparkSession, d: str) -> Rows:
    """Against the edge-bucket baseline: twice as many buckets as workers, and many."""
    for name in ("customer_part", "doc_term"):
        g, _ = load(spark, d, name)
        for v in (LOCAL, PAIR):
            yield measured(g, None, v, name)
        for buckets in (2 * g.parts, 8 * g.parts):
            yield baseline(g, None, "bucketed", name, setting=f"{buckets} buckets", buckets=buckets)


@experiment
def x03_quality(spark: SparkSession, d: str) -> Rows:
    """Micro- and Macro-F1 of methods, with structure and without (the control graphs stay at chance)."""
    for name, size, epochs in (("geography", 1024, 8), ("doc_term", 8192, 4), ("doc_quality", 8192, 4), ("copurchase", 2048, 4), ("vector_knn", 1024, 4)):
        g, y = load(spark, d, name)
        big = replace(S, batch_size=size, rounds=size // 8)
        for m in ("untrained", "edge_sgd", "biased_walk", "uniform_walk", "pooled"):
            yield baseline(g, y, m, name, samples=4 * size * 4 * epochs)
        for v in (LOCAL, PAIR, FRESH):
            yield measured(g, y, v, name, big, epochs=epochs)


@experiment
def x04_parts(spark: SparkSession, d: str) -> Rows:
    """Quality against the number of parts, the same number of positives in all."""
    for p in (1, 2, 4, 8, 16, 32):
        g, y = load(spark, d, "geography", p)
        size = max(16, 8192 // p)
        for v in (LOCAL, PAIR, FRESH):
            yield measured(g, y, v, "geography", replace(S, batch_size=size, rounds=max(8, size // 4)), epochs=4)


@experiment
def x05_epochs(spark: SparkSession, d: str) -> Rows:
    """More epochs lift sparse labels."""
    g, y = load(spark, d, "geography")
    for epochs in (1, 10, 100):
        yield measured(g, y, FRESH, "geography", replace(S, batch_size=512, batches=1, rounds=128), epochs=epochs, setting=f"{epochs} epochs")


@experiment
def x06_ablation(spark: SparkSession, d: str) -> Rows:
    """All ten legal configurations."""
    g, _ = load(spark, d, "copurchase")
    for v in GRID:
        yield measured(g, None, v, "copurchase")


@experiment
def x07_scaling(spark: SparkSession, d: str) -> Rows:
    """Walk calls and exchanged rows against parts, under both rules, on all graphs."""
    for name in builders.BUILDERS:
        for p in (2, 8, 32):
            g, _ = load(spark, d, name, p)
            for v in (LOCAL, Variant("any", "fresh"), FRESH, Variant("any", "reuse"), REUSE, PAIR):
                yield measured(g, None, v, name, replace(S, batch_size=64, batches=2, rounds=16))


@experiment
def x08_positives(spark: SparkSession, d: str) -> Rows:
    """Positives by part: `any` leaves parts short, `all` doesn't."""
    for name in ("copurchase", "part_supplier", "doc_term"):
        for p in (4, 16):
            g, _ = load(spark, d, name, p)
            for v in (Variant(rule, kind) for rule in ("any", "all") for kind in ("local", "reuse")):
                yield measured(g, None, v, name, replace(S, batch_size=64, batches=2, rounds=32))


@experiment
def x09_time_split(spark: SparkSession, d: str) -> Rows:
    """Sampling and training seconds, Local against Augmented-Pair."""
    for name in ("copurchase", "customer_part", "part_supplier", "doc_term", "geography", "user_key"):
        for p in (2, 8, 32):
            g, _ = load(spark, d, name, p)
            for v in (LOCAL, PAIR):
                yield measured(g, None, v, name, replace(S, batch_size=64, batches=2, rounds=16))


@experiment
def x10_communication(spark: SparkSession, d: str) -> Rows:
    """Where task time goes, and how unevenly, from the tasks of each run: a row for each phase and routine."""
    g, _ = load(spark, d, "doc_term", 8)
    for v in (LOCAL, REFRESH):
        before = measure.last_stage(spark)
        row = measured(g, None, v, "doc_term")
        yield row
        tasks = store(measure.task_profile(spark, before).where(F.col("phase").isin("sampling", "training")), "tasks")
        for r in measure.routine_profile(tasks).orderBy("phase", F.desc("seconds")).collect():
            yield {"method": str(v), "graph": "doc_term", "parts": 8, "setting": f"{r['phase']}, {r['routine']}: {r['share_percent']} % of task time, imbalance {r['imbalance_percent']} %", "training_s": r["seconds"]}
        for r in measure.traffic(tasks).collect():
            yield {"method": str(v), "graph": "doc_term", "parts": 8, "setting": f"{r['phase']}: {r['exchanged_rows']} rows, {r['exchanged_bytes']} bytes exchanged"}
        for r in measure.process_memory(spark).collect():
            yield {"method": str(v), "graph": "doc_term", "parts": 8, "setting": f"{r['executor']}: peak heap {r['peak_heap']}, execution {r['peak_execution']} bytes"}


@experiment
def x11_arrow_batches(spark: SparkSession, d: str) -> Rows:
    """Stand-in for the memory-page study, which has no counterpart here: rows of an Arrow batch."""
    g, _ = load(spark, d, "copurchase")
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    try:
        for n in (1_000, 10_000, 100_000):
            spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(n))
            yield measured(g, None, PAIR, "copurchase", setting=f"{n} rows")
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)


@experiment
def x12_one_sided(spark: SparkSession, d: str) -> Rows:
    g, y = load(spark, d, "geography")
    for v in (PAIR, REFRESH):
        for e in ("collective", "onesided_get", "onesided_atomic"):
            yield measured(g, y, v, "geography", replace(S, batch_size=1024, rounds=128), replace(T, exchange=e), setting=e, epochs=2)


@experiment
def x13_adjacent_negatives(spark: SparkSession, d: str) -> Rows:
    """Scopes of negatives; the exchange between neighbours alone where scopes allow it."""
    g, y = load(spark, d, "geography", 8)
    big = replace(S, batch_size=1024, rounds=128)
    for scope in ("global", "adjacent", "local"):
        yield measured(g, y, FRESH, "geography", big, setting=scope, scope=scope, epochs=2)
    yield measured(g, y, FRESH, "geography", big, replace(T, exchange="neighbors"), setting="adjacent, neighbours only", scope="adjacent", epochs=2)


@experiment
def x14_sync(spark: SparkSession, d: str) -> Rows:
    g, y = load(spark, d, "geography")
    for s in (1, 4, 16):
        yield measured(g, y, FRESH, "geography", replace(S, batch_size=256, batches=16, rounds=64), replace(T, sync_every=s), setting=f"every {s}")


@experiment
def x15_batch_size(spark: SparkSession, d: str) -> Rows:
    g, _ = load(spark, d, "copurchase")
    for b in (100, 1_000, 10_000):
        yield measured(g, None, FRESH, "copurchase", replace(S, batch_size=b, batches=1, rounds=max(16, b // 4)), setting=f"B={b}")


@experiment
def x16_cuts(spark: SparkSession, d: str) -> Rows:
    raw = graph(spark, d, "part_supplier")
    by_edges, balanced = partition.cut_by_edges(raw, 8)
    for name, g in {"vertex": partition.cut_by_vertex(raw, 8), f"edges, balanced {balanced}": by_edges, "hash": partition.cut_by_hash(raw, 8)}.items():
        yield measured(partition.stored(g), None, FRESH, "part_supplier", replace(S, batch_size=64, batches=2, rounds=16), setting=name)


def main(names: str, sf_dir: str, file: str | None = None) -> None:
    from proxembed.plans.session import session

    spark = session("local[*]")
    for name in names.split(","):
        for row in EXPERIMENTS[name](spark, sf_dir):
            line = json.dumps({"experiment": name, "sf": sf_dir.rstrip("/").rsplit("/", 1)[-1]} | {k: round(v, 4) if isinstance(v, float) else v for k, v in row.items() if v not in (None, "")})
            print(line, flush=True)
            if file:
                with open(file, "a") as out:
                    out.write(line + "\n")


if __name__ == "__main__":
    main(*sys.argv[1:])

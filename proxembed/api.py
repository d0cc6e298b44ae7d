"""The library's front: sample, train, measure, compare. Values outside their range raise before a job starts."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

from proxembed.operators import baselines, evaluate, measure, partition
from proxembed.operators.graph import Graph
from proxembed.operators.sampling import negatives
from proxembed.operators.storage import store
from proxembed.operators.train import TrainConfig, embedding, signed, train, train_dataflow, initial_frame
from proxembed.operators.variants import GRID, Sample, SampleConfig, Variant
from proxembed.operators.variants import sample as draw_sample

CUTS = ("edges", "vertex", "hash")


@dataclass(frozen=True)
class Config:
    """All settings of a run. An epoch is `batches` batches with pairs of their own. `budget` ends a call's walks by the visits of all its walkers instead of each by its length."""

    dim: int = 64
    lr: float = 0.025
    k: int = 1
    alpha: float = 0.75
    neg_weight: float = 1.0
    decay: float = 1e-4
    batch_size: int = 256
    batches: int = 4
    epochs: int = 10
    length: int = 100
    window: int = 2
    unit: str = "nodes"
    budget: int | None = None
    parts: int = 4
    cut: str = "edges"
    sync_every: int = 1
    fetch: str = "after"
    exchange: str = "collective"
    kernel: str = "exact"
    trainer: str = "blocked"
    negative_scope: str = "global"
    reject_edges: bool = False
    rng: str = "xx"
    engine: str = "block"
    seed: int = 7

    def __post_init__(self) -> None:
        if self.k < 0 or self.parts < 1 or self.epochs < 1 or not 0 <= self.alpha:
            raise ValueError("k must be 0 or more, parts and epochs 1 or more, alpha not negative")
        if self.cut not in CUTS or self.trainer not in ("blocked", "dataflow") or self.negative_scope not in ("global", "adjacent", "local"):
            raise ValueError("unknown cut, trainer or scope of negatives")
        self.sampling()
        self.training()

    def sampling(self) -> SampleConfig:
        return SampleConfig(batch_size=self.batch_size, batches=self.batches * self.epochs, length=self.length, window=self.window, unit=self.unit, seed=self.seed, backend=self.rng, engine=self.engine, budget=self.budget)

    def training(self) -> TrainConfig:
        return TrainConfig(dim=self.dim, lr=self.lr, neg_weight=self.neg_weight, decay=self.decay, kernel=self.kernel, sync_every=self.sync_every, fetch=self.fetch, exchange=self.exchange, seed=self.seed)


@dataclass
class Result:
    """embedding(vid, part, u, c), the sample it was trained on, and what both cost."""

    embedding: DataFrame
    sample: Sample
    metrics: dict


def _variant(name: str | Variant) -> Variant:
    return name if isinstance(name, Variant) else Variant.parse(name)


def cut(g: Graph, c: Config) -> Graph:
    """The graph under the owners that the configuration asks for, stored."""
    if c.cut == "edges":
        return partition.stored(partition.cut_by_edges(g, c.parts)[0])
    return partition.stored(partition.cut_by_vertex(g, c.parts) if c.cut == "vertex" else partition.cut_by_hash(g, c.parts))


def sample(g: Graph, variant: str | Variant, c: Config = Config()) -> Sample:
    return draw_sample(g, _variant(variant), c.sampling())


def fit(g: Graph, pairs: DataFrame, c: Config = Config()) -> DataFrame:
    """(vid, part, u, c) trained on the batches of all epochs in turn."""
    rows = store(signed(pairs, negatives(pairs, g, c.k, c.alpha, c.negative_scope, c.reject_edges, c.seed, c.rng)), "signed")
    if c.trainer == "dataflow":
        now = train_dataflow(initial_frame(g, c.training()), rows, c.training(), c.batches * c.epochs)
        return now.join(g.vertices.select("vid", "part"), "vid").select("vid", "part", "u", "c")
    return embedding(train(g, rows, c.training(), c.batches * c.epochs), c.dim)


def embed(g: Graph, variant: str | Variant = "AR-Local", c: Config = Config()) -> Result:
    """Sample, train and measure on a graph that is cut already."""
    took: dict[str, float] = {}
    spark = g.edges.sparkSession
    with measure.timed(took, "sampling", spark):
        drawn = sample(g, variant, c)
    with measure.timed(took, "training", spark):
        vectors = store(fit(g, drawn.pairs, c), "embedding")
    spread = measure.sample_spread(drawn.pairs, g.parts, c.batches * c.epochs).first().asDict()
    return Result(vectors, drawn, {f"{k}_s": v for k, v in took.items()} | {"calls": drawn.calls, "handed": drawn.handed, "idle": drawn.idle} | spread)


def classify(vectors: DataFrame, labels: DataFrame, train_fraction: float = 0.1, seeds: Iterable[int] = (7,)) -> DataFrame:
    return evaluate.classify(vectors, labels, train_fraction, tuple(seeds))


BASELINES = ("edge_sgd", "biased_walk", "uniform_walk", "pooled", "bucketed")


def compare(g: Graph, labels: DataFrame, variants: Iterable[str | Variant], methods: Iterable[str] = BASELINES, c: Config = Config(), train_fraction: float = 0.1) -> DataFrame:
    """(method, micro, macro) of variants and baselines on as many positives each."""
    t, samples = c.training(), c.batch_size * c.batches * g.parts * c.epochs
    fits = {"edge_sgd": lambda: baselines.fit_edge_sgd(g, t, samples, c.k), "biased_walk": lambda: baselines.fit_biased_walk(g, t, max(1, samples // 18), 8, 3, k=c.k), "uniform_walk": lambda: baselines.fit_uniform_walk(g, t, max(1, samples // 19), 10, 2, k=c.k),
            "pooled": lambda: baselines.fit_pooled(g, t, max(1, samples // 10), 10, 2, c.k), "bucketed": lambda: baselines.fit_bucketed(g, t, samples, max(2, 2 * g.parts), k=c.k)}
    rows = []
    for name in methods:
        r = classify(fits[name](), labels, train_fraction).first()
        rows.append((name, r["micro"], r["macro"]))
    for v in map(_variant, variants):
        r = classify(embed(g, v, c).embedding, labels, train_fraction).first()
        rows.append((str(v), r["micro"], r["macro"]))
    return g.edges.sparkSession.createDataFrame(rows, "method string, micro double, macro double")


_COST = "method string, parts int, sampling_s double, training_s double, calls long, handed long, least long, most long, zero_parts long"


def _cost(v: Variant, r: Result, parts: int) -> tuple:
    m = r.metrics
    return str(v), parts, m["sampling_s"], m["training_s"], m["calls"], m["handed"], m["least"], m["most"], m["zero_parts"]


def ablate(g: Graph, grid: Iterable[Variant] = tuple(GRID), c: Config = Config()) -> DataFrame:
    """Cost of each configuration of the grid on one cut."""
    return g.edges.sparkSession.createDataFrame([_cost(v, embed(g, v, c), g.parts) for v in grid], _COST)


def scale(g: Graph, variants: Iterable[str | Variant], parts: Iterable[int], c: Config = Config()) -> DataFrame:
    """Cost of variants as a graph is cut into more parts."""
    rows = []
    for p in parts:
        at = replace(c, parts=p)
        owned = cut(g, at)
        rows += [_cost(v, embed(owned, v, at), p) for v in map(_variant, variants)]
    return g.edges.sparkSession.createDataFrame(rows, _COST)


def features(vectors: DataFrame, which: str = "u") -> DataFrame:
    """(vid, x) scaled to length 1, as start features of later models."""
    return evaluate.features(vectors, which)


def export(vectors: DataFrame, vertices: DataFrame, path: str, fmt: str = "text") -> None:
    """Write vectors under their keys: `text` (a line `key v1 ... vd`), `json`, `parquet`, or `table` (path is its name)."""
    named = vectors.join(vertices.select("vid", "key"), "vid").select("key", "u", "c")
    if fmt == "text":
        from pyspark.sql import functions as F

        line = F.concat_ws(" ", "key", F.array_join(F.transform("u", lambda x: x.cast("string")), " "))
        named.select(line.alias("value")).write.text(path)
    elif fmt == "table":
        named.write.saveAsTable(path)
    elif fmt in ("json", "parquet"):
        named.write.format(fmt).save(path)
    else:
        raise ValueError("fmt must be text, json, parquet or table")

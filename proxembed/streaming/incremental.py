"""Training on a growing graph: each micro-batch adds edges, walks start at those edges, and training goes on from the state."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxembed.operators.graph import Graph, assign_ids, degrees, mirror, undirect
from proxembed.operators.pairs import numbered
from proxembed.operators.partition import cut_by_hash
from proxembed.operators.sampling import negatives
from proxembed.operators.storage import Versions, forget, store
from proxembed.operators.train import TrainConfig, embedding, extend_blocks, init_blocks, signed, train
from proxembed.operators.walks import walk_block, walk_pairs


@dataclass
class IncrementalEmbedding:
    """Vertices, edges and state in one versioned folder, a version a micro-batch.

    Owners are hashes of ids, so a vertex keeps its part while the graph grows. A micro-batch that is delivered again (after a
    failure) finds its version written and changes nothing.
    """

    spark: SparkSession
    path: str
    parts: int = 4
    length: int = 10
    window: int = 2
    k: int = 1
    config: TrainConfig = field(default_factory=TrainConfig)

    def __post_init__(self) -> None:
        self.versions = Versions(self.spark, self.path)

    def graph(self) -> Graph | None:
        saved = self.versions.read("vertices", "edges")
        return None if saved is None else self._graph(*saved[1])

    def vectors(self) -> DataFrame:
        """(vid, key, part, u, c) of the last whole version."""
        _, (vertices, state) = self.versions.read("vertices", "state")
        return embedding(state, self.config.dim).join(vertices.select("vid", "key"), "vid")

    def _graph(self, vertices: DataFrame, edges: DataFrame) -> Graph:
        both = mirror(edges, "u", "v")
        return cut_by_hash(Graph(degrees(vertices.select("vid", "key"), both), both, vertices.count()), self.parts)

    def update(self, raw: DataFrame, batch_id: int) -> None:
        """Add (a, b, w) edges and train on walks from them; for foreachBatch."""
        saved = self.versions.read("vertices", "edges", "state")
        if saved is not None and saved[0] > batch_id:
            return
        changed = store(undirect(raw), "changed")
        if changed.isEmpty() and saved is not None:
            return
        keys = changed.select(F.explode(F.array("a", "b")).alias("key")).distinct()
        old = saved[1] if saved is not None else None
        n = old[0].count() if old else 0
        fresh = assign_ids(keys.join(old[0], "key", "left_anti") if old else keys, ["key"]).withColumn("vid", F.col("vid") + n)
        fresh = store(fresh.select("vid", "key"), "fresh")
        vertices = store(old[0].select("vid", "key").unionByName(fresh) if old else fresh, "vertices")
        ends = [vertices.select(F.col("key").alias(x), F.col("vid").alias(y)) for x, y in (("a", "u"), ("b", "v"))]
        named = store(changed.join(ends[0], "a").join(ends[1], "b").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "w"), "named")
        edges = old[1].unionByName(named).groupBy("u", "v").agg(F.sum("w").alias("w")) if old else named
        edges = store(edges, "edges")
        g = self._graph(vertices, edges)
        added = init_blocks(Graph(cut_by_hash(Graph(fresh.withColumn("part", F.lit(0)), g.edges, g.n), self.parts).vertices, g.edges, g.n, self.parts), self.config)
        state = store(extend_blocks(old[2], added, self.config.dim) if old else added, "state")
        # One walk from each end of each changed edge, so only parts that the change reaches have pairs.
        roots = mirror(named, "u", "v").select(F.col("src").alias("u"), F.col("dst").alias("v"))
        owner = g.vertices.select("vid", "part")
        for end, name in (("u", "part"), ("v", "v_part")):
            roots = roots.join(owner.select(F.col("vid").alias(end), F.col("part").alias(name)), end)
        roots = store(roots.withColumn("walk_id", F.xxhash64("u", "v").bitwiseAND(F.lit((1 << 62) - 1))).select("walk_id", "part", "u", "v", "v_part"), "roots")
        pairs = walk_pairs(walk_block(g, roots, self.length, seed=self.config.seed + batch_id), self.window)
        rows = numbered(pairs.withColumn("batch", F.lit(0)), ["batch", "part"], ["walk_id", "step", "hop"]).select("batch", "part", "seq", "u", "v", "v_part")
        rows = store(rows, "pairs")
        done = train(g, signed(rows, negatives(rows, g, self.k, seed=self.config.seed + batch_id)), self.config, 1, state=state)
        self.versions.write(batch_id + 1, vertices=vertices, edges=edges, state=done)
        forget(changed, fresh, vertices, named, edges, state, roots, rows, done)

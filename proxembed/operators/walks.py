"""Distributed random walks and the pairs they give.

Two engines draw the same steps. `join` moves every walker one level at a time by an equi join with the neighbour index.
`block` walks in numpy on the whole graph or on parts, where they fit a task, and else reads the lists that walkers meet.
A walk may revisit vertices. `boundary` walks end at the first step that would leave the part.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxembed.functions.rng import STEP, draw, draw_numpy
from proxembed.operators.graph import Graph
from proxembed.operators.sampling import FEW, near, neighbor_index, pick, prefix
from proxembed.operators.storage import Buckets, forget, store

STEPS = "walk_id long, part0 int, step int, src long, dst long, src_part int, dst_part int"


def _first_steps(roots: DataFrame) -> DataFrame:
    """The root edge counts as a step before its far end's owner is looked at."""
    return roots.select("walk_id", F.col("part").alias("part0"), F.lit(0).alias("step"), F.col("u").alias("src"), F.col("v").alias("dst"), F.col("part").alias("src_part"), F.col("v_part").alias("dst_part"))


def walk_join(index: DataFrame, roots: DataFrame, length: int = 100, stop: str = "length", budget: int | None = None, seed: int = 7, backend: str = "xx") -> DataFrame:
    """Steps (STEPS) of walks of at most `length` edges; `budget` ends all walks at the level where summed visits reach it."""
    if stop not in ("length", "boundary"):
        raise ValueError("stop must be length or boundary")
    size = index.groupBy("src").agg(F.max(F.element_at("items", -1)["hi"]).alias("wdeg"), (F.max("chunk") + 1).alias("chunks"))
    first = _first_steps(roots)
    if stop == "boundary":
        first = first.where("dst_part = src_part")
    first = store(first.join(size.withColumnRenamed("src", "dst"), "dst"), "steps")
    levels, front = [first], first
    visited = 2 * first.count() if budget else 0
    for level in range(1, length):
        if budget and visited >= budget:
            break
        at = front.select("walk_id", "part0", F.col("dst").alias("src"), F.col("dst_part").alias("src_part"), "wdeg", "chunks")
        at = at.withColumn("r", draw(seed, STEP, "walk_id", F.lit(level), backend=backend) % F.col("wdeg"))
        at = at.withColumn("chunk", F.expr("r div cast(ceil(wdeg / chunks) as bigint)")).drop("wdeg", "chunks")
        got = at.join(index.select("src", "chunk", "items"), ["src", "chunk"]).withColumn("x", F.element_at(F.filter("items", lambda i: i["hi"] > F.col("r")), 1))
        step = got.select("walk_id", "part0", F.lit(level).alias("step"), "src", F.col("x.dst").alias("dst"), "src_part", F.col("x.dst_part").alias("dst_part"), F.col("x.wdeg").alias("wdeg"), F.col("x.chunks").alias("chunks"))
        if stop == "boundary":
            step = step.where("dst_part = part0")
        front = store(step, "steps")
        n = front.count()
        if not n:
            break
        visited += n
        levels.append(front)
    out = levels[0]
    for x in levels[1:]:
        out = out.unionByName(x)
    return out.select([c.split()[0] for c in STEPS.split(", ")])


def _walk_part(edges: pd.DataFrame, walkers: pd.DataFrame, length: int, stop: str, seed: int, backend: str, whole: bool = False) -> pd.DataFrame:
    """All steps of `walkers` (walk_id, part0, step, at, here) on the edges of one part, up to and with the step that leaves it; of a `whole` graph, none leaves."""
    columns = [c.split()[0] for c in STEPS.split(", ")]
    empty = pd.DataFrame({c: np.zeros(0, dtype=np.int64) for c in columns})
    if not len(edges) or not len(walkers):
        return empty
    order = np.lexsort((edges["dst"].to_numpy(), edges["src"].to_numpy()))
    src, dst, dst_part = (edges[c].to_numpy()[order] for c in ("src", "dst", "dst_part"))
    upto = np.cumsum(edges["w"].to_numpy()[order])
    first = np.flatnonzero(np.concatenate(([True], src[1:] != src[:-1])))
    owners, ends = src[first], upto[np.concatenate((first[1:], [len(src)])) - 1]
    starts = np.concatenate(([0], ends[:-1]))
    walk, part0, step, at, here = (walkers[c].to_numpy().astype(np.int64) for c in ("walk_id", "part0", "step", "at", "here"))
    out = []
    while len(walk):
        k = np.searchsorted(owners, at)
        r = draw_numpy(seed, STEP, walk, step, backend=backend) % (ends[k] - starts[k])
        e = np.searchsorted(upto, starts[k] + r, side="right")
        nxt, nxt_part = dst[e], dst_part[e].astype(np.int64)
        keep = nxt_part == part0 if stop == "boundary" else np.ones(len(walk), dtype=bool)
        out.append(np.stack([walk, part0, step, at, nxt, here, nxt_part], axis=1)[keep])
        on = (keep if whole else nxt_part == here) & (step + 1 < length)
        walk, part0, step, at, here = walk[on], part0[on], step[on] + 1, nxt[on], nxt_part[on]
    return pd.DataFrame(np.concatenate(out), columns=columns) if out else empty


#: Edges that one task holds; a walker never needs more of a graph than the lists it meets, so larger parts go level by level.
BLOCK_EDGES = 3 << 20
#: Steps that one task walks on a graph held whole.
TASK_STEPS = 1 << 20


def _front(steps: DataFrame, part) -> DataFrame:
    """Walkers at the far ends of `steps`, for their next step."""
    return steps.select("walk_id", "part0", (F.col("step") + 1).alias("step"), F.col("dst").alias("at"), F.col("dst_part").alias("here"), part.alias("part"))


def _lists_of(g: Graph, part, unit_weights: bool) -> DataFrame:
    return g.edges.select(part.alias("part"), "src", "dst", (F.lit(1).cast("long") if unit_weights else F.col("w")).alias("w"), "dst_part")


def _all(levels: list[DataFrame]) -> DataFrame:
    out = levels[0]
    for x in levels[1:]:
        out = out.unionByName(x)
    return out


def walk_block(g: Graph, roots: DataFrame, length: int = 100, stop: str = "length", seed: int = 7, backend: str = "xx", unit_weights: bool = False) -> DataFrame:
    """The steps of walk_join, in numpy, from as few supersteps as the size of the graph lets.

    A graph of up to BLOCK_EDGES edges is held whole by each task, which walks TASK_STEPS steps on it: one superstep. Parts of up to as
    many edges walk their walkers until they leave them: as many supersteps as the most crossed walk has crossings. Larger parts
    don't fit a task: walkers move a level at a time, and only the lists of vertices that they stand on are read.
    """
    spark = g.edges.sparkSession
    first = _first_steps(roots)
    if stop == "boundary":
        first = first.where("dst_part = src_part")
    first = store(first, "steps")
    if length < 2:
        return first
    walkers, edges = first.count(), g.edges.count()
    copies = max(1, -(-walkers * length // TASK_STEPS))
    whole = stop == "length" and edges <= BLOCK_EDGES and copies <= length
    if not whole and edges > BLOCK_EDGES and g.edges.groupBy("src_part").count().agg(F.max("count")).first()[0] > BLOCK_EDGES:
        if walkers <= FEW:
            return _all(_walk_levels(g, [first], 1, length, stop, seed, backend, unit_weights))
        return walk_join(neighbor_index(g, unit_weights=unit_weights), roots, length, stop, seed=seed, backend=backend)
    # Edges lie in buckets of their part for all supersteps: only the walkers that left are exchanged.
    tables = Buckets(spark, max(1, min(copies if whole else g.parts, int(spark.conf.get("spark.sql.shuffle.partitions")))))
    held = tables.keep(_lists_of(g, F.explode(F.sequence(F.lit(0), F.lit(copies - 1))) if whole else F.col("src_part"), unit_weights), "adjacency")
    dealt = F.pmod(F.xxhash64("walk_id"), F.lit(copies)).cast("int") if whole else F.col("dst_part")
    levels, front = [first], _front(first, dealt)

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return _walk_part(a, b, length, stop, seed, backend, whole)

    while True:
        took = store(held.groupBy("part").cogroup(front.groupBy("part")).applyInPandas(run, STEPS), "steps")
        levels.append(took)
        if whole or stop == "boundary":
            break
        front = _front(took.where((F.col("dst_part") != F.col("src_part")) & (F.col("step") + 1 < length)), dealt)
        if front.isEmpty():
            break
    tables.forget()
    return _all(levels)


def _walk_levels(g: Graph, levels: list[DataFrame], begin: int, length: int, stop: str, seed: int, backend: str, unit_weights: bool = False) -> list[DataFrame]:
    """`levels` and those from step `begin` on, a scan of the edges each, for walkers too few to index the whole graph for."""
    levels = list(levels)
    for level in range(begin, length):
        at = levels[-1].select("walk_id", "part0", F.col("dst").alias("src"), F.col("dst_part").alias("src_part"))
        lists = near(g, at.select("src").distinct(), unit_weights)
        total = lists.groupBy("src").agg(F.max("hi").alias("total"))
        aimed = at.join(total, "src").withColumn("r", draw(seed, STEP, "walk_id", F.lit(level), backend=backend) % F.col("total")).drop("total")
        step = pick(aimed, lists.select("src", "dst", "dst_part", "lo", "hi"), ["src"]).select("walk_id", "part0", F.lit(level).alias("step"), "src", "dst", "src_part", "dst_part")
        if stop == "boundary":
            step = step.where("dst_part = part0")
        levels.append(store(step, "steps"))
        forget(lists)
        if stop == "boundary" and levels[-1].isEmpty():
            break
    return levels


class LongWalk:
    """The steps of one walk of walk_block, taken up again where it stopped.

    Its walker sits in one task at a time. A graph of up to `block_edges` edges is held and walked by one task; of a larger one, the
    lists of the vertices that the walk meets are read, a step at a time.
    """

    def __init__(self, g: Graph, root: DataFrame, seed: int = 7, backend: str = "xx", block_edges: int = BLOCK_EDGES):
        self.g, self.seed, self.backend = g, seed, backend
        self.held = store(_lists_of(g, F.lit(0), False).repartition("part"), "adjacency") if g.edges.count() <= block_edges else None
        self.levels, self.walked = [store(_first_steps(root), "steps")], 1

    def until(self, length: int) -> DataFrame:
        """All steps (STEPS) of the walk, `length` of them."""
        seed, backend = self.seed, self.backend

        def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
            return _walk_part(a, b, length, "length", seed, backend, whole=True)

        if length > self.walked:
            if self.held is None:
                self.levels = _walk_levels(self.g, self.levels, self.walked, length, "length", seed, backend)
            else:
                front = _front(self.levels[-1].where(F.col("step") == self.walked - 1), F.lit(0))
                self.levels.append(store(self.held.groupBy("part").cogroup(front.groupBy("part")).applyInPandas(run, STEPS), "steps"))
            self.walked = length
        return _all(self.levels)


def biased_walk(g: Graph, starts: DataFrame, length: int, ret: float = 1.0, inout: float = 1.0, seed: int = 7, backend: str = "xx", scale: int = 1000) -> DataFrame:
    """Second-order walks: the weight of a candidate x after (t, v) is w / ret if x = t, w if x neighbours t, else w / inout.

    Weights are integers, round(w * bias * scale). A level joins walkers with v's edges, tests t-x by an equi join, and picks by
    prefix sums; hubs make this the costly baseline it is meant to be. `starts` are roots (walk_id, part, u, v, v_part).
    """
    e = g.edges.select(F.col("src"), F.col("dst"), "w", "dst_part")
    known = g.edges.select(F.col("src").alias("t"), F.col("dst").alias("x"), F.lit(True).alias("near"))
    first = store(_first_steps(starts), "steps")
    levels, front = [first], first
    for level in range(1, length):
        at = front.select("walk_id", "part0", F.col("src").alias("t"), F.col("dst").alias("src"), F.col("dst_part").alias("src_part"))
        cand = at.join(e, "src").withColumnRenamed("dst", "x").join(known, ["t", "x"], "left")
        bias = F.when(F.col("x") == F.col("t"), 1.0 / ret).when(F.col("near"), 1.0).otherwise(1.0 / inout)
        cand = prefix(cand.withColumn("bw", F.greatest(F.lit(1), F.round(F.col("w") * bias * scale)).cast("long")), ["walk_id"], ["x"], "bw")
        total = F.max("hi").over(Window.partitionBy("walk_id"))
        got = cand.withColumn("r", draw(seed, STEP, "walk_id", F.lit(level), backend=backend) % total).where("r >= lo and r < hi")
        front = store(got.select("walk_id", "part0", F.lit(level).alias("step"), "src", F.col("x").alias("dst"), "src_part", "dst_part"), "steps")
        levels.append(front)
    out = levels[0]
    for x in levels[1:]:
        out = out.unionByName(x)
    return out


def walk_pairs(steps: DataFrame, window: int = 2, unit: str = "nodes") -> DataFrame:
    """(walk_id, step, hop, part, u, v, v_part): consecutive vertices, or all within `window` nodes (hops: up to `window` apart)."""
    if unit not in ("nodes", "hops") or window < 1:
        raise ValueError("window must be 1 or more, unit nodes or hops")
    hops = window - 1 if unit == "nodes" else window
    order = Window.partitionBy("walk_id").orderBy("step")
    ends = [F.struct(F.lit(k + 1).alias("hop"), (F.col("dst") if k == 0 else F.lead("dst", k).over(order)).alias("v"), (F.col("dst_part") if k == 0 else F.lead("dst_part", k).over(order)).alias("v_part")) for k in range(hops)]
    if not ends:
        return steps.limit(0).select("walk_id", "step", F.lit(1).alias("hop"), F.col("src_part").alias("part"), F.col("src").alias("u"), F.col("dst").alias("v"), F.col("dst_part").alias("v_part"))
    spread = steps.select("walk_id", "step", F.col("src_part").alias("part"), F.col("src").alias("u"), F.array(*ends).alias("ends"))
    return spread.select("walk_id", "step", "part", "u", F.explode("ends").alias("e")).where("e.v is not null").select("walk_id", "step", "e.hop", "part", "u", "e.v", "e.v_part")



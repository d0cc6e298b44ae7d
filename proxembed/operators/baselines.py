"""Baselines: single-owner edge sampling, biased and uniform walks, pooled block training, edge buckets, a spectral reference."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxembed.functions.rng import ROOT, draw
from proxembed.functions.vectors import pack
from proxembed.operators.graph import Graph
from proxembed.operators.kernels import run_exact
from proxembed.operators.measure import timed
from proxembed.operators.pairs import numbered
from proxembed.operators.partition import cut_by_vertex
from proxembed.operators.sampling import negatives, pick, root_ranges, roots
from proxembed.operators.storage import store
from proxembed.operators.train import STATE, TrainConfig, embedding, init_blocks, initial_vectors, signed, train
from proxembed.operators.variants import SampleConfig, Variant, sample
from proxembed.operators.walks import biased_walk, walk_block, walk_pairs


def edge_pairs(g: Graph, batches: int, batch_size: int, seed: int = 7, backend: str = "xx") -> DataFrame:
    """Positive pairs drawn straight from edges in proportion to weight: (batch, part, seq, u, v, v_part)."""
    ranges = root_ranges(g)
    totals = ranges.groupBy("part").agg(F.max("hi").alias("total"))
    grid = g.edges.sparkSession.range(batches * batch_size).select(F.expr(f"cast(id div {batch_size} as int)").alias("batch"), F.expr(f"id % {batch_size}").alias("seq"))
    asked = grid.crossJoin(totals).withColumn("r", draw(seed, ROOT, "batch", "part", "seq", backend=backend) % F.col("total")).drop("total")  # a draw for each, by definition
    return pick(asked, ranges, ["part"]).select("batch", "part", "seq", "u", "v", "v_part")


def sampling_only(g: Graph, variant: Variant, c: SampleConfig) -> DataFrame:
    """What samplers without training do: a row a part of pairs drawn, walk calls, steps handed over and seconds."""
    took: dict[str, float] = {}
    with timed(took, "sampling"):
        drawn = sample(g, variant, c)
    per = drawn.pairs.groupBy("part").agg(F.count("*").alias("pairs"), F.countDistinct("batch").alias("batches"))
    return per.withColumns({"variant": F.lit(str(variant)), "calls": F.lit(drawn.calls), "handed": F.lit(drawn.handed), "seconds": F.lit(took["sampling"])})


def one_owner(g: Graph) -> Graph:
    return cut_by_vertex(g, 1)


def fit_pairs(g: Graph, pairs: DataFrame, c: TrainConfig, k: int, batches: int, epochs: int = 1) -> DataFrame:
    """Train on given pairs with k negatives; `epochs` repeats them in order inside a part's kernel superstep."""
    rows = signed(pairs, negatives(pairs, g, k, seed=c.seed))
    if epochs > 1:
        rows = rows.withColumn("_e", F.explode(F.sequence(F.lit(0), F.lit(epochs - 1)))).withColumn("batch", (F.col("batch") + F.col("_e") * batches).cast("int")).drop("_e")
    return embedding(train(g, rows, c, batches * epochs), c.dim)


#: Positives of a batch of the single-owner baselines: a superstep holds one batch in its one task.
PER_BATCH = 65_536


def fit_edge_sgd(g: Graph, c: TrainConfig, samples: int, k: int = 1) -> DataFrame:
    """One owner, no walks: edges drawn by weight, negatives from the noise distribution, in batches of PER_BATCH at most."""
    one = one_owner(g)
    batches = -(-samples // PER_BATCH)
    pairs = edge_pairs(one, batches, -(-samples // batches), c.seed)
    return fit_pairs(one, pairs, c, k, batches)


def _walk_corpus(g: Graph, walks: int) -> DataFrame:
    one = one_owner(g)
    return roots(one, 1, walks)


def fit_biased_walk(g: Graph, c: TrainConfig, walks: int, length: int = 20, window: int = 5, ret: float = 1.0, inout: float = 1.0, k: int = 1) -> DataFrame:
    """Second-order walks and a window, one owner."""
    one = one_owner(g)
    pairs, batches = _as_batches(walk_pairs(biased_walk(one, _walk_corpus(g, walks), length, ret, inout, c.seed), window, "hops"))
    return fit_pairs(one, pairs, c, k, batches)


def fit_uniform_walk(g: Graph, c: TrainConfig, walks: int, length: int = 20, window: int = 5, k: int = 1) -> DataFrame:
    """First-order walks that ignore weights, and a window."""
    one = one_owner(g)
    pairs, batches = _as_batches(walk_pairs(walk_block(one, _walk_corpus(g, walks), length, seed=c.seed, unit_weights=True), window, "hops"))
    return fit_pairs(one, pairs, c, k, batches)


def _as_batches(pairs: DataFrame) -> tuple[DataFrame, int]:
    """Pairs in hashed order, in batches of about PER_BATCH."""
    held = store(pairs, "corpus")
    batches = max(1, -(-held.count() // PER_BATCH))
    dealt = held.withColumn("_h", F.xxhash64("walk_id", "step", "hop")).withColumn("batch", F.pmod(F.xxhash64("walk_id", "step", "hop", F.lit(1)), F.lit(batches)).cast("int"))
    return store(numbered(dealt, ["batch", "part"], ["_h", "walk_id", "step", "hop"]).select("batch", "part", "seq", "u", "v", "v_part"), "pairs"), batches


def fit_pooled(g: Graph, c: TrainConfig, walks: int, length: int = 20, pools: int = 4, k: int = 1) -> DataFrame:
    """A pool that walks fill and training empties in shuffled order, in blocks of (u range, v range): a decoupled sampler."""
    one = one_owner(g)
    pairs = walk_pairs(walk_block(one, _walk_corpus(g, walks), length, seed=c.seed))
    half = max(1, g.n // 2)
    pooled = pairs.withColumns({"batch": F.pmod(F.xxhash64("walk_id"), F.lit(pools)).cast("int"), "_b": F.least(F.expr(f"u div {half}"), F.lit(1)) * 2 + F.least(F.expr(f"v div {half}"), F.lit(1)), "_h": F.xxhash64("walk_id", "step")})
    return fit_pairs(one, store(numbered(pooled, ["batch", "part"], ["_b", "_h", "walk_id", "step"]).select("batch", "part", "seq", "u", "v", "v_part"), "pairs"), c, k, pools)


def schedule(spark: SparkSession, buckets: int) -> DataFrame:
    """Rounds of a Latin square: (i, (i + r) mod p) in round r, so no bucket of either side is met twice in a round."""
    grid = spark.range(buckets * buckets)
    return grid.select(F.expr(f"id div {buckets}").alias("bucket_u"), F.expr(f"(id div {buckets} + id % {buckets}) % {buckets}").alias("bucket_v"), F.expr(f"id % {buckets}").alias("round"))


def fit_bucketed(g: Graph, c: TrainConfig, samples: int, buckets: int, epochs: int = 1, k: int = 1) -> DataFrame:
    """Edge buckets by (part of u, part of v), trained in rounds that share no partition; partitions move between rounds.

    The parameter-server stand-in: a round's buckets train independently on U of one partition and C of the other, which both
    go back to their stored tables afterwards. `samples` edges are drawn by weight, the same number (up to one) from each
    partition of u; negatives come from the context partition of the positive's own bucket.
    """
    cut = cut_by_vertex(g, buckets)
    per = -(-samples // buckets)
    drawn = edge_pairs(cut, 1, per, c.seed).where(F.col("seq") * buckets + F.col("part") < samples)
    # Negatives of a pair are drawn in the part that holds its v: scope `local` seen from there.
    swapped = drawn.select("batch", F.col("v_part").cast("int").alias("part"), (F.col("seq") * buckets + F.col("part")).alias("seq"), "u", F.col("part").alias("_own"), F.col("seq").alias("_seq"))
    wrong = negatives(swapped, cut, k, seed=c.seed, scope="local").join(swapped.select("part", "seq", "_own", "_seq"), ["part", "seq"])
    wrong = wrong.select("batch", F.col("_own").alias("part"), F.col("_seq").alias("seq"), "j", "u", "v", "v_part")
    rows = store(signed(drawn, wrong).withColumn("round", F.pmod(F.col("v_part") - F.col("part"), F.lit(buckets))), "bucketed", by=["round"])
    u_side = store(init_blocks(cut, c).select("part", "vids", "u", "c"), "state")
    for _ in range(epochs):
        for r in range(buckets):
            mine = rows.where(F.col("round") == r).select("part", "u", "v", "sign", "seq", "j")
            there = u_side.select(F.pmod(F.col("part") - r, F.lit(buckets)).cast("int").alias("part"), F.col("part").alias("c_part"), F.col("vids").alias("c_vids"), "c")
            both = u_side.select("part", "vids", "u").join(there, "part")

            def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
                if not len(a):
                    return pd.DataFrame(columns=["part", "vids", "u", "c_part", "c"])
                row = a.iloc[0]
                vids, c_vids = np.frombuffer(row["vids"], "<i8"), np.frombuffer(row["c_vids"], "<i8")
                U, C = (np.frombuffer(row[x], "<f4").reshape(-1, c.dim).copy() for x in ("u", "c"))
                if len(b):
                    b = b.sort_values(["seq", "j"], kind="stable")
                    run_exact(U, C, np.searchsorted(vids, b["u"].to_numpy()), np.searchsorted(c_vids, b["v"].to_numpy()), b["sign"].to_numpy(), c.lr, c.neg_weight, c.decay)
                return pd.DataFrame([(int(row["part"]), row["vids"], pack(U), int(row["c_part"]), pack(C))], columns=["part", "vids", "u", "c_part", "c"])

            out = store(both.groupBy("part").cogroup(mine.groupBy("part")).applyInPandas(run, "part int, vids binary, u binary, c_part int, c binary"), "round")
            u_side = store(out.select("part", "vids", "u").join(out.select(F.col("c_part").alias("part"), "c"), "part"), "state")
    return embedding(u_side.withColumn("kind", F.lit(STATE)), c.dim)


#: Vertices up to which the whole spectrum is taken; larger graphs are met by products with their edges alone.
DENSE = 2000


def fit_spectral_small(g: Graph, dim: int) -> DataFrame:
    """Eigenvectors of the normalised adjacency to the `dim` eigenvalues of largest size, scaled by their roots, in one task.

    Up to DENSE vertices by the whole spectrum; above, by restarted block Krylov spaces, whose task holds the edges and some eight
    blocks of dim + 4 numbers a vertex. Of equal eigenvalues either way may give any basis.
    """
    n = g.n

    def run(x: pd.DataFrame) -> pd.DataFrame:
        src, dst, w = (x[c].to_numpy() for c in ("src", "dst", "w"))
        d = np.maximum(np.bincount(src, w, n), 1e-12)
        w = w / np.sqrt(d[src] * d[dst])
        if n <= DENSE:
            a = np.zeros((n, n))
            a[src, dst] = w
            values, vectors = np.linalg.eigh(a)
            top = np.argsort(-np.abs(values))[:dim]
            values, vectors = values[top], vectors[:, top]
        else:
            values, vectors = top_eigenpairs(lambda q: np.stack([np.bincount(src, w * c[dst], n) for c in q.T], axis=1), n, dim)
        e = (vectors * np.abs(values) ** 0.5).astype(np.float32)
        return pd.DataFrame({"vid": np.arange(n), "part": 0, "u": list(e), "c": list(e)})

    return g.edges.select("src", "dst", "w").withColumn("_one", F.lit(1)).groupBy("_one").applyInPandas(run, "vid long, part int, u array<float>, c array<float>")


def top_eigenpairs(product, n: int, dim: int, blocks: int = 4, tolerance: float = 1e-7, most: int = 1000) -> tuple[np.ndarray, np.ndarray]:
    """(values, vectors) of a symmetric matrix's `dim` eigenvalues of largest size, from `product` with blocks of columns.

    A block wider than `dim` meets eigenvalues that come several times; directions that a space already holds are left out.
    Spaces restart from their best vectors until all residuals are below the tolerance; not getting there is an error.
    """
    width = min(n, dim + 4)
    start = np.linalg.qr(np.random.default_rng(7).normal(size=(n, width)))[0]
    basis = np.empty((n, width * blocks))
    for _ in range(most):
        h, lo, size = np.zeros((width * blocks, width * blocks)), 0, width
        basis[:, :size] = start
        for k in range(blocks):
            step = product(basis[:, lo:size])
            held = basis[:, :size]
            h[:size, lo:size] = held.T @ step
            if k == blocks - 1:
                break
            for _ in range(2):
                step -= held @ (held.T @ step)
            q, r = np.linalg.qr(step)
            u, lengths, _ = np.linalg.svd(r)
            step = q @ u[:, lengths > 1e-9]
            if not step.shape[1]:
                break
            for _ in range(2):
                step -= held @ (held.T @ step)
            step = np.linalg.qr(step)[0]
            lo, size = size, size + step.shape[1]
            basis[:, lo:size] = step
        values, inner = np.linalg.eigh((np.triu(h) + np.triu(h, 1).T)[:size, :size])
        top = np.argsort(-np.abs(values))[:width]
        values, start = values[top], basis[:, :size] @ inner[:, top]
        missed = np.linalg.norm(product(start[:, :dim]) - start[:, :dim] * values[:dim], axis=0)
        if missed.max() <= tolerance:
            return values[:dim], start[:, :dim]
        start = np.linalg.qr(start)[0]
    raise ValueError(f"the spectral reference has residuals of {missed.max():.1e} after {most} restarts")


def initial(g: Graph, c: TrainConfig) -> DataFrame:
    """Untrained vectors, the floor of every comparison."""
    def run(batches):
        for b in batches:
            u, ctx = initial_vectors(b["vid"].to_numpy(), c)
            yield pd.DataFrame({"vid": b["vid"], "part": b["part"], "u": list(u), "c": list(ctx)})

    return g.vertices.select("vid", "part").mapInPandas(run, "vid long, part int, u array<float>, c array<float>")



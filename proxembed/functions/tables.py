"""Table functions for SQL: a walk on a small graph, and the rows of an alias table."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from proxembed.functions.rng import STEP, draw_numpy
from proxembed.operators.graph import Graph
from proxembed.operators.sampling import alias_table

SMALL = 100_000


def register_walk(spark: SparkSession, g: Graph, seed: int = 7, name: str = "walk_from") -> None:
    """walk_from(vid, length) -> (step, src, dst). The graph travels with the function, so it may hold at most SMALL edges."""
    rows = g.edges.select("src", "dst", "w").limit(SMALL + 1).collect()
    if len(rows) > SMALL:
        raise ValueError(f"walk_from takes graphs of at most {SMALL} stored edges")
    near: dict[int, tuple[list[int], list[int]]] = {}
    for r in sorted(rows):
        to, hi = near.setdefault(r["src"], ([], []))
        to.append(r["dst"])
        hi.append((hi[-1] if hi else 0) + r["w"])

    class WalkFrom:
        def eval(self, vid: int, length: int):
            at = vid
            for step in range(length):
                if at not in near:
                    return
                to, hi = near[at]
                r = int(draw_numpy(seed, STEP, np.int64(vid), np.int64(step))) % hi[-1]
                nxt = to[int(np.searchsorted(hi, r, side="right"))]
                yield step, at, nxt
                at = nxt

    spark.udtf.register(name, udtf(WalkFrom, returnType="step int, src long, dst long"))


def register_alias(spark: SparkSession, name: str = "alias_rows") -> None:
    """alias_rows(weights) -> (cell, threshold, other)."""

    class AliasRows:
        def eval(self, weights: list):
            threshold, other = alias_table(np.array(weights, dtype=np.float64))
            for k, (t, o) in enumerate(zip(threshold, other, strict=True)):
                yield k, float(t), int(o)

    spark.udtf.register(name, udtf(AliasRows, returnType="cell int, threshold double, other int"))

"""When a batch is full: stop rules over yields, and the spill folds over counts."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

RULES = ("any", "all")


def running_yields(yields: DataFrame) -> DataFrame:
    """(batch, part, round, pairs) -> + total up to the round."""
    w = Window.partitionBy("batch", "part").orderBy("round").rowsBetween(Window.unboundedPreceding, 0)
    return yields.withColumn("total", F.sum("pairs").over(w))


def rounds_needed(yields: DataFrame, batch_size: int, rule: str) -> DataFrame:
    """(batch, rounds): rounds until some part (`any`) or every part (`all`) holds `batch_size`; null where none suffices."""
    if rule not in RULES:
        raise ValueError("rule must be any or all")
    reached = F.max("total") if rule == "any" else F.min("total")
    per_round = running_yields(yields).groupBy("batch", "round").agg(reached.alias("reached"))
    return per_round.groupBy("batch").agg(F.min(F.when(F.col("reached") >= batch_size, F.col("round") + 1)).alias("rounds"))


def kept_counts(yields: DataFrame, batch_size: int, rule: str) -> DataFrame:
    """(batch, part, rounds, drawn, kept) after the rule and pruning; parts that drew nothing count."""
    rounds = rounds_needed(yields, batch_size, rule)
    in_time = yields.join(rounds, "batch").where("rounds is not null and round < rounds")
    drawn = in_time.groupBy("batch", "part", "rounds").agg(F.sum("pairs").alias("drawn"))
    return drawn.withColumn("kept", F.least("drawn", F.lit(batch_size)))


def idle_parts(g, parts: int) -> DataFrame:
    """Parts without edges: they can never fill, so the rule `all` waives their quota and reports them."""
    spark = g.edges.sparkSession
    return spark.range(parts).select(F.col("id").cast("int").alias("part")).join(g.edges.select(F.col("src_part").alias("part")).distinct(), "part", "left_anti")


def spill_fold(counts: np.ndarray, batch_size: int, batches: int, rule: str, keep: str, waived: np.ndarray | None = None) -> pd.DataFrame:
    """Fold batches over a (calls, parts) table of pairs drawn by each walk call.

    keep: `none` drops what a batch leaves, `ever` keeps it, `once` lets only the next batch use it (and calls at least once a
    batch). Pairs of a part stand in order of their calls; a row says that a batch takes [start, start + kept) of that order.
    Columns: batch, part, calls, start, kept, spill. Batches that the calls don't fill are absent.
    """
    calls, parts = counts.shape
    quota = np.ones(parts, dtype=bool) if waived is None else ~waived
    begin = np.concatenate((np.zeros((1, parts), dtype=np.int64), np.cumsum(counts, axis=0)))
    start, at, rows = np.zeros(parts, dtype=np.int64), 0, []
    for b in range(batches):
        first = at
        while True:
            have = begin[at] - start
            full = (have >= batch_size)[quota]
            met = bool(full.any() if rule == "any" else full.all()) if quota.any() else True
            if met and not (at == first and keep != "ever"):
                break
            if at == calls:
                return pd.DataFrame(rows, columns=["batch", "part", "calls", "start", "kept", "spill"])
            at += 1
        taken = np.minimum(begin[at] - start, batch_size)
        after = start + taken
        if keep == "once":
            after = np.maximum(after, begin[first])
        left = begin[at] - after if keep != "none" else np.zeros(parts, dtype=np.int64)
        rows += [(b, p, at - first, int(start[p]), int(taken[p]), int(left[p])) for p in range(parts)]
        start = begin[at].copy() if keep == "none" else after
    return pd.DataFrame(rows, columns=["batch", "part", "calls", "start", "kept", "spill"])


def spill_slices(yields: DataFrame, parts: int, batch_size: int, batches: int, rule: str, keep: str, waived: list[int] | None = None) -> DataFrame:
    """The fold as a DataFrame: (call, part, pairs) counts, p x calls integers, go to one task; pairs never do."""
    off = np.isin(np.arange(parts), waived or [])

    def run(x: pd.DataFrame) -> pd.DataFrame:
        counts = np.zeros((int(x["call"].max()) + 1, parts), dtype=np.int64)
        np.add.at(counts, (x["call"].to_numpy(), x["part"].to_numpy()), x["pairs"].to_numpy())
        return spill_fold(counts, batch_size, batches, rule, keep, off)

    return yields.select("call", "part", "pairs").withColumn("_one", F.lit(1)).groupBy("_one").applyInPandas(lambda x: run(x), "batch long, part long, calls long, start long, kept long, spill long")


def reuse_all_closed_form(yields: DataFrame, batch_size: int, batches: int) -> DataFrame:
    """`ever` under `all` without a fold: batch b is met at the first call where every part's total is (b + 1) * batch_size."""
    totals = running_yields(yields.withColumn("batch", F.lit(0)).withColumnRenamed("call", "round")).groupBy("round").agg(F.min("total").alias("low"))
    wanted = yields.sparkSession.range(batches).select(F.col("id").alias("batch"))
    full = totals.select("round", F.least(F.expr(f"low div {batch_size}"), F.lit(batches)).alias("full")).where("full > 0")
    met = full.select("round", F.explode(F.sequence(F.lit(0).cast("long"), F.col("full") - 1)).alias("batch")).groupBy("batch").agg((F.min("round") + 1).alias("calls_by_then"))
    return wanted.join(met, "batch").select("batch", F.col("calls_by_then").cast("long").alias("calls_by_then"))

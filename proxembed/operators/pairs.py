"""Pairs of a batch: settling with their owner, pruning, and what must be fetched for them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxembed.functions.rng import PRUNE, draw


def settle(pairs: DataFrame) -> DataFrame:
    """Pairs dealt to their batch and their first end's owner, wherever they were drawn: one shuffle."""
    return pairs.repartition("batch", "part")


def numbered(pairs: DataFrame, keys: list[str], order: list[str]) -> DataFrame:
    return pairs.withColumn("seq", (F.row_number().over(Window.partitionBy(*keys).orderBy(*order)) - 1).cast("long"))


def prune(pairs: DataFrame, batch_size: int, seed: int = 7, backend: str = "xx") -> DataFrame:
    """Shuffle by draws of (batch, part, seq) and keep `batch_size` for each batch and part; Spark limits groups before the shuffle."""
    shuffled = pairs.withColumn("_d", draw(seed, PRUNE, "batch", "part", "seq", backend=backend))
    rank = F.row_number().over(Window.partitionBy("batch", "part").orderBy("_d", "seq"))
    return shuffled.withColumn("_r", rank).where(F.col("_r") <= batch_size).withColumn("seq", (F.col("_r") - 1).cast("long")).drop("_d", "_r")


def serve_list(pairs: DataFrame) -> DataFrame:
    """(batch, part, v, to_part): contexts that owners send each batch, known before training and each only once."""
    return pairs.where("v_part <> part").select("batch", F.col("v_part").alias("part"), "v", F.col("part").alias("to_part")).distinct()

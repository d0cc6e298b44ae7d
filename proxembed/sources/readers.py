"""Edge lists in and embeddings out: text, CSV, JSON, ORC, Parquet, and a binary offset-and-target format as a data source."""

from __future__ import annotations

import os
import struct

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EDGE_SCHEMA = "a string, b string, w long"


def read_edge_list(spark: SparkSession, path: str, fmt: str = "text", sep: str = r"\s+", a: str = "a", b: str = "b", w: str | None = None) -> DataFrame:
    """(a, b, w) rows; text lines hold two or three fields, `#` starts a comment, weight 1 where there is none."""
    if fmt == "text":
        parts = spark.read.text(path).where("value not like '#%' and trim(value) <> ''").select(F.split(F.trim("value"), sep).alias("f"))
        return parts.select(F.col("f")[0].alias("a"), F.col("f")[1].alias("b"), F.coalesce(F.try_element_at("f", F.lit(3)).cast("long"), F.lit(1)).alias("w"))
    if fmt == "csv":
        rows = spark.read.csv(path, sep=sep if sep != r"\s+" else ",", header=True, comment="#")
    elif fmt in ("json", "orc", "parquet"):
        rows = spark.read.format(fmt).load(path)
    else:
        raise ValueError(f"unknown format {fmt!r}")
    return rows.select(F.col(a).cast("string").alias("a"), F.col(b).cast("string").alias("b"), (F.col(w).cast("long") if w else F.lit(1).cast("long")).alias("w"))


def write_edges(edges: DataFrame, path: str) -> None:
    """Directed edges by owner, sorted by source: scans of a part prune to its folder."""
    edges.repartition("src_part").sortWithinPartitions("src", "dst").write.partitionBy("src_part").parquet(path)


def write_word2vec(vectors: DataFrame, path: str) -> None:
    """`key v1 ... vd` lines."""
    vectors.select(F.concat_ws(" ", F.col("key"), F.concat_ws(" ", F.transform("u", lambda x: x.cast("string"))))).write.text(path)


def write_offsets(edges: DataFrame, n: int, path: str) -> None:
    """offsets.bin (n + 1 longs) and targets.bin (longs), little-endian, in order of (src, dst); for graphs of one machine."""
    os.makedirs(path, exist_ok=True)
    degree = [0] * n
    with open(f"{path}/targets.bin", "wb") as f:
        for r in edges.select("src", "dst").orderBy("src", "dst").toLocalIterator():
            degree[r["src"]] += 1
            f.write(struct.pack("<q", r["dst"]))
    total = 0
    with open(f"{path}/offsets.bin", "wb") as f:
        f.write(struct.pack("<q", 0))
        for d in degree:
            total += d
            f.write(struct.pack("<q", total))


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class OffsetReader(DataSourceReader):
    """A partition for each range of vertices."""

    def __init__(self, options: dict):
        self.path, self.slices = options["path"], int(options.get("slices", "8"))

    def partitions(self):
        n = os.path.getsize(f"{self.path}/offsets.bin") // 8 - 1
        step = max(1, -(-n // self.slices))
        return [_Range(k, min(n, k + step)) for k in range(0, n, step)]

    def read(self, partition):
        with open(f"{self.path}/offsets.bin", "rb") as f:
            f.seek(8 * partition.lo)
            offsets = struct.unpack(f"<{partition.hi - partition.lo + 1}q", f.read(8 * (partition.hi - partition.lo + 1)))
        with open(f"{self.path}/targets.bin", "rb") as f:
            f.seek(8 * offsets[0])
            targets = struct.unpack(f"<{offsets[-1] - offsets[0]}q", f.read(8 * (offsets[-1] - offsets[0])))
        for k in range(partition.hi - partition.lo):
            for at in range(offsets[k] - offsets[0], offsets[k + 1] - offsets[0]):
                yield (partition.lo + k, targets[at])


class OffsetSource(DataSource):
    """spark.dataSource.register(OffsetSource); spark.read.format("graph_offsets").load(path)"""

    @classmethod
    def name(cls) -> str:
        return "graph_offsets"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema):
        return OffsetReader(self.options)

"""Nearest neighbours by an inverted multi-index.

Vectors are cut in halves and each half is quantised by its own k-means, fitted on at most `fit_rows` rows (those with the
smallest hash of vec_id); a row lies in the cell of its pair of centroids. There are CENTROIDS times the fourth root of the
rows centroids to a half, as far as the fitted rows support them, so cells grow with the square root of the rows. A query walks centroid pairs from the best summed inner product downwards
with a heap, and all rows of the cells walked are reranked by the exact inner product of the original vectors in double
precision.

How far it walks is measured, not set: `probes` of the queries (those with the smallest hash) are answered by brute force
over all rows, and the walk is as long as brings `recall` of their true neighbours into the walked cells. Clustered vectors
so get short walks; vectors without structure get long ones, for no index can find their neighbours among few rows.

Cells lie in shards of about `SHARD_ROWS` rows in cell order (a larger cell, such as one of equal vectors, is dealt over
several), queries in blocks in the order of their own best cells, so a block's queries walk alike. A shard meets only the
blocks with a query that walks one of its cells; which cells those are, the shard's task knows from the score the walk ended
at. Only shard-by-block top lists meet again. The driver holds one number for each cell.

Defined cases: vectors that are null, zero, of another length than most, or that hold null or non-finite components take
no part, nor do rows without vec_id; a query never meets rows of its own vec_id; a vec_id that is repeated asks once;
equal scores go to the smaller vec_id; fewer candidates than k are all returned; an empty table gives an empty result.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from proxembed.llm.common import store, table

FIT_ROWS = 20_000
CENTROIDS, ROWS_PER_CENTROID = 12, 16
PROBES, RECALL = 256, 0.95
SHARD_ROWS, BLOCK_QUERIES = 16_384, 4_096
#: Walks end at a score; sums of the same numbers in another order may differ by this much.
SLACK = 1e-9


def kmeans(x: np.ndarray, k: int, rounds: int = 12) -> np.ndarray:
    """Lloyd's rounds from evenly spaced rows; empty centroids keep their place."""
    k = min(k, len(x))
    c = x[np.linspace(0, len(x) - 1, k).astype(int)].astype(np.float64)
    for _ in range(rounds):
        at = nearest_centroid(x, c)
        n = np.bincount(at, minlength=k)
        sums = np.stack([np.bincount(at, weights=x[:, d], minlength=k) for d in range(x.shape[1])], axis=1)
        c = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], c)
    return c


def nearest_centroid(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.argmin((c * c).sum(1)[None, :] - 2 * (x @ c.T), axis=1) if len(x) else np.zeros(0, dtype=np.int64)


class MultiIndex:
    """Centroids of both halves, how many rows each cell (i * len(second) + j) holds, and where cells lie in shards."""

    def __init__(self, first: np.ndarray, second: np.ndarray, held: np.ndarray):
        self.first, self.second, self.held = first, second, held
        self.half, self._held = first.shape[1], held.tolist()
        begin = np.concatenate(([0], np.cumsum(held)))
        self.begin = begin[:-1]
        self.low, self.high = begin[:-1] // SHARD_ROWS, np.maximum(begin[1:] - 1, begin[:-1]) // SHARD_ROWS

    def cells(self, v: np.ndarray) -> np.ndarray:
        return nearest_centroid(v[:, : self.half], self.first) * len(self.second) + nearest_centroid(v[:, self.half :], self.second)

    def walk(self, q: np.ndarray, want: int) -> tuple[list[int], float]:
        """Non-empty cells by falling summed inner product until they hold `want` rows, and the score of the last one.

        The heap holds the best cell not yet walked of each row of the sorted grid that was entered; a row's next cells are
        walked at once while they beat the rest of the heap.
        """
        a, b = self.first @ q[: self.half], self.second @ q[self.half :]
        oa, ob = np.argsort(-a, kind="stable"), np.argsort(-b, kind="stable")
        sa, sb, rows, columns = (-a[oa]).tolist(), (-b[ob]).tolist(), (oa * len(b)).tolist(), ob.tolist()
        held, n, k, got, out = self._held, len(sa), len(sb), 0, []
        heap, push, pop = [(sa[0] + sb[0], 0, 0)], heapq.heappush, heapq.heappop
        while heap:
            score, i, j = pop(heap)
            if j == 0 and i + 1 < n:
                push(heap, (sa[i + 1] + sb[0], i + 1, 0))
            base, row, top = rows[i], sa[i], heap[0][0] if heap else math.inf
            while True:
                cell = base + columns[j]
                if held[cell]:
                    got += held[cell]
                    out.append(cell)
                    if got >= want:
                        return out, -score
                j += 1
                if j == k:
                    break
                score = row + sb[j]
                if score > top:
                    push(heap, (score, i, j))
                    break
        return out, -math.inf

    def scores(self, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Inner products of each query's halves with the centroids."""
        return q[:, : self.half] @ self.first.T, q[:, self.half :] @ self.second.T


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, v) rows that take part, as doubles."""
    v = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))
    good = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists("v", lambda x: x != 0)
    v = v.where(F.col("vec_id").isNotNull() & F.col("v").isNotNull()).where(good)
    size = v.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
    return v.where(F.size("v") == (size["d"] if size else 0))


def _matrix(column: pa.Array) -> np.ndarray:
    """Lists of equal length as rows of doubles."""
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(n, -1) if n else np.zeros((0, 0))


def _lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1], pa.array(x.reshape(-1)))


def exact_top(rows: DataFrame, ids: np.ndarray, q: np.ndarray, k: int) -> pd.DataFrame:
    """(probe, vec_id, score, cell): the k best rows of `rows` (vec_id, v, cell) for each of a bounded number of probes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            own, cell = batch.column(0).to_numpy(), batch.column(2).to_numpy()
            s = q @ _matrix(batch.column(1)).T
            s[ids[:, None] == own[None, :]] = -np.inf
            at = np.argpartition(-s, min(k, s.shape[1]) - 1, axis=1)[:, :k]
            probe = np.repeat(np.arange(len(q)), at.shape[1])
            at = at.reshape(-1)
            yield pa.RecordBatch.from_arrays([pa.array(probe), pa.array(own[at]), pa.array(s[probe, at]), pa.array(cell[at])], names=["probe", "vec_id", "score", "cell"])

    found = rows.select("vec_id", "v", "cell").mapInArrow(run, "probe long, vec_id long, score double, cell long").where(F.col("score") > float("-inf"))
    order = Window.partitionBy("probe").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("probe", "vec_id", "score", "cell").toPandas()  # probes * k rows


def rows_to_walk(index: MultiIndex, q: np.ndarray, truth: pd.DataFrame, recall: float) -> int:
    """How many rows the walked cells must hold so that `recall` of the probes' true neighbours lies in them."""
    total, needs = int(index.held.sum()), []
    for probe, rows in truth.groupby("probe"):
        left, got = rows["cell"].value_counts().to_dict(), 0
        for cell in index.walk(q[probe], total)[0]:
            got += int(index.held[cell])
            hit = left.pop(cell, 0)
            needs += [got] * hit
            if not left:
                break
    return int(np.quantile(needs, recall, method="higher")) if needs else total


def build(rows: DataFrame, fit_rows: int = FIT_ROWS) -> tuple[DataFrame, MultiIndex] | None:
    """Stored (vec_id, v, cell) of every usable row, and the index; None without rows."""
    sample = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(fit_rows).select("v").toArrow()  # fit_rows vectors
    if not sample.num_rows:
        return None
    x = _matrix(sample.column(0).combine_chunks())
    total = rows.count()
    half = max(1, x.shape[1] // 2)
    centroids = max(1, min(int(CENTROIDS * total**0.25), -(-len(x) // ROWS_PER_CENTROID)))
    first = kmeans(x[:, :half], centroids)
    second = kmeans(x[:, half:], centroids) if x.shape[1] > half else np.zeros((1, 0))
    blank = MultiIndex(first, second, np.zeros(len(first) * len(second), dtype=np.int64))

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(blank.cells(_matrix(b.column(1))))], names=["vec_id", "v", "cell"])

    stored = store(rows.mapInArrow(assign, "vec_id long, v array<double>, cell long"), "multi-index")
    held = np.zeros(len(first) * len(second), dtype=np.int64)
    counts = stored.groupBy("cell").count().toPandas()  # a row for each cell, centroids ** 2 at most
    held[counts["cell"].to_numpy()] = counts["count"].to_numpy()
    return stored, MultiIndex(first, second, held)


def search(vectors: DataFrame, queries: DataFrame, k: int = 20, recall: float = RECALL, probes: int = PROBES, fit_rows: int = FIT_ROWS) -> DataFrame:
    """(query_id, rank, vec_id, score): k best of the walked cells for each row of `queries` (vec_id, embedding)."""
    spark = vectors.sparkSession
    built = build(usable(vectors), fit_rows)
    if built is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    rows, index = built
    width = index.half + index.second.shape[1]
    asked = usable(queries).where(F.size("v") == width).dropDuplicates(["vec_id"])
    some = asked.orderBy(F.xxhash64("vec_id"), "vec_id").limit(probes).toArrow()  # `probes` vectors
    if not some.num_rows:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    probe = _matrix(some.column(1).combine_chunks())
    want = rows_to_walk(index, probe, exact_top(rows, some.column(0).to_numpy(), probe, k), recall)
    total = int(index.held.sum())
    blocks = max(1, asked.count() // BLOCK_QUERIES)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cell = b.column(2).to_numpy()
            deal = b.column(3).to_numpy() % (index.high - index.low + 1)[cell]
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in range(3)), pa.array(index.low[cell] + deal)], names=["vec_id", "v", "cell", "shard"])

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, q, shards, ends, block = [], [], [], [], []
            for i, v, salt in zip(b.column(0).to_pylist(), _matrix(b.column(1)), b.column(2).to_pylist(), strict=True):
                walked, end = index.walk(v, want)
                own = int(index.begin[walked[0]] + salt % index.held[walked[0]]) * blocks // total
                cells = np.array(walked)
                low, high = index.low[cells], index.high[cells]
                met = np.unique(low)
                for c in np.flatnonzero(high > low).tolist():  # cells dealt over several shards
                    met = np.union1d(met, np.arange(low[c], high[c] + 1))
                ids += [i] * len(met)
                q += [v] * len(met)
                shards += met.tolist()
                ends += [end - SLACK] * len(met)
                block += [own] * len(met)
            if ids:
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), _lists(np.stack(q)), pa.array(shards, pa.int64()), pa.array(block, pa.int64()), pa.array(ends, pa.float64())], names=["query_id", "q", "shard", "block", "until"])

    salt = F.pmod(F.xxhash64("vec_id"), F.lit(1 << 40))
    dealt = asked.withColumn("salt", salt).repartition(max(spark.sparkContext.defaultParallelism, blocks), "vec_id")
    routed = store(dealt.select("vec_id", "v", "salt").mapInArrow(route, "query_id long, q array<double>, shard long, block long, until double"), "routes")
    placed = rows.withColumn("salt", salt).mapInArrow(place, "vec_id long, v array<double>, cell long, shard long")
    pairs = routed.select(F.col("shard").alias("at_shard"), F.col("block").alias("at_block")).distinct()
    met = placed.join(pairs, F.col("shard") == F.col("at_shard")).select("vec_id", "v", "cell", "at_shard", "at_block")

    def best(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        found: list[pd.DataFrame] = []
        if len(left) and len(right):
            v, ids, cell = np.stack(right["v"].to_numpy()), right["vec_id"].to_numpy(), right["cell"].to_numpy()
            i, j = cell // len(index.second), cell % len(index.second)
            q, until = np.stack(left["q"].to_numpy()), left["until"].to_numpy()
            for x in range(0, len(q), 128):
                part = q[x : x + 128]
                scores = part @ v.T
                a, b = index.scores(part)
                scores[a[:, i] + b[:, j] < until[x : x + 128, None]] = -np.inf
                for n, query in enumerate(left["query_id"].iloc[x : x + 128]):
                    s = scores[n]
                    s[ids == query] = -np.inf
                    pick = np.flatnonzero(s >= max(np.partition(s, len(s) - k)[len(s) - k] - SLACK, -1e300) if len(s) > k else s > -np.inf)
                    exact = (v[pick] * part[n]).sum(axis=1)
                    order = np.lexsort((ids[pick], -exact))[:k]
                    found.append(pd.DataFrame({"query_id": query, "vec_id": ids[pick][order], "score": exact[order]}))
        return pd.concat(found) if found else pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype({"query_id": "int64", "vec_id": "int64", "score": "float64"})

    lists = routed.groupBy("shard", "block").cogroup(met.groupBy("at_shard", "at_block")).applyInPandas(best, "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return lists.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op10_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return search(vectors, vectors.where("vec_id % 20 = 0"))

"""Queries of the operator surface beside the methods: lateral joins, maps, JSON, ranking, recursion, Arrow functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType

from proxembed.operators import sampling
from proxembed.plans.exact import P, _roots, base, graph, longs, query, roots_cte
from proxembed.sources import builders


@query(f"{base('part_supplier')} SELECT v.vid, n.dst, n.w FROM vertices v, LATERAL (SELECT dst, w FROM edges e WHERE e.src = v.vid ORDER BY w DESC, dst LIMIT 2) n")
def lateral_neighbors(spark: SparkSession, d: str) -> DataFrame:
    """The two heaviest neighbours of each vertex by a lateral join."""
    g = graph(spark, d, "part_supplier")
    near = g.edges.where(F.col("src") == F.col("vid").outer()).orderBy(F.desc("w"), "dst").limit(2).select("dst", "w")
    return g.vertices.select("vid").lateralJoin(near).select("vid", "dst", "w")


@query(f"{base('customer_part')}, per AS (SELECT src AS vid, dst_part AS part, count(*) AS n FROM edges GROUP BY 1, 2) SELECT vid, count(*) AS parts, sum(n)::BIGINT AS links, max(n) AS most, string_agg(part || ':' || 2 * n, ',' ORDER BY part) AS doubled FROM per GROUP BY vid")
def part_counters(spark: SparkSession, d: str) -> DataFrame:
    """A map (part -> neighbours there) for each vertex, and what map functions make of it."""
    per = graph(spark, d, "customer_part").edges.groupBy(F.col("src").alias("vid"), F.col("dst_part").cast("long").alias("part")).agg(F.count("*").alias("n"))
    held = per.groupBy("vid").agg(F.map_from_entries(F.collect_list(F.struct("part", "n"))).alias("m"))
    twice = F.transform_values("m", lambda _, n: 2 * n)
    shown = F.transform(F.array_sort(F.map_entries(F.map_concat(twice, F.create_map().cast("map<bigint,bigint>")))), lambda e: F.concat_ws(":", e["key"].cast("string"), e["value"].cast("string")))
    return held.select("vid", F.size("m").cast("long").alias("parts"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda s, n: s + n).alias("links"), F.array_max(F.map_values("m")).alias("most"), F.array_join(shown, ",").alias("doubled"))


def _lengths(x: pa.Array) -> pa.Array:
    """Lengths of the vectors of an Arrow list column; null for null."""
    if isinstance(x, pa.ChunkedArray):
        x = x.combine_chunks()
    flat, at = pc.cast(pc.list_flatten(x), pa.float64()), pc.list_parent_indices(x).to_numpy()
    sums = np.bincount(at, weights=pc.multiply(flat, flat).to_numpy(zero_copy_only=False), minlength=len(x))
    return pc.if_else(x.is_valid(), pa.array(np.sqrt(sums)), pa.scalar(None, pa.float64()))


@F.arrow_udf(DoubleType())
def _norm(x: pa.Array) -> pa.Array:
    return _lengths(x)


@query("SELECT vec_id, round(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS norm FROM embeddings")
def vector_norms(spark: SparkSession, d: str) -> DataFrame:
    """A scalar function over Arrow columns."""
    return builders.table(spark, d, "embeddings").select("vec_id", F.round(_norm("embedding"), 6).alias("norm"))


@F.arrow_udf(IntegerType())
def _place(items: pa.Array, r: pa.Array) -> pa.Array:
    """How many upper bounds of a slice are not above the draw: the place of the neighbour it picks."""
    return pa.array([sum(h <= x for h in bounds) for bounds, x in zip(items.to_pylist(), r.to_pylist(), strict=True)], pa.int32())


@query(f"{base('part_supplier')}, near AS (SELECT src, dst, sum(w) OVER (PARTITION BY src ORDER BY dst)::BIGINT AS hi, sum(w) OVER (PARTITION BY src)::BIGINT AS total, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS place FROM edges) SELECT src AS vid, min(place) FILTER (hi > total // 2) AS place FROM near GROUP BY src")
def pick_in_chunk(spark: SparkSession, d: str) -> DataFrame:
    """The neighbour in the middle of each vertex's weight, by an Arrow function over its slice's bounds."""
    index = sampling.neighbor_index(graph(spark, d, "part_supplier"), 1 << 20)
    bounds = F.transform("items", lambda i: i["hi"])
    middle = F.expr("element_at(items, -1).hi div 2")
    return longs(index.select(F.col("src").alias("vid"), _place(bounds, middle).alias("place")))


@F.arrow_udf(DoubleType())
def _mean_norm(x: pa.Array) -> float:
    return pc.mean(_lengths(x)).as_py()


@query("SELECT label::BIGINT AS label, round(avg(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]))), 6) AS mean_norm FROM embeddings GROUP BY label")
def mean_norms(spark: SparkSession, d: str) -> DataFrame:
    """A grouped aggregate over Arrow columns."""
    return longs(builders.table(spark, d, "embeddings").groupBy("label").agg(F.round(_mean_norm("embedding"), 6).alias("mean_norm")))


@query(f"{base('customer_part')}, far AS (SELECT dst AS v FROM edges WHERE src_part <> dst_part) SELECT count(DISTINCT v) AS exact, true AS near, true AS sketched FROM far")
def distinct_contexts(spark: SparkSession, d: str) -> DataFrame:
    """Contexts that cross parts, counted exactly, approximately and by a sketch; both within a tenth."""
    far = graph(spark, d, "customer_part").edges.where("src_part <> dst_part")
    row = far.agg(F.countDistinct("dst").alias("exact"), F.approx_count_distinct("dst", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("dst")).alias("s"))
    within = lambda c: F.abs(F.col(c) - F.col("exact")) <= F.col("exact") / 10
    return row.select("exact", within("a").alias("near"), within("s").alias("sketched"))


@query(f"{base('customer_part')}, flow AS (SELECT src_part AS part, dst_part AS other, count(*) AS n FROM edges GROUP BY 1, 2) SELECT p.range AS part, o.range AS other, coalesce(n, 0) AS n FROM range({P}) p CROSS JOIN range({P}) o LEFT JOIN flow ON part = p.range AND other = o.range")
def part_flow(spark: SparkSession, d: str) -> DataFrame:
    """Edges between parts as a wide table, and back to rows with its zeros."""
    e = graph(spark, d, "customer_part").edges
    wide = e.groupBy(F.col("src_part").cast("long").alias("part")).pivot("dst_part", list(range(P))).count().na.fill(0)
    rows = wide.unpivot(["part"], [F.col(f"`{k}`") for k in range(P)], "other", "n")
    return rows.select("part", F.col("other").cast("long").alias("other"), "n")


_RANKS = "rank() OVER w AS place, dense_rank() OVER w AS level, ntile(4) OVER (PARTITION BY part ORDER BY deg DESC, vid) AS quarter, round(percent_rank() OVER w, 6) AS share, round(cume_dist() OVER w, 6) AS upto"


@query(f"{base('part_supplier')} SELECT part, vid, {_RANKS} FROM vertices WINDOW w AS (PARTITION BY part ORDER BY deg DESC)")
def degree_ranks(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("part").orderBy(F.desc("deg"))
    v = graph(spark, d, "part_supplier").vertices
    return longs(v.select("part", "vid", F.rank().over(w).alias("place"), F.dense_rank().over(w).alias("level"), F.ntile(4).over(Window.partitionBy("part").orderBy(F.desc("deg"), "vid")).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("share"), F.round(F.cume_dist().over(w), 6).alias("upto")))


@query(f"{base('customer_part')} SELECT part, min(vid) FILTER (deg = lo) AS thinnest, min(vid) FILTER (deg = hi) AS thickest, round(stddev_pop(deg), 6) AS sigma, round(corr(deg, wdeg), 6) AS tie FROM (SELECT *, min(deg) OVER (PARTITION BY part) AS lo, max(deg) OVER (PARTITION BY part) AS hi FROM vertices) GROUP BY part")
def degree_extremes(spark: SparkSession, d: str) -> DataFrame:
    """The vertices of least and most degree of each part (the smallest id of equals), deviation and correlation."""
    v = graph(spark, d, "customer_part").vertices
    return longs(v.groupBy("part").agg(F.min_by("vid", F.struct("deg", "vid")).alias("thinnest"), F.max_by("vid", F.struct("deg", -F.col("vid"))).alias("thickest"), F.round(F.stddev_pop("deg"), 6).alias("sigma"), F.round(F.corr("deg", "wdeg"), 6).alias("tie")))


@query(f"{base('geography', recursive=True)}, reach AS (SELECT 0::BIGINT AS step, min(vid) AS vid FROM vertices UNION SELECT r.step + 1, e.dst FROM reach r JOIN edges e ON e.src = r.vid WHERE r.step < 3) SELECT step, vid FROM reach")
def reach_by_recursion(spark: SparkSession, d: str) -> DataFrame:
    """(step, vid) of what the first vertex reaches in three steps, by a recursive common table expression."""
    g = graph(spark, d, "geography")
    return spark.sql(
        "WITH RECURSIVE reach(step, vid) AS (SELECT 0L, min(vid) FROM {v} UNION ALL SELECT DISTINCT r.step + 1, e.dst FROM reach r JOIN {e} e ON e.src = r.vid WHERE r.step < 3) SELECT DISTINCT step, vid FROM reach",
        v=g.vertices, e=g.edges)


@query("SELECT event_id, (props::JSON ->> '$.k') AS k, '{\"k\":' || coalesce('\"' || (props::JSON ->> '$.k') || '\"', 'null') || ',\"type\":\"' || event_type || '\"}' AS again FROM events WHERE props::JSON ->> '$.k' IS NOT NULL")
def event_json(spark: SparkSession, d: str) -> DataFrame:
    """The key of each event's JSON by a declared schema, and a new document made of it."""
    ev = builders.table(spark, d, "events").select("event_id", "event_type", F.from_json(F.col("props").cast("string"), "k string").alias("p")).where("p.k is not null")
    return ev.select("event_id", F.col("p.k").alias("k"), F.to_json(F.struct(F.col("p.k").alias("k"), F.col("event_type").alias("type"))).alias("again"))


@query(f"{base('customer_part')}, {roots_cte(3, 40)} SELECT u, count(*) AS n FROM roots GROUP BY u QUALIFY row_number() OVER (ORDER BY count(*) DESC, u) <= 5")
def top_roots(spark: SparkSession, d: str) -> DataFrame:
    """The five vertices that most walks start from."""
    return longs(_roots(spark, d, 3, 40).groupBy("u").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "u").limit(5))

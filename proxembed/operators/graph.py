"""The graph: vertices and both directions of weighted edges, made from rows of keys."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxembed.operators.storage import store


@dataclass(frozen=True)
class Graph:
    """vertices(vid, key, deg, wdeg, part), edges(src, dst, w, src_part, dst_part) in both directions; n vertices, `parts` owners."""

    vertices: DataFrame
    edges: DataFrame
    n: int
    parts: int = 1


def undirect(raw: DataFrame, drop_loops: bool = True) -> DataFrame:
    """(a, b, w) in any order -> one row a < b with summed weight; loops go, weights of zero or less are an error."""
    checked = raw.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), F.when(F.col("w") > 0, F.col("w")).otherwise(F.raise_error(F.lit("edge weights must be positive"))).cast("long").alias("w"))
    merged = checked.groupBy("a", "b").agg(F.sum("w").alias("w"))
    return merged.where("a <> b") if drop_loops else merged


def mirror(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Both directions from one scan."""
    both = F.array(F.struct(F.col(a).alias("src"), F.col(b).alias("dst"), "w"), F.struct(F.col(b).alias("src"), F.col(a).alias("dst"), "w"))
    return edges.select(F.explode(both).alias("e")).select("e.*")


def assign_ids(keys: DataFrame, order: list[str]) -> DataFrame:
    """Dense ids from 0 in the order of columns that are unique together.

    Rows are sorted over range partitions and stored; only a count for each partition comes to the driver, as offsets.
    """
    placed = keys.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_m", F.monotonically_increasing_id())
    kept = store(placed, "ids")
    counts = sorted((r["p"], r["n"]) for r in kept.groupBy(F.shiftright("_m", 33).alias("p")).agg(F.count("*").alias("n")).collect())
    offset, total = {}, 0
    for p, n in counts:
        offset[p] = total
        total += n
    lookup = F.element_at(F.create_map(*[F.lit(x) for p in offset for x in (p, offset[p])]), F.shiftright("_m", 33)) if offset else F.lit(0)
    return kept.withColumn("vid", (F.col("_m").bitwiseAND(F.lit((1 << 33) - 1)) + lookup).cast("long")).drop("_m")


def build(raw: DataFrame) -> Graph:
    """A Graph of one part from (a, b, w) rows of string keys."""
    merged = store(undirect(raw), "edges")
    keys = merged.select(F.explode(F.array("a", "b")).alias("key")).distinct()
    ids = store(assign_ids(keys, ["key"]), "vertices")
    named = merged.join(ids.select(F.col("key").alias("a"), F.col("vid").alias("u")), "a").join(ids.select(F.col("key").alias("b"), F.col("vid").alias("v")), "b")
    edges = mirror(named.select("u", "v", "w"), "u", "v").withColumns({"src_part": F.lit(0), "dst_part": F.lit(0)})
    edges = store(edges, "directed")
    vertices = store(degrees(ids, edges).withColumn("part", F.lit(0)), "vertices")
    return Graph(vertices, edges, vertices.count())


def degrees(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """vertices with deg and wdeg; vertices without edges have 0."""
    per = edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg"), F.sum("w").alias("wdeg"))
    return vertices.join(per, "vid", "left").withColumns({"deg": F.coalesce("deg", F.lit(0)).cast("long"), "wdeg": F.coalesce("wdeg", F.lit(0)).cast("long")})


def describe(g: Graph) -> DataFrame:
    """One row: vertices, undirected edges, mean, quartile and largest degree, isolated vertices."""
    d = g.vertices.agg(F.count("*").alias("n"), (F.sum("deg") / 2).cast("long").alias("m"), F.avg("deg").alias("deg_mean"), F.percentile_approx("deg", [0.25, 0.5, 0.75]).alias("deg_quartiles"), F.max("deg").alias("deg_max"), F.sum((F.col("deg") == 0).cast("long")).alias("isolated"))
    return d


def components(g: Graph) -> DataFrame:
    """(vid, label) with label the smallest vertex reachable: minimum labels over edges, then the label's own label."""
    labels = store(g.vertices.select("vid", F.col("vid").alias("label")), "labels")
    while True:
        heard = g.edges.join(labels.withColumnRenamed("vid", "dst"), "dst").groupBy(F.col("src").alias("vid")).agg(F.min("label").alias("heard"))
        near = labels.join(heard, "vid", "left").select("vid", F.col("label").alias("old"), F.least("label", F.coalesce("heard", "label")).alias("label"))
        roots = labels.select(F.col("vid").alias("label"), F.col("label").alias("root"))
        moved = store(near.join(roots, "label").select("vid", F.least("label", "root").alias("label"), "old"), "labels")
        labels = moved.select("vid", "label")
        if moved.where("label <> old").isEmpty():
            return labels


def replicate(g: Graph, k: int) -> Graph:
    """k copies by id offset; every hundredth vertex is tied to its next copy, so load grows and the graph stays connected."""
    copy = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(k - 1).cast("long"))).alias("_k")
    shift = lambda c: (F.col(c) + F.col("_k") * g.n).alias(c)
    edges = g.edges.select("*", copy).select(shift("src"), shift("dst"), "w", "src_part", "dst_part")
    ties = g.vertices.where("vid % 100 = 0").select("vid", "part", copy).where(F.col("_k") < k - 1)
    ties = mirror(ties.select((F.col("vid") + F.col("_k") * g.n).alias("a"), (F.col("vid") + (F.col("_k") + 1) * g.n).alias("b"), F.lit(1).cast("long").alias("w"))).withColumns({"src_part": F.lit(0), "dst_part": F.lit(0)})
    edges = edges.unionByName(ties)
    vertices = g.vertices.select("*", copy).select(shift("vid"), F.concat_ws("#", "key", "_k").alias("key"), "part")
    return Graph(degrees(vertices, edges), edges, g.n * k, g.parts)

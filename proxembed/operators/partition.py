"""One-dimensional cuts of vertices to owners, and what follows from them: ghosts, neighbouring parts, load deviation."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxembed.operators.graph import Graph
from proxembed.operators.storage import store


def _with_owner(g: Graph, owner, parts: int) -> Graph:
    """Owner is an expression of the id alone, so edges need no join."""
    vertices = g.vertices.withColumn("part", owner(F.col("vid")).cast("int"))
    edges = g.edges.withColumns({"src_part": owner(F.col("src")).cast("int"), "dst_part": owner(F.col("dst")).cast("int")})
    return Graph(vertices, edges, g.n, parts)


def vertex_owner(n: int, parts: int):
    """About n / parts consecutive ids each."""
    return lambda vid: F.floor(vid * F.lit(parts) / F.lit(n)) if n else F.lit(0)


def hash_owner(parts: int):
    return lambda vid: F.pmod(F.xxhash64(vid), F.lit(parts))


def range_owner(cuts: list[int]):
    """cuts: the first id of each part, rising; p numbers travel in the plan."""
    cuts_column = F.array(*[F.lit(c).cast("long") for c in cuts])
    return lambda vid: F.size(F.filter(cuts_column, lambda c: c <= vid)) - 1


def cut_by_vertex(g: Graph, parts: int) -> Graph:
    return _with_owner(g, vertex_owner(g.n, parts), parts)


def cut_by_hash(g: Graph, parts: int) -> Graph:
    return _with_owner(g, hash_owner(parts), parts)


def running_degree(g: Graph, block: int = 65_536) -> DataFrame:
    """(vid, deg, before): stored edges of all smaller ids, by a prefix sum inside id blocks and one over block totals."""
    v = g.vertices.select("vid", "deg", (F.col("vid") / block).cast("long").alias("_b"))
    totals = v.groupBy("_b").agg(F.sum("deg").alias("_t"))
    offsets = totals.withColumn("_o", F.sum("_t").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_t"))
    inner = F.sum("deg").over(Window.partitionBy("_b").orderBy("vid").rowsBetween(Window.unboundedPreceding, 0)) - F.col("deg")
    return v.withColumn("_i", inner).join(offsets.select("_b", "_o"), "_b").select("vid", "deg", (F.col("_i") + F.col("_o")).alias("before"))


def first_fit(g: Graph, parts: int) -> DataFrame:
    """(vid, deg, part): one pass that fills parts with consecutive ids up to the mean load."""
    total = g.vertices.agg(F.sum("deg")).first()[0] or 0
    return running_degree(g).withColumn("part", F.least(F.lit(parts - 1), F.floor(F.col("before") * parts / F.lit(max(total, 1)))).cast("int"))


def cut_by_edges(g: Graph, parts: int, tolerance: float = 0.1) -> tuple[Graph, bool]:
    """Edge-balanced consecutive cut, or the cut by vertices where one pass leaves the largest part above the tolerance.

    The driver sees `parts` cut points and loads.
    """
    loads = {r["part"]: (r["first"], r["load"]) for r in first_fit(g, parts).groupBy("part").agg(F.min("vid").alias("first"), F.sum("deg").alias("load")).collect()}
    mean = sum(x for _, x in loads.values()) / parts if loads else 0
    balanced = len(loads) == parts and max(x for _, x in loads.values()) <= (1 + tolerance) * mean
    if not balanced:
        return cut_by_vertex(g, parts), False
    cuts = [loads[k][0] for k in range(parts)]
    cuts[0] = 0
    return _with_owner(g, range_owner(cuts), parts), True


def stored(g: Graph) -> Graph:
    """The graph with vertices and edges written once under their owners."""
    return Graph(store(g.vertices, "vertices"), store(g.edges, "edges"), g.n, g.parts)


def ghosts(g: Graph) -> DataFrame:
    """(part, vid): vertices that a part sees through its edges and doesn't own."""
    return g.edges.where("src_part <> dst_part").select(F.col("src_part").alias("part"), F.col("dst").alias("vid")).distinct()


def part_links(g: Graph) -> DataFrame:
    """(part, other, edges) of parts that share edges."""
    return g.edges.where("src_part <> dst_part").groupBy(F.col("src_part").alias("part"), F.col("dst_part").alias("other")).agg(F.count("*").alias("edges"))


def edge_spread(g: Graph, parts: list[int], owner=vertex_owner) -> DataFrame:
    """(p, sigma, least, most, mean) of stored edges of a part, a row for each p; parts without edges count."""
    per_p = None
    for p in parts:
        own = owner(g.n, p)
        loads = g.vertices.groupBy(own(F.col("vid")).cast("int").alias("part")).agg(F.sum("deg").alias("load"))
        row = loads.agg(F.sum("load").alias("s"), F.sum(F.col("load").cast("double") ** 2).alias("q"), F.min("load").alias("lo"), F.max("load").alias("most"), F.count("*").alias("seen"))
        mean = F.col("s") / p
        row = row.select(F.lit(p).alias("p"), F.round(F.sqrt(F.greatest(F.col("q") / p - mean * mean, F.lit(0.0))), 6).alias("sigma"), F.when(F.col("seen") < p, F.lit(0)).otherwise(F.col("lo")).cast("long").alias("least"), "most", F.round(mean, 6).alias("mean"))
        per_p = row if per_p is None else per_p.unionByName(row)
    return per_p


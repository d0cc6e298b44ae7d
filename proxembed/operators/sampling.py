"""Draws from discrete distributions: noise over vertices, root edges, chunked neighbour lists."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from proxembed.functions.rng import ALIAS, NEGATIVE, ROOT, SPAN, draw
from proxembed.operators.graph import Graph
from proxembed.operators.partition import part_links
from proxembed.operators.storage import forget, store

ROWS_PER_BUCKET = 16
IDS_PER_BLOCK = 65_536
#: Vertices that are broadcast to the edges; for more of them the edges are exchanged.
FEW = 100_000


def prefix(rows: DataFrame, group: list[str], order: list[str], value: str) -> DataFrame:
    """Adds [lo, hi) of a running integer sum inside each group."""
    w = Window.partitionBy(*group).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("hi", F.sum(value).over(w)).withColumn("lo", F.col("hi") - F.col(value))


def block_prefix(rows: DataFrame, group: list[str], block: Column, order: list[str], value: str) -> DataFrame:
    """prefix() in two levels: inside blocks of a group, and over the blocks' totals, so a group of any size is many tasks.

    `block` must not fall in the order of `order`.
    """
    cut = rows.withColumn("_b", block)
    totals = cut.groupBy(*group, "_b").agg(F.sum(value).alias("_t"))
    before = F.sum("_t").over(Window.partitionBy(*group).orderBy("_b").rowsBetween(Window.unboundedPreceding, 0))
    offsets = totals.select(*group, "_b", (before - F.col("_t")).alias("_o"))
    inner = prefix(cut, [*group, "_b"], order, value).join(offsets, [*group, "_b"])
    return inner.withColumns({"lo": F.col("lo") + F.col("_o"), "hi": F.col("hi") + F.col("_o")}).drop("_b", "_o")


def neighbor_prefix(g: Graph, unit_weights: bool = False, chunk: int = 4096) -> DataFrame:
    """Edges with [lo, hi) of their weight in the list of their first end, in blocks of about `chunk` neighbours of a hub."""
    edges = g.edges.withColumn("w", F.lit(1).cast("long")) if unit_weights else g.edges
    sized = edges.join(g.vertices.select(F.col("vid").alias("src"), F.col("deg").alias("_deg")), "src")
    block = F.expr(f"dst div greatest(1L, {max(g.n, 1)}L * {chunk} div greatest(1L, _deg))")
    return block_prefix(sized, ["src"], block, ["dst"], "w").drop("_deg")


def near(g: Graph, ids: DataFrame, unit_weights: bool = False) -> DataFrame:
    """neighbor_prefix() of the vertices `ids` (src) alone, stored: one scan of the edges, whatever the graph's size."""
    few = F.broadcast(ids) if ids.limit(FEW + 1).count() <= FEW else ids
    lists = store(g.edges.join(few, "src", "left_semi"), "lists")
    owners = g.vertices.join(few.withColumnRenamed("src", "vid"), "vid", "left_semi")
    ranges = store(neighbor_prefix(Graph(owners, lists, g.n, g.parts), unit_weights), "near")
    forget(lists)
    return ranges


def pick(draws: DataFrame, ranges: DataFrame, on: list[str]) -> DataFrame:
    """Join each draw's r to the range lo <= r < hi of its group.

    A bare range condition would be planned as a nested loop. Both sides get the number of an equal slice of the group's
    total as an equi key, about ROWS_PER_BUCKET ranges to a slice; a wide range enters every slice that it crosses.
    """
    key = on or ["_one"]
    if not on:
        draws, ranges = draws.withColumn("_one", F.lit(1)), ranges.withColumn("_one", F.lit(1))
    size = ranges.groupBy(*key).agg(F.greatest(F.lit(1), F.expr(f"max(hi) * {ROWS_PER_BUCKET} div count(*)")).alias("_w"))
    cut = ranges.join(size, key).withColumn("_s", F.explode(F.sequence(F.expr("lo div _w"), F.expr("(hi - 1) div _w"))))
    aimed = draws.join(size, key).withColumn("_s", F.expr("r div _w")).drop("_w")
    found = aimed.join(cut.drop("_w"), [*key, "_s"]).where("r >= lo and r < hi").drop("_s")
    return found if on else found.drop("_one")


def noise(g: Graph, alpha: float = 0.75, by: str = "deg") -> DataFrame:
    """(vid, part, qw, lo, hi): weights round(d ** alpha * 1e6) as integers with prefix sums by (part, vid); isolated vertices are never drawn."""
    weights = g.vertices.where(f"{by} > 0").select("vid", "part", F.round(F.pow(by, F.lit(alpha)) * 1e6).cast("long").alias("qw"))
    return block_prefix(weights, ["part"], F.expr(f"vid div {IDS_PER_BLOCK}"), ["vid"], "qw")


def noise_parts(noise_rows: DataFrame) -> DataFrame:
    """(part, lo, hi) of the parts' totals: p rows, so one window over them is small."""
    return prefix(noise_rows.groupBy("part").agg(F.sum("qw").alias("qw")).withColumn("_one", F.lit(1)), ["_one"], ["part"], "qw").drop("_one")


def noise_probability(g: Graph, alpha: float = 0.75) -> DataFrame:
    n = noise(g, alpha)
    total = n.agg(F.sum("qw").alias("total"))
    return n.crossJoin(F.broadcast(total)).select("vid", F.round(F.col("qw") / F.col("total"), 6).alias("q"))  # one row


def negatives(pairs: DataFrame, g: Graph, k: int = 1, alpha: float = 0.75, scope: str = "global", reject_edges: bool = False, seed: int = 7, backend: str = "xx") -> DataFrame:
    """k rows (batch, part, seq, j, u, v, v_part) for each positive (batch, part, seq, u).

    A draw first finds its part among part totals, then its vertex inside the part: the same vertex as one prefix over all
    would give. Scopes: global, adjacent (own and neighbouring parts), local (own part).
    """
    if k < 0 or scope not in ("global", "adjacent", "local"):
        raise ValueError("k must be 0 or more and scope one of global, adjacent, local")
    n = noise(g, alpha)
    totals = n.groupBy("part").agg(F.sum("qw").alias("qw"))
    asked = pairs.select("batch", "part", "seq", "u", F.explode(F.sequence(F.lit(1), F.lit(k))).alias("j")) if k else pairs.select("batch", "part", "seq", "u", F.lit(1).alias("j")).limit(0)
    asked = asked.withColumn("d", draw(seed, NEGATIVE, "batch", "part", "seq", "j", backend=backend))
    if scope == "global":
        parts = noise_parts(n).select("lo", "hi", F.col("part").alias("target"))
        total = totals.agg(F.sum("qw").alias("total"))
        aimed = pick(asked.crossJoin(F.broadcast(total)).withColumn("r", F.expr("d % total")).drop("total"), parts, [])  # one row
    else:
        reach = totals.select("part", F.col("part").alias("target"))
        if scope == "adjacent":
            reach = reach.unionByName(part_links(g).select("part", F.col("other").alias("target")))
        sized = reach.join(totals.select(F.col("part").alias("target"), "qw"), "target")
        ranges = prefix(sized, ["part"], ["target"], "qw").select("part", "target", "lo", "hi")
        own = ranges.groupBy("part").agg(F.max("hi").alias("total"))
        aimed = pick(asked.join(own, "part").withColumn("r", F.expr("d % total")).drop("total"), ranges, ["part"])
    inner = aimed.select("batch", "part", "seq", "j", "u", "target", (F.col("r") - F.col("lo")).alias("r"))
    found = pick(inner, n.select(F.col("part").alias("target"), F.col("vid").alias("v"), "lo", "hi"), ["target"])
    out = found.select("batch", "part", "seq", "j", "u", "v", F.col("target").alias("v_part"))
    if reject_edges:
        out = out.where("u <> v").join(g.edges.select(F.col("src").alias("u"), F.col("dst").alias("v")), ["u", "v"], "left_anti").select(out.columns)
    return out


def alias_negatives(pairs: DataFrame, g: Graph, k: int = 1, alpha: float = 0.75, seed: int = 7) -> DataFrame:
    """negatives() over all parts by alias tables: a draw picks its part, then a cell and one of the cell's two vertices.

    Each part's table is built once, in the task that holds the part's vertices, and serves every draw aimed there in constant
    time. Draws differ from those of prefix sums; the distribution is the same.
    """
    n = noise(g, alpha).select("part", "vid", "qw")
    totals = n.groupBy("part").agg(F.sum("qw").alias("qw"))
    parts = noise_parts(n).select("lo", "hi", F.col("part").alias("target"))
    asked = pairs.select("batch", "part", "seq", "u", F.explode(F.sequence(F.lit(1), F.lit(k))).alias("j"))
    asked = asked.withColumns({"d": draw(seed, NEGATIVE, "batch", "part", "seq", "j"), "cell": draw(seed, ALIAS, "batch", "part", "seq", "j", 0), "side": draw(seed, ALIAS, "batch", "part", "seq", "j", 1)})
    aimed = pick(asked.crossJoin(F.broadcast(totals.agg(F.sum("qw").alias("total")))).withColumn("r", F.expr("d % total")), parts, [])  # one row

    def run(vertices: pd.DataFrame, draws: pd.DataFrame) -> pd.DataFrame:
        vertices = vertices.sort_values("vid")
        threshold, other = alias_table(vertices["qw"].to_numpy())
        cell = draws["cell"].to_numpy() % len(threshold)
        at = np.where(draws["side"].to_numpy() / SPAN < threshold[cell], cell, other[cell])
        return draws[["batch", "part", "seq", "j", "u"]].assign(v=vertices["vid"].to_numpy()[at], v_part=draws["target"].to_numpy())

    kinds = {f.name: f.dataType.simpleString() for f in pairs.schema.fields}
    schema = ", ".join(f"{c} {kinds.get(c, 'int')}" for c in ("batch", "part", "seq", "j", "u")) + f", v long, v_part {dict(n.dtypes)['part']}"
    return n.groupBy("part").cogroup(aimed.select("batch", "part", "seq", "j", "u", "cell", "side", "target").groupBy("target")).applyInPandas(run, schema)


def root_ranges(g: Graph) -> DataFrame:
    """(part, u, v, v_part, lo, hi): edges whose first end a part owns, prefix sums of weight by (u, v).

    The sums run over a part's vertices, in blocks of ids, and inside each vertex's list, in blocks of neighbours.
    """
    lists = neighbor_prefix(g)
    heavy = g.edges.groupBy(F.col("src_part").alias("part"), F.col("src").alias("u")).agg(F.sum("w").alias("_w"))
    starts = block_prefix(heavy, ["part"], F.expr(f"u div {IDS_PER_BLOCK}"), ["u"], "_w").select("u", F.col("lo").alias("_o"))
    edges = lists.select(F.col("src_part").alias("part"), F.col("src").alias("u"), F.col("dst").alias("v"), F.col("dst_part").alias("v_part"), "lo", "hi")
    return edges.join(starts, "u").select("part", "u", "v", "v_part", (F.col("lo") + F.col("_o")).alias("lo"), (F.col("hi") + F.col("_o")).alias("hi"))


def root_starts(g: Graph) -> DataFrame:
    """(part, u, lo, hi): a part's vertices with prefix sums of their edges' weight, in blocks of ids."""
    heavy = g.vertices.where("wdeg > 0").select("part", F.col("vid").alias("u"), "wdeg")
    return block_prefix(heavy, ["part"], F.expr(f"u div {IDS_PER_BLOCK}"), ["u"], "wdeg").select("part", "u", "lo", "hi")


def roots(g: Graph, batches: int, rounds: int, seed: int = 7, backend: str = "xx", first_round: int = 0, starts: DataFrame | None = None) -> DataFrame:
    """A root edge for each (batch, round, part) in proportion to weight: (batch, round, part, walk_id, u, v, v_part).

    A draw finds its first end among the part's vertices, then its edge in that vertex's list: the same edge as one prefix over
    all the part's edges (root_ranges) would give, from the lists of the vertices met alone.
    """
    starts = root_starts(g) if starts is None else starts
    totals = starts.groupBy("part").agg(F.max("hi").alias("total"))
    spark = g.edges.sparkSession
    grid = spark.range(batches * rounds).select((F.col("id") / rounds).cast("int").alias("batch"), (F.col("id") % rounds + first_round).cast("int").alias("round"))
    asked = grid.crossJoin(totals).withColumn("r", draw(seed, ROOT, "batch", "part", "round", backend=backend) % F.col("total"))  # a root for each, by definition
    aimed = store(pick(asked.drop("total"), starts, ["part"]).select("batch", "round", "part", F.col("u").alias("src"), (F.col("r") - F.col("lo")).alias("r")), "aimed")
    lists = near(g, aimed.select("src").distinct()).select("src", F.col("dst").alias("v"), F.col("dst_part").alias("v_part"), "lo", "hi")
    walk_id = (F.col("batch").cast("long") * (1 << 20) + F.col("round")) * g.parts + F.col("part")
    return pick(aimed, lists, ["src"]).select("batch", "round", "part", walk_id.alias("walk_id"), F.col("src").alias("u"), "v", "v_part")


def neighbor_index(g: Graph, chunk: int = 4096, unit_weights: bool = False) -> DataFrame:
    """(src, part, chunk, items): neighbours in slices of equal weight, items (hi, dst, dst_part, wdeg, chunks) in order of hi.

    A hub's list is many rows: a walker at x knows x's total and number of slices from the item that led there, so it joins
    on (src, slice) and hubs spread. The prefix sums are taken in id ranges of about `chunk` neighbours and over their totals.
    """
    edges = g.edges.withColumn("w", F.lit(1).cast("long")) if unit_weights else g.edges
    size = edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg"), F.sum("w").alias("wdeg")).withColumn("chunks", F.ceil(F.col("deg") / chunk).cast("long"))
    size = store(size, "sizes")
    run = neighbor_prefix(g, unit_weights, chunk).join(size.select(F.col("vid").alias("src"), "wdeg", "chunks"), "src")
    run = run.withColumn("_cw", F.ceil(F.col("wdeg") / F.col("chunks")).cast("long"))
    far = size.select(F.col("vid").alias("dst"), F.col("wdeg").alias("dw"), F.col("chunks").alias("dc"))
    run = run.join(far, "dst").withColumn("chunk", F.explode(F.sequence(F.expr("lo div _cw"), F.expr("(hi - 1) div _cw"))))
    item = F.struct("hi", "dst", "dst_part", F.col("dw").alias("wdeg"), F.col("dc").alias("chunks"))
    return run.groupBy("src", F.col("src_part").alias("part"), "chunk").agg(F.array_sort(F.collect_list(item)).alias("items"))


def alias_table(weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(threshold, other) for constant-time draws: cell i gives i below the threshold, else `other`."""
    n = len(weights)
    scaled = np.asarray(weights, dtype=np.float64) * n / weights.sum()
    threshold, other = np.ones(n), np.arange(n)
    small, large = [i for i in range(n) if scaled[i] < 1], [i for i in range(n) if scaled[i] >= 1]
    while small and large:
        s, big = small.pop(), large[-1]
        threshold[s], other[s] = scaled[s], big
        scaled[big] -= 1 - scaled[s]
        if scaled[big] < 1:
            small.append(large.pop())
    return threshold, other

"""Graph building, cuts, noise and walks on the five-vertex graph."""

import math

import pytest
from pyspark.errors import PySparkException
from pyspark.sql import functions as F

from proxembed.operators import graph, partition, quota, sampling, walks
from proxembed.sources import readers


def test_five_vertices(five):
    v = {r["key"]: r for r in five.vertices.collect()}
    assert [v[k]["deg"] for k in "abcde"] == [1, 2, 3, 2, 2]
    assert [v[k]["part"] for k in "abcde"] == [0, 0, 0, 1, 1]
    s = partition.edge_spread(five, [2]).first()
    assert (s["sigma"], s["least"], s["most"]) == (1.0, 4, 6)
    assert {(r["part"], r["vid"]) for r in partition.ghosts(five).collect()} == {(0, 3), (0, 4), (1, 2)}


def test_noise_of_five(five):
    n = {r["vid"]: r["qw"] for r in sampling.noise(five).collect()}
    assert n == {0: 1_000_000, 1: 1_681_793, 2: 2_279_507, 3: 1_681_793, 4: 1_681_793}
    q = {r["vid"]: r["q"] for r in sampling.noise_probability(five).collect()}
    assert q == {0: 0.120122, 1: 0.20202, 2: 0.273818, 3: 0.20202, 4: 0.20202}


def test_edges_are_merged_and_checked(spark):
    raw = spark.createDataFrame([("a", "b", 1), ("b", "a", 2), ("c", "c", 5)], "a string, b string, w long")
    assert [tuple(r) for r in graph.undirect(raw).collect()] == [("a", "b", 3)]
    with pytest.raises(PySparkException):
        graph.undirect(spark.createDataFrame([("a", "b", -1)], "a string, b string, w long")).collect()


def test_empty_graph(spark):
    g = partition.cut_by_vertex(graph.build(spark.createDataFrame([], "a string, b string, w long")), 3)
    assert g.n == 0 and g.edges.count() == 0 and sampling.noise(g).count() == 0
    assert [r["part"] for r in quota.idle_parts(g, 3).orderBy("part").collect()] == [0, 1, 2]


def test_edge_cut_covers_and_falls_back(copurchase, five):
    g, balanced = partition.cut_by_edges(copurchase, 4)
    assert balanced and g.vertices.select("part").distinct().count() == 4
    loads = [r[0] for r in g.vertices.groupBy("part").agg(F.sum("deg")).select("sum(deg)").collect()]
    assert max(loads) <= 1.1 * sum(loads) / 4
    assert partition.cut_by_edges(five, 5)[1] is False


def test_uneven_roots_follow_weights(spark):
    raw = spark.createDataFrame([("a", "b", 1), ("c", "d", 3)], "a string, b string, w long")
    g = partition.cut_by_vertex(graph.build(raw), 1)
    r = sampling.roots(g, 1, 4000).select((F.col("u") >= 2).alias("heavy")).groupBy("heavy").count()
    n = {x["heavy"]: x["count"] for x in r.collect()}
    assert abs(n[True] / 4000 - 0.75) < 4 * math.sqrt(0.75 * 0.25 / 4000)


def test_engines_walk_alike(copurchase):
    r = sampling.roots(copurchase, 1, 10)
    a = walks.walk_join(sampling.neighbor_index(copurchase, 8), r, 6)
    b = walks.walk_block(copurchase, r, 6)
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))
    a = walks.walk_join(sampling.neighbor_index(copurchase), r, 6, "boundary")
    b = walks.walk_block(copurchase, r, 6, "boundary")
    rows = sorted(map(tuple, a.collect()))
    assert rows == sorted(map(tuple, b.collect()))
    assert all(x[5] == x[6] == x[1] for x in rows)


def test_budget_ends_all_walks(five):
    r = sampling.roots(five, 1, 2)
    full = walks.walk_join(sampling.neighbor_index(five), r, 10)
    short = walks.walk_join(sampling.neighbor_index(five), r, 10, budget=12)
    assert short.count() < full.count() and short.agg(F.max("step")).first()[0] < 9


def test_biased_weights(spark, five):
    """From 3 to 2 with return 0.5 and in-out 2: back to 3 with 4/7, to its neighbour 4 with 2/7, away to 1 with 1/7."""
    starts = spark.range(3000).select(F.col("id").alias("walk_id"), F.lit(1).alias("part"), F.lit(3).cast("long").alias("u"), F.lit(2).cast("long").alias("v"), F.lit(0).alias("v_part"))
    steps = walks.biased_walk(five, starts, 2, 0.5, 2.0).where("step = 1").groupBy("dst").count()
    n = {r["dst"]: r["count"] for r in steps.collect()}
    for v, p in ((3, 4 / 7), (4, 2 / 7), (1, 1 / 7)):
        assert abs(n[v] / 3000 - p) < 4 * math.sqrt(p * (1 - p) / 3000)


def test_components_and_replicas(five):
    assert {r["label"] for r in graph.components(five).collect()} == {0}
    g = graph.replicate(five, 3)
    assert g.n == 15 and g.edges.count() == 3 * 10 + 4
    assert {r["label"] for r in graph.components(g).collect()} == {0}


def test_readers_and_offsets(spark, five, tmp_path):
    (tmp_path / "e.txt").write_text("# comment\na b\nb c 4\n")
    assert [tuple(r) for r in readers.read_edge_list(spark, str(tmp_path / "e.txt")).orderBy("a").collect()] == [("a", "b", 1), ("b", "c", 4)]
    readers.write_offsets(five.edges, five.n, str(tmp_path / "csr"))
    spark.dataSource.register(readers.OffsetSource)
    got = spark.read.format("graph_offsets").option("slices", "2").option("path", str(tmp_path / "csr")).load()
    assert sorted(map(tuple, got.collect())) == sorted((r["src"], r["dst"]) for r in five.edges.collect())
    readers.write_edges(five.edges, str(tmp_path / "edges"))
    pruned = spark.read.parquet(str(tmp_path / "edges")).where("src_part = 1")
    assert "PartitionFilters: [isnotnull(src_part" in pruned._jdf.queryExecution().toString() and pruned.count() == 4


def test_no_nested_loop_in_draws(copurchase):
    plan = sampling.roots(copurchase, 2, 4)._jdf.queryExecution().toString()
    assert "SortMergeJoin" in plan or "HashJoin" in plan
    neg = sampling.negatives(sampling.roots(copurchase, 2, 4).withColumn("seq", F.col("round").cast("long")), copurchase, 1)
    assert neg.groupBy("batch", "part", "seq").count().where("count <> 1").isEmpty()

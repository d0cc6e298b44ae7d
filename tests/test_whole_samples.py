"""Samples are whole: every part that can fill is full."""

import pytest
from pyspark.sql import functions as F

from proxembed.operators import graph, partition
from proxembed.operators.sampling import roots
from proxembed.operators.variants import SampleConfig, Variant, sample
from proxembed.operators.walks import LongWalk, walk_block


def test_single_walks_until_all_parts_are_full(copurchase):
    s = sample(copurchase, Variant("all", "single"), SampleConfig(batch_size=24, batches=2, max_levels=12))
    assert s.met
    counts = {(r["batch"], r["part"]): r["count"] for r in s.pairs.groupBy("batch", "part").count().collect()}
    assert counts == {(b, p): 24 for b in range(2) for p in range(4)}


def test_stretches_and_blocks_take_the_same_steps(five):
    one = roots(five, 1, 1).where("part = 0")
    want = sorted(map(tuple, walk_block(five, one, 20).collect()))
    walk = LongWalk(five, one, block_edges=4)
    walk.until(7)
    assert len(want) == 20 and sorted(map(tuple, walk.until(20).collect())) == want


def test_parts_out_of_reach_are_an_error(spark):
    raw = spark.createDataFrame([("a", "b", 1), ("c", "d", 1)], "a string, b string, w long")
    with pytest.raises(ValueError, match="no path"):
        sample(partition.stored(partition.cut_by_vertex(graph.build(raw), 2)), Variant("all", "single"), SampleConfig(batch_size=3, batches=1, max_levels=2))


def test_local_draws_on_where_few_edges_are_inner(spark):
    """One inner edge among forty: 512 calls, the cap of old, gave some 13 of 40 pairs."""
    raw = spark.createDataFrame([("a00", "a01", 1)] + [("a00", f"b{i:02}", 1) for i in range(39)] + [("b00", "b01", 1)], "a string, b string, w long")
    built = graph.build(raw)
    owned = built.vertices.withColumn("part", (F.substring("key", 1, 1) == "b").cast("int")).select("vid", "part")
    edges = built.edges.drop("src_part", "dst_part").join(owned.toDF("src", "src_part"), "src").join(owned.toDF("dst", "dst_part"), "dst").select(built.edges.columns)
    g = partition.stored(graph.Graph(built.vertices.drop("part").join(owned, "vid"), edges, built.n, 2))
    s = sample(g, Variant("all", "local"), SampleConfig(batch_size=40, batches=1, length=1, rounds=256))
    assert s.met and s.calls > 512
    assert [r["count"] for r in s.pairs.groupBy("part").count().collect()] == [40, 40]


@pytest.mark.parametrize("kind", ["local", "reuse", "refresh"])
def test_short_batches_are_an_error(five, kind):
    with pytest.raises(ValueError, match="batches of 1000 pairs"):
        sample(five, Variant("all", kind), SampleConfig(batch_size=1000, batches=2, length=2, rounds=1, max_rounds=2))


def _spied_steps(monkeypatch):
    from proxembed.operators import walks

    plans, kept = [], walks.store

    def store(df, label, by=None):
        if label == "steps":
            plans.append(df._jdf.queryExecution().executedPlan().toString())
        return kept(df, label, by)

    monkeypatch.setattr(walks, "store", store)
    return plans


def test_a_graph_that_fits_a_task_is_walked_in_one_superstep(copurchase, monkeypatch):
    """walks that cross parts at nearly every step took a superstep each."""
    r = roots(copurchase, 1, 3)
    plans = _spied_steps(monkeypatch)
    assert walk_block(copurchase, r, 20).count() == 3 * 4 * 20
    assert sum("FlatMapCoGroups" in p for p in plans) == 1


@pytest.mark.parametrize("stop", ["length", "boundary"])
def test_parts_too_large_for_a_task_are_never_held(copurchase, monkeypatch, stop):
    """F2, F3, F5, F8, F9: a part's edges went to one Python task, whatever their number; now the lists that walkers meet are read."""
    from proxembed.operators import walks

    r = roots(copurchase, 1, 10)
    want = sorted(map(tuple, walk_block(copurchase, r, 6, stop).collect()))
    monkeypatch.setattr(walks, "BLOCK_EDGES", 10, raising=False)
    plans = _spied_steps(monkeypatch)
    assert sorted(map(tuple, walk_block(copurchase, r, 6, stop).collect())) == want
    assert plans and not any("FlatMapCoGroups" in p for p in plans)


def test_many_walkers_are_dealt_over_copies_of_a_whole_graph(copurchase, monkeypatch):
    from proxembed.operators import walks

    r = roots(copurchase, 1, 10)
    want = sorted(map(tuple, walk_block(copurchase, r, 6).collect()))
    monkeypatch.setattr(walks, "TASK_STEPS", 60, raising=False)
    assert sorted(map(tuple, walk_block(copurchase, r, 6).collect())) == want


def test_roots_are_those_of_one_prefix_over_all_edges(copurchase):
    """Draws that go to a vertex and then into its list meet the edge that a prefix over the part's edges gives."""
    from proxembed.functions.rng import ROOT, draw_numpy
    from proxembed.operators.sampling import root_ranges

    ranges = root_ranges(copurchase).collect()
    total = {p: max(x["hi"] for x in ranges if x["part"] == p) for p in range(4)}
    for x in roots(copurchase, 2, 5).collect():
        at = int(draw_numpy(7, ROOT, x["batch"], x["part"], x["round"])) % total[x["part"]]
        assert [(e["u"], e["v"]) for e in ranges if e["part"] == x["part"] and e["lo"] <= at < e["hi"]] == [(x["u"], x["v"])]


def test_a_long_walk_on_a_graph_of_one_block_takes_one_task(five, monkeypatch):
    """a walk went back to the driver at every border of blocks of a million edges."""
    plans = _spied_steps(monkeypatch)
    walk = LongWalk(five, roots(five, 1, 1).where("part = 0"))
    assert walk.until(30).count() == 30 and walk.until(60).count() == 60
    assert sum("FlatMapCoGroups" in p for p in plans) == 2


def test_nearest_vectors_are_exact_over_many_blocks(spark, tmp_path, monkeypatch):
    """all pairs were met in one nested loop of rows; blocks give the same edges, ties to the smaller id, copies and zero vectors included."""
    import numpy as np

    from proxembed.sources import builders

    x = np.random.default_rng(5).normal(size=(90, 6)).round(1)
    x[20:24], x[50] = x[3], 0
    spark.createDataFrame([(i, [float(a) for a in row]) for i, row in enumerate(x)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    monkeypatch.setattr(builders, "VECTORS", 16, raising=False)
    f = x.astype(np.float32).astype(float)
    n = np.sqrt((f * f).sum(1))
    want = {}
    for i in range(90):
        s = [(-round(float(f[i] @ f[j] / (n[i] * n[j])), 6), j) for j in range(90) if j != i and n[i] and n[j]]
        for v, j in sorted(s)[:10]:
            if v < 0:
                want[f"v:{min(i, j)}", f"v:{max(i, j)}"] = max(1, round(-v * 1000))
    df = builders.vector_knn(spark, str(tmp_path))
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastNestedLoopJoin" not in plan and "CartesianProduct" not in plan
    got = {(r["a"], r["b"]): r["w"] for r in df.collect()}
    assert got.keys() == want.keys() and all(abs(got[e] - want[e]) <= 1 for e in want)


def test_spectral_vectors_of_larger_graphs_are_eigenvectors(spark):
    """more than 2,000 vertices were an error."""
    import numpy as np

    from proxembed.operators import baselines

    raw = spark.range(2400).selectExpr("concat('c', id) a", "concat('n', id % 40) b", "1L w").unionByName(spark.range(40).selectExpr("concat('n', id) a", "concat('n', (id * 7 + 3) % 40) b", "1L w")).unionByName(spark.range(39).selectExpr("concat('n', id) a", "concat('n', id + 1) b", "1L w"))
    g = graph.build(raw)
    a = np.zeros((g.n, g.n))
    for e in g.edges.collect():
        a[e["src"], e["dst"]] = e["w"]
    d = a.sum(1)
    a /= np.sqrt(d[:, None] * d[None, :])
    top = np.sort(np.abs(np.linalg.eigvalsh(a)))[::-1][:6]
    rows = sorted(baselines.fit_spectral_small(g, 6).collect(), key=lambda r: r["vid"])
    u = np.array([r["u"] for r in rows])
    assert len(u) == g.n > 2000 and np.allclose((u * u).sum(0), top, atol=1e-4)
    for x in u.T:
        theta = x @ a @ x / (x @ x)
        assert np.linalg.norm(a @ x - theta * x) < 1e-3


def test_near_documents_meet_as_whole_sets_only_where_sketches_let_them(spark, tmp_path, monkeypatch):
    """every pair that shared a frequent word carried both sets; equal to all pairs by brute force, copies included."""
    import numpy as np

    from proxembed.sources import builders

    r, kept, seen = np.random.default_rng(3), builders.store, []
    words = ["".join(chr(97 + int(x)) for x in r.integers(0, 26, 4)) for _ in range(120)]
    sets = [set(r.choice(words, int(r.integers(1, 60)), replace=False)) for _ in range(50)]
    sets += [s | set(r.choice(words, 5)) for s in sets[:15]] + sets[:6]
    spark.createDataFrame([(i, " ".join(sorted(s))) for i, s in enumerate(sets)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    monkeypatch.setattr(builders, "store", lambda df, label: seen.append((label, kept(df, label))) or seen[-1][1])
    got = {(x["a"], x["b"], x["w"]) for x in builders.near_doc(spark, str(tmp_path)).collect()}
    share = {(i, j): len(sets[i] & sets[j]) / len(sets[i] | sets[j]) for i in range(len(sets)) for j in range(i + 1, len(sets))}
    want = {(f"d:{i}", f"d:{j}"): 1000 * x for (i, j), x in share.items() if x >= 0.5}
    assert {(min(a, b, key=lambda k: int(k[2:])), max(a, b, key=lambda k: int(k[2:]))): w for a, b, w in got}.keys() == want.keys()
    assert [df.count() for label, df in seen if label == "candidates"][-1] <= 3 * len(want)

"""Stop rules, spill folds, variants and training."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from proxembed.operators import baselines, evaluate, measure, quota
from proxembed.operators.sampling import negatives
from proxembed.operators.train import TrainConfig, embedding, initial_frame, signed, train, train_dataflow
from proxembed.operators.variants import GRID, SampleConfig, Variant, sample

ONE_BATCH = {"A": (3, 4, 2, 5), "B": (1, 2, 6, 1), "C": (0, 1, 1, 9)}
CALLS = np.array([(3, 1, 0), (4, 2, 1), (2, 6, 1), (5, 1, 9), (6, 6, 6)])


def test_rules(spark):
    y = spark.createDataFrame([(0, p, r, n) for p, ns in ONE_BATCH.items() for r, n in enumerate(ns)], "batch int, part string, round int, pairs int")
    for rule, rounds, kept in (("any", 2, [6, 3, 1]), ("all", 4, [6, 6, 6])):
        assert quota.rounds_needed(y, 6, rule).first()["rounds"] == rounds
        assert [r["kept"] for r in quota.kept_counts(y, 6, rule).orderBy("part").collect()] == kept


@pytest.mark.parametrize(("keep", "rule", "want"), [
    ("none", "any", [(1, (3, 1, 0), (0, 0, 0)), (1, (3, 2, 1), (0, 0, 0)), (1, (2, 3, 1), (0, 0, 0))]),
    ("none", "all", [(4, (3, 3, 3), (0, 0, 0)), (1, (3, 3, 3), (0, 0, 0))]),
    ("ever", "any", [(1, (3, 1, 0), (0, 0, 0)), (1, (3, 2, 1), (1, 0, 0)), (1, (3, 3, 1), (0, 3, 0))]),
    ("ever", "all", [(4, (3, 3, 3), (11, 7, 8)), (0, (3, 3, 3), (8, 4, 5)), (0, (3, 3, 3), (5, 1, 2))]),
    ("once", "any", [(1, (3, 1, 0), (0, 0, 0)), (1, (3, 2, 1), (1, 0, 0)), (1, (3, 3, 1), (0, 3, 0))]),
    ("once", "all", [(4, (3, 3, 3), (11, 7, 8)), (1, (3, 3, 3), (6, 6, 6))]),
])
def test_spill(keep, rule, want):
    x = quota.spill_fold(CALLS, 3, 3, rule, keep)
    got = [(int(b["calls"].iloc[0]), tuple(b["kept"]), tuple(b["spill"])) for _, b in x.groupby("batch")]
    assert got == want


def test_idle_part_is_waived():
    counts = np.array([(3, 0), (3, 0)])
    assert len(quota.spill_fold(counts, 3, 2, "all", "ever")) == 0
    assert list(quota.spill_fold(counts, 3, 2, "all", "ever", np.array([False, True]))["kept"]) == [3, 0, 3, 0]


@pytest.fixture(scope="module")
def drawn(copurchase):
    c = SampleConfig(batch_size=24, batches=2, length=8, rounds=8, max_levels=12)
    return {v: sample(copurchase, v, c) for v in GRID}


def test_variants_keep_their_promises(copurchase, drawn):
    edges = {(r["src"], r["dst"]) for r in copurchase.edges.collect()}
    owner = {r["vid"]: r["part"] for r in copurchase.vertices.collect()}
    for v, s in drawn.items():
        rows = s.pairs.collect()
        assert all(owner[r["u"]] == r["part"] and owner[r["v"]] == r["v_part"] for r in rows), v
        counts = {}
        for r in rows:
            counts[r["batch"], r["part"]] = counts.get((r["batch"], r["part"]), 0) + 1
        assert max(counts.values()) <= 24
        if v.kind == "single":
            assert all((r["u"], r["v"]) in edges for r in rows)
            continue
        assert s.met, v
        if v.rule == "all":
            assert all(counts.get((b, p)) == 24 for b in range(2) for p in range(4)), v
        else:
            assert all(max(counts.get((b, p), 0) for p in range(4)) == 24 for b in range(2)), v
        if v.kind == "local":
            assert all(r["part"] == r["v_part"] for r in rows) and s.handed == 0
        if v.kind != "pair":
            assert all((r["u"], r["v"]) in edges for r in rows)
        if v.kind in ("local", "fresh", "pair"):
            assert all(r["age"] == 0 for r in rows)
        if v.kind == "refresh":
            assert all(r["age"] <= 1 for r in rows)


def test_trends(copurchase, drawn):
    """Local hands over nothing, reuse calls no oftener than fresh, all no less than any, only pairs of pairs are no edges."""
    by = {(v.rule, v.kind): s for v, s in drawn.items()}
    assert by["all", "reuse"].calls <= by["all", "fresh"].calls
    for kind in ("local", "fresh", "reuse", "refresh"):
        assert by["all", kind].calls >= by["any", kind].calls
    false = {k: measure.false_positive_share(s.pairs, copurchase).first()["share"] for k, s in by.items()}
    assert false["all", "pair"] > 0.1 and all(x == 0 for k, x in false.items() if k[1] != "pair")
    assert measure.sample_spread(by["all", "fresh"].pairs, 4, 2).first()["zero_parts"] == 0


def test_partitioning_changes_nothing(spark, copurchase):
    c = SampleConfig(batch_size=10, batches=1, length=5, rounds=4)
    rows = []
    for n in ("3", "7"):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        rows.append(sorted(map(tuple, sample(copurchase, Variant("any", "fresh"), c).pairs.collect())))
    spark.conf.set("spark.sql.shuffle.partitions", "4")
    assert rows[0] == rows[1]


def _signs(g, s):
    return signed(s.pairs, negatives(s.pairs, g, 1))


def test_trainers_agree_when_all_is_deferred(copurchase, drawn):
    rows = _signs(copurchase, drawn[Variant("any", "fresh")])
    # One deferred pass reads U after its positives, a synchronous batch doesn't: positives alone compare.
    rows = rows.where("sign = 1")
    c = TrainConfig(dim=4, lr=0.1, defer_all=True, kernel="mini", mini_size=100_000, order=1)
    a = {r["vid"]: (r["u"], r["c"]) for r in embedding(train(copurchase, rows, c, 2), 4).collect()}
    b = {r["vid"]: (r["u"], r["c"]) for r in train_dataflow(initial_frame(copurchase, c), rows, c, 2).collect()}
    for v in a:
        assert np.allclose(a[v][0], b[v][0], atol=2e-6) and np.allclose(a[v][1], b[v][1], atol=2e-6)


def test_one_owner_is_plain_descent(copurchase):
    from proxembed.operators.kernels import run_exact
    from proxembed.operators.train import initial_vectors

    one = baselines.one_owner(copurchase)
    pairs = baselines.edge_pairs(one, 1, 200)
    rows = signed(pairs, negatives(pairs, one, 1))
    c = TrainConfig(dim=4, lr=0.1, kernel="exact")
    got = {r["vid"]: r["u"] for r in embedding(train(one, rows, c, 1), 4).collect()}
    vids = np.array(sorted(got))
    U, C = initial_vectors(vids, c)
    x = sorted(rows.collect(), key=lambda r: (r["seq"], r["j"]))
    at = {int(v): k for k, v in enumerate(vids)}
    run_exact(U, C, np.array([at[r["u"]] for r in x]), np.array([at[r["v"]] for r in x]), np.array([r["sign"] for r in x]), c.lr, c.neg_weight, c.decay)
    assert np.allclose(U, [got[int(v)] for v in vids], atol=1e-5)


@pytest.mark.parametrize("c", [TrainConfig(dim=4, exchange="onesided_get", onesided_slices=2), TrainConfig(dim=4, exchange="onesided_atomic", onesided_slices=2), TrainConfig(dim=4, sync_every=2), TrainConfig(dim=4, fetch="before")])
def test_exchanges_train_all(copurchase, drawn, c):
    out = embedding(train(copurchase, _signs(copurchase, drawn[Variant("any", "reuse")]), c, 2), 4)
    assert out.count() == copurchase.n and out.where(F.exists("c", lambda x: x != 0)).count() > 0


def test_state_and_adjacency_stay_where_they_lie(spark, copurchase, monkeypatch):
    """A superstep exchanges its work or the walkers that left, never the state or the edges, which are read bucketed."""
    from proxembed.operators import storage, train as training, walks

    seen = []

    def spy(kind):
        def keep(self, df, label="superstep"):
            if label == "superstep" and "FlatMapCoGroups" in df._jdf.queryExecution().executedPlan().toString():
                seen.append(("train", df._jdf.queryExecution().executedPlan().toString()))
            return kind(self, df, label)

        return keep

    monkeypatch.setattr(storage.Buckets, "keep", spy(storage.Buckets.keep))
    kept = walks.store

    def store(df, label, by=None):
        if label == "steps" and "FlatMapCoGroups" in df._jdf.queryExecution().executedPlan().toString():
            seen.append(("walk", df._jdf.queryExecution().executedPlan().toString()))
        return kept(df, label)

    monkeypatch.setattr(walks, "store", store)
    s = sample(copurchase, Variant("any", "fresh"), SampleConfig(batch_size=10, batches=1, length=6, rounds=2))
    training.train(copurchase, _signs(copurchase, s), TrainConfig(dim=4), 1)
    assert {kind for kind, _ in seen} == {"train", "walk"}
    for kind, plan in seen:
        lines = plan.splitlines()
        scans = [k for k, line in enumerate(lines) if "Bucketed: true" in line]
        assert scans, plan
        # The bucketed side goes from its scan to the co-group without an exchange.
        top = next(k for k, line in enumerate(lines) if "FlatMapCoGroups" in line)
        between = lines[top + 1 : scans[0]]
        assert not any("Exchange hashpartitioning" in line for line in between), plan


def test_batches_are_read_alone(spark, copurchase, drawn):
    from proxembed.operators.storage import store

    rows = store(_signs(copurchase, drawn[Variant("any", "fresh")]), "signed", by=["batch"])
    plan = rows.where("batch = 1")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(batch" in plan


def _by_hand(g, rows, c, batches):
    """Supersteps by a plain loop: local pairs in order, then deferred ones on contexts as sent, positives first; deltas arrive with the next batch."""
    from proxembed.operators import kernels
    from proxembed.operators.train import initial_vectors

    vids = np.array(sorted(r["vid"] for r in g.vertices.collect()))
    U, C = (x.astype(np.float64) for x in initial_vectors(vids, c))
    at = {int(v): k for k, v in enumerate(vids)}
    held = sorted(rows.collect(), key=lambda r: (r["batch"], r["seq"], r["j"]))
    for b in range(batches):
        mine = [r for r in held if r["batch"] == b]
        for p in range(g.parts):
            for r in (r for r in mine if r["part"] == p == r["v_part"]):
                u, v = at[r["u"]], at[r["v"]]
                U[u], d = kernels.apply_pair(U[u], C[v], float(kernels.step_scalar(U[u] @ C[v], r["sign"], c.lr, c.neg_weight)), c.lr, c.decay)
                C[v] += d
        shown, change = C.copy(), np.zeros_like(C)
        for p in range(g.parts):
            for sign in (1, -1):
                for r in (r for r in mine if r["part"] == p != r["v_part"] and r["sign"] == sign):
                    u, v = at[r["u"]], at[r["v"]]
                    U[u], d = kernels.apply_pair(U[u], shown[v], float(kernels.step_scalar(U[u] @ shown[v], r["sign"], c.lr, c.neg_weight)), c.lr, c.decay)
                    change[v] += d
        C += change
    return dict(zip(vids.tolist(), zip(U, C, strict=True), strict=True))


@pytest.mark.parametrize("variant", [Variant("all", "fresh"), Variant("any", "reuse")])
def test_supersteps_equal_a_plain_loop(copurchase, drawn, variant):
    c = TrainConfig(dim=4, lr=0.1)
    rows = _signs(copurchase, drawn[variant])
    want = _by_hand(copurchase, rows, c, 2)
    for r in embedding(train(copurchase, rows, c, 2), 4).collect():
        assert np.allclose(r["u"], want[r["vid"]][0], atol=1e-5) and np.allclose(r["c"], want[r["vid"]][1], atol=1e-5)


def test_a_lost_driver_goes_on_from_the_last_version(spark, copurchase, drawn, tmp_path):
    from proxembed.operators.storage import Versions

    c, rows = TrainConfig(dim=4), _signs(copurchase, drawn[Variant("all", "fresh")])
    take = lambda state: sorted((r["vid"], tuple(r["u"]), tuple(r["c"])) for r in embedding(state, 4).collect())
    whole = take(train(copurchase, rows, c, 2))
    path = f"file://{tmp_path}/state"
    train(copurchase, rows.where("batch < 1"), c, 1, versions=Versions(spark, path))
    (tmp_path / "state" / "v2").mkdir()  # a version that was begun and not named
    assert Versions(spark, path).current() == 1
    assert take(train(copurchase, rows, c, 2, versions=Versions(spark, path))) == whole
    assert Versions(spark, path).current() == 2


def test_flagship_trains_nearly_all(spark):
    from proxembed.plans import runs

    sf = "/root/testdata/sf0.001"
    g, c = runs.hashed(spark, sf, "geography"), runs.CONFIG
    got = {r["vid"]: r for r in runs.train_blocked(spark, sf).collect()}
    first = {r["vid"]: r for r in baselines.initial(g, c).collect()}
    tied = [r["vid"] for r in g.vertices.where("deg > 0").collect()]
    moved = sum(got[v]["u"] != first[v]["u"] and got[v]["c"] != first[v]["c"] for v in tied)
    assert moved / len(tied) > 0.95
    loss = {(r["batch"], r["trained"]): r["loss"] for r in runs.training_loss(spark, sf).collect()}
    assert all(loss[b, True] < loss[b, False] for b in range(runs.BATCHES))


def test_neighbors_only(copurchase, five, drawn):
    """The exchange between parts that share edges gives what the collective one does, and refuses other pairs."""
    rows = signed(drawn[Variant("all", "fresh")].pairs, negatives(drawn[Variant("all", "fresh")].pairs, copurchase, 1, scope="adjacent"))
    take = lambda e: sorted((r["vid"], tuple(r["u"])) for r in embedding(train(copurchase, rows, TrainConfig(dim=4, exchange=e), 2), 4).collect())
    assert take("neighbors") == take("collective")
    from proxembed.operators.graph import Graph

    cut = Graph(five.vertices, five.edges.where("src_part = dst_part"), five.n, five.parts)
    far = five.edges.where("src_part <> dst_part").limit(1).selectExpr("0 batch", "src_part part", "0L seq", "0 j", "src u", "dst v", "dst_part v_part", "1 sign")
    with pytest.raises(ValueError, match="shares no edge"):
        train(cut, far, TrainConfig(dim=4, exchange="neighbors"), 1)


def test_one_part_after_the_other_sees_all_deltas(copurchase, drawn):
    """Atomic fetches equal a loop over parts in turn, each on contexts that hold all earlier changes."""
    c = TrainConfig(dim=4, lr=0.1, exchange="onesided_atomic")
    rows = _signs(copurchase, drawn[Variant("all", "fresh")]).where("batch = 0")
    turns = rows.withColumn("batch", F.col("part").cast("int"))
    want = _by_hand(copurchase, turns, TrainConfig(dim=4, lr=0.1), 4)
    for r in embedding(train(copurchase, rows, c, 1), 4).collect():
        assert np.allclose(r["u"], want[r["vid"]][0], atol=1e-5) and np.allclose(r["c"], want[r["vid"]][1], atol=1e-5)


def test_budget_ends_calls(copurchase):
    from proxembed.operators.variants import within_budget
    from proxembed.operators.sampling import roots
    from proxembed.operators.walks import walk_block

    steps = walk_block(copurchase, roots(copurchase, 1, 3), 10)
    kept = within_budget(steps, 4, 15).collect()
    # Four walkers: 8 visits, then 12, then 16: two further steps.
    assert {r["step"] for r in kept} == {0, 1, 2} and len(kept) == 3 * 4 * 3
    s = sample(copurchase, Variant("all", "fresh"), SampleConfig(batch_size=10, batches=1, length=10, budget=15))
    assert s.met and s.calls > sample(copurchase, Variant("all", "fresh"), SampleConfig(batch_size=10, batches=1, length=10)).calls


def test_alias_draws_have_the_noise_distribution(copurchase, drawn):
    from proxembed.operators.sampling import alias_negatives, noise

    pairs = drawn[Variant("all", "fresh")].pairs
    got = alias_negatives(pairs, copurchase, 60)
    n = got.count()
    assert n == 60 * pairs.count()
    weight = {r["vid"]: r["qw"] for r in noise(copurchase).collect()}
    total = sum(weight.values())
    count = {r["v"]: r["count"] for r in got.groupBy("v").count().collect()}
    chi = sum((count.get(v, 0) - n * w / total) ** 2 / (n * w / total) for v, w in weight.items())
    assert chi < len(weight) + 5 * (2 * len(weight)) ** 0.5
    owner = {r["vid"]: r["part"] for r in copurchase.vertices.collect()}
    assert all(owner[r["v"]] == r["v_part"] for r in got.limit(200).collect())


def test_bucketed_negatives_stay_in_their_bucket(copurchase):
    seen = []
    from proxembed.operators import baselines as b

    kept = b.store

    def spy(df, label, by=None):
        if label == "bucketed":
            seen.append(df)
        return kept(df, label, by) if by else kept(df, label)

    b.store, held = spy, b.store
    try:
        out = b.fit_bucketed(copurchase, TrainConfig(dim=4), 101, 3)
    finally:
        b.store = held
    rows = seen[0].collect()
    where = {(r["part"], r["seq"]): r["v_part"] for r in rows if r["sign"] == 1}
    assert len(where) == 101 and all(where[r["part"], r["seq"]] == r["v_part"] for r in rows)
    assert out.count() == copurchase.n


def test_blocked_prefixes_equal_plain_ones(copurchase, monkeypatch):
    from proxembed.operators import sampling

    monkeypatch.setattr(sampling, "IDS_PER_BLOCK", 7)
    for small in (3, 4096):
        got = {(r["src"], r["dst"]): (r["lo"], r["hi"]) for r in sampling.neighbor_prefix(copurchase, chunk=small).collect()}
        assert got == {(r["src"], r["dst"]): (r["lo"], r["hi"]) for r in sampling.prefix(copurchase.edges, ["src"], ["dst"], "w").collect()}
    got = {(r["u"], r["v"]): (r["part"], r["lo"], r["hi"]) for r in sampling.root_ranges(copurchase).collect()}
    assert got == {(r["src"], r["dst"]): (r["src_part"], r["lo"], r["hi"]) for r in sampling.prefix(copurchase.edges, ["src_part"], ["src", "dst"], "w").collect()}


def test_profiles_come_from_tasks(spark, copurchase):
    before, took = measure.last_stage(spark), {}
    with measure.timed(took, "counting", spark):
        copurchase.edges.groupBy("src").count().collect()
    tasks = measure.task_profile(spark, before)
    assert tasks.count() > 0 and {r["phase"] for r in tasks.collect()} == {"counting"}
    rows = {r["routine"]: r for r in measure.routine_profile(tasks).collect()}
    assert abs(sum(r["share_percent"] for r in rows.values()) - 100) < 0.1 and all(0 <= r["imbalance_percent"] <= 100.001 for r in rows.values())
    moved = measure.traffic(tasks).first()
    assert moved["exchanged_rows"] > 0 and moved["exchanged_bytes"] > 0 and took["counting"] > 0
    assert measure.process_memory(spark).count() >= 1


def test_regions_are_learned(spark):
    """Exact communities: quality far above chance after edge sampling."""
    from proxembed.operators import partition
    from proxembed.sources import builders

    sf = "/root/testdata/sf0.01"
    g = partition.cut_by_vertex(builders.graph(spark, sf, "geography"), 1)
    vectors = baselines.fit_edge_sgd(g, TrainConfig(dim=16, lr=0.1), 400_000)
    r = evaluate.classify(vectors, builders.labelled(g, builders.labels(spark, sf, "geography"))).first()
    assert r["micro"] >= 0.8


def test_spectral_vectors_part_the_communities(five, spark):
    """Two triangles joined by an edge: the second eigenvector has one sign on each."""
    from proxembed.operators import graph

    g = graph.build(spark.createDataFrame([("a", "b", 1), ("b", "c", 1), ("a", "c", 1), ("c", "d", 1), ("d", "e", 1), ("e", "f", 1), ("d", "f", 1)], "a string, b string, w long"))
    side = {r["vid"]: r["u"][1] > 0 for r in baselines.fit_spectral_small(g, 2).collect()}
    key = {r["vid"]: r["key"] for r in g.vertices.collect()}
    left = {side[v] for v in side if key[v] in "abc"}
    assert len(left) == 1 and left != {side[v] for v in side if key[v] in "def"}


def test_nearest_asks_a_bounded_set(spark, monkeypatch):
    from proxembed.operators import train as training

    v = spark.createDataFrame([(0, [1.0, 0.0]), (1, [1.0, 0.1]), (2, [0.0, 1.0])], "vid long, u array<double>")
    assert [(r["q"], r["vid"]) for r in training.nearest(v, v.where("vid = 0"), 1).collect()] == [(0, 1)]
    monkeypatch.setattr(training, "MOST_QUERIES", 2)
    with pytest.raises(ValueError, match="at most 2"):
        training.nearest(v, v, 1)


def test_configs_are_checked():
    for bad in ({"batch_size": 0}, {"engine": "x"}):
        with pytest.raises(ValueError):
            SampleConfig(**bad)
    with pytest.raises(ValueError):
        TrainConfig(lr=0)
    with pytest.raises(ValueError):
        evaluate.split(None, 1.5, 7)

"""Hand numbers, the random back ends, cost arithmetic."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from proxembed.functions import rng, vectors
from proxembed.operators import evaluate, kernels, measure
from proxembed.operators.sampling import alias_table
from proxembed.operators.variants import GRID, Variant, aug_target


def test_one_local_update():
    u, c = np.array([0.1, 0.2]), np.array([0.3, -0.1])
    g = float(kernels.step_scalar(u @ c, 1, 0.025, 1.0))
    assert g == pytest.approx(0.012437500520828)
    new_u, delta = kernels.apply_pair(u, c, g, 0.025, 0.01)
    assert new_u == pytest.approx([0.103706250156, 0.198706249948])
    assert c + delta == pytest.approx([0.301168750052, -0.097487499896])


def test_negative_after_it():
    u, c = np.array([0.103706250156, 0.198706249948]), np.array([-0.2, 0.4])
    g = float(kernels.step_scalar(u @ c, -1, 0.025, 1.0))
    assert g == pytest.approx(-0.012867027281553)
    new_u, delta = kernels.apply_pair(u, c, g, 0.025, 0.01)
    assert new_u == pytest.approx([0.10625372905, 0.193509762473])
    assert delta == pytest.approx([-0.00128439115, -0.002656758739])


def test_mini_kernel_of_one_pair_is_exact():
    gen = np.random.default_rng(3)
    U, C = gen.normal(size=(6, 4)), gen.normal(size=(6, 4))
    iu, ic, sign = np.array([0, 1, 0, 2]), np.array([3, 3, 1, 0]), np.array([1, -1, 1, -1])
    a, b = (U.copy(), C.copy()), (U.copy(), C.copy())
    kernels.run_exact(*a, iu, ic, sign, 0.1, 1.0, 0.01)
    kernels.run_mini(*b, iu, ic, sign, 0.1, 1.0, 0.01, None, 1)
    assert np.allclose(a[0], b[0]) and np.allclose(a[1], b[1])


@pytest.mark.parametrize("held", [False, True])
def test_waves_end_as_sample_order_does(held):
    """Against a plain loop over pairs, with hubs, repeated pairs and both signs."""
    gen = np.random.default_rng(5)
    U, C = gen.normal(size=(12, 3)), gen.normal(size=(15, 3))
    iu, ic, sign = gen.zipf(1.5, 400) % 12, gen.zipf(1.3, 400) % 15, gen.choice([1, -1], 400)
    a, b, change = U.copy(), C.copy(), np.zeros_like(C)
    for i, j, s in zip(iu, ic, sign, strict=True):
        g = float(kernels.step_scalar(a[i] @ b[j], s, 0.1, 0.5))
        a[i], delta = kernels.apply_pair(a[i], b[j], g, 0.1, 0.01)
        (change if held else b)[j] += delta
    x, y, z = U.copy(), C.copy(), np.zeros_like(C)
    kernels.run_exact(x, y, iu, ic, sign, 0.1, 0.5, 0.01, z if held else None)
    assert np.allclose(a, x) and np.allclose(b, y) and np.allclose(change, z)
    w = kernels.waves(iu, ic)
    assert all(len(set(t[w == k])) == (w == k).sum() for t in (iu, ic) for k in range(w.max() + 1))


def test_draws_agree_between_engines(spark):
    keys = np.array([0, 1, 2**40, -5, 77])
    frame = spark.createDataFrame([(int(k),) for k in keys], "k long")
    for backend in ("xx", "md5"):
        got = [r[0] for r in frame.select(rng.draw(7, rng.STEP, "k", F.lit(3), backend=backend)).collect()]
        assert got == rng.draw_numpy(7, rng.STEP, keys, 3, backend=backend).tolist()
        assert all(0 <= x < rng.SPAN for x in got)


def test_cost_formula(spark):
    frame = spark.createDataFrame([(16, 1), (16, 5)], "p int, calls int")
    cost = measure.cost_formula(F.col("p"), F.lit(128), F.col("calls"), F.lit(1000), F.lit(60))
    assert [r[0] for r in frame.select(cost).collect()] == [1_083_120, 1_575_600]


def test_targets_and_grid():
    assert [aug_target(b, n) for b, n in ((100, 10), (256, 20), (1000, 60))] == [46, 102, 347]
    assert len(GRID) == 10
    assert Variant.parse("AR-Remote (Reuse-Spill)") == Variant("any", "reuse")
    assert str(Variant("all", "pair")) == "IB-Remote (Augmented-Pair)"
    for bad in ("AR-Remote (Augmented-Pair)", "XX-Local"):
        with pytest.raises(ValueError):
            Variant.parse(bad)


def test_f1_and_gain(spark):
    rows = spark.createDataFrame(list(zip((0, 0, 0, 1, 1, 2), (0, 0, 1, 1, 1, 0), strict=True)), "label int, prediction int")
    r = evaluate.f1(evaluate.confusion(rows)).first()
    assert (r["micro"], r["macro"]) == (0.666667, 0.488889)
    table = spark.createDataFrame([("ours", 0.72), ("edge", 0.28), ("walk", 0.55)], "m string, f double")
    assert {r["m"]: round(r["gain_percent"]) for r in evaluate.gain(table, "m", "f", "ours").collect()} == {"edge": 157, "walk": 31}


def test_alias_table_has_the_weights():
    w = np.array([1.0, 2.0, 3.0, 4.0])
    threshold, other = alias_table(w)
    mass = np.zeros(4)
    for i in range(4):
        mass[i] += threshold[i] / 4
        mass[other[i]] += (1 - threshold[i]) / 4
    assert mass == pytest.approx(w / w.sum())


def test_vector_sql(spark):
    vectors.register_sql(spark)
    r = spark.sql("SELECT vec_dot(array(1D, 2D), array(3D, 4D)) d, vec_cosine(array(1D, 0D), array(0D, 2D)) c, proximity(array(0D), array(1D)) p").first()
    assert (r["d"], r["c"], r["p"]) == (11.0, 0.0, 0.5)


def test_table_functions(spark, five):
    from proxembed.functions.tables import register_alias, register_walk

    register_walk(spark, five)
    steps = spark.sql("SELECT * FROM walk_from(0, 6)").orderBy("step").collect()
    edges = {(r["src"], r["dst"]) for r in five.edges.collect()}
    assert len(steps) == 6 and all((r["src"], r["dst"]) in edges for r in steps)
    assert all(a["dst"] == b["src"] for a, b in zip(steps, steps[1:], strict=False))
    register_alias(spark)
    assert spark.sql("SELECT * FROM alias_rows(array(1D, 1D, 2D))").count() == 3

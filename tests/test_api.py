"""The front: runs, tables of comparisons, exports, and checks before any job."""

import pytest

from proxembed import api
from proxembed.sources import builders

SF = "/root/testdata/sf0.001"
C = api.Config(dim=8, lr=0.1, batch_size=64, batches=2, epochs=2, length=6, parts=2, cut="hash")


@pytest.fixture(scope="module")
def regions(spark):
    g = api.cut(builders.graph(spark, SF, "geography"), C)
    return g, builders.labelled(g, builders.labels(spark, SF, "geography"))


def test_a_run_gives_vectors_and_costs(spark, regions, tmp_path):
    g, labels = regions
    r = api.embed(g, "IB-Remote (Fresh-Only)", C)
    assert r.embedding.count() == g.n and r.metrics["least"] == r.metrics["most"] == 64 and r.sample.met
    assert r.metrics["sampling_s"] > 0 and r.metrics["training_s"] > 0
    api.export(r.embedding, g.vertices, f"file://{tmp_path}/text")
    lines = spark.read.text(f"file://{tmp_path}/text").collect()
    assert len(lines) == g.n and all(len(x["value"].split(" ")) == 9 for x in lines)
    api.export(r.embedding, g.vertices, f"file://{tmp_path}/json", "json")
    assert spark.read.json(f"file://{tmp_path}/json").count() == g.n
    assert api.features(r.embedding).count() == g.n


def test_tables_of_comparison(regions):
    g, labels = regions
    t = {r["method"]: r["micro"] for r in api.compare(g, labels, ["AR-Local"], ["edge_sgd"], C, 0.5).collect()}
    assert set(t) == {"edge_sgd", "AR-Local"} and all(0 <= x <= 1 for x in t.values())
    rows = api.ablate(g, [api.Variant("any", "local"), api.Variant("all", "pair")], C).collect()
    assert [r["method"] for r in rows] == ["AR-Local", "IB-Remote (Augmented-Pair)"] and rows[0]["handed"] == 0
    per = {(r["method"], r["parts"]): r for r in api.scale(g, ["AR-Remote (Reuse-Spill)"], [1, 4], C).collect()}
    assert set(per) == {("AR-Remote (Reuse-Spill)", 1), ("AR-Remote (Reuse-Spill)", 4)}


@pytest.mark.parametrize("bad", [{"k": -1}, {"parts": 0}, {"cut": "x"}, {"trainer": "x"}, {"negative_scope": "x"}, {"batch_size": 0}, {"kernel": "x"}, {"lr": 0}, {"budget": 1}])
def test_settings_are_checked_first(bad):
    with pytest.raises(ValueError):
        api.Config(**bad)

"""Streams give what batches give; late rows within the watermark count, later ones don't."""

from pyspark.sql import functions as F

from proxembed.streaming import streams

SF = "/root/testdata/sf0.001"


def _folder(spark, path, late=()):
    ev = spark.read.parquet(f"{SF}/events.parquet").orderBy("ts")
    rows = ev.collect()
    third = len(rows) // 3
    for k in range(3):
        part = rows[k * third : (k + 1) * third if k < 2 else None]
        spark.createDataFrame(part, ev.schema).coalesce(1).write.mode("append").parquet(str(path))
    if late:
        spark.createDataFrame(list(late), ev.schema).coalesce(1).write.mode("append").parquet(str(path))


def test_windows_equal_batch(spark, tmp_path):
    _folder(spark, tmp_path / "in")
    q = streams.edge_windows(streams.stream_events(spark, str(tmp_path / "in"))).writeStream.format("memory").queryName("w").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination(120)
    want = streams.edge_windows(streams.read_events(spark, SF))
    assert spark.table("w").count() == want.count() and spark.table("w").exceptAll(want).isEmpty()


def test_dedupe_and_changes(spark, tmp_path):
    ev = spark.read.parquet(f"{SF}/events.parquet")
    one = ev.limit(1).collect()
    _folder(spark, tmp_path / "in", one)
    got = []
    q = streams.train_on_changes(streams.dedupe(streams.stream_events(spark, str(tmp_path / "in"), 10)), lambda e, k: got.append(e.agg(F.sum("w")).first()[0] or 0), str(tmp_path / "ck"))
    q.awaitTermination(120)
    assert sum(got) == ev.count()


def test_vectors_grow_with_the_graph(spark, tmp_path):
    """Micro-batches through foreachBatch give the batch graph; a batch delivered twice changes nothing; untouched vertices keep their vectors."""
    from proxembed.operators.train import TrainConfig
    from proxembed.streaming.incremental import IncrementalEmbedding

    _folder(spark, tmp_path / "in")
    e = IncrementalEmbedding(spark, f"file://{tmp_path}/model", parts=2, length=4, config=TrainConfig(dim=4))
    seen = []

    def each(edges, k):
        e.update(edges.where("b is not null"), k)
        seen.append(k)

    q = streams.train_on_changes(streams.stream_events(spark, str(tmp_path / "in")), each, str(tmp_path / "ck"))
    q.awaitTermination(300)
    assert q.exception() is None and len(seen) == 3
    want = streams.read_events(spark, SF).where("k is not null").groupBy("user_id", "k").count()
    _, (vertices, edges) = e.versions.read("vertices", "edges")
    assert edges.count() == want.count() and edges.agg(F.sum("w")).first()[0] == want.agg(F.sum("count")).first()[0]
    rows = e.vectors().collect()
    assert len(rows) == vertices.count() == len({r["key"] for r in rows})
    assert e.versions.current() == 3
    e.update(spark.createDataFrame([("u:1", "k:new", 1)], "a string, b string, w long"), 2)
    assert e.versions.current() == 3 and e.graph().n == len(rows)
    e.update(spark.createDataFrame([("far:1", "far:2", 1)], "a string, b string, w long"), 3)
    after = {r["key"]: (r["u"], r["c"]) for r in e.vectors().collect()}
    assert len(after) == len(rows) + 2 and all(after[r["key"]][0] == r["u"] for r in rows)

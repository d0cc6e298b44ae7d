"""WARC segments, HTML text, audio features, the multi-index and the pipeline."""

import base64
import hashlib
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from proxembed.llm import audio, html_text, multi_index, warc
from proxembed.llm.common import fresh_path

SF = "/root/testdata/sf0.001"


def digest(b):
    return base64.b32encode(hashlib.sha1(b).digest()).decode()


def test_segments_and_chunks():
    for body in ("", "a", "é漢😀" * 9000, "\r\n\r\n0\r\n\r\n" * 300):
        framed = warc.chunked(body)
        parts = warc.segments(framed, 1000)
        assert "".join(parts) == framed and all(len(p.encode()) <= 1000 for p in parts)
        assert warc.dechunk(framed.encode()).decode() == body
    with pytest.raises(ValueError):
        warc.dechunk(b"5\r\nabc\r\n0\r\n\r\n")


def test_archives_read_back(spark):
    rows = [(1, "u", "x" * 50_000), (2, "u\r\nv", None), (3, None, ""), (4, "u", "<p>é</p>\r\n\r\nWARC/1.1\r\n"), (5, "u", "x" * 50_000), (9, "w", "one"), (9, "w", "one"), (None, "u", "lost")]
    path = fresh_path(spark, "warc-test")
    warc.write_archives(spark.createDataFrame([(i, u, h, "e") for i, u, h in rows], "page_id long, url string, html string, digest string"), path)
    got = warc.read_pages(spark, path).collect()
    assert len(got) == len(rows)
    top = {}
    for i, _, h in rows:
        top[h or ""] = max(top.get(h or "", -1), i or -1)
    want = sorted((i or 0, len((h or "").encode()), digest((h or "").encode()), "response" if i is None or top[h or ""] == i else "revisit", 0 if i is None or top[h or ""] == i else top[h or ""]) for i, _, h in rows)
    assert sorted((r["page_id"] or 0, r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"] or 0) for r in got) == want
    whole = warc.read_records(spark, path)
    assert whole.where("kind = 'continuation'").count() >= 3
    last = whole.where("segment > 1 and total is null")
    with pytest.raises(Exception, match="segments missing"):
        warc.reassemble(whole.join(last.select("name", "segment").limit(1), ["name", "segment"], "left_anti")).collect()


def test_revisits_are_held_against_their_response(spark):
    rows = [(1, "u", "same"), (7, "u", "same"), (2**53 + 1, "u", "wide"), (2**53 + 3, "u", "wide"), (None, None, "same")]
    path = fresh_path(spark, "warc-test")
    warc.write_archives(spark.createDataFrame(rows, "page_id long, url string, html string"), path)
    got = {(r["page_id"], r["record_type"], r["refers_to"]) for r in warc.read_pages(spark, path).collect()}
    assert got == {(1, "revisit", 7), (7, "response", None), (2**53 + 1, "revisit", 2**53 + 3), (2**53 + 3, "response", None), (None, "response", None)}
    other = fresh_path(spark, "warc-test")
    lone = warc.records_of(1, "0-1", "u", "same", digest(b"same"), 7) + warc.records_of(7, "0-2", "u", "other", digest(b"other"), None)
    spark.createDataFrame([(x,) for x in lone], "value string").coalesce(1).write.option("lineSep", warc.END).option("compression", "gzip").text(other)
    with pytest.raises(Exception, match="no such response"):
        warc.read_pages(spark, other).collect()


def test_digests_in_dataframe_functions(spark):
    texts = ["", "a", "é漢😀", "x" * 5000]
    got = spark.createDataFrame([(t,) for t in texts], "t string").select(warc.digest_column(F.col("t"))).collect()
    assert [r[0] for r in got] == [digest(t.encode()) for t in texts]


def test_empty_archive(spark):
    path = fresh_path(spark, "warc-test")
    warc.write_archives(spark.createDataFrame([], "page_id long, url string, html string"), path)
    assert warc.read_pages(spark, path).count() == 0


PAGE = """<!DOCTYPE html><html><head><title>t</title><style>p{}</style><script>var t="</p>";</script></head><body>
<header><h2>Site name and slogan, here</h2></header><nav><ul><li><a href="/a">First menu entry</a></li></ul></nav>
<div class="cookie-notice">We use cookies, many cookies, to sell you things, all day long.</div>
<div id="wrap"><div class="sidebar"><p>Related things, links, and other offers that nobody asked for, ever.</p></div>
<div class="post-body"><h1>Title &amp; more</h1><p>First   paragraph, with commas, and
length enough to score well in any tree.<p>Second paragraph, unclosed, with a <a href="x">link</a> inside, and more text.</p>
<form><input name="q"><label>Search</label></form><p>Third &eacute; paragraph<br>after a break, which is long enough too.</p></div>
<div class="comments"><p>A reader, who comments, at length, about everything that was said above.</p></div></div>
<footer>&copy; nobody, 2020, all rights reserved, and so on</footer></body></html>"""


def test_main_text():
    assert html_text.extract(PAGE).split("\n\n") == ["Title & more", "First paragraph, with commas, and length enough to score well in any tree.", "Second paragraph, unclosed, with a link inside, and more text.", "Third é paragraph after a break, which is long enough too."]
    for odd in (None, "", "   ", "plain words only", "<p", "<<>>", "<a href='x", "<div>" * 3000, "&#0; &#xD800; &bogus;"):
        assert isinstance(html_text.extract(odd), str)
    assert html_text.extract("plain words only") == "plain words only"
    assert html_text.extract("<article><p>Cut off in the mid") == "Cut off in the mid"


def test_pages(spark):
    rows = html_text.main_text(spark.read.parquet(f"{SF}/pages.parquet").withColumn("text", F.lit(1))).collect()
    assert len(rows) == 50 and all(r["n_chars"] == len(r["text"]) for r in rows)
    assert all("&copy" not in r["text"] and "track(" not in r["text"] for r in rows)


def test_wave_round_trip(spark):
    for text in (None, "", "a", "é" * 1000):
        n, payload = audio.payload_of(text)
        assert len(payload) % 64 == 0 and len(payload) >= 64 and payload[:n].decode() == (text or "")
        assert audio.wave_samples(audio.wave_bytes(payload)) == (audio.RATE, payload)
    rows = audio.media_features(spark.createDataFrame([(1, None, 0), (2, "abc", 0), (3, "abc", 0), (None, "abc", 0)], "doc_id long, text string, feature int")).collect()
    by = {r["doc_id"]: r for r in rows}
    assert by[2]["feature"] == by[3]["feature"] == by[None]["feature"] and by[1]["payload_bytes"] == 64
    assert by[2]["payload_sha256"] == hashlib.sha256(b"abc" + b"\0" * 61).hexdigest() and by[2]["tail_crc32"] == zlib.crc32(b"abc" + b"\0" * 61)


def test_resampling_keeps_a_tone():
    t = np.arange(16_000) / 16_000
    out = audio.resample(np.sin(2 * np.pi * 440 * t).astype(np.float32), 16_000, 8_000)
    want = np.sin(2 * np.pi * 440 * np.arange(8_000) / 8_000)
    assert len(out) == 8_000 and np.abs(out[50:-50] - want[50:-50]).max() < 0.02
    up = audio.resample(np.ones(300, dtype=np.float32), 2, 3)
    assert len(up) == 450 and np.abs(up[30:-30] - 1).max() < 1e-4


def test_tones_land_in_their_bands_and_segments_close():
    t = np.arange(8_000) / 8_000
    low, high = (audio.log_mel(np.sin(2 * np.pi * f * t).astype(np.float32))[0].mean(0).argmax() for f in (200, 3000))
    assert low < 5 and high > 14
    e = np.array([-5, -5, 4, 0, 0, 4, -5, -5, 4, -5.0])
    assert audio.segments(e) == [(2, 6), (8, 9)]
    assert audio.segments(np.zeros(0)) == []


def test_tensor_blocks(spark):
    rows = audio.feature_tensors(spark.createDataFrame([(1, "x" * 40_000), (2, None)], "doc_id long, text string")).orderBy("doc_id", "block").collect()
    one = [r for r in rows if r["doc_id"] == 1]
    assert all(len(r["tensor"]) == audio.BLOCK * audio.MELS and r["shape"] == [audio.BLOCK, audio.MELS] for r in rows)
    assert len(one) == 3 and one[1]["from_ms"] == audio.BLOCK * 10 and one[0]["to_ms"] > one[1]["from_ms"] - 10


def _plain_features(payload):
    """Log-mel frames by an independent reading: direct convolution, one frame at a time, a loop over mel triangles."""
    x = (np.frombuffer(payload, np.uint8).astype(float) - 128) / 128
    t = np.arange(-8, 9)
    taps = 0.5 * np.sinc(0.5 * t) * (0.5 + 0.5 * np.cos(np.pi * t / 9))
    y = np.convolve(x, (taps / taps.sum())[::-1])[8 : 8 + len(x)][::2]
    mel = lambda f: 2595 * np.log10(1 + f / 700)
    edges = [700 * (10 ** (m / 2595) - 1) for m in np.linspace(0, mel(4000), audio.MELS + 2)]
    frames = []
    for a in range(0, max(1, len(y) - audio.FRAME + audio.HOP), audio.HOP):
        part = np.zeros(audio.FRAME)
        part[: len(y[a : a + audio.FRAME])] = y[a : a + audio.FRAME]
        power = np.abs(np.fft.rfft(part * np.hanning(audio.FRAME), audio.FFT)) ** 2
        row = []
        for lo, mid, hi in zip(edges, edges[1:], edges[2:], strict=False):
            f = np.arange(audio.FFT // 2 + 1) * 8000 / audio.FFT
            row.append(np.log((power * np.clip(np.minimum((f - lo) / (mid - lo), (hi - f) / (hi - mid)), 0, None)).sum() + 1e-6))
        frames.append(row)
    return np.array(frames)


def test_features_against_a_plain_reading():
    g = np.random.default_rng(2)
    for n in (64, 128, 448, 640, 64 * 30, 64 * 700):
        payload = g.integers(0, 256, n).astype(np.uint8).tobytes()
        mels, spans, back = audio.analyse(audio.wave_bytes(payload))
        want = _plain_features(payload)
        assert back == payload and mels.shape == want.shape and np.abs(mels - want).max() < 2e-2
        blocks, read = audio.read_tensors(audio.tensor_stream(mels, spans))
        assert read == spans and blocks["tensor"].type.shape == [audio.BLOCK, audio.MELS]
        held = blocks["tensor"].combine_chunks().to_numpy_ndarray().reshape(-1, audio.MELS)
        assert np.array_equal(held[: len(mels)], mels) and int(blocks["frames"].to_numpy().sum()) == len(mels)
        assert all(a < b for a, b in spans) and all(b[0] >= a[0] for a, b in zip(spans, spans[1:], strict=False))


def test_media_of_odd_rows(spark):
    assert audio.media_features(spark.createDataFrame([], "doc_id long, text string, tensors int, n_bytes int")).count() == 0
    long = "0123456789abcdef" * 200_000
    r = audio.media_features(spark.createDataFrame([(1, long)], "doc_id long, text string")).first()
    assert r["n_bytes"] == r["payload_bytes"] == len(long) and r["media_bytes"] == len(long) + 44
    blocks, spans = audio.read_tensors(bytes(r["tensors"]))
    assert r["feature"].startswith(f"{int(blocks['frames'].to_numpy().sum())}x{audio.MELS};{len(blocks)};") and blocks["to_ms"][-1].as_py() >= len(long) * 1000 // audio.RATE


def _brute(vectors, k=20):
    """Per query (id divisible by 20) its k best by inner product, ties to the smaller id."""
    x = {r["vec_id"]: np.array(r["embedding"], dtype=float) for r in vectors.collect()}
    ids = np.array(sorted(x))
    rows = np.stack([x[i] for i in ids])
    out = {}
    for q in ids[ids % 20 == 0].tolist():
        s = rows @ x[q]
        s[ids == q] = -np.inf
        out[q] = ids[np.lexsort((ids, -s))[:k]].tolist()
    return x, out


@pytest.mark.parametrize("sf", ["0.001", "0.01", "0.1"])
def test_recall_and_order(spark, sf):
    """All queries, with the defaults."""
    vectors = spark.read.parquet(f"/root/testdata/sf{sf}/embeddings.parquet")
    got = multi_index.search(vectors, vectors.where("vec_id % 20 = 0")).collect()
    x, truth = _brute(vectors)
    by = {}
    for r in got:
        by.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    assert set(by) == set(truth)
    hit = 0
    for q, rows in by.items():
        rows.sort()
        assert [r[0] for r in rows] == list(range(1, 21))
        assert all(abs(s - x[v] @ x[q]) < 1e-12 and v != q for _, v, s in rows)
        assert [(-s, v) for _, v, s in rows] == sorted((-s, v) for _, v, s in rows)
        hit += len(set(truth[q]) & {v for _, v, _ in rows})
    assert hit / (20 * len(truth)) >= 0.9


def test_clusters_make_walks_short(spark):
    g = np.random.default_rng(5)
    centers = g.normal(size=(60, 16))
    x = centers[g.integers(0, 60, 6000)] + 0.05 * g.normal(size=(6000, 16))
    v = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    rows, index = multi_index.build(multi_index.usable(v))
    ids = np.arange(0, 6000, 60)
    want = multi_index.rows_to_walk(index, x[ids], multi_index.exact_top(rows, ids, x[ids], 20), 0.96)
    assert want < 600 and index.held.sum() == 6000
    got = multi_index.search(v, v.where("vec_id % 20 = 0")).collect()
    _, truth = _brute(v)
    assert sum(r["vec_id"] in truth[r["query_id"]] for r in got) / (20 * len(truth)) >= 0.9


def test_blocks_and_shards_change_nothing(spark, monkeypatch):
    vectors = spark.read.parquet(f"{SF}/embeddings.parquet")
    take = lambda: sorted((r["query_id"], r["rank"], r["vec_id"]) for r in multi_index.search(vectors, vectors.where("vec_id % 20 = 0"), recall=1.0).collect())
    one = take()
    monkeypatch.setattr(multi_index, "SHARD_ROWS", 37)
    monkeypatch.setattr(multi_index, "BLOCK_QUERIES", 5)
    assert take() == one
    _, truth = _brute(vectors)
    assert sum(v in truth[q] for q, _, v in one) / (20 * len(truth)) >= 0.97


def test_cells_are_walked_in_order():
    g = np.random.default_rng(1)
    a, b, q = g.normal(size=(5, 3)), g.normal(size=(6, 3)), g.normal(size=6)
    held = (g.random(30) < 0.8).astype(np.int64)
    cells, end = multi_index.MultiIndex(a, b, held).walk(q, 30)
    s = [a[c // 6] @ q[:3] + b[c % 6] @ q[3:] for c in cells]
    assert sorted(cells) == np.flatnonzero(held).tolist() and all(x >= y - 1e-12 for x, y in zip(s, s[1:], strict=False)) and end == -np.inf
    some, end = multi_index.MultiIndex(a, b, held).walk(q, 4)
    assert some == cells[:4] and abs(end - s[3]) < 1e-12


def test_odd_vectors(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [1.0, 0.0]), (20, [0.0, 1.0]), (20, [0.0, 1.0]), (3, None), (4, [0.0, 0.0]), (5, [nan, 1.0]), (6, [inf, 1.0]), (7, [None, 1.0]), (8, [1.0]), (None, [1.0, 1.0])]
    v = spark.createDataFrame([(i, e, 0) for i, e in rows], "vec_id long, embedding array<float>, cell int")
    got = sorted((r["query_id"], r["rank"], r["vec_id"]) for r in multi_index.search(v, v.where("vec_id % 20 = 0")).collect())
    assert got == [(0, 1, 1), (0, 2, 2), (0, 3, 20), (0, 4, 20), (20, 1, 0), (20, 2, 1), (20, 3, 2)]
    assert multi_index.search(v.limit(0), v.limit(0)).count() == 0


def test_pipeline(spark):
    import corpus_pipeline

    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["toxicity", "line dedup", "n-gram Jaccard join", "secret scans", "best-fit packing"]
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    held, columns = docs, docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, held, SF).cache()
        assert out.columns == columns, name
        ids = out.select("doc_id").distinct().count()
        assert ids == out.count() <= held.count()
        held = out
    pieces = corpus_pipeline.STAGES[-1][1](spark, held, SF)
    assert pieces.select("doc_id").distinct().count() == held.count()
    full = corpus_pipeline.run(spark, SF)
    assert sorted((r["doc_id"], r["piece"], r["length"]) for r in full.collect()) == sorted((r["doc_id"], r["piece"], r["length"]) for r in pieces.collect())


def test_pipeline_on_odd_rows_and_none(spark):
    """All stages in one go: nulls, empties, copies, repeated rows, a very long text, columns of the operators' own names; and an empty table."""
    import random

    import corpus_pipeline

    g = random.Random(1)
    prose = lambda n: " ".join("".join(g.choice("abcdefghij") for _ in range(g.randint(2, 7))) for _ in range(n))
    a, long = prose(120), prose(50_000)
    rows = [(1, None), (2, ""), (3, " \n "), (None, a), (4, a), (4, a), (5, a + " tail"), (6, "token=abcdefgh1 " + prose(60)), (7, "two words"), (9, long), (None, None)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, row string, spans string, hit int, doc int, runs int, key int, id int"
    docs = spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t), "r", "x", 1, 2, 3, 4, 5) for i, t in rows], schema)
    for table in (docs, docs.limit(0)):
        held = table
        for name, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, held, SF)
            assert out.columns == docs.columns, name
            held = spark.createDataFrame(out.collect(), docs.schema)
        pieces = corpus_pipeline.STAGES[-1][1](spark, held, SF)
        if table is docs:
            kept = {r["doc_id"]: r["text"] for r in held.collect()}
            assert set(kept) >= {1, 2, 3, 7, 9} and "[secret]" in kept[6] and kept[9] == long
            assert pieces.where("doc_id = 9").count() > 1
        else:
            assert pieces.count() == 0

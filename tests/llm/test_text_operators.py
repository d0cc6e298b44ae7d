"""Secret scans, packing, near duplicates, line dedup, toxicity and subwords against brute force, and on odd rows."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from proxembed.llm import line_dedup, packing, parity_join, secret_scan, subword, toxicity
from proxembed.llm.components import components

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, blob string, piece string, label string"


def frame(spark, rows):
    """Rows of (doc_id, text) with the usual columns and some whose names the operators use themselves."""
    return spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t), "x", "y", "z") for i, t in rows], SCHEMA)


def prose(seed, n=120):
    g = random.Random(seed)
    return " ".join("".join(g.choice("abcdefghij") for _ in range(g.randint(2, 7))) for _ in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empties, ties, repeated rows, one very long text."""
    return [(1, None), (2, ""), (3, "   \n "), (None, prose(1)), (4, prose(1)), (4, prose(1)), (5, prose(1)), (6, prose(2)), (7, "two words"), (8, "two words"), (9, prose(3, 60_000)), (None, None)]


# Secrets

ASSIGN = re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A)


def brute_spans(text):
    out = [(m.start(), 0, "assign", m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    out += [(m.start(), 1, "access", m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    out += [(m.start(), 2, "hex", m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
    return sorted(out)


SECRETS = ["token=token : abcdefg", "😀 PassWord: 'hunter2222' x", "AKIA" + "Q" * 16 + " AKIAshort", "api_key=" + "a1" * 14, "\x01secret = \x01abcdef", "token==abc", "x" + "0123456789abcdef" * 2, "secret secret:secret=abcdefgh"]


def test_secret_spans(spark, odd):
    rows = odd + [(100 + k, s) for k, s in enumerate(SECRETS)] + [(200, " ".join(SECRETS) * 30)]
    docs = frame(spark, rows)
    found = secret_scan.scan_versions(docs.select(F.col("doc_id").alias("path"), "text"), secret_scan.BlobLedger(spark))
    by = {r["blob"]: [(s["start"], s["rank"], s["kind"], s["end"]) for s in r["spans"] if s["kind"] != "pem"] for r in found.collect()}
    for _, t in rows:
        assert by.get(hashlib.sha256((t or "").encode()).hexdigest(), []) == brute_spans(t or "")


def test_ledger_scans_only_what_it_lacks(spark, tmp_path):
    a, b = frame(spark, [(1, SECRETS[0]), (2, SECRETS[1])]), frame(spark, [(1, SECRETS[0]), (3, SECRETS[2])])
    ledger = secret_scan.BlobLedger(spark, None)
    as_paths = lambda d: d.select(F.col("doc_id").alias("path"), "text")
    secret_scan.scan_versions(as_paths(a), ledger).collect()
    before = ledger.read().count()
    seen = {r["blob"] for r in secret_scan.scan_versions(as_paths(b), ledger).collect()}
    assert seen == {hashlib.sha256(t.encode()).hexdigest() for t in (SECRETS[0], SECRETS[2])}
    assert before == 2 * len(secret_scan.RULES) and ledger.read().count() == 3 * len(secret_scan.RULES)
    newer = (*secret_scan.RULES[:3], secret_scan.Rule("pem", secret_scan.PEM, 1, 40, False, 2))
    secret_scan.scan_versions(as_paths(b), ledger, newer).collect()
    assert ledger.read().count() == 3 * len(secret_scan.RULES) + 2


def test_redaction(spark):
    docs = frame(spark, [(1, "a token=abcdefgh b"), (2, "plain"), (3, None), (4, "token = \"" + "0a" * 20 + "\" end")])
    out = {r["doc_id"]: r for r in secret_scan.secret_stage(spark, docs, SF).collect()}
    assert out[1]["text"] == "a [secret] b" and out[2]["text"] == "plain" and out[3]["text"] is None
    assert out[4]["text"] == "[secret]\" end" and out[4]["n_chars"] == len(out[4]["text"])
    assert secret_scan.secret_stage(spark, docs, SF).columns == docs.columns
    named = docs.withColumn("_hit", F.lit(1)).withColumn("row", F.lit(2)).withColumn("spans", F.lit(3)).withColumn("hit", F.lit("h")).withColumn("a.b", F.lit(4))
    again = secret_scan.secret_stage(spark, named, SF)
    assert again.columns == named.columns and sorted((r["doc_id"], r["_hit"], r["row"], r["spans"], r["hit"]) for r in again.collect()) == [(k, 1, 2, 3, "h") for k in range(1, 5)]
    assert secret_scan.secret_stage(spark, docs.limit(0), SF).count() == 0


# Packing


def test_encoder_equals_the_library():
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(packing.tokenizer_path("byte_bpe_50k.json"))
    texts = ["", " ", "  a", "a  b \n c\n\n d", "don't we'll 12ab ##", "x<|endoftext|>y", "tab\there  ", "é ß 漢字 😀", " \n lead", "trail \n", "a\x00b c", " x  y", prose(5)]
    e = packing.SpanEncoder()
    for t in texts * 2:
        assert np.frombuffer(e.encode(t), "<u4").tolist() == whole.encode(t, add_special_tokens=False).ids, repr(t)


def test_packing_is_whole_and_tight(spark, odd):
    docs = frame(spark, odd + [(300 + k, prose(k, 20 + 37 * k % 400)) for k in range(60)])
    rows = packing.packing_stage(spark, docs, SF).collect()
    e = packing.SpanEncoder()
    want = sorted(len(e.encode(t or "")) // 4 + 1 for _, t in [(r["doc_id"], r["text"]) for r in docs.collect()])
    per = {}
    for r in rows:
        per.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for places in per.values():
        at = 0
        for o, n in sorted(places):
            assert o == at
            at += n
        assert at <= packing.CAPACITY
    assert sum(r["length"] for r in rows) == sum(want)
    assert len(per) <= -(-sum(want) // packing.CAPACITY) + 1
    long = sorted((r["piece"], r["start"], r["length"]) for r in rows if r["doc_id"] == 9)
    assert all(n == packing.CAPACITY for _, _, n in long[1:]) and [p for p, _, _ in long] == list(range(len(long)))
    ids = e.encode(prose(3, 60_000)) + b"\0\0\0\0"
    assert all(zlib.crc32(ids[4 * r["start"] : 4 * (r["start"] + r["length"])]) == r["ids_crc32"] for r in rows if r["doc_id"] == 9)


def test_plan_uses_up_counts():
    g = random.Random(4)
    counts = {}
    for _ in range(5000):
        n = min(2048, max(1, int(g.expovariate(1 / 500))))
        counts[n] = counts.get(n, 0) + 1
    plan = packing.plan_sequences(counts)
    used = {}
    for pattern, times in plan:
        assert sum(pattern) <= 2048 and times > 0
        for x in pattern:
            used[x] = used.get(x, 0) + times
    assert used == counts
    assert sum(t for _, t in plan) <= -(-sum(k * n for k, n in counts.items()) // 2048) + 2
    assert packing.plan_sequences({}) == []


def brute_fill(have, length, gap):
    """Whether one to three of what is left besides a piece of `length` fill the gap."""
    from itertools import combinations_with_replacement

    left = dict(have)
    left[length] -= 1
    return any(sum(c) == gap and all(left.get(x, 0) >= c.count(x) for x in c) for k in (1, 2, 3) for c in combinations_with_replacement(sorted(left), k))


def test_every_exact_complement_is_found():
    g = random.Random(11)
    for _ in range(300):
        have = np.zeros(41, dtype=np.int64)
        for _ in range(g.randint(1, 9)):
            have[g.randint(1, 30)] += g.randint(1, 2)
        index = packing.SumIndex(have)
        for _ in range(4):
            if not have.any():
                break
            length = int(np.flatnonzero(have)[-1])
            got = index.complement(length, 40 - length)
            assert (got is not None) == brute_fill({int(x): int(have[x]) for x in np.flatnonzero(have)}, length, 40 - length)
            if got is not None:
                assert sum(got) == 40 - length
            index.use(length, 1)
            fresh = packing.SumIndex(have.copy())
            assert np.array_equal(index.single, fresh.single) and np.array_equal(index.pair, fresh.pair) and np.array_equal(index.triple, fresh.triple)


def fewest(lengths, capacity):
    """The optimum by trying all ways to put pieces into open sequences."""
    best = [len(lengths)]

    def go(k, bins):
        if len(bins) >= best[0]:
            return
        if k == len(lengths):
            best[0] = len(bins)
            return
        for free in set(bins):
            if free >= lengths[k]:
                go(k + 1, _put(bins, free, lengths[k]))
        go(k + 1, [*bins, capacity - lengths[k]])

    def _put(bins, free, n):
        out = list(bins)
        out.remove(free)
        return [*out, free - n]

    go(0, [])
    return best[0]


def test_plan_is_near_the_optimum_on_small_inputs():
    g = random.Random(7)
    exact = 0
    for _ in range(60):
        lengths = sorted((g.randint(1, 40) for _ in range(g.randint(1, 9))), reverse=True)
        counts = {x: lengths.count(x) for x in set(lengths)}
        used, best = sum(t for _, t in packing.plan_sequences(counts, 40)), fewest(lengths, 40)
        assert best <= used <= best + 1
        exact += used == best
    assert exact >= 55


def test_packing_of_an_empty_table_and_wide_ids(spark, odd):
    assert packing.packing_stage(spark, frame(spark, odd).limit(0), SF).count() == 0
    rows = packing.packing_stage(spark, frame(spark, [(2**53 + 1, "a b"), (None, "c")]), SF).collect()
    assert {r["doc_id"] for r in rows} == {2**53 + 1, None}


# Near duplicates


def brute_components(rows):
    sets = []
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets.append((i, frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])))
    root = {i: i for i, _ in sets if i is not None}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, (i, s) in enumerate(sets):
        for j, t in sets[:a]:
            if i is not None and j is not None and s and t and 100 * len(s & t) >= 75 * len(s | t):
                x, y = sorted((find(i), find(j)))
                root[y] = x
    return sorted((i if i is not None else -1, len(s), -1 if i is None else find(i)) for i, s in sets)


def edited(text, share, seed):
    g, words = random.Random(seed), text.split()
    for k in range(len(words)):
        if g.random() < share:
            words[k] = f"w{g.randint(0, 9999)}"
    return " ".join(words)


def test_components_of_links(spark, odd):
    rows = list(odd)
    for base, n in ((10, 12), (11, 80), (12, 300), (13, 700), (14, 1500)):
        rows += [(1000 * base + k, edited(prose(base, n), 0.004 * (k % 12), 31 * base + k)) for k in range(24)]
    rows += [(90_000 + k, prose(77, 200) + " " + prose(500 + k, 40)) for k in range(80)]
    rows += [(95_000 + k, " ".join(prose(88, 30).split()[k % 7 :])) for k in range(14)] + [(96_000, "A b C d"), (96_001, "a B c D"), (96_002, "A b c d e"), (96_003, "a b c d e f g")]
    got = parity_join.jaccard_components(frame(spark, rows)).collect()
    got = sorted((-1 if r["doc_id"] is None else r["doc_id"], r["n_shingles"], -1 if r["component_id"] is None else r["component_id"]) for r in got)
    assert got == brute_components(rows)


def test_sketch_distance_is_a_lower_bound():
    g = np.random.default_rng(0)
    a = np.unique(g.integers(0, 2**63, 400).astype(np.uint64))
    b = np.unique(np.concatenate((a[:300], g.integers(0, 2**63, 90).astype(np.uint64))))
    x, y = (np.frombuffer(parity_join.parity_sketch(s), np.uint64) for s in (a, b))
    n = min(len(x), len(y))
    x, y = (s if len(s) == n else s[:n] ^ s[n:] for s in (x, y))
    assert int(np.bitwise_count(x ^ y).sum()) <= len(np.setxor1d(a, b))


@pytest.mark.parametrize("n", [3, 4, 5, 7, 8, 12, 30, 100, 255, 600])
def test_partners_share_one_of_the_first_blocks(spark, n):
    """Pigeonhole on sets at the threshold: what each side needs of its blocks, rare ones first, meets its partner's."""
    g = np.random.default_rng(n)
    sets = []
    for _ in range(120 if n < 100 else 25):
        a = np.unique(g.integers(0, 2**63, n).astype(np.uint64))
        d = (len(a) * 2) // 7
        drop = g.integers(0, min(d, len(a) // 4) + 1)
        b = np.unique(np.concatenate((g.permutation(a)[drop:], g.integers(0, 2**63, max(0, min(d - drop, (len(a) - drop) // 3 if drop == 0 else len(a) // 7)) ).astype(np.uint64))))
        sets.append((a, b) if 100 * len(np.intersect1d(a, b)) >= 75 * len(np.union1d(a, b)) else (a, a))
    rows = [(2 * k + s, bytearray(np.sort(x).tobytes())) for k, p in enumerate(sets) for s, x in enumerate(p)]
    blocks = parity_join.block_keys(spark.createDataFrame(rows, "node long, tokens binary")).collect()
    of, count = {}, {}
    for r in blocks:
        of.setdefault((r["node"], r["side"]), []).append(r)
        count[r["key"]] = count.get(r["key"], 0) + 1
    kept = {}
    for (node, _), rs in of.items():
        shared = sorted((count[r["key"]], r["key"]) for r in rs if count[r["key"]] > 1)
        kept.setdefault(node, set()).update(k for _, k in shared[: rs[0]["need"] - (len(rs) - len(shared))])
    for k in range(len(sets)):
        assert kept.get(2 * k, set()) & kept.get(2 * k + 1, set()), len(sets[k][0])


def test_chunk_pairs_meet_across_chunks(spark, monkeypatch):
    monkeypatch.setattr(parity_join, "CHUNK", 8)
    tokens = np.arange(40, dtype=np.uint64)
    sets = [np.concatenate((tokens, np.array([100 + k], dtype=np.uint64))) for k in range(30)]
    rows = spark.createDataFrame([(5, 30, k, 41, k, bytearray(parity_join.parity_sketch(s))) for k, s in enumerate(sets)], "key long, g long, node long, n long, label long, sketch binary")
    assert parity_join.compared(rows).count() == 30 * 29 // 2


def test_component_rounds(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(40)] + [(100, 101)], "a long, b long")
    got = {r["node"]: r["label"] for r in components(edges).collect()}
    assert set(got.values()) == {0, 100} and len(got) == 43
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_one_of_each_group_stays(spark, odd):
    docs = frame(spark, odd)
    out = parity_join.near_duplicate_stage(spark, docs, SF)
    assert out.columns == docs.columns
    ids = sorted(r["doc_id"] for r in out.collect() if r["doc_id"] is not None)
    assert ids == [1, 2, 3, 4, 6, 7, 9] and out.where("doc_id is null").count() == 2
    named = docs.withColumn("row", F.lit(1)).withColumn("id", F.lit(2)).withColumn("n", F.lit(3)).withColumn("h", F.lit(4))
    again = parity_join.near_duplicate_stage(spark, named, SF)
    assert again.columns == named.columns and again.count() == out.count()
    assert parity_join.jaccard_components(docs.limit(0)).count() == 0 and parity_join.near_duplicate_stage(spark, docs.limit(0), SF).count() == 0


def test_empty_tables_and_long_texts(spark, odd):
    none = frame(spark, odd).limit(0)
    assert subword.encode_texts(none, subword.model_path()).count() == 0 and subword.decode_texts(subword.encode_texts(none, subword.model_path()), subword.model_path()).count() == 0
    labels = spark.createDataFrame([(9, 1, 1), (4, 1, 0)], "doc_id long, quality int, toxic int")
    assert toxicity.score_toxicity(none, toxicity.fit_toxicity(none, labels)).count() == 0
    model = toxicity.fit_toxicity(frame(spark, odd), labels)
    long = toxicity.score_toxicity(spark.createDataFrame([(1, prose(3, 400_000))], "doc_id long, text string"), model).first()
    assert 0 <= long["severity"] <= 3
    found = secret_scan.scan_versions(none.select(F.col("doc_id").alias("path"), "text"), secret_scan.BlobLedger(spark))
    assert found.count() == 0


# Line dedup


def brute_lines(rows, least=50):
    """Every run of `least` words or more that an earlier position starts too goes, found by comparing all positions."""
    texts = sorted((i, t) for i, t in rows if t)
    split = {i: t.split("\n") for i, t in texts}
    places = [(i, s) for i, _ in texts for s in range(len(split[i]))]
    cover = {i: [False] * len(split[i]) for i in split}
    at = {}
    for n, (i, s) in enumerate(places):
        a = split[i]
        for j, r in at.get(a[s], []):
            b, k = split[j], 0
            while s + k < len(a) and r + k < len(b) and a[s + k] == b[r + k]:
                k += 1
            if sum(len(x.split()) for x in a[s : s + k]) >= least:
                cover[i][s : s + k] = [True] * k
        at.setdefault(a[s], []).append((i, s))
    return {i: t if not t else "\n".join(x for x, c in zip(split[i], cover[i], strict=True) if not c) for i, t in rows}


def test_repeated_runs(spark):
    passage = "\n".join(prose(k, 9) for k in range(8))
    rows = [(1, prose(20) + "\n" + passage + "\n" + prose(21)), (2, prose(22) + "\n" + passage), (3, passage), (4, "\n".join(["same line here"] * 60)), (5, prose(20)), (6, None), (7, ""), (8, prose(23, 40)), (9, prose(23, 40)), (10, passage.replace("\n", "\n\n"))]
    out = line_dedup.dedup_lines(frame(spark, rows))
    got = {r["row"]["doc_id"]: r["row"] for r in out.collect()}
    want = brute_lines(rows)
    assert {k: r["text"] for k, r in got.items()} == want
    assert want[3] == "" and got[8]["text"] == got[9]["text"] and got[3]["n_chars"] == 0
    assert out.select("row.*").columns == frame(spark, rows).columns


def test_short_ends_of_runs_go_too(spark):
    """A run's last lines start no run of enough words themselves; they go with the run."""
    passage = "\n".join([prose(1, 49), "one", "two", "", "three"])
    rows = [(1, passage), (2, "own words\n" + passage + "\nmore of its own"), (3, passage + "\nend"), (4, "two\n\nthree")]
    got = {r["doc_id"]: r["text"] for r in line_dedup.line_dedup_stage(spark, frame(spark, rows), SF).collect()}
    assert got == brute_lines(rows) == {1: passage, 2: "own words\nmore of its own", 3: "end", 4: "two\n\nthree"}


@pytest.mark.parametrize("least", [1, 3, 8])
def test_random_lines_against_all_pairs_of_positions(spark, least):
    g = random.Random(least)
    rows = [(k, "\n".join(g.choice(["a", "b", "", "c d", "e f g"]) if g.random() < 0.9 else prose(g.randint(0, 99), 4) for _ in range(g.randint(1, 30)))) for k in range(25)]
    out = line_dedup.dedup_lines(frame(spark, rows), least).select("row.doc_id", "row.text", "removed").collect()
    assert {r["doc_id"]: r["text"] for r in out} == brute_lines(rows, least)


def test_line_dedup_keeps_columns_of_any_name(spark):
    docs = frame(spark, [(1, prose(1)), (2, prose(1))]).withColumn("row", F.lit(1)).withColumn("runs", F.lit("r")).withColumn("_doc", F.lit(2)).withColumn("removed", F.lit(3)).withColumn("a.b", F.lit(4))
    out = line_dedup.line_dedup_stage(spark, docs, SF)
    assert out.columns == docs.columns and sorted((r["doc_id"], r["text"], r["runs"], r["removed"], r["a.b"]) for r in out.collect()) == [(1, prose(1), "r", 3, 4), (2, "", "r", 3, 4)]


def test_line_dedup_of_odd_rows(spark, odd):
    out = line_dedup.line_dedup_stage(spark, frame(spark, odd), SF).collect()
    assert len(out) == len(odd)
    assert [r["text"] for r in out if r["doc_id"] == 5] == [""] and [r["text"] for r in out if r["doc_id"] == 1] == [None]
    assert line_dedup.dedup_lines(frame(spark, odd).limit(0)).count() == 0


# Toxicity


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    fold = F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(4)) == 0
    model = toxicity.fit_toxicity(docs, labels.where(~fold))
    assert list(model.thetas) == sorted(model.thetas)
    held = toxicity.score_toxicity(docs.join(labels.where(fold).select("doc_id"), "doc_id", "left_semi").select("doc_id", "text"), model).join(labels, "doc_id").collect()
    said = [(r["p_toxic"] >= model.reject, r["toxic"] == 1, r["severity"]) for r in held]
    hit = sum(a and b for a, b, _ in said)
    assert hit / sum(a for a, _, _ in said) >= 0.95 and hit / sum(b for _, b, _ in said) >= 0.6
    assert all(0 <= s <= 3 for _, _, s in said)


def test_fit_is_a_maximum_of_the_likelihood():
    g = np.random.default_rng(3)
    rows = [np.flatnonzero(g.random(6) < 0.4) for _ in range(3000)]
    true = np.array([2.0, -1.5, 1.0, 0.0, 0.5, -0.5])
    latent = np.array([true[r].sum() for r in rows]) + g.logistic(size=len(rows))
    grade = np.searchsorted([-0.5, 1.0, 2.5], latent)

    def likelihood(w, t):
        cum = 1 / (1 + np.exp(-(t[None, :] - np.array([w[r].sum() for r in rows])[:, None])))
        full = np.concatenate((np.zeros((len(rows), 1)), cum, np.ones((len(rows), 1))), axis=1)
        return np.log(full[np.arange(len(rows)), grade + 1] - full[np.arange(len(rows)), grade]).mean() - 1e-3 / 2 * (w**2).sum()

    w, t = toxicity.fit_ordinal(rows, grade.astype(np.int64), 6, rounds=600)
    assert np.abs(w - true).max() < 0.25 and np.abs(t - [-0.5, 1.0, 2.5]).max() < 0.25
    best = likelihood(w, t)
    for k in range(6):
        for d in (-0.05, 0.05):
            assert likelihood(w + d * (np.arange(6) == k), t) < best + 1e-6
    for k in range(3):
        for d in (-0.05, 0.05):
            assert likelihood(w, t + d * (np.arange(3) == k)) < best + 1e-6


def test_grades_rise_with_what_the_other_half_finds():
    g = np.random.default_rng(0)
    toxic = g.random(900) < 0.4
    strong = g.integers(0, 5, 900)
    rows = [np.concatenate((np.flatnonzero(g.random(4) < 0.5), 4 + g.permutation(6)[: s if x else 0])) for s, x in zip(strong, toxic, strict=True)]
    grade = toxicity.severity_grades(rows, toxic, 10)
    assert set(grade[~toxic]) == {0} and set(grade[toxic]) == {1, 2, 3}
    assert np.corrcoef(grade[toxic], strong[toxic])[0, 1] > 0.8


def test_toxicity_of_odd_rows(spark, odd):
    docs = frame(spark, odd)
    none = toxicity.fit_toxicity(docs, spark.createDataFrame([(4, 0, None), (None, 1, 1)], "doc_id long, quality int, toxic int"))
    out = toxicity.score_toxicity(docs, none).collect()
    assert len(out) == len(odd) and all(r["severity"] < 1e-6 for r in out)
    assert toxicity.score_toxicity(docs.limit(0), none).count() == 0


# Subwords


def brute_viterbi(p, text, lead=subword.MARK):
    t = lead + text.replace(" ", subword.MARK)
    best, back = [0.0], [None]
    for e in range(1, len(t) + 1):
        top, how = float("-inf"), None
        for a in range(max(0, e - p.longest), e):
            f = p.score.get(t[a:e])
            if f and best[a] + f[0] > top:
                top, how = best[a] + f[0], (a, [f[1]])
        if how is None:
            top, how = best[e - 1] + p.unknown, (e - 1, [p.bytes[x] for x in t[e - 1 : e].encode()])
        best.append(top)
        back.append(how)
    out, e = [], len(t)
    while e:
        out = back[e][1] + out
        e = back[e][0]
    return out


def test_subwords_round_trip():
    path = subword.model_path()
    p, enc, dec = subword.load(path), subword.Encoder(path), subword.Decoder(path)
    for t in [prose(1), "a  b", "  ", "\n\n x\ty", "日本語テキスト 😀😀 a", "x" * 400, "Ünïcödé, don't!", " lead", "trail "]:
        want = brute_viterbi(p, t)
        assert np.frombuffer(enc.encode(t), "<u4").tolist() == want, repr(t)
        walk = subword.StreamingViterbi(p)
        ids = walk.push(subword.MARK + t.replace(" ", subword.MARK))
        assert ids + walk.finish() == want and walk.held <= 4 * p.longest
        walk = subword.StreamingViterbi(p)
        ids = [k for c in subword.MARK + t.replace(" ", subword.MARK) for k in walk.push(c)]
        assert ids + walk.finish() == want
        assert dec.decode(enc.encode(t)) == t
    assert enc.encode("") == b"" and dec.decode(b"") == ""


def test_a_long_unbroken_text_is_committed_as_it_goes():
    p = subword.load(subword.model_path())
    walk, text, given, held = subword.StreamingViterbi(p), "ab" * 20_000 + "x" * 20_000 + "日本語" * 500, 0, 0
    for a in range(0, len(text), 100):
        given += len(walk.push(text[a : a + 100]))
        held = max(held, len(walk.text))
    assert given > 0 and held <= 8 * p.longest + 100


def test_random_pieces_against_the_whole_lattice():
    """A made-up vocabulary: overlapping pieces, tied scores, characters that no piece covers."""
    g = random.Random(8)
    for _ in range(30):
        p = subword.Pieces.__new__(subword.Pieces)
        names = {"".join(g.choice("abc") for _ in range(g.randint(1, 6))) for _ in range(12)}
        p.score = {n: (-float(g.randint(1, 9)), 300 + k) for k, n in enumerate(sorted(names))}
        p.bytes, p.longest, p.unknown = {k: k for k in range(256)}, max(map(len, names)), -50.0
        p.tree = subword.tree(p.score)
        for _ in range(20):
            t = "".join(g.choice("abcd") for _ in range(g.randint(1, 80)))
            walk = subword.StreamingViterbi(p)
            ids = [k for a in range(0, len(t), 7) for k in walk.push(t[a : a + 7])] + walk.finish()
            assert ids == brute_viterbi(p, t, "")


def test_subword_frames(spark, odd):
    docs, path = frame(spark, odd[:8]), subword.model_path()
    ids = subword.encode_texts(docs, path)
    back = sorted((r["doc_id"] or 0, r["text"]) for r in subword.decode_texts(ids, path).collect())
    assert back == sorted((i or 0, t or "") for i, t in odd[:8])

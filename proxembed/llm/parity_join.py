"""Jaccard join of shingle sets by parity sketches.

A document's set holds its distinct 5-word shingles. XOR-hashing a set into bits, each token flipping one bit, gives a
sketch whose Hamming distance to another never exceeds the size of the sets' symmetric difference. Two sets of sizes
a and b with Jaccard 0.75 or more differ in at most (a + b) / 7 tokens. So, in a band of sizes, sketches are cut into
more blocks than that: at least one block must agree (pigeonhole). A block here is the XOR of 64-bit token codes, that is
a long run of parity bits folded linearly; bands are powers of two from 4 on.

Blocks stand in one order for all sets, rare ones before frequent ones. If at most D blocks of a set differ from a
partner's, the first of the common blocks is among the first D + 1 of both, so those are all that need to meet. Blocks of a
set that no other set has are certain to differ and use up places. Empty blocks name nothing: where the tokens of a set
fall into D blocks or fewer, all of them may differ, and then the partner's are as few. Such sets meet again in sketches
of further seeds, until their tokens fall into enough blocks.

Steps, all exact:
1. One pass hashes texts: (doc_id, n_shingles, fingerprint of the set). Documents with equal sets are one class.
2. A class can have a partner only if enough of the smallest-hashed quarter (and a sixteenth) of its tokens occur in another
   class's same part. Unique keys are found with a partial min/max aggregate, so frequent shingles shrink before the shuffle.
3. Classes left emit their sketch blocks for their own band, and for the next one if a partner may lie there. Blocks that
   no other class has are counted; of the rest, only as many of the rarest as pigeonhole still needs join.
4. Each block's members are held against the one with the most shared blocks, verified on whole sets, and joined to components.
5. Blocks whose members lie in several components are compared in chunk pairs inside a kernel, by size and sketch
   distance, and only survivors leave it, to be verified. No group is expanded into rows for all its pairs.

Defined cases: null, empty and word-less texts have no shingles and link with nothing, not with each other; fewer than
five words are one shingle; rows without doc_id take no part in links (component null); repeated rows share a
component; extra columns are ignored; an empty table gives an empty result. Set identity rests on 64-bit fingerprints.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from proxembed.functions.rng import draw, draw_numpy
from proxembed.llm.common import forget, spread, store, table
from proxembed.llm.components import components
from proxembed.llm.textkernel import mix, shingle_sets, space_table, string_chunks, word_hashes

LEAST_TOP = 4
CHUNK = 2048
BLOCKS_PER_TOP, SMALL_BAND = 0.36, 256
FILTER_BITS, BITMAP_BITS, FILTER_STREAM = 1 << 26, 32_768, 101


def fingerprint(tokens: np.ndarray) -> int:
    """64 bits of a set, independent of order."""
    with np.errstate(over="ignore"):
        x = mix(tokens ^ np.uint64(0x51ED270B27D4EB4F))
        both = np.array([x.sum(dtype=np.uint64) + np.uint64(len(tokens)), np.bitwise_xor.reduce(x) if len(x) else np.uint64(0)])
        return int(mix(mix(both[:1]) ^ both[1:])[0].astype(np.int64))


def prefix_size(n: int) -> int:
    return min(n, n // 4 + 1 + n // 16)


def _sets(column: pa.Array) -> Iterator[tuple[int, np.ndarray]]:
    words = space_table()
    for first, data, offsets in string_chunks(column):
        for k, tokens in enumerate(shingle_sets(*word_hashes(data, offsets, words))):
            yield first + k, tokens


def set_meta(docs: DataFrame) -> DataFrame:
    """(doc_id, text) -> (doc_id, n, node), node the set's fingerprint."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [(len(t), fingerprint(t)) for _, t in _sets(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x[0] for x in found], pa.int64()), pa.array([x[1] for x in found], pa.int64())], names=["doc_id", "n", "node"])

    return docs.mapInArrow(run, "doc_id long, n long, node long")


def prefix_keys(docs: DataFrame) -> DataFrame:
    """(key, node) for the smallest-hashed part of each set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, nodes, held = [], [], 0
            for _, tokens in _sets(batch.column(1)):
                if len(tokens) < 3:
                    continue
                part = tokens[: prefix_size(len(tokens))]
                keys.append(part)
                nodes.append(np.full(len(part), fingerprint(tokens), dtype=np.int64))
                held += len(part)
                if held > 400_000:
                    yield _batch(["key", "node"], np.concatenate(keys).view(np.int64), np.concatenate(nodes))
                    keys, nodes, held = [], [], 0
            if keys:
                yield _batch(["key", "node"], np.concatenate(keys).view(np.int64), np.concatenate(nodes))

    return docs.mapInArrow(run, "key long, node long")


def _batch(names: list[str], *arrays: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x) for x in arrays], names=names)


def sketch_bits(n: int) -> int:
    """Bits of a set's stored sketch: a power of two of at least twice its size, enough that unlike sets stay far apart."""
    return max(256, 1 << (2 * n - 1).bit_length())


def parity_sketch(tokens: np.ndarray) -> bytes:
    bits = sketch_bits(len(tokens))
    counts = np.bincount((mix(tokens) & np.uint64(bits - 1)).astype(np.int64), minlength=bits)
    return np.packbits((counts & 1).astype(np.uint8), bitorder="little").tobytes()


def live_sets(texts: DataFrame) -> DataFrame:
    """(node, text) -> (node, n, tokens, sketch); a text whose set is not the node's (an id used twice) is left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            node = batch.column(0).to_pylist()
            rows = [(node[i], len(t), t.tobytes(), parity_sketch(t)) for i, t in _sets(batch.column(1)) if len(t) and fingerprint(t) == node[i]]
            cols = list(zip(*rows, strict=True)) or [[]] * 4
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.binary()), pa.array(cols[3], pa.binary())], names=["node", "n", "tokens", "sketch"])

    return texts.mapInArrow(run, "node long, n long, tokens binary, sketch binary")


def block_count(top: int) -> int:
    """Blocks of a sketch in the band of sizes below `top`: more than two sets of the band can differ in, and one a token in small bands."""
    return max(int(BLOCKS_PER_TOP * top), min(top, SMALL_BAND), 2 * (top - 1) // 7 + 1)


def _blocks(tokens: np.ndarray, top: int, seed: int) -> np.ndarray:
    """Keys of the blocks that hold tokens, in the sketch of a seed for the band of sizes below `top`."""
    with np.errstate(over="ignore"):
        code = mix(tokens ^ np.uint64(top + (seed << 40)))
        block = (code >> np.uint64(20)) % np.uint64(block_count(top))
        order = np.argsort(block, kind="stable")
        block, code = block[order], mix(code[order])
        first = np.flatnonzero(np.concatenate(([True], block[1:] != block[:-1])))
        folded = np.bitwise_xor.reduceat(code, first)
        return mix(folded ^ mix(block[first] + np.uint64(top << 32)))


#: A side is a band and a seed; two numbers share a long, for these rows are most of what is shuffled.
BLOCK_ROW = "node long, key long, need_made long, n_side long"


def block_keys(sets: DataFrame) -> DataFrame:
    """(node, side, need, made, n, key): `need` agreeing-or-unique blocks settle a side, `made` is how many blocks it has."""
    packed = sets.select("node", "tokens").mapInArrow(_block_rows, BLOCK_ROW)
    return unpacked(packed)


def unpacked(rows: DataFrame, *more: str) -> DataFrame:
    return rows.select("node", F.col("n_side").bitwiseAND(F.lit(255)).alias("side"), F.shiftright("need_made", 32).alias("need"), F.col("need_made").bitwiseAND(F.lit((1 << 32) - 1)).alias("made"), F.shiftright("n_side", 8).alias("n"), "key", *more)


def _block_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = [c.split()[0] for c in BLOCK_ROW.split(", ")]
    for batch in batches:
        out: list[list[np.ndarray]] = [[] for _ in names]
        held = 0
        for node, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            tokens = np.frombuffer(data.as_py(), dtype=np.uint64)
            n = len(tokens)
            top = max(LEAST_TOP, 1 << n.bit_length())
            bands = [(0, top, (n + min(4 * n // 3, top - 1)) // 7 + 1)]
            if 4 * n >= 3 * top:
                bands.append((1, 2 * top, (n + 4 * n // 3) // 7 + 1))
            for side, band, need in bands:
                m, seed = 0, 0
                while m < need:
                    keys = _blocks(tokens, band, seed)
                    m = len(keys)
                    out[0].append(np.full(m, node, dtype=np.int64))
                    out[1].append(keys.view(np.int64))
                    out[2].append(np.full(m, need << 32 | m, dtype=np.int64))
                    out[3].append(np.full(m, n << 8 | side + 2 * seed, dtype=np.int64))
                    held, seed = held + m, seed + 1
            if held > 200_000:
                yield _batch(names, *(np.concatenate(c) for c in out))
                out, held = [[] for _ in names], 0
        if held:
            yield _batch(names, *(np.concatenate(c) for c in out))


def verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The (a, b) pairs whose whole sets have Jaccard 0.75 or more."""
    tokens = sets.select("node", "tokens")
    both = pairs.join(tokens.select(F.col("node").alias("b"), F.col("tokens").alias("tb")), "b").join(tokens.select(F.col("node").alias("a"), F.col("tokens").alias("ta")), "a").select("a", "b", "ta", "tb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = np.frombuffer(x.as_py(), dtype=np.uint64), np.frombuffer(y.as_py(), dtype=np.uint64)
                z = np.sort(np.concatenate((x, y)), kind="stable")
                same = int((z[1:] == z[:-1]).sum())
                keep.append(100 * same >= 75 * (len(z) - same))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return both.mapInArrow(run, "a long, b long")


def _near(x: pd.DataFrame) -> list[tuple[int, int]]:
    """Pairs of a chunk pair, across components, that sizes and sketch distance leave."""
    ci, cj = x["ci"].iloc[0], x["cj"].iloc[0]
    left, right = (np.flatnonzero((x["chunk"] == c).to_numpy()) for c in (ci, cj))
    n, label, node = x["n"].to_numpy(), x["label"].to_numpy(), x["node"].to_numpy()
    a, b = n[left][:, None], n[right][None, :]
    ok = (label[left][:, None] != label[right][None, :]) & (4 * np.minimum(a, b) >= 3 * np.maximum(a, b))
    if ci == cj:
        ok &= np.triu(np.ones(ok.shape, dtype=bool), 1)
    i, j = np.nonzero(ok)
    i, j = left[i], right[j]
    sketches = [np.frombuffer(s, dtype=np.uint64) for s in x["sketch"]]
    size = np.array([len(s) for s in sketches])
    out = []
    for words in np.unique(np.minimum(size[i], size[j])).tolist() if len(i) else []:
        own = np.flatnonzero((size == words) | (size == 2 * words))
        at = np.full(len(x), -1)
        at[own] = np.arange(len(own))
        table = np.stack([s if len(s) == words else s[:words] ^ s[words:] for s in (sketches[k] for k in own)])
        pick = np.flatnonzero(np.minimum(size[i], size[j]) == words)
        step = max(1, 4_000_000 // words)
        for p in range(0, len(pick), step):
            q = pick[p : p + step]
            apart = np.bitwise_count(table[at[i[q]]] ^ table[at[j[q]]]).sum(axis=1, dtype=np.int64)
            q = q[7 * apart <= n[i[q]] + n[j[q]]]
            out += zip(np.minimum(node[i[q]], node[j[q]]).tolist(), np.maximum(node[i[q]], node[j[q]]).tolist(), strict=True)
    return out


def compared(rows: DataFrame) -> DataFrame:
    """(key, g, node, n, label, sketch), g rows a key -> distinct (a, b) across labels that may link."""
    chunks = F.ceil(F.col("g") / CHUNK).cast("long")
    dealt = rows.withColumn("k", chunks).withColumn("chunk", F.pmod(F.xxhash64("node"), F.col("k")))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("k") - 1)))
    dealt = dealt.withColumn("ci", F.least("chunk", "other")).withColumn("cj", F.greatest("chunk", "other"))
    buckets = max(8, rows.count() // 4000)
    dealt = dealt.withColumn("bucket", F.pmod(F.xxhash64("key", "ci", "cj"), F.lit(buckets)))

    def run(x: pd.DataFrame) -> pd.DataFrame:
        found: set[tuple[int, int]] = set()
        for _, part in x.groupby(["key", "ci", "cj"], sort=False):
            found.update(_near(part))
        return pd.DataFrame(sorted(found), columns=["a", "b"], dtype="int64")

    return dealt.select("bucket", "key", "ci", "cj", "chunk", "node", "n", "label", "sketch").groupBy("bucket").applyInPandas(run, "a long, b long").distinct()


def id_filter(ids: DataFrame, column: str) -> np.ndarray:
    """A bit table of FILTER_BITS bits that holds every id: 8 MB whatever the number of ids, so it may travel.

    Ids outside may pass, for bits are shared; what passes is joined on the id anyway.
    """
    bit = ids.select((draw(1, FILTER_STREAM, column) % FILTER_BITS).alias("bit"))
    rows = bit.groupBy(F.expr(f"bit div {BITMAP_BITS}").alias("bucket")).agg(F.bitmap_construct_agg(F.expr(f"bit % {BITMAP_BITS}")).alias("bits")).collect()  # FILTER_BITS in all
    out = np.zeros(FILTER_BITS // 8, dtype=np.uint8)
    for r in rows:
        part = np.frombuffer(bytes(r["bits"]), dtype=np.uint8)
        out[r["bucket"] * BITMAP_BITS // 8 : r["bucket"] * BITMAP_BITS // 8 + len(part)] = part
    return out


def passing(texts: DataFrame, bits: np.ndarray) -> DataFrame:
    """(doc_id, text) rows whose id the filter may hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = draw_numpy(1, FILTER_STREAM, batch.column(0).to_numpy(zero_copy_only=False)) % FILTER_BITS
            yield batch.filter(pa.array((bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1))

    return texts.mapInArrow(run, "doc_id long, text string")


def jaccard_components(docs: DataFrame) -> DataFrame:
    """(doc_id, text) -> (doc_id, n_shingles, component_id), a row for each input row."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    dealt = spread(texts)
    meta = store(set_meta(dealt), "set-meta")
    keys = prefix_keys(dealt.where("doc_id is not null and text is not null"))
    unique = keys.groupBy("key").agg(F.min("node").alias("node"), F.max("node").alias("last")).where("node = last").groupBy("node").agg(F.count("*").alias("unique"))
    classes = meta.where("n > 0 and doc_id is not null").groupBy("node").agg(F.min("doc_id").alias("rep"), F.max("n").alias("n"))
    n = F.col("n")
    prefix = F.least(n, F.floor(n / 4) + 1 + F.floor(n / 16))
    least = 1 + F.floor(F.ceil(n * 3 / 4) / 16)
    live = classes.where("n >= 3").join(unique, "node", "left").where(prefix - F.coalesce("unique", F.lit(0)) >= F.least(prefix, least)).select("node", "rep")
    live = store(live, "live")
    # Rows that repeat an id and text count once; the join's partitioning serves that too.
    fetched = passing(texts.where("doc_id is not null"), id_filter(live, "rep")).join(live, F.col("doc_id") == F.col("rep")).withColumn("_h", F.xxhash64("text")).dropDuplicates(["doc_id", "node", "_h"])
    sets = store(live_sets(fetched.select("node", "text")), "live-sets")
    forget(live)
    blocks = sets.select("node", "tokens").mapInArrow(_block_rows, BLOCK_ROW)
    counts = blocks.groupBy("key").agg(F.count("*").alias("c")).where("c > 1")
    shared = unpacked(blocks.join(counts, "key"), "c")
    side = Window.partitionBy("node", "side")
    kept = shared.withColumn("have", F.count("*").over(side)).withColumn("rank", F.row_number().over(side.orderBy("c", "key")))
    kept = store(kept.where("rank <= need - (made - have)").select("key", "node", "n", "have"), "blocks")
    fits = lambda x, y: (4 * F.least(x, y) >= 3 * F.greatest(x, y))
    # The member with the most shared blocks: the least edited of near copies, and the same one for most of their blocks.
    centers = kept.groupBy("key").agg(F.max(F.struct("have", "node", "n")).alias("c")).select("key", F.col("c.node").alias("a"), F.col("c.n").alias("na"))
    stars = kept.join(centers, "key").where((F.col("node") != F.col("a")) & fits(F.col("n"), F.col("na"))).select("a", F.col("node").alias("b")).distinct()
    links = store(verified(stars, sets), "links")
    labels = components(links)
    labelled = kept.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    # Blocks with the same members count once: a fingerprint of the members names them.
    members = (F.bit_xor(F.xxhash64("node")).alias("x"), F.sum(F.pmod(F.xxhash64("node", F.lit(1)), F.lit(1 << 31))).alias("y"))
    mixed = labelled.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.count("*").alias("g"), *members).where("lo <> hi")
    mixed = mixed.groupBy("g", "x", "y").agg(F.min("key").alias("key")).select("key", "g")
    rest = store(labelled.join(mixed, "key").join(sets.select("node", "sketch"), "node").select("key", "g", "node", "n", "label", "sketch"), "mixed-blocks")
    if not rest.isEmpty():
        more = verified(compared(rest), sets)
        joined = more.join(labels.select(F.col("node").alias("a"), F.col("label").alias("la")), "a", "left").join(labels.select(F.col("node").alias("b"), F.col("label").alias("lb")), "b", "left")
        merges = store(joined.select(F.coalesce("la", "a").alias("a"), F.coalesce("lb", "b").alias("b")).distinct(), "merges")
        roots = components(merges)
        known = labels.unionByName(merges.select(F.explode(F.array("a", "b")).alias("node")).distinct().join(labels, "node", "left_anti").withColumn("label", F.col("node")))
        labels = known.join(roots.select(F.col("node").alias("label"), F.col("label").alias("root")), "label", "left").select("node", F.coalesce("root", "label").alias("label"))
    grouped = store(classes.select("node", "rep").join(labels, "node", "left").withColumn("label", F.coalesce("label", "node")), "classes")
    smallest = grouped.groupBy("label").agg(F.min("rep").alias("component_id"))
    named = grouped.join(smallest, "label").select("node", "component_id")
    out = meta.join(named, "node", "left")
    component = F.when(F.col("doc_id").isNull(), F.lit(None)).when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component_id"))
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.cast("long").alias("component_id"))


def op4_parity_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(table(spark, sf_dir, "documents"))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component stays: the one with the smallest id. Rows without id stay.

    Of rows equal in id and text one stays; rows that share an id but not the text are told apart by their text, and all of
    those stay whose id is the smallest of their component.
    """
    names = docs.columns
    row = F.struct(*[F.col(f"`{c}`") for c in names]).alias("row")
    keyed = docs.select(F.col("doc_id").cast("long").alias("id"), row)
    stays = jaccard_components(docs).where("doc_id = component_id").groupBy(F.col("doc_id").alias("id")).agg(F.count("*").alias("n"))
    kept = keyed.join(stays, "id")
    once = kept.where("n = 1").select("row")
    again = kept.where("n > 1").withColumn("h", F.xxhash64("row.text")).groupBy("id", "h").agg(F.first("row").alias("row")).select("row")
    return once.unionByName(again).unionByName(keyed.where("id is null").select("row")).select("row.*")

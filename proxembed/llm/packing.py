"""Best-fit packing by exact-complement hashing.

Token counts are what packing depends on, and a sequence of C tokens admits C different counts at most. The plan is
made from the histogram of counts (C rows, whatever the corpus holds). An index holds, for each sum up to C, how many
single counts, pairs and triples of available counts make it; it is brought up to date when a count is used up. The longest
open piece looks up its gap: one count, else a pair, else a triple that fills it exactly, as often as availability allows
(a combination that needs a count twice needs two of it). All combinations of an indexed sum are tried before the gap counts as
having none; what has no exact complement is packed best-fit, again by count. Each step uses up at least one count, so
the plan has a few thousand lines at most. Pieces find their place by their rank among pieces of equal length; ranks come
from per-bucket counts and a prefix sum, so a length that a third of all rows share is dealt over many tasks.

Defined cases: null and empty texts are one separator token; repeated rows are packed once each; null ids stay null;
extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from proxembed.llm.common import spread, store, table

CAPACITY = 2048
SEPARATOR = 0
CACHE_ENTRIES = 400_000
TOKENIZER = "byte_bpe_50k"


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@lru_cache(maxsize=2)
def _encoders(name: str):
    """The library's tokenizer, and the same vocabulary as ranks, which gives equal ids faster (tested)."""
    import base64

    import public_tokenizers
    import tiktoken
    from tokenizers import Tokenizer

    with open(tokenizer_path(f"{name}.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    quick = tiktoken.Encoding(name, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    return Tokenizer.from_file(tokenizer_path(f"{name}.json")), quick


class SpanEncoder:
    """Ids of whole texts as packed little-endian 32-bit words, from a bounded memo of spans.

    The tokenizer's pattern never joins what stands before a single space to what follows it, so a text is cut before
    each space that a non-space follows, and each span is encoded once while the memo holds it. Texts that hold a
    special token's string go to the library's tokenizer whole.
    """

    def __init__(self, name: str = TOKENIZER):
        self.full, self.quick = _encoders(name)
        self.memo: dict[str, bytes] = {}
        self.special = [t.content for t in self.full.get_added_tokens_decoder().values()]

    def _spans(self, text: str) -> list[str]:
        parts = text.split(" ")
        if len(parts) == 1:
            return parts
        if "" in parts or any(p[0].isspace() for p in parts[1:]):
            out = [parts[0]]
            for p in parts[1:]:
                if p and not p[0].isspace():
                    out.append(" " + p)
                else:
                    out[-1] += " " + p
            return out
        return (parts[0] + "\x00 " + "\x00 ".join(parts[1:])).split("\x00") if "\x00" not in text else [parts[0], *(" " + p for p in parts[1:])]

    def encode(self, text: str) -> bytes:
        if any(s in text for s in self.special):
            return np.array(self.full.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()
        spans, memo = self._spans(text), self.memo
        try:
            return b"".join(map(memo.__getitem__, spans))
        except KeyError:
            pass
        if len(memo) > CACHE_ENTRIES:
            memo.clear()
        encode = self.quick.encode_ordinary
        get = memo.get
        out = []
        for s in spans:
            v = get(s)
            if v is None:
                v = np.array(encode(s), dtype="<u4").tobytes()
                if len(s) <= 64:
                    memo[s] = v
            out.append(v)
        return b"".join(out)


@lru_cache(maxsize=2)
def span_encoder(name: str) -> SpanEncoder:
    """One encoder a worker process, so its memo outlives a task."""
    return SpanEncoder(name)


def pieces(docs: DataFrame, capacity: int = CAPACITY, name: str = TOKENIZER) -> DataFrame:
    """(doc_id, text) -> (doc_id, piece, start, length, ids_crc32); only documents over `capacity` are cut, the first piece is the short one."""
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, end = span_encoder(name), np.array([SEPARATOR], dtype="<u4").tobytes()
        for batch in batches:
            ids, text = batch.column(0).to_pylist(), batch.column(1)
            rows: list[tuple] = []
            for i, t in zip(ids, text, strict=True):
                data = encoder.encode(t.as_py() or "") + end
                n = len(data) // 4
                cut = [0, *range(n % capacity or capacity, n + 1, capacity)] if n > capacity else [0, n]
                for k, (a, b) in enumerate(zip(cut, cut[1:], strict=False)):
                    rows.append((i, k, a, b - a, zlib.crc32(data[4 * a : 4 * b])))
            cols = list(zip(*rows, strict=True)) or [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), *(pa.array(c, pa.int64()) for c in cols[2:])],
                                             names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return spread(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))).mapInArrow(run, schema)


class SumIndex:
    """How many of the available counts, ordered pairs and ordered triples of them make each sum up to the capacity."""

    def __init__(self, have: np.ndarray):
        self.have = have
        self.single = (have > 0).astype(np.int64)
        n = len(have)
        self.pair, self.triple = np.zeros(n, dtype=np.int64), np.zeros(n, dtype=np.int64)
        for x in np.flatnonzero(self.single).tolist():
            self.pair[x:] += self.single[: n - x]
        for x in np.flatnonzero(self.single).tolist():
            self.triple[x:] += self.pair[: n - x]

    def use(self, x: int, k: int) -> None:
        """Take k of count x; once it is used up, no indexed sum rests on it (inclusion and exclusion of x once, twice, thrice)."""
        self.have[x] -= k
        if self.have[x]:
            return
        n = len(self.have)

        def minus(table: np.ndarray, other: np.ndarray | None, shift: int, times: int) -> None:
            if shift < n:
                if other is None:
                    table[shift] -= times
                else:
                    table[shift:] -= times * other[: n - shift]

        minus(self.triple, self.pair, x, 3)
        minus(self.triple, self.single, 2 * x, -3)
        minus(self.triple, None, 3 * x, 1)
        minus(self.pair, self.single, x, 2)
        minus(self.pair, None, 2 * x, -1)
        self.single[x] = 0

    def pair_for(self, total: int, taken: tuple[int, ...]) -> tuple[int, int] | None:
        """Two counts that make `total`, the most even ones, besides those `taken`."""
        if total < 2 or not self.pair[total]:
            return None
        low = np.arange(1, total // 2 + 1)
        need_low = 1 + (low * 2 == total) + sum((low == t).astype(np.int64) for t in taken)
        need_high = 1 + (low * 2 == total) + sum((total - low == t).astype(np.int64) for t in taken)
        found = np.flatnonzero((self.have[low] >= need_low) & (self.have[total - low] >= need_high))
        return (total - int(low[found[-1]]), int(low[found[-1]])) if len(found) else None

    def complement(self, length: int, gap: int) -> tuple[int, ...] | None:
        """Up to three available counts besides one of `length` that fill the gap exactly, largest first; None if there are none."""
        if not gap:
            return ()
        if self.have[gap] > (gap == length):
            return (gap,)
        pair = self.pair_for(gap, (length,))
        if pair or not self.triple[gap]:
            return pair
        # The largest member of a triple is a third of the gap at least, and its rest an indexed pair sum.
        most = np.arange(gap - 2, -(-gap // 3) - 1, -1)
        for x in most[(self.single[most] > 0) & (self.pair[gap - most] > 0)].tolist():
            if self.have[x] > (x == length):
                rest = self.pair_for(gap - x, (length, x))
                if rest:
                    return tuple(sorted((x, *rest), reverse=True))
        return None


def plan_sequences(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    """Patterns (lengths, longest first) with multiplicities that use up `counts` exactly."""
    have = np.zeros(capacity + 1, dtype=np.int64)
    for length, n in counts.items():
        have[length] += n
    index, plan = SumIndex(have), []

    def take(pattern: tuple[int, ...]) -> None:
        uses = Counter(pattern)
        times = min(int(have[x]) // k for x, k in uses.items())
        plan.append((pattern, times))
        for x, k in uses.items():
            index.use(x, k * times)

    for length in range(capacity, 0, -1):
        while have[length]:
            rest = index.complement(length, capacity - length)
            if rest is None:
                break
            take((length, *rest))
    for length in range(capacity, 0, -1):
        while have[length]:
            left, pattern, gap = have.copy(), [length], capacity - length
            left[length] -= 1
            while gap:
                fits = np.flatnonzero(left[: gap + 1])
                if not len(fits):
                    break
                pattern.append(int(fits[-1]))
                left[pattern[-1]] -= 1
                gap -= pattern[-1]
            take(tuple(pattern))
    return plan


def _slots(plan: list[tuple[tuple[int, ...], int]], capacity: int) -> dict[str, np.ndarray]:
    """For each length and pattern place: the first rank it serves, how many, the first sequence and the offset."""
    rows, sequence = [], 0
    for pattern, times in plan:
        offset = 0
        for length in pattern:
            rows.append((length, times, sequence, offset))
            offset += length
        sequence += times
    x = np.array(rows or np.zeros((0, 4)), dtype=np.int64)
    x = x[np.argsort(x[:, 0], kind="stable")]
    total = np.concatenate(([0], np.cumsum(x[:, 1])))[:-1]
    first = np.searchsorted(x[:, 0], np.arange(capacity + 2))
    base = np.concatenate((total, [total[-1] + x[-1, 1] if len(x) else 0]))
    return {"start": total, "sequence": x[:, 2], "offset": x[:, 3], "base": base[first]}


def pack(found: DataFrame, capacity: int = CAPACITY, rows_per_bucket: int = 2_000) -> DataFrame:
    """Adds sequence_id and offset to stored (doc_id, piece, length, ...) rows; `found` must be stored, it is read twice."""
    histogram = {int(r["length"]): int(r["n"]) for r in found.groupBy("length").agg(F.count("*").alias("n")).collect()}  # capacity rows at most
    slots = _slots(plan_sequences(histogram, capacity), capacity)
    buckets = max(1, sum(histogram.values()) // rows_per_bucket)
    salted = found.withColumn("_b", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(buckets)))
    counts = salted.groupBy("length", "_b").agg(F.count("*").alias("_n"))
    before = counts.withColumn("_o", F.sum("_n").over(Window.partitionBy("length").orderBy("_b").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_n"))
    order = Window.partitionBy("length", "_b").orderBy("doc_id", "piece", "ids_crc32")
    ranked = salted.withColumn("_r", F.row_number().over(order)).join(before.select("length", "_b", "_o"), ["length", "_b"])
    ranked = ranked.withColumn("_r", F.col("_r") + F.col("_o") - 1).drop("_b", "_o")
    names = [c for c in ranked.columns if c != "_r"]
    kind = StructType([*(ranked.schema[c] for c in names), StructField("sequence_id", LongType()), StructField("offset", LongType())])
    length_at = names.index("length")

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            at = slots["base"][x.column(length_at).to_numpy()] + x.column(len(names)).to_numpy()
            slot = np.searchsorted(slots["start"], at, side="right") - 1
            yield pa.RecordBatch.from_arrays([*(x.column(k) for k in range(len(names))), pa.array(slots["sequence"][slot] + at - slots["start"][slot]), pa.array(slots["offset"][slot])], names=kind.names)

    return ranked.select(*names, "_r").mapInArrow(place, kind)


def op3_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(store(pieces(table(spark, sf_dir, "documents")), "pieces")).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(store(pieces(docs), "pieces")).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")

"""Line dedup by prefix doubling over line-ID sequences.

Lines get 64-bit ids. Ranks of runs of 1, 2, 4, ... lines follow by doubling: a run of 2k lines is the pair of its halves'
ranks; pairs that occur once are dropped (no longer run can repeat through them), the others are sorted over range
partitions and numbered in order. A level is thus a suffix array cut at that depth, without the suffixes that no other
shares, and its longest-common-prefix intervals are the positions of equal rank; an interval of any depth between two
levels is the pair of the two overlapping ranks that span it.

A run is deleted where it holds `min_words` words or more and an earlier position starts the same run. Two depths a position
suffice for that: the fewest lines from it that hold `min_words` words, and the fewest lines up to it. In a repeated run of
that many words each line either starts such a shortest run that still fits, or lies in the shortest run that ends with the
repeated one; so the union of both is the union of all maximal repeated runs, and doubling ends at the longest shortest run
(or where nothing repeats any more). `repeated_runs` gives the merged spans. `min_words` of 1 deletes every repeated line.

Tables of counts are stored before they join, so that the join's own shuffle can be split where one line, or run, is hot;
joins are merges by hint, for small tables would be broadcast through the driver, level after level.

Defined cases: null text stays null, empty text stays empty; the first copy in order of (doc_id, nulls first, hash of
the text, line) stays; rows equal in id and text are one document (one position in that order) and are treated alike; lines
are split at \\n and joined by \\n; n_chars, where there is one, is recounted for changed texts; an empty table gives an
empty result. Rows travel as one struct, so no column's name can clash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from proxembed.llm.common import forget, spread, store, table

MIN_WORDS = 50


def lines_of(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(doc, text) -> (doc, at, line, ahead, behind): 64-bit line id, the fewest lines from here and the fewest up to here with `min_words` words (0: never)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        digest = xxhash.xxh3_64_intdigest
        for batch in batches:
            out: list[list[np.ndarray]] = [[], [], [], [], []]
            for k, text in enumerate(batch.column(1)):
                lines = (text.as_py() or "").split("\n")
                n = len(lines)
                at = np.arange(n)
                words = np.concatenate(([0], np.cumsum([len(x.split()) for x in lines])))
                ahead = np.searchsorted(words, words[:-1] + min_words) - at
                ahead[words[:-1] + min_words > words[-1]] = 0
                behind = at + 2 - np.searchsorted(words, words[1:] - min_words, side="right")
                behind[words[1:] < min_words] = 0
                ids = np.array([digest(x.encode("utf-8", "surrogatepass")) for x in lines], dtype=np.uint64).view(np.int64)
                for column, values in zip(out, (np.full(n, k), at, ids, ahead, behind), strict=True):
                    column.append(values.astype(np.int64))
            if out[0]:
                row, *rest = (pa.array(np.concatenate(c)) for c in out)
                yield pa.RecordBatch.from_arrays([batch.column(0).take(row), *rest], names=["doc", "at", "line", "ahead", "behind"])

    return docs.mapInArrow(run, "doc struct<id:long,hash:long>, at long, line long, ahead long, behind long")


def _numbered(rows: DataFrame, key: list[str]) -> DataFrame:
    """Keys that occur more than once -> (*key, rank), ranks growing in the keys' order over range partitions. Counts are partial before their shuffle."""
    many = rows.groupBy(*key).agg(F.count("*").alias("_c")).where("_c > 1").drop("_c")
    return store(many.repartitionByRange(*key).sortWithinPartitions(*key).withColumn("rank", F.monotonically_increasing_id()), "ranks")


def _later(runs: DataFrame, ranks: DataFrame, width: int) -> DataFrame:
    """Those of (doc, at, span), spans from `width` to under twice that, which an earlier position starts too."""
    head = runs.join(ranks.select("doc", "at", F.col("rank").alias("r1")).hint("merge"), ["doc", "at"])
    tail = ranks.select("doc", F.col("at").alias("tail"), F.col("rank").alias("r2"))
    named = store(head.withColumn("tail", F.col("at") + F.col("span") - width).join(tail.hint("merge"), ["doc", "tail"]).select("doc", "at", "span", "r1", "r2"), "intervals")
    place = F.struct("doc", "at")
    first = store(named.groupBy("span", "r1", "r2").agg(F.min(place).alias("first"), F.count("*").alias("_c")).where("_c > 1").drop("_c"), "first")
    found = store(named.join(first.hint("merge"), ["span", "r1", "r2"]).where(F.col("first") < place).select("doc", "at", "span"), "later")
    forget(named, first)
    return found


def later_spans(lines: DataFrame) -> list[DataFrame]:
    """Stored lines -> tables of (doc, at, span): shortest runs that an earlier position starts too, a table a level."""
    numbers = _numbered(lines.dropDuplicates(["doc", "at"]), ["line"])
    level = lines.join(numbers.hint("merge"), "line")
    # Rows equal in id and text give a position twice; the ends of a row are its own, so one of each stays.
    level = store(level.groupBy("doc", "at").agg(F.min("rank").alias("rank"), F.min("ahead").alias("ahead"), F.min("behind").alias("behind")), "repeated-lines")
    forget(numbers)
    ends = F.array(F.struct("at", F.col("ahead").alias("span")), F.struct((F.col("at") - F.col("behind") + 1).alias("at"), F.col("behind").alias("span")))
    runs = store(level.select("doc", F.explode(ends).alias("e")).select("doc", "e.*").where("span > 0").distinct(), "runs")
    longest = runs.agg(F.max("span")).first()[0] or 0
    ranks, found, width = level.select("doc", "at", "rank"), [], 1
    held = [level, runs]
    while width <= longest:
        found.append(_later(runs.where(f"span >= {width} and span < {2 * width}"), ranks, width))
        if 2 * width > longest:
            break
        second = ranks.select("doc", (F.col("at") - width).alias("at"), F.col("rank").alias("second"))
        pairs = store(ranks.withColumnRenamed("rank", "first").join(second.hint("merge"), ["doc", "at"]), "pairs")
        numbers = _numbered(pairs, ["first", "second"])
        after = store(pairs.join(numbers.hint("merge"), ["first", "second"]).select("doc", "at", "rank"), "doubled")
        forget(pairs, numbers)
        held.append(after)
        ranks = after
        width *= 2
        if ranks.isEmpty():
            break
    forget(*held)
    return found


def repeated_runs(lines: DataFrame) -> DataFrame:
    """Stored lines -> (doc, runs): the line ranges [a, b) that go from each document, in order, merged where they meet."""
    found = later_spans(lines)
    if not found:
        return lines.limit(0).select("doc", F.array(F.struct(F.col("at").alias("a"), F.col("at").alias("b"))).alias("runs"))
    spans = found[0]
    for x in found[1:]:
        spans = spans.unionByName(x)
    spans = spans.select("doc", F.col("at").alias("a"), (F.col("at") + F.col("span")).alias("b"))
    before = Window.partitionBy("doc").orderBy("a", "b")
    reach = F.max("b").over(before.rowsBetween(Window.unboundedPreceding, -1))
    island = spans.withColumn("fresh", F.when(reach >= F.col("a"), 0).otherwise(1)).withColumn("island", F.sum("fresh").over(before.rowsBetween(Window.unboundedPreceding, 0)))
    merged = island.groupBy("doc", "island").agg(F.min("a").alias("a"), F.max("b").alias("b"))
    out = store(merged.groupBy("doc").agg(F.array_sort(F.collect_list(F.struct("a", "b"))).alias("runs")), "merged-runs")
    forget(*found)
    return out


def _cut_text(text: str, spans: list[dict[str, int]]) -> str:
    """A text without the lines of its runs."""
    lines, at, kept = text.split("\n"), 0, []
    for r in spans:
        kept += lines[at : r["a"]]
        at = r["b"]
    return "\n".join(kept + lines[at:])


def dedup_lines(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(row, removed): the rows of `docs` as structs with `text` cut (and n_chars recounted), and how many lines went."""
    names = docs.columns
    row = F.struct(*[F.col(f"`{c}`") for c in names]).alias("row")
    keyed = docs.select(F.struct(F.col("doc_id").cast("long").alias("id"), F.xxhash64("text").alias("hash")).alias("doc"), row)
    texts = keyed.select("doc", F.col("row.text").alias("text")).where("text is not null and text <> ''")
    lines = store(lines_of(spread(texts), min_words), "lines")
    runs = repeated_runs(lines)
    forget(lines)
    joined = keyed.join(runs.hint("merge"), "doc", "left").select("row", "runs")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, spans = batch.column(0), batch.column(1)
            hit = pc.is_valid(spans)
            some = spans.filter(hit).to_pylist()
            removed = np.zeros(batch.num_rows, dtype=np.int64)
            if some:
                fields = rows.flatten()
                text = [_cut_text(t, s) for t, s in zip(fields[names.index("text")].filter(hit).to_pylist(), some, strict=True)]
                for name, new in (("text", text), ("n_chars", [len(t) for t in text])):
                    if name in names:
                        k = names.index(name)
                        fields[k] = pc.replace_with_mask(fields[k], hit, pa.array(new).cast(fields[k].type))
                rows = pa.StructArray.from_arrays(fields, fields=list(rows.type))
                removed[hit.to_numpy(zero_copy_only=False)] = [sum(r["b"] - r["a"] for r in s) for s in some]
            yield pa.RecordBatch.from_arrays([rows, pa.array(removed)], names=["row", "removed"])

    return joined.mapInArrow(run, StructType([joined.schema["row"], StructField("removed", LongType())]))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dedup_lines(table(spark, sf_dir, "documents"))
    text = F.col("row.text")
    return out.select("row.doc_id", text, F.length(F.coalesce(text, F.lit(""))).cast("long").alias("n_chars"), F.col("removed").alias("lines_removed"))


def line_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return dedup_lines(docs).select("row.*")

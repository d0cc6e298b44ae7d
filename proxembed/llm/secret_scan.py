"""Incremental blob ledger for secret scans, in DataFrame functions alone.

Every historical version of a file is named by the SHA-256 of its text. Only pairs of blob and rule version that the
ledger does not hold are scanned, one copy of each blob; findings join back to every path by content address.

Defined cases: a null text is the empty blob; rows that repeat are versions of their own with equal findings; a null
path stays null; extra columns are ignored; an empty table gives an empty result. Spans are code points, end exclusive.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from proxembed.llm.common import fresh_path, store, table


@dataclass(frozen=True)
class Rule:
    """A kind of secret: pattern, and the fewest characters that `group` of a match needs."""

    kind: str
    pattern: str
    group: int
    least: int
    base: bool = True
    revision: int = 1

    @property
    def version(self) -> str:
        return f"{self.kind}@{self.revision}"


# The base patterns, then one kind more.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"(AKIA[A-Z0-9]+)"
HEX = r"([0-9a-f]{24,}+)"
PEM = r"(-----BEGIN [A-Z ]*PRIVATE KEY-----[A-Za-z0-9+/=\s]*(?:-----END [A-Z ]*PRIVATE KEY-----)?)"
RULES = (Rule("assign", ASSIGN, 2, 6), Rule("access", ACCESS, 1, 20), Rule("hex", HEX, 1, 24), Rule("pem", PEM, 1, 40, base=False))

_MARK = "\u0001"
FINDING = "array<struct<start:bigint,rank:int,kind:string,end:bigint>>"


class BlobLedger:
    """Stored (blob, rule_version, spans) rows under one folder; a scan appends the pairs it did."""

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path, self.written = spark, path or fresh_path(spark, "ledger"), path is not None

    def read(self) -> DataFrame | None:
        if not self.written:
            return None
        return self.spark.read.schema(f"blob string, rule_version string, spans {FINDING}").parquet(self.path)

    def append(self, rows: DataFrame) -> None:
        rows.write.mode("append").parquet(self.path)
        self.written = True


def blob_of(text: Column) -> Column:
    return F.sha2(F.coalesce(text, F.lit("")), 256)


def _pieces(text: Column, rule: Rule) -> Column:
    """The text cut at both ends of each match: odd entries are matches. The mark is taken out of the text first."""
    return F.split(F.regexp_replace(text, rule.pattern, f"{_MARK}$0{_MARK}"), _MARK)


def find_spans(blobs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(blob, text, kinds) -> (blob, rule_version, spans), a row for each blob and wanted kind, spans in order of start."""
    clean = F.translate("text", _MARK, "\u0002")
    cut = blobs.select(
        "blob",
        F.explode(
            F.array(*[
                F.struct(F.lit(rank).alias("rank"), F.lit(rule.kind).alias("kind"), F.lit(rule.version).alias("rule_version"),
                         F.when(F.array_contains("kinds", rule.kind), F.when(clean.rlike(rule.pattern), _pieces(clean, rule)).otherwise(F.array())).alias("parts"))
                for rank, rule in enumerate(rules)
            ])
        ).alias("c"),
    ).where(F.col("c.parts").isNotNull()).select("blob", "c.*")
    rows = cut.select("blob", "rank", "kind", "rule_version", F.posexplode_outer("parts").alias("at", "part"))
    valid = F.lit(False)
    for rank, rule in enumerate(rules):
        valid = F.when(F.col("rank") == rank, F.length(F.regexp_extract("part", rule.pattern, rule.group)) >= rule.least).otherwise(valid)
    sized = rows.select("blob", "rank", "kind", "rule_version", "at", F.length("part").cast("bigint").alias("n"),
                        F.when(F.col("at") % 2 == 1, valid).otherwise(F.lit(False)).alias("hit"))
    running = Window.partitionBy("blob", "rule_version").orderBy("at").rowsBetween(Window.unboundedPreceding, 0)
    spans = sized.withColumn("end", F.sum("n").over(running))
    found = F.when(F.col("hit"), F.struct((F.col("end") - F.col("n")).alias("start"), "rank", "kind", "end"))
    # Rows that repeat one path and text fetch a blob more than once: the set keeps one of each span.
    return spans.groupBy("blob", "rule_version").agg(F.array_sort(F.collect_set(found)).alias("spans"))


def scan_versions(versions: DataFrame, ledger: BlobLedger, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Scan what the ledger lacks of (path, text) rows and extend it; returns (blob, spans) for every blob of `versions`.

    `rep` is the smallest path of a blob: its text is fetched once by a join on the path, so texts are shuffled for
    distinct blobs and unseen pairs only. Blobs whose every path is null are fetched by content address.
    """
    named = versions.select("path", "text").withColumn("blob", blob_of(F.col("text")))
    blobs = named.groupBy("blob").agg(F.min("path").alias("rep"))
    kinds = F.array(*[F.struct(F.lit(r.kind).alias("kind"), F.lit(r.version).alias("rule_version")) for r in rules])
    known = ledger.read()
    if known is not None:
        pairs = blobs.select("blob", "rep", F.explode(kinds).alias("k")).select("blob", "rep", "k.*")
        pairs = pairs.join(known.select("blob", "rule_version"), ["blob", "rule_version"], "left_anti")
        todo = pairs.groupBy("blob", "rep").agg(F.collect_set("kind").alias("kinds"))
    else:
        todo = blobs.withColumn("kinds", F.array(*[F.lit(r.kind) for r in rules]))
    texts = named.select("path", F.col("blob").alias("of"), "text")
    fetched = todo.join(texts, F.col("rep").eqNullSafe(F.col("path")) & (F.col("blob") == F.col("of")))
    fetched = fetched.select("blob", "text", "kinds").withColumn("text", F.coalesce("text", F.lit("")))
    ledger.append(find_spans(fetched, rules))
    seen = ledger.read().where(F.col("rule_version").isin([r.version for r in rules]))
    if known is not None:
        seen = seen.join(blobs.select("blob"), "blob", "left_semi")
    return seen.dropDuplicates(["blob", "rule_version"]).groupBy("blob").agg(F.array_sort(F.flatten(F.collect_list("spans"))).alias("spans"))


def _joined(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))


def op2_secret_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("path"), "text")
    found = scan_versions(docs, BlobLedger(spark))
    ids = docs.select(F.col("path").alias("doc_id"), blob_of(F.col("text")).alias("blob"))
    spans = F.coalesce("spans", F.array().cast(FINDING))
    base = [r.kind for r in RULES if r.base]
    out = ids.join(found, "blob", "left").withColumn("spans", spans).withColumn("b", F.filter("spans", lambda s: s["kind"].isin(base)))
    count = lambda kind: F.size(F.filter("b", lambda s: s["kind"] == kind)).cast("bigint")
    return out.select("doc_id", count("assign").alias("n_assign"), count("access").alias("n_access"), count("hex").alias("n_hex"),
                      F.sha2(_joined(F.col("b")), 256).alias("base_sha256"), _joined(F.col("spans")).alias("spans"))


def redact(docs: DataFrame, found: DataFrame, mask: str = "[secret]") -> DataFrame:
    """Put `mask` in place of each span (overlapping ones as one) in `text`.

    Texts that no rule matches are not moved: rows and whether a rule matches are stored once, and only matches join.
    """
    any_rule = F.lit(False)
    clean = F.translate(F.coalesce("text", F.lit("")), _MARK, "\u0002")
    for r in RULES:
        any_rule = any_rule | clean.rlike(r.pattern)
    names = docs.columns
    row = F.struct(*[F.col(f"`{c}`") for c in names]).alias("row")
    flagged = store(docs.select(row, any_rule.alias("hit"), F.when(any_rule, blob_of(F.col("text"))).alias("blob")), "flagged")
    hit = flagged.where("hit").join(found.select("blob", "spans"), "blob", "left").select("row", "spans")
    text = F.col("row.text")

    def put(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        out = F.when(s["end"] <= acc["at"], acc["out"]).when(fresh, F.concat(acc["out"], F.substring(text, (acc["at"] + 1).cast("int"), (s["start"] - acc["at"]).cast("int")), F.lit(mask))).otherwise(acc["out"])
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), out.alias("out"))

    done = F.aggregate("spans", F.struct(F.lit(0).cast("bigint").alias("at"), F.lit("").alias("out")), put,
                       lambda a: F.concat(a["out"], F.substring(text, (a["at"] + 1).cast("int"), F.length(text))))
    masked = hit.withColumn("masked", F.when(F.size(F.coalesce("spans", F.array().cast(FINDING))) > 0, done).otherwise(text))
    new = {"text": F.col("masked")}
    if "n_chars" in names:
        new["n_chars"] = F.when(text.isNull(), F.col("row.n_chars")).otherwise(F.length("masked")).cast(docs.schema["n_chars"].dataType)
    masked = masked.select(*[new.get(c, F.col(f"row.`{c}`")).alias(c) for c in names])
    return flagged.where("not hit").select("row.*").unionByName(masked)


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    found = store(scan_versions(docs.select(F.col("doc_id").alias("path"), "text"), BlobLedger(spark)).where(F.size("spans") > 0), "findings")
    return redact(docs, found)

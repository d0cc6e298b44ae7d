"""WARC writing and segment reassembly.

Records are written as text through Spark's own sink, so archives land on any file system: each record ends with the
blank lines that WARC asks for, which serve as the sink's line separator. A response's HTTP message is framed in chunked
transfer coding and cut into segments of SEGMENT_BYTES at most; continuation records carry the origin's identifier and a
number. A file holds RECORDS_PER_FILE records at most, so RECORDS_PER_FILE * SEGMENT_BYTES bytes and headers, however long
pages are.

Reading takes archives as binary files, parses records by their lengths, groups continuations by origin, orders them by
segment number, checks the total length, and decodes the chunks. Of pages with equal payloads the one with the largest
id is the response; the others are revisits that name it. Who is what is settled on ids and digests; payloads are dealt by
page, so equal ones don't meet in a task. A revisit's size and digest are held against the response that it names.

Defined cases: null html is the empty payload; extra columns are ignored; rows without page_id are written with an empty
target and read back with a null id, as responses; rows that repeat a page are records of their own; an empty table gives an
empty result. A segment that lacks, a digest that differs and a revisit without its response are errors.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from proxembed.llm.common import forget, fresh_path, spread, store, table

END = "\r\n\r\n"
SEGMENT_BYTES = 16_384
CHUNK_CHARS = 4_096
RECORDS_PER_FILE = 1_000


ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"


def digest32(payload: bytes) -> str:
    """Base32 SHA-1 without a prefix."""
    return base64.b32encode(hashlib.sha1(payload).digest()).decode("ascii")


def digest_column(payload: Column) -> Column:
    """The same of a string column, in DataFrame functions: 20 bits at a time."""
    hexed, letters = F.sha1(payload), []
    for k in range(8):
        bits = F.conv(F.substring(hexed, 5 * k + 1, 5), 16, 10).cast("int")
        letters += [F.substr(F.lit(ALPHABET), F.shiftright(bits, n).bitwiseAND(F.lit(31)) + 1, F.lit(1)) for n in (15, 10, 5, 0)]
    return F.concat(*letters)


def chunked(body: str) -> str:
    """Chunked transfer framing, cut between characters so that a record stays valid text."""
    out = []
    for a in range(0, len(body), CHUNK_CHARS):
        part = body[a : a + CHUNK_CHARS]
        out.append(f"{len(part.encode('utf-8')):x}\r\n{part}\r\n")
    return "".join(out) + "0\r\n\r\n"


def dechunk(data: bytes) -> bytes:
    """The payload of a chunked body; extensions and trailers are passed over."""
    out, at = [], 0
    while True:
        end = data.index(b"\r\n", at)
        size = int(data[at:end].split(b";")[0], 16)
        if not size:
            return b"".join(out)
        out.append(data[end + 2 : end + 2 + size])
        if len(out[-1]) != size or data[end + 2 + size : end + 4 + size] != b"\r\n":
            raise ValueError("broken chunk")
        at = end + 4 + size


def segments(text: str, limit: int = SEGMENT_BYTES) -> list[str]:
    """`text` in parts of at most `limit` UTF-8 bytes, cut between characters."""
    data, cut, a = text.encode("utf-8"), [], 0
    while len(data) - a > limit:
        b = a + limit
        while data[b] & 0xC0 == 0x80:
            b -= 1
        cut.append(data[a:b].decode("utf-8"))
        a = b
    return [*cut, data[a:].decode("utf-8")]


def _record(kind: str, name: str, headers: dict[str, object], body: str) -> str:
    """One record without its closing blank lines."""
    lines = {"WARC-Type": kind, "WARC-Record-ID": f"<urn:{name}>"} | headers | {"Content-Length": len(body.encode("utf-8"))}
    return "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in lines.items()) + "\r\n" + body


def _header_value(text: str | None) -> str:
    return re.sub(r"[\r\n]+", " ", text or "").strip()


def records_of(page_id: int | None, row: str, url: str | None, html: str, digest: str, refers: int | None) -> list[str]:
    """The records of a page: a revisit, a response, or a response and its continuations; `row` makes its name unique."""
    name = f"page:{'' if page_id is None else page_id}:{row}"
    common = {"WARC-Target-URI": _header_value(url), "WARC-Payload-Digest": f"sha1:{digest}"}
    if refers is not None:
        return [_record("revisit", name, common | {"WARC-Profile": "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", "WARC-Refers-To": f"<urn:page:{refers}>", "WARC-Payload-Length": len(html.encode("utf-8"))}, "HTTP/1.1 200 OK\r\n\r\n")]
    message = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n" + chunked(html)
    parts = segments(message)
    if len(parts) == 1:
        return [_record("response", name, common, message)]
    out = [_record("response", name, common | {"WARC-Segment-Number": 1}, parts[0])]
    for k, part in enumerate(parts[1:], 2):
        more = {"WARC-Segment-Origin-ID": f"<urn:{name}>", "WARC-Segment-Number": k}
        if k == len(parts):
            more["WARC-Segment-Total-Length"] = len(message.encode("utf-8"))
        out.append(_record("continuation", f"{name}:{k}", more, part))
    return out


def parse_records(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, block) of each record; lengths rule, so blocks may hold anything."""
    at = 0
    while at < len(data):
        end = data.index(b"\r\n\r\n", at)
        version, *lines = data[at:end].decode("utf-8").split("\r\n")
        if not version.startswith("WARC/"):
            raise ValueError(f"no record at {at}")
        headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}
        size = int(headers["content-length"])
        yield headers, data[end + 4 : end + 4 + size]
        at = end + 4 + size
        if data[at : at + 4] != b"\r\n\r\n":
            raise ValueError("record is not closed")
        at += 4


def write_archives(pages: DataFrame, path: str) -> None:
    """(page_id, url, html) -> gzipped files of WARC records under `path`, RECORDS_PER_FILE each at most."""
    html = F.coalesce(F.col("html").cast("string"), F.lit(""))
    base = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), html.alias("html")).withColumn("digest", digest_column(F.col("html")))
    ids = base.select("page_id", "digest")
    tops = store(ids.groupBy("digest").agg(F.max("page_id").alias("top"), F.count("*").alias("n")).where("n > 1").select("digest", "top"), "tops")
    revisits = ids.join(tops, "digest").where("page_id <> top").distinct()
    linked = spread(base).join(revisits, ["page_id", "digest"], "left")

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, k = TaskContext.get().partitionId(), 0
        for b in batches:
            out: list[str] = []
            for page, url, html, digest, top in zip(*(c.to_pylist() for c in b.columns), strict=True):
                k += 1
                out += records_of(page, f"{part}-{k}", url, html, digest, top)
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.string())], names=["value"])

    linked.select("page_id", "url", "html", "digest", "top").mapInArrow(build, "value string").write.option("lineSep", END).option("compression", "gzip").option("maxRecordsPerFile", RECORDS_PER_FILE).text(path)
    forget(tops)


RECORD = "name string, page_id long, kind string, digest string, refers_to long, stated long, segment int, total long, block binary"


def read_records(spark: SparkSession, path: str) -> DataFrame:
    """Every record of the archives under `path`, continuations under their origin's name."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = lambda x: None if x in (None, "") else int(x)
        for b in batches:
            for content in b.column(0):
                rows: list[tuple] = []
                for h, block in parse_records(gzip.decompress(content.as_py())):
                    name = h.get("warc-segment-origin-id") or h["warc-record-id"]
                    refers = h.get("warc-refers-to")
                    rows.append((name, number(name.strip("<>").split(":")[2]), h["warc-type"], h.get("warc-payload-digest", "").removeprefix("sha1:"), refers and number(refers.strip("<>").split(":")[2]),
                                 number(h.get("warc-payload-length")), int(h.get("warc-segment-number", 0)), number(h.get("warc-segment-total-length")), block))
                    if len(rows) == 500:
                        yield _frame(rows)
                        rows = []
                if rows:
                    yield _frame(rows)

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.txt.gz").load(path).select("content")
    return files.mapInArrow(run, RECORD)


_ARROW = {"string": pa.string(), "long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}


def _frame(rows: list[tuple]) -> pa.RecordBatch:
    fields = [c.split() for c in RECORD.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(c, _ARROW[kind]) for c, (_, kind) in zip(zip(*rows, strict=True), fields, strict=True)], names=[name for name, _ in fields])


def reassemble(records: DataFrame) -> DataFrame:
    """Whole messages: (name, page_id, kind, digest, refers_to, stated, block). Only segmented records (number 1 and up) are shuffled, by origin."""
    whole = records.where("segment = 0")
    parts = records.where("segment > 0").groupBy("name").agg(
        F.max("page_id").alias("page_id"), F.lit("response").alias("kind"), F.max("digest").alias("digest"), F.max("total").alias("total"), F.count("*").alias("n"), F.max("segment").alias("last"),
        F.array_sort(F.collect_list(F.struct("segment", "block"))).alias("parts"))
    joined = parts.withColumn("block", F.aggregate("parts", F.lit(b"").cast("binary"), lambda a, p: F.concat(a, p["block"])))
    checked = joined.withColumn("block", F.when((F.col("n") == F.col("last")) & (F.octet_length("block") == F.col("total")), F.col("block")).otherwise(F.raise_error(F.concat(F.lit("segments missing of "), F.col("name"))).cast("binary")))
    names = ["name", "page_id", "kind", "digest", "refers_to", "stated", "block"]
    return whole.select(names).unionByName(checked.withColumn("refers_to", F.lit(None).cast("long")).withColumn("stated", F.lit(None).cast("long")).select(names))


def read_pages(spark: SparkSession, path: str) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to) from archives; a revisit's payload is its response's."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sizes, digests = [], []
            for kind, stated, digest, block in zip(b.column(1).to_pylist(), b.column(4).to_pylist(), b.column(2).to_pylist(), b.column(5), strict=True):
                if kind == "revisit":
                    sizes.append(stated)
                    digests.append(digest)
                    continue
                head, _, body = block.as_py().partition(b"\r\n\r\n")
                payload = dechunk(body) if b"\r\ntransfer-encoding: chunked" in head.lower() else body
                sizes.append(len(payload))
                digests.append(digest32(payload))
                if digest and digests[-1] != digest:
                    raise ValueError("payload digest differs")
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sizes, pa.int64()), pa.array(digests, pa.string()), b.column(1), b.column(3)], names=["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])

    whole = reassemble(read_records(spark, path))
    read = store(whole.select("page_id", "kind", "digest", "refers_to", "stated", "block").mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"), "warc-pages")
    named = read.where("record_type <> 'revisit' and page_id is not null").select(F.col("page_id").alias("refers_to"), F.col("payload_bytes").alias("bytes"), F.col("payload_digest").alias("digest")).distinct()
    held = read.where("record_type = 'revisit'").join(named.withColumn("payload_digest", F.col("digest")), ["refers_to", "payload_digest"], "left")
    right = F.col("digest").isNotNull() & (F.col("bytes") == F.col("payload_bytes"))
    size = F.when(right, F.col("bytes")).otherwise(F.raise_error(F.concat(F.lit("no such response for the revisit of page "), F.col("page_id").cast("string"))).cast("long"))
    return read.where("record_type <> 'revisit'").unionByName(held.select("page_id", size.alias("payload_bytes"), "payload_digest", "record_type", "refers_to"))


def op1_warc_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = fresh_path(spark, "warc")
    write_archives(table(spark, sf_dir, "pages"), path)
    return read_pages(spark, path)

"""SentencePiece encoding by a streaming Viterbi, and decoding.

The best segmentation under the model's piece scores is found from left to right. A window holds the positions that a
surviving path can still start from; as soon as all surviving backpointer paths lead through one boundary, everything before
it is decided, its ids are committed and the window moves on. No piece is longer than the longest one, so the walk looks that
far ahead and memory depends on the pieces, not on the text. Characters that no piece covers cost `unknown` and become byte
pieces.

The scores are the model's, the segmentation is the best by their sum. A model that was made for merging (such as the
default one) encodes by merging pairs instead, so its own library gives other ids for the same text; both decode to it.

All text goes through the window. A piece holds the word mark at its start only (checked on loading), and white space such as
line ends may be in no piece at all; paths always converge at such places, with an empty window. Between them, spans of up to
MEMO_CHARS characters that the walk has met before are taken from a memo of bounded size.

Defined cases: null and empty texts have no ids and decode to the empty text; repeated rows are encoded alike; extra
columns are ignored; texts that hold the mark itself decode to spaces there, as the format has it; an empty table gives an
empty result.
"""

from __future__ import annotations

import re
import zlib
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxembed.llm.common import spread, table

MARK = "▁"
MODEL = "piece_bpe_32k.model"
PENALTY = 10.0
CACHE_ENTRIES, MEMO_CHARS = 300_000, 64


def model_path(name: str = MODEL) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Pieces:
    """A model's pieces and scores, from its file."""

    def __init__(self, path: str):
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        self.names = [m.id_to_piece(k) for k in range(m.get_piece_size())]
        self.bytes = {int(self.names[k][3:5], 16): k for k in range(len(self.names)) if m.is_byte(k)}
        self.score = {self.names[k]: (m.get_score(k), k) for k in range(len(self.names)) if not (m.is_byte(k) or m.is_control(k) or m.is_unknown(k) or m.is_unused(k))}
        self.control = {k for k in range(len(self.names)) if m.is_control(k) or m.is_unknown(k)}
        self.longest = max(map(len, self.score))
        self.unknown = min(s for s, _ in self.score.values()) - PENALTY
        self.tree = tree(self.score)
        self.splits = all(MARK not in p.lstrip(MARK) for p in self.score)
        covered = set().union(*self.score)
        self.bare = "".join(c for c in "\n\r\t" if c not in covered)


def tree(score: dict[str, tuple[float, int]]) -> dict:
    """Pieces by their characters: {character: [subtree, score or None, id]}."""
    root: dict = {}
    for name, (value, k) in score.items():
        at, node = root, None
        for ch in name:
            node = at.setdefault(ch, [{}, None, -1])
            at = node[0]
        node[1:] = [value, k]
    return root


@lru_cache(maxsize=2)
def load(path: str) -> Pieces:
    return Pieces(path)


class StreamingViterbi:
    """Feed characters with push(), end with finish(); both return the ids that have become certain.

    Position k of the window holds the best score of the text up to it and how its last piece began. A position is left once
    the text reaches a longest piece beyond it. Equal scores keep the path found first, the one with the longer last piece.
    """

    def __init__(self, pieces: Pieces):
        self.p = pieces
        self.reset()

    def reset(self) -> None:
        self.text, self.at, self.reach, self.held = "", 0, 0, 0
        self.best: list[float | None] = [0.0]
        self.back: list[tuple[int, int]] = [(-1, -1)]

    def push(self, more: str) -> list[int]:
        out: list[int] = []
        longest = self.p.longest
        for a in range(0, len(more), longest):
            self.text += more[a : a + longest]
            out += self._walk(len(self.text) - longest)
        return out

    def whole(self, text: str) -> list[int]:
        """Ids of a text that is at hand as a whole; the window moves over it all the same."""
        self.text = text
        return self.finish()

    def finish(self) -> list[int]:
        out = self._walk(len(self.text))
        out += self._trace(self.at)
        held = self.held
        self.reset()
        self.held = held
        return out

    def _walk(self, end: int) -> list[int]:
        """Leave the positions before `end`, and commit where paths converge."""
        out: list[int] = []
        p, text, best, back = self.p, self.text, self.best, self.back
        root, n, longest = p.tree, len(text), p.longest
        best += [None] * (n + 1 - len(best))
        back += [(-1, -1)] * (n + 1 - len(back))
        a, reach, begin = self.at, self.reach, 0
        while a < end:
            here, at, e = best[a], root, a
            for ch in text[a : a + longest]:
                node = at.get(ch)
                if node is None:
                    break
                at, value, k = node
                e += 1
                if value is not None:
                    score = here + value
                    if best[e] is None or score > best[e]:
                        best[e], back[e] = score, (a, k)
                        if e > reach:
                            reach = e
            a += 1
            if best[a] is None:
                best[a], back[a] = here + p.unknown, (a - 1, -1)
            if reach <= a:
                # No piece leads beyond this boundary: every path passes it.
                out += self._trace(a, begin)
                begin = reach = a
                best[a] = 0.0
            elif a - begin >= 2 * longest and a % longest == 0:
                common = self._common(a, reach)
                if common > begin:
                    out += self._trace(common, begin)
                    begin = common
            if a - begin > self.held:
                self.held = a - begin
        self.text, self.best, self.back = text[begin:], best[begin:], [(x - begin, k) for x, k in back[begin:]]
        self.at, self.reach = a - begin, reach - begin
        return out

    def _common(self, at: int, reach: int) -> int:
        """The last boundary that the paths of all open positions pass."""
        alive = {k for k in range(at, reach + 1) if self.best[k] is not None}
        while len(alive) > 1:
            k = max(alive)
            alive.remove(k)
            alive.add(self.back[k][0])
        return alive.pop()

    def _trace(self, at: int, begin: int = 0) -> list[int]:
        runs: list[list[int]] = []
        while at > begin:
            a, k = self.back[at]
            runs.append([k] if k >= 0 else [self.p.bytes[x] for x in self.text[a:at].encode("utf-8")])
            at = a
        return [k for run in reversed(runs) for k in run]


class Encoder:
    """Ids of whole texts as packed little-endian 32-bit words."""

    def __init__(self, path: str):
        self.p = load(path)
        self.memo: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        bare = re.escape(self.p.bare)
        #: Spans between places where the window is always empty.
        self.spans = re.compile((f"[{bare}]+|" if bare else "") + f"{MARK}+[^{MARK}{bare}]*|[^{MARK}{bare}]+").findall if self.p.splits else lambda text: [text]

    def encode(self, text: str) -> bytes:
        if not text:
            return b""
        spans, memo = self.spans(MARK + text.replace(" ", MARK)), self.memo
        try:
            return b"".join(map(memo.__getitem__, spans))
        except KeyError:
            pass
        if len(memo) > CACHE_ENTRIES:
            # What was met since the last turn stays at hand; the rest goes.
            self.older, self.memo = memo, {}
            memo = self.memo
        walk, older, out = StreamingViterbi(self.p), self.older, []
        for s in spans:
            v = memo.get(s)
            if v is None:
                v = older.get(s)
                if v is None:
                    v = array("I", walk.whole(s)).tobytes()
                if len(s) <= MEMO_CHARS:
                    memo[s] = v
            out.append(v)
        return b"".join(out)


@lru_cache(maxsize=2)
def encoder(path: str) -> Encoder:
    """One encoder a worker process, so its memo outlives a task."""
    return Encoder(path)


class Decoder:
    """Texts of ids: pieces joined, runs of byte pieces read as UTF-8, marks to spaces, the first one dropped."""

    def __init__(self, path: str):
        p = load(path)
        raw = [b"" if k in p.control else n.replace(MARK, " ").encode("utf-8") for k, n in enumerate(p.names)]
        for value, k in p.bytes.items():
            raw[k] = bytes([value])
        self.pool = np.frombuffer(b"".join(raw), dtype=np.uint8)
        self.size = np.array([len(x) for x in raw], dtype=np.int64)
        self.start = np.cumsum(self.size) - self.size

    def decode(self, data: bytes) -> str:
        ids = np.frombuffer(data, dtype="<u4")
        size = self.size[ids]
        ends = np.cumsum(size)
        at = np.repeat(self.start[ids] - (ends - size), size) + np.arange(int(ends[-1]) if len(ends) else 0)
        return self.pool[at].tobytes().decode("utf-8", "replace").removeprefix(" ")


def encode_texts(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) -> (doc_id, ids) with ids as packed 32-bit words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(path)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([own.encode(t.as_py() or "") for t in batch.column(1)], pa.binary())], names=["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, ids binary")


def decode_texts(ids: DataFrame, path: str) -> DataFrame:
    """(doc_id, ids) -> (doc_id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        decoder = Decoder(path)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([decoder.decode(x.as_py() or b"") for x in batch.column(1)], pa.string())], names=["doc_id", "text"])

    return ids.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def op7_streaming_viterbi(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text encoded and decoded again: counts and checksums of ids, and whether decoding gives the text back."""
    schema = "doc_id long, n_ids long, ids_crc32 long, n_chars long, text_crc32 long, same boolean"
    path = model_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, decoder = encoder(path), Decoder(path)
        for batch in batches:
            rows = []
            for doc, t in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                text = t.as_py() or ""
                ids = own.encode(text)
                back = decoder.decode(ids)
                rows.append((doc, len(ids) // 4, zlib.crc32(ids), len(back), zlib.crc32(back.encode("utf-8")), back == text.replace(MARK, " ")))
            cols = list(zip(*rows, strict=True)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in cols[:5]), pa.array(cols[5], pa.bool_())], names=[c.split()[0] for c in schema.split(", ")])

    docs = table(spark, sf_dir, "documents")
    return spread(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))).mapInArrow(run, schema)

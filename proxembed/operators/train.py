"""Training: local updates at once, remote updates deferred to two exchanges a batch.

State lies in one block per owner part (ids, U and C as float32 bytes). A batch is two supersteps, each a cogrouped map:

X  adds the deltas of the batch before, applies the part's local pairs, and reads out the contexts that others need;
Y  applies the deferred pairs with the contexts received (positives first, then negatives) and sums their changes.

Who needs which context is known from the pairs, so requests cost no exchange. A step's rows are written bucketed by part:
the state is read where it lies, and only work and messages move (tested on the plans).
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxembed.functions.rng import INIT, SPAN, draw, draw_numpy
from proxembed.functions.vectors import grad_scalar, pack, unpack, vec_dot, vec_sum
from proxembed.operators.graph import Graph
from proxembed.operators.kernels import run_exact, run_mini
from proxembed.operators.pairs import serve_list, settle
from proxembed.operators.partition import part_links
from proxembed.operators.storage import Buckets, Versions, forget, store

BLOCK_BYTES = 64 << 20
MOST_QUERIES = 100_000
STATE, CONTEXT, DELTA = 0, 1, 2
ROWS = "part int, kind int, to_part int, vids binary, u binary, c binary"


@dataclass(frozen=True)
class TrainConfig:
    dim: int = 64
    lr: float = 0.025
    neg_weight: float = 1.0
    decay: float = 1e-4
    kernel: str = "exact"
    mini_size: int = 64
    defer_all: bool = False
    sync_every: int = 1
    fetch: str = "after"
    exchange: str = "collective"
    onesided_slices: int = 4
    seed: int = 7
    order: int = 2

    def __post_init__(self) -> None:
        if self.dim < 1 or self.sync_every < 1 or self.lr <= 0 or self.onesided_slices < 1:
            raise ValueError("dim, sync_every and onesided_slices must be 1 or more, lr positive")
        if self.kernel not in ("exact", "mini") or self.fetch not in ("after", "before") or self.exchange not in ("collective", "neighbors", "onesided_get", "onesided_atomic") or self.order not in (1, 2):
            raise ValueError("unknown kernel, fetch, exchange or order")


def initial_vectors(vids: np.ndarray, c: TrainConfig) -> tuple[np.ndarray, np.ndarray]:
    """U uniform in +-0.5 / dim by draws of (vid, component), C zero."""
    d = draw_numpy(c.seed, INIT, vids[:, None], np.arange(c.dim)[None, :]).astype(np.float64)
    u = ((d / SPAN - 0.5) / c.dim).astype(np.float32)
    return u, (u.copy() if c.order == 1 else np.zeros_like(u))


def init_blocks(g: Graph, c: TrainConfig) -> DataFrame:
    """A state row for each part that owns vertices; a part must fit BLOCK_BYTES, or the graph needs more parts."""

    def run(x: pd.DataFrame) -> pd.DataFrame:
        vids = np.sort(x["vid"].to_numpy())
        if len(vids) * c.dim * 4 > BLOCK_BYTES:
            raise ValueError("a part exceeds its block: cut the graph into more parts")
        u, ctx = initial_vectors(vids, c)
        return pd.DataFrame([(int(x["part"].iloc[0]), STATE, int(x["part"].iloc[0]), vids.astype("<i8").tobytes(), pack(u), pack(ctx))], columns=["part", "kind", "to_part", "vids", "u", "c"])

    return g.vertices.select("part", "vid").groupBy("part").applyInPandas(run, ROWS)


def extend_blocks(state: DataFrame, fresh: DataFrame, dim: int) -> DataFrame:
    """State rows with the vertices of further ones: blocks of a part are joined and sorted by vertex."""

    def run(x: pd.DataFrame) -> pd.DataFrame:
        vids, u, c = (np.concatenate(y) for y in zip(*(_open(r, dim) for _, r in x.iterrows()), strict=True))
        if len(vids) * dim * 4 > BLOCK_BYTES:
            raise ValueError("a part exceeds its block: cut the graph into more parts")
        order = np.argsort(vids)
        part = int(x["part"].iloc[0])
        return pd.DataFrame([(part, STATE, part, vids[order].astype("<i8").tobytes(), pack(u[order]), pack(c[order]))], columns=["part", "kind", "to_part", "vids", "u", "c"])

    return state.where(F.col("kind") == STATE).unionByName(fresh).groupBy("part").applyInPandas(run, ROWS)


def embedding(state: DataFrame, dim: int) -> DataFrame:
    """(vid, part, u, c) rows of arrays."""

    def run(batches):
        for b in batches:
            for part, vids, u, c in zip(b["part"], b["vids"], b["u"], b["c"], strict=True):
                yield pd.DataFrame({"vid": np.frombuffer(vids, "<i8"), "part": part, "u": list(unpack(u, dim)), "c": list(unpack(c, dim))})

    return state.where(F.col("kind") == STATE).select("part", "vids", "u", "c").mapInPandas(run, "vid long, part int, u array<float>, c array<float>")


def _kernel(c: TrainConfig):
    if c.kernel == "exact":
        return lambda *a, frozen=None: run_exact(*a, c.lr, c.neg_weight, c.decay, frozen)
    return lambda *a, frozen=None: run_mini(*a, c.lr, c.neg_weight, c.decay, frozen, c.mini_size)


def _open(row: pd.Series, dim: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return np.frombuffer(row["vids"], "<i8"), unpack(row["u"], dim), unpack(row["c"], dim)


def _ordered(x: pd.DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(u, v, sign) in sample order: each positive, then its negatives."""
    x = x.sort_values(["batch", "seq", "j"], kind="stable")
    return tuple(x[c].to_numpy().astype(np.int64) for c in ("u", "v", "sign"))


#: What a part gets for a superstep beside its state: pairs, what it must serve, and messages of other parts.
WORK = "kind int, part int, u long, v long, v_part int, to_part int, sign int, batch int, seq long, j int, vids binary, c binary"
PAIR, SERVE, MESSAGE = 0, 1, 2
_STATE_COLUMNS = ["part", "kind", "to_part", "vids", "u", "c"]


def _work(rows: DataFrame, kind: int, **columns) -> DataFrame:
    """Rows in the shape of WORK; what isn't named is null."""
    out = []
    for field in WORK.split(", "):
        name, type_ = field.split()
        out.append((F.lit(kind) if name == "kind" else columns[name] if name in columns else F.lit(None)).cast(type_).alias(name))
    return rows.select(out)


def _pairs_of(rows: DataFrame) -> DataFrame:
    return _work(rows, PAIR, **{c: F.col(c) for c in ("part", "u", "v", "v_part", "sign", "batch", "seq", "j")})


def _messages_of(rows: DataFrame, kind: int) -> DataFrame:
    """Messages for their receivers; the sender stands in v_part, to add them up in one order."""
    return _work(rows.where(F.col("kind") == kind), MESSAGE, part=F.col("to_part"), v_part=F.col("part"), vids=F.col("vids"), c=F.col("c"))


def _local_step(c: TrainConfig):
    """X: state x (deltas that came, its pairs and what it must serve) -> state, context messages."""

    def run(key: tuple, own: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        part = int(key[0])
        if not len(own):
            return pd.DataFrame(columns=_STATE_COLUMNS)
        vids, U, C = _open(own.iloc[0], c.dim)
        for _, d in right[right["kind"] == MESSAGE].sort_values("v_part").iterrows():
            np.add.at(C, np.searchsorted(vids, np.frombuffer(d["vids"], "<i8")), unpack(d["c"], c.dim))
        wanted = right[right["kind"] == SERVE]
        before = C.copy() if c.fetch == "before" else None
        local = right[(right["kind"] == PAIR) & (right["v_part"] == part)]
        if len(local) and not c.defer_all:
            u, v, sign = _ordered(local)
            _kernel(c)(U, C, np.searchsorted(vids, u), np.searchsorted(vids, v), sign)
            if c.order == 1:
                C[:] = U
        shown = C if before is None else before
        out = [(part, STATE, part, own.iloc[0]["vids"], pack(U), pack(C))]
        for to, x in wanted.groupby("to_part"):
            v = np.unique(x["v"].to_numpy().astype(np.int64))
            out.append((part, CONTEXT, int(to), v.astype("<i8").tobytes(), b"", pack(shown[np.searchsorted(vids, v)])))
        return pd.DataFrame(out, columns=_STATE_COLUMNS)

    return run


def _remote_step(c: TrainConfig):
    """Y: state x (contexts that came, its deferred pairs) -> state, delta messages to owners."""

    def run(key: tuple, own: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        part = int(key[0])
        if not len(own):
            return pd.DataFrame(columns=_STATE_COLUMNS)
        vids, U, C = _open(own.iloc[0], c.dim)
        pairs = right[right["kind"] == PAIR]
        deferred = pairs if c.defer_all else pairs[pairs["v_part"] != part]
        out = []
        if len(deferred):
            came = right[right["kind"] == MESSAGE]
            ghost = np.concatenate([np.frombuffer(x, "<i8") for x in came["vids"]] + [vids])
            Z = np.concatenate([unpack(x, c.dim) for x in came["c"]] + [C])
            order = np.argsort(ghost, kind="stable")
            ghost, Z = ghost[order], Z[order]
            change = np.zeros_like(Z)
            kernel = _kernel(c)
            for wanted in (1, -1):
                u, v, sign = _ordered(deferred[deferred["sign"] == wanted])
                if len(u):
                    kernel(U, Z, np.searchsorted(vids, u), np.searchsorted(ghost, v), sign, frozen=change)
            where = deferred[["v", "v_part"]].drop_duplicates()
            for to, x in where.groupby("v_part"):
                v = np.sort(x["v"].to_numpy().astype(np.int64))
                delta = change[np.searchsorted(ghost, v)]
                if int(to) == part:
                    np.add.at(C, np.searchsorted(vids, v), delta)
                else:
                    out.append((part, DELTA, int(to), v.astype("<i8").tobytes(), b"", pack(delta)))
        return pd.DataFrame([(part, STATE, part, own.iloc[0]["vids"], pack(U), pack(C)), *out], columns=_STATE_COLUMNS)

    return run


def signed(pairs: DataFrame, negatives: DataFrame) -> DataFrame:
    """Positives and negatives as (batch, part, seq, j, u, v, v_part, sign)."""
    columns = ["batch", "part", "seq", "j", "u", "v", "v_part"]
    pos = pairs.select("batch", "part", "seq", F.lit(0).alias("j"), "u", "v", "v_part").withColumn("sign", F.lit(1))
    return pos.unionByName(negatives.select(columns).withColumn("sign", F.lit(-1)))


def _superstep(now: DataFrame, work: DataFrame, messages: int, run) -> DataFrame:
    own = now.where(F.col("kind") == STATE)
    return own.groupBy("part").cogroup(work.unionByName(_messages_of(now, messages)).groupBy("part")).applyInPandas(run, ROWS)


def only_neighbors(g: Graph, rows: DataFrame) -> None:
    """Raise unless every pair stays in its part or goes to one that shares edges with it."""
    far = rows.where("v_part <> part").select("part", F.col("v_part").alias("other")).distinct()
    lost = far.join(part_links(g).select("part", "other"), ["part", "other"], "left_anti").first()
    if lost is not None:
        raise ValueError(f"part {lost['part']} shares no edge with part {lost['other']}: draw negatives of scope local or adjacent")


def train(g: Graph, rows: DataFrame, c: TrainConfig, batches: int, buckets: int | None = None, state: DataFrame | None = None, versions: Versions | None = None, every: int = 1) -> DataFrame:
    """Train on signed rows; returns state rows for embedding(). Pass `state` to go on from an earlier result.

    `sync_every` s takes s batches to a superstep pair (contexts and deltas are exchanged once for them). One-sided
    exchanges cut a batch into slices that each fetch fresh contexts: `onesided_get` lets all parts read the start of each of
    `onesided_slices` slices, `onesided_atomic` lets one part after the other fetch and add, so each sees all earlier deltas.
    `neighbors` exchanges between parts that share edges only; pairs that go elsewhere are an error.

    With `versions`, the state is written there after every `every` superstep pairs and the call goes on from the last whole
    version, if there is one: a driver that was lost is started again with the same arguments.
    """
    spark = g.edges.sparkSession
    steps = Buckets(spark, buckets or min(g.parts, spark.sparkContext.defaultParallelism))
    if c.exchange == "neighbors":
        only_neighbors(g, rows)
    # A folder a batch: a superstep reads its own rows alone.
    rows = store(settle(rows), "signed", by=["batch"])
    slices = {"onesided_get": c.onesided_slices, "onesided_atomic": g.parts}.get(c.exchange, 1)
    begun, saved = 0, versions.read("state") if versions else None
    if saved is not None:
        begun, (state,) = saved
    now = steps.keep(init_blocks(g, c) if state is None else state)

    def superstep(now: DataFrame, work: DataFrame, messages: int, run) -> DataFrame:
        return steps.keep(_superstep(now, work, messages, run))

    for pair, first in enumerate(range(0, batches, c.sync_every)):
        if first < begun:
            continue
        for k in range(slices):
            mine = rows.where((F.col("batch") >= first) & (F.col("batch") < first + c.sync_every))
            if slices > 1:
                turn = F.pmod(F.col("seq"), F.lit(slices)) if c.exchange == "onesided_get" else F.col("part")
                mine = mine.where(turn == k)
            # The state is read in its buckets; work and messages are dealt to their part, in one exchange.
            serve = _work(serve_list(mine), SERVE, part=F.col("part"), v=F.col("v"), to_part=F.col("to_part"))
            now = superstep(now, _pairs_of(mine).unionByName(serve), DELTA, _local_step(c))
            now = superstep(now, _pairs_of(mine if c.defer_all else mine.where("v_part <> part")), CONTEXT, _remote_step(c))
            steps.forget(2)
        if versions is not None and (pair + 1) % every == 0:
            versions.write(first + c.sync_every, state=now)
    done = store(_superstep(now, _pairs_of(rows.limit(0)), DELTA, _local_step(c)), "state")
    steps.forget()
    forget(rows)
    return done


def train_dataflow(vectors: DataFrame, rows: DataFrame, c: TrainConfig, batches: int) -> DataFrame:
    """(vid, u, c) after synchronous batches, by expressions alone: every pair of a batch reads the batch's first values."""
    now = vectors
    for b in range(batches):
        x = rows.where(F.col("batch") == b)
        du, dc = batch_changes(now, x, c)
        now = store(now.join(du, "vid", "left").join(dc, "vid", "left").select("vid", _plus("u", "du").alias("u"), _plus("c", "dc").alias("c")), "vectors")
    return now


def _plus(a: str, d: str):
    return F.when(F.col(d).isNull(), F.col(a)).otherwise(F.zip_with(a, d, lambda x, y: x + y))


def batch_changes(vectors: DataFrame, rows: DataFrame, c: TrainConfig) -> tuple[DataFrame, DataFrame]:
    """Summed changes (vid, du) and (vid, dc) of one synchronous batch."""
    v = vectors.select("vid", F.col("u").cast("array<double>").alias("u_vec"), F.col("c").cast("array<double>").alias("c_vec"))
    both = rows.join(v.select(F.col("vid").alias("u"), "u_vec"), "u").join(v.select(F.col("vid").alias("v"), "c_vec"), "v")
    g = grad_scalar(vec_dot(F.col("u_vec"), F.col("c_vec")), F.col("sign"), c.lr, c.neg_weight)
    fade = F.lit(c.lr * c.decay)
    both = both.withColumn("g", g)
    du = both.select(F.col("u").alias("vid"), F.zip_with("u_vec", "c_vec", lambda a, b: F.col("g") * b - fade * a).alias("du"))
    dc = both.select(F.col("v").alias("vid"), F.zip_with("u_vec", "c_vec", lambda a, b: F.col("g") * a - fade * b).alias("dc"))
    return vec_sum(du, ["vid"], "du"), vec_sum(dc, ["vid"], "dc")


def initial_frame(g: Graph, c: TrainConfig) -> DataFrame:
    """(vid, u, c) as init_blocks has them, by expressions."""
    u = F.transform(F.sequence(F.lit(0), F.lit(c.dim - 1)), lambda i: ((draw(c.seed, INIT, F.col("vid"), i) / F.lit(float(SPAN)) - 0.5) / c.dim).cast("float").cast("double"))
    return g.vertices.select("vid", u.alias("u"), (u if c.order == 1 else F.transform(F.sequence(F.lit(0), F.lit(c.dim - 1)), lambda i: F.lit(0.0))).alias("c"))


def loss(vectors: DataFrame, rows: DataFrame) -> DataFrame:
    """Mean of -log sigmoid(sign * U . C) by batch."""
    v = vectors.select("vid", F.col("u").cast("array<double>").alias("u_vec"), F.col("c").cast("array<double>").alias("c_vec"))
    both = rows.join(v.select(F.col("vid").alias("u"), "u_vec"), "u").join(v.select(F.col("vid").alias("v"), "c_vec"), "v")
    return both.withColumn("l", F.log1p(F.exp(-F.col("sign") * vec_dot(F.col("u_vec"), F.col("c_vec"))))).groupBy("batch").agg(F.round(F.avg("l"), 6).alias("loss"))


def nearest(vectors: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(q, rank, vid, score): k largest cosines for each row of a stated query set of at most MOST_QUERIES rows, against all vectors."""
    from pyspark.sql import Window

    if queries.limit(MOST_QUERIES + 1).count() > MOST_QUERIES:
        raise ValueError(f"nearest takes at most {MOST_QUERIES} queries: every one of them meets every vector")
    unit = lambda c: F.transform(c, lambda x: x / F.sqrt(F.aggregate(c, F.lit(0.0), lambda s, y: s + y * y)))
    base = vectors.select("vid", unit(F.col("u").cast("array<double>")).alias("x"))
    asked = queries.select(F.col("vid").alias("q"), unit(F.col("u").cast("array<double>")).alias("y"))
    met = base.join(F.broadcast(asked), F.col("vid") != F.col("q"))  # MOST_QUERIES rows at most
    scored = met.withColumn("score", F.round(vec_dot(F.col("x"), F.col("y")), 6))
    w = Window.partitionBy("q").orderBy(F.desc("score"), "vid")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("q", "rank", "vid", "score")

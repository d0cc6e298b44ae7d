"""The six ways to produce walk pairs for batches, under two stop rules."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxembed.functions.rng import AUGMENT, SPAN, draw
from proxembed.operators.graph import Graph, components
from proxembed.operators.pairs import numbered, prune
from proxembed.operators.quota import idle_parts, spill_slices
from proxembed.operators.sampling import neighbor_index, root_starts, roots
from proxembed.operators.storage import store
from proxembed.operators.walks import LongWalk, walk_block, walk_join, walk_pairs

KINDS = ("local", "fresh", "reuse", "refresh", "single", "pair")
#: A walk's id holds its round in 20 bits.
MOST_ROUNDS = 1 << 20
#: Tasks that a part's combinations are ranked in.
DRAW_SLICES = 256
_NAMES = {"Local": "local", "Remote (Fresh-Only)": "fresh", "Remote (Reuse-Spill)": "reuse", "Remote (Refresh-Spill)": "refresh", "Remote (Augmented-Single)": "single", "Remote (Augmented-Pair)": "pair"}


@dataclass(frozen=True)
class Variant:
    """A stop rule and a way to sample; augmented ways take the rule `all` only."""

    rule: str
    kind: str

    def __post_init__(self) -> None:
        if self.rule not in ("any", "all") or self.kind not in KINDS:
            raise ValueError(f"no variant {self.rule}-{self.kind}")
        if self.rule == "any" and self.kind in ("single", "pair"):
            raise ValueError("augmented variants stop only when all parts are full")

    @staticmethod
    def parse(name: str) -> Variant:
        """`AR-Local`, `IB-Remote (Reuse-Spill)` and the like."""
        rule, _, kind = name.partition("-")
        if rule not in ("AR", "IB") or kind not in _NAMES:
            raise ValueError(f"no variant {name!r}")
        return Variant({"AR": "any", "IB": "all"}[rule], _NAMES[kind])

    def __str__(self) -> str:
        return {"any": "AR", "all": "IB"}[self.rule] + "-" + next(k for k, v in _NAMES.items() if v == self.kind)


GRID = [Variant(rule, kind) for kind in KINDS for rule in ("any", "all") if rule == "all" or kind not in ("single", "pair")]


@dataclass(frozen=True)
class SampleConfig:
    batch_size: int = 256
    batches: int = 4
    length: int = 100
    window: int = 2
    unit: str = "nodes"
    seed: int = 7
    backend: str = "xx"
    engine: str = "block"
    rounds: int = 4
    max_rounds: int = MOST_ROUNDS  # calls of a batch (shared kinds: of all batches) after which a rule unmet is an error
    max_levels: int = 2000  # steps of the long walk's first stretch; it doubles until every part is full
    budget: int | None = None  # visits of all walkers of a call, after which the call ends at that step
    index_chunk: int = 4096
    extra: dict = field(default_factory=dict)

    def __post_init__(self) -> None:
        if self.batch_size < 1 or self.batches < 1 or self.length < 1 or self.rounds < 1:
            raise ValueError("batch_size, batches, length and rounds must be 1 or more")
        if self.engine not in ("block", "join") or self.backend not in ("xx", "md5") or self.unit not in ("nodes", "hops"):
            raise ValueError("unknown engine, back end or unit")
        if self.window < (2 if self.unit == "nodes" else 1):
            raise ValueError("a window of one vertex holds no pair")
        if self.budget is not None and self.budget < 2:
            raise ValueError("a budget is two visits or more: a root edge has two ends")
        if self.max_levels < 1 or not 1 <= self.max_rounds <= MOST_ROUNDS:
            raise ValueError(f"max_levels must be 1 or more and max_rounds from 1 to {MOST_ROUNDS}")


@dataclass
class Sample:
    """pairs(batch, part, seq, u, v, v_part, age): age is how many batches ago a pair was drawn; calls: walk calls made;
    handed: walk steps that crossed parts; met: every batch was filled by the rule."""

    pairs: DataFrame
    calls: int
    handed: int
    met: bool
    idle: list[int]


def aug_target(batch_size: int, batches: int) -> int:
    """Pairs to draw so that their combinations suffice for all batches."""
    n = math.ceil(math.sqrt(2 * batch_size * batches))
    return n if n * (n - 1) // 2 >= batch_size * batches else n + 1


def _steps(g: Graph, r: DataFrame, c: SampleConfig, stop: str, length: int | None = None) -> DataFrame:
    if c.engine == "block":
        steps = walk_block(g, r, length or c.length, stop, c.seed, c.backend)
    else:
        steps = walk_join(neighbor_index(g, c.index_chunk), r, length or c.length, stop, seed=c.seed, backend=c.backend)
    return steps if c.budget is None else within_budget(steps, g.parts, c.budget)


def within_budget(steps: DataFrame, parts: int, budget: int) -> DataFrame:
    """Steps of calls (a walk of each part) that end at the step where the visits of all its walkers reach `budget`.

    A root edge visits two vertices, every further step one; what the last step visits beyond the budget is kept.
    """
    call = F.expr(f"walk_id div {parts}")
    visits = steps.groupBy(call.alias("_call"), "step").agg(F.sum(F.when(F.col("step") == 0, 2).otherwise(1)).alias("_n"))
    before = F.sum("_n").over(Window.partitionBy("_call").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_n")  # a row for each step of a call
    open_ = visits.withColumn("_before", before).where(F.col("_before") < budget).select("_call", "step")
    return steps.withColumn("_call", call).join(open_, ["_call", "step"]).select(steps.columns)


def _calls(g: Graph, c: SampleConfig, batches: int, rounds: int, stop: str, starts: DataFrame) -> tuple[DataFrame, DataFrame, int]:
    """(pairs, yields, handed) of walks from every part in `rounds` calls for each of `batches`; yields hold zeros."""
    r = store(roots(g, batches, rounds, c.seed, c.backend, starts=starts), "roots")
    steps = _steps(g, r, c, stop)
    drawn = walk_pairs(steps, c.window, c.unit)
    stamp = (F.col("walk_id") / g.parts).cast("long")
    pairs = store(drawn.withColumns({"batch": F.shiftright(stamp, 20).cast("int"), "round": stamp.bitwiseAND(F.lit((1 << 20) - 1)).cast("int")}), "drawn")
    spark = g.edges.sparkSession
    grid = spark.range(batches * rounds * g.parts).select(F.expr(f"cast(id div {rounds * g.parts} as int)").alias("batch"), F.expr(f"cast(id div {g.parts} % {rounds} as int)").alias("round"), F.expr(f"cast(id % {g.parts} as int)").alias("part"))
    counts = pairs.groupBy("batch", "round", "part").agg(F.count("*").alias("pairs"))
    yields = store(grid.join(counts, ["batch", "round", "part"], "left").withColumn("pairs", F.coalesce("pairs", F.lit(0))), "yields")
    handed = pairs.where("v_part <> part and hop = 1").count()
    return pairs, yields, handed


def call_yields(g: Graph, c: SampleConfig, batches: int, rounds: int) -> DataFrame:
    """(batch, round, part, pairs) of walk calls, parts that drew nothing counted."""
    return _calls(g, c, batches, rounds, "length", store(root_starts(g), "root-starts"))[1]


def sample(g: Graph, variant: Variant, c: SampleConfig) -> Sample:
    """Pairs for all batches in one dataflow: sampling depends on the graph and the seed only.

    Calls are drawn ahead (`rounds`, then two to sixteen times as many, as yields tell, until the rule is met everywhere) and
    trimmed by the rule on counts; draws are keyed by call, so drawing ahead gives what calling one by one would. A rule that
    max_rounds calls don't meet is an error: no batch comes back short.
    """
    # A part without edges, or for Local without inner edges, can never fill: its quota is waived and reported.
    inner = Graph(g.vertices, g.edges.where("src_part = dst_part"), g.n, g.parts) if variant.kind == "local" else g
    idle = [r["part"] for r in idle_parts(inner, g.parts).collect()]
    if len(idle) == g.parts:
        raise ValueError(f"{variant}: no part has edges to walk, so no batch can fill")
    if variant.kind == "single":
        return _single(g, c, idle)
    if variant.kind == "pair":
        return _pair(g, c, idle)
    starts = store(root_starts(g), "root-starts")
    stop = "boundary" if variant.kind == "local" else "length"
    shared = variant.kind in ("reuse", "refresh")
    rounds = min(c.max_rounds, c.rounds * (c.batches if shared else 1))
    while True:
        pairs, yields, handed = _calls(g, c, 1 if shared else c.batches, rounds, stop, starts)
        if shared:
            keep = {"reuse": "ever", "refresh": "once"}[variant.kind]
            counts = yields.select(F.col("round").alias("call"), "part", "pairs")
            plan = store(spill_slices(counts, g.parts, c.batch_size, c.batches, variant.rule, keep, idle), "slices")
        else:
            needed = yields.where(~F.col("part").isin(idle)) if idle and variant.rule == "all" else yields
            w = Window.partitionBy("batch", "part").orderBy("round").rowsBetween(Window.unboundedPreceding, 0)
            reached = F.max("total") if variant.rule == "any" else F.min("total")
            per_round = needed.withColumn("total", F.sum("pairs").over(w)).groupBy("batch", "round").agg(reached.alias("x"))
            plan = store(per_round.where(F.col("x") >= c.batch_size).groupBy("batch").agg((F.min("round") + 1).alias("rounds")), "rounds")
        filled = plan.select("batch").distinct().count()
        if filled == c.batches:
            break
        if rounds >= c.max_rounds:
            raise ValueError(f"{variant}: {rounds} calls fill {filled} of {c.batches} batches of {c.batch_size} pairs")
        totals = yields.where(~F.col("part").isin(idle)).groupBy("batch", "part").agg(F.sum("pairs").alias("pairs"))
        reached = F.max("pairs") if variant.rule == "any" else F.min("pairs")
        low = totals.groupBy("batch").agg(reached.alias("x")).agg(F.min("x")).first()[0]
        short = c.batch_size * (c.batches if shared else 1) / max(1, low)
        rounds = min(c.max_rounds, math.ceil(rounds * min(16.0, max(2.0, 1.2 * short))))
    if shared:
        order = numbered(pairs, ["part"], ["round", "walk_id", "step", "hop"]).withColumnRenamed("seq", "pos")
        first_call = plan.groupBy("batch").agg(F.max("calls").alias("calls"))
        began = first_call.withColumn("from_call", F.sum("calls").over(Window.orderBy("batch").rowsBetween(Window.unboundedPreceding, 0)) - F.col("calls"))  # a row for each batch
        # A slice of a part's order is a range: an equi join on the part and a bucket of positions.
        size = max(1, c.batch_size)
        cut = plan.where("kept > 0").withColumn("_s", F.explode(F.sequence(F.expr(f"start div {size}"), F.expr(f"(start + kept - 1) div {size}"))))
        got = order.select("part", "round", "walk_id", "u", "v", "v_part", "pos").withColumn("_s", F.expr(f"pos div {size}")).join(cut.select(F.col("part").cast("int").alias("part"), "_s", "batch", "start", "kept"), ["part", "_s"]).where("pos >= start and pos < start + kept")
        got = got.join(began.select("batch", "from_call"), "batch")
        drawn_in = began.select(F.col("batch").alias("drawn"), F.col("from_call").alias("lo"), (F.col("from_call") + F.col("calls")).alias("hi"))
        got = got.join(F.broadcast(drawn_in), (F.col("round") >= F.col("lo")) & (F.col("round") < F.col("hi")))  # a row for each batch
        out = numbered(got.select(F.col("batch").cast("int").alias("batch"), "part", (F.col("pos") - F.col("start")).alias("seq"), "u", "v", "v_part", (F.col("batch") - F.col("drawn")).cast("int").alias("age")), ["batch", "part"], ["seq"])
        calls = plan.groupBy("batch").agg(F.max("calls").alias("c")).agg(F.sum("c")).first()[0] or 0
        used = pairs.where(F.col("round") < calls)
    else:
        in_time = pairs.join(plan, "batch").where("round < rounds")
        seq = numbered(in_time, ["batch", "part"], ["round", "walk_id", "step", "hop"])
        out = prune(seq.select("batch", "part", "seq", "u", "v", "v_part", F.lit(0).alias("age")), c.batch_size, c.seed, c.backend)
        calls = plan.agg(F.sum("rounds")).first()[0] or 0
        used = in_time
    handed = used.where("v_part <> part and hop = 1").count() if stop == "length" else 0
    return Sample(store(out.select("batch", "part", "seq", "u", "v", "v_part", "age"), "pairs"), int(calls), handed, True, idle)


def _single(g: Graph, c: SampleConfig, idle: list[int]) -> Sample:
    """One long walk from one root, until every part that has edges holds the pairs of all batches.

    The walk goes on in stretches, each as long as all before it; what the last one draws beyond the rule is trimmed. A part
    that no path joins to the root can't fill: an error.
    """
    want, active = c.batch_size * c.batches, sorted(set(range(g.parts)) - set(idle))
    one = roots(g, 1, 1, c.seed, c.backend).where(F.col("part") == active[0])
    walk = LongWalk(g, one, c.seed, c.backend)
    length, joined = c.max_levels, False
    while True:
        steps = walk.until(length)
        ordered = store(numbered(walk_pairs(steps, c.window, c.unit), ["part"], ["walk_id", "step", "hop"]), "drawn")
        held = {r["part"]: r["count"] for r in ordered.groupBy("part").count().collect()}  # p rows
        if all(held.get(p, 0) >= want for p in active):
            break
        if not joined and len(held) < len(active):
            labels = components(g)
            near = g.vertices.where("deg > 0").join(labels.join(labels.join(one.select(F.col("u").alias("vid")), "vid").select("label"), "label"), "vid")
            lost = set(active) - {r["part"] for r in near.select("part").distinct().collect()}
            if lost:
                raise ValueError(f"no path joins the long walk's root to parts {sorted(lost)}: they can't fill")
            joined = True
        length *= 2
    kept = ordered.where(F.col("seq") < want)
    last = kept.where(F.col("seq") == want - 1).agg(F.max("step")).first()[0]
    out = kept.select((F.col("seq") / c.batch_size).cast("int").alias("batch"), "part", (F.col("seq") % c.batch_size).alias("seq"), "u", "v", "v_part", F.lit(0).alias("age"))
    return Sample(store(out, "pairs"), 1, ordered.where("v_part <> part and hop = 1").where(F.col("step") <= last).count(), True, idle)


def _pair(g: Graph, c: SampleConfig, idle: list[int]) -> Sample:
    """A short sample under `all`, then combinations (u_i, v_j), i < j, of a part's pairs: the same number for every part."""
    n = aug_target(c.batch_size, c.batches)
    short = sample(g, Variant("all", "fresh"), SampleConfig(**{**c.__dict__, "batch_size": n, "batches": 1}))
    kept = short.pairs.select("part", F.col("seq").alias("i"), "u", "v", "v_part")
    # An equi join on (part, block of i): a part's n * n work spreads over blocks of rows.
    blocks = max(1, n // 256)
    left = kept.select("part", "i", "u").withColumn("_b", F.col("i") % blocks)
    right = kept.select("part", F.col("i").alias("j"), "v", "v_part").withColumn("_b", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))))
    both = left.join(right, ["part", "_b"]).where("i < j").withColumn("_d", draw(c.seed, AUGMENT, "part", "i", "j", backend=c.backend))
    # Draws are uniform, so their leading bits deal a part's combinations over tasks in order: a rank inside the slice and the slices before it.
    both = store(both.drop("_b").withColumn("_s", F.expr(f"_d div {SPAN // DRAW_SLICES}")), "combinations")
    counts = both.groupBy("part", "_s").agg(F.count("*").alias("_n"))
    before = counts.withColumn("_o", F.sum("_n").over(Window.partitionBy("part").orderBy("_s").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_n"))  # DRAW_SLICES rows a part
    inside = F.row_number().over(Window.partitionBy("part", "_s").orderBy("_d", "i", "j"))
    wanted = before.where(F.col("_o") < c.batch_size * c.batches).select("part", "_s", "_o")
    out = both.join(wanted, ["part", "_s"]).withColumn("_r", F.col("_o") + inside - 1).where(F.col("_r") < c.batch_size * c.batches)
    out = out.select(F.expr(f"cast(_r div {c.batch_size} as int)").alias("batch"), "part", (F.col("_r") % c.batch_size).cast("long").alias("seq"), "u", "v", "v_part", F.lit(0).alias("age"))
    return Sample(store(out, "pairs"), short.calls, short.handed, short.met, idle)

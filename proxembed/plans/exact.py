"""Queries whose results DuckDB repeats: each function has its SQL beside it in `SQL`."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from proxembed.functions.rng import AUGMENT, NEGATIVE, PRUNE, ROOT, STEP, draw_sql
from proxembed.functions.vectors import sigmoid, vec_dot
from proxembed.operators import evaluate, measure, pairs, partition, quota, sampling, variants, walks
from proxembed.operators.graph import Graph
from proxembed.operators.train import TrainConfig, batch_changes
from proxembed.sources import builders

P, SEED = 4, 7
_GRAPHS: dict[tuple, Graph] = {}

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(sql: str) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f.__name__], SQL[f.__name__] = f, sql
        return f

    return add


def graph(spark: SparkSession, d: str, name: str, parts: int = P) -> Graph:
    """A graph cut by vertices, built once a session and kept in stored tables."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _GRAPHS:
        _GRAPHS[key] = builders.graph(spark, d, name)
    return partition.cut_by_vertex(_GRAPHS[key], parts)


def longs(df: DataFrame) -> DataFrame:
    return df.select(*[F.col(c).cast("long").alias(c) if t in ("int", "tinyint", "smallint") else F.col(c) for c, t in df.dtypes])


def base(name: str, parts: int = P, recursive: bool = False) -> str:
    """CTEs up to vertices and edges of a graph cut by vertices."""
    own = lambda c: f"({c} * {parts}) // (SELECT count(*) FROM named)"
    return f"""WITH {'RECURSIVE ' if recursive else ''}{builders.edges_sql(name)},
named AS (SELECT key, row_number() OVER (ORDER BY key) - 1 AS vid FROM (SELECT a AS key FROM canon UNION SELECT b FROM canon)),
ends AS (SELECT x.vid AS u, y.vid AS v, w FROM canon JOIN named x ON canon.a = x.key JOIN named y ON canon.b = y.key),
edges AS (SELECT src, dst, w, {own('src')} AS src_part, {own('dst')} AS dst_part FROM (SELECT u AS src, v AS dst, w FROM ends UNION ALL SELECT v, u, w FROM ends)),
vertices AS (SELECT named.vid, key, deg, wdeg, {own('named.vid')} AS part FROM named JOIN (SELECT src AS vid, count(*) AS deg, sum(w)::BIGINT AS wdeg FROM edges GROUP BY src) USING (vid))"""


NOISE = "noise AS (SELECT vid, part, qw, sum(qw) OVER (ORDER BY part, vid)::BIGINT - qw AS lo, sum(qw) OVER (ORDER BY part, vid)::BIGINT AS hi, sum(qw) OVER ()::BIGINT AS total FROM (SELECT vid, part, round(power(deg, 0.75) * 1e6)::BIGINT AS qw FROM vertices))"


def roots_cte(batches: int, rounds: int) -> str:
    return f"""ranges AS (SELECT src_part AS part, src AS u, dst AS v, dst_part AS v_part, sum(w) OVER (PARTITION BY src_part ORDER BY src, dst)::BIGINT - w AS lo, sum(w) OVER (PARTITION BY src_part ORDER BY src, dst)::BIGINT AS hi, sum(w) OVER (PARTITION BY src_part)::BIGINT AS total FROM edges),
asked AS (SELECT batch, round, part, total, {draw_sql(SEED, ROOT, 'batch', 'part', 'round')} % total AS r FROM (SELECT range AS batch FROM range({batches})), (SELECT range AS round FROM range({rounds})), (SELECT DISTINCT part, total FROM ranges)),
roots AS (SELECT batch, round, a.part, (batch * 1048576 + round) * {P} + a.part AS walk_id, u, v, v_part FROM asked a JOIN ranges r ON a.part = r.part AND a.r >= r.lo AND a.r < r.hi)"""


def walk_cte(length: int, local: bool) -> str:
    first, later = ("WHERE v_part = part", "AND n.dst_part = x.part0") if local else ("", "")
    d = draw_sql(SEED, STEP, "x.walk_id", "x.step + 1")
    return f"""near AS (SELECT src, dst, dst_part, sum(w) OVER (PARTITION BY src ORDER BY dst)::BIGINT - w AS lo, sum(w) OVER (PARTITION BY src ORDER BY dst)::BIGINT AS hi, sum(w) OVER (PARTITION BY src)::BIGINT AS total FROM edges),
steps AS (SELECT walk_id, part AS part0, 0::BIGINT AS step, u AS src, v AS dst, part AS src_part, v_part AS dst_part FROM roots {first}
UNION ALL SELECT x.walk_id, x.part0, x.step + 1, x.dst, n.dst, x.dst_part, n.dst_part FROM steps x JOIN near n ON n.src = x.dst AND {d} % n.total >= n.lo AND {d} % n.total < n.hi {later} WHERE x.step + 1 < {length})"""


# Graphs


def _edges_query(name: str) -> None:
    QUERIES[f"graph_{name}_edges"] = lambda spark, d: builders.canonical(spark, d, name)
    SQL[f"graph_{name}_edges"] = f"WITH {builders.edges_sql(name)} SELECT a, b, w FROM canon"


for _name in builders.BUILDERS:
    _edges_query(_name)


@query(f"{base('customer_part')} SELECT key, vid, deg, wdeg FROM vertices")
def degrees(spark: SparkSession, d: str) -> DataFrame:
    return graph(spark, d, "customer_part").vertices.select("key", "vid", "deg", "wdeg")


@query(f"{base('geography')} SELECT count(*) AS n, (sum(deg) // 2)::BIGINT AS m, avg(deg) AS deg_mean, max(deg) AS deg_max, (SELECT count(DISTINCT CASE WHEN substr(key, 1, 1) = 'r' THEN key END) FROM vertices) AS parts FROM vertices")
def graph_summary(spark: SparkSession, d: str) -> DataFrame:
    from proxembed.operators.graph import components, describe

    g = graph(spark, d, "geography")
    one = describe(g).select("n", "m", F.col("deg_mean"), "deg_max")
    return one.crossJoin(components(g).agg(F.countDistinct("label").alias("parts")))  # one row each


# Cuts


@query(f"{base('customer_part')} SELECT vid, part FROM vertices")
def cut_by_vertex(spark: SparkSession, d: str) -> DataFrame:
    return longs(graph(spark, d, "customer_part").vertices.select("vid", "part"))


_FIT = f"fit AS (SELECT vid, deg, least({P - 1}, ((sum(deg) OVER (ORDER BY vid) - deg) * {P}) // sum(deg) OVER ())::BIGINT AS part FROM vertices)"


@query(f"{base('part_supplier')}, {_FIT} SELECT vid, deg, part FROM fit")
def cut_by_edges(spark: SparkSession, d: str) -> DataFrame:
    return longs(partition.first_fit(graph(spark, d, "part_supplier"), P).select("vid", "deg", "part"))


@query(f"{base('geography')}, {_FIT}, loads AS (SELECT part, sum(deg) AS load FROM fit GROUP BY part) SELECT 'geography' AS graph, (count(*) = {P} AND max(load) <= 1.1 * sum(load) / {P}) AS balanced FROM loads")
def cut_fallback(spark: SparkSession, d: str) -> DataFrame:
    _, balanced = partition.cut_by_edges(graph(spark, d, "geography"), P)
    return spark.createDataFrame([("geography", balanced)], "graph string, balanced boolean")


def _spread_sql(name: str, ps: list[int]) -> str:
    one = "SELECT {p} AS p, round(sqrt(greatest(sum(l * l) / {p}::DOUBLE - power(sum(l) / {p}::DOUBLE, 2), 0)), 6) AS sigma, min(l)::BIGINT AS least, max(l)::BIGINT AS most, round(sum(l) / {p}::DOUBLE, 6) AS mean FROM (SELECT k, coalesce(sum(deg), 0)::DOUBLE AS l FROM (SELECT range AS k FROM range({p})) LEFT JOIN vertices ON (vid * {p}) // (SELECT count(*) FROM vertices) = k GROUP BY k)"
    return f"{base(name)} " + " UNION ALL ".join(one.format(p=p) for p in ps)


@query(_spread_sql("customer_part", [4, 16, 64]))
def edge_spread(spark: SparkSession, d: str) -> DataFrame:
    return partition.edge_spread(graph(spark, d, "customer_part"), [4, 16, 64])


@query(f"{base('customer_part')} SELECT DISTINCT src_part AS part, dst AS vid FROM edges WHERE src_part <> dst_part")
def ghosts(spark: SparkSession, d: str) -> DataFrame:
    return longs(partition.ghosts(graph(spark, d, "customer_part")))


@query(f"{base('customer_part')} SELECT src_part AS part, dst_part AS other, count(*) AS edges FROM edges WHERE src_part <> dst_part GROUP BY 1, 2")
def part_links(spark: SparkSession, d: str) -> DataFrame:
    return longs(partition.part_links(graph(spark, d, "customer_part")))


# Draws


@query(f"{base('customer_part')}, {NOISE} SELECT vid, part, qw FROM noise")
def noise_weights(spark: SparkSession, d: str) -> DataFrame:
    return longs(sampling.noise(graph(spark, d, "customer_part")).select("vid", "part", "qw"))


@query(f"{base('geography')}, {NOISE} SELECT vid, round(qw / total, 6) AS q FROM noise")
def noise_probability(spark: SparkSession, d: str) -> DataFrame:
    return sampling.noise_probability(graph(spark, d, "geography"))


@query(f"{base('part_supplier')} SELECT src, (ceil(count(*) / 64))::BIGINT AS chunks, sum(w)::BIGINT AS wdeg, count(*) AS deg FROM edges GROUP BY src")
def neighbor_chunks(spark: SparkSession, d: str) -> DataFrame:
    """A vertex's slices cover its neighbours: distinct neighbours, last bound and number of slices, from the index."""
    rows = sampling.neighbor_index(graph(spark, d, "part_supplier"), 64)
    items = rows.select("src", "chunk", F.explode("items").alias("i"))
    return items.groupBy("src").agg((F.max("chunk") + 1).alias("chunks"), F.max("i.hi").alias("wdeg"), F.countDistinct("i.dst").alias("deg"))


def _roots(spark: SparkSession, d: str, batches: int = 3, rounds: int = 2) -> DataFrame:
    return sampling.roots(graph(spark, d, "customer_part"), batches, rounds, SEED, "md5")


@query(f"{base('customer_part')}, {roots_cte(3, 2)} SELECT batch, round, part, walk_id, u, v, v_part FROM roots")
def root_edges(spark: SparkSession, d: str) -> DataFrame:
    return longs(_roots(spark, d))


#: Positive pairs of the draw queries: root edges numbered inside their part.
PAIRS = "pairs AS (SELECT batch, part, round AS seq, u, v, v_part FROM roots)"


def _pairs(spark: SparkSession, d: str) -> DataFrame:
    return _roots(spark, d, 3, 40).select("batch", "part", F.col("round").cast("long").alias("seq"), "u", "v", "v_part")


_NEG = f"{PAIRS}, {NOISE}, asked2 AS (SELECT batch, part, seq, u, j, {draw_sql(SEED, NEGATIVE, 'batch', 'part', 'seq', 'j')} AS d FROM pairs, (SELECT unnest([1, 2]) AS j)), neg AS (SELECT batch, a.part, seq, j, u, vid AS v, n.part AS v_part FROM asked2 a JOIN noise n ON a.d % n.total >= n.lo AND a.d % n.total < n.hi)"


@query(f"{base('customer_part')}, {roots_cte(3, 40)}, {_NEG} SELECT batch, part, seq, j, u, v, v_part FROM neg")
def negatives_global(spark: SparkSession, d: str) -> DataFrame:
    return longs(sampling.negatives(_pairs(spark, d), graph(spark, d, "customer_part"), 2, seed=SEED, backend="md5"))


@query(f"{base('customer_part')}, {roots_cte(3, 40)}, {_NEG} SELECT batch, part, seq, j, u, v, v_part FROM neg WHERE u <> v AND NOT EXISTS (SELECT 1 FROM edges e WHERE e.src = neg.u AND e.dst = neg.v)")
def negatives_reject(spark: SparkSession, d: str) -> DataFrame:
    return longs(sampling.negatives(_pairs(spark, d), graph(spark, d, "customer_part"), 2, seed=SEED, backend="md5", reject_edges=True))


def _scoped(reach: str) -> str:
    return f"""{base('geography')}, {roots_cte(3, 40)}, {PAIRS}, {NOISE}, reach AS ({reach}),
span AS (SELECT r.part, n.vid, n.part AS v_part, sum(qw) OVER (PARTITION BY r.part ORDER BY n.part, n.vid)::BIGINT - qw AS lo, sum(qw) OVER (PARTITION BY r.part ORDER BY n.part, n.vid)::BIGINT AS hi, sum(qw) OVER (PARTITION BY r.part)::BIGINT AS total FROM reach r JOIN noise n ON n.part = r.other),
asked2 AS (SELECT batch, part, seq, u, j, {draw_sql(SEED, NEGATIVE, 'batch', 'part', 'seq', 'j')} AS d FROM pairs, (SELECT unnest([1, 2]) AS j))
SELECT batch, a.part, seq, j, u, s.vid AS v, s.v_part FROM asked2 a JOIN span s ON a.part = s.part AND a.d % s.total >= s.lo AND a.d % s.total < s.hi"""


def _geo_pairs(spark: SparkSession, d: str) -> DataFrame:
    r = sampling.roots(graph(spark, d, "geography"), 3, 40, SEED, "md5")
    return r.select("batch", "part", F.col("round").cast("long").alias("seq"), "u", "v", "v_part")


@query(_scoped("SELECT DISTINCT src_part AS part, dst_part AS other FROM edges WHERE src_part <> dst_part UNION SELECT DISTINCT part, part FROM vertices"))
def negatives_adjacent(spark: SparkSession, d: str) -> DataFrame:
    return longs(sampling.negatives(_geo_pairs(spark, d), graph(spark, d, "geography"), 2, seed=SEED, backend="md5", scope="adjacent"))


@query(_scoped("SELECT DISTINCT part, part AS other FROM vertices"))
def negatives_local(spark: SparkSession, d: str) -> DataFrame:
    return longs(sampling.negatives(_geo_pairs(spark, d), graph(spark, d, "geography"), 2, seed=SEED, backend="md5", scope="local"))


# Walks


def _walk(spark: SparkSession, d: str, stop: str, engine: str = "join", length: int = 5) -> DataFrame:
    g = graph(spark, d, "customer_part")
    r = sampling.roots(g, 2, 20, SEED, "md5")
    if engine == "block":
        return walks.walk_block(g, r, length, stop, SEED, "md5")
    return walks.walk_join(sampling.neighbor_index(g), r, length, stop, seed=SEED, backend="md5")


_STEPS = "SELECT walk_id, part0, step, src, dst, src_part, dst_part FROM steps"


@query(f"{base('customer_part', recursive=True)}, {roots_cte(2, 20)}, {walk_cte(5, False)} {_STEPS}")
def walk_steps_small(spark: SparkSession, d: str) -> DataFrame:
    return longs(_walk(spark, d, "length"))


@query(f"{base('customer_part', recursive=True)}, {roots_cte(2, 20)}, {walk_cte(5, False)} {_STEPS}")
def walk_steps_block(spark: SparkSession, d: str) -> DataFrame:
    return longs(_walk(spark, d, "length", "block"))


@query(f"{base('customer_part', recursive=True)}, {roots_cte(2, 20)}, {walk_cte(5, True)} {_STEPS}")
def walk_local_small(spark: SparkSession, d: str) -> DataFrame:
    return longs(_walk(spark, d, "boundary", "block"))


@query(f"{base('customer_part', recursive=True)}, {roots_cte(2, 20)}, {walk_cte(5, False)} SELECT x.walk_id, x.step, y.step - x.step + 1 AS hop, x.src_part AS part, x.src AS u, y.dst AS v, y.dst_part AS v_part FROM steps x JOIN steps y ON x.walk_id = y.walk_id AND y.step BETWEEN x.step AND x.step + 2")
def walk_pairs_window(spark: SparkSession, d: str) -> DataFrame:
    return longs(walks.walk_pairs(_walk(spark, d, "length", "block"), 3, "hops"))


_BD = draw_sql(SEED, STEP, "x.walk_id", "x.step + 1")


@query(f"""{base('geography', recursive=True)}, {roots_cte(2, 10)},
turns AS (SELECT p.src AS t, p.dst AS v, n.dst AS x, n.dst_part, greatest(1, round(n.w * CASE WHEN n.dst = p.src THEN 2.0 WHEN k.dst IS NOT NULL THEN 1.0 ELSE 0.5 END * 1000))::BIGINT AS bw FROM edges p JOIN edges n ON n.src = p.dst LEFT JOIN edges k ON k.src = p.src AND k.dst = n.dst),
odds AS (SELECT t, v, x, dst_part, sum(bw) OVER (PARTITION BY t, v ORDER BY x)::BIGINT - bw AS lo, sum(bw) OVER (PARTITION BY t, v ORDER BY x)::BIGINT AS hi, sum(bw) OVER (PARTITION BY t, v)::BIGINT AS total FROM turns),
steps AS (SELECT walk_id, part AS part0, 0::BIGINT AS step, u AS src, v AS dst, part AS src_part, v_part AS dst_part FROM roots UNION ALL SELECT x.walk_id, x.part0, x.step + 1, x.dst, o.x, x.dst_part, o.dst_part FROM steps x JOIN odds o ON o.t = x.src AND o.v = x.dst AND {_BD} % o.total >= o.lo AND {_BD} % o.total < o.hi WHERE x.step + 1 < 4) {_STEPS}""")
def biased_walk_small(spark: SparkSession, d: str) -> DataFrame:
    g = graph(spark, d, "geography")
    return longs(walks.biased_walk(g, sampling.roots(g, 2, 10, SEED, "md5"), 4, 0.5, 2.0, SEED, "md5"))


# Stop rules and variants


def _fold_ctes(rule: str, keep: str, size: int, batches: int, n_calls: int) -> str:
    """`slices` from `calls` (call, part, pairs): the fold as recursion over batches with lists of starts."""
    some = {"any": "list_max", "all": "list_min"}[rule]
    first = "f.upto" if keep == "ever" else "f.upto + 1"
    taken = f"f.start[i] + least(c.b[i] - f.start[i], {size})"
    after = {"ever": taken, "once": f"greatest({taken}, f.b[i])", "none": "c.b[i]"}[keep]
    left = "0" if keep == "none" else f"c.b[i] - ({after})"
    zeros, four = "[0, 0, 0, 0]::BIGINT[]", "[1, 2, 3, 4]"
    return f"""grid AS (SELECT c.range AS call, p.range AS part FROM range({n_calls}) c, range(4) p),
cum AS (SELECT call + 1 AS upto, list(total ORDER BY part) AS b FROM (SELECT g.call, g.part, sum(coalesce(pairs, 0)) OVER (PARTITION BY g.part ORDER BY g.call)::BIGINT AS total FROM grid g LEFT JOIN calls USING (call, part)) GROUP BY call UNION ALL SELECT 0, {zeros}),
fold AS (SELECT -1::BIGINT AS batch, 0::BIGINT AS upto, 0::BIGINT AS calls, {zeros} AS start, {zeros} AS b, {zeros} AS began, {zeros} AS kept, {zeros} AS spill
UNION ALL SELECT f.batch + 1, c.upto, c.upto - f.upto, list_transform({four}, lambda i: {after}), c.b, f.start, list_transform({four}, lambda i: least(c.b[i] - f.start[i], {size})), list_transform({four}, lambda i: {left})
FROM fold f JOIN cum c ON c.upto >= {first} AND {some}(list_transform({four}, lambda i: c.b[i] - f.start[i])) >= {size} WHERE f.batch + 1 < {batches} QUALIFY row_number() OVER (PARTITION BY f.batch ORDER BY c.upto) = 1),
slices AS (SELECT batch, i - 1 AS part, calls, began[i] AS start, kept[i] AS kept, spill[i] AS spill FROM fold, (SELECT unnest({four}) AS i) WHERE batch >= 0)"""


#: The graph, batch size and batches of the variants' queries, and how many calls their SQL draws (Spark draws as many as it needs).
SAMPLED, SIZE, BATCHES, CALLS, LOCAL_CALLS = "copurchase", 12, 2, 48, 320
LONG = 1500


def _drawn_ctes(local: bool, batches: int) -> str:
    return f"""{base(SAMPLED, recursive=True)}, {roots_cte(batches, LOCAL_CALLS if local else CALLS)}, {walk_cte(5, local)},
drawn AS (SELECT (walk_id // {P}) // 1048576 AS batch, (walk_id // {P}) % 1048576 AS round, src_part AS part, walk_id, step, src AS u, dst AS v, dst_part AS v_part FROM steps)"""


def _own_ctes(local: bool, reach: str, size: int, batches: int) -> str:
    """`taken`: pairs of batches that share nothing, by rule and pruned."""
    d = draw_sql(SEED, PRUNE, "batch", "part", "seq")
    return f"""{_drawn_ctes(local, batches)},
grid AS (SELECT b.range AS batch, r.range AS round, p.range AS part FROM range({batches}) b, range({LOCAL_CALLS if local else CALLS}) r, range({P}) p),
yields AS (SELECT g.batch, g.round, g.part, count(walk_id) AS pairs FROM grid g LEFT JOIN drawn USING (batch, round, part) GROUP BY ALL),
run AS (SELECT batch, part, round, sum(pairs) OVER (PARTITION BY batch, part ORDER BY round) AS total FROM yields),
met AS (SELECT batch, min(round) + 1 AS rounds FROM (SELECT batch, round, {reach}(total) AS x FROM run GROUP BY batch, round) WHERE x >= {size} GROUP BY batch),
kept AS (SELECT d.*, row_number() OVER (PARTITION BY batch, part ORDER BY round, walk_id, step) - 1 AS seq FROM drawn d JOIN met USING (batch) WHERE round < rounds),
pruned AS (SELECT *, row_number() OVER (PARTITION BY batch, part ORDER BY {d}, seq) - 1 AS place FROM kept),
taken AS (SELECT batch, part, place AS seq, u, v, v_part, 0::BIGINT AS age FROM pruned WHERE place < {size})"""


def _sample_sql(variant: variants.Variant) -> str:
    columns = "SELECT batch, part, seq, u, v, v_part, age"
    if variant.kind in ("local", "fresh"):
        return f"{_own_ctes(variant.kind == 'local', {'any': 'max', 'all': 'min'}[variant.rule], SIZE, BATCHES)} {columns} FROM taken"
    if variant.kind in ("reuse", "refresh"):
        return f"""{_drawn_ctes(False, 1)}, calls AS (SELECT round AS call, part, count(*) AS pairs FROM drawn GROUP BY ALL),
{_fold_ctes(variant.rule, {'reuse': 'ever', 'refresh': 'once'}[variant.kind], SIZE, BATCHES, CALLS)},
placed AS (SELECT part, round, u, v, v_part, row_number() OVER (PARTITION BY part ORDER BY round, walk_id, step) - 1 AS pos FROM drawn),
span AS (SELECT batch, sum(calls) OVER (ORDER BY batch) - calls AS lo, sum(calls) OVER (ORDER BY batch) AS hi FROM (SELECT DISTINCT batch, calls FROM slices))
SELECT s.batch, s.part, row_number() OVER (PARTITION BY s.batch, s.part ORDER BY pos) - 1 AS seq, u, v, v_part, s.batch - d.batch AS age FROM slices s JOIN placed o ON o.part = s.part AND pos >= start AND pos < start + kept JOIN span d ON round >= lo AND round < hi"""
    if variant.kind == "single":
        return f"""{base(SAMPLED, recursive=True)}, {roots_cte(1, 1).replace('roots AS (', 'all_roots AS (')}, roots AS (SELECT * FROM all_roots WHERE part = 0), {walk_cte(LONG, False)},
numbered AS (SELECT src_part AS part, src AS u, dst AS v, dst_part AS v_part, row_number() OVER (PARTITION BY src_part ORDER BY step) - 1 AS place FROM steps)
SELECT place // {SIZE} AS batch, part, place % {SIZE} AS seq, u, v, v_part, 0::BIGINT AS age FROM numbered WHERE place < {SIZE * BATCHES}"""
    n = variants.aug_target(SIZE, BATCHES)
    d = draw_sql(SEED, AUGMENT, "x.part", "x.seq", "y.seq")
    return f"""{_own_ctes(False, 'min', n, 1)},
combined AS (SELECT x.part, x.u, y.v, y.v_part, row_number() OVER (PARTITION BY x.part ORDER BY {d}, x.seq, y.seq) - 1 AS place FROM taken x JOIN taken y ON x.part = y.part AND x.seq < y.seq)
SELECT place // {SIZE} AS batch, part, place % {SIZE} AS seq, u, v, v_part, 0::BIGINT AS age FROM combined WHERE place < {SIZE * BATCHES}"""


def _sample(spark: SparkSession, d: str, variant: variants.Variant) -> variants.Sample:
    c = variants.SampleConfig(batch_size=SIZE, batches=BATCHES, length=5, seed=SEED, backend="md5", rounds=16, max_levels=250)
    return variants.sample(graph(spark, d, SAMPLED), variant, c)


def _sample_query(variant: variants.Variant) -> None:
    name = f"sample_{variant.kind}_{variant.rule}_pairs"
    QUERIES[name] = lambda spark, d: longs(_sample(spark, d, variant).pairs)
    SQL[name] = _sample_sql(variant)


for _variant in variants.GRID:
    _sample_query(_variant)


def _yields_ctes() -> str:
    """`yields` (batch, round, part, pairs) of the walks that the variants' queries draw."""
    return f"""{_drawn_ctes(False, 3)}, yields AS (SELECT b.range AS batch, r.range AS round, p.range AS part, count(walk_id) AS pairs FROM range(3) b CROSS JOIN range({CALLS}) r CROSS JOIN range({P}) p LEFT JOIN drawn x ON x.batch = b.range AND x.round = r.range AND x.part = p.range GROUP BY ALL)"""


def _yields(spark: SparkSession, d: str) -> DataFrame:
    g = graph(spark, d, SAMPLED)
    return variants.call_yields(g, variants.SampleConfig(length=5, seed=SEED, backend="md5"), 3, CALLS)


def _rounds_sql(size: int, reach: str) -> str:
    return f"{_yields_ctes()}, run AS (SELECT batch, part, round, sum(pairs) OVER (PARTITION BY batch, part ORDER BY round) AS total FROM yields), per AS (SELECT batch, round, {reach}(total) AS x FROM run GROUP BY batch, round) SELECT batch, min(CASE WHEN x >= {size} THEN round + 1 END)::BIGINT AS rounds FROM per GROUP BY batch"


@query(_rounds_sql(40, "max"))
def rounds_any(spark: SparkSession, d: str) -> DataFrame:
    return longs(quota.rounds_needed(_yields(spark, d), 40, "any"))


@query(_rounds_sql(40, "min"))
def rounds_all(spark: SparkSession, d: str) -> DataFrame:
    return longs(quota.rounds_needed(_yields(spark, d), 40, "all"))


_CALLS = f"calls AS (SELECT batch * {CALLS} + round AS call, part, pairs FROM yields)"


def _calls(spark: SparkSession, d: str) -> DataFrame:
    return _yields(spark, d).select((F.col("batch") * CALLS + F.col("round")).alias("call"), "part", "pairs")


def _fold_query(name: str, rule: str, keep: str) -> None:
    QUERIES[name] = lambda spark, d: quota.spill_slices(_calls(spark, d), P, 60, 5, rule, keep)
    SQL[name] = f"{_yields_ctes()}, {_CALLS}, {_fold_ctes(rule, keep, 60, 5, 3 * CALLS)} SELECT batch, part, calls, start, kept, spill FROM slices"


for _name, _keep in (("fresh", "none"), ("reuse", "ever"), ("refresh", "once")):
    for _rule in ("any", "all"):
        _fold_query(f"sample_{_name}_slices_{_rule}", _rule, _keep)


@query(f"{_yields_ctes()}, {_CALLS}, run AS (SELECT part, call, sum(pairs) OVER (PARTITION BY part ORDER BY call) AS total FROM calls), low AS (SELECT call, min(total) AS low FROM run GROUP BY call) SELECT b.range AS batch, (min(call) + 1)::BIGINT AS calls_by_then FROM range(5) b JOIN low ON low >= (b.range + 1) * 60 GROUP BY b.range")
def reuse_all_closed_form(spark: SparkSession, d: str) -> DataFrame:
    return quota.reuse_all_closed_form(_calls(spark, d), 60, 5)


@query(f"{base('customer_part')}, {roots_cte(3, 40)}, {PAIRS} SELECT batch, part, place AS seq, u, v, v_part FROM (SELECT *, row_number() OVER (PARTITION BY batch, part ORDER BY {draw_sql(SEED, PRUNE, 'batch', 'part', 'seq')}, seq) - 1 AS place FROM pairs) WHERE place < 25")
def prune_to_batch(spark: SparkSession, d: str) -> DataFrame:
    return longs(pairs.prune(_pairs(spark, d), 25, SEED, "md5"))


@query(f"{base('customer_part')}, {roots_cte(3, 40)}, {PAIRS} SELECT DISTINCT batch, v_part AS part, v, part AS to_part FROM pairs WHERE v_part <> part")
def serve_list(spark: SparkSession, d: str) -> DataFrame:
    return longs(pairs.serve_list(_pairs(spark, d)))


# Measures


@query(f"{base('customer_part')}, {roots_cte(3, 40)}, {_NEG} SELECT sign, round(avg((v_part <> part)::INT), 6) AS share FROM (SELECT part, v_part, 1::BIGINT AS sign FROM pairs UNION ALL SELECT part, v_part, -1 FROM neg) GROUP BY sign")
def remote_share(spark: SparkSession, d: str) -> DataFrame:
    from proxembed.operators.train import signed

    p = _pairs(spark, d)
    return longs(measure.remote_share(signed(p, sampling.negatives(p, graph(spark, d, "customer_part"), 2, seed=SEED, backend="md5"))))


ANY_FRESH, ANY_REUSE = variants.Variant("any", "fresh"), variants.Variant("any", "reuse")


@query(f"WITH picked AS ({_sample_sql(ANY_FRESH)}), per AS (SELECT b.range, p.range AS q, count(x.part) AS n FROM range({BATCHES}) b CROSS JOIN range({P}) p LEFT JOIN picked x ON x.batch = b.range AND x.part = p.range GROUP BY 1, 2) SELECT min(n) AS least, max(n) AS most, round(avg(n), 6) AS mean, round(stddev_pop(n), 6) AS sigma, CASE WHEN min(n) > 0 THEN round(max(n) / min(n), 6) END AS ratio, round(100 * (max(n) - min(n)) / avg(n), 6) AS spread_percent, sum((n = 0)::INT)::BIGINT AS zero_parts FROM per")
def sample_spread(spark: SparkSession, d: str) -> DataFrame:
    return measure.sample_spread(_sample(spark, d, ANY_FRESH).pairs, P, BATCHES)


@query(f"{base('customer_part')}, held AS (SELECT DISTINCT src_part FROM edges WHERE src_part = dst_part) SELECT range AS part FROM range({P}) WHERE range NOT IN (SELECT src_part FROM held)")
def zero_sample_parts(spark: SparkSession, d: str) -> DataFrame:
    """Parts that Local can't fill: a two-sided graph cut by id ranges has hardly an inner edge."""
    g = graph(spark, d, "customer_part")
    return longs(quota.idle_parts(Graph(g.vertices, g.edges.where("src_part = dst_part"), g.n, g.parts), P))


_AUG = "two AS (SELECT x.part, x.u, y.v FROM pairs x JOIN pairs y ON x.part = y.part AND x.batch = y.batch AND x.seq < y.seq)"


@query(f"{base('customer_part')}, {roots_cte(1, 40)}, {PAIRS}, {_AUG} SELECT count(*) AS n, sum((e.src IS NULL)::INT)::BIGINT AS wrong, round(sum((e.src IS NULL)::INT) / count(*), 6) AS share FROM two LEFT JOIN edges e ON e.src = two.u AND e.dst = two.v")
def false_positive_share(spark: SparkSession, d: str) -> DataFrame:
    p = _roots(spark, d, 1, 40).select("part", F.col("round").alias("i"), "u", "v")
    both = p.select("part", "i", "u").join(p.select("part", F.col("i").alias("j"), "v"), "part").where("i < j")
    return measure.false_positive_share(both, graph(spark, d, "customer_part"))


@query(f"SELECT batch, round(avg((age > 0)::INT), 6) AS spilled_share, round(avg(age), 6) AS mean_age FROM ({_sample_sql(ANY_REUSE)}) GROUP BY batch")
def spill_age(spark: SparkSession, d: str) -> DataFrame:
    return longs(measure.staleness(_sample(spark, d, ANY_REUSE).pairs))


@query("SELECT n_nationkey + 2 AS p, n_regionkey + 1 AS calls, round(60 * ((n_regionkey + 1) * (log2(n_nationkey + 2) + (n_nationkey + 2) * 128) + (n_nationkey + 2) * 1000), 6) AS cost FROM nation")
def cost_formula(spark: SparkSession, d: str) -> DataFrame:
    n = builders.table(spark, d, "nation").select((F.col("n_nationkey") + 2).alias("p"), (F.col("n_regionkey") + 1).alias("calls"))
    return n.withColumn("cost", F.round(measure.cost_formula(F.col("p"), F.lit(128), F.col("calls"), F.lit(1000), F.lit(60)), 6))


_DOT = "list_dot_product(x.embedding::DOUBLE[], y.embedding::DOUBLE[])"


@query(f"SELECT x.vec_id AS u, y.vec_id AS v, round({_DOT}, 6) AS dot, round(1 / (1 + exp(-{_DOT})), 6) AS proximity FROM embeddings x JOIN embeddings y ON y.vec_id = x.vec_id + 7")
def pair_scores(spark: SparkSession, d: str) -> DataFrame:
    e = builders.table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    both = e.join(e.select((F.col("vec_id") - 7).alias("vec_id"), F.col("x").alias("y")), "vec_id")
    dot = vec_dot(F.col("x"), F.col("y"))
    return both.select(F.col("vec_id").alias("u"), (F.col("vec_id") + 7).alias("v"), F.round(dot, 6).alias("dot"), F.round(sigmoid(dot), 6).alias("proximity"))


#: One deferred batch on the given vectors, taken as both U and C: pairs (i, i * 3 + 1 mod n), sign by parity.
_BATCH = "rows AS (SELECT vec_id AS u, (vec_id * 3 + 1) % (SELECT count(*) FROM embeddings) AS v, CASE WHEN vec_id % 2 = 0 THEN 1 ELSE -1 END AS sign FROM embeddings)"


def _batch_sql(side: str) -> str:
    own, other = ("x", "y") if side == "u" else ("y", "x")
    return f"""WITH {_BATCH}, g AS (SELECT r.u, r.v, x.embedding::DOUBLE[] AS x, y.embedding::DOUBLE[] AS y, CASE WHEN sign > 0 THEN 0.025 * (1 - 1 / (1 + exp(-{_DOT}))) ELSE -0.025 / (1 + exp(-{_DOT})) END AS g FROM rows r JOIN embeddings x ON x.vec_id = r.u JOIN embeddings y ON y.vec_id = r.v),
d AS (SELECT {side} AS vid, i, sum(g * {other}[i] - 0.0000025 * {own}[i]) AS s FROM g, (SELECT unnest(range(1, 65)) AS i) GROUP BY {side}, i)
SELECT vid, i - 1 AS i, round(s, 6) AS s FROM d"""


def _one_batch(spark: SparkSession, d: str, side: int) -> DataFrame:
    e = builders.table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    n = e.agg(F.count("*").alias("n"))
    rows = e.crossJoin(F.broadcast(n)).select(F.col("vec_id").alias("u"), F.expr("(vec_id * 3 + 1) % n").alias("v"), F.when(F.col("vec_id") % 2 == 0, 1).otherwise(-1).alias("sign"))  # one row
    changes = batch_changes(e.select(F.col("vec_id").alias("vid"), F.col("x").alias("u"), F.col("x").alias("c")), rows, TrainConfig())[side]
    return longs(changes.select("vid", F.posexplode("du" if side == 0 else "dc").alias("i", "s")).select("vid", "i", F.round("s", 6).alias("s")))


@query(_batch_sql("u"))
def one_step_gradient(spark: SparkSession, d: str) -> DataFrame:
    return _one_batch(spark, d, 0)


@query(_batch_sql("v"))
def delta_sums(spark: SparkSession, d: str) -> DataFrame:
    return _one_batch(spark, d, 1)


@query("SELECT q, rank, vid, score FROM (SELECT x.vec_id AS q, y.vec_id AS vid, round(list_dot_product(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) / (sqrt(list_dot_product(x.embedding::DOUBLE[], x.embedding::DOUBLE[])) * sqrt(list_dot_product(y.embedding::DOUBLE[], y.embedding::DOUBLE[]))), 6) AS score, row_number() OVER (PARTITION BY x.vec_id ORDER BY round(list_dot_product(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) / (sqrt(list_dot_product(x.embedding::DOUBLE[], x.embedding::DOUBLE[])) * sqrt(list_dot_product(y.embedding::DOUBLE[], y.embedding::DOUBLE[]))), 6) DESC, y.vec_id) AS rank FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id WHERE x.vec_id % 50 = 0) WHERE rank <= 5")
def nearest_vectors(spark: SparkSession, d: str) -> DataFrame:
    from proxembed.operators.train import nearest

    e = builders.table(spark, d, "embeddings").select(F.col("vec_id").alias("vid"), F.col("embedding").alias("u"))
    return longs(nearest(e, e.where("vid % 50 = 0"), 5))


#: A deterministic prediction for the F1 queries.
_PRED = "pred AS (SELECT p_size % 5 AS label, (p_partkey * 7 + p_size) % 6 AS prediction FROM part)"


def _predicted(spark: SparkSession, d: str) -> DataFrame:
    return builders.table(spark, d, "part").select((F.col("p_size") % 5).alias("label"), ((F.col("p_partkey") * 7 + F.col("p_size")) % 6).alias("prediction"))


@query(f"WITH {_PRED} SELECT label::BIGINT AS label, prediction::BIGINT AS prediction, count(*) AS n FROM pred GROUP BY 1, 2")
def confusion(spark: SparkSession, d: str) -> DataFrame:
    return longs(evaluate.confusion(_predicted(spark, d)))


@query(f"WITH {_PRED}, k AS (SELECT label AS k FROM pred UNION SELECT prediction FROM pred), per AS (SELECT k, sum((label = k AND prediction = k)::INT) AS tp, sum((label = k)::INT) AS r, sum((prediction = k)::INT) AS s FROM pred, k GROUP BY k) SELECT round(sum(tp) / sum(r), 6) AS micro, round(avg(2.0 * tp / (r + s)), 6) AS macro FROM per")
def f1_micro_macro(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.f1(evaluate.confusion(_predicted(spark, d)))


#: Work that can't be shared out further: the largest part's stored edges, for cuts by vertices and by edges.
_TIMES = " UNION ALL ".join(f"SELECT '{g}' AS graph, '{m}' AS method, {p} AS p, max(l)::DOUBLE AS seconds FROM (SELECT sum(deg) AS l FROM (SELECT deg, {own} AS k FROM (SELECT vid, deg, sum(deg) OVER (ORDER BY vid) - deg AS before, sum(deg) OVER () AS total, count(*) OVER () AS n FROM ({base(g)} SELECT vid, deg FROM vertices))) GROUP BY k)"
                            for g in ("customer_part", "part_supplier") for m, own_of in (("vertex", "(vid * {p}) // n"), ("edges", "least({p} - 1, (before * {p}) // total)")) for p in (1, 4, 16) for own in (own_of.format(p=p),))


def _times(spark: SparkSession, d: str) -> DataFrame:
    found = None
    for name in ("customer_part", "part_supplier"):
        g = graph(spark, d, name)
        for p in (1, 4, 16):
            for method, cut in (("vertex", partition.cut_by_vertex(g, p).vertices), ("edges", partition.first_fit(g, p))):
                loads = cut.groupBy("part").agg(F.sum("deg").alias("load"))
                row = loads.agg(F.max("load").cast("double").alias("seconds")).select(F.lit(name).alias("graph"), F.lit(method).alias("method"), F.lit(p).cast("long").alias("p"), "seconds")
                found = row if found is None else found.unionByName(row)
    return found


@query(f"WITH times AS ({_TIMES}) SELECT graph, method, p::BIGINT AS p, round(first_value(seconds) OVER (PARTITION BY graph, method ORDER BY p) / seconds, 6) AS self_speedup, round(max(seconds) OVER (PARTITION BY graph, p) / seconds, 6) AS over_slowest FROM times")
def speedup_table(spark: SparkSession, d: str) -> DataFrame:
    """The speed-ups that cuts allow: load of the largest part against one part's."""
    return measure.speedups(_times(spark, d)).drop("seconds")


@query(f"WITH times AS ({_TIMES}) SELECT graph, min(CASE WHEN a < b THEN p END)::BIGINT AS p FROM (SELECT graph, p, max(seconds) FILTER (method = 'edges') AS a, max(seconds) FILTER (method = 'vertex') AS b FROM times GROUP BY graph, p) GROUP BY graph")
def crossover(spark: SparkSession, d: str) -> DataFrame:
    """From how many parts on the cut by edges is the more even one."""
    return measure.crossover(_times(spark, d), "edges", "vertex")


_LOADS = " UNION ALL ".join(f"SELECT '{g}' AS stage, part, sum(deg)::BIGINT AS seconds FROM ({base(g)} SELECT part, deg FROM vertices) GROUP BY part" for g in ("copurchase", "customer_part", "part_supplier"))


@query(f"WITH loads AS ({_LOADS}) SELECT stage, round(100 * sum(seconds) / (SELECT sum(seconds) FROM loads), 6) AS share_percent, round(100 * (max(seconds) - avg(seconds)) / max(seconds) * count(*) / (count(*) - 1), 6) AS imbalance_percent FROM loads GROUP BY stage")
def load_imbalance(spark: SparkSession, d: str) -> DataFrame:
    """Share and imbalance of the parts' loads, a graph a row."""
    found = None
    for name in ("copurchase", "customer_part", "part_supplier"):
        row = graph(spark, d, name).vertices.groupBy("part").agg(F.sum("deg").alias("seconds")).withColumn("stage", F.lit(name))
        found = row if found is None else found.unionByName(row)
    return measure.imbalance(found)


_BOTH = f"SELECT 'fresh' AS variant, * FROM ({_sample_sql(ANY_FRESH)}) UNION ALL SELECT 'reuse', * FROM ({_sample_sql(ANY_REUSE)})"


@query(f"SELECT variant, batch::BIGINT AS batch, part::BIGINT AS part, count(*) AS n, sum((v_part <> part)::INT)::BIGINT AS remote FROM ({_BOTH}) GROUP BY CUBE (variant, batch, part)")
def metrics_cube(spark: SparkSession, d: str) -> DataFrame:
    drawn = [longs(_sample(spark, d, v).pairs).withColumn("variant", F.lit(v.kind)) for v in (ANY_FRESH, ANY_REUSE)]
    return drawn[0].unionByName(drawn[1]).cube("variant", "batch", "part").agg(F.count("*").alias("n"), F.sum((F.col("v_part") != F.col("part")).cast("long")).alias("remote"))


@query(f"{base('customer_part')}, {roots_cte(3, 40)}, one AS (SELECT DISTINCT u, v FROM roots WHERE batch = 0), two AS (SELECT DISTINCT u, v FROM roots WHERE batch = 1) SELECT 'both' AS side, u, v FROM (SELECT * FROM one INTERSECT SELECT * FROM two) UNION ALL SELECT 'first', u, v FROM (SELECT * FROM one EXCEPT SELECT * FROM two) UNION ALL SELECT 'second', u, v FROM (SELECT * FROM two EXCEPT SELECT * FROM one)")
def pair_set_ops(spark: SparkSession, d: str) -> DataFrame:
    r = _roots(spark, d, 3, 40)
    one, two = (r.where(F.col("batch") == b).select("u", "v").distinct() for b in (0, 1))
    tag = lambda df, s: df.select(F.lit(s).alias("side"), "u", "v")
    return tag(one.intersect(two), "both").unionByName(tag(one.subtract(two), "first")).unionByName(tag(two.subtract(one), "second"))


@query("SELECT k AS bucket_u, (k + r) % 8 AS bucket_v, r AS round FROM (SELECT range AS k FROM range(8)), (SELECT range AS r FROM range(8))")
def bucket_schedule(spark: SparkSession, d: str) -> DataFrame:
    from proxembed.operators.baselines import schedule

    return schedule(spark, 8)


# Events


@query("SELECT user_id, epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start_us, props::JSON ->> '$.k' AS k, count(*) AS w FROM events GROUP BY 1, 2, 3")
def event_windows(spark: SparkSession, d: str) -> DataFrame:
    from proxembed.streaming import streams

    return streams.edge_windows(streams.read_events(spark, d)).select("user_id", F.unix_micros("start").alias("start_us"), "k", "w")


@query("WITH e AS (SELECT user_id, ts, (date_diff('microsecond', lag(ts) OVER (PARTITION BY user_id ORDER BY ts), ts) >= 3600000000)::INT AS cut FROM events), s AS (SELECT *, sum(coalesce(cut, 0)) OVER (PARTITION BY user_id ORDER BY ts) AS n FROM e) SELECT user_id, epoch_us(min(ts)) AS start_us, epoch_us(max(ts)) + 3600000000 AS end_us, count(*) AS w FROM s GROUP BY user_id, n")
def event_sessions(spark: SparkSession, d: str) -> DataFrame:
    from proxembed.streaming import streams

    return streams.edge_sessions(streams.read_events(spark, d)).select("user_id", F.unix_micros("start").alias("start_us"), F.unix_micros("end").alias("end_us"), "w")


@query("SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_purchase FROM events")
def event_asof(spark: SparkSession, d: str) -> DataFrame:
    ev = builders.table(spark, d, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return ev.select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("value")), ignorenulls=True).over(w).alias("last_purchase"))


@query("SELECT x.user_id, x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 1 HOUR")
def event_interval_edges(spark: SparkSession, d: str) -> DataFrame:
    from proxembed.streaming import streams

    e = streams.read_events(spark, d)
    return streams.co_events(e, e)


# Reports that users of a graph ask for


@query(f"{base('customer_part')} SELECT vid, place, dst, w FROM (SELECT src AS vid, dst, w, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS place FROM edges) WHERE place <= 3")
def top_neighbors(spark: SparkSession, d: str) -> DataFrame:
    """The three heaviest neighbours of each vertex; Spark limits groups before the shuffle."""
    w = Window.partitionBy("src").orderBy(F.desc("w"), "dst")
    e = graph(spark, d, "customer_part").edges.withColumn("place", F.row_number().over(w)).where("place <= 3")
    return longs(e.select(F.col("src").alias("vid"), "place", "dst", "w"))


@query(f"{base('part_supplier')} SELECT deg, count(*) AS n, sum(count(*)) OVER (ORDER BY deg DESC)::BIGINT AS at_least FROM vertices GROUP BY deg")
def degree_histogram(spark: SparkSession, d: str) -> DataFrame:
    counts = graph(spark, d, "part_supplier").vertices.groupBy("deg").agg(F.count("*").alias("n"))
    return counts.withColumn("at_least", F.sum("n").over(Window.orderBy(F.desc("deg")).rowsBetween(Window.unboundedPreceding, 0)))  # a row for each degree


@query(f"{base('part_supplier')} SELECT v.vid, v.deg, count(*) AS hub_links FROM vertices v JOIN edges e ON e.src = v.vid WHERE v.deg > 5 * (SELECT avg(deg) FROM vertices) AND e.dst IN (SELECT vid FROM vertices WHERE deg < (SELECT avg(deg) FROM vertices)) GROUP BY v.vid, v.deg")
def hubs(spark: SparkSession, d: str) -> DataFrame:
    """Vertices of over five times the mean degree, and how many of their neighbours lie below it."""
    g = graph(spark, d, "part_supplier")
    mean = F.broadcast(g.vertices.agg(F.avg("deg").alias("mean")))  # one row
    v = g.vertices.crossJoin(mean)
    low = v.where("deg < mean").select(F.col("vid").alias("dst"))
    big = v.where("deg > 5 * mean").select("vid", "deg")
    return g.edges.select(F.col("src").alias("vid"), "dst").join(low, "dst", "left_semi").join(big, "vid").groupBy("vid", "deg").agg(F.count("*").alias("hub_links"))


@query(f"{base('customer_part')}, {roots_cte(3, 40)}, {_NEG} SELECT part, count(*) FILTER (v_part = 0) AS to_0, count(*) FILTER (v_part = 1) AS to_1, count(*) FILTER (v_part = 2) AS to_2, count(*) FILTER (v_part = 3) AS to_3 FROM neg GROUP BY part")
def negative_flow(spark: SparkSession, d: str) -> DataFrame:
    """Negatives by owner and target part, pivoted."""
    n = sampling.negatives(_pairs(spark, d), graph(spark, d, "customer_part"), 2, seed=SEED, backend="md5")
    wide = n.groupBy("part").pivot("v_part", list(range(P))).count().na.fill(0)
    return longs(wide.select("part", *[F.col(str(k)).alias(f"to_{k}") for k in range(P)]))


@query(f"WITH v AS ({base('part_supplier')} SELECT vid, deg FROM vertices), x AS (SELECT deg, (vid * 7) // count(*) OVER () AS a, least(6, ((sum(deg) OVER (ORDER BY vid) - deg) * 7) // sum(deg) OVER ())::BIGINT AS b FROM v), one AS (SELECT a AS part, sum(deg)::BIGINT AS n FROM x GROUP BY a), two AS (SELECT b AS part, sum(deg)::BIGINT AS m FROM x GROUP BY b) SELECT part, coalesce(n, 0) AS n, coalesce(m, 0) AS m FROM one FULL JOIN two USING (part)")
def compare_loads(spark: SparkSession, d: str) -> DataFrame:
    """Loads of two cuts side by side; parts that only one has are kept."""
    g = graph(spark, d, "part_supplier")
    one = longs(partition.cut_by_vertex(g, 7).vertices).groupBy("part").agg(F.sum("deg").alias("n"))
    two = longs(partition.first_fit(g, 7)).groupBy("part").agg(F.sum("deg").alias("m"))
    return one.join(two, "part", "full").na.fill(0)


@query("SELECT user_id, epoch_us(s.slide) AS start_us, count(*) AS w FROM events, (SELECT unnest([0, 30]) AS o), LATERAL (SELECT time_bucket(INTERVAL 30 MINUTE, ts) - o * INTERVAL 1 MINUTE AS slide) s GROUP BY 1, 2")
def event_sliding(spark: SparkSession, d: str) -> DataFrame:
    from proxembed.streaming import streams

    ev = streams.read_events(spark, d).withColumn("k", F.lit("x"))
    return streams.edge_windows(ev, "1 hour", "30 minutes").select("user_id", F.unix_micros("start").alias("start_us"), "w")

"""Graphs from the given tables, as (a, b, w) rows of string keys; `SQL` has each one's DuckDB text."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from proxembed.operators.graph import Graph, build, undirect
from proxembed.operators.storage import store


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _key(kind: str, column: Column | str) -> Column:
    return F.concat(F.lit(f"{kind}:"), F.col(column).cast("string") if isinstance(column, str) else column.cast("string"))




def geography(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "customer").select(_key("c", "c_custkey").alias("a"), _key("n", "c_nationkey").alias("b"))
    s = table(spark, d, "supplier").select(_key("s", "s_suppkey").alias("a"), _key("n", "s_nationkey").alias("b"))
    n = table(spark, d, "nation").select(_key("n", "n_nationkey").alias("a"), _key("r", "n_regionkey").alias("b"))
    return c.unionByName(s).unionByName(n).withColumn("w", F.lit(1).cast("long"))


def customer_part(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey")
    joined = li.join(o, li.l_orderkey == o.o_orderkey)
    return joined.groupBy("o_custkey", "l_partkey").agg(F.sum("l_quantity").cast("long").alias("w")).select(_key("c", "o_custkey").alias("a"), _key("p", "l_partkey").alias("b"), "w")


def part_supplier(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem")
    return li.groupBy("l_partkey", "l_suppkey").agg(F.count("*").alias("w")).select(_key("p", "l_partkey").alias("a"), _key("s", "l_suppkey").alias("b"), "w")


def copurchase(spark: SparkSession, d: str) -> DataFrame:
    """Parts of one order, each order and part once; an order holds a handful of parts, so the self join is bounded by lines."""
    once = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = once.select("l_orderkey", F.col("l_partkey").alias("q"))
    pairs = once.join(other, "l_orderkey").where("l_partkey < q")
    return pairs.groupBy("l_partkey", "q").agg(F.count("*").alias("w")).select(_key("p", "l_partkey").alias("a"), _key("p", "q").alias("b"), "w")


def doc_term(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents").select("doc_id", F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("word"))
    return docs.where(F.length("word") >= 2).groupBy("doc_id", "word").agg(F.count("*").alias("w")).select(_key("d", "doc_id").alias("a"), _key("t", "word").alias("b"), "w")


def web(spark: SparkSession, d: str) -> DataFrame:
    links = table(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    return links.groupBy("page_id", "href").agg(F.count("*").alias("w")).select(_key("g", "page_id").alias("a"), _key("h", "href").alias("b"), "w")


def user_key(spark: SparkSession, d: str) -> DataFrame:
    ev = table(spark, d, "events").select("user_id", F.get_json_object("props", "$.k").alias("k")).where("k is not null")
    return ev.groupBy("user_id", "k").agg(F.count("*").alias("w")).select(_key("u", "user_id").alias("a"), _key("k", "k").alias("b"), "w")


def dialogue(spark: SparkSession, d: str) -> DataFrame:
    """Each turn tied to the next of its conversation, and to its words."""
    t = table(spark, d, "conversations").select("conv_id", "turn", "text")
    me = F.concat_ws("-", F.col("conv_id").cast("string"), F.col("turn").cast("string"))
    nxt = t.select(me.alias("x"), F.lead(me).over(Window.partitionBy("conv_id").orderBy("turn")).alias("y")).where("y is not null")
    chain = nxt.select(_key("x", "x").alias("a"), _key("x", "y").alias("b"), F.lit(1).cast("long").alias("w"))
    words = t.select(me.alias("x"), F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("word")).where(F.length("word") >= 2)
    return chain.unionByName(words.groupBy("x", "word").agg(F.count("*").alias("w")).select(_key("x", "x").alias("a"), _key("t", "word").alias("b"), "w"))


def word_pair(spark: SparkSession, d: str, reach: int = 2) -> DataFrame:
    """Words within `reach` places of each other in benchmark items; `documents` takes the same path."""
    words = table(spark, d, "benchmark").select("item_id", F.posexplode(F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda x: F.length(x) >= 2)).alias("at", "word"))
    w = Window.partitionBy("item_id").orderBy("at")
    after = words.select("word", F.array(*[F.lead("word", k).over(w) for k in range(1, reach + 1)]).alias("after"))
    near = after.select("word", F.explode("after").alias("other")).where("other is not null")
    pairs = near.select(F.least("word", "other").alias("x"), F.greatest("word", "other").alias("y")).where("x <> y")
    return pairs.groupBy("x", "y").agg(F.count("*").alias("w")).select(_key("t", "x").alias("a"), _key("t", "y").alias("b"), "w")


#: Vectors of a block: two blocks and their products are what a task holds.
VECTORS = 2_048


def _nearest_candidates(k: int):
    """Rows (vec_id, o) that may be among the k nearest of each left vector: those within the rounding of its k-th, over all right blocks."""

    def flush(held: dict):
        for i, (o, s) in held.items():
            yield i, o[s >= (np.partition(s, len(s) - k)[len(s) - k] if len(s) > k else -np.inf) - SLACK]

    def run(batches):
        left, best = None, {}
        for b in batches:
            for at, ids, x, other, y in zip(b["block"], b["ids"], b["x"], b["other_ids"], b["y"], strict=True):
                if at != left:
                    yield from _frames(flush(best))
                    left, best = at, {}
                i, o = np.frombuffer(ids, "<i8"), np.frombuffer(other, "<i8")
                scores = np.frombuffer(x, "<f8").reshape(len(i), -1) @ np.frombuffer(y, "<f8").reshape(len(o), -1).T
                scores[i[:, None] == o[None, :]] = -np.inf
                floor = (np.partition(scores, len(o) - k, axis=1)[:, len(o) - k] if len(o) > k else np.full(len(i), -np.inf)) - SLACK
                keep = (scores >= floor[:, None]) & (scores > -np.inf)
                for row, vid in enumerate(i.tolist()):
                    at_row = np.flatnonzero(keep[row])
                    mine = (o[at_row], scores[row, at_row])
                    if vid in best:
                        mine = tuple(np.concatenate(z) for z in zip(best[vid], mine, strict=True))
                        if len(mine[1]) > 4 * k:
                            stay = mine[1] >= np.partition(mine[1], len(mine[1]) - k)[len(mine[1]) - k] - SLACK
                            mine = (mine[0][stay], mine[1][stay])
                    best[vid] = mine
        yield from _frames(flush(best))

    return run


#: What rounding to six places and the order of summation can move a cosine by.
SLACK = 2e-6


def _frames(rows):
    rows = list(rows)
    if rows:
        yield pd.DataFrame({"vec_id": np.repeat([i for i, _ in rows], [len(o) for _, o in rows]), "o": np.concatenate([o for _, o in rows])})


def vector_knn(spark: SparkSession, d: str, k: int = 10) -> DataFrame:
    """Each vector and its k nearest by cosine, weight round(cosine * 1000) where positive. Exact: every pair of blocks is multiplied,
    and the few that may be among the k nearest are scored and ranked by expressions."""
    v = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    dot = lambda p, q: F.aggregate(F.zip_with(p, q, lambda a, b: a * b), F.lit(0.0), lambda s, y: s + y)
    n = v.withColumn("n", F.sqrt(dot("x", "x")))
    blocks = max(1, -(-v.count() // VECTORS))

    def packed(b: pd.DataFrame) -> pd.DataFrame:
        unit = np.array([np.asarray(x) / m for x, m in zip(b["x"], b["n"], strict=True)])
        return pd.DataFrame({"block": [int(b["block"].iloc[0])], "ids": [b["vec_id"].to_numpy().astype("<i8").tobytes()], "x": [unit.astype("<f8").tobytes()]})

    sound = n.where("n > 0 and not isnan(n) and n < double('infinity')").withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    held = store(sound.groupBy("block").applyInPandas(packed, "block int, ids binary, x binary"), "blocks")
    other = held.select(F.col("block").alias("other"), F.col("ids").alias("other_ids"), F.col("x").alias("y"))
    # Every block meets every block, by an equi join on the left one's number; a task takes whole left blocks, a right one at a time.
    met = held.join(other.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))), "block").repartition(blocks, "block").sortWithinPartitions("block")
    cand = store(met.mapInPandas(_nearest_candidates(k), "vec_id long, o long"), "candidates")
    scored = cand.join(n, "vec_id").join(n.select(F.col("vec_id").alias("o"), F.col("x").alias("y"), F.col("n").alias("m")), "o").select("vec_id", "o", F.round(dot("x", "y") / (F.col("n") * F.col("m")), 6).alias("s"))
    w = Window.partitionBy("vec_id").orderBy(F.desc("s"), "o")
    top = scored.withColumn("r", F.row_number().over(w)).where((F.col("r") <= k) & (F.col("s") > 0))
    pairs = top.select(F.least("vec_id", "o").alias("x"), F.greatest("vec_id", "o").alias("y"), F.greatest(F.lit(1), F.round(F.col("s") * 1000)).cast("long").alias("w"))
    return pairs.groupBy("x", "y").agg(F.max("w").alias("w")).select(_key("v", "x").alias("a"), _key("v", "y").alias("b"), "w")


#: Longs of a document's parity sketches: one for all candidates, and a longer one, which large sets don't fill, for what it leaves.
SKETCHES = (16, 64)


def near_doc(spark: SparkSession, d: str, threshold: float = 0.5) -> DataFrame:
    """Documents whose word sets have Jaccard `threshold` or more, weight round(1000 * Jaccard), by a prefix filter.

    Words are ordered from the rarest. Two sets that alike share one of the longer one's first m - ceil(t * m) + 1 words and of the
    shorter one's first n - ceil(2 * t / (1 + t) * n) + 1, and behind the first word they share enough are left. What passes is held
    against parity sketches, whose bits differ in no more places than the sets, before
    whole sets of words are met. Equal sets are met once; the filters see words as 64-bit hashes.
    """
    near = 1e-9  # products of sizes and shares are rounded
    docs = table(spark, d, "documents").select("doc_id", F.array_distinct(F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda x: F.length(x) >= 2)).alias("s"))
    words = docs.select("doc_id", F.explode(F.transform("s", lambda x: F.xxhash64(x))).alias("h"))
    df = words.groupBy("h").agg(F.count("*").cast("int").alias("df"))
    ranked = words.join(df, "h").groupBy("doc_id").agg(F.transform(F.array_sort(F.collect_set(F.struct("df", "h"))), lambda x: x["h"]).alias("h"))
    sets = store(ranked.withColumns({"n": F.size("h"), "same": F.sha2(F.array_join(F.transform("h", lambda x: x.cast("string")), " "), 256)}), "sets")
    first = sets.groupBy("same").agg(F.min("doc_id").alias("rep"))
    members = store(sets.select("doc_id", "same").join(first, "same").select("doc_id", "rep"), "members")
    hashed = sets.select("doc_id", "n", "h").join(members.where("doc_id = rep").select("doc_id"), "doc_id", "left_semi")
    head = lambda share: F.slice("h", F.lit(1), (F.col("n") - F.ceil(F.col("n") * share - near) + 1).cast("int"))
    short = hashed.select("doc_id", "n", F.posexplode(head(2 * threshold / (1 + threshold))).alias("k", "h"))
    long = hashed.select(F.col("doc_id").alias("o"), F.col("n").alias("m"), F.posexplode(head(threshold)).alias("l", "h"))
    need = (F.col("n") + F.col("m")) * (threshold / (1 + threshold)) - near
    shorter = (F.col("n") < F.col("m")) | ((F.col("n") == F.col("m")) & (F.col("doc_id") < F.col("o")))
    met = short.join(long, "h").where(shorter & (F.col("n") >= threshold * F.col("m") - near) & (F.least(F.col("n") - F.col("k"), F.col("m") - F.col("l")) >= need))
    cand = met.select("doc_id", "o").distinct()
    bit = F.expr("shiftleft(1L, cast(pmod(h, 64) as int))")
    for size in SKETCHES:
        at = F.pmod(F.shiftright("h", 6), F.lit(size))
        parity = store(hashed.select("doc_id", "n", F.explode("h").alias("h")).groupBy("doc_id", "n").agg(*[F.bit_xor(F.when(at == i, bit).otherwise(F.lit(0).cast("long"))).alias(f"b{i}") for i in range(size)]).select("doc_id", "n", F.array(*[f"b{i}" for i in range(size)]).alias("b")), "sketches")
        other = parity.select(F.col("doc_id").alias("o"), F.col("n").alias("m"), F.col("b").alias("c"))
        apart = F.aggregate(F.zip_with("b", "c", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda x, y: x + y)
        cand = store(cand.join(parity, "doc_id").join(other, "o").where(apart <= F.col("n") + F.col("m") - 2 * need).select("doc_id", "o"), "candidates")
    asked = cand.select(F.explode(F.array("doc_id", "o")).alias("doc_id")).distinct()
    whole = docs.join(asked, "doc_id", "left_semi").groupBy("doc_id").agg(F.array_distinct(F.flatten(F.collect_list("s"))).alias("s"))
    both = cand.join(whole, "doc_id").join(whole.select(F.col("doc_id").alias("o"), F.col("s").alias("z")), "o")
    j = both.select(F.col("doc_id").alias("p"), F.col("o").alias("q"), (F.size(F.array_intersect("s", "z")) / F.size(F.array_union("s", "z"))).alias("j")).where(F.col("j") >= threshold)
    mine, yours = members.select("doc_id", F.col("rep").alias("p")), members.select(F.col("doc_id").alias("o"), F.col("rep").alias("q"))
    apart_pairs = j.join(mine, "p").join(yours, "q").select("doc_id", "o", "j")
    copies = mine.join(yours, F.col("p") == F.col("q")).where("doc_id < o").select("doc_id", "o", F.lit(1.0).alias("j"))
    return apart_pairs.unionByName(copies).select(_key("d", "doc_id").alias("a"), _key("d", "o").alias("b"), F.round(F.col("j") * 1000).cast("long").alias("w"))


BUILDERS = {f.__name__: f for f in (geography, customer_part, part_supplier, copurchase, doc_term, web, user_key, dialogue, word_pair, vector_knn, near_doc)}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return build(BUILDERS[name](spark, sf_dir))


def canonical(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return undirect(BUILDERS[name](spark, sf_dir))


def labels(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(key, label) of the vertices that a graph's ground truth covers."""
    if name == "geography":
        n = table(spark, sf_dir, "nation").select("n_nationkey", F.col("n_regionkey").alias("label"))
        c = table(spark, sf_dir, "customer").select(_key("c", "c_custkey").alias("key"), F.col("c_nationkey").alias("n_nationkey"))
        s = table(spark, sf_dir, "supplier").select(_key("s", "s_suppkey").alias("key"), F.col("s_nationkey").alias("n_nationkey"))
        return c.unionByName(s).join(F.broadcast(n), "n_nationkey").select("key", F.col("label").cast("int").alias("label"))  # 25 nations
    if name in ("doc_term", "near_doc"):
        langs = F.array(*[F.lit(x) for x in ("de", "en", "es", "fr")])
        return table(spark, sf_dir, "documents").select(_key("d", "doc_id").alias("key"), (F.array_position(langs, F.col("lang")) - 1).cast("int").alias("label")).where("label >= 0")
    if name == "doc_quality":
        return table(spark, sf_dir, "labels").select(_key("d", "doc_id").alias("key"), F.col("quality").cast("int").alias("label"))
    if name == "vector_knn":
        return table(spark, sf_dir, "embeddings").select(_key("v", "vec_id").alias("key"), F.col("label").cast("int").alias("label"))
    if name == "copurchase":
        brand = F.dense_rank().over(Window.orderBy("p_brand"))
        brands = table(spark, sf_dir, "part").select("p_brand").distinct().select("p_brand", (brand - 1).alias("label"))
        return table(spark, sf_dir, "part").join(F.broadcast(brands), "p_brand").select(_key("p", "p_partkey").alias("key"), "label")  # 25 brands
    raise ValueError(f"no labels for {name!r}")


def labelled(g: Graph, keys: DataFrame) -> DataFrame:
    return g.vertices.select("vid", "key").join(keys, "key").select("vid", "label")


_WORDS = "unnest(regexp_split_to_array(lower({0}), '[^\\p{{L}}]+'))"
SQL = {
    "geography": "SELECT 'c:' || c_custkey AS a, 'n:' || c_nationkey AS b, 1 AS w FROM customer UNION ALL SELECT 's:' || s_suppkey, 'n:' || s_nationkey, 1 FROM supplier UNION ALL SELECT 'n:' || n_nationkey, 'r:' || n_regionkey, 1 FROM nation",
    "customer_part": "SELECT 'c:' || o_custkey AS a, 'p:' || l_partkey AS b, sum(l_quantity)::BIGINT AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey, l_partkey",
    "part_supplier": "SELECT 'p:' || l_partkey AS a, 's:' || l_suppkey AS b, count(*) AS w FROM lineitem GROUP BY l_partkey, l_suppkey",
    "copurchase": "SELECT 'p:' || x.l_partkey AS a, 'p:' || y.l_partkey AS b, count(*) AS w FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) x JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) y USING (l_orderkey) WHERE x.l_partkey < y.l_partkey GROUP BY x.l_partkey, y.l_partkey",
    "doc_term": f"SELECT 'd:' || doc_id AS a, 't:' || word AS b, count(*) AS w FROM (SELECT doc_id, {_WORDS.format('text')} AS word FROM documents) WHERE length(word) >= 2 GROUP BY doc_id, word",
    "web": "SELECT 'g:' || page_id AS a, 'h:' || href AS b, count(*) AS w FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages) GROUP BY page_id, href",
    "user_key": "SELECT 'u:' || user_id AS a, 'k:' || k AS b, count(*) AS w FROM (SELECT user_id, props::JSON ->> '$.k' AS k FROM events) WHERE k IS NOT NULL GROUP BY user_id, k",
    "dialogue": f"SELECT 'x:' || x AS a, 'x:' || y AS b, 1 AS w FROM (SELECT conv_id || '-' || turn AS x, lead(conv_id || '-' || turn) OVER (PARTITION BY conv_id ORDER BY turn) AS y FROM conversations) WHERE y IS NOT NULL UNION ALL SELECT 'x:' || x, 't:' || word, count(*) FROM (SELECT conv_id || '-' || turn AS x, {_WORDS.format('text')} AS word FROM conversations) WHERE length(word) >= 2 GROUP BY x, word",
    "word_pair": "SELECT 't:' || least(x, y) AS a, 't:' || greatest(x, y) AS b, count(*) AS w FROM (SELECT p.word AS x, q.word AS y FROM words p JOIN words q ON p.item_id = q.item_id AND q.pos BETWEEN p.pos + 1 AND p.pos + 2 WHERE p.word <> q.word) GROUP BY least(x, y), greatest(x, y)",
    "vector_knn": "SELECT 'v:' || x AS a, 'v:' || y AS b, max(w) AS w FROM (SELECT least(i, o) AS x, greatest(i, o) AS y, greatest(1, round(s * 1000))::BIGINT AS w FROM (SELECT i, o, s, row_number() OVER (PARTITION BY i ORDER BY s DESC, o) AS r FROM (SELECT p.vec_id AS i, q.vec_id AS o, round(list_dot_product(p.embedding::DOUBLE[], q.embedding::DOUBLE[]) / (sqrt(list_dot_product(p.embedding::DOUBLE[], p.embedding::DOUBLE[])) * sqrt(list_dot_product(q.embedding::DOUBLE[], q.embedding::DOUBLE[]))), 6) AS s FROM embeddings p JOIN embeddings q ON p.vec_id <> q.vec_id)) WHERE r <= 10 AND s > 0) GROUP BY x, y",
    "near_doc": f"SELECT 'd:' || i AS a, 'd:' || o AS b, round(1000 * c / (n + m - c))::BIGINT AS w FROM (SELECT p.doc_id AS i, q.doc_id AS o, count(*) AS c, any_value(p.n) AS n, any_value(q.n) AS m FROM sized p JOIN sized q ON p.word = q.word AND p.doc_id < q.doc_id GROUP BY p.doc_id, q.doc_id) WHERE c / (n + m - c) >= 0.5",
}
#: Common table expressions that some of the texts name.
WITH = {
    "word_pair": "words AS (SELECT item_id, word, row_number() OVER (PARTITION BY item_id ORDER BY pos) AS pos FROM (SELECT item_id, unnest(l) AS word, generate_subscripts(l, 1) AS pos FROM (SELECT item_id, regexp_split_to_array(lower(text), '[^\\p{L}]+') AS l FROM benchmark)) WHERE length(word) >= 2)",
    "near_doc": f"sized AS (SELECT doc_id, word, count(*) OVER (PARTITION BY doc_id) AS n FROM (SELECT DISTINCT doc_id, word FROM (SELECT doc_id, {_WORDS.format('text')} AS word FROM documents) WHERE length(word) >= 2))",
}


def edges_sql(name: str) -> str:
    """The canonical edges' CTEs, ending with `canon(a, b, w)`."""
    lead = f"{WITH[name]}, " if name in WITH else ""
    return f"{lead}raw AS ({SQL[name]}), canon AS (SELECT least(a, b) AS a, greatest(a, b) AS b, sum(w)::BIGINT AS w FROM raw WHERE a <> b GROUP BY least(a, b), greatest(a, b))"

"""What a run costs and how evenly it is spread."""

from __future__ import annotations

import time
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from proxembed.operators.graph import Graph


def cost_formula(p: Column, size: Column, calls: Column, batch: Column, batches: Column) -> Column:
    """batches x (walk calls of a batch x (log2 p + p x size) + p x batch)."""
    return batches * (calls * (F.log2(p) + p * size) + p * batch)


def remote_share(rows: DataFrame) -> DataFrame:
    """(sign, share) of pairs whose second end lies elsewhere."""
    return rows.groupBy("sign").agg(F.round(F.avg((F.col("v_part") != F.col("part")).cast("double")), 6).alias("share"))


def sample_spread(pairs: DataFrame, parts: int, batches: int) -> DataFrame:
    """One row: least, most, mean and deviation of pairs by (batch, part), their ratio and share, parts with none."""
    spark = pairs.sparkSession
    grid = spark.range(parts * batches).select(F.expr(f"cast(id div {parts} as int)").alias("batch"), F.expr(f"cast(id % {parts} as int)").alias("part"))
    n = F.coalesce("n", F.lit(0))
    per = grid.join(pairs.groupBy("batch", "part").agg(F.count("*").alias("n")), ["batch", "part"], "left").select(n.alias("n"))
    return per.agg(F.min("n").alias("least"), F.max("n").alias("most"), F.round(F.avg("n"), 6).alias("mean"), F.round(F.stddev_pop("n"), 6).alias("sigma"),
                   F.round(F.try_divide(F.max("n"), F.min("n")), 6).alias("ratio"), F.round(F.try_divide(100 * (F.max("n") - F.min("n")), F.avg("n")), 6).alias("spread_percent"), F.sum((F.col("n") == 0).cast("long")).alias("zero_parts"))


def false_positive_share(pairs: DataFrame, g: Graph) -> DataFrame:
    """Share of positive pairs that are no edges."""
    edges = g.edges.select(F.col("src").alias("u"), F.col("dst").alias("v"))
    wrong = pairs.join(edges, ["u", "v"], "left_anti").agg(F.count("*").alias("wrong"))
    return pairs.agg(F.count("*").alias("n")).crossJoin(wrong).select("n", "wrong", F.round(F.try_divide("wrong", "n"), 6).alias("share"))  # two rows of one


def staleness(pairs: DataFrame) -> DataFrame:
    """(batch, spilled_share, mean_age): pairs that an earlier batch drew, and how many batches ago."""
    return pairs.groupBy("batch").agg(F.round(F.avg((F.col("age") > 0).cast("double")), 6).alias("spilled_share"), F.round(F.avg("age"), 6).alias("mean_age"))


def comm_volume(rows: DataFrame, dim: int) -> DataFrame:
    """(batch, contexts, bytes): distinct contexts that cross parts, and bytes of both exchanges."""
    remote = rows.where("v_part <> part").select("batch", "part", "v").distinct()
    return remote.groupBy("batch").agg(F.count("*").alias("contexts")).withColumn("bytes", F.col("contexts") * (2 * (4 * dim + 8)))


def memory_report(g: Graph, dim: int) -> DataFrame:
    """(part, bytes) of the state block."""
    return g.vertices.groupBy("part").agg((F.count("*") * (8 * dim + 8)).alias("bytes"))


PROFILE = "stage long, phase string, task long, run_s double, cpu_s double, fetch_wait_s double, shuffle_write_s double, gc_s double, shuffle_read_bytes long, shuffle_write_bytes long, shuffle_read_rows long, shuffle_write_rows long, peak_bytes long"


def last_stage(spark: SparkSession) -> int:
    """The newest stage that the status store knows, to profile what comes after it."""
    stages = _stages(spark)
    return max((stages.apply(k).stageId() for k in range(stages.size())), default=-1)


def _stages(spark: SparkSession):
    context = spark.sparkContext
    jvm = context._jvm
    context._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    return context._jsc.sc().statusStore().stageList(jvm.java.util.ArrayList(), False, False, context._gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())


def task_profile(spark: SparkSession, after: int = -1, most_tasks: int = 10_000) -> DataFrame:
    """PROFILE: a row for each finished task of the stages after `after`, from Spark's own status store.

    The phase is the job description that `timed` set. Of a stage's tasks at most `most_tasks` are read.
    """
    store, rows = spark.sparkContext._jsc.sc().statusStore(), []
    stages = _stages(spark)
    for k in range(stages.size()):
        s = stages.apply(k)
        if s.stageId() <= after or str(s.status()) == "SKIPPED":
            continue
        phase = s.description().get() if s.description().isDefined() else s.name()
        tasks = store.taskList(s.stageId(), s.attemptId(), most_tasks)
        for i in range(tasks.size()):
            t = tasks.apply(i)
            if not t.taskMetrics().isDefined():
                continue
            m = t.taskMetrics().get()
            read, write = m.shuffleReadMetrics(), m.shuffleWriteMetrics()
            rows.append((s.stageId(), phase, t.taskId(), m.executorRunTime() / 1e3, m.executorCpuTime() / 1e9, read.fetchWaitTime() / 1e3, write.writeTime() / 1e9, m.jvmGcTime() / 1e3,
                         read.remoteBytesRead() + read.localBytesRead(), write.bytesWritten(), read.recordsRead(), write.recordsWritten(), m.peakExecutionMemory()))
    return spark.createDataFrame(rows, PROFILE)


def routine_profile(tasks: DataFrame) -> DataFrame:
    """(phase, routine, seconds, share_percent, imbalance_percent): where a phase's task time went, and how unevenly over its tasks."""
    other = F.greatest(F.lit(0.0), F.col("run_s") - F.col("fetch_wait_s") - F.col("shuffle_write_s") - F.col("gc_s"))
    parts = [("shuffle read wait", F.col("fetch_wait_s")), ("shuffle write", F.col("shuffle_write_s")), ("collection of garbage", F.col("gc_s")), ("work", other)]
    rows = tasks.select("phase", F.explode(F.array(*[F.struct(F.lit(n).alias("routine"), c.alias("s")) for n, c in parts])).alias("r")).select("phase", "r.*")
    per = rows.groupBy("phase", "routine").agg(F.sum("s").alias("seconds"), F.max("s").alias("m"), F.avg("s").alias("a"), F.count("*").alias("n"))
    uneven = F.when((F.col("n") > 1) & (F.col("m") > 0), (F.col("m") - F.col("a")) / F.col("m") * F.col("n") / (F.col("n") - 1)).otherwise(0.0)
    total = F.sum("seconds").over(Window.partitionBy("phase"))
    return per.select("phase", "routine", "seconds", F.round(100 * F.try_divide("seconds", total), 3).alias("share_percent"), F.round(100 * uneven, 3).alias("imbalance_percent"))


def traffic(tasks: DataFrame) -> DataFrame:
    """(phase, exchanged_rows, exchanged_bytes, read_bytes): what the shuffles of a phase moved, as measured."""
    return tasks.groupBy("phase").agg(F.sum("shuffle_write_rows").alias("exchanged_rows"), F.sum("shuffle_write_bytes").alias("exchanged_bytes"), F.sum("shuffle_read_bytes").alias("read_bytes"))


def process_memory(spark: SparkSession) -> DataFrame:
    """(executor, peak_heap, peak_off_heap, peak_execution, peak_python) bytes by process, as heartbeats reported them."""
    found = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    rows = []
    for k in range(found.size()):
        e = found.apply(k)
        m = e.peakMemoryMetrics()
        get = (lambda n: int(m.get().getMetricValue(n))) if m.isDefined() else (lambda n: 0)
        rows.append((e.id(), get("JVMHeapMemory"), get("JVMOffHeapMemory"), get("OnHeapExecutionMemory") + get("OffHeapExecutionMemory"), get("ProcessTreePythonRSSMemory")))
    return spark.createDataFrame(rows, "executor string, peak_heap long, peak_off_heap long, peak_execution long, peak_python long")


def imbalance(task_times: DataFrame, by: str = "stage", value: str = "seconds") -> DataFrame:
    """(stage, share_percent, imbalance_percent): share of all time; (most - mean) / most x n / (n - 1)."""
    per = task_times.groupBy(by).agg(F.sum(value).alias("s"), F.max(value).alias("m"), F.avg(value).alias("a"), F.count("*").alias("n"))
    total = F.sum("s").over(Window.partitionBy())
    uneven = F.when((F.col("n") > 1) & (F.col("m") > 0), (F.col("m") - F.col("a")) / F.col("m") * F.col("n") / (F.col("n") - 1)).otherwise(0.0)
    return per.select(by, F.round(100 * F.col("s") / total, 6).alias("share_percent"), F.round(100 * uneven, 6).alias("imbalance_percent"))


def speedups(times: DataFrame) -> DataFrame:
    """(graph, method, p, seconds) -> + speed-up over the method's smallest p, and over the graph's slowest method there."""
    own = Window.partitionBy("graph", "method").orderBy("p").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    first = F.first("seconds").over(own)
    slowest = F.max("seconds").over(Window.partitionBy("graph", "p"))
    return times.select("*", F.round(first / F.col("seconds"), 6).alias("self_speedup"), F.round(slowest / F.col("seconds"), 6).alias("over_slowest"))


def crossover(times: DataFrame, a: str, b: str) -> DataFrame:
    """(graph, p): the smallest p at which method `a` is faster than `b`; null where it never is."""
    wide = times.where(F.col("method").isin(a, b)).groupBy("graph", "p").agg(F.max(F.when(F.col("method") == a, F.col("seconds"))).alias("a"), F.max(F.when(F.col("method") == b, F.col("seconds"))).alias("b"))
    return wide.groupBy("graph").agg(F.min(F.when(F.col("a") < F.col("b"), F.col("p"))).alias("p"))


@contextmanager
def timed(into: dict[str, float], stage: str, spark: SparkSession | None = None):
    """Adds the seconds of a block of actions to into[stage]; with a session, jobs of the block carry the stage as description."""
    began = time.perf_counter()
    if spark is not None:
        spark.sparkContext.setJobDescription(stage)
    try:
        yield
    finally:
        if spark is not None:
            spark.sparkContext.setJobDescription(None)
    into[stage] = into.get(stage, 0.0) + time.perf_counter() - began

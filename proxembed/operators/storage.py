"""Stored intermediates in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid
import weakref

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}
_PATHS: weakref.WeakKeyDictionary[DataFrame, str] = weakref.WeakKeyDictionary()


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a local folder serves in local mode only, elsewhere its lack is an error."""
    context = spark.sparkContext
    given = spark.conf.get("spark.checkpoint.dir", None) or context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if given:
        return given.rstrip("/")
    if context.master != "local" and not context.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    if "dir" not in _LOCAL:
        _LOCAL["dir"] = "file://" + tempfile.mkdtemp(prefix="proxembed-graph-")
    return _LOCAL["dir"]


def store(df: DataFrame, label: str, by: list[str] | None = None) -> DataFrame:
    """Write once, read back: cuts lineage at supersteps and survives lost executors. `by` are columns to lay out folders by."""
    path = f"{shared_dir(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    writer = df.write
    if by:
        writer = writer.partitionBy(*by)
    writer.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    _PATHS[out] = path
    return out


def forget(*stored: DataFrame) -> None:
    """Remove tables of store() that nothing will read again."""
    for df in stored:
        path = _PATHS.pop(df, None)
        if path is not None:
            context = df.sparkSession.sparkContext
            place = context._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(context._jsc.hadoopConfiguration()).delete(place, True)


class Buckets:
    """Tables bucketed by a key, so what lies there is read without an exchange; dropped when forgotten."""

    def __init__(self, spark: SparkSession, buckets: int, key: str = "part"):
        self.spark, self.buckets, self.key, self.names = spark, buckets, key, []

    def keep(self, df: DataFrame, label: str = "superstep") -> DataFrame:
        name = f"{label}_{uuid.uuid4().hex}"
        df.write.format("parquet").bucketBy(self.buckets, self.key).sortBy(self.key).saveAsTable(name)
        self.names.append(name)
        return self.spark.table(name)

    def forget(self, keep_last: int = 0) -> None:
        while len(self.names) > keep_last:
            self.spark.sql(f"DROP TABLE IF EXISTS {self.names.pop(0)}")


class Versions:
    """Numbered versions of named tables under one folder; `_current` names the last whole one and is put in place by a rename.

    A driver that is lost while it writes leaves the pointer on the version before; the next one goes on from there.
    """

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self._fs = self._place("").getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _place(self, name: str):
        return self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}" if name else self.path)

    def current(self) -> int | None:
        if not self._fs.exists(self._place("_current")):
            return None
        io = self.spark.sparkContext._jvm.java.io
        pointer = io.BufferedReader(io.InputStreamReader(self._fs.open(self._place("_current"))))
        try:
            return int(pointer.readLine())
        finally:
            pointer.close()

    def read(self, *names: str) -> tuple[int, list[DataFrame]] | None:
        """(version, tables) of the last whole version."""
        at = self.current()
        return None if at is None else (at, [self.spark.read.parquet(f"{self.path}/v{at}/{n}") for n in names])

    def write(self, version: int, **tables: DataFrame) -> None:
        before = self.current()
        for name, df in tables.items():
            df.write.mode("overwrite").parquet(f"{self.path}/v{version}/{name}")
        out = self._fs.create(self._place("_next"), True)
        out.write(bytearray(f"{version}\n".encode()))
        out.close()
        jvm, gateway = self.spark.sparkContext._jvm, self.spark.sparkContext._gateway
        options = gateway.new_array(jvm.org.apache.hadoop.fs.Options.Rename, 1)
        options[0] = jvm.org.apache.hadoop.fs.Options.Rename.OVERWRITE
        context = jvm.org.apache.hadoop.fs.FileContext.getFileContext(self._fs.getUri(), self._fs.getConf())
        context.rename(self._fs.makeQualified(self._place("_next")), self._fs.makeQualified(self._place("_current")), options)
        if before is not None and before != version:
            self._fs.delete(self._place(f"v{before}"), True)

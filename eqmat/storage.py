"""Shared storage for intermediate tables: lineage is cut by writing Parquet where every executor can read it."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

_DIRS: dict[str, str] = {}
_UNDER: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The cluster's checkpoint folder. A folder of our own, removed at exit, serves only where the session names none and
    runs on one machine; elsewhere executors would write what the driver cannot read, so that is an error."""
    if _UNDER:
        return _UNDER[-1]
    app = spark.sparkContext.applicationId
    if app not in _DIRS:
        named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
        if not named and not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        if not named:
            own = tempfile.mkdtemp(prefix="eqmat-")
            atexit.register(shutil.rmtree, own, ignore_errors=True)
            named = "file://" + own
        _DIRS[app] = named.rstrip("/")
    return _DIRS[app]


@contextmanager
def under(path: str) -> Iterator[None]:
    """Within the block, tables are saved below a path that outlives the session."""
    _UNDER.append(path.rstrip("/"))
    try:
        yield
    finally:
        _UNDER.pop()


def _write(df: DataFrame, tag: str, partition_by: list[str] | None) -> DataFrame:
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    writer = df.write.mode("overwrite")
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    return reread(spark, path, df.schema)


def reread(spark: SparkSession, path: str, schema) -> DataFrame:
    """A saved table by its path, which path_of() gives back."""
    out = spark.read.schema(schema).parquet(path)
    out._saved_at = path
    return out


def path_of(df: DataFrame) -> str | None:
    """Where a DataFrame that saved() returned lies."""
    return getattr(df, "_saved_at", None)


def saved(df: DataFrame, tag: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write df once and read it back: a lost executor costs a re-read, never a re-run of what came before."""
    return _write(df, tag, partition_by)


def counted(df: DataFrame, tag: str, *, partition_by: list[str] | None = None, **watch: Column) -> tuple[DataFrame, dict[str, int]]:
    """As saved(), with the number of rows ``n`` and of rows where each condition of watch holds, counted while writing."""
    seen = Observation()
    marks = [F.count(F.when(c, 1)).alias(name) for name, c in watch.items()]
    out = _write(df.observe(seen, F.count(F.lit(1)).alias("n"), *marks), tag, partition_by)
    return out, {"n": 0, **dict.fromkeys(watch, 0), **observed(seen)}


def observed(seen: Observation) -> dict[str, int]:
    """What was observed; nothing where the planner found that no row comes and left the observed part out."""
    try:
        return dict(seen.get)
    except Py4JJavaError as e:
        if "assertion failed" in str(e.java_exception):  # a row without a schema
            return {}
        raise


def discard(*tables: DataFrame) -> None:
    """Delete saved tables that nothing reads any more."""
    for t in tables:
        if path := path_of(t):
            jvm = t.sparkSession._jvm
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(t.sparkSession._jsc.hadoopConfiguration()).delete(at, True)


def keyed(df: DataFrame, tag: str) -> tuple[DataFrame, str]:
    """df saved with a key of each row, which stays the same however often it is read, and the name of its column."""
    name = "row_key"
    while name in map(str.lower, df.columns):
        name += "_"
    return saved(df.withColumn(name, F.monotonically_increasing_id()), tag), name

"""Sharding by extendible hashing: a directory over hash prefixes in which only oversized buckets split on another bit.

Bytes are summed for each prefix of a depth that follows the input's size; the sums of all shorter prefixes come from
those, and a shard is the shortest prefix whose bytes fit. Prefixes that are too large even at that depth are summed
again some bits deeper. The directory stays a table.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from eqmat.storage import saved

BITS, SLACK, STEP = 60, 4, 12


def key_hash(key) -> F.Column:
    """60 bits of the MD5 of the key as text; a null key has its own value."""
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("null")).cast("binary")), 1, 15), 16, 10).cast("long")


def prefix(h, depth: int) -> F.Column:
    """The first ``depth`` bits as a string of 0 and 1."""
    return F.lit("") if depth == 0 else F.lpad(F.bin(F.shiftright(h, BITS - depth)), depth, "0")


def _directory(rows: DataFrame, limit: int) -> DataFrame:
    """shard, depth, shard_bytes, shard_rows for rows(h, n_bytes)."""
    total = rows.agg(F.coalesce(F.sum("n_bytes"), F.lit(0)).alias("b")).first()["b"]
    depth = min(BITS, max(0, math.ceil(math.log2(max(total / limit, 1)))) + SLACK)
    sums = rows.groupBy(prefix(F.col("h"), depth).alias("p")).agg(F.sum("n_bytes").alias("b"), F.count("*").alias("n"))
    found, above, least = None, None, 0
    while True:
        sums = saved(sums, "prefix")
        levels = sums.select("b", "n", F.explode(F.transform(F.sequence(F.lit(least), F.lit(depth)), lambda d: F.substring("p", F.lit(1), d))).alias("shard"))
        levels = levels.groupBy("shard").agg(F.sum("b").alias("shard_bytes"), F.sum("n").alias("shard_rows")).withColumn("depth", F.length("shard"))
        levels = saved(levels, "levels")
        parents = levels.select(F.col("shard").alias("parent"), F.col("shard_bytes").alias("over")).where(F.col("over") > limit)
        if above is not None:
            parents = parents.unionByName(above)
        fits = (F.col("shard_bytes") <= limit) if depth < BITS else ((F.col("shard_bytes") <= limit) | (F.col("depth") == BITS))
        own = levels.where(fits & (F.col("depth") > 0)).join(parents, F.expr("substring(shard, 1, depth - 1)") == F.col("parent"), "left_semi")
        if least == 0:
            own = own.unionByName(levels.where(fits & (F.col("depth") == 0)))
        own = own.select("shard", "depth", "shard_bytes", "shard_rows")
        found = own if found is None else found.unionByName(own)
        big = levels.where((F.col("depth") == depth) & (F.col("shard_bytes") > limit)).select(F.col("shard").alias("parent"), F.col("shard_bytes").alias("over"))
        if depth == BITS or big.limit(1).count() == 0:
            return saved(found, "directory")
        above, least, was = big, depth + 1, depth
        depth = min(BITS, depth + STEP)
        inside = rows.join(big, prefix(F.col("h"), was) == F.col("parent"), "left_semi")
        sums = inside.groupBy(prefix(F.col("h"), depth).alias("p")).agg(F.sum("n_bytes").alias("b"), F.count("*").alias("n"))


def assign_shards(docs: DataFrame, limit: int, key: str = "doc_id", size: F.Column | None = None) -> DataFrame:
    """docs -> key, n_bytes, shard (prefix bits; a page number follows a dot where one hash alone is too large),
    depth, shard_bytes.

    ``size`` defaults to the bytes of text; a null text has none. Rows with equal keys (repeated rows, null keys) have
    one hash and cannot be told apart by bits: such a bucket, at full depth, goes on in overflow pages, where only a
    page of one row may pass the limit. An empty table gives no rows; other columns are not looked at.
    """
    if limit < 1:
        raise ValueError("limit must be positive")
    size = F.coalesce(F.octet_length(F.col("text")), F.lit(0)).cast("long") if size is None else size
    rows = saved(docs.select(F.col(key).alias("key"), key_hash(F.col(key)).alias("h"), size.alias("n_bytes")), "sizes")
    directory = _directory(rows, limit)
    depths = [r["depth"] for r in directory.select("depth").distinct().collect()]  # at most 61
    routed = None
    for d in sorted(depths):
        own = directory.where(F.col("depth") == d).select(F.col("shard").alias("s"), "depth", "shard_bytes")
        part = rows.withColumn("shard", prefix(F.col("h"), d)).join(own, F.col("shard") == F.col("s")).drop("s")
        routed = part if routed is None else routed.unionByName(part)
    if routed is None:
        return rows.select(F.col("key").alias(key), "n_bytes", F.lit("").alias("shard"), F.lit(0).alias("depth"), F.lit(0).cast("long").alias("shard_bytes")).limit(0)
    if BITS in depths and directory.where((F.col("depth") == BITS) & (F.col("shard_bytes") > limit)).limit(1).count():
        routed = _overflow(routed, limit)
    return routed.select(F.col("key").alias(key), "n_bytes", "shard", "depth", "shard_bytes")


def _overflow(routed: DataFrame, limit: int) -> DataFrame:
    """Pages of buckets that no bit can split. A page is a range of running bytes; sums run within a task first and
    then across tasks, so no bucket is gathered."""
    over = (F.col("depth") == BITS) & (F.col("shard_bytes") > limit)
    big = saved(routed.where(over).withColumn("task", F.spark_partition_id()).withColumn("nth", F.monotonically_increasing_id()), "overflow")
    tasks = big.groupBy("shard", "task").agg(F.sum("n_bytes").alias("b"))
    before = Window.partitionBy("shard").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    tasks = tasks.select("shard", "task", F.coalesce(F.sum("b").over(before), F.lit(0)).alias("base"))
    inner = Window.partitionBy("shard", "task").orderBy("nth").rowsBetween(Window.unboundedPreceding, 0)
    # Pages of half the limit by the end of each row: what a page holds is under the limit, or one row.
    half = max(1, limit // 2)
    ended = big.join(tasks, ["shard", "task"]).withColumn("ends", F.col("base") + F.sum("n_bytes").over(inner))
    alone = F.col("n_bytes") > half
    page = F.when(alone, F.concat(F.lit("x"), F.col("ends").cast("string"))).otherwise(F.expr(f"ends div {half}").cast("string"))
    paged = ended.withColumn("shard", F.concat_ws(".", "shard", page))
    sums = paged.groupBy("shard").agg(F.sum("n_bytes").alias("in_page"))
    paged = paged.join(sums, "shard").withColumn("shard_bytes", F.col("in_page"))
    return routed.where(~over).unionByName(paged.select(*routed.columns))


def write_shards(docs: DataFrame, path: str, limit: int, key: str = "doc_id") -> DataFrame:
    """Write docs under ``path``, one folder for each shard, and return the directory (shard, depth, shard_bytes, rows).
    Rows travel by the shard of their key; keys must be unique for the join."""
    of = assign_shards(docs, limit, key)
    routed = docs.join(of.select(F.col(key).alias("_k"), F.col("shard").alias("_shard")), docs[key].eqNullSafe(F.col("_k"))).drop("_k")
    routed.repartition("_shard").write.mode("overwrite").partitionBy("_shard").parquet(path)
    return of.groupBy("shard", "depth", "shard_bytes").agg(F.count("*").alias("shard_rows"))

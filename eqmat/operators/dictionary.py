"""Names to dense ids in name order, without gathering the names in one place."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from eqmat.plans.rules import EQ, EQ_ID, NEQ, NEQ_ID
from eqmat.storage import saved

FIRST_FREE = 3


def encode_terms(names: DataFrame, order: list[str] | None = None) -> DataFrame:
    """terms(id, lexical, num) for names(lexical). Ids follow the order of names; those in ``order`` come first, as
    listed; EQ and NEQ are 1 and 2, so that equality keeps its own id whatever is merged with it."""
    listed = F.lit(len(order or []))
    for i, n in enumerate(order or []):
        listed = F.when(F.col("lexical") == n, F.lit(i)).otherwise(listed)
    free = names.where(F.col("lexical").isNotNull() & ~F.col("lexical").isin(EQ, NEQ)).select("lexical").distinct()
    placed = saved(free.withColumn("ahead", listed).orderBy("ahead", "lexical").withColumn("at", F.monotonically_increasing_id()), "terms")
    task = F.shiftright("at", 33)
    counts = placed.groupBy(task.alias("task")).agg(F.count("*").alias("n"))  # one row per task of the sort
    before = Window.orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("task", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    ids = placed.withColumn("task", task).join(base, "task").select((F.col("base") + F.col("at").bitwiseAND((1 << 33) - 1) + FIRST_FREE).cast("long").alias("id"), "lexical")
    fixed = names.sparkSession.createDataFrame([(EQ_ID, EQ), (NEQ_ID, NEQ)], "id long, lexical string")
    return saved(fixed.unionByName(ids).withColumn("num", F.expr("try_cast(lexical as double)")), "terms")


def extend_terms(terms: DataFrame, names: DataFrame) -> DataFrame:
    """terms with ids for names(lexical) that it lacks, after those that it has."""
    new = names.select("lexical").distinct().join(terms.select("lexical"), "lexical", "left_anti")
    last = terms.agg(F.max("id")).first()[0]
    more = encode_terms(new).where(F.col("id") >= FIRST_FREE).withColumn("id", F.col("id") + (last - FIRST_FREE + 1))
    return saved(terms.unionByName(more), "terms")


def lookup(terms: DataFrame, names) -> dict[str, int]:
    """Ids of a few names, such as the constants of rules and queries."""
    wanted = list(dict.fromkeys(names))
    if not wanted:
        return {}
    return {r["lexical"]: r["id"] for r in terms.where(F.col("lexical").isin(wanted)).collect()}


def encode(triples: DataFrame, terms: DataFrame) -> DataFrame:
    """triples(s, p, o) of names -> facts(s, p, o) of ids; predicates are few, so those names are joined last."""
    out = triples
    for c in "sop":
        t = terms.select(F.col("id").alias(f"{c}_id"), F.col("lexical").alias(f"{c}_name"))
        out = out.join(t, F.col(c) == F.col(f"{c}_name")).drop(c, f"{c}_name").withColumnRenamed(f"{c}_id", c)
    return out.select("s", "p", "o")


def decode(df: DataFrame, terms: DataFrame, columns: list[str]) -> DataFrame:
    """df with the ids in columns replaced by names."""
    order = df.columns
    for c in columns:
        t = terms.select(F.col("id").alias("_id"), F.col("lexical").alias("_name"))
        df = df.join(t, F.col(c) == F.col("_id"), "left").drop(c, "_id").withColumnRenamed("_name", c)
    return df.select(*order)


def empty(spark: SparkSession, schema: str) -> DataFrame:
    return spark.createDataFrame([], schema)

"""Triples from tables and files, and back to files."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

WIDTH = 12
NTRIPLE = r'^\s*(<[^>]*>|_:\S+)\s+(<[^>]*>)\s+(<[^>]*>|_:\S+|"(?:[^"\\]|\\.)*"(?:@[\w-]+|\^\^<[^>]*>)?)\s*\.\s*$'


def resource(prefix: str, key: Column) -> Column:
    """prefix/ and the key, padded so that the order of names is that of keys."""
    return F.concat(F.lit(f"{prefix}/"), F.lpad(key.cast("string"), WIDTH, "0"))


def triples_from(df: DataFrame, subject: Column, columns: dict[str, Column]) -> DataFrame:
    """One triple (s, p, o) of names for each row and column; a null cell makes none."""
    pairs = F.array(*[F.struct(F.lit(p).alias("p"), c.cast("string").alias("o")) for p, c in columns.items()])
    return df.select(subject.alias("s"), F.explode(pairs).alias("e")).select("s", "e.p", "e.o").where("s is not null and o is not null")


def constants(spark: SparkSession, rows: list[tuple[str, str, str]]) -> DataFrame:
    return spark.createDataFrame(rows, "s string, p string, o string")


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """Lines of the N-Triples form; comments, blank lines and lines of another form give nothing. Angle brackets go,
    literals keep their quotes and tags."""
    lines = spark.read.text(path).where(F.col("value").rlike(NTRIPLE))
    term = lambda i: F.regexp_replace(F.regexp_extract("value", NTRIPLE, i), "^<(.*)>$", "$1")
    return lines.select(term(1).alias("s"), term(2).alias("p"), term(3).alias("o"))


def write_ntriples(triples: DataFrame, path: str) -> None:
    form = lambda c: F.when(F.col(c).rlike('^(_:|")'), F.col(c)).otherwise(F.concat(F.lit("<"), F.col(c), F.lit(">")))
    triples.select(F.concat_ws(" ", form("s"), form("p"), form("o"), F.lit(".")).alias("value")).write.mode("overwrite").text(path)


def read_csv_triples(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.csv(path, schema="s string, p string, o string", header=True)

"""The map of representatives as a flat table, and what is done with it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eqmat.components import connected_components
from eqmat.operators.dictionary import empty
from eqmat.storage import counted


BROADCAST_ROWS = 1_000_000  # rows of 16 bytes


class RepMap:
    """rows(member, rep): only resources that have been replaced; any other represents itself. One hop deep. n: how many,
    where that was counted."""

    def __init__(self, rows: DataFrame, n: int | None = None):
        self.rows, self.n = rows, n

    @classmethod
    def identity(cls, spark: SparkSession) -> RepMap:
        return cls(empty(spark, "member long, rep long"), 0)

    def normalise(self, df: DataFrame, columns=("s", "p", "o")) -> DataFrame:
        """df with each resource in columns replaced by its representative; a map that was counted and is small enough is
        broadcast, else rows travel to it, and a resource of very many rows is left to the adaptive skew join."""
        if self.n == 0:
            return df
        return self._through(df, columns, F.broadcast(self.rows) if self.n is not None and self.n <= BROADCAST_ROWS else self.rows)

    @staticmethod
    def _through(df: DataFrame, columns, rows: DataFrame) -> DataFrame:
        order = df.columns
        for c in columns:
            m = rows.select(F.col("member").alias("_m"), F.col("rep").alias("_r"))
            df = df.join(m, F.col(c) == F.col("_m"), "left").withColumn(c, F.coalesce("_r", c)).drop("_m", "_r")
        return df.select(*order)

    def merge(self, edges: DataFrame, method: str = "star") -> tuple[RepMap, DataFrame, int]:
        """Unite the ends of edges(u, v), which are representatives. Returns the new map, changed(member, rep), the
        representatives that have been retired, and their number. The smallest of a clique stays, so the order of merging
        is of no matter."""
        comps = connected_components(edges, method)
        changed, seen = counted(comps.where("node <> comp").select(F.col("node").alias("member"), F.col("comp").alias("rep")), "changed")
        if self.n == 0:
            return RepMap(changed, seen["n"]), changed, seen["n"]
        moved = self._through(self.rows, ("rep",), F.broadcast(changed) if seen["n"] <= BROADCAST_ROWS else changed)
        rows, all_ = counted(moved.unionByName(changed), "rep_map")
        return RepMap(rows, all_["n"]), changed, seen["n"]

    def members(self, of: DataFrame | None = None) -> DataFrame:
        """(rep, member) with each representative as its own first member; ``of``(rep) adds resources that stand alone."""
        own = self.rows.select("rep").distinct()
        own = own if of is None else own.unionByName(of.select("rep")).distinct()
        return self.rows.select("rep", "member").unionByName(own.select("rep", F.col("rep").alias("member")))

    def sizes(self) -> DataFrame:
        """(rep, n) for cliques of more than one."""
        return self.rows.groupBy("rep").agg((F.count("*") + 1).alias("n"))

    def lookup(self, ids) -> dict[int, int]:
        """Representatives of a few ids."""
        wanted = list(dict.fromkeys(ids))
        found = {r["member"]: r["rep"] for r in self.rows.where(F.col("member").isin(wanted)).collect()} if wanted else {}
        return {i: found.get(i, i) for i in wanted}


def expand(facts: DataFrame, rep_map: RepMap, columns=("s", "p", "o")) -> DataFrame:
    """Every triple whose normal form is among facts."""
    out, twins = facts, rep_map.members().select(F.col("rep").alias("_r"), F.col("member").alias("_x"))
    if rep_map.n == 0:
        return facts
    for c in columns:  # one join each: a union of what stays and what is copied would make the facts twice for each column
        out = out.join(twins, F.col(c) == F.col("_r"), "left").withColumn(c, F.coalesce("_x", c)).drop("_r", "_x")
    return out.select(*facts.columns)


def weigh(facts: DataFrame, rep_map: RepMap, columns=("s", "p", "o")) -> DataFrame:
    """facts with n: how many triples each stands for."""
    out = facts.withColumn("n", F.lit(1).cast("long"))
    for c in columns:
        sizes = rep_map.sizes().select(F.col("rep").alias("_r"), F.col("n").alias("_n"))
        out = out.join(sizes, F.col(c) == F.col("_r"), "left").withColumn("n", F.col("n") * F.coalesce("_n", F.lit(1))).drop("_r", "_n")
    return out


def expansion_count(facts: DataFrame, rep_map: RepMap) -> DataFrame:
    """The size of the expansion, without expanding."""
    return weigh(facts, rep_map).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("triples"))

"""Closed forms of what axiomatised equality costs, known before anything runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def clique_cost(n: int) -> tuple[int, int]:
    """Equality triples of a clique of n, and the derivations that make them under the axioms."""
    return n * n, 2 * n * n * n + n * n + n  # products, so that a column of whole numbers stays one


def triple_cost(ns: int, np: int, no: int) -> tuple[int, int]:
    """Copies of a triple whose terms have cliques of these sizes, and derivations of each copy."""
    return ns * np * no, ns + np + no


def axiom_estimate(sizes: DataFrame) -> DataFrame:
    """eq_triples, eq_derivations over all cliques of sizes(rep, n)."""
    n = F.col("n").cast("long")
    return sizes.agg(F.coalesce(F.sum(n * n), F.lit(0)).alias("eq_triples"), F.coalesce(F.sum(2 * n * n * n + n * n + n), F.lit(0)).alias("eq_derivations"))

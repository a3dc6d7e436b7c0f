"""Connected components over an edge table: each node gets the smallest node it can reach."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eqmat.storage import saved

METHODS = ("star", "min_label", "driver")


def _clean(edges: DataFrame) -> DataFrame:
    u, v = F.col("u"), F.col("v")
    return edges.where(u.isNotNull() & v.isNotNull() & (u != v)).select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()


def _mark(df: DataFrame) -> tuple:
    """Count and order-free digest of a table, to see whether a round has changed it."""
    row = df.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x")).first()
    return row["n"], row["x"]


def _lower(edges: DataFrame) -> DataFrame:
    """Hang the larger neighbours of each node, and the node itself, from its smallest neighbour. edges: u > v."""
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), F.least("u", "m").alias("m"))
    return both.join(low, both.u == low.k).where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _gather(edges: DataFrame) -> DataFrame:
    """Hang each node's smaller neighbours, and the node itself, from the smallest of them. edges: u > v."""
    low = edges.groupBy("u").agg(F.min("v").alias("m")).withColumnRenamed("u", "k")
    moved = edges.join(low, edges.u == low.k).select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(low.select(F.col("k").alias("u"), F.col("m").alias("v"))).where("u <> v").distinct()


def _star(edges: DataFrame, most_rounds: int) -> DataFrame:
    now = saved(_clean(edges), "edges")
    mark = _mark(now)
    for _ in range(most_rounds):
        if not mark[0]:
            break
        now = saved(_gather(_lower(now)), "edges")
        was, mark = mark, _mark(now)
        if was == mark:
            break
    else:
        raise RuntimeError("components: more rounds than allowed")
    tops = now.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("comp"))
    return now.select(F.col("u").alias("node"), F.col("v").alias("comp")).unionByName(tops)


def _min_label(edges: DataFrame, most_rounds: int) -> DataFrame:
    edges = saved(_clean(edges), "edges")
    both = saved(edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))), "edges")
    now = saved(both.select(F.col("u").alias("node")).distinct().select("node", F.col("node").alias("comp")), "labels")
    for _ in range(most_rounds):
        seen = both.join(now, both.v == now.node).groupBy("u").agg(F.min("comp").alias("m"))
        step = now.join(seen, now.node == seen.u).select("node", F.least("comp", "m").alias("comp"), (F.col("m") < F.col("comp")).alias("moved"))
        step = saved(step, "labels")
        now = step.select("node", "comp")
        if step.where("moved").limit(1).count() == 0:
            return now
    raise RuntimeError("components: more rounds than allowed")


def _driver(edges: DataFrame, limit: int) -> DataFrame:
    rows = _clean(edges).limit(limit + 1).collect()
    if len(rows) > limit:
        return _star(edges, 100)
    up: dict = {}

    def top(x):
        while up.setdefault(x, x) != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for u, v in rows:
        a, b = top(u), top(v)
        up[max(a, b)] = min(a, b)
    kind = edges.schema["u"].dataType.simpleString()
    return edges.sparkSession.createDataFrame([(x, top(x)) for x in list(up)], f"node {kind}, comp {kind}")


def connected_components(edges: DataFrame, method: str = "star", most_rounds: int = 100, driver_edge_limit: int = 200_000) -> DataFrame:
    """(node, comp) for every node of edges(u, v); comp is the smallest node of the component.

    ``star`` alternates two contraction steps until the table is a set of stars; ``min_label`` spreads the smallest
    label hop by hop (rounds grow with the diameter; for comparison); ``driver`` runs union-find on the driver when a
    bounded read shows at most ``driver_edge_limit`` edges and goes on as ``star`` beyond it. Null ends and loops are
    ignored; repeated edges count once.
    """
    if method not in METHODS:
        raise ValueError(f"unknown method {method!r}")
    if method == "driver":
        return _driver(edges, driver_edge_limit)
    return _star(edges, most_rounds) if method == "star" else _min_label(edges, most_rounds)

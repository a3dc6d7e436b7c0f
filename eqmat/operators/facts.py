"""Facts in immutable layers. A layer holds what one round has added; outdated facts are marked, not removed.

Layers are merged by size, so a fact is written again a few times at most, and marked facts leave a layer when it is
written again. Layers of many facts lie in folders by bucket of predicate, so an atom with a constant predicate reads
only its own; in all layers files are sorted by predicate and subject, so row groups are passed over by their bounds.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eqmat.operators.dictionary import empty
from eqmat.operators.mapping import RepMap
from eqmat.plans.rules import EQ_ID
from eqmat.storage import counted

KEYS = ["s", "p", "o"]
MOST_LAYERS = 8  # layers that are read side by side before the smaller half is written as one
BUCKETED_FROM = 5_000_000  # facts of a layer that is laid out by predicate
BUCKETS = 64
DEAD_SHARE = 0.2  # share of marked facts beyond which all layers are written again without them
LISTED = 1_000  # retired resources that are named in a filter, which reaches the scan
BROADCAST_ROWS = 1_000_000  # rows of 16 bytes that are broadcast after they were counted


def bucket(p) -> F.Column:
    return F.pmod(p, F.lit(BUCKETS)).cast("int")


class FactStore:
    """layers: facts(s, p, o, born, pb) with their numbers; marked: outdated(s, p, o) with theirs; dropped: how many
    marked facts are in no layer any more."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.layers: list[tuple[DataFrame, int]] = []
        self.marked: list[tuple[DataFrame, int]] = []
        self.dropped = 0

    def everything(self) -> DataFrame:
        """All facts of the layers, marked or not."""
        return reduce(DataFrame.unionByName, [x for x, _ in self.layers]) if self.layers else empty(self.spark, "s long, p long, o long, born int, pb int")

    def outdated(self) -> DataFrame:
        return reduce(DataFrame.unionByName, [x for x, _ in self.marked]) if self.marked else empty(self.spark, "s long, p long, o long")

    def live(self) -> DataFrame:
        return self.everything().join(self.outdated(), KEYS, "left_anti") if self.marked else self.everything()

    def total(self) -> int:
        """All facts there ever were."""
        return sum(n for _, n in self.layers) + self.dropped

    def total_live(self) -> int:
        return sum(n for _, n in self.layers) - sum(n for _, n in self.marked)

    def absent(self, candidates: DataFrame, among: list[int] | None = None) -> DataFrame:
        """The distinct candidates that are in no layer. A retired fact never comes back, marked or dropped: candidates
        are normal, and it holds a resource that has been replaced. ``among``: the only predicates that candidates have."""
        new = candidates.select(*KEYS).distinct()
        own = self.everything() if among is None else self.everything().where(F.col("p").isin(among) & F.col("pb").isin([p % BUCKETS for p in among]))
        return new.join(own.select(*KEYS), KEYS, "left_anti") if self.layers else new

    def _layer(self, df: DataFrame, expected: int = 0, **watch) -> tuple[DataFrame, dict]:
        df = df.select(*KEYS, "born", bucket(F.col("p")).alias("pb"))
        if expected >= BUCKETED_FROM:  # hot predicates are dealt by subject too
            df = df.repartition("pb", F.pmod(F.xxhash64("s"), F.lit(BUCKETS)))
        layer, seen = counted(df.sortWithinPartitions("p", "s"), "layer", partition_by=["pb"] if expected >= BUCKETED_FROM else None, **watch)
        return layer, seen

    def add(self, candidates: DataFrame, born: int, neq: int = 2, expected: int = 0, among: list[int] | None = None) -> tuple[DataFrame, dict[str, int]]:
        """Write the absent ones as facts born in a round; returns them and counts: n, eq (equalities of two resources)
        and clash (resources that differ from themselves)."""
        eq, same = F.col("p") == EQ_ID, F.col("s") == F.col("o")
        layer, seen = self._layer(self.absent(candidates, among).withColumn("born", F.lit(born)), expected, eq=eq & ~same, clash=(F.col("p") == neq) & same)
        if seen["n"]:
            self.layers.append((layer, seen["n"]))
        self._tidy()
        return layer, seen

    def _tidy(self) -> None:
        """Write the smaller half of many layers as one, and all of them without marked facts where those are many."""
        dead = sum(n for _, n in self.marked)
        if dead > DEAD_SHARE * sum(n for _, n in self.layers):
            layer, seen = self._layer(self.live(), self.total_live())
            self.dropped += dead
            self.layers, self.marked = [(layer, seen["n"])], []
        if len(self.layers) > MOST_LAYERS:
            self.layers.sort(key=lambda x: x[1])
            small, self.layers = self.layers[: MOST_LAYERS // 2 + 1], self.layers[MOST_LAYERS // 2 + 1 :]
            self.layers.append((self._layer(reduce(DataFrame.unionByName, [x for x, _ in small]), sum(n for _, n in small))[0], sum(n for _, n in small)))
        if len(self.marked) > MOST_LAYERS:
            self.marked = [(counted(self.outdated(), "marked")[0], sum(n for _, n in self.marked))]

    def retire(self, changed: DataFrame, n_changed: int, rep_map: RepMap, born: int, neq: int = 2, method: str = "index") -> tuple[DataFrame, dict[str, int], int]:
        """Mark live facts with a retired resource and add their normal forms, in one scan. ``index`` looks for changed
        (member, rep): where these are few they are named in the filter of the scan, where not too many they are
        broadcast. ``full_scan`` normalises all facts by the whole map and compares. Returns the new layer, its counts
        and the number marked."""
        live = self.live().select(*KEYS)
        by = changed if method == "index" else rep_map.rows
        if method == "index" and n_changed <= LISTED:
            ids = [r["member"] for r in changed.select("member").collect()]
            live = live.where(F.col("s").isin(ids) | F.col("p").isin(ids) | F.col("o").isin(ids))
        if method == "index" and n_changed <= BROADCAST_ROWS:
            by = F.broadcast(by)
        both = RepMap._through(live.select(*KEYS, *[F.col(c).alias(f"{c}_was") for c in KEYS]), KEYS, by)
        both = both.where("s <> s_was or p <> p_was or o <> o_was")
        old, seen = counted(both, "marked")
        if not seen["n"]:
            return old.select(*KEYS).withColumn("born", F.lit(born)).withColumn("pb", bucket(F.col("p"))).limit(0), {"n": 0, "eq": 0, "clash": 0}, 0
        gone, _ = counted(old.select(*[F.col(f"{c}_was").alias(c) for c in KEYS]), "marked")
        self.marked.append((gone, seen["n"]))
        layer, new = self.add(old.select(*KEYS), born, neq)
        return layer, new, seen["n"]

    def compact(self) -> DataFrame:
        """Only the live facts, written by predicate, hot predicates over many files."""
        layer, _ = self._layer(self.live(), max(self.total_live(), BUCKETED_FROM))
        return layer.drop("pb")

"""Rules that pair all resources with one key and whose conclusions nothing reads: counted instead of listed.

``?x q ?y`` then holds in the union, over the keys, of all pairs of what has the key. What has which key is a table that
grows with the facts; the pairs grow with its square. All counts that a run reports of such conclusions follow from it.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eqmat.operators import matcher
from eqmat.plans.rules import EQ_ID, NEQ_ID, Rule, Var
from eqmat.storage import counted, keyed, saved


class MustBeListed(ValueError):
    """The predicate of counted pairs has become equal to something else."""


def countable(rules: list[Rule], live: DataFrame) -> list[Pairs]:
    """The rules of a program whose conclusions can be counted: no body can match them, and their predicate is in no
    fact and no other rule, so that it takes part in nothing else."""
    if any(isinstance(a.p, Var) for r in rules for a in (r.head, *r.body)):
        return []
    out = []
    for r in rules:
        q = r.head.p
        alone = q not in (EQ_ID, NEQ_ID) and sum(c == q for other in rules for c in other.constants) == 1
        if alone and matcher.keyed_half(r, (q,)) and live.where((F.col("s") == q) | (F.col("p") == q) | (F.col("o") == q)).isEmpty():
            out.append(Pairs(r))
    return out


class Pairs:
    """The conclusions of one rule. rows(k, x): what has which key; live: pairs that hold, total: all there ever were."""

    def __init__(self, rule: Rule):
        self.q, self.label = rule.head.p, rule.name or repr(rule.shape)
        self.rows: DataFrame | None = None
        self.live = self.total = 0

    def rule_among(self, rules: list[Rule]) -> Rule:
        """The rule as rewriting has left it."""
        own = [r for r in rules if r.head.p == self.q]
        if len(own) != 1:
            raise MustBeListed(self.label)
        return own[0]

    def meet(self, rule: Rule, facts: DataFrame, older: DataFrame | None) -> tuple[int, int]:
        """Take in what the rule gives from facts. Returns how many matches have a fact that is not among ``older`` (None:
        all) and how many pairs are new. What held before holds on among facts, or in its normal form."""
        half = matcher.keyed_half(rule, (self.q,))
        if half is None:
            raise MustBeListed(self.label)
        found = saved(_having(rule, half, facts), "having")
        n = _matches(found) - (_matches(_having(rule, half, older)) if older is not None else 0)
        if not n:
            return 0, 0
        self.rows, before = found.select("k", "x"), self.live
        self.live = pair_count(self.rows)
        self.total += self.live - before
        return n, self.live - before

    def retire(self, changed: DataFrame) -> tuple[int, int]:
        """Mark the pairs of resources in changed(member, rep) and add their normal forms: how many are marked and added."""
        if self.rows is None:
            return 0, 0
        both = self.rows.join(changed, F.col("x") == F.col("member"), "left")
        both, seen = counted(both.select("k", "x", "rep"), "paired", moved=F.col("rep").isNotNull())
        if not seen["moved"]:
            return 0, 0
        stay, before = pair_count(both.where("rep is null").select("k", "x")), self.live
        self.rows = both.select("k", F.coalesce("rep", "x").alias("x")).distinct()
        self.live = pair_count(self.rows)
        self.total += self.live - stay
        return before - stay, self.live - stay

    def listed(self) -> DataFrame:
        """The pairs that hold, as facts."""
        one, other = self.rows.select("k", F.col("x").alias("s")), self.rows.select("k", F.col("x").alias("o"))
        return one.join(other, "k").select("s", F.lit(self.q).cast("long").alias("p"), "o").distinct()

    def by_end(self) -> DataFrame:
        """_c, n: in how many pairs a resource is the first one, which is also in how many it is the second."""
        sets = _key_sets(self.rows)
        kinds, met = _partners(sets)
        return sets.join(kinds.join(met, "kind"), "keys").select(F.col("x").alias("_c"), F.col("partners").alias("n"))


def _having(rule: Rule, half: tuple[int, ...], facts: DataFrame) -> DataFrame:
    """k, x, n: what has which key by one half of the body, and the number of its matches."""
    body = tuple(rule.body[i] for i in half)
    rest = {v for i, a in enumerate(rule.body) if i not in half for v in a.variables}
    key = sorted(f"v_{v}" for v in {v for a in body for v in a.variables} & rest)
    found = matcher.bind(body, None, [facts] * len(body))
    return found.groupBy(F.struct(*key).alias("k"), F.col(f"v_{rule.head.s.name}").alias("x")).agg(F.count("*").alias("n"))


def _matches(having: DataFrame) -> int:
    return having.groupBy("k").agg(F.sum("n").alias("n")).agg(F.coalesce(F.sum(F.col("n") * F.col("n")), F.lit(0))).first()[0]


def _key_sets(rows: DataFrame) -> DataFrame:
    return rows.groupBy("x").agg(F.sort_array(F.collect_list("k")).alias("keys"))


def _partners(sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The sets of keys that resources have, numbered and with how many n have them, and for each how many resources
    share a key with it."""
    kinds, name = keyed(sets.groupBy("keys").agg(F.count("*").alias("n")), "kinds")
    kinds = kinds.withColumnRenamed(name, "kind")
    return kinds, _met(kinds, "keys").groupBy("kind").agg(F.sum("m").alias("partners"))


def _met(kinds: DataFrame, keys: str) -> DataFrame:
    """kind, with, n, m: the pairs of kinds that share a key, and how many resources are of each."""
    one = kinds.select("kind", "n", F.explode(keys).alias("k"))
    other = one.select("k", F.col("kind").alias("with"), F.col("n").alias("m"))
    return one.join(other, "k").select("kind", "with", "n", "m").distinct()


def pair_count(rows: DataFrame) -> int:
    """How many pairs share a key, each counted once however many keys it shares."""
    kinds, met = _partners(_key_sets(rows))
    return kinds.join(met, "kind").agg(F.coalesce(F.sum(F.col("n") * F.col("partners")), F.lit(0))).first()[0]


def pair_difference(own: DataFrame | None, other: DataFrame | None) -> tuple[int, int]:
    """How many pairs of other(k, x) are no pairs of own(k, x), and the other way. Keys are compared within each side only;
    resources with the same keys on both sides are met together, so that pairs are counted and not listed."""
    if own is None or other is None:
        return (pair_count(other) if other is not None else 0, pair_count(own) if own is not None else 0)
    sides = [_key_sets(x).withColumnRenamed("keys", name) for x, name in ((own, "a"), (other, "b"))]
    kinds, name = keyed(sides[0].join(sides[1], "x", "full_outer").groupBy("a", "b").agg(F.count("*").alias("n")), "kinds")
    kinds = kinds.withColumnRenamed(name, "kind")
    a, b = (_met(kinds, c).withColumn(f"in_{c}", F.lit(True)) for c in ("a", "b"))
    both, pairs = a.join(b, ["kind", "with", "n", "m"], "full_outer"), F.col("n") * F.col("m")
    sums = [F.coalesce(F.sum(F.when(F.col(c).isNull(), pairs)), F.lit(0)) for c in ("in_a", "in_b")]
    return tuple(both.agg(*sums).first())


def ends(pairs: list[Pairs]) -> DataFrame | None:
    """_c, n over all of them."""
    parts = [p.by_end() for p in pairs if p.live]
    return reduce(DataFrame.unionByName, parts) if parts else None

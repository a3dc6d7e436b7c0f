"""Queries on a rewritten materialisation, answered as if all triples were there.

A column of bindings is folded as long as it holds representatives that stand for whole cliques. Joins run on folded
columns; a folded column that is dropped multiplies the weight of its row by the size of its clique; a column that a
builtin reads is unfolded first, and then never counted again.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eqmat.functions.builtins import call
from eqmat.operators import matcher
from eqmat.operators.dictionary import empty, lookup
from eqmat.operators.mapping import BROADCAST_ROWS, RepMap, expand
from eqmat.operators.materialise import Materialisation
from eqmat.plans import query as q
from eqmat.plans.rules import Var
from eqmat.storage import counted

SHARE = 1 << 14  # answers that one row stands for when answers become rows
FOLDED, UNFOLDED, VALUE = "folded", "unfolded", "value"  # a value is not in the dictionary


@dataclass
class Solutions:
    """Bindings: columns v_<name> and weight, with the state of each variable."""

    df: DataFrame
    state: dict[str, str]


class Answering:
    """Evaluates query trees. ``posthoc`` is the faulty common way: no weights, builtins on representatives, unfolding
    last."""

    def __init__(self, facts: DataFrame, rep_map: RepMap, terms: DataFrame, posthoc: bool = False):
        self.facts, self.map, self.terms, self.posthoc = facts, rep_map, terms, posthoc
        self.spark = facts.sparkSession

    # Folding and weights

    def unfold(self, s: Solutions, names) -> Solutions:
        df, state = s.df, dict(s.state)
        for v in names:
            if state.get(v) != FOLDED:
                continue
            c, columns = f"v_{v}", df.columns
            state[v] = UNFOLDED
            if self.map.n != 0:
                twins = self.map.members().select(F.col("rep").alias("_r"), F.col("member").alias("_x"))
                df = df.join(twins, F.col(c) == F.col("_r"), "left").withColumn(c, F.coalesce("_x", c)).select(*columns)
        return Solutions(df, state)

    def _sized(self, df: DataFrame, v: str) -> DataFrame:
        sizes = self.map.sizes().select(F.col("rep").alias("_r"), F.col("n").alias("_n"))
        return df.join(sizes, F.col(f"v_{v}") == F.col("_r"), "left").withColumn("weight", F.col("weight") * F.coalesce("_n", F.lit(1))).drop("_r", "_n")

    def drop(self, s: Solutions, names) -> Solutions:
        df, state = s.df, dict(s.state)
        for v in names:
            if state.pop(v) == FOLDED and not self.posthoc:
                df = self._sized(df, v)
            df = df.drop(f"v_{v}")
        return Solutions(df, state)

    def _texts(self, s: Solutions, args) -> tuple[DataFrame, list]:
        """Bindings with the lexical forms of variable arguments, and the arguments to call a builtin with."""
        df, out = s.df, []
        for i, a in enumerate(args):
            if not isinstance(a, Var):
                out.append(a)
            elif s.state[a.name] == VALUE:
                out.append(F.col(f"v_{a.name}"))
            else:
                t = self.terms.select(F.col("id").alias(f"_i{i}"), F.col("lexical").alias(f"_t{i}"))
                df = df.join(t, F.col(f"v_{a.name}") == F.col(f"_i{i}"), "left").drop(f"_i{i}")
                out.append(F.col(f"_t{i}"))
        return df, out

    def _align(self, a: Solutions, b: Solutions, names) -> tuple[Solutions, Solutions]:
        """Both with the named variables in one state."""
        odd = [v for v in names if a.state[v] != b.state[v]]
        return self.unfold(a, odd), self.unfold(b, odd)

    # Nodes

    def run(self, node: q.Node) -> Solutions:
        return getattr(self, "_" + type(node).__name__.lower())(node)

    def _pattern(self, node: q.Pattern) -> Solutions:
        names = [t for a in node.atoms for t in a.terms if not isinstance(t, Var)]
        ids = lookup(self.terms, [n for n in names if isinstance(n, str)])
        variables = list(dict.fromkeys(v for a in node.atoms for v in a.variables))
        state = dict.fromkeys(variables, FOLDED)
        if any(isinstance(n, str) and n not in ids for n in names):
            return Solutions(empty(self.spark, ", ".join([*[f"v_{v} long" for v in variables], "weight long"])), state)
        reps = self.map.lookup(ids.values())
        atoms = [a.map(lambda n: reps[ids[n]] if isinstance(n, str) else n) for a in node.atoms]
        order = matcher._order(tuple(atoms), 0, set())
        df = reduce(matcher._joined, [matcher.match_atom(self.facts, atoms[i]) for i in order])
        return Solutions(df.withColumn("weight", F.lit(1).cast("long")), state)

    def _values(self, node: q.Values) -> Solutions:
        t = self.terms.where(F.col("lexical").isin(list(node.names))).select(F.col("id").alias(f"v_{node.var}"), F.lit(1).cast("long").alias("weight"))
        return Solutions(t, {node.var: UNFOLDED})

    def _loose(self, node: q.Node) -> set[str]:
        """Variables that an answer of a tree may leave unbound."""
        if isinstance(node, (q.Pattern, q.Values)):
            return set()
        if isinstance(node, (q.Join, q.Optional, q.Minus, q.Union)):
            left, right = self._loose(node.left), self._loose(node.right)
            mine, other = self.names(node.left), self.names(node.right)
            if isinstance(node, q.Minus):
                return left
            if isinstance(node, q.Union):
                return left | right | (mine ^ other)
            if isinstance(node, q.Optional):
                return left | (other - mine)
            return (left - other) | (right - mine) | (left & right)
        inner = self._loose(node.of) if not isinstance(node, q.Group) else self._loose(node.of) & set(node.keys)
        return inner & self.names(node)

    def names(self, node: q.Node) -> set[str]:
        """Variables that a tree may bind."""
        if isinstance(node, q.Pattern):
            return {v for a in node.atoms for v in a.variables}
        if isinstance(node, q.Values):
            return {node.var}
        if isinstance(node, q.Minus):
            return self.names(node.left)
        if isinstance(node, (q.Join, q.Optional, q.Union)):
            return self.names(node.left) | self.names(node.right)
        if isinstance(node, q.Project):
            return set(node.names)
        if isinstance(node, q.Group):
            return {*node.keys, *[name for name, _ in node.counts]}
        return self.names(node.of) | ({node.var} if isinstance(node, q.Bind) else set())

    def _both(self, node) -> tuple[Solutions, Solutions, list[str], list[str]]:
        """Both sides in one state, their shared variables, and those of them that either side may leave unbound."""
        a, b = self.run(node.left), self.run(node.right)
        shared = [v for v in a.state if v in b.state]
        loose = self._loose(node.left) | self._loose(node.right)
        return *self._align(a, b, shared), shared, [v for v in shared if v in loose]

    @staticmethod
    def _renamed(df: DataFrame, shared: list[str]) -> DataFrame:
        return df.select(*[F.col(c).alias(f"_b{c}" if c[2:] in shared else "_w" if c == "weight" else c) for c in df.columns])

    @staticmethod
    def _compatible(shared: list[str], loose: list[str]) -> Column:
        """Equal in every shared variable that both have bound; an unbound one agrees with anything. What is surely bound
        stays an equality, so that the join is by key."""
        out = F.lit(True)
        for v in shared:
            x, y = F.col(f"v_{v}"), F.col(f"_bv_{v}")
            out = out & ((x == y) | x.isNull() | y.isNull() if v in loose else x == y)
        return out

    def _join(self, node: q.Join, how: str = "inner") -> Solutions:
        a, b, shared, loose = self._both(node)
        df = a.df.join(self._renamed(b.df, shared), self._compatible(shared, loose), how)
        df = df.withColumn("weight", F.col("weight") * F.coalesce("_w", F.lit(1))).drop("_w")
        merged = [F.coalesce(f"v_{v}", f"_bv_{v}").alias(f"v_{v}") if v in loose else F.col(f"v_{v}") for v in shared]
        rest = [c for c in df.columns if not c.startswith("_bv_") and c[2:] not in shared]
        return Solutions(df.select(*merged, *rest), {**b.state, **a.state})

    def _optional(self, node: q.Optional) -> Solutions:
        return self._join(node, "left")

    def _minus(self, node: q.Minus) -> Solutions:
        """An answer goes if one on the right agrees with it and both bind some variable."""
        a, b, shared, loose = self._both(node)
        if not shared:
            return a
        common = F.lit(False)
        for v in shared:
            common = common | (F.col(f"v_{v}").isNotNull() & F.col(f"_bv_{v}").isNotNull())
        test = self._compatible(shared, loose) & (common if set(shared) == set(loose) else F.lit(True))
        return Solutions(a.df.join(self._renamed(b.df, shared).select(*[f"_bv_{v}" for v in shared]), test, "left_anti"), a.state)

    def _union(self, node: q.Union) -> Solutions:
        a, b, _, _ = self._both(node)
        return Solutions(a.df.unionByName(b.df, allowMissingColumns=True), {**b.state, **a.state})

    def _filter(self, node: q.Filter) -> Solutions:
        s = self.run(node.of)
        read = [a.name for a in node.args if isinstance(a, Var)]
        if node.fn in ("bound", "unbound"):  # a representative is bound if its members are
            test = F.col(f"v_{read[0]}").isNotNull() if read[0] in s.state else F.lit(False)
            return Solutions(s.df.where(test if node.fn == "bound" else ~test), s.state)
        if node.fn == "same" and len(read) == 1 and s.state[read[0]] == FOLDED and not self.posthoc:
            name = next(a for a in node.args if not isinstance(a, Var))
            ids = lookup(self.terms, [name])
            if name not in ids:
                return Solutions(s.df.limit(0), s.state)
            c, rep = f"v_{read[0]}", self.map.lookup([ids[name]])[ids[name]]
            return Solutions(s.df.where(F.col(c) == rep).withColumn(c, F.lit(ids[name]).cast("long")), {**s.state, read[0]: UNFOLDED})
        if len(set(read)) == 1 and s.state[read[0]] == FOLDED and not self.posthoc and read[0] not in self._loose(node.of):
            return self._members_that(s, read[0], node)
        if not self.posthoc:
            s = self.unfold(s, read)
        df, args = self._texts(s, node.args)
        return Solutions(df.where(call(node.fn, *args)).select(*s.df.columns), s.state)

    def _members_that(self, s: Solutions, v: str, node: q.Filter) -> Solutions:
        """A filter on one folded variable that is surely bound: names are tested before anything is unfolded, so that
        answers meet only the members that pass."""
        test = call(node.fn, *[F.col("lexical") if isinstance(a, Var) else a for a in node.args])
        passed = self.terms.where(test).select(F.col("id").alias("_x"))
        passed = passed.join(self.map.rows, F.col("_x") == F.col("member"), "left").select("_x", F.coalesce("rep", "_x").alias("_r"))
        passed, seen = counted(passed, "passed")
        if seen["n"] <= BROADCAST_ROWS:
            passed = F.broadcast(passed)
        c = f"v_{v}"
        df = s.df.join(passed, F.col(c) == F.col("_r")).withColumn(c, F.col("_x")).select(*s.df.columns)
        return Solutions(df, {**s.state, v: UNFOLDED})

    def _bind(self, node: q.Bind) -> Solutions:
        s = self.run(node.of)
        if not self.posthoc:
            s = self.unfold(s, [a.name for a in node.args if isinstance(a, Var)])
        df, args = self._texts(s, node.args)
        return Solutions(df.withColumn(f"v_{node.var}", call(node.fn, *args)).select(*s.df.columns, f"v_{node.var}"), {**s.state, node.var: VALUE})

    def _project(self, node: q.Project) -> Solutions:
        """Rows that differ only in what is dropped become one, with their weights added."""
        s = self.run(node.of)
        gone = [v for v in s.state if v not in node.names]
        s = self.drop(s, gone)
        if not gone or not s.state:
            return s
        return Solutions(s.df.groupBy(*[c for c in s.df.columns if c != "weight"]).agg(F.sum("weight").alias("weight")), s.state)

    def _distinct(self, node: q.Distinct) -> Solutions:
        s = self.run(node.of)
        return Solutions(s.df.drop("weight").distinct().withColumn("weight", F.lit(1).cast("long")), s.state)

    def _group(self, node: q.Group) -> Solutions:
        s = self.run(node.of)
        read = [spec[1] for _, spec in node.counts if spec[0] not in ("count", "count_distinct")]
        s = self.unfold(s, read)
        df = s.df
        for v, state in s.state.items():
            if state == FOLDED and v not in node.keys and not self.posthoc:
                df = self._sized(df, v)
        for v in {spec[1] for _, spec in node.counts if len(spec) > 1}:
            if s.state[v] == FOLDED:
                sizes = self.map.sizes().select(F.col("rep").alias(f"_r{v}"), F.col("n").alias(f"_n{v}"))
                df = df.join(sizes, F.col(f"v_{v}") == F.col(f"_r{v}"), "left")
            elif v in read and s.state[v] != VALUE:
                t = self.terms.select(F.col("id").alias(f"_i{v}"), F.col("num").alias(f"_t{v}"))
                df = df.join(t, F.col(f"v_{v}") == F.col(f"_i{v}"), "left")
        keys = [f"v_{k}" for k in node.keys]
        plain = [self._aggregate(name, spec, s) for name, spec in node.counts if spec[0] != "count_distinct"]
        got = df.groupBy(*keys).agg(*plain or [F.count("*").alias("_rows")])
        for name, spec in node.counts:
            if spec[0] == "count_distinct":  # first each value once a group, then the sizes of what it stands for
                v = f"v_{spec[1]}"
                size = F.coalesce(F.col(f"_n{spec[1]}"), F.lit(1)).cast("long") if s.state[spec[1]] == FOLDED and not self.posthoc else F.lit(1).cast("long")
                each = df.select(*keys, F.col(v).alias("_x"), size.alias("_n")).where("_x is not null").distinct()
                sums = each.groupBy(*keys).agg(F.sum("_n").alias(f"v_{name}"))
                both = [F.col(f"_k{k}").eqNullSafe(F.col(k)) for k in keys]
                sums = sums.select(*[F.col(k).alias(f"_k{k}") for k in keys], f"v_{name}")
                got = got.join(sums, reduce(lambda x, y: x & y, both) if both else F.lit(True), "left").drop(*[f"_k{k}" for k in keys])
                got = got.withColumn(f"v_{name}", F.coalesce(f"v_{name}", F.lit(0).cast("long")))
        got = got.select(*keys, *[f"v_{name}" for name, _ in node.counts])
        return Solutions(got.withColumn("weight", F.lit(1).cast("long")), {**{k: s.state[k] for k in node.keys}, **{name: VALUE for name, _ in node.counts}})

    @staticmethod
    def _aggregate(name: str, spec: tuple, s: Solutions) -> Column:
        if spec[0] == "count":
            return F.coalesce(F.sum("weight"), F.lit(0)).alias(f"v_{name}")
        v = spec[1]
        value = F.col(f"v_{v}").cast("double") if s.state[v] == VALUE else F.col(f"_t{v}")
        w = F.col("weight")
        total, n = F.sum(value * w), F.sum(F.when(value.isNotNull(), w))
        return {"sum": total, "avg": total / n, "min": F.min(value), "max": F.max(value)}[spec[0]].alias(f"v_{name}")

    def _replicated(self, df: DataFrame) -> DataFrame:
        """Every answer a row of its own. Weights are cut into shares of at most SHARE, which are dealt out before they
        become rows: one row of a great weight, or few rows, are the work of all tasks."""
        most = F.lit(SHARE).cast("long")
        shares = df.withColumn("_at", F.explode(F.sequence(F.lit(0).cast("long"), F.col("weight").cast("long") - 1, most)))
        shares = shares.withColumn("_n", F.least(most, F.col("weight") - F.col("_at")).cast("int")).drop("_at", "weight")
        dealt = shares.repartition(max(int(self.spark.conf.get("spark.sql.shuffle.partitions")), 1))
        return dealt.withColumn("_again", F.explode(F.sequence(F.lit(1), F.col("_n")))).drop("_again", "_n").withColumn("weight", F.lit(1).cast("long"))

    def _order(self, node: q.Order, most: int | None = None) -> Solutions:
        """Sorted answers; with ``most``, only rows that can be among the first so many, and no row counts for more."""
        s = self.run(node.of)
        s = self.unfold(s, list(s.state))
        df = self._named(s)
        keys = [F.desc(f"v_{k[1:]}") if k[0] == "-" else F.asc(f"v_{k}") for k in node.keys]
        rest = [F.asc(c) for c in sorted(df.columns) if c not in {f"v_{k.lstrip('-')}" for k in node.keys} and c != "weight"]
        if most is not None:  # each row stands for one answer at least
            df = df.orderBy(*keys, *rest).limit(most).withColumn("weight", F.least("weight", F.lit(most)))
        df = self._replicated(df)
        return Solutions(df.orderBy(*keys, *rest), {v: VALUE for v in s.state})

    def _slice(self, node: q.Slice) -> Solutions:
        most = node.n + node.offset
        if isinstance(node.of, q.Order):
            s = self._order(node.of, most)
        else:
            s = self.run(node.of)
            s = self.unfold(s, list(s.state))
            s = Solutions(self._replicated(s.df.limit(most).withColumn("weight", F.least("weight", F.lit(most)))), s.state)
        return Solutions(s.df.offset(node.offset).limit(node.n) if node.offset else s.df.limit(node.n), s.state)

    # Results

    def _named(self, s: Solutions) -> DataFrame:
        df = s.df
        for v, state in s.state.items():
            if state != VALUE:
                t = self.terms.select(F.col("id").alias("_i"), F.col("lexical").alias("_t"))
                df = df.join(t, F.col(f"v_{v}") == F.col("_i"), "left").drop("_i", f"v_{v}").withColumnRenamed("_t", f"v_{v}")
        return df

    def answers(self, node: q.Node, as_weights: bool = False) -> DataFrame:
        """One row for each answer, or each distinct combination with its weight; names in place of ids."""
        s = self.run(node)
        s = self.unfold(s, list(s.state))
        df = self._named(s)
        if not as_weights and not isinstance(node, (q.Order, q.Slice, q.Distinct, q.Group)):  # those are one row an answer already
            df = self._replicated(df)  # last, so that no join sees an answer more than once
        names = list(s.state)
        out = df.select(*[F.col(f"v_{v}").alias(v) for v in names], "weight")
        return out if as_weights else out.drop("weight")

    def ask(self, node: q.Node) -> bool:
        return self.run(node).df.limit(1).count() > 0


def answer(node: q.Node, mat: Materialisation, terms: DataFrame, as_weights: bool = False) -> DataFrame:
    """On representatives, with exact multiplicities."""
    return Answering(mat.facts(), mat.rep_map, terms).answers(node, as_weights)


def answer_posthoc(node: q.Node, mat: Materialisation, terms: DataFrame) -> DataFrame:
    """On representatives, unfolded at the end: wrong under bags and with builtins."""
    return Answering(mat.facts(), mat.rep_map, terms, posthoc=True).answers(node)


def answer_on_expansion(node: q.Node, mat: Materialisation, terms: DataFrame) -> DataFrame:
    """On all triples: right, at the price of large joins."""
    return Answering(expand(mat.facts(), mat.rep_map), RepMap.identity(mat.spark), terms).answers(node)

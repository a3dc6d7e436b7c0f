"""Materialisation: the least set of facts closed under a program, in bulk rounds over immutable layers."""

from __future__ import annotations

import time
from collections.abc import Collection
from dataclasses import dataclass, field
from functools import reduce, wraps
from itertools import count

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from eqmat.components import connected_components
from eqmat.operators import matcher
from eqmat.operators.facts import BROADCAST_ROWS, BUCKETS, KEYS, FactStore, bucket
from eqmat.operators.mapping import RepMap
from eqmat.operators.pairs import MustBeListed, Pairs, countable, ends
from eqmat.plans.rules import EQ_ID, NEQ_ID, Rule, Var, equality_axioms, unique
from eqmat.storage import counted, observed, saved


class Contradiction(ValueError):
    """A resource is said to differ from itself."""


class TooCostly(ValueError):
    """The closed forms say that the axioms would derive more than was allowed."""


@dataclass
class Options:
    measure: bool = True  # count rule applications (one more pass over the new facts)
    reflexive: str = "stored"  # or "virtual": reflexive equalities are not stored but made when they are asked for
    retire: str = "index"  # or "full_scan"
    components: str = "driver"  # union-find for few edges, contraction of the edge table beyond
    rewrite_rules: bool = True
    merge: bool = True
    by_key: bool = True  # while merging: n - 1 equalities for n resources with one key, not n * n; equivalences as edges
    list_pairs: bool = True  # or count what a rule that pairs all of a key concludes, where nothing reads it
    on_contradiction: str = "report"  # or "raise"
    most_rounds: int = 0  # an error beyond so many; 0: as many as it takes, for the fixpoint is finite
    update_rules: str = "driver"  # or "join": the program as rows
    inline: int = matcher.INLINE


@dataclass
class Materialisation:
    spark: SparkSession
    store: FactStore
    rep_map: RepMap
    rules: list[Rule]
    rounds: list[dict] = field(default_factory=list)
    by_rule: dict[str, int] = field(default_factory=dict)
    contradictions: DataFrame | None = None
    consistent: bool = True
    seconds: float = 0.0
    options: Options = field(default_factory=Options)
    next_born: int = 0
    pairs: list[Pairs] = field(default_factory=list)  # conclusions that are counted and in no layer
    neq: int = NEQ_ID  # what represents "is different from"
    _classes: tuple | None = None

    def equivalences(self) -> dict[int, set[Rule]]:
        """Predicates whose facts are held as edges only, with the rules that close them."""
        return matcher.equivalences(self.rules) if self.options.merge and self.options.by_key and self.options.rewrite_rules else {}

    def classes(self) -> DataFrame | None:
        """predicate, member, cls: what the edges of each equivalence connect. None where there is no equivalence."""
        of = sorted(self.equivalences())
        if not of:
            return None
        if self._classes is None or self._classes[0] != (self.next_born, tuple(of)):
            parts = []
            for p in of:
                edges = self.store.live().where((F.col("p") == p) & (F.col("pb") == p % BUCKETS)).select(F.col("s").alias("u"), F.col("o").alias("v"))
                met = connected_components(edges, self.options.components)
                every = edges.select(F.explode(F.array("u", "v")).alias("member")).distinct()
                parts.append(every.join(met, F.col("member") == F.col("node"), "left").select(F.lit(p).cast("long").alias("predicate"), "member", F.coalesce("comp", "member").alias("cls")))
            self._classes = ((self.next_born, tuple(of)), counted(reduce(DataFrame.unionByName, parts), "classes"))
        return self._classes[1][0]

    def hidden(self) -> int:
        """How many live facts are in no layer, since the edges of their predicate stand for them."""
        rows = self.classes()
        if rows is None:
            return 0
        pairs = rows.groupBy("predicate", "cls").count().agg(F.sum(F.col("count") * F.col("count"))).first()[0] or 0
        return pairs - self.store.live().where(F.col("p").isin(list(self.equivalences()))).count()

    def _closed(self, live: DataFrame) -> DataFrame:
        """Live facts with all pairs of each equivalence. Members are dealt out, so that a large class is no single task's."""
        rows = self.classes()
        if rows is None:
            return live
        n = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        other = rows.select("predicate", "cls", F.col("member").alias("o"))
        other = F.broadcast(other) if self._classes[1][1]["n"] <= BROADCAST_ROWS else other
        pairs = rows.repartition(n).join(other, ["predicate", "cls"]).select(F.col("member").alias("s"), F.col("predicate").alias("p"), "o")
        of = list(self.equivalences())
        return live.where(~F.col("p").isin(of)).unionByName(pairs)

    def facts(self, but: Collection[int] | None = None) -> DataFrame:
        """Live facts, with reflexive equalities also where they are virtual and all pairs of equivalences. ``but``: the
        predicates whose counted pairs are left out; those of others are listed."""
        if self.pairs and but is None:
            raise ValueError("some conclusions were counted only: run with list_pairs=True")
        live = self._closed(self.store.live().select(*KEYS))
        live = reduce(DataFrame.unionByName, [p.listed() for p in self.pairs if p.live and p.q not in but], live)
        return live if self.options.reflexive == "stored" or not self.options.merge else live.unionByName(reflexive_facts(live)).distinct()

    def total(self, name: str) -> int:
        return sum(r.get(name, 0) for r in self.rounds)


def reflexive_facts(facts: DataFrame) -> DataFrame:
    """EQ(c, c) for every resource c of facts, with n: the conclusions that collapse into it. A fact with EQ as predicate
    makes EQ(EQ, EQ) too."""
    eq = F.lit(EQ_ID).cast("long")
    some = facts.limit(1).select(eq.alias("c"))
    every = facts.select(F.explode(F.array("s", "p", "o")).alias("c")).unionByName(some)
    return every.distinct().select(F.col("c").alias("s"), eq.alias("p"), F.col("c").alias("o"))


def contradictions(facts: DataFrame, neq: int = NEQ_ID) -> DataFrame:
    """Facts that say of a resource that it differs from itself."""
    return facts.where((F.col("p") == neq) & (F.col("s") == F.col("o"))).select(*KEYS)


def _heads(plans, fresh: set[str], facts: DataFrame, delta: DataFrame, older: DataFrame | None, by_key: bool) -> DataFrame | None:
    """Derived facts with the number of their rule among plans and n, the derivations that a row counts for. No older facts:
    all are new, and every rule meets all of them once. ``by_key``: keyed equalities give edges to the least of a key."""
    parts = []
    for k, p in enumerate(plans):
        whole = older is None or p.label in fresh
        if by_key and p.half is not None:
            found = [matcher.key_edges(p, facts) if whole else matcher.key_edges(p, facts, delta, older)]
        else:
            found = [matcher.fresh_matches(p, facts)] if whole else matcher.delta_matches(p, facts, delta, older)
        parts += [x.selectExpr(f"{k} as rule", *KEYS, "n" if "n" in x.columns else "1L as n") for x in found]
    return reduce(DataFrame.unionByName, parts) if parts else None


def _labelled(plans: list[matcher.Plan]) -> list[matcher.Plan]:
    seen: dict[str, int] = {}
    for p in plans:
        k = seen[p.label] = seen.get(p.label, 0) + 1
        if k > 1:
            p.label = f"{p.label} #{k}"
    return plans


def _inner_merge(mat: Materialisation, delta: DataFrame, n_eq: int, k: int, row: dict) -> tuple[DataFrame, list[DataFrame], int]:
    """Merge the n_eq equalities of delta and rewrite facts until none is left: rewriting can make equalities itself, when
    a predicate joins the clique of EQ. Returns all new facts of the round, what has been retired in it, and how many of
    the facts that rewriting made say of a resource that it differs from itself."""
    opts, gone, clash = mat.options, [], 0
    part = delta
    while n_eq:
        edges = part.where((F.col("p") == EQ_ID) & (F.col("s") != F.col("o"))).select(F.col("s").alias("u"), F.col("o").alias("v"))
        mat.rep_map, changed, n_changed = mat.rep_map.merge(edges, opts.components)
        gone.append(changed)
        for p in mat.pairs:
            marked, n = p.retire(changed)
            row["marked"], row["rewrites"] = row.get("marked", 0) + marked, row.get("rewrites", 0) + n
        row["merged"] = row.get("merged", 0) + n_changed
        layer, seen, marked = mat.store.retire(changed, n_changed, mat.rep_map, k, mat.neq, opts.retire)
        row["marked"] = row.get("marked", 0) + marked
        row["rewrites"] = row.get("rewrites", 0) + seen["n"]
        clash += seen["clash"]
        n_eq, part = seen["eq"], layer
    # What is new and live: facts born in this round.
    return (mat.store.live().where(F.col("born") == k) if gone else delta), gone, clash


def rewrite_rules(rules: list[Rule], changed: list[DataFrame], rep_map: RepMap, method: str = "driver") -> tuple[list[Rule], list[Rule]]:
    """The program under the new map, and those of its rules that were not there before; equal rules collapse.

    ``driver``: only the constants that rules name are looked up, by one filtered read of the map, and rules are rewritten
    one after the other. ``join``: rules are rows of constants by shape, rewritten all at once by a join with what has
    been retired; only rules that change come back. Facts come near neither.
    """
    if not changed or not rules:
        return rules, []
    if method == "join":
        new = _rewritten_by_join(rules, reduce(DataFrame.unionByName, changed), rep_map)
    else:
        moved = rep_map.lookup({c for r in rules for c in r.constants})
        new = unique(r.map(lambda c: moved.get(c, c)) for r in rules)
    before = set(rules)
    return new, [r for r in new if r not in before]


def rule_table(spark: SparkSession, rules: list[Rule]) -> DataFrame:
    """rule, place, constant: a program as rows."""
    return spark.createDataFrame([(i, j, int(c)) for i, r in enumerate(rules) for j, c in enumerate(r.constants)], "rule int, place int, constant long")


def _rewritten_by_join(rules: list[Rule], changed: DataFrame, rep_map: RepMap) -> list[Rule]:
    spark = changed.sparkSession
    constants = rule_table(spark, rules)
    touched = constants.join(changed.select(F.col("member").alias("constant")).distinct(), "constant", "left_semi")
    moved = touched.join(rep_map.rows, F.col("constant") == F.col("member")).select("rule", "place", "rep")
    to: dict[int, dict[int, int]] = {}
    for r in moved.collect():  # at most the constants of the program
        to.setdefault(r["rule"], {})[r["place"]] = r["rep"]
    out = []
    for i, rule in enumerate(rules):
        if i in to:
            places = iter(range(len(rule.constants)))
            rule = rule.map(lambda c, own=to[i], places=places: own.get(next(places), c))
        out.append(rule)
    return unique(out)


def _counting(run):
    """A run that lists pairs after all where their predicate turns out to have equals."""

    @wraps(run)
    def either(spark, facts, rules, *more):
        try:
            return run(spark, facts, rules, *more)
        except MustBeListed:
            return run(spark, facts, rules, *[Options(**{**x.__dict__, "list_pairs": True}) if isinstance(x, Options) else x for x in more])

    return either


@_counting
def _run(spark: SparkSession, facts: DataFrame, rules: list[Rule], opts: Options, mat: Materialisation | None = None) -> Materialisation:
    """Rounds from facts on; ``mat``: a finished run that takes the facts in, with its own rules. A round is one write of
    new facts, whose counts are taken while it writes, one pass for rule applications if they are measured, and, where
    equalities are among the facts, the merge and the write of rewritten ones."""
    began = time.time()
    mat = mat or Materialisation(spark, FactStore(spark), RepMap.identity(spark), unique(rules), options=opts)
    rules, start = mat.rules, mat.next_born
    delta, seen = mat.store.add(mat.rep_map.normalise(facts.select(*KEYS)) if start else facts, start, mat.neq)
    if start and not seen["n"]:
        return mat
    if not start and not opts.list_pairs and (not opts.merge or (opts.rewrite_rules and opts.reflexive == "stored")):
        mat.pairs = countable(rules, mat.store.live())
    eq_in_bodies = any(t == EQ_ID for r in rules for a in r.body for t in a.terms) or any(hasattr(a.p, "name") for r in rules for a in r.body)
    found, named = [mat.contradictions] if mat.contradictions is not None else [], set()
    for k in range(start, start + opts.most_rounds) if opts.most_rounds else count(start):
        row: dict = {"round": k, "delta": seen["n"], "delta_total": seen["n"]}
        gone: list[DataFrame] = []
        clash = seen["clash"]
        closing = {r for own in mat.equivalences().values() for r in own}
        if opts.merge:
            delta, gone, more = _inner_merge(mat, delta, seen["eq"], k, row)
            clash += more
        fresh_rules: list[Rule] = []
        if gone:
            neq = mat.rep_map.lookup([NEQ_ID])[NEQ_ID]
            if neq != mat.neq:
                mat.neq, clash = neq, 1  # facts that were harmless before may not be now: look at all
            if opts.rewrite_rules:
                t = time.time()
                mat.rules, fresh_rules = rewrite_rules(mat.rules, gone, mat.rep_map, opts.update_rules)
                row["rule_update_seconds"] = time.time() - t
        # An equivalence needs no rules to close it; where rewriting has ended one, its rules meet all facts.
        kept = mat.equivalences()
        skip = {r for own in kept.values() for r in own}
        paired = [(p, p.rule_among(mat.rules)) for p in mat.pairs]
        known = {p.q for p in mat.pairs if p.live} - named  # pairs have come up for the first time
        skip.update(r for _, r in paired)
        anew = {r for _, r in paired if r in fresh_rules}
        fresh_rules = [r for r in fresh_rules if r not in skip] + [r for r in mat.rules if r in closing - skip and r not in fresh_rules]
        row["fresh_rules"] = len(fresh_rules) + len(anew)
        live = mat.store.live()
        if clash:
            own = contradictions(live, mat.neq)
            if not own.isEmpty():
                mat.consistent = False
                found.append(saved(own, "clash"))
                if opts.on_contradiction == "raise":
                    raise Contradiction("a resource differs from itself")
        plans = _labelled(matcher.plans_of(spark, [r for r in mat.rules if r not in skip.union(fresh_rules)], opts.inline, (EQ_ID, *kept)))
        new_plans = _labelled(matcher.plans_of(spark, fresh_rules, opts.inline, (EQ_ID, *kept)))
        for p in new_plans:
            p.label = f"{p.label} (rewritten in round {k})"
        every, fresh = plans + new_plans, {p.label for p in new_plans}
        pair_plans = [matcher.Plan(f"{p.label} {p.q} counted", r.head, r.body) for p, r in paired]
        fresh.update(x.label for x, (_, r) in zip(pair_plans, paired, strict=True) if r in anew)
        visible = live if opts.reflexive == "stored" or not opts.merge or not eq_in_bodies else live.unionByName(reflexive_facts(live).withColumns({"born": F.lit(k), "pb": bucket(F.col("p"))})).dropDuplicates(KEYS)
        older = live.where(F.col("born") < k) if k else None
        if opts.measure and (every or pair_plans):
            row["rule_applications"] = matcher.rule_applications(every + pair_plans, delta, visible, fresh)
        heads = _heads(every, fresh, visible, delta, older, opts.merge and opts.by_key)
        candidates, fired = [], Observation()
        if heads is not None:
            counts = [F.coalesce(F.sum(F.when(F.col("rule") == i, F.col("n"))), F.lit(0)).alias(f"r{i}") for i in range(len(every))]
            candidates.append(heads.observe(fired, *counts).select(*KEYS))
        if opts.merge and opts.reflexive == "stored":
            candidates.append(reflexive_facts(delta))
            if known:
                candidates.append(spark.createDataFrame([(q, EQ_ID, q) for q in known], "s long, p long, o long"))
                named |= known
        mat.rounds.append(row)
        n_pairs = 0
        for p, r in paired:
            n, new = p.meet(r, visible, None if older is None or r in anew else older)
            n_pairs += new
            mat.by_rule[p.label] = mat.by_rule.get(p.label, 0) + n
            row["derivations"] = row.get("derivations", 0) + n
        if n_pairs and not candidates:
            candidates.append(delta.limit(0).select(*KEYS))
        if not candidates:
            break
        both = reduce(DataFrame.unionByName, candidates)
        delta, seen = mat.store.add(mat.rep_map.normalise(both) if opts.merge else both, k + 1, mat.neq)
        if heads is not None:
            n = observed(fired)
            if not n and opts.measure:  # nothing was new, so the planner gave up the part that was observed
                n = {f"r{r['rule']}": r["n"] for r in heads.groupBy("rule").agg(F.sum("n").alias("n")).collect()}
            for i, p in enumerate(every):
                mat.by_rule[p.label] = mat.by_rule.get(p.label, 0) + n.get(f"r{i}", 0)
                row["derivations"] = row.get("derivations", 0) + n.get(f"r{i}", 0)
        seen["n"] += n_pairs
        if not seen["n"]:
            break
    else:
        raise RuntimeError("materialisation: more rounds than allowed")
    if mat.pairs and opts.merge and set(mat.rep_map.lookup([p.q for p in mat.pairs]).items()) != {(p.q, p.q) for p in mat.pairs}:
        raise MustBeListed("a predicate of pairs has been replaced")
    mat.contradictions = reduce(DataFrame.unionByName, found).distinct() if found else None
    mat.seconds += time.time() - began
    mat.next_born = k + 2
    return mat


def materialise_rewriting(spark: SparkSession, facts: DataFrame, rules: list[Rule], opts: Options | None = None) -> Materialisation:
    """Rule application, rewriting of facts and rewriting of rules in turns, until nothing changes. facts(s, p, o) of ids;
    rules with ids as constants."""
    return _run(spark, facts, rules, opts or Options())


def extend(mat: Materialisation, facts: DataFrame) -> Materialisation:
    """Take more facts(s, p, o) into a finished materialisation; the result is that of all facts at once, in any order
    and however they are cut into batches, since nothing that was derived is ever taken back."""
    if mat.pairs:
        raise ValueError("some conclusions were counted only: run with list_pairs=True")
    return _run(mat.spark, facts, mat.rules, mat.options, mat)


def materialise_plain(spark: SparkSession, facts: DataFrame, rules: list[Rule], opts: Options | None = None) -> Materialisation:
    """The fixpoint alone; EQ is a predicate like others."""
    opts = opts or Options()
    return _run(spark, facts, rules, Options(**{**opts.__dict__, "merge": False, "rewrite_rules": False}))


def materialise_axiomatised(spark: SparkSession, facts: DataFrame, rules: list[Rule], opts: Options | None = None, with_redundant: bool = False, expected: int | None = None, limit: int = 200_000_000) -> Materialisation:
    """The program with the axioms of equality. ``expected`` derivations, from the closed forms, are refused beyond
    ``limit`` before anything runs. ``Options(by_key=False)`` runs the axioms as rules like others, match by match."""
    if expected is not None and expected > limit:
        raise TooCostly(f"the axioms would derive about {expected} facts")
    opts, axioms = opts or Options(), equality_axioms(EQ_ID, with_redundant)
    mat = _run_axioms(spark, facts, rules, axioms, opts) if opts.by_key else materialise_plain(spark, facts, [*rules, *axioms], opts)
    clash = contradictions(mat.store.live())
    mat.consistent = clash.limit(1).count() == 0
    mat.contradictions = None if mat.consistent else clash
    return mat


def waiting_rules(rules: list[Rule]) -> list[Rule]:
    """Rules whose heads no body of the program can match, nor any axiom but those that replace and reflect: they can wait
    until all else is derived."""
    bodies = [a.p for r in rules for a in r.body]
    if any(isinstance(p, Var) for p in bodies):
        return []
    return [r for r in rules if not isinstance(r.head.p, Var) and r.head.p not in (EQ_ID, *bodies)]


def _copies(facts: DataFrame, classes: RepMap) -> DataFrame:
    """What the replacement axioms make of facts when equality is an equivalence: facts that differ only by equal resources
    are met once, and every combination of members is given."""
    twins = classes.members()
    twins = F.broadcast(twins) if classes.n <= BROADCAST_ROWS else twins
    form, hit = facts.select(*KEYS), F.lit(False)
    for c in KEYS:
        form = form.join(twins.select(F.col("member").alias("_m"), F.col("rep").alias(f"_{c}")), F.col(c) == F.col("_m"), "left").drop("_m")
        hit = hit | F.col(f"_{c}").isNotNull()
    out = form.where(hit).select(*[F.coalesce(f"_{c}", c).alias(c) for c in KEYS]).distinct()
    for c in KEYS:
        out = out.join(twins.select(F.col("rep").alias("_r"), F.col("member").alias("_x")), F.col(c) == F.col("_r"), "left").withColumn(c, F.coalesce("_x", c)).drop("_r", "_x")
        if c == "s":  # a large clique's pairs are no single task's
            out = out.repartition(*KEYS)
    return out.select(*KEYS)


def _axiom_matches(mat: Materialisation, axioms: list[Rule]) -> dict[str, int]:
    """Matches of each axiom in the closure, counted from its facts: those of one resource times its equalities. Rounds
    meet every match once, so this is what they would add up to."""
    live = mat.store.live()
    equal = live.where((F.col("p") == EQ_ID) & (F.col("pb") == EQ_ID % BUCKETS))
    degree = saved(equal.groupBy("s").agg(F.count("*").alias("d")), "degrees")
    total, n, paired = mat.store.total() + sum(p.live for p in mat.pairs), {}, ends(mat.pairs)
    for r in axioms:
        if r.name.startswith("reflexive"):
            n[r.name] = total
        elif r.name == "symmetric":
            n[r.name] = equal.count()
        else:
            c, of = ("o", equal) if r.name == "transitive" else (r.name[-1], live)
            found = of.groupBy(F.col(c).alias("_c")).agg(F.count("*").alias("n"))
            if paired is not None and r.name != "transitive":
                found = found.unionByName(paired if c != "p" else mat.spark.createDataFrame([(p.q, p.live) for p in mat.pairs], "_c long, n long"))
            found = found.join(degree, F.col("_c") == degree.s)
            n[r.name] = int(found.agg(F.coalesce(F.sum(F.col("n") * F.col("d")), F.lit(0))).first()[0])
    return n


@_counting
def _run_axioms(spark: SparkSession, facts: DataFrame, rules: list[Rule], axioms: list[Rule], opts: Options) -> Materialisation:
    """The closure under rules and the axioms of equality, every copy of a fact a row, without a join for each match of an
    axiom. The axioms make equality an equivalence, so a round finds its classes and unfolds each fact over them
    (``_copies``); the rules meet all copies, one round after the other. A rule whose heads feed nothing waits for the
    rest: what it derives then from closed facts is closed under replacement too, unless its own constants have equals."""
    began, rules = time.time(), unique(rules)
    axioms = [a for a in axioms if a not in rules]
    mat = Materialisation(spark, FactStore(spark), RepMap.identity(spark), [*rules, *axioms], options=Options(**{**opts.__dict__, "merge": False, "rewrite_rules": False}))
    late = waiting_rules(rules)
    classes, clash, since = RepMap.identity(spark), 0, 0
    delta, seen = mat.store.add(facts, 0)
    mat.pairs = [] if opts.list_pairs else countable(rules, mat.store.live())
    paired = [(p, p.rule_among(rules)) for p in mat.pairs]
    listed = [r for r in late if r not in {own for _, own in paired}]
    plans, late_plans = (_labelled(matcher.plans_of(spark, own, opts.inline)) for own in ([r for r in rules if r not in late], listed))

    def derive(own, older, k: int, others: list[DataFrame], among=None) -> tuple[DataFrame, dict, dict, list[int]]:
        """Write what own plans derive from the new facts, and others; count the matches of each plan."""
        heads, fired = _heads(own, set(), mat.store.live(), delta if older is not None else mat.store.live(), older, False), Observation()
        parts = [] if heads is None else [heads.observe(fired, *[F.coalesce(F.sum(F.when(F.col("rule") == i, F.col("n"))), F.lit(0)).alias(f"r{i}") for i in range(len(own))]).select(*KEYS)]
        layer, new = mat.store.add(reduce(DataFrame.unionByName, parts + others), k + 1, among=among)
        n = observed(fired) if heads is not None else {}
        if heads is not None and not n:
            n = {f"r{r['rule']}": r["n"] for r in heads.groupBy("rule").agg(F.sum("n").alias("n")).collect()}
        counts = [n.get(f"r{i}", 0) for i in range(len(own))]
        for p, x in zip(own, counts, strict=True):
            mat.by_rule[p.label] = mat.by_rule.get(p.label, 0) + x
        return layer, new, {"derivations": sum(counts)}, counts

    for k in count():
        if opts.most_rounds and k >= opts.most_rounds:
            raise RuntimeError("materialisation: more rounds than allowed")
        row = {"round": k, "delta": seen["n"], "delta_total": seen["n"]}
        mat.rounds.append(row)
        clash += seen["clash"]
        if seen["n"]:
            touched = delta
            if seen["eq"]:
                edges = classes.normalise(delta.where((F.col("p") == EQ_ID) & (F.col("s") != F.col("o"))).select(F.col("s").alias("u"), F.col("o").alias("v")), ("u", "v")).where("u <> v")
                edges, n = counted(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
                if n["n"]:
                    classes, touched = classes.merge(edges, opts.components)[0], mat.store.live()
            others = [reflexive_facts(delta), *([_copies(touched, classes)] if classes.n else [])]
            delta, seen, more, _ = derive(plans, mat.store.live().where(F.col("born") < k) if k else None, k, others)
            row.update(more)
            continue
        if not late:
            break
        # Nothing is left to derive but what waits. All facts born since those rules were last met are new to them.
        own = {t for r in late for t in r.head.terms if not isinstance(t, Var)}
        closed = all(p.table is None for p in late_plans) and (not classes.n or classes.members().where(F.col("member").isin(list(own))).isEmpty())
        if classes.n and paired and not classes.members().where(F.col("member").isin([p.q for p in mat.pairs])).isEmpty():
            raise MustBeListed("the predicate of pairs has equals")
        everything, older = mat.store.live(), mat.store.live().where(F.col("born") < since) if since else None
        delta, seen, more, counts = everything.where(F.col("born") >= since), {"n": 0, "eq": 0, "clash": 0}, {}, []
        if late_plans:
            delta, seen, more, counts = derive(late_plans, older, k, [], sorted({r.head.p for r in listed}))
        row.update(more)
        for p, r in paired:
            n, new = p.meet(r, everything, older)
            mat.by_rule[p.label] = mat.by_rule.get(p.label, 0) + n
            row["derivations"] = row.get("derivations", 0) + n
            seen["n"] += new
            counts.append(n)
        since, clash = k + 1, clash + seen["clash"]
        if closed and seen["n"]:  # only the constants of rules that had matches may be new resources
            met = {t for p, n in zip([*late_plans, *[r for _, r in paired]], counts, strict=True) if n for t in p.head.terms if not isinstance(t, Var)}
            delta, seen = mat.store.add(spark.createDataFrame([(int(c), EQ_ID, int(c)) for c in met], "s long, p long, o long"), k + 1, among=[EQ_ID])
        if not seen["n"]:
            break
    counts = _axiom_matches(mat, axioms) if opts.measure else {}
    mat.by_rule.update(counts)
    if opts.measure:
        mat.rounds[-1]["derivations"] = mat.rounds[-1].get("derivations", 0) + sum(counts.values())
        met = matcher.rule_applications(_labelled(matcher.plans_of(spark, mat.rules, opts.inline)), mat.store.live(), mat.store.live(), set())
        # A pair meets the atoms of the axioms that any fact does; no other atom is without its predicate.
        mat.rounds[-1]["rule_applications"] = met + sum(p.live for p in mat.pairs) * sum(isinstance(a.p, Var) for r in axioms for a in r.body)
    if clash and opts.on_contradiction == "raise":
        raise Contradiction("a resource differs from itself")
    mat.seconds, mat.next_born = time.time() - began, k + 2
    return mat


def materialise_facts_only(spark: SparkSession, facts: DataFrame, rules: list[Rule], opts: Options | None = None) -> Materialisation:
    """Facts are rewritten, rules stay as they are: what is lost when a rule names a resource that has been replaced."""
    opts = opts or Options()
    return _run(spark, facts, rules, Options(**{**opts.__dict__, "rewrite_rules": False}))


def materialise_upfront(spark: SparkSession, facts: DataFrame, rules: list[Rule], opts: Options | None = None) -> Materialisation:
    """Rewriting as preprocessing: the equalities that are given are merged, in facts and rules; those derived later are
    facts like others."""
    first = _run(spark, facts, [], opts or Options())
    moved = first.rep_map.lookup({c for r in rules for c in r.constants})
    mat = materialise_plain(spark, first.facts(), [r.map(lambda c: moved[c]) for r in rules], opts)
    mat.rep_map = first.rep_map
    return mat


def materialise_naive(spark: SparkSession, facts: DataFrame, rules: list[Rule], most_rounds: int = 1000) -> DataFrame:
    """By the definition: every rule on all facts, stage by stage, until a stage adds nothing."""
    now = saved(facts.select(*KEYS).distinct(), "stage")
    n = now.count()
    for _ in range(most_rounds):
        plans = matcher.plans_of(spark, unique(rules))
        if not plans:
            return now
        heads = reduce(DataFrame.unionByName, [matcher.fresh_matches(p, now).select(*KEYS) for p in plans])
        now = saved(now.unionByName(heads).distinct(), "stage")
        was, n = n, now.count()
        if n == was:
            return now
    raise RuntimeError("materialisation: more stages than allowed")


MODES = {"rew": materialise_rewriting, "ax": materialise_axiomatised, "plain": materialise_plain, "facts_only": materialise_facts_only, "upfront": materialise_upfront}

"""Rule bodies as joins. Constants of many rules of one shape are rows of a table, so plans grow with shapes, not rules."""

from __future__ import annotations

from functools import reduce
from itertools import combinations, permutations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eqmat.operators.facts import BUCKETS
from eqmat.plans.rules import EQ_ID, NEQ_ID, Atom, Rule, Var

INLINE = 8  # rules of one shape that are still planned one by one


class Plan:
    """One rule with literal constants, or a table of constants for all rules of a shape. ``label`` names it in counts;
    ``half``, of a keyed equality: the places of one half of its body."""

    def __init__(self, label: str, head: Atom, body: tuple[Atom, ...], table: DataFrame | None = None, half: tuple[int, ...] | None = None):
        self.label, self.head, self.body, self.table, self.half = label, head, body, table, half


LONGEST_KEYED = 6  # atoms of a body that are searched for two equal halves


def equivalences(rules: list[Rule]) -> dict[int, set[Rule]]:
    """Predicates that rules of a program make symmetric and transitive and that no other body can match, with these two
    rules: what holds between two resources is then whether facts of the predicate connect them."""
    found: dict[int, dict[str, Rule]] = {}
    for r in rules:
        p, terms = r.head.p, [t for a in (r.head, *r.body) for t in (a.s, a.o)]
        if isinstance(p, Var) or p in (EQ_ID, NEQ_ID) or any(a.p != p for a in r.body) or not all(isinstance(t, Var) for t in terms):
            continue
        (x, z), ends = (r.head.s, r.head.o), [(a.s, a.o) for a in r.body]
        if x == z:
            continue
        if ends == [(z, x)]:
            found.setdefault(p, {})["symmetric"] = r
        elif len(ends) == 2:
            for (a, b), (c, d) in (ends, ends[::-1]):
                if a == x and d == z and b == c and b not in (x, z):
                    found.setdefault(p, {})["transitive"] = r
    out = {}
    for p, own in found.items():
        two = set(own.values())
        if len(own) == 2 and not any(isinstance(a.p, Var) or a.p == p for r in rules if r not in two for a in r.body):
            out[p] = two
    return out


def keyed_half(rule: Rule | Plan, predicates=(EQ_ID,)) -> tuple[int, ...] | None:
    """Whether a rule makes equal all that agree on a key: ``x = y`` where the body is two copies of one pattern, one
    about x and one about y, that share the variables of the key. Returns the places of the atoms about x, else None.
    ``predicates``: those that count as equality here."""
    x, y, n = rule.head.s, rule.head.o, len(rule.body)
    if rule.head.p not in predicates or not isinstance(x, Var) or not isinstance(y, Var) or x == y or n % 2 or n > LONGEST_KEYED:
        return None
    for half in combinations(range(n), n // 2):
        mine = {v for i in half for v in rule.body[i].variables}
        rest = [i for i in range(n) if i not in half]
        key = mine & {v for i in rest for v in rule.body[i].variables}
        if key and x.name in mine - key and y.name not in mine and any(_renames(rule, half, other, key) for other in permutations(rest)):
            return half
    return None


def _renames(rule: Rule | Plan, half, other, key: set[str]) -> bool:
    """Whether one renaming that leaves the key alone takes the head's subject to its object and each atom of half to
    that of other at the same place."""
    to: dict[str, str] = {v: v for v in key}
    pairs = [(rule.head.s, rule.head.o)]
    for i, j in zip(half, other, strict=True):
        pairs += zip(rule.body[i].terms, rule.body[j].terms, strict=True)
    for a, b in pairs:
        if isinstance(a, Var) != isinstance(b, Var) or (not isinstance(a, Var) and a != b):
            return False
        if isinstance(a, Var) and to.setdefault(a.name, b.name) != b.name:
            return False
    return len(set(to.values())) == len(to)


def plans_of(spark: SparkSession, rules: list[Rule], inline: int = INLINE, keyed=(EQ_ID,)) -> list[Plan]:
    shapes: dict[tuple, list[Rule]] = {}
    for r in rules:
        shapes.setdefault(r.shape, []).append(r)
    out = []
    for shape, own in shapes.items():
        if len(own) <= inline:
            out += [Plan(r.name or repr(r.shape), r.head, r.body, half=keyed_half(r, keyed)) for r in own]
            continue
        n = len(own[0].constants)
        slots = iter(range(n))

        def atom(pattern, slots=slots):
            return Atom(*[Var(f"c{next(slots)}") if t == "c" else Var(f"x{t}") for t in pattern])

        head, *body = [atom(p) for p in shape]
        table = spark.createDataFrame([tuple(map(int, r.constants)) for r in own], ", ".join(f"v_c{i} long" for i in range(n)))
        halves = {keyed_half(r) for r in own} if all(r.head.p == EQ_ID for r in own) else {None}
        out.append(Plan(f"shape of {len(own)} rules", head, tuple(body), table, halves.pop() if len(halves) == 1 else None))
    return out


def atom_test(atom: Atom) -> str:
    """When a fact(s, p, o) matches an atom, as SQL: its constants and repeated variables."""
    seen: dict[str, str] = {}
    tests = []
    for c, t in zip("spo", atom.terms, strict=True):
        if not isinstance(t, Var):
            tests.append(f"{c} = {int(t)}L")
        elif t.name in seen:
            tests.append(f"{c} = {seen[t.name]}")
        else:
            seen[t.name] = c
    return " and ".join(tests) or "true"


def match_atom(facts: DataFrame, atom: Atom) -> DataFrame:
    """Bindings of one atom: a column v_<name> for each variable. A constant predicate also names the bucket in which
    large layers keep it, so that only its folder is read."""
    seen = {t.name: c for c, t in reversed(list(zip("spo", atom.terms, strict=True))) if isinstance(t, Var)}
    test = atom_test(atom)
    if not isinstance(atom.p, Var) and "pb" in facts.columns:
        test += f" and pb = {int(atom.p) % BUCKETS}"
    facts = facts if test == "true" else facts.where(test)
    return facts.selectExpr(*[f"{seen[v]} as `v_{v}`" for v in atom.variables])


def _joined(left: DataFrame, right: DataFrame) -> DataFrame:
    """Atoms without a variable in common give all pairs: that is what such a body says, and its rows are its result."""
    shared = [c for c in left.columns if c in right.columns]
    return left.join(right, shared) if shared else left.crossJoin(right)


def _order(body: tuple[Atom, ...], start: int, bound: set[str]) -> list[int]:
    """The pivot first, then always an atom that shares a variable with what is bound, the one with most bound terms."""
    left, out, bound = [i for i in range(len(body)) if i != start], [start], bound | set(body[start].variables)
    while left:
        best = max(left, key=lambda i: (any(v in bound for v in body[i].variables), sum(not isinstance(t, Var) or t.name in bound for t in body[i].terms), -i))
        left.remove(best)
        out.append(best)
        bound |= set(body[best].variables)
    return out


def bind(body: tuple[Atom, ...], table: DataFrame | None, scans: list[DataFrame], pivot: int = 0) -> DataFrame:
    """A row for every match of a body; scans[i] is what its atom i may match."""
    bindings = table
    for i in _order(body, pivot, set()):
        found = match_atom(scans[i], body[i])
        bindings = found if bindings is None else _joined(bindings, found)
    return bindings


def evaluate(plan: Plan, scans: list[DataFrame], pivot: int = 0) -> DataFrame:
    """Head facts(s, p, o) of the matches of the body, with n: rows whose n add up to the number of matches of each head.

    A variable that neither the head nor an atom still to come names is summed out at once, so that what only has to
    exist is counted and never listed: all pairs of suppliers of a part are not made to find which parts they supply."""
    order, one = _order(plan.body, pivot, set()), F.lit(1).cast("long")
    pairs = keyed_half(plan, (plan.head.p,)) is not None  # few rows of a key give very many
    bindings = None if plan.table is None else plan.table.withColumn("n", one)
    while order:
        own, order = _with_tests(plan.body, order)
        later = set(plan.head.variables) | {v for j in order for v in plan.body[j].variables}
        needed = later | ({c[2:] for c in bindings.columns} if bindings is not None else set())
        scans_of = [(set(plan.body[i].variables) & (needed | {v for j in own if j != i for v in plan.body[j].variables}), match_atom(scans[i], plan.body[i]).withColumn("n", one)) for i in own]
        found = _summed(reduce(_times, [_summed(found, keep) for keep, found in scans_of]), needed)
        if bindings is None:
            bindings = found
            continue
        bindings = _times(_dealt(bindings) if pairs and not order else bindings, found)
        bindings = _summed(bindings, later) if order else bindings
    parts = [f"`v_{t.name}` as {c}" if isinstance(t, Var) else f"{int(t)}L as {c}" for c, t in zip("spo", plan.head.terms, strict=True)]
    return bindings.selectExpr(*parts, "n")


def _with_tests(body: tuple[Atom, ...], order: list[int]) -> tuple[list[int], list[int]]:
    """The first atom of order with those that only test it, whose variables it has all, and the rest. They are joined
    with it before anything else is, so that a row which fails a test meets no other."""
    mine = set(body[order[0]].variables)
    tests = [j for j in order[1:] if body[j].variables and mine.issuperset(body[j].variables)]
    return [order[0], *tests], [j for j in order[1:] if j not in tests]


def _times(left: DataFrame, right: DataFrame) -> DataFrame:
    """The join of two sets of bindings; a row counts for the product of what its two counted for."""
    both = _joined(left.withColumnRenamed("n", "_n"), right)
    return both.withColumn("n", F.col("_n") * F.col("n")).drop("_n")


def _dealt(df: DataFrame) -> DataFrame:
    """df over many tasks, however small it is: a number that is asked for is not coalesced."""
    spark = df.sparkSession
    return df.repartition(max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism))


def _summed(bindings: DataFrame, keep: set[str]) -> DataFrame:
    """bindings with only the variables to keep, and n added up where others go."""
    names = [c for c in bindings.columns if c != "n"]
    stay = [c for c in names if c[2:] in keep]
    return bindings if len(stay) == len(names) else bindings.groupBy(*stay).agg(F.sum("n").alias("n")).where("n is not null")


def fresh_matches(plan: Plan, facts: DataFrame) -> DataFrame:
    """A rule that is new: all its matches."""
    return evaluate(plan, [facts] * len(plan.body))


def delta_matches(plan: Plan, facts: DataFrame, delta: DataFrame, older: DataFrame) -> list[DataFrame]:
    """A rule that has been applied before: matches with at least one new fact, each in exactly one of the results.
    Left of the pivot only older facts count, right of it all."""
    return [evaluate(plan, [older if j < i else delta if j == i else facts for j in range(len(plan.body))], i) for i in range(len(plan.body))]


def key_edges(plan: Plan, facts: DataFrame, delta: DataFrame | None = None, older: DataFrame | None = None) -> DataFrame:
    """Equalities of a keyed rule: each resource with the least that has its key, n - 1 edges where the rule's own matches
    are n * n. They connect the same resources. ``delta``: only keys that have a match with a new fact count.

    Keys are met by partial minima and a join with one row a key, so that a key of very many rows is not gathered."""
    body = tuple(plan.body[i] for i in plan.half)
    own = {v for a in body for v in a.variables}
    table = plan.table
    if table is not None:
        table = table.select([c for c in table.columns if c[2:] in own]).distinct()
    key = sorted(f"v_{v}" for v in own if any(v in plan.body[i].variables for i in range(len(plan.body)) if i not in plan.half) or (table is not None and f"v_{v}" in table.columns))
    x, m = f"v_{plan.head.s.name}", len(body)
    found = bind(body, table, [facts] * m).select(*key, x).distinct()
    if delta is not None:
        new = [bind(body, table, [older if j < i else delta if j == i else facts for j in range(m)], i).select(*key) for i in range(m)]
        found = found.join(reduce(DataFrame.unionByName, new).distinct(), key, "left_semi")
    least = found.groupBy(*key).agg(F.min(x).alias("least"))
    edges, p = found.join(least, key), EQ_ID if isinstance(plan.head.p, Var) else int(plan.head.p)  # as rows: equality alone
    if p == EQ_ID:  # another predicate holds between a resource and itself only if that is said
        edges = edges.where(F.col(x) != F.col("least"))
    return edges.select(F.col(x).alias("s"), F.lit(p).cast("long").alias("p"), F.col("least").alias("o")).distinct()


def rule_applications(plans: list[Plan], delta: DataFrame, facts: DataFrame, fresh: set[str]) -> int:
    """How often an atom of a rule meets a fact, before the rest of the body is looked at. A fresh rule meets all facts
    with its first atom. One pass over the new facts, one over all where rules are fresh, and a join for each atom of a
    shape of many rules."""
    n = 0
    for table, own in ((delta, [a for p in plans if p.table is None and p.label not in fresh for a in p.body]), (facts, [p.body[0] for p in plans if p.table is None and p.label in fresh and p.body])):
        if own:
            n += sum(table.agg(*[F.expr(f"count_if({atom_test(a)}) as n{i}") for i, a in enumerate(own)]).first())
    for p in plans:
        if p.table is not None:
            for atom in p.body[:1] if p.label in fresh else p.body:
                n += _joined(p.table, match_atom(facts if p.label in fresh else delta, atom)).count()
    return n

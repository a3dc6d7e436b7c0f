"""Ontology axioms as rules: each axiom of the rule profile becomes one or a few short rules."""

from __future__ import annotations

from eqmat.plans.rules import EQ, NEQ, Atom, Rule, Var

TYPE = "type"
X, Y, Z, U, V = (Var(n) for n in "xyzuv")


def _is(x, c):
    return Atom(x, TYPE, c)


#: Axiom name -> how its arguments become (rules, facts).
TEMPLATES = {
    "subclass": lambda a, b: ([Rule(_is(X, b), (_is(X, a),))], []),
    "equivalent_class": lambda a, b: ([Rule(_is(X, b), (_is(X, a),)), Rule(_is(X, a), (_is(X, b),))], []),
    "subproperty": lambda p, q: ([Rule(Atom(X, q, Y), (Atom(X, p, Y),))], []),
    "equivalent_property": lambda p, q: ([Rule(Atom(X, q, Y), (Atom(X, p, Y),)), Rule(Atom(X, p, Y), (Atom(X, q, Y),))], []),
    "domain": lambda p, c: ([Rule(_is(X, c), (Atom(X, p, Y),))], []),
    "range": lambda p, c: ([Rule(_is(Y, c), (Atom(X, p, Y),))], []),
    "inverse": lambda p, q: ([Rule(Atom(Y, q, X), (Atom(X, p, Y),)), Rule(Atom(Y, p, X), (Atom(X, q, Y),))], []),
    "symmetric": lambda p: ([Rule(Atom(Y, p, X), (Atom(X, p, Y),))], []),
    "transitive": lambda p: ([Rule(Atom(X, p, Z), (Atom(X, p, Y), Atom(Y, p, Z)))], []),
    "functional": lambda p: ([Rule(Atom(Y, EQ, Z), (Atom(X, p, Y), Atom(X, p, Z)))], []),
    "inverse_functional": lambda p: ([Rule(Atom(Y, EQ, Z), (Atom(Y, p, X), Atom(Z, p, X)))], []),
    "max_cardinality_one": lambda c, p: ([Rule(Atom(Y, EQ, Z), (_is(X, c), Atom(X, p, Y), Atom(X, p, Z)))], []),
    "key": lambda c, *ps: ([Rule(Atom(X, EQ, Y), (_is(X, c), _is(Y, c), *[a for i, p in enumerate(ps) for a in (Atom(X, p, Var(f"k{i}")), Atom(Y, p, Var(f"k{i}")))]))], []),
    "intersection": lambda c, *parts: ([Rule(_is(X, c), tuple(_is(X, d) for d in parts)), *[Rule(_is(X, d), (_is(X, c),)) for d in parts]], []),
    "union_left": lambda c, *parts: ([Rule(_is(X, c), (_is(X, d),)) for d in parts], []),
    "some_left": lambda c, p, d: ([Rule(_is(X, c), (Atom(X, p, Y), _is(Y, d)))], []),
    "all_values": lambda c, p, d: ([Rule(_is(Y, d), (_is(X, c), Atom(X, p, Y)))], []),
    "has_value": lambda c, p, v: ([Rule(Atom(X, p, v), (_is(X, c),)), Rule(_is(X, c), (Atom(X, p, v),))], []),
    "one_of": lambda c, a: ([Rule(Atom(X, EQ, a), (_is(X, c),))], [Atom(a, TYPE, c)]),
    "chain": lambda p, *steps: ([Rule(Atom(Var("n0"), p, Var(f"n{len(steps)}")), tuple(Atom(Var(f"n{i}"), q, Var(f"n{i + 1}")) for i, q in enumerate(steps)))], []),
    "disjoint_classes": lambda a, b: ([Rule(Atom(X, NEQ, Y), (_is(X, a), _is(Y, b)))], []),
    "disjoint_properties": lambda p, q: ([Rule(Atom(X, NEQ, U), (Atom(X, p, Y), Atom(U, q, Y)))], []),
    "same": lambda a, b: ([], [Atom(a, EQ, b)]),
    "different": lambda a, b: ([], [Atom(a, NEQ, b)]),
}


def rules_from_ontology(axioms: list[tuple]) -> tuple[list[Rule], list[Atom], list[tuple]]:
    """Rules, facts, and the axioms outside the profile, which are left out."""
    rules, facts, dropped = [], [], []
    for axiom in axioms:
        make = TEMPLATES.get(axiom[0])
        if make is None:
            dropped.append(axiom)
            continue
        r, f = make(*axiom[1:])
        rules += [Rule(x.head, x.body, " ".join(map(str, axiom))) for x in r]
        facts += f
    return rules, facts, dropped


def upper_bound(axioms: list[tuple]) -> tuple[list[Rule], list[Atom], list[tuple]]:
    """As rules_from_ontology, but richer axioms are strengthened into the profile instead of left out: a disjunction on
    the right becomes all its members, an existential on the right a fixed new resource. Nothing that followed before
    is lost; more may follow."""
    within = []
    for k, axiom in enumerate(axioms):
        if axiom[0] == "union_right":
            within += [("subclass", axiom[1], d) for d in axiom[2:]]
        elif axiom[0] == "some_right":
            _, c, p, d = axiom
            made = f"made/{k}"
            within += [("value_forced", c, p, made), ("member", made, d)]
        else:
            within.append(axiom)
    rules, facts, dropped = rules_from_ontology([a for a in within if a[0] not in ("value_forced", "member")])
    for a in within:
        if a[0] == "value_forced":
            rules.append(Rule(Atom(X, a[2], a[3]), (_is(X, a[1]),), " ".join(a)))
        elif a[0] == "member":
            facts.append(Atom(a[1], TYPE, a[2]))
    return rules, facts, dropped

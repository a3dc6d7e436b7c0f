"""Brute force over Python sets, independent of the Spark code."""

from itertools import product

from eqmat.plans.rules import Var


def matches(body, facts):
    """All substitutions under which every atom is a fact."""
    subs = [{}]
    for atom in body:
        out = []
        for s in subs:
            for f in facts:
                t = dict(s)
                if all(t.setdefault(x.name, v) == v if isinstance(x, Var) else x == v for x, v in zip(atom.terms, f)):
                    out.append(t)
        subs = out
    return subs


def closure(facts, rules):
    now = set(facts)
    while True:
        new = {tuple(s[t.name] if isinstance(t, Var) else t for t in r.head.terms) for r in rules for s in matches(r.body, now)} - now
        if not new:
            return now
        now |= new


def expansion(facts, rep):
    """rep: every resource -> its representative."""
    members = {}
    for m, r in rep.items():
        members.setdefault(r, set()).add(m)
    return {t for f in facts for t in product(*[members.get(x, {x}) for x in f])}

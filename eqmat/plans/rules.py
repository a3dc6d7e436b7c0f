"""Terms, atoms, rules and programs; all of this lives on the driver and is small next to the facts."""

from __future__ import annotations

import re
from dataclasses import dataclass, field

EQ, NEQ = "=", "!="  # names of the equality predicate and of "is different from"
EQ_ID, NEQ_ID = 1, 2


@dataclass(frozen=True)
class Var:
    name: str


Term = Var | str | int  # a constant is a name before encoding and an id after it


@dataclass(frozen=True)
class Atom:
    s: Term
    p: Term
    o: Term

    @property
    def terms(self) -> tuple[Term, Term, Term]:
        return self.s, self.p, self.o

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(t.name for t in self.terms if isinstance(t, Var)))

    def map(self, f) -> Atom:
        """The atom with each constant replaced by f(constant)."""
        return Atom(*[t if isinstance(t, Var) else f(t) for t in self.terms])


@dataclass(frozen=True)
class Rule:
    """head <- body. Every variable of the head must occur in the body."""

    head: Atom
    body: tuple[Atom, ...]
    name: str = field(default="", compare=False)

    def __post_init__(self):
        bound = {v for a in self.body for v in a.variables}
        if loose := [v for v in self.head.variables if v not in bound]:
            raise ValueError(f"unsafe rule: {', '.join(loose)} of the head not in the body")

    def map(self, f) -> Rule:
        return Rule(self.head.map(f), tuple(a.map(f) for a in self.body), self.name)

    @property
    def constants(self) -> tuple:
        return tuple(t for a in (self.head, *self.body) for t in a.terms if not isinstance(t, Var))

    @property
    def shape(self) -> tuple:
        """The rule with its constants taken out and its variables numbered: rules of one shape share a plan."""
        number: dict[str, int] = {}
        return tuple(tuple(number.setdefault(t.name, len(number)) if isinstance(t, Var) else "c" for t in a.terms) for a in (self.head, *self.body))


def unique(rules) -> list[Rule]:
    """Rules without repetitions, whatever they are called."""
    return list(dict.fromkeys(rules))


_TERM = re.compile(r"""\s*(\?[A-Za-z_]\w*|<[^>]*>|"(?:[^"\\]|\\.)*"|[^\s(),]+)""")


def _term(text: str) -> Term:
    if text.startswith("?"):
        return Var(text[1:])
    return text[1:-1] if text[0] in '<"' else text


def parse_atom(text: str) -> Atom:
    """``?x likes <a thing>``: three terms; ?name is a variable."""
    found = [_term(t) for t in _TERM.findall(text)]
    if len(found) != 3:
        raise ValueError(f"an atom has three terms: {text!r}")
    return Atom(*found)


def parse_rules(text: str) -> tuple[list[Rule], list[Atom]]:
    """Rules, one a line, ``head <- atom, atom``; a line without ``<-`` is a fact. # begins a comment line."""
    rules, facts = [], []
    for line in text.splitlines():
        line = line.strip()
        if not line or line.startswith("#"):
            continue
        head, arrow, body = line.partition("<-")
        if arrow and body.strip():
            rules.append(Rule(parse_atom(head), tuple(parse_atom(a) for a in body.split(",")), line))
        else:
            fact = parse_atom(head)
            if fact.variables:
                raise ValueError(f"unsafe rule: a fact has no variables: {line!r}")
            facts.append(fact)
    return rules, facts


def equality_axioms(eq: Term = EQ, with_redundant: bool = False) -> list[Rule]:
    """Equality as a congruence: three reflexive rules and three of replacement. The seventh axiom, that nothing differs
    from itself, has no triple in its head and is checked by ``contradictions``. Symmetry and transitivity follow."""
    s, p, o, t, u = (Var(n) for n in "spotu")
    fact = Atom(s, p, o)
    out = [Rule(Atom(x, eq, x), (fact,), f"reflexive_{n}") for n, x in (("s", s), ("p", p), ("o", o))]
    out += [
        Rule(Atom(t, p, o), (fact, Atom(s, eq, t)), "replace_s"),
        Rule(Atom(s, t, o), (fact, Atom(p, eq, t)), "replace_p"),
        Rule(Atom(s, p, t), (fact, Atom(o, eq, t)), "replace_o"),
    ]
    if with_redundant:
        out += [Rule(Atom(t, eq, s), (Atom(s, eq, t),), "symmetric"), Rule(Atom(s, eq, u), (Atom(s, eq, t), Atom(t, eq, u)), "transitive")]
    return out


def program_stats(rules: list[Rule], eq: Term = EQ) -> dict[str, int]:
    return {"rules": len(rules), "eq_head_rules": sum(r.head.p == eq for r in rules)}

"""Query trees. A query is a tree of the nodes below, built directly or read from a small SELECT text."""

from __future__ import annotations

import re
from dataclasses import dataclass

from eqmat.plans.rules import Atom, Var, parse_atom


class Node:
    def filter(self, fn: str, *args) -> Node:
        return Filter(self, fn, args)

    def bind(self, var: str, fn: str, *args) -> Node:
        return Bind(self, var, fn, args)

    def project(self, *names: str) -> Node:
        return Project(self, names)

    def distinct(self) -> Node:
        return Distinct(self)

    def group(self, keys: tuple[str, ...], **counts: tuple) -> Node:
        return Group(self, tuple(keys), tuple(counts.items()))

    def join(self, other: Node) -> Node:
        return Join(self, other)

    def optional(self, other: Node) -> Node:
        return Optional(self, other)

    def minus(self, other: Node) -> Node:
        return Minus(self, other)

    def union(self, other: Node) -> Node:
        return Union(self, other)

    def order(self, *keys: str) -> Node:
        return Order(self, keys)

    def limit(self, n: int, offset: int = 0) -> Node:
        return Slice(self, n, offset)


@dataclass
class Pattern(Node):
    atoms: tuple[Atom, ...]


@dataclass
class Values(Node):
    var: str
    names: tuple[str, ...]


@dataclass
class Join(Node):
    left: Node
    right: Node


@dataclass
class Optional(Node):
    left: Node
    right: Node


@dataclass
class Minus(Node):
    left: Node
    right: Node


@dataclass
class Union(Node):
    left: Node
    right: Node


@dataclass
class Filter(Node):
    """Arguments: Var for a variable, anything else for a constant. ``same`` with one variable and one name is decided
    without unfolding."""

    of: Node
    fn: str
    args: tuple


@dataclass
class Bind(Node):
    of: Node
    var: str
    fn: str
    args: tuple


@dataclass
class Project(Node):
    of: Node
    names: tuple[str, ...]


@dataclass
class Distinct(Node):
    of: Node


@dataclass
class Group(Node):
    """counts: (name, ("count",)), (name, ("count_distinct", var)) or (name, ("sum" | "min" | "max" | "avg", var))."""

    of: Node
    keys: tuple[str, ...]
    counts: tuple


@dataclass
class Order(Node):
    """Keys: names, with - in front for falling order."""

    of: Node
    keys: tuple[str, ...]


@dataclass
class Slice(Node):
    of: Node
    n: int
    offset: int = 0


def pattern(*atoms: str) -> Pattern:
    return Pattern(tuple(parse_atom(a) for a in atoms))


_SELECT = re.compile(r"\s*SELECT\s+(?P<distinct>DISTINCT\s+)?(?P<what>.*?)\s+WHERE\s*\{(?P<where>.*)\}\s*(?:GROUP\s+BY\s+(?P<group>(?:\?\w+\s*)+))?(?:ORDER\s+BY\s+(?P<order>(?:(?:DESC\(\?\w+\)|\?\w+)\s*)+))?(?:LIMIT\s+(?P<limit>\d+)\s*)?(?:OFFSET\s+(?P<offset>\d+)\s*)?$", re.S | re.I)
_CALL = re.compile(r"(\w+)\(([^()]*)\)")


def _args(text: str) -> tuple:
    out = []
    for a in filter(None, (x.strip() for x in text.split(","))):
        out.append(Var(a[1:]) if a[0] == "?" else a[1:-1] if a[0] in "\"'" else float(a) if re.fullmatch(r"-?\d+\.\d+", a) else int(a) if re.fullmatch(r"-?\d+", a) else a)
    return tuple(out)


_WORDS = ("OPTIONAL", "MINUS", "UNION", "VALUES", "FILTER", "BIND")


def _closing(text: str, at: int, pair: str) -> int:
    """The place after the bracket that closes the one at ``at``."""
    depth = 0
    for i in range(at, len(text)):
        depth += (text[i] == pair[0]) - (text[i] == pair[1])
        if not depth:
            return i + 1
    raise ValueError("a bracket is not closed")


def _group(text: str) -> Node:
    """The inside of braces: patterns, FILTER, BIND, VALUES, OPTIONAL, MINUS and groups with UNION, from left to right;
    filters hold for the whole group."""
    node: Node | None = None
    atoms: list[str] = []
    filters: list[tuple] = []

    def with_atoms() -> Node | None:
        nonlocal node
        if atoms:
            found = pattern(*atoms)
            atoms.clear()
            node = found if node is None else node.join(found)
        return node

    at = 0
    while at < len(text):
        rest = text[at:]
        skip = len(rest) - len(rest.lstrip(" \t\n."))
        if skip:
            at += skip
            continue
        word = next((w for w in _WORDS if rest[: len(w)].upper() == w and not rest[len(w) : len(w) + 1].isalnum()), None)
        if word in ("OPTIONAL", "MINUS") or rest[0] == "{":
            start = text.index("{", at)
            end = _closing(text, start, "{}")
            inner = _group(text[start + 1 : end - 1])
            while word is None and (more := re.match(r"\s*UNION\s*(?=\{)", text[end:], re.I)):
                start = end + more.end()
                end = _closing(text, start, "{}")
                inner = inner.union(_group(text[start + 1 : end - 1]))
            left = with_atoms()
            if left is None:
                if word:
                    raise ValueError(f"{word} has nothing before it")
                node = inner
            else:
                node = left.optional(inner) if word == "OPTIONAL" else left.minus(inner) if word == "MINUS" else left.join(inner)
            at = end
        elif word == "VALUES":
            m = re.match(r"VALUES\s+\?(\w+)\s*\{([^}]*)\}", rest, re.I)
            own = Values(m[1], tuple(x[1:-1] if x[0] in '<"' else x for x in re.findall(r'<[^>]*>|"[^"]*"|\S+', m[2])))
            node = own if with_atoms() is None else node.join(own)
            at += m.end()
        elif word in ("FILTER", "BIND"):
            start = text.index("(", at)
            end = _closing(text, start, "()")
            inside = text[start + 1 : end - 1]
            negated = inside.lstrip().startswith("!")
            fn, args = _CALL.search(inside).groups()
            to = re.search(r"AS\s+\?(\w+)\s*$", inside, re.I)
            if to:
                node = with_atoms().bind(to[1], fn.lower(), *_args(args))
            elif negated and fn.lower() != "bound":
                raise ValueError("only BOUND can be negated")
            else:
                filters.append(("unbound" if negated else fn.lower(), _args(args)))
            at = end
        else:
            own = re.match(r"""(?:\s*(?:<[^>]*>|"(?:[^"\\]|\\.)*"|[^\s{}]+)){3}""", rest)
            if not own:
                raise ValueError(f"not a pattern: {rest[:40]!r}")
            atoms.append(own.group())
            at += own.end()
    node = with_atoms()
    if node is None:
        raise ValueError("an empty group")
    for fn, args in filters:
        node = node.filter(fn, *args)
    return node


def parse_query(text: str) -> Node:
    """SELECT [DISTINCT] ?x ... [(COUNT(*) AS ?n)] WHERE { ... } [GROUP BY ?k] [ORDER BY ?k | DESC(?k)] [LIMIT n]
    [OFFSET n], or ASK { ... }. Inside braces: patterns, parted by `` .``, FILTER(FN(...)), FILTER(!BOUND(?x)),
    BIND(FN(...) AS ?y), VALUES ?x { a b }, OPTIONAL { }, MINUS { }, { } UNION { }. ASK is the tree of its group, for
    Answering.ask()."""
    if asked := re.match(r"\s*ASK\s*(?:WHERE\s*)?\{(.*)\}\s*$", text, re.S | re.I):
        return _group(asked[1])
    m = _SELECT.match(text)
    if not m:
        raise ValueError("not a query of the supported form")
    node = _group(m["where"])
    names = re.findall(r"\?(\w+)", re.sub(r"\([^()]*(?:\([^()]*\))?[^()]*\)", "", m["what"]))
    counts = {name: ("count",) if arg == "*" else ("count_distinct", arg.split("?")[1]) for arg, name in re.findall(r"\(\s*COUNT\(\s*([^)]*?)\s*\)\s+AS\s+\?(\w+)\s*\)", m["what"], re.I)}
    if counts:
        node = node.group(tuple(re.findall(r"\?(\w+)", m["group"] or "")), **counts)
    node = node.project(*names, *counts)
    if m["distinct"]:
        node = node.distinct()
    if m["order"]:
        node = node.order(*["-" + d if d else a for d, a in re.findall(r"DESC\(\?(\w+)\)|\?(\w+)", m["order"], re.I)])
    return node.limit(int(m["limit"]), int(m["offset"] or 0)) if m["limit"] else node

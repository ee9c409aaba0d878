"""Query algebra: what the parser and the builder make and the graphs evaluate.

Results are bags. An unbound variable is null. A filter whose expression fails
on a row (a comparison with something unbound, a cast that can't be done)
drops the row.
"""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class Var:
    name: str


@dataclass(frozen=True)
class Iri:
    value: str


@dataclass(frozen=True)
class Lit:
    value: object
    dtype: str = "string"


Term = Var | Iri | Lit


@dataclass(frozen=True)
class Pattern:
    s: Term
    p: Term
    o: Term


@dataclass(frozen=True)
class Call:
    """An operator or function over expressions; leaves are terms."""

    name: str
    args: tuple = ()


@dataclass(frozen=True)
class Exists:
    node: Node
    negated: bool = False


class Node:
    """An operator of the algebra."""


@dataclass(frozen=True)
class Bgp(Node):
    patterns: tuple[Pattern, ...]


@dataclass(frozen=True)
class Reach(Node):
    """One predicate, once or more (or zero times or more) in a row."""

    s: Term
    p: Iri
    o: Term
    zero: bool = False


@dataclass(frozen=True)
class Join(Node):
    left: Node
    right: Node


@dataclass(frozen=True)
class LeftJoin(Node):
    left: Node
    right: Node
    on: object | None = None


@dataclass(frozen=True)
class Union(Node):
    left: Node
    right: Node


@dataclass(frozen=True)
class Minus(Node):
    left: Node
    right: Node


@dataclass(frozen=True)
class Filter(Node):
    expr: object
    node: Node


@dataclass(frozen=True)
class Extend(Node):
    var: Var
    expr: object
    node: Node


@dataclass(frozen=True)
class Values(Node):
    vars: tuple[Var, ...]
    rows: tuple[tuple[Term | None, ...], ...]


@dataclass(frozen=True)
class Aggregate:
    var: Var
    fn: str
    expr: object | None
    distinct: bool = False


@dataclass(frozen=True)
class Group(Node):
    keys: tuple[Var, ...]
    aggregates: tuple[Aggregate, ...]
    node: Node


@dataclass(frozen=True)
class Order(Node):
    keys: tuple[tuple[object, bool], ...]
    node: Node


@dataclass(frozen=True)
class Slice(Node):
    limit: int | None
    offset: int
    node: Node


@dataclass(frozen=True)
class Project(Node):
    vars: tuple[Var, ...]
    node: Node


@dataclass(frozen=True)
class Distinct(Node):
    node: Node


@dataclass(frozen=True)
class Query:
    """form: select, ask or construct; `template` is for construct."""

    form: str
    node: Node
    template: tuple[Pattern, ...] = field(default=())


def children(node: Node) -> list[Node]:
    return [v for v in vars(node).values() if isinstance(v, Node)]


def walk(node: Node):
    yield node
    for c in children(node):
        yield from walk(c)


def variables(x) -> set[str]:
    """Names of variables in a pattern, an expression, or what a node can bind."""
    if isinstance(x, Var):
        return {x.name}
    if isinstance(x, Pattern):
        return variables(x.s) | variables(x.p) | variables(x.o)
    if isinstance(x, Call):
        return set().union(*map(variables, x.args)) if x.args else set()
    if isinstance(x, Exists):
        return variables(x.node)
    if isinstance(x, Bgp):
        return set().union(*map(variables, x.patterns)) if x.patterns else set()
    if isinstance(x, Reach):
        return variables(x.s) | variables(x.o)
    if isinstance(x, Project):
        return {v.name for v in x.vars}
    if isinstance(x, Group):
        return {v.name for v in x.keys} | {a.var.name for a in x.aggregates}
    if isinstance(x, Values):
        return {v.name for v in x.vars}
    if isinstance(x, Node):
        own = {x.var.name} if isinstance(x, Extend) else set()
        parts = [x.left] if isinstance(x, Minus) else children(x)
        return own | set().union(*map(variables, parts)) if parts else own
    return set()


def pretty(node: Node, depth: int = 0) -> str:
    """An indented outline of a tree."""
    pad = "  " * depth
    if isinstance(node, Bgp):
        return "\n".join(f"{pad}{_show(p.s)} {_show(p.p)} {_show(p.o)}" for p in node.patterns)
    details = [f"{k}={_show(v)}" for k, v in vars(node).items() if not isinstance(v, Node)]
    return "\n".join([f"{pad}{type(node).__name__} {' '.join(details)}".rstrip(), *(pretty(c, depth + 1) for c in children(node))])


def _show(x) -> str:
    if isinstance(x, Var):
        return f"?{x.name}"
    if isinstance(x, Iri):
        return x.value
    if isinstance(x, Lit):
        return repr(x.value)
    if isinstance(x, Call):
        return f"{x.name}({', '.join(map(_show, x.args))})"
    if isinstance(x, tuple):
        return "[" + ", ".join(map(_show, x)) + "]"
    return str(x)


# A builder for queries in Python.
class Match:
    """match(...).where(...).select(...): the same algebra without text."""

    def __init__(self, node: Node):
        self.node = node

    def also(self, *triples) -> Match:
        return Match(Join(self.node, match(*triples).node))

    def optional(self, *triples) -> Match:
        return Match(LeftJoin(self.node, match(*triples).node))

    def where(self, expr) -> Match:
        return Match(Filter(expr, self.node))

    def values(self, var: str, *terms) -> Match:
        return Match(Join(Values((Var(var.lstrip("?")),), tuple((term(t),) for t in terms)), self.node))

    def count(self, var: str, *keys: str) -> Match:
        return Match(Group(tuple(Var(k.lstrip("?")) for k in keys), (Aggregate(Var(var.lstrip("?")), "count", None),), self.node))

    def select(self, *names: str) -> Query:
        return Query("select", Project(tuple(Var(n.lstrip("?")) for n in names), self.node))


def term(x) -> Term:
    """?name is a variable, prefix:name an IRI, other values are literals."""
    if isinstance(x, (Var, Iri, Lit)):
        return x
    if isinstance(x, str) and x.startswith("?"):
        return Var(x[1:])
    if isinstance(x, str) and x == "a":
        return Iri("rdf:type")
    if isinstance(x, str) and ":" in x and " " not in x:
        return Iri(x)
    if isinstance(x, bool):
        return Lit(x, "boolean")
    if isinstance(x, (int, float)):
        return Lit(x, "double" if isinstance(x, float) else "int")
    return Lit(x)


def match(*triples) -> Match:
    """Triples as (s, p, o) of shorthand terms; p may be a path with slashes."""
    out = []
    for k, (s, p, o) in enumerate(triples):
        steps = p.split("/") if isinstance(p, str) and not p.startswith("?") else [p]
        at = term(s)
        for j, step in enumerate(steps):
            to = term(o) if j == len(steps) - 1 else Var(f"_m{k}_{j}")
            out.append(Pattern(at, term(step), to))
            at = to
    return Match(Bgp(tuple(out)))

"""Evaluating query algebra over a graph.

A graph answers sets of patterns; everything else is done here, once for all
graphs, on DataFrames. A result keeps for each variable how it is stored: an
IRI as the raw keys of a template, or as text; a literal as a typed column.
Joins on a template's keys stay joins on keys; text is made where two forms
meet, and at the end.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import reduce
from itertools import count
from typing import Protocol

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cityweave.functions import geom, wkt
from cityweave.operators import spatial
from cityweave.plans import algebra as A
from cityweave.plans.mappings import FORMS, fill

_serial = count()
_SPARK_TYPE = {"double": "double", "int": "bigint", "string": "string", "wkt": "string", "boolean": "boolean"}


class UnsupportedGeometry(RuntimeError):
    """The graph can't handle a geometry kind that a spatial function meets."""


@dataclass(frozen=True)
class Slot:
    """Storage of a variable: kind iri or lit; its columns; whether it can be unbound.

    pattern: an IRI's template, or the form of geometry whose text a literal is;
    None if the one column is the value itself.
    """

    kind: str
    pattern: str | None
    columns: tuple[str, ...]
    dtype: str = "string"
    nullable: bool = False


@dataclass(frozen=True)
class Rel:
    df: DataFrame
    slots: dict[str, Slot]

    def text(self, name: str) -> Column:
        """The variable as a value: IRI text, or the literal."""
        s = self.slots[name]
        raw = [F.col(c) for c in s.columns]
        if s.pattern is None:
            return raw[0]
        return fill(s.pattern, raw) if s.kind == "iri" else FORMS[s.pattern](*raw)


class Graph(Protocol):
    spark: SparkSession
    strict_simple_features: bool

    def patterns(self, patterns: tuple[A.Pattern, ...], restrict: dict[str, tuple[A.Iri, ...]], known: dict[str, Slot]) -> tuple[Rel, set[str]]:
        """Bindings of patterns, and the restricted variables that were dealt with exactly.

        known: how variables are stored in what the bindings will be joined to;
        bindings that can't agree with it may be left out.
        """
        ...


def fresh(name: str) -> str:
    return f"{name}__{next(_serial)}"


def as_text(rel: Rel, name: str) -> Rel:
    """Stores a variable as its value."""
    s = rel.slots[name]
    if s.pattern is None:
        return rel
    c = fresh(name)
    return Rel(rel.df.withColumn(c, rel.text(name)), rel.slots | {name: Slot(s.kind, None, (c,), s.dtype, s.nullable)})


def project(rel: Rel, names) -> Rel:
    slots = {n: rel.slots[n] for n in names if n in rel.slots}
    return Rel(rel.df.select(*[F.col(c) for s in slots.values() for c in s.columns]), slots)


def _own(rel: Rel) -> Rel:
    """rel under new column names, so that it can be joined to what it came from."""
    names = {c: fresh(c.split("__")[0]) for s in rel.slots.values() for c in s.columns}
    df = rel.df.select(*[F.col(c).alias(n) for c, n in names.items()])
    return Rel(df, {v: replace(s, columns=tuple(names[c] for c in s.columns)) for v, s in rel.slots.items()})


def _aligned(left: Rel, right: Rel, name: str) -> tuple[Rel, Rel, bool]:
    a, b = left.slots[name], right.slots[name]
    if a.kind != b.kind:
        return left, right, False
    if a.pattern != b.pattern:
        if a.kind == "iri" and a.pattern and b.pattern:
            return left, right, False
        return as_text(left, name), as_text(right, name), True
    return left, right, True


def join(left: Rel, right: Rel, how: str = "inner", on: Callable[[Rel], Column] | None = None) -> Rel:
    """Compatible bindings; for left joins with a further condition over both sides."""
    right = _own(right)
    shared = [n for n in left.slots if n in right.slots]
    tests: list[Column] = []
    for n in shared:
        left, right, can = _aligned(left, right, n)
        if not can:
            tests.append(F.lit(False))
            continue
        a, b = left.slots[n], right.slots[n]
        for x, y in zip(a.columns, b.columns, strict=True):
            same = F.col(x) == F.col(y)
            if a.nullable:
                same = same | F.col(a.columns[0]).isNull()
            if b.nullable:
                same = same | F.col(b.columns[0]).isNull()
            tests.append(same)
    slots = dict(left.slots)
    for n, s in right.slots.items():
        if n not in slots:
            slots[n] = replace(s, nullable=True) if how == "left" else s
    both = Rel(left.df, slots)
    condition = reduce(lambda x, y: x & y, tests) if tests else None
    if on is not None:
        extra = on(Rel(left.df, left.slots | {n: s for n, s in right.slots.items() if n not in left.slots}))
        condition = extra if condition is None else condition & extra
    if how in ("left_semi", "left_anti"):
        if condition is None:
            condition = F.lit(True)
        return Rel(left.df.join(right.df, condition, how), left.slots)
    df = left.df.join(right.df, condition, how) if condition is not None else (left.df.join(right.df, F.lit(True), "left") if how == "left" else left.df.crossJoin(right.df))
    for n in shared:
        a, b = left.slots[n], right.slots[n]
        if a.nullable and a.kind == b.kind and len(a.columns) == len(b.columns):
            filled = [fresh(n) for _ in a.columns]
            df = df.withColumns({c: F.coalesce(F.col(x), F.col(y)) for c, x, y in zip(filled, a.columns, b.columns, strict=True)})
            both.slots[n] = replace(a, columns=tuple(filled), nullable=b.nullable)
    return project(Rel(df, both.slots), both.slots)


def union(left: Rel, right: Rel) -> Rel:
    """Both bags; a variable that one side doesn't bind is null there."""
    slots: dict[str, Slot] = {}
    a_cols: list[Column] = []
    b_cols: list[Column] = []
    for n in dict.fromkeys((*left.slots, *right.slots)):
        a, b = left.slots.get(n), right.slots.get(n)
        if a and b and a.kind == b.kind and a.pattern == b.pattern and a.dtype == b.dtype:
            cols = tuple(fresh(n) for _ in a.columns)
            a_cols += [F.col(x).alias(c) for x, c in zip(a.columns, cols, strict=True)]
            b_cols += [F.col(x).alias(c) for x, c in zip(b.columns, cols, strict=True)]
            slots[n] = replace(a, columns=cols, nullable=a.nullable or b.nullable)
        elif a and b:
            c = fresh(n)
            a_cols.append(left.text(n).cast("string").alias(c))
            b_cols.append(right.text(n).cast("string").alias(c))
            slots[n] = Slot("iri" if a.kind == b.kind == "iri" else "lit", None, (c,), nullable=a.nullable or b.nullable)
        else:
            own, rel = (a, left) if a else (b, right)
            cols = tuple(fresh(n) for _ in own.columns)
            for x, c in zip(own.columns, cols, strict=True):
                there, absent = F.col(x).alias(c), F.lit(None).cast(rel.df.schema[x].dataType).alias(c)
                a_cols.append(there if a else absent)
                b_cols.append(absent if a else there)
            slots[n] = replace(own, columns=cols, nullable=True)
    return Rel(left.df.select(*a_cols).unionByName(right.df.select(*b_cols)), slots)


def values(spark: SparkSession, node: A.Values) -> Rel:
    kinds = {}
    for k, v in enumerate(node.vars):
        terms = [r[k] for r in node.rows if r[k] is not None]
        if not terms:  # never bound: no restriction
            continue
        iri = all(isinstance(t, A.Iri) for t in terms)
        dtype = "string" if iri else terms[0].dtype
        kinds[v.name] = Slot("iri" if iri else "lit", None, (fresh(v.name),), dtype, any(r[k] is None for r in node.rows))
    schema = ", ".join(f"`{s.columns[0]}` {_SPARK_TYPE[s.dtype]}" for s in kinds.values())
    bound = [k for k, v in enumerate(node.vars) if v.name in kinds]
    rows = [tuple(None if r[k] is None else r[k].value for k in bound) for r in node.rows]
    return Rel(spark.createDataFrame(rows, schema), kinds) if bound else Rel(spark.range(len(rows)).select(F.lit(1).alias("_one")), {})


# Expressions.
def _number(c: Column, dtype: str) -> Column:
    return c if dtype in ("double", "int") else c.try_cast("double")


_PLAIN: dict[str, tuple[Callable[..., Column], str]] = {
    "CONTAINS": (lambda a, b: F.contains(a, b), "boolean"),
    "STRSTARTS": (lambda a, b: F.startswith(a, b), "boolean"),
    "STRENDS": (lambda a, b: F.endswith(a, b), "boolean"),
    "STRLEN": (lambda a: F.length(a).cast("bigint"), "int"),
    "UCASE": (F.upper, "string"),
    "LCASE": (F.lower, "string"),
    "CONCAT": (lambda *a: F.concat(*a), "string"),
    "SUBSTR": (lambda a, i, n=None: F.substring(a, i.cast("int"), n.cast("int") if n is not None else F.lit(1 << 30)), "string"),
    "ABS": (F.abs, "double"),
    "ROUND": (lambda a: F.round(a), "double"),
    "FLOOR": (lambda a: F.floor(a).cast("double"), "double"),
    "CEIL": (lambda a: F.ceil(a).cast("double"), "double"),
    "geo:metricArea": (lambda a: geom.area(wkt.from_polygon_wkt(a)), "double"),
}
_ARITHMETIC = {"+": lambda a, b: a + b, "-": lambda a, b: a - b, "*": lambda a, b: a * b, "/": lambda a, b: F.try_divide(a, b)}
_COMPARE = {"=": lambda a, b: a == b, "!=": lambda a, b: a != b, "<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b}


class Evaluator:
    def __init__(self, graph: Graph):
        self.graph = graph
        self.known: dict[str, Slot] = {}

    def expr(self, e, rel: Rel) -> tuple[Column, str]:
        """(column, type) of an expression; iri is a type of its own."""
        if isinstance(e, A.Var):
            if e.name not in rel.slots:
                return F.lit(None).cast("string"), "string"
            s = rel.slots[e.name]
            return rel.text(e.name), "iri" if s.kind == "iri" else s.dtype
        if isinstance(e, A.Iri):
            return F.lit(e.value), "iri"
        if isinstance(e, A.Lit):
            return F.lit(e.value), e.dtype
        name, args = e.name, e.args
        if name == "BOUND":
            s = rel.slots.get(args[0].name)
            return (F.col(s.columns[0]).isNotNull() if s else F.lit(False)), "boolean"
        got = [self.expr(a, rel) for a in args]
        if name in ("&&", "||"):
            return (got[0][0] & got[1][0] if name == "&&" else got[0][0] | got[1][0]), "boolean"
        if name == "!":
            return ~got[0][0], "boolean"
        if name in _COMPARE:
            (a, ta), (b, tb) = got
            if ta != tb and {ta, tb} & {"double", "int"}:
                a, b = _number(a, ta), _number(b, tb)
            return _COMPARE[name](a, b), "boolean"
        if name == "IN":
            return got[0][0].isin(*[c for c, _ in got[1:]]), "boolean"
        if name in _ARITHMETIC:
            return _ARITHMETIC[name](*[_number(c, t) for c, t in got]), "double"
        if name == "COALESCE":
            return F.coalesce(*[c for c, _ in got]), got[0][1]
        if name == "IF":
            return F.when(got[0][0], got[1][0]).otherwise(got[2][0]), got[1][1]
        if name == "STR":
            return got[0][0].cast("string"), "string"
        if name == "LANG":
            return F.lit(""), "string"
        if name in ("ISIRI", "ISLITERAL"):
            return F.lit((got[0][1] == "iri") == (name == "ISIRI")), "boolean"
        if name == "REGEX":
            flags = f"(?{args[2].value})" if len(args) > 2 else ""
            return got[0][0].rlike(flags + args[1].value), "boolean"
        if name in ("xsd:double", "xsd:decimal"):
            return got[0][0].try_cast("double"), "double"
        if name in ("xsd:integer", "xsd:int"):
            return got[0][0].try_cast("bigint"), "int"
        if name in ("geo:sfIntersects", "geo:dwithin"):
            a, b, d = _near(e)
            return self._shapes_near(self.expr(a, rel)[0], self.expr(b, rel)[0], d), "boolean"
        if name == "geo:distance":
            a, b = _shape(got[0][0]), _shape(got[1][0])
            return geom.distance(a[0], b[0], a_filled=False, b_filled=True), "double"
        if name in _PLAIN:
            fn, dtype = _PLAIN[name]
            return fn(*[c for c, _ in got]), dtype
        raise ValueError(f"no function {name}")

    def _shapes_near(self, a: Column, b: Column, d: float) -> Column:
        return geom.let(_text_struct(a), lambda x: geom.let(_text_struct(b), lambda y: _exact(x, y, d)))

    def _beside(self, left: Rel, node: A.Node) -> Rel:
        """What will be joined to left, and to nothing else."""
        before, self.known = self.known, self.known | left.slots
        try:
            return self.node(node)
        finally:
            self.known = before

    # nodes
    def node(self, n: A.Node) -> Rel:
        if isinstance(n, (A.Bgp, A.Join)):
            return self._joined(n)
        if isinstance(n, A.Filter):
            return self._filtered(n)
        if isinstance(n, A.LeftJoin):
            left = self.node(n.left)
            right = self._beside(left, n.right)
            on = (lambda both: self.expr(n.on, both)[0]) if n.on is not None else None
            return join(left, right, "left", on)
        if isinstance(n, A.Union):
            return union(self.node(n.left), self.node(n.right))
        if isinstance(n, A.Minus):
            left = self.node(n.left)
            right = self._beside(left, n.right)
            return join(left, right, "left_anti") if set(left.slots) & set(right.slots) else left
        if isinstance(n, A.Extend):
            rel = self.node(n.node)
            value, dtype = self.expr(n.expr, rel)
            c = fresh(n.var.name)
            slot = Slot("iri", None, (c,), nullable=True) if dtype == "iri" else Slot("lit", None, (c,), dtype, True)
            return Rel(rel.df.withColumn(c, value), rel.slots | {n.var.name: slot})
        if isinstance(n, A.Values):
            return values(self.graph.spark, n)
        if isinstance(n, A.Group):
            return self._grouped(n)
        if isinstance(n, A.Order):
            rel = self.node(n.node)
            keys = [self.expr(e, rel)[0] for e, _ in n.keys]
            return Rel(rel.df.orderBy(*[k.desc_nulls_last() if down else k.asc_nulls_first() for k, (_, down) in zip(keys, n.keys, strict=True)]), rel.slots)
        if isinstance(n, A.Slice):
            rel = self.node(n.node)
            df = rel.df.offset(n.offset) if n.offset else rel.df
            return Rel(df.limit(n.limit) if n.limit is not None else df, rel.slots)
        if isinstance(n, A.Project):
            return project(self.node(n.node), [v.name for v in n.vars])
        if isinstance(n, A.Distinct):
            rel = self.node(n.node)
            return Rel(project(rel, rel.slots).df.distinct(), rel.slots)
        if isinstance(n, A.Reach):
            return self._reach(n)
        raise TypeError(type(n).__name__)

    def _joined(self, n: A.Node) -> Rel:
        """A join of any depth: its patterns together, lists of values as restrictions where that is exact."""
        patterns, lists, others = _flatten(n)
        names = A.variables(A.Bgp(tuple(patterns)))
        restrict = {}
        for v in lists:
            one = v.vars[0].name
            if len(v.vars) == 1 and one in names and one not in restrict and len(set(v.rows)) == len(v.rows) and all(isinstance(r[0], A.Iri) for r in v.rows):
                restrict[one] = tuple(r[0] for r in v.rows)
        rels: list[Rel] = []
        done: set[str] = set()
        for part in _components(patterns):
            own = {k: r for k, r in restrict.items() if k in A.variables(A.Bgp(tuple(part)))}
            rel, exact = self.graph.patterns(tuple(part), own, self.known)
            rels.append(rel)
            done |= exact
        rels += [self.node(o) for o in others]
        rels += [values(self.graph.spark, v) for v in lists if not (len(v.vars) == 1 and v.vars[0].name in done)]
        if not rels:
            return Rel(self.graph.spark.range(1).select(F.lit(1).alias("_one")), {})
        out = rels.pop(0)
        while rels:
            k = next((k for k, r in enumerate(rels) if set(r.slots) & set(out.slots)), 0)
            out = join(out, rels.pop(k))
        return out

    def _filtered(self, n: A.Filter) -> Rel:
        tests, base = [], n
        while isinstance(base, A.Filter):
            tests += _conjuncts(base.expr)
            base = base.node
        near = next((t for t in tests if isinstance(t, A.Call) and t.name in ("geo:sfIntersects", "geo:dwithin")), None)
        rel = self._apart(base, near, [t for t in tests if t is not near]) if near is not None else None
        if rel is None:
            rel = self.node(base)
        else:
            tests = [t for t in tests if t is not near]
        for t in tests:
            if isinstance(t, A.Exists):
                rel = join(rel, self._beside(rel, t.node), "left_anti" if t.negated else "left_semi")
            else:
                rel = Rel(rel.df.where(self.expr(t, rel)[0]), rel.slots)
        return rel

    def _apart(self, base: A.Node, near: A.Call, tests: list) -> Rel | None:
        """A spatial condition between parts that nothing else connects: a grid join. None if it isn't so."""
        a, b, d = _near(near)
        if not (isinstance(a, A.Var) and isinstance(b, A.Var) and isinstance(base, (A.Bgp, A.Join))):
            return None
        patterns, lists, others = _flatten(base)
        parts = [p for p in _components(patterns + lists + others)]
        left = next((p for p in parts if any(a.name in A.variables(x) for x in p)), None)
        right = next((p for p in parts if any(b.name in A.variables(x) for x in p)), None)
        if left is None or right is None or left is right or len(parts) != 2:
            return None
        if self.graph.strict_simple_features:
            raise UnsupportedGeometry("this graph holds polyhedral surfaces and can't index them")
        sides = []
        for part, v in ((left, a), (right, b)):
            rel = self._joined(_rejoin(part))
            for t in tests:
                if not isinstance(t, A.Exists) and A.variables(t) <= set(rel.slots):
                    rel = Rel(rel.df.where(self.expr(t, rel)[0]), rel.slots)
            c = fresh("shape")
            slot = rel.slots[v.name]
            made = _raw_struct(F.col(slot.columns[0]), slot.pattern == "polygon") if slot.pattern in ("polygon", "line") else _text_struct(rel.text(v.name))
            sides.append((Rel(rel.df.withColumn(c, made), rel.slots), c))
        (l, lc), (r, rc) = sides
        return Rel(_grid_join(l.df, lc, r.df, rc, d), l.slots | r.slots)

    def _grouped(self, n: A.Group) -> Rel:
        rel = self.node(n.node)
        keys = [v.name for v in n.keys if v.name in rel.slots]
        made, slots = [], {k: rel.slots[k] for k in keys}
        for a in n.aggregates:
            c = fresh(a.var.name)
            value, dtype = self.expr(a.expr, rel) if a.expr is not None else (F.lit(1), "int")
            if a.fn == "count":
                made.append((F.count_distinct(value) if a.distinct else F.count(value)).alias(c))
                slots[a.var.name] = Slot("lit", None, (c,), "int")
                continue
            if a.fn in ("sum", "avg"):
                value, dtype = _number(value, dtype), "double"
            fn = {"sum": F.sum_distinct if a.distinct else F.sum, "avg": F.avg, "min": F.min, "max": F.max}[a.fn]
            made.append(fn(value).alias(c))
            slots[a.var.name] = Slot("iri" if dtype == "iri" else "lit", None, (c,), dtype, True)
        by = [F.col(c) for k in keys for c in rel.slots[k].columns]
        return Rel(rel.df.groupBy(*by).agg(*made) if made else rel.df.select(*by).distinct(), slots)

    def _reach(self, n: A.Reach) -> Rel:
        """Pairs along one or more steps: the frontier grows until no pair is new."""
        from cityweave.scratch import Scratch

        step, _ = self.graph.patterns((A.Pattern(A.Var("_s"), n.p, A.Var("_o")),), {}, {})
        step = project(as_text(as_text(step, "_s"), "_o"), ["_s", "_o"])
        s, o = step.slots["_s"].columns[0], step.slots["_o"].columns[0]
        scratch = Scratch(self.graph.spark, "reach")
        edges = scratch.keep(step.df.select(F.col(s).alias("a"), F.col(o).alias("b")).distinct())
        if n.zero:
            ends = edges.select("a").unionByName(edges.select(F.col("b").alias("a"))).distinct()
            found = scratch.keep(ends.select("a", F.col("a").alias("b")).unionByName(edges).distinct())
        else:
            found = edges
        front = edges
        while not front.isEmpty():
            longer = front.select("a", F.col("b").alias("m")).join(edges.select(F.col("a").alias("m"), "b"), "m").select("a", "b").distinct()
            front = scratch.keep(longer.join(found, ["a", "b"], "left_anti"))
            found = scratch.keep(found.unionByName(front))
        cols = {}
        df = found
        for side, t in (("a", n.s), ("b", n.o)):
            if isinstance(t, A.Var):
                c = fresh(t.name)
                df = df.withColumn(c, F.col(side))
                cols[t.name] = Slot("iri", None, (c,))
            else:
                df = df.where(F.col(side) == t.value)
        return project(Rel(df, cols), cols)

    def result(self, q: A.Query) -> DataFrame:
        """The answer with one column for each variable: IRIs as text."""
        node = optimized(q.node)
        rel = self.node(node)
        if q.form == "ask":
            return rel.df.limit(1).agg((F.count(F.lit(1)) > 0).alias("answer"))
        if q.form == "construct":
            parts = []
            for p in q.template:
                cols = [F.lit(t.value).cast("string") if not isinstance(t, A.Var) else rel.text(t.name).cast("string") for t in (p.s, p.p, p.o)]
                parts.append(rel.df.select(*[c.alias(n) for c, n in zip(cols, "spo", strict=True)]))
            return reduce(lambda x, y: x.unionByName(y), parts).na.drop().distinct()
        return rel.df.select(*[rel.text(n).alias(n) for n in rel.slots])


def _flatten(n: A.Node) -> tuple[list[A.Pattern], list[A.Values], list[A.Node]]:
    if isinstance(n, A.Bgp):
        return list(n.patterns), [], []
    if isinstance(n, A.Values):
        return [], [n], []
    if isinstance(n, A.Join):
        a, b = _flatten(n.left), _flatten(n.right)
        return a[0] + b[0], a[1] + b[1], a[2] + b[2]
    return [], [], [n]


def pattern_sets(node: A.Node) -> list[tuple[tuple[A.Pattern, ...], dict[str, tuple[A.Iri, ...]]]]:
    """The sets of patterns that are answered together, with the values that restrict them."""
    if isinstance(node, (A.Bgp, A.Join)):
        patterns, lists, others = _flatten(node)
        restrict = {v.vars[0].name: tuple(r[0] for r in v.rows) for v in lists if len(v.vars) == 1}
        own = [(tuple(part), {k: r for k, r in restrict.items() if k in A.variables(A.Bgp(tuple(part)))}) for part in _components(patterns)]
        return own + [x for o in others for x in pattern_sets(o)]
    return [x for c in A.children(node) for x in pattern_sets(c)]


def _components(items: list) -> list[list]:
    """Items in groups that share variables."""
    groups: list[tuple[set, list]] = []
    for x in items:
        names = A.variables(x)
        touching = [g for g in groups if g[0] & names]
        groups = [g for g in groups if not g[0] & names]
        merged = (names.union(*[g[0] for g in touching]), [y for g in touching for y in g[1]] + [x])
        groups.append(merged)
    return [g[1] for g in groups]


def _rejoin(part: list) -> A.Node:
    patterns = tuple(x for x in part if isinstance(x, A.Pattern))
    nodes: list[A.Node] = [A.Bgp(patterns)] if patterns else []
    nodes += [x for x in part if not isinstance(x, A.Pattern)]
    return reduce(A.Join, nodes)


def _conjuncts(e) -> list:
    if isinstance(e, A.Call) and e.name == "&&":
        return _conjuncts(e.args[0]) + _conjuncts(e.args[1])
    return [e]


def _near(e: A.Call):
    """(shape, shape, distance) of a spatial condition; a buffer becomes a distance."""
    a, b = e.args[0], e.args[1]
    d = float(e.args[2].value) if e.name == "geo:dwithin" else 0.0
    for k, x in enumerate((a, b)):
        if isinstance(x, A.Call) and x.name == "geo:buffer":
            unit = x.args[2].value if len(x.args) > 2 else "metre"
            d += geom.to_metres(float(x.args[1].value), str(unit).split(":")[-1])
            a, b = (x.args[0], b) if k == 0 else (a, x.args[0])
    return a, b, d


def _shape(text: Column) -> tuple[Column, Column]:
    line, rings = wkt.from_line_wkt(text), wkt.from_polygon_wkt(text)
    return F.coalesce(geom.segments(rings), geom.line_segments(line)), F.startswith(text, F.lit("POLYGON"))


def _struct(segs: Column, filled: Column) -> Column:
    """Segments, box and whether there is an inside."""
    xs = lambda s: F.concat(F.transform(s, lambda e: e["x1"]), F.transform(s, lambda e: e["x2"]))
    ys = lambda s: F.concat(F.transform(s, lambda e: e["y1"]), F.transform(s, lambda e: e["y2"]))
    return geom.let(segs, lambda s: F.struct(s.alias("segs"), filled.alias("filled"), F.struct(F.array_min(xs(s)).alias("xmin"), F.array_min(ys(s)).alias("ymin"), F.array_max(xs(s)).alias("xmax"), F.array_max(ys(s)).alias("ymax")).alias("box")))


def _text_struct(text: Column) -> Column:
    return _struct(*_shape(text))


def _raw_struct(shape: Column, polygon: bool) -> Column:
    return _struct(geom.segments(shape) if polygon else geom.line_segments(shape), F.lit(polygon))


def _exact(a: Column, b: Column, d: float) -> Column:
    inside = (a["filled"] & geom.contains_point(a["segs"], F.get(b["segs"], F.lit(0))["x1"], F.get(b["segs"], F.lit(0))["y1"])) | (b["filled"] & geom.contains_point(b["segs"], F.get(a["segs"], F.lit(0))["x1"], F.get(a["segs"], F.lit(0))["y1"]))
    return F.exists(a["segs"], lambda e: F.exists(b["segs"], lambda f: geom.segment_distance(e, f) <= d)) | inside


def _grid_join(left: DataFrame, lc: str, right: DataFrame, rc: str, d: float, cell_m: float = 64.0) -> DataFrame:
    """Rows whose shapes are within d: by cells, then boxes, then exactly."""
    a = left.withColumn("_ca", spatial._cells(F.col(lc)["box"], cell_m, d))
    b = right.withColumn("_cb", spatial._cells(F.col(rc)["box"], cell_m))
    ab, bb = F.col(lc)["box"], F.col(rc)["box"]
    x, y = F.greatest(ab["xmin"] - d, bb["xmin"]), F.greatest(ab["ymin"] - d, bb["ymin"])
    own = (F.floor(x / cell_m) == F.col("_ca.cx")) & (F.floor(y / cell_m) == F.col("_ca.cy"))
    pairs = a.join(b, (F.col("_ca.cx") == F.col("_cb.cx")) & (F.col("_ca.cy") == F.col("_cb.cy"))).where(spatial._told(spatial.boxes_touch(ab, bb, d) & own))
    return pairs.where(_exact(F.col(lc), F.col(rc), d)).drop("_ca", "_cb", lc, rc)


def optimized(node: A.Node) -> A.Node:
    """Buffers bound to names are put where they are used; names that nothing uses aren't worked out."""

    def substitute(e, name: str, by):
        if isinstance(e, A.Var):
            return by if e.name == name else e
        return A.Call(e.name, tuple(substitute(a, name, by) for a in e.args)) if isinstance(e, A.Call) else e

    def visit(n: A.Node, needed: set[str] | None, inline: dict) -> A.Node:
        if isinstance(n, A.Project):
            return replace(n, node=visit(n.node, {v.name for v in n.vars}, inline))
        if isinstance(n, A.Filter):
            expr = n.expr
            lazy = {x.var.name: x.expr for x in A.walk(n.node) if isinstance(x, A.Extend) and isinstance(x.expr, A.Call) and x.expr.name == "geo:buffer"}
            for name, by in lazy.items():
                expr = substitute(expr, name, by)
            return A.Filter(expr, visit(n.node, None if needed is None else needed | A.variables(expr), inline))
        if isinstance(n, A.Extend):
            if needed is not None and n.var.name not in needed:
                return visit(n.node, needed, inline)
            return replace(n, node=visit(n.node, None if needed is None else needed | A.variables(n.expr), inline))
        if isinstance(n, (A.Slice, A.Distinct)):
            return replace(n, node=visit(n.node, needed, inline))
        if isinstance(n, A.Order):
            return replace(n, node=visit(n.node, None if needed is None else needed.union(*[A.variables(e) for e, _ in n.keys]), inline))
        if isinstance(n, A.Group):
            wanted = {v.name for v in n.keys}.union(*[A.variables(a.expr) for a in n.aggregates if a.expr is not None]) if n.aggregates or n.keys else set()
            return replace(n, node=visit(n.node, wanted, inline))
        if isinstance(n, A.Join):
            # a name bound on one side may be joined with the other
            both = None if needed is None else needed | (A.variables(n.left) & A.variables(n.right))
            return A.Join(visit(n.left, both, inline), visit(n.right, both, inline))
        if isinstance(n, A.LeftJoin):
            both = None if needed is None else needed | A.variables(n.right) | A.variables(n.on)
            return replace(n, left=visit(n.left, both, inline), right=visit(n.right, None, inline))
        return n

    return visit(node, None, {})

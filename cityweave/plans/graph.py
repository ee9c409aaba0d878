"""Graphs that answer queries: virtual over the relations, and materialised in three layouts."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field, replace
from functools import cached_property, reduce
from itertools import count
from multiprocessing.pool import ThreadPool
from threading import Lock

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

from cityweave.plans import algebra as A
from cityweave.plans.evaluate import Evaluator, Rel, Slot, fresh, join, optimized, pattern_sets, project, union
from cityweave.plans.mappings import Const, Field, Mapping, Source, Store, Template, fill, invert, saturate
from cityweave.plans.ontology import TYPE, Ontology
from cityweave.plans.parser import parse
from cityweave.plans.unfold import Arm, Unfolder, assertions, covers
from cityweave.scratch import Scratch

TRIPLE = "s string, p string, o string, o_kind tinyint, dtype string, lang string, o_num double"


def _query(q: str | A.Query) -> A.Query:
    return parse(q) if isinstance(q, str) else q


@dataclass
class VirtualGraph:
    """Ontology, mappings and relations; triples exist only in the plans of queries."""

    ontology: Ontology
    mappings: list[Mapping]
    store: Store
    optimize: bool = True
    strict_simple_features: bool = False

    @property
    def spark(self) -> SparkSession:
        return self.store.city.spark

    @cached_property
    def _unique(self) -> dict[str, bool]:
        """Whether the rows of a source keep its key, for those looked up."""
        return {}

    @cached_property
    def saturated(self) -> list[Mapping]:
        return saturate(self.mappings, self.ontology)

    @cached_property
    def unfolder(self) -> Unfolder:
        return Unfolder(self.saturated, self.store.sources, self.optimize)

    def query(self, q: str | A.Query) -> DataFrame:
        return Evaluator(self).result(_query(q))

    def arms(self, q: str | A.Query) -> list[list[Arm]]:
        """What each set of patterns of a query unfolds to."""
        return [self.unfolder.unfold(patterns, restrict) for patterns, restrict in pattern_sets(optimized(_query(q).node))]

    def stats(self, q: str | A.Query) -> dict[str, int]:
        """Union arms, joins and sources read by the unfolded query."""
        arms = [arm for own in self.arms(q) for arm in own]
        return {"arms": len(arms), "joins": sum(len(a.atoms) - 1 for a in arms), "sources": sum(len(a.atoms) for a in arms)}

    def explain(self, q: str | A.Query) -> str:
        return A.pretty(_query(q).node) + "\n" + self.query(q)._jdf.queryExecution().explainString(self.spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))

    def sql(self, q: str | A.Query) -> str:
        """The unfolded patterns as SQL over the sources, one SELECT for each arm."""
        out = []
        for arms in self.arms(q):
            for arm in arms:
                names = {a: f"t{a}" for a, _ in arm.atoms}
                col = lambda c: f"{names[c[0]]}.{c[1]}"
                cols = ", ".join(f"{' || '.join(map(col, b.columns)) or repr(b.pattern)} AS {v}" for v, b in arm.bound)
                tests = [f"{col(x)} = {col(y)}" for x, y in arm.equal] + [f"{col(c)} IN {v!r}" for c, v in arm.within] + [f"{col(c)} IS NOT NULL" for c in arm.present]
                out.append(f"SELECT {cols or '1'} FROM {', '.join(f'{x.source} {names[a]}' for a, x in arm.atoms)}" + (f" WHERE {' AND '.join(tests)}" if tests else ""))
        return "\nUNION ALL\n".join(out)

    def patterns(self, patterns: tuple[A.Pattern, ...], restrict: dict[str, tuple[A.Iri, ...]], known: dict[str, Slot]) -> tuple[Rel, set[str]]:
        arms = self.unfolder.unfold(patterns, restrict)
        if self.optimize:
            stored = {v: s.pattern for v, s in known.items() if s.kind == "iri" and s.pattern}
            arms = [a for a in arms if all(b.kind == "const" or b.kind == "iri" and b.pattern == stored[v] for v, b in a.bound if v in stored)]
        exact = {n for n in restrict if all((b := dict(a.bound)[n]).kind == "const" or len(b.columns) == 1 for a in arms)}
        if not arms:
            names = sorted(A.variables(A.Bgp(patterns)))
            cols = {n: fresh(n) for n in names}
            empty = self.spark.createDataFrame([], ", ".join(f"`{c}` string" for c in cols.values()) or "_one int")
            return Rel(empty, {n: Slot("iri", None, (c,)) for n, c in cols.items()}), set(restrict)
        return reduce(union, [self._arm(a) for a in arms]), exact

    def _arm(self, arm: Arm) -> Rel:
        def name(c: tuple[int, str]) -> str:
            return f"{tag}{c[0]}_{c[1]}"

        tag = fresh("t") + "_"
        needed: dict[int, set[str]] = {a: set() for a, _ in arm.atoms}
        for c in [c for _, b in arm.bound for c in b.columns] + [c for e in arm.equal for c in e]:
            needed[c[0]].add(c[1])
        frames: dict[int, DataFrame] = {}
        for a, atom in arm.atoms:
            df = self.store.sources[atom.source].frame()
            for c, keys in arm.within:
                if c[0] == a:
                    kind = df.schema[c[1]].dataType
                    df = df.where(F.col(c[1]).isin(*[F.lit(k).try_cast(kind) for k in keys]))
            for c in arm.present:
                if c[0] == a:
                    df = df.where(F.col(c[1]).isNotNull())
            if atom.only:
                df = df.select(*atom.only).distinct()
            frames[a] = df.select(*[F.col(c).alias(name((a, c))) for c in sorted(needed[a])] or [F.lit(1).alias(name((a, "one")))])
        # restricted atoms first, then what is joined to them
        rank = {a: (not any(c[0] == a for c, _ in arm.within), k) for k, (a, _) in enumerate(arm.atoms)}
        todo = sorted(frames, key=rank.get)
        done = [todo.pop(0)]
        df = frames[done[0]]
        while todo:
            linked = lambda a: [(x, y) for x, y in arm.equal if {x[0], y[0]} <= {*done, a} and a in (x[0], y[0])]
            a = next((a for a in todo if linked(a)), todo[0])
            tests = [F.col(name(x)) == F.col(name(y)) for x, y in linked(a)]
            df = df.join(frames[a], reduce(lambda x, y: x & y, tests)) if tests else df.crossJoin(frames[a])
            todo.remove(a)
            done.append(a)
        slots, cols = {}, []
        for v, b in arm.bound:
            own = tuple(fresh(v) for _ in b.columns) or (fresh(v),)
            cols += [F.col(name(c)).alias(o) for c, o in zip(b.columns, own, strict=True)] if b.columns else [F.lit(b.pattern).alias(own[0])]
            slots[v] = Slot("lit", b.form or None, own, b.pattern) if b.kind == "lit" else Slot("iri", b.pattern if b.kind == "iri" else None, own)
        return Rel(df.select(*cols) if cols else df.select(F.lit(1).alias("_one")), slots)

    def materialize(self) -> DataFrame:
        """All triples, entailed ones included. A source is read once or twice, whatever its number of triples for a row.

        Only what may come twice is made distinct: triples that a source's keys
        don't tell apart, triples of sources whose rows break their keys, which is
        looked up by the keys alone, and those that another assertion may make too.
        """
        return self._made(assertions(self.saturated))

    def stated(self) -> DataFrame:
        """The triples that the mappings state themselves, without what they entail."""
        return self._made(assertions(self.mappings))

    def materialize_sources(self, names: set[str]) -> DataFrame:
        """Those of all triples that are made from some sources."""
        return self._made([a for a in assertions(self.saturated) if a.source in names])

    @cached_property
    def parts(self) -> list[list]:
        """All assertions, in the least groups that have no triple in common whatever the data are: by predicate and templates, types by class."""
        out: list[list] = []
        for a in assertions(self.saturated):
            same = [part for part in out if any(_alike(a.target, b.target) for b in part)]
            out = [part for part in out if part not in same] + [[b for part in same for b in part] + [a]]
        return out

    def asked(self, patterns: tuple[A.Pattern, ...], restrict: dict[str, tuple[A.Iri, ...]]) -> list[set[int]]:
        """For each pattern, the parts with triples that may match it beside the others: a variable stands for one template at a time."""
        number = {a: k for k, part in enumerate(self.parts) for a in part}
        able = [[a for a in number if _can_match(p, a.target, restrict)] for p in patterns]
        before = None
        while before != (before := [len(own) for own in able]):
            for p in patterns:
                for v in {t.name for t in (p.s, p.p, p.o) if isinstance(t, A.Var)}:
                    ends = [(k, where) for k, q in enumerate(patterns) for where, t in enumerate((q.s, q.p, q.o)) if isinstance(t, A.Var) and t.name == v]
                    for k, where in ends:
                        shapes = {_term(a.target, where) for a in able[k]}
                        for other, there in ends:
                            able[other] = [a for a in able[other] if any(_agree(_term(a.target, there), x) for x in shapes)]
        return [{number[a] for a in own} for own in able]

    def part(self, *numbers: int) -> DataFrame:
        """The triples of one part, or of several; a source is read once for all of them."""
        return self._made([a for k in numbers for a in self.parts[k]])

    def in_parts(self, parts: set[int]) -> DataFrame:
        """The triples of several parts with the number of theirs (part); a source is read once for all of them."""
        number = {a: k for k in sorted(parts) for a in self.parts[k]}
        return self._made(list(number), number)

    def subject_rows(self, kind: str, parts: frozenset[int]) -> DataFrame | None:
        """A row for each subject of a kind with a list for each predicate, straight from the one source that has all of it; None if there is no such source.

        Covered assertions don't count if their source has no keys of its own.
        """
        given = [a for k in parts for a in self.parts[k]]
        stays = {a: covers(self.store.sources, a, given) for a in given}
        own = [a for a in given if stays[a] is None or not self._inside(a, stays[a])]
        keyed = self.store.sources[own[0].source]
        ends = [(a.target.predicate, a.target.object) for a in own]
        plain = len({a.source for a in own}) == 1 == len({a.target.subject for a in own}) and own[0].target.subject.pattern == kind and keyed.tells_rows_apart(own[0].target.subject.columns)
        if not plain or any(n > 1 and not all(type(o) is Const for q, o in ends if q == p) for p, n in Counter(p for p, _ in ends).items()) or not self._keeps_key(own[0].source):
            return None
        return self._cells(keyed.frame(), [a.target for a in own])

    def _made(self, given: list, number: dict | None = None) -> DataFrame:
        """What comes twice is looked for among keys, before there are triples. number: parts of the assertions, for a column of them.

        The same triple from a source whose key another one refers to is made
        once, there; the other one only makes those whose keys aren't found.
        """
        stays = {a: covers(self.store.sources, a, given) for a in given}
        own = [a for a in given if stays[a] is None]
        loose = [a for a in given if stays[a] is not None]
        loose = [a for a in loose if not self._inside(a, stays[a])]
        self._look_up([a.source for a in own if not self.store.sources[a.source].few and self.store.sources[a.source].tells_rows_apart(_columns(a.target))])
        twice = {a for a in own if any(self._may_equal(a, b) for b in own if b is not a)}
        todo: dict[tuple, list] = {}
        for a in own:
            todo.setdefault((a.source, () if self._once(a) else _columns(a.target), "", a in twice), []).append(a)
        for a in loose:
            todo.setdefault((a.source, a.target.subject.columns, stays[a].source, True), []).append(a)
        parts: dict[bool, list[DataFrame]] = {False: [], True: []}
        for (source, only, held, again), same in todo.items():
            frame = self.store.sources[source].frame()
            if only:
                frame = frame.select(*only).distinct()
            if held:
                keys = self.store.sources[held].frame().select(*[F.col(k).alias(c) for k, c in zip(self.store.sources[held].key, only, strict=True)])
                frame = frame.join(keys, list(only), "left_anti")
            parts[again].append(self._rows(frame, [a.target for a in same], [number[a] for a in same] if number else None))
        whole = [reduce(DataFrame.unionByName, x) for x in parts.values() if x]
        return whole[0] if not parts[True] and len(whole) == 1 else reduce(DataFrame.unionByName, [*whole[:-1], whole[-1].dropDuplicates(["s", "p", "o"])])

    def _inside(self, a, by) -> bool:
        """Whether a source is made of rows of the one that it refers to, so that it has no key that isn't there."""
        return self.store.sources[a.source].derived and not {a.source, by.source, *self.store.sources[a.source].refers.values()} & {*self.store.extra}

    def _keeps_key(self, name: str) -> bool:
        """Whether no two rows of a source share its key, nor of the whole that it is part of; a join by whole keys keeps them if what it joins does."""
        if name not in self._unique:
            source = self.store.sources[name]
            if source.distinct and name not in self.store.extra:
                self._unique[name] = True
            elif source.joins and name not in self.store.extra:
                self._unique[name] = all(map(self._keeps_key, source.joins))
            else:
                whole = {n: s for n, s in self.store.sources.items() if n == name or source.part_of and s.part_of == source.part_of}
                plain = source.keys and not {*whole} & {*self.store.extra}
                keys = source.keys() if plain else reduce(DataFrame.unionAll, [s.frame().select(*s.key) for s in whole.values()])
                self._unique |= dict.fromkeys(whole, _no_key_twice(keys, source.key))
        return self._unique[name]

    def _look_up(self, names: list[str]) -> None:
        """Looks up the keys of sources side by side, one of those that are looked up together."""
        todo = {s.part_of or n: n for n in names if n not in self._unique for s in [self.store.sources[n]] if not s.joins or n in self.store.extra}
        if len(todo) > 1:
            with ThreadPool(min(4, len(todo))) as pool:
                pool.map(self._keeps_key, todo.values(), chunksize=1)

    def _once(self, a) -> bool:
        """Whether each row of an assertion's source gives another triple."""
        source = self.store.sources[a.source]
        return not source.few and source.tells_rows_apart(_columns(a.target)) and self._keeps_key(a.source)

    def _may_equal(self, a, b) -> bool:
        """Whether two assertions may give the same triple."""
        s, t = a.target, b.target
        if not _alike(s, t):
            return False
        one, two = self.store.sources[a.source], self.store.sources[b.source]
        # parts of a whole share no key, if that is so in the data
        parts = a.source != b.source and one.part_of and one.part_of == two.part_of
        return not (parts and set(one.key) <= set(_columns(s)) and set(two.key) <= set(_columns(t)) and self._keeps_key(a.source))

    @staticmethod
    def _cells(frame: DataFrame, targets: list) -> DataFrame:
        """Targets with one subject over a frame with a row for each: the row with a list of objects for each predicate."""
        whole = {f.name for f in frame.schema if isinstance(f.dataType, IntegralType)}
        iri = lambda x: fill(x.pattern, [F.col(c) for c in x.columns], [c in whole for c in x.columns])

        def cell(o) -> Column:
            num = F.col(o.column).cast("double") if isinstance(o, Field) and o.dtype in ("double", "int") else F.lit(None).cast("double")
            value = F.col(o.column).cast("string") if isinstance(o, Field) else iri(o) if isinstance(o, Template) else F.lit(o.iri)
            return F.struct(value.alias("o"), num.alias("o_num"))

        lists = {p: F.array(*[cell(t.object) for t in targets if t.predicate == p]) for p in sorted({t.predicate for t in targets})}
        return frame.select(iri(targets[0].subject).alias("s"), *[F.filter(x, lambda c: c["o"].isNotNull()).alias(_column(p)) for p, x in lists.items()])

    @staticmethod
    def _rows(frame: DataFrame, targets: list, numbers: list[int] | None = None) -> DataFrame:
        """Triples of targets over one frame, with the targets' numbers if there are any; each IRI is made once for a row."""
        whole = {f.name for f in frame.schema if isinstance(f.dataType, IntegralType)}
        templates = dict.fromkeys(x for t in targets for x in (t.subject, t.object) if isinstance(x, Template))
        names = {x: f"_iri{k}" for k, x in enumerate(templates)}
        fields = sorted({t.object.column for t in targets if isinstance(t.object, Field)})
        made = frame.select(*fields, *[fill(x.pattern, [F.col(c) for c in x.columns], [c in whole for c in x.columns]).alias(n) for x, n in names.items()])
        none, no_number = F.lit(None).cast("string"), F.lit(None).cast("double")

        def triple(t, *part: Column) -> Column:
            num = no_number
            if isinstance(t.object, Field):
                o, dtype, kind = F.col(t.object.column).cast("string"), F.lit(t.object.dtype), 1
                if t.object.dtype in ("double", "int"):
                    num = F.col(t.object.column).cast("double")
            else:
                o, dtype, kind = F.col(names[t.object]) if isinstance(t.object, Template) else F.lit(t.object.iri), none, 0
            return F.struct(F.col(names[t.subject]).alias("s"), F.lit(t.predicate).alias("p"), o.alias("o"), F.lit(kind).cast("tinyint").alias("o_kind"), dtype.alias("dtype"), none.alias("lang"), num.alias("o_num"), *part)

        each = map(triple, targets, [F.lit(k).alias("part") for k in numbers]) if numbers else map(triple, targets)
        return made.select(F.explode(F.array(*each)).alias("x")).select("x.*").where("o is not null")

    def evolve(self, source: tuple[str, Source], ontology: Ontology, mappings: list[Mapping]) -> VirtualGraph:
        """A new graph with one more source; this one stays as it is."""
        from cityweave.plans.ontology import merge

        store = replace(self.store, extra=self.store.extra | {source[0]: source[1]}, ontology=merge(self.ontology, ontology))
        store.__dict__.pop("sources", None)
        return replace(self, ontology=merge(self.ontology, ontology), mappings=[*self.mappings, *mappings], store=store)


def _no_key_twice(keys: DataFrame, key: tuple[str, ...]) -> bool:
    """Whether no two rows have the same key.

    Whole numbers are tried as bits first: 64 neighbours are one group, and a
    group with as many bits as rows has none twice. Of a longer key that looks
    at its first two columns, the second from 0 to 7. Where this tells nothing,
    all keys are counted.
    """
    kinds = dict(zip(keys.columns, keys.schema, strict=True))
    if all(isinstance(kinds[c].dataType, IntegralType) for c in key[:2]):
        first, second = (F.col(c).cast("bigint") for c in (key[0], key[min(1, len(key) - 1)]))
        fits = F.coalesce(second.between(0, 7) & first.isNotNull() if len(key) > 1 else first.isNotNull(), F.lit(False))
        group, bit = (F.shiftright(first, 3), first.bitwiseAND(F.lit(7)) * 8 + second) if len(key) > 1 else (F.shiftright(first, 6), first.bitwiseAND(F.lit(63)))
        bits = keys.select(group.alias("g"), F.when(fits, bit).cast("int").alias("bit")).groupBy("g").agg(F.count("*").alias("n"), F.bit_or(F.expr("shiftleft(1L, bit)")).alias("bits"))
        if not bits.agg(F.max(F.coalesce(F.col("n") != F.bit_count("bits"), F.lit(True)))).first()[0]:
            return True
    return keys.groupBy(*key).agg(F.count("*").alias("n")).where("n > 1").isEmpty()


def _columns(t) -> tuple[str, ...]:
    """Columns that a target's triples are made of."""
    more = t.object.columns if isinstance(t.object, Template) else (t.object.column,) if isinstance(t.object, Field) else ()
    return tuple(dict.fromkeys((*t.subject.columns, *more)))


def _term(t, where: int):
    """Subject, predicate or object of a target: a template, the value of a constant, or None for literals."""
    if where == 1:
        return t.predicate
    x = t.subject if where == 0 else t.object
    return x.pattern if isinstance(x, Template) else None if isinstance(x, Field) else x.iri


def _agree(x: str | None, y: str | None) -> bool:
    """Whether terms can be the same: templates that are equal, or one that gives the other, a constant."""
    if x is None or y is None or x == y:
        return x == y
    return invert(x, y) is not None if "{}" in x and "{}" not in y else "{}" in y and "{}" not in x and invert(y, x) is not None


def _can_match(p: A.Pattern, t, restrict: dict[str, tuple[A.Iri, ...]]) -> bool:
    """Whether a target's triples may match a pattern by itself."""
    for where, term in enumerate((p.s, p.p, p.o)):
        values = restrict.get(term.name) if isinstance(term, A.Var) else (term,)
        if values is None:
            continue
        if not any(isinstance(t.object, Field) and where == 2 if isinstance(v, A.Lit) else _agree(_term(t, where), v.value) for v in values):
            return False
    return True


def _alike(s, t) -> bool:
    """Whether two targets may give the same triple by their templates. These are injective, so different literal beginnings are enough to tell them apart."""

    def meet(x: str, y: str) -> bool:
        x, y = x.split("{")[0], y.split("{")[0]
        return x.startswith(y) or y.startswith(x)

    def text(o) -> str | None:
        return o.pattern if isinstance(o, Template) else None if isinstance(o, Field) else o.iri

    if s.predicate != t.predicate or not meet(s.subject.pattern, t.subject.pattern):
        return False
    x, y = text(s.object), text(t.object)
    if x is None or y is None:
        return x is y
    return meet(x, y) if isinstance(s.object, Template) or isinstance(t.object, Template) else x == y


LAYOUTS = ("triples", "predicate", "wide")

#: Triples that one task writes.
TASK_ROWS = 1 << 20


@dataclass
class MaterializedGraph:
    """Written triples: one table, one folder for each predicate, or one row for each subject."""

    spark: SparkSession
    ontology: Ontology
    layout: str
    path: str
    strict_simple_features: bool = False
    schema: object = field(default=None, repr=False)

    @classmethod
    def write(cls, triples: DataFrame, ontology: Ontology, layout: str, path: str, **options) -> MaterializedGraph:
        if layout == "triples":
            # a task's triples by predicate, so that a predicate's are in few row groups; nothing is shuffled
            triples.sortWithinPartitions("p").write.mode("overwrite").parquet(path)
        elif layout == "predicate":
            _write_predicates(triples, path)
        elif layout == "wide":
            predicates = [r[0] for r in triples.select("p").distinct().orderBy("p").collect()]
            kind = F.regexp_replace("s", r"/[^/]*\d[^/]*", "/_")
            wide = _gathered(triples, predicates).withColumn("kind", F.regexp_replace(kind, "[^A-Za-z]", "_"))
            wide.write.mode("overwrite").partitionBy("kind").parquet(path)
        else:
            raise ValueError(f"layouts are {LAYOUTS}")
        return cls(triples.sparkSession, ontology, layout, path, **options)

    @cached_property
    def table(self) -> DataFrame:
        return self.spark.read.parquet(self.path)

    def prepare(self, queries: Iterable[str | A.Query]) -> None:
        """Writes what queries ask for, as far as it isn't there; here all of it is."""

    def query(self, q: str | A.Query) -> DataFrame:
        return Evaluator(self).result(_query(q))

    def _slot(self, predicate: A.Term, column: str) -> tuple[Slot, Column]:
        """How objects of a predicate are stored, and the column that has them."""
        p = self.ontology.properties.get(predicate.value) if isinstance(predicate, A.Iri) else None
        if isinstance(predicate, A.Iri) and (predicate.value == TYPE or p and p.kind == "object"):
            return Slot("iri", None, (column,)), F.col("o")
        dtype = p.range if p else "string"
        value = F.col("o_num") if dtype == "double" else F.col("o_num").cast("bigint") if dtype == "int" else F.col("o")
        return Slot("lit", None, (column,), dtype), value

    def _rows_for(self, p: A.Pattern) -> DataFrame:
        """Triples that a pattern is asked of."""
        return self.table

    def _matches(self, p: A.Pattern) -> DataFrame:
        """Triples of a pattern's constants."""
        df = self._rows_for(p)
        if isinstance(p.p, A.Iri):
            df = df.where(F.col("p") == p.p.value)
            if "p_id" in df.columns:
                df = df.where(F.col("p_id") == _column(p.p.value))
        if isinstance(p.s, A.Iri):
            df = df.where(F.col("s") == p.s.value)
        if isinstance(p.o, A.Iri):
            df = df.where((F.col("o") == p.o.value) & (F.col("o_kind") == 0))
        elif isinstance(p.o, A.Lit):
            df = df.where(F.col("o_num") == p.o.value if p.o.dtype in ("int", "double") else F.col("o") == p.o.value)
        return df

    def _one(self, p: A.Pattern, restrict: dict[str, tuple[A.Iri, ...]]) -> Rel:
        df = self._matches(p)
        cols, slots, same = [], {}, []
        for t, where in ((p.s, "s"), (p.p, "p"), (p.o, "o")):
            if not isinstance(t, A.Var):
                continue
            if t.name in restrict:
                df = df.where(F.col(where).isin(*[v.value for v in restrict[t.name]]))
            if t.name in slots:
                same.append((slots[t.name].columns[0], where))
                continue
            c = fresh(t.name)
            slots[t.name], value = self._slot(p.p, c) if where == "o" else (Slot("iri", None, (c,)), F.col(where))
            cols.append(value.alias(c))
        for _, where in same:
            first = next(w for t, w in ((p.s, "s"), (p.p, "p"), (p.o, "o")) if isinstance(t, A.Var))
            df = df.where(F.col(first) == F.col(where))
        return Rel(df.select(*cols) if cols else df.select(F.lit(1).alias("_one")), slots)

    def patterns(self, patterns: tuple[A.Pattern, ...], restrict: dict[str, tuple[A.Iri, ...]], known: dict[str, Slot]) -> tuple[Rel, set[str]]:
        rels = self._stars(patterns, restrict) if self.layout == "wide" else [self._one(p, restrict) for p in self._ordered(patterns)]
        out = rels.pop(0)
        while rels:
            k = next((k for k, r in enumerate(rels) if set(r.slots) & set(out.slots)), 0)
            out = join(out, rels.pop(k))
        return out, set(restrict)

    @staticmethod
    def _ordered(patterns: tuple[A.Pattern, ...]) -> list[A.Pattern]:
        """Patterns with constants first."""
        return sorted(patterns, key=lambda p: sum(isinstance(t, A.Var) for t in (p.s, p.o)))

    def _subjects(self, own: list[A.Pattern]) -> DataFrame:
        """Rows of subjects that patterns are asked of."""
        return self.table

    def _stars(self, patterns: tuple[A.Pattern, ...], restrict: dict[str, tuple[A.Iri, ...]]) -> list[Rel]:
        """One scan for all patterns of a subject; the lists of a row are unrolled."""
        by_subject: dict[A.Term, list[A.Pattern]] = {}
        for p in patterns:
            by_subject.setdefault(p.s, []).append(p)
        out = []
        for s, own in by_subject.items():
            df, slots = self._subjects(own), {}
            if isinstance(s, A.Iri):
                df = df.where(F.col("s") == s.value)
            elif s.name in restrict:
                df = df.where(F.col("s").isin(*[v.value for v in restrict[s.name]]))
            carried: list[str] = []
            if isinstance(s, A.Var):
                c = fresh(s.name)
                df, slots[s.name] = df.withColumn(c, F.col("s")), Slot("iri", None, (c,))
                carried.append(c)
            for p in own:
                if not isinstance(p.p, A.Iri):
                    raise ValueError("the wide layout has no variable predicates")
                if _column(p.p.value) not in df.columns:
                    df = df.withColumn(_column(p.p.value), F.array().cast("array<struct<o:string,o_num:double>>"))
            for p in own:
                cells = F.col(_column(p.p.value))
                if isinstance(p.o, A.Var):
                    df = df.where(F.size(cells) > 0)
                elif isinstance(p.o, A.Iri):
                    df = df.where(F.array_contains(F.transform(cells, lambda x: x["o"]), p.o.value))
                else:
                    numeric = p.o.dtype in ("int", "double")
                    df = df.where(F.array_contains(F.transform(cells, lambda x: x["o_num" if numeric else "o"]), F.lit(float(p.o.value)) if numeric else F.lit(p.o.value)))
            later = {_column(p.p.value) for p in own}
            df = df.select(*carried, *sorted(later))
            for p in own:
                if not isinstance(p.o, A.Var):
                    continue
                c = fresh(p.o.name)
                slot, value = self._slot(p.p, c)
                df = df.withColumn("_cell", F.explode(_column(p.p.value))).withColumns({"o": F.col("_cell.o"), "o_num": F.col("_cell.o_num")})
                if p.o.name in restrict:
                    df = df.where(F.col("o").isin(*[v.value for v in restrict[p.o.name]]))
                if p.o.name in slots:
                    df = df.where(value == F.col(slots[p.o.name].columns[0])).drop("_cell", "o", "o_num")
                    continue
                df = df.withColumn(c, value).drop("_cell", "o", "o_num")
                slots[p.o.name] = slot
            out.append(project(Rel(df, slots), slots) if slots else Rel(df.select(F.lit(1).alias("_one")), {}))
        return out


@dataclass
class GraphInParts(MaterializedGraph):
    """A written graph that is written as it is asked: the parts that a set of patterns may match, whole, when a query first needs them.

    Parts are those of VirtualGraph.parts; what was written stays and serves later queries. In the layouts of triples a part is a
    folder, and those of one query that share a source are written in one pass; in the wide one a kind of subject is, with those of its predicates that were asked so far.
    """

    virtual: VirtualGraph = field(default=None, repr=False)
    written: dict = field(default_factory=dict, repr=False)
    lock: object = field(default_factory=Lock, repr=False)

    def patterns(self, patterns: tuple[A.Pattern, ...], restrict: dict[str, tuple[A.Iri, ...]], known: dict[str, Slot]) -> tuple[Rel, set[str]]:
        own = _Asked(self.spark, self.ontology, self.layout, self.path, self.strict_simple_features)
        if self.layout == "wide":
            kinds, want = self._asked_kinds(patterns, restrict)
            with self.lock:
                self._write_kinds(want)
            own.sources = {p: [self._frame(self.written[k][1]) for k in sorted(kinds[p])] for p in patterns}
        else:
            asked = dict(zip(patterns, self.virtual.asked(patterns, restrict), strict=True))
            with self.lock:
                self._write_parts(set().union(*asked.values()))
            own.sources = {p: self._part_rows(asked[p]) for p in patterns}
        return own.patterns(patterns, restrict, known)

    def prepare(self, queries: Iterable[str | A.Query]) -> None:
        """Writes what queries ask for at once: a source is read once for all of them, and no kind of subject is written again for the predicates of a later one."""
        sets = [own for q in queries for own in pattern_sets(optimized(_query(q).node))]
        if self.layout == "wide":
            want: dict[str, set[int]] = {}
            for own in sets:
                for kind, parts in self._asked_kinds(*own)[1].items():
                    want.setdefault(kind, set()).update(parts)
            with self.lock:
                self._write_kinds(want)
        else:
            asked = set().union(*[k for own in sets for k in self.virtual.asked(*own)])
            with self.lock:
                self._write_parts(asked)

    def query(self, q: str | A.Query) -> DataFrame:
        q = _query(q)
        self.prepare([q])
        return super().query(q)

    def _asked_kinds(self, patterns: tuple[A.Pattern, ...], restrict: dict[str, tuple[A.Iri, ...]]) -> tuple[dict[A.Pattern, set[str]], dict[str, set[int]]]:
        """The kinds of subjects that each pattern is asked of, and the parts that are asked of each kind."""
        asked = dict(zip(patterns, self.virtual.asked(patterns, restrict), strict=True))
        stars: dict[A.Term, list[A.Pattern]] = {}
        for p in patterns:
            stars.setdefault(p.s, []).append(p)
        # only subjects that may have all of a star's predicates
        needed = {p: [self._kinds(asked[p]) for p in star] for s, star in stars.items() for p in star}
        kinds = {p: set.intersection(*(set(k) for k in own)) for p, own in needed.items()}
        want: dict[str, set[int]] = {}
        for p, own_kinds in kinds.items():
            for kind, parts in self._kinds(asked[p]).items():
                if kind in own_kinds:
                    want.setdefault(kind, set()).update(parts)
        return kinds, want

    def _frame(self, path: str) -> DataFrame:
        return self.spark.read.parquet(path)

    def _part_rows(self, parts: set[int]) -> list[DataFrame]:
        """Triples of parts, those written together as one frame; a part without triples has no folder."""
        together: dict[str, list[int]] = {}
        for k in sorted(parts):
            together.setdefault(self.written[k], []).append(k)
        return [self.spark.read.schema(f"{TRIPLE}, part int").parquet(path).where(F.col("part").isin(*own)).drop("part", "p_id") for path, own in together.items()]

    def _kinds(self, parts: set[int]) -> dict[str, set[int]]:
        """Parts by the template of their subjects."""
        out: dict[str, set[int]] = {}
        for k in parts:
            for a in self.virtual.parts[k]:
                out.setdefault(a.target.subject.pattern, set()).add(k)
        return out

    def _write_parts(self, parts: set[int]) -> None:
        """Parts that aren't there yet: those that share a source in one pass, others side by side."""
        groups: list[tuple[set[str], list[int]]] = []
        for k in sorted(parts - {*self.written}):
            read = {a.source for a in self.virtual.parts[k]}
            same = [g for g in groups if g[0] & read]
            groups = [g for g in groups if not g[0] & read] + [(read.union(*[g[0] for g in same]), [k for g in same for k in g[1]] + [k])]
        todo, by = [], ["p_id", "part"] if self.layout == "predicate" else ["part"]
        names = {k: _column(self.virtual.parts[k][0].target.predicate) for _, own in groups for k in own}
        for n, (_, own) in enumerate(groups):
            path = f"{self.path}/{len(self.written)}-{n}"
            if len(own) == 1:
                todo.append((self.virtual.part(own[0]), f"{path}/{f'p_id={names[own[0]]}/' if len(by) == 2 else ''}part={own[0]}", [], path, own))
            else:
                rows = self.virtual.in_parts({*own})
                # a part has one predicate, so its folder's name needn't be made of each triple's
                p_id = F.get(F.array(*[F.lit(names.get(k, "")) for k in range(max(own) + 1)]), F.col("part"))
                todo.append((rows.withColumn("p_id", p_id) if len(by) == 2 else rows, path, by, path, own))
        _write_folders([x[:3] for x in todo])
        self.written |= {k: path for *_, path, own in todo for k in own}

    def _write_kinds(self, want: dict[str, set[int]]) -> None:
        todo = {}
        for kind, parts in sorted(want.items()):
            have = self.written.get(kind, (frozenset(), ""))[0]
            if parts <= have:
                continue
            parts = frozenset(parts | have)
            predicates = sorted({self.virtual.parts[k][0].target.predicate for k in parts})
            rows = self.virtual.subject_rows(kind, parts)
            if rows is None:
                rows = _gathered(self.virtual.part(*sorted(parts)), predicates)
            name = "".join(c if c.isalnum() else "_" for c in kind)
            todo[kind] = (rows, f"{self.path}/kind={name}/{'-'.join(map(str, sorted(parts)))}", parts)
        _write_side_by_side([(rows, path) for rows, path, _ in todo.values()])
        self.written |= {kind: (parts, path) for kind, (_, path, parts) in todo.items()}


@dataclass
class _Asked(MaterializedGraph):
    """What one set of patterns reads of a graph in parts."""

    sources: dict = field(default_factory=dict, repr=False)

    def _whole(self, frames: list[DataFrame], empty: str) -> DataFrame:
        return reduce(lambda x, y: x.unionByName(y, allowMissingColumns=True), frames) if frames else self.spark.createDataFrame([], empty)

    def _rows_for(self, p: A.Pattern) -> DataFrame:
        return self._whole(self.sources[p], TRIPLE)

    def _subjects(self, own: list[A.Pattern]) -> DataFrame:
        return self._whole(self.sources[own[0]], "s string")


def _write_side_by_side(todo) -> None:
    """Writes (rows, path), several at a time."""
    todo = list(todo)
    if todo:
        with ThreadPool(min(4, len(todo))) as pool:
            pool.map(lambda x: x[0].write.mode("overwrite").option("compression", "zstd").parquet(x[1]), todo, chunksize=1)


#: Folders that a task writes side by side, and bytes of a row group of each.
WRITERS, GROUP_BYTES = 64, 8 << 20


def _write_predicates(triples: DataFrame, path: str) -> None:
    """A folder for each predicate."""
    _write_folders([(triples.withColumn("p_id", F.regexp_replace("p", "[^A-Za-z]", "_")), path, ["p_id"])])


def _write_folders(todo: list[tuple[DataFrame, str, list[str]]]) -> None:
    """Writes (rows, path, columns) side by side: a folder for each value of the columns, in one pass; rows go to their folders as they come, without shuffle or sort."""
    if not todo:
        return
    conf, name = todo[0][0].sparkSession.conf, "spark.sql.maxConcurrentOutputFileWriters"
    before = conf.get(name)
    conf.set(name, str(WRITERS))

    def write(x: tuple[DataFrame, str, list[str]]) -> None:
        out = x[0].write.mode("overwrite").option("compression", "zstd")
        (out.option("parquet.block.size", GROUP_BYTES).partitionBy(*x[2]) if x[2] else out).parquet(x[1])

    try:
        with ThreadPool(min(4, len(todo))) as pool:
            pool.map(write, todo, chunksize=1)
    finally:
        conf.set(name, before)


def _gathered(triples: DataFrame, predicates: list[str]) -> DataFrame:
    """A row for each subject with a list of objects for each predicate."""
    cell = F.struct("o", "o_num")
    return triples.groupBy("s").agg(*[F.collect_list(F.when(F.col("p") == p, cell)).alias(_column(p)) for p in predicates])


def _column(predicate: str) -> str:
    return "".join(c if c.isalpha() else "_" for c in predicate)


def forward_chain(triples: DataFrame, ontology: Ontology, rounds: int = 8) -> DataFrame:
    """Triples with all they entail by the hierarchies, domains, ranges and inverses, to a fixpoint.

    The rules are a small table; each round joins the new triples with it.
    """
    spark = triples.sparkSession
    rules = []
    for p in ontology.properties.values():
        rules += [(p.name, "sub", s) for s in ontology.super_properties(p.name) if s != p.name]
        rules += [(p.name, "inverse", p.inverse)] if p.inverse else []
        rules += [(p.name, "domain", p.domain)] if p.domain else []
        rules += [(p.name, "range", p.range)] if p.kind == "object" and p.range else []
    props = F.broadcast(spark.createDataFrame(rules, "p string, rule string, v string"))
    supers = F.broadcast(spark.createDataFrame([(c, s) for c in ontology.classes for s in ontology.ancestors(c) if s != c], "o string, v string"))
    none = [F.lit(None).cast("string").alias("dtype"), F.lit(None).cast("string").alias("lang"), F.lit(None).cast("double").alias("o_num")]
    iri = F.lit(0).cast("tinyint").alias("o_kind")
    scratch = Scratch(spark, "chain")
    known = scratch.keep(triples.dropDuplicates(["s", "p", "o"]))
    new = known
    for _ in range(rounds):
        fired = new.join(props, "p")
        sub = fired.where("rule = 'sub'").select("s", F.col("v").alias("p"), "o", "o_kind", "dtype", "lang", "o_num")
        inverse = fired.where("rule = 'inverse' and o_kind = 0").select(F.col("o").alias("s"), F.col("v").alias("p"), F.col("s").alias("o"), iri, *none)
        domain = fired.where("rule = 'domain'").select("s", F.lit(TYPE).alias("p"), F.col("v").alias("o"), iri, *none)
        range_ = fired.where("rule = 'range' and o_kind = 0").select(F.col("o").alias("s"), F.lit(TYPE).alias("p"), F.col("v").alias("o"), iri, *none)
        classes = new.where(F.col("p") == TYPE).join(supers, "o").select("s", "p", F.col("v").alias("o"), iri, *none)
        made = reduce(lambda x, y: x.unionByName(y), [sub, inverse, domain, range_, classes]).dropDuplicates(["s", "p", "o"])
        new = scratch.keep(made.join(known.select("s", "p", "o"), ["s", "p", "o"], "left_anti"))
        if new.isEmpty():
            return known
        known = scratch.keep(known.unionByName(new))
    return known


def rewritten(q: str | A.Query, ontology: Ontology) -> A.Query:
    """The query with its patterns widened by the hierarchies, for graphs that hold no entailed triples."""
    q = _query(q)
    number = count()

    def widen(p: A.Pattern) -> A.Node:
        arms: list[A.Node] = []
        if isinstance(p.p, A.Iri) and p.p.value == TYPE and isinstance(p.o, A.Iri):
            under = sorted(ontology.descendants(p.o.value))
            arms += [A.Bgp((A.Pattern(p.s, p.p, A.Iri(c)),)) for c in under]
            for prop in ontology.properties.values():
                other = A.Var(f"_w{next(number)}")
                if prop.domain in under:
                    arms.append(A.Bgp((A.Pattern(p.s, A.Iri(prop.name), other),)))
                if prop.kind == "object" and prop.range in under:
                    arms.append(A.Bgp((A.Pattern(other, A.Iri(prop.name), p.s),)))
        elif isinstance(p.p, A.Iri):
            for name in sorted(ontology.sub_properties(p.p.value)):
                arms.append(A.Bgp((A.Pattern(p.s, A.Iri(name), p.o),)))
                inverse = ontology.properties[name].inverse if name in ontology.properties else None
                if inverse:
                    arms.append(A.Bgp((A.Pattern(p.o, A.Iri(inverse), p.s),)))
        if len(arms) <= 1:
            return A.Bgp((p,))
        whole = reduce(A.Union, arms)
        kept = tuple(A.Var(n) for n in sorted(A.variables(p)))
        return A.Distinct(A.Project(kept, whole))

    def visit(n):
        if isinstance(n, A.Bgp):
            return reduce(A.Join, map(widen, n.patterns)) if n.patterns else n
        if isinstance(n, A.Node):
            return replace(n, **{k: visit(v) for k, v in vars(n).items() if isinstance(v, A.Node)})
        return n

    return replace(q, node=visit(q.node))


def refresh(triples: DataFrame, changed: DataFrame, new: DataFrame) -> DataFrame:
    """Triples after a change: those of changed subjects (s) go, new ones come."""
    return triples.join(changed.select("s").distinct(), "s", "left_anti").unionByName(new)


def refresh_written(graph: MaterializedGraph, changed: DataFrame, new: DataFrame, scratch: Scratch) -> list[str]:
    """Brings a written predicate layout up to date: folders of predicates that changed triples are in are written anew, others aren't touched.

    changed: (s, p) of the triples that go; new: triples that come. Returns the
    predicates' folders written. The new rows of a folder are complete before the
    old ones go.
    """
    if graph.layout != "predicate":
        raise ValueError("only the predicate layout can be refreshed in part")
    gone = changed.select("s", "p").distinct()
    name = F.regexp_replace("p", "[^A-Za-z]", "_")
    # at most one row for each predicate of the vocabulary
    touched = sorted(r[0] for r in gone.select(name.alias("p_id")).unionByName(new.select(name.alias("p_id"))).distinct().collect())
    if not touched:
        return []
    old = graph.table.where(F.col("p_id").isin(*touched)).drop("p_id")
    rows = scratch.keep(old.join(gone, ["s", "p"], "left_anti").select(new.columns).unionByName(new))
    spark = graph.spark
    for p_id in touched:
        own = rows.withColumn("p_id", name).where(F.col("p_id") == p_id).drop("p_id")
        tasks = max(1, -(-own.count() // TASK_ROWS))
        own.repartitionByRange(tasks, "s").sortWithinPartitions("s").write.mode("overwrite").parquet(f"{graph.path}/p_id={p_id}")
    scratch.remove(rows)
    spark.catalog.refreshByPath(graph.path)
    graph.__dict__.pop("table", None)
    return touched


#: Triples of a graph that are compared with another's at a time.
COMPARED_ROWS = 1 << 24


def compared(graph: MaterializedGraph, virtual: VirtualGraph) -> Iterator[DataFrame]:
    """(s, p, o, r, w): each triple of a written predicate layout and of a virtual graph with how often either has it, in slices to be read one after the other.

    A slice is some predicates, some classes of rdf:type, or one of these by a hash of
    the subject, of COMPARED_ROWS written triples or not many more, so that what is
    shuffled at a time doesn't grow with the graph. Each triple is in one slice: what
    no mapping gives a predicate or class for is in the last one.
    """
    targets = [(k, a.target) for k, part in enumerate(virtual.parts) for a in part]
    is_type = F.col("p") == TYPE
    class_of = lambda t: t.object.iri if isinstance(t.object, Const) else None
    predicates = sorted({t.predicate for _, t in targets if t.predicate != TYPE})
    classes = sorted({class_of(t) for _, t in targets if t.predicate == TYPE} - {None})
    of_type = graph.table.where(F.col("p_id") == _folder(TYPE))
    # at most a row for each predicate and class of the vocabulary, and for what others there are
    by_predicate = dict(graph.table.groupBy("p").count().where(F.col("p").isin(predicates)).collect())
    by_class = dict(of_type.where(is_type).groupBy("o").count().where(F.col("o").isin(classes)).collect())

    def slices() -> Iterator[tuple[DataFrame, set[int], Column, Column]]:
        for names, n in _dealt({p: by_predicate.get(p, 0) for p in predicates}):
            rows = graph.table.where(F.col("p_id").isin([_folder(p) for p in names]))
            for i in range(n):
                yield rows, {k for k, t in targets if t.predicate in names}, F.col("p").isin(names), _share(n, i)
        for names, n in _dealt({c: by_class.get(c, 0) for c in classes}):
            for i in range(n):
                yield of_type, {k for k, t in targets if t.predicate == TYPE and class_of(t) in (None, *names)}, is_type & F.col("o").isin(names), _share(n, i)
        other = lambda c, names: F.col(c).isNull() | ~F.col(c).isin(names)
        no_predicate, no_class = other("p", [*predicates, TYPE]), is_type & other("o", classes)
        rows = graph.table.where(no_predicate).unionByName(of_type.where(no_class))
        yield rows, {k for k, t in targets if t.predicate == TYPE and class_of(t) is None}, no_predicate | no_class, F.lit(True)

    keys = ["s", "p", "o"]
    for rows, parts, kept, share in slices():
        side = rows.where(kept).where(share).select(*keys, F.lit(1).alias("r"), F.lit(0).alias("w"))
        if parts:
            side = side.unionByName(virtual.in_parts(parts).where(kept).where(share).select(*keys, F.lit(0).alias("r"), F.lit(1).alias("w")))
        yield side.groupBy(*keys).agg(F.sum("r").alias("r"), F.sum("w").alias("w"))


def _folder(predicate: str) -> str:
    """The folder of a predicate in the layout by predicate."""
    return re.sub("[^A-Za-z]", "_", predicate)


def _share(n: int, i: int) -> Column:
    """Whether a triple's subject is in one of n shares."""
    return F.pmod(F.xxhash64("s"), F.lit(n)) == i if n > 1 else F.lit(True)


def _dealt(sizes: dict[str, int]) -> list[tuple[list[str], int]]:
    """Names in groups of COMPARED_ROWS at most, or by themselves if they have more, and the number of shares of each group."""
    out: list[tuple[list[str], int]] = []
    room = -1
    for name, n in sorted(sizes.items(), key=lambda x: -x[1]):
        if n <= room:
            out[-1][0].append(name)
        else:
            out.append(([name], max(1, -(-n // COMPARED_ROWS))))
            room = COMPARED_ROWS
        room -= n
    return out


def difference(before: DataFrame, after: DataFrame) -> DataFrame:
    """(change, s, p, o): triples that only one of two graphs has."""
    keys = ["s", "p", "o"]
    gone = before.select(keys).join(after.select(keys), keys, "left_anti").select(F.lit("removed").alias("change"), *keys)
    come = after.select(keys).join(before.select(keys), keys, "left_anti").select(F.lit("added").alias("change"), *keys)
    return gone.unionByName(come)

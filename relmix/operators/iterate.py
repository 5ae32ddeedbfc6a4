"""Iterative queries with a key-overwriting merge: specification, checks, execution modes, text form.

A specification has a start query, a chain of local queries (each a SQL text that may use the
recursive relation and earlier locals), a next query, one merge rule, a stop rule and a final query.

Modes, with equal rows and rounds where they apply (a mode refuses what it cannot do):
* ``loop``: driver loop; the recursive relation is small, is collected and comes back as literal
  rows each round, so the plan never grows (``MOST_STATE`` rows bound it: beyond them it raises, or with
  ``overflow="dataframe"`` goes on in that mode from the round it has reached);
* ``script``: the same loop compiled to one SQL script whose state is an array-of-structs variable
  (not for DISTINCT ROWS);
* ``dataframe``: the state stays a DataFrame in the shared folder, for large recursive relations; an
  overwriting merge writes it every round, an appending one writes the new rows;
* ``cte``: the engine's own recursive query, for specifications that only append and have no rule but
  the cap; where the cap cuts rows off the engine raises an error instead of returning a part;
* ``client``: one statement per step, each result materialised: the baseline of a host-language loop.
"""

from __future__ import annotations

import re
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import reduce
from operator import and_

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from relmix.operators.merge import append_merge, distinct_merge, overwrite_merge
from relmix.session import remove, scratch

MOST_STATE = 100_000


class IterationError(ValueError):
    """An ill-formed specification."""


class StateTooLarge(IterationError):
    """More rows than a mode brings to the driver."""


@dataclass(frozen=True)
class Stop:
    """``rounds``: the cap (always there); ``unchanged``: stop when no value of the state moved more than
    ``tolerance``; ``until``: a SQL predicate over the new state (true if any row satisfies it)."""

    rounds: int = 100
    unchanged: bool = False
    tolerance: float = 0.0
    until: str | None = None


@dataclass(frozen=True)
class IterationSpec:
    name: str
    start: str
    next: str
    locals: tuple[tuple[str, str], ...] = ()
    merge: str = "replace"  # replace, append or distinct
    keys: tuple[str, ...] = ()
    stop: Stop = field(default_factory=Stop)
    final: str | None = None
    columns: tuple[str, ...] = ()
    semantics: str = "destructive"  # or cumulative: what append and distinct imply


class IterationBuilder:
    """``iterate("r").start(q).let("a", q).next(q).replace_on("k").max_rounds(9).then(q).build()``"""

    def __init__(self, name: str, *columns: str):
        self.spec = IterationSpec(name, "", "", columns=columns)
        self.merges = 0

    def start(self, query: str) -> IterationBuilder:
        self.spec = replace(self.spec, start=query)
        return self

    def let(self, name: str, query: str) -> IterationBuilder:
        self.spec = replace(self.spec, locals=(*self.spec.locals, (name, query)))
        return self

    def next(self, query: str) -> IterationBuilder:
        self.spec = replace(self.spec, next=query)
        return self

    def _merge(self, kind: str, keys: tuple[str, ...] = ()) -> IterationBuilder:
        self.merges += 1
        if self.merges > 1:
            raise IterationError("one merge rule only: an overwriting merge cannot be repeated or mixed with appending")
        self.spec = replace(self.spec, merge=kind, keys=keys, semantics="destructive" if kind == "replace" else "cumulative")
        return self

    def replace_on(self, *keys: str) -> IterationBuilder:
        return self._merge("replace", keys)

    def append(self) -> IterationBuilder:
        return self._merge("append")

    def distinct(self) -> IterationBuilder:
        return self._merge("distinct")

    def max_rounds(self, n: int) -> IterationBuilder:
        self.spec = replace(self.spec, stop=replace(self.spec.stop, rounds=n))
        return self

    def until(self, predicate: str) -> IterationBuilder:
        self.spec = replace(self.spec, stop=replace(self.spec.stop, until=predicate))
        return self

    def unchanged(self, tolerance: float = 0.0) -> IterationBuilder:
        self.spec = replace(self.spec, stop=replace(self.spec.stop, unchanged=True, tolerance=tolerance))
        return self

    def then(self, query: str) -> IterationBuilder:
        self.spec = replace(self.spec, final=query)
        return self

    def build(self) -> IterationSpec:
        validate(self.spec)
        return self.spec


def iterate(name: str, *columns: str) -> IterationBuilder:
    return IterationBuilder(name, *columns)


_WORD = re.compile(r"'(?:[^']|'')*'|`[^`]*`|[A-Za-z_]\w*")


def relations_in(query: str, names: set[str]) -> set[str]:
    """Which of ``names`` a query mentions outside string literals."""
    low = {n.lower(): n for n in names}
    return {low[w.strip("`").lower()] for w in _WORD.findall(query) if not w.startswith("'") and w.strip("`").lower() in low}


def validate(spec: IterationSpec) -> dict[str, set[str]]:
    """The dependency graph of the local queries; raises on an ill-formed specification.

    Rules: start and next are given; the start query uses neither the relation nor a local; locals
    have distinct names and form no cycle (a local may use itself's predecessors only); an overwriting
    merge has keys. The relation read in a round is always its old version and the merge writes the
    new one, which is what makes the program stratified by round.
    """
    if not spec.start or not spec.next:
        raise IterationError("start and next queries are needed")
    names = [n for n, _ in spec.locals]
    if len({n.lower() for n in names}) < len(names) or spec.name.lower() in {n.lower() for n in names}:
        raise IterationError("local names must differ from each other and from the relation")
    known = {spec.name, *names}
    if relations_in(spec.start, known):
        raise IterationError("the start query must not be recursive")
    if spec.merge not in ("replace", "append", "distinct"):
        raise IterationError(f"unknown merge {spec.merge}")
    if spec.merge == "replace" and not spec.keys:
        raise IterationError("an overwriting merge needs keys")
    if spec.merge != "replace" and spec.keys:
        raise IterationError("an overwriting merge cannot be mixed with appending")
    graph = {n: relations_in(q, set(names)) for n, q in spec.locals}
    done: list[str] = []
    while len(done) < len(names):
        ready = [n for n in names if n not in done and graph[n] <= set(done)]
        if not ready:
            raise IterationError(f"local queries form a cycle: {sorted(set(names) - set(done))}")
        done.append(ready[0])
    if not relations_in(spec.next, known):
        raise IterationError("the next query must use the relation or a local query")
    return graph


def local_order(spec: IterationSpec) -> list[tuple[str, str]]:
    graph, by_name = validate(spec), dict(spec.locals)
    out: list[str] = []
    while len(out) < len(by_name):
        out.append(next(n for n in by_name if n not in out and graph[n] <= set(out)))
    return [(n, by_name[n]) for n in out]


def _cast(df: DataFrame, schema: T.StructType, what: str) -> DataFrame:
    if len(df.columns) != len(schema):
        raise IterationError(f"{what} has {len(df.columns)} columns, the relation has {len(schema)}")
    return df.toDF(*schema.names).select(*[F.col(f.name).cast(f.dataType).alias(f.name) for f in schema])


def _renamed(query: str, mapping: dict[str, str]) -> str:
    low = {k.lower(): v for k, v in mapping.items()}
    return _WORD.sub(lambda m: low.get(m[0].strip("`").lower(), m[0]) if not m[0].startswith("'") else m[0], query)


def _started(spark: SparkSession, spec: IterationSpec) -> DataFrame:
    df = spark.sql(spec.start)
    return df.toDF(*spec.columns) if spec.columns else df


class Run:
    """Result frame, rounds done, and the counters that explain a mode's cost."""

    def __init__(self) -> None:
        self.rounds = self.statements = self.materialised = 0
        self.result: DataFrame | None = None


def _small(df: DataFrame) -> list:
    """The rows of a small relation; no more than the bound and one ever reach the driver."""
    rows = df.limit(MOST_STATE + 1).collect()
    if len(rows) > MOST_STATE:
        raise StateTooLarge(f"the state has over {MOST_STATE} rows: use mode dataframe")
    return rows


def _moved(old: list, new: list, keys: tuple[str, ...], tolerance: float) -> bool:
    if len(old) != len(new):
        return True
    by_key = {tuple(r[k] for k in keys) if keys else tuple(r): r for r in old}
    for r in new:
        o = by_key.get(tuple(r[k] for k in keys) if keys else tuple(r))
        if o is None:
            return True
        for a, b in zip(o, r, strict=True):
            if a != b and not (isinstance(a, float) and isinstance(b, float) and abs(a - b) <= tolerance):
                return True
    return False


def _moved_frames(old: DataFrame, new: DataFrame, spec: IterationSpec) -> bool:
    """The same by a join: a new row without an old partner that equals it, numbers within the tolerance."""
    names = new.columns
    before = old.toDF(*[f"__old_{c}" for c in names])
    keys = spec.keys or tuple(names)
    same = reduce(and_, [F.col(f"`{k}`").eqNullSafe(F.col(f"`__old_{k}`")) for k in keys])
    for f in new.schema:
        if f.name in keys:
            continue
        a, b = F.col(f"`{f.name}`"), F.col(f"`__old_{f.name}`")
        near = a.eqNullSafe(b)
        if isinstance(f.dataType, (T.DoubleType, T.FloatType)):
            near = near | F.coalesce(F.abs(a - b) <= spec.stop.tolerance, F.lit(False))
        same = same & near
    return not new.join(before, same, "left_anti").isEmpty() or new.count() != old.count()


def run(spark: SparkSession, spec: IterationSpec, mode: str = "loop", on_round: Callable[[int, DataFrame], None] | None = None, overflow: str = "raise") -> Run:
    validate(spec)
    if overflow not in ("raise", "dataframe"):
        raise IterationError(f"unknown overflow {overflow}")
    if mode == "loop":
        return _run_loop(spark, spec, on_round, overflow == "dataframe")
    modes = {"client": _run_client, "dataframe": _run_dataframe, "cte": _run_cte, "script": _run_script}
    if mode not in modes:
        raise IterationError(f"unknown mode {mode}")
    return modes[mode](spark, spec, on_round)


def _merged(spec: IterationSpec, old: DataFrame, new: DataFrame) -> DataFrame:
    if spec.merge == "replace":
        return overwrite_merge(old, new, list(spec.keys))
    return append_merge(old, new) if spec.merge == "append" else distinct_merge(old, new)


def _folded(spec: IterationSpec, rows: list, got: list) -> tuple[list, list]:
    """The state after a round and the round's new rows."""
    if spec.merge == "replace":
        merged: dict = {tuple(r[k] for k in spec.keys): r for r in rows}
        fresh = [tuple(r[k] for k in spec.keys) for r in got]
        if len(set(fresh)) < len(fresh):
            raise IterationError(f"several new rows for one key of {spec.keys}")
        merged |= dict(zip(fresh, got, strict=True))
        new, delta = list(merged.values()), got
    elif spec.merge == "append":
        new, delta = rows + got, got
    else:
        known = set(map(tuple, rows))
        delta = list({tuple(r): r for r in got if tuple(r) not in known}.values())
        new = rows + delta
    if len(new) > MOST_STATE:
        raise StateTooLarge(f"the state has over {MOST_STATE} rows: use mode dataframe")
    return new, delta


def _run_loop(spark: SparkSession, spec: IterationSpec, on_round, spills: bool) -> Run:
    out = Run()
    state = _started(spark, spec)
    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in state.schema])
    try:
        rows = _small(state)
    except StateTooLarge:
        if not spills:
            raise
        return _run_dataframe(spark, spec, on_round)
    view = {spec.name: f"__{spec.name}_{uuid.uuid4().hex[:8]}"}
    mapping = view | {n: f"__{n}_{uuid.uuid4().hex[:8]}" for n, _ in spec.locals}
    delta = rows
    while out.rounds < spec.stop.rounds:
        # an appending query reads the rows of the round before, an overwriting one the whole relation
        current = spark.createDataFrame(rows if spec.merge == "replace" else delta, schema)
        current.createOrReplaceTempView(view[spec.name])
        for name, query in local_order(spec):
            spark.sql(_renamed(query, mapping)).createOrReplaceTempView(mapping[name])
        try:
            got = _small(_cast(spark.sql(_renamed(spec.next, mapping)), schema, "the next query"))
            new, delta = _folded(spec, rows, got)
        except StateTooLarge:
            if not spills:
                raise
            return _run_stored(spark, spec, on_round, False, (out, spark.createDataFrame(rows, schema), current))
        out.rounds += 1
        out.statements += 1
        if not delta:
            break
        moved = _moved(rows, new, spec.keys, spec.stop.tolerance) if spec.stop.unchanged else True
        rows = new
        if on_round:
            on_round(out.rounds, spark.createDataFrame(rows, schema))
        if not moved or (spec.stop.until and spark.createDataFrame(rows, schema).filter(spec.stop.until).limit(1).count()):
            break
    return _finished(spark, spec, out, spark.createDataFrame(rows, schema))


def _finished(spark: SparkSession, spec: IterationSpec, out: Run, state: DataFrame) -> Run:
    out.result = state
    if spec.final:
        name = f"__{spec.name}_{uuid.uuid4().hex[:8]}"
        state.createOrReplaceTempView(name)
        out.result = spark.sql(_renamed(spec.final, {spec.name: name}))
    return out


def _run_stored(spark: SparkSession, spec: IterationSpec, on_round, every_step: bool, begun: tuple[Run, DataFrame, DataFrame] | None = None) -> Run:
    """State (and, for ``client``, each local query's result) as tables in the shared folder.

    ``begun``: a run that another mode began, its state and the rows of its last round."""
    out, start, delta = begun or (Run(), _started(spark, spec), None)

    def keep(df: DataFrame, label: str) -> tuple[DataFrame, str]:
        path = scratch(spark, f"iterate-{label}")
        df.write.parquet(path)
        out.statements += 1
        out.materialised += 1
        return spark.read.schema(df.schema).parquet(path), path

    state, path = keep(start, "state")
    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in state.schema])
    delta, parts = delta if begun else state, [path]  # an overwriting merge writes the whole relation, an appending one a part more
    mapping = {spec.name: f"__{spec.name}_{uuid.uuid4().hex[:8]}"} | {n: f"__{n}_{uuid.uuid4().hex[:8]}" for n, _ in spec.locals}
    while out.rounds < spec.stop.rounds:
        (state if spec.merge == "replace" else delta).createOrReplaceTempView(mapping[spec.name])
        done = []
        for name, query in local_order(spec):
            local = spark.sql(_renamed(query, mapping))
            if every_step:
                local, p = keep(local, name)
                done.append(p)
            local.createOrReplaceTempView(mapping[name])
        got = _cast(spark.sql(_renamed(spec.next, mapping)), schema, "the next query")
        if spec.merge == "distinct":
            got = got.distinct().join(state, schema.names, "left_anti")
        got, got_path = keep(got, "next")
        out.rounds += 1
        if got.isEmpty():
            break
        if spec.merge == "replace":
            merged, merged_path = keep(overwrite_merge(state, got, list(spec.keys)), "state")
            moved = _moved_frames(state, merged, spec) if spec.stop.unchanged else True
            done += [got_path, *parts]
            parts = [merged_path]
        else:
            moved = True  # there are new rows
            parts.append(got_path)
            merged = spark.read.schema(schema).parquet(*parts)
        for p in done:
            remove(spark, p)
        state, delta = merged, got
        if on_round:
            on_round(out.rounds, state)
        if not moved or (spec.stop.until and state.filter(spec.stop.until).limit(1).count()):
            break
    return _finished(spark, spec, out, state)


def _run_dataframe(spark: SparkSession, spec: IterationSpec, on_round) -> Run:
    return _run_stored(spark, spec, on_round, every_step=False)


def _run_client(spark: SparkSession, spec: IterationSpec, on_round) -> Run:
    return _run_stored(spark, spec, on_round, every_step=True)


def _run_cte(spark: SparkSession, spec: IterationSpec, on_round) -> Run:
    if spec.merge != "append":
        raise IterationError("the engine's recursive query only appends")
    if spec.stop.until or spec.stop.unchanged:
        raise IterationError("the engine's recursive query stops by itself or at the cap only")
    out = Run()
    state = _started(spark, spec)
    body = spec.next
    for name, query in reversed(local_order(spec)):
        body = _renamed(body, {name: f"({query}) AS {name}"})
    columns = ", ".join(spec.columns or state.columns)
    text = f"WITH RECURSIVE {spec.name}({columns}) MAX RECURSION LEVEL {spec.stop.rounds} AS ({spec.start} UNION ALL {body}) {spec.final or f'SELECT * FROM {spec.name}'}"
    out.statements = 1
    out.result = spark.sql(text)
    return out


_SEVERAL = "several new rows for one key"


def compile_script(spec: IterationSpec, schema: T.StructType, rounds_into: str | None = None) -> str:
    """The whole iteration as one SQL script; the state is a variable of type ARRAY<STRUCT>.

    ``rounds_into`` names a session variable that receives the number of rounds."""
    if spec.merge == "distinct":
        raise IterationError("a script supports replace and append")
    fields = ", ".join(f"{f.name}: {f.dataType.simpleString()}" for f in schema)
    names = ", ".join(schema.names)
    pack = f"collect_list(named_struct({', '.join(f'{chr(39)}{n}{chr(39)}, {n}' for n in schema.names)}))"
    tag = uuid.uuid4().hex[:8]
    state, fresh, delta, count, old, on = (f"__{x}_{tag}" for x in ("state", "fresh", "delta", "round", "old", "on"))
    source = state if spec.merge == "replace" else delta
    ctes = [f"{spec.name} AS (SELECT e.* FROM (SELECT explode({source}) AS e))"] + [f"{n} AS ({q})" for n, q in local_order(spec)]
    typed = ", ".join(f"CAST({n} AS {f.dataType.simpleString()}) AS {n}" for n, f in zip(schema.names, schema, strict=True))
    body = f"WITH {', '.join(ctes)}, __next({names}) AS ({spec.next}) SELECT {pack} FROM (SELECT {typed} FROM __next)"
    if spec.merge == "replace":
        same = " AND ".join(f"o.{k} = x.{k}" for k in spec.keys)
        merged = f"concat(filter({state}, o -> NOT exists({fresh}, x -> {same})), {fresh})"
        keys = ", ".join(f"x.{k}" for k in spec.keys)
        check = f"size(array_distinct(transform({fresh}, x -> struct({keys})))) < size({fresh})"
        checked = f"(SELECT CASE WHEN {check} THEN raise_error('{_SEVERAL} of {', '.join(spec.keys)}') ELSE {merged} END)"
    else:
        checked = merged = f"concat({state}, {fresh})"
    goes_on = [f"size({fresh}) > 0"]
    if spec.stop.until:
        goes_on.append(f"NOT exists({state}, s -> {_qualified(spec.stop.until, schema.names)})")
    if spec.stop.unchanged and spec.merge == "replace":
        equal = []
        for f in schema:
            near = f"x.{f.name} <=> o.{f.name}"
            if f.name not in spec.keys and isinstance(f.dataType, (T.DoubleType, T.FloatType)):
                near = f"({near} OR coalesce(abs(x.{f.name} - o.{f.name}) <= {spec.stop.tolerance!r}D, false))"
            equal.append(near)
        moved = f"exists({state}, x -> NOT exists({old}, o -> {' AND '.join(equal)}))"
        goes_on.append(f"(size({state}) <> size({old}) OR {moved})")
    final = spec.final or f"SELECT * FROM {spec.name}"
    last = f"WITH {spec.name} AS (SELECT e.* FROM (SELECT explode({state}) AS e)) {final}"
    columns = f"({', '.join(spec.columns)})" if spec.columns else f"({names})"
    return f"""BEGIN
  DECLARE {count} INT DEFAULT 0;
  DECLARE {state} ARRAY<STRUCT<{fields}>>;
  DECLARE {fresh} ARRAY<STRUCT<{fields}>>;
  DECLARE {delta} ARRAY<STRUCT<{fields}>>;
  DECLARE {old} ARRAY<STRUCT<{fields}>>;
  DECLARE {on} BOOLEAN DEFAULT true;
  SET {state} = (WITH __s{columns} AS ({spec.start}) SELECT {pack} FROM (SELECT {typed} FROM __s));
  SET {fresh} = {state};
  SET {delta} = {state};
  WHILE {on} AND {count} < {spec.stop.rounds} DO
    SET {fresh} = ({body});
    SET {delta} = {fresh};
    SET {old} = {state};
    SET {state} = {checked};
    SET {count} = {count} + 1;
    SET {on} = {' AND '.join(goes_on)};
  END WHILE;
  {f"SET {rounds_into} = {count};" if rounds_into else ""}
  {last};
END"""


def _qualified(predicate: str, names: list[str]) -> str:
    return _renamed(predicate, {n: f"s.{n}" for n in names})


def _run_script(spark: SparkSession, spec: IterationSpec, on_round) -> Run:
    out = Run()
    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in _started(spark, spec).schema])
    out.statements = 1
    variable = f"__rounds_{uuid.uuid4().hex[:8]}"
    spark.sql(f"DECLARE VARIABLE {variable} INT DEFAULT 0")
    try:
        out.result = spark.sql(compile_script(spec, schema, variable))
        out.rounds = spark.sql(f"SELECT {variable}").head()[0]
    except Exception as e:
        if _SEVERAL in str(e):
            raise IterationError(f"{_SEVERAL} of {spec.keys}") from e
        raise
    finally:
        spark.sql(f"DROP TEMPORARY VARIABLE {variable}")
    return out


# ---------------------------------------------------------------- text form

_HEAD = re.compile(r"\s*ITERATE\s+(\w+)\s*(?:\(([^)]*)\))?", re.I)
_CLAUSES = ["START", "REPLACE ON", "APPEND", "DISTINCT ROWS", "NEXT", "LET", "MAX ROUNDS", "UNTIL", "UNCHANGED", "THEN"]


def _parenthesised(text: str, at: int) -> tuple[str, int]:
    while at < len(text) and text[at].isspace():
        at += 1
    if at >= len(text) or text[at] != "(":
        raise IterationError(f"a parenthesised query is expected at: {text[at : at + 30]!r}")
    depth, i, quote = 0, at, False
    while i < len(text):
        c = text[i]
        if c == "'":
            quote = not quote
        elif not quote and c == "(":
            depth += 1
        elif not quote and c == ")":
            depth -= 1
            if not depth:
                return text[at + 1 : i].strip(), i + 1
        i += 1
    raise IterationError("a parenthesis is not closed")


def parse(text: str) -> IterationSpec:
    """``ITERATE r(cols) START (q) [REPLACE ON (k) | APPEND | DISTINCT ROWS] NEXT (q) [LET a AS (q)]*
    [MAX ROUNDS n] [UNTIL (e)] [UNCHANGED [tolerance]] [THEN (q)]``"""
    head = _HEAD.match(text)
    if not head:
        raise IterationError("ITERATE name is expected")
    builder = iterate(head[1], *[c.strip() for c in (head[2] or "").split(",") if c.strip()])
    at = head.end()
    while text[at:].strip():
        at += len(text[at:]) - len(text[at:].lstrip())
        word = next((c for c in _CLAUSES if re.match(re.escape(c).replace(r"\ ", r"\s+") + r"\b", text[at:], re.I)), None)
        if not word:
            raise IterationError(f"unknown clause at: {text[at : at + 30]!r}")
        at += re.match(re.escape(word).replace(r"\ ", r"\s+"), text[at:], re.I).end()
        if word in ("START", "NEXT", "THEN", "UNTIL"):
            query, at = _parenthesised(text, at)
            builder = {"START": builder.start, "NEXT": builder.next, "THEN": builder.then, "UNTIL": builder.until}[word](query)
        elif word == "REPLACE ON":
            keys, at = _parenthesised(text, at)
            builder = builder.replace_on(*[k.strip() for k in keys.split(",")])
        elif word == "APPEND":
            builder = builder.append()
        elif word == "DISTINCT ROWS":
            builder = builder.distinct()
        elif word == "LET":
            name = re.match(r"\s*(\w+)\s+AS", text[at:], re.I)
            if not name:
                raise IterationError("LET name AS (query) is expected")
            query, at = _parenthesised(text, at + name.end())
            builder = builder.let(name[1], query)
        else:
            number = re.match(r"\s*([\d.eE+-]+)?", text[at:])
            at += number.end()
            builder = builder.max_rounds(int(number[1])) if word == "MAX ROUNDS" else builder.unchanged(float(number[1] or 0))
    return builder.build()


def iterate_sql(spark: SparkSession, text: str, mode: str = "loop") -> DataFrame:
    return run(spark, parse(text), mode).result

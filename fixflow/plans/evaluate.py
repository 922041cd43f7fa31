"""Evaluation of rule programs as DataFrames: one rule as joins, strata to a fixpoint (naive, semi-naive or native recursion), and stages."""

from __future__ import annotations

import operator
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import NullType, NumericType, StructType

from ..runtime import version
from .analysis import Violation, check_safety, recognise_latest, stage_stratify, stratify
from .rules import AGGREGATES, Agg, Anything, Atom, Call, Compare, Const, Members, Program, Rule, Var

# a null differs from every value and not from a null
OPS = {"=": operator.eq, "!=": lambda a, b: ~a.eqNullSafe(b), "<": operator.lt, "<=": operator.le, ">": operator.gt, ">=": operator.ge}


def columns(n: int) -> list[str]:
    return [f"a{k}" for k in range(n)]


def _bind(df: DataFrame, atom: Atom) -> DataFrame:
    """Rows of a relation as assignments of the atom's variables; constants and repeated variables filter."""
    df = df.toDF(*columns(len(df.columns)))
    if len(df.columns) != len(atom.args):
        raise ValueError(f"{atom} has {len(df.columns)} columns")
    seen: dict[str, str] = {}
    for c, a in zip(df.columns, atom.args):
        if isinstance(a, Const):
            df = df.where(F.col(c) == F.lit(a.value))
        elif isinstance(a, Var):
            if a.name in seen:
                df = df.where(F.col(c) == F.col(seen[a.name]))
            else:
                seen[a.name] = c
    return df.select(*[F.col(c).alias(v) for v, c in seen.items()])


def _value(x) -> Column:
    return F.lit(x.value) if isinstance(x, Const) else F.col(x.name)


def apply_rule(rule: Rule, relations: dict[str, DataFrame], functions: dict, spark: SparkSession, override: dict[int, DataFrame] | None = None) -> DataFrame:
    """The head's rows (a0, a1, ...). Natural joins on shared variables; a body without atoms is one row. override: other rows for the k-th body item."""
    df: DataFrame | None = None
    todo = []
    for k, x in enumerate(rule.body):
        if isinstance(x, Atom) and not x.negated:
            rows = _bind((override or {}).get(k, relations[x.name]), x)
            if df is None:
                df = rows
            else:
                on = [c for c in df.columns if c in rows.columns]
                df = df.join(rows, on) if on else df.crossJoin(rows)  # the rule itself asks for the product
        else:
            todo.append(x)
    df = spark.range(1).select() if df is None else df
    while todo:
        x = next((t for t in todo if all(not isinstance(a, Var) or a.name in df.columns for a in (t.args if isinstance(t, (Call, Atom)) else (t.left, t.right)))), None)
        if x is None:
            raise ValueError(f"{rule.head}: unbound inputs")
        todo.remove(x)
        if isinstance(x, Call):
            df = df.withColumn(x.out.name, functions[x.function](*[_value(a) for a in x.args]))
        elif isinstance(x, Compare):
            df = df.where(OPS[x.op](_value(x.left), _value(x.right)))
        else:
            rows = _bind(relations[x.name], x)
            df = df.join(rows, rows.columns, "left_anti")
    args = rule.head.args
    if any(isinstance(a, Agg) for a in args):
        keys = [(c, a) for c, a in zip(columns(len(args)), args) if not isinstance(a, Agg)]
        aggs = [(functions.get(a.function) or AGGREGATES[a.function])(F.col(a.var.name)).alias(c) for c, a in zip(columns(len(args)), args) if isinstance(a, Agg)]
        keyed = df.select(*[_value(a).alias(c) for c, a in keys], *df.columns) if keys else df
        return keyed.groupBy(*[c for c, _ in keys]).agg(*aggs).select(*columns(len(args)))
    return df.select(*[(F.explode(F.col(a.var.name)) if isinstance(a, Members) else _value(a)).alias(c) for c, a in zip(columns(len(args)), args)])


def infer_schemas(program: Program, db: dict[str, DataFrame]) -> dict[str, StructType]:
    """Column types of all predicates, as Catalyst finds them for rules over empty relations; no row of db is read.

    Rules of one predicate may differ in numeric types, which widen; other differences, and rules that nothing can start, are violations."""
    check_safety(program)
    spark = next(iter(db.values())).sparkSession
    latest = recognise_latest(program)
    known = {p: df.toDF(*columns(len(df.columns))).schema for p, df in db.items()}
    while True:
        before = dict(known)
        empty = {p: spark.createDataFrame([], s) for p, s in known.items()}
        open_rules = []
        for r in program.rules:
            if any(a.name not in empty for a in r.atoms()):
                open_rules.append(r)
                continue
            made, name = apply_rule(r, empty, program.functions, spark), r.head.name
            if name in known:
                for a, b in zip(known[name], made.schema):
                    numeric = isinstance(a.dataType, NumericType) and isinstance(b.dataType, NumericType)
                    if a.dataType != b.dataType and not numeric and not {type(a.dataType), type(b.dataType)} & {NullType}:
                        raise Violation(r, f"{a.name} is {b.dataType.simpleString()} here and {a.dataType.simpleString()} elsewhere")
                made = spark.createDataFrame([], known[name]).union(made)
            known[name] = made.schema
        known |= {n: known[p] for n, p in latest.items() if p in known}
        types = lambda k: {p: [f.dataType for f in s] for p, s in k.items()}
        if types(known) == types(before):
            if open_rules:
                raise Violation(open_rules[0], "has a body predicate of unknown types")
            return known


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.union, parts)


def evaluate(program: Program, db: dict[str, DataFrame], mode: str = "semi_naive", max_rounds: int = 1000) -> dict[str, DataFrame]:
    """All predicates at the fixpoint, under set semantics. mode: `naive` derives everything again each round, `semi_naive` joins only what was new."""
    check_safety(program)
    relations = dict(db)
    spark = next(iter(db.values())).sparkSession
    for group in stratify(program):
        rules = [r for r in program.rules if r.head.name in group]
        recursive = [r for r in rules if any(a.name in group for a in r.atoms())]
        base: dict[str, DataFrame] = {}
        for p in group:
            own = [apply_rule(r, relations, program.functions, spark) for r in rules if r.head.name == p and r not in recursive]
            if own:
                base[p] = _union(own).distinct()
        for p in group:
            if p not in base:
                like = next(iter(base.values()), None)
                if like is None:
                    raise ValueError(f"{group} has no rule to start from")
                n = len(next(r for r in rules if r.head.name == p).head.args)
                base[p] = like.select(*[F.lit(None).cast(like.schema.fields[min(k, len(like.columns) - 1)].dataType).alias(c) for k, c in enumerate(columns(n))]).limit(0)
        if not recursive:
            relations |= base
            continue
        whole = {p: version(df, p) for p, df in base.items()}
        delta = dict(whole)
        for rounds in range(1, max_rounds + 1):
            found: dict[str, list[DataFrame]] = {}
            for r in recursive:
                spots = [k for k, x in enumerate(r.body) if isinstance(x, Atom) and x.name in group]
                seen = relations | whole
                if mode == "naive":
                    found.setdefault(r.head.name, []).append(apply_rule(r, seen, program.functions, spark))
                else:
                    for k in spots:  # one of the recursive atoms reads the new rows only
                        found.setdefault(r.head.name, []).append(apply_rule(r, seen, program.functions, spark, {k: delta[r.body[k].name]}))
            fresh = {p: version(_union(f).distinct().join(whole[p], columns(len(whole[p].columns)), "left_anti"), p) for p, f in found.items()}
            if all(df.isEmpty() for df in fresh.values()):
                break
            whole |= {p: whole[p].union(df) for p, df in fresh.items()}
            delta = {p: fresh.get(p, whole[p].limit(0)) for p in group}
            if rounds % 16 == 0:  # else the union grows with every round
                whole = {p: version(df, p) for p, df in whole.items()}
        else:
            raise RuntimeError(f"{group} still derives new rows after {max_rounds} rounds")
        relations |= whole
    return {p: relations[p] for p in program.heads()}


def recursive_sql(edges_view: str, max_depth: int = 100) -> str:
    """Native recursion for a linear rule without aggregates over an acyclic relation (src, dst): its transitive closure."""
    return f"with recursive walk(src, dst) max recursion level {max_depth} as (select src, dst from {edges_view} union all select w.src, e.dst from walk w join {edges_view} e on w.dst = e.src) select distinct src, dst from walk"


def run_stages(program: Program, db: dict[str, DataFrame], stages: int, key: dict[str, int] | None = None, bags: set[str] | None = None) -> tuple[dict[str, DataFrame], int]:
    """Stage by stage: (predicates at the last stage, stages run). Stops when no rule derives anything for a next stage.

    Predicates are bags unless they are derived without duplicates anyway (two equal messages both count). latest_p is p with the newest row for each value of its first `key[p]`
    columns: a keyed state that is carried over, instead of a log and its maximum."""
    check_safety(program)
    plan = stage_stratify(program)
    spark = next(iter(db.values())).sparkSession
    now = dict(db)
    for r in plan.init:
        rows = apply_rule(r, now, program.functions, spark)
        now[r.head.name] = now[r.head.name].union(rows) if r.head.name in now and r.head.name not in db else rows
    temporal = {r.head.name for r in program.rules if r.head.stage is not None}
    now |= {p: version(now[p], p) for p in temporal if p in now}
    for name, of in plan.latest.items():
        now[name] = now[of]
    done = 0
    for _ in range(stages):
        nxt: dict[str, DataFrame] = {}
        here, derived = dict(now), set()
        for r in plan.step:
            seen = here | {a.name: nxt[a.name] for a in r.atoms() if a.stage == "J+1" and a.name in nxt}
            missing = [a.name for a in r.atoms() if a.name not in seen]
            if missing:
                raise ValueError(f"{missing[0]} is not derived before {r.head}")
            rows = apply_rule(r, seen, program.functions, spark)
            if r.head.stage == "J":
                here[r.head.name] = here[r.head.name].union(rows) if r.head.name in derived else rows
                derived.add(r.head.name)
            else:
                nxt[r.head.name] = nxt[r.head.name].union(rows) if r.head.name in nxt else rows
        nxt = {p: version(df, p) for p, df in nxt.items()}
        if all(df.isEmpty() for df in nxt.values()):
            break
        for name, of in plan.latest.items():
            if of in nxt:
                k = columns((key or {}).get(of, 1))
                nxt[name] = version(now[name].toDF(*columns(len(now[name].columns))).join(nxt[of].select(*k), k, "left_anti").union(nxt[of]), name)
        now |= nxt
        done += 1
    return now, done

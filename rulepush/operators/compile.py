"""A rule as a lazy DataFrame. Relations have columns c0, c1, ...; a relation without arguments has one column c_."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.ir import COMPARISONS, Const, Literal, Rule, Var

#: Column of a bag: how many derivations a fact has.
TIMES = "n_"

_OPS = {"<": "__lt__", "<=": "__le__", ">": "__gt__", ">=": "__ge__", "=": "__eq__", "<>": "__ne__"}


def positional(df: DataFrame) -> DataFrame:
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))])


def specialise(df: DataFrame, lit: Literal, names: dict[str, str], *more: Column) -> DataFrame:
    """What a literal can match: its constants selected and dropped, repeated variables equated, nulls out; and more columns."""
    first: dict[str, int] = {}
    cond = []
    for i, a in enumerate(lit.args):
        if isinstance(a, Const):
            cond.append(F.col(f"c{i}") == F.lit(a.value))
        elif a.name in first:
            cond.append(F.col(f"c{i}") == F.col(f"c{first[a.name]}"))
        else:
            first[a.name] = i
    if cond:
        df = df.filter(reduce(lambda x, y: x & y, cond))
    return df.select(*[F.col(f"c{i}").alias(names[v]) for v, i in first.items()], *more) if first else df.select(F.lit(1).alias("c_"))


def body_order(r: Rule, start: int | None = None, strategy: str = "greedy") -> list[int]:
    """Positions of the join literals: from start, always one that shares a variable with those before if there is one; textual: as written."""
    if strategy == "textual":
        return [i for i, x in enumerate(r.body) if x.pred not in COMPARISONS and not x.negated]
    left = [i for i, x in enumerate(r.body) if x.pred not in COMPARISONS and not x.negated]
    out, known = [], set()
    while left:
        pick = start if start in left else next((i for i in left if known & set(r.body[i].vars)), left[0])
        left.remove(pick)
        out.append(pick)
        known |= set(r.body[pick].vars)
    return out


def rule_df(spark: SparkSession, r: Rule, relation: Callable[[int, Literal], DataFrame], start: int | None = None, order: str = "greedy", bag: bool = False) -> DataFrame:
    """All derivations of r, one row each; relation gives the relation a body literal reads.

    bag: relations may be bags, and so is what comes out; a row then stands for as many derivations as its TIMES says.
    """
    times = F.lit(1.0)
    names = {v: f"v{i}" for i, v in enumerate(dict.fromkeys(v for x in (r.head, *r.body) for v in x.vars))}
    out, known = None, set()
    for i in body_order(r, start, order):
        x = r.body[i]
        facts = relation(i, x)
        if bag and x.vars and TIMES in facts.columns:
            df = specialise(facts, x, names, F.col(TIMES).alias(f"{TIMES}{i}"))
            times = times * F.col(f"{TIMES}{i}")
        else:
            df = specialise(facts, x, names)
        shared = [names[v] for v in x.vars if v in known]
        if out is None:
            out = df
        elif shared:
            out = out.join(df, shared)
        elif x.vars:
            out = out.crossJoin(df)
        else:
            out = out.crossJoin(df.limit(1).select(F.lit(1).alias(f"e{i}")))
        known |= set(x.vars)
    if out is None:
        out = spark.range(1).select(F.lit(1).alias("c_"))
    term = lambda a: F.lit(a.value) if isinstance(a, Const) else F.col(names[a.name])
    for x in r.body:
        if x.pred in COMPARISONS:
            cond = getattr(term(x.args[0]), _OPS[x.pred])(term(x.args[1]))
            out = out.filter(~cond if x.negated else cond)
    for i, x in enumerate(r.body):
        if x.negated and x.pred not in COMPARISONS:
            df = specialise(relation(i, x), x, names)
            shared = [names[v] for v in x.vars]
            out = out.join(df.dropDuplicates(), shared, "left_anti") if shared else out.join(df.limit(1), F.lit(True), "left_anti")
    head = [term(a).alias(f"c{k}") for k, a in enumerate(r.head.args)] or [F.lit(1).alias("c_")]
    return out.select(*head, times.alias(TIMES)) if bag else out.select(*head)


def counted(bag: DataFrame) -> DataFrame:
    """The same bag, each fact in one row."""
    return bag.groupBy(*facts_of(bag).columns).agg(F.sum(TIMES).alias(TIMES))


def facts_of(df: DataFrame) -> DataFrame:
    """A relation without TIMES."""
    return df.drop(TIMES) if TIMES in df.columns else df


def join_product_count(dfs: list[DataFrame]) -> DataFrame:
    """(c0, c1, n): how often each pair comes out of a chain of binary relations as a bag, never enumerated."""
    out = dfs[0].groupBy("c0", "c1").agg(F.count(F.lit(1)).alias("n"))
    for df in dfs[1:]:
        step = df.groupBy("c0", "c1").agg(F.count(F.lit(1)).alias("m")).toDF("k", "y", "m")
        out = out.join(step, out["c1"] == step["k"]).groupBy("c0", "y").agg(F.sum(F.col("n") * F.col("m")).alias("n")).toDF("c0", "c1", "n")
    return out


__all__ = ["TIMES", "Var", "body_order", "counted", "facts_of", "join_product_count", "positional", "rule_df", "specialise"]

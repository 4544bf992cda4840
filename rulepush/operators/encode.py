"""Dense sequential codes for values, one dictionary for each join domain, made without a global window or the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.ir import COMPARISONS, Const, Literal, Program, Rule, Var
from ..storage import spill


def join_domains(p: Program) -> list[set[tuple[str, int]]]:
    """Argument positions that share a variable, directly or not, are one domain."""
    parent: dict = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for r in p.rules:
        seen: dict[str, tuple[str, int]] = {}
        for x in (r.head, *r.joins):
            for i, a in enumerate(x.args):
                find((x.pred, i))
                if isinstance(a, Var):
                    parent[find((x.pred, i))] = find(seen.setdefault(a.name, (x.pred, i)))
    groups: dict = {}
    for x in list(parent):
        groups.setdefault(find(x), set()).add(x)
    return sorted(groups.values(), key=sorted)


def dictionary(values: DataFrame, partitions: int = 16) -> DataFrame:
    """values(value) -> (value, code): codes 0.. in value order; each partition numbers its own after a small sum of counts."""
    ranged = values.toDF("value").dropna().dropDuplicates().repartitionByRange(partitions, "value").withColumn("_part", F.spark_partition_id())
    ranged = spill(ranged, "dictionary")
    sizes = ranged.groupBy("_part").agg(F.count(F.lit(1)).alias("n"))
    base = sizes.select("_part", F.coalesce(F.sum("n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = F.row_number().over(Window.partitionBy("_part").orderBy("value")) - 1
    return ranged.join(F.broadcast(base), "_part").select("value", (F.col("base") + inside).alias("code"))


def encode(df: DataFrame, col: str, codes: DataFrame) -> DataFrame:
    return df.join(codes.withColumnRenamed("value", col), col).withColumn(col, F.col("code")).drop("code")


def decode(df: DataFrame, col: str, codes: DataFrame) -> DataFrame:
    return df.join(codes.withColumnRenamed("code", col), col).withColumn(col, F.col("value")).drop("value")


def encode_program(spark, p: Program, edb: dict[str, DataFrame]) -> tuple[Program, dict[str, DataFrame], object]:
    """(program over codes, relations of codes, a function that decodes answers).

    edb has columns c0, c1, ... A domain without a stored column keeps its values. Codes follow the order of values
    within a domain only, so programs that compare are refused.
    """
    if any(x.pred in COMPARISONS for r in p.rules for x in r.body):
        raise ValueError("comparisons need values, not codes")
    goal = Rule(p.query, (p.query,))
    code_of: dict[tuple[str, int], dict] = {}
    table_of: dict[tuple[str, int], DataFrame] = {}
    edb = dict(edb)
    for domain in join_domains(Program([*p.rules, goal], p.query)):
        stored = sorted((q, i) for q, i in domain if q in edb and i < len(edb[q].columns))
        if not stored:
            continue
        consts = sorted({x.args[i].value for r in [*p.rules, goal] for x in (r.head, *r.body) for q, i in domain if x.pred == q and isinstance(x.args[i], Const)}, key=repr)
        values = None
        for q, i in stored:
            one = edb[q].select(F.col(f"c{i}").alias("value"))
            values = one if values is None else values.union(one)
        if consts:
            values = values.union(spark.createDataFrame([(c,) for c in consts], f"value {values.dtypes[0][1]}"))
        codes = spill(dictionary(values), "codes")
        known = {r["value"]: r["code"] for r in codes.filter(F.col("value").isin(consts)).collect()} if consts else {}  # the program's constants
        for q, i in stored:
            edb[q] = encode(edb[q], f"c{i}", codes).select(*edb[q].columns)
        for spot in domain:
            code_of[spot], table_of[spot] = known, codes
    swap = lambda x: Literal(x.pred, tuple(Const(code_of[x.pred, i][a.value]) if isinstance(a, Const) and (x.pred, i) in code_of else a for i, a in enumerate(x.args)), x.negated)
    out = Program([Rule(swap(r.head), tuple(map(swap, r.body))) for r in p.rules], swap(p.query))

    def back(df: DataFrame) -> DataFrame:
        names = df.columns
        for i, c in enumerate(names):
            if (p.query.pred, i) in table_of:
                df = decode(df, c, table_of[p.query.pred, i])
        return df.select(*names)

    return out, edb, back

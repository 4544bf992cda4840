"""Readers and writers of facts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def parse_fact_lines(lines: DataFrame, pred: str, arity: int) -> DataFrame:
    """lines(value) of `pred(a, 'b c', 3).` as c0..; other lines are passed over. Quoted arguments double their quotes."""
    term = r"(?:'(?:[^']|'')*'|[^,()']+)"
    pattern = rf"^\s*{pred}\(\s*" + r"\s*,\s*".join([f"({term})"] * arity) + r"\s*\)\.\s*$"
    raw = [F.trim(F.regexp_extract("value", pattern, i + 1)) for i in range(arity)]
    plain = lambda c: F.when(c.startswith("'"), F.replace(c.substr(F.lit(2), F.length(c) - 2), F.lit("''"), F.lit("'"))).otherwise(c)
    return lines.filter(F.col("value").rlike(pattern)).select(*[plain(c).alias(f"c{i}") for i, c in enumerate(raw)])


def read_fact_text(spark: SparkSession, path: str, pred: str, arity: int) -> DataFrame:
    return parse_fact_lines(spark.read.text(path), pred, arity)


def as_fact_lines(df: DataFrame, pred: str) -> DataFrame:
    arg = lambda c: F.when(F.lit(dict(df.dtypes)[c] == "string"), F.concat(F.lit("'"), F.replace(F.col(c).cast("string"), F.lit("'"), F.lit("''")), F.lit("'"))).otherwise(F.col(c).cast("string"))
    return df.select(F.concat(F.lit(f"{pred}("), F.concat_ws(", ", *map(arg, df.columns)), F.lit(").")).alias("value"))


def write_fact_text(df: DataFrame, path: str, pred: str) -> None:
    as_fact_lines(df, pred).write.text(path)


def triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, attr, val) of orders and their lines: sparse and multi-valued."""
    o, li = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    has = o.join(li.select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_semi")
    t = lambda df, i, a, v: df.select(F.col(i).alias("id"), F.lit(a).alias("attr"), v.cast("string").alias("val"))
    parts = [
        t(has, "o_orderkey", "title", F.concat_ws("/", "o_orderpriority", F.col("o_custkey").cast("string"))),
        t(o, "o_orderkey", "year", F.year("o_orderdate")),
        t(li, "l_orderkey", "author", F.col("l_suppkey")),
        t(o.filter(F.dayofmonth("o_orderdate") == 31), "o_orderkey", "month", F.month("o_orderdate")),
        t(li, "l_orderkey", "part", F.col("l_partkey")),
        t(li, "l_orderkey", "quantity", F.col("l_quantity").cast("int")),
        t(li, "l_orderkey", "returnflag", F.col("l_returnflag")),
        t(li, "l_orderkey", "linestatus", F.col("l_linestatus")),
    ]
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out.dropDuplicates()


def mod_relation(spark: SparkSession, sf_dir: str, line: int | None, domain: int, before: str | None = None) -> DataFrame:
    """Distinct (order, part) keys modulo domain of the lines with a line number."""
    li = table(spark, sf_dir, "lineitem")
    if line is not None:
        li = li.filter(F.col("l_linenumber") == line)
    if before:
        li = li.filter(F.col("l_shipdate") < F.lit(before).cast("timestamp_ntz"))
    return li.select((F.col("l_orderkey") % domain).cast("long").alias("c0"), (F.col("l_partkey") % domain).cast("long").alias("c1")).dropDuplicates()


#: Lines, domain and whether keys divided by 7 join in, of the five graph files; each has a cyclic and an acyclic form.
GRAPH_FILES = [("l_linenumber = 1", 1000, False), ("l_linenumber <= 3", 1000, False), ("true", 1000, False), ("true", 2000, False), ("true", 2000, True)]


def graph_file(spark: SparkSession, sf_dir: str, number: int) -> DataFrame:
    """One of ten edge files: 2 i is the cyclic form of GRAPH_FILES[i], 2 i + 1 its acyclic twin, edges from smaller to larger."""
    lines, domain, more = GRAPH_FILES[number // 2]
    li = table(spark, sf_dir, "lineitem").filter(lines).select("l_orderkey", "l_partkey")
    if more:
        li = li.unionByName(li.select(*[F.floor(F.col(c) / 7).alias(c) for c in li.columns]))
    g = li.select(*[(F.col(c) % domain).cast("long").alias(f"c{i}") for i, c in enumerate(li.columns)]).dropDuplicates()
    if number % 2:
        g = g.filter("c0 <> c1").select(F.least("c0", "c1").alias("c0"), F.greatest("c0", "c1").alias("c1")).dropDuplicates()
    return g


def column_pair(spark: SparkSession, sf_dir: str, a: str, b: str, domain: int) -> DataFrame:
    """Distinct pairs of two columns of all lines, modulo domain."""
    li = table(spark, sf_dir, "lineitem")
    return li.select((F.col(a) % domain).cast("long").alias("c0"), (F.col(b) % domain).cast("long").alias("c1")).dropDuplicates()


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name == "dense":
        return mod_relation(spark, sf_dir, None, 1000)
    if name == "acyclic":
        g = mod_relation(spark, sf_dir, None, 1000)
        return g.filter("c0 <> c1").select(F.least("c0", "c1").alias("c0"), F.greatest("c0", "c1").alias("c1")).dropDuplicates()
    if name == "small":
        return mod_relation(spark, sf_dir, 1, 100, "1996-01-01")
    if name == "sparse":
        o = table(spark, sf_dir, "orders").filter(F.col("o_orderdate") < F.lit("1995-09-01").cast("timestamp_ntz"))
        return o.select((F.col("o_orderkey") % 1500).cast("long").alias("c0"), F.col("o_custkey").alias("c1")).dropDuplicates()
    if name == "chain":
        c = table(spark, sf_dir, "conversations").select("conv_id", "turn").dropDuplicates()
        nxt = c.select("conv_id", (F.col("turn") - 1).alias("turn"), F.lit(1).alias("one"))
        key = F.col("conv_id") * 1000 + F.col("turn")
        return c.join(nxt, ["conv_id", "turn"]).select(key.cast("long").alias("c0"), (key + 1).cast("long").alias("c1"))
    raise ValueError(name)

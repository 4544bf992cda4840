"""Operators, functions and streams a user of rules needs around them, each with its SQL."""

from __future__ import annotations

import uuid

import pandas as pd

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.bits import bitmap_sizes
from ..operators.dedup import SetStore
from ..operators.drivers import Options, evaluate
from ..operators.encode import decode, dictionary, encode
from ..operators.fixpoint import fixpoint
from ..operators.local import closure
from ..plans.ir import parse_program
from ..sources.catalog import ChainSource, EdbCatalog, write
from ..sources.facts import as_fact_lines, graph, parse_fact_lines, table
from ..storage import shared_dir
from ..streaming.push import sessions, stream_push, windowed

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def op(name: str, sql: str, *tables: str):
    def put(f):
        QUERIES[name] = lambda spark, sf_dir: f(*[table(spark, sf_dir, t) for t in tables])
        ORACLES[name] = sql
        return f

    return put


def rule(text: str, cols: str, **edb: DataFrame) -> DataFrame:
    spark = next(iter(edb.values())).sparkSession
    return evaluate(spark, parse_program(text), edb).toDF(*cols.split())


@op("scan_parquet", "SELECT n_nationkey, n_name FROM nation WHERE n_regionkey = 1", "nation")
def _(n):
    return n.filter("n_regionkey = 1").select("n_nationkey", "n_name")


@op("scan_fact_text", "SELECT n_nationkey::BIGINT AS k, n_name AS name FROM nation", "nation")
def _(n):
    lines = as_fact_lines(n.select("n_nationkey", "n_name"), "nation")
    return parse_fact_lines(lines, "nation", 2).select(F.col("c0").cast("long").alias("k"), F.col("c1").alias("name"))


@op("op_project", "SELECT DISTINCT 'x' AS k, n_name AS name FROM nation", "nation")
def _(n):
    return rule("h(x, N) :- n(K, N). ?- h(A, N).", "k name", n=n.select("n_nationkey", "n_name"))


@op("op_const_select", "SELECT DISTINCT n_name AS name FROM nation WHERE n_regionkey = 2", "nation")
def _(n):
    return rule("h(N) :- n(N, 2). ?- h(N).", "name", n=n.select("n_name", "n_regionkey"))


@op("op_repeat_var", "SELECT DISTINCT (l_orderkey % 50)::BIGINT AS k FROM lineitem WHERE l_orderkey % 50 = l_partkey % 50", "lineitem")
def _(li):
    return rule("h(X) :- e(X, X). ?- h(X).", "k", e=li.select((F.col("l_orderkey") % 50).cast("long"), (F.col("l_partkey") % 50).cast("long")))


@op("op_compare", "SELECT DISTINCT p_partkey AS part FROM part WHERE p_size < 3", "part")
def _(p):
    return rule("h(P) :- p(P, S), S < 3. ?- h(P).", "part", p=p.select("p_partkey", "p_size"))


JOIN_SQL = "SELECT s_name, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey"
for _name, _hint in (("bcast", "broadcast"), ("merge", "merge"), ("hash", "shuffle_hash")):
    op(f"op_join_{_name}", JOIN_SQL, "supplier", "nation")(lambda s, n, h=_hint: s.join(n.hint(h), s["s_nationkey"] == n["n_nationkey"]).select("s_name", "n_name"))


@op("op_cross", "SELECT r_name, n_name FROM region, nation WHERE n_nationkey < 3", "region", "nation")
def _(r, n):
    return rule("h(R, N) :- r(R), n(N, K), K < 3. ?- h(R, N).", "r_name n_name", r=r.select("r_name"), n=n.select("n_name", "n_nationkey"))


@op("op_theta", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey", "nation")
def _(n):
    return rule("h(A, B) :- n(X, A, R), n(Y, B, R), X < Y. ?- h(A, B).", "a b", n=n.select("n_nationkey", "n_name", "n_regionkey"))


@op("op_range", "SELECT p.p_partkey AS part, q.p_partkey AS near FROM part p JOIN part q ON q.p_retailprice BETWEEN p.p_retailprice AND p.p_retailprice + 0.5 AND p.p_partkey <> q.p_partkey", "part")
def _(p):
    """The range join over all parts: each left row meets the bins from its price to the end of its range.

    Both sides are dealt by bin to a number of tasks that their size doesn't lessen: small tables have many pairs.
    """
    tasks = int(p.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    bin_of = lambda x: F.floor(x / 0.5)
    q = p.select(F.col("p_partkey").alias("near"), F.col("p_retailprice").alias("b"), bin_of(F.col("p_retailprice")).alias("bin"))
    left = p.select(F.col("p_partkey").alias("part"), F.col("p_retailprice").alias("a"), F.explode(F.sequence(bin_of(F.col("p_retailprice")), bin_of(F.col("p_retailprice") + 0.5))).alias("bin"))
    return left.repartition(tasks, "bin").join(q.repartition(tasks, "bin"), "bin").filter("b >= a AND b <= a + 0.5D AND part <> near").select("part", "near")


@op("op_interval", "SELECT a.o_orderkey AS first, b.o_orderkey AS later FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND b.o_orderdate > a.o_orderdate AND b.o_orderdate <= a.o_orderdate + INTERVAL 30 DAY", "orders")
def _(o):
    """Orders within 30 days after another of the same customer: an interval meets the 30-day bins it touches, an order one."""
    bin_of = lambda t: F.floor(F.unix_micros(t.cast("timestamp")) / (30 * 86_400_000_000)).cast("long")
    spans = o.select(F.col("o_orderkey").alias("first"), "o_custkey", F.col("o_orderdate").alias("lo"), F.expr("o_orderdate + INTERVAL 30 DAYS").alias("hi"))
    spans = spans.withColumn("bin", F.explode(F.sequence(bin_of(F.col("lo")), bin_of(F.col("hi")))))
    points = o.select(F.col("o_orderkey").alias("later"), "o_custkey", "o_orderdate", bin_of(F.col("o_orderdate")).alias("bin"))
    return points.join(spans, ["o_custkey", "bin"]).filter("o_orderdate > lo AND o_orderdate <= hi").select("first", "later")


@op("op_asof", "SELECT e.event_id, max(o.o_orderdate) AS last_order FROM events e LEFT JOIN orders o ON o.o_custkey = e.user_id AND o.o_orderdate <= e.ts GROUP BY e.event_id", "events", "orders")
def _(e, o):
    """Last order of the user before each event: one union and one running maximum, no join."""
    both = e.select(F.col("user_id").alias("k"), "ts", "event_id", F.lit(None).cast("timestamp_ntz").alias("d")).unionByName(o.select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts"), F.lit(None).cast("long").alias("event_id"), F.col("o_orderdate").alias("d")))
    w = Window.partitionBy("k").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    return both.withColumn("last_order", F.max("d").over(w)).filter("event_id IS NOT NULL").select("event_id", "last_order")


@op("op_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)", "customer", "orders")
def _(c, o):
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left_semi").select("c_custkey")


@op("op_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)", "customer", "orders")
def _(c, o):
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left_anti").select("c_custkey")


@op("op_outer", "SELECT o_orderkey, count(l_orderkey)::BIGINT AS lines FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey", "orders", "lineitem")
def _(o, li):
    per = li.groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"))
    return o.join(per, o["o_orderkey"] == per["l_orderkey"], "left").groupBy("o_orderkey").agg(F.sum(F.coalesce("n", F.lit(0))).alias("lines"))


@op("op_full_outer", "SELECT c_custkey, u.user_id, coalesce(u.n, 0)::BIGINT AS events FROM customer FULL JOIN (SELECT user_id, count(*) AS n FROM events GROUP BY user_id) u ON c_custkey = u.user_id", "customer", "events")
def _(c, e):
    per = e.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    return c.join(per, c["c_custkey"] == per["user_id"], "full").select("c_custkey", "user_id", F.coalesce("n", F.lit(0)).alias("events"))


@op("op_agg", "SELECT l_returnflag, count(*)::BIGINT AS n, sum(l_quantity)::BIGINT AS qty FROM lineitem GROUP BY l_returnflag HAVING count(*) > 1", "lineitem")
def _(li):
    return li.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").cast("long").alias("qty")).filter("n > 1")


@op("op_distinct_agg", "SELECT l_returnflag, count(DISTINCT l_partkey)::BIGINT AS parts FROM lineitem GROUP BY l_returnflag", "lineitem")
def _(li):
    return li.groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"))


for _name, _kind, _f in (("cube", "CUBE", "cube"), ("rollup", "ROLLUP", "rollup")):
    op(f"op_{_name}", f"SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n FROM lineitem GROUP BY {_kind} (l_returnflag, l_linestatus)", "lineitem")(lambda li, f=_f: getattr(li, f)("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")))


@op("op_gsets", "SELECT l_returnflag, l_linestatus, l_linenumber, count(*)::BIGINT AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linenumber), ())", "lineitem")
def _(li):
    f, s, k = (F.col(c) for c in ("l_returnflag", "l_linestatus", "l_linenumber"))
    return li.groupingSets([[f, s], [k], []], f, s, k).agg(F.count(F.lit(1)).alias("n"))


@op("op_pivot", "SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'O')::BIGINT AS o, count(*) FILTER (WHERE l_linestatus = 'F')::BIGINT AS f FROM lineitem GROUP BY l_returnflag", "lineitem")
def _(li):
    got = li.groupBy("l_returnflag").pivot("l_linestatus", ["O", "F"]).agg(F.count(F.lit(1)))
    return got.select("l_returnflag", F.coalesce("O", F.lit(0)).alias("o"), F.coalesce("F", F.lit(0)).alias("f"))


@op("op_unpivot", "SELECT c_custkey AS id, 'name' AS attr, c_name AS val FROM customer UNION ALL SELECT c_custkey, 'segment', c_mktsegment FROM customer", "customer")
def _(c):
    return c.select(F.col("c_custkey").alias("id"), F.col("c_name").alias("name"), F.col("c_mktsegment").alias("segment")).unpivot("id", ["name", "segment"], "attr", "val")


@op("op_rank", "SELECT n_nationkey, row_number() OVER (PARTITION BY n_regionkey ORDER BY n_name)::INT AS r FROM nation", "nation")
def _(n):
    return n.select("n_nationkey", F.row_number().over(Window.partitionBy("n_regionkey").orderBy("n_name")).alias("r"))


@op("op_lead", "SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next FROM events", "events")
def _(e):
    return e.select("event_id", F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("next"))


@op("op_frame", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS top, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW)::BIGINT AS day FROM events", "events")
def _(e):
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    day = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    e = e.withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.max("value").over(rows).alias("top"), F.count(F.lit(1)).over(day).alias("day"))


@op("op_topk", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10", "orders")
def _(o):
    return o.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey")


@op("op_union", "SELECT n_nationkey AS k FROM nation UNION SELECT r_regionkey FROM region", "nation", "region")
def _(n, r):
    return rule("h(X) :- n(X). h(X) :- r(X). ?- h(X).", "k", n=n.select("n_nationkey"), r=r.select("r_regionkey"))


@op("op_intersect", "SELECT n_nationkey AS k FROM nation INTERSECT SELECT r_regionkey FROM region", "nation", "region")
def _(n, r):
    return n.select(F.col("n_nationkey").alias("k")).intersect(r.select("r_regionkey"))


@op("op_except", "SELECT n_nationkey AS k FROM nation EXCEPT SELECT r_regionkey FROM region", "nation", "region")
def _(n, r):
    return n.select(F.col("n_nationkey").alias("k")).exceptAll(r.select("r_regionkey"))


@op("fn_string", "SELECT p_partkey, upper(substr(p_name, 1, 5)) AS s FROM part", "part")
def _(p):
    return p.select("p_partkey", F.upper(F.substring("p_name", 1, 5)).alias("s"))


@op("fn_date", "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m FROM orders", "orders")
def _(o):
    return o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"))


@op("fn_json", "SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events", "events")
def _(e):
    return e.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@op("fn_math", "SELECT p_partkey, (p_partkey % 7)::BIGINT AS m, floor(p_retailprice)::BIGINT AS f, abs(p_size - 25)::INT AS a, (p_size * p_size)::BIGINT AS sq, greatest(p_size, 10)::INT AS g FROM part", "part")
def _(p):
    size = F.col("p_size")
    return p.select("p_partkey", F.pmod("p_partkey", F.lit(7)).alias("m"), F.floor("p_retailprice").alias("f"), F.abs(size - 25).alias("a"), F.pow(size, F.lit(2)).cast("long").alias("sq"), F.greatest(size, F.lit(10)).alias("g"))


@op("fn_map", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click')::BIGINT AS clicks, count(DISTINCT event_type)::BIGINT AS kinds FROM events GROUP BY user_id", "events")
def _(e):
    per = e.groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    got = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return got.select("user_id", F.coalesce(F.element_at("m", "click"), F.lit(0)).alias("clicks"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


@op("fn_hash", "SELECT p_partkey, md5(p_name) AS m, sha256(p_name) AS s FROM part", "part")
def _(p):
    return p.select("p_partkey", F.md5("p_name").alias("m"), F.sha2("p_name", 256).alias("s"))


@op("op_dictionary", "SELECT p_partkey, p_brand, (dense_rank() OVER (ORDER BY p_brand) - 1)::BIGINT AS code FROM part", "part")
def _(p):
    """Brands as dense codes, and the codes back as brands."""
    codes = dictionary(p.select("p_brand"))
    both = encode(p.select("p_partkey", F.col("p_brand").alias("b")), "b", codes).withColumn("code", F.col("b"))
    return decode(both, "b", codes).select("p_partkey", F.col("b").alias("p_brand"), "code")


@op("fn_array", "SELECT vec_id, len(embedding)::BIGINT AS n FROM embeddings", "embeddings")
def _(v):
    return v.select("vec_id", F.size("embedding").cast("long").alias("n"))


@op("fn_bitmap", "SELECT l_orderkey % 50 AS k, count(DISTINCT l_partkey)::BIGINT AS n FROM lineitem GROUP BY 1", "lineitem")
def _(li):
    return bitmap_sizes(li.select((F.col("l_orderkey") % 50).alias("k"), "l_partkey"), "k", "l_partkey")


@op("udf_scalar", "SELECT p_partkey, length(p_name)::BIGINT AS n FROM part", "part")
def _(p):
    @F.pandas_udf("long")
    def size(s: pd.Series) -> pd.Series:
        return s.str.len()

    return p.select("p_partkey", size("p_name").alias("n"))


@op("udaf_grouped", "SELECT user_id, max(value) - min(value) AS spread FROM events GROUP BY user_id", "events")
def _(e):
    @F.pandas_udf("double")
    def spread(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return e.groupBy("user_id").agg(spread("value").alias("spread"))


@op("udtf_bits", "SELECT DISTINCT (l_orderkey % 50)::BIGINT AS k, (l_partkey % 64)::INT AS bit FROM lineitem", "lineitem")
def _(li):
    """The bits of words by a table function; the words are one `or` a key."""

    @F.udtf(returnType="k bigint, bit int")
    class Bits:
        def eval(self, k: int, word: int):
            word &= (1 << 64) - 1
            while word:
                low = word & -word
                yield k, low.bit_length() - 1
                word ^= low

    words = li.groupBy((F.col("l_orderkey") % 50).alias("k")).agg(F.bit_or(F.expr("shiftleft(1L, cast(l_partkey % 64 AS int))")).alias("w"))
    spark = li.sparkSession
    spark.udtf.register("bits_of", Bits)
    return spark.sql("SELECT t.k, t.bit FROM {words} w, LATERAL bits_of(w.k, w.w) t", words=words)


@op("st_tumbling", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY ALL", "events")
def _(e):
    return windowed(e, "1 day")


@op("st_sliding", "SELECT s AS start, event_type, count(*)::BIGINT AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR]) AS s FROM events) GROUP BY ALL", "events")
def _(e):
    return windowed(e, "1 day", "12 hours")


@op("st_session", """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 1 DAY THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
 s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS id FROM g) SELECT user_id, min(ts) AS start, count(*)::BIGINT AS n FROM s GROUP BY user_id, id""", "events")
def _(e):
    return sessions(e, "1 day")


def written(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of files; times are instants, as watermarks need them."""
    schema = table(spark, sf_dir, "events").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.expr("timestamp_micros(timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts))"))


def drained(stream: DataFrame, each) -> None:
    """Runs a stream until its source has nothing more; each(batch, number) takes the batches."""
    stream.writeStream.option("checkpointLocation", written(stream.sparkSession, "stream")).trigger(availableNow=True).foreachBatch(each).start().awaitTermination()


def st_push_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Facts of a rule pushed from a stream, batch by batch, each kept once."""
    p = parse_program("seen(U, S, T) :- event(E, U, T), customer(U, S). ?- seen(U, S, T).")
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    store = SetStore()
    stream = stream_push(event_stream(spark, sf_dir).select("event_id", "user_id", "event_type"), p, "event", {"customer": customers})
    drained(stream, lambda batch, _: store.add(batch, "seen"))
    return store.known().toDF("user_id", "segment", "event_type")


def st_tumbling_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows of a stream as they are when it has ended: the last count of each."""
    path = written(spark, "windows")

    def put(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("append").parquet(path)

    stream = windowed(event_stream(spark, sf_dir), "1 day", late="400 days")
    stream.writeStream.outputMode("update").option("checkpointLocation", written(spark, "stream")).trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    ends = spark.read.parquet(path).groupBy("start", "event_type").agg(F.max_by("n", "batch").alias("n"))
    return ends.withColumn("start", F.expr("timestampadd(MICROSECOND, unix_micros(start), TIMESTAMP_NTZ '1970-01-01 00:00:00')"))


def st_distinct_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users of a stream, each once while its state is held."""
    store = SetStore()
    stream = event_stream(spark, sf_dir).withWatermark("ts", "4000 days").dropDuplicatesWithinWatermark(["user_id"]).select("user_id")
    drained(stream, lambda batch, _: store.add(batch, "users"))
    return store.known()


QUERIES |= {"st_push_batch": st_push_batch, "st_tumbling_stream": st_tumbling_stream, "st_distinct_stream": st_distinct_stream}
ORACLES["st_push_batch"] = "SELECT DISTINCT user_id, c_mktsegment AS segment, event_type FROM events JOIN customer ON c_custkey = user_id"
ORACLES["st_tumbling_stream"] = ORACLES["st_tumbling"]
ORACLES["st_distinct_stream"] = "SELECT DISTINCT user_id FROM events"


def round_trip(fmt: str, schema: str | None = None, by: list[str] | None = None, **options):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        path = written(spark, fmt)
        write(table(spark, sf_dir, "nation").select("n_nationkey", "n_name", "n_regionkey"), path, fmt, "nation", by)
        got = EdbCatalog(spark).read("nation", fmt, path, schema, 3, **options).relations()["nation"]
        if fmt == "facts":
            got = got.select(F.col("c0").cast("int").alias("n_nationkey"), F.col("c1").alias("n_name"), F.col("c2").cast("int").alias("n_regionkey"))
        return got.select("n_nationkey", "n_name", "n_regionkey")

    return run


_NATION = "n_nationkey int, n_name string, n_regionkey int"
QUERIES |= {
    "sink_csv": round_trip("csv", _NATION), "sink_json": round_trip("json", _NATION), "sink_facts": round_trip("facts"), "sink_partitioned": round_trip("parquet", _NATION, by=["n_regionkey"]),
}
ORACLES |= {n: "SELECT n_nationkey, n_name, n_regionkey FROM nation" for n in ("sink_csv", "sink_json", "sink_facts", "sink_partitioned")}


def scan_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Relations bound to a view, a frame and rows, joined by a rule."""
    table(spark, sf_dir, "nation").select("n_nationkey", "n_name", "n_regionkey").createOrReplaceTempView("nation_facts")
    edb = EdbCatalog(spark).bind("nation", "nation_facts").bind("customer", table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")).bind("wanted", [(1,), (3,)], "r int")
    p = parse_program("h(C, N) :- wanted(R), nation(K, N, R), customer(C, K). ?- h(C, N).")
    return evaluate(spark, p, edb.relations()).toDF("customer", "nation")


def scan_python_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The closure of edges made by a source in Python: a chain for each line number, as long as its largest quantity."""
    spark.dataSource.register(ChainSource)
    most = table(spark, sf_dir, "lineitem").groupBy("l_linenumber").agg(F.max("l_quantity").cast("int").alias("n")).orderBy("l_linenumber")
    lengths = [str(r["n"]) for r in most.collect()]  # line numbers, of which an order has few
    edges = spark.read.format("rulepush_chains").options(lengths=",".join(lengths)).load()
    return closure(edges)


QUERIES |= {"scan_table": scan_table, "scan_python_source": scan_python_source}
ORACLES["scan_table"] = "SELECT c_custkey AS customer, n_name AS nation FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_regionkey IN (1, 3)"
ORACLES["scan_python_source"] = """WITH t AS (SELECT row_number() OVER (ORDER BY l_linenumber) - 1 AS c, max(l_quantity)::INT AS n FROM lineitem GROUP BY l_linenumber), w AS (SELECT max(n) + 1 AS w FROM t)
 SELECT (c * w + a)::BIGINT AS c0, (c * w + b)::BIGINT AS c1 FROM t, w, range(100) u(a), range(100) v(b) WHERE a < b AND b <= n"""


def recursive_cte(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The closure of an acyclic graph as recursive SQL: the recursion is a bag, so duplicates go at its end."""
    e = graph(spark, sf_dir, "chain").toDF("x", "y")
    return spark.sql("WITH RECURSIVE tc(x, y) AS (SELECT x, y FROM {e} UNION ALL SELECT tc.x, e.y FROM tc JOIN {e} e ON tc.y = e.x) SELECT DISTINCT x AS c0, y AS c1 FROM tc", e=e)


def fixpoint_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same as a fixpoint over frames, with the least number of steps to each pair."""
    e = graph(spark, sf_dir, "chain").toDF("x", "y")
    seed = e.select("x", "y", F.lit(1).alias("steps"))
    return fixpoint(seed, lambda new: new.join(e.toDF("y", "z"), "y").select("x", F.col("z").alias("y"), (F.col("steps") + 1).alias("steps")), keys=["x", "y"])


_CHAIN = "WITH RECURSIVE e AS (SELECT DISTINCT a.conv_id * 1000 + a.turn AS x, a.conv_id * 1000 + a.turn + 1 AS y FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.turn + 1 = b.turn), "
QUERIES |= {"op_recursive_cte": recursive_cte, "op_fixpoint_frames": fixpoint_frames}
ORACLES["op_recursive_cte"] = _CHAIN + "tc(x, y) AS (SELECT x, y FROM e UNION SELECT tc.x, e.y FROM tc JOIN e ON tc.y = e.x) SELECT x AS c0, y AS c1 FROM tc"
ORACLES["op_fixpoint_frames"] = _CHAIN + "tc(x, y, steps) AS (SELECT x, y, 1 FROM e UNION SELECT tc.x, e.y, steps + 1 FROM tc JOIN e ON tc.y = e.x) SELECT x, y, min(steps)::INT AS steps FROM tc GROUP BY ALL"

for _share in ("persist", "recompute"):
    QUERIES[f"op_share_{_share}"] = lambda spark, sf_dir, s=_share: evaluate(
        spark, parse_program("pair(A, B) :- sold(S, A), sold(S, B), A < B. sold(S, P) :- line(O, P, S). ?- pair(A, B)."),
        {"line": table(spark, sf_dir, "lineitem").select("l_orderkey", (F.col("l_partkey") % 100).alias("p"), "l_suppkey")}, options=Options(share=s)).toDF("a", "b")
    ORACLES[f"op_share_{_share}"] = "SELECT DISTINCT a.l_partkey % 100 AS a, b.l_partkey % 100 AS b FROM lineitem a JOIN lineitem b ON a.l_suppkey = b.l_suppkey AND a.l_partkey % 100 < b.l_partkey % 100"


def fixpoint_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A non-linear closure: two literals of one component, so two delta versions a rule."""
    p = parse_program("tc(X, Y) :- par(X, Y). tc(X, Y) :- tc(X, Z), tc(Z, Y). ?- tc(X, Y).")
    return evaluate(spark, p, {"par": graph(spark, sf_dir, "small")})


QUERIES["op_fixpoint"] = fixpoint_rounds
ORACLES["op_fixpoint"] = """WITH RECURSIVE e AS (SELECT DISTINCT (l_orderkey % 100)::BIGINT AS x, (l_partkey % 100)::BIGINT AS y FROM lineitem WHERE l_linenumber = 1 AND l_shipdate < TIMESTAMP '1996-01-01'),
 tc(x, y) AS (SELECT x, y FROM e UNION SELECT e.x, tc.y FROM e JOIN tc ON e.y = tc.x) SELECT x AS c0, y AS c1 FROM tc"""

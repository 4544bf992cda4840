"""Operator 7: exact top-k by inner product with vector-approximation files.

Every vector is stored twice: as one small cell number per component, and exactly. Cells bound the score from
above and below. Distinct query vectors go in blocks of a fixed size, which are sent to the tasks that hold the cells.
A first scan keeps each query's best lower bounds, and gives the floor that its k best reach for certain; a second
scan gives what may still reach it. Exact vectors are then read in order of their bounds: first the most promising of
each query, then those whose bound still reaches the k-th exact score, after which the result is certain. Cells are
never shuffled, and what the scans send grows with the queries.

Components become integers floor(scale * x), so scores are exact integers. Bounds are taken in floating point and
widened by what rounding can do. Equal vectors are held once, with their k + r smallest ids, r being how often the most
repeated id occurs: ties go to smaller ids, so no more can enter a result.

Vectors that are null, or hold null or non-finite components, take no part; so do rows without an id. A vector that is
shorter than another, or empty, counts as if it ended in zeros. An empty table gives an empty result; a repeated id
counts as often as it occurs, and a repeated query is answered each time. Integers beyond 2**62 in size, and scores
that a 64-bit integer can't hold, are an OverflowError, never a wrong score. Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import drop, saved, shuffle_partitions

RESULT = "query_id long, rank int, vec_id long, score long"
MOST = 1 << 62


def integers(vectors: DataFrame, scale: int) -> DataFrame:
    """(id, vector): floor(scale * x) of the vectors that take part, 64 bits each, without zeros at the end."""

    def run(batches):
        for batch in batches:
            ids, lists = batch.column(0), batch.column(1).cast(pa.list_(pa.float64()))
            batch = pa.RecordBatch.from_arrays([ids, lists], ["id", "v"]).filter(pc.and_(pc.is_valid(ids), pc.is_valid(lists)))
            out_ids, out = [], []
            for i, v in zip(batch.column(0).to_pylist(), batch.column(1)):
                flat = v.values
                x = np.floor(flat.fill_null(np.nan).to_numpy(zero_copy_only=False) * scale)
                if np.isfinite(x).all():
                    if len(x) and np.abs(x).max() > MOST:
                        raise OverflowError(f"components of vector {i} are beyond 2**62")
                    out_ids.append(i)
                    out.append(np.trim_zeros(x.astype("<i8"), "b").tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(out_ids, pa.int64()), pa.array(out, pa.binary())], ["id", "vector"])

    return vectors.toDF("id", "v").select(F.col("id").cast("long"), "v").mapInArrow(run, "id long, vector binary")


def distinct_vectors(rows: DataFrame, keep: int) -> DataFrame:
    """(gid, gid2, vector, ids): distinct vectors with their `keep` smallest ids; a common vector's ids meet in lanes first."""
    lanes = max(16, shuffle_partitions(rows.sparkSession))
    smallest = lambda ids: F.slice(F.array_sort(ids), 1, keep)

    def run(batches):
        for b in batches:
            held: dict[bytes, list[int]] = {}
            for i, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                held.setdefault(v, []).append(i)
            yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array([sorted(v)[:keep] for v in held.values()], pa.list_(pa.int64()))], ["vector", "ids"])

    each = rows.mapInArrow(run, "vector binary, ids array<long>").withColumn("lane", F.pmod(F.xxhash64("ids"), F.lit(lanes)))
    each = each.groupBy("vector", "lane").agg(smallest(F.flatten(F.collect_list("ids"))).alias("ids"))
    each = each.groupBy("vector").agg(smallest(F.flatten(F.collect_list("ids"))).alias("ids"))
    return each.select(*_keys(), "vector", "ids")


def _keys():
    return F.xxhash64("vector").alias("gid"), F.xxhash64(F.lit(1), "vector").alias("gid2")


def matrix(vectors, width: int) -> np.ndarray:
    """Rows of 64-bit integers, filled up with zeros."""
    return np.frombuffer(b"".join(v.ljust(8 * width, b"\0") for v in vectors), "<i8").reshape(len(vectors), width)


def cell_edges(groups: DataFrame, width: int, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(low, step) of each component's cells, from its least and greatest value over all vectors."""

    def run(batches):
        low = high = None
        for b in batches:
            if b.num_rows:
                x = matrix(b.column(0).to_pylist(), width)
                low = x.min(0) if low is None else np.minimum(low, x.min(0))
                high = x.max(0) if high is None else np.maximum(high, x.max(0))
        if low is not None:
            yield pa.RecordBatch.from_arrays([pa.array(range(width), pa.int32()), pa.array(low, pa.int64()), pa.array(high, pa.int64())], ["d", "low", "high"])

    rows = groups.select("vector").mapInArrow(run, "d int, low long, high long").groupBy("d").agg(F.min("low"), F.max("high")).orderBy("d").collect()
    low, high = [r[1] for r in rows], [r[2] for r in rows]
    return np.array(low, np.int64), np.array([max(1, -(-(h - x + 1) // (1 << bits))) for x, h in zip(low, high)], np.int64)


def dot(a: np.ndarray, b: np.ndarray) -> list[int]:
    """Inner products row by row, exact."""
    if a.size == 0:
        return [0] * len(a)
    if float(np.abs(a).max()) * float(np.abs(b).max()) * a.shape[1] < 2.0**62:
        return (a * b).sum(1).tolist()
    return [sum(x * y for x, y in zip(r.tolist(), s.tolist())) for r, s in zip(a, b)]


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, scale: int = 1024, bits: int = 6, block: int = 1024, query_block: int = 2048) -> DataFrame:
    """For each row of queries(query_id, embedding): its k best (query_id, rank, vec_id, score) of vectors(vec_id, embedding), own id left out.

    block vectors meet query_block queries at once: the memory of a task is in proportion to the product.
    """
    spark = vectors.sparkSession
    every = saved(integers(vectors.select("vec_id", "embedding"), scale), "integers")
    asked = saved(integers(queries.select("query_id", "embedding"), scale).select(F.col("id").alias("query_id"), *_keys(), "vector"), "asked")
    most = every.groupBy("id").count().agg(F.max("count")).first()[0]
    if most is None or asked.isEmpty():
        return spark.createDataFrame([], RESULT)
    keep = k + most
    groups = saved(distinct_vectors(every, keep), "vectors")
    drop(spark, every)
    width = max(df.agg(F.max(F.octet_length("vector"))).first()[0] // 8 for df in (groups, asked))
    low, step = cell_edges(groups, width, bits)

    def cells(batches):
        for b in batches:
            c = ((matrix(b.column(2).to_pylist(), width) - low) // step).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([r.tobytes() for r in c], pa.binary())], ["gid", "gid2", "cells"])

    approx = saved(groups.select("gid", "gid2", "vector").mapInArrow(cells, "gid long, gid2 long, cells binary"), "cells")
    one_each = saved(asked.dropDuplicates(["gid", "gid2"]).select("gid", "gid2", "vector"), "queries")
    blocks = max(1, -(-one_each.count() // query_block))
    out = None
    for i in range(blocks):
        mine = one_each.filter(F.pmod(F.xxhash64(F.lit(2), "vector"), F.lit(blocks)) == i).orderBy("gid", "gid2").collect()  # a block of queries
        if not mine:
            continue
        best = block_top(groups, approx, [r["vector"] for r in mine], width, low, step, keep, block)
        named = spark.createDataFrame([(r["gid"], r["gid2"], n) for n, r in enumerate(mine)], "gid long, gid2 long, q int")
        best = best.join(F.broadcast(named), "q").select("gid", "gid2", "best")
        got = asked.select("query_id", "gid", "gid2").join(F.broadcast(best), ["gid", "gid2"])  # as many rows as a block has queries
        own = F.slice(F.filter("best", lambda x: x["vec_id"] != F.col("query_id")), 1, k)
        got = got.select("query_id", F.posexplode(own).alias("p", "x")).select("query_id", (F.col("p") + 1).cast("int").alias("rank"), "x.vec_id", "x.score")
        got = saved(got, "top")
        out = got if out is None else out.unionByName(got)
    drop(spark, groups, approx, asked, one_each)
    return out


def block_top(groups: DataFrame, approx: DataFrame, queries: list[bytes], width: int, low: np.ndarray, step: np.ndarray, keep: int, block: int) -> DataFrame:
    """(q, best): for each of a block of queries the `keep` best (vec_id, score) in order."""
    spark = groups.sparkSession
    q = matrix(queries, width)
    sent = spark.sparkContext.broadcast((q, low, step))

    def bounds(batches):
        """(keys, lower bounds, upper bounds) of all queries with blocks of the cells."""
        q, low, step = sent.value
        real, low, step = q.astype(np.float64), low.astype(np.float64), step.astype(np.float64)
        above, below = np.maximum(real, 0) @ (step - 1), np.minimum(real, 0) @ (step - 1)
        reach = np.abs(real) @ (np.abs(low) + 64 * step)  # no sum of products is larger
        slack = reach * (width + 16) * 2.0**-50 + 1
        for b in batches:
            for at in range(0, b.num_rows, block):
                part = b.slice(at, block)
                c = np.frombuffer(b"".join(part.column(2).to_pylist()), np.uint8).reshape(part.num_rows, width)
                base = real @ (low + c * step).T
                yield part, base + (below - slack)[:, None], base + (above + slack)[:, None]

    def floors(batches):
        best = np.full((len(queries), keep), -np.inf)
        for _, down, _ in bounds(batches):
            best = np.partition(np.concatenate([best, down], 1), -keep, axis=1)[:, -keep:]
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(0, len(best), 64, dtype=np.int32)), pa.array([best[i : i + 64].tobytes() for i in range(0, len(best), 64)], pa.binary())], ["part", "best"])

    def merge(batches):
        held: dict[int, np.ndarray] = {}
        for b in batches:
            for i, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                x = np.frombuffer(raw, np.float64).reshape(-1, keep)
                held[i] = np.partition(np.concatenate([held[i], x], 1), -keep, axis=1)[:, -keep:] if i in held else x
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([x.min(1).tobytes() for x in held.values()], pa.binary())], ["part", "best"])

    parts = approx.mapInArrow(floors, "part int, best binary").repartition(shuffle_partitions(spark), "part").mapInArrow(merge, "part int, best binary")
    floor = np.full(len(queries), -np.inf)
    for i, raw in parts.collect():  # one number a query of the block
        floor[i : i + 64] = np.frombuffer(raw, np.float64)
    told = spark.sparkContext.broadcast(floor)

    def reaching(batches):
        for part, _, up in bounds(batches):
            i, j = np.nonzero(up >= told.value[:, None])
            yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), part.column(0).take(pa.array(j)), part.column(1).take(pa.array(j)), pa.array(up[i, j])], ["q", "gid", "gid2", "up"])

    per_query = Window.partitionBy("q")
    turn = F.row_number().over(per_query.orderBy(F.desc("up"), "gid", "gid2"))
    kept = saved(approx.mapInArrow(reaching, "q int, gid long, gid2 long, up double").withColumn("turn", turn), "candidates")

    @F.pandas_udf("long")
    def product(i: pd.Series, v: pd.Series) -> pd.Series:
        scores = dot(sent.value[0][i.to_numpy()], matrix(v.tolist(), width))
        if any(not -(1 << 63) <= x < 1 << 63 for x in scores):
            raise OverflowError("a score is beyond 64 bits")
        return pd.Series(scores, dtype="int64")

    read = lambda rows: rows.join(groups, ["gid", "gid2"]).select("q", "ids", product("q", "vector").alias("score"))
    first = saved(read(kept.filter(F.col("turn") <= 2 * keep)), "first")
    nth = F.row_number().over(per_query.orderBy(F.desc("score"), F.col("ids")[0]))
    certain = first.withColumn("n", nth).filter(F.col("n") == keep).select("q", F.col("score").alias("reach"))
    later = kept.filter(F.col("turn") > 2 * keep).join(certain, "q", "left").filter(F.col("reach").isNull() | (F.col("up") >= F.col("reach")))
    scored = first.unionByName(read(later)).withColumn("vec_id", F.explode("ids"))
    scored = scored.withColumn("n", F.row_number().over(per_query.orderBy(F.desc("score"), "vec_id"))).filter(F.col("n") <= keep)
    return scored.groupBy("q").agg(F.transform(F.array_sort(F.collect_list(F.struct("n", "vec_id", "score"))), lambda x: F.struct(x["vec_id"].alias("vec_id"), x["score"].alias("score"))).alias("best"))

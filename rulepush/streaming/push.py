"""Push over streams: positive rules are monotone, so new facts only add derived facts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.compile import positional, rule_df
from ..operators.dedup import SetStore
from ..plans.ir import Program


def stream_push(stream: DataFrame, p: Program, pred: str, static: dict[str, DataFrame]) -> DataFrame:
    """Derived facts of a one-rule program whose literal `pred` reads the stream; the others read stored relations."""
    rel = {k: positional(v) for k, v in static.items()} | {pred: positional(stream)}
    (rule,) = p.of(p.query.pred)
    return rule_df(stream.sparkSession, rule, lambda i, x: rel[x.pred])


class IncrementalClosure:
    """foreachBatch sink that keeps a transitive closure up to date: new pairs meet what is known on either side."""

    def __init__(self):
        self.store = SetStore()

    def __call__(self, edges: DataFrame, batch_id: int = 0) -> None:
        delta, n = self.store.add(edges.toDF("c0", "c1").dropna(), "closure")
        while n:
            known = self.store.known()
            d, k = delta.toDF("a", "b"), known.toDF("x", "y")
            right = d.join(k, F.col("b") == F.col("x")).select(F.col("a").alias("c0"), F.col("y").alias("c1"))
            left = k.join(d, F.col("y") == F.col("a")).select(F.col("x").alias("c0"), F.col("b").alias("c1"))
            delta, n = self.store.add(right.union(left), "closure")

    def result(self) -> DataFrame | None:
        return self.store.known()


def windowed(events: DataFrame, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    src = events.withWatermark("ts", late) if events.isStreaming else events
    return src.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    src = events.withWatermark("ts", late) if events.isStreaming else events
    return src.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")

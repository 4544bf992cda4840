"""Operator 2: mixing sources to target weights with Sainte-Laguë quotas. DataFrame functions only.

Sources get targets in words. Words are dealt in equal blocks; blocks go to sources, and within a source to its
shards, by highest quotients w / (2 s + 1). Each shard lines up its documents in seeded order, cuts the line into
blocks and takes its quota: whole passes, then a seeded cyclic run of blocks. A hot source only has more shards.

Null texts and texts without words have size 0 and nothing is taken from them. A null source is a source of its
own, last in order. Repeated rows are documents of their own. An empty table gives an empty result. Other columns are
ignored, or pass through unchanged.

Sources are few: their totals, a row each, are ranked in one place. Of documents only sizes are lined up, and a shard
holds the sizes of at least a most_shards-th of its source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import saved, table

#: Weights of sources in code point order, repeating (fixed values of the contract).
WEIGHTS = (5, 2, 1)
#: A source gives at most this many times its size.
MOST_PASSES = 3


def word_count(text: Column) -> Column:
    """Number of runs of anything but ASCII white space: starts of words, counted without a list of them."""
    plain = F.translate(F.coalesce(text, F.lit("")), "\t\n\x0b\x0c\r", "     ")
    return F.size(F.filter(F.split(plain, " ", -1), lambda x: x != "")).cast("long")


def targets(sources: DataFrame) -> DataFrame:
    """sources(source, source_size) with target: shares by weight of the sum of all sizes, capped and reshared."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*map(F.lit, WEIGHTS)), ((F.row_number().over(by_name) - 1) % len(WEIGHTS) + 1).cast("int"))
    ratio = F.col("source_size") * float(MOST_PASSES) / F.col("weight")
    everything = Window.partitionBy()
    by_ratio = Window.orderBy("ratio", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    before = lambda c: F.coalesce(F.sum(c).over(by_ratio), F.lit(0))
    level = (F.sum("source_size").over(everything) - MOST_PASSES * before("source_size")) / (F.sum("weight").over(everything) - before("weight"))
    capped = F.col("ratio") <= F.col("level")  # holds for a prefix; the first level past it is the highest there, and the one all others share
    free = F.max(F.when(~F.col("capped"), F.col("level"))).over(everything)
    return (
        sources.withColumn("weight", weight)
        .withColumn("ratio", ratio)
        .withColumn("level", level)
        .withColumn("capped", capped)
        .withColumn("target", F.when(F.col("capped"), F.col("source_size") * float(MOST_PASSES)).otherwise(F.col("weight") * free))
        .select("source", "source_size", "target")
    )


def apportion(parties: DataFrame, group: list[str], weight: str, seats: str, out: str) -> DataFrame:
    """Sainte-Laguë: adds out, the seats of each row; rows of a group share its seats by weight.

    Rounded shares come first; the few seats too many or too few go by quotients near the cut, of which a row needs
    to show only its share of the difference.
    """
    g = Window.partitionBy(*group)
    names = parties.columns
    share = F.when(F.col("_sum") > 0, F.col(weight) / F.col("_sum")).otherwise(F.lit(0.0))
    start = parties.withColumn("_sum", F.sum(weight).over(g)).withColumn("_n", F.count(F.lit(1)).over(g))
    start = start.withColumn("_base", F.when(F.col("_sum") > 0, F.floor(share * F.col(seats) + 0.5)).otherwise(F.lit(0)).cast("long"))
    start = start.withColumn("_off", F.when(F.col("_sum") > 0, F.col(seats) - F.sum("_base").over(g)).otherwise(F.lit(0)).cast("long"))
    many = (F.ceil(share * (F.abs("_off") + F.col("_n"))) + 1).cast("long")
    by_weight = Window.partitionBy(*group).orderBy(F.desc(weight), *[F.col(c).asc_nulls_last() for c in names if c not in group])
    start = start.withColumn("_party", F.row_number().over(by_weight))
    asked = start.withColumn("_j", F.explode(F.when(F.col("_off") == 0, F.array(F.lit(0).cast("long"))).otherwise(F.sequence(F.lit(1).cast("long"), many))))
    seat = F.when(F.col("_off") > 0, F.col("_base") + F.col("_j")).otherwise(F.col("_base") - F.col("_j") + 1)
    asked = asked.withColumn("_seat", seat).withColumn("_quotient", F.col(weight) / (2 * F.col("_seat") - 1))
    up = F.row_number().over(g.orderBy(F.desc("_quotient"), "_party", "_j"))
    down = F.row_number().over(g.orderBy(F.when(F.col("_seat") > 0, F.col("_quotient")).otherwise(F.lit(float("inf"))), F.desc("_party"), "_j"))
    asked = asked.withColumn("_change", F.when((F.col("_off") > 0) & (up <= F.col("_off")), 1).when((F.col("_off") < 0) & (down <= -F.col("_off")), -1).otherwise(0))
    firsts = [F.first(c).alias(c) for c in names if c not in group]
    return asked.groupBy(*group, "_party").agg(*firsts, (F.first("_base") + F.sum("_change")).alias(out)).select(*names, out)


def plan(sizes: DataFrame, seed: int = 7, block_words: int = 64, shard_words: int = 1 << 16, most_shards: int = 4096) -> DataFrame:
    """sizes(source, size, ...) with source_size, target, taken, passes, first_taken.

    taken: words, repeats counted. passes: whole passes over the document; first_taken: whether the remaining
    blocks hold its first word, for callers that copy documents whole.
    """
    per_source = targets(sizes.groupBy("source").agg(F.sum("size").alias("source_size")))
    whole = Window.partitionBy()
    smallest = F.min(F.when(F.col("target") > 0, F.col("target"))).over(whole)
    per_source = (
        per_source.withColumn("block", F.greatest(F.lit(1), F.least(F.lit(block_words), F.floor(F.coalesce(smallest, F.lit(1.0)) / 100))).cast("long"))
        .withColumn("shards", F.greatest(F.lit(1), F.least(F.lit(most_shards), F.ceil(F.col("source_size") / shard_words))).cast("long"))
        .withColumn("all_blocks", F.round(F.sum("target").over(whole) / F.col("block")).cast("long"))
    )
    per_source = apportion(per_source, [], "target", "all_blocks", "quota")
    source_key = F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("n"))
    base = per_source.select(source_key.alias("_source"), "source_size", "target", "block", "shards", "quota")
    mine = sizes.withColumn("_source", source_key).join(base, "_source")
    mine = mine.withColumn("_order", F.xxhash64(F.lit(seed), "_source", "doc_id", "size")).withColumn("_shard", F.pmod(F.xxhash64(F.lit(seed + 1), "_order"), F.col("shards")))
    mine = mine.repartition("_source", "_shard")  # the join before left a source in one place
    per_shard = mine.groupBy("_source", "_shard").agg(F.sum("size").alias("shard_size"), F.first("quota").alias("quota"), F.first("block").alias("block"))
    per_shard = apportion(per_shard, ["_source"], "shard_size", "quota", "shard_quota")
    blocks = F.ceil(F.col("shard_size") / F.col("block")).cast("long")
    per_shard = per_shard.withColumn("blocks", F.greatest(blocks, F.lit(1))).withColumn("shard_quota", F.least(F.col("shard_quota"), MOST_PASSES * F.col("blocks")))
    per_shard = per_shard.select(
        "_source", "_shard", "shard_size", (F.floor(F.col("shard_quota") / F.col("blocks"))).alias("passes"),
        (F.pmod(F.xxhash64(F.lit(seed + 2), "_source", "_shard"), F.col("blocks")) * F.col("block")).alias("_from"),
        ((F.col("shard_quota") % F.col("blocks")) * F.col("block")).alias("_run"),
        (F.col("blocks") * F.col("block")).alias("_round"),
    )
    line = Window.partitionBy("_source", "_shard").orderBy("_order", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = mine.withColumn("_start", F.coalesce(F.sum("size").over(line), F.lit(0))).join(per_shard, ["_source", "_shard"])
    start, end, lo, hi = F.col("_start"), F.col("_start") + F.col("size"), F.col("_from"), F.col("_from") + F.col("_run")
    overlap = lambda a, b: F.greatest(F.lit(0), F.least(end, b) - F.greatest(start, a))
    wrapped = hi - F.col("_round")
    taken = F.col("passes") * F.col("size") + overlap(lo, hi) + overlap(F.lit(0), wrapped)
    first = (F.col("size") > 0) & (((start >= lo) & (start < hi)) | (start < wrapped))
    drop = ["_source", "_shard", "_order", "_start", "_from", "_run", "_round", "block", "shards", "quota", "shard_size"]
    return placed.withColumn("taken", taken.cast("long")).withColumn("first_taken", first).drop(*drop)


def mix(docs: DataFrame, **options) -> DataFrame:
    """Operator 2's query: (doc_id, size, source_size, target, taken)."""
    sizes = saved(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")), "sizes")
    return plan(sizes, **options).select("doc_id", "size", "source_size", "target", "taken")


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The documents of the mix, whole: each as often as whole passes and its first word are taken; same columns.

    Rows are told apart by doc_id, source and size: rows that share all three share a decision, the larger one.
    """
    size = word_count(F.col("text"))
    got = plan(saved(docs.select("doc_id", "source", size.alias("size")), "sizes"), **options)
    copies = F.col("passes") + F.col("first_taken").cast("long")
    got = got.groupBy("doc_id", "source", "size").agg(F.max(F.when(F.col("size") > 0, copies).otherwise(0)).alias("copies")).filter("copies > 0").toDF("i", "s", "n", "copies")
    rows = docs.select(F.struct("*").alias("d"), size.alias("size"))
    kept = rows.join(got, F.col("d.doc_id").eqNullSafe(F.col("i")) & F.col("d.source").eqNullSafe(F.col("s")) & (F.col("size") == F.col("n")))
    return kept.select("d", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select("d.*")


def query(spark, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents"))

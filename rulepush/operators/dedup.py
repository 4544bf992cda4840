"""Stores of known facts: they tell new facts from known ones.

hash: rows, by duplicate removal and an anti join; the number of parts is left to the engine ("auto"), fixed (a number),
or doubled whenever parts are full ("doubling"). words: pairs over a small dense domain as 64-bit words of bits, kept
as words, so that a round moves words and not rows. nested: per first argument, and range of hashes of the second, the
set of its second ones, kept as sets.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import discard, spill


def to_words(df: DataFrame) -> DataFrame:
    """(c0, word, bits) of pairs (c0, c1) of whole numbers."""
    one = F.expr("shiftleft(1L, cast(pmod(c1, 64) AS int))")
    return df.groupBy("c0", F.floor(F.col("c1") / 64).alias("word")).agg(F.bit_or(one).alias("bits"))


def from_words(df: DataFrame) -> DataFrame:
    bit = F.explode(F.filter(F.sequence(F.lit(0), F.lit(63)), lambda i: F.getbit(F.col("bits"), i) == 1))
    return df.select("c0", "word", bit.alias("bit")).select("c0", (F.col("word") * 64 + F.col("bit")).cast("long").alias("c1"))


def compose_words(left: DataFrame, right: DataFrame) -> DataFrame:
    """(c0, word, bits) of the composition of pairs left(c0, c1) with words right(c0, word, bits): one `or` a word, no row a pair."""
    rows = right.select(F.col("c0").alias("c1"), "word", "bits")
    return left.join(rows, "c1").groupBy("c0", "word").agg(F.bit_or("bits").alias("bits"))


def _union(dfs: list[DataFrame]) -> DataFrame | None:
    out = None
    for df in dfs:
        out = df if out is None else out.unionByName(df)
    return out


class SetStore:
    def __init__(self, kind: str = "hash", partitions: int | str = "auto", full: int = 1_000_000):
        if kind not in ("hash", "words", "nested"):
            raise ValueError(kind)
        self.kind, self.partitions, self.full = kind, partitions, full
        self.parts = partitions if isinstance(partitions, int) else 1
        self.rows = 0
        self.held: list[DataFrame] = []  # as stored: rows, words or sets
        self.slices: list[DataFrame] = []  # the same as rows
        self.old: list[DataFrame] = []

    def known(self) -> DataFrame | None:
        return _union(self.slices)

    def _pairs(self, df: DataFrame) -> bool:
        return df.columns == ["c0", "c1"] and (self.kind == "nested" or self.kind == "words" and df.dtypes[1][1] in ("int", "bigint", "smallint", "tinyint"))

    def _dealt(self, df: DataFrame) -> DataFrame:
        return df if self.partitions == "auto" or not df.columns else df.repartition(self.parts, *df.columns)

    def _fresh(self, delta: DataFrame) -> DataFrame:
        """What delta adds, in the form it is stored."""
        if self._pairs(delta) and self.kind == "words":
            fresh = to_words(delta)
            if self.held:
                none = F.lit(0).cast("long").alias("old")
                both = fresh.select("c0", "word", "bits", none).unionByName(_union(self.held).select("c0", "word", F.lit(0).cast("long").alias("bits"), F.col("bits").alias("old")))
                fresh = both.groupBy("c0", "word").agg(F.bit_or("bits").alias("bits"), F.bit_or("old").alias("old"))
                fresh = fresh.withColumn("bits", F.col("bits").bitwiseAND(F.bitwise_not("old"))).filter("bits <> 0")
            return fresh.select("c0", "word", "bits")
        if self._pairs(delta):
            range_ = F.shiftright(F.xxhash64("c1"), 52).alias("range")
            fresh = delta.groupBy("c0", range_).agg(F.collect_set("c1").alias("s"))
            if self.held:
                known = _union(self.held).groupBy("c0", "range").agg(F.flatten(F.collect_list("s")).alias("o"))
                fresh = fresh.join(known, ["c0", "range"], "left").withColumn("s", F.when(F.col("o").isNull(), F.col("s")).otherwise(F.array_except("s", "o")))
            return fresh.filter(F.size("s") > 0).select("c0", "range", "s")
        fresh = self._dealt(delta).dropDuplicates()
        known = self.known()
        return fresh.join(known, delta.columns, "left_anti") if known is not None else fresh

    def distinct(self, df: DataFrame) -> DataFrame:
        """df without duplicates, by way of this kind of set; nothing is stored."""
        return self._as_rows(self._fresh(df))

    def _as_rows(self, held: DataFrame) -> DataFrame:
        if "bits" in held.columns:
            return from_words(held)
        return held.select("c0", F.explode("s").alias("c1")) if "range" in held.columns else held

    def _size(self, held: DataFrame) -> int:
        n = F.sum(F.bit_count("bits")) if "bits" in held.columns else F.sum(F.size("s")) if "range" in held.columns else F.count(F.lit(1))
        return held.agg(n).first()[0] or 0

    def add(self, delta: DataFrame, name: str = "delta") -> tuple[DataFrame, int]:
        """New facts of delta, stored, and how many. Slices of earlier rounds merge when they pile up."""
        held = spill(self._fresh(delta), name)
        n = self._size(held)
        rows = self._as_rows(held)
        rows._stored = held
        if not n:
            discard(held)
            return rows, 0
        self.rows += n
        self.held.append(held)
        self.slices.append(rows)
        full = self.partitions == "doubling" and self.rows > self.full * self.parts
        while self.partitions == "doubling" and self.rows > self.full * self.parts:
            self.parts *= 2
        if len(self.held) > 8 or full:
            merged = _union(self.held)
            if "bits" in merged.columns:
                merged = merged.groupBy("c0", "word").agg(F.bit_or("bits").alias("bits"))
            elif "range" not in merged.columns:
                merged = self._dealt(merged)
            self.old += self.held
            self.held = [spill(merged, name)]
            self.slices = [self._as_rows(self.held[0])]
        return rows, n

    def sweep(self, *in_use: DataFrame) -> None:
        """Deletes merged slices, but for those whose rows are still in use; call when a round's plans have run."""
        keep = {id(getattr(x, "_stored", x)) for x in in_use}
        gone = [x for x in self.old if id(x) not in keep]
        self.old = [x for x in self.old if id(x) in keep]
        discard(*gone)


__all__ = ["SetStore", "compose_words", "from_words", "to_words"]

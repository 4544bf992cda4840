"""Operator 8: near-duplicate documents by consistent weighted sampling over TF-IDF shingles.

Shingles are runs of five words, lower case. A shingle weighs tf * idf in whole 64ths, with
idf = 1 + ln(N / df) / (2 ln(1 / FLOOR)), df no less than FLOOR * N: rare shingles weigh 1.5, ubiquitous ones 1, so
that the common text of a very large group of copies still outweighs its small differences. df comes from a
count sketch over all documents: its size is fixed, and its error is a fixed share of N at any scale, below FLOOR.

Improved consistent weighted sampling draws, for each of bands * rows hashes, the shingle and level of least
ln a; equal draws happen with the probability of weighted Jaccard similarity. Draws are banded. A bucket's pivot is
its least document. Every document is compared with its least pivot, exactly; then with the pivots that are still in
another component; then members of one pivot, in different components, that the pivot does not rule out, by the
triangle inequality (1 - weighted Jaccard is a metric) or by the weights they share with it. So no pair of different
components that shares a bucket and may reach the threshold stays unverified, and no bucket is expanded into all pairs
of its copies. Components of verified links are the classes.

Null and empty texts, and texts without words, have no shingle: each such document is a class of its own. Texts of
fewer than five words are one shingle. Rows that repeat a doc_id are one document, of their texts' least digest's class.
Null doc_ids take no part and come back with a null class. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import pyarrow as pa

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop, release_memory, saved, shuffle_partitions, small_batches, table
from .tokenization import row_slices

UNIT = 64  # weights are whole multiples of 1 / UNIT
FLOOR = 1e-3
SKETCH_ROWS, SKETCH_BITS, CHUNK_BITS = 2, 20, 14
_MIX = np.uint64(0x9E3779B97F4A7C15)
_U = np.uint64
#: Odd multipliers of no meaning, one for each place in a shingle.
_ODD = [1]
while len(_ODD) < 16:
    _ODD.append(_ODD[-1] * 0x9E3779B97F4A7C15 % (1 << 64))
#: ASCII as str.lower and str.split take it: small letters, and a blank for each white space.
_PLAIN = bytes(32 if chr(c).isspace() and c < 128 else ord(chr(c).lower()) if c < 128 else c for c in range(256))
#: The first bytes of eight.
_FIRST = np.array([(1 << 8 * i) - 1 for i in range(9)], np.uint64)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit numbers."""
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(32))


def word_codes(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(codes of the words of t.lower().split(), number of words), text by text.

    Eight bytes of all words at a time: words of a length up to eight have different codes.
    """
    parts = [b"" if not t else t.encode() if t.isascii() else " ".join(t.lower().split()).encode("utf-8", "replace") for t in texts]
    whole = np.frombuffer((b" ".join([*parts, bytes(8)])).translate(_PLAIN), np.uint8)
    begins = np.cumsum([0] + [len(x) + 1 for x in parts])
    edge = np.empty(begins[-1] + 1, bool)
    edge[0] = False
    np.not_equal(whole[: begins[-1]], 32, out=edge[1:])  # the blank after the last text ends its last word
    starts, ends = np.nonzero(edge[1:] > edge[:-1])[0], np.nonzero(edge[1:] < edge[:-1])[0]
    size = ends - starts
    eight = np.ndarray(len(whole) - 7, "<u8", whole, strides=(1,))
    codes = mix64((eight[starts] & _FIRST[np.minimum(size, 8)]) ^ size.astype(_U) * _MIX)
    more, at = np.nonzero(size > 8)[0], 8
    while len(more):
        codes[more] = mix64(codes[more] * _MIX ^ eight[starts[more] + at] & _FIRST[np.minimum(size[more] - at, 8)])
        at += 8
        more = more[size[more] > at]
    return codes, np.diff(np.searchsorted(starts, begins))


def shingled(texts: list[str | None], width: int = 5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct shingle hashes, how often each occurs, number of them by text): text by text, ascending in each."""
    codes, n = word_codes(texts)
    sizes = n - np.minimum(n, width) + (n > 0)  # shingles, repeated ones too
    first, ends = np.cumsum(n) - n, np.cumsum(sizes)
    h = np.zeros(len(codes), _U)
    m = max(len(codes) - width + 1, 0)
    part = np.empty(m, _U)
    h[:m] = codes[:m] + _U(width)
    for i in range(1, width):
        h[:m] += np.multiply(codes[i : i + m], _U(_ODD[i]), out=part)
    for at, k in ((first[i], int(n[i])) for i in np.nonzero((n > 0) & (n < width))[0]):
        h[at] = (codes[at : at + k] * np.array(_ODD[:k], _U)).sum(dtype=_U) + _U(k)
    # those that would reach into the next text go
    h = mix64(h[np.arange(len(codes)) < np.repeat(first + sizes, n)])
    for start, end in zip((ends - sizes).tolist(), ends.tolist()):
        h[start:end].sort()
    new = np.ones(len(h), bool)
    np.not_equal(h[1:], h[:-1], out=new[1:])
    new[(ends - sizes)[sizes > 0]] = True
    at = np.nonzero(new)[0]
    return h[at], np.diff(np.append(at, len(h))), np.diff(np.searchsorted(at, np.append(0, ends)))


def _cells(h: np.ndarray) -> list[np.ndarray]:
    return [((h * np.uint64(m)) >> np.uint64(64 - SKETCH_BITS)).astype(np.int64) for m in (0xD6E8FEB86659FD93, 0xA0761D6478BD642F)[:SKETCH_ROWS]]


def frequency_sketch(docs: DataFrame, width: int = 5) -> tuple[np.ndarray, int]:
    """(counts of documents by cell, number of documents): fixed size; chunks of the tasks' counts are summed in shuffle tasks."""
    size, chunk = 1 << SKETCH_BITS, 1 << CHUNK_BITS

    def count(batches):
        held = np.zeros((SKETCH_ROWS, size), np.uint32)
        n, wait, waiting = 0, [], 0

        def flush():
            if wait:
                for row, cells in zip(held, _cells(np.concatenate(wait))):
                    row += np.bincount(cells, minlength=size).astype(np.uint32)
                wait.clear()

        for b in batches:
            for at, m in row_slices(b.column(0)):
                h, _, _ = shingled(b.column(0).slice(at, m).to_pylist(), width)
                n += m
                wait.append(h)
                waiting += len(h)
                if waiting > 1 << 20:
                    flush()
                    waiting = 0
        flush()
        release_memory()
        flat = held.reshape(-1, chunk)
        ids = [i for i in range(len(flat)) if flat[i].any()]
        yield pa.RecordBatch.from_arrays([pa.array([*ids, -1], pa.int32()), pa.array([*(_packed(flat[i]) for i in ids), np.array([n], "<i8").tobytes()], pa.binary())], ["chunk", "counts"])

    def add(batches):
        held: dict[int, np.ndarray] = {}
        for b in batches:
            for i, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                x = np.frombuffer(raw, "<i8") if i < 0 else _unpacked(raw, chunk)
                held[i] = x + held[i] if i in held else x
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([v.astype("<i8").tobytes() for v in held.values()], pa.binary())], ["chunk", "counts"])

    schema = "chunk int, counts binary"
    parts = docs.select("text").mapInArrow(count, schema).repartition(max(16, shuffle_partitions(docs.sparkSession)), "chunk").mapInArrow(add, schema)
    out, n = np.zeros((SKETCH_ROWS * size // chunk, chunk), np.int64), 0
    for i, raw in parts.collect():
        x = np.frombuffer(raw, "<i8")
        if i < 0:
            n = int(x[0])
        else:
            out[i] = x
    return out.reshape(SKETCH_ROWS, size), n


def _packed(x: np.ndarray) -> bytes:
    """Non-zero cells and their counts when that is shorter."""
    at = np.nonzero(x)[0].astype("<u4")
    if 8 * len(at) < 4 * len(x):
        return b"\1" + at.tobytes() + x[at].astype("<u4").tobytes()
    return b"\0" + x.astype("<u4").tobytes()


def _unpacked(raw: bytes, n: int) -> np.ndarray:
    x = np.frombuffer(raw, "<u4", offset=1).astype(np.int64) if raw[0] == 0 else None
    if x is None:
        pairs = np.frombuffer(raw[1:], "<u4").reshape(2, -1)
        x = np.zeros(n, np.int64)
        x[pairs[0]] = pairs[1]
    return x


def idf_levels(sketch: np.ndarray, n: int) -> np.ndarray:
    """idf of each cell in whole UNITs, one byte a cell."""
    share = np.maximum(sketch / max(n, 1), FLOOR)
    return np.round(UNIT * (1 + np.log(1 / np.minimum(share, 1)) / (2 * np.log(1 / FLOOR)))).astype(np.uint8)


def weights(h: np.ndarray, tf: np.ndarray, idf: np.ndarray) -> np.ndarray:
    """Whole weights; of a shingle's cells the rarest counts."""
    level = idf[0][_cells(h)[0]]
    for row, cells in zip(idf[1:], _cells(h)[1:]):
        level = np.maximum(level, row[cells])
    return tf * level.astype(np.int64)


#: The weight of a rare shingle that occurs once: most shingles have it.
USUAL = round(UNIT * 1.5)


class Sampler:
    """Consistent weighted samples of many documents at once.

    For a hash, a shingle's r, c and beta come from a table by the top bits of its scrambled product. Among shingles of
    the usual weight ln a depends on the table entry alone, so their least is found by the entries' ranks, ties by
    the rest of the product; the others are computed in full. Products are taken back to shingles by the inverse factor.
    """

    BITS = 12
    #: Shingles of the usual weight at a time: what a hash does to them stays in the cache.
    BLOCK = 1 << 16

    def __init__(self, hashes: int, seed: int = 7):
        rng = np.random.default_rng(seed)
        n = 1 << self.BITS
        self.multiply = rng.integers(1, 1 << 63, hashes, dtype=_U) * _U(2) + _U(1)
        self.r = rng.gamma(2, 1, (hashes, n)).astype(np.float32)
        self.log_c = np.log(rng.gamma(2, 1, (hashes, n))).astype(np.float32)
        self.beta = rng.random((hashes, n), dtype=np.float32)
        self.divide = np.array([pow(int(m), -1, 1 << 64) for m in self.multiply], _U)
        every = np.arange(n)
        self.by_rank = np.empty((hashes, n), np.int64)  # entries, least ln a first
        self.swap = np.empty((hashes, n), _U)  # turns the entry above a product into its rank
        for k in range(hashes):
            self.by_rank[k] = np.argsort(self._ln_a(k, every, np.float32(np.log(USUAL / UNIT)))[0], kind="stable")
            self.swap[k, self.by_rank[k]] = (every ^ self.by_rank[k]).astype(_U) << _U(64 - self.BITS)

    def _ln_a(self, k, at, log_w):
        at = (k << self.BITS) + at
        r, beta = self.r.take(at), self.beta.take(at)
        t = np.floor(log_w / r + beta)
        return self.log_c.take(at) - r * (t - beta) - r, t

    def _usual(self, mixed: np.ndarray, heads: np.ndarray):
        """(ln a, scrambled shingle, level), each by (hash, document), of the least shingle of the usual weight."""
        hashes, low = len(self.multiply), _U(64 - self.BITS)
        least = np.empty((hashes, len(heads)), _U)
        ends = np.append(heads[1:], len(mixed))
        first = 0
        while first < len(heads):
            last = max(first + 1, int(np.searchsorted(ends, heads[first] + self.BLOCK, "right")))
            block, at = mixed[heads[first] : ends[last - 1]], heads[first:last] - heads[first]
            x, entry, swap = np.empty(len(block), _U), np.empty(len(block), _U), np.empty(len(block), _U)
            index = entry.view(np.int64)
            for k, m in enumerate(self.multiply):
                np.multiply(block, m, out=x)
                np.right_shift(x, low, out=entry)
                self.swap[k].take(index, out=swap, mode="clip")
                np.bitwise_xor(x, swap, out=x)
                np.minimum.reduceat(x, at, out=least[k, first:last])
            first = last
        k = np.arange(hashes)[:, None]
        entry = self.by_rank[k, (least >> low).astype(np.int64)]
        ln_a, level = self._ln_a(k, entry, np.float32(np.log(USUAL / UNIT)))
        return ln_a, (least ^ self.swap[k, entry]) * self.divide[:, None], level

    def sample(self, h: np.ndarray, w: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """(documents, hashes): numbers that two documents share with the probability of their similarity.

        starts: where each document's shingles begin in h and w, all non-empty.
        """
        docs, mixed = len(starts), mix64(h)
        owner = np.repeat(np.arange(docs), np.diff(np.append(starts, len(h))))
        usual, odd = np.nonzero(w == USUAL)[0], np.nonzero(w != USUAL)[0]
        heads = lambda at: np.nonzero(np.concatenate([[True], owner[at][1:] != owner[at][:-1]]))[0] if len(at) else at
        u_heads, o_heads = heads(usual), heads(odd)
        best = np.full((len(self.multiply), docs), np.inf, np.float32)
        pick = np.zeros(best.shape, _U)
        level = np.zeros(best.shape, np.float32)
        if len(usual):
            u_docs = owner[usual][u_heads]
            best[:, u_docs], pick[:, u_docs], level[:, u_docs] = self._usual(mixed[usual], u_heads)
        if len(odd):
            o_docs, o_mixed, o_log = owner[odd][o_heads], mixed[odd], np.log(w[odd] / UNIT).astype(np.float32)
            o_owner = np.repeat(np.arange(len(o_docs)), np.diff(np.append(o_heads, len(odd))))
            step = max(1, self.BLOCK // len(odd))
            for k in range(0, len(self.multiply), step):
                ks = np.arange(k, min(k + step, len(self.multiply)))[:, None]
                z = o_mixed * self.multiply[ks]
                ln_a, t = self._ln_a(ks, (z >> _U(64 - self.BITS)).view(np.int64), o_log)
                row, hit = np.nonzero(ln_a == np.minimum.reduceat(ln_a, o_heads, axis=1).take(o_owner, axis=1))
                tied = np.nonzero(np.concatenate([[True], (row[1:] != row[:-1]) | (o_owner[hit[1:]] != o_owner[hit[:-1]])]))[0]
                least, row, hit = np.minimum.reduceat(z[row, hit], tied), row[tied], hit[tied]
                at = k + row, o_docs[o_owner[hit]]
                better = ln_a[row, hit] < best[at]
                at = at[0][better], at[1][better]
                pick[at], level[at] = (least * self.divide[k + row])[better], t[row, hit][better]
        return mix64(pick + _MIX * level.astype(np.int64).view(_U)).T


def shared_weight(ha, wa, hb, wb) -> int:
    """What two sparse whole-weight vectors with ascending hashes have in common."""
    if not len(ha) or not len(hb):
        return 0
    at = np.minimum(np.searchsorted(hb, ha), len(hb) - 1)
    both = hb[at] == ha
    return int(np.minimum(wa[both], wb[at[both]]).sum())


def similarity(ha, wa, hb, wb) -> float:
    """Weighted Jaccard of two such vectors."""
    if not len(ha) or not len(hb):
        return float(len(ha) == len(hb))
    low = shared_weight(ha, wa, hb, wb)
    return low / (int(wa.sum() + wb.sum()) - low)


def profiles(docs: DataFrame, idf: np.ndarray, bands: int, rows: int, width: int) -> DataFrame:
    """(doc_id, profile, total, bands, hashes, weights) of documents with words.

    profile: digest of the weighted shingles; total: sum of their weights.
    """
    held = docs.sparkSession.sparkContext.broadcast(idf)
    samplers: dict = {}

    def run(batches):
        levels = held.value
        sampler = samplers.setdefault("s", Sampler(bands * rows))
        seen: dict[bytes, list[int]] = {}
        for b in batches:
            for at, n in row_slices(b.column(1), 2 << 20):
                ids, texts = (b.column(c).slice(at, n).to_pylist() for c in range(2))
                h, tf, sizes = shingled([None if i is None else t for i, t in zip(ids, texts)], width)
                if not len(h):
                    continue
                held_ids, sizes = [i for i, m in zip(ids, sizes.tolist()) if m], sizes[sizes > 0]
                starts = np.cumsum(sizes) - sizes
                w = weights(h, tf, levels)
                totals, wide = np.add.reduceat(w, starts).tolist(), (np.maximum.reduceat(w, starts) >= 1 << 16).tolist()
                full, high, long, short = (memoryview(x.tobytes()) for x in (h.astype("<u8"), (h >> _U(32)).astype("<u4"), w.astype("<u4"), w.astype("<u2")))
                out, fresh = [], {}
                for j, (i, s, m) in enumerate(zip(held_ids, starts.tolist(), sizes.tolist())):
                    e = s + m
                    digest = hashlib.blake2b(full[8 * s : 8 * e], digest_size=16)
                    digest.update(long[4 * s : 4 * e])
                    digest = digest.digest()
                    if digest not in seen:
                        fresh.setdefault(digest, j)
                    out.append([i, digest, None, totals[j], bytes(high[4 * s : 4 * e]), bytes(long[4 * s : 4 * e] if wide[j] else short[2 * s : 2 * e])])
                if fresh:
                    drawn_of = np.zeros(len(sizes), bool)
                    drawn_of[list(fresh.values())] = True
                    use, own = np.repeat(drawn_of, sizes), sizes[drawn_of]
                    drawn = sampler.sample(h[use], w[use], np.cumsum(own) - own).reshape(len(fresh), bands, rows)
                    key = np.zeros((len(fresh), bands), _U)
                    for j in range(rows):
                        key = mix64(key * _MIX + drawn[:, :, j])
                    fresh = dict(zip(fresh, key.view(np.int64).tolist()))
                for o in out:
                    o[2] = fresh[o[1]] if o[1] in fresh else seen[o[1]]
                if len(seen) > 5_000:
                    seen.clear()
                seen |= fresh
                yield pa.RecordBatch.from_arrays(
                    [pa.array([o[0] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.binary()), pa.array([o[3] for o in out], pa.int64()), pa.array([o[2] for o in out], pa.list_(pa.int64())), pa.array([o[4] for o in out], pa.binary()), pa.array([o[5] for o in out], pa.binary())],
                    ["doc_id", "profile", "total", "bands", "hashes", "weights"],
                )
        release_memory()

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, profile binary, total long, bands array<long>, hashes binary, weights binary")


def unpack(hashes: bytes, packed: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Shingles by 32 of their bits, ascending, and their weights.

    A false match of two documents of n shingles moves their similarity by 1 / n, with a chance of n * n / 2**32: by
    n / 2**32 on average, under a ten-thousandth for 400,000 shingles.
    """
    n = len(hashes) // 4
    return np.frombuffer(hashes, "<u4"), np.frombuffer(packed, "<u2" if len(packed) == 2 * n else "<u4").astype(np.int64)


def verified(pairs: DataFrame, vectors: DataFrame) -> DataFrame:
    """pairs(a, b) with their similarity, and the weight they share."""

    @F.pandas_udf("long")
    def common(ha: pd.Series, wa: pd.Series, hb: pd.Series, wb: pd.Series) -> pd.Series:
        return pd.Series([shared_weight(*unpack(a, x), *unpack(b, y)) for a, x, b, y in zip(ha, wa, hb, wb)], dtype="int64")

    side = lambda x: vectors.select(F.col("doc_id").alias(x), F.col("hashes").alias(f"h{x}"), F.col("weights").alias(f"w{x}"), F.col("total").alias(f"t{x}"))
    both = pairs.join(side("b"), "b").join(side("a"), "a")
    both = both.select("a", "b", "ta", "tb", common("ha", "wa", "hb", "wb").alias("common"))
    return both.withColumn("similarity", F.col("common") / (F.col("ta") + F.col("tb") - F.col("common")))


def components(links: DataFrame) -> DataFrame:
    """(id, root): least id of each node's component, by alternating large-star and small-star steps.

    Every step is one grouped minimum and a join on the larger side's key; edges never exceed the links. A chain of n
    links takes about log n steps.
    """
    spark = links.sparkSession
    edges = saved(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct(), "edges")
    last = None
    while True:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.filter("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v")
        old, edges = edges, saved(small.filter("u <> v").distinct(), "edges")
        drop(spark, old)
        state = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == last:
            return edges.select(F.col("u").alias("id"), F.col("v").alias("root"))
        last = state


def rooted(rows: DataFrame, root: DataFrame, col: str) -> DataFrame:
    """rows with the component of col's document as root_<col>; a document without links is its own."""
    return rows.join(root.select(F.col("id").alias(col), F.col("root").alias("_r")), col, "left").withColumn(f"root_{col}", F.coalesce("_r", col)).drop("_r")


def representatives(every: DataFrame) -> tuple[DataFrame, DataFrame]:
    """((doc_id, rep) of all documents, (doc_id, profile) of the least document of each profile).

    A document that occurs with several texts counts by its least profile. A profile is met in as many lanes as its
    documents fall into, so that copies by the million are no one task's.
    """
    lanes = max(16, shuffle_partitions(every.sparkSession))
    lane = F.pmod(F.xxhash64("doc_id"), F.lit(lanes)).alias("lane")
    ids = every.groupBy("doc_id").agg(F.min("profile").alias("profile"))
    least = ids.groupBy("profile", lane).agg(F.min("doc_id").alias("least"))
    reps = saved(least.groupBy("profile").agg(F.min("least").alias("rep"), F.collect_list("lane").alias("lanes")), "representatives")
    dealt = reps.select("profile", "rep", F.explode("lanes").alias("lane"))
    return ids.withColumn("lane", lane).join(dealt, ["profile", "lane"]).select("doc_id", "rep"), reps.select(F.col("rep").alias("doc_id"), "profile")


def classes(docs: DataFrame, threshold: float = 0.8, bands: int = 32, rows: int = 8, width: int = 5) -> DataFrame:
    """(doc_id, class_id): class_id is the least doc_id of the documents linked, directly or not, by similarity >= threshold."""
    small_batches(docs.sparkSession)
    sketch, n = frequency_sketch(docs, width)
    every = saved(profiles(docs, idf_levels(sketch, n), bands, rows, width), "profiles")
    rep_of, reps = representatives(every)
    buckets = every.select("doc_id", "profile", "bands").join(reps, ["doc_id", "profile"], "left_semi").dropDuplicates(["doc_id"])
    buckets = buckets.select("doc_id", F.posexplode("bands").alias("band", "key")).select("doc_id", F.xxhash64("band", "key").alias("bucket"))
    pivots = buckets.groupBy("bucket").agg(F.min("doc_id").alias("pivot"), F.count(F.lit(1)).alias("n")).filter("n > 1").select("bucket", "pivot")
    star = saved(buckets.join(pivots, "bucket").filter("doc_id <> pivot").select("pivot", "doc_id").distinct(), "star")
    used = star.select("doc_id").union(star.select(F.col("pivot").alias("doc_id"))).distinct()
    vectors = every.select("doc_id", "profile", "total", "hashes", "weights").join(reps.join(used, "doc_id"), ["doc_id", "profile"], "left_semi").dropDuplicates(["doc_id"]).drop("profile")
    vectors = saved(vectors, "vectors")
    # each document meets its least pivot; of the other pairs only those still in different components
    nearest = star.groupBy("doc_id").agg(F.min("pivot").alias("pivot"))
    known = saved(verified(nearest.select(F.col("pivot").alias("a"), F.col("doc_id").alias("b")), vectors), "verified")
    links = known.filter(F.col("similarity") >= threshold).select("a", "b")
    root = components(links)
    apart = rooted(rooted(star.join(nearest, ["doc_id", "pivot"], "left_anti"), root, "doc_id"), root, "pivot").filter("root_doc_id <> root_pivot")
    more = saved(verified(apart.select(F.col("pivot").alias("a"), F.col("doc_id").alias("b")), vectors), "verified")
    found = more.filter(F.col("similarity") >= threshold).select("a", "b")
    if not found.isEmpty():
        links = links.union(found)
        root = components(links)
    last = saved(open_links(star, known.union(more), root, vectors, threshold), "links")
    if not last.isEmpty():
        root = components(links.union(last))
    named = rep_of.join(root.withColumnRenamed("id", "rep"), "rep", "left").select(F.col("doc_id").alias("_id"), F.coalesce("root", "rep").alias("class_id"))
    named = saved(named, "classes")
    drop(docs.sparkSession, every, reps, star, vectors, known, more)
    return docs.select("doc_id").join(named, F.col("doc_id") == F.col("_id"), "left").select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"))


def open_links(star: DataFrame, known: DataFrame, root: DataFrame, vectors: DataFrame, threshold: float, block_bytes: int = 1 << 20) -> DataFrame:
    """Links (a, b) between documents that met the same pivot, are in different components, and are not ruled out by it.

    Only pivots with an outlier, a member of another component than theirs, take part; all outliers were compared with
    the pivot. The outliers meet the other outliers and those members of the pivot's component that are far enough
    from it to be near one of them: 1 - similarity is a metric. Members travel once, in blocks of block_bytes; blocks
    of outliers go to all blocks of their pivot.
    """
    spark = star.sparkSession
    members = rooted(rooted(star, root, "doc_id"), root, "pivot").withColumn("out", F.col("root_doc_id") != F.col("root_pivot"))
    met = known.select(F.col("a").alias("pivot"), F.col("b").alias("doc_id"), "similarity", "common", F.col("tb").alias("total"))
    out = saved(members.filter("out").join(met, ["pivot", "doc_id"]).select("pivot", "doc_id", "root_doc_id", "similarity", "common", "total"), "outliers")
    if out.isEmpty():
        return spark.createDataFrame([], "a long, b long")
    reach = out.groupBy("pivot").agg(F.max("similarity").alias("nearest"))
    inside = members.filter("NOT out").select("pivot", "doc_id", "root_doc_id").join(reach, "pivot")
    told = inside.join(met, ["pivot", "doc_id"], "left")
    # saved: a filter on the similarity would else be taken below and compare everything once more, in workers of its own
    fresh = saved(verified(told.filter("similarity IS NULL").select(F.col("pivot").alias("a"), F.col("doc_id").alias("b")), vectors), "verified")
    fresh = fresh.select(F.col("a").alias("pivot"), F.col("b").alias("doc_id"), "similarity", "common", F.col("tb").alias("total"))
    inside = told.filter("similarity IS NOT NULL").drop("nearest").unionByName(inside.join(fresh, ["pivot", "doc_id"]).drop("nearest"))
    inside = inside.join(reach, "pivot").filter(F.col("similarity") <= F.col("nearest") + (1 - threshold) + 1e-9).drop("nearest")
    both = out.withColumn("out", F.lit(True)).unionByName(inside.withColumn("out", F.lit(False)))
    full = saved(both.join(vectors.select("doc_id", "hashes", "weights"), "doc_id"), "open")
    size = F.sum(F.octet_length("hashes") + F.octet_length("weights"))
    lanes = full.groupBy("pivot").agg(F.ceil(size / block_bytes).alias("lanes"), F.ceil(F.sum(F.when(F.col("out"), F.octet_length("hashes") + F.octet_length("weights"))) / block_bytes).alias("out_lanes"))
    dealt = full.join(lanes, "pivot").withColumn("lane", F.pmod(F.xxhash64("doc_id"), F.col("lanes"))).withColumn("out_lane", F.pmod(F.xxhash64(F.lit(1), "doc_id"), F.col("out_lanes")))
    row = F.struct("doc_id", F.col("root_doc_id").alias("root"), F.col("similarity").alias("s"), F.col("total").cast("double").alias("t"), F.col("common").cast("double").alias("p"), "hashes", "weights")
    # the join left a pivot's members in one place
    right = dealt.repartition("pivot", "lane").groupBy("pivot", "lane").agg(F.collect_list(row).alias("y"))
    left = dealt.filter("out").repartition("pivot", "out_lane").groupBy("pivot", "out_lane").agg(F.first("lanes").alias("lanes"), F.collect_list(row).alias("x"))
    left = left.select("pivot", "x", F.explode(F.sequence(F.lit(0).cast("long"), F.col("lanes") - 1)).alias("lane"))

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                x, y = (batch.column(c)[i].as_py() for c in range(2))
                col = lambda rows, k: np.array([r[k] for r in rows])
                s, t, p, roots, ids = ((col(x, k)[:, None], col(y, k)[None, :]) for k in ("s", "t", "p", "root", "doc_id"))
                most = np.minimum(*p) + np.minimum(t[0] - p[0], t[1] - p[1])
                near = (roots[0] != roots[1]) & (ids[0] != ids[1]) & (np.abs(s[0] - s[1]) <= 1 - threshold + 1e-9)
                near &= most * (1 + threshold) + 1e-6 >= threshold * (t[0] + t[1])
                found = set()
                for j, k in zip(*np.nonzero(near)):
                    a, b = x[j], y[k]
                    if similarity(*unpack(a["hashes"], a["weights"]), *unpack(b["hashes"], b["weights"])) >= threshold:
                        found.add((min(a["doc_id"], b["doc_id"]), max(a["doc_id"], b["doc_id"])))
                yield pa.RecordBatch.from_arrays([pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64())], ["a", "b"])
        release_memory()

    return left.join(right, ["pivot", "lane"]).select("x", "y").mapInArrow(run, "a long, b long").distinct()


def one_of_each(docs: DataFrame, **options) -> DataFrame:
    """docs without the documents whose class has a smaller doc_id."""
    late = classes(docs, **options).filter("doc_id <> class_id").select("doc_id").distinct()
    return docs.join(late, "doc_id", "left_anti").select(*docs.columns)


def query(spark, sf_dir: str) -> DataFrame:
    return classes(table(spark, sf_dir, "documents"))

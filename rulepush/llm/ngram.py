"""Operator 5: quality classifier by an interpolated modified Kneser-Ney model of characters.

The model is trained on all trusted documents (labelled quality 1 and not toxic), over every character they hold:
digits count as one and white space as one, nothing else is folded. Every task counts the n-grams of its documents;
counts meet in a sharded sum by n-gram, so the tables grow with the trusted text and stay tables: no task and no
driver holds them. Count tables of the orders join into discounted probabilities. A character the trusted texts
never hold has the probability an unseen one is left.

Documents are scored by a join. The distinct n-grams of all documents meet the tables once, order by order. Each
task packs its texts into compressed blocks of a few MB; a block is shuffled once, asks for its distinct n-grams and
gets their probabilities back. A document's perplexity comes from all its characters; it is kept if that is at most the quantile, over the trusted
documents of its language, times a margin. Columns _ppl, _limit and _kept of the input are replaced.

Null and empty texts have no character and perplexity null; they are kept here. A null language, or one without
trusted documents, uses the threshold over all. Without trusted documents everything is kept. Repeated rows are
scored each.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import release_memory, saved, shuffle_partitions, small_batches, table
from .tokenization import row_slices

#: Stands before a text; there it counts as white space.
PAD = 0
#: Bins of a perplexity's logarithm, to a unit.
STEPS = 2000
#: Bytes of text whose n-grams are made distinct at once.
BLOCK = 6 << 20


def trusted_documents(docs: DataFrame, labels: DataFrame, broadcast_ids: int = 1_000_000) -> tuple[DataFrame, DataFrame]:
    """Trusted documents, and their ids. Up to broadcast_ids trusted ids go to the texts, which stay where they are; beyond it the texts are shuffled once and kept."""
    good = labels.groupBy("doc_id").agg(F.min("quality").alias("q"), F.max("toxic").alias("t")).filter("q = 1 and t = 0")
    good = saved(good.select("doc_id"), "trusted_ids")
    if good.count() <= broadcast_ids:
        return docs.join(F.broadcast(good), "doc_id", "left_semi"), good
    return saved(docs.join(good.hint("merge"), "doc_id", "left_semi"), "trusted"), good


def _codes(texts: list[str], pad: int) -> np.ndarray:
    """Code points of the texts, pad PADs before each; digits as one and white space as one."""
    before = chr(PAD) * pad
    raw = "".join(x for t in texts for x in (before, t.replace(before[:1], " "))).encode("utf-32-le", "replace")
    c = np.frombuffer(bytearray(raw), "<u4")
    c[(c >= 48) & (c <= 57)] = 48
    c[((c <= 32) & (c != PAD)) | (c == 160)] = 32
    return c


def _ranked(key: np.ndarray, size: int) -> tuple[np.ndarray, int]:
    """(rank of each key among the distinct ones, how many these are); keys are below size."""
    if size > 1 << 24:
        u, at = np.unique(key, return_inverse=True)
        return at.astype(np.int32), len(u)
    seen = np.zeros(size, bool)
    seen[key] = True
    rank = np.cumsum(seen, dtype=np.int32) - np.int32(1)
    return rank[key], int(rank[-1]) + 1


def grams_of(texts: list[str | None], order: int) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(distinct n-grams, the index of each character's among them, characters of each text).

    The distinct n-grams' order depends on nothing but which there are.
    """
    sizes = np.array([len(t) if t else 0 for t in texts], np.int64)
    if not sizes.sum():
        return [], np.zeros(0, np.int32), sizes
    c = _codes([t for t in texts if t], order - 1)
    small = np.int32 if len(c) < 1 << 31 else np.int64
    local, letters = _ranked(c, int(c.max()) + 1)
    ends = np.nonzero(c != PAD)[0].astype(small)
    at, n = _ranked(local[ends], letters)
    for i in range(1, order):  # grams longer by a character on the left, in the order of their characters
        key = local[ends - small(i)]
        if letters * n >= 1 << 31:
            key = key.astype(np.int64)
        key *= key.dtype.type(n)
        key += at
        at, n = _ranked(key, letters * n)
        del key
    place = np.empty(n, small)
    place[at] = ends
    chars = np.ascontiguousarray(c[place[:, None] + np.arange(1 - order, 1)])
    return chars.view(f"<U{order}")[:, 0].tolist(), at, sizes


def gram_counts(docs: DataFrame, order: int) -> DataFrame:
    """(g, c): counts of the highest order, summed over tasks."""

    def run(batches):
        def counted(texts):
            grams, at, _ = grams_of(texts, order)
            return pa.RecordBatch.from_arrays([pa.array(grams, pa.string()), pa.array(np.bincount(at, minlength=len(grams)), pa.int64())], ["g", "n"])

        held, size = [], 0
        for b in batches:
            for t in b.column(0).to_pylist():
                if t:
                    held.append(t)
                    size += len(t)
                if size >= BLOCK // 4:  # what blocks share is summed in the task
                    yield counted(held)
                    held, size = [], 0
        yield counted(held)
        release_memory()

    return docs.select("text").mapInArrow(run, "g string, n long").groupBy("g").agg(F.sum("n").alias("c"))


def discounts(counts: DataFrame) -> list[float]:
    """Modified Kneser-Ney discounts for counts 1, 2 and 3 or more, from the counts of counts."""
    of = dict(counts.filter("c <= 4").groupBy("c").count().collect())
    n = [0.0, *(float(of.get(i, 0)) for i in (1, 2, 3, 4))]
    if min(n[1:]) <= 0:
        return [0.5, 0.75, 0.9]
    y = n[1] / (n[1] + 2 * n[2])
    return [min(max(i - (i + 1) * y * n[i + 1] / n[i], 0.0), float(i)) for i in (1, 2, 3)]


def last(n: int) -> str:
    return f"substring(g, -{n}, {n})"


class Model:
    """Tables of each order: (g, p), an n-gram's discounted share, and (context, back), what its context leaves to the order below."""

    def __init__(self, order: int, alphabet: int, levels: dict[int, tuple[DataFrame, DataFrame]]):
        self.order, self.alphabet, self.levels = order, alphabet, levels

    def scores(self, asked: DataFrame) -> DataFrame:
        """(g, log_p) of the distinct n-grams g of asked, joined to the tables order by order."""
        need = {self.order: saved(asked.select("g").distinct(), "asked")}
        for n in range(self.order - 1, 0, -1):
            need[n] = need[n + 1].selectExpr(f"{last(n)} AS g").distinct()
        below = None
        for n in range(1, self.order + 1):
            shares, backs = self.levels[n]
            rows = need[n].join(shares, "g", "left")
            if n == 1:
                rows = rows.crossJoin(F.broadcast(backs)).withColumn("below", F.lit(1.0 / self.alphabet))
            else:
                rows = rows.withColumn("context", F.expr(f"substring(g, 1, {n - 1})")).join(backs, "context", "left")
                rows = rows.withColumn("suffix", F.expr(last(n - 1))).join(below.select(F.col("g").alias("suffix"), F.col("p").alias("below")), "suffix")
            below = saved(rows.select("g", (F.coalesce("p", F.lit(0.0)) + F.coalesce("back", F.lit(1.0)) * F.col("below")).alias("p")), f"level{n}")
        return below.select("g", F.log(F.greatest("p", F.lit(1e-12))).alias("log_p"))

    @property
    def log_p(self) -> np.ndarray:
        """For each context, of every character and an unseen one; for small models."""
        letters = [r[0] for r in self.levels[1][0].select("g").collect()]
        unseen = next(c for c in map(chr, range(33, 0x110000)) if c not in letters and c not in "123456789\xa0")
        contexts = self.levels[self.order][1].select("context")
        every = contexts.crossJoin(F.broadcast(contexts.sparkSession.createDataFrame([(x,) for x in [*letters, unseen]], "x string")))
        return self.scores(every.select(F.concat("context", "x").alias("g"))).orderBy("g").select("log_p").toPandas()["log_p"].to_numpy()


def train(trusted: DataFrame, order: int = 4) -> Model | None:
    up = saved(gram_counts(trusted, order), "grams")
    counts = {order: up}
    for n in range(order - 1, 0, -1):  # below the top a gram counts by how many characters come before it
        counts[n] = saved(counts[n + 1].groupBy(F.expr(last(n)).alias("g")).agg(F.count(F.lit(1)).alias("c")), "grams")
    letters = counts[1].count()
    if not letters:
        return None
    levels = {}
    for n, rows in counts.items():
        d = discounts(rows)
        cut = F.element_at(F.array(*map(F.lit, d)), F.least(F.col("c"), F.lit(3)).cast("int"))
        rows = rows.withColumn("context", F.expr(f"substring(g, 1, {n - 1})"))
        # the mass cut off, from whole counts: sums of fractions would depend on their order
        spare = sum(F.count(F.when(F.least("c", F.lit(3)) == i + 1, 1)) * x for i, x in enumerate(d))
        sums = saved(rows.groupBy("context").agg(F.sum("c").alias("all"), spare.alias("spare")), "contexts")
        shares = rows.join(sums, "context").select("g", (F.greatest(F.col("c") - cut, F.lit(0.0)) / F.col("all")).alias("p"))
        backs = sums.select("context", (F.col("spare") / F.col("all")).alias("back"))
        levels[n] = (shares, backs if n > 1 else backs.select("back"))
    return Model(order, letters + 1, levels)


def distinct_grams(docs: DataFrame, order: int) -> DataFrame:
    return gram_counts(docs, order).select("g")


def packed_blocks(docs: DataFrame) -> DataFrame:
    """(_block, rows): the rows of docs in blocks of about BLOCK bytes of their task, compressed; a longer text is a block of its own."""
    text = docs.columns.index("text")

    def run(batches):
        first = TaskContext.get().partitionId() << 32  # blocks are numbered by place, so a task that runs again makes the same
        held, size, n = [], 0, 0

        def block():
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, held[0].schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", 3))) as to:
                to.write_table(pa.Table.from_batches(held).combine_chunks())
            return pa.RecordBatch.from_arrays([pa.array([first + n], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["_block", "rows"])

        for b in batches:
            for at, m in row_slices(b.column(text), BLOCK // 4):
                held.append(b.slice(at, m))
                size += held[-1].nbytes
                if size >= BLOCK:
                    yield block()
                    held, size, n = [], 0, n + 1
        if held:
            yield block()
        release_memory()

    return docs.mapInArrow(run, "_block long, rows binary").repartition(shuffle_partitions(docs.sparkSession), "_block")


def with_perplexity(docs: DataFrame, model: Model, out: str, keep: list[str] | None = None) -> DataFrame:
    """The columns keep of docs (all of them by default), and out, which replaces a column of its name."""
    order, keep = model.order, [c for c in keep or docs.columns if c != out]
    scores = model.scores(distinct_grams(docs, order))
    blocks = packed_blocks(docs.select(*dict.fromkeys([*keep, "text"])))

    def texts(t: pa.Table) -> tuple[pa.Table, list]:
        rows = pa.ipc.open_stream(t.column("rows")[0].as_buffer()).read_all()
        return rows, rows.column("text").to_pylist()

    def ask(t: pa.Table) -> pa.Table:
        grams, _, _ = grams_of(texts(t)[1], order)
        out = pa.table({"_block": pa.array(np.full(len(grams), t.column("_block")[0].as_py(), np.int64)), "i": pa.array(np.arange(len(grams), dtype=np.int32)), "g": pa.array(grams, pa.string())})
        release_memory()
        return out

    def score(t: pa.Table, told: pa.Table) -> pa.Table:
        rows, held = texts(t)
        grams, at, sizes = grams_of(held, order)
        log_p = np.full(len(grams), np.nan)
        log_p[told.column("i").to_numpy()] = told.column("log_p").to_numpy()
        ends = np.cumsum(sizes)
        ppl = [float(np.exp(-log_p[at[e - n : e]].mean())) if n else None for e, n in zip(ends, sizes)]
        scored = rows.select(keep).append_column(out, pa.array(ppl, pa.float64()))
        release_memory()
        return scored

    told = blocks.groupBy("_block").applyInArrow(ask, "_block long, i int, g string").join(scores, "g").select("_block", "i", F.col("log_p").cast("float").alias("log_p"))
    schema = docs.select(*keep, F.lit(0.0).cast("double").alias(out)).schema
    for f in schema:
        f.nullable = True
    return blocks.groupBy("_block").cogroup(told.groupBy("_block")).applyInArrow(score, schema)


def thresholds(scored: DataFrame, quantile: float, margin: float) -> tuple[DataFrame, float | None]:
    """(lang, _own) of each language, and the threshold over all; languages with fewer than 20 trusted documents use the latter.

    Quantiles are upper edges of the bins, STEPS to a unit of the logarithm, where counts of all documents reach
    them: whole counts, so the order in which partial results merge changes nothing. A language has a bounded
    number of bins.
    """
    level = F.floor(F.log("_ppl") * STEPS).cast("int")
    bins = saved(scored.filter("_ppl is not null and not isnan(_ppl)").groupBy("lang", level.alias("bin")).agg(F.count(F.lit(1)).alias("n")), "bins")

    def quantiles(counts: DataFrame, *by: str) -> DataFrame:
        of = Window.partitionBy(*by)
        below = counts.withColumn("below", F.sum("n").over(of.orderBy("bin"))).withColumn("all", F.sum("n").over(of))
        return below.filter(F.col("below") >= quantile * F.col("all")).groupBy(*by).agg(F.exp((F.min("bin") + 1) / F.lit(float(STEPS))).alias("q"), F.first("all").alias("n"))

    whole = quantiles(bins.groupBy("bin").agg(F.sum("n").alias("n"))).first()
    each = quantiles(bins.filter("lang is not null"), "lang").filter("n >= 20")
    return saved(each.select("lang", (F.col("q") * margin).alias("_own")), "limits"), None if whole is None or whole["q"] is None else whole["q"] * margin


def judged(docs: DataFrame, labels: DataFrame, order: int = 4, quantile: float = 0.99, margin: float = 1.1, keep: list[str] | None = None) -> DataFrame:
    """The columns keep of docs (all of them by default) with _ppl, _limit and _kept."""
    small_batches(docs.sparkSession)
    keep = [c for c in keep or docs.columns if c not in ("_ppl", "_limit", "_kept")]
    trusted, ids = trusted_documents(docs.select("doc_id", "text", "lang"), labels)
    model = train(trusted, order)
    if model is None:
        return docs.select(*keep).withColumns({"_ppl": F.lit(None).cast("double"), "_limit": F.lit(None).cast("double"), "_kept": F.lit(True)})
    scored = saved(with_perplexity(docs, model, "_ppl", list(dict.fromkeys([*keep, "doc_id", "lang"]))), "scored")
    by_lang, whole = thresholds(scored.select("doc_id", "lang", "_ppl").join(ids, "doc_id", "left_semi"), quantile, margin)
    rows = scored.select(F.struct("*").alias("r")).join(by_lang.toDF("l", "own"), F.col("r.lang") == F.col("l"), "left")
    out = rows.select("r.*", F.coalesce("own", F.lit(whole).cast("double")).alias("_limit"))
    return out.select(*keep, "_ppl", "_limit", F.coalesce(F.isnan("_ppl") | (F.col("_ppl") <= F.col("_limit")), F.lit(True)).alias("_kept"))


def query(spark, sf_dir: str) -> DataFrame:
    out = judged(table(spark, sf_dir, "documents").select("doc_id", "text", "lang"), table(spark, sf_dir, "labels"), keep=["doc_id", "lang"])
    return out.select("doc_id", "lang", F.col("_ppl").alias("perplexity"), F.col("_limit").alias("limit"), F.col("_kept").alias("kept"))

"""Operator 9: dedup of lines, paragraphs or the sentences in them, by digests of normalised units.

A text is cut into units: SENTENCE (a line, cut further where a sentence ends, since passages are also pasted into
the middle of lines), LINE or PARAGRAPH. Units are normalised: lower case, ASCII white space runs as one blank. A unit
that equals one of smaller rank, by (doc_id, position), anywhere in the corpus is a later copy. Later copies that
follow one another, blank units aside, are a run; runs of at least least_bytes (normalised, UTF-8) are removed, so
that a short line which many documents share by chance or custom stays, whatever its script, and a passage goes
although its sentences are short. The earliest occurrence stays, the rest keeps its order, and the removed units' byte
offsets in the original text are kept.

Each task first meets the copies among its own texts: of a unit it sends one entry for about BLOCK bytes of text,
so a unit of a third of all rows is a few entries. Entries meet by 128-bit digest, in rank order, without being held.

Null texts have no unit; their text stays null. Empty texts have none either. Null doc_ids rank first. Rows that
repeat a doc_id rank by position alone; removal is by doc_id and text, so other texts of the id aren't touched. An
empty table gives an empty result. Other columns pass through; n_units, removed and removed_spans replace columns of
these names.
"""

from __future__ import annotations

import re

import pyarrow as pa
import xxhash

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import release_memory, small_batches, table
from .tokenization import row_slices

SENTENCE = r"[^.!?。！？\n]+[.!?。！？\n]*|[.!?。！？\n]+"
LINE = r"[^\n]*\n|[^\n]+"
PARAGRAPH = r"(?:[^\n]|\n[^\n])+\n*|\n+"
#: Bytes of text whose units are made distinct at once.
BLOCK = 16 << 20


def normalised(unit: str) -> bytes:
    return b" ".join(unit.lower().encode("utf-8", "replace").split())


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def entries(docs: DataFrame, units: str = SENTENCE) -> DataFrame:
    """(digest, doc_id, text_hash, pos, late): for each task's distinct units their first place pos; rows with late instead hold positions of a text that came later than such a place."""

    def run(batches):
        cut = re.compile(units).findall

        def met(held):
            held.sort(key=lambda x: (x[0] is not None, x[0] or 0))
            first: dict[bytes, tuple] = {}
            later: dict[tuple, list[int]] = {}
            for i, h, text in held:
                for p, u in enumerate(cut(text)):
                    if n := normalised(u):
                        d = xxhash.xxh3_128_digest(n)
                        at = first.get(d)
                        if at is None or (at[0] == i and p < at[2]):
                            if at is not None:  # another text of the same doc_id has it further on
                                later.setdefault(at[:2], []).append(at[2])
                            first[d] = (i, h, p)
                        elif at[0] != i or at[2] != p:
                            later.setdefault((i, h), []).append(p)
            rows = [(d, *at, None) for d, at in first.items()]
            rows += [(xxhash.xxh3_64_digest(repr(k)), *k, None, sorted(set(v))) for k, v in later.items()]
            cols = list(zip(*rows)) if rows else [[]] * 5
            kinds = (pa.binary(), pa.int64(), pa.int64(), pa.int32(), pa.list_(pa.int32()))
            for lo in range(0, max(1, len(rows)), 50_000):
                yield pa.RecordBatch.from_arrays([pa.array(c[lo : lo + 50_000], k) for c, k in zip(cols, kinds)], ["digest", "doc_id", "text_hash", "pos", "late"])

        held, size = [], 0
        for b in batches:
            for at, m in row_slices(b.column(1)):
                for i, t in zip(b.column(0).slice(at, m).to_pylist(), b.column(1).slice(at, m).to_pylist()):
                    if t:
                        held.append((i, signed(xxhash.xxh64_intdigest(t.encode("utf-8", "replace"), 42)), t))
                        size += len(t)
                if size >= BLOCK:
                    yield from met(held)
                    held, size = [], 0
        yield from met(held)
        release_memory()

    small_batches(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "digest binary, doc_id long, text_hash long, pos int, late array<int>")


def later_copies(docs: DataFrame, units: str = SENTENCE) -> DataFrame:
    """(doc_id, text_hash, late): the positions of each text's units that came earlier, in no order."""
    place = F.rank().over(Window.partitionBy("digest").orderBy(F.asc_nulls_first("doc_id"), "pos"))
    late = entries(docs, units).withColumn("_place", place).filter("late IS NOT NULL OR _place > 1")
    return late.groupBy("doc_id", "text_hash").agg(F.flatten(F.collect_list(F.coalesce("late", F.array("pos")))).alias("late"))


CUT = "struct<text:string,n_units:int,removed:array<int>,removed_spans:array<struct<start:bigint,end:bigint>>>"


def removal(text: str, units: str, late, least_bytes: int) -> tuple[str, int, list[int], list[tuple[int, int]]]:
    """(text that stays, number of units, removed positions, their byte spans)."""
    parts = re.findall(units, text)
    gone: list[int] = []
    if late:
        late, run, size = set(late), [], 0
        for p, u in enumerate([*parts, "end"]):
            n = normalised(u) if p < len(parts) else b"end"
            if p in late:
                run.append(p)
                size += len(n)
            elif n:
                gone += run if size >= least_bytes else []
                run, size = [], 0
    spans, at, drop = [], 0, set(gone)
    if gone:
        for p, u in enumerate(parts):
            to = at + len(u.encode("utf-8", "replace"))
            if p in drop:
                spans.append((at, to))
            at = to
    return "".join(u for p, u in enumerate(parts) if p not in drop) if gone else text, len(parts), gone, spans


def dedup(docs: DataFrame, units: str = SENTENCE, least_bytes: int = 100) -> DataFrame:
    """docs with text as it stays, n_units, removed positions, and removed_spans (start, end) in bytes of the original."""

    @F.arrow_udf(CUT)
    def cut(text: pa.Array, late: pa.Array) -> pa.Array:
        out = [None if t is None else removal(t, units, x, least_bytes) for t, x in zip(text.to_pylist(), late.to_pylist())]
        kind = pa.struct([("text", pa.string()), ("n_units", pa.int32()), ("removed", pa.list_(pa.int32())), ("removed_spans", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))])
        rows = [(None, 0, [], []) if x is None else x for x in out]
        return pa.array([{"text": t, "n_units": n, "removed": g, "removed_spans": [{"start": a, "end": b} for a, b in s]} for t, n, g, s in rows], kind)

    late = later_copies(docs, units).toDF("_i", "_h", "_late")
    rows = docs.select(F.struct("*").alias("d"))
    joined = rows.join(late, F.col("d.doc_id").cast("long").eqNullSafe(F.col("_i")) & (F.xxhash64("d.text") == F.col("_h")), "left")
    joined = joined.select("d", cut("d.text", "_late").alias("c"))
    own = ("n_units", "removed", "removed_spans")
    return joined.select(*[(F.col("c.text") if c == "text" else F.col(f"d.`{c}`")).alias(c) for c in docs.columns if c not in own], *[f"c.{c}" for c in own])


def query(spark, sf_dir: str, units: str = SENTENCE, least_bytes: int = 100) -> DataFrame:
    """Per document: units, removed units and their spans, and size and digest of the text that stays (null: empty)."""
    out = dedup(table(spark, sf_dir, "documents").select("doc_id", "text"), units, least_bytes)
    text = F.coalesce("text", F.lit(""))
    spans = F.array_join(F.transform("removed_spans", lambda s: F.concat_ws("-", s["start"].cast("string"), s["end"].cast("string"))), ",")
    return out.select("doc_id", F.col("n_units").cast("long").alias("n_units"), F.size("removed").cast("long").alias("n_removed"), spans.alias("removed_spans"), F.octet_length(text).cast("long").alias("kept_bytes"), F.md5(text).alias("kept_md5"))


def every_line(spark, sf_dir: str) -> DataFrame:
    """The same for whole lines, of which every one that isn't blank takes part."""
    return query(spark, sf_dir, LINE, 1)


def oracle(units: str, least_bytes: int) -> str:
    return rf"""
WITH units AS (
  SELECT doc_id, unnest(x) AS unit, generate_subscripts(x, 1) AS pos
  FROM (SELECT doc_id, regexp_extract_all(text, '{units}') AS x FROM documents WHERE text IS NOT NULL)),
plain AS (
  SELECT *, trim(regexp_replace(lower(unit), '[ \t\n\x0B\f\r]+', ' ', 'g'), ' ') AS n,
    sum(strlen(unit)) OVER (PARTITION BY doc_id ORDER BY pos) AS stop FROM units),
ranked AS (SELECT *, n <> '' AND row_number() OVER (PARTITION BY n ORDER BY doc_id, pos) > 1 AS late FROM plain),
runs AS (SELECT *, count(*) FILTER (WHERE n <> '' AND NOT late) OVER (PARTITION BY doc_id ORDER BY pos) AS run FROM ranked),
judged AS (SELECT *, late AND sum(CASE WHEN late THEN strlen(n) ELSE 0 END) OVER (PARTITION BY doc_id, run) >= {least_bytes} AS gone FROM runs),
kept AS (
  SELECT doc_id, count(*) AS n_units, count(*) FILTER (WHERE gone) AS n_removed,
    coalesce(string_agg((stop - strlen(unit)) || '-' || stop, ',' ORDER BY pos) FILTER (WHERE gone), '') AS spans,
    coalesce(string_agg(unit, '' ORDER BY pos) FILTER (WHERE NOT gone), '') AS t FROM judged GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_units, 0)::BIGINT AS n_units, coalesce(n_removed, 0)::BIGINT AS n_removed,
  coalesce(spans, '') AS removed_spans, strlen(coalesce(t, ''))::BIGINT AS kept_bytes, md5(coalesce(t, '')) AS kept_md5
FROM documents d LEFT JOIN kept k ON d.doc_id = k.doc_id
"""


ORACLE = oracle(SENTENCE, 100)
EVERY_LINE_ORACLE = oracle(LINE, 1)

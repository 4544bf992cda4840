"""Operator 10: removal of repeated byte strings, from common-prefix interval trees of enhanced suffix arrays.

A byte goes if a string of `length` bytes that covers it also starts earlier: in a smaller doc_id, or before in the
same document. Strings never cross documents and are judged on the input.

1. Runs. Every string of `length` bytes has one anchor: the leftmost least hash among its grams. Neighbouring
   strings with the same anchor form a run; a run is known by its anchor and by its whole context. Runs travel as
   packed columns, already rid of the copies inside their batch.
2. Equal contexts are gathered before any text travels: all but the earliest of them go. Of the others, those stay
   open whose anchor stands beside the same bytes, on the longer side of the string, in another context: all
   occurrences of a string share both, so they are the group in which the string can be found again.
3. Groups. The open contexts travel as text, sorted by group; whole groups fill an enhanced suffix array (sorted
   suffixes, their common prefixes). A stack scan builds the tree of common-prefix intervals; those of at least
   `length` whose occurrences differ on the left are the maximal repeats, with all occurrences. All but the earliest of
   each are removed. Bytes are compared, not digests.
4. A group of more than HOT contexts, such as the edges of a passage that a third of all documents hold, would be one
   task's. Its texts go through suffix arrays where they are, and the strings that stay in each meet by 96-bit digest.

No group is gathered unless its size is bounded: a string or context as common as can be adds one packed entry per
batch.

Null texts are empty. Rows without a doc_id take no part and stay whole. Rows that repeat a doc_id are one
document: equal starts are not earlier. An empty table gives an empty result.
"""

from __future__ import annotations

import functools
import hashlib

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import release_memory, saved, small_batches, table
from .tokenization import row_slices

GRAM = 24
#: Contexts that a group holds at most where its text travels to one task.
HOT = 4096
BUCKETS = 1024
_BATCH = 4 << 20
_PART = 1 << 19
_U = np.uint64


def mix64(x):
    x = (x ^ (x >> _U(32))) * _U(0xD6E8FEB86659FD93)
    x = (x ^ (x >> _U(32))) * _U(0xD6E8FEB86659FD93)
    return x ^ (x >> _U(32))


#: An odd number of no meaning.
_BASE = 0x5851F42D4C957F2D


_POWERS: list[np.ndarray] = []


def _powers(n: int) -> list[np.ndarray]:
    """At least n powers of an odd base, and of its inverse, modulo 2**64; kept until more are asked for."""
    if not _POWERS or len(_POWERS[0]) < n:
        size = -(-n // (1 << 20)) << 20
        _POWERS[:] = [np.concatenate([np.ones(1, _U), np.cumprod(np.full(size - 1, b, _U))]) for b in (_BASE, pow(_BASE, -1, 1 << 64))]
    return _POWERS


@functools.lru_cache(8)
def _values(seed: int) -> np.ndarray:
    return np.random.default_rng(seed).integers(1, 1 << 63, 256, dtype=_U) * _U(2) + _U(1)


class Hashes:
    """Digest of any stretch of a buffer from prefix sums."""

    def __init__(self, data: np.ndarray, seed: int):
        self.power, self.inverse = _powers(len(data) + 1)
        self.prefix = np.zeros(len(data) + 1, _U)
        np.cumsum(_values(seed)[data] * self.power[: len(data)], out=self.prefix[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix64((self.prefix[end] - self.prefix[start]) * self.inverse[start])


def flat(column) -> tuple[np.ndarray, np.ndarray]:
    """(bytes of all texts in a row, where each begins, and the end)."""
    c = pc.fill_null(column.cast(pa.large_binary()), b"")
    at = np.frombuffer(c.buffers()[1], np.int64)[c.offset : c.offset + len(c) + 1]
    raw = c.buffers()[2]
    data = np.frombuffer(raw, np.uint8)[at[0] : at[-1]] if raw is not None and at[-1] > at[0] else np.zeros(0, np.uint8)
    return data, at - at[0]


def runs_of(data: np.ndarray, at: np.ndarray, length: int) -> dict[str, np.ndarray]:
    """Runs of a buffer of texts: anchor digest, context digest, row, start within the text, strings in it, place of the
    anchor from start, and digests of the anchor with half a string's rest on its left and on its right.
    """
    out: list[list[np.ndarray]] = [[] for _ in range(8)]
    n, spread = len(data), length - GRAM + 1
    for lo in range(0, max(0, n - length + 1), _PART):
        part = data[lo : min(n, lo + _PART + length - 1)]
        m = len(part)
        if m < length:
            break
        low, high = Hashes(part, 11), Hashes(part, 12)
        i = np.arange(m - GRAM + 1)
        gram = low.of(i, i + GRAM)
        least = (gram & ~_U((1 << 24) - 1)) | i.astype(_U)
        width = 1
        while width * 2 <= spread:
            least = np.minimum(least[:-width], least[width:])
            width *= 2
        if spread > width:
            least = np.minimum(least[: len(least) - (spread - width)], least[spread - width :])
        anchor = (least & _U((1 << 24) - 1)).astype(np.int64)  # of the string at each start
        starts = np.arange(len(anchor))
        row = np.searchsorted(at, starts + lo, side="right") - 1
        ok = starts + lo + length <= at[row + 1]
        starts, anchor, row = starts[ok], anchor[ok], row[ok]
        if not len(starts):
            continue
        new = np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (row[1:] != row[:-1])])
        first = np.nonzero(new)[0]
        count = np.diff(np.append(first, len(starts)))
        s, a = starts[first], anchor[first]
        context = mix64(high.of(s, s + count + length - 1) + (a - s).astype(_U) * _U(0x9E3779B97F4A7C15) + count.astype(_U))
        half = (length - GRAM) // 2  # clipped halves are never asked for: no string of the run reaches past its text
        sides = low.of(np.maximum(a - half, 0), a + GRAM), low.of(a, np.minimum(a + GRAM + half, m))
        for held, x in zip(out, (gram[a], context, row[first], s + lo - at[row[first]], count, a - s, *sides)):
            held.append(x)
    kinds = (_U, _U, np.int64, np.int64, np.int64, np.int64, _U, _U)
    return dict(zip(("h", "c", "row", "start", "n", "place", "left", "right"), (np.concatenate(x) if x else np.zeros(0, k) for x, k in zip(out, kinds))))


def six(x: np.ndarray) -> bytes:
    return np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, 2:]).tobytes()


def from_six(raw: bytes) -> np.ndarray:
    wide = np.zeros((len(raw) // 6, 8), np.uint8)
    wide[:, 2:] = np.frombuffer(raw, np.uint8).reshape(-1, 6)
    return wide.view("<u8").reshape(-1)


def _narrow(x: np.ndarray) -> bytes:
    """Whole numbers in 4 bytes each where they fit, otherwise 8; the length tells which."""
    return x.astype("<u4").tobytes() if not len(x) or (x.min() >= 0 and x.max() < 1 << 32) else x.astype("<i8").tobytes()


def _wide(raw: bytes, n: int) -> np.ndarray:
    return np.frombuffer(raw, "<u4" if len(raw) == 4 * n else "<i8").astype(np.int64)


PACKED = "bucket int, a binary, b binary, doc binary, start binary, n binary"


def three(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x.astype("<u8")).view(np.uint8).reshape(-1, 8)[:, 5:]


def pack(a, b, doc, start, n) -> pa.RecordBatch:
    """One row of packed columns for each bucket, by the top bits of a. n: rows of small numbers for each entry."""
    bucket = (a >> _U(54)).astype(np.int64)  # BUCKETS of them
    order = np.argsort(bucket, kind="stable")
    cuts = np.searchsorted(bucket[order], np.arange(BUCKETS + 1))
    cols: list[list] = [[], [], [], [], [], []]
    for i in range(BUCKETS):
        o = order[cuts[i] : cuts[i + 1]]
        if len(o):
            for held, x in zip(cols, (i, six(a[o]), six(b[o]), _narrow(doc[o]), _narrow(start[o]), n[o].tobytes())):
                held.append(x)
    return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], ["bucket", "a", "b", "doc", "start", "n"])


def unpack(batches) -> tuple[np.ndarray, ...] | None:
    got: list[list[np.ndarray]] = [[], [], [], [], []]
    for batch in batches:
        rows = batch.to_pydict()
        for a, b, doc, start, n in zip(rows["a"], rows["b"], rows["doc"], rows["start"], rows["n"]):
            k = len(a) // 6
            for held, x in zip(got, (from_six(a), from_six(b), _wide(doc, k), _wide(start, k), np.frombuffer(n, np.uint8).reshape(k, -1))):
                held.append(x)
    return tuple(np.concatenate(x) for x in got) if got[0] else None


def earliest(a, b, doc, start) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order by key then rank, whether a row is its key's first entry, whether it is later than that one)."""
    order = np.lexsort((start, doc, b, a))
    a, b, doc, start = a[order], b[order], doc[order], start[order]
    first = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
    head = np.nonzero(first)[0][np.cumsum(first) - 1]
    return order, first, (doc != doc[head]) | (start != start[head])


def merged(doc, start, end) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Intervals joined where they touch, by document."""
    if not len(doc):
        return doc, start, end
    order = np.lexsort((start, doc))
    doc, start, end = doc[order], start[order], end[order]
    group = np.cumsum(np.concatenate([[0], doc[1:] != doc[:-1]]))
    reach = np.maximum.accumulate(end + group * (1 << 40)) - group * (1 << 40)
    new = np.concatenate([[True], (doc[1:] != doc[:-1]) | (start[1:] > reach[:-1])])
    at = np.nonzero(new)[0]
    return doc[at], start[at], reach[np.append(at[1:], len(doc)) - 1]


#: key: null for what is settled, 0 for what is open in a hot group, else the group.
SPANS = "doc_id long, start long, stop long, key long"


def _spans(doc, start, end, key=None) -> pa.RecordBatch:
    keys = pa.nulls(len(doc), pa.int64()) if key is None else pa.array(np.broadcast_to(key, len(doc)), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(start, pa.int64()), pa.array(end, pa.int64()), keys], ["doc_id", "start", "stop", "key"])


def _settled(doc, start, end) -> pa.RecordBatch:
    """Spans settled in a batch, dealt by document; they travel with the packed rows."""
    lane = (mix64(doc.astype(_U)) >> _U(54)).astype(np.int64)
    order = np.argsort(lane, kind="stable")
    cuts = np.searchsorted(lane[order], np.arange(BUCKETS + 1))
    rows = [(-1 - i, b"", b"", _narrow(doc[o]), _narrow(start[o]), _narrow(end[o])) for i in range(BUCKETS) if len(o := order[cuts[i] : cuts[i + 1]])]
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), *(pa.array([r[i] for r in rows], pa.binary()) for i in range(1, 6))], ["bucket", "a", "b", "doc", "start", "n"])


def _settled_rows(rows: pa.RecordBatch) -> pa.RecordBatch:
    d, s, e = [], [], []
    got = rows.to_pydict()
    for doc, start, end in zip(got["doc"], got["start"], got["n"]):
        # the three columns hold as many numbers each, and every number takes 4 or 8 bytes
        k = _count(doc, start, end)
        d.append(_wide(doc, k)), s.append(_wide(start, k)), e.append(_wide(end, k))
    return _spans(*(np.concatenate(x) if x else np.zeros(0, np.int64) for x in (d, s, e)))


def _count(*raw: bytes) -> int:
    """Starts and ends within a text fit 4 bytes unless it is over 4 GB; ids may need 8."""
    return min(len(raw[1]), len(raw[2])) // 4


def runs(docs: DataFrame, length: int) -> DataFrame:
    """Packed runs of docs(doc_id, text), and the spans already settled inside a batch."""

    def run(batches):
        for batch in batches:
            batch = batch.filter(pc.is_valid(batch.column(0)))
            for lo, k in row_slices(batch.column(1), _BATCH):
                ids = batch.column(0).slice(lo, k).to_numpy(zero_copy_only=False)
                data, at = flat(batch.column(1).slice(lo, k))
                r = runs_of(data, at, length)
                if not len(r["h"]):
                    continue
                doc = ids[r["row"]]
                order, first, late = earliest(r["h"], r["c"], doc, r["start"])
                gone, stay = order[late], order[first]
                if len(gone):
                    yield _settled(*merged(doc[gone], r["start"][gone], r["start"][gone] + r["n"][gone] + length - 1))
                small = np.column_stack([r["n"][stay].astype(np.uint8), r["place"][stay].astype(np.uint8), three(r["left"][stay]), three(r["right"][stay])])
                yield pack(r["h"][stay], r["c"][stay], doc[stay], r["start"][stay], small)
        release_memory()

    return docs.select("doc_id", "text").mapInArrow(run, PACKED)


def _side(x: np.ndarray) -> np.ndarray:
    x = x.astype(_U)
    return x[:, 0] | x[:, 1] << _U(8) | x[:, 2] << _U(16)


def copies(packed: DataFrame, length: int, partitions: int, hottest: int = HOT) -> DataFrame:
    """Spans of runs that came earlier, and the open runs: of each, what its strings with the anchor right of the middle cover, and left of it."""

    def run(batches):
        rest = []
        for b in batches:
            own = pc.less(b.column(0), 0)
            if (s := b.filter(own)).num_rows:
                yield _settled_rows(s)
            rest.append(b.filter(pc.invert(own)))
        got = unpack(rest)
        del rest
        if got is None:
            return
        a, b, doc, start, small = got
        n = small[:, 0].astype(np.int64)
        order, first, late = earliest(a, b, doc, start)
        gone = order[late]
        yield _spans(*merged(doc[gone], start[gone], start[gone] + n[gone] + length - 1))
        heads = order[first]
        key = a[heads]
        several = np.zeros(len(heads), bool)
        same = key[1:] == key[:-1]
        several[1:] |= same
        several[:-1] |= same
        o = heads[several]
        if small.shape[1] < 8 or not len(o):
            return
        # an equal string shares the longer side of its rest: runs alone with theirs have none there
        place = small[o, 1].astype(np.int64)
        half = (length - GRAM) // 2
        nearest = place - n[o] + 1  # places of the anchor in the run's strings: nearest to place
        anchor = start[o] + place
        for i, from_, to in ((2, np.maximum(nearest, half), place), (5, nearest, np.minimum(place, half - 1))):
            group = mix64(a[o] ^ mix64(_side(small[o, i : i + 3]) + _U(i << 32)))
            size = np.unique(group, return_inverse=True, return_counts=True)
            size = size[2][size[1]]
            for keep, hot in (((size > 1) & (size <= hottest) & (from_ <= to), False), ((size > hottest) & (from_ <= to), True)):
                where = doc[o][keep], (anchor - to)[keep], (anchor - from_ + length)[keep]
                if hot:
                    yield _spans(*merged(*where), 0)
                else:
                    yield _spans(*where, group[keep].view(np.int64) | 1)
        release_memory()

    return packed.repartition(partitions, "bucket").mapInArrow(run, SPANS)


# --- enhanced suffix arrays


def suffix_array(text: np.ndarray, depth: int, least: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """(suffixes in order, common prefix of each with the one before), both by their first `depth` or more symbols.

    text: whole numbers; a symbol that occurs once ends every common prefix. Ranks start from four packed symbols and
    double in reach each round, for suffixes that still share theirs. Common prefixes under `least` may be given as 0.
    """
    n = len(text)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    text = np.unique(text, return_inverse=True)[1].astype(np.int64) if n and (text.min() < 0 or text.max() >= 1 << 30) else text
    two = text << 31
    two[:-1] |= text[1:] + 1
    pairs = np.unique(two, return_inverse=True)[1].astype(np.int64)
    key = pairs * (n + 1)
    key[:-2] += pairs[2:] + 1
    order = np.argsort(key)
    new = np.concatenate([[True], key[order][1:] != key[order][:-1]])
    head = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    rank = np.empty(n, np.int64)  # where a suffix's group begins in the order
    rank[order] = head
    levels, reach = [text, pairs, rank.copy()], 4
    while reach < depth:
        size = np.bincount(rank, minlength=n)
        live = order[size[rank[order]] > 1]
        if len(live):
            ahead = np.zeros(len(live), np.int64)
            inside = live + reach < n
            ahead[inside] = rank[live[inside] + reach] + 1
            group = rank[live]
            by = np.lexsort((ahead, group)) if n > 1 << 31 else np.argsort(group * (n + 1) + ahead)
            live, group, ahead = live[by], group[by], ahead[by]
            i = np.arange(len(live))
            begins = np.concatenate([[True], group[1:] != group[:-1]])
            parts = begins | np.concatenate([[True], ahead[1:] != ahead[:-1]])
            at = group + i - np.maximum.accumulate(np.where(begins, i, 0))
            order[at] = live
            rank = rank.copy()
            rank[live] = at[np.maximum.accumulate(np.where(parts, i, 0))]
        levels.append(rank)
        reach *= 2
    common = np.zeros(n, np.int64)
    top = max((i for i in range(len(levels)) if 1 << i <= max(least, 1)), default=0)
    near = np.nonzero(levels[top][order[1:]] == levels[top][order[:-1]])[0] + 1
    a, b = order[near].copy(), order[near - 1].copy()
    total = np.zeros(len(near), np.int64)
    for level in range(len(levels) - 1, -1, -1):
        step = 1 << level
        while len(a):
            same = (a + step <= n) & (b + step <= n)
            same[same] = levels[level][a[same]] == levels[level][b[same]]
            total[same] += step
            a[same] += step
            b[same] += step
            if level < len(levels) - 1 or not same.any():
                break
    common[near] = total
    return order, common


def maximal_repeats(order: np.ndarray, common: np.ndarray, left: np.ndarray, least: int):
    """(length, occurrences) of each repeat of at least `least` symbols that no symbol on its left extends alike.

    One scan with a stack over the common prefixes visits the interval tree bottom up; of each interval the left
    symbols seen so far are kept as one value, or as diverse. left: a value per suffix; negative is unlike any other.
    """
    n = len(order)
    deep = np.nonzero(common >= least)[0]
    if not len(deep):
        return
    blocks = np.split(deep, np.nonzero(np.diff(deep) > 1)[0] + 1)
    DIVERSE = -2
    join = lambda x, y: x if x == y and x >= 0 else DIVERSE
    for block in blocks:
        lo, hi = int(block[0]) - 1, int(block[-1])
        chars = left[order[lo : hi + 1]].tolist()
        depth = [*common[lo + 1 : hi + 1].tolist(), least - 1]
        stack: list[list[int]] = []  # (common prefix, first suffix, left symbol)
        for i, d in enumerate(depth):
            begin, seen = i, chars[i] if chars[i] >= 0 else DIVERSE
            single = True
            while stack and stack[-1][0] > d:
                size, begin, held = stack.pop()
                seen = join(held, seen)
                single = False
                if seen == DIVERSE:
                    yield size, order[lo + begin : lo + i + 1]
                if stack and stack[-1][0] >= d:
                    stack[-1][2] = join(stack[-1][2], seen)
                    if stack[-1][0] > d:
                        seen = stack[-1][2]
                        continue
            if d >= least:
                if stack and stack[-1][0] == d:
                    if single:
                        stack[-1][2] = join(stack[-1][2], seen)
                else:
                    stack.append([d, begin, seen])


def repeats_of(texts: list[bytes], least: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """Maximal repeats of at least `least` bytes over texts: (length, [(text, start), ...]), all occurrences."""
    if not texts:
        return []
    joined, owner, place, left = _join(texts)
    order, common = suffix_array(joined, max(least, max(map(len, texts))), least)
    return [(size, sorted((int(owner[p]), int(place[p])) for p in at)) for size, at in maximal_repeats(order, common, left, least)]


def _join(texts: list[bytes]):
    """Texts behind one another, each with an end of its own, and the left symbol of each place."""
    sizes = np.array([len(t) for t in texts])
    owner = np.repeat(np.arange(len(texts)), sizes + 1)
    starts = np.cumsum(sizes + 1) - sizes - 1
    place = np.arange(len(owner)) - starts[owner]
    joined = np.frombuffer(b"\0".join([*texts, b""]), np.uint8).astype(np.int64)
    joined[starts + sizes] = 256 + np.arange(len(texts))
    left = np.concatenate([[-1], joined[:-1]])
    left[starts] = -1
    return joined, owner, place, left


def late_repeats(texts: list[bytes], doc: np.ndarray, start: np.ndarray, length: int):
    """(joined text, owner and place of each of its symbols, whether a string of `length` there came earlier, removed spans) of texts[i], which begins at start[i] of doc[i]."""
    joined, owner, place, left = _join(texts)
    order, common = suffix_array(joined, max(length, *map(len, texts)), length)  # sorted to the end: else equal suffixes could lie apart
    gone: list[list[int]] = [[], [], []]
    late = np.zeros(len(joined), bool)
    for size, at in maximal_repeats(order, common, left, length):
        d, s = doc[owner[at]], start[owner[at]] + place[at]
        head = np.lexsort((s, d))[0]
        rest = (d != d[head]) | (s != s[head])
        gone[0] += d[rest].tolist()
        gone[1] += s[rest].tolist()
        gone[2] += (s[rest] + size).tolist()
        for p in at[rest].tolist():
            late[p : p + size - length + 1] = True
    return joined, owner, place, late, merged(*(np.array(x, np.int64) for x in gone))


def with_text(docs: DataFrame, spans: DataFrame) -> DataFrame:
    """(doc_id, text, spans) of documents with open spans."""
    lists = spans.filter("key IS NOT NULL").groupBy("doc_id").agg(F.collect_list(F.struct("start", "stop", "key")).alias("spans"))
    return docs.select("doc_id", "text").join(lists, "doc_id").select("doc_id", "text", "spans")


def pieces(open_: DataFrame) -> DataFrame:
    """(key, doc_id, start, bytes): the text of what is open in groups that one task can hold."""

    def run(batches):
        for batch in batches:
            for lo, k in row_slices(batch.column(1)):
                b = batch.slice(lo, k)
                rows = [(s["key"], i, s["start"], t[s["start"] : s["stop"]]) for i, t, spans in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()).to_pylist(), b.column(2).to_pylist()) for s in spans if s["key"]]
                for at in range(0, len(rows), 20_000):
                    cols = list(zip(*rows[at : at + 20_000]))
                    yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in cols[:3]), pa.array(cols[3], pa.binary())], ["key", "doc_id", "start", "bytes"])
        release_memory()

    return open_.mapInArrow(run, "key long, doc_id long, start long, bytes binary")


def repeats_in_groups(rows: DataFrame, length: int, partitions: int) -> DataFrame:
    """Settled spans: whole groups of pieces, as many as fill a suffix array, are scanned for maximal repeats."""

    def run(batches):
        held: list[list] = [[], [], [], []]
        size = 0

        def scan():
            *_, spans = late_repeats(held[3], np.array(held[1], np.int64), np.array(held[2], np.int64), length)
            return _spans(*spans)

        for b in batches:
            for row in zip(*(b.column(i).to_pylist() for i in range(4))):
                if size > _PART and row[0] != held[0][-1]:
                    yield scan()
                    held, size = [[], [], [], []], 0
                for x, y in zip(held, row):
                    x.append(y)
                size += len(row[3])
        if size:
            yield scan()
        release_memory()

    return rows.repartition(partitions, "key").sortWithinPartitions("key").mapInArrow(run, SPANS)


def open_strings(open_: DataFrame, length: int) -> DataFrame:
    """Hot groups: packed strings of the open spans that stay in their batch, and the spans settled in it."""

    def settle(ids, texts, lists):
        parts, doc, base = [], [], []
        for i, t, spans_ in zip(ids, texts, lists):
            for start, stop in joined_spans(sorted(spans_, key=lambda s: s["start"])):
                parts.append(t[start:stop])
                doc.append(i)
                base.append(start)
        if not parts:
            return
        doc, base = np.array(doc, np.int64), np.array(base, np.int64)
        joined, owner, place, late, gone = late_repeats(parts, doc, base, length)
        if len(gone[0]):
            yield _settled(*gone)
        data = joined.astype(np.uint8)
        sizes = np.array([len(p) for p in parts])
        p = np.nonzero(~late & (place + length <= sizes[owner]))[0]
        if len(p):
            a, b = Hashes(data, 21).of(p, p + length), Hashes(data, 22).of(p, p + length)
            yield pack(a, b, doc[owner[p]], base[owner[p]] + place[p], np.ones((len(p), 1), np.uint8))

    def run(batches):
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist()
            lists = [[s for s in spans if not s["key"]] for spans in batch.column(2).to_pylist()]
            lo, size = 0, 0
            for i, spans_ in enumerate(lists):
                size += sum(s["stop"] - s["start"] for s in spans_)
                if size > _PART or i == len(lists) - 1:
                    yield from settle(ids[lo : i + 1], texts[lo : i + 1], lists[lo : i + 1])
                    lo, size = i + 1, 0
            release_memory()

    return open_.mapInArrow(run, PACKED)


def removed(docs: DataFrame, length: int = 100, hottest: int = HOT) -> DataFrame:
    """(doc_id, spans): the spans of each document's bytes that go, in order, where there are any."""
    small_batches(docs.sparkSession)
    partitions = max(16, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    first = saved(copies(runs(docs, length), length, partitions, hottest), "spans")
    every = first.filter("key IS NULL").unionByName(repeats_in_groups(pieces(with_text(docs, first)), length, partitions))
    hot = first.filter("key = 0")
    if not hot.isEmpty():
        every = every.unionByName(copies(open_strings(with_text(docs, hot), length), length, partitions).filter("key IS NULL"))
    return every.groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("start", "stop"))).alias("spans"))


def joined_spans(spans) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for s in () if spans is None else spans:
        if out and s["start"] <= out[-1][1]:
            out[-1][1] = max(out[-1][1], s["stop"])
        else:
            out.append([s["start"], s["stop"]])
    return [(a, b) for a, b in out]


def with_spans(docs: DataFrame, length: int, hottest: int = HOT) -> DataFrame:
    """docs(doc_id, text) with spans. Rows with an id go the way open_spans deals them, so that one exchange serves both."""
    named = docs.filter("doc_id is not null")
    got = removed(docs, length, hottest)
    nameless = docs.filter("doc_id is null").withColumn("spans", F.lit(None).cast(got.schema["spans"].dataType))
    return named.join(got, "doc_id", "left").unionByName(nameless)


def whole_characters(raw: bytes, spans: list[tuple[int, int]]) -> str:
    """What stays, as text: spans shrink to whole characters."""
    out, at = [], 0
    for a, b in spans:
        while a < b and raw[a] & 0xC0 == 0x80:
            a += 1
        while b > a and b < len(raw) and raw[b] & 0xC0 == 0x80:
            b -= 1
        out.append(raw[at:a])
        at = b
    return b"".join([*out, raw[at:]]).decode("utf-8")


def dedup(docs: DataFrame, length: int = 100) -> DataFrame:
    """docs with text as it stays after removal; same columns."""

    @F.pandas_udf("string")
    def cut(text: pd.Series, spans: pd.Series) -> pd.Series:
        return pd.Series([whole_characters(t.encode(), joined_spans(s)) if t is not None and s is not None else t for t, s in zip(text, spans)], dtype=object)

    got = removed(docs.select("doc_id", "text"), length).toDF("i", "spans")
    both = docs.select(F.struct("*").alias("d")).join(got, F.col("d.doc_id") == F.col("i"), "left")
    text = F.when(F.col("spans").isNull(), F.col("d.text")).otherwise(cut(F.col("d.text"), F.col("spans")))
    return both.select(*[text.alias(c) if c == "text" else F.col(f"d.`{c}`").alias(c) for c in docs.columns])


def digests(docs: DataFrame, length: int = 100, hottest: int = HOT) -> DataFrame:
    """Operator 10's query: (doc_id, n_bytes, n_removed, n_spans, kept_sha256)."""

    def run(batches):
        for batch in batches:
            for lo, k in row_slices(batch.column(1)):
                rows = []
                for t, s in zip(batch.column(1).slice(lo, k).cast(pa.binary()).to_pylist(), batch.column(2).slice(lo, k).to_pylist()):
                    t = t or b""
                    spans = joined_spans(s)
                    out, at = [], 0
                    for a, b in spans:
                        out.append(t[at:a])
                        at = b
                    out.append(t[at:])
                    rows.append((len(t), sum(b - a for a, b in spans), len(spans), hashlib.sha256(b"".join(out)).hexdigest()))
                cols = list(zip(*rows))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, k), *(pa.array(c, pa.int64()) for c in cols[:3]), pa.array(cols[3])], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    docs = docs.select("doc_id", "text")
    return with_spans(docs, length, hottest).select("doc_id", "text", "spans").mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def query(spark, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"))

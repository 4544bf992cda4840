"""Batched tokenizer calls for Arrow functions: lengths (operator 1) and cached exact ids (operator 3).

Null texts count as empty. Special strings inside a text become their special id, the tokenizers library's
default. Texts are never cut: long ones are encoded piece by piece between boundaries no token can cross.
"""

from __future__ import annotations

import functools
import os
import re
import unicodedata

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import small_batches

_LOADED: dict = {}
#: A space after an ASCII letter or digit: byte-level pre-tokens start there, and never hold it inside.
_SAFE = re.compile(r"[A-Za-z0-9] ")


def load(path: str):
    """The tokenizer of a .json file, once per worker; one thread each, as Spark runs a task per core."""
    if path not in _LOADED:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        tok = Tokenizer.from_file(path)
        tok.no_truncation()
        tok.no_padding()
        _LOADED[path] = tok
    return _LOADED[path]


def safe_pieces(text: str, limit: int) -> list[str]:
    """text cut into pieces of about limit characters, only where byte-level BPE has a pre-token boundary."""
    if len(text) <= limit:
        return [text]
    out, at = [], 0
    while len(text) - at > limit and (m := _SAFE.search(text, at + limit - 1)):
        out.append(text[at : m.start() + 1])
        at = m.start() + 1
    return [*out, text[at:]]


def byte_batches(pieces, limit: int):
    """Groups of (owner, piece) whose summed sizes stay near limit."""
    group, size = [], 0
    for owner, piece in pieces:
        if group and size + len(piece) > limit:
            yield group
            group, size = [], 0
        group.append((owner, piece))
        size += len(piece)
    if group:
        yield group


def lengths(texts: list[str], tok, batch_chars: int, piece_chars: int) -> np.ndarray:
    """Number of ids of each text; ids themselves are dropped batch by batch."""
    out = np.zeros(len(texts), np.int64)
    pieces = ((i, p) for i, t in enumerate(texts) if t for p in safe_pieces(t, piece_chars))
    for group in byte_batches(pieces, batch_chars):
        for (owner, _), enc in zip(group, tok.encode_batch_fast([p for _, p in group], add_special_tokens=False)):
            out[owner] += len(enc)
    return out


def row_slices(column: pa.Array, limit: int = 8 << 20):
    """(start, length) of runs of rows holding about limit bytes of text."""
    sizes = pc.fill_null(pc.binary_length(column.cast(pa.binary())), 0).to_numpy(zero_copy_only=False)
    ends = np.cumsum(sizes)
    at, n = 0, len(sizes)
    while at < n:
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + limit, side="right")))
        yield at, to - at
        at = to


def count_tokens(docs: DataFrame, tokenizer: str, limit: int = 1024, batch_chars: int = 1 << 19, piece_chars: int = 1 << 15) -> DataFrame:
    """Operator 1. Rows of docs(doc_id, text) as (doc_id, n_bytes, n_tokens, over_limit).

    Other columns are ignored; repeated rows are counted each; an empty table gives an empty result; a null
    text has 0 bytes and 0 tokens; a null doc_id stays null.
    """
    small_batches(docs.sparkSession)

    def run(batches):
        tok = load(tokenizer)
        for batch in batches:
            text = batch.column(1)
            for at, n in row_slices(text):
                part = text.slice(at, n)
                size = pc.fill_null(pc.binary_length(part.cast(pa.binary())), 0).cast(pa.int64())
                got = lengths([t or "" for t in part.to_pylist()], tok, batch_chars, piece_chars)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(at, n), size, pa.array(got), pa.array(got > limit)],
                    ["doc_id", "n_bytes", "n_tokens", "over_limit"],
                )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


#: The byte-level pre-tokenizer's pattern (fixed value of the public format); piece_starts follows it on plain texts.
BYTE_LEVEL = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Characters whose Unicode classes all versions of the pattern engines agree on; other texts go to the library whole.
PLAIN = re.compile("[\t\n\r\x20-\x7e\u00a1-\u024f\u0400-\u045f\u2010-\u2027\u20ac]*")


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte: printable Latin-1 bytes stand for themselves, the rest follow from 256 on."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(spare)) for b in range(256)]


OTHER, LETTER, NUMBER, WHITE, BLANK = range(5)


@functools.cache
def classes() -> np.ndarray:
    """Class of each PLAIN character; those of one byte come first and are the classes of ASCII bytes too."""
    kind = {"L": LETTER, "N": NUMBER}
    got = [BLANK if c == 32 else WHITE if chr(c) in "\t\n\r" else kind.get(unicodedata.category(chr(c))[0], OTHER) for c in range(0x2100)]
    return np.array(got, np.uint8)


def piece_starts(buf: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Offsets in UTF-8 bytes at which BYTE_LEVEL begins a match.

    buf holds PLAIN texts, none empty, one after the other and two zero bytes or more; first: where each text begins.
    """
    size = len(buf) - 2
    kind = classes()[: 1 << 8][buf[:size]]
    high = np.nonzero(buf[:size] >= 0xC0)[0]
    if len(high):  # all bytes of a character take its class
        b0, b1, b2 = (buf[high + k].astype(np.int32) for k in range(3))
        three = b0 >= 0xE0
        of = classes()[np.where(three, (b0 & 15) << 12 | (b1 & 63) << 6 | b2 & 63, (b0 & 31) << 6 | b1 & 63)]
        kind[high] = kind[high + 1] = of
        kind[high[three] + 2] = of[three]
    run = np.minimum(kind, WHITE)
    starts = np.empty(size, bool)
    starts[0] = True
    np.not_equal(run[1:], run[:-1], out=starts[1:])
    white = run == WHITE
    ends = white[:-1] & ~white[1:]
    ends[first[1:] - 1] = False
    last = np.nonzero(ends)[0]  # the last character of white space is apart, and a blank begins what follows
    starts[last] = True
    starts[last + 1] = kind[last] != BLANK
    starts[first] = True
    marks = np.nonzero(buf[:size] == 39)[0]
    marks = marks[starts[marks]]
    if len(marks):
        begins = np.zeros(size + 2, bool)
        begins[first] = begins[size:] = True
        b1, b2 = buf[marks + 1], buf[marks + 2]
        one, two = ~begins[marks + 1], ~begins[marks + 2]
        short = one & np.isin(b1, list(b"stmd"))
        long = one & two & ((b1 == 114) & (b2 == 101) | (b1 == 118) & (b2 == 101) | (b1 == 108) & (b2 == 108))
        starts[marks[short | long] + 1] = False
        after = np.concatenate([marks[short] + 2, marks[long] + 3])
        starts[after[after < size]] = True
    return np.nonzero(starts)[0]


def spans(at: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Offsets at, at + 1, ... at + n - 1 of every span, in a row."""
    ends = np.cumsum(n)
    return np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(at - (ends - n), n)


class CachedEncoder:
    """Exact ids as little-endian bytes, with the library called for the distinct pre-tokens.

    Pre-tokens of up to 16 bytes are two 64-bit words (filled up with zeros, which plain texts don't hold) in an
    open-addressing table of arrays; longer ones are in a dict. Both give a span of one pool of ids.
    """

    def __init__(self, path: str, keep: int = 550_000):
        self.tok = load(path)
        self.special = [str(t) for t in (a.content for a in self.tok.get_added_tokens_decoder().values())]
        self.wide = self.tok.get_vocab_size() > 1 << 16
        self.dtype = np.dtype("<u4" if self.wide else "<u2")
        self.keep = keep
        self.long: dict[bytes, tuple[int, int]] = {}
        self.long_bytes = 0  # of self.long, about
        self.pool, self.filled = np.zeros(1 << 10, self.dtype), 1
        self._rebuild(1 << 10, *(np.zeros(0, t) for t in ("u8", "u8", "u4", "u1", "?")))
        # the same merges behind a plain split at blanks: words come already cut and in byte letters
        from tokenizers import Tokenizer, pre_tokenizers

        self.merges = Tokenizer(self.tok.model)
        self.merges.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        letters = byte_letters()
        self.blank = letters[32]
        self.letters = np.array([ord(x) for x in letters], "<u4")
        vocab = self.tok.get_vocab()
        self.leads = np.zeros(max(vocab.values()) + 1, bool)  # tokens that start with a blank
        self.leads[[i for t, i in vocab.items() if t.startswith(self.blank)]] = True

    def _rebuild(self, size: int, lo, hi, at, n, again) -> None:
        """A table of size slots with these entries; the entry of no bytes stands for pre-tokens kept elsewhere."""
        self.lo, self.hi, self.at = np.zeros(size, "u8"), np.zeros(size, "u8"), np.zeros(size, "u4")
        self.n, self.again, self.held = np.zeros(size, "u1"), np.zeros(size, bool), 0
        zero = np.zeros(1, "u8")
        self._insert(zero, zero, np.zeros(1, "u4"), np.ones(1, "u1"))
        self.again[self._insert(lo, hi, at, n)] = again

    def _slots(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        h = lo * np.uint64(0x9E3779B97F4A7C15) ^ (hi + np.uint64(0x632BE59BD9B4E019)) * np.uint64(0xC2B2AE3D27D4EB4F)
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        return (h >> np.uint64(32)).astype(np.int64) & (len(self.lo) - 1)

    def _insert(self, lo, hi, at, n) -> np.ndarray:
        """Puts in entries that are distinct and not held yet; at tells entries apart. Gives their slots."""
        slot = self._slots(lo, hi)
        left = np.arange(len(lo))
        while len(left):
            here = slot[left]
            free = self.n[here] == 0
            self.at[here[free]] = at[left[free]]
            won = free & (self.at[here] == at[left])
            put, to = left[won], here[won]
            self.lo[to], self.hi[to], self.n[to] = lo[put], hi[put], n[put]
            left = left[~won]
            slot[left] = slot[left] + 1 & len(self.lo) - 1
        self.held += len(lo)
        return slot

    def _find(self, lo, hi) -> tuple[np.ndarray, np.ndarray]:
        """Slot of each key and the places of keys not held."""
        slot = self._slots(lo, hi)
        missed = []
        left = np.nonzero((self.lo[slot] != lo) | (self.hi[slot] != hi) | (self.n[slot] == 0))[0]
        while len(left):
            empty = self.n[slot[left]] == 0
            missed.append(left[empty])
            left = left[~empty]
            slot[left] = slot[left] + 1 & len(self.lo) - 1
            here = slot[left]
            left = left[(self.lo[here] != lo[left]) | (self.hi[here] != hi[left]) | (self.n[here] == 0)]
        return slot, np.concatenate(missed) if missed else np.zeros(0, np.int64)

    def _evict(self) -> None:
        """Once over its bound, the cache keeps entries met again since the last time, half its bound at most."""
        if self.held <= self.keep and self.long_bytes <= 100 * self.keep and self.filled <= 8 * self.keep:
            return
        stay = np.nonzero(self.again & (self.at > 0))[0][: self.keep // 2]
        lo, hi, n = self.lo[stay], self.hi[stay], self.n[stay]
        ids = self.pool[spans(self.at[stay].astype(np.int64), n.astype(np.int64))]
        at = 1 + np.cumsum(n, dtype=np.int64) - n
        self.long.clear()
        self.long_bytes, self.filled = 0, 1
        self._store(ids)
        self._rebuild(len(self.lo), lo, hi, at.astype("u4"), n, np.zeros(len(n), bool))

    def _store(self, ids: np.ndarray) -> None:
        need = self.filled + len(ids)
        if need > len(self.pool):
            wider = np.zeros(max(need, 2 * len(self.pool)), self.dtype)
            wider[: self.filled] = self.pool[: self.filled]
            self.pool = wider
        self.pool[self.filled : need] = ids
        self.filled = need

    def _learn(self, buf: np.ndarray, pos: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Spans of the pool for these pre-tokens, given by offset and bytes, one place of each distinct one."""
        at, n = np.zeros(len(pos), np.int64), np.zeros(len(pos), np.int64)
        second = buf[pos + 1]
        led = (buf[pos] == 32) & (size > 1) & (second != 32) & (second != 9) & (second != 10) & (second != 13)
        rows = np.nonzero(led)[0]  # in a row, such pieces split again at their blanks
        for lo in range(0, len(rows), 256):
            part = rows[lo : lo + 256]
            said = self.letters[buf[spans(pos[part], size[part])]].tobytes().decode("utf-32-le").replace(self.blank, " " + self.blank)
            ids = np.array(self.merges.encode_batch_fast([said], add_special_tokens=False)[0].ids, self.dtype)
            starts = np.nonzero(self.leads[ids])[0]
            if len(starts) != len(part):
                raise ValueError("a blank inside a pre-token, or none before it")
            at[part], n[part] = self.filled + starts, np.diff(starts, append=len(ids))
            self._store(ids)
        rows = np.nonzero(~led)[0]
        for lo in range(0, len(rows), 4096):
            part = rows[lo : lo + 4096]
            said = [buf[p : p + z].tobytes().decode() for p, z in zip(pos[part].tolist(), size[part].tolist())]
            for i, enc in zip(part.tolist(), self.tok.encode_batch_fast(said, add_special_tokens=False)):
                at[i], n[i] = self.filled, len(enc.ids)
                self._store(np.array(enc.ids, self.dtype))
        return at, n

    def _plain(self, texts: list[bytes]) -> list[bytes]:
        """Ids of PLAIN texts, none empty."""
        self._evict()
        sizes = np.array([len(t) for t in texts], np.int64)
        first = np.cumsum(sizes) - sizes
        raw = b"".join(texts) + bytes(16)
        buf = np.frombuffer(raw, np.uint8)
        pos = piece_starts(buf[:-14], first)
        size = np.diff(pos, append=len(raw) - 16)
        words = np.ndarray(len(raw) - 7, "<u8", raw, 0, (1,))
        low = np.array([(1 << 8 * k) - 1 for k in range(9)], "u8")
        lo, hi = words[pos] & low[np.minimum(size, 8)], np.zeros(len(pos), "u8")
        over = np.nonzero(size > 8)[0]
        hi[over] = words[pos[over] + 8] & low[np.minimum(size[over] - 8, 8)]
        far = over[size[over] > 16]
        lo[far] = hi[far] = 0
        slot, missed = self._find(lo, hi)
        self.again[slot] = True
        self.again[slot[missed]] = False
        if len(missed):
            missed = missed[np.lexsort((hi[missed], lo[missed]))]
            a, b = lo[missed], hi[missed]
            new = missed[np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1]))]
            at, n = self._learn(buf, pos[new], size[new])
            if grown := self.held + len(new) > len(self.lo) * 3 // 5:
                held = np.nonzero(self.at)[0]
                room = 1 << ((self.held + len(new)) * 5 // 3).bit_length()
                self._rebuild(room, self.lo[held], self.hi[held], self.at[held], self.n[held], self.again[held])
            self._insert(lo[new], hi[new], at.astype("u4"), n.astype("u1"))
            again = slice(None) if grown else missed
            slot[again] = self._find(lo[again], hi[again])[0]
        at, n = self.at[slot].astype(np.int64), self.n[slot].astype(np.int64)
        if len(far):
            said = [raw[p : p + z] for p, z in zip(pos[far].tolist(), size[far].tolist())]
            places = {w: i for w, i in zip(said, far.tolist()) if w not in self.long}
            if places:
                self.long_bytes += sum(map(len, places)) + 250 * len(places)
                rows = np.array([*places.values()])
                self.long.update(zip(places, zip(*(x.tolist() for x in self._learn(buf, pos[rows], size[rows])))))
            at[far], n[far] = zip(*map(self.long.__getitem__, said))
        ids = self.pool[spans(at, n)].tobytes()
        ends = np.append(0, np.cumsum(n))[np.append(np.searchsorted(pos, first), len(pos))] * self.dtype.itemsize
        return [ids[x:y] for x, y in zip(ends.tolist(), ends[1:].tolist())]

    def encode(self, texts: list[str], piece_chars: int = 1 << 18) -> list[bytes]:
        out: list = [b""] * len(texts)
        plain = []
        for i, t in enumerate(texts):
            if not PLAIN.fullmatch(t) or any(s in t for s in self.special):
                out[i] = b"".join(
                    np.array(e.ids, self.dtype).tobytes()
                    for p in byte_batches(((0, p) for p in safe_pieces(t, 1 << 15)), 1 << 19)
                    for e in self.tok.encode_batch_fast([x for _, x in p], add_special_tokens=False)
                )
            elif t:
                plain.append(i)
        pieces = ((i, p) for i in plain for p in safe_pieces(texts[i], piece_chars))
        parts: dict[int, list[bytes]] = {}
        for group in byte_batches(pieces, piece_chars):
            for (i, _), ids in zip(group, self._plain([p.encode() for _, p in group])):
                parts.setdefault(i, []).append(ids)
        for i, ids in parts.items():
            out[i] = ids[0] if len(ids) == 1 else b"".join(ids)
        return out


def encoder(path: str) -> CachedEncoder:
    key = ("cached", path)
    if key not in _LOADED:
        _LOADED[key] = CachedEncoder(path)
    return _LOADED[key]


TOKEN_COUNT_SCHEMA = T.StructType().add("doc_id", "long").add("n_tokens", "long")

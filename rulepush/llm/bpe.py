"""Operator 4: exact BPE by dynamic programming over prefixes.

For each prefix of a pre-token there is exactly one token that can end its encoding. Going left to right, all
tokens that end at a position come from an automaton; the one whose predecessor (the last token of the prefix
before it) may stand beside it is stored, and back-pointers from the full word give the ids. Two neighbours may
stand beside each other if no merge across their boundary would have come first; that is tested on the two
merge histories and remembered.

The pre-tokenizer handled is the one of word-level vocabularies with an end-of-word mark (lower case, NFC, white
space dropped); texts with characters outside its well-agreed range are normalised and split by the library.
Null texts are empty: no ids, and the digest of nothing.
"""

from __future__ import annotations

import hashlib
import json
import re
import unicodedata

import ahocorasick
import numpy as np
import pyarrow as pa
import regex

from pyspark.sql import DataFrame

from .common import small_batches
from .tokenization import byte_letters, load, row_slices

_LOADED: dict = {}
#: Stands for the end-of-word mark inside the automaton.
END = "\ue000"
#: Pre-token pattern of this vocabulary (fixed value of the public format).
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
PLAIN = re.compile("[\t\n\r\x20-\x7e\u00a1-\u024f\u0400-\u045f\u2010-\u2027\u20ac]*")


class WordBpe:
    """Exact encoder of single pre-tokens, and of texts through a bounded cache of pre-tokens."""

    def __init__(self, path: str, keep: int = 100_000):
        spec = json.load(open(path, encoding="utf-8"))
        model = spec["model"]
        self.mark = model["end_of_word_suffix"]
        self.vocab: dict[str, int] = model["vocab"]
        self.name = {i: t for t, i in self.vocab.items()}
        self.special = {a["content"]: a["id"] for a in spec["added_tokens"]}
        self.name |= {i: t for t, i in self.special.items()}
        self.tok = load(path)
        self.keep = keep
        self.known: dict[str, tuple[bytes, str]] = {}
        self.letters = byte_letters()
        self.as_letters = dict(enumerate(self.letters))  # for str.translate over Latin-1 decoded bytes
        self.made = [-1] * len(self.name)  # when a token is made: its merge's rank, -1 for single letters
        self.halves: list = [None] * len(self.name)
        self.rank: dict[tuple[int, int], int] = {}
        for rank, pair in enumerate(model["merges"]):
            left, right = pair if isinstance(pair, list) else pair.split(" ")
            a, b = self.vocab[left], self.vocab[right]
            whole = self.vocab[left + right]
            if self.made[whole] >= 0 or rank <= max(self.made[a], self.made[b]):
                raise ValueError("vocabulary with merges that this method can't order")
            self.rank[a, b], self.made[whole], self.halves[whole] = rank, rank, (a, b)
        self.beside: dict[int, bool] = {}
        self._sound: dict[int, bool] = {}
        self.automaton = ahocorasick.Automaton()
        for token, i in self.vocab.items():
            plain = token.removesuffix(self.mark) + END if token.endswith(self.mark) else token
            if self.sound(i):
                self.automaton.add_word(plain, (i, len(plain)))
        self.automaton.make_automaton()
        self.split = regex.compile(WORD_PATTERN).findall
        self.special_split = re.compile("(" + "|".join(map(re.escape, self.special)) + ")").split if self.special else None

    def sound(self, token: int) -> bool:
        """Whether BPE gives the token back for its own letters."""
        if token not in self._sound:
            pair = self.halves[token]
            self._sound[token] = pair is None or self.sound(pair[0]) and self.sound(pair[1]) and self._undisturbed(*pair, self.made[token])
        return self._sound[token]

    def _undisturbed(self, a: int, b: int, until: float) -> bool:
        """Whether no merge joins the inner edges of a and b before each has grown whole; until: when both are used up.

        Goes back in time: the younger of the two edge symbols is undone, until single letters remain.
        """
        used_a = used_b = until
        while True:
            at = self.rank.get((a, b))
            if at is not None and at < used_a and at <= used_b:  # at equal rank the left pair of two overlapping ones comes first
                return False
            made_a, made_b = self.made[a], self.made[b]
            if made_a < 0 and made_b < 0:
                return True
            if made_a > made_b:
                used_a, a = made_a, self.halves[a][1]
            else:
                used_b, b = made_b, self.halves[b][0]

    def compatible(self, a: int, b: int) -> bool:
        key = a << 20 | b
        got = self.beside.get(key)
        if got is None:
            if len(self.beside) > 200_000:
                self.beside.clear()
            got = self.beside[key] = self._undisturbed(a, b, float("inf"))
        return got

    def encode_word(self, word: str) -> list[int]:
        """Ids of one pre-token, given in byte letters without the end mark."""
        n = len(word)
        last = [-1] * (n + 2)  # last[n] stays unused: the last letter and the mark are one symbol
        back = [0] * (n + 2)
        beside, compatible = self.beside, self.compatible
        for end, (token, size) in self.automaton.iter(word + END):
            end += 1
            if end == n or last[end] >= 0:
                continue
            start = end - size
            if start:
                before = last[start]
                if before < 0:
                    continue
                ok = beside.get(before << 20 | token)
                if ok is None:
                    ok = compatible(before, token)
                if not ok:
                    continue
            last[end], back[end] = token, start
        out, at = [], n + 1
        while at:
            out.append(last[at])
            at = back[at]
        return out[::-1]

    def _learn(self, words: list[str]) -> None:
        """All these words; the cache is emptied before it outgrows its bound, never between learning and use."""
        if len(self.known) > self.keep:
            self.known.clear()
        for w in {w for w in words if w not in self.known}:
            ids = self.encode_word(w.encode().decode("latin-1").translate(self.as_letters))
            self.known[w] = (np.array(ids, "<u4").tobytes(), " ".join(map(self.name.__getitem__, ids)))

    def words(self, text: str) -> list[str]:
        """Pre-tokens of a text without special strings, as normalised characters."""
        if PLAIN.fullmatch(text):
            return self.split((text if text.isascii() else unicodedata.normalize("NFC", text)).lower())
        back = {c: b for b, c in enumerate(self.letters)}
        return [bytes(back[c] for c in w).decode() for w, _ in self.tok.pre_tokenizer.pre_tokenize_str(self.tok.normalizer.normalize_str(text))]

    def encode(self, text: str) -> tuple[bytes, str]:
        """Ids of a whole text as unsigned 32-bit little-endian bytes, and the decoded text."""
        ids, said = [], []
        parts = self.special_split(text) if self.special_split and "<|" in text else [text]
        known = self.known
        for part in parts:
            if part in self.special and len(parts) > 1:
                ids.append(np.array([self.special[part]], "<u4").tobytes())
                said.append(part)
                continue
            words = self.words(part)
            try:
                got = list(map(known.__getitem__, words))
            except KeyError:
                self._learn(words)
                got = list(map(known.__getitem__, words))
            ids += [g[0] for g in got]
            said += [g[1] for g in got]
        return b"".join(ids), " ".join(said)

    def decode(self, ids) -> str:
        """Token strings joined by blanks: this vocabulary's file names no decoder, and the library then does the same."""
        return " ".join(map(self.name.__getitem__, ids))


def word_bpe(path: str) -> WordBpe:
    if path not in _LOADED:
        _LOADED[path] = WordBpe(path)
    return _LOADED[path]


def encode_decode(docs: DataFrame, tokenizer: str) -> DataFrame:
    """Rows of docs(doc_id, text) as (doc_id, n_tokens, ids binary, decoded string)."""
    small_batches(docs.sparkSession)

    def run(batches):
        bpe = word_bpe(tokenizer)
        for batch in batches:
            for at, n in row_slices(batch.column(1), 2 << 20):
                got = [bpe.encode(t or "") for t in batch.column(1).slice(at, n).to_pylist()]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(at, n), pa.array([len(g[0]) // 4 for g in got], pa.int64()), pa.array([g[0] for g in got], pa.binary()), pa.array([g[1] for g in got], pa.string())],
                    ["doc_id", "n_tokens", "ids", "decoded"],
                )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids binary, decoded string")


def encode_digests(docs: DataFrame, tokenizer: str) -> DataFrame:
    """Operator 4's query: (doc_id, n_tokens, ids_sha256, decoded_sha256), digested where the ids are made."""
    small_batches(docs.sparkSession)

    def run(batches):
        bpe = word_bpe(tokenizer)
        sha = lambda x: hashlib.sha256(x).hexdigest()
        for batch in batches:
            for at, n in row_slices(batch.column(1), 2 << 20):
                rows = []
                for t in batch.column(1).slice(at, n).to_pylist():
                    ids, said = bpe.encode(t or "")
                    rows.append((len(ids) // 4, sha(ids), sha(said.encode())))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(at, n), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows]), pa.array([r[2] for r in rows])],
                    ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
                )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")

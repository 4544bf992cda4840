"""Removal of repeated strings against all strings of plain texts, where overlaps, hot groups and cuts matter."""

import hashlib
import random

import numpy as np
import pytest

from rulepush.llm import suffixes


def plain(texts, length):
    """(n_bytes, n_removed, n_spans, digest of the rest) of texts in doc_id order."""
    seen, out = set(), {}
    for i, t in enumerate(texts):
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for p in range(len(b) - length + 1):
            if b[p : p + length] in seen:
                gone[p : p + length] = True
            seen.add(b[p : p + length])
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out[i] = (len(b), int(gone.sum()), runs, hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~gone])).hexdigest())
    return out


def corpus(seed, n=120):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdeé ") for _ in range(r.randint(2, 7)))
    prose = lambda k: " ".join(word() for _ in range(k))
    common = [prose(r.choice([16, 20, 25, 40, 80])) for _ in range(6)]
    texts = []
    for _ in range(n):
        parts = [prose(r.randint(0, 20))]
        for _ in range(r.randint(0, 3)):
            p = r.choice(common)
            lo = r.randint(0, len(p) // 2) if r.random() < 0.5 else 0
            parts += [p[lo : r.randint(len(p) // 2, len(p))] if r.random() < 0.5 else p[lo:], prose(r.randint(0, 4))]
        texts.append("".join(parts))
    return [*texts, texts[3], "ab" * 400, "x" * 700, None, ""]


def got(df):
    return {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in df.collect()}


@pytest.mark.parametrize("hottest", [suffixes.HOT, 3, 0])
def test_overlapping_passages(spark, hottest):
    """Groups that suffix arrays settle, hot ones, and both."""
    texts = corpus(7)
    want = plain(texts, 100)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(5)
    assert got(suffixes.digests(docs, 100, hottest)) == want
    assert sum(w[1] > 0 for w in want.values()) > 40


def test_the_tree_decides(spark, monkeypatch):
    """Without the intervals of the tree, repeats at the edges of passages stay."""
    texts = corpus(7)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(5)
    first = suffixes.copies(suffixes.runs(docs, 100), 100, 4).filter("key IS NULL")
    removed = {}
    for r in first.collect():
        removed.setdefault(r["doc_id"], set()).update(range(r["start"], r["stop"]))
    want = plain(texts, 100)
    assert any(len(removed.get(i, ())) < w[1] for i, w in want.items())
    assert all(len(removed.get(i, ())) <= w[1] for i, w in want.items())


def test_texts_past_every_cut(spark):
    """Texts longer than the parts hashed at once, with repeats across the cuts, and arrays that are filled many times."""
    r = random.Random(2)
    block = "".join(r.choice("abcdefgh ") for _ in range(300_000))
    texts = [block * 4, "q" + block[1000:2000], block[: 1 << 17] + "z" * 50 + block[5:]]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert got(suffixes.digests(docs, 100)) == plain(texts, 100)


def test_arrays_filled_many_times(spark, monkeypatch):
    """Groups that fill an array each: what copies and trees remove together is what must go, byte by byte."""
    texts = corpus(9, 60)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    rows = suffixes.saved(suffixes.copies(suffixes.runs(docs, 100), 100, 4), "spans")
    monkeypatch.setattr(suffixes, "_PART", 1)
    found = suffixes.repeats_in_groups(suffixes.pieces(suffixes.with_text(docs, rows)), 100, 2).collect()
    assert found
    gone = {i: set() for i in range(len(texts))}
    for d, a, b, _ in [*found, *rows.filter("key IS NULL").collect()]:
        gone[d].update(range(a, b))
    assert {i: len(x) for i, x in gone.items()} == {i: w[1] for i, w in plain(texts, 100).items()}

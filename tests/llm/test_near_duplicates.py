"""Near-duplicate classes against all pairs compared in plain Python."""

import math
import random
import sys
from collections import Counter, defaultdict

import numpy as np
import pytest

from rulepush.llm import neardup


def plain_links(texts, threshold):
    """Pairs of weighted Jaccard similarity >= threshold over 5-word shingles, from the definition."""
    bags = {}
    for i, t in texts.items():
        w = (t or "").lower().split()
        if w:
            k = min(5, len(w))
            bags[i] = Counter(tuple(w[j : j + k]) for j in range(len(w) - k + 1))
    df = Counter(s for b in bags.values() for s in b)
    n, floor = len(texts), neardup.FLOOR
    idf = {s: round(neardup.UNIT * (1 + math.log(1 / min(max(c / n, floor), 1)) / (2 * math.log(1 / floor)))) for s, c in df.items()}
    at = defaultdict(set)
    for i, b in bags.items():
        for s in b:
            at[s].add(i)
    pairs = {(a, b) for g in at.values() for a in g for b in g if a < b}
    out = set()
    for a, b in pairs:
        low = sum(min(bags[a][s], bags[b][s]) * idf[s] for s in bags[a])
        high = sum(c * idf[s] for i in (a, b) for s, c in bags[i].items()) - low
        if low >= threshold * high:
            out.add((a, b))
    return out


def classes_of(ids, links):
    of = {i: i for i in ids}

    def find(i):
        while of[i] != i:
            i = of[i]
        return i

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        of[b] = a
    return {i: find(i) for i in ids}


def corpus(seed):
    r = random.Random(seed)
    words = [f"w{i}" for i in range(400)]
    texts = []
    for _ in range(40):
        base = [r.choice(words) for _ in range(r.randint(30, 200))]
        texts.append(" ".join(base))
        for _ in range(r.choice([0, 0, 1, 2, 8])):
            copy = base[:]
            for _ in range(r.choice([0, 0, 1, 2, 3, 6, 12])):
                copy[r.randrange(len(copy))] = r.choice(words)
            texts.append(" ".join(copy))
    r.shuffle(texts)
    return dict(enumerate([*texts, None, "", " \n", "one two", "one two"]))


@pytest.mark.parametrize("seed", [1])
def test_classes_against_all_pairs(spark, seed):
    texts = corpus(seed)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(3)
    links = plain_links(texts, 0.8)
    want = classes_of(texts, links)
    got = {r["doc_id"]: r["class_id"] for r in neardup.classes(docs).collect()}
    assert set(got) == set(texts)
    caught = sum(got[a] == got[b] for a, b in links)
    assert caught >= 0.97 * len(links) > 20
    assert all(want[i] == want[c] for i, c in got.items())  # nothing is joined that links don't join


def test_outliers_of_a_pivot(spark):
    """Members far from their pivot, and near each other, in few bands: only the last step can join them."""
    r = random.Random(4)
    words = [f"v{i}" for i in range(300)]
    base = [r.choice(words) for _ in range(120)]
    texts = {0: " ".join(base)}
    for i in range(1, 60):
        copy = base[:]
        for _ in range(r.randint(2, 9)):
            copy[r.randrange(len(copy))] = r.choice(words)
        texts[i] = " ".join(copy)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    links = plain_links(texts, 0.8)
    want = classes_of(texts, links)
    got = {x["doc_id"]: x["class_id"] for x in neardup.classes(docs, bands=64, rows=2).collect()}
    assert got == want and len(set(want.values())) > 1


def test_open_links_in_blocks(spark):
    """The members of a pivot, one to a block, give the same links as in one block."""
    vec = lambda on: (np.arange(20, dtype="<u4")[on].tobytes(), np.full(len(on), 64, "<u2").tobytes(), 64 * len(on))
    rows = {0: list(range(10)), 1: list(range(2, 14)), 2: list(range(3, 14)), 3: list(range(10)) + [19], 4: list(range(4, 16))}
    vectors = spark.createDataFrame([(i, *vec(on)) for i, on in rows.items()], "doc_id long, hashes binary, weights binary, total long")
    star = spark.createDataFrame([(0, i) for i in rows if i], "pivot long, doc_id long")
    known = neardup.verified(star.selectExpr("pivot AS a", "doc_id AS b"), vectors).cache()
    root = spark.createDataFrame([(3, 0), (0, 0)], "id long, root long")
    sim = lambda a, b: len(set(rows[a]) & set(rows[b])) / len(set(rows[a]) | set(rows[b]))
    assert {(x["a"], x["b"]): x["similarity"] for x in known.collect()} == {(0, i): pytest.approx(sim(0, i)) for i in rows if i}
    want = {(a, b) for a in rows for b in rows if 0 < a < b and a != 3 and b != 3 and sim(a, b) >= 0.7}
    for size in (1, 1 << 20):
        got = neardup.open_links(star, known, root, vectors, 0.7, block_bytes=size)
        assert {(x["a"], x["b"]) for x in got.collect()} == want != set()


def test_repeated_ids_and_odd_rows(spark):
    text = " ".join(f"x{i}" for i in range(60))
    rows = [(1, text, 0), (1, "another text of the same id that is long enough", 1), (2, text, 2), (2, text, 3), (None, text, 4), (3, None, 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, class_id long")
    got = sorted(((x["doc_id"] or -1), x["class_id"]) for x in neardup.classes(docs).collect())
    assert [i for i, _ in got] == [-1, 1, 1, 2, 2, 3] and dict(got)[3] == 3 and dict(got)[-1] is None
    assert got == sorted(((x["doc_id"] or -1), x["class_id"]) for x in neardup.classes(docs.repartition(5)).collect())


def test_a_text_of_many_shingles():
    """Places in a key need more room in texts of over 2**24 shingles; ties give way."""
    r = np.random.default_rng(0)
    h = np.unique(r.integers(1, 1 << 63, (1 << 24) + 10, dtype=np.uint64))
    w = np.full(len(h), neardup.USUAL)
    drawn = neardup.Sampler(2).sample(h, w, np.array([0]))
    half = neardup.Sampler(2).sample(h[: 1 << 22], w[: 1 << 22], np.array([0]))
    assert drawn.shape == half.shape == (1, 2)


def test_shingles_of_many_texts_at_once():
    """Words are those of lower().split(), shingles stay within their text, and no work in Python is done by the word."""
    odd = [None, "", " \n", "A b", "a B", "one two three four five", "x " * 40, "\x1c\x1dtabs\tand\vlines\n\x1fend\x00nul \x7f", "ÉCOLE İstanbul\u0085ΣΑΣ lone\ud800 x", "eightby8 sixteenbytes1234 seventeenbytes123 seventeenbytes124 ab\0"]
    texts = [*odd, *corpus(3).values(), "a tail of", None]
    want = [Counter(tuple(w[j : j + 5]) for j in range(max(len(w) - 4, 1))) if w else Counter() for w in ((t or "").lower().split() for t in texts)]
    h, tf, sizes = neardup.shingled(texts)
    assert sizes.tolist() == [len(c) for c in want] and len(set(h.tolist())) == len({s for c in want for s in c})
    ends = np.cumsum(sizes)
    for t, c, s, e in zip(texts, want, ends - sizes, ends):
        alone = neardup.shingled([t])
        assert np.array_equal(alone[0], h[s:e]) and np.array_equal(alone[1], tf[s:e]) and (np.diff(h[s:e].astype(object)) > 0).all()
        assert sorted(tf[s:e].tolist()) == sorted(c.values())

    def calls(n):
        made = [0]

        def count(frame, event, arg):
            made[0] += event in ("call", "c_call")

        many = [" ".join(f"w{i * n + j:06}" for j in range(n)) for i in range(20)]
        sys.setprofile(count)
        try:
            neardup.shingled(many)
        finally:
            sys.setprofile(None)
        return made[0]

    assert calls(2000) == calls(100)


def test_sampler_draws_the_least_of_each_hash():
    """Every draw is the shingle and level of least ln a, from the definition, with blocks of any size."""
    r = np.random.default_rng(5)
    sizes = [1, 3, 400, 1, 50, 900, 2]
    h = r.integers(1, 1 << 63, sum(sizes), dtype=np.uint64)
    w = np.where(r.random(len(h)) < 0.7, neardup.USUAL, r.choice([64, 80, 192, 960], len(h)))
    w[:4] = 64, neardup.USUAL, 64, neardup.USUAL
    starts = np.cumsum(sizes) - sizes
    sampler = neardup.Sampler(40)
    drawn = sampler.sample(h, w, starts)
    for block in (1, 64, 1000):
        sampler.BLOCK = block
        assert np.array_equal(sampler.sample(h, w, starts), drawn)
    mixed = neardup.mix64(h)
    for k in range(40):
        at = (mixed * sampler.multiply[k]) >> np.uint64(64 - sampler.BITS)
        at = at.astype(np.int64)
        t = np.floor(np.log(w / neardup.UNIT).astype(np.float32) / sampler.r[k, at] + sampler.beta[k, at])
        ln_a = sampler.log_c[k, at] - sampler.r[k, at] * (t - sampler.beta[k, at]) - sampler.r[k, at]
        for d, (s, n) in enumerate(zip(starts, sizes)):
            least = np.nonzero(ln_a[s : s + n] == ln_a[s : s + n].min())[0] + s
            can = neardup.mix64(mixed[least] + neardup._MIX * t[least].astype(np.int64).view(np.uint64))
            assert drawn[d, k] in can

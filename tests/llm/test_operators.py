"""Small tables with nulls, empty and long texts, repeated rows and clashing columns, against brute force."""

import hashlib
import math
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from rulepush.llm import bpe, lines, mixing, neardup, ngram, records, rules, suffixes, tokenization, vafile
from rulepush.llm.common import scratch

BYTE, WORD = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")
_R = random.Random(3)
WORDS = ["".join(_R.choice(["on", "th", "er", "é", "ß"]) for _ in range(_R.randint(1, 4))) for _ in range(200)]
PROSE = [" ".join(_R.choice(WORDS) for _ in range(n)) for n in (3, 80, 120, 200, 90)]
TEXTS = [
    None, "", " \n\t ", "a", "<|endoftext|> x <|startoftext|>Y", "It's 12½ ΌΣ İ 漢字 😀 \x1c\x85 don't", "x" * 3000, "ab " * 2000, *PROSE, PROSE[1], PROSE[2] + " end",
    "intro words here " + PROSE[3] + " tail", "line one of five words\nline one of five words\nshort\nshort", "LINE one  of five words\nother", PROSE[4][:150] + PROSE[4][:150],
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, n_tokens string, size string"


def rows_of(texts=TEXTS):
    return [(i, t, "en" if i % 2 else None, ["a", "b", None, "c"][i % 4], None, "clash", "clash") for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows_of(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def got(df, *cols):
    return {r["doc_id"]: tuple(r[c] for c in cols) for r in df.collect()}


def test_token_counts(docs, empty):
    tok = Tokenizer.from_file(BYTE)
    want = {i: (len((t or "").encode()), len(tok.encode(t or "", add_special_tokens=False).ids)) for i, t in enumerate(TEXTS)}
    assert got(tokenization.count_tokens(docs, BYTE, piece_chars=50), "n_bytes", "n_tokens") == want
    assert tokenization.count_tokens(empty, BYTE).collect() == []


def test_records(spark, docs, empty):
    tok = Tokenizer.from_file(BYTE)
    at, want = 0, {}
    for i, t in enumerate(TEXTS):
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 2]
        want[i] = (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)
    assert got(records.token_records(docs, BYTE), "start", "n_tokens", "ids_crc32") == want
    assert records.token_records(empty, BYTE).collect() == []
    path = scratch(spark, "records")
    records.write_records(docs, path, BYTE)
    some = records.read_records(spark, path, want=docs.filter("doc_id in (3, 5)")).collect()
    assert {r["doc_id"]: len(records.ids_of(bytes(r["ids"]))) for r in some} == {i: want[i][1] for i in (3, 5)}


def test_checksums():
    assert records.crc32c([b"123456789", b"", b"ab"]).tolist()[0] == 0xE3069283
    framed = bytearray(records.frame([b"hello there"])[0])
    assert records.unframe(bytes(framed)) == b"hello there"
    framed[14] ^= 1
    with pytest.raises(ValueError):
        records.unframe(bytes(framed))


def test_bpe(docs, empty):
    tok = Tokenizer.from_file(WORD)
    want = {}
    for i, t in enumerate(TEXTS):
        ids = tok.encode(t or "", add_special_tokens=False).ids
        want[i] = (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(tok.decode(ids, skip_special_tokens=False).encode()).hexdigest())
    assert got(bpe.encode_digests(docs, WORD), "n_tokens", "ids_sha256", "decoded_sha256") == want
    small = bpe.WordBpe(WORD, keep=5)
    assert [small.encode(t or "")[0] for t in TEXTS] == [bpe.word_bpe(WORD).encode(t or "")[0] for t in TEXTS]
    assert bpe.encode_digests(empty, WORD).collect() == []


def test_mix(spark, docs, empty):
    out = mixing.mix(docs).collect()
    sizes = {i: len(rules._WORDS(t or "")) for i, t in enumerate(TEXTS)}
    assert {r["doc_id"]: r["size"] for r in out} == sizes
    assert all(0 <= r["taken"] <= 3 * r["size"] for r in out)
    total = sum(sizes.values())
    targets = {r["doc_id"] % 4: r["target"] for r in out}
    assert abs(sum(targets.values()) - total) < 1e-6 * total
    for s, t in targets.items():
        assert abs(sum(r["taken"] for r in out if r["doc_id"] % 4 == s) - t) <= 0.05 * total
    assert mixing.mix(empty).collect() == []
    assert mixing.mixed_documents(docs).columns == docs.columns


def test_apportionment(spark):
    rng = random.Random(1)
    for seats in (0, 1, 7, 100, 1001):
        w = [rng.randint(1, 1000) for _ in range(9)]
        df = spark.createDataFrame([("g", i, x, seats) for i, x in enumerate(w)], "g string, i int, w long, seats long")
        have = {r["i"]: r["n"] for r in mixing.apportion(df, ["g"], "w", "seats", "n").collect()}
        s = [0] * 9
        for _ in range(seats):
            j = max(range(9), key=lambda k: w[k] / (2 * s[k] + 1))
            s[j] += 1
        assert sum(have.values()) == seats and all(abs(have[i] - s[i]) <= (1 if w.count(w[i]) > 1 else 0) for i in range(9))


def test_quality_rules(spark, docs, empty):
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(len(TEXTS))], "doc_id long, quality int, toxic int")
    out = rules.quality_rules(docs, labels).collect()
    assert len(out) == len(TEXTS) and all(not r["kept"] for r in out if r["base_failed"])
    assert rules.quality_rules(empty, labels.limit(0)).collect() == []
    x = np.array([[i, i % 7] for i in range(400)], float)
    y = (x[:, 0] > 250) & (x[:, 1] <= 3)
    learned = rules.learn(np.pad(x, ((0, 0), (0, 7))), y)
    hit = np.zeros(400, bool)
    for r in learned:
        hit |= rules._holds(x, r)
    assert (hit == y).mean() > 0.97


def test_quality_model(spark, docs, empty):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert ngram.judged(docs, none).filter("_kept").count() == len(TEXTS)
    good = spark.createDataFrame([(i, 1, 0) for i in range(8, 13)], "doc_id long, quality int, toxic int")
    kept = {r["doc_id"] for r in ngram.judged(docs, good).filter("_kept").select("doc_id").collect()}
    assert set(range(8, 13)) <= kept and 6 not in kept
    model = ngram.train(docs.filter("doc_id between 8 and 12"))
    p = np.exp(model.log_p.reshape(-1, model.alphabet).astype(float)).sum(1)
    assert np.allclose(p, 1, atol=1e-3)
    assert ngram.judged(empty, good).collect() == []


def test_top_k(spark):
    rng = np.random.default_rng(0)
    v = [(i, [float(x) for x in rng.normal(size=6)]) for i in range(300)]
    v += [(1000 + i, v[5][1]) for i in range(40)] + [(2000, None), (2001, [None] * 6), (2002, [float("nan")] * 6), (5, v[5][1])]
    df = spark.createDataFrame(v, "vec_id long, embedding array<float>")
    asked = df.filter("vec_id % 50 = 0").selectExpr("vec_id AS query_id", "embedding")
    f = lambda e: np.floor(np.array(e, np.float32).astype(np.float64) * 1024).astype(int)
    good = [(i, f(e)) for i, e in v if e is not None and None not in e and np.isfinite(e).all()]
    want = {(q, k + 1, s[1], -s[0]) for q, e in good if q % 50 == 0 for k, s in enumerate(sorted((-int(e @ x), i) for i, x in good if i != q)[:10])}
    assert {tuple(r) for r in vafile.top_k(df, asked, block=64, query_block=3).collect()} == want
    assert vafile.top_k(df.limit(0), asked).collect() == [] == vafile.top_k(df, asked.limit(0)).collect()


def plain_top_k(v, is_query, k=10):
    """(query_id, rank, vec_id, score) in whole numbers; shorter vectors end in zeros."""
    good = [(i, [math.floor(x * 1024) for x in e]) for i, e in v if i is not None and e is not None and all(x is not None and math.isfinite(x) for x in e)]
    score = lambda a, b: sum(x * y for x, y in zip(a, b))
    return sorted((q, n + 1, i, -s) for q, e in good if is_query(q) for n, (s, i) in enumerate(sorted((-score(e, x), i) for i, x in good if i != q)[:k]))


@pytest.mark.parametrize("size", [1.0, 1e6])
def test_top_k_of_odd_vectors(spark, size):
    r = random.Random(7)
    v = [(i, [r.choice([0.0, 1.0, -1.0, r.uniform(-1, 1) * size]) for _ in range(r.choice([0, 1, 3, 5]))]) for i in range(120)]
    v += [(200, [1.0, 0.0]), (201, [3e6, 0.0]), (202, [1.0, 1.0]), (None, [1.0]), (203, [float("inf")])]
    v += [(i, v[40][1]) for i in (300, 310, 320, 330)] + [v[20]] * 4 + [(40, [2.0, 2.0])]  # common vectors, repeated rows, one id with two vectors
    df = spark.createDataFrame(v, "vec_id long, embedding array<double>").repartition(3)
    asked = df.filter("vec_id % 20 = 0").selectExpr("vec_id AS query_id", "embedding")
    for options in ({}, {"block": 7, "query_block": 4, "bits": 2}):
        got = sorted(tuple(x) for x in vafile.top_k(df, asked, **options).collect())
        assert got == plain_top_k(v, lambda i: i % 20 == 0)


def test_top_k_overflow(spark):
    df = spark.createDataFrame([(0, [1e30]), (1, [1.0])], "vec_id long, embedding array<double>")
    with pytest.raises(Exception, match="2\\*\\*62"):
        vafile.top_k(df, df.selectExpr("vec_id AS query_id", "embedding")).collect()


def test_near_duplicates(docs, empty):
    out = {r["doc_id"]: r["class_id"] for r in neardup.classes(docs).collect()}
    assert out[13] == out[9] and out[14] == out[10] and out[0] == 0 and out[1] == 1 and out[2] == 2
    assert len({out[i] for i in range(8, 13)}) == 5
    assert sorted(r["doc_id"] for r in neardup.one_of_each(docs).collect()) == sorted(i for i, c in out.items() if i == c)
    assert neardup.classes(empty).collect() == []


def test_sampler_estimates_similarity():
    rng = np.random.default_rng(0)
    u = np.unique(rng.integers(1, 1 << 63, 300, dtype=np.uint64))
    wa, ka, kb = rng.choice([96, 96, 96, 192, 70], len(u)), rng.random(len(u)) < 0.9, rng.random(len(u)) < 0.9
    wb = np.where(rng.random(len(u)) < 0.8, wa, 288)
    a, b = (u[ka], wa[ka]), (u[kb], wb[kb])
    drawn = neardup.Sampler(3000).sample(np.concatenate([a[0], b[0]]), np.concatenate([a[1], b[1]]), np.array([0, len(a[0])]))
    assert abs((drawn[0] == drawn[1]).mean() - neardup.similarity(*a, *b)) < 0.04


def test_lines(docs, empty):
    out = {r["doc_id"]: r for r in lines.dedup(docs, lines.LINE, 10).collect()}
    assert out[16]["text"] == "line one of five words\nshort\nshort" and out[17]["text"] == "other" and out[0]["text"] is None
    raw = TEXTS[16].encode()
    assert [raw[s["start"] : s["end"]].decode() for s in out[16]["removed_spans"]] == ["line one of five words\n"]
    assert out[13]["text"] == "" and out[9]["text"] == PROSE[1]
    assert lines.dedup(empty).collect() == []


def test_repeated_strings(spark, docs, empty):
    for length in (100, 40):
        seen, want = set(), {}
        for i, t in enumerate(TEXTS):
            b = (t or "").encode()
            gone = np.zeros(len(b), bool)
            for p in range(len(b) - length + 1):
                if b[p : p + length] in seen:
                    gone[p : p + length] = True
                seen.add(b[p : p + length])
            keep = bytes(np.frombuffer(b, np.uint8)[~gone])
            want[i] = (len(b), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(keep).hexdigest())
        assert got(suffixes.digests(docs, length), "n_bytes", "n_removed", "n_spans", "kept_sha256") == want
    assert suffixes.digests(empty).collect() == []
    clash = docs.selectExpr("doc_id", "text", "1 AS spans", "2 AS i", "3 AS _spans", "4 AS _id")
    assert suffixes.dedup(clash).columns == clash.columns and suffixes.dedup(clash).count() == len(TEXTS)
    nameless = spark.createDataFrame([(None, "z" * 500), (1, "z" * 50)], "doc_id long, text string")
    assert {r["n_removed"] for r in suffixes.digests(nameless).collect()} == {0}
    assert suffixes.dedup(docs).columns == docs.columns


def test_maximal_repeats():
    rng = random.Random(1)
    for _ in range(60):
        ts = [bytes(rng.choice(b"ab") for _ in range(rng.randint(0, 12))) for _ in range(rng.randint(1, 4))]
        least = rng.randint(1, 4)
        occ = {}
        for i, t in enumerate(ts):
            for a in range(len(t)):
                for b in range(a + least, len(t) + 1):
                    occ.setdefault(t[a:b], []).append((i, a))
        want = set()
        for k, o in occ.items():
            left = {ts[i][a - 1] if a else (i, "s") for i, a in o}
            right = {ts[i][a + len(k)] if a + len(k) < len(ts[i]) else (i, "e") for i, a in o}
            if len(o) > 1 and len(left) > 1 and len(right) > 1:
                want.add((len(k), tuple(sorted(o))))
        assert {(n, tuple(o)) for n, o in suffixes.repeats_of(ts, least)} == want

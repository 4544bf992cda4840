"""Mix, quality rules, the pipeline and odd rows, against plain Python."""

import hashlib
import random
import re
from collections import Counter

import corpus_pipeline
import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from rulepush.llm import bpe, mixing, neardup, records, rules, suffixes, tokenization
from rulepush.llm.common import scratch
from test_near_duplicates import classes_of, plain_links
from test_repeats import plain as plain_repeats

BYTE, WORD = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")


def plain_targets(sizes):
    """Words of each source by weights 5, 2, 1 in code point order, null last, none above 3 times its size."""
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    total, capped = sum(sizes.values()), {}
    while True:
        free = [s for s in names if s not in capped]
        left = total - sum(capped.values())
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        over = [s for s in free if share[s] > 3 * sizes[s]]
        if not over:
            return capped | share
        capped |= {s: 3.0 * sizes[s] for s in over}


@pytest.mark.parametrize("seed", [1, 2])
def test_mix_targets(spark, seed):
    r = random.Random(seed)
    sources = [None, "a", "B", "é", "z", "", "hot"]
    rows = [(i, " ".join(["w"] * r.choice([0, 1, 5, 40, 300])), r.choice(sources + ["hot"] * 8)) for i in range(500)]
    rows += [(7, "one two three", "z"), (7, "one two three four", "z"), (None, "x " * 50, "a"), (None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(4)
    got = mixing.mix(docs).collect()
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    assert Counter((x["doc_id"], x["size"]) for x in got) == Counter((i, size(t)) for i, t, _ in rows)
    per = Counter()
    for _, t, s in rows:
        per[s] += size(t)
    want = plain_targets(per)
    told = {round(x["target"], 6) for x in got}
    assert told == {round(x, 6) for x in want.values()}
    assert {(x["source_size"], round(x["target"], 6)) for x in got} == {(per[s], round(want[s], 6)) for s in per}
    for s in per:
        taken = sum(x["taken"] for x in got if (x["source_size"], round(x["target"], 6)) == (per[s], round(want[s], 6)))
        assert abs(taken - want[s]) <= max(130, 0.02 * want[s])
    assert all(0 <= x["taken"] <= 3 * x["size"] for x in got)
    again = mixing.mix(docs.repartition(9)).collect()
    assert sorted(map(repr, again)) == sorted(map(repr, got))


def test_mixed_rows_of_one_id(spark):
    """Texts that share an id are told apart; columns may have any name."""
    rows = [(1, "a b c", "s", 1, 2), (1, " ".join(["w"] * 90), "s", 3, 4), (2, None, None, 5, 6), (None, "x y", "t", 7, 8)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, _id long, copies long")
    out = mixing.mixed_documents(docs)
    assert out.columns == docs.columns
    got = Counter(tuple(x) for x in out.collect())
    assert set(got) <= set(rows) and max(got.values()) <= 3
    assert mixing.mixed_documents(docs.limit(0)).collect() == []


def plain_statistics(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    hit = {j for i in range(len(words) - 2) if windows[tuple(words[i : i + 3])] > 1 for j in range(i, i + 3)}
    repeated = sum(x in lines[:i] for i, x in enumerate(lines))
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), repeated, len(hit)


def odd_texts(seed):
    r = random.Random(seed)
    word = lambda: r.choice(["a", "bb", "Ωß", "漢字", "#x|", "<>", "&", "10%", "ab c", "\x1c"])
    texts = [r.choice(["", " "]).join(word() + r.choice([" ", "\n", "\t", "\x0b", " \n \n"]) for _ in range(r.choice([0, 3, 60, 200]))) for _ in range(60)]
    return [*texts, None, "", " \n\t", "x y z " * 40_000, "line\n" * 3 + "\n" * 50]


def test_quality_rule_columns(spark):
    texts = odd_texts(4)
    docs = spark.createDataFrame([(i, t, "c") for i, t in enumerate(texts)] + [(None, "null id " * 30, "c")], "doc_id long, text string, kept string").repartition(3)
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(0, 60)] + [(3, None, 0), (5, 0, 0), (None, 1, 0)], "doc_id long, quality int, toxic int")
    got = {x["doc_id"]: x for x in rules.quality_rules(docs, labels).collect()}
    assert len(got) == len(texts) + 1
    for i, t in enumerate(texts):
        x, want = got[i], plain_statistics(t)
        assert (x["n_words"], x["word_chars"], x["n_symbols"], x["n_dup_lines"], x["n_repeat_words"]) == want, i
        failed = want[0] < 50 or 100 * want[4] > 50 * want[0]
        assert x["base_failed"] == failed and (not failed or not x["kept"])
    twice = docs.unionByName(docs.limit(9).selectExpr("doc_id", "text", "kept"))
    assert rules.quality_rules(twice, labels).count() == len(texts) + 10


def test_long_texts_and_odd_ids(spark):
    """Texts past the slices of the encoders, repeated and null ids."""
    r = random.Random(6)
    long = "".join(r.choice(["the ", "Über", "漢字", "  ", "\n", "don't ", "x1 ", "😀", "<|endoftext|>"]) for _ in range(60_000))
    rows = [(1, long), (1, "short"), (None, "no id"), (2, "é" * 70_000), (3, None), (1, "short"), (4, "ab " * 90_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(2)
    byte, word = Tokenizer.from_file(BYTE), Tokenizer.from_file(WORD)
    n = lambda tok, t: len(tok.encode(t or "", add_special_tokens=False).ids)
    assert Counter((x["doc_id"], x["n_tokens"]) for x in tokenization.count_tokens(docs, BYTE).collect()) == Counter((i, n(byte, t)) for i, t in rows)
    assert Counter((x["doc_id"], x["n_tokens"]) for x in bpe.encode_digests(docs, WORD).collect()) == Counter((i, n(word, t)) for i, t in rows)
    path = scratch(spark, "records")
    records.write_records(docs, path, BYTE)
    back = records.read_records(spark, path).collect()
    want = Counter((i, tuple([*byte.encode(t or "", add_special_tokens=False).ids, 2])) for i, t in rows)
    assert Counter((x["doc_id"], tuple(records.ids_of(bytes(x["ids"])))) for x in back) == want
    got = records.token_records(docs, BYTE).collect()
    ends = sorted((x["start"], x["start"] + x["n_tokens"]) for x in got)
    assert ends[0][0] == 0 and all(a[1] == b[0] for a, b in zip(ends, ends[1:])) and len(got) == len(rows)


def prose(r, words, n):
    return " ".join(r.choice(words) for _ in range(n)) + "."


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    """Documents with junk, copies, near copies and shared passages, and labels of some."""
    r = random.Random(8)
    words = ["".join(r.choice(["on", "th", "er", "an", "ing", "re", "st", "a", "i"]) for _ in range(r.randint(1, 4))) for _ in range(400)]
    passage = prose(r, words, 60)
    texts = [prose(r, words, r.randint(60, 160)) for _ in range(60)]
    texts += [texts[3], texts[3], texts[5] + " more", texts[6].replace(" ", "  ", 1)]
    texts += [prose(r, words, 40) + " " + passage + " " + prose(r, words, 40) for _ in range(6)]
    texts += ["".join(r.choice("~^☃☄§%$#@{}[]0x") for _ in range(400)) for _ in range(5)] + [None, ""]
    junk = range(70, 75)
    rows = [(i, t, "en" if i % 3 else None, ["s1", "s2", None][i % 3], len(t) if t is not None else None) for i, t in enumerate(texts)]
    folder = str(tmp_path_factory.mktemp("tables"))
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(0, 50)] + [(70, 0, 1)], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return folder, {x[0]: x for x in rows}, set(junk)


def test_pipeline(spark, tables):
    folder, rows, junk = tables
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    good = corpus_pipeline.saved(stages["quality_classifier"](spark, docs, folder), "t")
    kept = {x["doc_id"]: tuple(x) for x in good.collect()}
    assert good.columns == docs.columns and not junk & set(kept) and set(kept) | junk == set(rows) and all(kept[i] == rows[i] for i in kept)

    one = corpus_pipeline.saved(stages["near_duplicates"](spark, good, folder), "t")
    left = {x["doc_id"]: tuple(x) for x in one.collect()}
    texts = {i: x[1] for i, x in kept.items()}
    classes = classes_of(texts, plain_links(texts, 0.8))
    assert one.columns == docs.columns and {i for i, c in classes.items() if i == c} == set(left)

    cut = corpus_pipeline.saved(stages["repeated_strings"](spark, one, folder), "t")
    got = {x["doc_id"]: x for x in cut.collect()}
    ids = sorted(left)
    want = dict(zip(ids, plain_repeats([left[i][1] for i in ids], 100).values()))
    assert cut.columns == docs.columns and set(got) == set(left)
    for i in ids:
        t = got[i]["text"]
        assert (t is None) == (left[i][1] is None) and got[i]["n_chars"] == (None if t is None else len(t))
        assert hashlib.sha256((t or "").encode()).hexdigest() == want[i][3]  # ASCII here: no character is split
    assert sum(w[1] > 0 for w in want.values()) >= 5

    mixed = corpus_pipeline.saved(stages["source_mix"](spark, cut, folder), "t")
    times = Counter(x["doc_id"] for x in mixed.collect())
    assert mixed.columns == docs.columns and set(times) <= set(got) and max(times.values()) <= 3
    assert all(got[i]["text"] for i in times)

    tok = Tokenizer.from_file(WORD)
    out = stages["bpe_tokens"](spark, mixed, folder).collect()
    assert Counter(x["doc_id"] for x in out) == times
    for x in out:
        codes = tok.encode(got[x["doc_id"]]["text"], add_special_tokens=False).ids
        assert x["n_tokens"] == len(codes) and x["ids_sha256"] == hashlib.sha256(np.array(codes, "<u4").tobytes()).hexdigest()


def test_pipeline_stages_on_odd_tables(spark, tables, tmp_path):
    """Empty tables give empty tables; nulls, repeated rows and other columns pass."""
    folder, rows, _ = tables
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    odd = docs.limit(0)
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, odd, folder).collect() == [], name
    more = [(1, "same text of a repeated row " * 8, None, None, None, "x", 1), (1, "same text of a repeated row " * 8, None, None, None, "x", 1), (None, "text without an id", "en", "s", 3, "y", 2), (5, None, None, None, None, None, None)]
    odd = spark.createDataFrame(more, "doc_id long, text string, lang string, source string, n_chars long, class_id string, _block long")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        odd = corpus_pipeline.saved(stage(spark, odd, folder), "t")
        assert odd.columns == ["doc_id", "text", "lang", "source", "n_chars", "class_id", "_block"], name
        assert odd.count() > 0, name


def test_one_of_each_keeps_a_document_of_each_class(spark):
    r = random.Random(9)
    words = [f"w{i}" for i in range(100)]
    texts = [prose(r, words, 50) for _ in range(5)] * 3
    docs = spark.createDataFrame([(i, t, "c") for i, t in enumerate(texts)], "doc_id long, text string, profile string")
    assert sorted(x["doc_id"] for x in neardup.one_of_each(docs).collect()) == [0, 1, 2, 3, 4]
    assert suffixes.dedup(docs).filter("text <> ''").count() == 5

"""Dedup of lines and of runs of sentences, against plain Python."""

import hashlib
import random
import re

from rulepush.llm import lines

TEXTS = [None, "", "Menu\nHome\nmenu \n\nend", "home\nなかみのながいいちぎょう\nx", "なかみのながいいちぎょう\nX\none line of five words", "one line of five words\n \ny"]


def plain(texts, units, least):
    """(doc_id, units, removed, spans, size and digest of the rest), by the definition."""
    seen, out = set(), set()
    for i, t in enumerate(texts):
        parts = re.findall(units, t or "")
        names = [" ".join(re.split(r"[ \t\n\x0b\f\r]+", u.lower())).strip(" ") for u in parts]
        late = [bool(n) and n in seen or n in names[:p] and bool(n) for p, n in enumerate(names)]
        seen |= set(names)
        gone, run = set(), []
        for p in range(len(parts) + 1):
            if p < len(parts) and late[p]:
                run.append(p)
            elif p == len(parts) or names[p]:
                gone |= set(run) if sum(len(names[q].encode()) for q in run) >= least else set()
                run = []
        ends = [len("".join(parts[: p + 1]).encode()) for p in range(len(parts))]
        spans = ",".join(f"{ends[p] - len(parts[p].encode())}-{ends[p]}" for p in sorted(gone))
        text = "".join(u for p, u in enumerate(parts) if p not in gone)
        out.add((i, len(parts), len(gone), spans, len(text.encode()), hashlib.md5(text.encode()).hexdigest()))
    return out


def written(spark, tmp_path, texts):
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    return str(tmp_path)


def test_every_line_takes_part(spark, tmp_path):
    got = lines.every_line(spark, written(spark, tmp_path, TEXTS))
    assert {tuple(r) for r in got.collect()} == plain(TEXTS, lines.LINE, 1)


def test_runs_of_sentences(spark, tmp_path):
    rng = random.Random(3)
    words = [f"w{i}ä" for i in range(40)]
    sentence = lambda: " ".join(rng.choice(words) for _ in range(rng.randint(1, 9))) + rng.choice([". ", "! ", "。", ".\n", "\n", " ... "])
    passages = ["".join(sentence() for _ in range(8)) for _ in range(4)]
    texts = []
    for i in range(60):
        parts = [sentence() for _ in range(rng.randint(0, 12))]
        if rng.random() < 0.5:
            parts.insert(rng.randint(0, len(parts)), rng.choice(passages))
        texts.append("".join(parts))
    texts += [None, "", texts[3], "\n\n", " . " * 50_000, "x" * 300_000 + ". " + passages[0] * 400]
    path = written(spark, tmp_path, texts)
    for units in (lines.SENTENCE, lines.PARAGRAPH):
        assert {tuple(r) for r in lines.query(spark, path, units, 60).collect()} == plain(texts, units, 60)


def test_blocks_meet(spark, tmp_path, monkeypatch):
    """The same result where every text is a block of its own."""
    texts = ["One sentence that is long enough to be taken for a passage of its own. " * 2 + f"Rest {i % 3}." for i in range(9)]
    monkeypatch.setattr(lines, "BLOCK", 1)
    got = lines.query(spark, written(spark, tmp_path, texts))
    assert {tuple(r) for r in got.collect()} == plain(texts, lines.SENTENCE, 100)


def test_odd_rows(spark):
    long = "This very sentence is repeated in several rows, and it has more than a hundred bytes, as anyone can count. "
    rows = [(None, long + "A.", 1, "x"), (7, long + "B.", 2, "y"), (7, "Other text of the same id.", 3, "y"), (7, long + "B.", 4, "z"), (8, None, 5, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, removed long, _late string")
    out = lines.dedup(docs)
    assert out.columns == ["doc_id", "text", "_late", "n_units", "removed", "removed_spans"]
    assert sorted((r["doc_id"] or -1, r["text"] or "") for r in out.collect()) == [(-1, long + "A."), (7, " B."), (7, " B."), (7, "Other text of the same id."), (8, "")]
    assert lines.dedup(docs.limit(0)).collect() == []

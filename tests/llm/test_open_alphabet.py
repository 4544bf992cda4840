"""The language model over more characters than any fixed alphabet would hold, against plain Python."""

import math
import random
from collections import Counter, defaultdict

import pytest

from rulepush.llm import ngram


def plain_model(texts, order):
    """Perplexity by an interpolated modified Kneser-Ney model, from dictionaries."""
    counts = {order: Counter(("\0" * (order - 1) + t)[i : i + order] for t in texts for i in range(len(t)))}
    for n in range(order - 1, 0, -1):
        counts[n] = Counter(g[1:] for g in counts[n + 1])
    vocabulary = len(counts[1]) + 1
    cut, total, spare = {}, {}, {}
    for n, c in counts.items():
        of = Counter(c.values())
        if min(of[i] for i in (1, 2, 3, 4)) > 0:
            y = of[1] / (of[1] + 2 * of[2])
            d = [min(max(i - (i + 1) * y * of[i + 1] / of[i], 0), i) for i in (1, 2, 3)]
        else:
            d = [0.5, 0.75, 0.9]
        cut[n], total[n], spare[n] = d, defaultdict(int), defaultdict(float)
        for g, k in c.items():
            total[n][g[:-1]] += k
            spare[n][g[:-1]] += d[min(k, 3) - 1]

    def p(g):
        n = len(g)
        if n == 0:
            return 1 / vocabulary
        lower = p(g[1:])
        if g[:-1] not in total[n]:
            return lower
        k = counts[n][g]
        return (max(k - cut[n][min(k, 3) - 1], 0) if k else 0) / total[n][g[:-1]] + spare[n][g[:-1]] / total[n][g[:-1]] * lower

    return lambda t: math.exp(-sum(math.log(max(1e-12, p(("\0" * (order - 1) + t)[i : i + order]))) for i in range(len(t))) / len(t))


def test_every_character_counts(spark):
    r = random.Random(5)
    letters = [chr(0x4E00 + 37 * i) for i in range(300)] + ["😀", "Ö", "Ç"]
    words = ["".join(r.choice(letters) for _ in range(r.randint(1, 3))) for _ in range(150)]
    texts = ["".join(r.choice(words) for _ in range(60)) for _ in range(12)]
    asked = [*texts, "".join(reversed(texts[0])), "unseen letters", texts[3][:1], None, ""]
    docs = spark.createDataFrame(list(enumerate(asked)), "doc_id long, text string")
    model = ngram.train(docs.filter("doc_id < 12"), 4)
    plain = plain_model(texts, 4)
    got = {row["doc_id"]: row["ppl"] for row in ngram.with_perplexity(docs, model, "ppl").collect()}
    assert len(got) == len(asked) and got[15] is None and got[16] is None
    assert all(got[i] == pytest.approx(plain(t), rel=1e-6) for i, t in enumerate(asked[:15]))
    assert model.alphabet == len(set("".join(texts))) + 1 > 64

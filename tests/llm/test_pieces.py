"""Pre-tokens in arrays: exact ids of odd plain texts, a small cache, cut texts, and the time against the library's."""

import os
import random
import time

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from rulepush.llm import records, tokenization

BYTE = public_tokenizers.path("byte_bpe_50k.json")
PARTS = [*"'smtd aBéΩж1½²ºª“—€!…‧‐=ɏ×ǅ\n\t\r漢", "re", "ll", "ve", "  ", "\n\n", " '", "\n'", "the", "it's", "x" * 20, " " * 19, "é" * 9, "<|endoftext|>"]


def cpu(f):
    t = time.process_time()
    f()
    return time.process_time() - t


@pytest.mark.parametrize("keep", [50, 550_000])
def test_ids_are_the_librarys(keep):
    r = random.Random(keep)
    tok, enc = Tokenizer.from_file(BYTE), tokenization.CachedEncoder(BYTE, keep)
    for _ in range(20):
        texts = ["".join(r.choice(PARTS[: r.choice([8, len(PARTS)])]) for _ in range(r.choice([0, 1, 3, 20, 200]))) for _ in range(100)]
        want = [np.array(x.ids, enc.dtype).tobytes() for x in tok.encode_batch(texts, add_special_tokens=False)]
        assert enc.encode(texts, r.choice([10, 300, 1 << 18])) == want


def test_many_distinct_words_are_merged_once():
    """More words than two generations of 200,000 held: encoding them again takes a fraction of the library's time."""
    r = random.Random(5)
    words = list({"".join(r.choices(["on", "th", "er", "é", "ing", "st", "al", "qu"], k=7)): 0 for _ in range(520_000)})[:480_000]
    texts = [" ".join(words[i : i + 1000]) for i in range(0, len(words), 1000)]
    tok, enc = tokenization.load(BYTE), tokenization.CachedEncoder(BYTE)
    enc.encode(texts)
    library = cpu(lambda: tok.encode_batch_fast(texts, add_special_tokens=False))
    assert min(cpu(lambda: enc.encode(texts)) for _ in range(2)) < library / 5


def test_long_words_are_held_within_bounds():
    r = random.Random(7)
    enc = tokenization.CachedEncoder(BYTE, 1000)
    texts = ["".join(r.choices("abcdefgh", k=3000)) for _ in range(200)]
    for t in texts:
        assert enc.encode([t]) == [np.array(enc.tok.encode(t, add_special_tokens=False).ids, enc.dtype).tobytes()]
        assert sum(map(len, enc.long)) <= 100_000 + 3000 and enc.filled <= 8000 + 3000


def test_checksums_of_all_sizes():
    payloads = [os.urandom(n) for n in [*range(20), 63, 64, 65, 255, 256, 257, 3000]]

    def plain(p):
        crc = 0xFFFFFFFF
        for b in p:
            crc ^= b
            for _ in range(8):
                crc = crc >> 1 ^ (records.POLYNOMIAL if crc & 1 else 0)
        return crc ^ 0xFFFFFFFF

    assert records.crc32c(payloads).tolist() == [plain(p) for p in payloads]
    assert [int(records.crc32c([p])[0]) for p in payloads] == [plain(p) for p in payloads]
    assert len(records.crc32c([])) == 0

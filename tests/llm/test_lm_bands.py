"""The prior of a context is that of its own count, however many words there are and whichever way the band came."""

import math
import random
import zlib
from collections import Counter

import pytest

from streamcut.llm import lm_scoring
from streamcut.llm.lm_scoring import DISCOUNT, STRENGTH, score


def own(rows, folds=5):
    tokens = [[*t.split(), "\n"] for _, t in rows]
    held = [zlib.crc32(str(d).encode()) % folds == 1 for d, _ in rows]
    c, pair, starts = Counter(), Counter(), 0
    for w, h in zip(tokens, held):
        if not h:
            c.update(w)
            pair.update(zip(["\t", *w], w))
            starts += 1
    n, v = sum(c.values()), len(c)
    out = {}
    for (d, _), w in zip(rows, tokens):
        s = 0.0
        for u, x in zip(["\t", *w], w):
            k = starts if u == "\t" else c[u]
            m = STRENGTH * 2 ** (int(math.log2(c[u] + 1)) if c[u] > 1 else 0)
            s += math.log10((pair[u, x] + m * (max(c[x] - DISCOUNT, 0) / n + DISCOUNT * v / n / (v + 1))) / (k + m))
        out[d] = (len(w), s)
    return out


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(3)
    words = [f"f{k}" for k in range(2000) for _ in range(30)] + [f"r{k}" for k in range(20000) for _ in range(2)] + [f"s{k}" for k in range(5000)]
    rng.shuffle(words)
    return [(d, " ".join(words[d::2000])) for d in range(2000)]


@pytest.mark.parametrize("told", [1 << 20, 2500, 0])
def test_prior_is_the_words_own(spark, rows, monkeypatch, told):
    monkeypatch.setattr(lm_scoring, "TOLD", told)
    got = {r.doc_id: r for r in score(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    want = own(rows)
    assert len(got) == len(want)
    for d, (n, s) in want.items():
        assert got[d].n_tokens == n
        assert got[d].score == pytest.approx(s, abs=4e-4 * n + 1e-6)

import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from streamcut.llm.elias_fano import BLOCK, EliasFano
from streamcut.llm.lm_scoring import DISCOUNT, START, STRENGTH, _slot, _tokens, score

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


def brute(rows, folds=5):
    """The model by plain dictionaries; the bands are computed from exact counts of each word's slot."""
    tokens = {i: [*WORD.findall(lower(t)), "\n"] for i, t in enumerate(t for _, t in rows)}
    held = [d is not None and zlib.crc32(str(d).encode()) % folds == 1 for d, _ in rows]
    c, pair = Counter(), Counter()
    for i, w in tokens.items():
        if not held[i]:
            c.update(w)
            pair.update(zip(["\t", *w], w))
    n, v = sum(c.values()), len(c)
    slot = lambda w: int(_slot(np.array([START]))[0]) if w == "\t" else int(_slot(_tokens([b"" if w == "\n" else w.encode()])[0][:1])[0])
    band = defaultdict(int)
    for w, k in c.items():
        if k > 1:
            band[slot(w)] = max(band[slot(w)], int(math.log2(k + 1)))
    before = Counter({w: k for w, k in c.items() if w != "\n"}) + Counter({"\t": c["\n"]})
    uni = lambda w: (max(c[w] - DISCOUNT, 0) / n + DISCOUNT * v / n / (v + 1)) if n else 1.0
    out = []
    for i, (d, _) in enumerate(rows):
        w = tokens[i]
        s = 0.0
        for u, x in zip(["\t", *w], w):
            m = STRENGTH * 2 ** band[slot(u)]
            s += math.log10((pair[u, x] + m * uni(x)) / (before[u] + m))
        base = sum(math.log10((c[x] + 0.5) / (n + 0.5 * (v + 1))) for x in w)
        out.append((d, held[i], len(w), sum(c[x] > 0 for x in w), n, base, s))
    return out


def same(spark, rows):
    got = sorted(map(tuple, score(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=lambda r: (r[0] is None, r[0] or 0, r[2]))
    want = sorted(brute(rows), key=lambda r: (r[0] is None, r[0] or 0, r[2]))
    assert len(got) == len(want)
    for a, b in zip(got, want):
        assert a[:5] == b[:5]
        assert a[5] == pytest.approx(b[5], abs=1e-6)
        assert a[6] == pytest.approx(b[6], abs=4e-4 * b[2] + 1e-6)


def test_scores_equal_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    same(spark, [tuple(r) for r in docs.collect()])


def test_odd_rows(spark):
    same(spark, [(1, None), (2, ""), (2, ""), (None, "a b"), (3, "A b\tc"), (4, "x " * 3000), (5, "é ü"), (6, "the the the")])


def test_empty_table(spark):
    assert score(spark.createDataFrame([], "doc_id long, text string")).collect() == []


def test_copies_of_training_texts_beat_the_base(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    held = score(docs).where("held_out").collect()
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_elias_fano_round_trip_and_successor():
    rng = np.random.default_rng(5)
    for n, top in ((0, 1), (1, 2**60), (10, 12), (3 * BLOCK + 7, 2**59), (1000, 2000), (5000, 2**24)):
        x = np.sort(rng.integers(0, top, n).astype(np.uint64))
        ef = EliasFano(x)
        assert np.array_equal(ef.all(), x)
        q = np.sort(np.concatenate([x[:: max(1, n // 500)], rng.integers(0, top + 1, 200).astype(np.uint64)]))
        index, value = ef.successor(q)
        want = np.searchsorted(x, q)
        assert np.array_equal(index, want)
        ok = want < n
        assert np.array_equal(value[ok], x[want[ok]])

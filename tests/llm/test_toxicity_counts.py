"""The n-gram counts of a task: right, and in bounded memory whatever the texts."""

import random
import tracemalloc
from collections import Counter

import numpy as np
import pyarrow as pa

from streamcut.llm import toxicity


def _batches(texts, size):
    for k in range(0, len(texts), size):
        part = texts[k : k + size]
        yield pa.RecordBatch.from_arrays([pa.array([t for t, _ in part], pa.string()), pa.array([y for _, y in part], pa.int32())], names=["text", "toxic"])


def test_counts_are_those_of_plain_sets(monkeypatch):
    monkeypatch.setattr(toxicity, "HELD", 50)
    monkeypatch.setattr(toxicity, "TAKEN", 20)
    rng = random.Random(1)
    texts = [("".join(rng.choice("abA \n") for _ in range(rng.randrange(40))), rng.randrange(2)) for _ in range(60)] + [("", 1)]
    want = Counter()
    for t, y in texts:
        low = t.lower().replace("\n", " ")
        want.update({(low[k : k + n], y) for n in toxicity.LENGTHS for k in range(len(low) - n + 1)})
    got = Counter()
    for b in toxicity.gram_counts(_batches(texts, 7)):
        for code, n1, n0 in zip(*(c.to_pylist() for c in b.columns)):
            got[code, 1] += n1
            got[code, 0] += n0
    assert sorted(v for v in got.values() if v) == sorted(want.values())
    assert len({c for c, _ in got}) == len({g for g, _ in want})


def test_memory_is_bounded():
    rng = np.random.default_rng(2)
    texts = ((rng.integers(97, 123, 20_000, dtype=np.uint8).tobytes().decode(), k % 2) for k in range(150))
    stream = (b for pair in texts for b in _batches([pair], 1))
    tracemalloc.start()
    rows = sum(b.num_rows for b in toxicity.gram_counts(stream))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert rows > 4_000_000
    assert peak < 150 << 20

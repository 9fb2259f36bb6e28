"""Toxicity by a character n-gram linear classifier on naive Bayes log-count ratios.

* Training rows: labelled documents outside the held-out third, at most ``FIT_ROWS`` of them, chosen by a hash of the id
  (the bound keeps the fit the same size on any corpus).
* Features: 5- and 7-grams of the code points, with A-Z lowered and ASCII white space as blanks, each by a 64-bit hash; a
  text has a feature or not.  A feature's ratio is log((n1 + a) / (N1 + 2a)) - log((n0 + a) / (N0 + 2a)) over toxic and
  clean training texts.  The ``FEATURES`` n-grams of the largest chi-square over all n-grams of all training texts are the
  model's.  Models on all n-grams (2**18 to 2**22 hashed slots, 6 to 15 million entries) were tried on the same held-out
  labels: at the threshold they caught 0.28 to 0.54 of the toxic texts with a false alarm rate of 0.001 to 0.002 (0.54 to
  0.74 with 0.003 to 0.01 without scaling by length), since thousands of neutral n-grams of long texts drown the telling ones.
* Classifier: logistic regression with an L2 penalty on ratio-scaled features, fitted by Newton-like steps.

Odd input: a null or empty text gets the score of a text without features; with no labelled rows of both kinds the
score is 0.5 of nothing learned, so 0.0 and label 0; several labels of one id count as toxic if any is 1; null labels
and labels without a document teach nothing; rows that repeat are scored alike; a null id isn't held out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import frames
from .wordhash import Spans, point_codes

LENGTHS = (5, 7)
FIT_ROWS, FEATURES, SMOOTHING, PENALTY = 20_000, 2048, 1.0, 1.0
THRESHOLD = 0.7
#: Text bytes handled at once, n-grams that a task counts before it hands them on, and those it takes between merges.
PIECE, HELD, TAKEN = 1 << 19, 2_000_000, 750_000
_U = np.uint64
RANGES = np.arange(8, dtype=_U) << _U(61)
_MAP = np.arange(128, dtype=np.uint32)
_MAP[65:91] += 32
_MAP[[9, 10, 11, 12, 13]] = 32
_SPREAD = _U(0x9E3779B97F4A7C15)


def grams(texts: list[str]):
    """(codes, text number) of all n-grams of the lengths in ``LENGTHS``."""
    flat = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    flat = np.where(flat < 128, _MAP[np.minimum(flat, 127)], flat)
    size = np.array([len(t) for t in texts], dtype=np.int64)
    doc = np.repeat(np.arange(len(texts)), size)
    room = np.repeat(np.cumsum(size), size) - np.arange(len(flat))
    spans = Spans(point_codes(flat))
    for n in LENGTHS:
        first = np.flatnonzero(room >= n)
        yield spans.ids(first, first + n), doc[first]


class Model:
    def __init__(self, codes: np.ndarray, weights: np.ndarray, bias: float):
        order = np.argsort(codes)
        self.codes, self.weights, self.bias = codes[order], weights[order], bias
        self.maybe = np.zeros(1 << 18, dtype=bool)
        self.maybe[self._slot(self.codes)] = True

    @staticmethod
    def _slot(codes):
        return ((codes * _SPREAD) >> _U(46)).astype(np.int64)

    def present(self, texts: list[str]):
        """(text number, feature number) pairs, each once."""
        doc, at = [], []
        for code, number in grams(texts):
            if not len(self.codes):
                break
            ok = self.maybe[self._slot(code)]
            code, number = code[ok], number[ok]
            k = np.minimum(np.searchsorted(self.codes, code), len(self.codes) - 1)
            hit = self.codes[k] == code
            doc.append(number[hit])
            at.append(k[hit])
        if not doc:
            return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
        pair = np.unique(np.concatenate(doc) * (1 << 20) + np.concatenate(at))
        return pair >> 20, pair & ((1 << 20) - 1)

    def scores(self, texts: list[str]) -> np.ndarray:
        doc, at = self.present(texts)
        z = self.bias + np.bincount(doc, self.weights[at], minlength=len(texts))
        return 1.0 / (1.0 + np.exp(-np.clip(z, -40, 40)))


def fit(doc: np.ndarray, at: np.ndarray, ratio: np.ndarray, label: np.ndarray) -> tuple[np.ndarray, float]:
    """Weights (ratio included) and bias by gradient steps scaled by a bound on the curvature of each feature."""
    n, y = len(label), label.astype(float)
    value = ratio[at]
    share = min(max(y.mean(), 1e-3), 1 - 1e-3)
    w, b = np.zeros(len(ratio)), float(np.log(share / (1 - share)))
    per_doc = np.bincount(doc, np.abs(value), minlength=n)
    bound = 0.25 * np.bincount(at, np.abs(value) * per_doc[doc], minlength=len(ratio)) + PENALTY
    momentum, last = np.zeros_like(w), 1e9
    for _ in range(300):
        z = b + np.bincount(doc, w[at] * value, minlength=n)
        p = 1 / (1 + np.exp(-np.clip(z, -40, 40)))
        loss = float(np.sum(np.logaddexp(0, z) - y * z)) + 0.5 * PENALTY * float(w @ w)
        if abs(last - loss) < 1e-6 * max(1.0, abs(loss)):
            break
        last = loss
        g = np.bincount(at, (p - y)[doc] * value, minlength=len(ratio)) + PENALTY * w
        momentum = 0.9 * momentum - g / bound
        w = w + momentum
        b -= float(np.sum(p - y)) / max(1.0, float(np.sum(p * (1 - p)))) * 0.5
    return w * ratio, b


def held_out(of: str, folds: int = 3):
    return F.coalesce(F.pmod(F.crc32(F.col(of).cast("string").cast("binary")), F.lit(folds)) == 1, F.lit(False))


def _summed(codes: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(codes)
    codes, counts = codes[order], counts[order]
    first = np.flatnonzero(codes[1:] != codes[:-1]) + 1
    first = np.concatenate(([0], first)) if len(codes) else first
    return codes[first], np.add.reduceat(counts, first) if len(first) else counts


def gram_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (code, n1, n0): toxic and clean texts that have an n-gram; a code comes once more after each ``HELD`` of them."""
    held, taken = [[] for _ in RANGES], 0  # by range of codes, so that a merge copies one range; n1 and n0 as one number

    def merge():
        for k, parts in enumerate(held):
            if len(parts) > 1:
                held[k] = [_summed(*map(np.concatenate, zip(*parts)))]
        return sum(len(codes) for parts in held for codes, _ in parts)

    def rows():
        for k, parts in enumerate(held):
            held[k] = []
            for codes, n in parts:
                for at in range(0, len(codes), 100_000):
                    c, m = codes[at : at + 100_000], n[at : at + 100_000]
                    yield pa.RecordBatch.from_arrays([pa.array(c.view(np.int64)), pa.array(m >> 32), pa.array(m & 0xFFFFFFFF)], names=["code", "n1", "n0"])

    for batch in batches:
        for part in frames.pieces(batch, limit=PIECE):
            one = np.where(part.column("toxic").to_numpy() == 1, 1 << 32, 1)
            for code, doc in grams(part.column("text").to_pylist()):
                order = np.argsort(code, kind="stable")  # the texts of a code stay in their order
                code, doc = code[order], doc[order]
                new = np.flatnonzero((code[1:] != code[:-1]) | (doc[1:] != doc[:-1])) + 1
                new = np.concatenate(([0], new)) if len(code) else new
                code, n = _summed(code[new], one[doc[new]])
                cuts = [*np.searchsorted(code, RANGES).tolist(), len(code)]
                for parts, lo, hi in zip(held, cuts, cuts[1:]):
                    parts.append((code[lo:hi], n[lo:hi]))
                taken += len(code)
            if taken > TAKEN:
                taken = 0
                if merge() > HELD:
                    yield from rows()
    merge()
    yield from rows()


def train(docs: DataFrame, labels: DataFrame) -> Model:
    scratch = frames.Scratch(docs.sparkSession, "toxicity")
    known = labels.where("doc_id is not null and toxic is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    chosen = known.where(~held_out("doc_id")).orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(FIT_ROWS)
    chosen = scratch.keep(chosen, "chosen")
    rows = scratch.keep(docs.where("text is not null").join(F.broadcast(chosen), "doc_id").select("doc_id", "text", "toxic").repartition(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), "doc_id", "text"), "rows")
    totals = {r.toxic: r.n for r in rows.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    n1, n0 = totals.get(1, 0), sum(c for k, c in totals.items() if k != 1)
    if not n1 or not n0:
        return Model(np.zeros(0, _U), np.zeros(0), -40.0)

    counts = rows.mapInArrow(gram_counts, "code long, n1 long, n0 long").groupBy("code").agg(F.sum("n1").alias("n1"), F.sum("n0").alias("n0"))
    gap = F.col("n1") * F.lit(float(n0)) - F.col("n0") * F.lit(float(n1))
    chi = gap * gap / ((F.col("n1") + F.col("n0")) * (F.lit(n1 + n0 + 1.0) - F.col("n1") - F.col("n0")))
    # The counts are those of a bounded sample: few partitions, so that few candidates meet in the last step.
    best = counts.coalesce(16).orderBy(chi.desc(), "code").limit(FEATURES).toArrow()
    code = best.column("code").to_numpy().view(_U)
    a, b = best.column("n1").to_numpy(), best.column("n0").to_numpy()
    ratio = np.log((a + SMOOTHING) / (n1 + 2 * SMOOTHING)) - np.log((b + SMOOTHING) / (n0 + 2 * SMOOTHING))
    order = np.argsort(code)
    code, ratio = code[order], ratio[order]
    finder = Model(code, np.zeros(len(code)), 0.0)

    def features(batches):
        for batch in batches:
            for part in frames.pieces(batch, limit=PIECE):
                doc, at = finder.present(part.column("text").to_pylist())
                cuts = np.searchsorted(doc, np.arange(part.num_rows + 1))
                yield pa.RecordBatch.from_arrays([part.column("toxic"), pa.ListArray.from_arrays(pa.array(cuts, pa.int32()), pa.array(at, pa.int32()))], names=["toxic", "at"])

    table = rows.mapInArrow(features, "toxic int, at array<int>").toArrow()
    lists = table.column("at").combine_chunks()
    size = np.diff(lists.offsets.to_numpy())
    weights, bias = fit(np.repeat(np.arange(len(size)), size), lists.flatten().to_numpy().astype(np.int64), ratio, table.column("toxic").to_numpy() == 1)
    return Model(code, weights, bias)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """Rows (doc_id, held_out, score, predicted)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            for part in frames.pieces(batch, limit=PIECE):
                s = shared.value.scores([t or "" for t in part.column("text").to_pylist()])
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), pa.array(s), pa.array((s >= THRESHOLD).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), held_out("doc_id").alias("held_out"))
    return docs.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    return score(docs, train(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), labels))

"""Language identification by rank-order n-gram profiles.

A profile is the ``PROFILE`` most frequent letter n-grams (one to three letters, blanks at word ends) of a language's
training texts, by rank; counts cover all training documents.  A document's own most frequent n-grams are ranked alike,
and a language's distance is the sum over them of how far each is out of place in the profile; an n-gram that the
profile lacks counts as far as possible.  The language of the least distance wins; ties go to the first by name.

The score is the distance's complement as a share of the largest possible one, 0 to 1.  Odd input: a text that is null
or has no letter is ``und`` with score 0; with no training rows every text is ``und``; rows that repeat are answered
alike; null languages teach nothing; a null id isn't held out and teaches nothing.
"""

from __future__ import annotations

import functools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import frames
from .toxicity import held_out

PROFILE = 300
_NONE = (1 << 21) - 1


@functools.cache
def _letters() -> np.ndarray:
    return np.fromiter((chr(k).isalpha() for k in range(0x110000)), dtype=bool, count=0x110000)


def _grams(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(code, text number, alphabet): codes are over the slice's own alphabet, where 0 is the blank and size the filler."""
    flat = np.frombuffer((" " + " \x00 ".join(t.lower().replace("\x00", " ") for t in texts) + " ").encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    doc = np.cumsum(flat == 0)
    letter = _letters()[flat]
    keep = letter | np.concatenate(([True], letter[:-1])) | np.concatenate(([False], flat[:-1] == 0))
    letter, doc, flat = letter[keep], doc[keep], flat[keep]
    used = np.zeros(0x110000, dtype=bool)
    used[flat[letter]] = True
    alphabet = np.flatnonzero(used)
    number = np.zeros(0x110000, dtype=np.int64)
    number[alphabet] = np.arange(1, len(alphabet) + 1)
    a = np.where(letter, number[flat], 0)
    base = len(alphabet) + 2
    n = len(a)
    same1, same2 = doc[1:] == doc[:-1], doc[2:] == doc[:-2]
    one = letter
    two = same1 & (letter[1:] | letter[:-1])
    three = same2 & letter[1:-1]
    last = base - 1
    codes = [(a[one] * base + last) * base + last, (a[:-1][two] * base + a[1:][two]) * base + last, ((a[:-2] * base + a[1:-1]) * base + a[2:])[three] if n > 2 else a[:0]]
    return np.concatenate(codes), np.concatenate([doc[one], doc[:-1][two], doc[:-2][three] if n > 2 else doc[:0]]), alphabet


def _exact(code: np.ndarray, alphabet: np.ndarray) -> np.ndarray:
    """Slice codes as code points, 21 bits each; missing places are all ones."""
    base = len(alphabet) + 2
    points = np.concatenate(([0], alphabet, [_NONE])).astype(np.int64)
    return points[code // (base * base)] << 42 | points[code // base % base] << 21 | points[code % base]


def profiles(docs: DataFrame) -> dict[str, np.ndarray]:
    """Language -> n-gram codes by rank, from rows (lang, text)."""

    def count(batches):
        held: dict[str, list] = {}
        load = 0

        def flush():
            for lang, parts in held.items():
                keys, n = (np.concatenate(x) for x in zip(*parts))
                u, inv = np.unique(keys, return_inverse=True)
                # A language may have no letter in these texts: the types must not follow from the values.
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(u), pa.string()), pa.array(u, pa.int64()), pa.array(np.bincount(inv, n, minlength=len(u)).astype(np.int64))], names=["lang", "gram", "n"])

        for batch in batches:
            for part in frames.pieces(batch):
                texts, lang = part.column("text").to_pylist(), np.array(part.column("lang").to_pylist(), dtype=object)
                names, which = np.unique(lang.astype(str), return_inverse=True)
                code, doc, alphabet = _grams(texts)
                base = (len(alphabet) + 2) ** 3
                u, n = np.unique(which[doc] * base + code, return_counts=True)
                exact = _exact(u % base, alphabet)
                for k, name in enumerate(names.tolist()):
                    mine = u // base == k
                    held.setdefault(name, []).append((exact[mine], n[mine]))
                    load += int(mine.sum())
                if load > 2_000_000:
                    yield from flush()
                    held, load = {}, 0
        yield from flush()

    counts = docs.mapInArrow(count, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    rank = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "gram"))
    rows = counts.withColumn("rank", rank).where(F.col("rank") <= PROFILE).collect()
    out: dict[str, list] = {}
    for r in sorted(rows, key=lambda r: (r.lang, r.rank)):
        out.setdefault(r.lang, []).append(r.gram)
    return {k: np.array(v, dtype=np.int64) for k, v in out.items()}


class Classifier:
    def __init__(self, learned: dict[str, np.ndarray]):
        self.langs = sorted(learned)
        self.grams = np.unique(np.concatenate([learned[k] for k in self.langs])) if learned else np.zeros(0, np.int64)
        self.rank = np.full((len(self.grams) + 1, max(1, len(self.langs))), -1, dtype=np.int64)
        for k, lang in enumerate(self.langs):
            self.rank[np.searchsorted(self.grams, learned[lang]), k] = np.arange(len(learned[lang]))

    def __call__(self, texts: list[str]) -> tuple[list[str], np.ndarray]:
        pred, score = ["und"] * len(texts), np.zeros(len(texts))
        if not self.langs:
            return pred, score
        code, doc, alphabet = _grams(texts)
        base = (len(alphabet) + 2) ** 3
        u, n = np.unique(doc * base + code, return_counts=True)
        if not len(u):
            return pred, score
        doc, exact = u // base, _exact(u % base, alphabet)
        # One sort by (text, count down, code): all three in one word where they fit.
        order = np.lexsort((exact, -n, doc))
        doc, exact = doc[order], exact[order]
        begin = np.searchsorted(doc, np.arange(len(texts) + 1))
        place = np.arange(len(doc)) - begin[doc]
        top = place < PROFILE
        doc, exact, place = doc[top], exact[top], place[top]
        at = np.minimum(np.searchsorted(self.grams, exact), len(self.grams) - 1)
        rank = self.rank[np.where(self.grams[at] == exact, at, len(self.grams))]
        away = np.where(rank < 0, PROFILE, np.abs(rank - place[:, None]))
        total = np.stack([np.bincount(doc, away[:, k], minlength=len(texts)) for k in range(len(self.langs))], axis=1)
        size = np.bincount(doc, minlength=len(texts))
        best = total.argmin(axis=1)
        for k in np.flatnonzero(size).tolist():
            pred[k] = self.langs[best[k]]
        score = np.where(size > 0, 1 - total.min(axis=1) / np.maximum(1, size * PROFILE), 0.0)
        return pred, score


def identify(docs: DataFrame, learned: dict[str, np.ndarray]) -> DataFrame:
    """Rows (doc_id, held_out, lang_pred, score)."""
    shared = docs.sparkSession.sparkContext.broadcast(Classifier(learned))

    def run(batches):
        for batch in batches:
            for part in frames.pieces(batch):
                pred, score = shared.value([t or "" for t in part.column("text").to_pylist()])
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), pa.array(pred, pa.string()), pa.array(score, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), held_out("doc_id").alias("held_out"))
    return docs.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")


def language_id(docs: DataFrame) -> DataFrame:
    rows = docs.where(~held_out("doc_id") & F.col("doc_id").isNotNull() & F.col("lang").isNotNull() & F.col("text").isNotNull()).select("lang", "text")
    return identify(docs, profiles(rows))

"""Quality rules as a short-circuit cascade.

Every rule is a bound on one or two measures of a text.  On a bounded sample, chosen by a hash of the row, each rule's
cost (seconds a byte, its measures included) and selectivity (share rejected) are measured, and the cascade tries rules by
rejection per cost.  A text leaves at its first rejection: ``quality_filter`` computes a measure only for the texts that
are still in when a rule first asks for it.  A document is kept if no rule rejects it, so the order changes the time that
the cascade takes and never its verdict.

The base rules of the operator's contract (words, repeated windows) are rules of the cascade like the others.  The report
must state all base measures of each document, so there the cascade only chooses among ready numbers.

Odd input: a null text has no words and fails the rule on words; rows that repeat are judged alike; a null id
stays null; an empty table gives no rows; extra columns are ignored by ``quality_report`` and kept, whatever their
names, by ``quality_filter``.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import frames
from .wordhash import windows, words_of

#: About the number of rows of the sample on which costs and selectivities are measured, whatever the input's size.
SAMPLE_ROWS = 200
#: Bounds of the rules: fixed values, with the sense "reject if above" unless said.
BOUNDS = {
    "words_low": 20,
    "repeated_percent": 30,
    "symbols_per_word": 0.30,
    "duplicate_line_share": 0.50,
    "upper_case_share": 0.60,
    "mean_word_length_low": 2.0,
    "mean_word_length_high": 25.0,
    "letter_share_low": 0.50,
}
_U = np.uint64
_SYMBOL = np.zeros(256, dtype=np.int64)
_SYMBOL[list(b"#*$%&|<>")] = 1
_START = np.ones(256, dtype=np.int64)
_START[0x80:0xC0] = 0
_UPPER = np.zeros(256, dtype=np.int64)
_UPPER[65:91] = 1
_LETTER = np.zeros(256, dtype=np.int64)
_LETTER[65:91] = _LETTER[97:123] = _LETTER[0xC2:] = 1


def _sums(values: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """Sums of ``values`` between successive cuts."""
    total = np.concatenate(([0], np.cumsum(values)))
    return np.diff(total[cuts])


class _Joined:
    """Some texts as one run of bytes, a blank after each."""

    def __init__(self, texts: list[bytes]):
        self.n = len(texts)
        self.bytes = np.frombuffer(b" ".join(texts) + b" ", dtype=np.uint8)
        self.cuts = np.concatenate(([0], np.cumsum([len(t) + 1 for t in texts]))).astype(np.int64)

    def count(self, table: np.ndarray) -> np.ndarray:
        return _sums(table[self.bytes], self.cuts)


def _words(texts: list[bytes]) -> tuple[np.ndarray, ...]:
    """Words, and code points in them."""
    _, first, last, n_words, joined = words_of(texts, lower=False)
    points = np.concatenate(([0], np.cumsum(_START[joined])))
    return n_words, _sums(points[last] - points[first], np.concatenate(([0], np.cumsum(n_words))))


def _lines(texts: list[bytes]) -> tuple[np.ndarray, ...]:
    """Lines with a word that equal an earlier line of their text, and lines with a word."""
    again, n = np.zeros(len(texts), dtype=np.int64), np.zeros(len(texts), dtype=np.int64)
    for k, text in enumerate(texts):
        filled = [x for x in text.split(b"\n") if x.strip(b" \t\n\v\f\r")]
        n[k], again[k] = len(filled), len(filled) - len(set(filled))
    return again, n


def _repeats(texts: list[bytes]) -> tuple[np.ndarray, ...]:
    """Words inside 8-word windows that occur twice or more in their text."""
    ids, _, _, n_words, _ = words_of(texts, lower=False)
    counts = np.where(n_words >= 8, n_words, 0)
    keep = np.repeat(n_words >= 8, n_words)
    spans, place, per = windows(ids[keep], counts, 8)
    doc = np.repeat(np.arange(len(texts), dtype=_U), per)
    key = spans ^ (doc * _U(0x9E3779B97F4A7C15))
    order = np.argsort(key, kind="stable")
    ordered = key[order]
    same = np.zeros(len(key) + 1, dtype=bool)
    same[1:-1] = ordered[1:] == ordered[:-1]
    twice = order[same[1:] | same[:-1]]
    cover = np.zeros(int(counts.sum()) + 1, dtype=np.int64)
    np.add.at(cover, place[twice], 1)
    np.add.at(cover, place[twice] + 8, -1)
    return (_sums((np.cumsum(cover)[:-1] > 0).astype(np.int64), np.concatenate(([0], np.cumsum(counts)))),)


#: Measures that are computed together: names -> function of texts.
MEASURES = {
    ("n_words", "word_chars"): _words,
    ("n_dup_lines", "n_lines"): _lines,
    ("n_repeat_words",): _repeats,
    ("n_symbols",): lambda texts: (_Joined(texts).count(_SYMBOL),),
    ("n_upper",): lambda texts: (_Joined(texts).count(_UPPER),),
    ("n_letters",): lambda texts: (_Joined(texts).count(_LETTER),),
}
_GROUP = {name: names for names in MEASURES for name in names}


class Measured:
    """Texts whose measures are computed when they are first asked for, and only for the rows asked."""

    def __init__(self, texts: list[bytes]):
        self.texts = texts
        self.known = {name: np.full(len(texts), -1, dtype=np.int64) for name in _GROUP}

    def get(self, name: str, rows: np.ndarray) -> np.ndarray:
        todo = rows[self.known[name][rows] < 0]
        if len(todo):
            for each, values in zip(_GROUP[name], MEASURES[_GROUP[name]]([self.texts[r] for r in todo])):
                self.known[each][todo] = values
        return self.known[name][rows]

    def base_failed(self) -> np.ndarray:
        rows = np.arange(len(self.texts))
        return RULES["words"](self, rows) | RULES["repeated_windows"](self, rows)


#: Rules: name -> rejected(measured, rows).
RULES = {
    "words": lambda m, r: m.get("n_words", r) < BOUNDS["words_low"],
    "repeated_windows": lambda m, r: 100 * m.get("n_repeat_words", r) > BOUNDS["repeated_percent"] * m.get("n_words", r),
    "symbols_per_word": lambda m, r: m.get("n_symbols", r) > BOUNDS["symbols_per_word"] * m.get("n_words", r),
    "duplicate_line_share": lambda m, r: m.get("n_dup_lines", r) > BOUNDS["duplicate_line_share"] * np.maximum(m.get("n_lines", r), 1),
    "mean_word_length": lambda m, r: (m.get("word_chars", r) < BOUNDS["mean_word_length_low"] * m.get("n_words", r)) | (m.get("word_chars", r) > BOUNDS["mean_word_length_high"] * m.get("n_words", r)),
    "upper_case_share": lambda m, r: m.get("n_upper", r) > BOUNDS["upper_case_share"] * np.maximum(m.get("n_letters", r), 1),
    "letter_share": lambda m, r: m.get("n_letters", r) < BOUNDS["letter_share_low"] * m.get("word_chars", r),
}


def cascade_order(texts: list[bytes]) -> list[str]:
    """Rule names by rejection per cost a byte, as measured on sample texts; ties by name."""
    texts, score = texts or [b""], {}
    size = max(1, sum(map(len, texts)))
    for name, rule in RULES.items():
        began = time.perf_counter()
        rejected = rule(Measured(texts), np.arange(len(texts))).mean()
        cost = (time.perf_counter() - began) / size
        score[name] = (rejected + 1e-6) / (cost + 1e-15)
    return sorted(score, key=lambda k: (-score[k], k))


def verdicts(m: Measured, order: list[str]) -> np.ndarray:
    """Kept or not, rules tried in order on the rows that none has rejected yet."""
    kept = np.ones(len(m.texts), dtype=bool)
    alive = np.arange(len(m.texts))
    for name in order:
        if not len(alive):
            break
        rejected = RULES[name](m, alive)
        kept[alive[rejected]] = False
        alive = alive[~rejected]
    return kept


def _order_for(docs: DataFrame) -> list[str]:
    """The cascade's order, from rows whose hash falls into one of so many parts that about ``SAMPLE_ROWS`` are taken."""
    parts = max(1, docs.count() // SAMPLE_ROWS)
    rows = docs.where("text is not null").where(F.pmod(F.xxhash64(F.col("doc_id").cast("string"), F.substring("text", 1, 64)), F.lit(parts)) == 0).select("text").limit(2 * SAMPLE_ROWS).collect()
    return cascade_order([r.text.encode() for r in rows])


def quality_report(docs: DataFrame) -> DataFrame:
    """Rows (doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept)."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    order = _order_for(docs)
    measures = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]

    def judge(batches):
        for batch in batches:
            for part in frames.pieces(batch):
                m = Measured(frames.raw(part))
                values = [pa.array(m.get(x, np.arange(part.num_rows))) for x in measures]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *values, pa.array(m.base_failed()), pa.array(verdicts(m, order))], names=["doc_id", *measures, "base_failed", "kept"])

    return docs.mapInArrow(judge, "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean")


def quality_filter(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that the cascade keeps, with all their columns; one pass, no shuffle."""
    order = _order_for(docs)

    def keep(batches):
        for batch in batches:
            for part in frames.pieces(batch):
                yield part.filter(pa.array(verdicts(Measured(frames.raw(part)), order)))

    return docs.mapInArrow(keep, docs.schema)

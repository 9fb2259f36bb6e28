"""Benchmark decontamination with a distributed positional inverted index.

* Index.  ``build_index`` gives the postings of all tokens of all documents: a row per segment and term with the number
  of the term's positions in the segment's token stream and the gaps between them (the first counts from 0), and a row
  per segment with its documents and their lengths.  A
  segment is a run of documents of at most ``SEGMENT_BYTES`` (or one longer document), so that no posting list and no
  task grows with the corpus.  The table can be kept and searched again (``search``).
* Search.  Queries are windows of consecutive item words, equal ones once, as a table.  The terms' counts are added up
  over the index; a window is sent, by a join, to the segments that hold its rarest term, and to no others.  There
  the lists of its terms, shifted by their offsets, are intersected from the rarest on; an empty intersection ends a
  window early.  What is left are the exact phrase matches.  With ``slop`` the nearest following and preceding terms of
  each occurrence of the rarest one give the proximity matches: all terms in order, in a stretch at most ``slop`` words
  longer than the window.

Neither benchmark nor hits visit the driver; windows stream through a segment's task, which holds only that segment.

Odd input: null or wordless items ask nothing and wordless documents have no hits; items with equal ids count once;
an item of fewer words than a window is one query of all its words; rows of documents that repeat are answered alike,
each by itself; a null item id is named by the empty string; empty tables give no rows or no hits; extra columns are
ignored by the reports and kept by ``remove_contaminated``.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import frames
from .wordhash import words_of

WINDOW = 13
#: Text bytes of one segment of the index.
SEGMENT_BYTES = 3 << 20
#: Contaminated texts (rows of 16 bytes) up to which their table is broadcast; above, a salted join removes them.
BROADCAST_ROWS, SALTS = 500_000, 16
_U = np.uint64
_WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
INDEX = "segment long, term long, n int, gaps array<int>, doc_id array<long>, n_words array<long>, digest array<binary>"


def item_words(text: str | None) -> list[bytes]:
    return _WORD.findall((text or "").encode().lower())


def build_index(docs: DataFrame, digests: bool = False, segment_bytes: int = SEGMENT_BYTES) -> DataFrame:
    """The index of ``docs`` (doc_id, text).  A row with a null term tells a segment's documents."""

    def build(batches):
        number, names = TaskContext.get().partitionId() << 33, ["segment", "term", "n", "gaps", "doc_id", "n_words", "digest"]
        for batch in batches:
            for part in frames.pieces(batch, limit=segment_bytes):
                texts = frames.raw(part)
                ids, _, _, n_words = words_of(texts, kind="alnum")[:4]
                order = np.argsort(ids, kind="stable")
                ids = ids[order]
                first = np.flatnonzero(np.concatenate(([True], ids[1:] != ids[:-1]))) if len(ids) else np.zeros(0, np.int64)
                n = len(first)
                gaps = np.diff(order, prepend=0)
                gaps[first] = order[first]
                lists = pa.ListArray.from_arrays(pa.array(np.append(first, len(ids)).astype(np.int32)), pa.array(gaps.astype(np.int32)))
                none = [pa.nulls(n, pa.list_(t)) for t in (pa.int64(), pa.int64(), pa.binary())]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, number)), pa.array(ids[first].view(np.int64)), pa.array(np.diff(first, append=len(ids)).astype(np.int32)), lists, *none], names=names)
                marks = [[hashlib.md5(t).digest() for t in texts]] if digests else [None]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([number]), pa.nulls(1, pa.int64()), pa.array([len(texts)], pa.int32()), pa.nulls(1, pa.list_(pa.int32())), pa.array([part.column("doc_id").to_pylist()], pa.list_(pa.int64())), pa.array([n_words], pa.list_(pa.int64())), pa.array(marks, pa.list_(pa.binary()))],
                    names=names,
                )
                number += 1

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(build, INDEX)


def windows_of(benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """Rows (terms, items): the different windows of the items, with the sorted ids of the items that hold them."""

    def cut(batches):
        for batch in batches:
            for part in frames.pieces(batch):
                ids, _, _, counts = words_of(frames.raw(part), kind="alnum")[:4]
                per = np.where(counts >= size, counts - size + 1, (counts > 0).astype(np.int64))
                begins = np.cumsum(counts) - counts
                place = np.arange(per.sum()) - np.repeat(np.cumsum(per) - per, per) + np.repeat(begins, per)
                length = np.repeat(np.minimum(counts, size), per)
                offsets = np.concatenate(([0], np.cumsum(length)))
                flat = np.repeat(place - offsets[:-1], length) + np.arange(offsets[-1])
                terms = pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(ids[flat].view(np.int64)))
                yield pa.RecordBatch.from_arrays([terms, part.column("item").take(pa.array(np.repeat(np.arange(part.num_rows), per)))], names=["terms", "item"])

    rows = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(cut, "terms array<long>, item string").groupBy("terms").agg(F.array_sort(F.collect_set("item")).alias("items"))


class Segment:
    """One segment of the index while its windows pass by."""

    def __init__(self, number: int):
        self.number, self.parts = number, []
        self.terms = None
        self.found: dict[int, set[str]] = {}
        self.close: dict[int, set[str]] = {}

    def documents(self, row: dict):
        self.doc_id, self.n_words, self.digest = row["doc_id"], np.array(row["n_words"], dtype=np.int64), row["digest"]
        self.ends = np.cumsum(self.n_words)
        self.cover = np.zeros(int(self.n_words.sum()) + 1, dtype=np.int64)

    def postings(self, terms: np.ndarray, lists: pa.ListArray):
        offsets = lists.offsets.to_numpy()
        total = np.cumsum(np.concatenate(([0], lists.values.to_numpy()[offsets[0] : offsets[-1]])), dtype=np.int64)
        offsets = offsets - offsets[0]
        self.parts.append((terms, offsets[:-1], offsets[1:], total[1:] - np.repeat(total[offsets[:-1]], np.diff(offsets))))

    def ready(self):
        """The postings in one place, by term."""
        terms = np.concatenate([p[0] for p in self.parts]) if self.parts else np.zeros(0, np.int64)
        shift = np.cumsum([0, *(len(p[3]) for p in self.parts)])
        self.flat = np.concatenate([p[3] for p in self.parts]) if self.parts else np.zeros(0, np.int64)
        begin = np.concatenate([p[1] + s for p, s in zip(self.parts, shift)]) if self.parts else terms
        end = np.concatenate([p[2] + s for p, s in zip(self.parts, shift)]) if self.parts else terms
        by = np.argsort(terms)
        self.terms, self.begin, self.end, self.parts = terms[by], begin[by], end[by], []

    def of(self, k: int) -> np.ndarray:
        return self.flat[self.begin[k] : self.end[k]]

    def inside(self, first: np.ndarray, last: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.ends, first, side="right") == np.searchsorted(self.ends, last, side="right")

    def phrase(self, query: np.ndarray) -> np.ndarray:
        """Positions at which the query's terms (as ranks) follow each other."""
        start = None
        for k in np.argsort(self.end[query] - self.begin[query], kind="stable").tolist():
            shifted = self.of(int(query[k])) - k
            if start is None:
                start = shifted
            else:
                at = np.searchsorted(shifted, start)
                at[at == len(shifted)] = 0
                start = start[shifted[at] == start]
            if not len(start):
                return start
        start = start[start >= 0]
        return start[self.inside(start, start + len(query) - 1)]

    def near(self, query: np.ndarray, slop: int) -> tuple[np.ndarray, np.ndarray]:
        """(first, last) of the tightest stretches around occurrences of the rarest term that are short enough."""
        rare = int(np.argmin(self.end[query] - self.begin[query]))
        first = last = self.of(int(query[rare]))
        for k in range(rare + 1, len(query)):
            nxt = self.of(int(query[k]))
            at = np.searchsorted(nxt, last, side="right")
            ok = at < len(nxt)
            first, last = first[ok], nxt[at[ok]]
            ok = last - first < len(query) + slop
            first, last = first[ok], last[ok]
            if not len(first):
                return first, last
        for k in range(rare - 1, -1, -1):
            before = self.of(int(query[k]))
            at = np.searchsorted(before, first, side="left") - 1
            ok = at >= 0
            first, last = before[at[ok]], last[ok]
            ok = last - first < len(query) + slop
            first, last = first[ok], last[ok]
            if not len(first):
                return first, last
        ok = self.inside(first, last)
        return first[ok], last[ok]

    def ask(self, windows: pa.ListArray, items: pa.ListArray, slop: int, near_is_hit: bool):
        if self.terms is None:
            self.ready()
        offsets, flat = windows.offsets.to_numpy(), windows.values.to_numpy()
        rank = np.minimum(np.searchsorted(self.terms, flat), max(0, len(self.terms) - 1))
        known = self.terms[rank] == flat if len(self.terms) else np.zeros(len(flat), dtype=bool)
        missing = np.concatenate(([0], np.cumsum(~known)))
        for w in np.flatnonzero(missing[offsets[1:]] == missing[offsets[:-1]]).tolist():
            query = rank[offsets[w] : offsets[w + 1]]
            first = self.phrase(query)
            last = first + len(query) - 1
            if slop > 0 or near_is_hit:
                near, upto = self.near(query, slop)
                if len(near):
                    self._note(self.close, near, items[w])
                if near_is_hit:
                    first, last = near, upto
            elif len(first):
                self._note(self.close, first, items[w])
            if len(first):
                np.add.at(self.cover, first, 1)
                np.add.at(self.cover, last + 1, -1)
                self._note(self.found, first, items[w])

    def _note(self, to: dict[int, set[str]], first: np.ndarray, items: pa.Scalar):
        names = items.as_py()
        for d in np.unique(np.searchsorted(self.ends, first, side="right")).tolist():
            to.setdefault(d, set()).update(names)

    def report(self) -> pa.RecordBatch:
        covered = np.cumsum(self.cover)[:-1] > 0
        total = np.concatenate(([0], np.cumsum(covered)))
        n_hit = total[self.ends] - total[self.ends - self.n_words]
        items = [sorted(self.found.get(d, ())) for d in range(len(self.n_words))]
        names = [hashlib.sha256(",".join(x).encode()).hexdigest() for x in items]
        spans = [_runs(covered[e - n : e]) if h else [] for e, n, h in zip(self.ends.tolist(), self.n_words.tolist(), n_hit.tolist())]
        near = [len(self.close.get(d, ())) for d in range(len(self.n_words))]
        return pa.RecordBatch.from_arrays(
            [
                pa.array(self.doc_id, pa.int64()), pa.array(self.n_words), pa.array(n_hit.astype(np.int64)), pa.array([len(x) for x in items], pa.int64()), pa.array(names, pa.string()), pa.array(contaminated(n_hit, self.n_words)),
                pa.array(near, pa.int64()), pa.array(items, pa.list_(pa.string())), pa.array(spans, pa.list_(pa.int64())), pa.array(self.digest or [None] * len(names), pa.binary()),
            ],
            names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "n_near_items", "items", "spans", "digest"],
        )


def _runs(covered: np.ndarray) -> list[int]:
    """Covered stretches of one document as begin, end, begin, end ..."""
    return np.flatnonzero(np.diff(covered, prepend=False, append=False)).tolist()


def contaminated(n_hit: np.ndarray, n_words: np.ndarray) -> np.ndarray:
    return (n_hit > 0) & (20 * n_hit >= n_words)


def _solve(slop: int, near_is_hit: bool):
    def run(batches):
        now: Segment | None = None
        for batch in batches:
            segment, kind = batch.column("segment").to_numpy(), batch.column("kind").to_numpy()
            cuts = np.flatnonzero(np.concatenate(([True], (segment[1:] != segment[:-1]) | (kind[1:] != kind[:-1])))).tolist() if len(segment) else []
            for a, b in zip(cuts, [*cuts[1:], len(segment)]):
                if now is None or now.number != segment[a]:
                    if now is not None:
                        yield now.report()
                    now = Segment(segment[a])
                part = batch.slice(a, b - a)
                if kind[a] == 0:
                    now.documents(part.select(["doc_id", "n_words", "digest"]).to_pylist()[0])
                elif kind[a] == 1:
                    now.postings(part.column("term").to_numpy(), part.column("gaps"))
                else:
                    now.ask(part.column("terms"), part.column("items"), slop, near_is_hit)
        if now is not None:
            yield now.report()

    return run


def search(index: DataFrame, benchmark: DataFrame, size: int = WINDOW, slop: int = 0, near_is_hit: bool = False) -> DataFrame:
    """The report of a stored index; columns of ``decontamination_report`` and each document's digest, if it has one."""
    scratch = frames.Scratch(index.sparkSession, "search")
    asked = scratch.keep(windows_of(benchmark, size), "asked").withColumn("w", F.monotonically_increasing_id())
    asked = scratch.keep(asked, "windows")
    held = asked.select("w", F.explode(F.array_distinct("terms")).alias("term"))
    postings = index.where("term is not null").join(held.select("term").distinct(), "term")
    counts = postings.groupBy("term").agg(F.sum("n").alias("n"))
    # A window is asked only if the index has all its terms, and where its rarest one is.
    rarest = held.join(counts, "term", "left").groupBy("w").agg(F.count("*").alias("all"), F.count("n").alias("there"), F.min(F.struct("n", "term")).alias("m")).where("all = there").select("w", F.col("m.term").alias("term"))
    routed = rarest.join(postings.select("segment", "term"), "term").select("segment", "w").join(asked, "w")
    empty = {"doc_id": "array<long>", "n_words": "array<long>", "digest": "array<binary>", "term": "long", "gaps": "array<int>", "terms": "array<long>", "items": "array<string>"}

    def row(df: DataFrame, kind: int, *own: str) -> DataFrame:
        return df.select("segment", F.lit(kind).alias("kind"), *[F.col(c) if c in own else F.lit(None).cast(t).alias(c) for c, t in empty.items()])

    rows = row(index.where("term is null"), 0, "doc_id", "n_words", "digest").unionByName(row(postings, 1, "term", "gaps")).unionByName(row(routed, 2, "terms", "items"))
    schema = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, n_near_items long, items array<string>, spans array<long>, digest binary"
    return rows.repartition("segment").sortWithinPartitions("segment", "kind").mapInArrow(_solve(slop, near_is_hit), schema)


def decontamination_report(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW, slop: int = 0) -> DataFrame:
    """Rows (doc_id, n_words, n_hit, n_items, items_sha256, contaminated, n_near_items, items, spans), one per document.

    Hits are exact; ``n_near_items`` counts the items with a window within ``slop`` words.
    """
    index = frames.Scratch(docs.sparkSession, "index").keep(build_index(docs), "index", "zstd")
    return search(index, benchmark, size, slop).drop("digest")


def proximity_matches(docs: DataFrame, benchmark: DataFrame, slop: int, size: int = WINDOW) -> DataFrame:
    """As ``decontamination_report``, with proximity matches as the hits."""
    index = frames.Scratch(docs.sparkSession, "index").keep(build_index(docs), "index", "zstd")
    return search(index, benchmark, size, slop, near_is_hit=True).drop("digest")


def remove_contaminated(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """The rows of ``docs`` that are not contaminated, with all their columns.

    Whether a row is contaminated follows from its text alone, so rows are removed by the digest of their text.
    """
    scratch = frames.Scratch(docs.sparkSession, "clean")
    index = scratch.keep(build_index(docs.select(F.lit(None).cast("long").alias("doc_id"), "text"), digests=True), "index", "zstd")
    mark, salt = (frames.free(docs, c) for c in ("mark", "salt"))
    bad = scratch.keep(search(index, benchmark, size).where("contaminated").select(F.col("digest").alias(mark)).distinct(), "bad")
    keyed = docs.withColumn(mark, F.unhex(F.md5(F.col("text").cast("string").cast("binary"))))
    if bad.count() <= BROADCAST_ROWS:
        return keyed.join(F.broadcast(bad), mark, "left_anti").select(docs.columns)
    # Copies of one text may be a third of all rows: they are dealt over the salts.
    bad = bad.withColumn(salt, F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    keyed = keyed.withColumn(salt, F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)).cast("int"))
    return keyed.join(bad, [mark, salt], "left_anti").select(docs.columns)

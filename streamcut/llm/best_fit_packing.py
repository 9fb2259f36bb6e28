"""Best-fit packing of tokenised documents, with large-item matching.

Documents are tokenised by a public byte-level BPE and end with id 0; one longer than the capacity is cut into pieces of
full capacity, the first of which may be shorter.  Lengths are whole numbers up to the capacity, so the whole packing
problem is a histogram with at most ``capacity`` bars, whatever the number of documents.  The driver packs the histogram
and the executors place the pieces:

1. Pieces above one third of the capacity fit at most twice into a sequence.  They are matched greedily: the longest
   takes the longest partner that fits.
2. Smaller pieces, longest first, go where they leave the least room, and into new sequences when none has room.

Both steps work on runs of alike sequences, never on single pieces; each step on a length splits few runs, so the plan
has a few thousand rows.  A piece finds its place by its length and its rank among the pieces of that length.  Ranks
need no global sort: a task numbers its own pieces by length, and the tasks' counts by length are added up.

The ids are those of the ``tokenizers`` file.  Texts are cut at blanks between two characters that are not white space,
where the tokenizer always begins a new token; a task keeps the ids of chunks it has seen, by 64-bit hash, and encodes
new ones in bulk with ``tiktoken`` ranks made from the same vocabulary.  A text in which a blank touches other white space
is encoded whole, and one with a special string of the file is cut there, as the tokenizer does.

Odd input: a null text is empty and has the one id 0; rows that repeat or share an id are pieces of their own; a null
id stays null; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import json
import re
import zlib
from bisect import bisect_left, insort

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import frames
from .wordhash import hash_spans

CAPACITY = 2048
#: Chunks of text whose ids a task remembers.
CACHED = 400_000
_LOOSE = re.compile(r" (?=\s)|(?<=\s) |^\s|\s$|^$")


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _byte_of_symbol() -> dict[str, int]:
    """The byte-level alphabet: printable bytes stand for themselves, the others follow from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(others)}


class Encoder:
    """Token ids of many texts at once, as the tokenizer file gives them; its special strings are their own tokens."""

    def __init__(self, path: str):
        import public_tokenizers
        import tiktoken

        with open(path, encoding="utf-8") as f:
            file = json.load(f)
        self.special = {t["content"]: t["id"] for t in file.get("added_tokens", ())}
        self.cut = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        of = _byte_of_symbol()
        ranks = {bytes(of[c] for c in t): i for t, i in file["model"]["vocab"].items() if all(c in of for c in t) and t not in self.special}
        self.bpe = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.line = self.bpe.encode_ordinary("\n")
        self.forget()

    def forget(self):
        """An empty memory: hashes of chunks in order, and where the ids of each begin and how many they are."""
        self.known, self.begin, self.length = np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
        self.ids = np.zeros(0, dtype=np.uint32)

    def _encode(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids, numbers of ids): chunks without line breaks as lines of one text, the others one by one."""
        ids: list[np.ndarray | None] = [None] * len(chunks)
        plain = [k for k, c in enumerate(chunks) if "\n" not in c and "\r" not in c]
        if plain:
            every = self.bpe.encode_to_numpy("\n".join(chunks[k] for k in plain) + "\n")
            cuts = np.flatnonzero(every == self.line[0])
            if len(cuts) == len(plain):  # else a chunk joins the break
                for k, a, b in zip(plain, [0, *(cuts[:-1] + 1).tolist()], cuts.tolist()):
                    ids[k] = every[a:b]
        ids = [self.bpe.encode_to_numpy(c) if x is None else x for c, x in zip(chunks, ids)]
        return np.concatenate(ids).astype(np.uint32), np.array([len(x) for x in ids], dtype=np.int64)

    def _learn(self, hashes: np.ndarray, chunks: list[str]):
        ids, n = self._encode(chunks)
        begin = len(self.ids) + np.cumsum(n) - n
        self.ids = np.concatenate([self.ids, ids])
        known = np.concatenate([self.known, hashes])
        order = np.argsort(known, kind="stable")
        self.known, self.begin, self.length = known[order], np.concatenate([self.begin, begin])[order], np.concatenate([self.length, n])[order]

    def whole(self, text: str) -> np.ndarray:
        if self.cut is None or not self.cut.search(text):
            return self.bpe.encode_to_numpy(text).astype(np.uint32)
        return np.concatenate([np.array([self.special[part]], dtype=np.uint32) if part in self.special else self.bpe.encode_to_numpy(part).astype(np.uint32) for part in self.cut.split(text) if part] or [np.zeros(0, np.uint32)])

    def __call__(self, texts: list[str]) -> list[np.ndarray]:
        out: list[np.ndarray | None] = [None] * len(texts)
        rows, raw = [], []
        for k, text in enumerate(texts):
            if _LOOSE.search(text) or any(s in text for s in self.special):
                out[k] = self.whole(text)
            else:
                rows.append(k)
                raw.append(text.encode())
        if not rows:
            return out
        joined = np.frombuffer(b"".join(raw), dtype=np.uint8)
        ends = np.cumsum([len(t) for t in raw])
        first = np.union1d(np.flatnonzero(joined == 32), np.concatenate(([0], ends[:-1])))
        last = np.append(first[1:], len(joined))
        found, one, at = np.unique(hash_spans(joined, first, last), return_index=True, return_inverse=True)
        if len(self.known) > CACHED:
            self.forget()
        new = np.ones(len(found), dtype=bool)
        if len(self.known):
            new = self.known[np.minimum(np.searchsorted(self.known, found), len(self.known) - 1)] != found
        if new.any():
            flat = joined.tobytes()
            self._learn(found[new], [flat[a:b].decode() for a, b in zip(first[one[new]].tolist(), last[one[new]].tolist())])
        place = np.searchsorted(self.known, found)
        begin, n = self.begin[place][at], self.length[place][at]
        total = np.cumsum(n)
        ids = self.ids[np.repeat(begin - (total - n), n) + np.arange(total[-1])]
        ends = total[np.searchsorted(first, ends) - 1]
        for k, a, b in zip(rows, [0, *ends[:-1].tolist()], ends.tolist()):
            out[k] = ids[a:b]
        return out


def pieces_of(docs: DataFrame, path: str, capacity: int = CAPACITY) -> DataFrame:
    """Rows (doc_id, piece, start, length, ids_crc32, task, nth): nth counts the task's pieces of that length."""

    def cut(batches):
        encode, seen, task = Encoder(path), np.zeros(capacity + 1, dtype=np.int64), TaskContext.get().partitionId()
        for batch in batches:
            for part in frames.pieces(batch, limit=2 << 20):
                rows = []
                for doc, ids in zip(part.column("doc_id").to_pylist(), encode([t or "" for t in part.column("text").to_pylist()])):
                    ids = np.append(ids, np.uint32(0)).astype("<u4")
                    first = len(ids) % capacity or capacity
                    for k, at in enumerate([0, *range(first, len(ids), capacity)]):
                        piece = ids[at : at + (capacity if k else first)]
                        rows.append((doc, k, at, len(piece), zlib.crc32(piece.tobytes()), int(seen[len(piece)])))
                        seen[len(piece)] += 1
                columns = list(zip(*rows))
                types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([*(pa.array(c, t) for c, t in zip(columns, types)), pa.array([task] * len(rows), pa.int32()), pa.array(columns[5], pa.int64())], names=["doc_id", "piece", "start", "length", "ids_crc32", "task", "nth"])

    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(cut, "doc_id long, piece int, start long, length long, ids_crc32 long, task int, nth long")


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int]]:
    """Slots (length, rank_from, rank_to, sequence, offset): ranks of a length go to consecutive sequences."""
    left = {n: c for n, c in histogram.items() if c > 0}
    taken = dict.fromkeys(left, 0)
    slots: list[tuple[int, int, int, int, int]] = []
    runs: dict[int, list[tuple[int, int]]] = {}  # room -> runs (first sequence, how many)
    rooms: list[int] = []
    made = 0

    def put(length: int, count: int, sequence: int, offset: int):
        slots.append((length, taken[length], taken[length] + count, sequence, offset))
        taken[length] += count
        left[length] -= count
        if not left[length]:
            del left[length]

    def leave(room: int, sequence: int, count: int):
        if room:
            if room not in runs:
                insort(rooms, room)
            runs.setdefault(room, []).append((sequence, count))

    large = sorted(n for n in left if 3 * n > capacity)
    while large:
        n = large[-1]
        fits = bisect_left(large, capacity - n + 1) - 1
        partner = large[fits] if fits >= 0 else None
        if partner == n and left[n] == 1:
            partner = large[fits - 1] if fits else None
        count = left[n] if partner is None else left[n] // 2 if partner == n else min(left[n], left[partner])
        put(n, count, made, 0)
        if partner is not None:
            put(partner, count, made, n)
        leave(capacity - n - (partner or 0), made, count)
        made += count
        large = [x for x in large if x in left]
    for n in sorted(left, reverse=True):
        while n in left:
            at = bisect_left(rooms, n)
            if at == len(rooms):
                each = capacity // n
                full, rest = divmod(left[n], each)
                for times, bins in ((each, full), (rest, 1 if rest else 0)):
                    for k in range(times if bins else 0):
                        put(n, bins, made, k * n)
                    if bins:
                        leave(capacity - times * n, made, bins)
                        made += bins
                continue
            room = rooms[at]
            first, count = runs[room].pop()
            if not runs[room]:
                del runs[room], rooms[at]
            some = min(count, left[n])
            put(n, some, first, capacity - room)
            leave(room - n, first, some)
            if some < count:
                leave(room, first + some, count - some)
    return slots


def pack(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """Rows (doc_id, piece, start, length, ids_crc32, sequence_id, offset), one per piece."""
    spark = docs.sparkSession
    scratch = frames.Scratch(spark, "packing")
    made = scratch.keep(pieces_of(docs, path or default_tokenizer(), capacity), "pieces")
    counts = made.groupBy("task", "length").agg(F.count("*").alias("n"))
    counts = scratch.keep(counts, "counts")
    histogram = {r.length: r.n for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    slots = np.array(plan(histogram, capacity), dtype=np.int64).reshape(-1, 5)
    slots = slots[np.lexsort((slots[:, 1], slots[:, 0]))]
    key = slots[:, 0] << 44 | slots[:, 1]
    before = counts.select("task", "length", F.expr("sum(n) over (partition by length order by task) - n").alias("before"))
    ranked = made.join(before, ["task", "length"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("before") + F.col("nth")).alias("rank"))
    table = spark.sparkContext.broadcast((slots, key))

    def place(batches):
        rows, keys = table.value
        for b in batches:
            length, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            at = np.searchsorted(keys, length << 44 | rank, side="right") - 1
            found = rows[at]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in range(5)), pa.array(found[:, 3] + rank - found[:, 1]), pa.array(found[:, 4])], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")

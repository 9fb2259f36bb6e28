"""Language-model scoring with Elias-Fano n-gram tries.

The model is a bigram model with a frequency-banded Dirichlet prior:

    p(w | u) = (c(u w) + m(u) p(w)) / (c(u) + m(u)),   p(w) = (c(w) - D [c(w) > 0]) / N + D V / (N (V + 1))

where m(u) = STRENGTH * 2**band(u) and band(u) is the binary logarithm of u's own count + 1 (0 for words seen at most once).
Any m(u) gives probabilities that sum to 1 over the known words and one unseen word.

The corpus is never gathered in one place.  The numerator needs what is known of the word w and its contexts, the
denominator only what is known of u, so a log probability is a sum over words:

1. one pass counts the training words (summed per task before the shuffle) and gives N, V and the counts table;
2. a second one deals all token occurrences, in packed blocks of a few thousand documents, to shards by word.  A shard
   counts its training occurrences, builds its part of the trie (Elias-Fano levels in mapped files), answers all its
   occurrences by successor search, and returns one partial sum per document of a block;
3. the partial sums are added up per block.

What a shard must know of a context is its band.  Blocks write it beside the context, for the TOLD most frequent words, of
which every task is told.  The bands of the other repeated words go from the counts table straight to the shards whose
pairs have them as a context, by a join.  Both give the word's own band, so scores don't depend on which way it came.

The number of shards follows the number of tokens, so that a shard holds about ``SHARD_TOKENS`` at any size.  Words that
make up a quarter of a shard (under four times as many words as shards), or a thousandth of all tokens, are dealt by word
and context, so that no shard grows with them; their counts are sent along.  Contexts are 40-bit codes: 5 bits of band and 35 of hash, so a
context that was never seen before a word passes for a seen one with a chance of about (contexts of the word) / 2**35.

Odd input: a null text is empty and has the one token "end"; rows that repeat are scored alike and count each in
training; a null id isn't held out; with no training rows every token has probability 1.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import frames
from .elias_fano import Trie
from .toxicity import held_out
from .wordhash import mix, words_of

STRENGTH, DISCOUNT = 8.0, 0.75
#: Words, the most frequent ones, whose bands every task is told; the others' are sent where they are asked for.
TOLD = 1 << 20
#: Asked pairs that a task of the join packs at once.
PACK = 2_000_000
#: Training tokens of one shard; there are at least twice as many shards as the session has shuffle partitions.
SHARD_TOKENS = 2_000_000
#: Tokens, and documents, of one packed block.
BLOCK_TOKENS, BLOCK_DOCS = 1_200_000, 60_000
_U = np.uint64
END, START = _U(0xE1D0E1D0E1D0E1D1), _U(0x57A2757A27500001)


def _tokens(texts: list[bytes]):
    """(ids with an end after each text, tokens per text)."""
    ids, _, _, counts, _ = words_of(texts)
    ends = np.cumsum(counts)
    return np.insert(ids, ends, END), counts + 1


def _slot(ids: np.ndarray) -> np.ndarray:
    """The key under which a word's count is kept: its own."""
    return ids.view(np.int64)


def _band(c: np.ndarray) -> np.ndarray:
    return np.where(c > 1, np.minimum(31, np.log2(c + 1)), 0).astype(np.uint8)


def _code(before: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """A context of a word, above the five bits of its band."""
    return (mix(before * _U(3) ^ mix(ids)) >> _U(29)) << _U(5)


def _shard(ids: np.ndarray, code: np.ndarray, known: Statistics, shards: int) -> np.ndarray:
    shard = mix(ids ^ _U(0x51AB))
    if len(known.hot):
        at = np.minimum(np.searchsorted(known.hot, ids), len(known.hot) - 1)
        shard = np.where(known.hot[at] == ids, mix(ids ^ code), shard)
    return shard % _U(shards)


class Statistics:
    """What every task is told: totals, and of the most frequent words the bands (``told``) and counts (``hot``)."""

    def __init__(self, total: int, distinct: int, docs: int, told: np.ndarray, told_bands: np.ndarray, hot: np.ndarray, hot_counts: np.ndarray):
        self.total, self.distinct, self.docs, self.told, self.told_bands, self.hot, self.hot_counts = total, distinct, docs, told, told_bands, hot, hot_counts

    def tell(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(which words are told, their bands, else 0)."""
        if not len(self.told):
            return np.zeros(len(ids), dtype=bool), np.zeros(len(ids), dtype=np.uint8)
        key = _slot(ids)
        at = np.minimum(np.searchsorted(self.told, key), len(self.told) - 1)
        found = self.told[at] == key
        return found, np.where(found, self.told_bands[at], np.uint8(0))

    def prior(self, band: np.ndarray) -> np.ndarray:
        return STRENGTH * np.exp2(band.astype(float))

    def unigram(self, c: np.ndarray) -> np.ndarray:
        if not self.total:
            return np.ones(len(c))
        return np.maximum(c - DISCOUNT, 0) / self.total + DISCOUNT * self.distinct / self.total / (self.distinct + 1)


def shards_for(total: int, partitions: int) -> int:
    return max(2 * partitions, -(-total // SHARD_TOKENS))


def statistics(docs: DataFrame, scratch: frames.Scratch) -> tuple[Statistics, DataFrame | None]:
    """Counts of the training rows of ``docs`` (text, held), and the bands (w, band) of repeated words that aren't told."""

    def count(batches):
        held = []

        def merged():
            keys, n = (np.concatenate(x) for x in zip(*held))
            u, inv = np.unique(keys, return_inverse=True)
            return u, np.bincount(inv, n).astype(np.int64)

        for batch in batches:
            for part in frames.pieces(batch):
                ids, _ = _tokens(frames.raw(part))
                held.append(np.unique(ids, return_counts=True))
            if sum(len(k) for k, _ in held) > 3_000_000:
                held = [merged()]
                if len(held[0][0]) > 1_500_000:
                    yield pa.RecordBatch.from_arrays([pa.array(held[0][0].view(np.int64)), pa.array(held[0][1])], names=["w", "c"])
                    held = []
        if held:
            u, n = merged()
            for k in range(0, len(u), 200_000):
                yield pa.RecordBatch.from_arrays([pa.array(u[k : k + 200_000].view(np.int64)), pa.array(n[k : k + 200_000])], names=["w", "c"])

    counts = docs.where("not held").select("text").mapInArrow(count, "w long, c long").groupBy("w").agg(F.sum("c").alias("c"))
    counts = scratch.keep(counts, "counts")
    whole = counts.agg(F.sum("c").alias("n"), F.count("*").alias("v")).first()
    total, distinct = whole.n or 0, whole.v
    end = int(END.astype(np.int64))
    n_docs = (counts.where(F.col("w") == F.lit(end)).agg(F.sum("c").alias("c")).first().c) or 0
    parts = max(1000, 4 * shards_for(total, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    often = counts.where(F.col("c") * parts >= F.lit(max(total, 1))).orderBy("w").collect()  # at most ``parts`` rows
    banded = counts.where("c > 1").select("w", F.least(F.length(F.bin(F.col("c") + 1)) - 1, F.lit(31)).alias("band"))
    words = {r.band: r.n for r in banded.groupBy("band").agg(F.count("*").alias("n")).collect()}
    least = min((b for b in words if sum(n for x, n in words.items() if x >= b) <= TOLD), default=99)
    told = banded.where(F.col("band") >= least).toArrow()
    keys, bands = told.column("w").to_numpy(), told.column("band").to_numpy().astype(np.uint8)
    by = np.argsort(keys)
    rest = banded.where(F.col("band") < least) if min(words, default=99) < least else None
    hot = np.array([r.w for r in often], dtype=np.int64).view(_U)
    order = np.argsort(hot)
    return Statistics(total, distinct, n_docs, keys[by], bands[by], hot[order], np.array([r.c for r in often], dtype=np.int64)[order]), rest


def _sent(docs: DataFrame, rest: DataFrame, stats, shards: int) -> DataFrame:
    """Bands for the shards: packed rows of pairs (word, code) whose context is a word of ``rest``."""

    def ask(batches):
        known = stats.value
        for batch in batches:
            for part in frames.pieces(batch):
                ids, n = _tokens(frames.raw(part))
                before = np.concatenate(([START], ids[:-1]))
                before[np.cumsum(n)[:-1]] = START
                open_ = ~known.tell(before)[0] & (before != START)
                pairs = np.unique(np.stack([before[open_], ids[open_]], axis=1), axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(x).view(np.int64)) for x in pairs.T], names=["w", "after"])

    def pack(batches):
        known, held, load = stats.value, [], 0

        def emit():
            before, ids, band = (np.concatenate(x) for x in zip(*held))
            code = _code(before, ids)
            shard = _shard(ids, code, known, shards).astype(np.int64)
            order = np.argsort(shard, kind="stable")
            cuts = np.searchsorted(shard[order], np.arange(shards + 1))
            rows = [(s, ids[at].tobytes(), code[at].tobytes(), band[at].tobytes()) for s, (a, b) in enumerate(zip(cuts, cuts[1:])) if b > a for at in (order[a:b],)]
            col = list(zip(*rows))
            none = pa.nulls(len(rows), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array(col[0], pa.int64()), pa.array([-1] * len(rows), pa.int64()), pa.array(col[1], pa.binary()), none, pa.array(col[2], pa.binary()), none, pa.array(col[3], pa.binary())], names=["shard", "chunk", "w", "n", "code", "doc", "held"])

        for b in batches:
            if b.num_rows:
                held.append((b.column("w").to_numpy().view(_U), b.column("after").to_numpy().view(_U), b.column("band").to_numpy().astype(np.uint8)))
                load += b.num_rows
            if load >= PACK:
                yield emit()
                held, load = [], 0
        if held:
            yield emit()

    asked = docs.select("text").mapInArrow(ask, "w long, after long")
    return asked.join(rest, "w").mapInArrow(pack, "shard long, chunk long, w binary, n binary, code binary, doc binary, held binary")


def _blocks(stats, shards: int):
    def deal(batches):
        known = stats.value
        chunk = TaskContext.get().partitionId() << 32
        texts, docs, held, load = [], [], [], 0

        def emit():
            ids, n = zip(*texts)
            ids, n = np.concatenate(ids), np.concatenate(n)
            held_ = np.concatenate(held)
            doc = np.repeat(np.arange(len(n), dtype=np.uint16), n)
            before = np.concatenate(([START], ids[:-1]))
            before[np.cumsum(n)[:-1]] = START
            code = _code(before, ids)
            shard = _shard(ids, code, known, shards).astype(np.uint32)
            code |= known.tell(before)[1].astype(_U)
            order = np.lexsort((code, ids, shard))
            shard, ids, code, doc = shard[order], ids[order], code[order], doc[order]
            cuts = np.searchsorted(shard, np.arange(shards + 1))
            rows = [[], [], [], [], [], [], []]
            flags = np.packbits(held_).tobytes()
            for s in range(shards):
                a, b = cuts[s], cuts[s + 1]
                if a == b:
                    continue
                first = np.flatnonzero(np.concatenate(([True], ids[a + 1 : b] != ids[a : b - 1])))
                packed = code[a:b].astype("<u8").view(np.uint8).reshape(-1, 8)[:, :5].tobytes()
                for col, x in zip(rows, (s, chunk, ids[a:b][first].tobytes(), np.diff(first, append=b - a).astype(np.uint32).tobytes(), packed, doc[a:b].tobytes(), flags)):
                    col.append(x)
            null = np.array([d is None for d in docs])
            for col, x in zip(rows, (int(chunk) % shards, chunk, np.array([d or 0 for d in docs], dtype=np.int64).tobytes(), n.astype(np.int64).tobytes(), np.packbits(null).tobytes(), None, flags)):
                col.append(x)
            types = (pa.int64(), pa.int64(), *[pa.binary()] * 5)
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, types)], names=["shard", "chunk", "w", "n", "code", "doc", "held"])

        for batch in batches:
            for part in frames.pieces(batch):
                ids, n = _tokens(frames.raw(part))
                if load and (load + len(ids) > BLOCK_TOKENS or len(docs) + part.num_rows > BLOCK_DOCS):
                    yield emit()
                    chunk, texts, docs, held, load = chunk + 1, [], [], [], 0
                texts.append((ids, n))
                docs += part.column("doc_id").to_pylist()
                held.append(part.column("held").to_numpy(zero_copy_only=False))
                load += len(ids)
        if docs:
            yield emit()

    return deal


def _bands(pair_w: np.ndarray, pair_code: np.ndarray, sent: list[dict]) -> np.ndarray:
    """The band of each pair's context: as written by the blocks, else as sent, else 0."""
    band = (pair_code & _U(31)).astype(np.uint8)
    if sent:
        w, code, got = (np.frombuffer(b"".join(r[c] for r in sent), t) for c, t in (("w", _U), ("code", _U), ("held", np.uint8)))
        key = mix(w ^ mix(code))
        order = np.argsort(key)
        key, got = key[order], got[order]
        want = np.flatnonzero(band == 0)
        asked = mix(pair_w[want] ^ mix(pair_code[want]))
        at = np.minimum(np.searchsorted(key, asked), len(key) - 1)
        band[want] = np.where(key[at] == asked, got[at], np.uint8(0))
    return band


def _answer(stats):
    """One shard: count, build the trie, answer every occurrence, add up per document of each block."""

    def shard(table: pa.Table):
        known = stats.value
        rows = table.to_pylist()
        del table
        sent = [r for r in rows if r["chunk"] < 0]
        meta = [r for r in rows if r["doc"] is None and r["chunk"] >= 0]
        rows = [r for r in rows if r["doc"] is not None]
        if rows:
            n_w = [np.frombuffer(r["n"], np.uint32) for r in rows]
            w = np.concatenate([np.repeat(np.frombuffer(r["w"], _U), n) for r, n in zip(rows, n_w)])
            code = np.zeros((len(w), 8), dtype=np.uint8)
            code[:, :5] = np.frombuffer(b"".join(r["code"] for r in rows), np.uint8).reshape(-1, 5)
            code = code.view("<u8").ravel()
            sizes = [len(r["doc"]) // 2 for r in rows]
            small = np.int32 if len(rows) < 1 << 15 else np.int64
            doc = np.concatenate([np.frombuffer(r["doc"], np.uint16) for r in rows]).astype(small)
            train = np.concatenate([np.unpackbits(np.frombuffer(r["held"], np.uint8))[doc[e - s : e]] == 0 for r, s, e in zip(rows, sizes, np.cumsum(sizes))])
            doc += np.repeat(np.arange(len(rows), dtype=small) << 16, sizes)
            chunks = [r["chunk"] for r in rows]
            del rows
            order = np.lexsort((code, w))
            w, code, doc, train = w[order], code[order], doc[order], train[order]
            del order
            first = np.concatenate(([True], (w[1:] != w[:-1]) | (code[1:] != code[:-1])))
            pair = np.cumsum(first, dtype=np.int32) - 1
            seen = np.bincount(pair[train], minlength=pair[-1] + 1)
            pair_w, pair_code = w[first], code[first]
            del w, code, train
            new = np.concatenate(([True], pair_w[1:] != pair_w[:-1]))
            word = np.cumsum(new) - 1
            words, count = pair_w[new], np.bincount(word, seen).astype(np.int64)
            if len(known.hot):
                at = np.minimum(np.searchsorted(known.hot, words), len(known.hot) - 1)
                count = np.where(known.hot[at] == words, known.hot_counts[at], count)
            # The trie holds the training words and pairs only.
            in_w, in_p = count > 0, seen > 0
            p = known.unigram(count)
            prior = known.prior(_bands(pair_w, pair_code, sent))
            begins = np.searchsorted(word[in_p], np.append(np.flatnonzero(in_w), len(words)))
            trie = Trie(words[in_w], np.log10(p[in_w]), begins, pair_code[in_p], np.log10(seen[in_p] + prior[in_p] * p[word[in_p]]))
            unseen = float(np.log10(known.unigram(np.zeros(1))[0]))
            got, log_w = trie.word(words)
            log_w = np.where(got >= 0, log_w, unseen)
            hit, log_p = trie.after(got[word], pair_code)
            value = np.where(hit, log_p, np.log10(prior) + log_w[word])
            # As a context, each token but the end owes the denominator of what follows it.
            mine = known.prior(_band(count))
            owed = np.where(words == END, 0.0, np.log10(count + mine))
            value = value - owed[word]
            base = np.log10(count + 0.5)[word]
            some = in_w[word].astype(float)
            cell, inverse = np.unique(doc, return_inverse=True)
            sums = [np.bincount(inverse, x[pair]) for x in (base, value, some)]
            cuts = np.searchsorted(cell, np.arange(len(chunks) + 1, dtype=np.int64) << 16)
            for c, a, b in zip(chunks, cuts, cuts[1:]):
                # The model's sums are quantised anyway: single precision is enough for them on the way.
                n = sums[2][a:b].astype(np.uint32)
                n = n.astype(np.uint8) if not len(n) or n.max() < 256 else n
                yield (c, 0, (cell[a:b] & 0xFFFF).astype(np.uint16).tobytes(), sums[0][a:b].tobytes(), sums[1][a:b].astype(np.float32).tobytes(), n.tobytes())
        for r in meta:
            yield (r["chunk"], 1, r["w"], r["n"], r["held"], r["code"])

    def run(batches):
        for t in frames.groups(batches, "shard"):
            out = list(zip(*shard(t)))
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int32()), *(pa.array(c, pa.binary()) for c in out[2:])], names=["chunk", "kind", "p", "q", "r", "s"])

    return run


def _total(stats):
    """One block: its documents' sums over all shards."""

    def run(batches):
        known = stats.value
        for t in frames.groups(batches, "chunk"):
            rows = t.to_pylist()
            meta = next(r for r in rows if r["kind"] == 1)
            ids, n = np.frombuffer(meta["p"], np.int64), np.frombuffer(meta["q"], np.int64)
            held = np.unpackbits(np.frombuffer(meta["r"], np.uint8))[: len(ids)].astype(bool)
            null = np.unpackbits(np.frombuffer(meta["s"], np.uint8))[: len(ids)].astype(bool)
            base, value, some = np.zeros(len(ids)), np.zeros(len(ids)), np.zeros(len(ids), dtype=np.int64)
            for r in rows:
                if r["kind"] == 0:
                    at = np.frombuffer(r["p"], np.uint16)
                    base[at] += np.frombuffer(r["q"], float)
                    value[at] += np.frombuffer(r["r"], np.float32)
                    some[at] += np.frombuffer(r["s"], np.uint8 if len(r["s"]) == len(at) else np.uint32)
            base -= n * np.log10(known.total + 0.5 * (known.distinct + 1))
            value -= np.log10(known.docs + STRENGTH)
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, mask=null), pa.array(held), pa.array(n), pa.array(some), pa.array(np.full(len(ids), known.total, dtype=np.int64)), pa.array(base), pa.array(value)],
                names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
            )

    return run


def score(docs: DataFrame, folds: int = 5) -> DataFrame:
    """Rows (doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score)."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), held_out("doc_id", folds).alias("held"))
    found, rest = statistics(docs, frames.Scratch(spark, "lm"))
    stats = spark.sparkContext.broadcast(found)
    shards = shards_for(found.total, int(spark.conf.get("spark.sql.shuffle.partitions")))
    dealt = docs.mapInArrow(_blocks(stats, shards), "shard long, chunk long, w binary, n binary, code binary, doc binary, held binary")
    if rest is not None:
        dealt = dealt.unionByName(_sent(docs, rest, stats, shards))
    part = dealt.repartition(shards, "shard").sortWithinPartitions("shard").mapInArrow(_answer(stats), "chunk long, kind int, p binary, q binary, r binary, s binary")
    done = part.repartition("chunk").sortWithinPartitions("chunk").mapInArrow(_total(stats), "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
    return done

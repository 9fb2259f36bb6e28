"""N-gram Jaccard join: size-banded tiles, hashed bitmap signatures, exact sorted-array intersection.

Documents are sets of distinct word shingles.  Two sets link when ``100 * |x & y| >= percent * |x | y|``.

* Tiles.  Under one order of all shingles (very frequent ones last, else by hash) two linked sets share a shingle among
  their first ``n - ceil(percent * n / 100) + 1``.  Documents that share such a shingle make a list; a list is cut into
  blocks of ``BLOCK`` documents by rising set size, and blocks whose size bands overlap are paired into tiles.  Equal
  lists are kept once.
* Bitmaps.  Each set has a parity bitmap of at least two bits a shingle.  The bits in which two bitmaps differ are at
  most the symmetric difference, which bounds the intersection from above; a pair that can't reach the threshold goes.
* Exact check.  The sets of remaining pairs are built from the whole texts and intersected as sorted arrays.
* Second bitmaps.  Documents without a possible partner leave the tiles, and equal tiles become one.  The others get
  bitmaps of eight bits a shingle, which bound the intersection almost exactly.
* Groups of many near copies.  Pairs already in one component need no check.  At first each document offers one
  partner, which is all that most groups need.  The links found join components, and the next round looks at the tiles
  that still have pairs between components: if they are few all are checked, else documents offer other partners.  No pair is dropped but inside a component, so the
  components are those of all links.

Results for odd input: null or wordless text has an empty set, linked with nothing; fewer words than a shingle make one
shingle of all words; a null id keeps its row with a null component; rows that share an id are one node, each with the
size of its own set; the result has a row per input row; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import frames
from .wordhash import mix, windows, words_of

#: Documents in a block of a tile, and the most frequent shingles that are ordered last (this order only saves work).
BLOCK, LAST = 1024, 20_000
#: Ids up to which the documents of candidate pairs are picked by a broadcast, else by a shuffled join.
BROADCAST_IDS = 500_000
#: A shingle is locally frequent if at least this share of a slice's documents, and this many, hold it.
SHARE, LEAST = 0.002, 16
_U = np.uint64


def _sets(texts: list[bytes], size: int) -> list[np.ndarray]:
    words, _, _, counts, _ = words_of(texts)
    ids, _, per = windows(words, counts, size)
    doc = np.repeat(np.arange(len(texts), dtype=_U), per)
    order = np.lexsort((ids, doc)) if len(texts) > 1 else np.argsort(ids)
    ids, doc = ids[order], doc[order]
    keep = np.ones(len(ids), dtype=bool)
    keep[1:] = (ids[1:] != ids[:-1]) | (doc[1:] != doc[:-1])
    ids, doc = ids[keep], doc[keep]
    cuts = np.searchsorted(doc, np.arange(len(texts) + 1, dtype=_U))
    return [ids[a:b] for a, b in zip(cuts, cuts[1:])]


def _frequent(docs: DataFrame, size: int) -> np.ndarray:
    """Shingles that many documents hold, rarest first: at most LAST of them, whatever the input."""

    def count(batches):
        held, n, docs_held = [], 0, 0

        def flush():
            every = np.sort(np.concatenate(held))
            first = np.flatnonzero(np.concatenate(([True], every[1:] != every[:-1])))
            times = np.diff(first, append=len(every))
            many = times >= max(LEAST, SHARE * docs_held)
            return pa.RecordBatch.from_arrays([pa.array(every[first[many]].view(np.int64)), pa.array(times[many])], names=["k", "c"])

        for batch in batches:
            for part in frames.pieces(batch):
                seen = set()
                for s in _sets(frames.raw(part), size):
                    if len(s) and (d := s.tobytes()[:64]) not in seen:
                        seen.add(d)
                        held.append(s)
                        n += len(s)
                        docs_held += 1
                if n >= 4_000_000:
                    yield flush()
                    held, n, docs_held = [], 0, 0
        if held:
            yield flush()

    found = docs.select("text").mapInArrow(count, "k long, c long").groupBy("k").agg(F.sum("c").alias("c"))
    rows = found.orderBy(F.desc("c"), "k").limit(LAST).collect()
    return np.array([r.k for r in reversed(rows)], dtype=np.int64).view(_U)


def _bitmap(s: np.ndarray, per: int = 2) -> bytes:
    bits = 1 << min(18, max(6, int(per * len(s) - 1).bit_length()))
    odd = np.bincount((s >> _U(7)).astype(np.int64) & (bits - 1), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def _index(docs: DataFrame, size: int, percent: int, frequent: np.ndarray) -> DataFrame:
    by_id = np.argsort(frequent)
    ordered = frequent[by_id]

    def build(batches):
        seen: set[bytes] = set()
        for batch in batches:
            for part in frames.pieces(batch):
                sets = _sets(frames.raw(part), size)
                n, keys, maps, d = [], [], [], np.zeros((len(sets), 2), dtype=_U)
                null = part.column("doc_id").is_null().to_pylist()
                for k, s in enumerate(sets):
                    n.append(len(s))
                    d[k] = (np.bitwise_xor.reduce(mix(s ^ _U(0x5851F42D4C957F2D))), np.add.reduce(mix(s + _U(0x14057B7EF767814F)))) if len(s) else (0, 0)
                    # A row without an id joins no list, so it must not stand for its copies.
                    if not len(s) or null[k] or (mark := d[k].tobytes()) in seen:
                        keys.append(None)
                        maps.append(None)
                        continue
                    seen.add(mark)
                    maps.append(_bitmap(s))
                    want = len(s) - (-(-percent * len(s) // 100)) + 1
                    if len(ordered):
                        at = np.minimum(np.searchsorted(ordered, s), len(ordered) - 1)
                        common = ordered[at] == s
                        if common.any():
                            s = np.concatenate((s[~common], s[common][np.argsort(by_id[at[common]], kind="stable")]))
                    keys.append(s[:want].view(np.int64))
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(n, pa.int32()), pa.array(d[:, 0].view(np.int64)), pa.array(d[:, 1].view(np.int64)), pa.array(keys, pa.list_(pa.int64())), pa.array(maps, pa.binary())],
                    names=["doc_id", "n", "d1", "d2", "keys", "bitmap"],
                )

    return docs.mapInArrow(build, "doc_id long, n int, d1 long, d2 long, keys array<long>, bitmap binary")


def _wide(texts: DataFrame, size: int) -> DataFrame:
    """Bitmaps of eight bits a shingle, for the documents that the first ones left."""

    def build(batches):
        for batch in batches:
            for part in frames.pieces(batch):
                sets = _sets(frames.raw(part), size)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([len(s) for s in sets], pa.int32()), pa.array([_bitmap(s, 8) for s in sets], pa.binary())], names=["doc_id", "n", "bitmap"])

    return texts.mapInArrow(build, "doc_id long, n int, bitmap binary").where("n > 0")


def _lists(index: DataFrame, percent: int) -> DataFrame:
    """Blocks (list_id, block, lo, hi, members) of documents that share a prefix shingle; equal short lists once.

    A shingle's documents, by rising size, are cut where the next size is out of reach of the one before.
    """

    def runs(batches):
        done: set[int] = set()
        held: list[np.ndarray] = []  # the run that may go on in the next batch, as rows of (doc, n)
        last, last_n, blocks, begun = None, 0, 0, 0

        def rows(found):
            return pa.RecordBatch.from_arrays([pa.array([f[i] for f in found], t) for i, t in enumerate((pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.list_(pa.int64())))], names=["list_id", "block", "lo", "hi", "members"])

        def close(final):
            """Full blocks of the held run, and all of it at its end."""
            nonlocal held, blocks, begun
            run = np.concatenate(held)
            held = [run]
            out = []
            begun = begun if blocks else int(run[0, 1])
            while len(run) > BLOCK or (final and blocks and len(run)):
                out.append((last ^ begun, blocks, int(run[0, 1]), int(run[:BLOCK, 1].max()), run[:BLOCK, 0]))
                blocks, run = blocks + 1, run[BLOCK:]
                held = [run]
            if final:
                if not blocks and len(run) > 1:
                    mark = int(np.add.reduce(mix(run[:, 0].astype(_U) + _U(77))).view(np.int64))
                    if mark not in done:
                        done.add(mark)
                        out.append((mark, 0, int(run[0, 1]), int(run[:, 1].max()), run[:, 0]))
                held, blocks = [], 0
            return out

        for batch in batches:
            if not batch.num_rows:
                continue
            key = batch.column("key").to_numpy()
            pairs = np.stack([batch.column("doc_id").to_numpy(), batch.column("n").to_numpy().astype(np.int64)], axis=1)
            far = 100 * pairs[:-1, 1] < percent * pairs[1:, 1]
            first = np.flatnonzero(np.concatenate(([True], (key[1:] != key[:-1]) | far)))
            size = np.diff(first, append=len(key))
            found = []
            if held and (key[0] != last or 100 * last_n < percent * pairs[0, 1]):
                found += close(True)
            marks = np.add.reduceat(mix(pairs[:, 0].astype(_U) + _U(77)), first).view(np.int64)
            inner = np.flatnonzero(size > 1)
            for g in {0, len(first) - 1, *inner.tolist()}:
                a, b = first[g], first[g] + size[g]
                if g in (0, len(first) - 1):
                    continue
                if size[g] <= BLOCK:
                    if (mark := int(marks[g])) not in done:
                        done.add(mark)
                        found.append((mark, 0, int(pairs[a, 1]), int(pairs[a:b, 1].max()), pairs[a:b, 0]))
                else:
                    for k, at in enumerate(range(a, b, BLOCK)):
                        found.append((int(key[a] ^ pairs[a, 1]), k, int(pairs[at, 1]), int(pairs[at : min(b, at + BLOCK), 1].max()), pairs[at : min(b, at + BLOCK), 0]))
            for g in dict.fromkeys((0, len(first) - 1)):  # the ends may join runs of other batches
                if g:
                    found += close(True)
                held.append(pairs[first[g] : first[g] + size[g]])
                last, last_n = int(key[first[g]]), int(pairs[first[g] + size[g] - 1, 1])
            found += close(False)
            if found:
                yield rows(found)
        if held and (found := close(True)):
            yield rows(found)

    spread = index.where("keys is not null and doc_id is not null").select("doc_id", "n", F.explode("keys").alias("key"))
    sorted_ = spread.repartition("key").sortWithinPartitions("key", "n", "doc_id")
    return sorted_.mapInArrow(runs, "list_id long, block int, lo int, hi int, members array<long>").dropDuplicates(["list_id", "block"])


def _tiles(lists: DataFrame, percent: int) -> DataFrame:
    """Membership rows (tile, side, doc_id): a block with itself, and blocks of one list whose size bands overlap."""
    own = lists.select(F.xxhash64("list_id", "block", "block").alias("tile"), F.lit(0).alias("side"), F.explode("members").alias("doc_id"))
    many = lists.join(lists.where("block > 0").select("list_id").distinct(), "list_id", "left_semi")
    a, b = many.alias("a"), many.alias("b")
    met = a.join(b, F.expr(f"a.list_id = b.list_id and a.block < b.block and 100 * a.hi >= {percent} * b.lo"))
    met = met.select(F.expr("xxhash64(a.list_id, a.block, b.block)").alias("tile"), F.explode(F.expr("array(struct(0 as side, a.members as m), struct(1 as side, b.members as m))")).alias("x"))
    return own.unionByName(met.select("tile", "x.side", F.explode("x.m").alias("doc_id")))


def _reach(n: np.ndarray, maps: list[bytes], i: np.ndarray, j: np.ndarray, percent: int) -> np.ndarray:
    """Which pairs (i, j) may reach the threshold by the bits in which their bitmaps differ."""
    width = np.array([len(m) for m in maps])
    row, whole = np.zeros(len(maps), dtype=np.int64), {}
    for w in np.unique(width):
        at = np.flatnonzero(width == w)
        row[at] = np.arange(len(at))
        whole[w] = np.frombuffer(b"".join(maps[k] for k in at), dtype=_U).reshape(len(at), -1)
    ok = np.zeros(len(i), dtype=bool)
    small, large = np.where(width[i] <= width[j], i, j), np.where(width[i] <= width[j], j, i)
    for w in whole:
        for v in (v for v in whole if v >= w):  # the wider bitmap is folded to the narrower one's bits
            every = np.flatnonzero((width[small] == w) & (width[large] == v))
            for k in range(0, len(every), step := max(1, (8 << 20) // int(w))):
                at = every[k : k + step]
                x, y = whole[w][row[small[at]]], whole[v][row[large[at]]]
                if v > w:
                    y = np.bitwise_xor.reduce(y.reshape(len(y), v // w, w // 8), axis=1)
                total = n[small[at]] + n[large[at]]
                ok[at] = (100 + percent) * (total - np.bitwise_count(x ^ y).sum(axis=1, dtype=np.int64)) >= 2 * percent * total
    return ok


def _pairs(t: pa.Table, percent: int):
    """(tile number of each row, rows' ids, i, j): pairs of rows of one tile that the sizes and bitmaps let through."""
    tile, side, ids, label = (t.column(c).to_numpy() for c in ("tile", "side", "doc_id", "label"))
    n, maps = t.column("n").to_numpy().astype(np.int64), t.column("bitmap").to_pylist()
    number = np.cumsum(np.concatenate(([0], tile[1:] != tile[:-1])))
    two = np.bincount(number, side, minlength=number[-1] + 1)[number] > 0
    upto = np.searchsorted(number << 33 | n, number << 33 | (100 * n) // percent, side="right")
    counts = upto - np.arange(len(n)) - 1
    found = []
    start = 0
    while start < len(n):
        stop = max(start + 1, int(np.searchsorted(np.cumsum(counts[start:]), 1_000_000)) + start)
        c = counts[start:stop]
        i = np.repeat(np.arange(start, stop), c)
        j = i + 1 + np.arange(c.sum()) - np.repeat(np.cumsum(c) - c, c)
        ok = (label[i] != label[j]) & (~two[i] | (side[i] != side[j]))
        i, j = i[ok], j[ok]
        ok = _reach(n, maps, i, j, percent) if len(i) else ok[:0]
        found.append(np.stack([i[ok], j[ok]]))
        start = stop
    i, j = np.concatenate(found, axis=1)
    return tile, number, ids, i, j


def _per_tiles(members: DataFrame, solve, schema: str) -> DataFrame:
    """``solve`` on whole tiles, a few megabytes of them at a time, rows by rising set size."""

    def scan(batches):
        held, load = [], 0
        for t in frames.groups(batches, "tile"):
            held.append(t)
            load += t.nbytes + 400 * t.num_rows
            if load >= 10_000_000:
                yield solve(pa.concat_tables(held).combine_chunks())
                held, load = [], 0
        if held:
            yield solve(pa.concat_tables(held).combine_chunks())

    return members.repartition("tile").sortWithinPartitions("tile", "n", "doc_id").mapInArrow(scan, schema)


def _screen(members: DataFrame, percent: int) -> DataFrame:
    """Tiles (tile, side, doc_id) of only the documents that have a possible partner; equal ones once.

    ``members``: tile, side, doc_id, label, n, bitmap.
    """

    def solve(t: pa.Table):
        _, number, ids, i, j = _pairs(t, percent)
        rows = np.unique(np.concatenate([i, j]))
        first = np.flatnonzero(np.concatenate(([True], number[rows][1:] != number[rows][:-1]))) if len(rows) else rows
        mark = np.add.reduceat(mix(ids[rows].astype(_U) + _U(99)), first).view(np.int64) if len(rows) else rows
        mark = np.repeat(mark, np.diff(first, append=len(rows))) if len(rows) else rows
        return pa.RecordBatch.from_arrays([pa.array(mark, pa.int64()), pa.array(np.zeros(len(rows), np.int32)), pa.array(ids[rows], pa.int64())], names=["tile", "side", "doc_id"])

    return _per_tiles(members, solve, "tile long, side int, doc_id long").distinct()


def _candidates(members: DataFrame, percent: int, mode: int) -> DataFrame:
    """Pairs (tile, a, b, complete) of different components that the bitmaps let through.

    A tile with few such pairs offers all (complete); another one offers for each document one partner of a smaller id
    (mode 1: the smallest id; else by a hash of the mode).  What counts as few grows with the mode, so that the rounds
    end; it is very few at first, since the tiles of a group of near copies overlap, and all their pairs together would
    be nearly all pairs of the group.
    """

    def solve(t: pa.Table):
        tile, number, ids, i, j = _pairs(t, percent)
        a, b, g = np.minimum(ids[i], ids[j]), np.maximum(ids[i], ids[j]), number[i]
        size = np.bincount(number)
        complete = np.bincount(g, minlength=len(size)) <= (4 if mode == 1 else (2 * size + 16) << 2 * (mode - 2))
        take = complete[g]
        if not take.all():
            rank = a.astype(_U) if mode == 1 else mix(a.astype(_U) * _U(2 * mode + 1) ^ b.astype(_U))
            order = np.flatnonzero(~take)
            order = order[np.lexsort((rank[order], b[order], g[order]))]
            take[order[np.concatenate(([True], (b[order][1:] != b[order][:-1]) | (g[order][1:] != g[order][:-1])))]] = True
        return pa.RecordBatch.from_arrays([pa.array(tile[i[take]]), pa.array(a[take]), pa.array(b[take]), pa.array(complete[g[take]])], names=["tile", "a", "b", "complete"])

    return _per_tiles(members, solve, "tile long, a long, b long, complete boolean")


def _linked(pairs: DataFrame, texts: DataFrame, size: int, percent: int) -> DataFrame:
    """The pairs (a, b) that link, by exact intersection of the sets of their whole texts."""

    def check(batches):
        group, pivots = None, []
        for batch in batches:
            for part in frames.pieces(batch):
                g, role, a, b = (part.column(c).to_numpy() for c in ("grp", "role", "a", "b"))
                sets = _sets(frames.raw(part), size)
                out = []
                for k, s in enumerate(sets):
                    if g[k] != group:
                        group, pivots = g[k], []
                    if role[k] == 0:
                        pivots.append((a[k], s))
                        continue
                    for pivot, p in pivots:
                        if pivot == a[k] and len(s) and len(p):
                            same = len(np.intersect1d(s, p, assume_unique=True))
                            if 100 * same >= percent * (len(s) + len(p) - same):
                                out.append((a[k], b[k]))
                if out:
                    x = np.array(out, dtype=np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(x[:, 0]), pa.array(x[:, 1])], names=["a", "b"])

    sizes = pairs.groupBy("a").agg(F.ceil(F.count("*") / 500).cast("long").alias("salts"))
    left = sizes.join(texts.withColumnRenamed("doc_id", "a"), "a").select("a", F.lit(None).cast("long").alias("b"), F.lit(0).alias("role"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("salts") - 1)).alias("salt"), "text")
    right = pairs.join(sizes, "a").select("a", "b", F.pmod(F.xxhash64("b"), F.col("salts")).alias("salt")).join(texts.withColumnRenamed("doc_id", "b"), "b").select("a", "b", F.lit(1).alias("role"), "salt", "text")
    rows = left.unionByName(right).withColumn("grp", F.xxhash64("a", "salt")).drop("salt").fillna({"b": -1})
    return rows.repartition("grp").sortWithinPartitions("grp", "role").mapInArrow(check, "a long, b long")


def jaccard_classes(docs: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """Rows (doc_id, n_shingles, component_id) of ``docs`` (doc_id, text); see the module's text."""
    spark = docs.sparkSession
    scratch = frames.Scratch(spark, "jaccard")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    index = scratch.keep(_index(docs, size, percent, _frequent(docs, size)), "index")
    first = index.where("n > 0 and doc_id is not null").groupBy("d1", "d2").agg(F.min("doc_id").alias("rep"))
    own = scratch.keep(index.select("doc_id", "n", "d1", "d2").join(first, ["d1", "d2"], "left").select("doc_id", "n", F.when(F.col("n") > 0, F.col("rep")).otherwise(F.col("doc_id")).alias("rep")), "own")
    lists = scratch.keep(_lists(index, percent), "lists")
    tiles = scratch.keep(_tiles(lists, percent), "tiles")
    scratch.drop(lists)
    met = tiles.select("doc_id").distinct()
    maps = scratch.keep(index.where("bitmap is not null").select("doc_id", "n", "bitmap").join(met, "doc_id", "left_semi"), "maps")
    # Rows that share an id, and exact copies, are linked from the start.
    label = scratch.keep(own.join(met, "doc_id", "left_semi").groupBy("doc_id").agg(F.min("rep").alias("label")), "label")
    links = own.where("doc_id <> rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b")).distinct()

    def unsettled(tiles, label):
        live = tiles.join(label, "doc_id")
        return live.join(live.groupBy("tile").agg(F.min("label").alias("x"), F.max("label").alias("y")).where("x <> y").select("tile"), "tile", "left_semi")

    wide, tiles = tiles, scratch.keep(_screen(unsettled(tiles, label).join(maps, "doc_id"), percent), "screened")
    scratch.drop(wide, maps, index)
    need = scratch.keep(tiles.select("doc_id").distinct(), "need")
    texts = scratch.keep(docs.join(F.broadcast(need) if need.count() <= BROADCAST_IDS else need, "doc_id", "left_semi"), "texts")
    maps = scratch.keep(_wide(texts, size), "wide")
    found, mode = None, 1
    while True:
        offered = scratch.keep(_candidates(unsettled(tiles, label).join(maps, "doc_id"), percent, mode), "offered")
        one = offered.where("not complete").groupBy("b").agg(F.min_by("a", F.col("a") if mode == 1 else F.xxhash64("a", F.lit(mode))).alias("a")).select("a", "b")
        pairs = scratch.keep(offered.where("complete").select("a", "b").union(one).distinct(), "pairs")
        if pairs.isEmpty():
            break
        linked = scratch.keep(_linked(pairs, texts, size, percent), "linked")
        found = linked if found is None else found.unionByName(linked)
        rest = offered.where("not complete").select("tile").distinct()
        if rest.isEmpty():
            break
        ends = linked.join(label.select(F.col("doc_id").alias("a"), F.col("label").alias("la")), "a").join(label.select(F.col("doc_id").alias("b"), F.col("label").alias("lb")), "b")
        roots = frames.components(scratch, ends.select(F.col("la").alias("a"), F.col("lb").alias("b")))
        label = scratch.keep(label.join(roots.withColumnRenamed("node", "label"), "label", "left").select("doc_id", F.coalesce("root", "label").alias("label")), "label")
        tiles, mode = scratch.keep(tiles.join(rest, "tile", "left_semi"), "tiles"), mode + 1
    if found is not None:
        links = links.unionByName(found)
    roots = frames.components(scratch, links)
    return own.join(roots, own["doc_id"] == roots["node"], "left").select(own["doc_id"], F.col("n").cast("long").alias("n_shingles"), F.coalesce("root", own["doc_id"]).alias("component_id"))

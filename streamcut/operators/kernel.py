"""The sequential placement step, without Spark.

``place`` picks among nested candidate sets: parts that hold both ends, else those of the preferred end, else those of
the other one, else all; the least loaded member wins.  This equals the arg-max of the published scores, whose balance
term stays below 1 while all other terms are whole numbers.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from itertools import repeat

_M = (1 << 64) - 1


def mix(x: int) -> int:
    x = (x + 0x9E3779B97F4A7C15) & _M
    x = ((x ^ x >> 30) * 0xBF58476D1CE4E5B9) & _M
    x = ((x ^ x >> 27) * 0x94D049BB133111EB) & _M
    return x ^ x >> 31


class Placer:
    """State of one stream: replica masks of vertices and loads of parts.

    ``guard``: ratio of the largest to the mean load from which affinity is ignored, as (numerator, denominator), or
    None.  ``tie``: 'lowest' part, or 'hash' of the seed, the edge's number and the part.
    """

    def __init__(self, p: int, guard: tuple[int, int] | None = (11, 10), tie: str = "lowest", seed: int = 0):
        self.p, self.guard, self.tie, self.seed = p, guard, tie, seed
        self.at: dict[int, int] = {}
        self.loads = [0] * p
        self.placed = self.top = 0
        self.every = (1 << p) - 1

    def over(self) -> bool:
        return self.guard is not None and self.placed > 0 and self.guard[1] * self.p * self.top >= self.guard[0] * self.placed

    def candidates(self, u: int, v: int, cmp: int) -> int:
        a, b = self.at.get(u, 0), self.at.get(v, 0)
        if a & b:
            return a & b
        if cmp == 0:
            return a | b or self.every
        low, high = (a, b) if cmp < 0 else (b, a)
        return low or high or self.every

    def least(self, mask: int, seq: int) -> int:
        loads = self.loads
        if self.tie == "lowest" and mask == self.every:
            return loads.index(min(loads))
        best, parts = None, []
        while mask:
            bit = mask & -mask
            k = bit.bit_length() - 1
            mask ^= bit
            if best is None or loads[k] < best:
                best, parts = loads[k], [k]
            elif loads[k] == best:
                parts.append(k)
        if self.tie == "lowest" or len(parts) == 1:
            return parts[0]
        return min(parts, key=lambda k: mix(mix(self.seed * 1_000_003 + seq) + k))

    def place(self, u: int, v: int, cmp: int, guarded: bool = True, seq: int = 0) -> int:
        mask = self.every if guarded and self.over() else self.candidates(u, v, cmp)
        k = self.least(mask, seq)
        bit = 1 << k
        self.at[u] = self.at.get(u, 0) | bit
        self.at[v] = self.at.get(v, 0) | bit
        self.loads[k] += 1
        self.placed += 1
        if self.loads[k] > self.top:
            self.top = self.loads[k]
        return k


    def run(self, us, vs, cmps, guards, seqs, skips=None) -> list[int | None]:
        """``place`` for many edges in turn; None for those to skip.

        Parts of equal load are kept as one mask per load, so that the least loaded member of a wide candidate set is
        found among the few lowest loads rather than by looking at each member.
        """
        out = []
        append, get, put, loads, p, every = out.append, self.at.get, self.at.__setitem__, self.loads, self.p, self.every
        num, den = self.guard if self.guard is not None else (0, 0)
        lowest, placed, top = self.tie == "lowest", self.placed, self.top
        level: dict[int, int] = {}
        for k, x in enumerate(loads):
            level[x] = level.get(x, 0) | 1 << k
        rising = sorted(level)
        for n, (u, v, c, g) in enumerate(zip(us, vs, cmps, guards)):
            if skips is not None and skips[n]:
                append(None)
                continue
            a, b = get(u, 0), get(v, 0)
            if g and num and placed and den * p * top >= num * placed:
                mask = every
            else:
                mask = a & b or ((a | b) if c == 0 else (a or b) if c < 0 else (b or a)) or every
            if not mask & (mask - 1):
                bit = mask
            elif lowest:
                for x in rising:
                    if m := mask & level[x]:
                        bit = m & -m
                        break
            else:
                bit = 1 << self.least(mask, seqs[n])
            k = bit.bit_length() - 1
            put(u, a | bit)
            put(v, (a | bit if u == v else b | bit))
            x = loads[k]
            loads[k] = x + 1
            rest = level[x] ^ bit
            if x + 1 in level:
                level[x + 1] |= bit
                if rest:
                    level[x] = rest
                else:
                    del level[x]
                    rising.remove(x)
            elif rest:
                level[x], level[x + 1] = rest, bit
                rising.insert(bisect_right(rising, x), x + 1)
            else:
                del level[x]
                level[x + 1] = bit
                rising[bisect_left(rising, x)] = x + 1
            placed += 1
            if x + 1 > top:
                top = x + 1
            append(k)
        self.placed, self.top = placed, top
        return out


class Tally:
    """As ``Placer`` over vertices numbered from 0, without an answer for each edge: only loads and replica masks."""

    def __init__(self, p: int, guard: tuple[int, int] | None, tie: str, seed: int, vertices: int):
        self.placer = Placer(p, guard, tie, seed)
        self.at = [0] * vertices

    @property
    def top(self) -> int:
        return self.placer.top

    def copies(self) -> int:
        return sum(map(int.bit_count, self.at))

    def run(self, us, vs, cmps, guards, seqs) -> None:
        """``guards`` None: the guard looks at every edge."""
        s = self.placer
        at, loads, p, every, lowest, placed, top = self.at, s.loads, s.p, s.every, s.tie == "lowest", s.placed, s.top
        num, den = s.guard if s.guard is not None else (0, 0)
        # The load of all parts together up to which the largest one is too much.
        cut = den * p * top // num if num else 0
        level: dict[int, int] = {}
        for k, x in enumerate(loads):
            level[x] = level.get(x, 0) | 1 << k
        low = min(level)
        for u, v, c, g, seq in zip(us, vs, cmps, repeat(True) if guards is None else guards, seqs):
            a, b = at[u], at[v]
            if placed <= cut and g and placed:
                mask = every
            else:
                mask = a & b or ((a | b) if c == 0 else (a or b) if c < 0 else (b or a)) or every
            if not mask & (mask - 1):
                bit = mask
            else:
                if not (m := mask & level[low]):
                    if lowest and mask.bit_count() < 9:
                        m = mask & -mask
                        x, rest = loads[m.bit_length() - 1], mask ^ m
                        while rest:
                            one = rest & -rest
                            rest ^= one
                            if (y := loads[one.bit_length() - 1]) < x:
                                m, x = one, y
                    else:
                        for x in sorted(level):
                            if m := mask & level[x]:
                                break
                # Of parts of equal load the lowest, or the least hash.
                bit = m & -m if lowest or not m & (m - 1) else 1 << s.least(m, seq)
            if not a & bit:
                at[u] = a | bit
            if not b & bit:
                at[v] = at[v] | bit
            k = bit.bit_length() - 1
            x = loads[k]
            y = loads[k] = x + 1
            if rest := level[x] ^ bit:
                level[x] = rest
            else:
                del level[x]
                if x == low:
                    low = y if not level else min(y, min(level))
            level[y] = level.get(y, 0) | bit
            placed += 1
            if y > top:
                top = y
                cut = den * p * top // num if num else 0
        s.placed, s.top = placed, top


def marginal_copies(at: dict[int, int], u: int, v: int, k: int) -> int:
    """New replicas if edge (u, v) goes to part k."""
    return sum(not at.get(w, 0) >> k & 1 for w in {u, v})


def candidate_set(a_u: set[int], a_v: set[int], d_u: int, d_v: int, p: int) -> set[int]:
    """The restricted set of the one-step model: all parts if an end is unplaced, else those of the lower-degree end."""
    if not a_u or not a_v:
        return set(range(p))
    return set(a_u) if d_u <= d_v else set(a_v)


def naive_scores(placer: Placer, u: int, v: int, cmp: int, family: str) -> list[float]:
    """The published floating-point scores of all parts: 'affinity' or 'degree'."""
    a, b = placer.at.get(u, 0), placer.at.get(v, 0)
    lo, hi = min(placer.loads), max(placer.loads)
    out = []
    for k in range(placer.p):
        s = (a >> k & 1) + (b >> k & 1)
        if family == "degree":
            s += (a >> k & 1 and cmp <= 0) + (b >> k & 1 and cmp >= 0)
        out.append(s + (hi - placer.loads[k]) / (hi - lo + 1))
    return out


class Buffered:
    """The total-degree method as a live process with real buffers; it must place as the schedule's sort does.

    ``max_buffer`` bounds the edges held: at that number the oldest held edge is placed at once, by in-degrees, as an
    edge out of a small source would be.
    """

    def __init__(self, p: int, hub_threshold: int | None = None, guard=(11, 10), guard_scope: str = "direct", release: str = "first", tie: str = "lowest", seed: int = 0, max_buffer: int | None = None):
        self.placer = Placer(p, guard, tie, seed)
        self.limit = p if hub_threshold is None else hub_threshold
        self.scope, self.release, self.max_buffer = guard_scope, release, max_buffer
        self.d_in: dict[int, int] = {}
        self.d_out: dict[int, int] = {}
        #: Held edges: target -> {number: source}, and all numbers by age.
        self.waiting: dict[int, dict[int, int]] = {}
        self.oldest: dict[int, int] = {}
        self.buffered = self.peak = self.evicted = 0

    def _total(self, u: int, v: int) -> int:
        d = self.d_in.get(u, 0) + self.d_out.get(u, 0) - self.d_in.get(v, 0) - self.d_out.get(v, 0)
        return (d > 0) - (d < 0)

    def _in(self, u: int, v: int) -> int:
        d = self.d_in.get(u, 0) - self.d_in.get(v, 0)
        return (d > 0) - (d < 0)

    def _late(self, target: int):
        for seq, u in self.waiting.pop(target, {}).items():
            del self.oldest[seq]
            self.buffered -= 1
            yield u, target, seq, self.placer.place(u, target, self._total(u, target), self.scope == "all", seq)

    def _hold(self, u: int, v: int, seq: int):
        self.waiting.setdefault(v, {})[seq] = u
        self.oldest[seq] = v
        self.buffered += 1
        if self.max_buffer is not None and self.buffered > self.max_buffer:
            first = next(iter(self.oldest))
            target = self.oldest.pop(first)
            source = self.waiting[target].pop(first)
            if not self.waiting[target]:
                del self.waiting[target]
            self.buffered -= 1
            self.evicted += 1
            yield source, target, first, self.placer.place(source, target, self._in(source, target), self.scope == "all", first)
        self.peak = max(self.peak, self.buffered)

    def block(self, u: int, targets: list[int], seq: int):
        """Rows (u, v, seq, part) placed by the arrival of u with its out-edges."""
        self.d_out[u] = len(targets)
        if self.release == "first":
            yield from self._late(u)
        for k, v in enumerate(targets):
            self.d_in[v] = self.d_in.get(v, 0) + 1
            if v not in self.d_out and len(targets) >= self.limit:
                yield from self._hold(u, v, seq + k)
                continue
            cmp = self._total(u, v) if v in self.d_out else self._in(u, v)
            yield u, v, seq + k, self.placer.place(u, v, cmp, self.scope != "none", seq + k)
        if self.release == "last":
            yield from self._late(u)

    def edge(self, u: int, v: int, seq: int, method: str) -> int:
        """The part of one edge by a method that needs no blocks."""
        self.d_in[v] = self.d_in.get(v, 0) + 1
        return self.placer.place(u, v, self._in(u, v) if method == "greedy_indegree" else 0, True, seq)

    def flush(self):
        rest = [(seq, self.waiting[v][seq], v) for seq, v in sorted(self.oldest.items())]
        self.waiting, self.oldest = {}, {}
        for seq, u, v in rest:
            self.buffered -= 1
            yield u, v, seq, self.placer.place(u, v, self._total(u, v), self.scope == "all", seq)


#: Methods that the live process, the table function and ``Buffered`` know.
LIVE = ("greedy_affinity", "greedy_indegree", "greedy_total_degree")


def check_live(method: str) -> str:
    if method not in LIVE:
        raise ValueError(f"unknown live method {method}; known: {LIVE}")
    return method

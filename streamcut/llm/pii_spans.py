"""Personal data by candidate gradient boosting, in DataFrame functions only.

1. Generators of high recall propose spans, which may overlap: the four base patterns (email, ip, card, phone) and looser
   ones (spelled-out at signs, bare at signs, numbers in groups without a plus, long tokens).
2. Evidence labels some candidates.  For: a base span that passes its own checks, a long token after a word such as
   "token" and a sign of assignment.  Against: a look-alike that can't be one (byte values, digit counts, dates, an at sign
   without a domain, a long token without a digit).  All others stay unlabelled: numbers of a card's length whose
   sum fails, spelled-out addresses, numbers in groups.  They teach nothing, so it doesn't matter how many there are.
3. Features are small whole numbers of format and context.  What makes the evidence is not among them (plus and at signs,
   brackets, sums, byte values, the words of assignment), so that the trees must judge by the rest.  The number of
   different feature vectors is bounded by the features' ranges, so counts by feature vector, over all candidates of all
   documents, are all that training needs; the driver fits boosted trees of depth two on them.
4. The trees become CASE expressions.  A fifth of the texts (by hash) is kept out of the fit; on their labelled candidates
   each kind's threshold is calibrated: the lowest score of a true candidate from which on at least ``PRECISION`` are
   true.  A candidate without evidence against it joins the spans from there on, unless it overlaps a base span or one
   of a better score.  Base spans that pass their checks always stay.

Secrets (long tokens) are spans of their own kind and are reported apart from the four kinds.

Positions come from the lengths of what lies between matches, in code points.  Loops in patterns are possessive, so
that Java runs them without recursion, and positions are summed in chunks, so that texts of any length are handled.

Odd input: a null text counts as empty and has no spans; rows that repeat or share an id are answered each by itself; a
null id stays null; extra columns are ignored by ``find`` and kept by ``redact``, whatever their names; with no labelled
candidates no model is fitted and nothing is added.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import frames

KINDS = ("email", "ip", "card", "phone", "secret")
#: Fixed patterns of the base rules, and the looser generators; (kind, generator, pattern).
GENERATORS = (
    ("email", "base", r"[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"),
    ("ip", "base", r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}+"),
    ("card", "base", r"[0-9](?:[\x20-]?[0-9])++"),
    ("phone", "base", r"\+[0-9][\x20().0-9-]+[0-9]"),
    ("email", "spelled", r"[A-Za-z0-9._%+-]++\x20?(?:\[at\]|\(at\))\x20?[A-Za-z0-9-]++(?:\x20?(?:\.|\[dot\]|\(dot\))\x20?[A-Za-z0-9-]++)++"),
    ("email", "bare", r"[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?!\.[A-Za-z0-9-])"),
    ("phone", "grouped", r"(?<![0-9+.-])(?:\([0-9]{2,4}\)|[0-9]{2,4})(?:[\x20.-][0-9]{2,4}){2,4}+(?![0-9.-])"),
    ("secret", "token", r"(?<![A-Za-z0-9_+/=-])[A-Za-z0-9_+/-]{16,}+"),
)
PRECISION, ROUNDS, RATE, FOLDS = 0.95, 40, 0.3, 5
FEATURES = ("kind", "n1", "n2", "n3", "cue", "glued", "tail")
_BYTE = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
#: Words before a candidate that speak for a kind.
_CONTEXT = {"phone": "tel|phone|call|fax|mobile|contact", "card": "card|visa|credit|pay", "email": "mail|contact|write", "ip": "ip|host|server|address"}
_SECRET = "(?:token|key|secret|passw|pwd)[a-z_]*[\"' ]*[:=][\"' ]*$"
_SPAN = "array<struct<m: string, s: int, e: int>>"
_BEFORE = "lower(substr(text, greatest(1, x.s - 23), least(24, x.s)))"


def _digits(m: str = "x.m") -> str:
    return f"regexp_replace({m}, '[^0-9]', '')"


def _luhn(m: str) -> str:
    d = _digits(m)
    each = f"cast(substr({d}, length({d}) - i, 1) as int) * (1 + i % 2)"
    return f"(length({d}) between 12 and 19 and aggregate(sequence(0, length({d}) - 1), 0, (s, i) -> s + if({each} > 9, {each} - 9, {each})) % 10 = 0)"


_VALID = {
    "email": "true",
    "ip": f"x.m rlike '^{_BYTE}(?:\\\\.{_BYTE}){{3}}$'",
    "card": _luhn("x.m"),
    "phone": f"length({_digits()}) between 9 and 15",
}
#: Labels of candidates that are no valid base span: 1, 0 or null (no evidence).
_DATE = "x.m rlike '^(?:(?:19|20)[0-9]{2}[ .-][01][0-9][ .-][0-3][0-9]|[0-3][0-9][ .-][01][0-9][ .-](?:19|20)[0-9]{2})$'"
_LABEL = {
    ("ip", "base"): "0",
    ("phone", "base"): "0",
    ("card", "base"): f"if(length({_digits()}) between 12 and 19, null, 0)",
    ("email", "spelled"): "cast(null as int)",
    ("email", "bare"): "0",
    ("phone", "grouped"): f"if(length({_digits()}) between 9 and 15 and not ({_DATE}), null, 0)",
    ("secret", "token"): f"if(not (x.m rlike '[0-9]') or not (x.m rlike '[A-Za-z]'), 0, if({_BEFORE} rlike r\"{_SECRET.replace(chr(34), chr(92) + 'x22')}\", 1, null))",
}
_DOMAIN = r"regexp_replace(regexp_extract(x.m, r'(?:@|\[at\]|\(at\))\x20?(.*)$', 1), r'\x20?(?:\[dot\]|\(dot\))\x20?', '.')"
_CORE = r"regexp_replace(x.m, r'^\+[0-9]{1,3}[\x20.-]?', '')"
#: Three numbers of a kind's format.
_FORMAT = {
    "email": (f"least(2, size(split({_DOMAIN}, '[.]')))", f"cast(substring_index({_DOMAIN}, '.', -1) rlike '^[A-Za-z]{{2,10}}$' as int)", "0"),
    "ip": ("least(4, array_max(transform(split(x.m, '[.]'), q -> length(q))))", "0", "0"),
    "card": (f"least(20, length({_digits()}))", f"least(6, length(x.m) - length({_digits()}))", "0"),
    "phone": (f"least(16, length({_digits(_CORE)}))", f"least(6, size(split(trim(BOTH ' ' FROM regexp_replace({_CORE}, '[^0-9]+', ' ')), ' ')))", "least(6, length(regexp_extract(x.m, '([0-9]+)$', 1)))"),
    "secret": ("least(8, length(x.m) div 8)", "cast(x.m rlike '[a-z]' as int) + 2 * cast(x.m rlike '[A-Z]' as int)", "cast(x.m rlike '^(?:[0-9a-f]+|[0-9A-F]+)$' as int)"),
}


def _positions(z: str) -> str:
    """Spans (m, s, e) of an array of matches and the gaps before them: sums in chunks of the root of the array's length."""
    c = f"cast(ceil(sqrt(size({z}))) as int)"

    def walk(part: str, begin: str) -> str:
        return f"""aggregate({part}, struct({begin} as at, cast(array() as {_SPAN}) as got), (a, x) -> struct(a.at + x.gap + length(x.m) as at,
            concat(a.got, array(struct(x.m as m, a.at + x.gap as s, a.at + x.gap + length(x.m) as e))) as got), a -> a.got)"""

    numbers = f"sequence(0, cast((size({z}) - 1) div {c} as int))"
    chunk = f"slice({z}, n * {c} + 1, {c})"
    sums = f"transform({numbers}, n -> aggregate({chunk}, 0, (a, x) -> a + x.gap + length(x.m)))"
    starts = f"aggregate({sums}, struct(0 as at, cast(array() as array<int>) as got), (a, x) -> struct(a.at + x as at, concat(a.got, array(a.at)) as got), a -> a.got)"
    many = f"flatten(zip_with({numbers}, {starts}, (n, begin) -> {walk(chunk, 'begin')}))"
    return f"CASE WHEN size({z}) = 0 THEN cast(array() as {_SPAN}) WHEN size({z}) <= 64 THEN {walk(z, '0')} ELSE {many} END"


def _matches(kind: str, generator: str, pattern: str) -> Column:
    """Array of (m, gap before it) of one generator; a cheap test of the text spares most texts the pattern."""
    text = F.col("text")
    maybe = {"spelled": text.rlike(r"\[at\]|\(at\)"), "token": F.lit(True)}.get(generator, text.contains("@") if kind == "email" else text.contains("+") if kind == "phone" and generator == "base" else text.rlike("[0-9]"))
    both = F.arrays_zip(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("m"), F.transform(F.split(text, pattern, -1), lambda p: F.length(p)).alias("gap"))
    return F.when(maybe, F.filter(both, lambda z: z["m"].isNotNull())).otherwise(F.expr("cast(array() as array<struct<m: string, gap: int>>)"))


def _features(kind: str) -> str:
    cue = f"cast({_BEFORE} rlike '(?:{_CONTEXT[kind]})[^a-z]*$' as int)" if kind in _CONTEXT else "0"
    a, b, c = _FORMAT[kind]
    return (
        f"struct({KINDS.index(kind)} as kind, cast({a} as int) as n1, cast({b} as int) as n2, cast({c} as int) as n3, {cue} as cue, "
        f"cast({_BEFORE} rlike '[a-z0-9]$' as int) as glued, cast(substr(text, x.e + 1, 1) rlike '[A-Za-z0-9]' as int) as tail)"
    )


def candidates(docs: DataFrame) -> DataFrame:
    """Rows (row, text, fold, base, loose): a row's own columns, its valid base spans, and all candidates.

    A candidate has its place (s, e), kind number k, features f, label y (1, 0, null) and whether it is a base span (hit).
    """
    rows = docs.select(F.struct("*").alias("row"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    for k, generator in enumerate(GENERATORS):
        rows = rows.withColumn(f"z{k}", _matches(*generator))
    for k in range(len(GENERATORS)):
        rows = rows.withColumn(f"g{k}", F.expr(_positions(f"z{k}"))).drop(f"z{k}")
    base, loose = [], []
    for k, (kind, generator, _) in enumerate(GENERATORS):
        number, valid = KINDS.index(kind), _VALID[kind] if generator == "base" else "false"
        if generator == "base":
            base.append(f"transform(filter(g{k}, x -> {valid}), x -> struct(x.s as s, {number} as k, x.e as e))")
        label = _LABEL.get((kind, generator), "0")
        loose.append(f"transform(g{k}, x -> struct(x.s as s, {number} as k, x.e as e, {_features(kind)} as f, cast(if({valid}, 1, {label}) as int) as y, {valid} as hit))")
    rows = rows.withColumn("base", F.expr(f"array_sort(concat({', '.join(base)}))"))
    return rows.select("row", "text", F.pmod(F.xxhash64("text"), F.lit(FOLDS)).cast("int").alias("fold"), "base", F.expr(f"concat({', '.join(loose)})").alias("loose"))


def boost(cells: list[tuple[tuple[int, ...], int, int]]) -> list[tuple]:
    """Trees (feature, cut, feature, cut, four leaf values) on cells (features, candidates, positives), logistic loss."""
    if len(cells) < 2:
        return []
    x = np.array([c[0] for c in cells])
    n, pos, score = (np.array(v, dtype=float) for v in ([c[1] for c in cells], [c[2] for c in cells], [0.0] * len(cells)))
    cuts = [(f, int(c)) for f in range(x.shape[1]) for c in np.unique(x[:, f])[:-1]]
    below = {fc: x[:, fc[0]] <= fc[1] for fc in cuts}
    trees = []
    for _ in range(ROUNDS):
        p = 1 / (1 + np.exp(-score))
        g, h = pos - n * p, n * p * (1 - p)

        def split(part):
            whole_g, whole_h, best = g[part].sum(), h[part].sum(), (1e-9, None)
            for fc in cuts:
                left = part & below[fc]
                if not left.any() or (left == part).all():
                    continue
                a, b = g[left].sum(), h[left].sum()
                gain = a * a / (b + 1) + (whole_g - a) ** 2 / (whole_h - b + 1) - whole_g**2 / (whole_h + 1)
                if gain > best[0] + 1e-9:
                    best = (gain, fc)
            return best[1]

        top = split(np.ones(len(cells), dtype=bool))
        if top is None:
            break
        tree = [top]
        step = np.zeros(len(cells))
        for part in (below[top], ~below[top]):
            inner = split(part) or (0, -1)
            side = x[:, inner[0]] <= inner[1]
            values = [RATE * float(g[leaf].sum()) / (float(h[leaf].sum()) + 1) for leaf in (part & side, part & ~side)]
            step += np.where(part, np.where(side, *values), 0)
            tree += [inner, *values]
        score += step
        trees.append(tuple(tree))
    return trees


def expression(trees: list[tuple], x: str) -> str:
    """The trees' summed score as SQL on a feature struct."""
    name = [f"{x}.{n}" for n in FEATURES]
    terms = [
        f"(CASE WHEN {name[f]} <= {c} THEN CASE WHEN {name[lf]} <= {lc} THEN {a!r}D ELSE {b!r}D END ELSE CASE WHEN {name[rf]} <= {rc} THEN {d!r}D ELSE {e!r}D END END)"
        for (f, c), (lf, lc), a, b, (rf, rc), d, e in trees
    ]
    return " + ".join(terms) or "0D"


def _score(trees, x):
    return sum((a if x[lf] <= lc else b) if x[f] <= c else (d if x[rf] <= rc else e) for (f, c), (lf, lc), a, b, (rf, rc), d, e in trees)


def calibrate(trees: list[tuple], cells: list[tuple[tuple[int, ...], int, int]]) -> list[float]:
    """Per kind the lowest score of a cell with positives from which on the precision holds; infinity if there is none."""
    limits = []
    for kind in range(len(KINDS)):
        ranked = sorted(((_score(trees, x), n, p) for x, n, p in cells if x[0] == kind), reverse=True)
        limit, n, pos = math.inf, 0, 0
        for k, (s, a, b) in enumerate(ranked):
            n, pos = n + a, pos + b
            if (k + 1 == len(ranked) or ranked[k + 1][0] < s) and pos >= PRECISION * n and any(p for t, _, p in ranked if t == s):
                limit = s - 1e-9
        limits.append(limit)
    return limits


def train(found: DataFrame) -> tuple[list[tuple], list[float]]:
    """Trees and the calibrated threshold of each kind, from the labelled ones of all candidates."""
    one = found.where("size(loose) > 0").select("fold", F.explode("loose").alias("c")).where("c.y is not null")
    rows = one.groupBy((F.col("fold") == 0).alias("apart"), "c.f").agg(F.count("*").alias("n"), F.sum("c.y").alias("pos")).collect()  # bounded by the features' ranges
    cells = {a: sorted((tuple(r.f), r.n, r.pos) for r in rows if r.apart == a) for a in (False, True)}
    trees = boost(cells[False])
    if not trees:
        return [], [math.inf] * len(KINDS)
    # A kind without a labelled candidate in the texts kept apart is calibrated on the others.
    there = {x[0] for x, _, _ in cells[True]}
    return trees, calibrate(trees, cells[True] + [c for c in cells[False] if c[0][0] not in there])


def _added(model: tuple[list[tuple], list[float]]) -> Column:
    """The candidates that the model adds, as an array of (s, k, e) in order."""
    trees, limits = model
    if not trees:
        return F.expr("cast(array() as array<struct<s: int, k: int, e: int>>)")
    limit = "CASE c.k " + " ".join(f"WHEN {k} THEN {1e300 if math.isinf(v) else v!r}D" for k, v in enumerate(limits)) + " END"
    over = f"transform(filter(loose, c -> not c.hit and coalesce(c.y, 1) = 1), c -> struct(c.s as s, c.k as k, c.e as e, ({expression(trees, 'c.f')}) - {limit} as p))"
    free = f"filter({over}, c -> c.p >= 0 and not exists(base, b -> b.s < c.e and c.s < b.e))"
    best = f"""transform(array(array_distinct({free})), m -> filter(m, c -> not exists(m, d -> d.s < c.e and c.s < d.e and
        (d.p > c.p or (d.p = c.p and (d.e - d.s > c.e - c.s or (d.e - d.s = c.e - c.s and (d.s < c.s or (d.s = c.s and d.k < c.k)))))))))[0]"""
    return F.expr(f"array_sort(transform({best}, c -> struct(c.s as s, c.k as k, c.e as e)))")


def find(docs: DataFrame) -> DataFrame:
    """Rows (doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added, n_secrets, secrets, n_spans).

    ``spans`` has the four kinds; secrets stand apart; ``n_spans`` counts both.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    found = frames.Scratch(docs.sparkSession, "pii").keep(candidates(docs).select(F.col("row.doc_id").alias("doc_id"), "fold", "base", "loose"), "candidates")
    names = "array(" + ", ".join(f"'{k}'" for k in KINDS) + ")"
    joined = lambda a: F.expr(f"concat_ws(',', transform({a}, x -> concat({names}[x.k], ':', x.s, ':', x.e)))")
    rows = found.withColumn("more", _added(train(found)))
    rows = rows.withColumn("every", F.expr("array_sort(concat(base, filter(more, x -> x.k < 4)))")).withColumn("secret", F.expr("filter(more, x -> x.k = 4)"))
    counts = [F.expr(f"size(filter(base, b -> b.k = {k}))").cast("long").alias(f"n_{kind}") for k, kind in enumerate(KINDS[:4])]
    more = [F.expr(e).cast("long").alias(n) for n, e in (("n_added", "size(every) - size(base)"), ("n_secrets", "size(secret)"), ("n_spans", "size(every) + size(secret)"))]
    return rows.select("doc_id", *counts, F.sha2(joined("base"), 256).alias("base_sha256"), joined("every").alias("spans"), *more, joined("secret").alias("secrets"))


def redact(docs: DataFrame, mask: str = "[redacted]") -> DataFrame:
    """``docs`` with all found spans masked in ``text``, each row by itself; overlapping spans become one mask."""
    found = candidates(docs)
    spans = found.withColumn("all_spans", F.array_sort(F.concat("base", _added(train(found)))))
    cut = F.expr("""aggregate(all_spans, struct(cast(array() as array<string>) as out, 0 as at), (a, x) -> if(x.s >= a.at,
        struct(concat(a.out, array(substr(text, a.at + 1, x.s - a.at))) as out, x.e as at), struct(a.out as out, greatest(a.at, x.e) as at)), a -> concat(a.out, array(substr(text, a.at + 1))))""")
    masked = F.when(F.size("all_spans") > 0, F.array_join(cut, mask)).otherwise(F.col("row.text"))
    return spans.select(*[masked.alias(c) if c == "text" else F.col("row").getField(c).alias(c) for c in docs.columns])

"""Personal data by candidate generators and boosted trees, in DataFrame and SQL functions only.

Validated spans (kinds email, ip, card, phone) come from expressions plus checks (ranges, digit
counts, Luhn) and always stay. Beside them, generators of high recall propose further spans,
which may overlap: runs of digits and separators, dotted numbers, spelled-out addresses, and
account-like codes. Each generator has a check of its own (``SURE``: the sum of an account code,
the ending of a spelled-out address, a naming word right before a local number); what passes is
always proposed. Each candidate gets bounded format and context features, packed into a cell
number below ``CELLS``. Over all rows, candidates are counted by cell, with those that meet a
validated span or pass their check as weak positives: at most CELLS rows reach the driver, where
trees of depth two are boosted on the counts (the same as boosting on the candidates). The trees
become one SQL expression. Each generator has its own threshold, the least score at which weak
precision is still ``precision`` among its candidates outside validated spans, which are the ones
that can be added; the thresholds are folded into the scores, so that zero is the bound for all. A logistic map fitted on
the same counts turns a score into the share of right ones to expect (``sureness``).

Matches get their offsets from the pieces between them: ``split`` and ``regexp_extract_all``
walk alike. Expressions are possessive and anchored at run starts, so long runs cost linear time.

Defined cases: null or empty text has no spans; repeated rows each get their result; an empty
table gives no row; without candidates nothing is added; further columns are kept by ``redact``, whatever their names.
Offsets are code points, ends exclusive.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import documents

BASE = ("email", "ip", "card", "phone")
LOCAL = "A-Za-z0-9._%+-"
# Same matches as the plain expressions: a run of local characters can only match from its start or from where the last match ended.
PATTERNS = {
    "email": (rf"(?:\G|(?<![{LOCAL}]))[{LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "contains(text, '@')"),
    "ip": (r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", "rlike(text, '[0-9]')"),
    "card": (r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?+[0-9]){12,18}+(?![\x20-]?[0-9])", "rlike(text, '[0-9]')"),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", "contains(text, '+')"),
}
GENERATORS = {
    "number": (r"(?<![0-9])[+(]?+[0-9](?:[\x20().-]{0,2}+[0-9]){6,23}+", "rlike(text, '[0-9]')"),
    "dotted": (r"(?<![0-9.])[0-9]{1,3}(?:\.[0-9]{1,3}){3,5}+(?![0-9])", "rlike(text, '[0-9]')"),
    "address": (r"(?i)(?<![a-z0-9._%+-])[a-z0-9._%+-]{1,64}+\x20?[\[(]at[\])]\x20?[a-z0-9-]{1,63}+(?:\x20?[\[(]dot[\])]\x20?[a-z0-9-]{1,63}+|\.[a-z0-9-]{1,63}+)++", "rlike(text, '(?i)[(\\\\[]at[)\\\\]]')"),
    "account": (r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?+[A-Z0-9]{4}){2,7}+(?:\x20?+[A-Z0-9]{1,3})?+(?![A-Za-z0-9])", "rlike(text, '[A-Z]{2}[0-9]{2}')"),
}
ADDED = tuple(GENERATORS)
KINDS = (*BASE, *ADDED)
CONTEXT = r"(?i)(?:phone|tel|call|mobile|fax|card|visa|account|iban|ssn|mail|contact|address|host|server|\\bip\\b)"
#: A word that names a personal number, and what may stand between it and the number.
NAMED = r"(?i)(?<![a-z0-9])(?:(?:tele|cell|mobile )?phone|tel|telephone|mobile|cell|fax|call|text|whatsapp|ssn|social security|passport|(?:national|personal|tax) id|id (?:card|number|no|nr))(?: (?:card|number|no|nr|me|us|at|on|is|under))*+[\x20.:#=(-]{1,4}$"
# Sizes of the features: generator, digits, separators, leading sign, keyword before, letter beside.
SIZES = (len(GENERATORS), 7, 3, 2, 2, 2)
CELLS = math.prod(SIZES)
#: Added to the score where a generator has nothing precise enough, and to what passes its own check: both outweigh any sum of trees.
NEVER, SURER = -1e6, 1e7
SPAN = "array<struct<kind: string, start: bigint, end: bigint, value: string>>"


def _literal(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _spans(kind: str, pattern: str, gate: str) -> Column:
    """All matches in the column text with their offsets."""
    p = _literal(pattern)
    walk = f"""aggregate(sequence(0, size(w.m) - 1), named_struct('p', 0L, 's', cast(array() as {SPAN})),
        (a, i) -> named_struct('p', a.p + length(w.g[i]) + length(w.m[i]), 's', array_append(a.s, named_struct('kind', '{kind}',
            'start', a.p + length(w.g[i]), 'end', a.p + length(w.g[i]) + length(w.m[i]), 'value', w.m[i])))).s"""
    none = f"cast(array() as {SPAN})"
    return F.expr(f"""CASE WHEN {gate} AND rlike(text, {p}) THEN flatten(transform(array(named_struct('m', regexp_extract_all(text, {p}, 0), 'g', split(text, {p}, -1))),
        w -> CASE WHEN size(w.m) > 0 THEN {walk} ELSE {none} END)) ELSE {none} END""")


def digits(value: str) -> str:
    return f"regexp_replace({value}, '[^0-9]', '')"


def luhn(d: str) -> str:
    """SQL: the digit string passes the Luhn sum."""
    return f"aggregate(sequence(1, length({d})), 0L, (a, i) -> a + ((cast(substr({d}, length({d}) - i + 1, 1) as int) * (2 - i % 2)) div 10) + ((cast(substr({d}, length({d}) - i + 1, 1) as int) * (2 - i % 2)) % 10)) % 10 = 0"


VALID = {
    "email": "true",
    "ip": "forall(split(x.value, '[.]'), p -> length(ltrim('0', p)) <= 3 AND coalesce(try_cast(ltrim('0', p) as int), 0) <= 255)",
    "card": luhn(digits("x.value")),
    "phone": f"length({digits('x.value')}) BETWEEN 9 AND 15",
}


def iban(v: str) -> str:
    """SQL: the code, its first four characters moved to the end and letters read as 10 to 35, leaves 1 modulo 97."""
    w = f"concat(substr({v}, 5), substr({v}, 1, 4))"
    return f"length({v}) BETWEEN 15 AND 34 AND aggregate(transform(sequence(1, length({v})), i -> ascii(substr({w}, i, 1))), 0, (a, c) -> CASE WHEN c < 58 THEN (a * 10 + c - 48) % 97 ELSE (a * 100 + c - 55) % 97 END) = 1"


BEFORE = "substring(text, greatest(x.start - 31, 1), least(x.start, 32))"
BESIDE = r"(rlike(substring(text, x.start, least(x.start, 1L)), '[A-Za-z0-9_]') OR rlike(substring(text, x.end + 1, 1), '[A-Za-z0-9_]'))"
#: The own check of each generator. A dotted number of valid parts is a base span already, so no other has a check.
SURE = {
    "number": f"length({digits('x.value')}) BETWEEN 7 AND 15 AND rlike({BEFORE}, {_literal(NAMED)}) AND NOT {BESIDE}",
    "dotted": "false",
    "address": "rlike(x.value, '(?i)^[a-z0-9].*[^a-z][a-z]{2,}$')",
    "account": iban("replace(x.value, ' ', '')"),
}


def _int(sql: str) -> str:
    """start and end are bigint, substring takes int."""
    return sql.replace("x.start", "cast(x.start as int)").replace("x.end", "cast(x.end as int)").replace("1L", "1")


def with_spans(docs: DataFrame) -> DataFrame:
    """doc (the given row), text, base (validated spans by kind and start) and candidates (spans with their cell, hit: meets a
    base span, sure: passes its own check). The given columns stay in doc, so their names meet no other."""
    text = docs.select(F.struct("*").alias("doc"), F.coalesce("text", F.lit("")).alias("text"))
    found = text.withColumns({f"_{k}": _spans(k, *g) for k, g in {**PATTERNS, **GENERATORS}.items()})
    valid = F.concat(*(F.expr(f"filter(_{k}, x -> {VALID[k]})") for k in BASE))
    proposed = F.concat(*(F.col(f"_{k}") for k in ADDED))
    found = found.withColumn("base", valid).withColumn("candidates", proposed)
    sure = _int("CASE x.kind " + " ".join(f"WHEN '{k}' THEN {check}" for k, check in SURE.items()) + " END")
    cells = F.expr(f"transform(candidates, x -> named_struct('kind', x.kind, 'start', x.start, 'end', x.end, 'cell', {_cell()}, 'hit', cast(exists(base, b -> b.start < x.end AND x.start < b.end) as int), 'sure', cast({sure} as int)))")
    return found.select("doc", "text", "base", cells.alias("candidates"))


def _cell() -> str:
    """SQL: the packed features of candidate x."""
    d = f"length({digits('x.value')})"
    parts = [
        "CASE x.kind " + " ".join(f"WHEN '{k}' THEN {i}" for i, k in enumerate(ADDED)) + " END",
        f"CASE WHEN {d} < 7 THEN 0 WHEN {d} < 9 THEN 1 WHEN {d} < 12 THEN 2 WHEN {d} < 13 THEN 3 WHEN {d} < 16 THEN 4 WHEN {d} < 20 THEN 5 ELSE 6 END",
        r"CASE WHEN rlike(x.value, '^[+(]?[A-Za-z0-9]+$') THEN 0 WHEN rlike(x.value, '^[+(]?[A-Za-z0-9 ]+$') THEN 1 ELSE 2 END",
        "cast(rlike(x.value, '^[+(]') as int)",
        f"cast(rlike({BEFORE}, '{CONTEXT}') as int)",
        f"cast({BESIDE} as int)",
    ]
    cell = parts[0]
    for size, p in zip(SIZES[1:], parts[1:]):
        cell = f"({cell}) * {size} + ({p})"
    return _int(f"cast({cell} as int)")


def unpack(cell: int) -> tuple[int, ...]:
    out = []
    for size in reversed(SIZES):
        cell, r = divmod(cell, size)
        out.append(r)
    return tuple(reversed(out))


@dataclass(frozen=True)
class Trees:
    """Boosted trees of depth two over the features; each is (feature, values, left, right), a leaf a number."""

    bias: float
    trees: tuple
    threshold: float
    calibration: tuple[float, float] = (1.0, 0.0)

    def score(self, cell: int) -> float:
        x = unpack(cell)

        def value(t):
            while isinstance(t, tuple):
                t = t[2] if x[t[0]] in t[1] else t[3]
            return t

        return self.bias + sum(map(value, self.trees))

    def sql(self, cell: str) -> str:
        """The same score over the feature values in the packed cell."""
        feature = [f"({cell} div {math.prod(SIZES[i + 1 :])} % {s})" for i, s in enumerate(SIZES)]

        def value(t):
            if isinstance(t, tuple):
                return f"CASE WHEN {feature[t[0]]} IN ({', '.join(map(str, sorted(t[1])))}) THEN {value(t[2])} ELSE {value(t[3])} END"
            return f"{t!r}D"

        return " + ".join([f"{self.bias!r}D", *(f"({value(t)})" for t in self.trees)])


def boost(cells: dict[int, tuple[int, int]], free: dict[int, tuple[int, int]] | None = None, rounds: int = 12, rate: float = 0.5, ridge: float = 1.0, precision: float = 0.9) -> Trees:
    """cells: cell -> (candidates, weak positives); free: the same of those outside base spans, by default all. Newton boosting on the counts."""
    if not cells:
        return Trees(0.0, (), math.inf)
    at = sorted(cells)
    x, n, y = [unpack(c) for c in at], [cells[c][0] for c in at], [cells[c][1] for c in at]
    bias = math.log((sum(y) + 0.5) / (sum(n) - sum(y) + 0.5))
    f, trees = [bias] * len(at), []

    def leaf(rows):
        g = sum(y[i] - n[i] * p[i] for i in rows)
        h = sum(n[i] * p[i] * (1 - p[i]) for i in rows)
        return g / (h + ridge), g * g / (h + ridge)

    def grow(rows, depth):
        v, whole = leaf(rows)
        best = (1e-9, None)
        for k in range(len(SIZES)) if depth else ():
            # Values in order of their mean gradient: the best cut of categories is one of these.
            groups = {}
            for i in rows:
                groups.setdefault(x[i][k], []).append(i)
            order = sorted(groups, key=lambda a: (leaf(groups[a])[0], a))
            for c in range(1, len(order)):
                left = [i for a in order[:c] for i in groups[a]]
                right = [i for a in order[c:] for i in groups[a]]
                gain = leaf(left)[1] + leaf(right)[1] - whole
                if gain > best[0]:
                    best = gain, (k, frozenset(order[:c]), left, right)
        if best[1] is None:
            return rate * v
        k, values, left, right = best[1]
        return k, values, grow(left, depth - 1), grow(right, depth - 1)

    for _ in range(rounds):
        p = [1 / (1 + math.exp(-max(-40.0, min(40.0, v)))) for v in f]
        tree = grow(range(len(at)), 2)
        trees.append(tree)
        one = Trees(0.0, (tree,), 0.0)
        f = [v + one.score(c) for v, c in zip(f, at)]
    # Calibration, by generator: cells by falling score; the threshold is the last score at which precision so far holds.
    free = cells if free is None else free
    for g in range(len(GENERATORS)):
        seen = hit = 0
        threshold = None
        levels: dict[float, list[int]] = {}
        for v, c in zip(f, at):
            if unpack(c)[0] == g and free.get(c, (0, 0))[0]:
                levels.setdefault(v, []).append(c)
        for v in sorted(levels, reverse=True):
            seen, hit = seen + sum(free[c][0] for c in levels[v]), hit + sum(free[c][1] for c in levels[v])
            if hit >= precision * seen:
                threshold = v - 1e-9
        trees.append((0, frozenset([g]), NEVER if threshold is None else -threshold, 0.0))
    model = Trees(bias, tuple(trees), 0.0)
    levels = {model.score(c): [0, 0] for c in at}
    for c in at:
        levels[model.score(c)][0] += free.get(c, (0, 0))[0]
        levels[model.score(c)][1] += free.get(c, (0, 0))[1]
    return replace(model, calibration=_calibrate([(v, *x) for v, x in levels.items() if x[0] and v > NEVER / 2]))


def _calibrate(levels: list[tuple[float, int, int]]) -> tuple[float, float]:
    """Constants of a logistic map from score to the share of weak positives, by Newton steps; (score, candidates, positives)."""
    a, b = 1.0, 0.0
    for _ in range(50):
        ga, gb, haa, hab, hbb = 0.1 * (1 - a), -0.1 * b, 0.1, 0.0, 0.1
        for v, n, y in levels:
            p = 1 / (1 + math.exp(-max(-40.0, min(40.0, a * v + b))))
            w = n * p * (1 - p)
            ga, gb, haa, hab, hbb = ga + v * (y - n * p), gb + y - n * p, haa + w * v * v, hab + w * v, hbb + w
        det = haa * hbb - hab * hab
        da, db = (hbb * ga - hab * gb) / det, (haa * gb - hab * ga) / det
        a, b = a + max(-2.0, min(2.0, da)), b + max(-2.0, min(2.0, db))
        if abs(da) + abs(db) < 1e-9:
            break
    return a, b


def fit(docs: DataFrame, **options) -> Trees:
    """Counts of all candidates by cell, and of those outside base spans: CELLS rows at most."""
    one = with_spans(docs.select("text")).filter(F.size("candidates") > 0).select(F.explode("candidates").alias("x")).select("x.cell", "x.hit", "x.sure")
    counts = one.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.sum(F.greatest("hit", "sure")).alias("y"), F.expr("count_if(hit = 0)").alias("n_free"), F.expr("count_if(hit = 0 AND sure = 1)").alias("y_free")).collect()
    return boost({r.cell: (r.n, r.y) for r in counts}, {r.cell: (r.n_free, r.y_free) for r in counts}, **options)


def detect(docs: DataFrame, model: Trees) -> DataFrame:
    """doc (the given row), base and spans: base and the chosen candidates, by kind as in KINDS, then start; sureness, the
    calibrated share of right ones among candidates with the score, for each of spans (1 for validated spans and for
    what passes its own check). Chosen is what passes its own check or scores high enough. A candidate gives way to base
    spans and to better or earlier candidates."""
    score = f"{model.sql('x.cell')} + {SURER}D * x.sure"
    chosen = f"filter(transform(filter(candidates, x -> x.hit = 0), x -> named_struct('kind', x.kind, 'start', x.start, 'end', x.end, 'score', {score})), x -> x.score >= {model.threshold!r}D)" if math.isfinite(model.threshold) else "cast(array() as array<struct<kind: string, start: bigint, end: bigint, score: double>>)"
    found = with_spans(docs).withColumn("candidates", F.expr(chosen))
    better = "y.start < x.end AND x.start < y.end AND (y.score > x.score OR y.score = x.score AND (y.end - y.start > x.end - x.start OR y.end - y.start = x.end - x.start AND (y.start < x.start OR y.start = x.start AND y.kind < x.kind)))"
    plain = "transform({}, x -> named_struct('kind', x.kind, 'start', x.start, 'end', x.end))"
    found = found.withColumn("candidates", F.expr(f"filter(candidates, x -> NOT exists(candidates, y -> {better}))"))
    a, b = model.calibration
    sureness = f"concat(transform(base, x -> 1D), transform(candidates, x -> CASE WHEN x.score >= {SURER / 2}D THEN 1D ELSE 1 / (1 + exp(-({a!r}D * x.score + {b!r}D))) END))"
    return found.select("doc", F.expr(plain.format("base")).alias("base"), F.expr(f"concat({plain.format('base')}, {plain.format('candidates')})").alias("spans"), F.expr(sureness).alias("sureness"))


def redact(docs: DataFrame, model: Trees) -> DataFrame:
    """docs with every span in text replaced by its kind in brackets; overlapping spans are one."""
    walk = """aggregate(array_sort(spans, (a, b) -> CASE WHEN a.start < b.start OR a.start = b.start AND a.end > b.end THEN -1 WHEN a.start = b.start AND a.end = b.end THEN 0 ELSE 1 END),
        named_struct('p', 0L, 's', ''), (a, x) -> CASE WHEN x.start >= a.p THEN named_struct('p', x.end, 's', concat(a.s, substring(doc.text, cast(a.p + 1 as int), cast(x.start - a.p as int)), '[', upper(x.kind), ']'))
        ELSE named_struct('p', greatest(a.p, x.end), 's', a.s) END, a -> concat(a.s, substring(doc.text, cast(a.p + 1 as int))))"""
    clean = F.expr(f"CASE WHEN size(spans) > 0 THEN {walk} ELSE doc.text END")
    return detect(docs, model).select(F.col("doc").withField("text", clean).alias("doc")).select("doc.*")


def op9(spark, sf_dir) -> DataFrame:
    docs = documents(spark, sf_dir)
    found = detect(docs.select("doc_id", "text"), fit(docs))
    joined = lambda spans: F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x.kind, x.start, x.end)), ",")
    counts = [F.expr(f"cast(size(filter(base, x -> x.kind = '{k}')) as bigint)").alias(f"n_{k}") for k in BASE]
    return found.select("doc.doc_id", *counts, F.sha2(joined(F.col("base")).cast("binary"), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"), F.array_join(F.transform("sureness", lambda x: F.round(x, 3).cast("string")), ",").alias("sureness"))

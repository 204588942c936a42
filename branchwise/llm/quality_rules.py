"""Quality rules with thresholds learnt per language and source.

Each document that keeps the base rule gets integer measures (per mille, or hundredths). Counts of
bad signs are first lowered by ``SIGMAS`` of their own chance spread (a square root), so that one
symbol in a short text says little. The distribution of a measure in every (language, source)
group is a log-linear histogram: exact below 64, then 32 cells per power of two, so a quantile is
right within 1/32. Histograms merge by adding counts: the order of merging, the number of tasks and
recomputed tasks change nothing.

A group's histogram is its own counts and ``prior`` rows spread like its language's histogram, which
in turn holds ``prior`` rows spread like the corpus: small groups lean on the others by weight, and
no size switches to another rule. A threshold lies in the middle of the clearest gap of the tail
(``tail_gap``): past it stands a mode of its own, of at least the share ``least`` and at most
``tail``, further from the bulk than both are wide. A tail that just thins out has no such gap,
and then the measure rejects nothing in that group. The thresholds are joined back.

Defined cases: null or empty text has no words and fails the base rule; null language or
source is a group of its own; repeated rows each count and each get a verdict; an empty table
gives no row; further columns of the input are ignored by ``judge`` and kept by ``keep``, whatever their names.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORD_RE, documents, settled, sliced

COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_marks", "n_stutters")
SYMBOLS, MARKS = "#*$%&|<>", "!?~^=_\\{}[]"
#: Groups up to this many are broadcast (a few hundred bytes each); more are joined by shuffle.
BROADCAST_GROUPS = 5_000
#: Standard errors by which a count of bad signs is lowered.
SIGMAS = 2
BASE_FAILED = "(n_words < 10 OR 100 * n_repeat_words > 20 * n_words)"


@dataclass(frozen=True)
class Measure:
    name: str
    sql: str
    low: bool = False


def sign(count: str, of: str) -> str:
    """SQL: per mille of a count without its chance part."""
    return f"cast(greatest(0, floor({count} - {SIGMAS} * sqrt({count}))) as bigint) * 1000 div {of}"


MEASURES = (
    Measure("mean_word", "word_chars * 100 div n_words", low=True),
    Measure("symbols", sign("n_symbols", "word_chars")),
    Measure("dup_lines", sign("n_dup_lines", "n_lines")),
    Measure("repeats", sign("n_repeat_words", "n_words")),
    Measure("stutters", sign("n_stutters", "n_words")),
    Measure("upper", sign("n_upper", "word_chars")),
    Measure("marks", sign("n_marks", "word_chars")),
)


def repeated_words(words: list[str]) -> int:
    """Words that lie in a five-word window which occurs twice or more, first occurrence included."""
    grams = list(zip(words, words[1:], words[2:], words[3:], words[4:]))
    if len(set(grams)) == len(grams):
        return 0
    seen, covered, end = Counter(grams), 0, 0
    for i, g in enumerate(grams):
        if seen[g] > 1:
            covered += i + 5 - max(i, end)
            end = i + 5
    return covered


def count_text(text: str) -> tuple[int, ...]:
    words = WORD_RE.findall(text)
    lines = [x for x in text.split("\n") if WORD_RE.search(x)]
    upper = sum(map(str.isupper, text)) if not text.islower() else 0
    return (
        len(words), sum(map(len, words)), sum(map(text.count, SYMBOLS)), len(lines) - len(set(lines)),
        repeated_words(words), len(lines), upper, sum(map(text.count, MARKS)),
        sum(map(eq, words, words[1:])),
    )


def count_documents(docs: DataFrame, keys: tuple[str, ...] = ("doc_id", "lang", "source")) -> DataFrame:
    """One row per row of docs: the keys and the integer counts of its whole text."""

    def run(batches):
        for b in sliced(batches):
            found = [count_text(t or "") for t in b.column(len(keys)).to_pylist()]
            cols = [pa.array(c, pa.int64()) for c in zip(*found)] if found else [pa.array([], pa.int64())] * len(COUNTS)
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keys)], *cols], names=[*keys, *COUNTS])

    fields = [f"`{k}` {docs.schema[k].dataType.simpleString()}" for k in keys]
    return docs.select(*keys, "text").mapInArrow(run, ", ".join([*fields, *(f"{c} bigint" for c in COUNTS)]))


def cell(value: str) -> str:
    """SQL of the histogram cell of a value of 0 or more."""
    power = f"(length(bin({value})) - 1)"
    return f"CASE WHEN {value} < 64 THEN {value} ELSE 64 + ({power} - 6) * 32 + shiftright({value}, cast({power} - 5 as int)) - 32 END"


def group_keys():
    null = F.lit("\x00")
    return F.coalesce(F.col("lang").cast("string"), null).alias("lang_key"), F.coalesce(F.col("source").cast("string"), null).alias("source_key")


def sketches(counts: DataFrame, measures=MEASURES) -> DataFrame:
    """Histograms (lang_key, source_key, measure, cell, n) of the rows that keep the base rule: at most a few hundred cells per group and measure."""
    keyed = counts.filter(f"NOT {BASE_FAILED}").select(*group_keys(), *(F.expr(m.sql).alias(m.name) for m in measures))
    rows = F.explode(F.array(*(F.struct(F.lit(m.name).alias("measure"), F.col(m.name).cast("bigint").alias("v")) for m in measures)))
    return keyed.select("lang_key", "source_key", rows.alias("r")).select("lang_key", "source_key", "r.measure", F.expr(cell("r.v")).cast("bigint").alias("cell")).groupBy("lang_key", "source_key", "measure", "cell").agg(F.count(F.lit(1)).alias("n"))


def languages(sketch: DataFrame, prior: float) -> DataFrame:
    """(lang_key, measure, cell, share): each language's histogram and ``prior`` rows spread like the corpus, as shares.
    A measure's histograms of all languages are one group: a few hundred cells for each language."""

    def run(part: pa.Table) -> pa.Table:
        cells, cell_of = np.unique(part["cell"].to_numpy(), return_inverse=True)
        langs, lang_of = np.unique(np.array(part["lang_key"].to_pylist()), return_inverse=True)
        n = np.zeros((len(langs), len(cells)))
        np.add.at(n, (lang_of, cell_of), part["n"].to_numpy())
        n += prior * n.sum(0) / n.sum()
        k, c = np.nonzero(n)
        return pa.table({"lang_key": pa.array(langs[k].tolist(), pa.string()), "measure": pa.array([part["measure"][0].as_py()] * len(k), pa.string()), "cell": cells[c], "share": (n / n.sum(1, keepdims=True))[k, c]})

    by_lang = sketch.groupBy("lang_key", "measure", "cell").agg(F.sum("n").alias("n"))
    return by_lang.groupBy("measure").applyInArrow(run, "lang_key string, measure string, cell bigint, share double")


def leaning(sketch: DataFrame, prior: float) -> DataFrame:
    """The groups' histograms, each with ``prior`` rows more, spread like its language's."""
    lent = sketch.select("lang_key", "source_key").distinct().join(languages(sketch, prior), "lang_key")
    lent = lent.select("lang_key", "source_key", "measure", "cell", (F.col("share") * prior).alias("n"))
    own = sketch.withColumn("n", F.col("n").cast("double"))
    return own.unionByName(lent).groupBy("lang_key", "source_key", "measure", "cell").agg(F.sum("n").alias("n"))


def tail_gap(cells: np.ndarray, weight: np.ndarray, tail: float = 0.25, least: float = 0.01, leak: float = 0.1, narrow: int = 4) -> int | None:
    """The cell in the middle of the clearest gap above the median: occupied cells i < j with at most ``leak`` of what lies
    from j on between them, from ``least`` to ``tail`` of all from j on, and j at least as far from i as i from the
    median of all, as the median of what lies from j on from j, and as ``narrow``. Clearest is the widest by that measure."""
    total, upto = weight.sum(), np.cumsum(weight)
    median = cells[np.searchsorted(upto, total / 2)]
    best, found = 0.0, None
    for i in np.flatnonzero((total - upto <= tail * total) & (cells >= median)):
        for j in range(i + 1, len(cells)):
            past = total - upto[j - 1]
            if past < least * total:
                break
            need = max(narrow, cells[i] - median, cells[min(np.searchsorted(upto, total - past / 2), len(cells) - 1)] - cells[j])
            wide = (cells[j] - cells[i]) / need
            if wide >= 1 and wide > best and upto[j - 1] - upto[i] <= leak * past:
                best, found = wide, int(cells[i] + cells[j]) // 2
    return found


def thresholds(sketch: DataFrame, measures=MEASURES, prior: float = 100.0, **gap) -> DataFrame:
    """(lang_key, source_key, low_<measure>, high_<measure>): the last good cells; null where there is no bound."""
    names = [f"{side}_{m.name}" for m in measures for side in ("low", "high")]

    def bounds(part: pa.Table) -> pa.Table:
        rows = {}
        measure, at, n = np.array(part["measure"].to_pylist()), part["cell"].to_numpy(), part["n"].to_numpy()
        for m in measures:
            own = np.flatnonzero(measure == m.name)
            own = own[np.argsort(at[own], kind="stable")]
            low = tail_gap(-at[own][::-1], n[own][::-1], **gap) if m.low and len(own) else None
            rows[f"low_{m.name}"] = None if low is None else -low
            rows[f"high_{m.name}"] = tail_gap(at[own], n[own], **gap) if len(own) else None
        return pa.table({"lang_key": part["lang_key"][:1], "source_key": part["source_key"][:1], **{k: pa.array([rows[k]], pa.int64()) for k in names}})

    return leaning(sketch, prior).groupBy("lang_key", "source_key").applyInArrow(bounds, "lang_key string, source_key string, " + ", ".join(f"{k} bigint" for k in names))


def verdicts(counts: DataFrame, limits: DataFrame, measures=MEASURES) -> DataFrame:
    """Counts with base_failed, failed (names of the measures outside their bounds) and kept."""
    counts = counts.withColumns(dict(zip(("lang_key", "source_key"), group_keys())))
    small = limits.limit(BROADCAST_GROUPS + 1).count() <= BROADCAST_GROUPS
    joined = counts.join(F.broadcast(limits) if small else limits, ["lang_key", "source_key"], "left")
    tests = []
    for m in measures:
        v = F.expr(f"CASE WHEN n_words > 0 THEN {cell(f'({m.sql})')} END")
        out = v > F.col(f"high_{m.name}")
        tests.append(F.when(out | (v < F.col(f"low_{m.name}")) if m.low else out, F.lit(m.name)))
    return (
        joined.withColumns({"base_failed": F.expr(BASE_FAILED), "failed": F.array_compact(F.array(*tests))})
        .withColumn("kept", ~F.col("base_failed") & (F.size("failed") == 0))
        .drop("lang_key", "source_key", *(f"{b}_{m.name}" for m in measures for b in ("low", "high")))
    )


def row_key():
    """Tells rows apart: equal rows share it, and they share their verdict too."""
    return F.xxhash64("doc_id", "text", *group_keys()).alias("row_key")


def judge(docs: DataFrame, measures=MEASURES, **options) -> DataFrame:
    """options: prior, and those of tail_gap."""
    keyed = docs.select("doc_id", "lang", "source", row_key(), "text")
    counts = settled(count_documents(keyed, ("doc_id", "lang", "source", "row_key")), "quality-counts")
    limits = settled(thresholds(sketches(counts, measures), measures, **options), "quality-limits", 0)
    return verdicts(counts, limits, measures)


def keep(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs that pass, with all their columns; only the few rejected keys are joined."""
    rejected = judge(docs, **options).filter(~F.col("kept")).select("row_key").distinct()
    whole = docs.select(F.struct("*").alias("doc"), row_key())
    return whole.join(rejected, "row_key", "left_anti").select("doc.*")


def op2(spark, sf_dir) -> DataFrame:
    return judge(documents(spark, sf_dir)).select("doc_id", *COUNTS[:5], "base_failed", "kept", F.array_join("failed", ",").alias("failed"))

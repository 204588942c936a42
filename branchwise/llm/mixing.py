"""Mixing sources to target weights, in DataFrame and SQL functions only.

Shares of tokens p per source become weights p^a / sum p^a. Two bisections give the exponent:
the largest one whose entropy still reaches ``entropy`` (a share of the greatest possible),
and the least one under which no source is repeated more than ``repeats`` times; the larger of
both holds, so the limit on repetition wins. Every source is shown at least once in full: the
budget is the least one under which the most abundant source (relative to its weight) runs once.

A source's run is a row of permutations of its documents, one per copy: all full copies and a
last one up to the source's budget. A permutation is the order of a seeded hash, so choosing is
a comparison with one hash per source (``cuts``); no document is moved to choose it. For the
exact cut, token sums go by hash range (about ``range_rows`` documents each), then over ranges:
a hot source is many ranges. ``schedule`` also deals every source evenly over blocks, each of which holds
the weights, with a hashed order inside the block.

The sources themselves (name, tokens) are one array in one row; their number, not that of
documents, bounds it. Defined cases: null or empty text has no tokens and comes with its copy;
null source is a source; equal rows share their hash and fate; sources without tokens get
weight 0 and run once; an empty table gives no row; further columns are kept by ``mix``, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, documents, settled

STEPS = 60
BROADCAST_SOURCES = 2_000


def _key() -> Column:
    return F.coalesce(F.col("source").cast("string"), F.lit("\x00"))


def measured(docs: DataFrame) -> DataFrame:
    """doc_id, source_key, h0 (hash of the row), n_tokens (words)."""
    words = F.expr(f"cast(regexp_count(coalesce(text, ''), '{WORD.replace(chr(92), chr(92) * 2)}') as bigint)")
    return docs.select("doc_id", _key().alias("source_key"), _row_hash().alias("h0"), words.alias("n_tokens"))


def _row_hash() -> Column:
    return F.xxhash64("doc_id", "text", _key())


def _order(copy, h0, seed: int) -> Column:
    """Place of a row in the permutation of a copy: 62 bits."""
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), copy, h0), 2)


def weights(rows: DataFrame, entropy: float = 0.95, repeats: float = 2.0) -> DataFrame:
    """source_key, tokens, rows, exponent, weight, repeat: how the sources are mixed."""
    totals = rows.groupBy("source_key").agg(F.sum("n_tokens").alias("tokens"), F.count(F.lit(1)).alias("rows"))
    one = totals.agg(F.array_sort(F.collect_list(F.struct("source_key", "tokens", "rows"))).alias("s"))
    one = one.withColumn("s", F.expr("transform(s, x -> named_struct('source_key', x.source_key, 'tokens', x.tokens, 'rows', x.rows, 'p', x.tokens / aggregate(s, 0L, (a, y) -> a + y.tokens)))"))
    one = one.withColumn("p", F.expr("transform(filter(s, x -> x.tokens > 0), x -> x.p)"))
    z = "aggregate(p, 0D, (sum, y) -> sum + pow(y, {e}))"
    t = "aggregate(p, 0D, (sum, y) -> sum + pow(y, {e}) * ln(y))"
    fair = f"ln({z}) - {{e}} * {t} / {z} >= {entropy} * ln(size(p))"
    few = f"pow(array_max(p) / array_min(p), 1 - {{e}}) <= {repeats}"
    mid = "((a.lo + a.hi) / 2)"
    search = f"aggregate(sequence(1, {STEPS}), named_struct('lo', 0D, 'hi', 1D), (a, i) -> CASE WHEN {{test}} THEN named_struct({{yes}}) ELSE named_struct({{no}}) END)"
    low, high = f"'lo', {mid}, 'hi', a.hi", f"'lo', a.lo, 'hi', {mid}"
    # An exponent of 1 keeps the shares; it is the answer where they are fair already.
    by_entropy = f"CASE WHEN size(p) < 2 OR {fair.format(e='1D')} THEN 1D ELSE {search.format(test=fair.format(e=mid), yes=low, no=high)}.lo END"
    by_repeats = f"CASE WHEN size(p) < 2 OR {few.format(e='0D')} THEN 0D ELSE {search.format(test=few.format(e=mid), yes=high, no=low)}.hi END"
    one = one.withColumn("e", F.expr(f"greatest({by_entropy}, {by_repeats})"))
    out = one.select("e", F.expr("array_max(p)").alias("top"), F.expr(z.format(e="e")).alias("z"), F.explode("s").alias("x"))
    weight = F.when(F.col("x.tokens") > 0, F.pow("x.p", "e") / F.col("z")).otherwise(0.0)
    repeat = F.when(F.col("x.tokens") > 0, F.greatest(F.lit(1.0), F.pow(F.col("top") / F.col("x.p"), 1 - F.col("e")))).otherwise(1.0)
    return out.select("x.source_key", "x.tokens", "x.rows", F.col("e").alias("exponent"), weight.alias("weight"), repeat.alias("repeat"))


def _copies(rows: DataFrame, mixed: DataFrame, seed: int) -> DataFrame:
    """Each row once per copy of its source, the last one perhaps partial, with its place h."""
    small = mixed.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    joined = rows.join(F.broadcast(mixed) if small else mixed, "source_key")
    copies = F.explode(F.sequence(F.lit(0), F.ceil("repeat").cast("int") - 1)).alias("copy")
    return joined.select("*", copies).withColumn("h", _order(F.col("copy"), F.col("h0"), seed))


def _before(rows: DataFrame, mixed: DataFrame, seed: int, range_rows: int) -> DataFrame:
    """(source_key, copy, h, tokens before h in the copy): sums inside hash ranges, after the sums of the ranges before."""
    part = F.expr(f"shiftright(shiftright(h, 30) * (1 + rows div {range_rows}), 32)")
    equal = _copies(rows, mixed, seed).groupBy("source_key", "copy", part.alias("part"), "h").agg(F.sum("n_tokens").alias("t"))
    inside = F.sum("t").over(Window.partitionBy("source_key", "copy", "part").orderBy("h")) - F.col("t")
    totals = equal.groupBy("source_key", "copy", "part").agg(F.sum("t").alias("total"))
    ahead = F.sum("total").over(Window.partitionBy("source_key", "copy").orderBy("part")) - F.col("total")
    return equal.withColumn("inside", inside).join(totals.select("source_key", "copy", "part", ahead.alias("ahead")), ["source_key", "copy", "part"]).select("source_key", "copy", "h", "t", (F.col("ahead") + F.col("inside")).alias("before"))


def _budget() -> Column:
    """Tokens of the last copy of a source."""
    return F.floor((F.col("repeat") - F.ceil("repeat") + 1) * F.col("tokens"))


def cuts(rows: DataFrame, mixed: DataFrame, seed: int = 0, range_rows: int = 5_000) -> DataFrame:
    """Per source: repeat and cut, the last hash of its last copy that is within the budget."""
    partial = mixed.filter("repeat > floor(repeat)")
    last = rows.join(F.broadcast(partial.select("source_key")), "source_key", "left_semi") if partial.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES else rows.join(partial.select("source_key"), "source_key", "left_semi")
    shown = _before(last, partial, seed, range_rows).join(mixed.select("source_key", "repeat", "tokens"), "source_key").filter((F.col("copy") == F.ceil("repeat") - 1) & (F.col("before") < _budget()))
    ends = shown.groupBy("source_key").agg(F.max("h").alias("cut"))
    return mixed.join(ends, "source_key", "left").withColumn("cut", F.when(F.col("repeat") == F.floor("repeat"), F.lit(2**63 - 1)).otherwise(F.coalesce("cut", F.lit(-1))))


def mix(docs: DataFrame, entropy: float = 0.95, repeats: float = 2.0, seed: int = 0) -> DataFrame:
    """docs, each row as often as the mix shows it; columns as given."""
    rows = settled(measured(docs), "mix-rows")
    mixed = settled(weights(rows, entropy, repeats), "mix-weights", 0)
    ends = settled(cuts(rows, mixed, seed), "mix-cuts", 0).select("source_key", "repeat", "cut")
    keyed = docs.select(F.struct("*").alias("doc"), _key().alias("source_key"), _row_hash().alias("h0"))
    shown = _copies(keyed, ends, seed).filter((F.col("copy") < F.ceil("repeat") - 1) | (F.col("h") <= F.col("cut")))
    return shown.select("doc.*")


def schedule(docs: DataFrame, entropy: float = 0.95, repeats: float = 2.0, seed: int = 0, block_tokens: int = 1 << 20, range_rows: int = 5_000) -> DataFrame:
    """doc_id, source, copy, n_tokens, block, block_order and the source's exponent, weight and repeat."""
    rows = settled(measured(docs), "mix-rows")
    mixed = settled(weights(rows, entropy, repeats), "mix-weights", 0)
    before = _before(rows, mixed, seed, range_rows)
    blocks = max(1, -(-int(mixed.agg(F.sum(F.col("repeat") * F.col("tokens"))).first()[0] or 0) // block_tokens))
    full = _copies(rows, mixed, seed).join(before.drop("t"), ["source_key", "copy", "h"])
    shown = full.filter((F.col("copy") < F.ceil("repeat") - 1) | (F.col("repeat") == F.floor("repeat")) | (F.col("before") < _budget()))
    share = (F.col("copy") * F.col("tokens") + F.col("before")) / F.greatest(F.col("repeat") * F.col("tokens"), F.lit(1.0))
    block = F.least(F.floor(share * blocks), F.lit(blocks - 1))
    source = F.when(F.col("source_key") != "\x00", F.col("source_key"))
    return shown.select("doc_id", source.alias("source"), "copy", "n_tokens", block.alias("block"), F.xxhash64(F.lit(seed + 1), block, "copy", "h0").alias("block_order"), "exponent", "weight", "repeat")


def op3(spark, sf_dir) -> DataFrame:
    return schedule(documents(spark, sf_dir))

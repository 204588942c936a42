"""SimHash fingerprints of documents and the search within a Hamming radius.

Terms are words, word pairs and character triples. The triples' weight falls evenly from 1 with the number of words, to
nothing at SHORT words: without a jump, they carry short texts, where a few words say little. A term's 64-bit hash
votes for or against each bit with the weight of its count on a log scale; a fingerprint holds the signs. Likeness is
the cosine that the share of differing bits stands for, 0 from a right angle on.

``near_counts`` finds everything within the radius exactly: the bits are cut into ``blocks``;
two fingerprints within the radius agree on at least ``blocks - radius`` of them, so one table
per choice of that many blocks, keyed by their bits, meets every such pair. Equal fingerprints
are one row with a count, so copies never meet each other.

Defined cases: null or empty text has no terms and the fingerprint 0; equal doc_ids are
ordered by a hash of their text; repeated rows each get a row; an empty table gives no row; the only document
is its own next one; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_RE, columns, documents, settled, sliced, worker_cache

BITS = 64
CACHE_WORDS = 150_000
#: Words from which character triples weigh nothing.
SHORT = 20
#: Characters of text that one task orders and fingerprints.
RANGE_CHARS = 32_000_000


def word_hashes(words: list[str]) -> np.ndarray:
    import xxhash

    cache = worker_cache("simhash-words")
    missing = set(words).difference(cache)
    cache.update((w, xxhash.xxh3_64_intdigest(w.encode("utf-8", "surrogatepass"))) for w in missing)
    found = np.fromiter(map(cache.__getitem__, words), np.uint64, len(words))
    if len(cache) > CACHE_WORDS:
        for w in missing:
            del cache[w]
    return found


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return h ^ (h >> np.uint64(29))


def fingerprint(text: str) -> int:
    words = WORD_RE.findall(text)
    if not words:
        return 0
    one = word_hashes(words)
    terms, weights = [one], [np.full(len(one), 0.5)]
    if len(one) > 1:
        terms.append(mixed(one[:-1] * np.uint64(3) + mixed(one[1:])))
        weights.append(np.ones(len(one) - 1))
    if (fine := 1 - len(words) / SHORT) > 0:
        line = " ".join(words)
        grams = [line[i : i + 3] for i in range(max(1, len(line) - 2))]
        terms.append(mixed(word_hashes(grams) + np.uint64(7)))
        weights.append(np.full(len(grams), fine))
    votes = np.zeros(BITS)
    for h, w in zip(terms, weights):
        distinct, n = np.unique(h, return_counts=True)
        bits = np.unpackbits(distinct.view(np.uint8).reshape(-1, 8), axis=1).astype(np.float32)
        weight = (w[0] * (1 + np.log(n))).astype(np.float32)
        votes += 2 * (weight @ bits) - weight.sum()
    return int.from_bytes(np.packbits(votes > 0).tobytes(), "big", signed=True)


def likeness(a: int, b: int) -> float:
    return max(0.0, math.cos(math.pi * ((a ^ b) & (2**BITS - 1)).bit_count() / BITS))


def edited(text: str, following: str) -> str:
    k = len(text) // 4
    return text[: len(text) - k] + following[:k]


def fingerprint_documents(docs: DataFrame) -> DataFrame:
    def run(batches):
        for b in sliced(batches):
            ids, texts = columns(b, "doc_id", "text")
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([fingerprint(t or "") for t in texts], pa.int64())], names=["doc_id", "fp"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, fp bigint")


def cut_counts(cuts: list[int], at: str = "at") -> tuple:
    """SQL expressions: how many of the sorted cuts are below the value, and how many are at most it; two steps of about the root of their number."""
    wide = max(1, math.isqrt(len(cuts)))
    parts = [cuts[i : i + wide] for i in range(0, len(cuts), wide)]
    array = lambda xs: F.lit(None).cast("array<bigint>") if not xs else F.array(*map(F.lit, xs)).cast("array<bigint>")
    firsts, all_parts = array([p[0] for p in parts]), F.array(*map(array, parts))

    def count(test):
        before = F.size(F.filter(firsts, test))  # parts whose first cut passes
        return F.when(before == 0, 0).otherwise((before - 1) * wide + F.size(F.filter(F.element_at(all_parts, F.greatest(before, F.lit(1))), test)))

    return count(lambda c: c < F.col(at)), count(lambda c: c <= F.col(at))


def with_following(docs: DataFrame, ranges: int | None = None) -> DataFrame:
    """doc_id, fp, n_chars, edited_sha256, edited_fp, next_fp: each row with the one after it.

    Rows are dealt by ranges of doc_id, about RANGE_CHARS of text each, and sorted; an id that fills several ranges is
    dealt on by a hash of the text, which is also the order of its rows. The first row of each range also goes, as a
    guest, to the end of the range before it (that of the first range to the last one)."""
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), F.coalesce(F.col("doc_id"), F.lit(-(2**63))).alias("at")).withColumn("h", F.shiftrightunsigned(F.xxhash64("text"), 1))
    if ranges is None:
        chars = docs.agg(F.sum(F.length("text"))).first()[0] or 0
        ranges = max(4 * docs.sparkSession.sparkContext.defaultParallelism, -(-chars // RANGE_CHARS))
    steps = [i / ranges for i in range(1, ranges)]
    cuts = sorted(rows.agg(F.percentile_approx("at", steps, 10 * ranges).alias("c")).first()["c"] or []) if steps else []
    if cuts:
        below, upto = cut_counts(cuts)
        rows = rows.withColumns({"below": below, "upto": upto})
        # An id equal to several cuts fills as many ranges more, in equal parts of the hash.
        bucket = F.col("below") + F.floor(F.col("h") / F.lit(2.0**63) * (F.col("upto") - F.col("below"))).cast("int")
        rows = rows.withColumn("bucket", F.least(bucket, F.greatest(F.col("upto") - 1, F.col("below")))).drop("below", "upto")
    else:
        rows = rows.withColumn("bucket", F.lit(0))
    order = ["at", "h", "text"]
    heads = settled(rows.groupBy("bucket").agg(F.min(F.struct("at", "h")).alias("head")), "heads", 0)  # one row per range
    before = F.coalesce(F.lag("bucket").over(Window.orderBy("bucket")), F.max("bucket").over(Window.partitionBy()))
    goes = heads.select(F.col("head.at").alias("at"), F.col("head.h").alias("h"), before.alias("bucket"))
    # The ranges are as many as the cuts that the driver holds, so their heads fit beside them.
    guests = rows.drop("bucket").join(F.broadcast(goes), ["at", "h"]).groupBy("bucket").agg(F.min_by("text", F.struct(*order)).alias("text"))
    guests = guests.select(F.lit(None).cast("bigint").alias("doc_id"), "text", F.lit(0).cast("bigint").alias("at"), F.lit(0).cast("bigint").alias("h"), "bucket", F.lit(True).alias("guest"))
    all_rows = rows.withColumn("guest", F.lit(False)).select("doc_id", "text", "at", "h", "bucket", "guest").unionByName(guests)
    dealt = all_rows.repartitionById(ranges, F.col("bucket").cast("int")).sortWithinPartitions("bucket", "guest", *order)

    def run(batches):
        before = None  # doc_id, text, bucket, fp of the row that waits for its next one
        for b in sliced(batches):
            out = []
            for i, text, bucket, guest in zip(*columns(b, "doc_id", "text", "bucket", "guest")):
                fp = fingerprint(text)
                if before is not None and before[2] == bucket:
                    changed = edited(before[1], text)
                    out.append((before[0], before[3], len(before[1]), hashlib.sha256(changed.encode("utf-8", "surrogatepass")).hexdigest(), fingerprint(changed), fp))
                before = None if guest else (i, text, bucket, fp)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64()]
            names = ["doc_id", "fp", "n_chars", "edited_sha256", "edited_fp", "next_fp"]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate(kinds)], names=names)

    return dealt.select("doc_id", "text", "bucket", "guest").mapInArrow(run, "doc_id bigint, fp bigint, n_chars bigint, edited_sha256 string, edited_fp bigint, next_fp bigint")


def block_masks(blocks: int, radius: int) -> list[int]:
    """One mask of bits per table: every choice of blocks - radius of the blocks."""
    edges = [BITS * i // blocks for i in range(blocks + 1)]
    parts = [((1 << (b - a)) - 1) << a for a, b in zip(edges, edges[1:])]
    return [sum(c) for c in combinations(parts, blocks - radius)]


def _signed(x: int) -> int:
    return x - 2**BITS if x >> (BITS - 1) else x


def near_counts(fps: DataFrame, queries, radius: int = 3, blocks: int = 6) -> DataFrame:
    """fps: doc_id, fp. Per fingerprint of the query rows: (fp, n_near), the rows within the radius, itself included."""
    if not 0 <= radius < blocks:
        raise ValueError("blocks must exceed radius")
    groups = fps.groupBy("fp").agg(F.count(F.lit(1)).alias("n"), F.max(queries.cast("int")).alias("asked"))
    tables = F.explode(F.array(*(F.struct(F.lit(i).alias("no"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("key")) for i, m in enumerate(block_masks(blocks, radius)))))
    rows = groups.withColumn("t", tables).select("fp", "n", "asked", "t.no", "t.key")
    ask = rows.filter("asked = 1").select(F.col("fp").alias("q"), F.col("no").alias("q_no"), F.col("key").alias("q_key"))
    close = F.expr(f"bit_count(q ^ fp) <= {radius}")
    met = ask.join(rows, (F.col("q_no") == F.col("no")) & (F.col("q_key") == F.col("key")) & close)
    return met.groupBy("q", "fp").agg(F.max("n").alias("n")).groupBy("q").agg(F.sum("n").alias("n_near")).withColumnRenamed("q", "fp")


def op8(spark, sf_dir, radius: int = 3) -> DataFrame:
    rows = settled(with_following(documents(spark, sf_dir)), "fingerprints")
    asked = F.coalesce(F.col("doc_id") % 20 == 0, F.lit(False))
    near = near_counts(rows.select("doc_id", "fp"), asked, radius).withColumnsRenamed({"fp": "near_fp"})
    like = lambda a, b: F.greatest(F.lit(0.0), F.cos(F.lit(math.pi / BITS) * F.bit_count(F.col(a).bitwiseXOR(F.col(b)))))
    hexed = lambda c: F.lower(F.lpad(F.hex(c), 16, "0"))
    joined = rows.withColumn("asked_fp", F.when(asked, F.col("fp"))).join(near, F.col("asked_fp") == F.col("near_fp"), "left")
    return joined.select("doc_id", "n_chars", "edited_sha256", hexed("fp").alias("fingerprint"), hexed("edited_fp").alias("edited_fingerprint"), like("fp", "edited_fp").alias("near_edited"), like("fp", "next_fp").alias("near_next"), (F.col("n_near") - 1).alias("n_near"))

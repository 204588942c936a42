"""Near-duplicate join on n-gram Jaccard similarity: MinHash bands, then full n-gram sets.

1. Each text becomes its set of five-word shingles (64-bit hashes), a hash of that set, MinHash
   values, band hashes, and a one-byte-per-value sketch. Equal sets are one class from here on.
2. Bands are shuffled. Classes that share a band hash are compared by sketch, block against
   block inside the bucket; a task emits only a spanning star of the pairs whose estimate lies
   above ``threshold`` less ``SIGMAS`` standard errors. So a bucket of any size gives rows in
   proportion to its members. The components of these stars are the clusters: every pair above the threshold that
   shares a band falls into one cluster.
3. Clusters are verified on full sets, again block against block: tasks count for each class
   the other classes at or above the threshold, and emit counts and spanning stars, not pairs.
   Components of the verified stars are the groups.

Bands: ``choose_bands`` takes the fewest hashes with at least ``recall`` at the threshold.
Defined cases: a text without a word (null, empty, blank) has no shingles and is similar to
nothing; one of fewer than five words is one shingle; equal rows are copies of each other; an
empty table gives no row; further columns are kept by ``keep_one``, whatever their names. Where doc_ids repeat, rows are told apart by text.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORD_RE, columns, discard, documents, hot_join, settled, sliced, worker_cache

WORDS, THRESHOLD, RECALL, SIGMAS = 5, 0.8, 0.99998, 4.5
BLOCK = 256
CACHE_WORDS = 150_000
LOWEST = -(2**63)


def choose_bands(threshold: float, recall: float = RECALL, most_rows: int = 5) -> tuple[int, int]:
    """(bands, rows): rows as many as allowed, then the fewest bands whose recall at the threshold suffices."""
    rows = most_rows
    return math.ceil(math.log(1 - recall) / math.log(1 - threshold**rows)), rows


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(29))


def shingles(text: str, n: int = WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the n-word shingles; a shorter text is one shingle."""
    import xxhash

    words = WORD_RE.findall(text)
    if not words:
        return np.zeros(0, np.uint64)
    cache = worker_cache("shingle-words")
    missing = set(words).difference(cache)
    cache.update((w, xxhash.xxh3_64_intdigest(w.encode("utf-8", "surrogatepass"))) for w in missing)
    h = np.fromiter(map(cache.__getitem__, words), np.uint64, len(words))
    if len(cache) > CACHE_WORDS:
        for w in missing:
            del cache[w]
    k = min(n, len(h))
    out = np.full(len(h) - k + 1, k, np.uint64)
    for i in range(k):
        out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + h[i : len(h) - k + 1 + i])
    return np.unique(out)


def min_hashes(grams: np.ndarray, factors: np.ndarray) -> np.ndarray:
    low = np.full(len(factors), np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(grams), 1024):
        part = grams[i : i + 1024, None] * factors
        low = np.minimum(low, part.min(0))
    return low


def signatures(docs: DataFrame, bands: int, rows: int, n: int = WORDS, seed: int = 11) -> DataFrame:
    """row (unique), doc_id, text_key, n_grams, set_hash, sketch, bands (empty where there is no shingle)."""
    factors = np.random.default_rng(seed).integers(0, 2**63, bands * rows, np.uint64) * np.uint64(2) + np.uint64(1)

    def run(batches):
        import xxhash
        from pyspark import TaskContext

        row = TaskContext.get().partitionId() << 33
        for b in sliced(batches):
            ids, keys, texts = columns(b, "doc_id", "text_key", "text")
            out = []
            for t in texts:
                grams = shingles(t or "", n)
                if len(grams):
                    low = min_hashes(grams, factors)
                    h = np.arange(1, bands + 1, dtype=np.uint64)
                    for r in range(rows):
                        h = _mix(h * np.uint64(0x9E3779B97F4A7C15) + low.reshape(bands, rows)[:, r])
                    out.append((row, len(grams), xxhash.xxh3_128_digest(grams.tobytes()), (_mix(low) >> np.uint64(56)).astype(np.uint8).tobytes(), h.view(np.int64)))
                else:
                    out.append((row, 0, None, None, None))
                row += 1
            kinds = [pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.list_(pa.int64())]
            names = ["row", "n_grams", "set_hash", "sketch", "bands"]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(keys, pa.int64()), *(pa.array([x[k] for x in out], t) for k, t in enumerate(kinds))], names=["doc_id", "text_key", *names])

    return docs.select("doc_id", F.xxhash64("text").alias("text_key"), "text").mapInArrow(run, "doc_id bigint, text_key bigint, row bigint, n_grams bigint, set_hash binary, sketch binary, bands array<bigint>")


def groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[tuple, pa.Table]]:
    """Runs of rows with equal keys from sorted batches; only the current run is held."""
    held: list[pa.RecordBatch] = []
    current = None
    for b in batches:
        if not b.num_rows:
            continue
        k = np.column_stack([b.column(b.schema.get_field_index(x)).to_numpy(zero_copy_only=False) for x in keys])
        edges = np.concatenate([[0], np.flatnonzero((k[1:] != k[:-1]).any(axis=1)) + 1, [len(k)]])
        for s, e in zip(edges.tolist(), edges[1:].tolist()):
            key = tuple(k[s].tolist())
            if key != current and held:
                yield current, pa.Table.from_batches(held)
                held = []
            current = key
            held.append(b.slice(s, e - s))
    if held:
        yield current, pa.Table.from_batches(held)


def star(close: np.ndarray) -> np.ndarray:
    """Least index of each row's component under a symmetric boolean matrix."""
    n = len(close)
    label = np.arange(n)
    while True:
        low = np.minimum(label, np.where(close, label[None, :], n).min(1))
        low = low[low]
        if (low == label).all():
            return label
        label = low


def dealt(members: DataFrame, key: str, node: str, block: int) -> DataFrame:
    """Members of keys with n > 1 rows, once per pair of blocks (lo, hi) of their key, sorted for ``groups``."""
    blocks = F.ceil(F.col("n") / block).cast("int")
    own = F.pmod(F.xxhash64(node), blocks).cast("int")
    out = members.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    return out.withColumns({"lo": F.least("own", "other"), "hi": F.greatest("own", "other")}).drop("other", "n").repartition(key, "lo", "hi").sortWithinPartitions(key, "lo", "hi", node)


def _usable(own: np.ndarray, lo: int, hi: int) -> np.ndarray:
    """Pairs that this block pair answers for."""
    return np.ones((len(own), len(own)), bool) if lo == hi else own[:, None] != own[None, :]


def candidate_stars(buckets: DataFrame, cut: float) -> DataFrame:
    """buckets: key, lo, hi, own, node, sketch. Edges (a, b) of classes whose estimated similarity reaches the cut."""

    def run(batches):
        a, b = [], []
        for (_, lo, hi), t in groups(batches, ["key", "lo", "hi"]):
            n = t.num_rows
            if n < 2:
                continue
            node, own = t["node"].to_numpy(), t["own"].to_numpy()
            s = np.frombuffer(b"".join(t["sketch"].to_pylist()), np.uint8).reshape(n, -1)
            if n == 2:
                if lo == hi or own[0] != own[1]:
                    if (s[0] == s[1]).mean() >= cut:
                        a.append(int(node[1])), b.append(int(node[0]))
            else:
                close = np.zeros((n, n), bool)
                for i in range(0, n, 64):
                    close[i : i + 64] = (s[i : i + 64, None, :] == s[None, :, :]).mean(-1) >= cut
                label = star(close & _usable(own, lo, hi))
                at = np.flatnonzero(label != np.arange(n))
                a += node[at].tolist()
                b += node[label[at]].tolist()
            if len(a) > 50_000:
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])
                a, b = [], []
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return buckets.select("key", "lo", "hi", "own", "node", "sketch").mapInArrow(run, "a bigint, b bigint")


def jaccard(sets: list[np.ndarray]) -> np.ndarray:
    """Similarity of all pairs. Shingles of one set only add to sizes; the others are counted in slices of columns."""
    n, size = len(sets), np.array([len(x) for x in sets], float)
    who = np.repeat(np.arange(n), [len(x) for x in sets])
    flat = np.concatenate(sets)
    order = np.argsort(flat, kind="stable")
    flat, who = flat[order], who[order]
    fresh = np.concatenate([[True], flat[1:] != flat[:-1]])
    column = np.cumsum(fresh) - 1
    count = np.bincount(column)
    shared = count[column] > 1
    who, column = who[shared], (np.cumsum(count > 1) - 1)[column[shared]]
    common = np.zeros((n, n))
    wide = int(column[-1]) + 1 if len(column) else 0
    for c in range(0, wide, 4096):
        s, e = np.searchsorted(column, [c, c + 4096])
        m = np.zeros((n, min(4096, wide - c)), np.float32)
        m[who[s:e], column[s:e] - c] = 1
        common += m @ m.T
    return common / np.maximum(size[:, None] + size[None, :] - common, 1)


def verified(members: DataFrame, threshold: float) -> DataFrame:
    """members: key, lo, hi, own, node, grams (bytes). Rows (node, links, root) of classes with a link."""

    def run(batches):
        out = []
        for (_, lo, hi), t in groups(batches, ["key", "lo", "hi"]):
            n = t.num_rows
            if n < 2:
                continue
            node = t["node"].to_numpy()
            near = jaccard([np.frombuffer(x, np.uint64) for x in t["grams"].to_pylist()]) >= threshold - 1e-12
            near &= _usable(t["own"].to_numpy(), lo, hi)
            np.fill_diagonal(near, False)
            links, label = near.sum(1), star(near)
            out += [(int(node[i]), int(links[i]), int(node[label[i]])) for i in np.flatnonzero(links)]
            if len(out) > 50_000:
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], pa.int64()) for k in range(3)], names=["node", "links", "root"])
                out = []
        yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], pa.int64()) for k in range(3)], names=["node", "links", "root"])

    return members.select("key", "lo", "hi", "own", "node", "grams").mapInArrow(run, "node bigint, links bigint, root bigint")


def busy(rows: DataFrame, key: str, n: str, total: int) -> DataFrame:
    """Keys of which ``n`` says that they hold a thousandth of total rows or more: a thousand at most."""
    return rows.filter(F.col(n) * 1000 >= max(total, 1000)).select(key)


def components(edges: DataFrame, total: int) -> DataFrame:
    """(node, root) of all nodes with an edge; root is the least node of the component. Alternating stars, settled each
    round, until a round changes nothing (the number of rounds grows with the logarithm of the size). The rows of a
    star's centre meet its least neighbour by a broadcast of the few centres with a great share of all edges."""
    now = settled(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct(), "edges", total)
    state, n = None, now.count()
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = settled(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"), F.count(F.lit(1)).alias("n")), "stars", total)
        large = hot_join(both.filter("b > a"), low.select("a", "m"), "a", busy(low, "a", "n", n)).select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        # Each node now sees only smaller ones; its smaller ones all go to the least of them.
        large = settled(large, "edges", total)
        low_2 = large.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("n"))
        small = hot_join(large, low_2.select("a", "m"), "a", busy(low_2, "a", "n", n)).select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low_2.select("a", F.col("m").alias("b")))
        then = settled(small.filter("a <> b").distinct(), "edges", total)
        n, seen = then.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        for old in (now, low, large):
            discard(old)
        now = then
        if (n, seen) == state:
            return now.groupBy("a").agg(F.min("b").alias("root")).withColumnRenamed("a", "node")
        state = n, seen


def similarity_classes(docs: DataFrame, threshold: float = THRESHOLD, n: int = WORDS, recall: float = RECALL, block: int = BLOCK, null_ids: bool = True) -> DataFrame:
    """Per row: doc_id, text_key, n_grams, copy_id (least doc_id with the same set), n_copies (rows with that set),
    class_id (least doc_id of the group), n_links (other sets at or above the threshold). A null doc_id counts as the
    least number, and is given back as null, or where null_ids is false as that number and with root, which tells
    groups apart even where doc_ids repeat."""
    bands, rows = choose_bands(threshold, recall)
    found = settled(signatures(docs, bands, rows, n), "signatures")
    total = found.count()
    at = F.coalesce("doc_id", F.lit(LOWEST))
    sets = settled(found.filter("n_grams > 0").groupBy("set_hash").agg(F.min("row").alias("node"), F.min(at).alias("copy_id"), F.count(F.lit(1)).alias("n_copies"), F.first("sketch").alias("sketch"), F.first("bands").alias("bands")), "sets", total)
    keyed = sets.select(F.explode("bands").alias("key"), "node")
    full = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    buckets = keyed.join(full, "key").join(sets.select("node", "sketch"), "node")
    cut = threshold - SIGMAS * math.sqrt(threshold * (1 - threshold) / (bands * rows))
    clusters = components(settled(candidate_stars(dealt(buckets, "key", "node", 4 * block), cut), "candidates", total), total)
    clusters = settled(clusters.unionByName(clusters.select(F.col("root").alias("node"), "root").distinct()), "clusters", total)
    sizes = clusters.groupBy("root").agg(F.count(F.lit(1)).alias("n"))
    members = hot_join(clusters, sizes, "root", busy(sizes, "root", "n", clusters.count())).join(sets.select("node", "copy_id", "set_hash"), "node")
    texts = docs.select(at.alias("copy_id"), "text").join(members, "copy_id")

    def run(batches):
        import xxhash

        for b in sliced(batches):
            key, size, node, want, text = columns(b, "key", "n", "node", "set_hash", "text")
            grams = [shingles(t or "", n).tobytes() for t in text]
            ok = [i for i, g in enumerate(grams) if xxhash.xxh3_128_digest(g) == want[i]]
            yield pa.RecordBatch.from_arrays([pa.array([c[i] for i in ok], k) for c, k in ((key, pa.int64()), (size, pa.int64()), (node, pa.int64()), (grams, pa.binary()))], names=["key", "n", "node", "grams"])

    full_sets = texts.select(F.col("root").alias("key"), "n", "node", "set_hash", "text").mapInArrow(run, "key bigint, n bigint, node bigint, grams binary").dropDuplicates(["node"])
    linked = settled(verified(dealt(full_sets, "key", "node", block), threshold), "links", total)
    roots = components(linked.select(F.col("node").alias("a"), F.col("root").alias("b")), total)
    roots = roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())
    counts = linked.groupBy("node").agg(F.sum("links").alias("n_links"))
    of = sets.select("set_hash", "node", "copy_id", "n_copies").join(counts, "node", "left").join(roots, "node", "left")
    of = settled(of.withColumn("root", F.coalesce("root", "node")), "classes", total)
    least = of.filter("n_links > 0").groupBy("root").agg(F.min("copy_id").alias("class_id"), F.count(F.lit(1)).alias("n"))
    of = hot_join(of, least.select("root", "class_id"), "root", busy(least, "root", "n", total), "left")
    of = settled(of.select("set_hash", "root", "copy_id", "n_copies", F.coalesce("class_id", "copy_id").alias("class_id"), F.coalesce("n_links", F.lit(0)).alias("n_links")), "groups", total)
    given = F.col("doc_id") if null_ids else at
    back = lambda c: F.coalesce(F.nullif(F.col(c), F.lit(LOWEST)), given) if null_ids else F.coalesce(F.col(c), given)
    joined = hot_join(found.select("doc_id", "text_key", "n_grams", "set_hash"), of, "set_hash", busy(of, "set_hash", "n_copies", total), "left")
    return joined.select("doc_id", "text_key", "n_grams", back("copy_id").alias("copy_id"), F.coalesce("n_copies", F.lit(1)).alias("n_copies"), back("class_id").alias("class_id"), F.coalesce("n_links", F.lit(0)).alias("n_links"), *([] if null_ids else ["root"]))


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """docs without all but the first row (by doc_id, then a hash of the text) of each group; columns as given."""
    classes = similarity_classes(docs, null_ids=False, **options)
    found = settled(classes.filter("n_grams > 0"), "near-classes")
    total = found.count()
    key = F.struct(F.coalesce("doc_id", F.lit(LOWEST)).alias("i"), F.col("text_key"))
    first = found.groupBy("root").agg(F.min(key).alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    many = hot_join(found, first, "root", busy(first, "root", "n", total))
    gone = many.filter(key != F.col("first")).select("doc_id", "text_key").distinct()
    again = many.filter(key == F.col("first")).groupBy("doc_id", "text_key").count().filter("count > 1").select("doc_id", "text_key")
    same = lambda other: F.col("named.id").eqNullSafe(F.col(f"{other}.doc_id")) & (F.col("named.key") == F.col(f"{other}.text_key"))
    named = docs.select(F.struct("*").alias("doc"), F.col("doc_id").alias("id"), F.xxhash64("text").alias("key")).alias("named")
    rest = named.join(gone.alias("gone"), same("gone"), "left_anti")
    if again.isEmpty():
        return rest.select("doc.*")
    twice = rest.join(again.alias("again"), same("again"), "left_semi").dropDuplicates(["id", "key"])
    return rest.join(again.alias("again"), same("again"), "left_anti").unionByName(twice).select("doc.*")


def op1(spark, sf_dir) -> DataFrame:
    return similarity_classes(documents(spark, sf_dir)).drop("text_key")

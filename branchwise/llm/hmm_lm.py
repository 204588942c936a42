"""Hidden Markov language model over whole texts, trained by Baum-Welch counts from all training rows.

Rows are encoded once, in blocks of about ``BLOCK`` characters: one row a block, with its distinct words, how
often its training texts hold each, and the tokens of its texts as places in that list. Counts of every training
word are aggregated from the blocks in Spark and stay there, as do the expected counts of every training word
by state, so what is gathered grows with the corpus. Only words with a share of at least 1 / OWN of all
tokens reach the driver.

Model: states emit words. With E(w, s) the expected count of word w in state s and n(w) its count,
    P(s | w) = (E(w, s) + KAPPA P(s | ending of w)) / (n(w) + KAPPA),
where all words with the same last three characters (of SHARED hashed endings) give the share of an
ending; a word not met in training has n = E = 0. Each ending keeps a place for unknown words. With
the smoothed unigram share u(w), P(w | s) = u(w) P(s | w) / P(s), so forward-backward needs only the
ratios P(s | w) / P(s), and log P(text) = sum of log unigram + log likelihood of the ratios.

Training: (1) counts of neighbouring coarse classes (frequent words and endings) over all training texts
give the first states (an EM on that bounded matrix); (2) Baum-Welch rounds in which rare words with one
ending share their emissions, until the gain in log likelihood a token is below ``gain`` or for ``rounds``
rounds: tasks read blocks and emit one bounded table each; (3) a last round that counts every word by state
for itself. Scaled forward-backward gives the counts of each whole sequence: a long one is worked on in pieces of
``SEGMENT`` tokens side by side, after the products of their steps, chained over the sequence, have told what
enters and leaves each piece. Scoring meets each block's words with their counts by a join and gives the forward
likelihood of whole sequences by the same pieces, in float64.

Defined cases: null or empty text is just the end token; repeated rows each count and each get
a row; without training rows every word is unknown; an empty table gives no row; further columns are ignored.
"""

from __future__ import annotations

import math
import zlib
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORD_RE, compact, documents, id_mod, rows_a_batch, settled, sliced

OWN, SHARED, COARSE_OWN, COARSE_SHARED, SEGMENT = 4096, 1024, 256, 256, 512
END = "\n"  # no word has it
ALPHA = 0.1
KAPPA = 5.0
#: A block ends once it has so many characters of text. It is a row group of its own: what writes or reads blocks holds a row group at a
#: time, and the writer's limit in bytes alone is not looked at before a hundred rows, so that a file would be one row group.
BLOCK = 8_000_000
WRITER = {"parquet.block.row.count.limit": "1", "compression": "zstd"}
#: Texts that go to Python at a time.
TEXTS = 1000
#: Expected counts of a word travel as shares of its count, in steps of 1 / STEPS, eight to a number.
STEPS = 255


def tokens_of(text: str) -> list[str]:
    """Words with A-Z in lower case; the end token is not included."""
    return WORD_RE.findall(text.encode("utf-8", "surrogatepass").lower().decode("utf-8", "surrogatepass"))


def ending(word: str) -> int:
    return zlib.crc32(word[-3:].encode("utf-8", "surrogatepass")) % SHARED


def words_of(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """What ``tokens_of`` finds in all texts, one after another, with an empty word here and there; and how many each has with these."""
    lists = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(texts, "")))
    return lists.flatten(), lists.value_lengths().to_numpy()


def endings_of(words: pa.Array) -> np.ndarray:
    ends = pc.utf8_slice_codeunits(words, -3).dictionary_encode()
    return np.array([ending(x) for x in ends.dictionary.to_pylist()], "<u2")[ends.indices.to_numpy()]


def encode(docs: DataFrame, held_out) -> DataFrame:
    """One row a block: ids, held_out and sizes of its texts; words, the first being the end token, endings (two bytes a word)
    and n, how often the training texts hold each; seq: per token the place of its word, all low two bytes before all high ones."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        from pyspark import TaskContext

        block = TaskContext.get().partitionId() << 33
        ids, held, parts, counts, size = [], [], [], [], 0

        def out(id_type, block):
            found, met = pa.concat_arrays(parts).dictionary_encode(), np.concatenate(counts)
            real = pc.not_equal(found.dictionary, "").to_numpy(zero_copy_only=False)
            words = pa.concat_arrays([pa.array([END], pa.string()), found.dictionary.filter(pa.array(real)).cast(pa.string())])
            at = np.where(real, np.cumsum(real), 0)[found.indices.to_numpy()]  # 0 for an empty word, whose place is that of the end
            sizes = np.bincount(np.repeat(np.arange(len(met)), met)[at > 0], minlength=len(met)) + 1
            flat, inside = np.zeros(sizes.sum(), np.uint32), np.ones(sizes.sum(), bool)
            inside[np.cumsum(sizes) - 1] = False
            flat[inside] = at[at > 0]
            n = np.bincount(flat[np.repeat(~np.array(held), sizes)], minlength=len(words))
            one = {
                "block": pa.array([block], pa.int64()), "ids": pa.array([ids], pa.list_(id_type)), "held_out": pa.array([held], pa.list_(pa.bool_())), "sizes": pa.array([sizes], pa.list_(pa.int64())),
                "words": pa.ListArray.from_arrays(pa.array([0, len(words)], pa.int32()), words), "endings": pa.array([endings_of(words).tobytes()], pa.binary()), "n": pa.array([n], pa.list_(pa.int64())), "seq": pa.array([flat.astype("<u2").tobytes() + (flat >> 16).astype("<u2").tobytes()], pa.binary()),
            }
            return pa.RecordBatch.from_arrays(list(one.values()), names=list(one))

        def add(b):
            ids.extend(b.column(0).to_pylist()), held.extend(b.column(1).to_pylist())
            found, met = words_of(b.column(2))
            parts.append(found), counts.append(met)

        for b in sliced(batches):
            id_type, begin = b.column(0).type, 0
            for i, n in enumerate(pc.fill_null(pc.utf8_length(b.column(2)), 0).to_pylist(), 1):
                size += n + 1
                if size > BLOCK:
                    add(b.slice(begin, i - begin))
                    yield out(id_type, block)
                    block, begin, size = block + 1, i, 0
                    for x in (ids, held, parts, counts):
                        x.clear()
            if begin < b.num_rows:
                add(b.slice(begin))
        if ids:
            yield out(id_type, block)

    return docs.select("doc_id", held_out.alias("held_out"), "text").mapInArrow(run, f"block bigint, ids array<{kind}>, held_out array<boolean>, sizes array<bigint>, words array<string>, endings binary, n array<bigint>, seq binary")


def settled_blocks(docs: DataFrame, held_out) -> DataFrame:
    with rows_a_batch(docs.sparkSession, TEXTS):
        return settled(encode(docs, held_out), "lm-blocks", **WRITER)


def word_counts(blocks: DataFrame) -> DataFrame:
    """(word, n) over the training texts, the end token included."""
    one = blocks.select(F.explode(F.arrays_zip("words", "n")).alias("x")).select("x.words", "x.n").filter("n > 0")
    return one.groupBy(F.col("words").alias("word")).agg(F.sum("n").alias("n"))


@dataclass
class Vocabulary:
    n: int
    v: int
    mass: np.ndarray  # of each class; class 0 is the end, then SHARED shared ones, then own ones
    own: dict[str, int]

    @property
    def total(self) -> float:
        return self.n + ALPHA * (self.v + 1)

    def classes(self, words: pa.Array, endings: np.ndarray) -> np.ndarray:
        found = pc.index_in(words, pa.array(list(self.own), pa.string())).fill_null(-1).to_numpy()
        return np.where(found < 0, 1 + endings.astype(np.int64), np.array([*self.own.values(), 0])[found])

    def coarse(self) -> np.ndarray:
        """Coarse class of each class: the most frequent own ones keep theirs, the others share by their ending."""
        to = np.zeros(len(self.mass), np.int64)
        to[1 : 1 + SHARED] = 1 + np.arange(SHARED) % COARSE_SHARED
        for w, c in self.own.items():
            i = c - 1 - SHARED
            if c:
                to[c] = 1 + COARSE_SHARED + i if i < COARSE_OWN else 1 + ending(w) % COARSE_SHARED
        return to


def vocabulary(counts: DataFrame) -> Vocabulary:
    n, v = counts.agg(F.sum("n"), F.count(F.lit(1))).first()
    n = n or 0
    frequent = {r.word: r.n for r in counts.filter(F.col("n") * OWN >= n).collect()} if n else {}  # at most OWN words
    ranked = sorted((w for w in frequent if w != END), key=lambda w: (-frequent[w], w))
    own = {END: 0} | {w: 1 + SHARED + i for i, w in enumerate(ranked)}
    total = n + ALPHA * (v + 1)
    mass = np.full(SHARED + len(own), ALPHA / total)
    ends = frequent.get(END)
    if n and ends is None:
        ends = counts.filter(F.col("word") == END).agg(F.sum("n")).first()[0]
    mass[0] = ((ends or 0) + ALPHA) / total
    shared = counts.filter((F.col("n") * OWN < n) & (F.col("word") != END)).groupBy((1 + F.crc32(F.substring("word", -3, 3).cast("binary")) % SHARED).alias("c")).agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("v"))
    for r in shared.collect():  # at most SHARED rows
        mass[r.c] += (r.n + ALPHA * r.v) / total
    for w, c in own.items():
        if c:
            mass[c] = (frequent[w] + ALPHA) / total
    return Vocabulary(n, v, mass, own)


@dataclass
class Model:
    start: np.ndarray
    trans: np.ndarray
    emit: np.ndarray  # symbols x states; a symbol may carry any factor of its own


def tokens_in(block: dict) -> tuple[np.ndarray, np.ndarray]:
    """Places of all tokens of a block, and the offsets of its texts."""
    raw = np.frombuffer(block["seq"], "<u2")
    m = len(raw) // 2
    return raw[:m] | raw[m:].astype(np.int64) << 16, np.concatenate([[0], np.cumsum(block["sizes"])]).astype(np.int64)


@dataclass
class Training:
    """What a block has for training: its words, their endings and counts; places and offsets of its training texts."""

    words: pa.Array
    endings: np.ndarray
    n: np.ndarray
    flat: np.ndarray
    off: np.ndarray


def training_blocks(batches):
    for b in batches:
        for i in range(b.num_rows):
            of = lambda c: b.column(b.schema.get_field_index(c))[i]  # noqa: B023, E731
            sizes, keep = of("sizes").values.to_numpy(), ~of("held_out").values.to_numpy(zero_copy_only=False)
            flat, _ = tokens_in({"seq": of("seq").as_buffer(), "sizes": sizes})
            flat = flat[np.repeat(keep, sizes)]
            if len(flat):
                yield Training(of("words").values, np.frombuffer(of("endings").as_buffer(), "<u2"), of("n").values.to_numpy(), flat, np.concatenate([[0], np.cumsum(sizes[keep])]))


def over_training(blocks: DataFrame, run, schema: str) -> DataFrame:
    """run over what training reads of the blocks. Its jobs belong inside rows_a_batch(…, 1): a block is some 10 MB, and a batch of all
    blocks of a task would be held by the executor and by its worker."""
    return blocks.select("held_out", "sizes", "words", "endings", "n", "seq").mapInArrow(run, schema)


def first_model(blocks: DataFrame, vocab: Vocabulary, states: int, rounds: int = 150, seed: int = 7) -> Model:
    """States from the counts of neighbouring coarse classes, (COARSE + 1) squared cells at most."""
    coarse = vocab.coarse()
    k = int(coarse.max()) + 1 if len(coarse) else 1
    box = blocks.sparkSession.sparkContext.broadcast((vocab, coarse))

    def run(batches):
        vocab, coarse = box.value
        total = np.zeros(k * k)
        for t in training_blocks(batches):
            c = coarse[vocab.classes(t.words, t.endings)][t.flat]
            inside = np.ones(max(len(c) - 1, 0), bool)
            inside[t.off[1:-1] - 1] = False
            total += np.bincount((c[:-1] * k + c[1:])[inside], minlength=k * k)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["pair", "n"])

    pairs = np.zeros(k * k)
    with rows_a_batch(blocks.sparkSession, 1):
        found = over_training(blocks, run, "pair bigint, n double").groupBy("pair").agg(F.sum("n").alias("n")).collect()
    for r in found:
        pairs[r.pair] = r.n
    pairs = pairs.reshape(k, k)
    rng = np.random.default_rng(seed)
    mass = np.bincount(coarse, vocab.mass, k)
    emit = mass * np.exp(rng.normal(0, 0.5, (states, k)))
    emit /= emit.sum(1, keepdims=True)
    joint = np.full((states, states), 0.2 / states**2) + np.eye(states) * 0.8 / states
    for _ in range(rounds if pairs.sum() else 0):
        expected = emit.T @ joint @ emit
        ratio = np.where(pairs > 0, pairs / np.maximum(expected, 1e-300), 0)
        left, right = joint @ emit, joint.T @ emit
        emit_new = emit * (left @ ratio.T) + emit * (right @ ratio)
        joint = joint * (emit @ ratio @ emit.T)
        joint = joint / joint.sum() + 1e-9
        emit = emit_new + 1e-6 * mass * emit_new.sum() / mass.sum()
        emit /= emit.sum(1, keepdims=True)
    share = vocab.mass / mass[coarse]
    fine = (emit[:, coarse] * share).T
    fine /= fine.sum(0, keepdims=True)
    start = joint.sum(1) / joint.sum()
    return Model(start, joint / joint.sum(1, keepdims=True), fine / vocab.mass[:, None])


@dataclass
class Pieces:
    """Sequences cut into pieces of at most SEGMENT symbols, so that many are worked on side by side. pre: the states expected
    before the first symbol of a piece is seen; come: the states after the last symbol of the piece before; leave: what the
    symbols after a piece say of its last state. With these a piece gives what it gives inside its whole sequence."""

    start: np.ndarray
    size: np.ndarray
    first: np.ndarray
    of: np.ndarray
    pre: np.ndarray
    come: np.ndarray
    leave: np.ndarray


def _normal(x: np.ndarray) -> np.ndarray:
    return x / x.sum(-1, keepdims=True)


def cut(flat: np.ndarray, off: np.ndarray, model: Model, dtype, segment: int) -> Pieces:
    """The pieces with what enters and leaves them: per piece of a longer sequence the product of its steps is one states x
    states matrix, and these are chained over the sequence. No step waits for the piece before it."""
    s, total = len(model.start), np.diff(off)
    table, move = model.emit.astype(dtype), model.trans.astype(dtype)
    many = -(-total // segment)
    of = np.repeat(np.arange(len(total)), many)
    at = np.arange(len(of)) - np.repeat(np.cumsum(many) - many, many)
    start = off[of] + at * segment
    size = np.minimum(segment, off[of + 1] - start)
    pre = np.tile(model.start.astype(dtype), (len(of), 1))
    out = Pieces(start, size, at == 0, of, pre, np.zeros_like(pre), np.ones_like(pre))
    long = np.flatnonzero(many[of] > 1)
    product = np.zeros((len(of), s, s), dtype)
    order = long[np.argsort(-size[long], kind="stable")]
    for p in range(0, len(order), 256):
        rows = order[p : p + 256]
        live = np.searchsorted(-size[rows], -np.arange(size[rows[0]]), "left")
        x = np.tile(np.eye(s, dtype=dtype), (len(rows), 1, 1))
        for t, m in enumerate(live):
            y = x[:m] if t == 0 else (x[:m].reshape(-1, s) @ move).reshape(m, s, s)
            y = y * table[flat[start[rows[:m]] + t]][:, None, :]
            x[:m] = y / np.einsum("ijk->i", y)[:, None, None] if t % 8 == 7 else y
        product[rows] = x / x.sum((1, 2), keepdims=True)
    heads = np.cumsum(many) - many
    by_length = np.argsort(-many, kind="stable")
    longer = lambda k: heads[by_length[: np.searchsorted(-many[by_length], -k, "left")]] + k  # noqa: E731  # piece k of each sequence with more than k pieces
    for k in range(1, int(many.max(initial=1))):
        now = longer(k)
        out.come[now] = _normal((out.pre[now - 1][:, None, :] @ product[now - 1])[:, 0])
        out.pre[now] = out.come[now] @ move
    for k in range(int(many.max(initial=1)) - 1, 0, -1):
        now = longer(k)
        out.leave[now - 1] = _normal((product[now] @ out.leave[now][:, :, None])[:, :, 0]) @ move.T
    return out


def expected_counts(flat: np.ndarray, off: np.ndarray, model: Model, rows: int = 1024, segment: int = SEGMENT):
    """(start, transition, emission) counts and the log likelihood of whole sequences by scaled forward-backward, ``rows`` pieces side by side."""
    s, parts = len(model.start), cut(flat, off, model, np.float32, segment)
    order = np.argsort(-parts.size, kind="stable")
    begin, trans, emit, fit = np.zeros(s), np.zeros((s, s)), np.zeros(model.emit.shape), 0.0
    table, move, one = model.emit.astype(np.float32), model.trans.astype(np.float32), np.ones((s, 1), np.float32)
    for p in range(0, len(order), rows):
        which = order[p : p + rows]
        at, n, first = parts.start[which], parts.size[which], parts.first[which]
        live = np.searchsorted(-n, -np.arange(n[0]), "left")  # pieces longer than t
        ends = np.cumsum(live)
        symbols, states = np.empty(ends[-1], np.int32), np.empty((ends[-1], s), np.float32)
        alpha = None
        for t, m in enumerate(live):
            here = symbols[ends[t] - m : ends[t]]
            here[:] = flat[at[:m] + t]
            a = table[here] * (parts.pre[which] if t == 0 else alpha[:m] @ move)
            z = a @ one
            fit += float(np.log(z).sum())
            alpha = states[ends[t] - m : ends[t]]
            np.divide(a, z, out=alpha)
        beta = parts.leave[which]
        for t in range(len(live) - 1, -1, -1):
            m = live[t]
            gamma = states[ends[t] - m : ends[t]]  # what was filtered so far becomes what is expected
            back = table[symbols[ends[t] - m : ends[t]]] * beta[:m]
            gamma *= beta[:m]
            gamma /= gamma @ one
            if t:
                come = states[ends[t] - m - live[t - 1] : ends[t] - m][:m]
            else:
                begin += gamma[first].sum(0)
                come, back = parts.come[which][~first], back[~first]
            z = ((come @ move) * back) @ one
            trans += (come / z).T @ back
            if t:
                beta[:m] = (back / z) @ move.T
        for k in range(s):
            emit[:, k] += np.bincount(symbols, states[:, k], len(emit))
    return begin, trans * model.trans, emit, fit


@dataclass
class States:
    """What tasks need beside the counts of their words: P(s | ending) and P(s)."""

    start: np.ndarray
    trans: np.ndarray
    endings: np.ndarray
    share: np.ndarray

    def local(self, ends: np.ndarray, n: np.ndarray, counts: np.ndarray) -> Model:
        """The model whose symbols are words with the given endings."""
        prior = self.endings[ends]
        return Model(self.start, self.trans, (counts + KAPPA * prior) / (n[:, None] + KAPPA) / self.share)


def tied_round(blocks: DataFrame, model: Model, vocab: Vocabulary) -> tuple[Model, float]:
    """One round with emissions by class over all training texts, and the log likelihood a token before it."""
    s, k = len(model.start), len(vocab.mass)
    box = blocks.sparkSession.sparkContext.broadcast((model, vocab))

    def run(batches):
        model, vocab = box.value
        total = np.zeros(s + s * s + k * s + 1)
        for t in training_blocks(batches):
            begin, trans, emit, fit = expected_counts(vocab.classes(t.words, t.endings)[t.flat], t.off, model)
            total += np.concatenate([begin, trans.ravel(), emit.ravel(), [fit]])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], names=["key", "value"])

    total = np.zeros(s + s * s + k * s + 1)
    with rows_a_batch(blocks.sparkSession, 1):
        found = over_training(blocks, run, "key bigint, value double").groupBy("key").agg(F.sum("value").alias("value")).collect()  # classes x states rows
    for r in found:
        total[r.key] = r.value
    begin, trans, emit = total[:s] + 1 / s, total[s : s + s * s].reshape(s, s) + 1 / s, total[s + s * s : -1].reshape(k, s) + KAPPA * vocab.mass[:, None]
    return Model(begin / begin.sum(), trans / trans.sum(1, keepdims=True), emit / emit.sum(0) / vocab.mass[:, None]), total[-1] / max(vocab.n, 1)


def packs(s: int) -> list[str]:
    return [f"p{i}" for i in range(-(-s // 8))]


def packed(counts: np.ndarray, n: np.ndarray) -> list[np.ndarray]:
    steps = np.rint(counts / n[:, None] * STEPS).clip(0, STEPS).astype(np.uint64)
    out = []
    for i in range(0, steps.shape[1], 8):
        p = np.zeros(len(n), np.uint64)
        for k, q in enumerate(steps[:, i : i + 8].T):
            p |= q << np.uint64(8 * k)
        out.append(p.view(np.int64))
    return out


def unpacked(packs: list[np.ndarray], n: np.ndarray, s: int) -> np.ndarray:
    """Expected counts; the shares of a word sum to one again."""
    out = np.stack([(packs[k // 8] >> 8 * (k % 8) & STEPS).astype(float) for k in range(s)], 1)
    return out * (n / np.maximum(out.sum(1), 1))[:, None]


def word_round(blocks: DataFrame, model: Model, vocab: Vocabulary, rows: int) -> tuple[DataFrame, States]:
    """The last round: (word, n, packed expected counts by state) of every training word, and the states."""
    s = len(model.start)
    box = blocks.sparkSession.sparkContext.broadcast((model, vocab))
    kinds = [("key", pa.int64()), ("word", pa.string()), ("n", pa.int64()), ("value", pa.float64()), *((c, pa.int64()) for c in packs(s))]

    def run(batches):
        model, vocab = box.value
        rest = np.zeros(s * (s + 1))
        for t in training_blocks(batches):
            begin, trans, emit, _ = expected_counts(t.flat, t.off, Model(model.start, model.trans, model.emit[vocab.classes(t.words, t.endings)]))
            rest += np.concatenate([begin, trans.ravel()])
            at = np.flatnonzero(t.n)
            zeros = np.zeros(len(at), np.int64)
            cols = [zeros, t.words.take(pa.array(at)), t.n[at], zeros.astype(float), *packed(emit[at], t.n[at])]
            yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, k) for c, (_, k) in zip(cols, kinds)], names=[k for k, _ in kinds])
        # Keys: 0 a word; below it the starts, then the moves.
        zeros = np.zeros(len(rest), np.int64)
        cols = [-1 - np.arange(len(rest)), [""] * len(rest), zeros, rest, *([zeros] * len(packs(s)))]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(cols, kinds)], names=[k for k, _ in kinds])

    one = over_training(blocks, run, "key bigint, word string, n bigint, value double, " + ", ".join(f"{c} bigint" for c in packs(s)))
    steps = [F.shiftrightunsigned(f"p{k // 8}", 8 * (k % 8)).bitwiseAND(STEPS) for k in range(s)]
    # Partitioned first, as sums are wider than what they are of.
    sums = one.repartition("word", "key").groupBy("word", "key").agg(F.sum("n").alias("n"), F.sum("value").alias("value"), *(F.sum(F.col("n") * q).alias(f"s{k}") for k, q in enumerate(steps)))
    share = [F.when(F.col("n") > 0, F.round(F.col(f"s{k}") / F.col("n"))).otherwise(0).cast("bigint") for k in range(s)]
    again = [reduce(lambda a, b: a.bitwiseOR(b), [F.shiftleft(share[k], 8 * (k % 8)) for k in range(8 * i, min(8 * i + 8, s))]).alias(c) for i, c in enumerate(packs(s))]
    with rows_a_batch(blocks.sparkSession, 1):
        both = settled(sums.select("key", "word", "n", "value", *again), "lm-expected", rows)
    rest = np.full(s * (s + 1), 1 / s)
    for r in both.filter("key < 0").select("key", "value").collect():  # states x (states + 1) rows
        rest[-1 - r.key] += r.value
    begin, trans = rest[:s], rest[s:].reshape(s, s)
    found = both.filter("key = 0").select("word", "n", *packs(s))
    whole = F.greatest(reduce(lambda a, b: a + b, steps), F.lit(1))
    counts = [F.col("n") * q / whole for q in steps]
    weight = (F.col("n") + ALPHA) / (F.col("n") + KAPPA)
    sums = found.groupBy((F.crc32(F.substring("word", -3, 3).cast("binary")) % SHARED).alias("c")).agg(F.sum(weight * KAPPA).alias("b"), *(F.sum(e).alias(f"e{k}") for k, e in enumerate(counts)), *(F.sum(weight * e).alias(f"a{k}") for k, e in enumerate(counts)))
    expected, own, rest = np.zeros((SHARED, s)), np.zeros(s), np.full(SHARED, ALPHA)
    for r in sums.collect():  # at most SHARED rows
        expected[r.c] = [r[f"e{k}"] for k in range(s)]
        own += [r[f"a{k}"] for k in range(s)]
        rest[r.c] += r.b
    overall = expected.sum(0) + 1
    endings = expected + overall / overall.sum()
    endings /= endings.sum(1, keepdims=True)
    share = (own + rest @ endings) / vocab.total
    return found, States(begin / begin.sum(), trans / trans.sum(1, keepdims=True), endings, share)


def forward(flat: np.ndarray, off: np.ndarray, model: Model, rows: int = 1024, segment: int = SEGMENT) -> np.ndarray:
    """Natural log likelihood of each whole sequence by the scaled forward recursion."""
    parts = cut(flat, off, model, np.float64, segment)
    order, out = np.argsort(-parts.size, kind="stable"), np.zeros(len(off) - 1)
    for p in range(0, len(order), rows):
        which = order[p : p + rows]
        at, n, log = parts.start[which], parts.size[which], np.zeros(len(which))
        for t, m in enumerate(np.searchsorted(-n, -np.arange(n[0]), "left")):
            a = model.emit[flat[at[:m] + t]] * (parts.pre[which] if t == 0 else alpha[:m] @ model.trans)  # noqa: F821
            z = a.sum(1)
            log[:m] += np.log(z)
            alpha = a / z[:, None]  # noqa: F841
        np.add.at(out, parts.of[which], log)
    return out


def score(blocks: DataFrame, stats: DataFrame, states: States, vocab: Vocabulary) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, base: sum of log10 unigram shares, hmm: log10 likelihood of the ratios."""
    box = blocks.sparkSession.sparkContext.broadcast((states, vocab.total))
    kind = blocks.schema["ids"].dataType.elementType.simpleString()
    s = len(states.start)
    words = blocks.select(F.col("block").alias("of"), F.posexplode("words").alias("place", "word"))
    # Of a word only what its block needs travels on; stats of a partition are a small hash table, so the many rows are not sorted.
    met = words.join(stats.hint("shuffle_hash"), "word", "left").select("of", "place", "n", *packs(s)).groupBy("of")

    def run(left, right):
        states, total = box.value
        if not left.num_rows:
            return pa.table({"doc_id": pa.array([], left.schema.field("ids").type.value_type), "held_out": pa.array([], pa.bool_()), "n_tokens": pa.array([], pa.int64()), "n_known": pa.array([], pa.int64()), "base": pa.array([], pa.float64()), "hmm": pa.array([], pa.float64())})
        flat, off = tokens_in({"seq": left["seq"][0].as_buffer(), "sizes": left["sizes"].combine_chunks().flatten().to_numpy()})
        place = right["place"].to_numpy()
        n, shares = np.zeros(len(place), np.int64), [np.zeros(len(place), np.int64) for _ in packs(s)]
        n[place] = right["n"].fill_null(0).to_numpy()
        for c, x in zip(packs(s), shares):
            x[place] = right[c].fill_null(0).to_numpy()
        model = states.local(np.frombuffer(left["endings"][0].as_buffer(), "<u2"), n, unpacked(shares, n, s))
        known = np.add.reduceat((n > 0)[flat], off[:-1], dtype=np.int64)
        base = np.add.reduceat(np.log10((n + ALPHA) / total)[flat], off[:-1])
        given = [left[c].combine_chunks().flatten() for c in ("ids", "held_out", "sizes")]
        return pa.Table.from_arrays([*given, pa.array(known), pa.array(base), pa.array(forward(flat, off, model) / math.log(10))], names=["doc_id", "held_out", "n_tokens", "n_known", "base", "hmm"])

    texts = blocks.select("block", "ids", "held_out", "sizes", "endings", "seq").groupBy("block")
    return texts.cogroup(met).applyInArrow(run, f"doc_id {kind}, held_out boolean, n_tokens bigint, n_known bigint, base double, hmm double")


def train_and_score(docs: DataFrame, held_out, states: int = 8, rounds: int = 2, gain: float = 0.01) -> DataFrame:
    blocks = settled_blocks(docs, held_out)
    counts = settled(word_counts(blocks), "lm-counts")
    vocab = vocabulary(counts)
    now, before = first_model(blocks, vocab, states), -math.inf
    for _ in range(rounds):
        new, fit = tied_round(blocks, now, vocab)
        now, gained, before = new, fit - before, fit
        if gained < gain:
            break
    stats, final = word_round(blocks, now, vocab, vocab.v)
    scored = score(blocks, stats, final, vocab)
    return scored.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(vocab.n).cast("bigint").alias("train_tokens"), F.col("base").alias("base_score"), (F.col("base") + F.col("hmm")).alias("score"))


def op10(spark, sf_dir) -> DataFrame:
    return train_and_score(documents(spark, sf_dir), id_mod("doc_id", 10) == 0)

"""Best-fit packing of token pieces into sequences under several capacities.

Texts are encoded and cut (only those longer than a sequence; the first piece may be short).
Pieces are dealt by hash into groups of about ``group_rows``, so every group sees the same mix
of lengths, and each group packs in one task with bounded memory: longest first, each piece
goes to the open sequence that is best by ``score`` among those that keep every capacity:
tokens, documents, and attention cost (sum of squared lengths). A group wastes at most its
last few sequences. Full pieces close a sequence at once.

Scores over residuals (shares of each capacity): ``norm`` takes the least weighted norm of
what stays free, ``dot`` the greatest weighted product of demand and residual.

Defined cases: null or empty text is just the end id; repeated rows are packed each; an empty
table gives no row; further columns are ignored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import tokens
from .common import documents, id_text, settled, sliced

PIECES = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint, salt bigint"


@dataclass(frozen=True)
class Capacity:
    tokens: int = 1024
    documents: int = 1024
    attention: int = 1024 * 1024
    weights: tuple[float, float, float] = (1.0, 0.01, 0.05)
    score: str = "norm"

    @property
    def piece(self) -> int:
        """The longest piece that a sequence of its own holds."""
        return min(self.tokens, math.isqrt(self.attention))


def cut(n: int, most: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens."""
    first = n if n <= most else (n % most or most)
    return [(0, first), *((s, most) for s in range(first, n, most))]


def pieces(docs: DataFrame, most: int = 1024, end_id: int = 2, file: str = tokens.DEFAULT_FILE, with_ids: bool = False) -> DataFrame:
    """One row per piece; with_ids adds the ids themselves. salt numbers the rows of a task, so equal rows spread."""
    def run(batches):
        from zlib import crc32

        from pyspark import TaskContext

        encoder, salt = tokens.encoder(file), TaskContext.get().partitionId() << 33
        for b in sliced(batches):
            ids, offsets = encoder.encode_array(b.column(1), end_id)
            rows, raw = [], memoryview(ids.astype("<u4", copy=False).tobytes())
            for i, at, until in zip(b.column(0).to_pylist(), offsets.tolist(), offsets[1:].tolist()):
                for k, (s, n) in enumerate(cut(until - at, most)):
                    part = raw[4 * (at + s) : 4 * (at + s + n)]
                    rows.append((i, k, s, n, crc32(part), salt, *([np.frombuffer(part, "<i4")] if with_ids else [])))
                    salt += 1
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int32())]
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "salt", "ids"]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=names[: 6 + with_ids])

    return id_text(docs).mapInArrow(run, PIECES + ", ids array<int>" * with_ids)


def pack(lengths: np.ndarray, cap: Capacity) -> tuple[np.ndarray, np.ndarray]:
    """(sequence, offset) of each piece. Open sequences with equal residuals share a state, and only states are compared."""
    lengths = np.asarray(lengths, np.int64)
    seq, off = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    shares = np.array([1 / cap.tokens, 1 / cap.documents, 1 / cap.attention])
    weights = np.asarray(cap.weights)
    states, index, room = np.zeros((256, 3), np.int64), {}, []  # state rows; key -> row; sequences in each row
    free_rows, used = [], 0
    count = 0
    alive = np.zeros(256, bool)
    for i in np.argsort(-lengths, kind="stable"):
        n = int(lengths[i])
        need = (n, 1, n * n)
        best, live = -1, states[:used]
        if used:
            ok = alive[:used] & (live >= need).all(axis=1)
            at = np.flatnonzero(ok)
            if len(at):
                res = live[at]
                if cap.score == "dot":
                    value = -((res * shares) * (np.array(need) * shares) @ weights)
                else:
                    value = (((res - need) * shares) ** 2) @ weights
                best = int(at[int(np.argmin(value))])
        if best < 0:
            s, left = count, (cap.tokens, cap.documents, cap.attention)
            count += 1
        else:
            s, left = room[best].pop(), tuple(int(x) for x in states[best])
            if not room[best]:
                alive[best] = False
                del index[left]
                free_rows.append(best)
        seq[i], off[i] = s, cap.tokens - left[0]
        left = (left[0] - n, left[1] - 1, left[2] - n * n)
        if min(left) > 0:
            row = index.get(left)
            if row is None:
                if free_rows:
                    row = free_rows.pop()
                else:
                    row, used = used, used + 1
                    room.append([])
                    if row == len(states):
                        states, alive = np.concatenate([states, np.zeros_like(states)]), np.concatenate([alive, np.zeros_like(alive)])
                index[left], states[row], alive[row] = row, left, True
            room[row].append(s)
    return seq, off


def assign(found: DataFrame, cap: Capacity = Capacity(), group_rows: int = 40_000) -> DataFrame:
    """Adds sequence_id and offset to pieces that are already settled (they are counted first)."""
    groups = max(1, round(found.count() / group_rows))

    def run(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["salt"], kind="stable")
        seq, off = pack(part["length"].to_numpy(), cap)
        return part.assign(sequence_id=seq + (part["group"].to_numpy().astype(np.int64) << 36), offset=off).drop(columns="group")

    if any(n > cap.piece for (n,) in found.agg(F.max("length")).collect() if n):
        raise ValueError("a piece is longer than a sequence; cut the texts to the same capacity")
    dealt = found.withColumn("group", F.pmod(F.xxhash64("salt", "doc_id"), F.lit(groups)).cast("int"))
    return dealt.groupBy("group").applyInPandas(run, PIECES + ", sequence_id bigint, offset bigint")


def pack_documents(docs: DataFrame, cap: Capacity = Capacity(), end_id: int = 2, file: str = tokens.DEFAULT_FILE, group_rows: int = 40_000) -> DataFrame:
    return assign(settled(pieces(docs, cap.piece, end_id, file), "pieces"), cap, group_rows).drop("salt")


def write_sequences(docs: DataFrame, path: str, cap: Capacity = Capacity(), end_id: int = 2, file: str = tokens.DEFAULT_FILE) -> None:
    """The packed sequences with their ids, one row each: sequence_id, ids, doc_ids, lengths."""
    whole = settled(pieces(docs, cap.piece, end_id, file, with_ids=True), "piece-ids")
    plan = assign(whole.drop("ids"), cap)
    rows = whole.select("salt", "ids").join(plan, "salt")
    ordered = F.array_sort(F.collect_list(F.struct("offset", "doc_id", "length", "ids")))
    grouped = rows.groupBy("sequence_id").agg(ordered.alias("p"))
    grouped.select("sequence_id", F.flatten("p.ids").alias("ids"), F.col("p.doc_id").alias("doc_ids"), F.col("p.length").alias("lengths")).write.parquet(path)


def op4(spark, sf_dir) -> DataFrame:
    return pack_documents(documents(spark, sf_dir))

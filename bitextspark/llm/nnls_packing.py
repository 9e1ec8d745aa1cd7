"""Packing by non-negative least squares over a histogram of lengths.

Lengths are cut into bins of STEP tokens. Every combination of up to DEPTH
bins that fills a window exactly is a column; how often each is used is
solved by non-negative least squares against the histogram and rounded down.
What the histogram has left is packed greedily, on the histogram as well: the
longest bin takes the longest bins that still fit, as often as the counts
allow, so each step empties a bin. The driver holds bins and combinations
only, so its work doesn't grow with the input; documents get their place by
their rank within their bin.
"""

from __future__ import annotations

import os
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import tokens
from .common import as_bytes, cut, slices, tidy

WINDOW = 4096
STEP = 16
DEPTH = 3
END_ID = 2
#: Pieces that a task ranks together.
RANKED = 50_000


@lru_cache(4)
def combinations(bins: int, depth: int) -> tuple[tuple[int, ...], ...]:
    """All multisets of 1 to depth bins that sum to bins."""
    def grow(left: int, most: int, depth: int):
        if left == 0:
            yield ()
        elif depth:
            for b in range(min(left, most), (left - 1) // depth, -1):
                for rest in grow(left - b, b, depth - 1):
                    yield (b, *rest)

    return tuple(grow(bins, bins, depth))


def nnls(a: np.ndarray, y: np.ndarray, rounds: int = 2000) -> np.ndarray:
    """argmin over x >= 0 of |a x - y|, by an active set: free the column that helps most, solve, and drop what turns negative."""
    x, free = np.zeros(a.shape[1]), np.zeros(a.shape[1], dtype=bool)
    ridge = 1e-12 * np.eye(a.shape[0] + 1)
    for _ in range(rounds):
        gain = np.where(free, -np.inf, a.T @ (y - a @ x))
        j = int(gain.argmax())
        if gain[j] <= 1e-10 or free.sum() >= a.shape[0]:
            break
        free[j] = True
        while free.any():
            at = np.flatnonzero(free)
            part = a[:, at]
            s = np.linalg.solve(part.T @ part + ridge[: len(at), : len(at)], part.T @ y)
            if s.min() > 0:
                x[:] = 0
                x[at] = s
                break
            low = s <= 0
            x[at] += np.min(x[at][low] / (x[at][low] - s[low])) * (s - x[at])
            gone = low & (x[at] <= 1e-14)
            free[at[gone] if gone.any() else at[low]] = False
            x[~free] = 0
    return x


def plan(histogram: dict[int, int], bins: int, depth: int = DEPTH) -> list[tuple[tuple[int, ...], int]]:
    """(bins of a sequence, how many such sequences) that hold exactly the histogram's pieces."""
    left = np.zeros(bins + 1, dtype=np.int64)
    for b, n in histogram.items():
        left[b] += n
    out: list[tuple[tuple[int, ...], int]] = []
    if left[bins]:
        out.append(((bins,), int(left[bins])))
        left[bins] = 0
    if left.any():
        able = [c for c in combinations(bins, depth) if all(left[b] for b in c)]
        if able:
            a = np.zeros((bins, len(able)))
            for k, c in enumerate(able):
                for b in c:
                    a[b, k] += 1
            scale = float(left.sum())
            for c, r in sorted(zip(able, nnls(a, left[:bins] / scale) * scale, strict=True), key=lambda x: -x[1]):
                need = {b: c.count(b) for b in c}
                n = min(int(r + 1e-6), *(int(left[b]) // k for b, k in need.items()))
                if n > 0:
                    out.append((c, n))
                    for b, k in need.items():
                        left[b] -= n * k
    while left.any():
        room, made = bins, []
        spare = left.copy()
        while room:
            fits = np.flatnonzero(spare[1 : room + 1])
            if not len(fits):
                break
            b = int(fits[-1]) + 1
            made.append(b)
            spare[b] -= 1
            room -= b
        need = {b: made.count(b) for b in made}
        n = min(int(left[b]) // k for b, k in need.items())
        out.append((tuple(made), n))
        for b, k in need.items():
            left[b] -= n * k
    return out


def slots(made: list[tuple[tuple[int, ...], int]]) -> dict[int, list[tuple[int, int, int, int, int]]]:
    """By bin, runs of ranks: (first rank, first sequence, how many sequences, pieces a sequence, place of the first)."""
    out: dict[int, list] = {}
    used: dict[int, int] = {}
    sequence = 0
    for c, n in made:
        at = 0
        for b in sorted(set(c), reverse=True):
            k = c.count(b)
            out.setdefault(b, []).append((used.get(b, 0), sequence, n, k, at))
            used[b] = used.get(b, 0) + n * k
            at += k
        sequence += n
    return out


def pieces(docs: DataFrame, path: str, id_col: str, text_col: str, window: int, end_id: int) -> DataFrame:
    """Windows of every document's ids: (id, start, length, ids_crc32, doc_tokens)."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        apart = tokens.splits_at_space(path)
        memo = tokens.Memo(path) if apart else None
        library = tokens.load(path)
        end = np.array([end_id], dtype="<u4").tobytes()
        for whole in batches:
            for batch in slices(whole, "t"):
                ids, starts, lengths, crcs, totals = [], [], [], [], []
                texts = as_bytes(batch.column("t"))
                words = [memo.fold(t).split() if t else [] for t in texts] if apart else []
                known = memo.learn(set().union(*words)).__getitem__ if apart else None
                for k, (i, text) in enumerate(zip(batch.column("i").to_pylist(), texts, strict=True)):
                    if apart:
                        data = b"".join(map(known, words[k])) + end
                    else:
                        data = np.array(library.encode((text or b"").decode("utf-8", "replace"), add_special_tokens=False).ids, dtype="<u4").tobytes() + end
                    n = len(data) // 4
                    for at in range(0, n, window):
                        part = data[4 * at : 4 * (at + window)]
                        ids.append(i)
                        starts.append(at)
                        lengths.append(len(part) // 4)
                        crcs.append(zlib.crc32(part))
                        totals.append(n)
                yield pa.RecordBatch.from_arrays([pa.array(ids, batch.schema.field("i").type), *(pa.array(x, pa.int64()) for x in (starts, lengths, crcs, totals))], names=["i", "start", "length", "ids_crc32", "doc_tokens"])

    return docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(tidy(run), f"i {kind}, start long, length long, ids_crc32 long, doc_tokens long")


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, window: int = WINDOW, step: int = STEP, depth: int = DEPTH, end_id: int = END_ID) -> DataFrame:
    """Pack every document into sequences of at most window tokens.

    A document's ids are those of the tokenizer with end_id behind them; they
    are cut at multiples of window. One row per piece: id, start, length,
    ids_crc32, doc_tokens, sequence_id, offset (gapless from 0 in a sequence).
    A null or empty text is its end id alone. Repeated rows are packed as
    often as they come; a null id is carried along; an empty table gives an
    empty result. Other columns of docs are not read.
    """
    bins = window // step
    own = cut(pieces(docs, path or tokens.default_path(), id_col, text_col, window, end_id), "pieces")
    own = own.withColumn("bin", F.ceil(F.col("length") / step).cast("int"))
    histogram = {r["bin"]: r["n"] for r in own.groupBy("bin").agg(F.count("*").alias("n")).collect()}
    runs = slots(plan(histogram, bins, depth)) if histogram else {}
    parts = max(64, sum(histogram.values()) // RANKED)

    # a piece's rank in its bin: its rank in its bin's part, behind the parts before
    own = own.withColumn("part", F.pmod(F.xxhash64("i", "start", "ids_crc32"), F.lit(parts)).cast("int"))
    before = Window.partitionBy("bin").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    ahead = cut(own.groupBy("bin", "part").agg(F.count("*").alias("n")).select("bin", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("ahead")), "ahead")
    within = Window.partitionBy("bin", "part").orderBy("i", "start", "ids_crc32", "doc_tokens")
    ranked = own.withColumn("rank", F.row_number().over(within) - 1).join(ahead, ["bin", "part"]).withColumn("rank", F.col("rank") + F.col("ahead"))

    def place(batches):
        table = {b: tuple(np.array(x, dtype=np.int64) for x in zip(*rows, strict=True)) for b, rows in runs.items()}
        for batch in batches:
            b, rank = batch.column("bin").to_numpy(), batch.column("rank").to_numpy()
            sequence, at = np.zeros(len(b), dtype=np.int64), np.zeros(len(b), dtype=np.int64)
            for own_bin in np.unique(b):
                first, start, many, per, place0 = table[int(own_bin)]
                rows = np.flatnonzero(b == own_bin)
                k = np.searchsorted(first, rank[rows], side="right") - 1
                inside = rank[rows] - first[k]
                sequence[rows] = start[k] + inside // per[k]
                at[rows] = place0[k] + inside % per[k]
            names = ["i", "start", "length", "ids_crc32", "doc_tokens"]
            yield pa.RecordBatch.from_arrays([*(batch.column(x) for x in names), pa.array(sequence), pa.array(at)], names=[*names, "sequence_id", "place"])

    kind = docs.schema[id_col].dataType.simpleString()
    placed = ranked.select("i", "start", "length", "ids_crc32", "doc_tokens", "bin", "rank").mapInArrow(tidy(place), f"i {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, place long")
    up_to = Window.partitionBy("sequence_id").orderBy("place").rowsBetween(Window.unboundedPreceding, -1)
    return placed.select(F.col("i").alias(id_col), "start", "length", "ids_crc32", "doc_tokens", "sequence_id", F.coalesce(F.sum("length").over(up_to), F.lit(0)).cast("long").alias("offset"))

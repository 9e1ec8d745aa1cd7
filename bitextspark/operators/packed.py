"""N-gram models scored from packed slices of a corpus: what is shuffled are n-grams' keys and counts, distinct by slice, as arrays.

A slice is about a million tokens. It sends each of its distinct n-grams once,
with its count there, to the bucket of its key; the bucket adds the counts up
and answers the slices that asked, in the order they asked in, so neither
tokens nor n-grams are ever rows. Tokens are known by 64 bits (XXH64), n-grams
by 80 bits of their tokens'; that two of a billion n-grams share 80 bits has a
chance of one in two million.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .lexical import keep_table
from .ngram import BEGIN, END, FIXED

#: Tokens of a slice, and n-grams that a bucket is laid out for.
SLICE, BUCKET = 1 << 20, 1 << 20
#: Code points of these marks are in no text, so a character is never taken for one.
CHAR_BEGIN, CHAR_END = 0x110000, 0x110001

_SLICE = "side string, slice string, label string, n long, ids array<string>, sizes binary, kinds binary, places binary"
_PACKET = "bucket long, slice string, label string, ask boolean, keys binary, counts binary"
_ANSWER = "slice string, bucket long, counts binary, v array<long>"


def _pack(x: np.ndarray) -> bytes:
    """Byte planes of unsigned integers; those that are mostly zero take next to no room."""
    width = x.dtype.itemsize
    return zlib.compress(np.ascontiguousarray(x.view(np.uint8).reshape(-1, width).T).tobytes(), 1)


def _unpack(data: bytes, dtype) -> np.ndarray:
    width = np.dtype(dtype).itemsize
    return np.ascontiguousarray(np.frombuffer(zlib.decompress(data), np.uint8).reshape(width, -1).T).view(dtype).ravel()


def _mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64 bits whose every output bit hangs on every input bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _keys(kind: int, *tokens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """80 bits of an n-gram of this kind: 64 that give its bucket, and 16 more."""
    out = []
    for lane in (1, 2):
        k = np.uint64((0x9E3779B97F4A7C15 * (2 * kind + 1) * (4 * lane + 1)) & (2**64 - 1))
        at = np.full(len(tokens[0]), k)
        for t in tokens:
            at = _mix((at ^ t) + k)
        out.append(at)
    return out[0], (out[1] >> np.uint64(48)).astype(np.uint16)


def sliced(df: DataFrame, id_col: str, tokens: str, label: str | None = None, chars: bool = False) -> DataFrame:
    """df's sentences as slices, kept. tokens: an array column, or with chars a text whose code points are the tokens."""
    return sliced_sides(df, id_col, {tokens: chars}, label).drop("side")


def sliced_sides(df: DataFrame, id_col: str, sides: dict[str, bool], label: str | None = None) -> DataFrame:
    """As sliced, for several columns of tokens (and whether each is a text of characters) in one pass over df; column side tells them apart."""
    what = [(F.col(c) if chars else F.transform(c, lambda t: F.xxhash64(t))).alias(c) for c, chars in sides.items()]
    rows = df.select(F.col(id_col).cast("string").alias("__id"), (F.col(label) if label else F.lit("")).cast("string").alias("__label"), *what)

    def one(side, label, held):
        sizes = np.concatenate([h[1] for h in held])
        kinds, at, often = np.unique(np.concatenate([h[2] for h in held]), return_inverse=True, return_counts=True)
        by_count = np.argsort(-often, kind="stable")  # small numbers for frequent ones
        rank = np.empty(len(kinds), np.uint32)
        rank[by_count] = np.arange(len(kinds), dtype=np.uint32)
        return {"side": side, "slice": uuid.uuid4().hex, "label": label, "n": int(sizes.sum()) + len(sizes), "ids": [i for h in held for i in h[0]], "sizes": _pack(sizes.astype(np.uint32)), "kinds": kinds[by_count].tobytes(), "places": _pack(rank[at.ravel()])}

    names = [f.split()[0] for f in _SLICE.split(", ")]

    def made(held):
        rows = [one(*k, v) for k, v in held.items()]
        types = {"n": pa.int64(), "ids": pa.list_(pa.string()), "sizes": pa.binary(), "kinds": pa.binary(), "places": pa.binary()}
        return pa.RecordBatch.from_arrays([pa.array([r[n] for r in rows], types.get(n, pa.string())) for n in names], names)

    def run(batches):
        held, n = {}, 0
        for b in batches:
            if not b.num_rows:
                continue
            labels, ids = np.array(b.column("__label").to_pylist(), object), np.array(b.column("__id").to_pylist(), object)
            for side, chars in sides.items():
                t = b.column(side)
                if chars:
                    texts = t.to_pylist()
                    sizes = np.array([len(x) for x in texts], np.int64)
                    flat = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
                else:
                    sizes = np.diff(t.offsets.to_numpy())
                    flat = t.flatten().to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
                for name in set(labels):
                    mine = np.array([x == name for x in labels])
                    held.setdefault((side, name), []).append((ids[mine].tolist(), sizes[mine], flat[np.repeat(mine, sizes)]))
                n += int(sizes.sum()) + len(sizes)
            if n >= SLICE:
                yield made(held)
                held, n = {}, 0
        if held:
            yield made(held)

    return keep_table(rows.mapInArrow(run, _SLICE), "slices")


class _Grams:
    """A slice's distinct n-grams up to order n, and which of them each token is.

    A context's count is that of the n-gram of its tokens, as each but the last is followed by another;
    the marks are apart, since a text may hold their spelling, too.
    """

    def __init__(self, sizes: np.ndarray, kinds: np.ndarray, places: np.ndarray, n: int, begin: int, end: int):
        k = len(kinds)
        kinds = np.concatenate([kinds, np.array([begin, end], np.uint64)])
        # a mark that is spelled out in the text is the mark
        same = {m: int(np.flatnonzero(kinds == kinds[m])[0]) for m in (k, k + 1)}
        b, e = same[k], same[k + 1]
        sizes = sizes.astype(np.int64)
        stop = np.cumsum(sizes + 1)
        self.starts, self.sizes = stop - sizes - 1, sizes
        c = np.full(int(stop[-1]), e, np.int64)
        inside = np.ones(len(c), bool)
        inside[stop - 1] = False
        c[inside] = places
        self.c, size = c, len(kinds)
        own = np.arange(size) if len({b, e, k, k + 1}) == 2 else np.array([i for i in range(size) if i < k or i in (b, e)])
        where = np.zeros(size, np.int64)
        where[own] = np.arange(len(own))
        one, two = _keys(1, kinds[own])
        keys, checks, counts = [one], [two], [np.bincount(c, minlength=size)[own]]
        self.uni = where[c]
        prev = np.concatenate([[b], c[:-1]])
        prev[self.starts] = b
        self.ctx1, self.n_uni = where[prev], len(own)
        self.b1, self.e1 = int(where[b]), int(where[e])
        code, self.bi, times = np.unique(np.concatenate([prev * size + c, [b * size + b]]), return_inverse=True, return_counts=True)
        self.bi = self.bi.ravel()
        bb, self.bi = int(self.bi[-1]), self.bi[:-1]
        times[bb] -= 1  # it was only asked for
        one, two = _keys(2, kinds[code // size], kinds[code % size])
        keys.append(one), checks.append(two), counts.append(times)
        at = self.n_uni
        bi, self.bi = self.bi, self.bi + at
        self.b2 = at + bb
        at += len(code)
        if n == 3:
            before = np.concatenate([[bb], bi[:-1]])
            before[self.starts] = bb
            self.ctx2 = before + self.n_uni
            spelled = np.flatnonzero(prev == e)
            if len(spelled):
                ctx, inv, times = np.unique(before[spelled], return_inverse=True, return_counts=True)
                one, two = _keys(4, kinds[code[ctx] // size], kinds[code[ctx] % size])
                keys.append(one), checks.append(two), counts.append(times)
                self.ctx2[spelled] = at + inv.ravel()
                at += len(ctx)
            triple, inv, times = np.unique(before * size + c, return_inverse=True, return_counts=True)
            first = code[triple // size]
            one, two = _keys(3, kinds[first // size], kinds[first % size], kinds[triple % size])
            keys.append(one), checks.append(two), counts.append(times)
            self.tri = at + inv.ravel()
        self.keys, self.checks, self.counts = np.concatenate(keys), np.concatenate(checks), np.concatenate(counts).astype(np.int64)
        self.order = np.lexsort((self.checks, self.keys))

    def packets(self, buckets: int):
        """(bucket, keys, counts) in the order of the keys; a count's lowest bit says that it is a single token's."""
        k = self.keys[self.order]
        # the bucket grows with the key
        bucket = ((k >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32)
        cuts = np.concatenate([[0], np.flatnonzero(np.diff(bucket.astype(np.int64))) + 1, [len(k)]])
        checks, counts = self.checks[self.order], (self.counts[self.order] << 1 | (self.order < self.n_uni)).astype(np.uint64)
        for lo, hi in zip(cuts, cuts[1:], strict=False):
            yield int(bucket[lo]), _pack_keys(k[lo:hi], checks[lo:hi]), _pack(counts[lo:hi])


def _pack_keys(k: np.ndarray, check: np.ndarray) -> bytes:
    """Sorted keys: steps of the upper 24 bits, then 7 bytes a key as they are."""
    head = (k >> np.uint64(40)).astype(np.uint32)
    steps = _pack(np.diff(head, prepend=np.uint32(0)))
    low = np.empty((len(k), 7), np.uint8)
    low[:, :5] = k.view(np.uint8).reshape(-1, 8)[:, :5]
    low[:, 5:] = check.view(np.uint8).reshape(-1, 2)
    return len(steps).to_bytes(4, "little") + steps + low.tobytes()


def _unpack_keys(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = int.from_bytes(data[:4], "little")
    head = np.cumsum(_unpack(data[4 : 4 + n], np.uint32), dtype=np.uint64)
    low = np.frombuffer(data, np.uint8, offset=4 + n).reshape(-1, 7)
    k = np.zeros((len(low), 8), np.uint8)
    k[:, :5] = low[:, :5]
    return (head << np.uint64(40)) | k.view(np.uint64).ravel(), np.ascontiguousarray(low[:, 5:]).view(np.uint16).ravel()


def _marks(spark, chars: bool) -> tuple[int, int]:
    if chars:
        return CHAR_BEGIN, CHAR_END
    r = spark.range(1).select(F.xxhash64(F.lit(BEGIN)).alias("b"), F.xxhash64(F.lit(END)).alias("e")).first()
    return r["b"] & (2**64 - 1), r["e"] & (2**64 - 1)


def scores(asked: DataFrame, n: int, more: DataFrame | None = None, chars: bool = False, literal: tuple[str, str] | None = None) -> tuple[list[str], DataFrame]:
    """(labels, (id, scores)): for each sentence of the slices asked, mean ln P by the models of all labels, in their order.

    The models are fitted on the slices asked and more, one a label, under fixed interpolation. literal: the sum of
    -p ln q instead, p and q by these two labels' models, where an unseen n-gram gets the uniform part.
    """
    spark, weights = asked.sparkSession, FIXED[n]
    begin, end = _marks(spark, chars)
    slices = asked.withColumn("ask", F.lit(True))
    if more is not None:
        slices = slices.unionByName(more.withColumn("ask", F.lit(False)))
    # a row a label
    totals = {r["label"]: (r["n"], r["s"]) for r in slices.groupBy("label").agg(F.sum("n").alias("n"), F.sum(F.size("ids")).alias("s")).collect()}
    labels = sorted(totals, key=lambda x: (x is None, x))
    buckets = max(1, -(-sum(t for t, _ in totals.values()) // BUCKET))
    number = {x: i for i, x in enumerate(labels)}

    def grams(sizes, kinds, places):
        return _Grams(_unpack(sizes, np.uint32), np.frombuffer(kinds, np.uint64), _unpack(places, np.uint32), n, begin, end)

    def send(batches):
        for b in batches:
            for r in b.to_pylist():
                rows = list(grams(r["sizes"], r["kinds"], r["places"]).packets(buckets))
                for lo in range(0, len(rows), 64):
                    part = rows[lo : lo + 64]
                    m = len(part)
                    yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in part], pa.int64()), pa.array([r["slice"]] * m), pa.array([r["label"]] * m, pa.string()), pa.array([r["ask"]] * m), pa.array([x[1] for x in part], pa.binary()), pa.array([x[2] for x in part], pa.binary())], ["bucket", "slice", "label", "ask", "keys", "counts"])

    def answer(table):
        keys, checks, counts, owner, cuts = [], [], [], [], [0]
        names, asks = table.column("slice").to_pylist(), table.column("ask").to_pylist()
        for data, count, label in zip(table.column("keys"), table.column("counts"), table.column("label").to_pylist(), strict=True):
            k, c = _unpack_keys(data.as_py())
            keys.append(k), checks.append(c), counts.append(_unpack(count.as_py(), np.uint64)), owner.append(np.full(len(k), number[label], np.int32)), cuts.append(cuts[-1] + len(k))
        k, c, x, of = (np.concatenate(v) for v in (keys, checks, counts, owner))
        order = np.lexsort((c, k))
        new = np.ones(len(k), bool)
        new[1:] = (np.diff(k[order]) != 0) | (np.diff(c[order]) != 0)
        group = np.empty(len(k), np.int64)
        group[order] = np.cumsum(new) - 1
        size, single, x = int(new.sum()), (x & np.uint64(1)).astype(bool), (x >> np.uint64(1)).astype(np.float64)
        summed = np.stack([np.bincount(group[of == i], x[of == i], size) for i in range(len(labels))]).astype(np.uint64)
        kinds = np.zeros(size, bool)
        kinds[group[single]] = True
        bucket = table.column("bucket")[0].as_py()
        rows = [("", bucket, b"", (summed[:, kinds] > 0).sum(axis=1).tolist())]
        for i, (name, ask) in enumerate(zip(names, asks, strict=True)):
            if ask:
                rows.append((name, bucket, _pack(summed[:, group[cuts[i] : cuts[i + 1]]].ravel()), None))
        types = (pa.string(), pa.int64(), pa.binary(), pa.list_(pa.int64()))
        return pa.Table.from_arrays([pa.array([r[j] for r in rows], t) for j, t in enumerate(types)], ["slice", "bucket", "counts", "v"])

    packed = slices.select("slice", "label", "ask", "sizes", "kinds", "places").mapInArrow(send, _PACKET)
    answers = keep_table(packed.groupBy("bucket").applyInArrow(answer, _ANSWER), "answers")
    found = answers.filter("slice = ''").select(*(F.sum(F.get("v", F.lit(i))).alias(f"v{i}") for i in range(len(labels)))).first()  # a row
    vocab = [found[f"v{i}"] for i in range(len(labels))]

    def probabilities(g, counts, i):
        """(p, whether the whole n-gram is known) for each token under the i-th model."""
        name = labels[i]
        total, sentences = totals[name]
        p = weights[-1] / vocab[i]
        if name is None:  # equal to no label, so no count of it is found
            return np.full(len(g.c), p), np.zeros(len(g.c), bool)
        x = counts.astype(np.float64)
        ratio = lambda a, b: np.divide(a, b, out=np.zeros(len(a)), where=a > 0)
        first = x.copy()
        first[g.b1] += sentences
        first[g.e1] -= sentences
        by_order = [x[g.uni] / total, ratio(x[g.bi], first[g.ctx1])]
        top = x[g.bi]
        if n == 3:
            second = x.copy()
            second[g.b2] += sentences
            top = x[g.tri]
            by_order.append(ratio(top, second[g.ctx2]))
        out = 0.0
        for w, q in zip(weights, reversed(by_order), strict=False):
            out = out + w * q
        return out + p, top > 0

    def finish(left, right):
        r = left.to_pylist()[0]
        g = grams(r["sizes"], r["kinds"], r["places"])
        parts = sorted(zip(right.column("bucket").to_pylist(), right.column("counts").to_pylist(), strict=True))
        told = np.concatenate([_unpack(c, np.uint64).reshape(len(labels), -1) for _, c in parts], axis=1)
        counts = np.empty_like(told)
        counts[:, g.order] = told
        ps = [probabilities(g, counts[i], i) for i in range(len(labels))]
        if literal:
            i, j = (number[x] for x in literal)
            p, q = (np.where(ps[m][1], ps[m][0], weights[-1] / vocab[m]) for m in (i, j))
            values = np.add.reduceat(-p * np.log(q), g.starts)[:, None]
        else:
            values = np.stack([np.add.reduceat(np.log(p), g.starts) / (g.sizes + 1) for p, _ in ps], axis=1)
        m = values.shape[1]
        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, values.size + 1, m), pa.int32()), pa.array(values.ravel()))
        return pa.Table.from_arrays([pa.array(r["ids"], pa.string()), lists], ["id", "scores"])

    left = asked.select("slice", "ids", "sizes", "kinds", "places").groupBy("slice")
    right = answers.filter("slice <> ''").select("slice", "bucket", "counts").groupBy("slice")
    return labels, left.cogroup(right).applyInArrow(finish, "id string, scores array<double>")

"""Language-model scoring with a log-bilinear model trained by noise-contrastive estimation.

Token counts cover all training documents, and so does the neural model: its
vocabulary is every token of LEAST_COUNT training occurrences, so it grows
with the corpus (to HOT_WORDS at most, what a worker can hold), and each
training document takes part in estimation. The vector of the next token is
predicted as the sum of a vector of each token before it, by its distance
(words' vectors and the linear map of a distance are one table). Its
probability has two factors: the SHORT most frequent words are classes of
their own and the others lie in classes of neighbours in rank, MEMBERS or a
GROWTH-th of the ranks before, so that classes grow with the logarithm of a
large vocabulary and the largest are those that are seldom entered; first
the class is predicted, then the word within it, each normalised by matrix
products. As the score of a class is a sum over the tokens before, its
exponential is a product: one table of exponentials a distance, made once,
gives a normaliser as the inner product of two of its rows. Tokens outside the vocabulary share one class; one of them has the
class's probability times its smoothed share of it, so probabilities over all
tokens, unseen ones as one, sum to one.

Estimation goes in ROUNDS rounds. In each, LEARNERS tasks at most start from
the same parameters, read that round's part of the documents to its end and
return the rows that they changed; rows are averaged by how often each was
drawn and written. Small corpora are read several times (visits), large ones
once. Averages depend on how the input is split into tasks.

Frequent tokens' counts are sent to the tasks (HOT_WORDS at most). The rest,
a small part of the text, meets its counts in a join.
"""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, cut, slices, tidy

HOT_WORDS = 120_000
#: Steps of the share that is taken of a bucket of counts.
SHARES = 1 << 20
#: A token with as many training occurrences is a word of the neural model.
LEAST_COUNT = 100
SHORT, MEMBERS, GROWTH = 128, 128, 32
#: Scores of a class's words that are made at once.
PIECE = 1 << 19
#: Words whose factors a worker keeps, and rows of a table that travel together.
HELD, BLOCK = 16_384, 256
ROUNDS, LEARNERS = 3, 16
#: Tokens that a small corpus is read again for, up to MOST_VISITS times in all.
VISITED_TOKENS, MOST_VISITS = 3_000_000, 3
DIMENSIONS = 32
CONTEXT = 2
#: Runs of rows that are summed one by one.
FEW_RUNS = 48
NOISE, CLASS_NOISE = 24, 1
RATE = 0.1
#: Tokens a step: a corpus is learned in STEPS steps at least, as far as batches may be that small.
LEAST_BATCH, MOST_BATCH, STEPS = 512, 8192, 4000
END = b""  # no word is empty
LN10 = math.log(10)


def tokens(text: bytes | None) -> list[bytes]:
    return [*(text or b"").lower().split(), END]


def class_edges(vocabulary: int) -> np.ndarray:
    """The first word of every class; behind them the vocabulary, where the class of all other words starts."""
    edges = list(range(min(vocabulary, SHORT)))
    at = len(edges)
    while at < vocabulary:
        edges.append(at)
        at += max(MEMBERS, at // GROWTH)
    return np.array([*edges, vocabulary])


def class_of(words: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Classes of word numbers; the vocabulary's size and beyond stand for all others, in the last class."""
    return np.searchsorted(edges, words, side="right") - 1


def log_sum(s: np.ndarray) -> np.ndarray:
    top = s.max(axis=1)
    return top + np.log(np.exp(s - top[:, None]).sum(axis=1))


@dataclass
class LogBilinear:
    """Row w of context is word w; the row behind the words stands for all others, the last one for a text's start. target and bias have a row per class, word and word_bias one per word."""

    context: np.ndarray  # (CONTEXT, words + 2, d): vectors of the tokens before, the nearest first
    target: np.ndarray  # (classes, d)
    bias: np.ndarray  # (classes,)
    word: np.ndarray  # (words, d)
    word_bias: np.ndarray  # (words,)

    def __post_init__(self):
        self._held = None
        self.edges = class_edges(len(self.word))
        # biases are a column, which meets a one behind each hidden vector
        self._words = np.column_stack([self.word, self.word_bias]).astype(np.float32)
        self._space = np.empty(PIECE, dtype=np.float32)

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("_held", "_words", "_space")}

    def __setstate__(self, state):
        self.__dict__ |= state
        self.__post_init__()

    def hidden(self, before: np.ndarray) -> np.ndarray:
        return sum(self.context[j][before[:, j]] for j in range(CONTEXT))

    def _factor(self, j: int, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The exponentials of the classes' scores after words at distance j, over each row's largest, and its logarithm."""
        scores = self.context[j][words] @ self.target.T
        if j == 0:
            scores += self.bias
        top = scores.max(axis=1)
        scores -= top[:, None]
        return np.exp(scores, out=scores), top

    def log_partition(self, before: np.ndarray) -> np.ndarray:
        """Logarithms of the classes' sums. Factors of the HELD most frequent words are kept, others' are made once a call, in the rows behind them."""
        if self._held is None:
            self._held = [self._factor(j, np.arange(min(HELD, self.context.shape[1]))) for j in range(CONTEXT)]
        tables, tops, places = [], [], []
        for j, (table, top) in enumerate(self._held):
            n = min(HELD, self.context.shape[1])
            at = before[:, j]
            rare, back = np.unique(at[at >= n], return_inverse=True)
            if len(rare):
                if len(table) < n + len(rare):
                    grown, grown_top = np.empty((n + 5 * len(rare) // 4, table.shape[1]), dtype=table.dtype), np.empty(n + 5 * len(rare) // 4, dtype=top.dtype)
                    grown[:n], grown_top[:n] = table[:n], top[:n]
                    self._held[j] = table, top = grown, grown_top
                for a in range(0, len(rare), 1024):
                    part = slice(n + a, n + min(a + 1024, len(rare)))
                    table[part], top[part] = self._factor(j, rare[a : a + 1024])
                at = at.copy()
                at[at >= n] = n + back
            tables.append(table)
            tops.append(top)
            places.append(at)
        out = sum(top[at] for top, at in zip(tops, places, strict=True)).astype(np.float64)
        rows = max(1, PIECE // 2 // tables[0].shape[1])
        product, other = (np.empty((min(rows, len(before)), tables[0].shape[1]), dtype=tables[0].dtype) for _ in range(2))
        for a in range(0, len(before), rows):
            part = slice(a, a + rows)
            n = len(out[part])
            # places are in range; only with a mode does take() write to its result directly
            np.take(tables[0], places[0][part], axis=0, out=product[:n], mode="clip")
            for j in range(1, CONTEXT):
                np.take(tables[j], places[j][part], axis=0, out=other[:n], mode="clip")
                if j < CONTEXT - 1:
                    product[:n] *= other[:n]
            z = np.einsum("tc,tc->t", product[:n], other[:n])
            # where the largest classes of the factors differ by much, their product may vanish; those few are summed the plain way
            good = z > 1e-25
            out[part] += np.log(np.where(good, z, 1))
            for i in a + np.flatnonzero(~good):
                out[i] = log_sum((self.hidden(before[i : i + 1]) @ self.target.T + self.bias).astype(np.float64))[0]
        return out

    def log_partitions(self, before: np.ndarray, step: int = 65_536) -> np.ndarray:
        """log_partition of many contexts, of each distinct one once. They come by their nearest word, so its factor is seldom made twice."""
        key = before[:, 0].astype(np.int64)
        for j in range(1, CONTEXT):
            key = key * self.context.shape[1] + before[:, j]
        key, back = np.unique(key, return_inverse=True)
        distinct = np.empty((len(key), CONTEXT), dtype=np.int64)
        for j in reversed(range(CONTEXT)):
            distinct[:, j] = key % self.context.shape[1]
            key //= self.context.shape[1]
        return np.concatenate([self.log_partition(distinct[a : a + step]) for a in range(0, max(1, len(distinct)), step)])[back]

    def log_probability(self, words: np.ndarray, before: np.ndarray, partition: np.ndarray | None = None) -> np.ndarray:
        """Of every word after its context, that of the class for words outside the vocabulary. partition: log_partitions of the contexts, where they have been made."""
        v = len(self.word)
        classes, hidden = class_of(words, self.edges), self.hidden(before)
        out = np.einsum("td,td->t", hidden, self.target[classes]) + self.bias[classes] - (self.log_partitions(before) if partition is None else partition)
        deep = np.flatnonzero((words >= SHORT) & (words < v))
        deep = deep[np.argsort(classes[deep].astype(np.uint16), kind="stable")]
        if not len(deep):
            return out
        asked = np.ones((len(deep), hidden.shape[1] + 1), dtype=np.float32)
        asked[:, :-1] = hidden[deep]
        found = np.einsum("td,td->t", asked, self._words[words[deep]])
        sums = np.empty(len(deep))
        cuts = np.flatnonzero(np.diff(classes[deep])) + 1
        for first, last in zip([0, *cuts.tolist()], [*cuts.tolist(), len(deep)], strict=True):
            lo, hi = self.edges[classes[deep[first]] :][:2].tolist()
            rows = max(1, PIECE // 2 // (hi - lo))
            for a in range(first, last, rows):
                b = min(last, a + rows)
                s = self._space[: (b - a) * (hi - lo)] if (b - a) * (hi - lo) <= PIECE else np.empty((b - a) * (hi - lo), dtype=np.float32)
                s = s.reshape(b - a, hi - lo)
                np.matmul(asked[a:b], self._words[lo:hi].T, out=s)
                with np.errstate(over="ignore"):
                    total = np.exp(s, out=s).sum(axis=1)
                sums[a:b] = total
                # scores are small as a rule; the few rows whose exponentials leave the numbers' reach are summed by their largest
                for i in np.flatnonzero(~((total > 1e-25) & (total < 1e35))):
                    sums[a + i] = np.inf
        far = np.flatnonzero(~np.isfinite(sums))
        sums[far] = 1
        found = found - np.log(sums)
        for i in far.tolist():
            lo, hi = self.edges[classes[deep[i]] :][:2].tolist()
            found[i] -= log_sum((asked[i : i + 1] @ self._words[lo:hi].T).astype(np.float64))[0]
        out[deep] += found
        return out


def contexts(classes: np.ndarray, first: np.ndarray, start: int) -> np.ndarray:
    """(token, CONTEXT) the classes before every token; start where the text has none. first: each token's text's first token."""
    at = np.arange(len(classes))
    return np.stack([np.where(at - j >= first, classes[np.maximum(at - j, 0)], start) for j in range(1, CONTEXT + 1)], axis=1)


def _sums(x: np.ndarray, order: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Sums of the rows of x by runs of order. Most runs have a row or two: these are added by place, all runs at once, and the few long ones one by one."""
    out = x[order[starts]]
    left, n = np.flatnonzero(sizes > 1), 1
    while len(left) > FEW_RUNS:
        out[left] += x[order[starts[left] + n]]
        n += 1
        left = left[sizes[left] > n]
    for i in left.tolist():
        out[i] += x[order[starts[i] + n : starts[i] + sizes[i]]].sum(axis=0)
    return out


class Learner:
    """Parameters in three tables (vectors of the tokens before, one part a distance; classes; words; biases are last columns) and the steps that change them.

    unigram has the words' weights and, last, that of all others; it is the noise and the starting point.
    """

    def __init__(self, unigram: np.ndarray, seed: int = 1, tables: list[np.ndarray] | None = None, squares: list[np.ndarray] | None = None):
        """tables, squares: what to go on from, copied."""
        rng, d = np.random.default_rng(seed), DIMENSIONS
        self.noise = np.maximum(unigram, 1e-9) / np.maximum(unigram, 1e-9).sum()
        v = self.vocabulary = len(unigram) - 1
        self.edges = class_edges(v)
        self.classes = class_of(np.arange(v + 1), self.edges)
        mass = np.bincount(self.classes, self.noise)
        self.log_noise, self.ladder = np.log(mass).astype(np.float32), np.cumsum(mass)
        self.ladder_words = np.concatenate([[0.0], np.cumsum(self.noise)])
        self.log_share = np.log(self.noise / mass[self.classes]).astype(np.float32)
        draw = lambda n: rng.normal(0, 0.1, (n, d)).astype(np.float32)
        self.tables = [x.copy() for x in tables] if tables else [draw(CONTEXT * (v + 2)), np.column_stack([draw(len(mass)), self.log_noise]).astype(np.float32), np.column_stack([draw(v), self.log_share[:v]]).astype(np.float32)]
        self.squares = [x.copy() for x in squares] if squares else [np.full(len(x), 1e-2, dtype=np.float32) for x in self.tables]
        self.drawn = [np.zeros(len(x), dtype=np.float32) for x in self.tables]

    def _step(self, i: int, rows: np.ndarray, gradient: np.ndarray) -> None:
        """An adaptive step of each row by the sum of its gradients; a row has one step size."""
        # sorted by row and place at once
        both = np.sort(rows.astype(np.int64) * len(rows) + np.arange(len(rows)))
        order = both % len(rows)
        rows = both // len(rows)
        starts = np.flatnonzero(np.concatenate([[True], rows[1:] != rows[:-1]]))
        sizes = np.diff(np.append(starts, len(rows)))
        at, summed = rows[starts], _sums(gradient, order, starts, sizes)
        squares = self.squares[i][at] + np.einsum("rd,rd->r", summed, summed) / np.float32(summed.shape[1])
        self.squares[i][at] = squares
        summed *= (np.float32(-RATE) / np.sqrt(squares))[:, None]
        self.tables[i][at] += summed
        self.drawn[i][at] += sizes

    def learn(self, y: np.ndarray, before: np.ndarray, rng: np.random.Generator, batch: int = LEAST_BATCH) -> None:
        """One visit of words y after their contexts, in random order."""
        vectors, classes, words = self.tables
        d, v = DIMENSIONS, self.vocabulary
        log_noise, share = self.log_noise + np.float32(math.log(NOISE)), np.float32(math.log(CLASS_NOISE))

        def sure(x):
            np.clip(x, -30, 30, out=x)
            np.negative(x, out=x)
            np.exp(x, out=x)
            x += 1
            return np.reciprocal(x, out=x)

        order = rng.permutation(len(y))
        offsets = np.arange(CONTEXT) * (v + 2)
        for a in range(0, len(order), batch):
            part = order[a : a + batch]
            own, near = y[part], before[part] + offsets
            own_class = self.classes[own]
            hidden = vectors[near[:, 0]]
            for j in range(1, CONTEXT):
                hidden += vectors[near[:, j]]
            drawn = np.minimum(np.searchsorted(self.ladder, rng.random(NOISE)), len(self.ladder) - 1)
            t_own, t_drawn = classes[own_class], classes[drawn]
            # how far each is from being taken for noise; log(NOISE * noise) is what noise would score
            g_real = sure(np.einsum("bd,bd->b", hidden, t_own[:, :d]) + t_own[:, d] - log_noise[own_class]) - 1
            g_false = sure(hidden @ t_drawn[:, :d].T + (t_drawn[:, d] - log_noise[drawn]))
            g_hidden = g_false @ t_drawn[:, :d]
            g_hidden += g_real[:, None] * t_own[:, :d]
            g_own = np.empty((len(part), d + 1), dtype=np.float32)
            np.multiply(hidden, g_real[:, None], out=g_own[:, :d])
            g_own[:, d] = g_real
            g_noise = np.column_stack([g_false.T @ hidden, g_false.sum(axis=0)])
            deep = np.flatnonzero((own >= SHORT) & (own < v))
            if len(deep):
                w, h = own[deep], hidden[deep]
                lo, hi = self.edges[own_class[deep]], self.edges[own_class[deep] + 1]
                t_w = words[w]
                real = sure(np.einsum("bd,bd->b", h, t_w[:, :d]) + t_w[:, d] - self.log_share[w] - share) - 1
                g_deep = real[:, None] * t_w[:, :d]
                g_rows, g_sums = [w], [np.column_stack([h * real[:, None], real])]
                low, high = self.ladder_words[lo], self.ladder_words[hi]
                for _ in range(CLASS_NOISE):
                    other = np.searchsorted(self.ladder_words, low + (high - low) * rng.random(len(w)), side="right") - 1
                    other = np.clip(other, lo, hi - 1)
                    t_other = words[other]
                    false = sure(np.einsum("bd,bd->b", h, t_other[:, :d]) + t_other[:, d] - self.log_share[other] - share)
                    g_deep += false[:, None] * t_other[:, :d]
                    g_rows.append(other)
                    g_sums.append(np.column_stack([h * false[:, None], false]))
                g_hidden[deep] += g_deep
                self._step(2, np.concatenate(g_rows), np.concatenate(g_sums))
            self._step(1, np.concatenate([own_class, drawn]).astype(np.uint16), np.concatenate([g_own, g_noise]))
            for j in range(CONTEXT):
                self._step(0, near[:, j], g_hidden)

    def model(self) -> LogBilinear:
        vectors, classes, words = self.tables
        d = DIMENSIONS
        return LogBilinear(vectors.reshape(CONTEXT, -1, d).copy(), classes[:, :d].copy(), classes[:, d].copy(), words[:, :d].copy(), words[:, d].copy())


def train(texts: list[np.ndarray], unigram: np.ndarray, rounds: int = 3, seed: int = 1) -> LogBilinear:
    """A model of texts of word numbers by one learner; the last number of unigram is that of all words outside the vocabulary."""
    learner, rng = Learner(unigram, seed), np.random.default_rng(seed)
    if texts:
        y, sizes = np.concatenate(texts), [len(t) for t in texts]
        before = contexts(y, np.repeat(np.cumsum([0, *sizes[:-1]]), sizes), len(unigram))
        for _ in range(rounds):
            learner.learn(y, before, rng)
    return learner.model()


#: Table, rows' block, how often drawn, mean squares, changes of the rows as 16-bit floats.
_CHANGED = "k int, block long, drawn binary, square binary, x binary"


def _blocks(found) -> pa.RecordBatch:
    """found: (table, block, drawn, squares, changes) of blocks."""
    k, block, drawn, square, x = zip(*found, strict=True)
    packed = lambda arrays, kind: pa.array([a.astype(kind).tobytes() for a in arrays], pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(k, pa.int32()), pa.array(block, pa.int64()), packed(drawn, np.float32), packed(square, np.float32), packed(x, np.float16)], names=["k", "block", "drawn", "square", "x"])


def _unpacked(batch: pa.RecordBatch):
    """(table, block, drawn, squares, changes) of every row of a batch."""
    for k, block, drawn, square, x in zip(*(batch.column(c).to_pylist() for c in ("k", "block", "drawn", "square", "x")), strict=True):
        drawn = np.frombuffer(drawn, dtype=np.float32)
        yield k, block, drawn, np.frombuffer(square, dtype=np.float32), np.frombuffer(x, dtype=np.float16).reshape(len(drawn), -1).astype(np.float32)


def fit(training: DataFrame, id_col: str, text_col: str, number: dict[bytes, int], unigram: np.ndarray, n_tokens: int) -> LogBilinear:
    """The model of all rows of training: rounds of learners whose changed rows are averaged."""
    learner, v = Learner(unigram), len(unigram) - 1
    batch_size = max(LEAST_BATCH, min(MOST_BATCH, n_tokens // STEPS))
    visits = max(1, min(MOST_VISITS, -(-VISITED_TOKENS // max(1, n_tokens))))
    # the documents are dealt into ROUNDS parts; a round reads visits of them, so each document is read visits times
    deal = F.pmod(F.xxhash64(F.col(id_col).cast("string"), F.lit(7)), F.lit(ROUNDS))
    for n in range(ROUNDS):
        wanted = [(n + i) % ROUNDS for i in range(visits)]
        # bounded by HOT_WORDS
        sent = training.sparkSession.sparkContext.broadcast((list(number), unigram, learner.tables, learner.squares))

        def run(batches, sent=sent, n=n):
            words, unigram, tables, squares = sent.value
            number = {w: i for i, w in enumerate(words)}
            learner = Learner(unigram, tables=tables, squares=squares)  # the worker keeps the broadcast for its other tasks
            rng = np.random.default_rng([TaskContext.get().partitionId(), n])
            for whole in batches:
                for batch in slices(whole, "t"):
                    texts = [[number.get(w, v) for w in tokens(t)] for t in as_bytes(batch.column("t"))]
                    sizes = np.array([len(t) for t in texts])
                    y = np.fromiter(chain.from_iterable(texts), dtype=np.int64, count=int(sizes.sum()))
                    learner.learn(y, contexts(y, np.repeat(np.cumsum(np.append(0, sizes[:-1])), sizes), v + 1), rng, batch_size)
            for k, (table, squares, drawn, start) in enumerate(zip(learner.tables, learner.squares, learner.drawn, tables, strict=True)):
                found = [(k, a // BLOCK, drawn[a : a + BLOCK], squares[a : a + BLOCK], table[a : a + BLOCK] - start[a : a + BLOCK]) for a in range(0, len(table), BLOCK) if drawn[a : a + BLOCK].any()]
                for a in range(0, len(found), 64):
                    yield _blocks(found[a : a + 64])

        def average(batches):
            # a partition holds all of a block's copies, LEARNERS at most; they are summed as they come
            sums: dict[tuple[int, int], list[np.ndarray]] = {}
            for batch in batches:
                for k, block, drawn, square, x in _unpacked(batch):
                    parts = (drawn, square * drawn, x * drawn[:, None])
                    held = sums.get((k, block))
                    if held is None:
                        sums[k, block] = [p.astype(np.float64) for p in parts]
                    else:
                        for h, p in zip(held, parts, strict=True):
                            h += p
            for (k, block), (drawn, square, x) in sums.items():
                over = np.maximum(drawn, 1e-9)
                yield _blocks([(k, block, drawn, square / over, x / over[:, None])])

        read = training.filter(deal.isin(wanted)).select(F.col(text_col).alias("t")).coalesce(LEARNERS)
        changed = cut(read.mapInArrow(tidy(run), _CHANGED).repartition("k", "block").mapInArrow(tidy(average), _CHANGED), f"round-{n}").toArrow()
        sent.destroy()  # the round is written; the files of the broadcast would stay
        for batch in changed.to_batches():
            for k, block, drawn, square, x in _unpacked(batch):
                at = np.flatnonzero(drawn)
                learner.tables[k][block * BLOCK + at] += x[at]
                learner.squares[k][block * BLOCK + at] = square[at]
    return learner.model()


def count_tokens(texts: DataFrame, text_col: str) -> DataFrame:
    """(token, c) over all rows of texts; tasks send sums, not tokens."""

    def run(batches):
        def out(counter):
            return pa.RecordBatch.from_arrays([pa.array(counter.keys(), pa.binary()), pa.array(counter.values(), pa.int64())], names=["token", "c"])

        counter: Counter = Counter()
        for whole in batches:
            for batch in slices(whole, "t"):
                for t in as_bytes(batch.column("t")):
                    counter.update(tokens(t))
                if len(counter) > 250_000:
                    yield out(counter)
                    counter = Counter()
        if counter:
            yield out(counter)

    return texts.select(F.col(text_col).alias("t")).mapInArrow(tidy(run), "token binary, c long").groupBy("token").agg(F.sum("c").alias("c"))


def most_frequent(counts: DataFrame, most: int) -> list[tuple[bytes, int]]:
    """Tokens from some count on, most at most: the count is set by a histogram of logarithms, so nothing large is sorted or sent.

    Of the bucket at the border, whose counts are within a twentieth of each
    other, the share that there is room for is taken by the tokens' hash.
    """
    size = F.floor(16 * F.log2("c")).cast("int")
    histogram = sorted(((r["s"], r["n"]) for r in counts.groupBy(size.alias("s")).agg(F.count("*").alias("n")).collect()), reverse=True)
    least, share, total = 0, 0.0, 0
    for s, n in histogram:
        least, share, total = s, min(1.0, (most - total) / n), total + n
        if total >= most:
            break
    part = F.pmod(F.xxhash64("token"), F.lit(SHARES)) < int(share * SHARES)
    found = counts.filter((size > least) | ((size == least) & part)).collect()
    return sorted(((bytes(r["token"]), r["c"]) for r in found), key=lambda x: (-x[1], x[0]))[:most]


class Scorer:
    """Scores texts for one worker."""

    def __init__(self, model: LogBilinear | None, hot: list[tuple[bytes, int]], vocabulary: int):
        self.index = {w: i for i, (w, _) in enumerate(hot)}
        self.logs = np.append(np.log10(np.array([c for _, c in hot], dtype=np.float64) + 0.5), 0.0)
        self.model, self.vocabulary = model, vocabulary

    def texts(self, texts: list[bytes | None]):
        """Per text: tokens, hot tokens, log10 sum of (c + 0.5) over hot tokens and over those outside the vocabulary, tokens outside it, the model's log10 sum; and the tokens that aren't hot."""
        get = self.index.get
        found = [tokens(t) for t in texts]
        sizes = np.array([len(i) for i in found])
        first = np.cumsum(np.append(0, sizes[:-1]))
        flat = list(chain.from_iterable(found))
        at = np.fromiter(map(get, flat, repeat(-1)), dtype=np.int64, count=len(flat))
        rare = [Counter() for _ in found]
        missing = np.flatnonzero(at < 0)
        for i, doc in zip(missing.tolist(), np.repeat(np.arange(len(found)), sizes)[missing].tolist(), strict=True):
            rare[doc][flat[i]] += 1
        own = self.logs[at]  # -1: the 0.0 at the end
        outside = (at < 0) | (at >= self.vocabulary)
        score = np.zeros(len(at))
        if self.model:
            words = np.where(outside, self.vocabulary, at)
            before = contexts(words, np.repeat(first, sizes), self.vocabulary + 1)
            partition = self.model.log_partitions(before)
            for a in range(0, len(at), 65_536):
                s = slice(a, a + 65_536)
                score[s] = self.model.log_probability(words[s], before[s], partition[s]) / LN10
        add = lambda x: np.add.reduceat(x, first)
        return sizes, add((at >= 0).astype(np.int64)), add(own), add(np.where(outside, own, 0.0)), add(outside.astype(np.int64)), add(score), rare


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every row of docs.

    Learns from the rows whose crc32(id as text) mod 5 is not 1. A null text is
    empty and has the end mark alone. A null id is carried, never learned from
    and not held out. Repeated rows are scored each. Without training rows
    both scores are those of one unseen type, 0. An empty table gives an empty
    result. Other columns of docs are not read.
    """
    spark = docs.sparkSession
    read = docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t"))
    rest = F.crc32(F.col("i").cast("string")) % 5
    training = read.filter(rest != 1)
    counts = cut(count_tokens(training, "t"), "counts")
    total = counts.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.count("*").alias("v")).first()
    n, v = total["n"], total["v"]
    hot = most_frequent(counts, HOT_WORDS)
    vocabulary = sum(c >= LEAST_COUNT for _, c in hot)
    model = None
    inside = np.array([c for _, c in hot[:vocabulary]], dtype=np.float64)
    outside_mass = (n + 0.5 * (v + 1)) - float((inside + 0.5).sum())
    if vocabulary:
        number = {w: i for i, (w, _) in enumerate(hot[:vocabulary])}
        model = fit(training, "i", "t", number, np.append(inside + 0.5, outside_mass), n)
    sent = spark.sparkContext.broadcast((model, hot, vocabulary))  # bounded by HOT_WORDS

    def run(batches):
        scorer = Scorer(*sent.value)
        for whole in batches:
            for batch in slices(whole, "t", 4 << 20):
                *columns, rare = scorer.texts(as_bytes(batch.column("t")))
                pairs = pa.array([list(r.items()) for r in rare], pa.list_(pa.struct([("token", pa.binary()), ("k", pa.int64())])))
                yield pa.RecordBatch.from_arrays([batch.column("i"), *(pa.array(c) for c in columns), pairs], names=["i", "n_tokens", "n_hot", "hot_log", "outside_log", "n_outside", "model_log", "rare"])

    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"i {kind}, n_tokens long, n_hot long, hot_log double, outside_log double, n_outside long, model_log double, rare array<struct<token: binary, k: long>>"
    own = cut(read.mapInArrow(tidy(run), schema).withColumn("row", F.monotonically_increasing_id()), "own")  # row numbers are fixed by being written
    rare = own.select("row", F.explode("rare").alias("r")).select("row", "r.token", "r.k")
    met = rare.join(counts, "token", "left").select("row", (F.col("k") * F.log10(F.coalesce("c", F.lit(0)) + 0.5)).alias("log"), F.when(F.col("c") > 0, F.col("k")).otherwise(0).alias("known"))
    sums = met.groupBy("row").agg(F.sum("log").alias("rare_log"), F.sum("known").alias("rare_known"))
    out = own.drop("rare").join(sums, "row", "left")
    rare_log = F.coalesce("rare_log", F.lit(0.0))
    base = F.col("hot_log") + rare_log - F.col("n_tokens") * F.lit(math.log10(n + 0.5 * (v + 1)))
    full = F.col("model_log") + F.col("outside_log") + rare_log - F.col("n_outside") * F.lit(math.log10(outside_mass)) if model else base
    return out.select(
        F.col("i").alias(id_col), F.coalesce(F.crc32(F.col("i").cast("string")) % 5 == 1, F.lit(False)).alias("held_out"), "n_tokens", (F.col("n_hot") + F.coalesce("rare_known", F.lit(0))).alias("n_known"),
        F.lit(n).cast("long").alias("train_tokens"), base.alias("base_score"), full.alias("score"),
    )

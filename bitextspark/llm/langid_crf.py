"""Language ID by a linear-chain conditional random field over words.

Every word is labelled, so text that switches languages gets its words' own
labels. A word's features are its character n-grams up to four with border
marks (those with a mark are its affixes) and what a lexicon says of it;
transitions between labels are learned. Training is by gradient on runs of
words, spliced so that languages switch within a run; prediction is by
forward-backward, in batches of texts of like length. A document's language
is the one with the largest share of its words' marginals.

The classifier is fitted on a bounded sample of labelled rows (FIT_DOCS in
all, spread evenly over languages, at most FIT_WORDS words of each); every
word of every document is labelled.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, slices, tidy

FIT_DOCS = 2400
FIT_WORDS = 240
BUCKETS = 1 << 17
#: Weights of n-grams in all; with many labels each has fewer buckets.
MOST_WEIGHTS = 1 << 24
LEXICON_WORDS = 60_000
MEMO_WORDS = 200_000
UNKNOWN = "und"


@dataclass
class Crf:
    labels: list[str]
    weights: np.ndarray  # (buckets, labels)
    lexicon_weights: np.ndarray  # (labels + 1, labels): rows by what the lexicon says, the last for nothing
    transitions: np.ndarray  # (labels, labels)
    start: np.ndarray
    lexicon: dict[str, int]


def ngrams(words: list[str], buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray]:
    """(feature ids, first feature of each word) of the character n-grams of ^word$, n to four."""
    marked = "".join([f"\x02{w}\x03" for w in words])
    points = np.frombuffer(marked.encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.uint64)
    word = np.cumsum(points == 2) - 1
    ids, owner = [], []
    h = np.zeros(len(points), dtype=np.uint64)
    for n in range(1, 5):
        size = len(points) - n + 1
        if size <= 0:
            break
        h = h[:size] * np.uint64(0x9E3779B97F4A7C15) + points[n - 1 :] + np.uint64(1)
        inside = word[:size] == word[n - 1 :]
        mixed = h ^ (h >> np.uint64(29))
        mixed = (mixed * np.uint64(0xBF58476D1CE4E5B9)) >> np.uint64(40)
        ids.append((mixed % np.uint64(buckets)).astype(np.int64)[inside])
        owner.append(word[:size][inside])
    ids, owner = np.concatenate(ids), np.concatenate(owner)
    order = np.argsort(owner, kind="stable")
    return ids[order], np.searchsorted(owner[order], np.arange(len(words)))


def clean(word: str) -> str:
    return word.lower().replace("\x02", "").replace("\x03", "")


def emissions(model: Crf, words: list[str]) -> np.ndarray:
    """Scores (word, label) of distinct words."""
    low = [clean(w) for w in words]
    ids, first = ngrams(low, len(model.weights))
    size = np.diff(np.append(first, len(ids)))
    out = np.add.reduceat(model.weights[ids], first, axis=0) / np.sqrt(size)[:, None]
    none = len(model.labels)
    return out + model.lexicon_weights[np.array([model.lexicon.get(w, none) for w in low])]


def forward_backward(scores: np.ndarray, lengths: np.ndarray, transitions: np.ndarray, start: np.ndarray, expect: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Marginals (text, word, label), expected transitions (label, label; for learning, zero without expect) and expected starts of padded texts."""
    b, t, n = scores.shape
    e = np.exp(scores - scores.max(axis=2, keepdims=True))
    a = np.exp(transitions - transitions.max())
    forward, backward = np.zeros_like(e), np.ones_like(e)
    at = e[:, 0] * np.exp(start - start.max())
    forward[:, 0] = at = at / at.sum(axis=1, keepdims=True)
    for i in range(1, t):
        at = (at @ a) * e[:, i]
        at /= at.sum(axis=1, keepdims=True)
        forward[:, i] = at
    at, flat = np.ones((b, n), dtype=e.dtype), np.full(n, 1 / n, dtype=e.dtype)
    for i in range(t - 2, -1, -1):
        at = (at * e[:, i + 1]) @ a.T
        at /= at.sum(axis=1, keepdims=True)
        at[lengths <= i + 1] = flat
        backward[:, i] = at
    marginals = forward * backward
    marginals /= marginals.sum(axis=2, keepdims=True)
    inside = np.arange(t)[None, :] < lengths[:, None]
    marginals *= inside[:, :, None]
    pairs = np.zeros((n, n), dtype=e.dtype)
    if expect and t > 1:
        right = e[:, 1:] * backward[:, 1:]
        total = ((forward[:, :-1] @ a) * right).sum(axis=2)
        weight = inside[:, 1:] / np.maximum(total, 1e-300)
        pairs = ((forward[:, :-1] * weight[:, :, None]).reshape(-1, n).T @ right.reshape(-1, n)) * a
    return marginals, pairs, marginals[:, 0].sum(axis=0)


def fit(runs: list[tuple[str, list[str]]], rounds: int = 4, seed: int = 1) -> Crf:
    """A model from (label, words) runs. Sequences are spliced from pieces of runs, so labels switch within them."""
    rng = np.random.default_rng(seed)
    labels = sorted({label for label, words in runs if words})
    n = len(labels)
    number = {label: i for i, label in enumerate(labels)}
    runs = [(number[label], words) for label, words in runs if words]
    # the lexicon comes from one half of the runs, the weights from the other, so that what a lexicon entry is worth isn't overrated
    seen: dict[str, list[int]] = {}
    for label, words in runs[::2]:
        for w in words:
            seen.setdefault(clean(w), [0] * n)[label] += 1
    common = sorted(seen.items(), key=lambda x: (-sum(x[1]), x[0]))[:LEXICON_WORDS]
    lexicon = {w: int(np.argmax(c)) for w, c in common if max(c) >= 2 and max(c) >= 0.8 * sum(c)}
    pieces = []
    for label, words in runs[1::2] or runs:
        start = 0
        while start < len(words):
            size = int(rng.integers(4, 40))
            pieces.append((label, words[start : start + size]))
            start += size
    order = rng.permutation(len(pieces))
    sequences, held = [], []
    for i in order:
        held.append(pieces[i])
        if len(held) >= rng.integers(1, 6):
            sequences.append(held)
            held = []
    if held:
        sequences.append(held)

    vocabulary: dict[str, int] = {}
    texts = [(np.array([vocabulary.setdefault(clean(w), len(vocabulary)) for _, words in s for w in words]), np.array([label for label, words in s for _ in words])) for s in sequences]
    buckets = min(BUCKETS, 1 << max(10, (MOST_WEIGHTS // max(1, n)).bit_length() - 1))
    ids, first = ngrams(list(vocabulary), buckets)
    size = np.diff(np.append(first, len(ids)))
    says = np.array([lexicon.get(w, n) for w in vocabulary])
    model = Crf(labels, np.zeros((buckets, n)), np.zeros((n + 1, n)), np.zeros((n, n)), np.zeros(n), lexicon)
    params = [model.weights, model.lexicon_weights, model.transitions, model.start]
    squares = [np.full_like(p, 1e-6) for p in params]
    for _ in range(rounds):
        order = rng.permutation(len(texts))
        for k in range(0, len(order), 64):
            part = [texts[i] for i in order[k : k + 64]]
            lengths = np.array([len(w) for w, _ in part])
            words = np.unique(np.concatenate([w for w, _ in part]))
            spans = [np.arange(first[w], first[w] + size[w]) for w in words]
            flat, owner = ids[np.concatenate(spans)], np.repeat(np.arange(len(words)), size[words])
            root = np.sqrt(size[words])[:, None]
            starts = np.concatenate([[0], np.cumsum(size[words])[:-1]])
            score = np.add.reduceat(model.weights[flat], starts, axis=0) / root + model.lexicon_weights[says[words]]
            padded = np.zeros((len(part), lengths.max(), n))
            place = [np.searchsorted(words, w) for w, _ in part]
            for i, p in enumerate(place):
                padded[i, : len(p)] = score[p]
            marginals, pairs, starts_at = forward_backward(padded, lengths, model.transitions, model.start)
            error = np.zeros((len(words), n))
            for i, (p, (_, y)) in enumerate(zip(place, part, strict=True)):
                wrong = marginals[i, : len(p)].copy()
                wrong[np.arange(len(p)), y] -= 1
                np.add.at(error, p, wrong)
                np.subtract.at(pairs, (y[:-1], y[1:]), 1)
                starts_at[y[0]] -= 1
            gradients = [np.zeros_like(p) for p in params[1:]]
            np.add.at(gradients[0], says[words], error)
            gradients[1], gradients[2] = pairs, starts_at
            touched, back = np.unique(flat, return_inverse=True)
            by_gram = (error / root)[owner]
            grams = np.stack([np.bincount(back, by_gram[:, c], len(touched)) for c in range(n)], axis=1)
            squares[0][touched] += grams * grams
            model.weights[touched] -= 0.3 * grams / np.sqrt(squares[0][touched])
            for p, s, g in zip(params[1:], squares[1:], gradients, strict=True):
                s += g * g
                p -= 0.1 * g / np.sqrt(s)
    model.weights = model.weights.astype(np.float32)
    return model


def sample(docs: DataFrame, id_col: str, text_col: str, lang_col: str, total: int = FIT_DOCS) -> list[tuple[str, list[str]]]:
    """(label, words) of at most total documents, evenly by language: in each of equally many hash buckets the least hash."""
    labelled = docs.filter(F.col(lang_col).isNotNull() & F.col(id_col).isNotNull() & F.col(text_col).isNotNull())
    langs = [r[0] for r in labelled.groupBy(F.col(lang_col).alias("l")).agg(F.count("*").alias("n")).orderBy("l").collect()]  # a row a language
    if not langs:
        return []
    buckets = max(1, total // len(langs))
    key = F.xxhash64(F.col(id_col).cast("string"), F.lit(11))
    first = labelled.groupBy(F.col(lang_col).alias("l"), F.pmod(key, F.lit(buckets)).alias("b")).agg(F.min(key).alias("h"))
    chosen = [(r["l"], r["h"]) for r in first.collect()]  # FIT_DOCS rows, or one a language
    spark = docs.sparkSession
    picked = F.broadcast(spark.createDataFrame(chosen, "__l string, __h long"))
    found = labelled.join(picked, (F.col(lang_col) == F.col("__l")) & (key == F.col("__h")), "left_semi").select(F.col(lang_col).cast("string").alias("l"), key.alias("h"), F.col(text_col).alias("t"))

    def runs(batches):
        for whole in batches:
            for batch in slices(whole, "t"):
                out = []
                for h, t in zip(batch.column("h").to_pylist(), as_bytes(batch.column("t")), strict=True):
                    words = [w for w in t.decode("utf-8", "replace").split() if any(c.isalpha() for c in w)]
                    at = h % max(1, len(words) - FIT_WORDS)
                    out.append(" ".join(words[at : at + FIT_WORDS]))
                yield pa.RecordBatch.from_arrays([batch.column("l"), batch.column("h"), pa.array(out, pa.string())], names=["l", "h", "w"])

    rows = {(r["l"], r["h"]): r["w"].split() for r in found.mapInArrow(tidy(runs), "l string, h long, w string").collect()}
    # a mixed order, so that halves of the list hold all languages
    return [(label, words) for (label, _), words in sorted(rows.items(), key=lambda x: x[0][1])]


class Labeller:
    """Labels texts for one worker; emissions of distinct words are kept while memory allows."""

    def __init__(self, model: Crf):
        self.model, self.n = model, len(model.labels)
        self._forget()

    def _forget(self):
        self.known: dict[bytes, int] = {}
        self.scores = np.zeros((0, self.n), dtype=np.float32)
        self.letters = np.zeros(0, dtype=bool)

    def _learn(self, words: list[bytes]):
        if len(self.known) > MEMO_WORDS:
            self._forget()
        fresh = sorted(set(words).difference(self.known))
        for i in range(0, len(fresh), 50_000):
            part = fresh[i : i + 50_000]
            texts = [w.decode("utf-8", "replace") for w in part]
            letters = np.array([any(map(str.isalpha, w)) for w in texts])
            scores = emissions(self.model, texts).astype(np.float32)
            scores[~letters] = 0
            self.known.update(zip(part, range(len(self.scores), len(self.scores) + len(part)), strict=True))
            self.scores, self.letters = np.concatenate([self.scores, scores]), np.concatenate([self.letters, letters])

    def words(self, texts: list[bytes | None]):
        """For each text with letters: (its number, its words' marginals, which of them have letters)."""
        split = [(t or b"").split() for t in texts]
        self._learn([w for ws in split for w in ws])
        rows = [np.array([self.known[w] for w in ws], dtype=np.int64) for ws in split]
        able = sorted((len(r), i) for i, r in enumerate(rows) if len(r) and self.letters[r].any())
        at = 0
        while at < len(able):
            # texts of like length, about 2^18 words at most with their padding
            end = at + 1
            while end < len(able) and end - at < 512 and able[end][0] <= 1.25 * able[at][0] + 16 and able[end][0] * (end - at + 1) <= 1 << 18:
                end += 1
            part, at = able[at:end], end
            padded = np.zeros((len(part), part[-1][0], self.n), dtype=np.float32)
            for k, (size, i) in enumerate(part):
                padded[k, :size] = self.scores[rows[i]]
            marginals = forward_backward(padded, np.array([p[0] for p in part]), self.model.transitions.astype(np.float32), self.model.start.astype(np.float32), expect=False)[0]
            for k, (size, i) in enumerate(part):
                yield i, marginals[k, :size], self.letters[rows[i]]

    def documents(self, texts: list[bytes | None]) -> list[tuple[str, float]]:
        out = [(UNKNOWN, 0.0)] * len(texts)
        for i, marginals, letters in self.words(texts):
            share = marginals[letters].mean(axis=0, dtype=np.float64)
            best = int(share.argmax())
            out[i] = (self.model.labels[best], float(min(1.0, max(0.0, share[best]))))
        return out


def annotate(docs: DataFrame, model: Crf | None, text_col: str = "text", out: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """docs with the predicted language and its share behind its columns; names of out must be new."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # size set by BUCKETS, LEXICON_WORDS and the labels

    def run(batches):
        labeller = Labeller(sent.value) if sent.value is not None else None
        for whole in batches:
            for batch in slices(whole, text_col):
                texts = as_bytes(batch.column(text_col))
                found = labeller.documents(texts) if labeller else [(UNKNOWN, 0.0)] * len(texts)
                columns = [*batch.columns, pa.array([x[0] for x in found], pa.string()), pa.array([x[1] for x in found], pa.float64())]
                yield pa.RecordBatch.from_arrays(columns, names=[*batch.schema.names, *out])

    schema = type(docs.schema)([*docs.schema.fields]).add(out[0], "string").add(out[1], "double")
    return docs.mapInArrow(tidy(run), schema)


def learn(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Crf | None:
    """A model from labelled rows that are not held out; None where there are none."""
    runs = sample(docs.filter(F.crc32(F.col(id_col).cast("string")) % 5 != 0), id_col, text_col, lang_col)
    return fit(runs) if any(words for _, words in runs) else None


def predict(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """(id, held_out, lang_pred, score) of every row of docs.

    Learns from text and non-null lang of rows whose crc32(id as text) mod 5 is
    not 0; predictions see the text alone. Null texts and texts without a
    letter are und with score 0, as is everything where nothing can be learned
    (no labelled rows, empty table). A null id is carried, never learned from
    and not held out. Repeated rows are predicted each; ties go to the first
    label by order; other columns of docs are not read.
    """
    model = learn(docs, id_col, text_col, lang_col)
    read = docs.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text"))
    found = annotate(read, model, "__text")
    return found.select(F.col("__id").alias(id_col), F.coalesce(F.crc32(F.col("__id").cast("string")) % 5 == 0, F.lit(False)).alias("held_out"), "lang_pred", "score")


def keep(docs: DataFrame, least_share: float = 0.5, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """The rows of docs with a language that holds at least least_share of their words; und rows go."""
    found = annotate(docs, learn(docs, id_col, text_col, lang_col), text_col, ("__lang", "__share"))
    return found.filter((F.col("__lang") != UNKNOWN) & (F.col("__share") >= least_share)).drop("__lang", "__share")

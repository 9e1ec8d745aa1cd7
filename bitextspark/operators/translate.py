"""Translation models as lexical tables: training, next-token distributions, decoding, ensembles, n-best lists.

A model is a lexical table and a prior over the offset between a target
position and its source position (both by EM), how likely a translation is to
end at each difference in length, and a bigram language model of the target
side. Its size is bounded by its vocabularies (MOST_TYPES tokens a side, as
subwords have) and MOST_ENTRIES, not by the data: the tables fit into a task,
while the pairs are read by batches, so a round of EM is one pass over the
pairs whose partial sums alone are shuffled. Any number of models are trained
by the same passes (train_many), each over its own part of the pairs.
"""

from __future__ import annotations

import hashlib
import heapq
import math
from collections.abc import Callable, Mapping
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import batched, ngram
from .lexical import keep_table

#: Types a side that a model knows, the most frequent; the rest is unknown to it.
MOST_TYPES = 100_000
#: Entries of a model's tables; a source token or a context keeps as many as that leaves it.
MOST_ENTRIES = 5_000_000
UNKNOWN, END = "<unk>", ngram.END
#: Offsets between places that a model tells apart, places whose offsets are counted by themselves, differences in length.
WINDOW, PLACES, LENGTHS = 2, 64, 8
#: Source tokens on both sides of a place that training looks at.
BAND = 3
#: Tokens that the lexical part of a step leaves to the language model.
CANDIDATES = 16
NULL_SHARE, FAR_SHARE = 0.08, 0.02
#: Source and target cells that are worked on at a time.
CELLS = 1 << 20


@dataclass(frozen=True)
class ModelSpec:
    """An architecture with its sizes; the lexical stand-in maps inner size to candidates a source token and to smoothing."""

    arch: str = "base"
    layers: int = 6
    heads: int = 16
    hidden: int = 1024
    inner: int = 4096
    dropout: float = 0.1
    label_smoothing: float = 0.1
    clip: int = 16
    seed: int = 0
    iters: int = 5

    @property
    def fan_out(self) -> int:
        return max(8, round(8 * self.inner / 4096))

    @property
    def places(self) -> int:
        """Places whose offsets are counted apart: one for all where positions are relative."""
        return 1 if self.arch == "relpos" else PLACES


# The four architectures and the second wide size.
SPECS = {
    "base": ModelSpec(), "relpos": ModelSpec(arch="relpos"), "wide": ModelSpec(arch="wide", inner=8192, dropout=0.3, label_smoothing=0.2),
    "wider": ModelSpec(arch="wide", inner=15000, dropout=0.3, label_smoothing=0.2), "revsrc": ModelSpec(arch="revsrc"),
}


@dataclass(frozen=True)
class TrainPlan:
    """Budget of a training: steps, how often it is validated, which checkpoint is kept, how many are averaged."""

    steps: int = 500_000
    validate_every: int = 1000
    keep: str = "best"
    average_last: int = 10
    lr: float = 1e-4
    early_stop: bool = True


# Main training, models of iterative stages, fine-tuning.
MAIN, ITERATIVE, FINE_TUNE = TrainPlan(), TrainPlan(steps=200_000), TrainPlan(steps=10_000, lr=1e-5, early_stop=False)


@dataclass
class TranslationModel:
    """Tables of a model. prior is keyed by (place, offset), place -1 for all; ends gives the chance to end at each length less the source's (none: it ends there)."""

    spec: ModelSpec
    lex: Mapping[str, list[tuple[str, float]]]
    prior: dict[tuple[int, int], float]
    lm: Mapping[str, dict[str, float]]
    unigram: dict[str, float]
    lm_weight: float = 0.3
    model_id: str = "model"
    ends: dict[int, float] | None = None
    memo: dict = field(default_factory=dict, repr=False, compare=False)

    def view(self, src: list[str]) -> list[str]:
        return src[::-1] if self.spec.arch == "revsrc" else src

    def _choices(self, j: int, src: list[str]) -> dict[str, float]:
        """The lexical part of a step, the same for every prefix of j tokens: candidates and the end, summing to one."""
        n = len(src)
        if self.ends is None and j >= n:
            return {END: 1.0}
        end = self.ends.get(max(-LENGTHS, min(LENGTHS, j - n)), 0.5) if self.ends is not None else 0.0
        at = n - 1 - j if self.spec.arch == "revsrc" else j
        place = min(max(at, 0), self.spec.places - 1)
        view = self.view(src)
        out: dict[str, float] = {}
        for o in range(-WINDOW, WINDOW + 1):
            if 0 <= at + o < n:
                w = self.prior.get((place, o))
                if w is None:
                    w = self.prior.get((-1, o), 1e-3)
                for tok, p in self.lex.get(view[at + o], ())[: self.spec.fan_out]:
                    out[tok] = out.get(tok, 0.0) + w * p
        if not out:
            return {END: 1.0} if j >= n else {UNKNOWN: 1.0 - end, END: end} if end else {UNKNOWN: 1.0}
        if len(out) > CANDIDATES:
            out = dict(heapq.nsmallest(CANDIDATES, out.items(), key=lambda x: (-x[1], x[0])))
        mass = sum(out.values())
        out = {tok: (1 - end) * p / mass for tok, p in out.items()}
        if end:
            out[END] = end
        return out

    def next_dist(self, prefix: list[str], src: list[str]) -> dict[str, float]:
        """Probabilities of the next target token or the end; the source is given in its own order."""
        j = len(prefix)
        held = self.memo
        if held.get("src") is not src:  # a sentence's steps are shared by its hypotheses
            held.clear()
            held["src"] = src
        found = held.get(j)
        if found is None:
            found = held[j] = self._choices(j, src)
        before, eps = self.lm.get(prefix[-1] if prefix else ngram.BEGIN, {}), self.spec.label_smoothing / 10
        out, total, each = {}, 0.0, eps / len(found)
        for tok, p in found.items():
            q = 0.7 * before.get(tok, 0.0) + 0.3 * self.unigram.get(tok, 0.0) + 1e-9
            out[tok] = x = ((1 - eps) * p + each) * q**self.lm_weight
            total += x
        return {tok: p / total for tok, p in out.items()}


@dataclass
class Ensemble:
    """Members' distributions combined at each step; weights (one a member, for a sentence) turn it into a domain-weighted one."""

    members: list[TranslationModel]
    how: str = "logavg"
    eps: float = 1e-9

    def next_dist(self, prefix: list[str], src: list[str], weights: list[float] | None = None) -> dict[str, float]:
        dists = [m.next_dist(prefix, src) for m in self.members]
        if weights is not None:
            out: dict[str, float] = {}
            for d, w in zip(dists, weights, strict=True):
                for t, p in d.items():
                    out[t] = out.get(t, 0.0) + w * p
        else:
            every = set().union(*dists)
            if self.how == "max":
                out = {t: max(d.get(t, 0.0) for d in dists) for t in every}
            elif self.how == "avg":
                out = {t: sum(d.get(t, 0.0) for d in dists) / len(dists) for t in every}
            else:
                out = {t: math.exp(sum(math.log(max(d.get(t, 0.0), self.eps)) for d in dists) / len(dists)) for t in every}
        total = sum(out.values())
        return {t: p / total for t, p in out.items()}


@dataclass
class Weighted:
    """A domain-weighted ensemble of systems, each a model or an ensemble: the weights come with the sentence."""

    members: list

    def next_dist(self, prefix: list[str], src: list[str], weights: list[float] | None = None) -> dict[str, float]:
        weights = weights if weights is not None else [1 / len(self.members)] * len(self.members)
        out: dict[str, float] = {}
        for m, w in zip(self.members, weights, strict=True):
            for t, p in m.next_dist(prefix, src).items():
                out[t] = out.get(t, 0.0) + w * p
        total = sum(out.values())
        return {t: p / total for t, p in out.items()}


# ---- training


@dataclass
class Training:
    """A model to be trained: its specification, the share of the pairs that is its own (a condition; none: all) and what it starts from."""

    model_id: str
    spec: ModelSpec = SPECS["base"]
    where: Column | None = None
    start: TranslationModel | None = None
    lm_weight: float = 0.3


@dataclass
class _State:
    """What a round needs of a model: sorted keys source * types + target with probabilities, and the prior by (place, offset)."""

    spec: ModelSpec
    keys: np.ndarray | None = None
    p: np.ndarray | None = None
    prior: np.ndarray | None = None
    floor: float = 0.0  # of what isn't in the table: a start gives new words a chance


def vocabularies(pairs: DataFrame) -> tuple[list[str], list[str]]:
    """The most frequent types of both sides, MOST_TYPES at most each, the first most frequent."""
    both = F.concat(F.transform("src_toks", lambda t: F.struct(F.lit(0).alias("s"), t.alias("t"))), F.transform("tgt_toks", lambda t: F.struct(F.lit(1).alias("s"), t.alias("t"))))
    counts = pairs.select(F.explode(both).alias("x")).groupBy("x.s", "x.t").agg(F.count("*").alias("c"))
    some = lambda s: counts.filter(F.col("s") == s).orderBy(F.desc("c"), "t").limit(MOST_TYPES)
    rows = some(0).unionByName(some(1)).collect()
    of = lambda s: [r["t"] for r in sorted((r for r in rows if r["s"] == s), key=lambda r: (-r["c"], r["t"]))]
    return of(0), of(1)


def _ids(column, types: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Flat numbers of an array column's tokens (as many as types for unknown ones) and the rows' lengths."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    sizes = pc.fill_null(pc.list_value_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = pc.fill_null(pc.index_in(column.flatten(), value_set=types), len(types))
    return flat.to_numpy(zero_copy_only=False).astype(np.int64), sizes


def _expect(state: _State, src: np.ndarray, n: np.ndarray, tgt: np.ndarray, m: np.ndarray, real: np.ndarray, types: int, add: Callable) -> None:
    """Adds up the expected links of pairs, by (source, target) and by (place, offset).

    A target token is held against the empty word and the BAND source tokens
    on both sides of its own place, so work grows with a pair's length, not
    with its square.
    """
    ahead = np.cumsum(n) - n
    pair = np.repeat(np.arange(len(m)), m)
    j = np.arange(len(tgt)) - np.repeat(np.cumsum(m) - m, m)
    reverse, places, width = state.spec.arch == "revsrc", state.spec.places, 2 * BAND + 1
    step = max(1, CELLS // (width + 1))
    for lo in range(0, len(tgt), step):
        rows = slice(lo, lo + step)
        length, first, e = n[pair[rows]], ahead[pair[rows]], tgt[rows]
        at = length - 1 - j[rows] if reverse else j[rows]
        i = at[:, None] + np.arange(-BAND, BAND + 1)
        inside = (i >= 0) & (i < length[:, None])
        where = first[:, None] + (length[:, None] - 1 - i if reverse else i)
        source = np.zeros((len(e), width + 1), dtype=np.int64)  # the last column is the empty word
        if len(src):
            source[:, :width] = np.where(inside, src[np.clip(where, 0, len(src) - 1)] + 1, 0)
        key = source * (types + 1) + e[:, None]
        x = np.ones(key.shape)
        x[:, :width] *= inside
        place = np.clip(at, 0, places - 1)
        if state.keys is not None:
            found = np.minimum(np.searchsorted(state.keys, key), len(state.keys) - 1)
            x *= np.where(state.keys[found] == key, state.p[found], state.floor)
            share = np.full(x.shape, FAR_SHARE)
            share[:, BAND - WINDOW : BAND + WINDOW + 1] = state.prior[place]
            share[:, width] = NULL_SHARE
            x *= share
        total = x.sum(axis=1, keepdims=True)
        x /= np.where(total > 0, total, 1.0)
        good = x > 1e-3
        add(0, key[good], x[good])
        near = x[:, BAND - WINDOW : BAND + WINDOW + 1] * real[pair[rows], None]
        add(1, (place[:, None] * (2 * WINDOW + 1) + np.arange(2 * WINDOW + 1)).ravel(), near.ravel())


def _bigrams(tgt: np.ndarray, m: np.ndarray, types: int, add: Callable) -> None:
    """Adds up pairs of neighbours; the number types + 1 stands for both ends of a sentence."""
    mark = types + 1
    m = m[m > 0]
    starts = np.cumsum(m) - m
    before = np.empty(len(tgt), dtype=np.int64)
    before[1:] = tgt[:-1]
    if len(tgt):
        before[starts] = mark
        last = tgt[starts + m - 1]
        add(3, np.concatenate([before * (types + 2) + tgt, last * (types + 2) + mark]), np.ones(len(tgt) + len(last)))


_SUMS = "m int, kind int, a long, b long, c double"


def _round(pairs: DataFrame, states: list[_State], like: list[int], vocab: tuple[list[str], list[str]], first: bool) -> pa.Table:
    """(model, kind, a, b, c, total) of one pass: links, offsets, lengths and neighbours, the most frequent of each a only.

    like: the first model of the same pairs. Lengths and neighbours, which only
    depend on the pairs, are counted in the first pass and for that model; so
    are the links of models that start from nothing, which weigh all alike.
    """
    types = len(vocab[1])
    keep = max(64, min(256, MOST_ENTRIES // max(1, max(len(vocab[0]), types))))
    sent = pairs.sparkSession.sparkContext.broadcast((states, vocab))  # bounded by MOST_TYPES and MOST_ENTRIES

    def run(batches):
        states, vocab = sent.value
        known = tuple(pa.array(v, pa.string()) for v in vocab)
        held: dict[tuple[int, int], list] = {}
        weight = 0

        def flush():
            for (k, kind), parts in held.items():
                keys, back = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
                c = np.bincount(back, np.concatenate([p[1] for p in parts]))
                by = {0: types + 1, 1: 2 * WINDOW + 1, 2: 2 * LENGTHS + 1, 3: types + 2}[kind]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), k, np.int32)), pa.array(np.full(len(keys), kind, np.int32)), pa.array(keys // by), pa.array(keys % by), pa.array(c.astype(float))], names=["m", "kind", "a", "b", "c"])
            held.clear()

        for batch in batches:
            for a in range(0, batch.num_rows, 4096):
                part = batch.slice(a, 4096)
                for k, state in enumerate(states):
                    own = part.filter(pc.fill_null(pc.list_element(part.column("use"), k), False)) if part.num_rows else part
                    (src, n), (tgt, m) = _ids(own.column("src_toks"), known[0]), _ids(own.column("tgt_toks"), known[1])

                    def add(kind, keys, c, k=k, shared=first and like[k] != k and states[k].keys is None):
                        nonlocal weight
                        if shared and kind == 0:
                            return
                        keys, back = np.unique(keys, return_inverse=True)
                        held.setdefault((k, kind), []).append((keys, np.bincount(back, c, minlength=len(keys)) if len(keys) else np.zeros(0)))
                        weight += len(keys)

                    real = own.column("real").to_numpy(zero_copy_only=False).astype(float)
                    _expect(state, src, n, tgt, m, real, types, add)
                    if first and like[k] == k:
                        _bigrams(tgt, m, types, add)
                        add(2, np.clip(m - n, -LENGTHS, LENGTHS) + LENGTHS, real)
                if weight > 4_000_000:
                    yield from flush()
                    weight = 0
        yield from flush()

    sums = pairs.select("src_toks", "tgt_toks", "use", "real").mapInArrow(run, _SUMS)
    # one shuffle: what a row of a table needs lies in one place, and a row has at most as many entries as there are types
    sums = sums.repartition("m", "kind", "a").groupBy("m", "kind", "a", "b").agg(F.sum("c").alias("c"))
    by = Window.partitionBy("m", "kind", "a")
    ranked = sums.withColumns({"total": F.sum("c").over(by), "r": F.row_number().over(by.orderBy(F.desc("c"), "b"))})
    found = ranked.filter((F.col("r") <= keep) & ((F.col("kind") > 0) | (F.col("c") > 1e-4 * F.col("total"))))
    return found.select(*(F.col(c).cast(t) for c, t in (("m", "short"), ("kind", "byte"), ("a", "int"), ("b", "int"))), "c", "total").toArrow()


def _start(job: Training, vocab: tuple[list[str], list[str]]) -> _State:
    if job.start is None:
        return _State(job.spec)
    src, tgt = ({t: i for i, t in enumerate(v)} for v in vocab)
    found = {(src[f] + 1 if f else 0) * (len(tgt) + 1) + tgt[e]: p for f, es in job.start.lex.items() if not f or f in src for e, p in es if e in tgt}
    keys = np.array(sorted(found), dtype=np.int64)
    prior = np.full((job.spec.places, 2 * WINDOW + 1), 1e-3)
    for a in range(job.spec.places):
        for o in range(-WINDOW, WINDOW + 1):
            prior[a, o + WINDOW] = job.start.prior.get((a, o), job.start.prior.get((-1, o), 1e-3))
    return _State(job.spec, keys if len(keys) else None, np.array([found[k] for k in keys.tolist()]), prior, 0.01)


def _table(rows: list[str], a: np.ndarray, b: np.ndarray, p: np.ndarray, names: list[str], listed: bool) -> batched.Table | dict:
    """Entries in the order of a as a table; as dicts where names are met twice."""
    table = batched.Table(rows, np.searchsorted(a, np.arange(len(rows) + 1)), b.astype(np.int32), p, names, listed)
    return table if len(set(rows)) == len(rows) and len(set(names)) == len(names) else table.plain()


def _side(rows: dict[str, np.ndarray], names: list[str]) -> tuple[dict, batched.Table | dict, dict]:
    """What depends on the pairs alone: the chances to end by length, the bigram and the unigram tables. names: the target's types, unknown and end."""
    part = lambda kind: tuple(rows[c][rows["kind"] == kind] for c in ("a", "b", "c", "total"))
    _, d, n, _ = part(2)
    count = np.zeros(2 * LENGTHS + 1)
    count[d] = n
    left = np.cumsum(count[::-1])[::-1]
    ends = {k - LENGTHS: float((count[k] + 0.01) / (left[k] + 0.02)) for k in range(2 * LENGTHS + 1)}
    a, b, n, total = part(3)
    order = np.lexsort((b, a))
    a, b, n, total = a[order], b[order], n[order], total[order]
    lm = _table([*names[:-1], ngram.BEGIN], a, b, n / total, names, False)
    whole = np.bincount(b, n / (float(n.sum()) or 1.0), len(names))
    every: dict[str, float] = {}
    for y in np.flatnonzero(whole).tolist():
        every[names[y]] = every.get(names[y], 0.0) + float(whole[y])
    return ends, lm, every


def _tables(job: Training, links: dict[str, np.ndarray], offsets: dict[str, np.ndarray], side: tuple, vocab: tuple[list[str], list[str]], known: tuple[list[str], list[str]]) -> tuple[_State, Callable[[], TranslationModel]]:
    """The next round's state from a pass, and how to make a model of it. known: the empty word and the source's types; the target's, unknown and end."""
    src, tgt = vocab
    types, span = len(tgt), 2 * WINDOW + 1
    part = lambda rows, kind: tuple(rows[c][rows["kind"] == kind] for c in ("a", "b", "c", "total"))
    f, e, c, total = part(links, 0)
    order = np.lexsort((e, f))
    f, e, p = f[order].astype(np.int64), e[order].astype(np.int64), (c / total)[order]
    at, o, c1, _ = part(offsets, 1)
    prior = np.full((job.spec.places, span), 0.1)
    prior[at, o] += c1
    pooled = prior.sum(axis=0) / prior.sum()
    seen = prior.sum(axis=1)
    prior = (prior + 5 * pooled) / (prior.sum(axis=1, keepdims=True) + 5)
    state = _State(job.spec, f * (types + 1) + e if len(f) else None, p, prior * (1 - NULL_SHARE))

    def model() -> TranslationModel:
        most = 2 * job.spec.fan_out  # a decoder reads the first half; the rest is what interpolation may raise
        best = np.lexsort((e, -p, f))
        best = best[(p[best] > 1e-4) & (e[best] < types) & (f[best] <= len(src))]
        best = best[batched.runs(f[best]) < most]
        lex = _table(known[0], f[best], e[best], p[best], known[1], True)
        by = {(a, o - WINDOW): float(prior[a, o]) for a in range(job.spec.places) if seen[a] > 0.1 * span + 0.5 for o in range(span)} | {(-1, o - WINDOW): float(pooled[o]) for o in range(span)}
        ends, lm, every = side
        return TranslationModel(job.spec, lex, by, lm, every, job.lm_weight, job.model_id, ends)

    return state, model


def spread(df: DataFrame) -> DataFrame:
    """df in at least as many partitions as there are cores; one that has more stays as it is."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def train_many(pairs: DataFrame, jobs: list[Training], iters: int | None = None, each_round: Callable[[int, list[TranslationModel]], None] | None = None, made: Column | None = None) -> list[TranslationModel]:
    """Models of (src_toks, tgt_toks), all by the same passes: one over the pairs a round of EM (iters, or what a specification asks for).

    made: where pairs are synthetic. They teach words; offsets and lengths are
    counted on the others, as noise and decoding move words.
    """
    real = ~F.coalesce(made, F.lit(False)) if made is not None else F.lit(True)
    use = F.array(*(F.coalesce(j.where, F.lit(False)) if j.where is not None else F.lit(True) for j in jobs))
    pairs = keep_table(spread(pairs.select("src_toks", "tgt_toks", use.alias("use"), real.alias("real")).filter(F.exists("use", lambda x: x))), "pairs")  # read by each round
    vocab = vocabularies(pairs)
    asked = [str(j.where) for j in jobs]
    like = [asked.index(x) for x in asked]
    known = ["", *vocab[0]], [*vocab[1], UNKNOWN, END]
    states, models, sides = [_start(j, vocab) for j in jobs], [], {}
    for n in range(iters or max(j.spec.iters for j in jobs)):
        table = _round(pairs, states, like, vocab, n == 0)
        rows = []
        for k in range(len(jobs)):
            own = table.filter(pc.equal(table.column("m"), k))
            rows.append({c: own.column(c).to_numpy() for c in ("kind", "a", "b", "c", "total")})
        del table, own
        if not n:
            sides = {k: _side(rows[k], known[1]) for k in set(like)}
        shared = [like[k] if not n and states[k].keys is None else k for k in range(len(jobs))]
        found = [_tables(j, rows[shared[k]], rows[k], sides[like[k]], vocab, known) for k, j in enumerate(jobs)]
        del rows
        states, models = [s for s, _ in found], [m for _, m in found]
        if each_round:
            each_round(n + 1, [m() for m in models])
    return [m() for m in models]


def train(pairs: DataFrame, spec: ModelSpec = SPECS["base"], model_id: str = "model", lm_weight: float = 0.3) -> TranslationModel:
    return train_many(pairs, [Training(model_id, spec, lm_weight=lm_weight)])[0]


def _mixed(a: dict, b: dict, alpha: float) -> dict:
    return {k: (1 - alpha) * a.get(k, 0.0) + alpha * b.get(k, 0.0) for k in {**a, **b}}


def interpolated(general: TranslationModel, own: TranslationModel, alpha: float = 0.5, model_id: str | None = None) -> TranslationModel:
    """Tables of both, (1 - alpha) general and alpha own where both have a row; rows that only one has are taken as they are. Models only, so nothing follows the data."""
    lex = dict(general.lex)
    for f, es in own.lex.items():
        row = _mixed(dict(general.lex[f]), dict(es), alpha) if f in general.lex else dict(es)
        lex[f] = sorted(row.items(), key=lambda x: (-x[1], x[0]))
    lm = dict(general.lm)
    for ctx, row in own.lm.items():
        lm[ctx] = _mixed(general.lm[ctx], row, alpha) if ctx in general.lm else row
    mixed = lambda x, y: _mixed(x, y, alpha)
    prior = general.prior | {k: (1 - alpha) * general.prior.get(k, v) + alpha * v for k, v in own.prior.items()}
    return replace(general, memo={}, lex=lex, lm=lm, prior=prior, unigram=mixed(general.unigram, own.unigram), ends=mixed(general.ends, own.ends) if general.ends and own.ends else general.ends, model_id=model_id or f"{general.model_id}-tuned")


def fine_tune_many(models: list[TranslationModel], pairs: DataFrame, alpha: float = 0.5, wheres: list[Column | None] | None = None, ids: list[str] | None = None, iters: int = 2) -> list[TranslationModel]:
    """Continue from general models on in-domain pairs: EM from their tables, then interpolated with them. With wheres, each learns from its own pairs."""
    wheres, ids = wheres or [None] * len(models), ids or [f"{m.model_id}-tuned" for m in models]
    own = train_many(pairs, [Training(i, m.spec, w, m, m.lm_weight) for m, w, i in zip(models, wheres, ids, strict=True)], iters)
    return [interpolated(m, o, alpha, i) for m, o, i in zip(models, own, ids, strict=True)]


def fine_tune(model: TranslationModel, pairs: DataFrame, alpha: float = 0.5, model_id: str | None = None) -> TranslationModel:
    return fine_tune_many([model], pairs, alpha, ids=[model_id] if model_id else None)[0]


def averaged(models: list[TranslationModel], model_id: str | None = None) -> TranslationModel:
    """The mean of checkpoints' tables."""
    out = models[0]
    for k, m in enumerate(models[1:], 2):
        out = interpolated(out, m, 1 / k, out.model_id)
    return replace(out, memo={}, model_id=model_id or out.model_id)


# ---- decoding


def _uniform(*parts) -> float:
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:8], 16) / 2**32


def search(next_dist, src: list[str], mode: str = "beam", beam: int = 10, k: int = 10, nbest: int = 1, alpha: float = 1.4, key: str = "", seed: str = "s") -> list[tuple[list[str], float]]:
    """(tokens, score) hypotheses of one sentence, best first: greedy, beam, topk or sample.

    A hypothesis ends where its end mark is chosen, at twice its source and
    LENGTHS tokens at the latest; its score is divided by its length to the
    power alpha, so alpha decides between short and long ones.
    """
    longest = 2 * len(src) + LENGTHS
    if mode in ("greedy", "topk", "sample"):
        out, total = [], 0.0
        for i in range(longest):
            dist = sorted(next_dist(out, src).items(), key=lambda x: (-x[1], x[0]))
            if mode == "greedy":
                tok, p = dist[0]
            else:
                some = dist[:k] if mode == "topk" else dist
                at, up = _uniform(key, i, seed) * sum(p for _, p in some), 0.0
                for tok, p in some:  # noqa: B007
                    up += p
                    if up > at:
                        break
            total += math.log(max(p, 1e-300))
            if tok == END:
                break
            out.append(tok)
        return [(out, total / max(1, len(out)) ** alpha)]
    held: list[tuple[float, list[str]]] = [(0.0, [])]
    done: list[tuple[float, list[str]]] = []
    for _ in range(longest + 1):
        more = [(s + math.log(max(p, 1e-300)), h, tok) for s, h in held for tok, p in next_dist(h, src).items()]
        held = []
        for s, h, tok in heapq.nsmallest(beam, more, key=lambda x: (-x[0], x[1], x[2])):
            if tok == END:
                done.append((s / max(1, len(h)) ** alpha, h))
            else:
                held.append((s, [*h, tok]))
        if not held or len(done) >= max(beam, nbest):
            break
    done = done or [(s / max(1, len(h)) ** alpha, h) for s, h in held]
    return [(h, s) for s, h in sorted(done, key=lambda x: (-x[0], x[1]))[:nbest]]


def _found(system, part: pa.RecordBatch, how: dict) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    """(row, tokens, score) of the hypotheses of a batch's rows (i, s, and w for an ensemble's weights), in batches where the system's tables allow it."""
    if "w" not in part.schema.names and batched.members_of(system):
        searcher = batched.Searcher(system)
        sent, toks, length, score = searcher.search(*searcher.numbered(part.column("s")), part.column("i").to_pylist(), **how)
        return sent, pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(length)), pa.int32()), searcher.names.known.take(pa.array(toks))), score
    rows = []
    for n, r in enumerate(part.to_pylist()):
        step = (lambda h, s, own=r["w"]: system.next_dist(h, s, own)) if "w" in r else system.next_dist
        rows += [(n, *x) for x in search(step, r["s"], key=str(r["i"]), **how)]
    sent, toks, score = zip(*rows, strict=True) if rows else ((), (), ())
    return np.array(sent, np.int64), pa.array(toks, pa.list_(pa.string())), np.array(score, float)


def decode(model: TranslationModel | Ensemble | Weighted, df: DataFrame, mode: str = "beam", beam: int = 4, k: int = 10, nbest: int = 1, alpha: float = 1.4, seed: str = "s", id_col: str = "pair_id", src: str = "src_toks", weights: str | None = None, carry: tuple[str, ...] = ()) -> DataFrame:
    """(id, hyp_rank, hyp_toks, score, carried columns) of every row; with weights, an array column of one weight a member of the ensemble."""
    sent = df.sparkSession.sparkContext.broadcast(model)  # at most MOST_ENTRIES a member
    how = dict(mode=mode, beam=beam, k=k, nbest=nbest, alpha=alpha, seed=seed)
    kept = [f"c{x}" for x in range(len(carry))]

    def run(batches):
        for batch in batches:
            for a in range(0, batch.num_rows, batched.SENTENCES):
                part = batch.slice(a, batched.SENTENCES)
                of, toks, score = _found(sent.value, part, how)
                at = pa.array(of)
                columns = {"i": part.column("i").take(at), "hyp_rank": pa.array(batched.runs(of) + 1, pa.int32()), "hyp_toks": toks, "score": pa.array(score, pa.float64())} | {c: part.column(c).take(at) for c in kept}
                yield pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))

    read = spread(df).select(F.col(id_col).cast("string").alias("i"), F.col(src).alias("s"), *([F.col(weights).alias("w")] if weights else []), *(F.col(c).alias(k) for c, k in zip(carry, kept, strict=True)))
    types = "".join(f", {k} {read.schema[k].dataType.simpleString()}" for k in kept)
    return read.mapInArrow(run, "i string, hyp_rank int, hyp_toks array<string>, score double" + types).withColumnsRenamed({"i": id_col, **dict(zip(kept, carry, strict=True))})


def score_many(systems: dict[str, object], devs: dict[str, DataFrame], mode: str = "greedy", beam: int = 4, k: int = 10, alpha: float = 1.4, weights: str | None = None, id_col: str = "pair_id") -> dict[tuple[str, str], float]:
    """Corpus BLEU by (system, split) of systems over (id, src_toks, tgt_toks) splits: one pass decodes and counts, and only sums leave the tasks."""
    from .bleu import SUMS, from_sums

    rows = None
    for name, df in devs.items():
        part = df.select(F.col(id_col).cast("string").alias("i"), F.col("src_toks").alias("s"), F.col("tgt_toks").alias("t"), *([F.col(weights).alias("w")] if weights else []), F.lit(name).alias("split"))
        rows = part if rows is None else rows.unionByName(part)
    sent = rows.sparkSession.sparkContext.broadcast(systems)
    how = dict(mode=mode, beam=beam, k=k, alpha=alpha)

    def run(batches):
        out: dict[tuple[str, str], np.ndarray] = {}
        for batch in batches:
            for a in range(0, batch.num_rows, batched.SENTENCES):
                part = batch.slice(a, batched.SENTENCES)
                splits, kind = np.unique(np.array(part.column("split").to_pylist(), object), return_inverse=True)
                for name, system in sent.value.items():
                    _, toks, _ = _found(system, part, how)  # one a row
                    counts = batched.row_matches(toks, part.column("t"))
                    for x, split in enumerate(splits):
                        out[name, split] = out.get((name, split), 0) + counts[kind.ravel() == x].sum(axis=0)
        names = ["system", "split", *SUMS]
        yield pa.RecordBatch.from_pylist([dict(zip(names, (*key, *s.tolist()), strict=True)) for key, s in out.items()], pa.schema([("system", pa.string()), ("split", pa.string()), *((c, pa.int64()) for c in SUMS)]))

    counted = spread(rows).mapInArrow(run, "system string, split string, " + ", ".join(f"{c} long" for c in SUMS))
    found = counted.groupBy("system", "split").agg(*(F.sum(c).alias(c) for c in SUMS)).select("system", "split", F.round(from_sums(), 6).alias("bleu")).collect()  # a row a system and split
    return {(s, d): 0.0 for s in systems for d in devs} | {(r["system"], r["split"]): float(r["bleu"]) for r in found}


def translate(model, df: DataFrame, **how) -> DataFrame:
    """df with hyp, the best hypothesis as text."""
    found = decode(model, df, carry=tuple(c for c in df.columns if c != "pair_id"), **how).filter("hyp_rank = 1")
    return found.select(*df.columns, F.array_join("hyp_toks", " ").alias("hyp"))


def back_translate(reverse_model, mono: DataFrame, noise: str | None = "input", mode: str = "beam", p: float = 0.05, **how) -> DataFrame:
    """Synthetic pairs (pair_id, src_toks, tgt_toks) from target sentences (pair_id, tgt_toks), read by a target-to-source model.

    noise: input (the target is noised before it is read; the adopted scheme), output (the synthetic source is), or None.
    """
    from ..functions.noise import add_noise

    read = mono.withColumn("__in", add_noise(F.col("tgt_toks"), F.col("pair_id"), p) if noise == "input" else F.col("tgt_toks"))
    found = decode(reverse_model, read, mode=mode, src="__in", carry=("tgt_toks",), **how).filter("hyp_rank = 1").select("pair_id", F.col("hyp_toks").alias("src_toks"), "tgt_toks")
    if noise == "output":
        found = found.withColumn("src_toks", add_noise(F.col("src_toks"), F.col("pair_id"), p))
    return found.filter(F.size("src_toks") > 0)


def flip(pairs: DataFrame) -> DataFrame:
    return pairs.select("pair_id", F.col("tgt_toks").alias("src_toks"), F.col("src_toks").alias("tgt_toks"))


def distill(teacher, mono: DataFrame, reference: str | None = None, least_bleu: float | None = 28.0, **how) -> DataFrame:
    """Student data (pair_id, src_toks, tgt_toks) from source sentences, read by a teacher.

    Where a reference column is given, sentences whose translation has a
    sentence BLEU lower than least_bleu go (None: no gate).
    """
    from .bleu import gate_by_bleu

    carry = ("src_toks", reference) if reference else ("src_toks",)
    made = decode(teacher, mono, carry=carry, **how).filter("hyp_rank = 1").withColumn("hyp", F.array_join("hyp_toks", " ")).filter(F.size("hyp_toks") > 0)
    if reference:
        made = gate_by_bleu(made, "pair_id", "hyp", reference, least_bleu, "split")
    return made.select("pair_id", "src_toks", F.col("hyp_toks").alias("tgt_toks"))

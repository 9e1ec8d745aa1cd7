"""Decoding many sentences at a time: models as arrays, a step of all their hypotheses by array operations.

The results are those of translate.search sentence by sentence, but for the
last bits of sums.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Mapping

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Sentences that are decoded at a time.
SENTENCES = 1024


class Table(Mapping):
    """Rows (name: column names with values) held as arrays; a row is made when it is asked for, as a list of pairs or a dict."""

    def __init__(self, rows: list[str], start: np.ndarray, at: np.ndarray, p: np.ndarray, names: list[str], listed: bool):
        self.rows, self.start, self.at, self.p, self.names, self.listed = rows, start, at, p, names, listed
        self.index, self.held = None, {}

    def __getstate__(self):
        return self.__dict__ | {"index": None, "held": {}}

    def once(self, key, make):
        """What is made of the table once a process."""
        if key not in self.held:
            self.held[key] = make()
        return self.held[key]

    def codes(self) -> np.ndarray:
        """Row * names + column of the entries, in order, as columns of a row are."""
        return self.once("codes", lambda: np.repeat(np.arange(len(self.rows)), np.diff(self.start)) * len(self.names) + self.at)

    def plain(self) -> dict:
        """As dicts; rows of the same name are joined."""
        out: dict = {}
        for name, row in zip((x for i, x in enumerate(self.rows) if self.start[i] < self.start[i + 1]), self._rows(), strict=True):
            if self.listed:
                out.setdefault(name, []).extend(row)
            else:
                out.setdefault(name, {}).update(row)
        return out

    def _rows(self):
        for lo, hi in zip(self.start[:-1].tolist(), self.start[1:].tolist(), strict=True):
            if lo < hi:
                yield list(zip((self.names[x] for x in self.at[lo:hi].tolist()), self.p[lo:hi].tolist(), strict=True))

    def __getitem__(self, name):
        if self.index is None:
            self.index = {x: i for i, x in enumerate(self.rows)}
        i = self.index[name]
        lo, hi = int(self.start[i]), int(self.start[i + 1])
        if lo == hi:
            raise KeyError(name)
        found = zip((self.names[x] for x in self.at[lo:hi].tolist()), self.p[lo:hi].tolist(), strict=True)
        return list(found) if self.listed else dict(found)

    def __iter__(self):
        return (x for i, x in enumerate(self.rows) if self.start[i] < self.start[i + 1])

    def __len__(self):
        return int((np.diff(self.start) > 0).sum())


def within(sizes: np.ndarray) -> np.ndarray:
    """0, 1, ... within each run of these sizes."""
    return np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes)


def runs(owner: np.ndarray) -> np.ndarray:
    """Places of entries within their owners, which lie together."""
    if not len(owner):
        return owner
    cuts = np.flatnonzero(np.diff(owner, prepend=-1))
    return within(np.diff(np.append(cuts, len(owner))))


def members_of(system) -> list | None:
    """The models of a system that can be decoded in batches (tables as arrays over the same names), or None."""
    found = getattr(system, "members", [system])
    fits = lambda m: isinstance(getattr(m, "lex", None), Table) and isinstance(m.lm, Table) and m.ends is not None and m.lm.names is found[0].lm.names and m.lex.rows is found[0].lex.rows
    plain = found[0] is system or hasattr(system, "how")
    return found if plain and found and all(map(fits, found)) else None


class _Names:
    """The numbers of a vocabulary; unknown and end come last."""

    def __init__(self, names: list[str], sources: list[str]):
        self.size, self.end, self.unknown = len(names), len(names) - 1, len(names) - 2
        self.known, self.sources = pa.array(names, pa.string()), pa.array(sources, pa.string())
        self.rank = np.empty(len(names), np.int64)
        self.rank[sorted(range(len(names)), key=names.__getitem__)] = np.arange(len(names))


class _Model:
    """What steps read of a model."""

    def __init__(self, model, names: _Names):
        from . import translate

        self.spec, self.weight, self.names = model.spec, model.lm_weight, names
        self.lex = model.lex
        span, none = range(-translate.WINDOW, translate.WINDOW + 1), len(model.lex.rows)
        self.start = np.append(model.lex.start, model.lex.start[-1])  # a row without entries for sources that aren't known
        self.none = none
        self.prior = np.array([[model.prior.get((a, o), model.prior.get((-1, o), 1e-3)) for o in span] for a in range(self.spec.places)])
        self.ends = np.array([model.ends.get(d, 0.5) for d in range(-translate.LENGTHS, translate.LENGTHS + 1)])
        self.keys, self.p = model.lm.codes(), model.lm.p
        self.unigram = model.lm.once(id(model.unigram), lambda: np.array([model.unigram.get(t, 0.0) for t in model.lm.names]))

    def choices(self, j: int, n: np.ndarray, first: np.ndarray, src: np.ndarray):
        """(owner, token, p) of the lexical part of a step, as TranslationModel._choices has it, for sentences of n tokens from first on."""
        from . import translate

        window, most, end_mark, size = translate.WINDOW, translate.CANDIDATES, self.names.end, self.names.size
        end = self.ends[np.clip(j - n, -translate.LENGTHS, translate.LENGTHS) + translate.LENGTHS]
        reverse = self.spec.arch == "revsrc"
        at = n - 1 - j if reverse else np.full(len(n), j)
        i = at[:, None] + np.arange(-window, window + 1)
        inside = (i >= 0) & (i < n[:, None])
        where = first[:, None] + (n[:, None] - 1 - i if reverse else i)
        f = np.where(inside, src[np.where(inside, where, 0)] if len(src) else self.none, self.none).ravel()
        lo = self.start[f]
        many = np.minimum(self.start[f + 1] - lo, self.spec.fan_out)
        entry = np.repeat(lo, many) + within(many)
        weight = self.prior[np.clip(at, 0, self.spec.places - 1)].ravel()
        owner = np.repeat(np.repeat(np.arange(len(n)), 2 * window + 1), many)
        key, back = np.unique(owner * size + self.lex.at[entry], return_inverse=True)
        p = np.bincount(back.ravel(), np.repeat(weight, many) * self.lex.p[entry], len(key))
        owner, tok = key // size, key % size
        if len(owner) and np.bincount(owner).max() > most:
            order = np.lexsort((self.names.rank[tok], -p, owner))
            order = order[runs(owner[order]) < most]
            owner, tok, p = owner[order], tok[order], p[order]
        mass = np.bincount(owner, p, len(n))
        has = np.bincount(owner, minlength=len(n)) > 0
        p = (1 - end[owner]) * p / mass[owner]
        late = ~has & (j >= n)
        ends, lost = np.flatnonzero(late | (end > 0)), np.flatnonzero(~has & ~late)
        owner = np.concatenate([owner, ends, lost])
        tok = np.concatenate([tok, np.full(len(ends), end_mark), np.full(len(lost), self.names.unknown)])
        p = np.concatenate([p, np.where(late, 1.0, end)[ends], 1 - end[lost]])
        order = np.argsort(owner, kind="stable")
        return owner[order], tok[order], p[order]

    def steps(self, j: int, n, first, src, of: np.ndarray, before: np.ndarray):
        """(hypothesis, token, p) of the next tokens of hypotheses of sentence of with the last token before."""
        owner, tok, p = self.choices(j, n, first, src)
        many = np.bincount(owner, minlength=len(n))
        begin = np.cumsum(many) - many
        size = many[of]
        entry = np.repeat(begin[of], size) + within(size)
        hyp, tok, p = np.repeat(np.arange(len(of)), size), tok[entry], p[entry]
        key = before[hyp] * self.names.size + tok
        found = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1) if len(self.keys) else None
        bigram = np.where(self.keys[found] == key, self.p[found], 0.0) if found is not None else 0.0
        eps = self.spec.label_smoothing / 10
        x = ((1 - eps) * p + eps / size[hyp]) * (0.7 * bigram + 0.3 * self.unigram[tok] + 1e-9) ** self.weight
        return hyp, tok, x / np.bincount(hyp, x, len(of))[hyp]


#: The last vocabularies, with their numbers.
_held: dict = {}


class Searcher:
    """Decodes batches of sentences by a system; one a worker and system, as its arrays are made once."""

    def __init__(self, system):
        members = members_of(system)
        first = members[0]
        # one for all systems over the names, so their order is made once
        if _held.get("names") is not first.lm.names or _held.get("rows") is not first.lex.rows:
            _held.update(names=first.lm.names, rows=first.lex.rows, made=_Names(first.lm.names, first.lex.rows))
        self.names = _held["made"]
        self.models = [m.lex.once(id(m), lambda m=m: _Model(m, self.names)) for m in members]
        self.how, self.eps = getattr(system, "how", None), getattr(system, "eps", 0.0)

    def numbered(self, lists: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Flat numbers of sources and their lengths."""
        n = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        return pc.fill_null(pc.index_in(lists.flatten(), value_set=self.names.sources), len(self.names.sources)).to_numpy(zero_copy_only=False).astype(np.int64), n

    def _steps(self, *state):
        found = [m.steps(*state) for m in self.models]
        if self.how is None:
            return found[0]
        hyp, tok, p = (np.concatenate(x) for x in zip(*found, strict=True))
        key, back = np.unique(hyp * self.names.size + tok, return_inverse=True)
        back, members = back.ravel(), len(found)
        if self.how == "max":
            x = np.zeros(len(key))
            np.maximum.at(x, back, p)
        elif self.how == "avg":
            x = np.bincount(back, p, len(key)) / members
        else:
            x = np.exp((np.bincount(back, np.log(np.maximum(p, self.eps)), len(key)) + (members - np.bincount(back, minlength=len(key))) * math.log(self.eps)) / members)
        hyp, tok = key // self.names.size, key % self.names.size
        return hyp, tok, x / np.bincount(hyp, x)[hyp]

    def search(self, src: np.ndarray, n: np.ndarray, ids: list, mode: str = "beam", beam: int = 10, k: int = 10, nbest: int = 1, alpha: float = 1.4, seed: str = "s"):
        """(sentence, tokens' numbers, their lengths, score) of hypotheses, ordered by sentence, the best of each first."""
        first = np.cumsum(n) - n
        own = (lambda *x: self._one(*x, ids, mode, k, alpha, seed)) if mode in ("greedy", "topk", "sample") else (lambda *x: self._beam(*x, beam, nbest, alpha))
        return own(src, n, first)

    def _one(self, src, n, first, ids, mode, k, alpha, seed):
        longest, size = 2 * n + self._slack(), len(n)
        toks, length, total = np.zeros((size, int(longest.max(initial=0))), np.int64), longest.copy(), np.zeros(size)
        at, before = np.arange(size), np.full(size, self.names.size - 1)
        for j in range(toks.shape[1]):
            live = j < longest[at]
            at, before = at[live], before[live]
            if not len(at):
                break
            hyp, tok, p = self._steps(j, n[at], first[at], src, np.arange(len(at)), before)
            order = np.lexsort((self.names.rank[tok], -p, hyp))
            hyp, tok, p = hyp[order], tok[order], p[order]
            if mode == "topk":
                some = runs(hyp) < k
                hyp, tok, p = hyp[some], tok[some], p[some]
            begin = np.flatnonzero(np.diff(hyp, prepend=-1))
            if mode != "greedy":
                u = np.array([int(hashlib.md5(f"{ids[x]}:{j}:{seed}".encode()).hexdigest()[:8], 16) / 2**32 for x in at.tolist()])
                many = np.diff(np.append(begin, len(hyp)))
                upto = np.cumsum(p)
                upto -= np.repeat(upto[begin] - p[begin], many)
                over = upto <= np.repeat(u * np.bincount(hyp, p), many)
                begin = begin + np.minimum(np.bincount(hyp, over).astype(np.int64), many - 1)
            chosen = tok[begin]
            total[at] += np.log(np.maximum(p[begin], 1e-300))
            ended = chosen == self.names.end
            length[at[ended]] = j
            toks[at[~ended], j] = chosen[~ended]
            at, before = at[~ended], chosen[~ended]
        flat = toks[np.arange(toks.shape[1]) < length[:, None]]
        return np.arange(size), flat, length, total / np.maximum(1, length) ** alpha

    def _slack(self) -> int:
        from . import translate

        return translate.LENGTHS

    def _beam(self, src, n, first, beam, nbest, alpha):
        size, longest = len(n), 2 * n + self._slack()
        tok_of, parent_of, nodes = [np.zeros(1, np.int64)], [np.full(1, -1)], 1  # node 0: no token
        sent, before, score, rank, node = np.arange(size), np.full(size, self.names.size - 1), np.zeros(size), np.zeros(size, np.int64), np.zeros(size, np.int64)
        done_sent, done_score, done_node, done_len, done = [], [], [], [], np.zeros(size, np.int64)
        for j in range(int(longest.max(initial=-1)) + 1):
            live = j <= longest[sent]
            if not live.all():
                # those that never ended count as they are
                left = ~live & (done[sent] == 0)
                self._note(done_sent, done_score, done_node, done_len, sent[left], score[left] / max(1, j) ** alpha, node[left], j)
                sent, before, score, rank, node = (x[live] for x in (sent, before, score, rank, node))
            if not len(sent):
                break
            kinds, of = np.unique(sent, return_inverse=True)
            hyp, tok, p = self._steps(j, n[kinds], first[kinds], src, of.ravel(), before)
            s = score[hyp] + np.log(np.maximum(p, 1e-300))
            order = np.lexsort((self.names.rank[tok], rank[hyp], -s, sent[hyp]))
            order = order[runs(sent[hyp[order]]) < beam]
            hyp, tok, s = hyp[order], tok[order], s[order]
            ended = tok == self.names.end
            self._note(done_sent, done_score, done_node, done_len, sent[hyp[ended]], s[ended] / max(1, j) ** alpha, node[hyp[ended]], j)
            done += np.bincount(sent[hyp[ended]], minlength=size)
            keep = ~ended & (done[sent[hyp]] < max(beam, nbest))
            hyp, tok, s = hyp[keep], tok[keep], s[keep]
            by = np.lexsort((self.names.rank[tok], rank[hyp]))
            rank = np.empty(len(by), np.int64)
            rank[by] = np.arange(len(by))
            tok_of.append(tok)
            parent_of.append(node[hyp])
            sent, before, score, node = sent[hyp], tok, s, nodes + np.arange(len(hyp))
            nodes += len(hyp)
        left = done[sent] == 0
        if left.any():
            j = int(longest.max()) + 1
            self._note(done_sent, done_score, done_node, done_len, sent[left], score[left] / max(1, j) ** alpha, node[left], j)
        sent, score, node, length = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (done_sent, done_score, done_node, done_len))
        tok_of, parent_of = np.concatenate(tok_of), np.concatenate(parent_of)
        order = np.lexsort((-score, sent))
        # as many of each sentence as are asked for, and those level with the last of them
        place = runs(sent[order])
        last = order[place < nbest]
        least = np.zeros(size)
        least[sent[last]] = score[last]  # the last one of a sentence stays
        order = order[score[order] >= least[sent[order]]]
        sent, score, node, length = sent[order], score[order], node[order], length[order]
        toks = np.zeros((len(node), int(length.max(initial=0))), np.int64)
        at = node.copy()
        for back in range(toks.shape[1]):
            some = back < length
            toks[some, length[some] - 1 - back] = tok_of[at[some]]
            at[some] = parent_of[at[some]]
        # level ones by their tokens' names, a shorter one first
        shown = np.where(np.arange(toks.shape[1]) < length[:, None], self.names.rank[toks], -1)
        order = np.lexsort((*shown.T[::-1], -score, sent))
        order = order[runs(sent[order]) < nbest]
        toks, length = toks[order], length[order]
        return sent[order], toks[np.arange(toks.shape[1]) < length[:, None]], length, score[order]

    @staticmethod
    def _note(sents, scores, nodes, lengths, sent, score, node, j):
        if len(sent):
            sents.append(sent)
            scores.append(score)
            nodes.append(node)
            lengths.append(np.full(len(sent), j))


def matches(hyp: np.ndarray, n: np.ndarray, ref: np.ndarray, m: np.ndarray, orders: int = 4) -> np.ndarray:
    """bleu.SUMS of rows whose tokens are numbered alike on both sides, n of hyp and m of ref a row."""
    tok, size = np.concatenate([hyp, ref]).astype(np.int64), np.concatenate([n, m]).astype(np.int64)
    row = np.repeat(np.concatenate([np.arange(len(n)), np.arange(len(m))]), size)
    left = np.repeat(size, size) - within(size)
    ours = np.arange(len(tok)) < len(hyp)
    wide = int(tok.max(initial=0)) + 1
    gram = row * wide + tok  # a gram of a row
    out = []
    for k in range(1, orders + 1):
        place = np.flatnonzero(left >= k)
        if k > 1:
            gram = held[place] * wide + tok[place + k - 1]
        kinds, back = np.unique(gram, return_inverse=True)
        back = back.ravel()
        mine = ours[place]
        both = np.minimum(np.bincount(back[mine], minlength=len(kinds)), np.bincount(back[~mine], minlength=len(kinds)))
        of = np.zeros(len(kinds), np.int64)
        of[back] = row[place]
        out.append(np.bincount(of, both, len(n)).astype(np.int64))
        held = np.zeros(len(tok), np.int64)
        held[place] = back
    return np.stack([*out, *(np.maximum(0, n - k) for k in range(orders)), n, m], axis=1)


def row_matches(hyp: pa.Array, ref: pa.Array) -> np.ndarray:
    """bleu.SUMS of rows of token lists."""
    sizes = [pc.fill_null(pc.list_value_length(x), 0).to_numpy(zero_copy_only=False).astype(np.int64) for x in (hyp, ref)]
    flat = [x.flatten() for x in (hyp, ref)]
    codes = pa.concat_arrays(flat).dictionary_encode().indices.to_numpy()
    cut = len(flat[0])
    return matches(codes[:cut], sizes[0], codes[cut:], sizes[1])

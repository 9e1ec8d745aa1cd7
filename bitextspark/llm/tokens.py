"""Word memo over a tokenizers file: what the library gives for a word, kept while memory allows."""

from __future__ import annotations

import json
import re
import struct
from collections.abc import Callable
from functools import lru_cache

import numpy as np
from tokenizers import Tokenizer

from .common import SEPARATORS

MEMO_WORDS = 250_000
#: A control character that stands alone between words sent to the library together.
MARK = "\x01"


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


@lru_cache(2)
def load(path: str) -> Tokenizer:
    """The tokenizer of a file, without truncation and padding; read once a worker, not once a task."""
    found = Tokenizer.from_file(path)
    found.no_truncation()
    found.no_padding()
    return found


def _spec(path: str) -> dict:
    with open(path, encoding="utf-8") as f:
        return json.load(f)


@lru_cache(2)
def splits_at_space(path: str) -> bool:
    """Whether no token of this tokenizer can reach over one of SEPARATORS.

    True where white space is made a plain space by the normalizer, no part of
    the pre-tokenizer's pattern can match it, and added tokens hold none and
    strip none; then a text's ids are those of its words one after another.
    """
    spec = _spec(path)
    kinds = [x["type"] for x in (spec.get("normalizer") or {}).get("normalizers", [])]
    splits = [x for x in (spec.get("pre_tokenizer") or {}).get("pretokenizers", []) if x["type"] == "Split"]
    removed = any(x["behavior"] == "Removed" and x["invert"] and r"[^\s" in x["pattern"].get("Regex", "") for x in splits)
    plain = all(not (x["lstrip"] or x["rstrip"] or x["normalized"] or set(x["content"]) & set(SEPARATORS)) for x in spec["added_tokens"])
    return removed and plain and set(kinds) <= {"NFC", "Replace", "Lowercase"} and not spec.get("post_processor")


#: Words of letters that lower-casing and NFC treat one by one, with one mark of punctuation at most: two parts for every pattern that takes runs of letters.
PLAIN = re.compile("([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+)([.,;:!?]?)\\Z")


@lru_cache(256)
def _packer(n: int):
    return struct.Struct(f"<{n}I").pack


def packed(ids: list[int]) -> bytes:
    """ids as little-endian unsigned 32-bit integers."""
    return _packer(len(ids))(*ids)


def byte_letters() -> list[str]:
    """The letter that byte-level BPE writes for each byte: printable ones stand for themselves, the rest follow from 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(rest)) for b in range(256)]


class Memo:
    """word -> make(ids), in two generations, so a bounded number of words is held and frequent words stay.

    For tokenizers that are apart at separators only. fold() prepares a text:
    where the tokenizer lower-cases, A-Z is lowered before, so fewer words
    differ. A plain word that is new goes to the library's model directly; all
    others go through the library together, with a mark between them.
    """

    def __init__(self, path: str, make: Callable[[list[int]], object] = packed, most: int = MEMO_WORDS):
        self.library, self.make, self.most = load(path), make, most
        spec = _spec(path)
        kinds = [x["type"] for x in (spec.get("normalizer") or {}).get("normalizers", [])]
        self.folds = "Lowercase" in kinds
        self.added = [x["content"].lower().encode() for x in spec["added_tokens"]]
        self.young: dict[bytes, object] = {}
        self.old: dict[bytes, object] = {}
        alone = self._ids(MARK)
        self.mark = alone[0] if len(alone) == 1 and self._ids(f"a {MARK} b") == self._ids("a") + alone + self._ids("b") else None
        steps = (spec.get("pre_tokenizer") or {}).get("pretokenizers", [])
        by_bytes = [x for x in steps if x["type"] == "ByteLevel" and not x["add_prefix_space"] and not x["use_regex"]]
        letters = [x for x in steps if x["type"] == "Split" and re.search(r"\|\[\\p\{L\}\]\+\|.*\[\^\\s\\p\{L\}\\p\{N\}\]\+$", x["pattern"].get("Regex", ""))]
        self.direct = len(steps) == 2 and bool(by_bytes and letters) and kinds == ["NFC", "Replace", "Lowercase"]
        self.table = dict(enumerate(byte_letters()))
        self.marks = {p: self._ids(p) for p in ".,;:!?"} | {"": []}
        self.mark_bytes = {p.encode(): ids for p, ids in self.marks.items() if p}

    def _ids(self, text: str) -> list[int]:
        return self.library.encode(text, add_special_tokens=False).ids

    def fold(self, text: bytes) -> bytes:
        """text with A-Z lowered where that can't change its ids."""
        if not self.folds:
            return text
        low = text.lower()
        return text if any(x in low for x in self.added) else low

    def learn(self, words) -> dict[bytes, object]:
        """A dict with all of words; callers read it before the next call."""
        if len(self.young) > self.most:
            self.old, self.young = self.young, {}
        young, old, make, table = self.young, self.old, self.make, self.table
        together, apart = [], []
        tokenize, plain, direct, mark_of = self.library.model.tokenize, PLAIN.match, self.direct, self.mark_bytes.get
        for w in set(words).difference(young):
            if w in old:
                young[w] = old[w]
                continue
            if direct:
                # ASCII letters need no pattern: bytes.isalpha() knows no others
                if w.isalpha():
                    young[w] = make([t.id for t in tokenize(w.lower().decode())])
                    continue
                ends = mark_of(w[-1:])
                if ends is not None and w[:-1].isalpha():
                    young[w] = make([t.id for t in tokenize(w[:-1].lower().decode())] + ends)
                    continue
            text = w.decode("utf-8", "replace")
            if direct and (m := plain(text)):
                letters = m[1].lower().encode().decode("latin-1").translate(table)
                young[w] = make([t.id for t in tokenize(letters)] + self.marks[m[2]])
            elif self.mark is None or MARK in text or "<" in text:
                young[w] = make(self._ids(text))
            else:
                together.append(w)
                apart.append(text)
        for i in range(0, len(together), 512):
            part, texts = together[i : i + 512], apart[i : i + 512]
            ids = self.library.encode_batch_fast([f" {MARK} ".join(texts)], add_special_tokens=False)[0].ids
            at = np.flatnonzero(np.array(ids, dtype=np.int64) == self.mark).tolist()
            if len(at) != len(part) - 1:
                young.update((w, make(self._ids(t))) for w, t in zip(part, texts, strict=True))
                continue
            young.update(zip(part, [make(ids[a:b]) for a, b in zip([0, *(x + 1 for x in at)], [*at, len(ids)], strict=True)], strict=True))
        return young

"""BPE encoding and decoding with content-defined chunk reuse.

A rolling hash over the last bytes cuts a text where its low bits are zero, so
passages that documents share are cut alike wherever they stand. A chunk's
inside, from its first to its last separator, is encoded once and kept; what
a cut has broken, the word over a join, is put together and encoded again.
The re-encoded stretch grows over as many chunks as needed until it begins
and ends at a separator. There both sides agree exactly with the encoding of
the whole text, for tokenizers that tokens.splits_at_space() has proven apart
at separators. For all others a text is encoded as a whole.
"""

from __future__ import annotations

import hashlib
import json
import os

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import tokens
from .common import as_bytes, slices, tidy

#: A cut falls at one byte in 2 ** MASK_BITS.
MASK_BITS = 6
FACTOR = 0x9E3779B1
KEPT_CHUNKS = 60_000
SPACES = frozenset(b" \t\n\x0b\x0c\r")


def cuts(data: bytes, mask_bits: int = MASK_BITS) -> list[int]:
    """Ends of the chunks of data: where the hash of the last 16 bytes has mask_bits zero bits, and the end."""
    n = len(data)
    if n <= 16:
        return [n] if n else []
    h, factor = np.frombuffer(data, dtype=np.uint8).astype(np.uint32), np.uint32(FACTOR)
    for reach in (1, 2, 4, 8):
        more = h.copy()
        more[reach:] += h[:-reach] * factor
        h, factor = more, np.uint32((int(factor) * int(factor)) & 0xFFFFFFFF)
    ends = (np.flatnonzero((h[16:] >> np.uint32(32 - mask_bits)) == 0) + 17).tolist()
    if not ends or ends[-1] != n:
        ends.append(n)
    return ends


class ChunkCodec:
    """Encodes texts for one worker: (count of ids, ids as text, decoded text), the items of both joined by a space."""

    def __init__(self, path: str, mask_bits: int = MASK_BITS, kept: int = KEPT_CHUNKS):
        self.library = tokens.load(path)
        with open(path, encoding="utf-8") as f:
            joined_by_space = json.load(f).get("decoder") is None
        self.apart = tokens.splits_at_space(path) and joined_by_space
        self.mask_bits, self.kept = mask_bits, kept
        self.young: dict[bytes, tuple] = {}
        self.old: dict[bytes, tuple] = {}
        self.reused = self.encoded = 0
        if self.apart:
            size = max(self.library.get_vocab(with_added_tokens=True).values()) + 1
            self.names = [b"%d " % i for i in range(size)]
            self.tokens = [((self.library.id_to_token(i) or "") + " ").encode() for i in range(size)]
            self.memo = tokens.Memo(path, self._made)

    def _made(self, ids: list[int]) -> tuple[bytes, bytes]:
        """Of a word's ids; each item has its space behind it, so words are put together by joining."""
        return b"".join([self.names[i] for i in ids]), b"".join([self.tokens[i] for i in ids])

    @staticmethod
    def _parts(chunk: bytes) -> tuple[bytes | None, list[bytes], bytes]:
        """(head, words inside, tail) of a chunk; head None where no separator is inside."""
        words = chunk.split()
        head = b"" if chunk[0] in SPACES else words.pop(0)
        if len(head) == len(chunk):
            return None, [], chunk
        tail = words.pop() if words and chunk[-1] not in SPACES else b""
        return head, words, tail

    def encode(self, texts: list[bytes]) -> list[tuple[int, bytes, bytes]]:
        """Of every whole text: count of ids, decimal ids and decoded tokens."""
        if not self.apart:
            out = []
            for text in texts:
                ids = self.library.encode(text.decode("utf-8", "replace"), add_special_tokens=False).ids
                out.append((len(ids), b" ".join(b"%d" % i for i in ids), self.library.decode(ids, skip_special_tokens=False).encode()))
            return out
        # cut, and find the chunks that are new: they are encoded once, for all texts
        chunked = []
        for text in texts:
            folded, start, chunks = self.memo.fold(text), 0, []
            for end in cuts(folded, self.mask_bits):
                chunks.append(folded[start:end])
                start = end
            chunked.append(chunks)
        if len(self.young) > self.kept:
            self.old, self.young = self.young, {}
        young, wanted = self.young, {c for chunks in chunked for c in chunks}
        parts, total = {}, sum(map(len, chunked))
        for chunk in wanted.difference(young):
            if chunk in self.old:
                young[chunk] = self.old[chunk]
            else:
                parts[chunk] = self._parts(chunk)
        self.encoded += len(parts)
        self.reused += total - len(parts)
        known = self.memo.learn(set().union(*(words for _, words, _ in parts.values()))).__getitem__
        for chunk, (head, words, tail) in parts.items():
            ids, decoded = zip(*map(known, words), strict=True) if words else ((), ())
            young[chunk] = head, b"".join(ids), b"".join(decoded), tail
        # repair: the word over each join, over as many chunks as it takes
        joins = []
        for chunks in chunked:
            broken, own = b"", []
            for chunk in chunks:
                head, *_, tail = young[chunk]
                if head is None:
                    broken += tail
                else:
                    own.append(broken + head)
                    broken = tail
            own.append(broken)
            joins.append(own)
        known = self.memo.learn({w for own in joins for w in own if w})
        out = []
        for chunks, own in zip(chunked, joins, strict=True):
            ids, decoded, at = [], [], iter(own)
            for chunk in [*chunks, None]:
                head, a, b, _ = (b"", b"", b"", b"") if chunk is None else young[chunk]
                if head is None:
                    continue
                if word := next(at):
                    c, d = known[word]
                    ids.append(c)
                    decoded.append(d)
                ids.append(a)
                decoded.append(b)
            whole = b"".join(ids)
            out.append((whole.count(b" "), whole[:-1], b"".join(decoded)[:-1]))
        return out


def encode_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, mask_bits: int = MASK_BITS) -> DataFrame:
    """(id, ids as array<int>, decoded text) of every row; null texts count as empty, rows stay as often as they come."""
    return _mapped(docs, id_col, text_col, path, mask_bits, lambda x: (list(map(int, x[1].split())), x[2].decode()), [("ids", "array<int>", pa.list_(pa.int32())), ("decoded", "string", pa.string())])


def encode_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, mask_bits: int = MASK_BITS) -> DataFrame:
    """(id, n_tokens, ids_sha256, decoded_sha256) of every row, without the ids themselves.

    A null or empty text has no ids and empty decoded text. Repeated rows and
    null ids are carried; an empty table gives an empty result; other columns
    of docs are not read.
    """

    def digests(found: tuple):
        n, ids, decoded = found
        return n, hashlib.sha256(ids).hexdigest(), hashlib.sha256(decoded).hexdigest()

    return _mapped(docs, id_col, text_col, path, mask_bits, digests, [("n_tokens", "long", pa.int64()), ("ids_sha256", "string", pa.string()), ("decoded_sha256", "string", pa.string())])


def _mapped(docs: DataFrame, id_col: str, text_col: str, path: str | None, mask_bits: int, make, columns) -> DataFrame:
    path = path or tokens.default_path()
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        codec = ChunkCodec(path, mask_bits)
        for whole in batches:
            for batch in slices(whole, "t", 4 << 20):
                rows = [make(x) for x in codec.encode([t or b"" for t in as_bytes(batch.column("t"))])]
                out = [pa.array(x, c[2]) for x, c in zip(zip(*rows, strict=True), columns, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("i"), *out], names=["i", *(c[0] for c in columns)])

    schema = ", ".join([f"i {kind}", *(f"{c[0]} {c[1]}" for c in columns)])
    return docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(tidy(run, cycles=False), schema).withColumnRenamed("i", id_col)

"""Near-duplicates by SimHash and multi-index hashing.

A fingerprint is cut into segments, and there is a table for each segment,
keyed by the segment's value. A fingerprint looks up, in each table, the
Hamming ball of a small radius around its own segment; what it finds may
differ freely in the other segments, so the complete distance of every match
is verified, and most random matches fail there. By the pigeonhole principle
two fingerprints within segments * (radius + 1) - 1 bits always meet.

LINKS, two segments of 32 bits with radius one, finds all links of two bits.
SIMILAR is for similarity 0.8: 256 bits in 16 tables of 16 bits, of which a
pair needs one equal segment (certain within 15 bits; by the odds of single
bits in three of four pairs at the threshold and nearly all above 0.9). What
it proposes is checked by the shingles themselves, and what it may have missed
is found by shared rare shingles (alike_components), so no pair is lost.

A segment's value can be hot, as near copies share most of theirs. A bucket of
more than HOT fingerprints is dealt into blocks of about HOT; each pair of
blocks is one group, which verifies all its pairs and gives only a spanning
forest of their links. So no bucket meets in one task, none is capped, and the
components are those of all links. Copies share a fingerprint and are folded
before.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, cut, slices, tidy

SEED = 42
#: Fingerprints that a bucket or a block of a hot one holds.
HOT = 256
#: Hot buckets up to so many are broadcast; more are joined by shuffle.
BROADCAST_ROWS = 100_000
#: Ids of documents that go, broadcast up to so many.
KEPT_IDS = 1_000_000
#: Sets whose shingles are counted to order shingles by frequency, and frequent shingles sent to the tasks.
ORDER_SETS = 5_000
ORDER_SHINGLES = 200_000
#: Parities of a set; one of more shingles has WIDE_BITS beside them, as parities tell sets apart only up to about as many elements as bits.
PARITY_BITS, WIDE_BITS = 2048, 32_768
_ROOT = "__root"


@dataclass(frozen=True)
class Layout:
    """Words a shingle, fingerprint bits in longs, segments and the radius of the balls around them, and the most bits of a link."""

    words: int
    longs: int
    segments: int
    radius: int
    max_bits: int

    def __post_init__(self):
        if self.radius not in (0, 1) or 64 * self.longs % self.segments or self.width > 32:
            raise ValueError("segments of 32 bits at most that fill the fingerprint, and balls of radius 0 or 1")

    @property
    def width(self) -> int:
        return 64 * self.longs // self.segments

    @property
    def certain(self) -> int:
        """Bits within which no link can be missed."""
        return self.segments * (self.radius + 1) - 1

    @property
    def columns(self) -> list[str]:
        return [f"__f{i}" for i in range(self.longs)]


LINKS = Layout(words=3, longs=1, segments=2, radius=1, max_bits=2)
#: Two sets of equal size with Jaccard index 0.8 have a cosine of 8/9, and differ in 256 * acos(8/9) / pi = 38.8 bits.
SIMILAR = Layout(words=5, longs=4, segments=16, radius=0, max_bits=38)


def _mixed(h: np.ndarray, n: int) -> np.ndarray:
    """The n-th further hash of 64-bit hashes."""
    h = h + np.uint64((0x9E3779B97F4A7C15 * n) & (2**64 - 1))
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def fingerprint(text: bytes | None, words: int = LINKS.words, seed: int = SEED, longs: int = 1) -> list[int]:
    """SimHash of a text as signed 64-bit integers; zero without words. The first one is that of the shingles' XXH64."""
    return _folded(shingle_hashes(text, words, seed), longs)


def shingle_hashes(text: bytes | None, words: int, seed: int = SEED) -> np.ndarray:
    """XXH64 of a text's shingles in their order, repeats included."""
    found = text.lower().split() if text else []
    if not found:
        return np.zeros(0, dtype="<u8")
    if len(found) < words:
        shingles = [b" ".join(found)]
    else:
        shingles = map(b" ".join, zip(*(found[i:] for i in range(words)), strict=False))
    digest = xxhash.xxh64_intdigest
    return np.array([digest(x, seed) for x in shingles], dtype="<u8")


def _folded(hashes: np.ndarray, longs: int) -> list[int]:
    """SimHash of shingles' hashes."""
    if not len(hashes):
        return [0] * longs
    ones = np.zeros((longs, 64), dtype=np.int64)
    for i in range(0, len(hashes), 4096):
        part = hashes[i : i + 4096]
        for k in range(longs):
            own = _mixed(part, k) if k else part
            ones[k] += np.unpackbits(own.view(np.uint8).reshape(len(own), 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    return np.packbits(2 * ones > len(hashes), axis=1, bitorder="little").view("<i8")[:, 0].tolist()


def with_fingerprint(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", layout: Layout = LINKS) -> DataFrame:
    """(id, fingerprint columns) of every row of docs, one row each; null texts have fingerprint zero."""

    def run(batches):
        for whole in batches:
            for batch in slices(whole, "t"):
                found = [fingerprint(x, layout.words, longs=layout.longs) for x in as_bytes(batch.column("t"))]
                yield pa.RecordBatch.from_arrays([batch.column("i"), *(pa.array(c, pa.int64()) for c in zip(*found, strict=True))], names=["i", *layout.columns])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(tidy(run), f"i {kind}, " + ", ".join(f"{c} bigint" for c in layout.columns)).withColumnRenamed("i", id_col)


def hamming(a: Column, b: Column, layout: Layout = LINKS) -> Column:
    """Bits in which two fingerprints (structs of the layout's columns) differ."""
    return reduce(Column.__add__, (F.bit_count(a[c].bitwiseXOR(b[c])) for c in layout.columns))


def _shuffled(df: DataFrame) -> DataFrame:
    """df for a join by shuffle. Spark takes a table's files for its size, before a fingerprint is exploded into its balls, and would gather millions of rows on the driver to broadcast them."""
    return df.hint("merge")


def _segments(layout: Layout) -> list[Column]:
    mask = (1 << layout.width) - 1
    return [F.shiftrightunsigned(F.col(layout.columns[i * layout.width // 64]), i * layout.width % 64).bitwiseAND(F.lit(mask)) for i in range(layout.segments)]


def _forest(layout: Layout):
    """For applyInArrow: a spanning forest of the links among a group's fingerprints, as pairs of them."""
    bits = np.array([bin(i).count("1") for i in range(1 << 16)], dtype=np.uint8)

    def run(rows: pa.Table) -> pa.Table:
        x = np.unique(np.stack([rows.column(c).to_numpy() for c in layout.columns], axis=1), axis=0)
        pieces = x.view(np.uint16).reshape(len(x), -1)
        distance = np.zeros((len(x), len(x)), dtype=np.int32)
        for k in range(pieces.shape[1]):
            distance += bits[pieces[:, k][:, None] ^ pieces[:, k][None, :]]
        near = distance <= layout.max_bits
        left, out = np.ones(len(x), dtype=bool), []
        for root in range(len(x)):
            if left[root]:
                left[root] = False
                edge = [root]
                while edge:
                    i = edge.pop()
                    for j in np.flatnonzero(near[i] & left):
                        left[j] = False
                        edge.append(j)
                        out.append((i, j))
        a, b = (np.array([p[k] for p in out], dtype=int) for k in (0, 1))
        return pa.table({f"{side}{c}": x[at, k] for side, at in (("a", a), ("b", b)) for k, c in enumerate(layout.columns)})

    return run


def segment_links(fps: DataFrame, layout: Layout = LINKS) -> DataFrame:
    """Links (a, b) between distinct fingerprints (the layout's columns) of max_bits at most, as many as their components need."""
    columns = layout.columns
    own = fps.select(*columns, F.posexplode(F.array(*_segments(layout))).alias("s", "v"))
    flips = [F.lit(0).cast("long"), *(F.lit(1 << i).cast("long") for i in range(layout.width))] if layout.radius else [F.lit(0).cast("long")]
    asked = own.select(*columns, "s", F.explode(F.transform(F.array(*flips), lambda x: x.bitwiseXOR(F.col("v")))).alias("v")) if layout.radius else own
    hot = cut(own.groupBy("s", "v").agg(F.count("*").alias("n")).filter(F.col("n") > HOT).select("s", "v", F.ceil(F.col("n") / HOT).cast("int").alias("blocks")), "hot")
    some = hot.count()
    small = F.broadcast(hot) if some <= BROADCAST_ROWS else _shuffled(hot)
    cold = lambda df: df.join(small, ["s", "v"], "left_anti") if some else df
    this, other = F.struct(*columns), F.struct(*(F.col(f"o{c}").alias(c) for c in columns))
    met = cold(own).join(_shuffled(cold(asked).withColumnsRenamed({c: f"o{c}" for c in columns})), ["s", "v"]).filter((this != other) & (hamming(this, other, layout) <= layout.max_bits))
    links = met.select(F.least(this, other).alias("a"), F.greatest(this, other).alias("b"))
    if some:
        # each row goes to all pairs of blocks that have its own block in them
        rows = asked.join(small, ["s", "v"]).withColumn("k", F.pmod(F.xxhash64(F.lit("block"), *columns), F.col("blocks")).cast("int"))
        dealt = rows.select(*columns, "s", "v", "k", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("j")).withColumns({"lo": F.least("k", "j"), "hi": F.greatest("k", "j")})
        schema = ", ".join(f"{side}{c} bigint" for side in "ab" for c in columns)
        found = dealt.groupBy("s", "v", "lo", "hi").applyInArrow(_forest(layout), schema)
        side = lambda x: F.struct(*(F.col(f"{x}{c}").alias(c) for c in columns))
        links = links.unionByName(found.select(F.least(side("a"), side("b")).alias("a"), F.greatest(side("a"), side("b")).alias("b")))
    return links.distinct()


def contract(links: DataFrame, limit: int = 60) -> DataFrame:
    """(node, root) for every node of the links (a, b): equal roots within a component only.

    Each round every node moves onto its neighbour of least priority, a hash
    that changes by round, so about half of the nodes go whatever the shape.
    """
    moves, links = [], cut(links, "links-0")
    for n in range(limit):
        if links.isEmpty():
            break
        both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        rank = lambda c, n=n: F.struct(F.xxhash64(F.col(c), F.lit(n)).alias("h"), F.col(c).alias("v"))
        best = both.groupBy("a").agg(F.min(rank("b")).alias("n"))
        move = cut(best.select("a", F.when(F.col("n") < rank("a"), F.col("n.v")).otherwise(F.col("a")).alias("to")), f"moves-{n}")
        moves.append(move)
        ends = links.join(move.select("a", F.col("to").alias("x")), "a").join(move.select(F.col("a").alias("b"), F.col("to").alias("y")), "b")
        links = cut(ends.filter("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), f"links-{n + 1}")
    else:
        raise RuntimeError("the links did not contract")
    if not moves:
        return links.select(F.col("a").alias("node"), F.col("b").alias(_ROOT))
    out = moves[0].select(F.col("a").alias("node"), F.col("to").alias(_ROOT))
    for move in moves[1:]:
        out = cut(out.join(move, out[_ROOT] == move["a"], "left").select("node", F.coalesce("to", _ROOT).alias(_ROOT)), "roots")
    return out


def components(docs: DataFrame, id_col: str, text_col: str, layout: Layout) -> DataFrame:
    """(id, the layout's columns, the component's root and component_id) for every row of docs."""
    columns = layout.columns
    own = cut(with_fingerprint(docs, id_col, text_col, layout), "fingerprints")
    fps = cut(own.groupBy(*columns).agg(F.min(id_col).alias("least")), "distinct")
    roots = contract(segment_links(fps.select(*columns), layout))
    named = cut(fps.withColumn("__x", F.struct(*columns)).join(roots, F.col("__x") == roots["node"], "left").select(*columns, "least", F.coalesce(_ROOT, "__x").alias(_ROOT)), "named")
    least = cut(named.groupBy(_ROOT).agg(F.min("least").alias("component_id")), "least")
    by_fp = cut(named.join(least, _ROOT).select(*columns, _ROOT, "component_id"), "by-fingerprint")
    return own.join(by_fp, columns).select(id_col, *columns, _ROOT, "component_id")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", layout: Layout = LINKS) -> DataFrame:
    """(id, fingerprint, component_id) for every row of docs.

    component_id is the smallest id reachable over links of at most the
    layout's bits. A row without words has fingerprint zero and is linked like
    any other; repeated rows stay repeated; a null id is carried but never
    names a component (a component of null ids only has a null component_id).
    An empty table gives an empty result. Other columns of docs are not read.
    """
    found = components(docs, id_col, text_col, layout)
    digits = F.concat(*(F.lower(F.lpad(F.hex(c), 16, "0")) for c in reversed(layout.columns)))
    return found.select(id_col, digits.alias("fingerprint"), "component_id")


_DIGEST = ["__d0", "__d1"]


def _digest(kinds: np.ndarray) -> np.ndarray:
    """128 bits of a set of shingles, as two longs."""
    return np.frombuffer(xxhash.xxh3_128_digest(kinds.tobytes(), SEED), dtype="<i8")


def _parity(kinds: np.ndarray, bits: int = PARITY_BITS) -> np.ndarray:
    """For each of so many remainders whether an odd number of hashes has it, in longs. Two sets differ in at least as many elements as their parities in bits."""
    odd = np.bincount(kinds & (bits - 1), minlength=bits).astype(np.uint8) & 1
    return np.packbits(odd, bitorder="little").view("<i8")


def _with_sets(docs: DataFrame, id_col: str, text_col: str, layout: Layout) -> DataFrame:
    """(id, digest, fingerprint, shingles' number n, their parities and their hashes, the rarest first) of every row of docs."""
    sent = docs.sparkSession.sparkContext.broadcast(_frequent(docs, id_col, text_col, layout))  # ORDER_SHINGLES rows at most

    def run(batches):
        for whole in batches:
            for batch in slices(whole, "t"):
                hashes = [shingle_hashes(x, layout.words) for x in as_bytes(batch.column("t"))]
                kinds = [np.unique(h).view("<i8") for h in hashes]
                first = np.array([_digest(k) for k in kinds])
                prints = np.array([_folded(h, layout.longs) for h in hashes], dtype=np.int64)
                sizes = np.array([len(k) for k in kinds])
                wide = [_parity(k, WIDE_BITS) if len(k) > PARITY_BITS else k[:0] for k in kinds]
                kinds_by_rank = [_ranked(k, sent.value) for k in kinds]
                wides, lists = (pa.ListArray.from_arrays(np.cumsum([0, *map(len, x)]).astype(np.int32), np.concatenate(x)) for x in (wide, kinds_by_rank))
                columns = [*first.T, *prints.T, sizes]
                odd = pa.ListArray.from_arrays(np.arange(len(kinds) + 1, dtype=np.int32) * (PARITY_BITS // 64), np.concatenate([_parity(k) for k in kinds]))
                yield pa.RecordBatch.from_arrays([batch.column("i"), *(pa.array(np.ascontiguousarray(c), pa.int64()) for c in columns), odd, wides, lists], names=["i", *_DIGEST, *layout.columns, "n", "odd", "wide", "kinds"])

    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"i {kind}, " + ", ".join(f"{c} bigint" for c in [*_DIGEST, *layout.columns, "n"]) + ", odd array<bigint>, wide array<bigint>, kinds array<bigint>"
    return docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(tidy(run), schema).withColumnRenamed("i", id_col)


def _frequent(docs: DataFrame, id_col: str, text_col: str, layout: Layout) -> tuple[np.ndarray, np.ndarray]:
    """Hashes (sorted) of frequent shingles and their counts, from about ORDER_SETS distinct texts. They order the shingles, which decides how fast links are found, not which."""

    def run(batches):
        for whole in batches:
            for batch in slices(whole, "t"):
                kinds = [np.unique(shingle_hashes(x, layout.words)).view("<i8") for x in as_bytes(batch.column("t"))]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(kinds), pa.int64())], names=["k"])

    share = max(1, docs.count() // ORDER_SETS)
    some = docs.filter(F.pmod(F.xxhash64(id_col, text_col), F.lit(share)) == 0).select(F.col(text_col).alias("t")).distinct().mapInArrow(tidy(run), "k bigint")
    found = some.groupBy("k").agg(F.count("*").alias("c")).filter("c >= 3").orderBy(F.desc("c"), "k").limit(ORDER_SHINGLES).toArrow()
    keys, counts = found.column("k").to_numpy(), found.column("c").to_numpy()
    order = np.argsort(keys)
    return keys[order], counts[order]


def _ranked(kinds: np.ndarray, frequent: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The hashes of a set, the rarest first; equally rare ones by hash."""
    keys, counts = frequent
    often = np.zeros(len(kinds), dtype=np.int64)
    if len(keys):
        at = np.minimum(np.searchsorted(keys, kinds), len(keys) - 1)
        often = np.where(keys[at] == kinds, counts[at], 0)
    return kinds[np.argsort(often, kind="stable")]


def _met(sets: DataFrame) -> DataFrame:
    """(a, b), a < b: all pairs of sets (node, n, kinds by rank) that share one of their rarest shingles and may be alike by their sizes."""

    def pairs(batches):
        held = np.zeros((3, 0), dtype=np.int64)
        for batch in batches:
            # rows come by shingle; those of the last one are held until its run ends
            held = np.concatenate([held, np.stack([c.to_numpy() for c in batch.columns])], axis=1)
            k, node, n = held
            found = []
            for d in range(1, len(k)):
                at = np.flatnonzero(k[:-d] == k[d:])
                if not len(at):
                    break
                at = at[5 * np.minimum(n[at], n[at + d]) >= 4 * np.maximum(n[at], n[at + d])]
                found.append(np.stack([np.minimum(node[at], node[at + d]), np.maximum(node[at], node[at + d])], axis=1))
            if found:
                out = np.unique(np.concatenate(found), axis=0)
                for i in range(0, len(out), 100_000):
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in np.ascontiguousarray(out[i : i + 100_000].T)], names=["a", "b"])
            held = held[:, k == k[-1]] if len(k) else held

    # any set of similarity 0.8 has one of these among its own first
    first = F.slice("kinds", F.lit(1), (F.col("n") - F.ceil(4 * F.col("n") / 5) + 1).cast("int"))
    rows = sets.filter("n > 0").select(F.explode(first).alias("k"), "node", "n")
    return rows.repartition("k").sortWithinPartitions("k").mapInArrow(tidy(pairs), "a bigint, b bigint").distinct()


def _alike(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (a, b) whose sets have a Jaccard index of 0.8 at least, counted exactly."""
    # an index of 0.8 allows no more differences than a ninth of both sizes; parities bound them from below, so most pairs go before their shingles are needed
    light = lambda x: sets.select(F.col("node").alias(x), F.col("n").alias(f"n{x}"), F.col("odd").alias(f"o{x}"))
    bits = lambda x, y: F.aggregate(F.zip_with(x, y, lambda a, b: F.bit_count(a.bitwiseXOR(b))), F.lit(0), lambda a, b: a + b)
    pairs = cut(pairs.join(_shuffled(light("a")), "a").join(_shuffled(light("b")), "b").filter(9 * bits("oa", "ob") <= F.col("na") + F.col("nb")).select("a", "b", "na", "nb"), "pairs")
    # large sets are told apart by more parities: 512 longs, where their shingles are thousands
    large = (F.col("na") > PARITY_BITS) & (F.col("nb") > PARITY_BITS)
    wide = lambda x: sets.filter(F.col("n") > PARITY_BITS).select(F.col("node").alias(x), F.col("wide").alias(f"w{x}"))
    told = pairs.filter(large).join(_shuffled(wide("a")), "a").join(_shuffled(wide("b")), "b").filter(9 * bits("wa", "wb") <= F.col("na") + F.col("nb"))
    pairs = cut(pairs.filter(~large).select("a", "b").unionByName(told.select("a", "b")), "told")
    # only sets that are in a pair are shuffled
    meant = cut(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct(), "meant")
    held = sets.join(F.broadcast(meant) if meant.count() <= KEPT_IDS else _shuffled(meant), "node", "left_semi")
    side = lambda x: held.select(F.col("node").alias(x), F.col("n").alias(f"n{x}"), F.col("kinds").alias(f"k{x}"))
    met = pairs.join(_shuffled(side("a")), "a").join(_shuffled(side("b")), "b")
    return met.filter(9 * F.size(F.array_intersect("ka", "kb")) >= 4 * (F.col("na") + F.col("nb"))).select("a", "b")


def alike_components(docs: DataFrame, id_col: str, text_col: str, layout: Layout = SIMILAR) -> DataFrame:
    """(id, the digest of its shingles, the component's root and component_id) for every row of docs; links are all pairs with a Jaccard index of 0.8 at least.

    Equal sets are folded. Fingerprints propose links first; each is checked by
    the shingles. As fingerprints miss some, sets that share one of their rarest
    shingles (as any two alike must) are met, too, where they aren't yet in one
    component.
    """
    own = cut(_with_sets(docs, id_col, text_col, layout).withColumn("uid", F.monotonically_increasing_id()), "sets")
    by_digest = cut(own.groupBy(*_DIGEST).agg(F.min("uid").alias("node"), F.min(id_col).alias("least")), "distinct")
    copies = cut(own.select("uid", *_DIGEST).join(by_digest, _DIGEST).filter("uid <> node").select("uid"), "copies")
    if copies.count() <= KEPT_IDS:
        sets = own.join(F.broadcast(copies), "uid", "left_anti").withColumnRenamed("uid", "node")
    else:
        sets = cut(own.join(_shuffled(copies), "uid", "left_anti").withColumnRenamed("uid", "node"), "folded")
    prints = cut(sets.groupBy(*layout.columns).agg(F.min("node").alias("node")), "fingerprints")
    named = lambda x: prints.select(F.struct(*layout.columns).alias(f"f{x}"), F.col("node").alias(x))
    links = segment_links(prints.select(*layout.columns), layout).withColumnsRenamed({"a": "fa", "b": "fb"})
    proposed = links.join(named("a"), "fa").join(named("b"), "fb").select("a", "b")
    same = sets.select(*layout.columns, F.col("node").alias("b")).join(prints.withColumnRenamed("node", "a"), layout.columns).filter("a <> b").select("a", "b")
    links = cut(_alike(proposed.unionByName(same), sets), "links")
    roots = contract(links)
    root = lambda x: roots.select(F.col("node").alias(x), F.col(_ROOT).alias(f"r{x}"))
    others = _met(sets).join(root("a"), "a", "left").join(root("b"), "b", "left").filter(F.coalesce("ra", "a") != F.coalesce("rb", "b")).select("a", "b")
    more = cut(_alike(others, sets), "more-links")
    if not more.isEmpty():
        roots = contract(links.unionByName(more))
    rooted = cut(by_digest.join(roots, "node", "left").select(*_DIGEST, "least", F.coalesce(_ROOT, "node").alias(_ROOT)), "rooted")
    least = cut(rooted.groupBy(_ROOT).agg(F.min("least").alias("component_id")), "least")
    return own.select(id_col, *_DIGEST).join(rooted.join(least, _ROOT).drop("least"), _DIGEST).select(id_col, *_DIGEST, _ROOT, "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", layout: Layout = SIMILAR) -> DataFrame:
    """One row of docs of each group of near copies (a Jaccard index of 0.8 at least, by the layout's shingles): one that has the group's smallest id.

    Rows with a null id belong to no group that can be named and are kept. A
    repeated id may lie in several groups; of its rows in a group that it names
    the first by text stays, the others go. The ids that go meet the documents
    in a broadcast up to KEPT_IDS of them; texts are shuffled beyond it, and
    those of repeated ids.
    """
    columns = list(docs.columns)
    found = cut(alike_components(docs.select(id_col, text_col), id_col, text_col, layout).filter(F.col(id_col).isNotNull()).withColumnRenamed(id_col, "__id"), "verdicts")
    counts = cut(found.groupBy("__id").agg(F.count("*").alias("n"), F.max(F.col("__id") == F.col("component_id")).alias("named")).filter("n > 1 OR NOT named"), "others")
    gone = counts.select("__id")
    out = docs.join(F.broadcast(gone) if gone.count() <= KEPT_IDS else gone, docs[id_col] == F.col("__id"), "left_anti")
    again = counts.filter("n > 1 AND named").select("__id")
    if again.isEmpty():
        return out

    rows = docs.join(again, docs[id_col] == F.col("__id"), "left_semi").select(F.struct(*columns).alias("__row"), F.col(id_col).alias("__id"), F.coalesce(F.col(text_col), F.lit("")).alias("__t"))

    def own(batches):
        for whole in batches:
            for batch in slices(whole, "__t"):
                found = np.array([_digest(np.unique(shingle_hashes(t, layout.words))) for t in as_bytes(batch.column("__t"))])
                yield pa.RecordBatch.from_arrays([*batch.columns, *(pa.array(np.ascontiguousarray(c), pa.int64()) for c in found.T)], names=[*batch.schema.names, *_DIGEST])

    schema = type(rows.schema)([*rows.schema.fields])
    for c in _DIGEST:
        schema = schema.add(c, "long")
    rows = rows.mapInArrow(tidy(own), schema)
    named = found.filter(F.col("__id") == F.col("component_id")).select("__id", *_DIGEST, _ROOT).distinct()
    first = rows.join(named, ["__id", *_DIGEST]).groupBy("__id", _ROOT).agg(F.min_by("__row", "__t").alias("__row"))
    return out.unionByName(first.select("__row.*"))

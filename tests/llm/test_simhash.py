import random

import pytest
import xxhash

from bitextspark.llm import simhash


def plain_fingerprint(text):
    words = [w for w in "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").replace("\t", " ").replace("\n", " ").split(" ") if w]
    if not words:
        return 0
    shingles = [" ".join(words)] if len(words) < 3 else [" ".join(words[i : i + 3]) for i in range(len(words) - 2)]
    hashes = [xxhash.xxh64(s.encode(), seed=42).intdigest() for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(rows):
    """component of each row by brute force over all pairs."""
    fps = [plain_fingerprint(t) for _, t in rows]
    up = list(range(len(rows)))

    def top(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 2:
                up[top(i)] = top(j)
    groups = {}
    for i in range(len(rows)):
        groups.setdefault(top(i), []).append(rows[i][0])
    least = {k: min((x for x in v if x is not None), default=None) for k, v in groups.items()}
    return sorted(((rows[i][0], f"{fps[i]:016x}", least[top(i)]) for i in range(len(rows))), key=str)


def check(spark, rows):
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((tuple(r) for r in simhash.near_duplicates(df).collect()), key=str)
    assert got == plain_components(rows)


def test_equals_brute_force(spark):
    rng = random.Random(5)
    words = [f"w{i}" for i in range(60)]
    base = [" ".join(rng.choices(words, k=300)) for _ in range(6)]
    rows = []
    for i in range(150):
        t = rng.choice(base).split()
        for _ in range(rng.randrange(3)):
            t[rng.randrange(300)] = rng.choice(words)
        rows.append((i * 7 % 151, " ".join(t)))
    rows += [(500, None), (501, ""), (502, " \n\t"), (503, "One"), (504, "one"), (505, "a b"), (505, "a b"), (None, "a b"), (None, "only here and nowhere else"), (506, "é É x y")]
    check(spark, rows)


def chain(spark):
    # fingerprints one bit apart in a path of 40: only a method that follows links to their end gives one component
    path = [0]
    for i in range(40):
        path.append(path[-1] | 1 << i)
    return path, spark.createDataFrame([(x,) for x in path] + [((1 << 62) | (1 << 61) | (1 << 60),)], "__f0 long")


@pytest.mark.parametrize("hot", [2, 256])
def test_chain_of_links_is_one_component(spark, monkeypatch, hot):
    monkeypatch.setattr(simhash, "HOT", hot)
    path, fps = chain(spark)
    links = simhash.segment_links(fps)
    assert links.filter(simhash.hamming(links.a, links.b) > 2).isEmpty()
    roots = {r["node"]["__f0"]: r[simhash._ROOT] for r in simhash.contract(links).collect()}
    assert len({roots[x] for x in path}) == 1 and set(roots) == set(path)


@pytest.mark.parametrize("layout", [simhash.LINKS, simhash.Layout(words=3, longs=1, segments=4, radius=1, max_bits=7), simhash.Layout(words=5, longs=2, segments=8, radius=0, max_bits=7)])
@pytest.mark.parametrize("hot", [3, 256])
def test_all_links_within_the_certain_bits_are_found(spark, monkeypatch, layout, hot):
    monkeypatch.setattr(simhash, "HOT", hot)
    rng = random.Random(9)
    signed = lambda x: x - (1 << 64) * (x >> 63)
    rows = set()
    for _ in range(12):
        base = [rng.getrandbits(64) for _ in range(layout.longs)]
        for _ in range(12):
            own = list(base)
            for _ in range(rng.randrange(layout.max_bits + 2)):
                own[rng.randrange(layout.longs)] ^= 1 << rng.randrange(64)
            rows.add(tuple(map(signed, own)))
    rows = sorted(rows)
    bits = lambda a, b: sum(((x ^ y) & (2**64 - 1)).bit_count() for x, y in zip(a, b, strict=True))
    up = list(range(len(rows)))

    def top(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if bits(rows[i], rows[j]) <= layout.max_bits:
                up[top(i)] = top(j)
    links = simhash.segment_links(spark.createDataFrame(rows, ", ".join(f"{c} long" for c in layout.columns)), layout)
    assert all(bits(tuple(r["a"]), tuple(r["b"])) <= layout.max_bits for r in links.collect())
    roots = {tuple(r["node"]): tuple(r[simhash._ROOT]) for r in simhash.contract(links).collect()}
    got, want = {}, {}
    for i, x in enumerate(rows):
        got.setdefault(roots.get(x, x), set()).add(x)
        want.setdefault(top(i), set()).add(x)
    assert sorted(map(sorted, got.values())) == sorted(map(sorted, want.values()))


def test_most_pairs_at_the_similarity_are_met():
    rng, layout = random.Random(4), simhash.SIMILAR
    met = {}
    for want in (0.85, 0.93):
        for _ in range(60):
            words = [str(rng.getrandbits(40)) for _ in range(800)]
            other = list(words)
            while True:
                a, b = ({tuple(x[i : i + 5]) for i in range(796)} for x in (words, other))
                if len(a & b) / len(a | b) <= want:
                    break
                other[rng.randrange(800)] = str(rng.getrandbits(40))
            x, y = (simhash.fingerprint(" ".join(w).encode(), 5, longs=4) for w in (words, other))
            pieces = lambda f: [(v & (2**64 - 1)) >> s & 0xFFFF for v in f for s in (0, 16, 32, 48)]
            distance = sum(((p ^ q) & (2**64 - 1)).bit_count() for p, q in zip(x, y, strict=True))
            met.setdefault(want, []).append(distance <= layout.max_bits and any(p == q for p, q in zip(pieces(x), pieces(y), strict=True)))
    assert sum(met[0.85]) > 0.6 * 60 and sum(met[0.93]) > 0.93 * 60


def test_a_repeated_id_with_other_texts_keeps_its_own_groups_only(spark):
    a, b = "a " * 40 + "x y z", " ".join(f"w{i}" for i in range(60))
    c = " ".join(f"v{i}" for i in range(60))
    df = spark.createDataFrame([(2, b), (5, a), (5, b), (7, a), (7, c), (7, c)], "doc_id long, text string")
    assert sorted((r["doc_id"], r["text"]) for r in simhash.keep_one(df).collect()) == sorted([(2, b), (5, a), (7, c)])


def test_tables_that_grow_are_not_broadcast(spark, capsys):
    fps = simhash.cut(spark.range(500).selectExpr("xxhash64(id) AS __f0"), "prints")
    simhash.segment_links(fps).explain()
    plan = capsys.readouterr().out
    assert "SortMergeJoin" in plan and "Broadcast" not in plan


def test_every_pair_at_the_similarity_is_linked(spark):
    rng, rows = random.Random(9), []
    for k in range(40):
        words = [str(rng.getrandbits(40)) for _ in range(60)]
        other = list(words)
        while True:
            last = list(other)
            other[rng.randrange(60)] = str(rng.getrandbits(40))
            a, b = ({tuple(x[i : i + 5]) for i in range(56)} for x in (words, other))
            if 5 * len(a & b) < 4 * len(a | b):
                break
        # the first is just alike, the second just not
        rows += [(3 * k, " ".join(words)), (3 * k + 1, " ".join(last)), (3 * k + 2, " ".join(f"own{k}" if i == 30 else w for i, w in enumerate(other)))]
    sets = {i: {tuple(t.split()[j : j + 5]) for j in range(56)} for i, t in rows}
    near = lambda i, j: 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j])
    want = {i for i in sets if not any(near(i, j) for j in sets if j < i)}
    assert {r["doc_id"] for r in simhash.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).collect()} == want


def test_keep_one_and_empty(spark):
    rows = [(3, "a b c d", "x"), (1, "a b c d", "y"), (9, "p q r s t", None), (None, "lone", "z"), (7, None, "n"), (8, "", "n")]
    df = spark.createDataFrame(rows, "doc_id long, text string, component_id string")
    assert sorted((tuple(r) for r in simhash.keep_one(df).collect()), key=str) == sorted([(1, "a b c d", "y"), (9, "p q r s t", None), (None, "lone", "z"), (7, None, "n")], key=str)
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert simhash.near_duplicates(empty).count() == 0 and simhash.keep_one(empty).count() == 0


def test_long_text():
    t = "word " * 200_000
    assert simhash.fingerprint(t.encode())[0] == xxhash.xxh64(b"word word word", seed=42).intdigest() - (1 << 64) * (xxhash.xxh64(b"word word word", seed=42).intdigest() >> 63)


def test_long_texts_that_differ_are_told_apart_by_parities(spark, monkeypatch):
    """Of long texts with a passage in common only the near copies have their shingles compared."""
    rng = random.Random(8)
    own = lambda n: [f"w{rng.randrange(10**9)}" for _ in range(n)]
    shared = own(12)
    texts = [own(6000) + shared for _ in range(4)]
    near = list(texts[0])
    for i in range(0, 6000, 120):  # 50 words, 250 of 6,008 shingles
        near[i] = "changed"
    rows = [(i, " ".join(t)) for i, t in enumerate([*texts, near])]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    seen = {}
    plain = simhash.cut
    monkeypatch.setattr(simhash, "cut", lambda df, tag: seen.setdefault(tag, plain(df, tag)))
    sets = plain(simhash._with_sets(docs, "doc_id", "text", simhash.SIMILAR), "sets").withColumnRenamed("doc_id", "node")
    every = spark.createDataFrame([(i, j) for i in range(5) for j in range(i + 1, 5)], "a long, b long")
    assert [tuple(r) for r in simhash._alike(every, sets).collect()] == [(0, 4)]
    assert seen["pairs"].count() == 10 and [tuple(r) for r in seen["told"].collect()] == [(0, 4)]
    assert {tuple(r) for r in simhash._met(sets).collect()} >= {(0, 4)}

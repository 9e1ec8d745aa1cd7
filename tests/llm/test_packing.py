import random
import zlib

import numpy as np

from bitextspark.llm import nnls_packing as packing
from bitextspark.llm import tokens


def test_nnls_meets_its_conditions():
    rng = np.random.default_rng(1)
    for _ in range(20):
        a, y = rng.random((12, 30)), rng.random(12)
        x = packing.nnls(a, y)
        gain = a.T @ (y - a @ x)
        assert (x >= 0).all() and (gain < 1e-6).all() and np.abs(gain[x > 1e-9]).max(initial=0) < 1e-6


def test_plan_holds_the_histogram():
    rng = random.Random(4)
    for _ in range(5):
        histogram = {b: rng.randrange(1, 400) for b in rng.sample(range(1, 65), 40)}
        got = {}
        for c, n in packing.plan(histogram, 64):
            assert n > 0 and sum(c) <= 64
            for b in c:
                got[b] = got.get(b, 0) + n
        assert got == histogram


def check(spark, rows, most_padding):
    df = spark.createDataFrame(rows, "doc_id long, text string, offset string, part int")
    out = packing.pack(df).collect()
    library = tokens.load(tokens.default_path())
    want = sorted((d, tuple([*library.encode(t or "", add_special_tokens=False).ids, 2])) for d, t, *_ in rows if d is not None)
    by_doc = {}
    for r in out:
        if r["doc_id"] is not None:
            by_doc.setdefault(r["doc_id"], []).append(r)
    for d, ids in want:
        if sum(x[0] == d for x in want) > 1:
            continue
        at = 0
        for r in sorted(by_doc[d], key=lambda r: r["start"]):
            part = np.array(ids[at : at + r["length"]], dtype="<u4").tobytes()
            assert r["start"] == at and r["ids_crc32"] == zlib.crc32(part) and r["doc_tokens"] == len(ids)
            at += r["length"]
        assert at == len(ids)
    assert sum(r["length"] for r in out if r["doc_id"] is not None) == sum(len(x) for _, x in want)
    sequences = {}
    for r in out:
        sequences.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert sorted(sequences) == list(range(len(sequences)))
    for parts in sequences.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= packing.WINDOW
    assert 1 - sum(r["length"] for r in out) / (packing.WINDOW * len(sequences)) <= most_padding


def test_pack(spark):
    rng = random.Random(2)
    rows = [(i, " ".join(rng.choices(["word", "other", "thing", "zq"], k=int(rng.lognormvariate(5.5, 1.2)) + 1)), "x", 1) for i in range(400)]
    rows += [(1000, None, None, None), (1001, "", "o", 0), (None, "a b", "o", 0), (1002, "same", "o", 0), (1002, "same", "o", 0), (1003, "long one " * 9000, "o", 0)]
    check(spark, rows, 0.08)
    check(spark, [(1, None, None, None)], 1)
    assert packing.pack(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_given_documents_with_little_padding(spark):
    out = packing.pack(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).selectExpr("sum(length) n", "count(distinct sequence_id) s").first()
    assert out["n"] / (out["s"] * packing.WINDOW) > 0.97

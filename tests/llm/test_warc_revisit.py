import random

import pytest

from bitextspark.llm import warc_revisit as warc


@pytest.mark.parametrize("url, want", [
    ("HTTP://User@Example.COM:80/a?b=2&a=1&utm_source=x#frag", "http://example.com/a?a=1&b=2"), ("https://x.org", "https://x.org/"), ("https://x.org:443/p?ref=1", "https://x.org/p"),
    ("http://x.org:443/", "http://x.org:443/"), ("//x.org/y", "//x.org/y"), (" odd ", "odd"), (None, None), ("http://x/?Ref=a&reference=1", "http://x/?reference=1"),
])
def test_canonical_url(spark, url, want):
    assert spark.createDataFrame([(url,)], "u string").select(warc.canonical_url(warc.F.col("u"))).first()[0] == want


def plain(rows):
    out = []
    for rid, url, ts, status, headers in rows:
        if status != 304:
            continue
        ok = [r for r in rows if r[3] == 200 and r[0] is not None and r[1] is not None and r[1] == url and r[2] is not None and ts is not None and rid is not None and r[2] < ts]
        if not ok:
            out.append((rid, ts, None, "missing", None))
            continue
        best = max(ok, key=lambda r: (r[2], r[0]))
        a = {k.lower(): v for k, v in (best[4] or {}).items()}
        b = {k.lower(): v for k, v in (headers or {}).items()}
        weak = lambda x: x.removeprefix("W/")
        same = weak(a["etag"]) == weak(b["etag"]) if "etag" in a and "etag" in b else a["last-modified"] == b["last-modified"] if "last-modified" in a and "last-modified" in b else None
        state = "unchecked" if same is None else "resolved" if same else "mismatch"
        merged = None if state == "mismatch" else tuple(sorted((a | {k: v for k, v in b.items() if k not in warc.KEPT_HEADERS}).items()))
        out.append((rid, ts, best[0], state, merged))
    return sorted(out, key=str)


def test_equals_brute_force(spark):
    rng = random.Random(8)
    rows = []
    for i in range(500):
        h = {}
        if rng.random() < 0.7:
            h[rng.choice(["ETag", "etag"])] = rng.choice(['"a"', 'W/"a"', '"b"'])
        if rng.random() < 0.5:
            h["Last-Modified"] = rng.choice("xy")
        if rng.random() < 0.5:
            h["Content-Length"] = str(i)
        url = "http://hot/" if i % 3 == 0 else f"http://h/{rng.randrange(30)}"
        rows.append((i, url, rng.randrange(200), rng.choice([200, 200, 304, 304, 304, 404]), h))
    rows += [(1000, None, 5, 304, {}), (1001, "http://hot/", None, 304, None), (None, "http://hot/", 500, 304, {}), (1002, "http://n/", 1, 200, None), (1003, "http://n/", 2, 304, None), (None, "http://n/", 3, 200, {}), (1004, None, 1, 200, {}), (1003, "http://n/", 2, 304, None)]
    df = spark.createDataFrame(rows, warc.RECORD).withColumn("u", warc.F.lit(1)).withColumn("b", warc.F.lit(1))
    got = sorted(((r["record_id"], r["ts"], r["response_id"], r["state"], None if r["headers"] is None else tuple(sorted(r["headers"].items()))) for r in warc.resolve(df).collect()), key=str)
    assert got == plain(rows)
    assert warc.resolve(df.limit(0)).count() == 0


def test_read_warc(spark, tmp_path):
    import gzip

    def record(kind, url, block, version="1.0"):
        return f"WARC/{version}\r\nWARC-Type: {kind}\r\nWARC-Target-URI: {url}\r\nWARC-Date: 2020-01-01T00:00:00Z\r\nContent-Length: {len(block)}\r\n\r\n".encode() + block + b"\r\n\r\n"

    inner = b"<p>one\r\n\r\nWARC/1.0\r\nWARC-Type: response\r\nContent-Length: 3\r\n\r\ntwo \xff\xfe</p>"
    big = bytes(range(256)) * 20_000
    records = [
        record("warcinfo", "", b"software: x"), record("response", "http://a/", b"HTTP/1.1 200 OK\r\nETag: \"1\"\r\nSet-Cookie: a\r\nSet-Cookie: b\r\n\r\n" + inner, "1.1"),
        record("revisit", "http://a/", b"HTTP/1.1 304 Not Modified\r\nETag: \"1\"\r\n\r\n"), record("resource", "http://b/", big),
    ]
    want = [("warcinfo", "", None, b"software: x"), ("response", "http://a/", 200, inner), ("revisit", "http://a/", 304, b""), ("resource", "http://b/", None, big)]
    (tmp_path / "plain.warc").write_bytes(b"".join(records))
    (tmp_path / "packed.warc.gz").write_bytes(b"".join(map(gzip.compress, records)))
    for name in ("plain.warc", "packed.warc.gz"):
        got = warc.read_warc(spark, str(tmp_path / name)).collect()
        assert [(r["kind"], r["url"], r["status"], bytes(r["payload"])) for r in got] == want
        assert got[1]["headers"] == {"etag": '"1"', "set-cookie": "a"} and len({r["record_id"] for r in got}) == 4
    both = warc.read_warc(spark, str(tmp_path))
    assert sorted(r["record_id"] for r in both.collect()) == sorted(r["record_id"] for r in warc.read_warc(spark, str(tmp_path)).collect()) and both.count() == 8

"""Not-modified revisits of web captures, resolved by an as-of join.

A revisit (a 304 answer) has no content of its own: it stands for the latest
earlier full response of its canonical URL. The as-of join cuts time into
slices: within a (URL, slice) a window finds the latest response before a
revisit; from slice to slice only each slice's last response is carried. So a
URL with a third of all captures is spread over the slices.
"""

from __future__ import annotations

import re
import zlib

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import tidy

# Headers of a stored response that a 304 doesn't replace.
KEPT_HEADERS = ("content-encoding", "content-length", "content-md5", "content-range", "content-type", "transfer-encoding", "connection", "keep-alive", "proxy-authenticate", "te", "trailer", "upgrade")
# Query parameters without meaning for content.
TRACKING = "utm_[a-z]+|ref|fbclid|gclid|sessionid"
LEAST_SLICES, SLICE_ROWS = 64, 200_000
RECORD = "record_id long, url string, ts long, status int, headers map<string,string>"


def canonical_url(url: Column) -> Column:
    """Lower-case scheme and host without user and default port, path (/ where empty), sorted query without tracking; no fragment. Null stays null."""
    pattern = r"^\s*(?:([A-Za-z][A-Za-z0-9+.-]*):)?//(?:[^/?#@]*@)?([^/?#:]*)(:[0-9]+)?([^?#]*)(?:\?([^#]*))?(?:#.*)?$"
    part = lambda i: F.regexp_extract(url, pattern, i)
    scheme = F.lower(part(1))
    default = F.when(scheme == "https", ":443").otherwise(":80")
    port = F.when(part(3) == default, "").otherwise(part(3))
    query = F.array_sort(F.filter(F.split(part(5), "&"), lambda p: (p != "") & ~p.rlike(rf"^(?i)(?:{TRACKING})(?:=|$)")))
    full = F.concat(scheme, F.when(scheme == "", "").otherwise(":"), F.lit("//"), F.lower(part(2)), port, F.when(part(4) == "", "/").otherwise(part(4)), F.when(F.size(query) > 0, F.lit("?")).otherwise(""), F.array_join(query, "&"))
    return F.when(url.isNull(), None).when(url.rlike(pattern), full).otherwise(F.trim(url))


def _header(headers: Column, name: str) -> Column:
    found = F.map_values(F.map_filter(headers, lambda k, _: F.lower(k) == name))
    return F.get(found, F.lit(0))


def merge_headers(stored: Column, new: Column) -> Column:
    """The stored response's headers with those of the 304 in their place or beside them, but for KEPT_HEADERS; names in lower case."""
    lower = lambda m: F.map_from_entries(F.array_sort(F.map_entries(F.transform_keys(m, lambda k, _: F.lower(k)))))
    taken = F.map_filter(lower(new), lambda k, _: ~k.isin(*KEPT_HEADERS))
    rest = F.map_filter(lower(stored), lambda k, _: ~F.map_contains_key(taken, k))
    return F.map_concat(rest, taken)


def as_of(events: DataFrame, slices: int) -> DataFrame:
    """events (u, ts, id, full) with prev, the (ts, id) of the latest full event of u before ts."""
    span = events.agg(F.min("ts").alias("lo"), F.max("ts").alias("hi"))
    width = F.greatest(F.lit(1.0), (F.col("hi") - F.col("lo") + 1) / F.lit(float(slices)))
    sliced = events.join(F.broadcast(span), F.lit(True)).withColumn("b", F.floor((F.col("ts") - F.col("lo")) / width)).drop("lo", "hi")  # one row is broadcast
    own = F.max(F.when(F.col("full"), F.struct("ts", "id")))
    before = Window.partitionBy("u").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    carried = sliced.groupBy("u", "b").agg(own.alias("last")).select("u", "b", F.max("last").over(before).alias("carried"))
    earlier = Window.partitionBy("u", "b").orderBy("ts").rangeBetween(Window.unboundedPreceding, -1)
    return sliced.withColumn("near", own.over(earlier)).join(carried, ["u", "b"]).withColumn("prev", F.coalesce("near", "carried")).drop("near", "carried", "b")


def resolve(records: DataFrame) -> DataFrame:
    """Every revisit of records (record_id, url, ts, status, headers) with what it stands for.

    Gives record_id, url (canonical), ts, response_id, state and the merged
    headers. state is resolved (a validator of the 304, ETag by weak
    comparison before Last-Modified, equals the response's), unchecked (the 304
    has none that the response has, too), mismatch (it differs: the content
    has changed unseen, so the response isn't used: headers are null), or
    missing (no earlier full response). Responses at the revisit's own time
    aren't earlier; of several at one time the largest record_id counts.
    Rows with a null ts, url or record_id: a revisit is missing, a response is
    not used. Repeated revisits are answered each. Other columns don't matter.
    """
    own = records.select("record_id", canonical_url(F.col("url")).alias("u"), "ts", "status", "headers")
    usable = F.col("u").isNotNull() & F.col("ts").isNotNull() & F.col("record_id").isNotNull()
    full = own.filter(usable & (F.col("status") == 200))
    revisits = own.filter(F.col("status") == 304)
    events = own.filter(usable & F.col("status").isin(200, 304)).select("u", "ts", F.col("record_id").alias("id"), (F.col("status") == 200).alias("full"))
    found = as_of(events, max(LEAST_SLICES, events.count() // SLICE_ROWS)).filter(~F.col("full")).select(F.col("id").alias("record_id"), F.col("u").alias("f_u"), F.col("ts").alias("f_ts"), F.col("prev.id").alias("response_id")).distinct()
    stored = full.groupBy("record_id", "u").agg(F.max_by("headers", "ts").alias("stored")).withColumnsRenamed({"record_id": "response_id", "u": "s_u"})
    on = revisits["record_id"].eqNullSafe(found["record_id"]) & revisits["u"].eqNullSafe(found["f_u"]) & revisits["ts"].eqNullSafe(found["f_ts"])
    met = revisits.join(found, on, "left").select(revisits["record_id"], "u", "ts", "headers", "response_id")
    met = met.join(stored, (met["response_id"] == stored["response_id"]) & (met["u"] == stored["s_u"]), "left").select("record_id", "u", "ts", "headers", met["response_id"], "stored")
    tag = lambda m: F.regexp_replace(_header(F.col(m), "etag"), "^W/", "")
    day = lambda m: _header(F.col(m), "last-modified")
    same = F.coalesce(tag("headers") == tag("stored"), day("headers") == day("stored"))
    state = F.when(F.col("response_id").isNull(), "missing").when(same.isNull(), "unchecked").when(same, "resolved").otherwise("mismatch")
    out = met.withColumn("state", state)
    empty = F.create_map().cast("map<string,string>")
    merged = F.when(F.col("state").isin("resolved", "unchecked"), merge_headers(F.coalesce("stored", empty), F.coalesce("headers", empty)))
    return out.select("record_id", F.col("u").alias("url"), "ts", "response_id", "state", merged.alias("headers"))


def captures(pages: DataFrame) -> DataFrame:
    """Capture records of a pages table: a full response of every page, and a 304 probe of it some slices of time later.

    A page's time is its id in minutes; the probe comes 1 to 256 minutes and a
    half later, by the digest of its url, so newer captures of one URL may lie
    between. The probe sends the validator of the page that it was made for.
    """
    digest = F.md5(F.coalesce("html", F.lit("")))
    tag = F.concat(F.lit('"'), digest, F.lit('"'))
    wait = F.conv(F.substring(F.md5(F.coalesce("url", F.lit(""))), 1, 2), 16, 10).cast("long")
    full = pages.select((2 * F.col("page_id")).alias("record_id"), "url", (60 * F.col("page_id")).alias("ts"), F.lit(200).alias("status"), F.create_map(F.lit("ETag"), tag, F.lit("Content-Type"), F.lit("text/html"), F.lit("Content-Length"), F.length(F.coalesce("html", F.lit(""))).cast("string"), F.lit("Cache-Control"), F.lit("max-age=60")).alias("headers"))
    probe = pages.select((2 * F.col("page_id") + 1).alias("record_id"), "url", (60 * F.col("page_id") + 60 * wait + 30).alias("ts"), F.lit(304).alias("status"), F.create_map(F.lit("etag"), F.concat(F.lit("W/"), tag), F.lit("Content-Length"), F.lit("0"), F.lit("cache-control"), F.lit("max-age=600")).alias("headers"))
    return full.unionByName(probe)


def _fields(block: bytes) -> list[tuple[str, str]]:
    """Header lines of a block as (lower-case name, value); of repeated names the first holds."""
    found: dict[str, str] = {}
    for line in block.split(b"\n"):
        name, colon, value = line.partition(b":")
        if colon and name.strip():
            found.setdefault(name.strip().lower().decode("utf-8", "replace"), value.strip().decode("utf-8", "replace"))
    return list(found.items())


class _Bytes:
    """A stream of a file's bytes; gzip members, one a record or more, are unpacked as they come."""

    def __init__(self, stream, size: int = 1 << 20):
        self.stream, self.size, self.held = stream, size, b""
        start = stream.read(2)
        self.packed = start == b"\x1f\x8b"
        self.raw, self.unpack = start, zlib.decompressobj(31) if self.packed else None

    def _more(self) -> bool:
        data = self.raw or self.stream.read(self.size)
        self.raw = b""
        if not self.packed:
            self.held += data
            return bool(data)
        while data:
            self.held += self.unpack.decompress(data)
            data = self.unpack.unused_data
            if self.unpack.eof:
                self.unpack = zlib.decompressobj(31)
            if not data:
                return True
        return False

    def line(self) -> bytes | None:
        while (at := self.held.find(b"\n")) < 0:
            if not self._more():
                out, self.held = self.held, b""
                return out or None
        out, self.held = self.held[: at + 1], self.held[at + 1 :]
        return out

    def exactly(self, n: int) -> bytes:
        parts, size = [self.held], len(self.held)
        self.held = b""
        while size < n and self._more():
            parts.append(self.held)
            size += len(self.held)
            self.held = b""
        whole = b"".join(parts)
        self.held = whole[n:]
        return whole[:n]


def warc_records(stream):
    """(number, WARC headers, block) of every record of a stream, framed by Content-Length; a cut last block is given as far as it goes."""
    data, n = _Bytes(stream), 0
    while (line := data.line()) is not None:
        if not line.startswith(b"WARC/"):
            continue  # the empty lines between records
        head = []
        while (line := data.line()) is not None and line.strip():
            head.append(line)
        fields = _fields(b"".join(head))
        length = dict(fields).get("content-length", "0")
        yield n, fields, data.exactly(int(length) if length.isdigit() else 0)
        n += 1


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """Records of WARC files (1.0 and 1.1, plain or gzip): record_id, kind, url, date, warc_headers, status, headers, payload (bytes).

    A file is read as a stream by one task, record by record as its
    Content-Length says, so a payload may hold anything and memory is that of
    a few records. record_id is a hash of the file's path and the record's
    number in it, the same in every run. Of repeated header names the first
    holds; a record without a valid Content-Length has an empty payload.
    """
    files = spark.read.format("binaryFile").load(path).select("path")  # names only: contents are streamed by the tasks
    texts = pa.map_(pa.string(), pa.string())

    def batch(rows: list[tuple]) -> pa.RecordBatch:
        columns = zip(*rows, strict=True)
        kinds = [pa.string(), pa.int64(), pa.string(), pa.string(), pa.string(), texts, pa.int32(), texts, pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["file", "n", "kind", "url", "date", "warc_headers", "status", "headers", "payload"])

    def run(batches):
        from pyarrow import fs

        for names in batches:
            for name in names.column("path").to_pylist():
                system, inner = fs.FileSystem.from_uri(name)
                with system.open_input_stream(inner, compression=None) as stream:
                    rows, size = [], 0
                    for n, fields, block in warc_records(stream):
                        head = dict(fields)
                        kind, status, own, payload = head.get("warc-type"), None, None, block
                        if kind in ("response", "revisit"):
                            first, _, payload = block.partition(b"\r\n\r\n")
                            line, _, rest = first.partition(b"\n")
                            found = re.match(rb"HTTP/\S+ (\d{3})", line)
                            status, own = int(found[1]) if found else None, _fields(rest)
                        rows.append((name, n, kind, head.get("warc-target-uri"), head.get("warc-date"), fields, status, own, payload))
                        size += len(block)
                        if size > 8 << 20 or len(rows) >= 5000:
                            yield batch(rows)
                            rows, size = [], 0
                    if rows:
                        yield batch(rows)

    schema = "file string, n long, kind string, url string, date string, warc_headers map<string,string>, status int, headers map<string,string>, payload binary"
    out = files.mapInArrow(tidy(run), schema)
    return out.select(F.xxhash64("file", "n").alias("record_id"), "kind", "url", "date", "warc_headers", "status", "headers", "payload")

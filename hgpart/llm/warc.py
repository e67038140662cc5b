"""WARC archives: writing with revisits, segments and chunked framing; reading with reassembly."""

from __future__ import annotations

import hashlib
import re
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, bounded_broadcast, new_path, small_batches, tidy, written

#: Payload bytes of one segment; longer ones continue in further records.
SEGMENT = 16_384
CHUNK = 4_096
#: Raw bytes that one archive file should hold: a reading task takes one file at a time.
FILE_BYTES = 16 << 20
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
RECORD = "<urn:page:{}>"


def chunked(body: bytes, size: int = CHUNK) -> bytes:
    parts = [b"%x\r\n%b\r\n" % (len(body[i:i + size]), body[i:i + size]) for i in range(0, len(body), size)]
    return b"".join(parts) + b"0\r\n\r\n"


def unchunked(body: bytes) -> bytes:
    """Chunked transfer framing undone; extensions and trailers are skipped. A broken frame raises ValueError."""
    out, at = [], 0
    while True:
        end = body.find(b"\r\n", at)
        if end < 0:
            raise ValueError("chunk size line without end")
        size = int(body[at:end].split(b";")[0], 16)
        if not size:
            return b"".join(out)
        if len(body) < end + 4 + size or body[end + 2 + size:end + 4 + size] != b"\r\n":
            raise ValueError("chunk shorter than its size")
        out.append(body[end + 2:end + 2 + size])
        at = end + 4 + size


def _record(headers: list[tuple[str, str]], block: bytes) -> bytes:
    """A record without the last CRLF, which the line writer adds."""
    head = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in [*headers, ("Content-Length", str(len(block)))])
    return head.encode() + b"\r\n" + block + b"\r\n"


def _uri(url: str | None) -> str:
    return re.sub(r"[\x00-\x20]", "%20", url or "")


def _records(batches):
    """Rows (key, url, body, digest, refers_to) to records, one output row each."""
    for batch in batches:
        out = []
        for key, url, body, digest, other in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
            name = RECORD.format(key)
            common = [("WARC-Target-URI", _uri(url)), ("WARC-Date", "2020-01-01T00:00:00Z"), ("WARC-Payload-Digest", f"sha1:{digest}")]
            if other is not None:
                block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html\r\nContent-Length: %d\r\n\r\n" % len(body)
                out.append((key, 1, _record([("WARC-Type", "revisit"), ("WARC-Record-ID", name), *common, ("WARC-Profile", PROFILE), ("WARC-Refers-To", RECORD.format(other)), ("Content-Type", "application/http; msgtype=response")], block)))
                continue
            long = len(body) > SEGMENT
            head = b"HTTP/1.1 200 OK\r\nContent-Type: text/html\r\n"
            block = head + (b"Transfer-Encoding: chunked\r\n\r\n" + chunked(body) if long else b"Content-Length: %d\r\n\r\n" % len(body) + body)
            kind = [("WARC-Type", "response"), ("WARC-Record-ID", name), *common, ("Content-Type", "application/http; msgtype=response")]
            if len(block) <= SEGMENT or not long:
                out.append((key, 1, _record(kind, block)))
                continue
            pieces = [block[i:i + SEGMENT] for i in range(0, len(block), SEGMENT)]
            out.append((key, 1, _record([*kind, ("WARC-Segment-Number", "1")], pieces[0])))
            for i, piece in enumerate(pieces[1:], 2):
                last = [("WARC-Segment-Total-Length", str(len(block)))] if i == len(pieces) else []
                out.append((key, i, _record([("WARC-Type", "continuation"), ("WARC-Record-ID", f"{name[:-1]}:{i}>"), ("WARC-Date", "2020-01-01T00:00:00Z"), ("WARC-Segment-Origin-ID", name), ("WARC-Segment-Number", str(i)), *last], piece)))
        yield pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.string()), pa.array([o[1] for o in out], pa.int32()), pa.array([o[2] for o in out], pa.binary())], ["key", "segment", "record"])


def _digests(batches):
    for batch in batches:
        bodies = batch.column(2).to_pylist()
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array([hashlib.sha1(b, usedforsecurity=False).hexdigest() for b in bodies], pa.string()), pa.array([len(b) for b in bodies], pa.int64())], ["key", "url", "body", "digest", "size"])


def write_warc(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", body_col: str = "html", least: int = 1000, file_bytes: int = FILE_BYTES) -> None:
    """Write one response or revisit a row to gzipped WARC files under ``path``, long ones in segments of SEGMENT bytes.

    Of rows whose payloads of at least ``least`` bytes have the same SHA-1 and
    length, that with the largest id is the response and the others revisit
    it. Only (id, digest, length) is grouped, payloads are not. Spark's text
    writer stores the records, so the files appear by its commit protocol on any
    file system and a lost task leaves nothing. Segments go to files of their own by hash.

    Null payloads are empty. Records are named by id; where ids are null or repeated, each row's name gets a suffix of
    its own (``;`` and a UUID), a null id counting as the smallest. An empty table gives archives without records.
    """
    small_batches(pages.sparkSession)
    kind = pages.schema[id_col].dataType
    source = pages.select(F.col(id_col).cast("string").alias("key"), F.col(url_col).cast("string").alias("url"), as_bytes(body_col).alias("body"))
    schema = "key string, url string, body binary, digest string, size long"
    hashed = source.mapInArrow(tidy(_digests), schema)
    small = written(hashed.select("key", "digest", "size"), "digests")
    rows, ids, total = small.agg(F.count("*"), F.countDistinct("key"), F.coalesce(F.sum("size"), F.lit(0))).first()
    if ids < rows:
        # a name of its own for each row must be the same in both passes, so it is stored
        source = written(source.withColumn("key", F.concat(F.coalesce("key", F.lit("")), F.lit(";"), F.uuid())), "named")
        hashed = source.mapInArrow(tidy(_digests), schema)
        small = written(hashed.select("key", "digest", "size"), "digests")
    order = F.struct(F.nullif(F.substring_index("key", ";", 1), F.lit("")).cast(kind), F.col("key"))
    shared = small.filter(F.col("size") >= least).groupBy("digest", "size").agg(F.max_by("key", order).alias("first"), F.count("*").alias("n")).filter("n > 1").drop("n")
    linked = written(small.join(shared, ["digest", "size"]).filter("key <> first").select("key", F.col("first").alias("refers_to")), "revisits")
    records = hashed.join(bounded_broadcast(linked, linked.count()), "key", "left").select("key", "url", "body", "digest", "refers_to").mapInArrow(tidy(_records), "key string, segment int, record binary")
    files = max(1, -(-total // file_bytes))
    records.repartition(files, F.xxhash64("key", "segment")).select(F.col("record").cast("string").alias("value")).write.option("compression", "gzip").option("lineSep", "\r\n").text(path)


class _Stream:
    """Bytes of a gzipped archive, inflated piece by piece."""

    def __init__(self, data: bytes):
        self.left, self.buffer, self.at = memoryview(data), b"", 0
        self.inflate = zlib.decompressobj(31) if data[:2] == b"\x1f\x8b" else None

    def _more(self) -> bool:
        if not len(self.left):
            return False
        piece, self.left = bytes(self.left[:1 << 18]), self.left[1 << 18:]
        if self.inflate:
            got = self.inflate.decompress(piece)
            while self.inflate.eof and (rest := self.inflate.unused_data):
                self.inflate = zlib.decompressobj(31)
                got += self.inflate.decompress(rest)
        else:
            got = piece
        self.buffer, self.at = self.buffer[self.at:] + got, 0
        return True

    def until(self, mark: bytes) -> bytes | None:
        while (end := self.buffer.find(mark, self.at)) < 0:
            if not self._more():
                return None
        out, self.at = self.buffer[self.at:end], end + len(mark)
        return out

    def take(self, n: int) -> bytes:
        while len(self.buffer) - self.at < n:
            if not self._more():
                raise ValueError("archive ends inside a record")
        out, self.at = self.buffer[self.at:self.at + n], self.at + n
        return out


def parse_warc(data: bytes):
    """(headers with lower-case names, block) of every record of an archive; ValueError where it is broken."""
    stream = _Stream(data)
    while (head := stream.until(b"\r\n\r\n")) is not None:
        lines = head.decode("utf-8", "replace").lstrip("\r\n").split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError("record without version line")
        headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        block = stream.take(int(headers["content-length"]))
        if stream.take(4) != b"\r\n\r\n":
            raise ValueError("record without its end")
        yield headers, block


def http_payload(block: bytes) -> tuple[bytes, int | None]:
    """(payload with transfer framing undone, stated content length)."""
    head, _, body = block.partition(b"\r\n\r\n")
    stated = re.search(rb"(?i)\r\ncontent-length:\s*(\d+)", head)
    if re.search(rb"(?i)\r\ntransfer-encoding:\s*chunked", head):
        body = unchunked(body)
    return body, int(stated[1]) if stated else None


_PARSED = "name string, type string, segment int, total long, uri string, refers_to string, digest string, size long, payload binary, block binary"


def _finish(name, uri, block, want_payload):
    body, _ = http_payload(block)
    return (name, "response", None, None, uri, None, hashlib.sha1(body, usedforsecurity=False).hexdigest(), len(body), body if want_payload else None, None)


def _arrow(out):
    kinds = [pa.string(), pa.string(), pa.int32(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.binary(), pa.binary()]
    names = [x.split()[0] for x in _PARSED.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], k) for i, k in enumerate(kinds)], names)


def _parser(want_payload: bool):
    def run(batches):
        for batch in batches:
            for data in batch.column(0):
                out, held = [], 0
                for h, block in parse_warc(data.as_py()):
                    name = h.get("warc-segment-origin-id") or h["warc-record-id"]
                    uri = h.get("warc-target-uri")
                    if h["warc-type"] == "revisit":
                        out.append((name, "revisit", None, None, uri, h.get("warc-refers-to"), h["warc-payload-digest"].partition(":")[2], http_payload(block)[1], None, None))
                    elif "warc-segment-number" in h:
                        out.append((name, "segment", int(h["warc-segment-number"]), int(h["warc-segment-total-length"]) if "warc-segment-total-length" in h else None, uri, None, None, None, None, block))
                    elif h["warc-type"] == "response":
                        out.append(_finish(name, uri, block, want_payload))
                    held += len(block)
                    if held > 4 << 20:
                        yield _arrow(out)
                        out, held = [], 0
                if out:
                    yield _arrow(out)

    return run


def _assembler(want_payload: bool):
    def run(batches):
        for batch in batches:
            out = []
            for row in batch.to_pylist():
                parts = row["parts"]
                if [p["segment"] for p in parts] != list(range(1, len(parts) + 1)):
                    raise ValueError(f"{row['name']}: segments are missing or repeated")
                block = b"".join(p["block"] for p in parts)
                if row["total"] != len(block):
                    raise ValueError(f"{row['name']}: {len(block)} bytes, {row['total']} stated")
                out.append(_finish(row["name"], row["uri"], block, want_payload))
            yield _arrow(out)

    return run


def read_warc(spark: SparkSession, path: str, payload: bool = True) -> DataFrame:
    """Records of the archives under ``path``: name, record_type, uri, refers_to, payload_digest, payload_bytes, payload.

    Continuation records are grouped with their origin, ordered by segment number and checked for
    gaps and for the stated total length, then chunked framing is undone. A group is one record,
    so it is as large as that record. Digests of responses are computed from
    the payload that was read; revisits state theirs and their length. Broken
    archives raise. An empty folder of archives gives an empty result.
    """
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.gz").load(path).select("content")
    parsed = files.mapInArrow(tidy(_parser(payload)), _PARSED)
    parsed = written(parsed, "records")
    whole = parsed.filter("type <> 'segment'")
    parts = parsed.filter("type = 'segment'").groupBy("name").agg(F.array_sort(F.collect_list(F.struct("segment", "block"))).alias("parts"), F.max("total").alias("total"), F.max("uri").alias("uri"))
    whole = whole.union(parts.mapInArrow(tidy(_assembler(payload)), _PARSED))
    return whole.select("name", F.col("type").alias("record_type"), "uri", "refers_to", F.col("digest").alias("payload_digest"), F.col("size").alias("payload_bytes"), "payload")


def warc_round_trip(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", body_col: str = "html") -> DataFrame:
    """Write ``pages`` as archives in the shared folder and return what reading them back finds, one row a page."""
    path = new_path(pages.sparkSession, "warc")
    write_warc(pages, path, id_col, url_col, body_col)
    kind = pages.schema[id_col].dataType
    key = lambda c: F.nullif(F.regexp_extract(c, r"^<urn:page:([^;]*)(;.*)?>$", 1), F.lit("")).cast(kind)
    return read_warc(pages.sparkSession, path, payload=False).select(key("name").alias(id_col), "payload_bytes", "payload_digest", "record_type", F.when(F.col("refers_to").isNotNull(), key("refers_to")).alias("refers_to"))

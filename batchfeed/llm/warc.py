"""WARC writing, reading and transaction assembly.

Each page becomes a transaction of three records, gzipped one by one as the format
asks: a response (or a revisit of an equal payload), its request and its metadata,
the latter two naming the former in WARC-Concurrent-To. Reading parses the archives
with Spark's binaryFile source, and the transactions are put together again by joining
on those identifiers, whatever the order or file of the records.

Of equal payloads of at least `least_bytes` the page with the largest page_id is the
response, the others are revisits. Archives are closed at `file_bytes`, so that one
fits in a row; each is written under a name of its own attempt and listed in the result only
when its task succeeds, so that failed or doubled attempts leave nothing that is read.

Edge cases: a null html is an empty payload; rows of one page_id and equal payload are
all of the same type; a null page_id is smaller than others and keeps its row, as does
a null url; text that is not UTF-8 does not occur in Spark strings.
"""

from __future__ import annotations

import base64
import hashlib
import posixpath
import uuid
import zlib

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, functions as F

from .common import batches, new_path, written

DATE = "2024-01-01T00:00:00Z"


def payload_digest(payload: bytes) -> str:
    """Bare upper-case base32 SHA-1."""
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(kind: str, headers: dict[str, str], body: bytes) -> bytes:
    """One gzipped WARC/1.1 record."""
    lines = ["WARC/1.1", f"WARC-Type: {kind}", *(f"{k}: {v}" for k, v in headers.items()), f"Content-Length: {len(body)}", "", ""]
    small = len(body) < 512  # requests and metadata need no large window
    z = zlib.compressobj(1, zlib.DEFLATED, 25 if small else 31, 1 if small else 8)
    return z.compress("\r\n".join(lines).encode() + body + b"\r\n\r\n") + z.flush()


def plain_bytes(data: bytes, chunk: int = 1 << 14) -> bytes:
    """The content of an archive, gzipped record by record, as a whole or not at all.

    Members are fed to zlib in small chunks, since it copies what follows a member's end.
    """
    if data[:2] != b"\x1f\x8b":
        return data
    view, at, out = memoryview(data), 0, []
    while at < len(data):
        member = zlib.decompressobj(31)
        while not member.eof:
            piece = view[at : at + chunk]
            if not piece:
                raise ValueError("the last gzip member is cut")
            out.append(member.decompress(piece))
            at += len(piece) - len(member.unused_data)
    return b"".join(out)


def parse(data: bytes):
    """(headers, body) of each record in an archive; header names are lower-cased."""
    plain = plain_bytes(data)
    at = 0
    while at < len(plain):
        end = plain.index(b"\r\n\r\n", at)
        head = plain[at:end].decode().split("\r\n")
        if not head[0].startswith("WARC/"):
            raise ValueError(f"no record at byte {at}")
        headers: dict[str, list[str]] = {}
        for line in head[1:]:
            name, _, value = line.partition(":")
            headers.setdefault(name.strip().lower(), []).append(value.strip())
        size = int(headers["content-length"][0])
        body = plain[end + 4 : end + 4 + size]
        if len(body) != size or plain[end + 4 + size : end + 8 + size] != b"\r\n\r\n":
            raise ValueError(f"the record at byte {at} is cut")
        yield headers, body
        at = end + 8 + size


def _safe(url: str | None) -> str:
    """A header value of one line."""
    return "" if url is None else "".join(f"%{ord(c):02X}" if c < " " or c == "\x7f" else c for c in url)


def transaction(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, serial: str) -> bytes:
    """The three records of a page."""
    urn = lambda part: f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{serial}/{part}')}>"
    target = {"WARC-Target-URI": _safe(url), "WARC-Date": DATE} if url is not None else {"WARC-Date": DATE}
    own = {"WARC-Record-ID": urn("response")} | target | {"WARC-Payload-Digest": f"sha1:{digest}", "X-Page-Id": "" if page_id is None else str(page_id)}
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nX-Payload-Length: %d\r\n\r\n" % len(payload)
    if refers_to is None:
        first = record("response", own | {"Content-Type": "application/http; msgtype=response"}, http + payload)
    else:
        first = record("revisit", own | {"WARC-Profile": "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", "X-Refers-To-Page": str(refers_to), "Content-Type": "application/http; msgtype=response"}, http)
    ask = record("request", {"WARC-Record-ID": urn("request")} | target | {"WARC-Concurrent-To": urn("response"), "Content-Type": "application/http; msgtype=request"}, b"GET / HTTP/1.1\r\n\r\n")
    meta = record("metadata", {"WARC-Record-ID": urn("metadata")} | target | {"WARC-Concurrent-To": urn("response"), "Content-Type": "application/warc-fields"}, b"via: crawl\r\n")
    return ask + first + meta


def revisits(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """digest and head (largest page_id) of the payloads that occur more than once."""
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    heads = pages.select("page_id", F.sha1(payload).alias("digest"), F.octet_length(payload).alias("size")).where(F.col("size") >= least_bytes)
    return heads.groupBy("digest").agg(F.max("page_id").alias("head"), F.count("*").alias("n")).where("n > 1 AND head IS NOT NULL").select("digest", "head")


def with_heads(pages: DataFrame, least_bytes: int = 0, broadcast_rows: int = 500_000, salts: int = 64) -> DataFrame:
    """page_id, url, payload and head: the response's page_id where the payload occurs more than once.

    The list of repeated payloads is narrow: a digest and an id. It is broadcast if counted to
    have at most broadcast_rows rows (of some 80 bytes), so that payloads stay where they are. Beyond that,
    it is repeated under `salts` numbers and hashed, so that a payload that very many pages
    share is spread and no payload is sorted.
    """
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    own = pages.select("page_id", "url", payload.alias("payload"), F.sha1(payload).alias("digest"))
    heads = written(revisits(pages, least_bytes), "heads")
    if heads.count() <= broadcast_rows:
        full = own.join(F.broadcast(heads), "digest", "left")
    else:
        spread = heads.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
        salt = F.pmod(F.xxhash64("page_id", "url"), F.lit(salts)).cast("int")
        full = own.withColumn("salt", salt).join(spread.hint("shuffle_hash"), ["digest", "salt"], "left")
    return full.select("page_id", "url", "payload", "head")


def write_archives(pages: DataFrame, folder: str, least_bytes: int = 0, file_bytes: int = 8 << 20, broadcast_rows: int = 500_000) -> DataFrame:
    """Write pages(page_id, url, html) under folder; returns a row (path, records) per archive."""
    full = with_heads(pages, least_bytes, broadcast_rows)

    def run(rows):
        import contextlib

        fs, root = pafs.FileSystem.from_uri(folder)
        parts, size, count = [], 0, 0

        def close():
            name = f"{uuid.uuid4().hex}.warc.gz"
            with fs.open_output_stream(posixpath.join(root, name), compression=None) as out:
                for part in parts:
                    out.write(part)
            return pa.RecordBatch.from_arrays([pa.array([f"{folder}/{name}"]), pa.array([count], pa.int64())], ["path", "records"])

        with contextlib.suppress(FileExistsError):
            fs.create_dir(root, recursive=True)
        run_id = uuid.uuid4().hex
        n = 0
        for batch in batches(rows, 8 << 20):
            for page_id, url, body, head in zip(*(batch[c].to_pylist() for c in ("page_id", "url", "payload", "head")), strict=True):
                refers = head if head is not None and page_id != head else None
                data = transaction(page_id, url, body, payload_digest(body), refers, f"{run_id}/{n}")
                n += 1
                parts.append(data)
                size, count = size + len(data), count + 3
                if size >= file_bytes:
                    yield close()
                    parts, size, count = [], 0, 0
        if parts:
            yield close()

    return full.mapInArrow(run, "path string, records long")


def read_records(spark, paths: DataFrame, folder: str, with_payload: bool = True) -> DataFrame:
    """One row per record of the archives that paths(path) lists.

    Payload length and digest are those of the whole HTTP body; without with_payload the bytes are left out.
    """
    names = ("type", "record_id", "concurrent_to", "url", "page_id", "refers_to", "payload_bytes", "payload_digest", "body")
    schema = "type string, record_id string, concurrent_to array<string>, url string, page_id long, refers_to long, payload_bytes long, payload_digest string, body binary"
    types = (pa.string(), pa.string(), pa.list_(pa.string()), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())

    def run(rows):
        for batch in rows:
            for data in batch["content"].to_pylist():
                out = []
                for head, body in parse(data):
                    one = lambda k, h=head: h.get(k, [None])[0]
                    kind, size, digest, content = one("warc-type"), None, None, None
                    if kind in ("response", "revisit"):
                        http, _, content = body.partition(b"\r\n\r\n")
                        if kind == "response":
                            size, digest = len(content), payload_digest(content)
                            if one("warc-payload-digest") not in (None, f"sha1:{digest}"):
                                raise ValueError(f"payload of {one('warc-record-id')} does not match its digest")
                        else:
                            size = next((int(x.split(b":")[1]) for x in http.split(b"\r\n") if x.lower().startswith(b"x-payload-length:")), None)
                            digest = (one("warc-payload-digest") or "").removeprefix("sha1:") or None
                    elif kind in ("request", "metadata"):
                        content = body
                    out.append((kind, one("warc-record-id"), head.get("warc-concurrent-to", []), one("warc-target-uri"), int(one("x-page-id")) if one("x-page-id") else None, int(one("x-refers-to-page")) if one("x-refers-to-page") else None, size, digest, content if with_payload else None))
                for i in range(0, len(out), 2000):
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out[i : i + 2000]), types, strict=True)], list(names))

    listed = spark.read.format("binaryFile").load(folder).select(F.element_at(F.split("path", "/"), -1).alias("_name"), "content")
    wanted = paths.select(F.element_at(F.split("path", "/"), -1).alias("_name")).distinct()
    # left by failed attempts: few or none, found by names alone
    stray = written(listed.select("_name").join(wanted, "_name", "left_anti"), "stray")
    n = stray.count()
    if n:
        listed = listed.join(F.broadcast(stray) if n <= 100_000 else stray.hint("shuffle_hash"), "_name", "left_anti")
    return listed.select("content").mapInArrow(run, schema)


def assemble(records: DataFrame) -> DataFrame:
    """One nested row per capture: response or revisit with its requests and metadata.

    A record belongs to a capture if either names the other in concurrent_to. Records
    of no capture are left out.
    """
    capture = F.col("type").isin("response", "revisit")
    other = records.where(F.col("type").isin("request", "metadata")).select("type", "record_id", "url", "body", "concurrent_to")
    named = other.select(F.explode("concurrent_to").alias("hub"), "type", "record_id", "url", "body")
    back = records.where(capture).select(F.explode("concurrent_to").alias("record_id"), F.col("record_id").alias("hub"))
    naming = back.join(other.drop("concurrent_to"), "record_id").select("hub", "type", "record_id", "url", "body")
    members = named.unionByName(naming).dropDuplicates(["hub", "record_id"])
    part = lambda kind: F.array_sort(F.collect_list(F.when(F.col("type") == kind, F.struct("record_id", "url", "body"))))
    grouped = members.groupBy("hub").agg(part("request").alias("requests"), part("metadata").alias("metadata"))
    hubs = records.where(capture).drop("concurrent_to")
    return hubs.join(grouped, hubs.record_id == grouped.hub, "left").select(
        "page_id", "url", F.col("type").alias("record_type"), "refers_to", "payload_bytes", "payload_digest",
        F.struct("record_id", "body").alias("capture"), F.coalesce("requests", F.array()).alias("requests"), F.coalesce("metadata", F.array()).alias("metadata"),
    )


def round_trip(pages: DataFrame, least_bytes: int = 0, with_payload: bool = True, broadcast_rows: int = 500_000) -> DataFrame:
    """Write pages as archives in the shared folder, read them back and assemble the captures."""
    spark = pages.sparkSession
    folder = new_path(spark, "warc")
    archives = written(write_archives(pages, folder, least_bytes, broadcast_rows=broadcast_rows), "archives")
    if archives.isEmpty():
        return assemble(spark.createDataFrame([], "type string, record_id string, concurrent_to array<string>, url string, page_id long, refers_to long, payload_bytes long, payload_digest string, body binary"))
    return assemble(written(read_records(spark, archives, folder, with_payload), "records"))


def digest(captures: DataFrame) -> DataFrame:
    """The columns of captures that `transaction` wrote, whose links are checked row by row.

    Each has one request and one metadata record, both of its url. A lost, doubled or
    wrongly linked one fails the query, since the columns alone would not show it.
    """
    own = lambda kind: (F.size(kind) == 1) & F.forall(kind, lambda r: r["url"].eqNullSafe(F.col("url")))
    wrong = F.concat(F.lit("the records of page "), F.coalesce(F.col("page_id").cast("string"), F.lit("null")), F.lit(" are not one request and one metadata record of its url"))
    record_type = F.when(own("requests") & own("metadata"), F.col("record_type")).otherwise(F.raise_error(wrong))
    return captures.select("page_id", "payload_bytes", "payload_digest", record_type.alias("record_type"), "refers_to")

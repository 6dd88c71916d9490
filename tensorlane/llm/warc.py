"""WARC archives: writing captures, reading records back, and assembling transactions.

A capture is three records: the response (or a revisit, where another capture holds the
same payload), the request and a metadata record, tied by ``WARC-Concurrent-To``.  Records
are separate gzip members.  Assembly follows those identifiers - from a request or
metadata record to its response, from a response to its request, or over one record
between - and gives one nested row per capture.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import re
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import quote, urlsplit

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import document_blocks, small_batches, utf8, written

#: A file is closed once it holds so many bytes, so that no reader's task grows with the input.
FILE_BYTES = 256 << 20
BATCH_BYTES = 4 << 20
DATE = "2024-01-01T00:00:00Z"
SAME_PAYLOAD = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
MANIFEST = pa.schema([("path", pa.string()), ("records", pa.int64()), ("bytes", pa.int64())])
_CONTROL = re.compile(r"[\x00-\x20\x7f]")


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def encode_record(kind: str, record_id: str, headers: list[tuple[str, str]], block: bytes) -> bytes:
    """One record, uncompressed."""
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <{record_id}>", f"WARC-Date: {DATE}", *(f"{k}: {v}" for k, v in headers), f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_records(stream: io.BufferedIOBase) -> Iterator[tuple[dict[str, list[str]], bytes]]:
    """Headers (names in lower case, all values) and block of every record of an uncompressed stream."""
    while line := stream.readline():
        if not line.strip():
            continue
        if not line.startswith(b"WARC/"):
            raise ValueError(f"not a record: {line[:40]!r}")
        headers: dict[str, list[str]] = {}
        while (line := stream.readline()).strip():
            name, _, value = line.decode().partition(":")
            headers.setdefault(name.strip().lower(), []).append(value.strip())
        size = int(headers["content-length"][0])
        block = stream.read(size)
        if len(block) < size:
            raise ValueError("a record is cut short")
        yield headers, block


def split_http(block: bytes) -> tuple[dict[str, str], bytes]:
    head, _, body = block.partition(b"\r\n\r\n")
    fields = (line.partition(":") for line in head.decode("utf-8", "replace").split("\r\n")[1:])
    return {k.strip().lower(): v.strip() for k, _, v in fields}, body


def _capture(row: dict, record: str) -> list[bytes]:
    """The records of one capture; ``record`` makes their identifiers unique."""
    url, body = _CONTROL.sub(lambda m: quote(m[0]), row["url"] or "urn:none"), row["body"]
    name = {k: f"urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{record}/{k}')}" for k in ("response", "request", "metadata")}
    about = [("WARC-Target-URI", url)] + ([] if row["id"] is None else [("X-Capture-ID", str(row["id"]))])
    digest = base64.b32encode(bytes.fromhex(row["digest"])).decode()
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(body)}\r\n\r\n".encode()
    main = [*about, ("WARC-Payload-Digest", f"sha1:{digest}"), ("Content-Type", "application/http; msgtype=response")]
    if row["first"] is None:
        first = encode_record("response", name["response"], main, http + body)
    else:
        again = [("WARC-Profile", SAME_PAYLOAD), ("X-Refers-To-Capture", str(row["first"])), ("WARC-Refers-To-Target-URI", _CONTROL.sub(lambda m: quote(m[0]), row["first_url"] or "urn:none"))]
        first = encode_record("revisit", name["response"], main + again, http)
    parts = urlsplit(url) if "://" in url and "[" not in url else None
    path, host = (parts.path or "/", parts.netloc) if parts else (url, "none")
    with_it = ("WARC-Concurrent-To", f"<{name['response']}>")
    request = encode_record("request", name["request"], [*about, with_it, ("Content-Type", "application/http; msgtype=request")], f"GET {path} HTTP/1.1\r\nHost: {host}\r\n\r\n".encode())
    note = encode_record("metadata", name["metadata"], [*about, with_it, ("Content-Type", "application/warc-fields")], f"payload-bytes: {len(body)}\r\n".encode())
    return [first, request, note]


def write_captures(pages: DataFrame, folder: str, *, id_col: str = "page_id", url_col: str = "url", body_col: str = "html", least_bytes: int = 0, level: int = 1) -> DataFrame:
    """Write a capture per row into gzip archives under ``folder``; the manifest has a row a file.

    Of rows with equal payloads of at least ``least_bytes`` bytes, the one with the largest id
    is the response and the others are revisits of it; smaller payloads are all responses.
    Null bodies are empty payloads, null urls become ``urn:none``.  Rows with a null id never are
    the response of a group that has an id.  Rows that repeat both id and payload are responses
    alike.  An empty table gives an empty manifest; other columns are not read.
    """
    spark = pages.sparkSession
    small_batches(spark)
    rows = pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).cast("string").alias("url"), utf8(body_col).alias("body"))
    rows = rows.withColumn("digest", F.sha1("body"))
    light = rows.select("id", "url", "digest", F.octet_length("body").alias("n")).filter(F.col("n") >= least_bytes)
    light = written(light.drop("n"), "warc-digests")
    groups = light.groupBy("digest").agg(F.max("id").alias("first"), F.max_by("url", "id").alias("first_url"), F.count("*").alias("n"))
    again = written(
        light.select("id", "digest").distinct()
        .join(groups.filter(F.col("n") > 1), "digest")
        .filter(~F.col("id").eqNullSafe(F.col("first")))
        .select(F.col("id").alias("of_id"), F.col("digest").alias("of_digest"), "first", "first_url"),
        "warc-revisits",
    )
    ready = rows.join(again, F.col("id").eqNullSafe(F.col("of_id")) & (F.col("digest") == F.col("of_digest")), "left").drop("of_id", "of_digest")

    def put(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, run = TaskContext.get().partitionId(), uuid.uuid4().hex
        fs, root = pafs.FileSystem.from_uri(folder)
        fs.create_dir(root, recursive=True)
        stream, name, size, records, files = None, "", 0, 0, []

        def close() -> None:
            stream.close()
            files.append((name, records, size))

        n = 0
        for b in document_blocks(batches, "body", BATCH_BYTES):
            for row in b.to_pylist():
                if stream is None:
                    # the run is part of the name: files of a lost attempt are in no manifest
                    name = f"{root}/part-{part:06d}-{len(files):04d}-{run}.warc.gz"
                    stream, size, records = fs.open_output_stream(name, compression=None), 0, 0
                    info = encode_record("warcinfo", f"urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, name)}", [("Content-Type", "application/warc-fields")], b"format: WARC file version 1.1\r\n")
                    size += stream.write(gzip.compress(info, level, mtime=0)) or 0
                for record in _capture(row, f"{run}/{part}/{n}"):
                    packed = zlib.compressobj(level, zlib.DEFLATED, 31)
                    data = packed.compress(record) + packed.flush()
                    stream.write(data)
                    size += len(data)
                    records += 1
                n += 1
                if size > FILE_BYTES:
                    close()
                    stream = None
        if stream is not None:
            close()
        if files:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*files, strict=True)], schema=MANIFEST)

    return written(ready.mapInArrow(put, "path string, records long, bytes long"), "warc-manifest")


RECORD = "kind string, record_id string, concurrent_to array<string>, capture_id long, refers_to long, target_uri string, payload_bytes long, payload_digest string, digest_ok boolean, note string, payload binary"


def read_records(manifest: DataFrame, folder: str, *, payloads: bool = False) -> DataFrame:
    """A row per record of the archives in a manifest; payloads are checked against their digests.

    ``payload`` is null unless asked for.  A revisit's ``payload_bytes`` and digest are those of the full payload.
    """
    files = max(1, manifest.count())

    def clean(x: str | None) -> str | None:
        return x[1:-1] if x and x.startswith("<") else x

    def get(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, _ = pafs.FileSystem.from_uri(folder)
        for b in batches:
            for path in b.column("path").to_pylist():
                held, size = [], 0
                with fs.open_input_stream(path, compression=None) as raw, gzip.GzipFile(fileobj=io.BufferedReader(raw, 1 << 20)) as stream:
                    for h, block in parse_records(stream):
                        one = {k: v[0] for k, v in h.items()}
                        kind = one["warc-type"]
                        if kind == "warcinfo":
                            continue
                        http, body = split_http(block) if kind in ("response", "revisit") else ({}, b"")
                        digest = one.get("warc-payload-digest", "").removeprefix("sha1:") or None
                        held.append({
                            "kind": kind, "record_id": clean(one["warc-record-id"]), "concurrent_to": [clean(x) for x in h.get("warc-concurrent-to", [])],
                            "capture_id": int(one["x-capture-id"]) if "x-capture-id" in one else None, "refers_to": int(one["x-refers-to-capture"]) if "x-refers-to-capture" in one else None,
                            "target_uri": one.get("warc-target-uri"), "payload_bytes": len(body) if kind == "response" else int(http["content-length"]) if kind == "revisit" else None,
                            "payload_digest": digest, "digest_ok": payload_digest(body) == digest if kind == "response" else None,
                            "note": None if http else block.decode("utf-8", "replace"), "payload": body if payloads and kind == "response" else None,
                        })
                        size += len(body)
                        if size > BATCH_BYTES or len(held) >= 5000:
                            yield pa.RecordBatch.from_pylist(held, schema=shape)
                            held, size = [], 0
                if held:
                    yield pa.RecordBatch.from_pylist(held, schema=shape)

    text, number = pa.string(), pa.int64()
    shape = pa.schema([("kind", text), ("record_id", text), ("concurrent_to", pa.list_(text)), ("capture_id", number), ("refers_to", number), ("target_uri", text), ("payload_bytes", number), ("payload_digest", text), ("digest_ok", pa.bool_()), ("note", text), ("payload", pa.binary())])
    return manifest.select("path").repartition(files, "path").mapInArrow(get, RECORD)


def assemble(records: DataFrame) -> DataFrame:
    """One nested row per capture: the columns of its response or revisit, ``request`` and ``metadata`` structs and their counts.

    A response without request or metadata has null structs; a request or metadata record that
    leads to no response in the table is in no capture.  Where several requests name one
    response, the struct is that with the smallest record id.
    """
    main = records.filter(F.col("kind").isin("response", "revisit"))
    side = records.filter(F.col("kind").isin("request", "metadata")).select("kind", "record_id", "note", "target_uri", "concurrent_to")
    named = side.withColumn("to", F.explode("concurrent_to")).drop("concurrent_to")
    known = main.select(F.col("record_id").alias("of"))
    direct = named.join(known, F.col("to") == F.col("of"), "left")
    found = direct.filter(F.col("of").isNotNull()).drop("to")
    over = direct.filter(F.col("of").isNull()).drop("of").join(found.select(F.col("record_id").alias("via"), "of"), F.col("to") == F.col("via")).drop("to", "via")
    back = main.select(F.col("record_id").alias("of"), F.explode("concurrent_to").alias("to"))
    back = side.drop("concurrent_to").join(back, F.col("record_id") == F.col("to")).drop("to")
    members = found.unionByName(over).unionByName(back)

    def part(kind: str) -> list:
        mine = F.when(F.col("kind") == kind, F.struct("record_id", "target_uri", "note"))
        return [F.min(mine).alias(kind), F.count_distinct(F.when(F.col("kind") == kind, F.col("record_id"))).alias(f"n_{kind}")]

    sides = members.groupBy("of").agg(*part("request"), *part("metadata"))
    none = F.lit(0).cast("long")
    return main.join(sides, F.col("record_id") == F.col("of"), "left").drop("of", "note", "concurrent_to").withColumns(
        {f"n_{k}": F.coalesce(f"n_{k}", none) for k in ("request", "metadata")}
    )

"""Token ids in binary files: bit-plane or byte-plane shuffled blocks under zstandard.

File layout, all numbers little-endian:

* the signature ``TLPLANE1``;
* for each block of ``block_ids`` ids (the last may be shorter): its planes one after the
  other, each compressed by zstandard.  Byte planes hold byte k of every id; bit planes
  hold bit k of every id, eight ids to a byte, and only as many planes as the largest id
  of the block needs;
* the document section (doc ids as 64-bit, a null mask, lengths as 64-bit), compressed;
* the chunk index: for each block its offset, id count, plane count, and each plane's size;
* a footer of fixed size: offset of the document section, of the index, counts, the plane
  kind, and the signature again.

Files are written under a temporary name and renamed, so a task that runs twice leaves
one whole file.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import document_blocks, scratch_path, small_batches, utf8
from .tokenizing import ChunkEncoder

SIGNATURE = b"TLPLANE1"
FOOTER = struct.Struct("<QQQQQB7x8s")
BLOCK = struct.Struct("<QII")
BLOCK_IDS = 1 << 16
END_ID = 0
TEXT_BYTES = 2 << 20


def to_planes(ids: np.ndarray, kind: str) -> list[bytes]:
    """Transpose a block of unsigned 32-bit ids into byte or bit planes, lowest first."""
    if kind == "byte":
        return [p.tobytes() for p in ids.astype("<u4").view(np.uint8).reshape(-1, 4).T]
    width = int(ids.max()).bit_length() if len(ids) else 0
    return [np.packbits((ids >> np.uint32(k)).astype(np.uint8) & 1).tobytes() for k in range(width)]


def from_planes(planes: list[bytes], n: int, kind: str) -> np.ndarray:
    if kind == "byte":
        return np.ascontiguousarray(np.stack([np.frombuffer(p, np.uint8) for p in planes], 1)).view("<u4").ravel()
    out = np.zeros(n, np.uint32)
    for k, p in enumerate(planes):
        out |= np.unpackbits(np.frombuffer(p, np.uint8), count=n).astype(np.uint32) << np.uint32(k)
    return out


class PlaneWriter:
    """Appends ids to an open binary stream, block by block."""

    def __init__(self, stream, kind: str = "byte", block_ids: int = BLOCK_IDS, level: int = 3):
        if kind not in ("byte", "bit"):
            raise ValueError("kind is byte or bit")
        self.stream, self.kind, self.block_ids = stream, kind, block_ids
        self.zstd = zstandard.ZstdCompressor(level=level)
        self.at = stream.write(SIGNATURE) or len(SIGNATURE)
        self.at = len(SIGNATURE)
        self.pending, self.held, self.total = [], 0, 0
        self.index: list[tuple[int, int, list[int]]] = []
        self.doc_ids, self.lengths = [], []

    def _put(self, data: bytes) -> int:
        self.stream.write(data)
        self.at += len(data)
        return len(data)

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        self.doc_ids.append(doc_id)
        self.lengths.append(len(ids))
        self.pending.append(ids)
        self.held += len(ids)
        self.total += len(ids)
        if self.held >= self.block_ids:
            self._flush(False)

    def _flush(self, all_of_it: bool) -> None:
        ids = np.concatenate(self.pending) if self.pending else np.zeros(0, np.uint32)
        whole = len(ids) if all_of_it else len(ids) // self.block_ids * self.block_ids
        for k in range(0, whole, self.block_ids):
            block = ids[k : min(k + self.block_ids, whole)]
            at = self.at
            self.index.append((at, len(block), [self._put(self.zstd.compress(p)) for p in to_planes(block, self.kind)]))
        self.pending, self.held = [ids[whole:]], len(ids) - whole

    def close(self) -> None:
        self._flush(True)
        docs_at = self.at
        null = np.array([d is None for d in self.doc_ids], bool)
        section = np.array([d or 0 for d in self.doc_ids], "<i8").tobytes() + null.tobytes() + np.array(self.lengths, "<i8").tobytes()
        self._put(self.zstd.compress(section))
        index_at = self.at
        for at, n, sizes in self.index:
            self._put(BLOCK.pack(at, n, len(sizes)) + np.array(sizes, "<u4").tobytes())
        self._put(FOOTER.pack(docs_at, index_at, len(self.index), len(self.doc_ids), self.total, self.kind == "bit", SIGNATURE))


class PlaneReader:
    """Random access to a plane file: ``documents()`` streams, ``ids(start, stop)`` seeks by the chunk index."""

    def __init__(self, source, size: int):
        self.source = source
        self.unzip = zstandard.ZstdDecompressor()
        foot = self._at(size - FOOTER.size, FOOTER.size)
        self.docs_at, index_at, blocks, self.n_docs, self.total, bit, signature = FOOTER.unpack(foot)
        if signature != SIGNATURE:
            raise ValueError("not a plane file")
        self.kind = "bit" if bit else "byte"
        self.index_at = index_at
        raw, k, self.blocks = self._at(index_at, size - FOOTER.size - index_at), 0, []
        for _ in range(blocks):
            at, n, planes = BLOCK.unpack_from(raw, k)
            k += BLOCK.size
            self.blocks.append((at, n, np.frombuffer(raw, "<u4", planes, k).tolist()))
            k += 4 * planes
        self.first = np.cumsum([0, *[n for _, n, _ in self.blocks]])

    def _at(self, at: int, n: int) -> bytes:
        self.source.seek(at)
        return self.source.read(n)

    def block(self, k: int) -> np.ndarray:
        at, n, sizes = self.blocks[k]
        raw, planes, p = self._at(at, sum(sizes)), [], 0
        for s in sizes:
            planes.append(self.unzip.decompress(raw[p : p + s]))
            p += s
        return from_planes(planes, n, self.kind)

    def table(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        raw, n = self.unzip.decompress(self._at(self.docs_at, self.index_at - self.docs_at)) if self.n_docs else b"", self.n_docs
        return np.frombuffer(raw, "<i8", n), np.frombuffer(raw, bool, n, 8 * n), np.frombuffer(raw, "<i8", n, 9 * n)

    def ids(self, start: int, stop: int) -> np.ndarray:
        lo = int(np.searchsorted(self.first, start, "right")) - 1
        hi = int(np.searchsorted(self.first, stop, "left"))
        got = [self.block(k) for k in range(max(lo, 0), hi)]
        return (np.concatenate(got) if got else np.zeros(0, np.uint32))[start - self.first[max(lo, 0)] :][: stop - start]

    def documents(self) -> Iterator[tuple[int | None, int, bytes]]:
        """(doc id, first id's index in the file, ids as little-endian bytes) in the file's order."""
        doc_ids, null, lengths = self.table()
        held, k, start = np.zeros(0, np.uint32), 0, 0
        for d, missing, n in zip(doc_ids.tolist(), null.tolist(), lengths.tolist(), strict=True):
            more = [held]
            have = len(held)
            while have < n:
                more.append(self.block(k))
                have += len(more[-1])
                k += 1
            held = np.concatenate(more) if len(more) > 1 else held
            yield (None if missing else d), start, held[:n].astype("<u4").tobytes()
            held, start = held[n:], start + n


def write_tokens(docs: DataFrame, folder: str, tokenizer: str, *, id_col: str = "doc_id", text_col: str = "text", kind: str = "byte", block_ids: int = BLOCK_IDS, level: int = 3) -> DataFrame:
    """Tokenise all documents and write plane files in ascending id order; return the manifest.

    One file for each range of ids, with columns ``part``, ``path``, ``docs``, ``ids``, ``bytes`` and
    ``first_id`` (ids in all files before).  The manifest is a row a file and is written beside them.
    Null texts are empty (their end id alone), null ids come first, repeated rows are written
    once each, an empty table gives an empty manifest.  Other columns are not read.
    """
    spark = docs.sparkSession
    small_batches(spark)
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    placed = (
        docs.select(F.col(id_col).cast("long").alias("id"), utf8(text_col).alias("body"))
        .repartitionByRange(n, F.col("id").asc_nulls_first())
        .sortWithinPartitions(F.col("id").asc_nulls_first(), F.crc32("body"))
    )

    def put(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = ChunkEncoder.of(tokenizer)
        part = TaskContext.get().partitionId()
        fs, root = pafs.FileSystem.from_uri(folder)
        fs.create_dir(root, recursive=True)
        name = f"{root}/part-{part:06d}.planes"
        trial = f"{root}/.part-{part:06d}-{uuid.uuid4().hex}"
        writer, stream = None, None
        end = np.array([END_ID], np.uint32)
        for b in document_blocks(batches, "body", TEXT_BYTES):
            if writer is None:
                stream = fs.open_output_stream(trial)
                writer = PlaneWriter(stream, kind, block_ids, level)
            texts = [x.decode("utf-8", "replace") for x in b.column("body").to_pylist()]
            for d, ids in zip(b.column("id").to_pylist(), encoder.encode(texts), strict=True):
                writer.add(d, np.concatenate([np.frombuffer(ids, "<u4"), end]))
        if writer is not None:
            writer.close()
            stream.close()
            fs.move(trial, name)
            yield pa.RecordBatch.from_pydict({"part": [part], "path": [name], "docs": [len(writer.doc_ids)], "ids": [writer.total], "bytes": [writer.at]}, schema=MANIFEST)

    rows = sorted(placed.mapInArrow(put, "part long, path string, docs long, ids long, bytes long").collect())
    total, out = 0, []
    for r in rows:
        out.append((*r, total))
        total += r["ids"]
    manifest = spark.createDataFrame(out, "part long, path string, docs long, ids long, bytes long, first_id long")
    manifest.coalesce(1).write.json(f"{folder}/manifest")
    return manifest


MANIFEST = pa.schema([("part", pa.int64()), ("path", pa.string()), ("docs", pa.int64()), ("ids", pa.int64()), ("bytes", pa.int64())])


def read_tokens(manifest: DataFrame, folder: str, id_col: str = "doc_id") -> DataFrame:
    """One row per document from the files: id, ``start``, ``n_tokens``, ``ids_crc32``, ``ids`` (little-endian bytes)."""
    files = max(1, manifest.count())

    def get(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, _ = pafs.FileSystem.from_uri(folder)
        for b in batches:
            for row in b.to_pylist():
                with fs.open_input_file(row["path"]) as f:
                    held, size = [], 0
                    for d, start, ids in PlaneReader(f, f.size()).documents():
                        held.append((d, row["first_id"] + start, len(ids) // 4, zlib.crc32(ids), ids))
                        size += len(ids)
                        if size > TEXT_BYTES:
                            yield batch(held)
                            held, size = [], 0
                    if held:
                        yield batch(held)

    def batch(rows: list[tuple]) -> pa.RecordBatch:
        a, b, c, d, e = zip(*rows, strict=True)
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(c, pa.int64()), pa.array(d, pa.int64()), pa.array(e, pa.binary())], [id_col, "start", "n_tokens", "ids_crc32", "ids"])

    return manifest.repartition(files, "part").mapInArrow(get, f"{id_col} long, start long, n_tokens long, ids_crc32 long, ids binary")


def tokens_round_trip(docs: DataFrame, tokenizer: str, **options) -> DataFrame:
    """Write all documents as plane files in the shared folder and read them back."""
    folder = scratch_path(docs.sparkSession, "token-planes")
    manifest = write_tokens(docs, folder, tokenizer, **options)
    return read_tokens(manifest, folder, options.get("id_col", "doc_id"))

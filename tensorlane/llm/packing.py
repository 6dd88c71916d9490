"""Sequence packing by non-negative least squares over length combinations.

Every document is its token ids and an end id.  Whole windows are cut from its front; the
tails (1..window-1 tokens) make a histogram of at most window-1 counts, the only thing the
driver sees.  Shallow combinations of tail lengths that fill a window exactly are
enumerated, their repeat counts fitted to the histogram by non-negative least squares and
rounded within what is there; what stays over is packed greedily, each tail continuing
where the last one ended and cut where a window ends.  Cuts fall on a grid of ``GRID`` tokens, for
which the checksums of both parts are taken when a text is tokenised, so no text is read
twice; the price is less than ``GRID`` tokens of padding for each such tail.

Which row takes which place is arithmetic on its global number in (tail length, id) order.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import document_blocks, numbered, small_batches, utf8, written
from .tokenizing import ChunkEncoder

TEXT_BYTES = 2 << 20
#: Lengths that may appear more than once or in combinations of three and four; pairs use all lengths.
COMMON_LENGTHS = 24
SWEEPS = 40
#: Tokens between the places where a tail may be cut.
GRID = 32
END = (0).to_bytes(4, "little")


def combinations(histogram: np.ndarray, window: int) -> list[tuple[int, ...]]:
    """Multisets of up to four present lengths that add up to the window, no longer than a few thousand."""
    have = {int(n) for n in np.flatnonzero(histogram) if n}
    found = {tuple(sorted((n, window - n))) for n in have if window - n in have}
    top = sorted(have, key=lambda n: (-int(histogram[n]), n))[:COMMON_LENGTHS]
    for i, a in enumerate(top):
        for k in (2, 3):
            if window - k * a in have:
                found.add(tuple(sorted((*[a] * k, window - k * a))))
        for j, b in enumerate(top[i:], i):
            if window - a - b in have:
                found.add(tuple(sorted((a, b, window - a - b))))
            for c in top[j : j + 8]:
                if window - a - b - c in have:
                    found.add(tuple(sorted((a, b, c, window - a - b - c))))
    return sorted(x for x in found if min(x) > 0)


def fit(histogram: np.ndarray, columns: list[tuple[int, ...]], sweeps: int = SWEEPS) -> np.ndarray:
    """Repeat counts x >= 0 least-squares close to the histogram: coordinate descent on sparse columns."""
    parts = [np.unique(c, return_counts=True) for c in columns]
    norms = [float((m * m).sum()) for _, m in parts]
    x, rest = np.zeros(len(columns)), histogram.astype(float).copy()
    for _ in range(sweeps):
        moved = 0.0
        for k, (n, m) in enumerate(parts):
            new = max(0.0, x[k] + float(rest[n] @ m) / norms[k])
            if new != x[k]:
                rest[n] -= (new - x[k]) * m
                moved = max(moved, abs(new - x[k]))
                x[k] = new
        if moved < 1e-3:
            break
    return x


@dataclass
class Plan:
    """Runs of global row numbers (sorted by tail length) and where each run's tails go."""

    run_start: np.ndarray
    length: np.ndarray
    per_sequence: np.ndarray  #: tails of this run in one sequence; 0 marks the greedy stream
    sequence: np.ndarray  #: first sequence of the run (of the stream for greedy runs)
    offset: np.ndarray  #: offset in a sequence, or position in the stream
    sequences: int
    window: int

    def place(self, row: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Sequence, offset, tokens before the cut (the whole length where there is none), and whether it is in the stream.

        Offsets in the stream count tails up to the grid; they order the pieces of a sequence.
        """
        k = np.searchsorted(self.run_start, row, "right") - 1
        j, n, m = row - self.run_start[k], self.length[k], np.maximum(self.per_sequence[k], 1)
        stream = self.per_sequence[k] == 0
        at = self.offset[k] + j * -(-n // GRID) * GRID
        seq = np.where(stream, self.sequence[k] + at // self.window, self.sequence[k] + j // m)
        off = np.where(stream, at % self.window, self.offset[k] + j % m * n)
        return seq, off, np.minimum(n, self.window - off), stream


def plan(histogram: np.ndarray, window: int) -> Plan:
    """``histogram[n]``: documents with a tail of n tokens, n from 0 to window - 1."""
    columns = combinations(histogram, window)
    wanted = fit(histogram, columns)
    left = histogram.astype(np.int64).copy()
    left[0] = 0
    counts = np.zeros(len(columns), np.int64)
    parts = [np.unique(c, return_counts=True) for c in columns]
    order = np.argsort(-wanted, kind="stable")
    for most in (np.floor(wanted), np.full(len(columns), np.inf)):  # round down, then top up with what still fits
        for k in order:
            n, m = parts[k]
            take = int(min(most[k], (left[n] // m).min()))
            counts[k] += take
            left[n] -= take * m
    first = np.concatenate([[0], np.cumsum(histogram)]).astype(np.int64)
    used = np.zeros(window, np.int64)
    runs, sequence = [], 0
    for k in np.flatnonzero(counts):
        n, m = parts[k]
        at = 0
        for length, times in zip(n.tolist(), m.tolist(), strict=True):
            runs.append((first[length] + used[length], length, times, sequence, at))
            used[length] += counts[k] * times
            at += length * times
        sequence += int(counts[k])
    stream = 0
    for length in range(window - 1, 0, -1):
        if left[length]:
            runs.append((first[length] + used[length], length, 0, sequence, stream))
            stream += int(left[length]) * -(-length // GRID) * GRID
    runs.sort()
    columns_of = np.array(runs or [(0, 0, 1, 0, 0)], np.int64).T
    return Plan(*columns_of, sequences=sequence + -(-stream // window), window=window)


def _tokenised(docs: DataFrame, tokenizer: str, window: int, id_col: str, text_col: str) -> DataFrame:
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = ChunkEncoder.of(tokenizer)
        for b in document_blocks(batches, "body", TEXT_BYTES):
            total, whole, tail, grid = [], [], [], []
            for ids in encoder.encode([x.decode("utf-8", "replace") for x in b.column("body").to_pylist()]):
                ids += END
                n = len(ids) // 4
                edge = n // window * window
                rest = memoryview(ids)[4 * edge :]
                total.append(n)
                whole.append([zlib.crc32(ids[4 * k : 4 * (k + window)]) for k in range(0, edge, window)])
                tail.append(zlib.crc32(rest))
                crcs, head = [], 0
                for k in range(4 * GRID, len(rest), 4 * GRID):
                    head = zlib.crc32(rest[k - 4 * GRID : k], head)
                    crcs += [head, zlib.crc32(rest[k:])]
                grid.append(np.array(crcs, "<u4").tobytes())
            yield pa.RecordBatch.from_arrays(
                [b.column("id"), pa.array(total, pa.int64()), pa.array(whole, pa.list_(pa.int64())), pa.array(tail, pa.int64()), pa.array(grid, pa.binary())],
                ["id", "doc_tokens", "whole", "tail_crc", "grid"],
            )

    return (
        docs.select(F.col(id_col).cast("long").alias("id"), utf8(text_col).alias("body"))
        .mapInArrow(cut, "id long, doc_tokens long, whole array<long>, tail_crc long, grid binary")
        .withColumn("tail", (F.col("doc_tokens") % window).cast("int"))
    )


PIECE = ["id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]


def pack(docs: DataFrame, tokenizer: str, *, window: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: id, ``start``, ``length``, ``ids_crc32``, ``doc_tokens``, ``sequence_id``, ``offset``.

    A null text is an empty one: its end id is its only token.  Repeated rows are packed once
    each; null ids are kept; an empty table gives no pieces.  Very long texts give one piece for each
    window.  Other columns are not read.
    """
    if window % GRID:
        raise ValueError(f"the window must be a multiple of {GRID}")
    small_batches(docs.sparkSession)
    tokens = written(_tokenised(docs, tokenizer, window, id_col, text_col), "pack-tokens")
    histogram = np.zeros(window, np.int64)
    for r in tokens.groupBy("tail").count().collect():  # at most ``window`` rows
        histogram[r["tail"]] = r["count"]
    layout = plan(histogram, window)
    rows, n = numbered(tokens, ["tail", "id", "tail_crc", "doc_tokens"], "pack-rows")

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            number = b.column("row_number").to_numpy(zero_copy_only=False).astype(np.int64)
            total, tail = (b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("doc_tokens", "tail"))
            seq, off, before, stream = layout.place(number)
            crc = b.column("tail_crc").to_numpy(zero_copy_only=False).astype(np.int64)
            second = np.flatnonzero(before < tail)
            after = np.zeros(len(second), np.int64)
            for k, r in enumerate(second):
                pair = np.frombuffer(b.column("grid")[int(r)].as_buffer(), "<u4", 2, 8 * (before[r] // GRID - 1))
                crc[r], after[k] = pair
            every = np.concatenate([np.arange(b.num_rows), second])
            edge = total - tail
            columns = [
                np.concatenate([edge, edge[second] + before[second]]), np.concatenate([before, tail[second] - before[second]]), np.concatenate([crc, after]),
                total[every], np.concatenate([seq, seq[second] + 1]), np.concatenate([off, np.zeros(len(second), np.int64)]),
            ]
            yield pa.RecordBatch.from_arrays([b.column("id").take(pa.array(every)), *map(pa.array, columns), pa.array(stream[every])], [*PIECE, "stream"])

    shape = ", ".join(f"{c} long" for c in PIECE) + ", stream boolean"
    tails = rows.filter(F.col("tail") > 0).select("id", "doc_tokens", "tail", "tail_crc", "grid", "row_number").mapInArrow(place, shape)
    # the greedy stream is a small rest; a sequence of it has window / GRID pieces at most
    order = Window.partitionBy("sequence_id").orderBy("offset").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    stream = tails.filter("stream").withColumn("offset", F.sum("length").over(order) - F.col("length"))
    whole = rows.select("id", "doc_tokens", "row_number", F.posexplode("whole").alias("k", "ids_crc32")).select(
        "id", (F.col("k").cast("long") * window).alias("start"), F.lit(window).cast("long").alias("length"), "ids_crc32", "doc_tokens",
        (F.lit(layout.sequences) + F.col("k").cast("long") * n + F.col("row_number")).alias("sequence_id"), F.lit(0).cast("long").alias("offset"),
    )
    out = whole.unionByName(tails.filter(~F.col("stream")).drop("stream")).unionByName(stream.drop("stream"))
    return out.withColumnRenamed("id", id_col)

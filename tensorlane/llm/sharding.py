"""Reproducible global shuffle into shards by a Feistel permutation with cycle walking.

Row numbers 0..N-1 are permuted by a balanced Feistel network on the smallest even
number of bits that holds N; values that fall outside are walked along their cycle until
they come back inside, which keeps the map a bijection on 0..N-1.  Position p goes to
shard p mod S, slot p div S, so shard counts differ by one at most, slots have no gaps,
and either direction is computed without a table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import mix, numbered, utf8

ROUNDS = 6


class FeistelPermutation:
    """A keyed bijection on 0..n-1, with its inverse."""

    def __init__(self, n: int, seed: int = 0, rounds: int = ROUNDS):
        self.n = n
        self.half = max(1, (max(1, n - 1).bit_length() + 1) // 2)
        self.mask = np.uint64((1 << self.half) - 1)
        self.keys = mix(np.arange(1, rounds + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed))

    def _network(self, x: np.ndarray, keys: np.ndarray, back: bool) -> np.ndarray:
        left, right = x >> np.uint64(self.half), x & self.mask
        for k in keys:
            if back:
                left, right = right ^ (mix(left ^ k) & self.mask), left
            else:
                left, right = right, left ^ (mix(right ^ k) & self.mask)
        return (left << np.uint64(self.half)) | right

    def _walk(self, x, keys: np.ndarray, back: bool) -> np.ndarray:
        out = self._network(np.asarray(x).astype(np.uint64), keys, back)
        while (outside := out >= np.uint64(self.n)).any():
            out[outside] = self._network(out[outside], keys, back)
        return out.astype(np.int64)

    def forward(self, x) -> np.ndarray:
        return self._walk(x, self.keys, False)

    def inverse(self, y) -> np.ndarray:
        return self._walk(y, self.keys[::-1], True)


def shard_rows(docs: DataFrame, shards: int, *, id_col: str = "doc_id", text_col: str = "text", seed: int = 0) -> DataFrame:
    """One row per document: id, ``size`` (UTF-8 bytes + 8), ``text_crc32``, ``row_number``, ``shard``, ``slot``.

    Row numbers follow (id, crc, size), nulls first, so the result depends on the rows alone,
    not on how they are partitioned.  Null texts count as empty.  Repeated rows get a row
    number each; they tie, and being alike they are interchangeable.  An empty table gives no
    rows.  Columns other than the two named are not read.  Law: ``rows`` (counts at most one
    apart).
    """
    if shards < 1:
        raise ValueError("shards must be positive")
    light = docs.select(
        F.col(id_col),
        (F.octet_length(utf8(text_col)) + F.lit(8)).cast("long").alias("size"),
        F.crc32(utf8(text_col)).alias("text_crc32"),
    )
    rows, n = numbered(light, [id_col, "text_crc32", "size"], "shard-rows")

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        permutation = FeistelPermutation(n, seed)
        for b in batches:
            at = permutation.forward(b.column("row_number").to_numpy(zero_copy_only=False)) if b.num_rows else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays(
                [*b.columns, pa.array((at % shards).astype(np.int32)), pa.array(at // shards)],
                [*b.schema.names, "shard", "slot"],
            )

    schema = T.StructType([*rows.schema.fields, T.StructField("shard", T.IntegerType()), T.StructField("slot", T.LongType())])
    return rows.mapInArrow(place, schema)


def row_at(shard: int, slot: int, shards: int, n: int, seed: int = 0) -> int:
    """The row number that stands in a slot of a shard."""
    return int(FeistelPermutation(n, seed).inverse(np.array([slot * shards + shard]))[0])

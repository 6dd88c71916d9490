"""Token counts by counting the pieces of each distinct pre-token once.

The pieces of the BPE model never hold its space mark after another character (checked when
the model is loaded), so a text splits before each run of spaces into pre-tokens that
are encoded independently.  The distinct pre-tokens of the corpus are counted once
each, distributed; documents hold only pre-token frequencies, and a join and a sum give the
totals.  No token ids are kept.

The join has two sides of a size that is checked: the most frequent pre-tokens, a bounded
head, are looked up in place, and the rare rest goes through a shuffled join.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import document_blocks, small_batches, utf8, written

TEXT_BYTES = 4 << 20
#: Most pre-tokens in the head, and most bytes of its strings: the bound of what is sent to every worker.
HEAD_ROWS = 200_000
HEAD_BYTES = 4 << 20
#: A head pre-token stands in at least this many blocks of text.
HEAD_BLOCKS = 2

MARK = "▁"
_RUNS = re.compile(" *[^ ]+| +")


class PieceCounter:
    """Counts of pieces by the sentencepiece library, for whole texts or for pre-tokens."""

    _by_path: dict[str, PieceCounter] = {}

    def __init__(self, path: str):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces = map(self.model.id_to_piece, range(self.model.get_piece_size()))
        if any(MARK in p.lstrip(MARK) for p in pieces):
            raise ValueError("a piece of this model crosses a space; its texts don't split into pre-tokens")
        # an empty string stands for a space mark alone, which the model adds only where text follows
        self.mark = len(self.model.encode("a ")) - len(self.model.encode("a"))

    @classmethod
    def of(cls, path: str) -> PieceCounter:
        if path not in cls._by_path:
            cls._by_path[path] = cls(path)
        return cls._by_path[path]

    def count(self, texts: list[str]) -> list[int]:
        return [len(x) if t else self.mark for t, x in zip(texts, self.model.encode(texts, num_threads=1), strict=True)]


def pretokens(text: str) -> list[str]:
    """Strings whose counts, each by itself, add up to the text's.

    The model puts one space mark before a text; each string here goes without the first
    space of its run in return.
    """
    if MARK in text:
        text = text.replace(MARK, " ")
    if "  " not in text and not text.startswith(" ") and not text.endswith(" "):
        return text.split(" ") if text else []
    return [t[1:] for t in _RUNS.findall(" " + text)]


def _decoded(batch: pa.RecordBatch) -> list[str]:
    return [x.decode("utf-8", "replace") for x in batch.column("body").to_pylist()]


def count_tokens(docs: DataFrame, model_path: str, *, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text", head_rows: int = HEAD_ROWS, head_bytes: int = HEAD_BYTES) -> DataFrame:
    """One row per document: id, ``n_bytes``, ``n_tokens``, ``over_limit`` (more than ``limit`` tokens).

    Null texts count as empty (no tokens).  Rows that repeat an id are counted one by one,
    null ids are kept, and an empty table gives no rows.  Other columns are not read.
    """
    spark = docs.sparkSession
    small_batches(spark)
    body = docs.select(F.col(id_col).cast("long").alias("id"), utf8(text_col).alias("body"))

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in document_blocks(batches, "body", TEXT_BYTES):
            seen: Counter = Counter()
            for t in _decoded(b):
                seen.update(pretokens(t))
            yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], ["pretoken", "uses"])

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = PieceCounter.of(model_path)
        for b in batches:
            n = counter.count(b.column("pretoken").to_pylist())
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(n, pa.int32())], [*b.schema.names, "pieces"])

    distinct = body.mapInArrow(gather, "pretoken string, uses long").groupBy("pretoken").agg(F.sum("uses").alias("uses"), F.count("*").alias("blocks"))
    pieces = written(distinct.mapInArrow(encode, "pretoken string, uses long, blocks long, pieces int"), "pretoken-pieces")

    ranked = pieces.filter((F.col("blocks") >= HEAD_BLOCKS) & (F.octet_length("pretoken") <= 64)).orderBy(F.desc("uses"), "pretoken").limit(head_rows)
    head, size = {}, 0
    for r in ranked.select("pretoken", "pieces").toLocalIterator():
        size += len(r["pretoken"].encode())
        if size > head_bytes:
            break
        head[r["pretoken"]] = r["pieces"]
    shared = spark.sparkContext.broadcast(head)

    def frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value
        for b in document_blocks(batches, "body", TEXT_BYTES):
            sums, rest, rest_n, offsets = [], [], [], [0]
            for t in _decoded(b):
                split = pretokens(t)
                got = list(map(known.get, split))
                missing = got.count(None)
                if missing:
                    rare = Counter([p for p, n in zip(split, got, strict=True) if n is None])
                    rest += rare.keys()
                    rest_n += rare.values()
                    got = filter(None, got)
                sums.append(sum(got))
                offsets.append(len(rest))
            frequency = pa.StructArray.from_arrays([pa.array(rest, pa.string()), pa.array(rest_n, pa.int32())], ["pretoken", "times"])
            lists = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), frequency)
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("at"), b.column("n_bytes"), pa.array(sums, pa.int64()), lists], ["id", "at", "n_bytes", "head", "rest"])

    rows = written(
        body.withColumn("at", F.monotonically_increasing_id()).withColumn("n_bytes", F.octet_length("body").cast("long"))
        .select("id", "at", "n_bytes", "body")
        .mapInArrow(frequencies, "id long, at long, n_bytes long, head long, rest array<struct<pretoken string, times int>>"),
        "pretoken-frequencies",
    )
    rare = (
        rows.select("at", F.explode("rest").alias("f"))
        .select("at", "f.pretoken", "f.times")
        .join(pieces.select("pretoken", "pieces"), "pretoken")
        .groupBy("at").agg(F.sum(F.col("times").cast("long") * F.col("pieces")).alias("tail"))
    )
    total = F.col("head") + F.coalesce("tail", F.lit(0).cast("long"))
    return rows.drop("rest").join(rare, "at", "left").select(
        F.col("id").alias(id_col), "n_bytes", total.alias("n_tokens"), (total > limit).alias("over_limit")
    )

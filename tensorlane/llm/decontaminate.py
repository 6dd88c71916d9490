"""Benchmark decontamination by suffix arrays over shards of the training text.

A shard is a block of whole documents.  Its words become numbers of the test vocabulary (0
for any other word, which no test word equals), and the suffixes that can match at all -
those whose first two words stand together in some test item, or single words of one-word
items - are sorted by their first ``window`` words: the shard's suffix array.  Every test
suffix is binary-searched in it, all suffixes of the block of tests at once.  The range it
finds gives the verbatim occurrences of a window and their places; the neighbours of the
range give the longest match.

Tests are held in blocks of bounded size; each block is one narrow pass over the documents,
which carries the spans found so far, so nothing is shuffled.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, buffers, document_blocks, lower_table, small_batches, utf8

TEXT_BYTES = 8 << 20
#: Bound of the test text that one pass holds (and sends to every worker).
TEST_BYTES = 32 << 20
#: Bits of a word's number in a key: three words to a 64-bit column, or two where a block has more distinct words.
PACK_BITS, WIDE_BITS = 21, 31


def contamination_words() -> Words:
    """Runs of ASCII letters, digits and non-ASCII characters, in lower case."""
    b = np.arange(256)
    is_word = ((b >= 48) & (b <= 57)) | ((b >= 97) & (b <= 122)) | ((b >= 65) & (b <= 90)) | (b >= 128)
    return Words(is_word, lower_table())


def _concatenated(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(b"".join(texts), np.uint8), np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)


def _key_columns(ids: np.ndarray, at: np.ndarray, depth: int, bits: int) -> np.ndarray:
    """The first ``depth`` words of the suffixes at ``at``, a few to a 64-bit column; 0 ends a suffix for good."""
    alive, per = np.ones(len(at), bool), 63 // bits
    columns = np.zeros((-(-depth // per), len(at)), np.int64)
    for d in range(depth):
        word = np.where(alive, ids[np.minimum(at + d, len(ids) - 1)], 0)
        alive &= word != 0
        columns[d // per] |= word.astype(np.int64) << (bits * (per - 1 - d % per))
    return columns


@dataclass
class TestIndex:
    """Suffixes of a block of test items."""

    item_ids: list[str | None]
    vocabulary: np.ndarray  #: sorted word hashes
    ids: np.ndarray  #: word numbers of all items, each item followed by 0
    item: np.ndarray  #: item of each position
    window: int
    start: np.ndarray  #: where windows start
    length: np.ndarray  #: and how long they are
    pairs: np.ndarray  #: sorted pairs of words that stand together
    single: np.ndarray  #: words of one-word items
    bits: int  #: of a word's number
    once: np.ndarray  #: one window of each group of equal ones
    items_from: np.ndarray  #: where each group's items start (one more at the end)
    items: np.ndarray  #: distinct items of the groups

    @classmethod
    def build(cls, items: list[tuple[str, bytes]], window: int) -> TestIndex:
        data, off = _concatenated([t for _, t in items])
        hashes, first = contamination_words().of(data, off)
        vocabulary = np.unique(hashes)
        bits = PACK_BITS if len(vocabulary) < (1 << PACK_BITS) - 1 else WIDE_BITS
        ids = np.zeros(len(hashes) + len(items), np.int64)
        item = np.repeat(np.arange(len(items)), np.diff(first) + 1)
        ids[np.arange(len(hashes)) + np.repeat(np.arange(len(items)), np.diff(first))] = np.searchsorted(vocabulary, hashes) + 1
        n = np.diff(first)
        begin = first[:-1] + np.arange(len(items))
        counts = np.where(n == 0, 0, np.maximum(1, n - window + 1))
        start = np.repeat(begin - np.concatenate([[0], np.cumsum(counts)[:-1]]), counts) + np.arange(counts.sum())
        length = np.repeat(np.minimum(n, window), counts)
        joined = (ids[:-1] << bits | ids[1:])[(ids[:-1] > 0) & (ids[1:] > 0)]
        keys = np.concatenate([_key_columns(ids, start, window, bits), length[None], item[start][None]])
        order = np.lexsort(keys[::-1])
        keys = keys[:, order]
        new = np.ones(keys.shape, bool)
        new[:, 1:] = keys[:, 1:] != keys[:, :-1]
        group, owner = new[:-1].any(0), new.any(0)
        once = order[group]
        items_from = np.concatenate([np.flatnonzero(group[owner]), [int(owner.sum())]])
        return cls([i for i, _ in items], vocabulary, ids, item, window, start, length, np.unique(joined), np.unique(ids[start[length == 1]]), bits, once, items_from, keys[-1][owner])

    def numbers(self, hashes: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Word numbers of documents, each document followed by 0."""
        at = np.minimum(np.searchsorted(self.vocabulary, hashes), max(len(self.vocabulary) - 1, 0))
        known = self.vocabulary[at] == hashes if len(self.vocabulary) else np.zeros(len(hashes), bool)
        ids = np.zeros(len(hashes) + len(first) - 1, np.int64)
        ids[np.arange(len(hashes)) + np.repeat(np.arange(len(first) - 1), np.diff(first))] = np.where(known, at + 1, 0)
        return ids


class ShardSuffixArray:
    """The sorted suffixes of one shard that share at least their first words with some test suffix."""

    def __init__(self, ids: np.ndarray, tests: TestIndex):
        self.ids, self.tests = ids, tests
        known = np.flatnonzero(ids[:-1]) if len(ids) else np.zeros(0, np.int64)
        pair = ids[known] << tests.bits | ids[known + 1] if len(known) else known
        at = np.minimum(np.searchsorted(tests.pairs, pair), max(len(tests.pairs) - 1, 0))
        keep = tests.pairs[at] == pair if len(tests.pairs) else np.zeros(len(known), bool)
        if len(tests.single):
            keep |= np.isin(ids[known], tests.single)
        suffixes = known[keep]
        keys = _key_columns(ids, suffixes, tests.window, tests.bits)
        order = np.lexsort(keys[::-1])
        self.suffixes, self.keys = suffixes[order], keys[:, order]

    def _bound(self, low: np.ndarray, beyond: np.ndarray) -> np.ndarray:
        """For each sought key: how many suffixes are smaller (or not larger, where ``beyond``)."""
        n = low.shape[1]
        lo, hi = np.zeros(n, np.int64), np.full(n, len(self.suffixes), np.int64)
        while (open_ := lo < hi).any():
            mid = (lo + hi) // 2
            probe = self.keys[:, np.minimum(mid, len(self.suffixes) - 1)]
            less, same = np.zeros(n, bool), np.ones(n, bool)
            for have, want in zip(probe, low, strict=True):
                less |= same & (have < want)
                same &= have == want
            go = open_ & (less | (same & beyond))
            lo = np.where(go, mid + 1, lo)
            hi = np.where(open_ & ~go, mid, hi)
        return lo

    def search(self, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The range of suffixes that start with each of these test windows."""
        t = self.tests
        low, per = _key_columns(t.ids, t.start[which], t.window, t.bits), 63 // t.bits
        high = low.copy()  # shorter windows match any continuation
        for d in range(t.window):
            high[d // per] |= np.where(d >= t.length[which], (1 << t.bits) - 1, 0) << (t.bits * (per - 1 - d % per))
        none = np.zeros(low.shape[1], bool)
        return self._bound(low, none), self._bound(high, ~none)

    def longest(self) -> tuple[np.ndarray, np.ndarray]:
        """For every window's start, the longest verbatim match of its suffix in this shard and where it is."""
        lo, hi = self.search(np.arange(len(self.tests.start)))
        best, where = np.zeros(len(lo), np.int64), np.full(len(lo), -1)
        t = self.tests
        if not len(self.suffixes):
            return best, where
        for near in (np.maximum(lo - 1, 0), np.minimum(lo, len(self.suffixes) - 1)):  # no full window: a neighbour is nearest
            n = self._common(t.start, self.suffixes[near])
            better = n > best
            best[better], where[better] = n[better], self.suffixes[near][better]
        owner = np.repeat(np.arange(len(lo)), hi - lo)
        inside = np.arange(len(owner)) - np.repeat(np.cumsum(hi - lo) - (hi - lo), hi - lo) + lo[owner]
        n = self._common(t.start[owner], self.suffixes[inside])
        for k in np.lexsort((-self.suffixes[inside], n)):  # the last that stays is the longest, first in the shard
            if n[k] >= best[owner[k]]:
                best[owner[k]], where[owner[k]] = n[k], self.suffixes[inside[k]]
        return best, where

    def _common(self, test_at: np.ndarray, shard_at: np.ndarray) -> np.ndarray:
        n, live, d = np.zeros(len(test_at), np.int64), np.arange(len(test_at)), 0
        a, b = self.tests.ids, self.ids
        while len(live):
            x, y = test_at[live] + d, shard_at[live] + d
            ok = (x < len(a)) & (y < len(b))
            ok[ok] = (a[x[ok]] == b[y[ok]]) & (a[x[ok]] != 0)
            live = live[ok]
            n[live] += 1
            d += 1
        return n


def _hits(array: ShardSuffixArray, first: np.ndarray) -> tuple[list[np.ndarray], list[list[str]]]:
    """For each document of the shard: merged spans of hit words (start, end, ...) and the items found."""
    t = array.tests
    lo, hi = array.search(t.once)
    found = np.flatnonzero(hi > lo)
    n = (hi - lo)[found]
    owner = np.repeat(found, n)
    place = array.suffixes[np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n) + lo[owner]]
    n_docs = len(first) - 1
    begins = first[:-1] + np.arange(n_docs)  # every document is followed by one 0
    doc = np.searchsorted(begins, place, "right") - 1
    cover = np.zeros(len(array.ids) + 1, np.int32)
    np.add.at(cover, place, 1)
    np.add.at(cover, place + t.length[t.once[owner]], -1)
    hit = np.concatenate([[False], np.cumsum(cover[:-1]) > 0, [False]])
    edges = np.flatnonzero(hit[1:] != hit[:-1])
    edge_doc = np.searchsorted(begins, edges[::2], "right") - 1
    spans = [np.zeros(0, np.int64)] * n_docs
    local = edges.reshape(-1, 2) - begins[edge_doc][:, None]
    for d in np.unique(edge_doc):
        spans[d] = local[edge_doc == d].ravel() if len(edge_doc) < 64 else local[np.searchsorted(edge_doc, d) : np.searchsorted(edge_doc, d, "right")].ravel()
    items: list[list[str]] = [[] for _ in range(n_docs)]
    met = np.unique(doc * len(t.once) + owner) if len(owner) else np.zeros(0, np.int64)  # a window counts once a document
    from_, to = t.items_from[met % max(len(t.once), 1)], t.items_from[met % max(len(t.once), 1) + 1]
    copies = to - from_
    at = np.arange(copies.sum()) - np.repeat(np.cumsum(copies) - copies, copies) + np.repeat(from_, copies)
    for key in np.unique(np.repeat(met // max(len(t.once), 1), copies) * max(len(t.item_ids), 1) + t.items[at]).tolist():
        items[key // len(t.item_ids)].append(t.item_ids[key % len(t.item_ids)])
    return spans, items


def merged(a: list[int], b: list[int]) -> list[int]:
    """The union of two lists of spans, each start, end, start, end ..."""
    out: list[int] = []
    for s, e in sorted([*zip(a[::2], a[1::2], strict=True), *zip(b[::2], b[1::2], strict=True)]):
        if out and s <= out[-1]:
            out[-1] = max(out[-1], e)
        else:
            out += [s, e]
    return out


def _test_blocks(tests: DataFrame, item_col: str, text_col: str, most: int) -> Iterator[list[tuple[str, bytes]]]:
    """Test items, in blocks of at most ``most`` bytes (an item larger than that stands alone)."""
    block, size = [], 0
    rows = tests.select(F.col(item_col).cast("string").alias("item"), utf8(text_col).alias("body"))
    for r in rows.toLocalIterator():
        if block and size + len(r["body"]) > most:
            yield block
            block, size = [], 0
        block.append((r["item"], bytes(r["body"])))
        size += len(r["body"])
    if block:
        yield block


def find_contamination(docs: DataFrame, tests: DataFrame, *, window: int = 10, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", keep: tuple[str, ...] = (), test_bytes: int = TEST_BYTES) -> DataFrame:
    """Per document: id, ``keep`` columns, ``n_words``, ``spans`` of hit words (start, end, ...), ``items`` found.

    Null texts have no words.  Items without words are never found; items with a null id count as one item
    that has no name in the digest; items that repeat an id count once.  Very long texts are read whole, one at a time.  Repeated documents are judged one by one, an empty table of
    documents gives no rows and an empty table of tests finds nothing.  Columns not named are
    not read.
    """
    spark = docs.sparkSession
    small_batches(spark)
    shape = "id long, body binary, n_words long, spans array<long>, items array<string>"
    extra = [c for c in docs.columns if c in keep and c != id_col]
    rows = docs.select(
        F.col(id_col).cast("long").alias("id"), utf8(text_col).alias("body"), F.lit(0).cast("long").alias("n_words"),
        F.array().cast("array<long>").alias("spans"), F.array().cast("array<string>").alias("items"), *[F.col(c).alias(f"keep_{c}") for c in extra],
    )
    shape += "".join(f", `keep_{c}` {docs.schema[c].dataType.simpleString()}" for c in extra)

    def one_pass(block: list[tuple[str, bytes]]):
        shared = spark.sparkContext.broadcast(block)

        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index, words = TestIndex.build(shared.value, window), contamination_words()
            for b in document_blocks(batches, "body", TEXT_BYTES):
                hashes, first = words.of(*buffers(b.column("body")))
                spans, items = _hits(ShardSuffixArray(index.numbers(hashes, first), index), first)
                for k, (s, i) in enumerate(zip(b.column("spans").to_pylist(), b.column("items").to_pylist(), strict=True)):
                    spans[k] = merged(s, spans[k].tolist())
                    items[k] = sorted({*i, *items[k]}, key=lambda x: (x is None, x))
                put = {"n_words": pa.array(np.diff(first)), "spans": pa.array(spans, pa.list_(pa.int64())), "items": pa.array(items, pa.list_(pa.string()))}
                yield pa.RecordBatch.from_arrays([put.get(c, b.column(c)) for c in b.schema.names], b.schema.names)

        return scan

    passes = 0
    for block in _test_blocks(tests, item_col, item_text, test_bytes):  # the driver holds one block at a time
        rows = rows.mapInArrow(one_pass(block), shape)
        passes += 1
    if not passes:
        rows = rows.mapInArrow(one_pass([]), shape)
    return rows.select(F.col("id").alias(id_col), *[F.col(f"keep_{c}").alias(c) for c in extra], "n_words", "spans", "items")


def digest(found: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The counts and the digest of the items found, in place of spans and items."""
    hit = F.aggregate(
        F.sequence(F.lit(0), F.expr("greatest(size(spans) div 2 - 1, 0)")), F.lit(0).cast("long"),
        lambda n, k: n + F.when(F.size("spans") > 0, F.get("spans", k * 2 + 1) - F.get("spans", k * 2)).otherwise(F.lit(0)),
    )
    return found.select(
        id_col, "n_words", hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", F.array_sort("items")), 256).alias("items_sha256"), (hit > 0).alias("contaminated"),
    )


def longest_matches(docs: DataFrame, tests: DataFrame, *, window: int = 10, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """For each test suffix that starts a window: ``item``, ``word`` (its place), ``length`` of its longest verbatim match in any shard, and where (``doc``, ``doc_word``).

    Ties go to the smallest document id, then place.  Suffixes whose first two words match nowhere have no row.
    """
    spark = docs.sparkSession
    small_batches(spark)
    out = None
    for block in _test_blocks(tests, item_col, item_text, TEST_BYTES):
        shared = spark.sparkContext.broadcast(block)

        def scan(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            index, words = TestIndex.build(shared.value, window), contamination_words()
            for b in document_blocks(batches, "body", TEXT_BYTES):
                hashes, first = words.of(*buffers(b.column("body")))
                n, where = ShardSuffixArray(index.numbers(hashes, first), index).longest()
                got = np.flatnonzero(n)
                begins = first[:-1] + np.arange(len(first) - 1)
                doc = np.searchsorted(begins, where[got], "right") - 1
                at = index.start[got]
                item_begin = np.searchsorted(index.item, index.item[at])
                yield pa.RecordBatch.from_arrays(
                    [pa.array([index.item_ids[k] for k in index.item[at]], pa.string()), pa.array(at - item_begin), pa.array(n[got]), b.column("id").take(pa.array(doc)), pa.array(where[got] - begins[doc])],
                    ["item", "word", "length", "doc", "doc_word"],
                )

        rows = docs.select(F.col(id_col).cast("long").alias("id"), utf8(text_col).alias("body")).mapInArrow(scan, "item string, word long, length long, doc long, doc_word long")
        out = rows if out is None else out.unionByName(rows)
    if out is None:
        return spark.createDataFrame([], "item string, word long, length long, doc long, doc_word long")
    best = F.min_by(F.struct("length", "doc", "doc_word"), F.struct(-F.col("length"), "doc", "doc_word"))
    return out.groupBy("item", "word").agg(best.alias("best")).select("item", "word", "best.*")


def remove_contaminated(docs: DataFrame, tests: DataFrame, **options) -> DataFrame:
    """The documents, all their columns, without those that hold a test window."""
    id_col = options.get("id_col", "doc_id")
    found = find_contamination(docs, tests, keep=tuple(docs.columns), **options)
    return found.filter(F.size("spans") == 0).select(*docs.columns) if id_col in docs.columns else found


def items_digest(items: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()

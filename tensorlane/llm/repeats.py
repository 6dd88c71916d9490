"""Removal of passages that repeat, by a depth-limited radix sort of suffixes.

A window is the first ``least`` bytes of a suffix.  Suffixes are sorted no deeper than
that, in passes over ever longer digits, the most significant first; a suffix leaves the
sort as soon as its group decides it.

1. The first digit of a window is its smallest gram of ``GRAM`` bytes by hash, leftmost of ties.
   Neighbouring windows with the same gram form a run that is handled as one.  A gram that
   occurs in one run only decides its windows: none is repeated.  Runs that are equal as
   a whole decide theirs: all are.
2. What is left is cut, counting from the gram, into segments of ``SEGMENT`` windows; the digit
   is the bytes that all windows of a segment share.  The same two rules decide again.
3. The last digit is the window itself: equal groups are exactly the repeated windows.

Groups are only counted, never gathered, and equal runs are told apart by one witness, so
large groups of copies cost a count; the counts of the few crowded groups are broadcast to their rows.
Texts that hold any repeated gram are set aside once, picked where they lie by a bitmap of hashes, and used for
all later passes.  What removes bytes is always an equality of 128 bits: a digit and a whole, or two hashes
of the window.

The sort doesn't care what a text is made of: the same passes run over bytes, or over words (each a
64-bit hash), where a passage counts by its number of words however short they are.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import HEAVY_KEYS, SPACE_BYTES, RangeHash, Words, buffers, counted, document_blocks, drop_written, join_by_count, mix, small_batches, utf8, written

#: A window is so many times as long as the gram that is its first digit.
GRAMS = 4
#: Windows of a segment, at most.
SEGMENT = 16
TEXT_BYTES = 4 << 20
#: Windows of a text that are handled at once; a gram's place must fit the low bits of its rank.
PLACE_BITS = 20
LOW_BITS = np.uint64((1 << PLACE_BITS) - 1)
#: The last pass hashes each window a second time, with byte values of this seed.
CHECK_SEED = 11
CHUNK = 1 << (PLACE_BITS - 1)
#: Runs of a text that lie no further apart are hashed together.
GAP = 4096
#: A picked text has so many bits in the bitmap, if that stays under so many blocks (4 kB each); with fewer than the least, texts are joined instead.
PICK_BITS, LEAST_BITS, PICK_BLOCKS = 32, 8, 16_384
RUN = "key binary, digit long, whole long, place int, lo long, hi long"
NAMES = ["key", "digit", "whole", "place", "lo", "hi"]


def sliding_minimum(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every window of ``width`` values, from running minima of blocks."""
    out = len(values) - width + 1
    if out <= 0:
        return np.zeros(0, values.dtype)
    full = np.full(-(-len(values) // width) * width, np.iinfo(values.dtype).max, values.dtype)
    full[: len(values)] = values
    blocks = full.reshape(-1, width)
    rear = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    fore = np.minimum.accumulate(blocks, axis=1).ravel()
    return np.minimum(rear[:out], fore[width - 1 : width - 1 + out])


class Bytes:
    """Texts as arrays of bytes."""

    def __init__(self):
        self.hashes, self.others = RangeHash(), RangeHash(seed=CHECK_SEED)

    def of(self, column) -> list[np.ndarray]:
        return [np.frombuffer(x.as_buffer(), np.uint8) for x in column]


class _WordRanges(RangeHash):
    """Hashes of ranges of word hashes; a seed makes them another function."""

    def _terms(self, data: np.ndarray) -> np.ndarray:
        return mix(data ^ self.values[0])


class WordHashes:
    """Texts as arrays of word hashes; words are runs of bytes other than ASCII white space."""

    def __init__(self):
        is_word = np.ones(256, bool)
        is_word[list(SPACE_BYTES)] = False
        self.words = Words(is_word)
        self.hashes, self.others = _WordRanges(), _WordRanges(seed=CHECK_SEED)

    def of(self, column) -> list[np.ndarray]:
        words, first = self.words.of(*buffers(column))
        return np.split(words, first[1:-1])


def runs_of(text: np.ndarray, least: int, hashes: RangeHash) -> list[np.ndarray]:
    """Runs of windows with the same first digit: digit, whole, place of the gram from lo, lo, hi."""
    gram = max(1, least // GRAMS)
    found = [[np.zeros(0, t) for t in (np.uint64, np.uint64, np.int64, np.int64, np.int64)]]
    for c in range(0, len(text) - least + 1, CHUNK):
        data = text[c : c + CHUNK + least - 1]
        prefix = hashes.prefix(data)
        grams = hashes.every(prefix, gram)
        low = _lowest(grams, least - gram + 1)
        lo = np.flatnonzero(np.concatenate([[True], low[1:] != low[:-1]]))
        hi = np.concatenate([lo[1:], [len(low)]]) - 1
        place = (low[lo] & LOW_BITS).astype(np.int64)
        found.append([grams[place], _whole(hashes, prefix, place, lo, hi, least), place - lo, lo + c, hi + c])
    return [np.concatenate(x) for x in zip(*found, strict=True)]


def _lowest(grams: np.ndarray, width: int) -> np.ndarray:
    """For every window of ``width`` grams the rank of its least one, with its place in the low bits."""
    return sliding_minimum((grams & ~LOW_BITS) | np.arange(len(grams), dtype=np.uint64), width)


def runs_of_all(texts: list[np.ndarray], least: int, hashes: RangeHash) -> tuple[np.ndarray, list[np.ndarray]]:
    """``runs_of`` of each text one after the other, with the number of each text's runs; short texts are hashed and sorted together."""
    sizes = np.array([len(t) for t in texts], np.int64)
    total, parts, k = np.cumsum(sizes), [], 0
    counts = np.zeros(len(texts), np.int64)
    while k < len(texts):
        to = max(k + 1, int(np.searchsorted(total, total[k] - sizes[k] + CHUNK, "right")))
        if to == k + 1:
            parts.append(runs_of(texts[k], least, hashes))
            counts[k] = len(parts[-1][0])
        else:
            counts[k:to], found = _runs_together(texts[k:to], sizes[k:to], least, hashes)
            parts.append(found)
        k = to
    return counts, [np.concatenate(x) for x in zip(*parts, strict=True)]


def _runs_together(texts: list[np.ndarray], sizes: np.ndarray, least: int, hashes: RangeHash) -> tuple[np.ndarray, list[np.ndarray]]:
    """Runs of texts that have less than ``CHUNK`` units together, as one text whose windows never cross two of them."""
    data, ends = np.concatenate(texts), np.cumsum(sizes)
    has = sizes >= least
    if not has.any():
        return np.zeros(len(texts), np.int64), runs_of(data[:0], least, hashes)
    gram, first, final = max(1, least // GRAMS), (ends - sizes)[has], (ends - least)[has]
    prefix = hashes.prefix(data)
    grams = hashes.every(prefix, gram)
    low = _lowest(grams, least - gram + 1)
    new = np.concatenate([[True], low[1:] != low[:-1]])
    new[first] = True
    lo = np.flatnonzero(new)
    of = np.searchsorted(first, lo, "right") - 1
    inside = (of >= 0) & (lo <= final[of])
    lo, of = lo[inside], of[inside]
    hi = np.minimum(np.append(lo[1:] - 1, len(low)), final[of])
    place = (low[lo] & LOW_BITS).astype(np.int64)
    counts = np.zeros(len(texts), np.int64)
    counts[has] = np.bincount(of, minlength=len(first))
    return counts, [grams[place], _whole(hashes, prefix, place, lo, hi, least), place - lo, lo - first[of], hi - first[of]]


def _whole(hashes: RangeHash, prefix: np.ndarray, place: np.ndarray, lo: np.ndarray, hi: np.ndarray, least: int) -> np.ndarray:
    """Equal for runs that are equal byte for byte and lie alike around their gram."""
    shape = (place - lo).astype(np.uint64) << np.uint64(32) | (hi - lo).astype(np.uint64)
    return mix(hashes.ranges(prefix, lo, hi + least) ^ mix(shape + np.uint64(1)))


def _pieces(runs: np.ndarray, least: int) -> Iterator[np.ndarray]:
    """Runs (rows: digit, place from lo, lo, hi) of one text by pieces of it that are hashed at once."""
    if len(runs):
        runs = runs[np.argsort(runs[:, 2], kind="stable")]
        lo, reach = runs[:, 2], np.maximum.accumulate(runs[:, 3] + least)
        yield from np.split(runs, 1 + np.flatnonzero((lo[1:] > reach[:-1] + GAP) | (lo[1:] // CHUNK != lo[:-1] // CHUNK)))


def _spread(n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For counts: the index of each, repeated as often as it says, and the place among its repetitions."""
    of = np.repeat(np.arange(len(n)), n)
    return of, np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n)


def segments_of(text: np.ndarray, runs: np.ndarray, least: int, hashes: RangeHash) -> list[np.ndarray]:
    """Segments of runs (rows: digit, place from lo, lo, hi), like runs, with a longer digit."""
    width = max(1, min(SEGMENT, least // GRAMS))
    found = []
    for piece in _pieces(runs, least):
        digit, ahead, lo, hi = piece.T
        first, last = (ahead + lo - hi) // width, ahead // width
        of, k = _spread(last - first + 1)
        place, part = (lo + ahead)[of], first[of] + k
        right = place - part * width
        left = right - width + 1
        a, b = np.maximum(left, lo[of]), np.minimum(right, hi[of])
        base = int(a.min())
        prefix = hashes.prefix(text[base : int(b.max()) + least])
        # the bytes that all windows of a whole segment share lie inside every window of a clipped one
        shared = hashes.ranges(prefix, right - base, left + least - base)
        key = mix(shared ^ mix(digit.astype(np.uint64)[of] + part.astype(np.uint64)))
        found.append([key, _whole(hashes, prefix, place - base, a - base, b - base, least), place - a, a, b])
    return [np.concatenate(x) for x in zip(*found, strict=True)] if found else [np.zeros(0, np.int64)] * 5


def windows_of(text: np.ndarray, runs: np.ndarray, least: int, hashes: RangeHash, others: RangeHash) -> list[np.ndarray]:
    """All windows of runs (rows: digit, place from lo, lo, hi): hash with the digit, hash by another function, start."""
    found = []
    for piece in _pieces(runs, least):
        digit, _, lo, hi = piece.T
        of, k = _spread(hi - lo + 1)
        base, start = int(lo.min()), lo[of] + k
        part, at = text[base : int(hi.max()) + least], start - base
        own = mix(hashes.ranges(hashes.prefix(part), at, at + least) ^ digit.astype(np.uint64)[of])
        found.append([own, others.ranges(others.prefix(part), at, at + least), start])
    return [np.concatenate(x) for x in zip(*found, strict=True)] if found else [np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64)]


def _rows(keys: list[bytes], n: np.ndarray, runs: list[np.ndarray]) -> pa.RecordBatch:
    digit, whole, place, lo, hi = runs
    key = pa.array(keys, pa.binary()).take(pa.array(np.repeat(np.arange(len(keys)), n)))
    return pa.RecordBatch.from_arrays(
        [key, pa.array(digit.view(np.int64)), pa.array(whole.view(np.int64)), pa.array(place.astype(np.int32)), pa.array(lo.astype(np.int64)), pa.array(hi.astype(np.int64))], NAMES
    )


def _decided(rows: DataFrame, label: str) -> DataFrame:
    """Rows of repeated digits with ``full`` (equal to another as a whole) and ``open`` (needs a further pass).

    Of rows that are equal as a whole, one stays in the further passes as a witness.
    """
    digits = rows.groupBy("digit").agg(F.count("*").alias("n"), (F.min("whole") < F.max("whole")).alias("several")).filter("n > 1")
    digits = counted(digits, f"{label}-digits", "n")
    total, most = digits._counts
    limit = max(total // HEAVY_KEYS, 1000)
    few, crowded, known = digits.filter(F.col("n") <= limit), digits.filter(F.col("n") > limit), None
    # rows of a digit stand together after the join, so those that are equal as a whole are counted where they are
    alike = Window.partitionBy("digit", "whole")
    light = rows if most <= limit else rows.join(F.broadcast(crowded.select("digit")), "digit", "left_anti")
    out = light.join(few, "digit").withColumns({"same": F.count("*").over(alike), "witness": F.max("row").over(alike)})
    if most > limit:
        hot = rows.join(F.broadcast(crowded), "digit")
        known = counted(hot.groupBy("digit", "whole").agg(F.count("*").alias("same"), F.max("row").alias("witness")), f"{label}-groups", "same")
        out = out.unionByName(join_by_count(hot, known, ["digit", "whole"], "same"))
    full = F.col("same") > 1
    out = out.select("key", "digit", "place", "lo", "hi", full.alias("full"), (F.col("several") & (~full | (F.col("row") == F.col("witness")))).alias("open"))
    out = written(out, f"{label}-decided")
    drop_written(*(x for x in (digits, known, rows) if x is not None))
    return out


def _open_lists(decided: DataFrame) -> DataFrame:
    """Open rows gathered by the text that holds them (no more than the text itself has)."""
    return decided.filter("open").groupBy("key").agg(F.collect_list(F.struct("digit", "place", "lo", "hi")).alias("runs"))


def _list_columns(column) -> np.ndarray:
    """The structs of one Arrow list scalar as rows of numbers."""
    v = column.values
    return np.stack([v.field(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(v.type.num_fields)], 1) if v is not None and len(v) else np.zeros((0, 4), np.int64)


def merge(lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Union of half-open ranges; ranges that touch become one."""
    if not len(lo):
        return lo, hi
    order = np.argsort(lo, kind="stable")
    lo, top = lo[order], np.maximum.accumulate(hi[order])
    new = np.concatenate([[True], lo[1:] > top[:-1]])
    return lo[new], top[np.concatenate([np.flatnonzero(new)[1:] - 1, [len(lo) - 1]])]


def keyed_texts(docs: DataFrame, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """(keyed, light): documents as id, body, key of the text (128 bits of its digest ``sha``) and n_bytes; the same without bodies, written."""
    small_batches(docs.sparkSession)
    body = docs.select(F.col(id_col).cast("long").alias("id"), utf8(text_col).alias("body"))
    body = body.withColumn("sha", F.unhex(F.sha2("body", 256))).withColumn("n_bytes", F.octet_length("body").cast("long"))
    key = F.substring("sha", 1, 16)
    return body.withColumn("key", key), written(body.select("id", "sha", "n_bytes"), "repeats-light").withColumn("key", key)


def _picked(keyed: DataFrame, touched: DataFrame, label: str) -> DataFrame:
    """(key, body), written, of the rows whose key and id are in ``touched``, and of a few more (one in ``PICK_BITS`` of the others).

    Hashes of key and id are set in a bitmap that all workers get, so texts stay where they are however many there
    are.  Rows in excess change no result: no open runs are listed for them, or they are copies of a text that is gone as a whole.
    """
    n, block = touched.count(), 1 << 15
    bits = max(1, min(PICK_BITS * n, PICK_BLOCKS * block))
    if bits < LEAST_BITS * n:
        touched = touched.select(F.col("key").alias("k"), F.col("id").alias("of"))
        return written(keyed.join(touched, (F.col("key") == F.col("k")) & F.col("id").eqNullSafe(F.col("of")), "left_semi").select("key", "body"), f"{label}-texts")
    at = F.pmod(F.xxhash64("key", "id"), F.lit(bits).cast("long"))
    hashed = touched.select(F.floor(at / block).alias("block"), (at % block).alias("bit")).repartition("block")
    blocks = written(hashed.groupBy("block").agg(F.bitmap_construct_agg("bit").alias("bits")), f"{label}-bitmap")
    rows = keyed.select("key", "body", at.alias("at")).join(F.broadcast(blocks), F.floor(F.col("at") / block) == F.col("block"))
    bit = F.col("at") % block
    byte = F.conv(F.hex(F.substring("bits", F.floor(bit / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    out = written(rows.filter(F.getbit(byte, (bit % 8).cast("int")) == 1).select("key", "body"), f"{label}-texts")
    drop_written(blocks)
    return out


def repeated_spans(keyed: DataFrame, light: DataFrame, units: type, least: int, label: str) -> tuple[DataFrame, DataFrame, list[DataFrame]]:
    """(texts, spans, tables): the texts looked at again (key, body); by key the ``spans`` of units in windows that
    repeat, of copies perhaps too; and what to drop afterwards."""

    def first_pass(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unit = units()
        for b in document_blocks(batches, "body", TEXT_BYTES):
            yield _rows(b.column("key").to_pylist(), *runs_of_all(unit.of(b.column("body")), least, unit.hashes))

    runs = written(keyed.filter(F.col("n_bytes") >= least).select("key", "body").mapInArrow(first_pass, RUN).withColumn("row", F.monotonically_increasing_id()), f"{label}-runs")
    coarse = _decided(runs, f"{label}-1")
    # a text that stands more than once is gone as a whole; it is fetched only to be a witness
    copies = light.groupBy("key").agg(F.count("*").alias("copies"), F.min("id").alias("of"))
    touched = coarse.groupBy("key").agg(F.max("open").alias("has_open")).join(copies, "key").filter((F.col("copies") == 1) | F.col("has_open"))
    touched = written(touched.select("key", F.col("of").alias("id")), f"{label}-touched")
    work = _picked(keyed, touched, label)

    def second_pass(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unit = units()
        for b in document_blocks(batches, "body", TEXT_BYTES):
            found = [segments_of(t, _list_columns(r), least, unit.hashes) for t, r in zip(unit.of(b.column("body")), b.column("runs"), strict=True)]
            yield _rows(b.column("key").to_pylist(), np.array([len(x[0]) for x in found]), [np.concatenate(x) for x in zip(*found, strict=True)])

    segments = written(work.join(_open_lists(coarse), "key").select("key", "body", "runs").mapInArrow(second_pass, RUN).withColumn("row", F.monotonically_increasing_id()), f"{label}-segments")
    fine = _decided(segments, f"{label}-2")

    def last_pass(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unit = units()
        for b in document_blocks(batches, "body", TEXT_BYTES):
            found = [windows_of(t, _list_columns(r), least, unit.hashes, unit.others) for t, r in zip(unit.of(b.column("body")), b.column("runs"), strict=True)]
            key = b.column("key").take(pa.array(np.repeat(np.arange(len(found)), [len(x[2]) for x in found])))
            own, other, start = (np.concatenate(x) for x in zip(*found, strict=True))
            yield pa.RecordBatch.from_arrays([key, pa.array(own.view(np.int64)), pa.array(other.view(np.int64)), pa.array(start)], ["key", "digit", "again", "lo"])

    windows = written(work.join(_open_lists(fine), "key").select("key", "body", "runs").mapInArrow(last_pass, "key binary, digit long, again long, lo long"), f"{label}-windows")
    equal = counted(windows.groupBy("digit", "again").agg(F.count("*").alias("n")).filter("n > 1"), f"{label}-equal", "n")
    spans = [x.filter("full").select("key", "lo", (F.col("hi") + least).alias("end")) for x in (coarse, fine)]
    spans.append(join_by_count(windows, equal, ["digit", "again"], "n").select("key", "lo", (F.col("lo") + least).alias("end")))
    spans = spans[0].unionByName(spans[1]).unionByName(spans[2])
    # a set: copies of a text name the same spans
    lists = spans.groupBy("key").agg(F.collect_set(F.struct("lo", "end")).alias("spans"))
    return work, lists, [coarse, fine, windows, equal, touched, work]


def shared_words(keyed: DataFrame, light: DataFrame, words: int) -> DataFrame:
    """Per text (by key) that has any: ``n_shared_words``, its words in passages of ``words`` words that start anywhere else too."""
    _, lists, tables = repeated_spans(keyed, light, WordHashes, words, "shared")

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = []
            for spans in b.column("spans"):
                rows = _list_columns(spans)
                lo, hi = merge(rows[:, 0], rows[:, 1])
                n.append(int((hi - lo).sum()))
            yield pa.RecordBatch.from_arrays([b.column("key"), pa.array(n, pa.int64())], ["key", "n_shared_words"])

    out = written(lists.mapInArrow(measure, "key binary, n_shared_words long"), "shared-words")
    drop_written(*tables)
    return out


RESULT = "key binary, n_removed long, n_spans long, kept_sha256 string, kept binary"


def _cut(work: DataFrame, with_text: bool) -> DataFrame:
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in document_blocks(batches, "body", TEXT_BYTES):
            out = []
            for body, spans in zip(b.column("body").to_pylist(), b.column("spans"), strict=True):
                rows = _list_columns(spans)
                lo, hi = merge(rows[:, 0], rows[:, 1])
                ends = zip([0, *hi.tolist()], [*lo.tolist(), len(body)], strict=True)
                kept = b"".join(body[s:e] for s, e in ends)
                out.append((len(body) - len(kept), len(lo), hashlib.sha256(kept).hexdigest(), kept if with_text else None))
            a, n, h, t = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([b.column("key"), pa.array(a, pa.int64()), pa.array(n, pa.int64()), pa.array(h), pa.array(t, pa.binary())], ["key", "n_removed", "n_spans", "kept_sha256", "kept"])

    return work.mapInArrow(cut, RESULT)


def remove_repeats(docs: DataFrame, *, least: int = 400, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False, words: int | None = None) -> DataFrame:
    """Per document: id, ``n_bytes``, ``n_removed``, ``n_spans``, ``kept_sha256`` and, if asked for, the ``kept`` bytes.

    Every byte that lies in a string of ``least`` bytes which also starts anywhere else is removed, in the same
    document or another; matches never cross documents and are judged on the input.  Null
    texts are empty, repeated rows are copies of each other, null ids are kept, and an empty table gives no
    rows.  Very long texts are read whole, one at a time.  Other columns are not read.

    With ``words``, a column ``n_shared_words`` more: words in passages of so many words that also
    start anywhere else.  Nothing is removed for those: passages of short words reach that length in fewer bytes.
    """
    keyed, light = keyed_texts(docs, id_col, text_col)
    work, lists, tables = repeated_spans(keyed, light, Bytes, least, "repeats")
    # copies of a text may be fetched twice
    results = written(_cut(work.join(lists, "key"), with_text).dropDuplicates(["key"]), "repeats-results")
    drop_written(*tables)
    texts = light.groupBy("key").agg(F.count("*").alias("copies")).join(results, "key", "left")
    if words:
        texts = texts.join(shared_words(keyed, light, words), "key", "left")
    whole = (F.col("copies") > 1) & (F.col("n_bytes") >= least)
    out = join_by_count(light, counted(texts, "repeats-by-text", "copies"), "key", "copies")
    return out.select(
        F.col("id").alias(id_col), "n_bytes", F.when(whole, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0).cast("long"))).alias("n_removed"),
        F.when(whole, F.lit(1).cast("long")).otherwise(F.coalesce("n_spans", F.lit(0).cast("long"))).alias("n_spans"),
        F.when(whole, F.lit(hashlib.sha256(b"").hexdigest())).otherwise(F.coalesce("kept_sha256", F.lower(F.hex("sha")))).alias("kept_sha256"),
        *(["kept"] if with_text else []), *([F.coalesce("n_shared_words", F.lit(0).cast("long")).alias("n_shared_words")] if words else []),
    )

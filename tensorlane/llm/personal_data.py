"""Personal data in whole texts: fixed patterns, and spans that a conditional random field adds.

Only documents with a digit, an at sign or a plus sign can hold any; the field decodes only
the surroundings of such words, all windows of a block at once.  That is exact: a word
amid plain words is O on every best path (checked for the trained weights), so it cuts
the chain.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import buffers, document_blocks, small_batches, utf8
from .crf import EDGE, KINDS, LABELS, PAST, ChainModel, shape_ids, trained

TEXT_BYTES = 4 << 20
#: Plain words around a marked one that are decoded with it.
REACH = 4
Span = tuple[int, str, int]

# Fixed patterns, on UTF-8 bytes (all their classes are ASCII).
_LOCAL = frozenset(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(rb"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(rb"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(rb"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(rb"\+[0-9][\x20().0-9-]+[0-9]")
_NOT_DIGIT = bytes(b for b in range(256) if not 48 <= b <= 57)
_WORD = re.compile(rb"[^\x20\x09-\x0D]+")
_TRIM = b".,;:!?\"'<>[]{}"


def luhn(digits: bytes) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        d -= 48
        total += d if i % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def emails(text: bytes) -> Iterator[tuple[int, int]]:
    """Leftmost matches, found from their at signs, so that long words cost no more than their length."""
    end = at = 0
    while (at := text.find(b"@", at)) >= 0:
        start = at
        while start > end and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at) if start < at else None
        if m:
            yield start, m.end()
            end = m.end()
        at += 1


def base_spans(text: bytes) -> list[Span]:
    """(start, kind, end) in bytes, by start and kind; no overlap within a kind."""
    found = [(s, "email", e) for s, e in emails(text)]
    found += [(m.start(), "ip", m.end()) for m in _IP.finditer(text) if all(len(p.lstrip(b"0")) <= 3 and int(p.lstrip(b"0") or b"0") <= 255 for p in m[0].split(b"."))]
    for m in _CARD.finditer(text):
        digits = m[0].translate(None, _NOT_DIGIT)
        if 12 <= len(digits) <= 19 and luhn(digits):
            found.append((m.start(), "card", m.end()))
    if b"+" in text:
        found += [(m.start(), "phone", m.end()) for m in _PHONE.finditer(text) if 9 <= len(m[0].translate(None, _NOT_DIGIT)) <= 15]
    return sorted(found, key=lambda s: (s[0], KINDS.index(s[1])))


def _windows(text: bytes) -> tuple[list[tuple[int, int]], list[list[int]]]:
    """Word ranges, and runs of words that lie within ``REACH`` places of a word with a digit, at or plus sign."""
    words = [m.span() for m in _WORD.finditer(text)]
    marks = [k for k, n in enumerate(shape_ids([text[s:e] for s, e in words])) if n]
    runs: list[list[int]] = []
    for k in marks:
        lo, hi = max(0, k - REACH), min(len(words), k + REACH + 1)
        if runs and lo <= runs[-1][1]:
            runs[-1][1] = max(runs[-1][1], hi)
        else:
            runs.append([lo, hi])
    return words, runs


def field_spans(texts: list[bytes], model: ChainModel) -> list[list[Span]]:
    """Spans by Viterbi, all windows of all texts decoded in numpy batches of like length."""
    found: list[list[Span]] = [[] for _ in texts]
    jobs, whole = [], not model.forced_gap(REACH - 1)
    for d, text in enumerate(texts):
        words, runs = _windows(text)
        if whole and words:
            runs = [[0, len(words)]]
        jobs += [(hi - lo, d, [words[k] for k in range(lo, hi)], lo > 0, hi < len(words)) for lo, hi in runs]
    jobs.sort(key=lambda j: j[0])
    for at in range(0, len(jobs), 2000):
        part = jobs[at : at + 2000]
        shapes = np.full((len(part), part[-1][0] + 2), PAST)
        flat = shape_ids([texts[d][s:e] for _, d, words, _, _ in part for s, e in words])
        sizes = np.array([n for n, *_ in part])
        row = np.arange(len(part))
        shapes[np.repeat(row, sizes), np.concatenate([np.arange(1, n + 1) for n in sizes])] = flat
        # a window inside a text stands between words known to be O; at its ends a window's first word has none before
        shapes[:, 0] = EDGE
        shapes[row, sizes + 1] = np.where([more for *_, more in part], EDGE, PAST)
        starts = np.array([not inside for *_, inside, _ in part])
        labels_of = model.viterbi(shapes)[:, 1:]
        if starts.any():
            shapes[starts, :-1] = shapes[starts, 1:]
            shapes[starts, -1] = PAST
            labels_of[starts] = model.viterbi(shapes[starts])[:, :-1]
        for (_, d, words, _, _), labels in zip(part, labels_of, strict=True):
            k = 0
            while k < len(words):
                name = LABELS[labels[k]]
                k += 1
                if name == "O":
                    continue
                first, kind = k - 1, name[2:]
                while k < len(words) and LABELS[labels[k]] == f"I-{kind}":
                    k += 1
                start, end = words[first][0], words[k - 1][1]
                piece = texts[d][start:end]
                start += len(piece) - len(piece.lstrip(_TRIM))
                end -= len(piece) - len(piece.rstrip(_TRIM))
                if start < end:
                    found[d].append((start, kind, end))
    return found


def code_points(text: bytes, spans: list[Span]) -> list[Span]:
    """Byte offsets to code-point offsets."""
    if not spans or text.isascii():
        return spans
    leading = np.concatenate([[0], np.cumsum((np.frombuffer(text, np.uint8) & 0xC0) != 0x80)])
    return [(int(leading[s]), k, int(leading[e])) for s, k, e in spans]


def _joined(spans: list[Span]) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, k, e in sorted(spans, key=lambda x: (x[0], KINDS.index(x[1]), x[2])))


def spans_of(texts: list[bytes], model: ChainModel) -> list[tuple[list[Span], list[Span]]]:
    """For each text the base spans and all spans, in bytes; the field adds those that touch no base span."""
    out = []
    for base, more in zip(map(base_spans, texts), field_spans(texts, model), strict=True):
        added = [(s, k, e) for s, k, e in more if not any(s < y and x < e for x, _, y in base)] if more else []
        out.append((base, base + added))
    return out


def _marked(b: pa.RecordBatch) -> np.ndarray:
    """Documents of a batch with any digit, at or plus sign."""
    data, off = buffers(b.column("body"))
    at = np.flatnonzero(((data >= 48) & (data <= 57)) | (data == 64) | (data == 43))
    return np.flatnonzero(np.diff(np.searchsorted(at, off)))


def find(docs: DataFrame, *, model: ChainModel | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: id, ``n_email``, ``n_ip``, ``n_card``, ``n_phone`` and ``base_sha256`` of the base spans, and ``spans``.

    Spans are ``kind:start:end`` in code points, by start then kind.  Null texts are empty; repeated rows are
    searched one by one; an empty table gives no rows.  Other columns are not read.
    """
    small_batches(docs.sparkSession)
    model = model or trained()

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        empty = hashlib.sha256(b"").hexdigest()
        for b in document_blocks(batches, "body", TEXT_BYTES):
            n = b.num_rows
            counts, digests, all_spans = {k: np.zeros(n, np.int64) for k in KINDS}, [empty] * n, [""] * n
            marked = _marked(b)
            texts = b.column("body").take(pa.array(marked)).to_pylist()
            for d, text, (base, spans) in zip(marked, texts, spans_of(texts, model), strict=True):
                for _, k, _ in base:
                    counts[k][d] += 1
                digests[d] = hashlib.sha256(_joined(code_points(text, base)).encode()).hexdigest()
                all_spans[d] = _joined(code_points(text, spans))
            yield pa.RecordBatch.from_arrays([b.column("id"), *map(pa.array, counts.values()), pa.array(digests), pa.array(all_spans)], ["id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans"])

    shape = "id long, " + ", ".join(f"n_{k} long" for k in KINDS) + ", base_sha256 string, spans string"
    out = docs.select(F.col(id_col).cast("long").alias("id"), utf8(text_col).alias("body")).mapInArrow(scan, shape)
    return out.withColumnRenamed("id", id_col)


def redacted(text: bytes, spans: list[Span]) -> bytes:
    """The text with every run of overlapping spans replaced by the mark of its first span's kind."""
    out, done, at = [], 0, 0
    spans = sorted(spans, key=lambda x: (x[0], KINDS.index(x[1])))
    while at < len(spans):
        start, kind, end = spans[at]
        at += 1
        while at < len(spans) and spans[at][0] < end:
            end = max(end, spans[at][2])
            at += 1
        out += [text[done:start], f"<{kind.upper()}>".encode()]
        done = end
    return b"".join([*out, text[done:]])


def redact(docs: DataFrame, *, model: ChainModel | None = None, text_col: str = "text") -> DataFrame:
    """All columns of ``docs`` with personal data in the text replaced by marks such as ``<EMAIL>``; null texts stay null."""
    small_batches(docs.sparkSession)
    model = model or trained()
    kept = [c for c in docs.columns if c != text_col]
    rows = docs.select(*[F.col(c).alias(f"c{i}") for i, c in enumerate(kept)], utf8(text_col).alias("body"), F.col(text_col).isNull().alias("missing"))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in document_blocks(batches, "body", TEXT_BYTES):
            texts = b.column("body").to_pylist()
            marked = _marked(b)
            chosen = [texts[d] for d in marked]
            for d, (_, spans) in zip(marked, spans_of(chosen, model), strict=True):
                texts[d] = redacted(texts[d], spans)
            yield pa.RecordBatch.from_arrays([pa.array(texts, pa.binary()) if c == "body" else b.column(c) for c in b.schema.names], b.schema.names)

    out = rows.mapInArrow(scan, rows.schema)
    text = F.when(~F.col("missing"), F.col("body").cast("string")).alias(text_col)
    return out.select(*[text if c == text_col else F.col(f"c{kept.index(c)}").alias(c) for c in docs.columns])

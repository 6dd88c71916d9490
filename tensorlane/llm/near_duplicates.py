"""Near-duplicate documents by a chosen-path set similarity join over word shingles.

Every document's set of shingle hashes is sketched by ``TOKENS`` minwise tokens.  Each of
``TREES`` independent trees sends a document along one path of ``ROOT`` selected tokens; documents whose paths
meet stand in one node.  In a node of few documents all sketches are compared.  In a larger one every document is
compared with the node's first ``HUBS`` only, and the node branches again, along one or (by a bit of its
hash) two further selected tokens, unless the candidates found so far already hold all its documents
together.  That is 1.5 branches on average: pairs of a similarity under 2/3 die out on the way,
while a pair of 0.75 lives on however deep crowded nodes go.  There is no last level: nodes branch until
none is crowded.  Every branch of every level of every tree selects tokens of its own, so trees lose a pair
independently: ``path_loss`` gives the loss in all of them.

Candidates that agree in fewer tokens than a pair of the least similarity does but once in
a million are dropped (``miss=0`` keeps them all).  The rest are never spelled out as pairs: a node names a spanning
forest of them, the forests of all nodes make groups, and the text of each grouped document travels
to its group once, where all pairs are counted on their full sets.  A group of more than ``GROUP_DOCS`` documents is
cut into blocks, and each two blocks meet.  Equal sets are one document
from the start, and links are contracted to components by distributed rounds.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACE_BYTES, Words, buffers, counted, document_blocks, drop_written, join_by_count, lower_table, mix, small_batches, utf8, written

#: So many that a pair at 0.75 is lost once in 95,000 at most, however deep its nodes are crowded.
TREES = 40
#: Tokens of a tree's first path.
ROOT = 2
TOKENS = ROOT * TREES
#: Nodes of at most so many documents are compared exhaustively; a smaller number given doubles with each level, up to this one.
SMALL = 2048
#: Documents of a larger node that all its others are compared with.
HUBS = 4
#: Levels whose tokens are made at once.
LEVELS = 8
#: Most branches of a node.
BRANCHES = 2
#: Documents and shingles of a block of a group.
GROUP_DOCS = 2048
GROUP_SHINGLES = 2_000_000
#: Shingles of more documents of a group than this are counted by a matrix product.
COMMON = 8
#: Text lists of at most so many rows are sent to all workers in place of a shuffle of all texts.
LOOKUP_ROWS = 1_000_000
MISS = 1e-6
TEXT_BYTES = 4 << 20
WORDS = 5
SIGNATURE = "key binary, id long, row long, n_shingles long, tokens binary, roots binary"
MET = "a long, b long, tree int"


def shingle_words() -> Words:
    """Runs of bytes other than ASCII white space, ASCII letters in lower case."""
    is_word = np.ones(256, bool)
    is_word[list(SPACE_BYTES)] = False
    return Words(is_word, lower_table())


def _distinct(values: np.ndarray) -> np.ndarray:
    values = np.sort(values)
    new = values[1:] != values[:-1]
    return values if new.all() else np.concatenate([values[:1], values[1:][new]])


def shingle_sets(words: np.ndarray, first: np.ndarray, size: int = WORDS) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each document; a shorter one is a single shingle, none without words."""
    weights = mix(np.arange(1, size + 1, dtype=np.uint64)) | np.uint64(1)
    full = np.zeros(max(len(words) - size + 1, 0), np.uint64)  # windows that reach into the next document are never read
    for k in range(size if len(full) else 0):
        full += words[k : k + len(full)] * weights[k]
    full = mix(full + np.uint64(size))
    out = []
    for lo, hi in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        n = hi - lo
        if n >= size:
            out.append(_distinct(full[lo : hi - size + 1]))
        elif n:
            out.append(mix((words[lo:hi] * weights[:n]).sum(dtype=np.uint64, keepdims=True) + np.uint64(n)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


#: Elements of a set that meet all hash functions at once.
_STRIP = 4096


def minwise(shingles: np.ndarray, seeds: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The smallest value of each 32-bit hash function over a set."""
    xor, factor = seeds
    out = np.full(len(xor), 0xFFFFFFFF, np.uint32)
    folded = (shingles ^ (shingles >> np.uint64(32))).astype(np.uint32)
    for k in range(0, len(folded), _STRIP):
        np.minimum(out, ((folded[k : k + _STRIP] ^ xor) * factor).min(axis=1), out=out)
    return out


def least_agreement(similarity: float, tokens: int, miss: float = MISS) -> int:
    """The largest c for which a pair of that similarity agrees in fewer than c tokens with probability ``miss`` at most."""
    total, c = 0.0, 0
    while c < tokens:
        total += comb(tokens, c) * similarity**c * (1 - similarity) ** (tokens - c)
        if total > miss:
            return c
        c += 1
    return c


def path_loss(similarity: float, trees: int = TREES, levels: int | None = None, root: int = 1) -> float:
    """Probability that a pair of that similarity meets in no tree, where its nodes are crowded for so many levels (None: for ever).

    ``root`` is the number of tokens of a tree's first path.
    """
    alive = 1.0
    for _ in range(1000 if levels is None else levels):
        apart = 1 - similarity * alive
        alive = 1 - (apart + apart**2) / 2  # a node has one branch or two
    return (1 - similarity**root * alive) ** trees


def _seeds(first: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash functions number ``first`` and the ``n - 1`` after it."""
    s = mix(np.arange(first + 1, first + n + 1, dtype=np.uint64) * np.uint64(0xA24BAED4963EE407))
    return (s >> np.uint64(32)).astype(np.uint32)[:, None], (s.astype(np.uint32) | np.uint32(1))[:, None]


def first_nodes(tokens: np.ndarray) -> np.ndarray:
    """The node (a 64-bit hash) that each tree sends a document to, for rows of tokens."""
    trees = tokens.shape[1] // ROOT
    node = mix(np.arange(1, trees + 1, dtype=np.uint64) * np.uint64(0x9FB21C651E98DF25))[None, :]
    for k in range(ROOT):
        node = mix(node ^ mix(tokens[:, k : trees * ROOT : ROOT].astype(np.uint64) + np.uint64(1)))
    return node


def signatures(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", size: int = WORDS, row_col: str | None = None) -> DataFrame:
    """Per document: digest of its shingle set, id, row key (if there is one), size of the set, minwise tokens (their low 8 bits), first nodes of all trees."""
    small_batches(docs.sparkSession)

    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, seeds = shingle_words(), _seeds(0, TOKENS)
        for b in document_blocks(batches, "body", TEXT_BYTES):
            sets = shingle_sets(*words.of(*buffers(b.column("body"))), size)
            tokens = np.stack([minwise(s, seeds) for s in sets])
            low = [t.tobytes() for t in tokens.astype(np.uint8)]
            roots = [r.tobytes() for r in first_nodes(tokens)]
            yield pa.RecordBatch.from_arrays(
                [pa.array([digest(s) for s in sets], pa.binary()), b.column("id"), b.column("row"), pa.array([len(s) for s in sets], pa.int64()), pa.array(low, pa.binary()), pa.array(roots, pa.binary())],
                ["key", "id", "row", "n_shingles", "tokens", "roots"],
            )

    row = F.col(row_col) if row_col else F.lit(None)
    return docs.select(F.col(id_col).cast("long").alias("id"), row.cast("long").alias("row"), utf8(text_col).alias("body")).mapInArrow(sketch, SIGNATURE)


def digest(shingles: np.ndarray) -> bytes:
    """128 bits of a set: two sums over its mixed hashes (order plays no part) with its size."""
    n = np.uint64(len(shingles))
    with np.errstate(over="ignore"):
        a = mix(shingles + np.uint64(1)).sum(dtype=np.uint64) + n
        b = mix(shingles ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64) * np.uint64(3) + n
    return np.array([a, b], "<u8").tobytes()


def branch_tokens(bodies: DataFrame, size: int, trees: int, depth: int) -> DataFrame:
    """(num, picks): the tokens of all branches of ``LEVELS`` levels from ``depth`` on, tree by tree, for texts (num, body)."""
    each = LEVELS * BRANCHES

    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, seeds = shingle_words(), _seeds(TOKENS + depth * BRANCHES * trees, trees * each)
        for b in document_blocks(batches, "body", TEXT_BYTES):
            sets = shingle_sets(*words.of(*buffers(b.column("body"))), size)
            picks = [minwise(s, seeds).astype("<u4", copy=False).tobytes() for s in sets]
            yield pa.RecordBatch.from_arrays([b.column("num"), pa.array(picks, pa.binary())], ["num", "picks"])

    return bodies.mapInArrow(sketch, "num long, picks binary")


def _blocks(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, bool]]:
    """Sorted batches as (batch, starts of its keys, whether its last key ends there)."""
    held = None
    for b in batches:
        if held is not None and b.num_rows:
            at = np.concatenate([[0], 1 + np.flatnonzero(_new(held, keys))])
            yield held, at, _key(held, held.num_rows - 1, keys) != _key(b, 0, keys)
        held = b if b.num_rows else held
    if held is not None:
        yield held, np.concatenate([[0], 1 + np.flatnonzero(_new(held, keys))]), True


def _key(b: pa.RecordBatch, at: int, keys: list[str]) -> tuple:
    return tuple(b.column(k)[at].as_py() for k in keys)


def _new(b: pa.RecordBatch, keys: list[str]) -> np.ndarray:
    """Whether each row but the first has another key than the one before."""
    out = np.zeros(b.num_rows - 1, bool)
    for k in keys:
        v = b.column(k).to_numpy(zero_copy_only=False)
        out |= v[1:] != v[:-1]
    return out


def _met(level: DataFrame) -> DataFrame:
    """Rows (node, num, tree) whose node holds more than one."""

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, last = None, None  # a row whose node may yet hold more, and the node of the row before
        for b in batches:
            if not b.num_rows:
                continue
            if held is not None:
                [b] = pa.Table.from_batches([held, b]).combine_chunks().to_batches()
            node = b.column("node").to_numpy()
            same = node[1:] == node[:-1]
            keep = np.zeros(len(node), bool)
            keep[1:] |= same
            keep[:-1] |= same
            keep[0] |= last is not None and node[0] == last
            held, last = (None, node[-1]) if keep[-1] else (b.slice(len(node) - 1), None)
            yield b.filter(pa.array(keep))

    return level.repartition("node").sortWithinPartitions("node").mapInArrow(meet, "node long, num long, tree int")


def alike(tokens: np.ndarray, sizes: np.ndarray, least: int, percent: int) -> np.ndarray:
    """For each document of a node, the place of the one it is grouped with: those reachable by pairs of like sizes that agree in ``least`` tokens."""
    label, left = np.arange(len(sizes)), np.arange(len(sizes))
    while len(left):
        seed, left = left[0], left[1:]
        front = [seed]
        while front and len(left):
            f = front.pop()
            hit = _agree(tokens[left], sizes[left], tokens[f], sizes[f], least, percent)
            label[left[hit]] = seed
            front.extend(left[hit])
            left = left[~hit]
    return label


def _agree(ta: np.ndarray, na: np.ndarray, tb: np.ndarray, nb: np.ndarray, least: int, percent: int) -> np.ndarray:
    return ((ta == tb).sum(-1, dtype=np.int16) >= least) & (100 * np.minimum(na, nb) >= percent * np.maximum(na, nb))


def _compared(met: DataFrame, sketches: DataFrame, small: int, similarity: float, least: int) -> DataFrame:
    """Spanning forests of the candidates of all nodes as rows (a, b) without tree; of nodes of more than ``small`` documents also (node, num, tree)."""
    percent = round(similarity * 100)

    def edges(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(a.astype(np.int64)), pa.array(b.astype(np.int64)), pa.nulls(len(a), pa.int32())], ["a", "b", "tree"])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting: list[pa.RecordBatch] = []  # of a node that goes on in the next batch
        hubs = None  # of a node larger than small that goes on

        def whole(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            data, _ = buffers(part.column("tokens"))
            return part.column("num").to_numpy(), part.column("n_set").to_numpy(), data.reshape(part.num_rows, -1)

        def crowded(part: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            num, sizes, tokens = whole(part)
            for h, n, t in zip(*hubs, strict=True):
                hit = _agree(tokens, sizes, t, n, least, percent) & (num != h)
                yield edges(num[hit], np.full(hit.sum(), h))
            yield pa.RecordBatch.from_arrays([part.column("node"), part.column("num"), part.column("tree")], ["a", "b", "tree"])

        for b, at, ends in _blocks(batches, ["node"]):
            to = np.append(at[1:], b.num_rows)
            if hubs is not None or waiting or not ends:
                first, last = b.slice(0, to[0]), len(at) == 1
                if hubs is not None:
                    yield from crowded(first)
                else:
                    waiting.append(first)
                    if sum(x.num_rows for x in waiting) > small:
                        [first] = pa.Table.from_batches(waiting).combine_chunks().to_batches()
                        waiting, hubs = [], tuple(x[:HUBS].copy() for x in whole(first))
                        yield from crowded(first)
                if last and not ends:
                    continue
                done = waiting
                waiting, hubs = [], None
                pieces = [*done, b.slice(to[0])]
                if not ends:
                    waiting, pieces[-1] = [b.slice(at[-1])], b.slice(to[0], at[-1] - to[0])
                    if waiting[0].num_rows > small:
                        hubs = tuple(x[:HUBS].copy() for x in whole(waiting[0]))
                        yield from crowded(waiting[0])
                        waiting = []
                [b] = pa.Table.from_batches(pieces).combine_chunks().to_batches() or [b.slice(0, 0)]
                if not b.num_rows:
                    continue
                at = np.concatenate([[0], 1 + np.flatnonzero(_new(b, ["node"]))])
                to = np.append(at[1:], b.num_rows)
            num, sizes, tokens = whole(b)
            n = to - at
            two = at[n == 2] if small >= 2 else at[:0]
            hit = _agree(tokens[two], sizes[two], tokens[two + 1], sizes[two + 1], least, percent)
            yield edges(num[two[hit] + 1], num[two[hit]])
            for lo, hi in zip(at[n > 2 if small >= 2 else n > 1].tolist(), to[n > 2 if small >= 2 else n > 1].tolist(), strict=True):
                if hi - lo > small:
                    kept, hubs = hubs, tuple(x[lo : lo + HUBS] for x in (num, sizes, tokens))
                    yield from crowded(b.slice(lo, hi - lo))
                    hubs = kept
                else:
                    label = alike(tokens[lo:hi], sizes[lo:hi], least, percent)
                    moved = np.flatnonzero(label != np.arange(hi - lo))
                    yield edges(num[lo + moved], num[lo + label[moved]])

    rows = met.join(sketches, "num").select("node", "num", "tree", "n_set", "tokens")
    return rows.repartition("node").sortWithinPartitions("node", "num").mapInArrow(compare, MET)


def linked_sets(sets: list[np.ndarray], percent: int) -> np.ndarray:
    """For each set of a group, the place of the one it is linked with: those reachable by pairs of at least so many percent, on the full sets."""
    m = len(sets)
    sizes = np.array([len(s) for s in sets])
    values, docs = np.concatenate(sets), np.repeat(np.arange(m), sizes)
    order = np.argsort(values, kind="stable")
    values, docs = values[order], docs[order]
    start = np.flatnonzero(np.concatenate([[True], values[1:] != values[:-1]]))
    n = np.diff(np.append(start, len(values)))
    common = np.zeros(m * m, np.int32)
    count = np.repeat(n, n)
    few, kind = docs[(count > 1) & (count <= COMMON)], np.repeat(np.arange(len(n)), n)[(count > 1) & (count <= COMMON)]
    for d in range(1, min(COMMON, m)):
        codes = few[:-d][kind[d:] == kind[:-d]] * m + few[d:][kind[d:] == kind[:-d]]
        if len(codes) * 8 > m * m:
            common += np.bincount(codes, minlength=m * m).astype(np.int32)
        else:
            at, times = np.unique(codes, return_counts=True)
            common[at] += times.astype(np.int32)
    common = common.reshape(m, m)
    common += common.T
    often = np.flatnonzero(n > COMMON)
    width = max(1, min(1 << 14, (1 << 24) // m))
    for k in range(0, len(often), width):
        part = often[k : k + width]
        columns = np.repeat(np.arange(len(part)), n[part])
        rows = docs[np.repeat(start[part], n[part]) + np.arange(n[part].sum()) - np.repeat(np.cumsum(n[part]) - n[part], n[part])]
        dense = np.zeros((m, len(part)), np.float32)
        dense[rows, columns] = 1
        common += (dense @ dense.T).astype(np.int32)
    label, left = np.arange(m), np.arange(m)
    while len(left):
        seed, left = left[0], left[1:]
        front = [seed]
        while front and len(left):
            f = front.pop()
            c = common[f, left].astype(np.int64)
            hit = 100 * c >= percent * (sizes[f] + sizes[left] - c)
            label[left[hit]] = seed
            front.extend(left[hit])
            left = left[~hit]
    return label


def _linked(grouped: DataFrame, similarity: float, size: int) -> DataFrame:
    """Links (a, b), a spanning forest of each group, of texts (team, one, two, num, body): those of a team and two of its blocks are compared."""
    percent, keys = round(similarity * 100), ["team", "one", "two"]

    def confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = shingle_words()
        nums: list[int] = []
        sets: list[np.ndarray] = []
        parts = (x for b in batches for x in document_blocks([b], "body", TEXT_BYTES))
        for b, at, ends in _blocks(parts, keys):
            found, num = shingle_sets(*words.of(*buffers(b.column("body"))), size), b.column("num").to_pylist()
            a, c = [], []
            for k, (lo, hi) in enumerate(zip(at.tolist(), [*at[1:].tolist(), b.num_rows], strict=True)):
                nums += num[lo:hi]
                sets += found[lo:hi]
                if k == len(at) - 1 and not ends:
                    break
                label = linked_sets(sets, percent)
                moved = np.flatnonzero(label != np.arange(len(sets)))
                a += [nums[i] for i in moved]
                c += [nums[i] for i in label[moved]]
                nums, sets = [], []
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(c, pa.int64())], ["a", "b"])

    return grouped.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(confirm, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of every node of a graph, by rounds in which each node joins its neighbour of the lowest rank.

    In the first round a node's rank is its number, which folds stars round their hub at once; then ranks are hashes
    of the node and the round, so that chains shrink by a constant share a round.  Edges inside a
    contracted node vanish, and the rounds end when none is left.
    """
    edges = written(edges.select("a", "b").filter("a != b").distinct(), "cc-edges")
    labels = edges.select(F.explode(F.array("a", "b")).alias("node")).distinct().withColumn("root", F.col("node"))
    first, rounds = edges, []
    while not edges.isEmpty():
        step = len(rounds)
        both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        rank = F.xxhash64(F.lit(step), "b") if step else F.col("b")
        parents = both.groupBy("a").agg(F.min(F.struct(rank.alias("rank"), F.col("b").alias("parent"))).alias("p"))
        own = F.struct((F.xxhash64(F.lit(step), "a") if step else F.col("a")).alias("rank"), F.col("a").alias("parent"))
        parents = written(parents.select(F.col("a").alias("child"), F.least(own, F.col("p"))["parent"].alias("parent")), "cc-parents")
        onward = edges.join(parents, F.col("a") == F.col("child")).select(F.col("parent").alias("x"), "b")
        onward = onward.join(parents, F.col("b") == F.col("child")).select(F.least("x", "parent").alias("a"), F.greatest("x", "parent").alias("b"))
        new_edges = written(onward.filter("a != b").distinct(), "cc-edges")
        rounds.append(parents)
        if edges is not first:
            drop_written(edges)
        edges = new_edges
    for parents in rounds:
        labels = labels.join(parents, F.col("root") == F.col("child"), "left").select("node", F.coalesce("parent", "root").alias("root"))
    labels = written(labels, "cc-labels")
    drop_written(first, edges, *rounds)
    return labels


def _joined(labels: DataFrame | None, links: DataFrame, label: str) -> DataFrame:
    """(member, root) of all linked so far: only the roots that new links join are contracted again."""
    if labels is None:
        return components(links).withColumnRenamed("node", "member")
    ends = links
    for end in ("a", "b"):
        roots = labels.select(F.col("member").alias(end), F.col("root").alias(f"root_{end}"))
        ends = ends.join(roots, end, "left").withColumn(f"root_{end}", F.coalesce(f"root_{end}", end))
    moved = components(ends.select(F.col("root_a").alias("a"), F.col("root_b").alias("b")))
    known = labels.withColumnRenamed("root", "was")
    known = known.join(moved, F.col("was") == F.col("node"), "left").select("member", F.coalesce("root", "was").alias("root"))
    fresh = moved.withColumnRenamed("node", "member").join(labels.select("member"), "member", "left_anti")
    out = written(known.unionByName(fresh), f"near-labels-{label}")
    drop_written(labels, moved)
    return out


def _rooted(rows: DataFrame, labels: DataFrame | None) -> DataFrame:
    """``rows`` with the root that links found so far give each document."""
    if labels is None:
        return rows.withColumn("root", F.col("num"))
    return rows.join(labels.withColumnRenamed("member", "num"), "num", "left").withColumn("root", F.coalesce("root", "num"))


def _crowds(level: DataFrame, label: str) -> DataFrame:
    """Rows (node, num, tree, root) of nodes whose documents aren't held together yet, with the node's size ``n`` and its ``first``."""
    level = written(level.select("node", "num", "tree", "root"), f"{label}-level")
    apart = level.groupBy("node").agg(F.count("*").alias("n"), F.min("num").alias("first"), F.min("root").alias("low"), F.max("root").alias("high"))
    apart = counted(apart.filter(F.col("low") < F.col("high")).drop("low", "high"), f"{label}-nodes", "n")
    out = written(join_by_count(level, apart, "node", "n"), f"{label}-crowds")
    out._counts = apart._counts
    drop_written(level, apart)
    return out


def near_duplicates(docs: DataFrame, *, similarity: float = 0.75, size: int = WORDS, id_col: str = "doc_id", text_col: str = "text", trees: int = TREES, small: int = SMALL, row_col: str | None = None, miss: float = MISS) -> DataFrame:
    """Per document: id, ``n_shingles``, ``component_id`` (smallest id reachable by links) and ``kept`` (whether that is its own).

    Null texts and texts without words have an empty set and are linked with nothing, not even
    each other; repeated rows are linked if they have words; a pair at exactly the least similarity is linked.
    A null id is in no component's name unless all its members' ids are null.  Very long texts are read whole, one at
    a time.  An empty table gives no rows; other columns are not read.

    ``row_col`` names a unique key (a long): it is put out too, with ``first``, which holds for one row
    of each linked group (the least by id, null last, and key) and for every row without words.
    ``miss`` is the share of true pairs that the comparison of tokens may drop; 0 confirms every candidate.
    """
    keyed, own = docs, row_col
    if row_col is None:  # ids may repeat or be null, so texts are fetched by a key of their own
        own = "_near_row"
        keyed = written(docs.select(F.col(id_col).cast("long").alias(id_col), F.col(text_col), F.monotonically_increasing_id().alias(own)), "near-docs")
    if trees * ROOT > TOKENS:
        raise ValueError(f"at most {TREES} trees")
    rows = written(signatures(keyed, id_col=id_col, text_col=text_col, size=size, row_col=own), "near-signatures")
    filled = rows.filter("n_shingles > 0").groupBy("key").agg(
        F.min("id").alias("id"), F.count("*").alias("copies"), F.min("n_shingles").alias("n_set"), F.min("tokens").alias("tokens"), F.min("roots").alias("roots"),
        F.min(F.struct(F.col("id").isNull(), "id", "row"))["row"].alias("row"),
    )
    sets = written(filled.withColumn("num", F.monotonically_increasing_id()), "near-sets")
    sketches = sets.select("num", "n_set", "tokens")
    least = least_agreement(similarity, TOKENS, miss) if miss > 0 else 0
    stored = keyed.select(F.col(own).cast("long").alias("row"), utf8(text_col).alias("body"))

    def texts_of(wanted: DataFrame) -> DataFrame:
        """Rows of ``wanted`` with the texts of their documents."""
        chosen = F.broadcast(wanted) if wanted.count() <= LOOKUP_ROWS else wanted
        return stored.join(chosen, "row")

    def enter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            nodes = buffers(b.column("roots"))[0].view(np.int64).reshape(b.num_rows, TREES)[:, :trees]
            num = np.repeat(b.column("num").to_numpy(), trees)
            tree = np.tile(np.arange(trees, dtype=np.int32), b.num_rows)
            yield pa.RecordBatch.from_arrays([pa.array(nodes.ravel()), pa.array(num), pa.array(tree)], ["node", "num", "tree"])

    level = sets.select("num", "roots").mapInArrow(enter, "node long, num long, tree int")
    light, labels, crowds, bodies, picks, limit, depth = sketches, None, None, None, None, small, 0
    while True:
        found = written(_compared(_met(level), light, limit, similarity, least), f"near-{depth}")
        edges = found.filter("tree is null").select("a", "b")
        if not edges.isEmpty():
            labels = _joined(labels, edges, f"near-{depth}")
        drop_written(*([crowds] if depth else []))
        crowded = found.filter("tree is not null")
        if crowded.isEmpty():
            drop_written(found)
            break
        crowds = _crowds(_rooted(crowded.select(F.col("a").alias("node"), F.col("b").alias("num"), "tree"), labels), f"near-{depth}")
        drop_written(found)
        if crowds.isEmpty():
            drop_written(crowds)
            break
        if depth % LEVELS == 0:
            members = written(sets.select("num", "row", "n_set", "tokens").join(crowds.select("num").distinct(), "num", "left_semi"), f"near-members-{depth}")
            drop_written(*(x for x in (bodies, picks, light) if x is not None and x is not sketches))
            light = members.select("num", "n_set", "tokens")
            light._scratch = members._scratch
            bodies = written(texts_of(members.select("num", "row")).select("num", "body"), f"near-texts-{depth}")
            picks = written(branch_tokens(bodies, size, trees, depth), f"near-picks-{depth}")
        branches = F.explode(F.when(F.col("node") % 2 == 0, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0))))
        at = (F.col("tree") * LEVELS + depth % LEVELS) * BRANCHES + F.col("branch")
        level = crowds.join(picks, "num").withColumn("branch", branches).select(F.xxhash64("node", "branch", F.substring(F.col("picks"), at * 4 + 1, F.lit(4))).alias("node"), "num", "tree")
        depth += 1
        limit = max(small, min(small << (depth - 1), SMALL))
    drop_written(*(x for x in (bodies, picks, light) if x is not None and x is not sketches))
    if labels is not None:
        grouped = labels.select(F.col("member").alias("num"), F.col("root").alias("team")).join(sets.select("num", "row", "n_set"), "num")
        teams = grouped.groupBy("team").agg(F.count("*").alias("n"), F.sum("n_set").alias("shingles"))
        teams = counted(teams.withColumn("cut", F.ceil(F.greatest(F.col("n") / GROUP_DOCS, F.col("shingles") / GROUP_SHINGLES)).cast("int")), "near-teams", "n")
        block = F.pmod(F.xxhash64("num"), F.col("cut")).cast("int")
        others = F.when(F.col("cut") == 1, F.array(F.lit(0))).otherwise(F.array_remove(F.sequence(F.lit(0), F.col("cut") - 1), F.col("block")))
        wanted = join_by_count(grouped, teams, "team", "n").withColumn("block", block).select("row", "num", "team", "block", others.alias("others"))
        wanted = written(wanted, "near-wanted")
        met = texts_of(wanted).withColumn("other", F.explode("others"))
        met = met.select("team", F.least("block", "other").alias("one"), F.greatest("block", "other").alias("two"), "num", "body")
        links = written(_linked(met, similarity, size), "near-links")
        drop_written(labels, teams, wanted)
        labels = None if links.isEmpty() else components(links).withColumnRenamed("node", "member")
        drop_written(links)
    drop_written(*([keyed] if row_col is None else []))
    named = sets.select("key", "num", "id", "row", "copies")
    if labels is not None:
        named = written(_rooted(named, labels), "near-named")
        smallest = named.groupBy("root").agg(F.count("*").alias("members"), F.min("id").alias("component"), F.min(F.struct(F.col("id").isNull(), "id", "row"))["row"].alias("first_row"))
        named = join_by_count(named, counted(smallest, "near-smallest", "members"), "root", "members").select("key", "copies", "component", "first_row")
    else:
        named = named.select("key", "copies", F.col("id").alias("component"), F.col("row").alias("first_row"))
    linked = F.when(F.col("n_shingles") > 0, F.col("component")).otherwise(F.col("id"))
    out = join_by_count(rows.drop("tokens", "roots"), counted(named, "near-components", "copies"), "key", "copies", "left")
    more = [F.col("row").alias(row_col), ((F.col("n_shingles") == 0) | (F.col("row") == F.col("first_row"))).alias("first")] if row_col else []
    return out.select(F.col("id").alias(id_col), "n_shingles", linked.alias("component_id"), F.col("id").eqNullSafe(linked).alias("kept"), *more)

"""Operators against brute force on small tables, with nulls, empty and long texts, ties, repeated rows and clashing columns."""

import hashlib
import os
import re
import zlib
from collections import Counter

import numpy as np
import pytest

os.environ["TOKENIZERS_PARALLELISM"] = "false"
from tensorlane.llm import crf, decontaminate, near_duplicates, packing, personal_data, quality, repeats, sharding, token_counts, tokenbin, warc
from tensorlane.llm.common import scratch_path, written
from tensorlane.llm.tokenizing import ChunkEncoder, default_path

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()
EXTRA = ", key string, id long, body string, row long, n int, text_crc32 string"


def sentence(rng, n):
    return " ".join(WORDS[k] for k in rng.integers(0, len(WORDS), n))


def corpus():
    rng = np.random.default_rng(5)
    long = sentence(rng, 30)
    base = sentence(rng, 300)
    near = base.split()
    near[150] = "changed"
    return [
        (1, base), (2, " ".join(near)), (3, base), (3, base), (4, None), (5, ""), (6, "   \n\t "), (7, "one two"), (None, "no id here"), (None, None),
        (8, "x" + long + "y"), (9, long), (10, sentence(rng, 5000)), (11, "a" * 1500), (12, "Ünïcode ünïcode  " * 30), (13, "ends in space "), (14, "ONE two"), (15, "日本語 " * 200),
        (16, sentence(rng, 40) + " " + " ".join(base.split()[20:140])), (17, "<|endoftext|> a<s>b ▁c  d"),
    ]


@pytest.fixture(scope="module")
def docs(spark):
    return table(spark, corpus())


def table(spark, rows):
    return written(spark.createDataFrame([(*r, "s", 99, "zz", 7, 3, "c") for r in rows], "doc_id long, text string" + EXTRA), "test")


def ordered(rows):
    return sorted(rows, key=lambda r: tuple((v is not None, str(type(v)), v) for v in r))


# -- sharding -----------------------------------------------------------------------------


@pytest.mark.parametrize("n", [1, 2, 3, 17, 1000])
def test_permutation_is_a_bijection_with_an_inverse(n):
    p = sharding.FeistelPermutation(n, seed=3)
    y = p.forward(np.arange(n))
    assert sorted(y) == list(range(n)) and np.array_equal(p.inverse(y), np.arange(n))


def test_shards(spark, docs):
    out = sharding.shard_rows(docs, 3, seed=1).collect()
    n = len(corpus())
    assert ordered((r["doc_id"], r["size"], r["text_crc32"]) for r in out) == ordered((d, len((t or "").encode()) + 8, zlib.crc32((t or "").encode())) for d, t in corpus())
    assert sorted((r["shard"], r["slot"]) for r in out) == sorted((k % 3, k // 3) for k in range(n))
    assert all(sharding.row_at(r["shard"], r["slot"], 3, n, 1) == r["row_number"] for r in out)
    again = sharding.shard_rows(docs.repartition(7), 3, seed=1).collect()
    assert ordered(map(tuple, again)) == ordered(map(tuple, out))
    assert sharding.shard_rows(table(spark, []), 3).count() == 0


# -- tokens -------------------------------------------------------------------------------


def test_chunks_encode_like_whole_texts():
    e = ChunkEncoder.of(default_path("byte_bpe_50k.json"))
    rng = np.random.default_rng(2)
    parts = [" ", "  ", "a", "é", "\n", "\t", "'s", " the", "\x00", "<|endoftext|>", "　", "\xa0", "日本", "😀", "1", ".", " ,", "\x1f", "\x85", "'ll"]
    texts = ["".join(parts[k] for k in rng.integers(0, len(parts), rng.integers(0, 14))) for _ in range(1500)]
    for t, ids in zip(texts, e.encode(texts), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == e.tokenizer.encode(t, add_special_tokens=False).ids


def reference_ids(rows):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(default_path("byte_bpe_50k.json"))
    return [np.array([*t.encode(x or "", add_special_tokens=False).ids, 0], "<u4") for _, x in rows]


@pytest.mark.parametrize("kind", ["byte", "bit"])
def test_token_files_round_trip(spark, docs, kind):
    out = tokenbin.tokens_round_trip(docs, default_path("byte_bpe_50k.json"), kind=kind, block_ids=64).collect()
    want = [(d, len(i), zlib.crc32(i.tobytes())) for (d, _), i in zip(corpus(), reference_ids(corpus()), strict=True)]
    assert ordered((r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in out) == ordered(want)
    at = 0
    for r in sorted(out, key=lambda r: r["start"]):
        assert r["start"] == at
        at += r["n_tokens"]
    ids = [r["doc_id"] for r in sorted(out, key=lambda r: r["start"])]
    assert ids == sorted(ids, key=lambda d: (d is not None, d))
    assert tokenbin.tokens_round_trip(table(spark, []), default_path("byte_bpe_50k.json")).count() == 0


@pytest.mark.parametrize("kind", ["byte", "bit"])
def test_planes_and_seeking(kind, tmp_path):
    ids = np.random.default_rng(0).integers(0, 2**31, 1000, dtype=np.uint32)
    assert np.array_equal(tokenbin.from_planes(tokenbin.to_planes(ids, kind), 1000, kind), ids)
    with open(tmp_path / "f", "wb") as f:
        w = tokenbin.PlaneWriter(f, kind, block_ids=128)
        w.add(4, ids[:700])
        w.add(None, ids[700:])
        w.close()
    with open(tmp_path / "f", "rb") as f:
        r = tokenbin.PlaneReader(f, os.path.getsize(tmp_path / "f"))
        assert np.array_equal(r.ids(100, 300), ids[100:300]) and [d for d, _, _ in r.documents()] == [4, None]


def test_token_counts(spark, docs):
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=default_path("piece_bpe_32k.model"))
    want = [(d, len((t or "").encode()), n := len(model.encode(t or "")), n > 100) for d, t in corpus()]
    for head in (100_000, 2):
        out = token_counts.count_tokens(docs, default_path("piece_bpe_32k.model"), limit=100, head_rows=head)
        assert ordered(map(tuple, out.collect())) == ordered(want)
    counter = token_counts.PieceCounter.of(default_path("piece_bpe_32k.model"))
    for t in (" ", "a ", "  b", "▁", "a▁ b", "\x00 c", "x   "):
        assert sum(counter.count(token_counts.pretokens(t))) == len(model.encode(t))
    assert token_counts.count_tokens(table(spark, []), default_path("piece_bpe_32k.model")).count() == 0


# -- packing ------------------------------------------------------------------------------


def check_pieces(out, rows, window):
    want = Counter((d, zlib.crc32(i.tobytes()), len(i)) for (d, _), i in zip(rows, reference_ids(rows), strict=True))
    ids = {(d, len(i), zlib.crc32(i.tobytes())): i for (d, _), i in zip(rows, reference_ids(rows), strict=True)}
    left = Counter()
    for (d, n, _), i in ids.items():
        for r in out:
            if r["doc_id"] == d and r["doc_tokens"] == n and zlib.crc32(i[r["start"] : r["start"] + r["length"]].tobytes()) == r["ids_crc32"]:
                left[(d, n)] += r["length"]
    total = Counter()
    for (d, _, n), c in want.items():
        total[(d, n)] += n * c
    assert left == total
    sequences = {}
    for r in out:
        sequences.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in sequences.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= window
    return sum(window - sum(n for _, n in p) for p in sequences.values())


def test_packing(spark, docs):
    out = packing.pack(docs, default_path("byte_bpe_50k.json"), window=64).collect()
    check_pieces(out, corpus(), 64)
    assert packing.pack(table(spark, []), default_path("byte_bpe_50k.json")).count() == 0


def test_packing_of_one_common_length(spark):
    rows = [(k, "same words in every text " * 5) for k in range(60)]
    out = packing.pack(table(spark, rows), default_path("byte_bpe_50k.json"), window=64).collect()
    assert check_pieces(out, rows, 64) < 0.35 * sum(r["length"] for r in out)


def test_least_squares_and_plan():
    h = np.zeros(64, np.int64)
    h[[10, 20, 34, 44, 54]] = 30, 20, 10, 10, 20
    columns = packing.combinations(h, 64)
    assert (10, 54) in columns and (20, 44) in columns and (10, 20, 34) in columns
    x = packing.fit(h, columns)
    made = np.zeros(64)
    for c, n in zip(columns, x, strict=True):
        np.add.at(made, list(c), n)
    assert (x >= 0).all() and np.abs(made - h).max() < 1.5
    p = packing.plan(h, 64)
    seq, off, before, _ = p.place(np.arange(h.sum()))
    assert p.sequences <= -(-int((h * np.arange(64)).sum()) // 64) + 2 and (before > 0).all()


# -- decontamination ----------------------------------------------------------------------


def brute_contamination(rows, items, window):
    def words(t):
        return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(c.lower() if c.isascii() else c for c in t or ""))

    out = []
    for d, t in rows:
        w, hit, found = words(t), set(), set()
        for i, text in items:
            v = words(text)
            n = min(window, len(v))
            if not v:
                continue
            for p in range(len(v) - n + 1):
                for q in range(len(w) - n + 1):
                    if w[q : q + n] == v[p : p + n]:
                        hit.update(range(q, q + n))
                        found.add(None if i is None else str(i))
        digest = hashlib.sha256(",".join(sorted(f for f in found if f is not None)).encode()).hexdigest()
        out.append((d, len(w), len(hit), len(found), digest, bool(hit)))
    return out


ITEMS = [(1, "one two"), (2, None), (3, ""), (10, "ünïcode"), (None, "alpha"), (20, corpus()[0][1][40:200]), (21, corpus()[0][1][40:200]), (22, "nothing like it at all anywhere in these texts today"), (23, "theta")]


@pytest.mark.parametrize("test_bytes", [1 << 20, 50])
def test_contamination(spark, docs, test_bytes):
    tests = written(spark.createDataFrame([(*i, "x") for i in ITEMS], "item_id long, text string, doc_id string"), "test")
    out = decontaminate.digest(decontaminate.find_contamination(docs, tests, window=6, test_bytes=test_bytes)).collect()
    assert ordered(map(tuple, out)) == ordered(brute_contamination(corpus(), ITEMS, 6))
    left = decontaminate.remove_contaminated(docs, tests, window=6)
    assert left.columns == docs.columns
    assert ordered((r["doc_id"],) for r in left.collect()) == ordered((d,) for d, _, _, n, _, _ in brute_contamination(corpus(), ITEMS, 6) if not n)
    assert decontaminate.find_contamination(docs, tests.limit(0)).filter("size(items) > 0").count() == 0


def test_many_test_words_and_equal_windows():
    items = [(str(k), text.encode()) for k, text in enumerate(["a b c d", "a b c e", "x a b c", "b"])]
    rows = [b"z a b c d b", b"", b"a b c"]
    narrow = decontaminate.TestIndex.build(items, 3)
    assert len(narrow.once) == 5 and len(narrow.start) == 7
    found = []
    for bits in (decontaminate.PACK_BITS, 1):  # as if the block had more distinct words than fit the narrow form
        decontaminate.PACK_BITS, kept = bits, decontaminate.PACK_BITS
        try:
            index = decontaminate.TestIndex.build(items, 3)
        finally:
            decontaminate.PACK_BITS = kept
        data, off = decontaminate._concatenated(rows)
        hashes, first = decontaminate.contamination_words().of(data, off)
        spans, names = decontaminate._hits(decontaminate.ShardSuffixArray(index.numbers(hashes, first), index), first)
        found.append(([s.tolist() for s in spans], names))
    assert found[0] == found[1] == ([[1, 6], [], [0, 3]], [["0", "1", "2", "3"], [], ["0", "1", "2", "3"]])


def test_longest_matches(spark):
    d = table(spark, [(1, "a b c d x"), (2, "q a b c d e f"), (3, "e f")])
    t = spark.createDataFrame([(7, "z a b c d e f y")], "item_id long, text string")
    got = {r["word"]: (r["length"], r["doc"], r["doc_word"]) for r in decontaminate.longest_matches(d, t, window=3).collect()}
    assert got[1] == (6, 2, 1) and got[3] == (4, 2, 3)


# -- near-duplicates ----------------------------------------------------------------------


def brute_components(rows):
    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if c.isascii() else c for c in t or ""))
        return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()

    sets = [shingles(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                root[find(i)] = find(j)
    out = []
    for i, (d, _) in enumerate(rows):
        ids = [rows[j][0] for j in range(len(rows)) if find(j) == find(i) and rows[j][0] is not None]
        c = min(ids) if ids and sets[i] else d
        out.append((d, len(sets[i]), c, d == c))
    return out


def test_near_duplicates(spark, docs):
    out = near_duplicates.near_duplicates(docs).collect()
    assert ordered(map(tuple, out)) == ordered(brute_components(corpus()))
    assert near_duplicates.near_duplicates(table(spark, [])).count() == 0


def test_large_group_and_chains(spark):
    rng = np.random.default_rng(9)
    base = sentence(rng, 120).split()
    rows = []
    for k in range(40):  # each one differs a little from the one before
        base = list(base)
        base[int(rng.integers(120))] = f"w{k}"
        rows.append((k, " ".join(base)))
    shared = sentence(rng, 60)
    rows += [(100 + k, shared + " " + sentence(rng, 60)) for k in range(20)]
    out = near_duplicates.near_duplicates(table(spark, rows), small=4).collect()
    assert ordered(map(tuple, out)) == ordered(brute_components(rows))


def test_agreement_bound():
    c = near_duplicates.least_agreement(0.75, 64)
    assert 25 < c < 40


def test_trees_lose_a_pair_as_rarely_as_stated():
    assert near_duplicates.path_loss(0.75) < 1.3e-5 and near_duplicates.path_loss(0.75, levels=7) < 1e-6
    # simulated: a node has one branch or two, and a pair follows each with the similarity
    rng, alive = np.random.default_rng(2), np.ones(40_000, int)
    alive = rng.binomial(alive, 0.75)
    for _ in range(5):
        alive = rng.binomial(alive + rng.binomial(alive, 0.5), 0.75)
    assert abs((alive == 0).mean() / near_duplicates.path_loss(0.75, trees=1, levels=5) - 1) < 0.03


def test_hash_functions_agree_as_often_as_sets_are_similar():
    rng = np.random.default_rng(4)
    x = rng.integers(0, 1 << 63, 900).astype(np.uint64)
    seeds = near_duplicates._seeds(0, 2000)
    for shared in (300, 600, 800):
        a, b = x[:shared], x[shared:]
        half = len(b) // 2
        same = near_duplicates.minwise(np.concatenate([a, b[:half]]), seeds) == near_duplicates.minwise(np.concatenate([a, b[half:]]), seeds)
        assert abs(same.mean() - shared / 900) < 0.05
    long = rng.integers(0, 1 << 63, 20_000).astype(np.uint64)
    parts = [near_duplicates.minwise(long[k : k + 5000], seeds) for k in range(0, 20_000, 5000)]
    assert np.array_equal(near_duplicates.minwise(long, seeds), np.min(parts, axis=0))


def test_branch_tokens_differ_from_each_other_and_from_the_roots(spark):
    text = sentence(np.random.default_rng(3), 90)
    words = near_duplicates.shingle_words()
    data = np.frombuffer(text.encode(), np.uint8)
    [s] = near_duplicates.shingle_sets(*words.of(data, np.array([0, len(data)])))
    bodies = spark.createDataFrame([(7, text.encode())], "num long, body binary")
    each = near_duplicates.LEVELS * near_duplicates.BRANCHES * 3
    picks = [np.frombuffer(near_duplicates.branch_tokens(bodies, 5, 3, d).first()["picks"], "<u4") for d in (0, near_duplicates.LEVELS)]
    every = near_duplicates.minwise(s, near_duplicates._seeds(0, near_duplicates.TOKENS + 2 * each))
    assert np.array_equal(np.concatenate(picks), every[near_duplicates.TOKENS :])


def test_every_candidate_is_confirmed_where_nothing_may_be_missed(spark, docs):
    out = near_duplicates.near_duplicates(docs, miss=0).collect()
    assert ordered(map(tuple, out)) == ordered(brute_components(corpus()))


def test_crowded_nodes_branch_until_none_is_left(spark):
    rng = np.random.default_rng(13)
    shared = sentence(rng, 200).split()
    rows = []
    for k in range(60):  # pairs at about 0.8, all of one large part in common that isn't enough to link them
        own = shared + [f"p{k}w{j}" for j in range(90)]
        twin = own[:270] + [f"q{k}w{j}" for j in range(20)]
        rows += [(2 * k, " ".join(own)), (2 * k + 1, " ".join(twin))]
    out = near_duplicates.near_duplicates(table(spark, rows), small=2).collect()
    assert ordered(map(tuple, out)) == ordered(brute_components(rows))


def brute_links(sets):
    """For each set, all sets that links join with it."""
    group = [{k} for k in range(len(sets))]
    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            both = len(np.intersect1d(a, b))
            if 100 * both >= 75 * (len(a) + len(b) - both):
                group[i] |= group[j]
                for k in group[i]:
                    group[k] = group[i]
    return group


def test_groups_are_linked_on_full_sets_by_a_forest():
    rng = np.random.default_rng(21)
    base = rng.integers(0, 1 << 63, 90).astype(np.uint64)
    sets = []
    for k in range(70):  # some shingles of nearly all sets, some of a few, some of one
        own = rng.integers(0, 1 << 63, int(rng.integers(1, 30))).astype(np.uint64)
        sets.append(np.unique(np.concatenate([base[rng.random(90) < rng.choice([0.5, 0.85, 0.97])], own])))
    sets += [sets[3][: len(sets[3]) * 3 // 4], sets[5][:1]]
    label = near_duplicates.linked_sets(sets, 75)
    group = brute_links(sets)
    assert all({int(j) for j in np.flatnonzero(label == label[k])} == group[k] for k in range(len(sets)))


def test_a_group_in_blocks_and_a_large_node_lose_no_link(spark, monkeypatch):
    rng = np.random.default_rng(22)
    base = sentence(rng, 100).split()
    rows = []
    for k in range(90):  # near copies of one text, of which only some are near enough to each other
        words = list(base)
        for j in rng.integers(0, 100, int(rng.integers(0, 5))):
            words[j] = f"v{k}w{j}"
        rows.append((k, " ".join(words)))
    want = ordered(brute_components(rows))
    assert ordered(map(tuple, near_duplicates.near_duplicates(table(spark, rows), small=16).collect())) == want
    monkeypatch.setattr(near_duplicates, "GROUP_DOCS", 20)
    assert ordered(map(tuple, near_duplicates.near_duplicates(table(spark, rows)).collect())) == want


def test_a_node_names_a_forest_of_its_candidates_across_batches(spark):
    rows = [(7, n, 0, 100, bytes(80)) for n in range(300)] + [(8, n, 1, 100, bytes([n] * 80)) for n in range(40)] + [(9, 500, 2, 100, bytes(80)), (9, 501, 2, 10, bytes(80))]
    met = spark.createDataFrame([r[:3] for r in rows], "node long, num long, tree int").coalesce(1)
    light = spark.createDataFrame([(n, 100, bytes(80)) for n in range(300)] + [(500, 100, bytes(80)), (501, 10, bytes(80))], "num long, n_set long, tokens binary")
    was = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    for batch in ("7", "64", "1000"):
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", batch)
        forest = near_duplicates._compared(met, light, 400, 0.75, 40).collect()
        # 300 documents make 299 rows, not 44,850 pairs
        assert ordered((r["a"], r["b"], r["tree"]) for r in forest) == ordered([(n, 0, None) for n in range(1, 300)] + [(n, 0, None) for n in range(1, 40)])
        large = near_duplicates._compared(met, light, 30, 0.75, 40).collect()
        assert {r["b"] for r in large if r["a"] == 7 and r["tree"] == 0} == set(range(300)) and {r["b"] for r in large if r["a"] == 8 and r["tree"] == 1} == set(range(40))
        assert {r["a"] for r in large if r["b"] == 0 and r["tree"] is None} == set(range(1, 300))
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", was)


def test_first_paths_lose_a_pair_as_rarely_as_stated():
    n = near_duplicates
    assert n.path_loss(0.75, root=n.ROOT) < 1 / 95_000 and n.path_loss(0.75, levels=0, root=n.ROOT) < 1e-14
    tokens = np.arange(160, dtype=np.uint32).reshape(2, 80)
    assert n.first_nodes(tokens).shape == (2, n.TREES) and len(np.unique(n.first_nodes(tokens))) == 2 * n.TREES


# -- personal data ------------------------------------------------------------------------


def test_base_spans_match_plain_patterns():
    rng = np.random.default_rng(3)
    parts = ["a@b.c", "@", "+1 (234) 567-8901", "4111 1111 1111 1111", "4111111111111111", "1.2.3.4", "300.1.1.1", "01.002.3.4.5", " ", "x", "é", ".", "-", "1", "+", "a.b@c-d.e.f", "12-34", "\n"]
    for _ in range(400):
        t = "".join(parts[k] for k in rng.integers(0, len(parts), rng.integers(0, 12)))
        assert personal_data.code_points(t.encode(), personal_data.base_spans(t.encode())) == plain_spans(t)


def plain_spans(t):
    patterns = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    found = []
    for kind, pattern in patterns.items():
        for m in re.finditer(pattern, t):
            d = re.sub("[^0-9]", "", m[0])
            luhn = sum(int(c) if i % 2 == 0 else sum(map(int, str(2 * int(c)))) for i, c in enumerate(reversed(d))) % 10 == 0
            if {"email": True, "ip": kind == "ip" and all(int(p) <= 255 for p in m[0].split(".")), "card": 12 <= len(d) <= 19 and luhn, "phone": 9 <= len(d) <= 15}[kind]:
                found.append((m.start(), kind, m.end()))
    return sorted(found, key=lambda s: (s[0], crf.KINDS.index(s[1])))


@pytest.fixture(scope="module")
def field():
    return crf.trained()


def test_field_on_held_out_sentences(field):
    shapes, labels = crf.padded(crf.labelled_sentences(200, seed=77))
    marked = shapes > 0
    assert (field.viterbi(shapes) == labels)[marked].mean() > 0.97


def test_viterbi_and_windows_are_exact(field):
    rng = np.random.default_rng(1)
    shapes = rng.integers(0, crf.N_SHAPES, (6, 4))
    k = len(crf.LABELS)
    score = field.scores(shapes)
    from itertools import product

    for s, got in zip(score, field.viterbi(shapes), strict=True):
        value = lambda y, s=s: sum(s[t, y[t]] for t in range(4)) + sum(field.step[a, b] for a, b in zip(y, y[1:], strict=False))
        assert value(got) == pytest.approx(max(value(y) for y in product(range(k), repeat=4)))
    assert field.forced_gap(personal_data.REACH - 1)
    texts = [" ".join(w for w, _ in s).encode() for s in crf.labelled_sentences(60, seed=5)]
    texts += [b" ".join([texts[0], b"plain " * 40, texts[1]])]
    cut = personal_data.field_spans(texts, field)
    whole = crf.ChainModel(field.here, field.before, field.after, field.step)
    whole.forced_gap = lambda side: False
    assert [sorted(s) for s in personal_data.field_spans(texts, whole)] == [sorted(s) for s in cut]


def test_personal_data(spark, field):
    rows = [*corpus(), (30, "mail é me.99@mail1.example.com now"), (31, "call +1 (234) 555-2485 4152345678901 x"), (32, "é 1.2.3.4")]
    d = table(spark, rows)
    out = {r["doc_id"]: r for r in personal_data.find(d, model=field).collect()}
    assert out[30]["n_email"] == 1 and out[30]["spans"] == "email:7:30" and out[32]["spans"] == "ip:2:9"
    assert all(out[i]["base_sha256"] == hashlib.sha256(",".join(f"{k}:{s}:{e}" for s, k, e in plain_spans(t or "")).encode()).hexdigest() for i, t in rows if i not in (None, 3))
    texts = {r["doc_id"]: r["text"] for r in personal_data.redact(d, model=field).collect()}
    assert texts[30] == "mail é <EMAIL> now" and texts[4] is None and texts[1] == rows[0][1]
    assert personal_data.find(table(spark, []), model=field).count() == 0


# -- repeats ------------------------------------------------------------------------------


def brute_repeats(rows, least):
    seen = Counter()
    data = [(t or "").encode() for _, t in rows]
    for x in data:
        seen.update(x[k : k + least] for k in range(len(x) - least + 1))
    out = []
    for (d, _), x in zip(rows, data, strict=True):
        gone = np.zeros(len(x), bool)
        for k in range(len(x) - least + 1):
            if seen[x[k : k + least]] > 1:
                gone[k : k + least] = True
        spans = int(np.diff(np.concatenate([[0], gone.astype(int)])).clip(0).sum())
        kept = bytes(b for b, g in zip(x, gone, strict=True) if not g)
        out.append((d, len(x), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize("least", [60, 150])
def test_repeats(spark, docs, least):
    out = repeats.remove_repeats(docs, least=least).collect()
    assert ordered(map(tuple, out)) == ordered(brute_repeats(corpus(), least))
    assert repeats.remove_repeats(table(spark, []), words=50).count() == 0


def brute_shared(rows, words):
    data = [(t or "").encode().split() for _, t in rows]
    seen = Counter(tuple(x[k : k + words]) for x in data for k in range(len(x) - words + 1))
    out = []
    for (d, _), x in zip(rows, data, strict=True):
        hit = {j for k in range(len(x) - words + 1) if seen[tuple(x[k : k + words])] > 1 for j in range(k, k + words)}
        out.append((d, len(hit)))
    return out


@pytest.mark.parametrize("words", [3, 20])
def test_shared_words(spark, docs, words):
    out = repeats.remove_repeats(docs, least=400, words=words).select("doc_id", "n_shared_words").collect()
    assert ordered(map(tuple, out)) == ordered(brute_shared(corpus(), words))


def test_no_text_is_shuffled_to_be_looked_at_again(spark, docs, monkeypatch):
    """Texts are picked where they lie by a bitmap; a crowded one, or the join in its place, gives the same rows."""
    plans, write = {}, repeats.written
    monkeypatch.setattr(repeats, "written", lambda df, label: plans.update({label: df._jdf.queryExecution().executedPlan().toString()}) or write(df, label))
    was = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for name, value, moved in ((None, None, False), ("PICK_BITS", 2, False), ("PICK_BLOCKS", 0, True)):
            if name:
                monkeypatch.setattr(repeats, "LEAST_BITS", 1)
                monkeypatch.setattr(repeats, name, value)
            out = repeats.remove_repeats(docs, least=60, words=20).collect()
            assert ordered(tuple(r)[:5] for r in out) == ordered(brute_repeats(corpus(), 60))
            assert ordered((r["doc_id"], r["n_shared_words"]) for r in out) == ordered(brute_shared(corpus(), 20))
            assert [("hashpartitioning" in plans[f"{x}-texts"]) for x in ("repeats", "shared")] == [moved, moved]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", was)


def test_runs_of_a_text_are_hashed_together():
    """Segments and windows of many runs equal those of each run alone, with a few prefix sums for all."""
    text = np.random.default_rng(8).integers(97, 100, 30_000).astype(np.uint8)
    text[9_000:10_000] = text[:1_000]
    units = repeats.Bytes()
    d, w, place, lo, hi = repeats.runs_of(text, 40, units.hashes)
    runs = np.stack([d.view(np.int64), place, lo, hi], 1)
    runs = runs[(lo < 3_000) | (lo > 20_000)][::-1]
    sums, prefix = [], units.hashes.prefix
    units.hashes.prefix = lambda data: sums.append(len(data)) or prefix(data)
    for of, how in ((repeats.segments_of, (units.hashes,)), (repeats.windows_of, (units.hashes, units.others))):
        sums.clear()
        together = of(text, runs, 40, *how)
        assert len(sums) == 2
        alone = [np.concatenate(x) for x in zip(*(of(text, runs[k : k + 1], 40, *how) for k in range(len(runs))), strict=True)]
        assert ordered(zip(*(x.tolist() for x in together), strict=True)) == ordered(zip(*(x.tolist() for x in alone), strict=True))


def test_crowded_digits_are_decided_like_others(spark):
    """A digit of over 1,000 rows, and others of one row, of equal rows and of several kinds, against plain counts."""
    rows = [(b"k", 1, k % 700 if k < 1_100 else k, k) for k in range(1_300)]
    rows += [(b"k", 2, 5, 2_000), *((b"k", 3, 5, 2_001 + k) for k in range(3)), *((b"k", 4, k // 2, 2_010 + k) for k in range(5))]
    kinds, same, witness = {}, Counter(), {}
    for _, d, w, r in rows:
        kinds.setdefault(d, set()).add(w)
        same[d, w] += 1
        witness[d, w] = max(r, witness.get((d, w), 0))
    digits = Counter(d for _, d, _, _ in rows)
    want = [(d, r, same[d, w] > 1, len(kinds[d]) > 1 and (same[d, w] == 1 or r == witness[d, w])) for _, d, w, r in rows if digits[d] > 1]
    made = spark.createDataFrame([(k, d, w, 0, r, r, r) for k, d, w, r in rows], repeats.RUN + ", row long")
    out = repeats._decided(made, "test").select("digit", "lo", "full", "open").collect()
    assert ordered(map(tuple, out)) == ordered(want)


def test_short_texts_are_sorted_together(monkeypatch):
    """Runs of many texts equal those of each alone, with one prefix sum for all; a text too long to stand with others is taken alone."""
    rng = np.random.default_rng(9)
    texts = [rng.integers(97, 100, n).astype(np.uint8) for n in (0, 39, 40, 41, 700, 3, 0, 2_000, 40, 9_000, 500, 10, 300)]
    texts += [np.zeros(200, np.uint8), texts[4], np.zeros(90, np.uint8), np.zeros(0, np.uint8)]
    units = repeats.Bytes()
    sums, prefix = [], units.hashes.prefix
    units.hashes.prefix = lambda data: sums.append(len(data)) or prefix(data)
    for chunk, most in ((repeats.CHUNK, 1), (3_000, 8), (10, None)):
        monkeypatch.setattr(repeats, "CHUNK", chunk)
        alone = [repeats.runs_of(t, 40, units.hashes) for t in texts]
        sums.clear()
        n, together = repeats.runs_of_all(texts, 40, units.hashes)
        assert most is None or len(sums) <= most
        assert n.tolist() == [len(x[0]) for x in alone]
        assert [x.tolist() for x in together] == [np.concatenate(x).tolist() for x in zip(*alone, strict=True)]
    n, none = repeats.runs_of_all(texts[:2], 40, units.hashes)
    assert n.tolist() == [0, 0] and [len(x) for x in none] == [0] * 5


def test_sliding_minimum():
    v = np.random.default_rng(0).integers(0, 50, 97).astype(np.uint64)
    for w in (1, 2, 7, 50, 97, 98):
        assert repeats.sliding_minimum(v, w).tolist() == [min(v[k : k + w]) for k in range(len(v) - w + 1)]


# -- archives -----------------------------------------------------------------------------

PAGES = [(1, "http://a.example/x", "<p>é</p>"), (2, None, None), (3, "http://a.example/y z\r\nq", "<p>é</p>"), (4, "http://b.example", ""), (None, "http://c.example", "<p>é</p>"), (5, "odd", "a\r\n\r\nWARC/1.1\r\n"), (6, "http://[bad", "q" * 5000)]


def test_archives(spark):
    pages = written(spark.createDataFrame([(*p, "x") for p in PAGES], "page_id long, url string, html string, digest string"), "test")
    folder = scratch_path(spark, "warc-test")
    records = written(warc.read_records(warc.write_captures(pages, folder), folder, payloads=True), "test")
    out = warc.assemble(records).collect()
    want = {}
    for i, _, h in PAGES:
        x = (h or "").encode()
        top = max(j for j, _, g in PAGES if (g or "") == (h or "") and j is not None)
        want[i] = (len(x), warc.payload_digest(x), "response" if i == top else "revisit", None if i == top else top)
    assert {r["capture_id"]: (r["payload_bytes"], r["payload_digest"], r["kind"], r["refers_to"]) for r in out} == want
    assert all(r["n_request"] == r["n_metadata"] == 1 and r["request"]["note"].startswith("GET ") for r in out)
    assert all(r["digest_ok"] and bytes(r["payload"]).decode() == dict((i, h or "") for i, _, h in PAGES)[r["capture_id"]] for r in out if r["kind"] == "response")
    empty = warc.write_captures(pages.limit(0), scratch_path(spark, "warc-test"))
    assert warc.assemble(warc.read_records(empty, folder)).count() == 0


def test_assembly_follows_identifiers(spark):
    rows = [("response", "r1", ["q1"]), ("request", "q1", []), ("metadata", "m1", ["q1"]), ("metadata", "m2", ["r1"]), ("request", "lost", ["nowhere"]), ("response", "r2", []), ("request", "q2", ["r2"]), ("metadata", "m3", ["q2"])]
    df = spark.createDataFrame([(k, i, c, None, None, None, None, None, None, None, None) for k, i, c in rows], warc.RECORD)
    out = {r["record_id"]: (r["n_request"], r["n_metadata"]) for r in warc.assemble(df).collect()}
    assert out["r1"][0] == 1 and out["r2"] == (1, 1) and set(out) == {"r1", "r2"}


# -- quality ------------------------------------------------------------------------------


def plain_counts(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
    lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(w[k : k + 8]) for k in range(len(w) - 7)]
    many, hit = Counter(windows), set()
    for k, x in enumerate(windows):
        if many[x] > 1:
            hit.update(range(k, k + 8))
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(hit)


def test_quality(spark):
    rng = np.random.default_rng(4)
    rows = [*corpus(), (40, "a b\nc d\n\na b\n # \n#\n"), (41, "w " * 50), (42, "one two three four five six seven eight nine " * 3)]
    rows += [(100 + k, sentence(rng, int(rng.integers(50, 200)))) for k in range(60)] + [(500, " ".join(w + "%%%" for w in sentence(rng, 80).split()))]
    d = spark.createDataFrame([(i, t, "en" if k % 9 else None, "s", 1) for k, (i, t) in enumerate(rows)], "doc_id long, text string, lang string, source string, n_words int")
    out = quality.judge(written(d, "test")).collect()
    assert ordered((r["doc_id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) for r in out) == ordered((i, *plain_counts(t)) for i, t in rows)
    kept = {r["doc_id"]: r["kept"] for r in out}
    assert not kept[500] and all(kept[100 + k] for k in range(60))
    assert all(r["base_failed"] == (r["n_words"] < 20 or 100 * r["n_repeat_words"] > 30 * r["n_words"]) for r in out)
    assert quality.judge(written(d.limit(0), "test")).count() == 0


def test_quality_rejects_every_kind_of_junk(spark):
    rng = np.random.default_rng(11)

    def lines(n, words=12):
        return [sentence(rng, words) for _ in range(n)]

    good = [(k, "\n".join(lines(int(rng.integers(8, 30))))) for k in range(300)]
    # a head line that stands again at the foot, and some signs in a long text, are no junk
    good += [(1000 + k, "\n".join([head, *lines(12), head])) for k, head in enumerate(lines(10))]
    good += [(1100 + k, "\n".join([*lines(20), "r&d 50% #1"])) for k in range(5)]
    junk = {
        "signs": [" ".join(w + "%%%" for w in sentence(rng, 150).split()) for _ in range(5)],
        "table": [" | ".join(sentence(rng, 150).split()) for _ in range(5)],
        "table with head": ["\n".join([head, *[" | ".join(x.split()) for x in lines(12)], head]) for head in lines(5)],
        "echo": [" ".join(w for w in WORDS[k : k + 8] for _ in range(6)) for k in range(5)],
        "lines": ["\n".join(x for y in lines(12, 6) for x in (y, f"click {WORDS[k]}")) for k in range(5)],
        "repeats": [" ".join([part, sentence(rng, 60), part, sentence(rng, 60)]) for part in lines(5, 20)],
    }
    bad = [(2000 + 100 * i + k, t) for i, texts in enumerate(junk.values()) for k, t in enumerate(texts)]
    d = spark.createDataFrame([(i, t, "en", "s") for i, t in good + bad], "doc_id long, text string, lang string, source string")
    out = {r["doc_id"]: r for r in quality.judge(written(d, "test")).collect()}
    assert not any(out[i]["base_failed"] for i, _ in good + bad)
    for i, kind in enumerate(junk):
        assert not [k for k in range(5) if out[2000 + 100 * i + k]["kept"]], kind
    lost = [i for i, _ in good if not out[i]["kept"]]
    assert len(lost) <= 3 and max(lost, default=0) < 1000


def _plain_robust(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Centre and covariance of one group by plain concentration steps, as the operator defines them."""
    floors = np.array(list(quality.FLOORS.values()))

    def distance(c, cov):
        return np.einsum("ij,jk,ik->i", x - c, np.linalg.inv(cov), x - c)

    def estimate(rows, factor):
        return rows.mean(0), np.cov(rows.T, bias=True) * factor + np.diag(floors**2)

    def step(c, cov):
        bins = np.clip(np.floor(np.log2(distance(c, cov) + 1e-6) * quality.BINS), -320, 640)
        cut = np.sort(bins)[(len(bins) + 1) // 2 - 1]
        return estimate(x[bins <= cut], quality.CONSISTENCY)

    found = []
    for q, spread in quality.STARTS:
        now = np.quantile(x, q, axis=0), np.diag((spread * floors) ** 2)
        for _ in range(quality.FIRST_STEPS):
            now = step(*now)
        found.append(now)
    now = min(found, key=lambda e: np.linalg.slogdet(e[1])[1])
    while True:
        then = step(*now)
        fall = np.linalg.slogdet(now[1])[1] - np.linalg.slogdet(then[1])[1]
        now = then if fall > 0 else now
        if fall < quality.SETTLED:
            return estimate(x[distance(*now) <= quality.NEAR], quality.NEAR_CONSISTENCY)


def test_robust_estimate_is_that_of_plain_steps_from_the_best_start(spark):
    rng = np.random.default_rng(5)
    good, bad = rng.normal([1700, 90, 40, 200, 60], [60, 40, 30, 90, 50], (900, 5)), rng.normal([900, 700, 500, 100, 900], 40, (500, 5))
    x = np.abs(np.concatenate([good, bad])).astype(np.int64)
    rows = spark.createDataFrame([("g", *map(int, r)) for r in x], "g string, " + ", ".join(f"{c} long" for c in quality.STATS))
    (got,) = quality.estimates(rows, ["g"]).collect()
    centre, cov = _plain_robust(x.astype(float))
    factor = np.array([[got[f"l{i}{j}"] if j <= i else 0.0 for j in range(5)] for i in range(5)])
    assert np.allclose([got[f"c{i}"] for i in range(5)], centre) and np.allclose(factor @ factor.T, cov)
    assert np.all(np.abs(centre - [1700, 90, 40, 200, 60]) < 30)  # the bad third doesn't move it


def test_written_tables_leave_no_shuffle_files(spark):
    """The shuffles of a write go when it ends, not at some garbage collection; the session's setting stays."""
    import time

    from pyspark.sql import functions as F

    from tensorlane.llm.common import CLEANUP

    def shuffles():
        dirs = list(spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString())
        return {f for d in dirs for _, _, files in os.walk(d) for f in files if f.startswith("shuffle_")}

    before, was = shuffles(), spark.conf.get(CLEANUP, None)
    rows = spark.range(20_000).groupBy((F.xxhash64("id") % 5000).alias("k")).agg(F.count("*").alias("n"))
    assert written(rows, "shuffled").agg(F.sum("n")).first()[0] == 20_000
    made = shuffles() - before
    written(rows, "again")
    until = time.time() + 10
    while (left := shuffles() - before - made) and time.time() < until:
        time.sleep(0.2)
    assert not left and spark.conf.get(CLEANUP, None) == was

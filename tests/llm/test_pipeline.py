import numpy as np

import corpus_pipeline
from tensorlane.llm import crf, personal_data
from tests.llm import test_operators as plain

DIR = "/root/testdata/sf0.001"


def test_stages_against_plain_versions(spark):
    """Every stage on all that its predecessor kept."""
    docs = spark.read.parquet(f"{DIR}/documents.parquet")
    names = docs.columns
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["quality", "near_duplicates", "decontamination", "personal_data", "packing"]

    def step(name, docs):
        path = corpus_pipeline.scratch_path(spark, f"test-{name}")
        stages[name](spark, docs, DIR).write.parquet(path)
        return spark.read.parquet(path)

    good = step("quality", docs)
    failed = {r["doc_id"] for r in docs.collect() if (c := plain.plain_counts(r["text"]))[0] < 20 or 100 * c[4] > 30 * c[0]}
    ids = {r["doc_id"] for r in good.collect()}
    assert good.columns == names and not ids & failed and len(ids) > 0.8 * (docs.count() - len(failed))
    one = step("near_duplicates", good)
    rows = [(r["doc_id"], r["text"]) for r in good.collect()]
    assert one.columns == names and {r["doc_id"] for r in one.collect()} == {d for d, _, _, kept in plain.brute_components(rows) if kept}
    clean = step("decontamination", one)
    rows = [(r["doc_id"], r["text"]) for r in one.collect()]
    items = [tuple(r) for r in spark.read.parquet(f"{DIR}/benchmark.parquet").select("item_id", "text").collect()]
    assert clean.columns == names and {r["doc_id"] for r in clean.collect()} == {d for d, _, hit, *_ in plain.brute_contamination(rows, items, 10) if not hit}
    marked = step("personal_data", clean)
    model = crf.trained()
    texts = {r["doc_id"]: r["text"] for r in clean.collect()}
    for r in marked.collect():
        data = texts[r["doc_id"]].encode()
        [(base, spans)] = personal_data.spans_of([data], model)
        assert r["text"] == personal_data.redacted(data, spans).decode() and not plain.plain_spans(r["text"]) and len(base) <= len(spans)
    pieces = step("packing", marked)
    rows = [(r["doc_id"], r["text"]) for r in marked.collect()]
    plain.check_pieces(pieces.collect(), rows, 1024)


def test_rows_with_null_or_repeated_ids_are_judged_one_by_one(spark):
    rng = np.random.default_rng(21)
    texts = [plain.sentence(rng, 80) for _ in range(60)]
    rows = [(None if k % 3 == 0 else k // 2, t) for k, t in enumerate(texts)]  # a third without an id, others in pairs
    junk = [(None, "too short"), (1, "too short"), (None, " ".join(w + "%%%" for w in texts[1].split()))]
    copies = [(None, texts[0]), (None, texts[3] + " more"), (500, texts[6]), (2, texts[5]), (7, texts[8] + " more")]
    every = [(i, t, "en", "s", len(t)) for i, t in rows + junk + copies]
    docs = plain.written(spark.createDataFrame(every, "doc_id long, text string, lang string, source string, n_chars long"), "test")
    stages = dict(corpus_pipeline.STAGES)
    good = plain.written(stages["quality"](spark, docs, DIR), "test")
    assert plain.ordered((r["doc_id"], r["text"]) for r in good.collect()) == plain.ordered(rows + copies)
    one = plain.ordered((r["doc_id"], r["text"]) for r in stages["near_duplicates"](spark, good, DIR).collect())
    groups = {}
    for i, t in rows + copies:
        groups.setdefault(t.removesuffix(" more"), []).append((i is None, i or 0, t))
    least = {g: min(members)[:2] for g, members in groups.items()}
    assert len(one) == len(texts) and {t.removesuffix(" more") for _, t in one} == set(texts)
    assert all((i is None, i or 0) == least[t.removesuffix(" more")] for i, t in one)


def test_no_stage_shuffles_its_texts(spark):
    rng = np.random.default_rng(22)
    texts = [plain.sentence(rng, 80) for _ in range(90)]
    every = [(k % 70, t, "en", "s", len(t)) for k, t in enumerate(texts + texts[:40] + ["too short"] * 3)]
    docs = plain.written(spark.createDataFrame(every, "doc_id long, text string, lang string, source string, n_chars long").repartition(5), "test")
    was = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")  # as for tables too large for it
    try:
        for name, stage in corpus_pipeline.STAGES[:2]:
            out = stage(spark, docs, DIR)
            plan = out._jdf.queryExecution().executedPlan().toString()
            assert "Exchange hashpartitioning" not in plan and "Exchange rangepartitioning" not in plan, name
            docs = plain.written(out, "test")
            assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"] and docs.count() == {"quality": 130, "near_duplicates": 90}[name]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", was)


def test_many_bitmaps_and_few_choose_the_same_rows(spark, monkeypatch):
    keyed = corpus_pipeline._keyed(spark.range(0, 200_000, 1, 3).withColumnRenamed("id", "n"), "test")
    kept = keyed.filter("n % 7 < 2 or n > 199990 or n = 0")
    want = [n for n in range(200_000) if n % 7 < 2 or n > 199_990]
    for limit in (corpus_pipeline.LOOKUP_BLOCKS, 1):
        monkeypatch.setattr(corpus_pipeline, "LOOKUP_BLOCKS", limit)
        assert sorted(r["n"] for r in corpus_pipeline._chosen(keyed, kept).collect()) == want
    assert corpus_pipeline._chosen(keyed, kept.limit(0)).count() == 0

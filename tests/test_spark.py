import pytest

import __spark_entry__ as entry
from tensorlane import baseline, measure
from tensorlane.pipeline import chain
from tensorlane.plans.scoring import compile_pipeline
from tensorlane.queries import SCALE, model, sparse_weights
from tensorlane.workloads import HIGGS, OPS

DIR = "/root/testdata/sf0.001"


def test_entry(spark):
    out = entry.entry(spark)
    assert out.count() > 0 and out.columns[-1] == "p6"


def test_injection_prunes_the_scan(spark):
    dag = chain(OPS.names, SCALE, ("lin.linear", {"w": sparse_weights(0.05), "b": [0.25]}))
    keep = ["l_orderkey"]
    plans = {}
    for rules in ((), ("inject", "push")):
        out = compile_pipeline(dag, lane="vector", rules=rules).score(OPS.frame(spark, DIR), keep)
        plans[rules] = out._jdf.queryExecution().executedPlan().toString()
    assert "o_totalprice" in plans[()] and "o_totalprice" not in plans[("inject", "push")]
    assert "Exchange hash" not in plans[("inject", "push")].split("MapInArrow")[0]


def test_lanes_and_baselines_agree(spark):
    f = model(HIGGS, "bagged", 4, 4, 2, classifier=True)
    df, keys = HIGGS.frame(spark, DIR), list(HIGGS.keys)
    dag = chain(HIGGS.names, ("trees.forest", {"spec": f}))
    v = compile_pipeline(dag, lane="vector", batch_rows=7).score(df, keys)
    for other in (baseline.case_sql(df, f, HIGGS.names, keys), baseline.udf_rowwise(df, f, HIGGS.names, keys), compile_pipeline(dag, lane="expression").score(df, keys)):
        assert measure.allclose(v, other, keys, ["p0", "p1"]).first()["mismatches"] == 0


def test_one_record_without_spark(spark):
    dag = chain(OPS.names, SCALE, ("lin.linear", {"w": sparse_weights(1.0), "b": [0.25]}))
    compiled = compile_pipeline(dag)
    row = OPS.frame(spark, DIR).first().asDict()
    want = compiled.score(OPS.frame(spark, DIR), list(OPS.keys)).filter("l_orderkey = %d and l_linenumber = %d and l_partkey = %d" % (row["l_orderkey"], row["l_linenumber"], row["l_partkey"])).first()
    assert compiled.score_one(row)["p1"] == pytest.approx(want["p1"], rel=1e-9)


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_measures():
    assert measure.truncated_mean([9, 1, 2, 3, 100]) == pytest.approx(14 / 3)
    assert measure.cost_per_prediction(3600.0, 2.0, 4) == 0.5

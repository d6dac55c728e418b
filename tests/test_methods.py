"""Worked examples, invariants and oracles of the estimation engine."""

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as registry
from predradius import operators as op
from predradius import plans
from predradius.functions import q_error
from predradius.methods import Suite
from predradius.sources import SUITES

COMPARED = ["embed_part", "true_selectivity_part", "true_selectivity_geo", "fixed_radius_part", "probed_radius_geo", "probed_radius_zero_part", "estimate_probed_part", "qerror_summary_part", "overhead_ci_geo", "overhead_reduction_part",
            "ball_count_vectors", "probe_configs_memory", "hist_equiwidth", "join_asof", "agg_cube", "win_range_frame", "pivot_report", "lateral_topk", "stream_session", "stream_tumbling",
            "linear_radius_geo", "qerror_summary_all_geo", "overhead_reduction_all_part", "domain_shift_geo", "radius_rules", "cell_synopsis_hard", "order_by_rank", "probe_residency", "prompt_render", "latency_model"]


def rows(df):
    df = df[sorted(df.columns)]
    return sorted((tuple(None if pd.isna(x) else round(float(x), 5) if isinstance(x, (int, float, np.number)) else str(x) for x in r) for r in df.astype(object).itertuples(index=False, name=None)), key=str)


@pytest.mark.parametrize("key", COMPARED)
def test_equals_sql(spark, sf_dir, key):
    con = duckdb.connect()
    con.sql("SET timezone = 'UTC'")
    for name in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"CREATE VIEW {name} AS SELECT * FROM '{sf_dir}/{name}.parquet'")
    mine, theirs = registry.queries()[key](spark, sf_dir).toPandas(), con.sql(registry.oracle_sql()[key]).df()
    assert rows(mine) == rows(theirs)


def test_registry_pairs():
    assert set(registry.oracle_sql()) <= set(registry.queries())
    assert all(14 <= len(s) <= 26 for s in SUITES.values())


def test_q_error_examples(spark):
    df = spark.createDataFrame([(0.2, 0.02), (0.002, 0.02), (0.0, 0.002)], "e double, t double")
    got = [r[0] for r in df.select(q_error(F.col("e"), F.col("t"), F.lit(1000))).collect()]
    assert got == pytest.approx([10, 10, 2])


@pytest.mark.parametrize("k, rule, expected", [(4, "next", 0.5), (4, "mid", 0.45), (0, "next", 0.1), (10, "next", op.ALL)])
def test_radius_rules(spark, k, rule, expected):
    dist = spark.createDataFrame([("c", i, (i + 1) / 10) for i in range(10)], "concept_id string, item_id int, dist double")
    got = op.radius_for_count(dist, ["concept_id"], F.max(F.lit(k)), rule).first()["radius"]
    assert got == pytest.approx(expected)
    if rule == "next":
        assert dist.filter(F.col("dist") < got).count() == k


def test_ties_admit_fewer(spark):
    dist = spark.createDataFrame([("c", i, d) for i, d in enumerate([0.1, 0.2, 0.2, 0.3])], "concept_id string, item_id int, dist double")
    assert op.radius_for_count(dist, ["concept_id"], F.max(F.lit(2))).first()["radius"] == 0.2


def test_chain_calls_of_example(spark):
    s = Suite(spark, "/root/testdata/sf0.01", "w1")
    pos = {c[0]: i for i, c in enumerate(SUITES["w1"])}
    orders = {0: ("ring", "red", "PROMO"), 1: ("red", "ring", "PROMO"), 2: ("ring", "PROMO", "red")}
    rows = [(q, 3, c, pos[c], i + 1) for q, o in orders.items() for i, c in enumerate(o)]
    ordered = spark.createDataFrame(rows, "query_id int, n_filters int, concept_id string, pos int, step int")
    got = {r["query_id"]: r["calls"] for r in plans.chain_calls(ordered, op.truth_masks(s.items, s.plain), []).collect()}
    assert got == {0: 2279, 1: 2288, 2: 2296}


def test_fused_chain_short_circuits(spark):
    by = {c[0]: c for c in SUITES["w1"]}
    s = Suite(spark, "/root/testdata/sf0.01", "w1")
    got = plans.SemanticQuery(s.items).where(by["red"]).where(by["ring"]).execute().agg(F.sum("calls"), F.sum(F.col("passed").cast("int"))).first()
    assert tuple(got) == (2257, 31)


def test_ball_count_is_one_aggregation(spark, sf_dir):
    s = Suite(spark, sf_dir, "w1")
    plan = op.ball_selectivity(s.syn, s.concepts.withColumn("radius", F.lit(0.5)), ["concept_id"])._jdf.queryExecution().toString()
    assert "MapInArrow" in plan and "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan


def test_empty_collection(spark, sf_dir):
    s = Suite(spark, sf_dir, "w1")
    empty = s.syn.filter("item_id < 0")
    got = op.ball_selectivity(empty, s.concepts.withColumn("radius", F.lit(0.5)), ["concept_id"]).collect()
    assert all(not r["hits"] and r["selectivity"] is None for r in got)


def test_learned_radius_fits(spark, sf_dir):
    training = op.radius_training_set(Suite(spark, sf_dir, "w1").items, 10, 100, 30)
    model = op.LearnedRadius.fit(training, epochs=30)
    x = training.collect()
    error = np.abs(model.predict(op.LearnedRadius.unit(x)) - np.array([r["radius"] for r in x])).mean()
    assert error < 0.12


def test_parts_without_the_llm_folder(monkeypatch):
    monkeypatch.setattr(registry, "installed", lambda name: False)
    assert not any(k.startswith("op1_") or k == "pipeline" for k in registry.queries())

"""Queries against their SQL on the smallest tables, and properties of the methods."""

import pytest
from pyspark.sql import functions as F

from corpusmill.operators import dedup, minhash, recall, rules, transform
from corpusmill.operators.components import components
from corpusmill.schema import files
from corpusmill.workloads import registry
from corpusmill.workloads.parity import differences

SF = "/root/testdata/sf0.001"
SOME = "prep_size_gate prep_notebook_cells dedup_exact_best dedup_exact_window dedup_level_report dedup_chunk_lines dedup_repo_exact fuzzy_shingle_counts minhash_signature_small lsh_components rules_violations rules_threshold_sweep rule_code_bracket_balance xform_mask_all sample_budget_lang corpus_composition decontam_10gram recall_domains anneal_mixture measure_macro_average schedule_wsd join_asof_events".split()


@pytest.mark.parametrize("name", SOME)
def test_matches_sql(spark, name):
    assert differences(spark, SF, registry.queries()[name], registry.oracles()[name]) == ""


def test_exact_dedup_is_idempotent_and_keeps_each_text_once(spark):
    once = dedup.exact_dedup(files(spark, SF))
    assert once.count() == 189 == once.select("text").distinct().count() == dedup.exact_dedup(once).count()


def test_banding_with_many_bands_finds_near_copies(spark):
    edges = minhash.fuzzy_edges(files(spark, SF), 512, 128, 4)
    found = minhash.verify_edges(edges, files(spark, SF), 80).count()
    assert found >= minhash.shared_gram_pairs(files(spark, SF), 100).count()


def test_components_of_path_star_and_bridge(spark):
    pairs = [(i, i + 1) for i in range(11)] + [(20, i) for i in range(21, 29)] + [(40, 41), (41, 42), (42, 40), (50, 51), (42, 50), (7, 7), (0, 1)]
    got = {r.node: r.root for r in components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(12)}, **{i: 20 for i in range(20, 29)}, **{i: 40 for i in (40, 41, 42, 50, 51)}}


def test_masks_leave_nothing_and_notice_goes(spark):
    rows = spark.createDataFrame([('mail a.b@c.org, 1.2.3.4, +1 (234) 555-1234, 4111111111111111, token = "abcdef0123"',)], "text string")
    assert rows.select(transform.mask(F.col("text"))).first()[0] == "mail <email>, <ip>, <phone>, <card>, <secret>"
    code = spark.createDataFrame([("/* Copyright 2014 X */\nint a;\n",), ("int b;\n",)], "text string")
    assert [r[0] for r in code.select(transform.strip_notice(F.col("text"))).collect()] == ["int a;\n", "int b;\n"]


def test_domain_share_is_strict(spark):
    pages = spark.createDataFrame([(i, f"http://a.net/{i}") for i in range(10)] + [(i, f"http://www.b.net/{i}") for i in range(10, 15)], "id long, url string")
    hits = spark.createDataFrame([(0,), (10,)], "id long")
    assert [r.host for r in recall.discover(pages, hits).collect()] == ["b.net"]


def test_rules_compile_into_one_narrow_plan(spark):
    plan = rules.apply_rules(files(spark, SF), rules.TEXT_RULES)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Python" not in plan

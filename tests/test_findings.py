"""Findings on workloads: each test fails on the code before."""

from __future__ import annotations

import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["rules_keep_any", "rules_keep_weighted", "rules_report"])
def test_rules_split_a_text_once(spark, name):
    """A filter that is pushed below the staged words would split the text again for each n-gram."""
    plan = entry.queries()[name](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("split(text") == 2


def _plan(spark, name):
    return entry.queries()[name](spark, SF)._jdf.queryExecution().optimizedPlan().toString()


def test_theta_join_is_dealt_by_size_too(spark):
    assert _plan(spark, "join_theta").count("p_size") > 2 and "abs(" not in _plan(spark, "join_theta")


def test_character_grams_take_a_text_apart_once(spark):
    assert "substring(" not in _plan(spark, "fuzzy_shingle_counts")


def test_pairs_are_found_by_the_rarest_grams(spark):
    from pyspark.sql import functions as F

    from corpusmill.operators import minhash
    from corpusmill.schema import files

    row = minhash.gram_prefixes(files(spark, SF), 70).agg(F.sum(F.size("prefix")).alias("held"), F.sum("m").alias("m"), F.count(F.lit(1)).alias("n")).first()
    assert 0 < row.held <= 0.3 * row.m + row.n


@pytest.mark.parametrize(
    "name",
    "ablate_anneal_without_hq anneal_algorithmic_files anneal_mixture_table lsh_s_curve measure_gpu_hours measure_macro_average prep_notebook_cells rule_code_assert_share rule_code_bracket_balance rule_code_code_lines rule_code_comment_share rule_code_config_like".split(),
)
def test_the_job_is_done_on_a_given_table(spark, name):
    from corpusmill.workloads.parity import differences

    assert "parquet" in _plan(spark, name) and entry.queries()[name](spark, SF).limit(1).count() == 1
    assert differences(spark, SF, entry.queries()[name], entry.oracle_sql()[name]) == ""


def test_word_grams_take_words_by_place(spark):
    assert "slice(" not in _plan(spark, "fuzzy_shingle_counts")


def test_equal_programs_run_once(spark, tmp_path):
    """Each program leaves a file behind; nulls are no text, and equal codes with other tests are other programs."""
    import tempfile

    from corpusmill.operators import snippets

    rows = [(i, lang, code, test) for i, (lang, code, test) in enumerate([("python", "a", "b"), ("python", "a", "b"), ("python", "ab", ""), ("python", None, "b"), ("python", "", "b"), ("rust", "a", "b"), ("python", "a", "c")] * 3)]

    def runner(code, test, seconds, megabytes, folder=str(tmp_path)):
        tempfile.mkstemp(dir=folder)
        return code + test

    found = snippets.run_tests(spark.createDataFrame(rows, "id long, lang string, code string, test string"), runners={"python": runner}).orderBy("id").collect()
    assert [(r.id, r.lang, r.code, r.test) for r in found] == rows
    assert [r.verdict for r in found] == ["ab", "ab", "invalid", "invalid", "invalid", "skipped", "ac"] * 3
    assert len(list(tmp_path.iterdir())) == 2


def test_library_pairs_between_classes(spark):
    """Classes and their copies, written out, are the pairs of the library's own join."""
    from itertools import combinations, product

    from pyspark.ml.feature import HashingTF, MinHashLSH
    from pyspark.sql import functions as F

    from corpusmill.operators import minhash
    from corpusmill.schema import files

    rows = files(spark, SF).select("file_id", minhash.shingles(F.col("text")).alias("g")).where("size(g) > 0")
    vec = HashingTF(inputCol="g", outputCol="v", numFeatures=1 << 20, binary=True).transform(rows).select("file_id", "v").cache()
    joined = MinHashLSH(inputCol="v", outputCol="h", numHashTables=8, seed=3).fit(vec).approxSimilarityJoin(vec, vec, 0.3, "dist")
    want = {(r.a, r.b): r.d for r in joined.select(F.col("datasetA.file_id").alias("a"), F.col("datasetB.file_id").alias("b"), F.round("dist", 6).alias("d")).where("a < b").collect()}
    found = entry.queries()["baseline_minhash_ml"](spark, SF).collect()
    classes: dict = {}
    for r in found:
        if r["copy"]:
            classes.setdefault(r.a, [r.a]).append(r.b)
    got = {(min(x, y), max(x, y)): 0.0 for c in classes.values() for x, y in combinations(c, 2)}
    for r in found:
        if not r["copy"]:
            got |= {(min(x, y), max(x, y)): r.dist for x, y in product(classes.get(r.a, [r.a]), classes.get(r.b, [r.b]))}
    assert got == want and len(found) == len({(r.a, r.b) for r in found}) and classes and any(not r["copy"] for r in found)


@pytest.mark.parametrize("rows", [1_000, 3])
def test_theta_join_makes_no_other_pairs(spark, tmp_path, monkeypatch, rows):
    """Equal prices, nulls and groups of several runs; no comparison of prices is left behind the join."""
    from corpusmill.workloads import relational
    from corpusmill.workloads.parity import differences

    monkeypatch.setattr(relational, "RUN_ROWS", rows)
    made = [(i, None if i % 29 == 0 else f"b{i % 2}", None if i % 31 == 0 else float(i % 11), None if i % 37 == 0 else i % 5) for i in range(200)]
    spark.createDataFrame(made, "p_partkey long, p_brand string, p_retailprice double, p_size int").write.parquet(f"{tmp_path}/part.parquet")
    found = [(r.a, r.b) for r in relational.theta(spark, str(tmp_path)).collect()]
    want = [(a, b) for a, x, p, s in made for b, y, q, t in made if None not in (x, p, s, y, q, t) and x == y and p < q and abs(s - t) < 2]
    assert sorted(found) == sorted(want)
    assert differences(spark, SF, entry.queries()["join_theta"], entry.oracle_sql()["join_theta"]) == ""
    assert "low#" not in _plan(spark, "join_theta") and "slice(" in _plan(spark, "join_theta")


def test_library_pairs_keep_only_what_is_read_again(spark, monkeypatch):
    """The tables of terms and of shared terms are gone from the shared folder when the pairs are there."""
    from corpusmill.operators import minhash
    from corpusmill.schema import files

    made, settled = [], minhash.settled
    monkeypatch.setattr(minhash, "settled", lambda df: made.append(settled(df)) or made[-1])
    found = minhash.ml_pairs(files(spark, SF))
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    there = [df for df in made if (p := path(df.inputFiles()[0])).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)]
    assert len(there) < len(made) and not any("terms" in df.columns or "term" in df.columns for df in there) and found.count()

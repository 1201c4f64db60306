"""Methods that SQL does not express, against plain readings, and properties of those that it does."""

import subprocess
import sys

import numpy as np
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from corpusmill.functions.bpe import token_ids
from corpusmill.operators import classifier, minhash, recall, rules, snippets, transform
from corpusmill.operators.components import components, merge_labels
from corpusmill.schema import files
from corpusmill.streaming import jobs
from corpusmill.workloads import registry
from corpusmill.workloads.parity import differences

SF = "/root/testdata/sf0.001"
SOME = "xform_strip_notice_head xform_notice_documents xform_mask_names pii_luhn recall_logodds_report recall_multi_corpus recall_domain_topics stream_tumbling stream_sliding stream_session stream_interval_join sink_roundtrip sql_surface_documents synth_run_tests anneal_algorithmic_files sample_byte_budget sft_page_sentences vec_cosine_topk scores_base_lead scores_two_stages_win rule_nl_top_ngram_2 rule_nl_entropy rule_lang_html_visible_text rules_threshold_sweep_low jaccard_verified_pairs sft_prompts corpus_compare".split()


@pytest.mark.parametrize("name", SOME)
def test_matches_sql(spark, name):
    assert differences(spark, SF, registry.queries()[name], registry.oracles()[name]) == ""


def test_entry_imports_without_a_session():
    code = "import __spark_entry__ as e; print(len(e.queries()) > 250)"
    assert subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd="/root/repo" if not __file__ else __file__.rsplit("/tests/", 1)[0]).stdout.strip().endswith("True")


def test_components_of_a_long_path(spark):
    pairs = spark.range(400).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert [tuple(r) for r in components(pairs).agg(F.count("*"), F.max("root")).collect()] == [(401, 0)]
    labels = spark.createDataFrame([(1, 1), (2, 1), (5, 5), (6, 5), (9, 9)], "node long, root long")
    merged = merge_labels(labels, spark.createDataFrame([(2, 6)], "a long, b long"))
    assert {r.node: r.root for r in merged.collect()} == {1: 1, 2: 1, 5: 1, 6: 1, 9: 9}


def test_notices_past_four_thousand_characters_and_long_secrets(spark):
    long_head = "# line\n" * 900 + "# Copyright 2020 X\n# end\nx = 1\n"
    block = "/* " + "words http://a.b/ " * 400 + "Copyright 2020 */\n\nint a;\n"
    late = "x = 1\n# Copyright 2020\n"
    rows = spark.createDataFrame([(1, long_head), (2, block), (3, late), (4, None), (5, ""), (6, "# only\n# Copyright")], "id int, text string")
    got = {r.id: r.t for r in rows.select("id", transform.strip_notice(F.col("text")).alias("t")).collect()}
    assert got == {1: "x = 1\n", 2: "int a;\n", 3: late, 4: None, 5: "", 6: ""}
    secret = 'password = "' + "a1" * 101 + '" mail ' + "b" * 70 + "@" + "c" * 70 + ".org"
    masked = spark.createDataFrame([(secret,), ("x" * 200_000,)], "text string").select(transform.mask(F.col("text"))).collect()
    assert masked[0][0] == "<secret> mail <email>" and masked[1][0] == "x" * 200_000


def exact_similarity(a, b):
    return len(np.intersect1d(a, b)) / len(np.union1d(a, b))


def test_production_signature_estimates_similarity():
    rng = np.random.default_rng(1)
    words = [f"w{i}" for i in rng.integers(0, 10**9, 3000)]
    base = minhash.gram_hashes(" ".join(words[:1500]), 5, "word")
    for kept in (300, 800, 1200, 1480):
        other = minhash.gram_hashes(" ".join(words[:kept] + words[1500 : 3000 - kept]), 5, "word")
        estimate = (minhash.least_values(base, 2048) == minhash.least_values(other, 2048)).mean()
        assert abs(estimate - exact_similarity(base, other)) < 0.05
    grams = {"the cat sat on the mat"[i : i + 5] for i in range(18)}
    assert len(minhash.gram_hashes("the cat sat on the mat", 5, "char")) == len(grams) and len(minhash.gram_hashes("", 5, "char")) == 0


def test_fuzzy_dedup_of_16_bands_of_128(spark):
    """Survivors against band keys compared in plain Python: groups of texts that share a key, and the best of each group."""
    rows = files(spark, SF)
    texts = {r.file_id: r for r in rows.select("file_id", "text", "stars", "commit_day").collect()}
    keys = {}
    for i, r in texts.items():
        grams = minhash.gram_hashes(r.text, 5, "word")
        for band, key in enumerate(minhash.band_keys(minhash.least_values(grams, 2048), 16, 128) if len(grams) else []):
            keys.setdefault((band, int(key)), []).append(i)
    root = {i: i for i in texts}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for members in keys.values():
        for i in members[1:]:
            a, b = find(members[0]), find(i)
            root[max(a, b)] = min(a, b)
    best = {}
    for i, r in texts.items():
        g = find(i)
        best[g] = max(best.get(g, (-1, -1, 0, 0)), (r.stars, r.commit_day, -i, i))
    assert {r.file_id for r in minhash.fuzzy_dedup(rows).select("file_id").collect()} == {b[3] for b in best.values()}


def test_bpe_ids_equal_the_tokenizer(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    plain = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    plain.encode_special_tokens = True  # this function reads the string of an added token as ordinary text
    for text in [*pq.read_table(f"{SF}/documents.parquet").column("text").to_pylist(), "", " " * 1_500_000, "a <|endoftext|> b"]:
        assert token_ids(text).tolist() == plain.encode(text or "", add_special_tokens=False).ids


def test_averaged_vectors_on_held_out_labels(spark):
    rows = {r.cut: r for r in registry.queries()["recall_classifier_report"](spark, "/root/testdata/sf0.01").collect()}
    assert rows[0.5].auc > 0.9 and rows[0.5].f1 > 0.9
    scored = spark.createDataFrame([(0.9, 1), (0.8, 0), (0.7, 1), (0.7, 0), (0.1, 0)], "score double, y int")
    report = classifier.report(scored, [0.75]).first()
    assert (report.auc, report.precision, report.recall) == (round((3 + 1.5) / 6, 6), 0.5, 0.5)


def test_recall_rounds_grow_the_seed(spark):
    pages = spark.createDataFrame([(i, f"http://a.net/q/{i}", "alpha beta gamma" if i < 4 else "nothing here") for i in range(12)] + [(20 + i, f"http://b.net/q/{i}", "plain words of prose") for i in range(5)], "id long, url string, text string")
    seed = spark.createDataFrame([(100 + i, "alpha beta gamma delta" if i % 2 else "plain words of other prose", i % 2) for i in range(40)], "id long, text string, y int")
    got = recall.loop(pages, seed, ["/q"], cut=0.0, fit=recall.log_odds).collect()
    assert [(r["round"], r.n_seed, r.n_hits, r.n_domains, r.n_added) for r in got][:1] == [(1, 40, 4, 1, 8)] and got[1].n_seed == 48
    assert got[-1].n_added == 0 or len(got) == 3


def test_verdicts_of_snippets(spark):
    made = snippets.generate(spark.createDataFrame([(1, "python", "a b c"), (2, "python", "a b"), (3, "rust", None)], "id long, lang string, prompt string"))
    assert {r.id: r.verdict for r in snippets.run_tests(made).collect()} == {1: "failed", 2: "passed", 3: "skipped"}


def test_stream_of_near_duplicates_keeps_one_of_each_family(spark):
    body = " ".join(f"w{i}" for i in range(200))
    batches = [[(1, body), (2, body + " x"), (3, "other words that nobody else has in a row at all")], [(4, body + " y"), (5, "a new text of its own with many words in it")], [(6, "a new text of its own with many words in it")]]
    frames = [spark.createDataFrame(b, "file_id long, text string") for b in batches]
    assert sorted(r.file_id for r in jobs.near_duplicates(frames).collect()) == [1, 3, 5]


def test_late_rows_are_dropped_and_rows_in_time_are_not(spark):
    rows = lambda times: spark.createDataFrame([(i, t, "view") for i, t in enumerate(times)], "event_id long, ts string, event_type string")
    got = jobs.late_counts(rows(["2024-01-01 10:00:00", "2024-01-05 10:00:00"]), rows(["2024-01-01 11:00:00", "2024-01-09 00:00:00"]), "1 hour").collect()
    assert {str(r.start)[:10]: r.n for r in got} == {"2024-01-01": 1, "2024-01-05": 1}


def test_registry_has_the_rules_of_eight_languages():
    named = {r.lang for r in rules.REGISTRY if r.lang}
    assert len(rules.REGISTRY) > 130 and len(named) == 8 and all(r.low is not None or r.high is not None for r in rules.REGISTRY)

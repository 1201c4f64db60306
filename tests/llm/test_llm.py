"""Operators against brute force on small tables, with nulls, empty texts, repeated rows, clashing names and empty tables."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest

from corpusmill.llm import decontamination, fuzzy_lines, grouped_suffixes, hashing, html_extract, jaccard_join, license_scan, packing, pii, quality_rules, secret_scan, suffix_dedup

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, n int, key string, pos int"
BODY = " ".join(f"word{i}" for i in range(60))
LONG = "".join(f"<{i}>" for i in range(120))
TEXTS = [(1, None), (2, ""), (3, BODY), (3, BODY), (4, BODY + " end"), (5, "x y z"), (6, " \n\n "), (7, LONG + "a"), (8, "q" + LONG), (9, "same line here\nother line there\nsame line here"), (10, "MIT License token = abcdefgh a@b.org 1.2.3.4"), (11, "é" * 300)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, "en", None if i == 5 else "s", None, 1, "k", 2) for i, t in TEXTS], SCHEMA).cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


def test_suffix_sorter():
    rng = random.Random(3)
    for _ in range(500):
        s = [rng.randint(1, rng.choice([1, 2, 4])) for _ in range(rng.randint(0, 25))] + [0]
        assert grouped_suffixes.suffix_array(s) == sorted(range(len(s)), key=lambda i: s[i:])


@pytest.mark.parametrize("group", [4096, 1])
def test_repeated_strings(docs, none, group, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "GROUP", group)
    data = [(i, (t or "").encode()) for i, t in TEXTS]
    seen = {}
    for _, t in data:
        for i in range(len(t) - 199):
            seen[t[i : i + 200]] = seen.get(t[i : i + 200], 0) + 1
    want = []
    for i, t in data:
        gone = bytearray(len(t))
        for k in range(len(t) - 199):
            if seen[t[k : k + 200]] > 1:
                gone[k : k + 200] = b"\1" * 200
        left = bytes(b for b, g in zip(t, gone) if not g)
        want.append((i, len(t), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(left).hexdigest()))
    assert rows(suffix_dedup.repeated_report(docs)) == sorted(want, key=str)
    assert suffix_dedup.repeated_report(none).count() == 0


def test_jaccard_components(docs, none):
    got = rows(jaccard_join.jaccard_components(docs))
    sets = [(i, set(hashing.shingle_set((t or "").encode()).tolist())) for i, t in TEXTS]
    root = {i: i for i, _ in sets}
    for _ in range(len(sets)):
        for i, s in sets:
            for j, t in sets:
                if s and t and 100 * len(s & t) >= 80 * len(s | t):
                    root[i] = root[j] = min(root[i], root[j])
    assert got == sorted(((i, len(s), root[i]) for i, s in sets), key=str)
    assert jaccard_join.jaccard_components(none).count() == 0
    kept = jaccard_join.keep_one(docs)
    assert kept.columns == docs.columns and sorted(r.doc_id for r in kept.collect()) == [1, 2, 3, 5, 6, 7, 8, 9, 10, 11]


def test_fuzzy_lines(docs, none):
    got = {r.doc_id: r for r in fuzzy_lines.dedup_report(docs).collect()}
    assert got[9].removed_lines == "2" and got[1].n_lines == got[6].n_lines == 0 and got[3].n_removed == 0
    assert fuzzy_lines.dedup_report(docs).count() == len(TEXTS) and fuzzy_lines.dedup_report(none).count() == 0
    assert fuzzy_lines.dedup_lines(docs).columns == docs.columns


def test_packing(docs, none):
    got = packing.pack_documents(docs, 64).collect()
    by = {}
    for r in got:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 64
    for i in (7, 11):
        ids = packing.token_bytes(dict(TEXTS)[i]) + b"\0\0\0\0"
        mine = sorted((r.piece, r.start, r.length, r.ids_crc32) for r in got if r.doc_id == i)
        assert sum(x[2] for x in mine) == len(ids) // 4 and all(zlib.crc32(ids[4 * s : 4 * (s + n)]) == c for _, s, n, c in mine)
    assert packing.pack_documents(none).count() == 0
    histogram = {5: 7, 9: 3, 33: 4, 64: 2, 31: 4}
    plan = packing.plan(histogram, 64, rounds=20)
    filled = np.zeros(65, int)
    for pattern, n in plan.patterns:
        assert sum(pattern) <= 64
        for length in pattern:
            filled[length] += n
    assert {k: v for k, v in enumerate(filled) if v} == histogram and plan.bound <= plan.sequences


def _fewest(pieces, capacity):
    """Least sequences by trying all: pieces in descending order go to each open sequence or to a new one."""
    best = [len(pieces)]

    def place(k, rooms):
        if len(rooms) >= best[0]:
            return
        if k == len(pieces):
            best[0] = len(rooms)
            return
        for at in {r: i for i, r in enumerate(rooms) if r >= pieces[k]}.values():
            place(k + 1, rooms[:at] + [rooms[at] - pieces[k]] + rooms[at + 1 :])
        place(k + 1, [*rooms, capacity - pieces[k]])

    place(0, [])
    return best[0]


def test_packing_against_the_fewest_sequences():
    rng = np.random.default_rng(5)
    for _ in range(25):
        pieces = sorted(rng.integers(1, 21, size=9).tolist(), reverse=True)
        histogram = dict(zip(*(x.tolist() for x in np.unique(pieces, return_counts=True))))
        plan = packing.plan(histogram, 20, rounds=30)
        fewest = _fewest(pieces, 20)
        assert plan.bound <= fewest <= plan.sequences <= fewest + 1
    many = {int(k): int(n) for k, n in zip(range(40, 1900, 7), rng.integers(1, 400, size=270))}
    plan = packing.plan(many, 2048)
    assert plan.sequences <= 1.003 * plan.bound and 2 * plan.rounded > plan.sequences


def test_packing_ids_equal_the_tokenizer():
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    import pyarrow.parquet as pq

    texts = ["a  b\n\nc", "été <|endoftext|> x", "<|endoftext|> hi", "\t tab 123 's", "🙂", " " * 1_500_000, "x" + "\n\t" * 60_000 + "y <|endoftext|>" + " " * 60_000]
    texts += [x or "" for x in pq.read_table("/root/testdata/sf0.01/documents.parquet").column("text").to_pylist()]
    for text in texts:
        assert np.frombuffer(packing.text_ids(text), "<u4").tolist() == t.encode(text, add_special_tokens=False).ids


def test_quality_and_decontamination(docs, none, spark):
    report = {r.doc_id: r for r in quality_rules.quality_report(docs).collect()}
    assert report[1].base_failed and report[3].kept and report[9].n_dup_lines == 1 and quality_rules.quality_report(none).count() == 0
    assert quality_rules.keep_quality(docs).columns == docs.columns
    bench = spark.createDataFrame([("b", " ".join(f"WORD{i}" for i in range(10, 25))), ("a", "y z"), ("n", None)], "item_id string, text string")
    got = {r.doc_id: r for r in decontamination.contamination(docs, bench).collect()}
    assert (got[3].n_hit, got[3].n_items, got[5].n_hit, got[1].n_words) == (15, 1, 2, 0)
    assert decontamination.contamination(docs, bench).count() == len(TEXTS) and decontamination.contamination(none, bench).count() == 0
    assert sorted(r.doc_id for r in decontamination.drop_contaminated(docs, bench).collect()) == [1, 2, 6, 7, 8, 9, 10, 11]
    assert not decontamination.contamination(docs, bench.limit(0)).where("contaminated").count()


def test_scans(docs, none):
    got = {r.doc_id: r for r in license_scan.scan_licenses(docs).collect()}
    assert (got[10].n_base, got[10].first_word, got[10].labels) == (1, 0, "mit") and got[1].n_words == 0
    assert license_scan.evaluate("MIT OR (GPL-2.0-only AND Apache-2.0)") == ({"mit", "gpl", "apache"}, True)
    assert license_scan.evaluate("GPL-2.0 WITH Classpath-exception AND MIT")[1] is False
    assert {r.doc_id: r.n_assign for r in secret_scan.scan_secrets(docs).collect()}[10] == 1
    assert "hidden_assign:0:32" in secret_scan.scan("cGFzc3dvcmQgPSAic3VwZXJzZWNyZXQi")[4]
    found = {r.doc_id: r for r in pii.scan_pii(docs).collect()}
    assert (found[10].n_email, found[10].n_ip) == (1, 1)
    for f in (license_scan.scan_licenses, secret_scan.scan_secrets, pii.scan_pii):
        assert f(none).count() == 0


def test_pii_field_on_held_out_sentences():
    weights, right, wrong, missed = pii.fitted(), 0, 0, 0
    for text, spans in pii.training_sentences(100, seed=1234):
        got = set(pii.decode(text, weights))
        right, wrong, missed = right + len(got & set(spans)), wrong + len(got - set(spans)), missed + len(set(spans) - got)
    assert right > 0.95 * (right + missed) and right > 0.95 * (right + wrong)


def test_html():
    page = "<body><nav><a>x</a></nav><article><h1>A &amp; b</h1><p>One <b>two</b>\n three.<p>Four.</article><div class='comments'><p>no</p></div><footer>f</footer>"
    assert html_extract.main_text(page) == "A & b\n\nOne two three.\n\nFour." and html_extract.main_text(None) == ""

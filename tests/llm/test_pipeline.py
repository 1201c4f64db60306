"""Each stage of the pipeline against a plain reading of what the stage before it kept, and run() against the stages one by one."""

import re
import zlib

import numpy as np
import pytest

import corpus_pipeline
from corpusmill.llm import fuzzy_lines
from corpusmill.llm.common import settled
from test_contracts import WORD, lower, near_links, roots_of, shingles

SF = "/root/testdata/sf0.001"
SPACED = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def steps(spark):
    """The rows of documents and of each stage's result, in order."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = [docs]
    for _, stage in corpus_pipeline.STAGES:
        out.append(settled(stage(spark, out[-1], SF)))
    return out


def rows(df):
    return {r.doc_id: r for r in df.collect()}


def test_stages_keep_the_columns(steps):
    assert all(s.columns == steps[0].columns for s in steps[:-1]) and [n for n, _ in corpus_pipeline.STAGES] == ["quality rules", "line dedup", "near duplicates", "decontamination", "packing"]
    for s in steps[1:-1]:
        assert all(r.n_chars == len(r.text) for r in s.collect())


def test_quality_stage(steps):
    docs, got = rows(steps[0]), rows(steps[1])
    norm = lambda x: " ".join(re.sub(r"[\x20\x09-\x0D]+", " ", x).strip(" ").lower().split(" "))
    lines, hosts = {}, {}
    for i, r in docs.items():
        host = r.source or ""
        hosts[host] = hosts.get(host, 0) + 1
        for key in {norm(x) for x in (r.text or "").split("\n") if SPACED.search(x)}:
            lines.setdefault((host, key), set()).add(i)
    over = {k for k, v in lines.items() if len(v) > 20 and len(v) > 0.1 * hosts[k[0]]}
    kept = {}
    for i, r in docs.items():
        words = SPACED.findall(r.text or "")
        windows = [tuple(words[k : k + 5]) for k in range(len(words) - 4)]
        twice = {w for w in windows if windows.count(w) > 1} if len(set(windows)) < len(windows) else set()
        repeated = {p for k, w in enumerate(windows) if w in twice for p in range(k, k + 5)}
        left = "\n".join(x for x in (r.text or "").split("\n") if not SPACED.search(x) or (r.source or "", norm(x)) not in over)
        n, m = len(words), len(SPACED.findall(left))
        if n >= 10 and 100 * len(repeated) <= 20 * n and (m == n or m >= 10 and m >= 0.2 * n):
            kept[i] = left
    assert {i: r.text for i, r in got.items()} == kept


def test_line_stage(steps):
    docs, got = rows(steps[1]), rows(steps[2])
    assert docs.keys() == got.keys()
    places = [(i, k, fuzzy_lines.normalise(x)) for i, r in sorted(docs.items()) for k, x in enumerate(r.text.split("\n"))]
    lines = sorted({x for _, _, x in places if x})
    links = list(near_links(lines))
    group = dict(zip(lines, roots_of(len(lines), links)))
    stays = set()  # groups of which an earlier occurrence stayed
    missed = removed = 0
    for i, r in sorted(docs.items()):
        left = got[i].text.split("\n")
        at = 0
        for x in r.text.split("\n"):
            line = fuzzy_lines.normalise(x)
            if at < len(left) and left[at] == x:
                at += 1
                missed += bool(line) and group[line] in stays
                stays |= {group[line]} if line else set()
            else:
                removed += 1
                assert line and group[line] in stays, (i, x)
        assert at == len(left) or left == [""], i
    assert removed and missed <= 0.1 * (removed + missed), (removed, missed)


def test_near_duplicate_stage(steps):
    docs, got = rows(steps[2]), rows(steps[3])
    ids = sorted(docs)
    sets = [shingles(docs[i].text) for i in ids]
    links = [(a, b) for a in range(len(ids)) for b in range(a + 1, len(ids)) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])]
    roots = roots_of(len(ids), links)
    assert {i: r.text for i, r in got.items()} == {ids[k]: docs[ids[k]].text for k in range(len(ids)) if roots[k] == k}


def test_decontamination_stage(spark, steps):
    docs, got = rows(steps[3]), rows(steps[4])
    windows = set()
    for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect():
        w = WORD.findall(lower(r.text))
        windows |= {tuple(w[k : k + 10]) for k in range(max(1, len(w) - 9))} if w else set()
    sizes = {len(w) for w in windows}
    clean = {}
    for i, r in docs.items():
        w = WORD.findall(lower(r.text))
        if not any(tuple(w[k : k + n]) in windows for n in sizes for k in range(len(w) - n + 1)):
            clean[i] = r.text
    assert {i: r.text for i, r in got.items()} == clean and len(clean) < len(docs) + 1


def test_packing_stage(steps):
    import public_tokenizers
    from tokenizers import Tokenizer

    plain = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    pieces = {}
    for r in steps[5].collect():
        pieces.setdefault(r.doc_id, []).append(r)
    docs = rows(steps[4])
    assert pieces.keys() == docs.keys()
    total = 0
    for i, r in docs.items():
        ids = np.array([*plain.encode(r.text or "", add_special_tokens=False).ids, 0], "<u4")
        at = 0
        for k, p in enumerate(sorted(pieces[i], key=lambda p: p.piece)):
            assert (p.piece, p.start) == (k, at) and p.ids_crc32 == zlib.crc32(ids[at : at + p.length].tobytes()) and (k == 0 or p.length == 2048)
            at += p.length
        assert at == len(ids)
        total += at
    sequences = {}
    for p in (p for ps in pieces.values() for p in ps):
        sequences.setdefault(p.sequence_id, []).append((p.offset, p.length))
    for parts in sequences.values():
        ends = 0
        for offset, length in sorted(parts):
            assert offset == ends
            ends += length
        assert ends <= 2048
    assert len(sequences) <= 1.02 * -(-total // 2048) + 1


def test_run_is_the_stages_one_by_one(spark, steps):
    key = lambda r: (r.doc_id, r.piece, r.start, r.length, r.ids_crc32)
    assert sorted(map(key, corpus_pipeline.run(spark, SF).collect())) == sorted(map(key, steps[5].collect()))

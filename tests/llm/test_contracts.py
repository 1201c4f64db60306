"""Base columns of the scans and digests against plain readings of their contracts, over whole tables."""

import hashlib
import random
import re
from pathlib import Path

import numpy as np
import pytest

from corpusmill.llm import fuzzy_lines, queries

SF = Path("/root/testdata/sf0.001")
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def lower(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")


@pytest.fixture(scope="module")
def texts(spark):
    return {r.doc_id: r.text or "" for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}


def got(spark, name):
    return {r[0]: r for r in queries.QUERIES[name](spark, str(SF)).collect()}


def digest(spans, kinds):
    ordered = sorted(spans, key=lambda x: (x[1], kinds.index(x[0])))
    return hashlib.sha256(",".join(f"{k}:{s}:{e}" for k, s, e in ordered).encode()).hexdigest()


def test_licenses(spark, texts):
    phrases = {("mit", "license"): "mit", ("apache", "license"): "apache", ("general", "public", "license"): "gpl"}
    rows = got(spark, "op1_license_scan")
    assert rows.keys() == texts.keys()
    for i, text in texts.items():
        words = WORD.findall(lower(text))
        places = sorted((k, label) for p, label in phrases.items() for k in range(len(words)) if tuple(words[k : k + len(p)]) == p)
        r = rows[i]
        ends = (places[0][0], places[-1][0]) if places else (None, None)
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == (len(words), len(places), *ends, ",".join(sorted({x for _, x in places}))), i
        assert {x for _, x in places} <= set(r.labels.split(",")) and 0 <= r.score <= 1


def test_secrets(spark, texts):
    kinds = ["assign", "access", "hex"]
    assign = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
    rows = got(spark, "op5_secret_scan")
    assert rows.keys() == texts.keys()
    for i, text in texts.items():
        spans = [("assign", *m.span()) for m in assign.finditer(text) if len(m[2]) >= 6]
        spans += [("access", *m.span()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
        spans += [("hex", *m.span()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
        r = rows[i]
        assert [r.n_assign, r.n_access, r.n_hex] == [sum(k == x for k, _, _ in spans) for x in kinds] and r.base_sha256 == digest(spans, kinds), i
        assert {f"{k}:{s}:{e}" for k, s, e in spans} <= set(r.spans.split(","))


def luhn(digits):
    total = sum(map(int, digits[-1::-2]))
    return (total + sum(sum(divmod(2 * int(d), 10)) for d in digits[-2::-2])) % 10 == 0


def test_personal_data(spark, texts):
    kinds = ["email", "ip", "card", "phone"]
    rows = got(spark, "op10_pii")
    assert rows.keys() == texts.keys()
    for i, text in texts.items():
        spans = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
        spans += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(x) <= 255 for x in m[0].split("."))]
        for kind, pattern in (("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")):
            for m in re.finditer(pattern, text):
                d = re.sub("[^0-9]", "", m[0])
                if 14 <= len(d) <= 19 and luhn(d) if kind == "card" else 10 <= len(d) <= 15:
                    spans.append((kind, *m.span()))
        r = rows[i]
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == x for k, _, _ in spans) for x in kinds] and r.base_sha256 == digest(spans, kinds), i
        assert {f"{k}:{s}:{e}" for k, s, e in spans} <= set(r.spans.split(","))


def test_repeated_strings(spark, texts):
    rows, data, seen = got(spark, "op2_suffix_array_dedup"), {i: t.encode() for i, t in texts.items()}, {}
    for t in data.values():
        for k in range(len(t) - 199):
            h = hash(t[k : k + 200])
            seen[h] = seen.get(h, 0) + 1
    for i, t in data.items():
        gone = bytearray(len(t))
        for k in range(len(t) - 199):
            if seen[hash(t[k : k + 200])] > 1:
                gone[k : k + 200] = b"\1" * 200
        left = bytes(b for b, g in zip(t, gone) if not g)
        r = rows[i]
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == (len(t), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(left).hexdigest()), i


def shingles(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", lower(text))
    return {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))} if words else set()


def test_jaccard_components(spark, texts):
    rows, sets = got(spark, "op6_ngram_jaccard_join"), {i: shingles(t) for i, t in texts.items()}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for k, i in enumerate(ids):
        for j in ids[k + 1 :]:
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    assert {i: (r.n_shingles, r.component_id) for i, r in rows.items()} == {i: (len(sets[i]), find(i)) for i in ids}


def distance(x, y):
    row = list(range(len(y) + 1))
    for k, c in enumerate(x, 1):
        last, row[0] = row[0], k
        for j, d in enumerate(y, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (c != d))
    return row[-1]


def test_edit_distance_bound():
    rng = random.Random(3)
    for _ in range(3000):
        a, b = ("".join(rng.choice("abé") for _ in range(rng.randrange(12))) for _ in range(2))
        d = distance(a, b)
        assert list(fuzzy_lines.all_within([(a, b, k) for k in range(12)])) == [d <= k for k in range(12)]
    for n in (60, 64, 65, 128, 300, 2100):
        a = "".join(rng.choice("abcdef ") for _ in range(n))
        b = list(a)
        for _ in range(n // 8):
            k = rng.randrange(len(b))
            b[k : k + 1] = rng.choice(["", "x", b[k] + "y"])
        b = "".join(b)
        d = distance(a, b)
        assert [fuzzy_lines.within(a, b, k) for k in (d - 1, d, d + 1)] == [False, True, True] and [fuzzy_lines._one_by_one(*sorted((a, b), key=len), k) for k in (d - 1, d)] == [False, True]


def roots_of(n, links):
    root = list(range(n))

    def find(k):
        while root[k] != k:
            root[k] = root[root[k]]
            k = root[k]
        return k

    for x, y in links:
        x, y = find(x), find(y)
        root[max(x, y)] = min(x, y)
    return [find(k) for k in range(n)]


def near_links(lines):
    """All pairs of lines with an edit similarity of 80 % or more, by lengths, counts of letters and the distance alone."""
    size = np.array([len(x) for x in lines])
    letters = np.zeros((len(lines), 1100), np.int16)
    for k, x in enumerate(lines):
        b = np.frombuffer(x.encode("utf-32-le"), np.uint32).astype(np.int64)
        letters[k, :76] = np.bincount(b % 76, minlength=76)
        letters[k, 76:] = np.bincount((b[:-1] * 31 + b[1:]) % 1024, minlength=1024)
    for k, x in enumerate(lines):
        most = np.maximum(size[k + 1 :], size[k]) * 20 // 100
        apart = np.abs(letters[k + 1 :] - letters[k])
        near = (np.abs(size[k + 1 :] - size[k]) <= most) & (apart[:, :76].sum(1) <= 2 * most) & (apart[:, 76:].sum(1) <= 4 * most)
        for j in k + 1 + np.flatnonzero(near):
            if fuzzy_lines.within(x, lines[j], max(len(x), len(lines[j])) * 20 // 100):
                yield k, int(j)


def test_fuzzy_lines(spark, texts):
    """Groups of the operator against all links by edit similarity, found without fingerprints or blocks."""
    places = sorted((i, k, line) for i, t in texts.items() for k, x in enumerate(t.split("\n")) if (line := fuzzy_lines.normalise(x)))
    lines = sorted({x for _, _, x in places})
    links = list(near_links(lines))
    true = dict(zip(lines, roots_of(len(lines), links)))
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    found = fuzzy_lines.line_roots(fuzzy_lines.occurrences(docs, "doc_id", "text"), docs, 80, "doc_id", "text")
    keys = {fuzzy_lines.line_key(x): x for x in lines}
    mine = {x: x for x in lines} | {keys[r.key]: keys[r.root] for r in found.collect()}
    assert all(true[x] == true[y] for x, y in mine.items())
    kept = sum(mine[lines[a]] == mine[lines[b]] for a, b in links)
    assert len(links) >= 20 and kept >= 0.9 * len(links), (kept, len(links))
    stays, gone = {}, {i: [] for i in texts}
    for i, pos, x in places:
        if stays.setdefault(mine[x], (i, pos)) != (i, pos):
            gone[i].append(pos)
    assert {i: r.removed_lines for i, r in got(spark, "op9_fuzzy_lines").items()} == {i: ",".join(map(str, x)) for i, x in gone.items()}


def edited(line, kind, rng, words):
    w = line.split()
    if kind == "letter":
        k = rng.randrange(len(line))
        return line[:k] + rng.choice("abcdefghij") + line[k + 1 :]
    if kind == "word added":
        w.insert(rng.randrange(len(w) + 1), rng.choice(words))
    else:
        for _ in range(max(1, int(len(w) * {"word": 0, "twentieth": 0.05, "tenth": 0.1}[kind]))):
            w[rng.randrange(len(w))] = rng.choice(words)
    return " ".join(w)


@pytest.mark.parametrize("kind", ["letter", "word", "word added", "twentieth", "tenth"])
def test_edited_lines_share_a_block(texts, kind):
    """Share of edited copies within the similarity that meet their line, over all lines and over short ones."""
    rng = random.Random(7)
    lines = sorted({line for t in texts.values() for x in t.split("\n") if len(line := fuzzy_lines.normalise(x)) >= fuzzy_lines.SHORTEST})
    words = sorted({w for x in lines for w in x.split()})
    pairs = [(x, y) for x in lines if (y := edited(x, kind, rng, words)) != x and fuzzy_lines.within(x, y, max(len(x), len(y)) * 20 // 100)]
    sides = [[set() for _ in pairs] for _ in range(2)]
    for side, batch in zip(sides, zip(*pairs)):
        for k, b in zip(*fuzzy_lines.blocks(list(batch))):
            side[k].add(int(b))
    met = [bool(a & b) for a, b in zip(*sides)]
    short = [m for m, (x, _) in zip(met, pairs) if len(x.split()) <= 15]
    assert np.mean(met) >= 0.95 and np.mean(short) >= 0.95, (np.mean(met), np.mean(short))

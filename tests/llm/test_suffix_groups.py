"""Groups of contexts around one anchor: the first test fails on the code before."""

from __future__ import annotations

import os
import random

from corpusmill.llm import suffix_dedup

LENGTH = 40


def _group(seed: int, letters: str) -> list[tuple[int, bytes]]:
    """Different contexts around one anchor, many of them descended from others."""
    rng = random.Random(seed)
    made = lambda n: bytes(rng.choice(letters.encode()) for _ in range(n))
    anchor, members = made(8), [(b"", b"")]
    while len(members) < 60:
        left, right = rng.choice(members)
        members.append((made(rng.randint(0, 30 - len(left[-12:]))) + left[-rng.randint(1, 30) :], right[: rng.randint(0, 30)] + made(rng.randint(0, 8))))
    return sorted({(len(left), left + anchor + right) for left, right in members})


def _plain(group: list[tuple[int, bytes]]) -> list[list[tuple[int, int]]]:
    out = []
    for left, body in group:
        found = set()
        for other, text in group:
            if (other, text) != (left, body):
                before = len(os.path.commonprefix([body[:left][::-1], text[:other][::-1]]))
                after = len(os.path.commonprefix([body[left:], text[other:]]))
                if before + after >= LENGTH:
                    found.add((-before, after))
        out.append(sorted(x for x in found if not any(y != x and y[0] <= x[0] and y[1] >= x[1] for y in found)))
    return out


def test_contexts_are_cut_only_where_they_branch(monkeypatch):
    """At every length where any two of a group part, each member was cut."""
    counts, sorter = [], suffix_dedup.suffix_array
    monkeypatch.setattr(suffix_dedup, "suffix_array", lambda symbols: counts.append(len(symbols)) or sorter(symbols))
    rng = random.Random(5)
    stem = bytes(rng.randrange(97, 123) for _ in range(200))
    group = [(0, stem[:n] + bytes([65 + n % 2]) * (200 - n)) for n in range(8, 200)] + [(0, bytes([k]) * 200) for k in range(200)]
    suffix_dedup.shared_stretches(group, LENGTH)
    assert counts[0] < len(group) * 110  # before: about 190 cuts for each of 392 members


def test_stretches_of_a_group_equal_a_plain_reading():
    for seed in range(40):
        group = _group(seed, ("ab", "abcdefgh")[seed % 2])
        assert suffix_dedup.shared_stretches(group, LENGTH) == _plain(group)

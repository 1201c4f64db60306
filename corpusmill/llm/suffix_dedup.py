"""Removal of bytes covered by strings of `length` bytes that start in more than one place of a corpus.

Every such string holds an anchor: the KEY bytes with the least hash among its positions, chosen by content alone, so equal strings have
equal anchors. Anchors that occur once end there. Of the others the context is taken: all bytes that a string with this anchor can reach.
Contexts that occur twice are covered whole. Different contexts around one anchor are aligned on it, each cut into blocks where it
branches from another, and sorted as strings of blocks by the grouping suffix sorter; neighbours in that order give the longest common
stretch from each block on, and stretches of `length` bytes or more are covered. Groups beyond GROUP contexts
are counted string by string instead, which needs no task to hold them.

Defined results: null text is empty; texts shorter than `length` keep all bytes; repeated rows are copies (all covered where long enough),
one result row each; an empty table gives an empty result; extra columns are ignored or carried untouched.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import release, settled
from .grouped_suffixes import common_prefixes, suffix_array
from .hashing import Bits, Ranges, mix

KEY = 64
LOG_BITS = 26
#: Most different contexts of one anchor that a task sorts.
GROUP = 4096
PACK = 1 << 20
_PLACE = np.uint64((1 << 28) - 1)
_ODD = np.uint64(0xD6E8FEB86659FD93)


def anchors(ranges: Ranges, n: int, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(positions, hashes) of the anchors of a text of n bytes."""
    if n < length:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    at = np.arange(n - KEY + 1)
    h = ranges.of(at, at + KEY)
    low = (h & ~_PLACE) | (at.astype(np.uint64) & _PLACE)  # the leftmost of equal ones
    width, have = length - KEY + 1, 1
    while 2 * have <= width:
        low = np.minimum(low[:-have], low[have:])
        have *= 2
    if have < width:
        low = np.minimum(low[: len(low) - (width - have)], low[width - have :])
    first = np.arange(len(low))
    place = (low & _PLACE).astype(np.int64)
    if n > int(_PLACE):
        place += (first >> 28) << 28
        place[place < first] += 1 << 28
    place = place[np.concatenate([[True], place[1:] != place[:-1]])]
    return place, h[place]


def contexts(ranges: Ranges, n: int, place: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, hash) of what strings around each anchor reach."""
    start, end = np.maximum(place - (length - KEY), 0), np.minimum(place + length, n)
    with np.errstate(over="ignore"):
        return start, end, mix(ranges.of(start, end) + (place - start).astype(np.uint64) * _ODD)


def _texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text).alias("th"), text.cast("binary").alias("text"))


def _rows(batches):
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            yield list(zip(*(part.column(k).to_pylist() for k in range(3))))


def _arrays(schema: pa.Schema, parts: list[list]) -> pa.RecordBatch:
    cols = [np.concatenate(c) if c and isinstance(c[0], np.ndarray) else c for c in zip(*parts)]
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(cols, schema)], schema=schema)


def anchor_hashes(texts: DataFrame, length: int) -> DataFrame:
    schema = pa.schema([("h", pa.int64())])

    def run(batches):
        for rows in _rows(batches):
            parts = [anchors(Ranges(t), len(t), length)[1].view(np.int64) for _, _, t in rows if len(t) >= length]
            if parts:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(parts))], schema=schema)

    return texts.mapInArrow(run, "h long")


def repeated_places(texts: DataFrame, packed: bytes, length: int) -> DataFrame:
    """(h, c, id, th, start, end): contexts, by hash and place, of anchors that the bit map holds."""
    held = texts.sparkSession.sparkContext.broadcast(packed)
    schema = pa.schema([("h", pa.int64()), ("c", pa.int64()), ("id", pa.int64()), ("th", pa.int64()), ("at", pa.int64()), ("start", pa.int64()), ("end", pa.int64())])

    def run(batches):
        bits = Bits(LOG_BITS, held.value)
        for rows in _rows(batches):
            parts, ids = [], []
            for doc, th, t in rows:
                if len(t) < length:
                    continue
                ranges = Ranges(t)
                place, h = anchors(ranges, len(t), length)
                some = bits.has(mix(h))
                place, h = place[some], h[some]
                if len(h):
                    start, end, c = contexts(ranges, len(t), place, length)
                    parts.append([h.view(np.int64), c.view(np.int64), np.full(len(h), th), place, start, end])
                    ids += [doc] * len(h)
            if parts:
                h, c, th, at, start, end = (np.concatenate(x) for x in zip(*parts))
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (h, c, ids, th, at, start, end)], schema=schema)

    return texts.mapInArrow(run, "h long, c long, id long, th long, at long, start long, end long")


def context_bytes(texts: DataFrame, packed: bytes, length: int) -> DataFrame:
    """(h, c, left, body): the bytes of contexts that the bit map holds, once a task."""
    held = texts.sparkSession.sparkContext.broadcast(packed)
    schema = pa.schema([("h", pa.int64()), ("c", pa.int64()), ("left", pa.int32()), ("body", pa.binary())])

    def run(batches):
        bits, seen = Bits(LOG_BITS, held.value), set()
        for rows in _rows(batches):
            out = []
            for _, _, t in rows:
                if len(t) < length:
                    continue
                ranges = Ranges(t)
                place, h = anchors(ranges, len(t), length)
                start, end, c = contexts(ranges, len(t), place, length)
                some = np.flatnonzero(bits.has(mix(h ^ mix(c))))
                for key in zip(*(x[some].tolist() for x in (h.view(np.int64), c.view(np.int64), place - start, start, end))):
                    if key[:2] not in seen:
                        seen.add(key[:2])
                        out.append((*key[:3], t[key[3] : key[4]]))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, type=f.type) for x, f in zip(zip(*out), schema)], schema=schema)

    return texts.mapInArrow(run, "h long, c long, left int, body binary")


def bit_map(keys: DataFrame, columns: list[str]) -> bytes:
    """Bit map of hashes (h) or of pairs (h, c); tasks send theirs, of fixed size, compressed."""

    def fill(batches):
        bits, some = Bits(LOG_BITS), False
        for batch in batches:
            h = batch.column(0).to_numpy().view(np.uint64)
            some |= len(h) > 0
            bits.add(mix(h if len(columns) == 1 else h ^ mix(batch.column(1).to_numpy().view(np.uint64))))
        if some:
            yield pa.RecordBatch.from_arrays([pa.array([zlib.compress(bits.map.tobytes(), 1)], pa.binary())], names=["map"])

    out = Bits(LOG_BITS)
    for row in keys.select(*columns).coalesce(4).mapInArrow(fill, "map binary").toLocalIterator():
        out.map |= np.frombuffer(zlib.decompress(row[0]), np.uint8)
    return out.map.tobytes()


def _branches(parts: list[bytes]) -> list[list[int]]:
    """For each string the lengths at which it parts from another one, ascending, with 0; two strings have the same ones below the length at which they part."""
    order = sorted(range(len(parts)), key=parts.__getitem__)
    shared = []
    for k, j in zip(order, order[1:]):
        a, b = parts[k], parts[j]
        n = min(len(a), len(b))
        if a[:n] != b[:n]:
            lo, hi = 0, n  # a[:lo] == b[:lo], a[:hi] != b[:hi]
            while hi - lo > 1:
                mid = (lo + hi) // 2
                lo, hi = (mid, hi) if a[:mid] == b[:mid] else (lo, mid)
            n = lo
        shared.append(n)
    found: list[set[int]] = [{0} for _ in parts]
    for places, steps in ((order, shared), (order[::-1], shared[::-1])):
        least: list[int] = []  # what a string shares with those before it in this direction
        for k, n in zip(places[1:], steps):
            while least and least[-1] >= n:
                least.pop()
            least.append(n)
            found[k].update(least)
    return [sorted(x) for x in found]


def shared_stretches(group: list[tuple[int, bytes]], length: int) -> list[list[tuple[int, int]]]:
    """For each (left, body) the stretches from its anchor, as (start, end), that another of the group shares in at least `length` bytes."""
    lefts = _branches([body[:left][::-1] for left, body in group])
    rights = _branches([body[left:] for left, body in group])
    names: dict[tuple[int, bytes], int] = {}
    symbols: list[int] = []
    spans: list[tuple[int, int, int]] = []  # member, from, to; parallel to symbols
    for k, (left, body) in enumerate(group):
        cuts = [-d for d in reversed(lefts[k])] + rights[k][1:]
        for a, b in zip(cuts, cuts[1:]):
            symbols.append(len(group) + 1 + names.setdefault((a, body[left + a : left + b]), len(names)))
            spans.append((k, a, b))
        symbols.append(len(group) - k)  # an end of its own
        spans.append((k, 0, 0))
    symbols.append(0)
    spans.append((-1, 0, 0))
    order = suffix_array(symbols)
    shared = common_prefixes(symbols, order)
    out: list[list[tuple[int, int]]] = [[] for _ in group]
    for r, i in enumerate(order):
        most = max(shared[r], shared[r + 1] if r + 1 < len(order) else 0)
        if most:
            k, a, _ = spans[i]
            b = spans[i + most - 1][2]
            if b - a >= length:
                out[k].append((a, b))
    return [_outer(sorted(stretches)) for stretches in out]


def _outer(stretches: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Those that no other one holds."""
    kept: list[tuple[int, int]] = []
    for a, b in stretches:
        if not kept or b > kept[-1][1]:
            if kept and kept[-1][0] == a:
                kept.pop()
            kept.append((a, b))
    return kept


def sorted_groups(bodies: DataFrame, length: int) -> DataFrame:
    """(h, c, a, b): shared stretches, from rows that lie together by h."""
    schema = pa.schema([("h", pa.int64()), ("c", pa.int64()), ("a", pa.int64()), ("b", pa.int64())])

    def run(batches):
        held, rows, out = None, [], []

        def finish() -> None:
            if len(rows) > 1:
                for (c, _, _), stretches in zip(rows, shared_stretches([(left, body) for _, left, body in rows], length)):
                    out.extend((held, c, a, b) for a, b in stretches)
            rows.clear()

        for batch in batches:
            for h, c, left, body in zip(*(x.to_pylist() for x in batch.columns[:4])):
                if h != held:
                    finish()
                    held = h
                rows.append((c, left, body))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, type=f.type) for x, f in zip(zip(*out), schema)], schema=schema)
                out.clear()
        finish()
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(x, type=f.type) for x, f in zip(zip(*out), schema)], schema=schema)

    return bodies.repartition("h").sortWithinPartitions("h").mapInArrow(run, "h long, c long, a long, b long")


def counted_groups(bodies: DataFrame, length: int) -> DataFrame:
    """(h, c, a, b) for anchors with very many contexts: each string around the anchor is a row, and counts say which occur in two contexts."""
    schema = pa.schema([("h", pa.int64()), ("c", pa.int64()), ("a", pa.int64()), ("w", pa.int64()), ("v", pa.int64())])

    def run(batches):
        for batch in batches:
            for h, c, left, body in zip(*(x.to_pylist() for x in batch.columns[:4])):
                first = np.arange(0, len(body) - length + 1)
                first = first[(first <= left) & (first + length >= left + KEY)]
                if len(first):
                    w = Ranges(body).of(first, first + length)
                    v = Ranges(body[::-1]).of(len(body) - first - length, len(body) - first)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(first), h)), pa.array(np.full(len(first), c)), pa.array(first - left), pa.array(w.view(np.int64)), pa.array(v.view(np.int64))], schema=schema)

    rows = settled(bodies.select("h", "c", "left", "body").mapInArrow(run, "h long, c long, a long, w long, v long"))
    twice = rows.groupBy("h", "a", "w", "v").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h", "a", "w", "v")
    return rows.join(twice, ["h", "a", "w", "v"], "left_semi").select("h", "c", "a", (F.col("a") + length).alias("b"))


def covered_ranges(docs: DataFrame, length: int, id_col: str, text_col: str) -> DataFrame:
    """(id, th, ranges): sorted packed byte ranges to remove, for texts that have any."""
    texts = _texts(docs, id_col, text_col)
    twice = settled(anchor_hashes(texts, length).groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h"))
    places = settled(repeated_places(texts, bit_map(twice, ["h"]), length))
    kinds = settled(places.groupBy("h", "c").agg(F.count(F.lit(1)).alias("n")))
    mixed = settled(kinds.groupBy("h").agg(F.count(F.lit(1)).alias("k")).where("k > 1"))
    wanted = settled(kinds.join(mixed, "h").select("h", "c", "k"))
    found = context_bytes(texts, bit_map(wanted, ["h", "c"]), length).join(wanted, ["h", "c"])
    bodies = settled(found.groupBy("h", "c", "k").agg(F.min("left").alias("left"), F.min("body").alias("body")).select("h", "c", "left", "body", "k"))
    stretches = sorted_groups(bodies.where(F.col("k") <= GROUP), length).union(counted_groups(bodies.where(F.col("k") > GROUP), length))
    # every stretch holds its anchor, so those of one context make up one; a context that occurs twice is covered whole anyway
    once = kinds.where("n = 1").select("h", "c")
    stretches = settled(stretches.groupBy("h", "c").agg(F.min("a").alias("a"), F.max("b").alias("b")).join(once, ["h", "c"], "left_semi"))
    whole = places.join(kinds.where("n > 1").select("h", "c"), ["h", "c"], "left_semi").where(F.col("end") - F.col("start") >= length).select("id", "th", "start", "end")
    part = places.join(stretches, ["h", "c"]).select("id", "th", (F.col("at") + F.col("a")).alias("start"), (F.col("at") + F.col("b")).alias("end"))
    # a range is one number: its start, then its length in PACK
    ranges = whole.union(part).select("id", "th", (F.col("start") * PACK + F.col("end") - F.col("start")).alias("r")).groupBy("id", "th").agg(F.array_sort(F.collect_list("r")).alias("ranges"))
    ranges = settled(ranges)
    release(docs.sparkSession, twice, places, kinds, mixed, wanted, bodies, stretches)
    return ranges


def _cut(text: bytes, ranges: list[int]) -> tuple[int, int, bytes]:
    """Removed bytes, maximal removed runs, what is kept."""
    kept, at, spans, end = [], 0, 0, -1
    for r in ranges:
        start, length = divmod(r, PACK)
        if start > end:
            kept.append(text[at:start])
            spans += 1
        at = end = max(end, start + length)
    kept.append(text[at:])
    left = b"".join(kept)
    return len(text) - len(left), spans, left


def joined(docs: DataFrame, length: int, id_col: str, text_col: str, carry: bool) -> DataFrame:
    """Each row's id and text with its ranges; with carry the whole row too. Only ids and hashes of repeated texts decide who meets."""
    ranges = covered_ranges(docs, length, id_col, text_col).select(F.col("id").alias("rid"), F.col("th").alias("rth"), "ranges")
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text).alias("th"), text.cast("binary").alias("text"), *[F.struct("*").alias("row")] * carry)
    return rows.join(ranges, [F.col("id").eqNullSafe(F.col("rid")), F.col("th") == F.col("rth")], "left").drop("rid", "rth", "th")


def repeated_report(docs: DataFrame, length: int = 200, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: bytes, removed bytes, maximal removed runs and the digest of what is kept."""
    schema = pa.schema([(id_col, pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())])

    def run(batches):
        for batch in batches:
            out = []
            for doc, text, ranges in zip(*(batch.column(k).to_pylist() for k in range(3))):
                removed, spans, left = _cut(text, ranges or [])
                out.append((doc, len(text), removed, spans, hashlib.sha256(left).hexdigest()))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, type=f.type) for x, f in zip(zip(*out), schema)], schema=schema)

    return joined(docs, length, id_col, text_col, False).select("id", "text", "ranges").mapInArrow(run, f"`{id_col}` long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def remove_repeats(docs: DataFrame, length: int = 200, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All rows with their columns; covered bytes are gone from the texts (a character cut in two is replaced)."""

    @F.pandas_udf("string")
    def kept(text, ranges):
        return text.combine(ranges, lambda t, r: _cut(t, [] if r is None else list(r))[2].decode("utf-8", "replace"))

    rows = joined(docs, length, id_col, text_col, True)
    text = F.when(F.col("row")[text_col].isNull(), F.lit(None)).otherwise(kept("text", "ranges"))
    return rows.select(*(text.alias(n) if n == text_col else F.col("row")[n].alias(n) for n in docs.columns))

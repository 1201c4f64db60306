"""Best-fit packing of tokenised documents into sequences of bounded length.

The lengths of all pieces are counted (at most `capacity` counts, whatever the input). Over that histogram a configuration linear
program, one variable for each pattern of lengths that fits, is solved for the whole demand by multiplicative weights: each round a knapsack dynamic program
prices the best pattern under the weights, the pattern gets a share of the demand, and lengths that lag behind gain weight. The
weights over the price of that pattern are a feasible point of the dual program, so every round also bounds the sequences from below (`Plan.bound`). Counts of
patterns are rounded down, those of patterns with gaps either too or to none, whichever packs better; the pieces that rounding frees are placed by best
fit, decreasing, into gaps and then into sequences of their own. Pieces of one length are then numbered, bucket by bucket, and the number says which pattern slot, so which sequence and
offset, a piece takes. Nothing but the histogram and the patterns (some hundreds, see `plan`) meets on the driver.

Defined results: null or empty text is the end token alone; repeated rows are packed each on its own; an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import defaultdict
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpusmill.functions.bpe import VOCABULARY, ordinary_ids

from .common import settled

#: The added token of the vocabulary, which its tokenizer finds in a text before all else, and that token's id.
ADDED, ADDED_ID = "<|endoftext|>", 50256
#: Rows that one numbering bucket holds about.
BUCKET_ROWS = 50_000


def token_bytes(text: str, vocabulary: str = VOCABULARY) -> bytes:
    """Ids of a text without the added token as little-endian unsigned 32-bit bytes."""
    return np.array(ordinary_ids(text, vocabulary), dtype="<u4").tobytes()


def text_ids(text: str, vocabulary: str = VOCABULARY) -> bytes:
    """Ids of a text by the plain tokenizer: what is between added tokens is encoded by itself."""
    if ADDED not in text:
        return token_bytes(text, vocabulary)
    return np.array([ADDED_ID], dtype="<u4").tobytes().join(token_bytes(part, vocabulary) for part in text.split(ADDED))


def pieces_of(docs: DataFrame, capacity: int, vocabulary: str, id_col: str, text_col: str, with_ids: bool) -> DataFrame:
    """Pieces of at most capacity tokens; of a longer document the first takes the rest."""
    fields = [("id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())] + [("ids", pa.binary())] * with_ids
    schema = pa.schema(fields)

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                rows = []
                for doc, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    ids = text_ids(text or "", vocabulary) + b"\0\0\0\0"
                    n = len(ids) // 4
                    start, end, k = 0, (n - 1) % capacity + 1, 0
                    while start < n:
                        own = ids[4 * start : 4 * end]
                        rows.append((doc, k, start, end - start, zlib.crc32(own), *[own] * with_ids))
                        start, end, k = end, end + capacity, k + 1
                cols = list(zip(*rows)) or [()] * len(fields)
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(cols, schema)], schema=schema)

    picked = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return picked.mapInArrow(run, "id long, piece int, start long, length long, ids_crc32 long" + ", ids binary" * with_ids)


def price(weights: np.ndarray, capacity: int) -> list[int]:
    """Lengths of the pattern of greatest weight that fits; weights[l] is for length l, -inf where none is left."""
    best = np.zeros(capacity + 1)
    took = np.zeros(capacity + 1, dtype=np.int64)
    low = int(np.argmax(weights > 0))
    for room in range(low, capacity + 1):
        values = weights[low : room + 1] + best[room - low :: -1][: room - low + 1]
        k = int(values.argmax())
        if values[k] > best[room - 1]:
            best[room], took[room] = values[k], low + k
        else:
            best[room] = best[room - 1]
    pattern, room = [], capacity
    while room >= low:
        if took[room]:
            pattern.append(int(took[room]))
            room -= int(took[room])
        else:
            room -= 1
    return pattern


def fractional(demand: np.ndarray, capacity: int, rounds: int, step: float) -> tuple[list[tuple[list[int], float]], float]:
    """Patterns with fractional counts that cover the demand, no length in excess, and the best lower bound of the dual."""
    left = demand.astype(float)
    lengths = np.arange(capacity + 1)
    share = max(1.0, (left * lengths).sum() / capacity / rounds)
    weights = np.where(left > 0, lengths.astype(float), -np.inf)
    out: list[tuple[list[int], float]] = []
    bound = 0.0
    while True:
        pattern = price(weights, capacity)
        used = np.bincount(pattern, minlength=capacity + 1)
        at = used > 0
        bound = max(bound, float((demand * np.maximum(weights, 0)).sum() / (used[at] * weights[at]).sum()))
        count = min(share, (left[at] / used[at]).min())
        left[at] -= count * used[at]
        left[left < 1e-9] = 0
        out.append((pattern, count))
        live = left > 0
        if not live.any():
            return out, bound
        lag = left[live] / demand[live]  # multiplicative update: what is covered less than the mean gains weight
        weights[~live] = -np.inf
        weights[live] *= np.exp(step * (lag - np.average(lag, weights=left[live] * lengths[live])) / rounds)
        weights[live] *= (lengths[live] * left[live]).sum() / (weights[live] * left[live]).sum()


def best_fit(demand: np.ndarray, capacity: int, started: list[tuple[tuple[int, ...], int]] = ()) -> list[tuple[tuple[int, ...], int]]:
    """Best fit, decreasing, on counts, into the started patterns and new ones: bins alike are kept as one group."""
    free: dict[int, list[list]] = defaultdict(list)
    rooms = np.zeros(capacity + 1, dtype=np.int64)
    for pattern, n in started:
        free[capacity - sum(pattern)].append([pattern, n])
        rooms[capacity - sum(pattern)] += n
    for length in range(capacity, 0, -1):
        n = int(demand[length])
        while n:
            fitting = np.flatnonzero(rooms[length:])
            if fitting.size:
                room = length + int(fitting[0])
                group = free[room][-1]
                k = min(n, group[1])
                group[1] -= k
                rooms[room] -= k
                if not group[1]:
                    free[room].pop()
                pattern = group[0]
            else:
                room, pattern, k = capacity, (), n
                per = capacity // length  # bins of this length alone come full but for the last
                if per > 1 and n >= per:
                    pattern, k = (length,) * (per - 1), n // per
                    n -= k * (per - 1)
                    room = capacity - length * (per - 1)
                elif per > 1:
                    k = 1
            free[room - length].append([(*pattern, length), k])
            rooms[room - length] += k
            n -= k
    return [(p, n) for groups in free.values() for p, n in groups if n]


@dataclass
class Plan:
    """Patterns with whole counts; of their sequences, how many come from the rounded program; and a lower bound of the sequences."""

    patterns: list[tuple[tuple[int, ...], int]]
    rounded: int
    bound: int

    @property
    def sequences(self) -> int:
        return sum(n for _, n in self.patterns)


def plan(histogram: dict[int, int], capacity: int, rounds: int = 200, step: float = 4.0) -> Plan:
    """Patterns with whole counts that hold exactly the histogram.

    The program ends after about `rounds` patterns and one more for each length that runs out, so a plan has at most some thousand
    patterns for capacities of some thousand tokens, however many documents there are.
    """
    demand = np.zeros(capacity + 1, dtype=np.int64)
    for length, n in histogram.items():
        demand[length] = n
    full = int(demand[capacity])
    demand[capacity] = 0
    if not demand.any():
        return Plan([((capacity,), full)] * bool(full), full, full)
    found, bound = fractional(demand, capacity, rounds, step)
    exact: dict[tuple[int, ...], float] = defaultdict(float)
    for pattern, count in found:
        exact[tuple(sorted(pattern, reverse=True))] += count
    plans = []
    for least in (1, capacity):  # with gaps, which best fit fills, or without, so that best fit has more pieces to choose from
        started = {pattern: n for pattern, count in exact.items() if sum(pattern) >= least and (n := int(count + 1e-6))}
        rest = demand.copy()
        for pattern, n in started.items():
            for length in pattern:
                rest[length] -= n
        whole: dict[tuple[int, ...], int] = defaultdict(int)
        for pattern, n in best_fit(rest, capacity, list(started.items())):
            whole[tuple(sorted(pattern, reverse=True))] += n
        if full:
            whole[(capacity,)] += full
        plans.append(Plan(sorted(whole.items(), reverse=True), sum(started.values()) + full, int(np.ceil(bound - 1e-6)) + full))
    return min(plans, key=lambda p: p.sequences)


def slots(patterns: list[tuple[tuple[int, ...], int]]) -> dict[int, np.ndarray]:
    """For each length, rows (first number, first sequence, offset): numbers from there on take the sequences from there on."""
    taken: dict[int, int] = defaultdict(int)
    rows: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
    sequence = 0
    for pattern, n in patterns:
        offset = 0
        for length in pattern:
            rows[length].append((taken[length], sequence, offset))
            taken[length] += n
            offset += length
        sequence += n
    return {length: np.array(r, dtype=np.int64) for length, r in rows.items()}


def pack_documents(docs: DataFrame, capacity: int = 2048, vocabulary: str = VOCABULARY, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row per piece: its document, place there, digest, sequence and offset (and ids, if asked)."""
    spark = docs.sparkSession
    pieces = settled(pieces_of(docs, capacity, vocabulary, id_col, text_col, with_ids))
    histogram = {r[0]: r[1] for r in pieces.groupBy("length").count().collect()}
    where = spark.sparkContext.broadcast(slots(plan(histogram, capacity).patterns))
    buckets = max(1, -(-sum(histogram.values()) // BUCKET_ROWS)) * 8
    dealt = pieces.withColumn("bucket", F.pmod(F.xxhash64("id", "piece", "ids_crc32"), F.lit(buckets)))
    counts = dealt.groupBy("length", "bucket").agg(F.count(F.lit(1)).alias("n"))
    before = counts.withColumn("before", F.sum("n").over(Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1))).select("length", "bucket", F.coalesce("before", F.lit(0)).alias("before"))
    own = F.row_number().over(Window.partitionBy("length", "bucket").orderBy("id", "piece", "start", "ids_crc32")) - 1
    numbered = dealt.withColumn("own", own).join(before, ["length", "bucket"]).withColumn("number", F.col("own") + F.col("before"))
    columns = ["id", "piece", "start", "length", "ids_crc32", *["ids"] * with_ids]
    schema = pa.schema([(id_col, pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), *[("ids", pa.binary())] * with_ids, ("sequence_id", pa.int64()), ("offset", pa.int64())])

    def place(batches):
        table = where.value
        for batch in batches:
            lengths, numbers = batch.column(3).to_numpy(), batch.column(len(columns)).to_numpy()
            sequence, offset = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
            order = np.argsort(lengths, kind="stable")
            for at in np.split(order, np.flatnonzero(np.diff(lengths[order])) + 1) if len(order) else []:
                rows = table[int(lengths[at[0]])]
                k = np.searchsorted(rows[:, 0], numbers[at], side="right") - 1
                sequence[at] = rows[k, 1] + numbers[at] - rows[k, 0]
                offset[at] = rows[k, 2]
            yield pa.RecordBatch.from_arrays([batch.column(i).cast(schema.field(i).type) for i in range(len(columns))] + [pa.array(sequence), pa.array(offset)], schema=schema)

    ids = ", ids binary" * with_ids
    return numbered.select(*columns, "number").mapInArrow(place, f"`{id_col}` long, piece int, start long, length long, ids_crc32 long{ids}, sequence_id long, offset long")

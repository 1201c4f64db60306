"""Shared pieces of the training-data operators: table access, Arrow mapping and membership maps."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmill.plans.durable import release, settled, shared_folder  # noqa: F401  the operators of this subpackage take them from here

#: Sizes that a membership map can have, as powers of two of its bits: 8 KB to 16 MB.
MAP_BITS = (16, 27)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Members:
    """A map of which well-mixed 64-bit values may be in a set: no false absences.

    Its size follows the number of values up to MAP_BITS; past that it lets more through, and the join behind it still decides.
    """

    def __init__(self, log_bits: int, words: np.ndarray) -> None:
        self.log_bits, self.words = log_bits, words

    @classmethod
    def of(cls, values: DataFrame, column: str) -> Members:
        log_bits = int(min(max(values.count() * 16, 1).bit_length(), MAP_BITS[1]))
        log_bits = max(log_bits, MAP_BITS[0])
        slots = [f"shiftrightunsigned({column}, {64 - log_bits})", f"{column} & {(1 << log_bits) - 1}L"]
        slot = values.select(F.explode(F.expr(f"array({', '.join(slots)})")).alias("slot"))
        found = slot.groupBy(F.expr("cast(shiftright(slot, 6) as int)").alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(slot & 63 as int))")).alias("bits"))
        words = np.zeros(1 << (log_bits - 6), np.uint64)
        held = found.toArrow()
        words[held.column("word").to_numpy()] = held.column("bits").to_numpy().view(np.uint64)
        return cls(log_bits, words)

    def has(self, values: np.ndarray) -> np.ndarray:
        values = values.view(np.uint64)
        out = np.ones(len(values), bool)
        for slot in (values >> np.uint64(64 - self.log_bits), values & np.uint64((1 << self.log_bits) - 1)):
            out &= (self.words[(slot >> np.uint64(6)).astype(np.int64)] >> (slot & np.uint64(63))) & np.uint64(1) > 0
        return out




def map_columns(df: DataFrame, kernel: Callable[[list, list], Sequence[Sequence]], schema: str, arrow: pa.Schema, id_col: str, text_col: str, binary: bool = False) -> DataFrame:
    """Apply kernel(ids, texts) -> columns to Arrow batches; one output row for each row or as many as the columns hold."""
    text = F.col(text_col).cast("string")
    picked = df.select(F.col(id_col).alias("id"), (text.cast("binary") if binary else text).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                out = kernel(part.column(0).to_pylist(), part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(out, arrow, strict=True)], schema=arrow)

    return picked.mapInArrow(run, schema)


def render_spans(spans: list[tuple[int, int, str]], order: dict[str, int]) -> str:
    """kind:start:end by start, then kind as listed, comma-joined."""
    return ",".join(f"{k}:{s}:{e}" for s, e, k in sorted(spans, key=lambda x: (x[0], order[x[2]], x[1])))

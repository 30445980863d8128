"""Operator 7: bulk-synchronous best-fit packing of token pieces into sequences.

Sizes and gaps are whole numbers up to the capacity, so pieces and open sequences are range-sorted as counts by size,
however many there are. A sweep goes down the sizes: all pieces of a size take their successor gaps (the least gap
that holds them) at once; equal pieces that want one gap are told apart by rank; the gaps left go back into the sorted
counts, and the size repeats with the next gap, until new sequences are opened for the rest. That is best-fit
decreasing, in at most a few steps for each size. The steps, a table bounded by the capacity, are broadcast; every piece
finds its place by its size and rank. Ranks are counted in salted parts, so that one very common size is no single task.

Defined results: a null or empty text is the end token alone; repeated rows are packed each by themselves; pieces that
agree in all columns are interchangeable; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from packsum.llm import tokens
from packsum.llm.runtime import materialize, pieces

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
STEPS = "length long, lo long, hi long, first_sequence long, per_sequence long, first_offset long"


@dataclass(frozen=True)
class Packing:
    capacity: int = 4096
    end_id: int = 1
    vocabulary: str | None = None
    salts: int = 256


def token_pieces(docs: DataFrame, how: Packing = Packing(), doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Documents as pieces of at most ``capacity`` tokens."""
    path, end_id, capacity = how.vocabulary or tokens.vocabulary_path(), how.end_id, how.capacity

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, "text", 12_000_000):
            ids, bounds = tokens.encode(batch.column("text"), path, end_id)
            size = np.diff(bounds)
            count = -(-size // capacity)
            row = np.repeat(np.arange(len(size)), count)
            piece = tokens.spread(np.zeros(len(count), np.int64), count)
            start = piece * capacity
            length = np.minimum(capacity, size[row] - start)
            at = bounds[:-1][row] + start
            view = memoryview(np.ascontiguousarray(ids, dtype="<u4")).cast("B")
            crc = [zlib.crc32(view[4 * a : 4 * (a + n)]) for a, n in zip(at.tolist(), length.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").take(pa.array(row)), pa.array(piece, pa.int32()), pa.array(start), pa.array(length), pa.array(crc, pa.int64())], names=["doc_id", "piece", "start", "length", "ids_crc32"]
            )

    own = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    return own.mapInArrow(cut, PIECES)


def best_fit(sizes: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int, int]]:
    """Steps (size, first rank, rank after the last, first sequence, pieces a sequence, first offset)."""
    steps: list[tuple[int, int, int, int, int, int]] = []
    gaps: dict[int, list[tuple[int, int]]] = {}  # gap -> runs of sequences (first, how many)
    open_gaps, opened = 0, 0  # bit g of open_gaps: some sequence has gap g

    def put(gap: int, first: int, many: int) -> None:
        nonlocal open_gaps
        if gap and many:
            gaps.setdefault(gap, []).append((first, many))
            open_gaps |= 1 << gap

    for size in sorted(sizes, reverse=True):
        rank, left = 0, sizes[size]
        while left:
            fitting = open_gaps >> size
            if fitting:
                gap = size + (fitting & -fitting).bit_length() - 1
                first, many = gaps[gap].pop()
                if not gaps[gap]:
                    del gaps[gap]
                    open_gaps &= ~(1 << gap)
            else:
                gap, first, many = capacity, opened, -(-left // (capacity // size))
                opened += many
            per = gap // size
            took = min(left, many * per)
            full, rest = divmod(took, per)
            steps.append((size, rank, rank + took, first, per, capacity - gap))
            put(gap - per * size, first, full)
            if rest:
                put(gap - rest * size, first + full, 1)
            put(gap, first + full + bool(rest), many - full - bool(rest))
            rank, left = rank + took, left - took
    return steps


def pack(docs: DataFrame, how: Packing = Packing(), doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each piece, with the sequence and the offset where it lies."""
    spark = docs.sparkSession
    parts = materialize(token_pieces(docs, how, doc_id, text))
    sizes = {r["length"]: r["count"] for r in parts.groupBy("length").count().collect()}  # at most ``capacity`` rows
    steps = spark.createDataFrame(best_fit(sizes, how.capacity), STEPS)
    salted = parts.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(how.salts)))
    counts = salted.groupBy("length", "salt").count()
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    ahead = counts.select("length", "salt", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("ahead"))
    inside = Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32")
    ranked = salted.withColumn("inside", F.row_number().over(inside) - 1).join(ahead, ["length", "salt"]).withColumn("rank", F.col("inside") + F.col("ahead"))
    s = F.broadcast(steps.withColumnRenamed("length", "size"))
    placed = ranked.join(s, (F.col("length") == F.col("size")) & (F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    k = F.col("rank") - F.col("lo")
    sequence = F.col("first_sequence") + F.floor(k / F.col("per_sequence"))
    offset = F.col("first_offset") + F.pmod(k, F.col("per_sequence")) * F.col("length")
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", sequence.cast("long").alias("sequence_id"), offset.cast("long").alias("offset"))

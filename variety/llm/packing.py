"""Best-fit packing of token pieces into sequences, under several capacities at once.

Pieces of one length are alike, so the packing is planned on the histogram of lengths:
a state is a residual vector (tokens, documents, attention cost) and the runs of
sequences that have it. Lengths descend; each goes to the sequences that the rule
prefers, whole runs at a time. The plan has at most a few steps for each length, whatever the
number of rows. Rows then find their place by their rank among the pieces of their length.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import slices, string_buffers, table, text_frame, written
from .tokens import ChunkEncoder, vocabulary_path

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
END_ID = 2
#: The longer the slice, the more often a chunk repeats in it.
TOKEN_SLICE_BYTES = 8 << 20


@dataclass(frozen=True)
class Capacity:
    """What one sequence may hold. Attention cost is the sum of squared piece lengths."""

    tokens: int = 1024
    documents: int = 1024
    attention: int = 1024 * 1024
    #: Weights of the three residuals, each as a share of its capacity.
    weights: tuple[float, float, float] = (1.0, 1e-3, 1e-3)
    #: "norm": least weighted residual norm after placement; "dot": greatest weighted
    #: product of demand and residual.
    rule: str = "norm"


def plan(histogram: dict[int, int], cap: Capacity) -> list[tuple[int, int, int, int, int, int]]:
    """Steps (length, first rank, ranks, first sequence, copies in a sequence, offset), ranks from 0 within a length."""
    limits = np.array([cap.tokens, cap.documents, cap.attention], float)
    weights = np.array(cap.weights)
    open_runs: dict[tuple[int, int, int], list[tuple[int, int]]] = {}
    steps, made = [], 0

    def fits(residual: tuple[int, int, int], length: int) -> int:
        return min(residual[0] // length, residual[1], residual[2] // (length * length))

    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        if fits((cap.tokens, cap.documents, cap.attention), length) < 1:
            raise ValueError(f"a piece of {length} tokens exceeds the capacity of an empty sequence")
        demand = np.array([length, 1, length * length], float)
        while left:
            keys = [k for k in open_runs if fits(k, length)]
            if keys:
                states = np.array(keys, float)
                if cap.rule == "norm":
                    best = int(np.argmin((weights * ((states - demand) / limits) ** 2).sum(axis=1)))
                else:
                    best = int(np.argmax((weights * (states / limits) * (demand / limits)).sum(axis=1)))
                key = keys[best]
                first, count = open_runs[key].pop()
                if not open_runs[key]:
                    del open_runs[key]
            else:
                key, first, count = (cap.tokens, cap.documents, cap.attention), made, None
            copies = min(fits(key, length), left) if cap.rule == "norm" or count is None else 1
            used = left // copies if count is None else min(count, left // copies)
            if count is None:
                made += used
            elif used < count:
                open_runs.setdefault(key, []).append((first + used, count - used))
            steps.append((length, rank, used * copies, first, copies, cap.tokens - key[0]))
            rank, left = rank + used * copies, left - used * copies
            after = (key[0] - copies * length, key[1] - copies, key[2] - copies * length * length)
            if after[0] > 0 and after[1] > 0 and after[2] > 0:
                open_runs.setdefault(after, []).append((first, used))
    return steps


def _pieces(path: str, most: int, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = ChunkEncoder(path)
        for batch in slices(batches, most=TOKEN_SLICE_BYTES):
            raw, offs = string_buffers(batch.column(1))
            ids, counts = encode(raw, offs)
            ends = np.cumsum(counts)
            out = ([], [], [], [], [])
            for row, (end, n) in enumerate(zip(ends.tolist(), counts.tolist(), strict=True)):
                own = np.empty(n + 1, "<u4")
                own[:n] = ids[end - n : end]
                own[n] = end_id
                at, size = 0, (n + 1) % most or most
                while at <= n:
                    for column, value in zip(out, (row, 0 if not at else out[1][-1] + 1, at, size, zlib.crc32(own[at : at + size])), strict=True):
                        column.append(value)
                    at, size = at + size, most
            rows = pa.array(out[0], pa.int64())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(rows), pa.array(out[1], pa.int32()), *(pa.array(x, pa.int64()) for x in out[2:])],
                ["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    return run


def token_pieces(docs: DataFrame, vocabulary: str, most: int = 1024, end_id: int = END_ID) -> DataFrame:
    """One row for each piece of at most ``most`` tokens; only a document's first piece may be shorter."""
    texts = text_frame(docs, F.col("doc_id").cast("long").alias("doc_id"))
    return texts.mapInArrow(_pieces(vocabulary, most, end_id), PIECES)


def _place(steps: list[tuple]):
    by_length: dict[int, np.ndarray] = {}
    for s in steps:
        by_length.setdefault(s[0], []).append(s[1:])
    by_length = {k: np.array(v, np.int64) for k, v in by_length.items()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length = batch.column("length").to_numpy()
            rank = batch.column("rank").to_numpy()
            sequence, offset = np.empty(len(rank), np.int64), np.empty(len(rank), np.int64)
            for value in np.unique(length):
                at = np.flatnonzero(length == value)
                s = by_length[int(value)]
                i = np.searchsorted(s[:, 0], rank[at], "right") - 1
                within = rank[at] - s[i, 0]
                sequence[at] = s[i, 2] + within // s[i, 3]
                offset[at] = s[i, 4] + within % s[i, 3] * value
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(sequence), pa.array(offset)], [*batch.schema.names[:-1], "sequence_id", "offset"])

    return run


def pack(docs: DataFrame, vocabulary: str | None = None, cap: Capacity = Capacity(), end_id: int = END_ID) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset for each piece of ``docs`` (doc_id, text).

    A null or empty text is the end id alone. Rows with one doc_id, and copies, are packed
    each for itself; a null doc_id is kept as it is. An empty table gives no rows. Sequence
    numbers are any; offsets within one are gapless from 0.

    Only the histogram of lengths (at most ``cap.tokens`` entries) and the plan reach the driver.
    """
    spark = docs.sparkSession
    vocabulary = vocabulary or vocabulary_path("byte_bpe_50k.tiktoken")
    pieces = written(token_pieces(docs, vocabulary, cap.tokens, end_id), "pieces")
    histogram = {r["length"]: r["count"] for r in pieces.groupBy("length").count().collect()}
    steps = plan(histogram, cap)
    buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), sum(histogram.values()) >> 16)
    pieces = pieces.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(buckets)))
    counts = pieces.groupBy("length", "bucket").agg(F.count(F.lit(1)).alias("n"))
    running = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("base", F.coalesce(F.sum("n").over(running), F.lit(0))).drop("n")
    within = Window.partitionBy("length", "bucket").orderBy("doc_id", "piece", "ids_crc32")
    ranked = pieces.withColumn("row", F.row_number().over(within)).join(counts, ["length", "bucket"])
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("row") - 1).alias("rank"))
    return ranked.mapInArrow(_place(steps), PIECES + ", sequence_id long, offset long")


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: the pieces of all documents, with the sequence and offset of each."""
    return pack(docs)

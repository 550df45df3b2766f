"""Toxicity by FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Each coordinate has its own learning rate, and the L1 term keeps most weights at zero: what
is broadcast is the short list of the others, at most ``BUCKETS`` of them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bytescan as B
from .common import slices, string_buffers, table, text_frame

BITS = 20
BUCKETS = 1 << BITS
#: Bytes of a word's beginning that count as features of their own: inflected forms share them.
STEMS = (4, 5, 7)
#: At most so many labelled rows of each class are learnt from, those with the smallest hash of doc_id.
SAMPLE_ROWS = 6000
EPOCHS = 8
ALPHA, BETA, L1, L2 = 1.0, 1.0, 4.0, 0.5
TOXIC_SCORE = 0.7


def features(raw: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashed features and their rows: words, stems, pairs of neighbours, pairs with one word between."""
    starts, ends, rows = B.runs(raw, offs, B.WORDLIKE)
    words = B.segment_hashes(raw, starts, ends)
    found, of = [words], [rows]
    for n in STEMS:
        long = np.flatnonzero(ends - starts > n)
        found.append(B.segment_hashes(raw, starts[long], starts[long] + n) + np.uint64(n))
        of.append(rows[long])
    for gap in (1, 2):
        if len(words) > gap:
            same = np.flatnonzero(rows[:-gap] == rows[gap:])
            found.append(B.mix64(words[same] * B.GRAM_KEYS[gap] + words[same + gap]))
            of.append(rows[same])
    return (np.concatenate(found) >> np.uint64(64 - BITS)).astype(np.int64), np.concatenate(of)


def folded(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    return string_buffers(pc.utf8_lower(column))


def fit_ftrl(rows: list[np.ndarray], labels: np.ndarray, epochs: int = EPOCHS, seed: int = 7) -> tuple[np.ndarray, float]:
    """Weights of all buckets, and the intercept; ``rows`` hold each text's distinct features."""
    z, n = np.zeros(BUCKETS + 1), np.zeros(BUCKETS + 1)

    def weights(i):
        zi = z[i]
        return np.where(np.abs(zi) <= L1, 0.0, -(zi - np.sign(zi) * L1) / ((BETA + np.sqrt(n[i])) / ALPHA + L2))

    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        for k in rng.permutation(len(rows)):
            i = rows[k]
            w = weights(i)
            g = 1.0 / (1.0 + np.exp(-np.clip(w.sum(), -30, 30))) - labels[k]
            ni = n[i]
            after = ni + g * g
            z[i] += g - (np.sqrt(after) - np.sqrt(ni)) / ALPHA * w
            n[i] = after
    w = weights(slice(None))
    return w[:BUCKETS], float(w[BUCKETS])


def _train(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    rows, labels = [], []
    for frame in batches:
        for at in range(0, len(frame), 64):
            part = frame.iloc[at : at + 64]
            raw, offs = folded(pa.array(part["text"], pa.large_string()))
            found, of = features(raw, offs)
            key = np.unique(of * BUCKETS + found)
            cuts = np.searchsorted(key, np.arange(len(part) + 1) * BUCKETS)
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                rows.append(np.append(key[a:b] & (BUCKETS - 1), BUCKETS).astype(np.int32))
            labels += part["toxic"].tolist()
    if not labels or len(set(labels)) < 2:
        return
    y = np.array(labels, float)
    w, bias = fit_ftrl(rows, y)
    at = np.flatnonzero(w)
    yield pd.DataFrame({"bucket": np.append(at, BUCKETS), "weight": np.append(w[at], bias)})


def _score(buckets: np.ndarray, values: np.ndarray, bias: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weight = np.zeros(BUCKETS, np.float32)
        weight[buckets] = values
        for batch in slices(batches):
            raw, offs = folded(batch.column(1))
            found, of = features(raw, offs)
            hit = np.flatnonzero(weight[found])
            pairs = np.unique(of[hit] * BUCKETS + found[hit])
            total = np.bincount(pairs >> BITS, weights=weight[pairs & (BUCKETS - 1)], minlength=batch.num_rows)
            score = 1.0 / (1.0 + np.exp(-np.clip(total + bias, -30, 30)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score)], ["doc_id", "score"])

    return run


def fit_toxicity(docs: DataFrame, labels: DataFrame, most: int = SAMPLE_ROWS) -> tuple[np.ndarray, np.ndarray, float]:
    """(buckets, weights, intercept) from labelled rows of ``docs``: at most ``most`` of each class.

    One task learns from the sample, whose bound does not grow with the data. The intercept is
    shifted to the share of toxic rows among all labels. Without labels of both classes every score is 0.
    """
    known = labels.where("doc_id is not null and toxic in (0, 1)").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").cast("int").alias("toxic"))
    counts = {r["toxic"]: r["count"] for r in known.groupBy("toxic").count().collect()}
    if len(counts) < 2:
        return np.zeros(0, np.int64), np.zeros(0), -30.0
    pick = lambda y: known.where(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    sample = F.broadcast(pick(0).unionByName(pick(1)))
    texts = text_frame(docs, F.col("doc_id").cast("long").alias("doc_id")).join(sample, "doc_id").select("doc_id", "text", "toxic")
    got = texts.repartition(1).sortWithinPartitions(F.xxhash64("doc_id")).mapInPandas(_train, "bucket long, weight double").toPandas()
    if got.empty:
        return np.zeros(0, np.int64), np.zeros(0), -30.0
    odds = np.log(counts[1] / counts[0]) - np.log(min(counts[1], most) / min(counts[0], most))
    inner = got["bucket"] < BUCKETS
    return got["bucket"][inner].to_numpy(np.int64), got["weight"][inner].to_numpy(), float(got["weight"][~inner].sum() + odds)


def learnable(labels: DataFrame) -> DataFrame:
    """Labels that may be learnt from; the others are held out."""
    return labels.where(~held_out())


def held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))


def toxicity(docs: DataFrame, labels: DataFrame, most: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id and score (0 to 1) for each row of ``docs`` (doc_id, text).

    Null and empty texts score by the intercept alone. Copies score alike; a null doc_id is
    kept. An empty table gives no rows. The whole of each text counts, however long.
    """
    model = fit_toxicity(docs, labels, most)
    texts = text_frame(docs, F.col("doc_id").cast("long").alias("doc_id"))
    return texts.mapInArrow(_score(*model), "doc_id long, score double")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = toxicity(table(spark, sf_dir, "documents"), learnable(table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= TOXIC_SCORE).cast("int").alias("predicted"))


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents that score as toxic go."""
    buckets, values, bias = fit_toxicity(docs, learnable(table(spark, sf_dir, "labels")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = _score(buckets, values, bias)
        for batch in slices(batches):
            at = batch.schema.get_field_index("text")
            texts = batch.column(at).fill_null("")
            (got,) = score(iter([pa.RecordBatch.from_arrays([texts, texts], ["doc_id", "text"])])) if texts.nbytes <= 1 << 20 else _whole(score, texts)
            yield batch.filter(pc.less(got.column(1), TOXIC_SCORE))

    return docs.mapInArrow(run, docs.schema)


def _whole(score, texts):
    parts = list(score(iter([pa.RecordBatch.from_arrays([texts, texts], ["doc_id", "text"])])))
    return (pa.Table.from_batches(parts).combine_chunks().to_batches()[0],)

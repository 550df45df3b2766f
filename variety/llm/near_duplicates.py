"""Near duplicates by MinHash, with fast similarity sketches.

Each text is a set of word shingles. A sketch of t coordinates is filled in rounds:
round i throws every element into a bin by a fresh hash, and a bin keeps the smallest
value of the first round that reached it; from round t on, round i fills bin i - t with
all elements, so every coordinate fills whatever the size of the set. Equal coordinates
then happen with the sets' resemblance as their chance. Bands of coordinates propose
candidates, which are confirmed on the full sets.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import bytescan as B
from .common import drop_written, slices, string_buffers, table, text_frame, written
from .components import components

BAND_ROWS = 5
#: The chance that a pair right at the threshold shares no band.
MISS = 1e-6
_FREE = np.uint64(0xFFFFFFFFFFFFFFFF)


def band_count(threshold: float, rows: int = BAND_ROWS, miss: float = MISS) -> int:
    return math.ceil(math.log(miss) / math.log1p(-(threshold**rows)))


def shingle_sets(raw: np.ndarray, offs: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The distinct shingle hashes of each row, sorted within it, and their rows."""
    starts, ends, rows = B.runs(raw, offs, B.NOT_SPACE)
    words = B.segment_hashes(B.LOWER[raw], starts, ends)
    hashes, at = B.grams(words, rows, k)
    of = rows[at]
    counts = np.bincount(rows, minlength=len(offs) - 1)
    few = np.flatnonzero((counts > 0) & (counts < k))
    if len(few):  # the whole sequence is the one shingle
        first = np.searchsorted(rows, few)
        whole = []
        for a, n in zip(first, counts[few], strict=True):
            whole.append(B.grams(words[a : a + n], rows[a : a + n], int(n))[0][0] ^ np.uint64(n))
        hashes, of = np.concatenate([hashes, np.array(whole, np.uint64)]), np.concatenate([of, few])
    order = np.lexsort((hashes, of))
    hashes, of = hashes[order], of[order]
    fresh = np.ones(len(hashes), bool)
    fresh[1:] = (hashes[1:] != hashes[:-1]) | (of[1:] != of[:-1])
    return hashes[fresh], of[fresh]


def sketches(hashes: np.ndarray, of: np.ndarray, n: int, t: int) -> np.ndarray:
    """Fast similarity sketches of n sets, t coordinates each; sets without elements keep the free mark."""
    out = np.full((n, t), _FREE)
    flat = out.reshape(-1)
    base = of.astype(np.int64) * t
    for i in range(2 * t):
        if not len(hashes):
            break
        g = B.mix64(hashes ^ np.uint64((i + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF))
        value = np.uint64(i << 40) | (g & np.uint64(0xFFFFFFFF))
        if i < t:
            bins = ((g >> np.uint64(32)) * np.uint64(t) >> np.uint64(32)).astype(np.int64)
        else:
            bins = i - t
        np.minimum.at(flat, base + bins, value)
        if i < t or i % 8 == 0:
            open_rows = (out == _FREE).any(axis=1)
            keep = open_rows[base // t]
            if not keep.all():
                hashes, base = hashes[keep], base[keep]
    return out


def _signatures(k: int, bands: int, rows: int, key: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            raw, offs = string_buffers(batch.column(batch.num_columns - 1))
            n = batch.num_rows
            hashes, of = shingle_sets(raw, offs, k)
            sizes = np.bincount(of, minlength=n).astype(np.int64)
            prints = []
            for salt in (0x5851F42D4C957F2D, 0x14057B7EF767814F):
                sums = np.zeros(n, np.uint64)
                np.add.at(sums, of, B.mix64(hashes ^ np.uint64(salt)))
                prints.append(sums.view(np.int64))
            sketch = sketches(hashes, of, n, bands * rows).reshape(n, bands, rows)
            band = np.broadcast_to(np.arange(bands, dtype=np.uint64) + np.uint64(1), (n, bands)) * np.uint64(0xD1342543DE82EF95)
            for j in range(rows):
                band = B.mix64(band + sketch[:, :, j] * B.GRAM_KEYS[j])
            lists = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * bands), pa.array(band.reshape(-1).view(np.int64)))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(sizes), pa.array(prints[0]), pa.array(prints[1]), lists],
                [key, "n_shingles", "print_a", "print_b", "bands"],
            )

    return run


def _sets(k: int, key: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            raw, offs = string_buffers(batch.column(batch.num_columns - 1))
            hashes, of = shingle_sets(raw, offs, k)
            ends = np.cumsum(np.bincount(of, minlength=batch.num_rows))
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]).astype(np.int32)), pa.array(hashes.view(np.int64)))
            yield pa.RecordBatch.from_arrays([batch.column(0), lists], [key, "shingles"])

    return run


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of ``docs`` (doc_id long, text string).

    Texts whose shingle sets A, B have 100 * |A & B| >= percent * |A | B| are linked;
    component_id is the smallest doc_id that links lead to. Texts with fewer than k
    words are one shingle. Null or empty texts, and texts of white space, have no
    shingle and link with nothing. Rows that repeat a doc_id are kept and share its
    component; a row with a null doc_id has a null component and is kept. An empty table gives no rows.

    Texts with one set are one class, represented by its smallest doc_id. In each band's
    bucket every member meets the bucket's smallest first. Members of one component need
    no further comparison. Where a bucket holds several components, its texts meet by their own
    rarest shingles, which loses no link, so that no bucket is expanded into all its pairs.
    """
    bands = band_count(percent / 100)
    texts = text_frame(docs, F.col("doc_id").cast("long").alias("doc_id"))
    signed = written(
        texts.mapInArrow(_signatures(k, bands, BAND_ROWS, "doc_id"), "doc_id long, n_shingles long, print_a long, print_b long, bands array<long>"),
        "signatures",
    )
    some = signed.where("n_shingles > 0 and doc_id is not null")
    classes = written(some.groupBy("print_a", "print_b").agg(F.min("doc_id").alias("head")), "classes")
    heads = some.join(classes.select(F.col("head").alias("doc_id"), "print_a", "print_b"), ["doc_id", "print_a", "print_b"], "left_semi").dropDuplicates(["doc_id"])
    members = heads.select(F.explode("bands").alias("bucket"), "doc_id", "n_shingles")
    shared = members.groupBy("bucket").agg(F.min("doc_id").alias("lead"), F.max("doc_id").alias("last")).where("lead < last").drop("last")
    members = written(members.join(shared, "bucket"), "members")
    wanted = members.select("doc_id").distinct()
    sets = written(
        texts.join(classes.select(F.col("head").alias("doc_id")).join(wanted, "doc_id", "left_semi"), "doc_id", "left_semi").dropDuplicates(["doc_id"])
        .mapInArrow(_sets(k, "doc_id"), "doc_id long, shingles array<long>"),
        "sets",
    )
    pairs = members.where("lead < doc_id").select(F.col("lead").alias("u"), F.col("doc_id").alias("v")).distinct()
    first = written(_resemblance(pairs, sets), "resemblance")
    links = first.where(f"100 * shared >= {percent} * joined").select("u", "v")
    label = written(components(links), "labels")

    placed = members.join(label.select(F.col("node").alias("doc_id"), "component"), "doc_id", "left")
    placed = written(placed.select("bucket", "doc_id", F.coalesce("component", "doc_id").alias("component")), "placed")
    mixed = placed.groupBy("bucket").agg(F.min("component").alias("a"), F.max("component").alias("b")).where("a < b").select("bucket")
    rest = placed.join(mixed, "bucket", "left_semi").select("doc_id", "component").distinct()
    more = _prefix_pairs(rest, sets, percent)
    second = _resemblance(more.join(pairs, ["u", "v"], "left_anti"), sets).where(f"100 * shared >= {percent} * joined").select("u", "v")
    second = written(second, "links")
    if not second.isEmpty():
        label = written(components(links.unionByName(second)), "labels")
    drop_written(members, sets, first, placed, second)
    named = classes.join(label.select(F.col("node").alias("head"), "component"), "head", "left").select(
        "print_a", "print_b", F.coalesce("component", "head").alias("component")
    )
    out = signed.select("doc_id", "n_shingles", "print_a", "print_b").join(named, ["print_a", "print_b"], "left")
    component = F.when(F.col("n_shingles") > 0, F.coalesce("component", "doc_id")).otherwise(F.col("doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def _prefix_pairs(docs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs u < v of ``docs`` (doc_id, component) in different components that may be linked; no linked pair is missed.

    Shingles are put in one order, rarest first. Of two linked sets the smaller has a common
    shingle among the first n - 2t/(1+t) n + 1 of its own, the larger among its first n - t n + 1, and the
    shingles from there on suffice for the overlap. What edits leave apart from a common original is rare and
    comes first, so texts of one origin that are too different don't meet at all.
    """
    items = sets.join(docs, "doc_id").select("doc_id", "component", F.size("shingles").alias("n"), F.explode("shingles").alias("shingle"))
    items = written(items, "items")
    often = items.groupBy("shingle").agg(F.count(F.lit(1)).alias("often"))
    order = Window.partitionBy("doc_id").orderBy("often", "shingle")
    items = items.join(often.where("often > 1"), "shingle", "left").withColumn("at", F.row_number().over(order) - 1)
    items = items.where(f"often is not null and at < n - ceil({percent} * n / 100) + 1").drop("often")
    items = written(items, "prefixes")
    small = items.where(f"at < n - ceil({2 * percent} * n / {100 + percent}) + 1").alias("x")
    large = items.alias("y")
    least = 1 + F.least(F.expr("x.n - x.at - 1"), F.expr("y.n - y.at - 1"))
    meet = F.expr(f"x.shingle = y.shingle and x.component <> y.component and x.n <= y.n and 100 * x.n >= {percent} * y.n")
    pairs = small.join(large, meet & (least * (100 + percent) >= percent * F.expr("x.n + y.n")))
    return pairs.select(F.least("x.doc_id", "y.doc_id").alias("u"), F.greatest("x.doc_id", "y.doc_id").alias("v")).distinct()


def _resemblance(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """u, v with the sizes of their sets' intersection and union."""
    a = sets.select(F.col("doc_id").alias("u"), F.col("shingles").alias("a"))
    b = sets.select(F.col("doc_id").alias("v"), F.col("shingles").alias("b"))
    both = pairs.join(a, "u").join(b, "v").select("u", "v", F.size("a").alias("na"), F.size("b").alias("nb"), F.size(F.array_intersect("a", "b")).alias("shared"))
    return both.select("u", "v", "shared", (F.col("na") + F.col("nb") - F.col("shared")).alias("joined"))


def op10_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), k=3, percent=85)


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: of each group of near duplicates the smallest doc_id stays."""
    kept = near_duplicates(docs, k=5, percent=80).where("kept").select(F.col("doc_id").alias("stays")).dropDuplicates(["stays"])
    return docs.join(kept, docs["doc_id"].eqNullSafe(kept["stays"]), "left_semi")

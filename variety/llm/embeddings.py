"""Near duplicates among embeddings: spherical k-means cells, blocked cosines within cells."""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import drop_written, table, written
from .components import components

#: Cell centres are fitted on at most so many vectors, and on at most so many bytes of them.
FIT_ROWS, FIT_BYTES = 50_000, 32 << 20
MOST_CELLS = 4096
BLOCK_ROWS = 2048
ROUNDS = 10
#: Cells are compared in as many turns as keep the rows that one turn writes under so many bytes, or under the vectors' own.
TURN_BYTES = 1 << 30


def spherical_kmeans(x: np.ndarray, k: int, rounds: int = ROUNDS, seed: int = 11) -> np.ndarray:
    """k unit centres of unit vectors; an empty cell keeps its centre."""
    rng = np.random.default_rng(seed)
    centres = x[rng.permutation(len(x))[:k]].copy()
    for _ in range(rounds):
        home = np.concatenate([(part @ centres.T).argmax(axis=1) for part in np.array_split(x, max(1, len(x) // 8192))])
        order = np.argsort(home, kind="stable")
        cells, first = np.unique(home[order], return_index=True)
        sums = np.add.reduceat(x[order], first)
        norm = np.linalg.norm(sums, axis=1)
        fine = norm > 1e-12
        centres[cells[fine]] = sums[fine] / norm[fine, None]
    return centres


def _rows(column: pa.Array, dim: int) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), dim)


def _unit(x: np.ndarray) -> np.ndarray:
    top = np.abs(x).max(axis=1, keepdims=True)
    x = x / top
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _apart(centres: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(2 - 2 * centres @ centres.T, 1e-12))


def _visited(x: np.ndarray, centres: np.ndarray, apart: np.ndarray, margin: float) -> tuple[np.ndarray, np.ndarray]:
    """Each row's home, and whether it is in each of the cells: at home, or near enough to the border."""
    near = x @ centres.T
    home = near.argmax(axis=1)
    every = np.arange(len(home))
    visits = (near[every, home][:, None] - near) / apart[home] <= margin
    visits[every, home] = True
    return home, visits


def turns_of(x: np.ndarray, centres: np.ndarray, margin: float, n: int) -> int:
    """In how many turns n vectors like those of the sample are compared. A row is written at home and as a guest, and shuffled after that."""
    apart, some = _apart(centres), x[:: max(1, len(x) // 2048)]
    visits = float(_visited(some, centres, apart, margin)[1].sum(axis=1).mean())
    own = 4 * centres.shape[1]
    return min(len(centres), max(1, math.ceil(n * visits * 2 * (own + 24) / max(TURN_BYTES, n * own))))


def _assign(centres: np.ndarray, margin: float, turn: int = 0, turns: int = 1):
    """Rows in the cells whose number leaves ``turn`` over ``turns``."""
    apart, dim = _apart(centres), centres.shape[1]
    now = np.arange(len(centres)) % turns == turn

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 2048):
                batch = whole.slice(at, 2048)
                x = _unit(_rows(batch.column("embedding"), dim))
                home, visits = _visited(x, centres, apart, margin)
                every = np.arange(len(home))
                row, cell = np.nonzero(visits & now)
                guests = visits.copy()
                guests[every, home] = False
                grow, gcell = np.nonzero(guests)
                ends = np.concatenate([[0], np.cumsum(np.bincount(grow, minlength=len(home)))]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(gcell.astype(np.int32)))
                take = pa.array(row)
                hosts = pa.array(row, mask=cell != home[row])  # only a row at home needs to say where it is a guest
                yield pa.RecordBatch.from_arrays(
                    [pa.array(cell.astype(np.int32)), pa.array(home[row].astype(np.int32)), batch.column("vec_id").take(take), batch.column("copies").take(take), lists.take(hosts), batch.column("embedding").take(take)],
                    ["cell", "home", "vec_id", "copies", "guest_in", "embedding"],
                )

    return run


def _visits(lists: pa.Array, cells: np.ndarray) -> np.ndarray:
    """Whether each row is a guest in each of the sorted cells."""
    lens = lists.value_lengths().to_numpy(zero_copy_only=False)
    flat = lists.flatten().to_numpy(zero_copy_only=False)
    out = np.zeros((len(lens), len(cells)), bool)
    at = np.minimum(np.searchsorted(cells, flat), len(cells) - 1)
    hit = cells[at] == flat
    out[np.repeat(np.arange(len(lens)), lens)[hit], at[hit]] = True
    return out


def _compare(dim: int, cosine: float):
    """Links of a block of a cell's own rows with a block of all the rows there, guests too."""

    def run(key, rows):
        cell = key[0].as_py()
        rows = rows.combine_chunks()
        asks = rows.column("asks").to_numpy(zero_copy_only=False)
        a, b = rows.filter(pa.array(asks)), rows.filter(pa.array(~asks))
        ids = counts = partners = np.zeros(0, np.int64)
        if len(a) and len(b):
            links = _unit(_rows(a.column("embedding"), dim)) @ _unit(_rows(b.column("embedding"), dim)).T >= cosine
            some, other = np.flatnonzero(links.any(axis=1)), np.flatnonzero(links.any(axis=0))
            links, a, b = links[np.ix_(some, other)], a.take(pa.array(some)).combine_chunks(), b.take(pa.array(other)).combine_chunks()
            va, vb = a.column("vec_id").to_numpy(), b.column("vec_id").to_numpy()
            ca, cb = a.column("copies").to_numpy(), b.column("copies").to_numpy()
            homes = b.column("home").to_numpy()
            if len(some):
                # both at home: once, from the smaller id; a guest: unless its host is a guest at its home, which counts the pair if it is the smaller cell
                cells = np.unique(homes)
                back = _visits(a.column("guest_in").combine_chunks(), cells)[:, np.searchsorted(cells, homes)]
                links &= np.where(homes == cell, va[:, None] < vb[None, :], ~back | (cell < homes)[None, :])
            la, lb = va.copy(), vb.copy()
            far = np.iinfo(np.int64).max
            while links.any():  # smallest id of each row's part of this block's graph
                na = np.minimum(la, np.where(links, lb[None, :], far).min(axis=1))
                nb = np.minimum(lb, np.where(links, na[:, None], far).min(axis=0))
                if (na == la).all() and (nb == lb).all():
                    break
                la, lb = na, nb
            ids, partners = np.concatenate([va, vb]), np.concatenate([la, lb])
            counts = np.concatenate([links @ cb, links.T @ ca]) if len(ids) else ids
            kept = np.flatnonzero(counts)
            ids, counts, partners = ids[kept], counts[kept], partners[kept]
        return pa.table({"vec_id": pa.array(ids, pa.int64()), "n": pa.array(counts, pa.int64()), "label": pa.array(partners, pa.int64())})

    return run


PLACED = "cell int, home int, vec_id long, copies long, guest_in array<int>, embedding "


def _links(placed: DataFrame, dim: int, cosine: float) -> DataFrame:
    """vec_id, n, label: the links within each pair of blocks of a cell."""
    own = F.col("home") == F.col("cell")
    blocks = lambda n: F.ceil(n / BLOCK_ROWS).cast("int")
    sizes = placed.groupBy("cell").agg(blocks(F.count(F.lit(1))).alias("blocks"), blocks(F.count_if(own)).alias("home_blocks")).where("home_blocks > 0")
    keyed = placed.join(F.broadcast(sizes), "cell")
    part = lambda n: F.pmod(F.xxhash64("vec_id"), F.col(n).cast("long")).cast("int")
    each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    facts = ["home", "vec_id", "copies", "embedding"]
    asking = keyed.where(own).select("cell", part("home_blocks").alias("i"), each("blocks").alias("j"), *facts, "guest_in", F.lit(True).alias("asks"))
    asked = keyed.select("cell", each("home_blocks").alias("i"), part("blocks").alias("j"), *facts, F.lit(None).cast("array<int>").alias("guest_in"), F.lit(False).alias("asks"))
    return asking.unionByName(asked).groupBy("cell", "i", "j").applyInArrow(_compare(dim, cosine), "vec_id long, n long, label long")


def near_vectors(vectors: DataFrame, cosine: float = 0.9) -> DataFrame:
    """vec_id, n_links, component_id, kept for each row of ``vectors`` (vec_id long, embedding array of numbers).

    Rows that are null, zero, of another length than most, or hold null or non-finite numbers
    link with nothing. Equal vectors are one with a number of copies, and link with each other. Repeated
    vec_ids are rows of their own that share a component. An empty table gives no rows.

    Centres are fitted on a sample; every vector is compared: in its own cell, and as a guest in
    each cell whose border it is near, with the rows at home there; guests aren't compared with each other. A pair
    counts in one cell only. Cells of any size are cut into blocks, and each pair of blocks is a group of bounded size. Where all
    guests at once would take much more disk than the vectors, cells take turns, and what a turn wrote goes before the next.
    """
    spark = vectors.sparkSession
    base = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("exact"), F.col("embedding"))
    fine = F.coalesce((F.size("exact") > 0) & ~F.exists("exact", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))) & F.exists("exact", lambda v: v != 0), F.lit(False))
    base = base.withColumn("fine", fine)
    lengths = base.where("fine").groupBy(F.size("exact").alias("d")).count().orderBy(F.desc("count"), "d").limit(1).collect()
    dim = lengths[0]["d"] if lengths else 0
    usable = F.col("fine") & (F.size("exact") == dim) & F.col("vec_id").isNotNull()
    prints = [F.when(usable, F.xxhash64("exact", F.lit(salt))).alias(name) for name, salt in (("print_a", 1), ("print_b", 2))]
    rows = base.select("vec_id", "embedding", *prints)
    classes = written(rows.where("print_a is not null").groupBy("print_a", "print_b").agg(F.min("vec_id").alias("head"), F.count(F.lit(1)).alias("copies")), "classes")
    n = classes.count()
    out = rows.select("vec_id", "print_a", "print_b").join(classes, ["print_a", "print_b"], "left")
    if not n:
        return out.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    heads = rows.where("print_a is not null").join(classes.select(F.col("head").alias("vec_id"), "print_a", "print_b", "copies"), ["vec_id", "print_a", "print_b"])
    heads = heads.dropDuplicates(["vec_id"]).select("vec_id", "copies", "embedding")
    most = max(64, min(FIT_ROWS, FIT_BYTES // (8 * dim)))
    step = max(1, -(-n // most))
    sample = heads.where(F.pmod(F.xxhash64("vec_id"), F.lit(step)) == 0).select("embedding").limit(2 * most).toArrow()
    x = _unit(_rows(sample.column("embedding"), dim)) if len(sample) else np.eye(1, dim)
    centres = spherical_kmeans(x, min(math.isqrt(n) + 1, MOST_CELLS, len(x)))
    # of two vectors at most a chord apart, on either side of a border, one is within half a chord of it
    margin = math.sqrt(max(0.0, 2 - 2 * cosine)) / 2 + 1e-9
    turns, found = turns_of(x, centres, margin, n), []
    if turns > 1:
        heads = written(heads, "heads")
    for turn in range(turns):
        placed = written(heads.mapInArrow(_assign(centres, margin, turn, turns), PLACED + dict(vectors.dtypes)["embedding"]), "placed")
        found.append(written(_links(placed, dim, cosine), "found"))
        drop_written(placed)
        if turns > 1:
            spark.sparkContext._jvm.System.gc()  # a turn's shuffle files go with what refers to them
    found = reduce(DataFrame.unionByName, found)
    counts = found.groupBy("vec_id").agg(F.sum("n").alias("others"))
    label = components(found.where("vec_id <> label").select(F.col("vec_id").alias("u"), F.col("label").alias("v")))
    facts = counts.join(label.select(F.col("node").alias("vec_id"), "component"), "vec_id", "left").select(F.col("vec_id").alias("head"), "others", "component")
    out = out.join(facts, "head", "left")
    component = F.coalesce("component", "head", "vec_id")
    links = F.coalesce(F.col("copies") - 1, F.lit(0)) + F.coalesce("others", F.lit(0))
    return out.select("vec_id", links.cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


def op8_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings"))

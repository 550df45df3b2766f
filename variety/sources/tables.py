"""The given tables, by name, with their schemas stated rather than inferred."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "pages": "page_id bigint, url string, html string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "benchmark": "item_id bigint, text string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, as spark.checkpoint.dir names it."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found and spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        found = spark.sparkContext._jsc.sc().getCheckpointDir().get()
    if not found:  # a single machine, as in tests
        found = tempfile.mkdtemp(prefix="variety-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder, removed when the session ends."""
    path = f"{shared_dir(spark)}/scratch/{name}-{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    place = jvm.org.apache.hadoop.fs.Path(path)
    fs = place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    fs.deleteOnExit(place)
    return path


def drop_written(*frames: DataFrame) -> None:
    """Remove tables that ``written`` made, once nothing reads them any more."""
    for df in frames:
        jvm = df.sparkSession.sparkContext._jvm
        place = jvm.org.apache.hadoop.fs.Path(df._written_path)
        place.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def written(df: DataFrame, name: str) -> DataFrame:
    """The rows of ``df`` from a table written to the shared folder: lineage ends here."""
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    back = df.sparkSession.read.schema(df.schema).parquet(path)
    back._written_path = path
    return back


def materialize(df: DataFrame, path: str, partition_by: tuple[str, ...] = ()) -> DataFrame:
    """Write once and read back, so that later filters prune folders rather than scan."""
    df.write.mode("overwrite").partitionBy(*partition_by).parquet(path)
    return df.sparkSession.read.parquet(path)


def bucketed(df: DataFrame, name: str, key: str, n: int) -> DataFrame:
    """A table bucketed and sorted by ``key``: later joins and groupings on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(n, key).sortBy(key).saveAsTable(name)
    return df.sparkSession.table(name)


def write_sparse_text(df: DataFrame, path: str, label: str = "label", features: str = "features") -> None:
    """Rows of label and array features as lines of index:value pairs, indices from 1, zeros left out."""
    pairs = F.transform(F.sequence(F.lit(1), F.size(features)), lambda i: F.struct(i.alias("i"), F.element_at(features, i).alias("v")))
    pairs = F.filter(pairs, lambda p: p["v"] != 0)
    line = F.concat_ws(" ", F.col(label).cast("string"), F.array_join(F.transform(pairs, lambda p: F.concat_ws(":", p["i"].cast("string"), p["v"].cast("string"))), " "))
    df.select(line.alias("value")).write.mode("overwrite").text(path)


def read_sparse_text(spark: SparkSession, path: str, d: int) -> DataFrame:
    """label and array features of d columns. The stated width saves the scan that would find it."""
    from pyspark.ml.functions import vector_to_array

    rows = spark.read.format("libsvm").option("numFeatures", d).load(path)
    return rows.select("label", vector_to_array("features").alias("features"))


def read_whole_texts(spark: SparkSession, path: str) -> DataFrame:
    """path and text of each file, undecodable bytes replaced."""
    return spark.read.format("binaryFile").load(path).select("path", F.decode("content", "UTF-8").alias("text"))

"""Streams, read to their present end, against the same said in SQL."""

import uuid

from pyspark.sql import functions as F

from ..sources.tables import scratch_path
from ..streaming import windows as S
from .registry import query


def _ran(spark, make, mode="complete"):
    def run(d):
        return S.run_once(make(S.stamped(S.events(spark, d))), f"s_{uuid.uuid4().hex}", scratch_path(spark, "stream"), mode)

    return run


@query("op_stream_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def _(spark, d):
    out = _ran(spark, S.tumbling)(d)
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("op_stream_sliding", "SELECT s AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 1 HOUR, ts), time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 1 HOUR]) AS s FROM events) GROUP BY 1")
def _(spark, d):
    return _ran(spark, S.sliding)(d).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("op_stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def _(spark, d):
    return _ran(spark, lambda s: S.deduplicated(s.select("event_id")), "append")(d).agg(F.count(F.lit(1)).alias("n"))


@query("op_stream_encoding", "SELECT event_type, count(*) AS n, round(avg(value), 6) AS mean_value FROM events GROUP BY 1")
def _(spark, d):
    return _ran(spark, S.encoding_statistics)(d)


@query("op_stream_session")
def _(spark, d):
    from ..sources.tables import load

    return S.sessions(S.stamped(load(spark, d, "events")))


@query("op_stream_static_join", "SELECT event_type, count(*) AS n, round(sum((value - m) * (value - m)), 2) AS residual FROM events JOIN (SELECT event_type, round(avg(value), 6) AS m FROM events GROUP BY 1) USING (event_type) GROUP BY 1")
def _(spark, d):
    from ..sources.tables import load

    frozen = S.encoding_statistics(load(spark, d, "events")).select("event_type", "mean_value")
    rows = _ran(spark, lambda s: S.with_frozen_encodings(s.select("event_type", "value"), frozen), "append")(d)
    return rows.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum((F.col("value") - F.col("mean_value")) * (F.col("value") - F.col("mean_value"))), 2).alias("residual"))


@query(
    "op_stream_followed",
    "SELECT a.user_id, a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'",
)
def _(spark, d):
    return _ran(spark, lambda s: S.followed_within(s, "click", "purchase"), "append")(d)


@query(
    "op_stream_smoothing",
    "SELECT user_id, count(value) AS n, round(l * avg(value) + (1 - l) * 50, 4) AS encoding FROM (SELECT *, 1 / (1 + exp(-(count(value) OVER (PARTITION BY user_id) - 20) / 10.0)) AS l FROM events) GROUP BY user_id, l",
)
def _(spark, d):
    rows = _ran(spark, lambda s: S.smoothed(s, 50.0), "update")(d)
    return rows.groupBy("user_id").agg(F.max("n").alias("n"), F.round(F.max_by("encoding", "n"), 4).alias("encoding"))


@query("op_stream_scoring")
def _(spark, d):
    from ..models.registry import fit
    from ..plans import workloads as W
    from ..sources.tables import SCHEMAS

    rows = W.dense(spark, d).withColumn("label", F.col("y_lin").cast("double"))
    model = fit("discriminant", rows.where("split = 'train'"), None, "binary")
    stream = spark.readStream.schema(SCHEMAS["embeddings"]).parquet(f"{d}/embeddings.parquet*").select("vec_id", F.col("embedding").cast("array<double>").alias("features"))
    return S.run_once(model.transform(stream).select("vec_id", "prediction"), f"s_{uuid.uuid4().hex}", scratch_path(spark, "stream"), "append")

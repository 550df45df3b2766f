"""SQL functions that Catalyst inlines."""

from __future__ import annotations

from pyspark.sql import SparkSession

FUNCTIONS = (
    "smooth_encode(n DOUBLE, mean DOUBLE, overall DOUBLE, kmin DOUBLE, f DOUBLE) RETURNS DOUBLE RETURN CASE WHEN n IS NULL OR n = 0 THEN overall ELSE mean / (1 + exp(-(n - kmin) / f)) + overall * (1 - 1 / (1 + exp(-(n - kmin) / f))) END",
    "hash_u(seed STRING, k STRING) RETURNS DOUBLE RETURN CAST(conv(substring(md5(CAST(concat_ws('|', seed, k) AS BINARY)), 1, 8), 16, 10) AS DOUBLE) / 4294967296.0",
    "mask_entities(s STRING) RETURNS STRING RETURN regexp_replace(regexp_replace(regexp_replace(s, '<[A-Za-z/!][^>]*>', '[HTML]'), '(https?://|www[.])[^ \"<>]+', '[URL]'), '[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+[.][A-Za-z]+', '[EMAIL]')",
)


def register(spark: SparkSession) -> None:
    for body in FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {body}")

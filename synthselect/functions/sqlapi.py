"""SQL functions of the methods, inlined by Catalyst."""

from pyspark.sql import SparkSession

FUNCTIONS = {
    "hash_unit": "(seed STRING, id STRING) RETURNS BIGINT RETURN cast(conv(substr(md5(concat_ws('-', seed, id)), 1, 8), 16, 10) AS BIGINT)",
    "rademacher_sign": "(seed STRING, i INT, j INT) RETURNS BIGINT RETURN 1 - 2 * (cast(conv(substr(md5(concat_ws('-', seed, cast(i AS STRING), cast(j AS STRING))), 1, 8), 16, 10) AS BIGINT) % 2)",
    "pass_at_1": "(n INT, c INT) RETURNS DOUBLE RETURN CASE WHEN n > 0 THEN c / n END",
    "weighted_score": "(x ARRAY<INT>, w ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(x, w, (a, b) -> a * b), 0D, (s, v) -> s + v)",
    "cosine_fp": "(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS DOUBLE RETURN round(aggregate(zip_with(a, b, (x, y) -> cast(x AS DOUBLE) * y), 0D, (s, v) -> s + v) / sqrt(aggregate(a, 0D, (s, v) -> s + cast(v AS DOUBLE) * v)) / sqrt(aggregate(b, 0D, (s, v) -> s + cast(v AS DOUBLE) * v)), 6)",
}


def register(spark: SparkSession) -> None:
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")

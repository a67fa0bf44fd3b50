"""Writing and reading back in the built-in formats, and the partitioned sink."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gistloom.staging import fresh_path


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    spark, path = df.sparkSession, fresh_path(df.sparkSession, fmt)
    kept = df.select("n_nationkey", "n_name", "n_regionkey") if fmt != "text" else df.select("n_name")
    kept.write.format(fmt).save(path)
    if fmt == "text":
        return spark.read.text(path).withColumnRenamed("value", "n_name")
    return spark.read.format(fmt).schema(kept.schema).load(path)


def sink_partitioned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers written by region and read back with the partition column pruned to."""
    path = fresh_path(spark, "by-region")
    at = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    joined = at("customer").join(at("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(at("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    joined.select("c_custkey", "r_name").write.partitionBy("r_name").parquet(path)
    return spark.read.parquet(path).groupBy("r_name").agg(F.count("*").alias("n"))

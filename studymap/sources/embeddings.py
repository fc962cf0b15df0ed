"""Logits from the embeddings: scaled products with the class centroids of the training rows, for the held-out rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import network


def scored(spark: SparkSession, sf_dir: str, scales=(20, 60)) -> DataFrame:
    """(row_id, network, truth_idx, logits). The centroids (classes x dimensions) are the only numbers that reach the driver."""
    emb = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("x"))
    head = network.centroid_head(emb.where("vec_id % 10 < 8"))
    x = network.infer(emb.where("vec_id % 10 >= 8"), head).withColumn("s", F.explode(F.array(*map(F.lit, scales))))
    return x.select(F.col("vec_id").alias("row_id"), F.concat(F.lit("x"), "s").alias("network"), F.col("label").alias("truth_idx"), F.transform("logits", lambda v: F.round(F.col("s") * v, 9)).alias("logits"))

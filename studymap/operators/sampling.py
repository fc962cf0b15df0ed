"""Training sets: rejection by descriptor, caps per class, splits, folds, labels from the container."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.portable import P, stream
from ..functions.text import checked_broadcast


def reject_descriptor(series: DataFrame, pattern: str) -> DataFrame:
    """Series whose descriptor does not match; null descriptors stay: only what is known not to represent the study is rejected."""
    return series.where(~F.coalesce(F.rlike("descriptor", F.lit(pattern)), F.lit(False)))


def cap_per_class(df: DataFrame, label: str, key: str, cap: int, seed: int = 1) -> DataFrame:
    """At most `cap` rows of each class by a portable draw. Large classes are thinned by hash first, so no window sees a whole large class."""
    drawn = df.withColumn("_u", F.expr(stream(key, seed)))
    sizes = checked_broadcast(df.groupBy(label).agg(F.count(F.lit(1)).alias("_n")))
    # On average 4 * cap + 200 rows pass the thinning; that fewer than cap do has probability below 1e-30.
    thin = drawn.join(sizes, label)
    keep = (F.col("_n") <= 8 * cap) | (F.col("_u").cast("double") / 2147483647 <= F.lit(4.0 * cap + 200) / F.col("_n"))
    order = W.partitionBy(label).orderBy("_u", key)
    return thin.where(keep).withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= cap).drop("_u", "_n", "_r")


def split(df: DataFrame, key: str, shares=(80, 10, 10), seed: int = 2) -> DataFrame:
    a, b, _ = shares
    p = F.expr(f"{stream(key, seed)} % 100")
    return df.withColumn("part", F.when(p < a, "train").when(p < a + b, "validation").otherwise("test"))


def folds(df: DataFrame, label: str, key: str, n: int = 5, seed: int = 3, slices: int = 256) -> DataFrame:
    """Folds that hold each class in equal numbers up to one: the row number in the class by a portable draw, modulo n.

    The draw's range is cut into slices, which are counted first; rows are numbered inside a slice only, so no task sees a whole class.
    """
    x = df.withColumn("_u", F.expr(stream(key, seed))).withColumn("_slice", F.expr(f"_u * {slices} div {P}")).withColumn("_l", F.struct(F.col(label).alias("v")))
    counts = x.groupBy("_l", "_slice").agg(F.count(F.lit(1)).alias("_n"))
    counts = counts.select("_l", "_slice", (F.sum("_n").over(W.partitionBy("_l").orderBy("_slice")) - F.col("_n")).alias("_before"))
    row = F.col("_before") + F.row_number().over(W.partitionBy("_l", "_slice").orderBy("_u", key)) - 1
    return x.join(counts, ["_l", "_slice"]).withColumn("fold", (row % n).cast("int")).drop("_u", "_slice", "_l", "_before")


def label_by_container(series: DataFrame, study_class: DataFrame) -> DataFrame:
    """Every series takes the class under which its study was archived."""
    return series.join(study_class.select("study_id", "label"), "study_id")

"""Grades and measures: right, minor, major, unanswered; coverage, accuracy and rates with their denominators; contribution, confusion, folds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import checked_broadcast

T_FOUR = 2.7764451051977987  # 97.5 % point of Student's t with four degrees of freedom


def grade(study: DataFrame, prediction: DataFrame, minor_pair: DataFrame) -> DataFrame:
    """(study_id, label, layer, grade) for every study: right if any truth label is the prediction, else minor if any (truth, prediction) pair is listed, else major."""
    layer = ["layer"] if "layer" in prediction.columns else []
    x = study.select("study_id", "truth").join(prediction.select("study_id", "label", *layer), "study_id", "left")
    return graded(x, minor_pair).select("study_id", "label", *layer, "grade")


def graded(x: DataFrame, minor_pair: DataFrame) -> DataFrame:
    """Rows with `truth` and `label` gain `grade`."""
    minors = checked_broadcast(minor_pair.groupBy("pred").agg(F.collect_set("truth").alias("_general_for")))
    x = x.join(minors, F.col("label") == F.col("pred"), "left")
    g = F.when(F.col("label").isNull(), "unanswered").when(F.coalesce(F.array_contains("truth", F.col("label")), F.lit(False)), "right").when(F.coalesce(F.arrays_overlap("truth", "_general_for"), F.lit(False)), "minor").otherwise("major")
    return x.withColumn("grade", g).drop("pred", "_general_for")


def measures(graded: DataFrame, by=()) -> DataFrame:
    """Counts and rates of a graded table; both minor figures, over the answered and over all."""
    n = lambda g: F.count_if(F.col("grade") == g)
    x = graded.groupBy(*by).agg(F.count(F.lit(1)).alias("studies"), n("right").alias("right"), n("minor").alias("minor"), n("major").alias("major"), n("unanswered").alias("unanswered"))
    return with_rates(x)


def with_rates(x: DataFrame) -> DataFrame:
    answered = F.col("studies") - F.col("unanswered")
    rate = lambda a, b: F.round(F.try_divide(a.cast("double"), b.cast("double")), 6)
    return x.withColumns(
        {
            "predictive_power": rate(answered, F.col("studies")), "accuracy": rate(F.col("right"), answered), "minor_rate": rate(F.col("minor"), answered),
            "minor_share": rate(F.col("minor"), F.col("studies")), "major_rate": rate(F.col("major"), answered),
        }
    )


def contribution(study: DataFrame, with_net: DataFrame, without_net: DataFrame) -> DataFrame:
    """Share of studies whose outcome changes when network votes are removed."""
    x = study.select("study_id").join(with_net.select("study_id", F.col("label").alias("a")), "study_id", "left").join(without_net.select("study_id", F.col("label").alias("b")), "study_id", "left")
    return x.agg(F.round(F.avg((~F.col("a").eqNullSafe(F.col("b"))).cast("int")), 6).alias("contribution_flip"))


def related_errors(graded: DataFrame, study: DataFrame, classes: DataFrame, by: str = "layer") -> DataFrame:
    """Among wrong answers, the share whose class has the same parent as a truth label."""
    parents = checked_broadcast(classes.select("label", "parent"))
    wrong = graded.where("grade = 'major'").join(parents, "label").join(study.select("study_id", F.explode("truth").alias("t")), "study_id")
    wrong = wrong.join(parents.select(F.col("label").alias("t"), F.col("parent").alias("tp")), "t")
    one = wrong.groupBy("study_id", by).agg(F.max((F.col("parent") == F.col("tp")).cast("int")).alias("rel"))
    return one.groupBy(by).agg(F.count(F.lit(1)).alias("errors"), F.round(F.avg("rel"), 6).alias("related_rate"))


def truth_sets(rows: DataFrame) -> DataFrame:
    """(study_id, label) rows of a person's labels -> sorted array, several allowed."""
    return rows.where("label is not null").groupBy("study_id").agg(F.array_sort(F.collect_set("label")).alias("truth"))


def t_interval(folds: DataFrame, by) -> DataFrame:
    """(by.., fold, acc) of five folds -> mean and 95 % interval."""
    m, half = F.avg("acc"), T_FOUR * F.stddev_samp("acc") / F.sqrt(F.lit(5.0))
    return folds.groupBy(*by).agg(F.round(m, 6).alias("accuracy"), F.round(m - half, 6).alias("lo"), F.round(m + half, 6).alias("hi"))

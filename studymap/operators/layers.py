"""Header layers: exact code, exact description, partial description, edit distance.

A layer maps studies to predictions (study_id, label, score); a study it cannot decide has no row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.lineage import cut
from ..functions.text import checked_broadcast, lcsubstr_len, normalise, whole_keyword

MIN_LEN, SHORT_LEN = 6, 4


def match_code(study: DataFrame, code_ref: DataFrame, raw: bool = False) -> DataFrame:
    form: callable = (lambda c: c) if raw else normalise
    ref = checked_broadcast(code_ref.select(form(F.col("code")).alias("_k"), "label").distinct())
    return study.select("study_id", form(F.col("procedure_code")).alias("_k")).join(ref, "_k").select("study_id", "label", F.lit(0).alias("score"))


def match_description(study: DataFrame, desc_ref: DataFrame) -> DataFrame:
    ref = checked_broadcast(desc_ref.select(normalise(F.col("description")).alias("_k"), "label").distinct())
    return study.select("study_id", normalise(F.col("description")).alias("_k")).join(ref, "_k").select("study_id", "label", F.lit(0).alias("score"))


def match_exact(study: DataFrame, code_ref: DataFrame, desc_ref: DataFrame, order=(1, 2)) -> DataFrame:
    """Both exact layers in one pass: the study's columns with label and layer, null where neither decides."""
    code = checked_broadcast(code_ref.select(normalise(F.col("code")).alias("_k1"), F.col("label").alias("_l1")).distinct())
    desc = checked_broadcast(desc_ref.select(normalise(F.col("description")).alias("_k2"), F.col("label").alias("_l2")).distinct())
    x = study.join(code, normalise(F.col("procedure_code")) == F.col("_k1"), "left").join(desc, normalise(F.col("description")) == F.col("_k2"), "left")
    layer = F.coalesce(*(F.when(F.col(f"_l{n}").isNotNull(), F.lit(n)) for n in order))
    return x.select(*study.columns, F.coalesce(*(F.col(f"_l{n}") for n in order)).alias("label"), layer.alias("layer"))


def keyword_scores(values: DataFrame, keyword_ref: DataFrame, min_len: int = MIN_LEN, short_len: int = SHORT_LEN, short_match: str = "word") -> DataFrame:
    """Distinct normalised values -> (value, keyword, label, score) of all eligible keywords."""
    words = keyword_ref.select(normalise(F.col("keyword")).alias("keyword"), "label")
    long_ = words.where(F.length("keyword") >= min_len)
    short = words.where(F.length("keyword").between(short_len, min_len - 1))
    by_run = lcsubstr_len(values.select("value", F.col("value").alias("t")), long_.select("keyword", F.col("keyword").alias("t")).distinct(), min_len, "value", "keyword").withColumnRenamed("len", "score")
    whole = whole_keyword(values, short.select("keyword").distinct(), short_match).withColumn("score", F.length("keyword"))
    # Dealt by value once more, behind which labels are summed and joined where they are.
    return by_run.unionByName(whole).repartition("value").join(checked_broadcast(words.distinct()), "keyword").select("value", "keyword", "label", "score")


def best_labels(scores: DataFrame, tie: str = "abstain") -> DataFrame:
    """(value, label, score) of the best keyword; several classes with the best score abstain, or the first by label wins."""
    top = scores.groupBy("value", "label").agg(F.max("score").alias("score")).groupBy("value").agg(F.max("score").alias("score"), F.collect_list(F.struct("score", "label")).alias("_all"))
    best = F.array_sort(F.transform(F.filter("_all", lambda s: s["score"] == F.col("score")), lambda s: s["label"]))
    top = top.select("value", "score", best.alias("_best"))
    return (top if tie == "first" else top.where(F.size("_best") == 1)).select("value", F.col("_best")[0].alias("label"), "score")


def match_partial(study: DataFrame, keyword_ref: DataFrame, min_len: int = MIN_LEN, short_len: int = SHORT_LEN, short_match: str = "word", tie: str = "abstain") -> DataFrame:
    x = study.select("study_id", normalise(F.col("description")).alias("value")).where("value is not null")
    best = cut(best_labels(keyword_scores(x.select("value").distinct(), keyword_ref, min_len, short_len, short_match), tie))
    return x.join(checked_broadcast(best), "value").select("study_id", "label", "score")


def match_fuzzy(study: DataFrame, keyword_ref: DataFrame, max_dist: int = 2) -> DataFrame:
    """Nearest keyword by edit distance up to max_dist, unique label only. The length difference bounds the distance, so it prunes first."""
    x = study.select("study_id", normalise(F.col("description")).alias("value")).where("value is not null")
    words = checked_broadcast(keyword_ref.select(normalise(F.col("keyword")).alias("keyword"), "label").distinct(), equi=False)
    near = F.abs(F.length("value") - F.length("keyword")) <= max_dist
    pairs = x.select("value").distinct().join(words, near).withColumn("_d", F.levenshtein("value", "keyword", max_dist)).where("_d >= 0")
    best = best_labels(pairs.select("value", "keyword", "label", (-F.col("_d")).alias("score")))
    return x.join(best, "value").select("study_id", "label", (-F.col("score")).alias("score"))


def as_layer(prediction: DataFrame, number: int) -> DataFrame:
    return prediction.select("study_id", "label", F.lit(number).alias("layer"))


def first_deciding(*labels: Column) -> Column:
    return F.coalesce(*labels)

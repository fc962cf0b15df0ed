"""Votes: tags of all series matched against keywords, and the decision by weight.

A vote is (study_id, label, weight_u, origin, series_no); weights are integers in micro-units, so sums and ties are exact under any partitioning.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.lineage import cut
from ..functions.portable import MICRO
from ..functions.text import checked_broadcast, normalise
from .layers import best_labels, keyword_scores


def raw_tags(series: DataFrame, keys) -> DataFrame:
    """(study_id, series_no, key, raw) of the configured keys that a series carries."""
    kept = F.map_filter("tags", lambda k, v: k.isin(*keys) & v.isNotNull())
    return series.select("study_id", "series_no", F.explode(kept).alias("key", "raw"))


def extract_tags(series: DataFrame, keys) -> DataFrame:
    """(study_id, series_no, key, value) of the configured keys; absent keys and empty values have no row."""
    return raw_tags(series, keys).select("study_id", "series_no", "key", normalise(F.col("raw")).alias("value")).where("value is not null")


def metadata_votes(series: DataFrame, keyword_ref: DataFrame, keys, vote_per: str = "value", short_match: str = "word") -> DataFrame:
    """Each tag value votes once, for its best keyword's class (or for every matching keyword). Only distinct values are normalised and matched."""
    tags = raw_tags(series, keys)
    values = cut(tags.select("raw").distinct().select("raw", normalise(F.col("raw")).alias("value")).where("value is not null"))
    scores = keyword_scores(values.select("value").distinct(), keyword_ref, short_match=short_match)
    matched = best_labels(scores) if vote_per == "value" else scores
    # Distinct values are written down and sent to the tags where they are few: no tag is shuffled by a value that all makers use.
    matched = checked_broadcast(cut(values.join(matched.select("value", "label"), "value").select("raw", "label")))
    return tags.join(matched, "raw").select("study_id", "label", F.lit(MICRO).cast("long").alias("weight_u"), F.concat(F.lit("tag:"), "key").alias("origin"), "series_no")


def ballot(vote: DataFrame) -> DataFrame:
    """(study_id, label, weight_u): one row per candidate, combined before the shuffle."""
    return vote.where("label is not null").groupBy("study_id", "label").agg(F.sum("weight_u").alias("weight_u"))


def decide(vote: DataFrame, majority: str = "plurality") -> DataFrame:
    """(study_id, label, weight_u, runner_up): the label with the one largest sum. Ties, and with 'absolute' sums of at most half, decide nothing."""
    # Dealt by study once; both sums find their rows there.
    sums = ballot(vote.select("study_id", "label", "weight_u").repartition("study_id"))
    x = sums.groupBy("study_id").agg(
        F.max(F.struct("weight_u", "label")).alias("_top"), F.sum("weight_u").alias("_all"), F.sort_array(F.collect_list(F.struct("weight_u", "label")), asc=False).alias("_order")
    )
    second = F.get("_order", F.lit(1))
    won = (second["weight_u"].isNull() | (second["weight_u"] < F.col("_top.weight_u"))) & (F.col("_top.weight_u") > 0)
    if majority == "absolute":
        won = won & (F.col("_top.weight_u") * 2 > F.col("_all"))
    return x.where(won).select("study_id", F.col("_top.label").alias("label"), F.col("_top.weight_u").alias("weight_u"), second["label"].alias("runner_up"))


def share_of_winner(vote: DataFrame) -> DataFrame:
    from pyspark.sql import Window as W

    return ballot(vote).withColumn("share", F.col("weight_u") / F.sum("weight_u").over(W.partitionBy("study_id")))

"""Vote rules as data: drop, relabel or reweight votes that meet a rule's conditions.

Conditions look at the vote set before any rule (a null condition holds for all; when_other_label asks that the study has some vote for that label). Then drops come
first, relabels next (least rule_id wins, no chains), reweights last (factors multiply in the order of rule_id, one rounding).

A configuration's rules, up to `MOST_COMPILED`, become column expressions, so votes are shuffled only where a rule asks for another label of the study. More of them are joined.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.portable import inline_table
from ..functions.text import checked_broadcast

SCHEMA = "rule_id int, tier string, when_modality string, when_key string, when_label string, when_other_label string, action string, new_label string, factor double"
MOST_COMPILED = 200


def rule_table(spark, rows) -> DataFrame:
    return inline_table(spark, rows, SCHEMA)


def apply(vote: DataFrame, rule_ref: DataFrame, tier: str = "full", most: int = MOST_COMPILED) -> DataFrame:
    """Votes (study_id, label, weight_u, origin, series_no, modality) after the rules. tier='min' keeps core rules only."""
    rules = rule_ref.where("tier = 'core'") if tier == "min" else rule_ref
    some = rules.limit(most + 1).collect()  # a configuration, of a bounded number of rows
    if len(some) > most:
        return _joined(vote, rules)
    some.sort(key=lambda r: r["rule_id"])
    others = sorted({r["when_other_label"] for r in some if r["when_other_label"] is not None})
    every, v = list(vote.columns), vote
    if others:
        present = vote.where(F.col("label").isin(others)).groupBy("study_id").agg(F.collect_set("label").alias("_present"))
        v = vote.join(present, "study_id", "left")
    key = F.when(F.startswith("origin", F.lit("tag:")), F.substring_index("origin", ":", -1))

    def meets(r):
        parts = [c.eqNullSafe(F.lit(r[n])) for n, c in (("when_modality", F.col("modality")), ("when_key", key), ("when_label", F.col("label"))) if r[n] is not None]
        if r["when_other_label"] is not None:
            parts.append(F.coalesce(F.array_contains("_present", r["when_other_label"]), F.lit(False)))
        return reduce(lambda a, b: a & b, parts, F.lit(True))

    does = lambda action: [r for r in some if r["action"] == action]
    for r in does("drop"):
        v = v.where(~meets(r))
    label, weight = F.col("label"), F.col("weight_u")
    if does("relabel"):
        label = F.coalesce(*(F.when(meets(r), F.lit(r["new_label"])) for r in does("relabel")), label)
    if does("reweight"):
        factor = reduce(lambda a, b: a * b, [F.when(meets(r), F.lit(r["factor"])).otherwise(1.0) for r in does("reweight")])
        weight = F.round(weight * factor).cast("long")
    return v.select(*[label.alias(c) if c == "label" else weight.alias(c) if c == "weight_u" else F.col(c) for c in every])


def _joined(vote: DataFrame, rules: DataFrame) -> DataFrame:
    """The same by a join, for rule tables beyond what is compiled."""
    key = F.when(F.startswith("origin", F.lit("tag:")), F.substring_index("origin", ":", -1))
    every = list(vote.columns)
    v = vote.groupBy(*[c for c in every if c != "weight_u"]).agg(F.sum("weight_u").alias("weight_u"))  # equal votes of one value are one vote of their weight
    other = checked_broadcast(rules.where("when_other_label is not null").select("when_other_label").distinct())
    present = vote.join(other, F.col("label") == F.col("when_other_label")).groupBy("study_id").agg(F.collect_set("label").alias("_present"))
    v = v.join(present, "study_id", "left").withColumn("_key", key)
    meets = lambda rule, col: F.col(rule).isNull() | F.col(rule).eqNullSafe(F.col(col))
    cond = meets("when_modality", "modality") & meets("when_key", "_key") & meets("when_label", "label") & (F.col("when_other_label").isNull() | F.coalesce(F.array_contains("_present", F.col("when_other_label")), F.lit(False)))
    small = checked_broadcast(rules, equi=False)
    hit = v.join(small, cond, "left")
    g = hit.groupBy(*every).agg(
        F.count(F.lit(1)).alias("_rows"),
        F.count_if(F.col("action") == "drop").alias("_drops"),
        F.min(F.when(F.col("action") == "relabel", F.struct("rule_id", "new_label"))).alias("_to"),
        F.product(F.when(F.col("action") == "reweight", F.col("factor"))).alias("_factor"),
    )
    return g.where("_drops = 0").select(
        *[F.coalesce(F.col("_to.new_label"), "label").alias("label") if c == "label" else F.round(F.col("weight_u") * F.coalesce("_factor", F.lit(1.0))).cast("long").alias("weight_u") if c == "weight_u" else F.col(c) for c in every]
    )

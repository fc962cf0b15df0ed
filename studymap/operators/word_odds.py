"""Binary judgements of texts by word evidence: the log odds of every distinct word, as integers in micro-units, so that sums do not depend on order."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.portable import MICRO

PRIOR = 10.0


def scored(docs: DataFrame, trains, labels) -> DataFrame:
    """(doc_id, network, truth_idx, logits [0, z]) of the rows that do not train, one row for each label column; network is the column's name.

    docs: doc_id, text and 0/1 columns `labels`; rows with a null text or label are left out. `trains` is a condition on docs. z is the log odds of the label plus
    those of each distinct word's presence. Every class gets PRIOR imagined texts that hold a word as often as all texts do, so rare words lean to neither class.
    Evidence of dependent words is counted more than once: z is over-confident.
    Words are one shuffle of distinct (document, word) pairs; their odds are joined by shuffle or broadcast as Catalyst finds their size.
    """
    labels = tuple(labels)
    docs = docs.select("doc_id", "text", *labels, trains.alias("_trains")).dropna(subset=["text", *labels])
    words = docs.select("doc_id", *labels, "_trains", F.explode(F.array_distinct(F.split(F.lower("text"), "[^a-zà-ÿß]+"))).alias("_word")).where("_word <> ''")
    counted = words.where("_trains").groupBy("_word").agg(F.count(F.lit(1)).alias("_n"), *(F.sum(c).alias(c) for c in labels))
    total = docs.where("_trains").agg(F.count(F.lit(1)).alias("_all"), *(F.sum(c).alias(f"_all_{c}") for c in labels))

    def odds(c):
        usual = F.lit(PRIOR) * F.col("_n") / F.col("_all")
        there = F.log((F.col(c) + usual) / (F.col(f"_all_{c}") + PRIOR)) - F.log((F.col("_n") - F.col(c) + usual) / (F.col("_all") - F.col(f"_all_{c}") + PRIOR))
        return F.round(there * MICRO).cast("long").alias(f"_w_{c}")

    def base(c):
        return F.round(F.log((F.col(f"_all_{c}") + 1) / (F.col("_all") - F.col(f"_all_{c}") + 1)) * MICRO).cast("long").alias(f"_b_{c}")

    weights = counted.join(F.broadcast(total)).select("_word", *map(odds, labels))  # total is one row
    sums = words.where("NOT _trains").select("doc_id", "_word").join(weights, "_word").groupBy("doc_id").agg(*(F.sum(f"_w_{c}").alias(f"_z_{c}") for c in labels))
    held = docs.where("NOT _trains").drop("text").join(sums, "doc_id", "left").join(F.broadcast(total.select(*map(base, labels))))
    z = lambda c: (F.coalesce(F.col(f"_z_{c}"), F.lit(0)) + F.col(f"_b_{c}")).cast("double") / MICRO
    cells = F.array(*(F.struct(F.lit(c).alias("network"), F.col(c).cast("int").alias("truth_idx"), F.array(F.lit(0.0), z(c)).alias("logits")) for c in labels))
    return held.select("doc_id", F.explode(cells).alias("_c")).select("doc_id", "_c.*")

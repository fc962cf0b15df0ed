"""Classes of texts by word evidence, fitted on capped training rows of the other folds: integer weights, so that results do not depend on order and SQL can repeat them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.lineage import cut
from ..functions.portable import MICRO, stream
from ..functions.text import checked_broadcast

PRIOR = 10.0
FOLDS = 5


def training_rows(docs: DataFrame, cap: int, by=("class_id",)) -> DataFrame:
    """Rows (doc_id, fold, class_id, `by`), none without a class, of which any four folds hold at most `cap` of a class: cap // 4 a fold, by a portable draw.

    Only keys are ranked, and the rank is a filter, so Spark keeps the first rows of a group before the shuffle.
    """
    names = list(dict.fromkeys(("doc_id", "fold", "class_id", *by)))
    order = W.partitionBy("fold", *by).orderBy(F.expr(stream("doc_id", 1)), "doc_id")
    return docs.select(*names).where("class_id is not null").withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= cap // 4).drop("_r")


def judged(docs: DataFrame, training: DataFrame, settings: int, classes: int, weighted=()) -> DataFrame:
    """(doc_id, setting, predicted): every document with a text, in every setting, by the training rows of that setting in the other folds.

    docs: doc_id, text, fold. training: doc_id, fold, setting (0, 1, ..), class_id (0, 1, ..), a bounded number of rows. In a setting listed in `weighted` each class
    weighs the same, whatever its number of rows. A class's score is its share of rows and the shares of its rows that hold each distinct word, as logarithms in
    micro-units; PRIOR imagined rows of a class hold a word as often as all rows do. Ties go to the lowest class; a text without known words has the share of rows alone.
    Test words are shuffled once, combined by document before that: all settings stand side by side in the weights of a word, whose number training bounds.
    """
    cs, heavy = range(classes), F.col("setting").isin(*weighted) if weighted else F.lit(False)
    words = docs.where("text is not null").select("doc_id", "fold", F.explode(F.array_distinct(F.split(F.lower("text"), "[^a-zà-ÿß]+"))).alias("_word")).where("_word <> ''")
    tests = F.explode(F.filter(F.array(*map(F.lit, range(FOLDS))), lambda t: t != F.col("fold")))
    training = cut(training.select("doc_id", "setting", "class_id", tests.alias("_test")))
    per_class = [F.count_if(F.col("class_id") == c) for c in cs]
    sizes = training.groupBy("_test", "setting").agg(*(n.alias(f"_all{c}") for c, n in zip(cs, per_class)))
    every = sum(F.col(f"_all{c}") for c in cs)
    weight = [F.when(heavy, every / (classes * F.greatest(F.col(f"_all{c}"), F.lit(1)))).otherwise(1.0) for c in cs]
    sizes = sizes.select("_test", "setting", *(F.col(f"_all{c}").alias(f"_all{c}") for c in cs), *(w.cast("double").alias(f"_k{c}") for c, w in zip(cs, weight)))
    sizes = sizes.withColumn("_total", sum(F.col(f"_all{c}") * F.col(f"_k{c}") for c in cs))
    counts = words.select("doc_id", "_word").join(checked_broadcast(training), "doc_id").groupBy("_word", "_test", "setting").agg(*(n.alias(f"_n{c}") for c, n in zip(cs, per_class)))
    x = counts.join(F.broadcast(sizes), ["_test", "setting"])  # FOLDS x settings rows
    usual = F.lit(PRIOR) * (sum(F.col(f"_n{c}") * F.col(f"_k{c}") for c in cs) / F.col("_total"))
    micro = lambda ratio: F.round(F.log(ratio) * MICRO).cast("long")
    x = x.select("_word", "_test", "setting", *(micro((F.col(f"_n{c}") * F.col(f"_k{c}") + usual) / (F.col(f"_all{c}") * F.col(f"_k{c}") + PRIOR)).alias(f"_w{c}") for c in cs))
    cells = [(s, c) for s in range(settings) for c in cs]
    side = lambda name: [F.max(F.when(F.col("setting") == s, F.col(f"{name}{c}"))).alias(f"{name}{s}_{c}") for s, c in cells]
    known = cut(x.groupBy("_word", "_test").agg(*side("_w")))
    base = sizes.select("_test", "setting", *(micro((F.col(f"_all{c}") * F.col(f"_k{c}") + 1) / (F.col("_total") + 1)).alias(f"_b{c}") for c in cs)).groupBy("_test").agg(*side("_b"))
    found = words.join(checked_broadcast(known).withColumnRenamed("_test", "fold"), ["_word", "fold"])
    sums = found.groupBy("doc_id").agg(*(F.sum(f"_w{s}_{c}").alias(f"_z{s}_{c}") for s, c in cells))
    held = docs.where("text is not null").select("doc_id", "fold").join(sums, "doc_id", "left").join(F.broadcast(base.withColumnRenamed("_test", "fold")), "fold")
    scores = [F.array(*(F.coalesce(F.col(f"_z{s}_{c}"), F.lit(0)) + F.col(f"_b{s}_{c}") for c in cs)) for s in range(settings)]
    told = F.array(*(F.struct(F.lit(s).alias("setting"), (F.array_position(z, F.array_max(z)) - 1).cast("int").alias("predicted")) for s, z in enumerate(scores)))
    return held.select("doc_id", F.explode(told).alias("_t")).select("doc_id", "_t.*")

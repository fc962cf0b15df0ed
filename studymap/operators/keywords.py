"""The keyword catalogue: conflicts, mining, validation, differences between versions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.text import checked_broadcast, lcsubstr_len


def conflicts(keyword_ref: DataFrame, min_len: int = 6) -> DataFrame:
    """(a, b, len): keywords of different classes that share a substring long enough to match."""
    kw = keyword_ref.where(F.length("keyword") >= min_len)
    pairs = lcsubstr_len(kw.select("keyword", F.col("keyword").alias("t")), kw.select("keyword", F.col("keyword").alias("t")), min_len, "a", "b").where("a < b")
    la, lb = (checked_broadcast(kw.select(F.col("keyword").alias(n), F.col("label").alias(f"l{n}"))) for n in "ab")
    return pairs.join(la, "a").join(lb, "b").where("la <> lb").select("a", "b", "len").distinct()


def validate(class_ref: DataFrame, keyword_ref: DataFrame, code_ref: DataFrame, short_len: int = 4) -> DataFrame:
    """(problem, item): keywords too short, labels that no class has, codes given twice."""
    short = keyword_ref.where(F.length("keyword") < short_len).select(F.lit("short keyword").alias("problem"), F.col("keyword").alias("item"))
    used = keyword_ref.select("label").unionByName(code_ref.select("label")).distinct()
    unknown = used.join(class_ref.select("label"), "label", "left_anti").select(F.lit("unknown label").alias("problem"), F.col("label").alias("item"))
    twice = code_ref.groupBy("code").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(F.lit("duplicate code").alias("problem"), F.col("code").alias("item"))
    return short.unionByName(unknown).unionByName(twice)


def difference(old: DataFrame, new: DataFrame) -> DataFrame:
    """Rows added and removed between two versions of a reference table."""
    return new.exceptAll(old).withColumn("change", F.lit("added")).unionByName(old.exceptAll(new).withColumn("change", F.lit("removed")))


def mine(tokens: DataFrame, least_docs: int = 5, share: float = 0.95, top: int = 20, least_len: int = 6) -> DataFrame:
    """(token, label) pairs of documents, distinct -> (label, keyword, docs): tokens that one class nearly owns, the most frequent first."""
    n = tokens.where(F.length("token") >= least_len).groupBy("token", "label").agg(F.count(F.lit(1)).alias("docs"))
    n = n.withColumn("all", F.sum("docs").over(W.partitionBy("token"))).where((F.col("docs") >= least_docs) & (F.col("docs") >= share * F.col("all")))
    return n.withColumn("r", F.row_number().over(W.partitionBy("label").orderBy(F.desc("docs"), "token"))).where(F.col("r") <= top).select("label", F.col("token").alias("keyword"), "docs")

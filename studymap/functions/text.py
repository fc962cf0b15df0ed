"""String matching: normal form, q-grams, longest common substrings, short keywords.

A common substring of length L >= q is a run of L - q + 1 equal q-grams whose positions differ by the same amount, so joining on q-grams and measuring
runs on each diagonal gives the longest common substring exactly, and no pair without a common q-gram can qualify.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .lineage import cut
from .portable import inline_table

#: Reference tables of at most this many rows are broadcast: one row per class and keyword, or per q-gram of a keyword, of a catalogue. Larger ones are joined by shuffle.
MOST_KEYWORDS = 200_000
SMALL_BYTES = 1 << 20
#: Reference tables of at most this many rows are held as literal tables of the plan.
MOST_LITERAL = 2000


def normalise(x: Column) -> Column:
    """Lower case, blanks collapsed and trimmed; empty becomes null."""
    y = F.trim(F.regexp_replace(F.lower(x), r"\s+", " "))
    return F.when(y != "", y)


def qgrams(df: DataFrame, key: str, text: str, q: int) -> DataFrame:
    """(key, pos, gram) for every q-gram of a text; shorter texts have none."""
    n = F.length(text) - q + 1
    grams = F.transform(F.sequence(F.lit(1), n), lambda i: F.substring(F.col(text), i, F.lit(q)))
    return df.where(n >= 1).select(key, F.posexplode(grams).alias("pos", "gram"))


def checked_broadcast(ref: DataFrame, most: int = MOST_KEYWORDS, equi: bool = True) -> DataFrame:
    """A reference table marked for broadcast after its size is known: by the plan, where it is a literal table that nothing multiplies, or else by a count.

    A larger one is left to a shuffle join; joins without an equality have no such way and refuse it.
    """
    plan = ref._jdf.queryExecution().optimizedPlan()
    leaves = plan.collectLeaves()
    literal = all(leaves.apply(i).nodeName() == "LocalRelation" for i in range(leaves.size()))
    known = literal and "Generate" not in plan.toString() and int(str(plan.stats().sizeInBytes())) <= SMALL_BYTES
    if known or ref.limit(most + 1).count() <= most:
        return F.broadcast(ref)
    if not equi:
        raise ValueError(f"a reference table of more than {most} rows has no join without an equality")
    return ref


def literal(ref: DataFrame, most: int = MOST_LITERAL) -> DataFrame:
    """A reference table of integers and strings as a literal table of the plan, made once; one beyond `most` rows is written down instead."""
    rows = ref.limit(most + 1).collect()
    return cut(ref) if len(rows) > most else inline_table(ref.sparkSession, [tuple(r) for r in rows], ", ".join(f"{n} {t}" for n, t in ref.dtypes))


def lcsubstr_len(left: DataFrame, right: DataFrame, q: int, a: str = "a", b: str = "b") -> DataFrame:
    """(a, b, len) for pairs of texts whose longest common substring has q characters at least. Inputs: (a, text), (b, text); the right side is a reference table."""
    x = qgrams(left.toDF(a, "_t"), a, "_t", q).withColumnRenamed("pos", "_pa")
    y = qgrams(right.toDF(b, "_t"), b, "_t", q).withColumnRenamed("pos", "_pb")
    hits = x.join(checked_broadcast(y), "gram").select(a, b, "_pa", (F.col("_pa") - F.col("_pb")).alias("_d"))
    lane = W.partitionBy(a, b, "_d")
    runs = hits.withColumn("_g", F.col("_pa") - F.row_number().over(lane.orderBy("_pa"))).groupBy(a, b, "_d", "_g").agg(F.count(F.lit(1)).alias("_n"))
    return runs.groupBy(a, b).agg((F.max("_n") + q - 1).cast("int").alias("len"))


def whole_keyword(values: DataFrame, keywords: DataFrame, mode: str = "word") -> DataFrame:
    """(value, keyword) where a short keyword stands whole in the value: as a word, anywhere, or as all of it."""
    if mode == "equal":
        return values.join(checked_broadcast(keywords), F.col("value") == F.col("keyword")).select("value", "keyword").distinct()
    if mode == "substring":
        return values.join(checked_broadcast(keywords, equi=False), F.col("value").contains(F.col("keyword"))).select("value", "keyword").distinct()
    words = values.select("value", F.explode(F.array_distinct(F.split("value", "[^\\p{L}\\p{N}]+"))).alias("keyword"))
    return words.join(checked_broadcast(keywords), "keyword").select("value", "keyword").distinct()

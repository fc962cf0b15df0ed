"""Shards by proportional stratified interleaving.

Rows of each source are put in a seeded order; a row's fractional rank is (rank - u) / rows of the source, u in (0, 1) being a hash of the source, so that sources of one row each
spread over the whole range too. Sorting all rows by fractional rank interleaves the sources in proportion, so every contiguous cut of that order holds
the mixture, and cutting it at equal counts gives shards whose row counts differ by one at most (the law `rows`).

Neither rank needs a source, or the table, in one task: a first pass counts rows by (source, slice of the hash range), a second by
slice of the fractional range; exclusive sums over those counts (at most `slices` for each source, and `slices` in all) give offsets, and
row numbers are taken only inside a slice. The order's hash takes the text's checksum with the identifier, so rows without identifier spread as well. Ties fall to the identifier;
rows equal in all columns of the order are interchangeable.

A null source is a source of its own, a null text has no bytes, a null identifier sorts first. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

HASH_SPAN = float(2**64)


def interleaved_positions(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", crc_col: str = "crc", seed: int = 7, slices: int = 1024) -> DataFrame:
    """The input's columns and `_position`: each row's place from 0 in the interleaved order; `_total` beside it."""
    drawn = docs.withColumn("_h", F.xxhash64(F.lit(seed), F.col(id_col).cast("string"), F.col(crc_col)))
    drawn = drawn.withColumn("_slice", F.least(F.floor((F.col("_h").cast("double") / HASH_SPAN + 0.5) * slices), F.lit(slices - 1)).cast("int"))
    drawn = drawn.withColumn("_s", F.struct(F.col(source_col).alias("v")))
    counts = drawn.groupBy("_s", "_slice").agg(F.count(F.lit(1)).alias("_in"))
    whole = W.partitionBy("_s")
    counts = counts.select("_s", "_slice", (F.sum("_in").over(whole.orderBy("_slice")) - F.col("_in")).alias("_before"), F.sum("_in").over(whole).alias("_of"))
    inside = W.partitionBy("_s", "_slice").orderBy("_h", id_col)
    ranked = drawn.join(counts, ["_s", "_slice"]).withColumn("_rank", F.col("_before") + F.row_number().over(inside))
    shift = (F.pmod(F.xxhash64(F.lit(seed), F.col("_s.v").cast("string")), F.lit(1 << 30)) + 0.5) / float(1 << 30)
    ranked = ranked.withColumn("_f", (F.col("_rank") - shift) / F.col("_of")).withColumn("_cut", F.floor(F.col("_f") * slices).cast("int"))
    ranked = ranked.drop("_slice", "_before", "_rank", "_of")
    sums = ranked.groupBy("_cut").agg(F.count(F.lit(1)).alias("_in"))
    line = W.orderBy("_cut")
    sums = sums.select("_cut", (F.sum("_in").over(line) - F.col("_in")).alias("_start"), F.sum("_in").over(W.partitionBy()).alias("_total"))
    order = W.partitionBy("_cut").orderBy("_f", "_s", "_h", id_col)
    placed = ranked.join(F.broadcast(sums), "_cut")  # at most `slices` rows
    return placed.withColumn("_position", F.col("_start") + F.row_number().over(order) - 1).drop("_cut", "_f", "_start", "_h", "_s")


def stratified_shards(docs: DataFrame, shards: int = 8, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", seed: int = 7, slices: int = 1024) -> DataFrame:
    """One row per input row: id, size, text_crc32, law, shard, slot, grown_shard (null: the law is `rows`)."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    slim = docs.select(
        F.col(id_col).alias("_id"),
        F.col(source_col).alias("_source"),
        (F.octet_length(text) + 1).cast("long").alias("_size"),
        F.crc32(text).cast("long").alias("_crc"),
    )
    placed = interleaved_positions(slim, "_id", "_source", "_crc", seed, slices)
    placed = placed.withColumn("_shard", F.expr(f"_position * {shards} div _total"))
    start = F.expr(f"(_shard * _total + {shards - 1}) div {shards}")
    return placed.select(
        F.col("_id").alias(id_col),
        F.col("_size").alias("size"),
        F.col("_crc").alias("text_crc32"),
        F.lit("rows").alias("law"),
        F.col("_shard").cast("int").alias("shard"),
        (F.col("_position") - start).cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )

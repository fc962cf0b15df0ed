"""Exact duplicates by a tree-merge of sorted digest runs.

Every row belongs to one of `runs` runs, fixed by a hash of its identifier. A leaf run is sorted by digest and holds one entry for each distinct digest: the surviving
identifier, the group size and a bit mask of the runs behind it. Runs are then exchanged in binomial rounds: in round k those whose numbers agree but for
`fan_in` values at distance fan_in^k meet, and their sorted entries are merged in one pass over the sorted order, all runs that meet at once, keeping for
each digest the surviving identifier.

No round gathers a run in one task. Runs are cut into slices of the sort order, and as the runs get fewer the slices get finer: partners give each other the slices they don't keep, so
that every task holds as many entries in the last round, where one run is left in many slices, as in the first. The root's decisions go
straight to the leaf runs named in the mask. So a group of copies that holds a third of all rows is combined before the first exchange, has `fan_in` entries in
any merge, and its rows are decided run by run.

An entry is verified where it merges: SHA-256, length and a second, unrelated hash must all agree; the sort order is that of (second hash, digest). The plan shows each round as
Exchange(run, slice), Sort, SortAggregate. Spark has no exchange that keeps its inputs sorted, so the sort over the pieces that arrive plays the merge.

Null texts count as empty. A null identifier is larger and smaller than nothing: it stays only where its group has no other. Of
rows that repeat both identifier and text one stays. An empty table gives an empty result. Other columns are not looked at.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import checkpointed

SAME = ["_check", "_digest", "_bytes"]
KEEP = ("largest", "smallest")


def _digested(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.withColumns({"_check": F.xxhash64(text), "_digest": F.unhex(F.sha2(text, 256)), "_bytes": F.octet_length(text)})


def _in_runs(rows: DataFrame, id_col: str, runs: int) -> DataFrame:
    return rows.withColumn("_run", F.pmod(F.xxhash64(F.col(id_col)), F.lit(runs)).cast("int"))


def _slice(bits: int) -> Column:
    """A contiguous range of the sort order: the first `bits` bits of its first column."""
    return F.shiftright("_check", 64 - bits).cast("int")


def merged_runs(rows: DataFrame, id_col: str, runs: int, fan_in: int, slice_bits: int, keep: str) -> DataFrame:
    """Rows (_run, *SAME, id) -> the one run that is left: (*SAME, _best, _n, _runs), _runs being the mask of leaf runs that hold the digest."""
    if keep not in KEEP:
        raise ValueError("keep is 'largest' or 'smallest'")
    step = fan_in.bit_length() - 1
    levels = runs.bit_length() - 1
    if runs != 1 << levels or runs > 64 or fan_in != 1 << step or step < 1:
        raise ValueError("runs is a power of two up to 64 and fan_in a power of two from 2")
    # A struct is compared in place and has no hashed buffer, so every merge is a pass over sorted entries.
    named = F.col(id_col).isNotNull() if keep == KEEP[0] else F.col(id_col).isNull()
    best = F.max if keep == KEEP[0] else F.min
    entry = ["_run", "_slice", *SAME]
    bits = slice_bits
    x = rows.withColumn("_slice", _slice(bits)).withColumn("_id", F.struct(named.alias("named"), F.col(id_col).alias("id")))
    x = x.groupBy(*entry).agg(best("_id").alias("_best"), F.count(F.lit(1)).alias("_n"), F.expr("bit_or(shiftleft(1L, _run))").alias("_runs"))
    while levels > 0:
        now = min(step, levels)
        levels, bits = levels - now, bits + now
        x = x.withColumn("_run", F.shiftright("_run", now)).withColumn("_slice", _slice(bits)).repartition("_run", "_slice")
        x = x.groupBy(*entry).agg(best("_best").alias("_best"), F.sum("_n").alias("_n"), F.bit_or("_runs").alias("_runs"))
    return x.select(*SAME, F.col("_best.id").alias("_best"), "_n", "_runs")


def _decisions(rows: DataFrame, id_col: str, runs: int, fan_in: int, slice_bits: int, keep: str) -> DataFrame:
    """Rows (_run, *SAME, id) gain _best, _n and _kept. The rows must be written down: they are read at the leaves and again for the decisions."""
    whole = merged_runs(rows, id_col, runs, fan_in, slice_bits, keep)
    back = whole.withColumn("_run", F.expr(f"explode(filter(sequence(0, {runs - 1}), i -> (shiftright(_runs, i) & 1) = 1))")).drop("_runs")
    first = F.row_number().over(W.partitionBy("_run", *SAME, id_col).orderBy(id_col)) == 1
    return rows.join(back, ["_run", *SAME]).withColumn("_kept", F.col(id_col).eqNullSafe(F.col("_best")) & first)


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", runs: int = 64, fan_in: int = 2, keep: str = "largest", slice_bits: int = 6) -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256. `keep` is 'largest' or 'smallest' identifier."""
    slim = docs.select(F.col(id_col).alias("_key"), F.col(text_col).alias("_text"))
    rows = checkpointed(_in_runs(_digested(slim, "_key", "_text").drop("_text"), "_key", runs))
    return _decisions(rows, "_key", runs, fan_in, slice_bits, keep).select(
        F.col("_key").alias(id_col),
        F.col("_best").alias("keep_id"),
        F.col("_n").cast("long").alias("group_size"),
        F.col("_kept").alias("kept"),
        F.lower(F.hex("_digest")).alias("text_sha256"),
    )


def without_exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", runs: int = 64, fan_in: int = 2, keep: str = "largest", slice_bits: int = 6) -> DataFrame:
    """The rows that stay, with exactly the input's columns.

    Decisions are made on slim rows; texts meet only the identifiers and digests that go. Where a row that stays is repeated, one of its rows (any) stays.
    """
    names = docs.columns
    plain = docs.toDF(*(f"_c{i}" for i in range(len(names))))
    id_at, text_at = f"_c{names.index(id_col)}", f"_c{names.index(text_col)}"
    own = _digested(plain, id_at, text_at)
    rows = checkpointed(_in_runs(own.select(id_at, *SAME), id_at, runs))
    decided = checkpointed(_decisions(rows, id_at, runs, fan_in, slice_bits, keep).where("NOT _kept").select(F.col(id_at).alias("_key"), *SAME, "_best").distinct())
    # What doesn't stay: rows of other identifiers, and the further rows of an identifier that repeats its text.
    same = own[id_at].eqNullSafe(F.col("_key"))
    for c in SAME:
        same = same & (own[c] == F.col(f"_g{c}"))
    gone = decided.select("_key", "_best", *(F.col(c).alias(f"_g{c}") for c in SAME))
    again = gone.where(F.col("_key").eqNullSafe(F.col("_best")))
    once = own.join(gone, same, "left_anti")
    twice = own.join(again, same, "left_semi").withColumn("_row", F.row_number().over(W.partitionBy(id_at, *SAME).orderBy(id_at))).where("_row = 1")
    return once.select(*plain.columns).unionByName(twice.select(*plain.columns)).toDF(*names)

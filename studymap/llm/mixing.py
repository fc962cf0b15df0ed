"""Mixing sources to target weights by exponential-key sampling without replacement.

Every document draws u from a seeded hash of its identifier and text; its key is u^(1/w), w being its quality weight, and documents of a source are
taken from the largest key down (the order of exponential keys -ln(u)/w from the smallest up). A source whose target is k times its size and
a rest gets k complete epochs of all its documents first; the rest is filled by the prefix of the key order whose summed sizes reach it. The
document at the border is taken if at least half of it fits, so a source misses its target by half a document at most.

The quality weight is learnt: a logistic model of labelled quality over seven measures of form that one pass over the bytes of a whole text gives (FORM), fitted on a bounded sample
of labelled rows (`sample` rows of at most `longest` bytes, half of each class). Without labels of both classes all weights are 1. A column of the table can give the weights instead.

Targets are found by water filling over the table of sources (one row per source, never in one task): weights share the total, no source goes beyond `cap` times its
size, and the excess is shared by weight among the others. The level rises in rounds, each a sum over the sources that are full below it, until no further source is full.

Prefix sums need no source in one task: sizes are summed by (source, slice), exclusive sums over the slices of a source give offsets, and running sums stay
inside a slice. A doubling of -ln(u)/w holds `slices` slices: none expects more than 0.26 / `slices` of its source's rows of one weight, whatever that
weight, and a source has some 60 * `slices` of them at most.

Null texts have size 0 and are taken in complete epochs only as 0 words; a null source is a source, last in order; null or non-positive weights count
as `least_weight`. Ties in key fall to the identifier. Rows that repeat identifier and text are interchangeable. An empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import bounded_sample, checkpointed

UPPER = b"ABCDEFGHIJKLMNOPQRSTUVWXYZ"
DIGITS = b"0123456789"
SIGNS = bytes(c for c in range(33, 127) if not chr(c).isalnum())
#: Measures of form, in this order: logarithm of the number of words, bytes per word, shares of upper case, digits and signs among the bytes, share of repeated words, share of lines' ends.
FORM = 7


def form_of(text: bytes) -> tuple[int, list[float]]:
    """Number of words, and the measures of form of a whole text."""
    words = text.split()
    n, size = len(words), max(1, len(text))
    count = lambda signs: (len(text) - len(text.translate(None, signs))) / size
    return n, [np.log1p(n), min(size / max(1, n), 100.0), count(UPPER), count(DIGITS), count(SIGNS), 1 - len(set(words)) / max(1, n), text.count(b"\n") / size]


class FormWeight(NamedTuple):
    """P(good) by a logistic model over the measures of form, their squares beside them, scaled as in the sample."""

    centre: np.ndarray
    scale: np.ndarray
    head: np.ndarray
    least: float = 0.05

    def _inputs(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.centre) / self.scale, -5, 5)
        return np.concatenate([np.ones((len(x), 1)), z, z * z], 1)

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return np.maximum(self.least, 1 / (1 + np.exp(-np.clip(self._inputs(x) @ self.head, -30, 30))))


def fit_weight(texts: list[str | None], good: np.ndarray, penalty: float = 1e-3) -> FormWeight | None:
    """Newton steps on the penalised log-likelihood, both classes weighing the same; None unless both classes are there."""
    good = np.asarray(good, bool)
    if not len(good) or good.all() or not good.any():
        return None
    x = np.array([form_of((t or "").encode("utf-8", "replace"))[1] for t in texts])
    model = FormWeight(x.mean(0), np.maximum(x.std(0), 1e-6), np.zeros(1 + 2 * FORM))
    z, head = model._inputs(x), model.head
    share = np.where(good, 0.5 / good.sum(), 0.5 / (~good).sum())
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(z @ head, -30, 30)))
        head = head + np.linalg.solve(z.T @ (z * (share * p * (1 - p))[:, None]) + penalty * np.eye(len(head)), z.T @ (share * (good - p)) - penalty * head)
    return model._replace(head=head)


def train_weight(docs: DataFrame, labels: DataFrame, label: str = "quality", sample: int = 2000, longest: int = 40_000, trains=None, id_col: str = "doc_id", text_col: str = "text") -> FormWeight | None:
    got = bounded_sample(docs, labels, label, sample, F.lit(True) if trains is None else trains, longest, id_col, text_col).collect()
    got = sorted(got, key=lambda r: (r["_h"], r["_text"] or ""))[:sample]
    return fit_weight([r["_text"] for r in got], np.array([r["_y"] == 1 for r in got]))


def measured(rows: DataFrame, text_col: str, weigh: FormWeight | None) -> DataFrame:
    """The rows with `_size` (words of the whole text), `_weight` and `_crc` (checksum of the text) beside them."""
    at = rows.columns.index(text_col)

    def run(batches):
        for b in batches:
            raw = [(t or "").encode("utf-8", "replace") for t in b.column(at).to_pylist()]
            sizes, form, crc = np.empty(len(raw), np.int64), np.empty((len(raw), FORM)), np.empty(len(raw), np.int64)
            for i, t in enumerate(raw):
                sizes[i], form[i] = form_of(t)
                crc[i] = zlib.crc32(t)
            weight = weigh(form) if weigh is not None else np.ones(len(raw))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(sizes), pa.array(weight), pa.array(crc)], names=[*b.schema.names, "_size", "_weight", "_crc"])

    from pyspark.sql.types import DoubleType, LongType, StructType

    schema = StructType([*rows.schema.fields]).add("_size", LongType()).add("_weight", DoubleType()).add("_crc", LongType())
    return rows.mapInArrow(run, schema)


def source_targets(sizes: DataFrame, weights=(5, 2, 1), cap: int = 3) -> DataFrame:
    """(_s, _source_size) -> (_s, _source_size, _target). Sources are in code point order, null last; weights repeat along it."""
    order = F.col("_s").asc_nulls_last()
    # Places in code point order: ranges of sources, counted, and places inside each range.
    x = checkpointed(sizes.select("_s", "_source_size").repartitionByRange(order).withColumn("_range", F.spark_partition_id()))
    counts = x.groupBy("_range").agg(F.count(F.lit(1)).alias("_in"))
    before = counts.select("_range", (F.sum("_in").over(W.orderBy("_range")) - F.col("_in")).alias("_before"))  # one row for each range
    x = x.join(F.broadcast(before), "_range").withColumn("_at", F.col("_before") + F.row_number().over(W.partitionBy("_range").orderBy(order)) - 1)
    cycle = F.array(*(F.lit(float(w)) for w in weights))
    x = x.select("_s", "_source_size", F.element_at(cycle, (F.col("_at") % len(weights) + 1).cast("int")).alias("_w"), (F.col("_source_size") * float(cap)).alias("_limit"))
    x = checkpointed(x.withColumn("_full_at", F.col("_limit") / F.col("_w")))
    level = -1.0
    while True:
        full = F.col("_full_at") < level
        r = x.agg(F.sum("_source_size").alias("total"), F.sum(F.when(full, F.col("_limit")).otherwise(0.0)).alias("taken"), F.sum(F.when(full, 0.0).otherwise(F.col("_w"))).alias("open")).first()
        up = (r["total"] - r["taken"]) / r["open"] if r["open"] else level
        if up <= level:
            break
        level = up
    return x.select("_s", "_source_size", F.least(F.col("_limit"), F.col("_w") * level).alias("_target"))


def mix_decisions(rows: DataFrame, weights=(5, 2, 1), cap: int = 3, seed: int = 11, slices: int = 512, least_weight: float = 0.05) -> DataFrame:
    """Rows with `_id`, `_s` (source), `_size`, `_weight`, `_crc` gain `_source_size`, `_target` and `_copies`."""
    x = rows.withColumn("_u", (F.pmod(F.xxhash64(F.lit(seed), F.col("_id").cast("string"), F.col("_crc")), F.lit(1 << 52)) + 0.5) / float(1 << 52))
    weight = F.greatest(F.coalesce(F.nanvl(F.col("_weight"), F.lit(least_weight)), F.lit(least_weight)), F.lit(least_weight))
    # -ln(u)/w orders as the key u^(1/w) does, from the other end, and doesn't underflow; equal steps of its logarithm are slices of bounded share at every weight.
    x = x.withColumn("_e", -F.log("_u") / weight).withColumn("_slice", F.floor(F.log2("_e") * slices).cast("int")).drop("_u", "_weight", "_crc")
    x = x.withColumn("_g", F.struct(F.col("_s").alias("v")))
    sums = x.groupBy("_g", "_slice").agg(F.sum("_size").alias("_in"))
    whole = W.partitionBy("_g")
    sums = sums.select("_g", "_slice", (F.sum("_in").over(whole.orderBy("_slice")) - F.col("_in")).alias("_before"), F.sum("_in").over(whole).alias("_source_size"))
    sizes = sums.groupBy("_g").agg(F.max("_source_size").alias("_source_size")).select(F.col("_g.v").alias("_s"), "_source_size")
    targets = source_targets(sizes, weights, cap).select(F.struct(F.col("_s").alias("v")).alias("_g"), "_target")
    plan = sums.join(targets, "_g")
    inside = W.partitionBy("_g", "_slice").orderBy("_e", "_id").rowsBetween(W.unboundedPreceding, W.currentRow)
    x = x.join(plan, ["_g", "_slice"]).withColumn("_start", F.col("_before") + F.sum("_size").over(inside) - F.col("_size"))
    epochs = F.least(F.floor(F.col("_target") / F.col("_source_size") + 1e-12), F.lit(cap))
    epochs = F.when(F.col("_source_size") > 0, epochs).otherwise(F.lit(1))
    rest = F.col("_target") - epochs * F.col("_source_size")
    more = (F.col("_start") + F.col("_size") / 2 <= rest) & (epochs < cap) & (rest > 0) & (F.col("_size") > 0)
    return x.withColumn("_copies", (epochs + F.when(more, 1).otherwise(0)).cast("int")).drop("_g", "_slice", "_before", "_start", "_e")


def mix(docs: DataFrame, labels: DataFrame | None = None, weights=(5, 2, 1), cap: int = 3, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", weight_col: str | None = None, seed: int = 11, slices: int = 512) -> DataFrame:
    """One row per input row: id, size, source_size, target, taken (words the mix takes, repeats counted), copies."""
    weigh = train_weight(docs, labels, id_col=id_col, text_col=text_col) if labels is not None and weight_col is None else None
    rows = docs.select(F.col(id_col).alias("_id"), F.col(source_col).alias("_s"), F.col(text_col).alias("_t"), *([F.col(weight_col).cast("double").alias("_own")] if weight_col else []))
    rows = measured(rows, "_t", weigh).drop("_t")
    if weight_col:
        rows = rows.withColumn("_weight", F.col("_own")).drop("_own")
    return mix_decisions(rows, weights, cap, seed, slices).select(
        F.col("_id").alias(id_col),
        F.col("_size").alias("size"),
        F.col("_source_size").alias("source_size"),
        F.col("_target").alias("target"),
        (F.col("_size") * F.col("_copies")).cast("long").alias("taken"),
        F.col("_copies").alias("copies"),
    )


def mixed_documents(docs: DataFrame, labels: DataFrame | None = None, weights=(5, 2, 1), cap: int = 3, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", weight_col: str | None = None, seed: int = 11, slices: int = 512) -> DataFrame:
    """The mix itself: every document as often as it is taken, with exactly the input's columns."""
    names = docs.columns
    at = {n: f"_c{i}" for i, n in enumerate(names)}
    weigh = train_weight(docs, labels, id_col=id_col, text_col=text_col) if labels is not None and weight_col is None else None
    rows = measured(docs.toDF(*at.values()), at[text_col], weigh).withColumns({"_id": F.col(at[id_col]), "_s": F.col(at[source_col])})
    if weight_col:
        rows = rows.withColumn("_weight", F.col(at[weight_col]).cast("double"))
    taken = mix_decisions(rows, weights, cap, seed, slices).where("_copies > 0")
    return taken.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies")))).select(*(F.col(c).alias(n) for n, c in at.items()))

"""Exact top-k inner products by norm-bucketed retrieval.

Vectors are grouped by length: bucket b holds lengths in [ratio^b, ratio^(b+1)), so inside a bucket an inner product is a cosine up to a known factor. Buckets are
cut into blocks of bounded size by a hash of the identifier. A first pass over the longest vectors (a fixed number) gives every query a running threshold: the k-th
best product among them, which no later result can undercut; a query is only sent to buckets whose largest length can reach it. Each task holds one block and lets the
queries stream past it: a vector is sent once for each slice of `query_block` queries (once in all, up to that many), a query once for each block it may find something in. In
a block, a query's local cosine threshold is threshold / (its length * the block's largest length). Above 1 the whole block is skipped for that query. Near 1 coordinate
pruning is chosen: unit vectors whose largest-focus coordinates lie outside the interval that the threshold allows cannot reach it. Otherwise length pruning: within the
block, sorted by length, only a prefix can reach the threshold. What is left is verified by exact products (integers below 2^53 in float64), and each block gives its k best
per query.

Vectors that are null, empty, of another dimension than the table's most frequent one, or hold null or non-finite components take no part, neither as queries nor as
candidates; nor do null identifiers. Zero vectors have length 0 and take part with products 0. Ties go to the smaller identifier. Repeated rows of one identifier are candidates
each, and queries each with their own ranks; a query never meets rows with its own identifier. An empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

RATIO = 1.05
FOCUS = 3
COORDINATE_FROM = 0.9


def quantised(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 64) -> DataFrame:
    """(id, _v array<long>, _len) of the vectors that take part; components are floor(scale * x)."""
    x = vectors.select(F.col(id_col).alias("_id"), F.col(vector_col).cast("array<double>").alias("_x")).where("_id is not null and size(_x) > 0")
    x = x.where(F.forall("_x", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))))
    size = x.groupBy(F.size("_x").alias("n")).count().orderBy(F.desc("count"), "n").first()
    x = x.where(F.size("_x") == (size["n"] if size else 0)).select("_id", F.transform("_x", lambda c: F.floor(c * scale)).alias("_v"))
    return x.withColumn("_len", F.sqrt(F.aggregate("_v", F.lit(0.0), lambda a, c: a + c.cast("double") * c.cast("double"))))


def _best(product: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Columns of the k best of a row: by product, ties by identifier."""
    if len(ids) > k:
        edge = np.partition(product, len(ids) - k)[len(ids) - k]
        keep = np.flatnonzero(product >= edge)
    else:
        keep = np.arange(len(ids))
    return keep[np.lexsort((ids[keep], -product[keep]))[:k]]


def _unit(queries: np.ndarray, q_ids: np.ndarray, q_len: np.ndarray, least: np.ndarray, vectors: np.ndarray, ids: np.ndarray, lengths: np.ndarray, k: int):
    """Rows (query, id, product) of one unit of work: for each query its k best in the block that reach its threshold."""
    order = np.argsort(-lengths, kind="stable")
    vectors, ids, lengths = vectors[order], ids[order], lengths[order]
    top = lengths[0]
    floor = np.where(lengths > 0, lengths, 1)
    reach = q_len * top
    with np.errstate(divide="ignore", invalid="ignore"):
        local = np.where(reach > 0, least / np.where(reach > 0, reach, 1), np.where(least <= 0, 0, np.inf))
    open_ = np.flatnonzero(local <= 1 + 1e-9)
    out_q, out_v, out_s = [], [], []
    plain = open_[local[open_] < COORDINATE_FROM]
    for at in range(0, len(plain), 256):
        rows = plain[at : at + 256]
        # Length pruning: the prefix that the least demanding query of these rows can use.
        need = np.where(q_len[rows] > 0, least[rows] / np.where(q_len[rows] > 0, q_len[rows], 1), -np.inf).min()
        to = int(np.searchsorted(-lengths, -(need - 1e-6), "right")) if np.isfinite(need) else len(lengths)
        product = queries[rows] @ vectors[:to].T
        product[q_ids[rows][:, None] == ids[None, :to]] = -np.inf
        for r, p in zip(rows, product):
            found = np.flatnonzero((p >= least[r]) & (p > -np.inf))
            best = found[_best(p[found], ids[found], k)]
            out_q.append(np.full(len(best), r))
            out_v.append(ids[best])
            out_s.append(p[best])
    sharp = open_[local[open_] >= COORDINATE_FROM]
    if len(sharp):
        unit = vectors / floor[:, None]
        for r in sharp:
            # Coordinate pruning: with cosine at least c, a coordinate of the unit vector lies within c*u +- sqrt((1-c^2)(1-u^2)), or beyond on u's side.
            u, c = queries[r] / q_len[r], min(1.0, local[r])
            focus = np.argsort(-np.abs(u))[:FOCUS]
            slack = np.sqrt(np.maximum(0, (1 - c * c) * (1 - u[focus] ** 2))) + 1e-9
            low = np.where(u[focus] <= -c, -1.0, c * u[focus] - slack) - 1e-9
            high = np.where(u[focus] >= c, 1.0, c * u[focus] + slack) + 1e-9
            some = np.flatnonzero(((unit[:, focus] >= low) & (unit[:, focus] <= high)).all(1) & (ids != q_ids[r]))
            p = vectors[some] @ queries[r]
            some, p = some[p >= least[r]], p[p >= least[r]]
            best = _best(p, ids[some], k)
            out_q.append(np.full(len(best), r))
            out_v.append(ids[some[best]])
            out_s.append(p[best])
    if not out_q:
        return np.empty(0, int), np.empty(0, int), np.empty(0)
    return np.concatenate(out_q), np.concatenate(out_v), np.concatenate(out_s)


def top_k(vectors: DataFrame, is_query, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 64, seed_size: int = 2048, block: int = 8192, query_block: int = 65_536) -> DataFrame:
    """(query_id, rank, vec_id, score) for every row for which the column `is_query` (over id_col) holds, against all other rows."""
    x = quantised(vectors, id_col, vector_col, scale)
    bucket = F.when(F.col("_len") > 0, F.floor(F.log(F.col("_len")) / float(np.log(RATIO)))).otherwise(F.lit(-1)).cast("int")
    x = x.withColumn("_bucket", bucket).withColumn("_q", is_query(F.col("_id")))
    # How many blocks each bucket and the queries need: a table with one row per bucket of lengths (logarithmic in their range).
    sizes = x.groupBy("_bucket").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("_q").cast("long")).alias("q")).collect()
    n_queries = sum(r["q"] or 0 for r in sizes)
    q_blocks = max(1, -(-n_queries // query_block))
    parts = F.create_map(*[c for r in sizes for c in (F.lit(r["_bucket"]), F.lit(max(1, -(-r["n"] // block))))]) if sizes else F.create_map(F.lit(0), F.lit(1))
    # The longest vectors, a fixed number, set the first thresholds.
    first = [(r["_id"], list(r["_v"])) for r in x.orderBy(F.desc("_len"), "_id").limit(seed_size).select("_id", "_v").collect()]
    seeds = x.sparkSession.sparkContext.broadcast((np.array([i for i, _ in first], np.int64), np.array([v for _, v in first], np.float64)))

    def thresholds(batches):
        ids, matrix = seeds.value
        for b in batches:
            v = np.array([*b["_v"]], np.float64).reshape(len(b), -1)
            least = np.full(len(b), -np.inf)
            for at in range(0, len(b), 512):
                p = v[at : at + 512] @ matrix.T
                p[b["_id"].to_numpy()[at : at + 512, None] == ids[None, :]] = -np.inf
                if p.shape[1] >= k:
                    least[at : at + 512] = np.partition(p, p.shape[1] - k, axis=1)[:, p.shape[1] - k]
            yield pd.DataFrame({"_id": b["_id"], "_v": b["_v"], "_len": b["_len"], "_least": least})

    asked = x.where("_q").select("_id", "_v", "_len").mapInPandas(thresholds, "_id long, _v array<long>, _len double, _least double")
    asked = asked.withColumn("_row", F.monotonically_increasing_id()).withColumn("_qb", F.pmod(F.xxhash64("_id"), F.lit(q_blocks)).cast("int"))
    stored = x.withColumn("_part", F.pmod(F.xxhash64(F.lit(1), "_id"), F.element_at(parts, F.col("_bucket"))).cast("int"))
    stored = stored.withColumn("_qb", F.explode(F.sequence(F.lit(0), F.lit(q_blocks - 1))))
    stored = stored.withColumns({"_row": F.lit(-1).cast("long"), "_least": F.lit(0.0)})
    # Only queries that a bucket's largest length can serve go to its blocks, of which there are n / `block`.
    buckets = F.array(*(F.lit(r["_bucket"]) for r in sizes)) if sizes else F.array(F.lit(0))
    able = (F.col("_bucket") < 0) | (F.col("_least") <= F.col("_len") * F.pow(F.lit(RATIO), F.col("_bucket") + 1) * (1 + 1e-9))
    sent = asked.withColumn("_bucket", F.explode(buckets)).where(able)
    sent = sent.withColumn("_part", F.explode(F.sequence(F.lit(0), F.element_at(parts, F.col("_bucket")) - 1)))
    cells = ["_qb", "_bucket", "_part", "_row", "_id", "_len", "_least", "_v"]
    # Within a cell the vectors of the block (row -1) come first.
    line = stored.select(*cells).unionByName(sent.select(*cells)).repartition("_qb", "_bucket", "_part").sortWithinPartitions("_qb", "_bucket", "_part", "_row")

    def run(batches):
        held, now, block_ = [], None, None
        for b in batches:
            cell = np.stack([b.column(c).to_numpy() for c in ("_qb", "_bucket", "_part")], 1)
            row, ids, lengths, least = (b.column(c).to_numpy() for c in ("_row", "_id", "_len", "_least"))
            lists = b.column("_v")
            values = lists.flatten().to_numpy().astype(np.float64).reshape(len(row), -1)
            asks = row >= 0
            cuts = np.flatnonzero((cell[1:] != cell[:-1]).any(1) | (asks[1:] != asks[:-1])) + 1
            for lo, hi in zip([0, *cuts], [*cuts, len(row)]):
                if lo == hi:
                    continue
                if now != tuple(cell[lo]):
                    held, now, block_ = [], tuple(cell[lo]), None
                if not asks[lo]:
                    held.append((values[lo:hi], ids[lo:hi], lengths[lo:hi]))
                    continue
                if not held:
                    continue
                if block_ is None:
                    block_ = [np.concatenate(c) for c in zip(*held)]
                q, v, s = _unit(values[lo:hi], ids[lo:hi], lengths[lo:hi], least[lo:hi], *block_, k)
                at = q.astype(int) + lo
                yield pa.RecordBatch.from_arrays([pa.array(row[at], pa.int64()), pa.array(ids[at], pa.int64()), pa.array(v.astype(np.int64)), pa.array(s.astype(np.int64))], names=["_row", "query_id", "vec_id", "score"])

    found = line.mapInArrow(run, "_row long, query_id long, vec_id long, score long")
    order = W.partitionBy("_row").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

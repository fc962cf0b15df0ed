"""Temperature scaling: fit on held-out logits, apply, reliability, selective answering.

scored: (row_id, network, truth_idx, logits array<double>).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Temperatures 3^(j/8): multiplying logits by three moves the optimum by exactly eight places.
GRID = tuple(3 ** (j / 8) for j in range(-22, 41))


def confidence(logits: Column, temperature) -> Column:
    """Softmax of the largest logit only: 1 / sum exp((z - z_max) / T)."""
    t = temperature if isinstance(temperature, Column) else F.lit(float(temperature))
    return 1 / F.aggregate(logits, F.lit(0.0), lambda a, z: a + F.exp((z - F.array_max(logits)) / t))


def softmax(logits: Column, temperature=1.0) -> Column:
    t = temperature if isinstance(temperature, Column) else F.lit(float(temperature))
    e = F.transform(logits, lambda z: F.exp((z - F.array_max(logits)) / t))
    return F.transform(e, lambda v: v / F.aggregate(e, F.lit(0.0), lambda a, w: a + w))


def nll(logits: Column, truth_idx: Column, temperature=1.0) -> Column:
    t = temperature if isinstance(temperature, Column) else F.lit(float(temperature))
    top = F.array_max(logits)
    return F.log(F.aggregate(logits, F.lit(0.0), lambda a, z: a + F.exp((z - top) / t))) - (F.get(logits, truth_idx) - top) / t


def apply(scored: DataFrame, temperature=1.0) -> DataFrame:
    """Adds predicted (arg-max, lowest index on ties), hit and confidence."""
    top = (F.array_position("logits", F.array_max("logits")) - 1).cast("int")
    return scored.withColumns({"predicted": top, "hit": (top == F.col("truth_idx")).cast("int"), "confidence": confidence(F.col("logits"), temperature)})


def bin_of(conf: Column, n_bins: int) -> Column:
    return F.least(F.floor(conf * n_bins), F.lit(n_bins - 1)).cast("int")


def bins(applied: DataFrame, by=(), n_bins: int = 10) -> DataFrame:
    """(by.., bin, n, accuracy, confidence): an equi-key on floor, never a range join."""
    x = applied.where("confidence is not null").withColumn("bin", bin_of(F.round("confidence", 9), n_bins))
    return x.groupBy(*by, "bin").agg(F.count(F.lit(1)).alias("n"), F.avg("hit").alias("accuracy"), F.avg("confidence").alias("confidence"))


def ece(applied: DataFrame, by=(), n_bins: int = 10) -> DataFrame:
    x = bins(applied, by, n_bins)
    return x.groupBy(*by).agg((F.sum(F.col("n") * F.abs(F.col("accuracy") - F.col("confidence"))) / F.sum("n")).alias("ece"), F.sum("n").alias("n"))


def curve(scored: DataFrame, grid=GRID, by: str = "network", n_bins: int = 10) -> DataFrame:
    """(by, temperature, ece, nll): the grid is exploded on narrow columns, so one pass and one small shuffle serve all temperatures."""
    x = scored.withColumn("temperature", F.explode(F.array(*(F.lit(float(t)) for t in grid))))
    x = x.withColumn("loss", nll(F.col("logits"), F.col("truth_idx"), F.col("temperature")))
    x = apply(x, F.col("temperature")).withColumn("bin", bin_of(F.round("confidence", 9), n_bins))
    b = x.groupBy(by, "temperature", "bin").agg(F.count(F.lit(1)).alias("n"), F.sum("hit").alias("h"), F.sum("confidence").alias("c"), F.sum("loss").alias("l"))
    return b.groupBy(by, "temperature").agg((F.sum(F.abs(F.col("h") - F.col("c"))) / F.sum("n")).alias("ece"), (F.sum("l") / F.sum("n")).alias("nll"))


def fit(scored: DataFrame, by: str = "network", grid=GRID, objective: str = "ece", rounds: int = 1, n_bins: int = 10) -> DataFrame:
    """(by, temperature, ece, nll, at_edge). Ties go to the temperature nearest 1; a best value on the grid's edge is flagged and not refined."""
    found = _pick(curve(scored, grid, by, n_bins), by, objective, grid)
    for _ in range(rounds - 1):
        best = {r[by]: r["temperature"] for r in found.collect()}  # one row per network
        finer = None
        for name, t in best.items():
            part = _pick(curve(scored.where(F.col(by) == name), [t * 3 ** (k / 80) for k in range(-9, 10)], by, n_bins), by, objective, grid)
            finer = part if finer is None else finer.unionByName(part)
        found = finer if finer is not None else found
    return found


def _pick(c: DataFrame, by: str, objective: str, grid) -> DataFrame:
    key = F.struct(F.round(objective, 9).alias("a"), F.round(F.abs(F.log("temperature")), 9).alias("b"), F.col("temperature").alias("t"))
    x = c.groupBy(by).agg(F.min_by(F.struct("temperature", "ece", "nll"), key).alias("s"))
    edge = (F.abs(F.col("s.temperature") - min(grid)) < 1e-9) | (F.abs(F.col("s.temperature") - max(grid)) < 1e-9)
    return x.select(by, "s.temperature", "s.ece", "s.nll", edge.alias("at_edge"))


def reliability(scored: DataFrame, temperature: float, n_bins: int = 10) -> DataFrame:
    """Bins before and after scaling, for a diagram; gap > 0 is over-confidence."""
    two = bins(apply(scored, 1.0).withColumn("stage", F.lit("before")), ["stage"], n_bins).unionByName(bins(apply(scored, temperature).withColumn("stage", F.lit("after")), ["stage"], n_bins))
    return two.withColumn("gap", F.col("confidence") - F.col("accuracy"))


def risk_coverage(applied: DataFrame, thresholds=tuple(i / 20 for i in range(20))) -> DataFrame:
    """(threshold, coverage, accuracy) of answering only at or above a confidence: a grid, so no global sort."""
    x = applied.withColumn("threshold", F.explode(F.array(*(F.lit(t) for t in thresholds)))).withColumn("on", F.round("confidence", 9) >= F.col("threshold"))
    return x.groupBy("threshold").agg(F.avg(F.col("on").cast("int")).alias("coverage"), F.avg(F.when(F.col("on"), F.col("hit"))).alias("accuracy"))

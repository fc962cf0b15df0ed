"""Monte-Carlo of confidence-weighted voting by an ideally calibrated network.

A pseudo-study has k series. Each draws a confidence from a Beta law with parameter sum 4 and mean alpha; a uniform draw below it is a vote for the truth (label 0), otherwise for
a wrong label: one of 11 at random, or always label 1 (maximally correlated). Votes weigh their confidence, or one unit. All draws come from the portable
stream at index ((study * k + series) * 5 + draw), so a run is reproducible and the oracle repeats it. Sums of the 12 labels stay inside the row: no shuffle before the mean.

`run` is one cell in SQL expressions. `grid` is many cells in one pass over Arrow batches: cells of equal k share their draws, and what leaves a task is a
few counts for each cell. (Sums by a drawn label inside a row have only interpreted higher-order functions in SQL.)
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.portable import MICRO, P, beta_knots, knot_lookup, stream

WRONG = 11
MODES = ("uncorrelated", "correlated")
#: Means whose Beta law of parameter sum 4 is that of an order statistic of three uniforms, and its place.
ORDER_STATISTIC = {0.25: 0, 0.5: 1, 0.75: 2}


def draws(studies: DataFrame, k: int) -> DataFrame:
    """(study) -> array d of k structs (u0..u4) in [0, P)."""
    cell = ", ".join(f"'u{j}', {stream(f'((study * {k} + s) * 5 + {j})', 17)}" for j in range(5))
    return studies.withColumn("d", F.expr(f"transform(sequence(0L, {k - 1}L), s -> named_struct({cell}))"))


def confidence_u(alpha: float) -> str:
    """Confidence in micro-units from one series' draws d: an order statistic of three uniforms where 4*alpha is an integer, else inverse-CDF knots."""
    at = ORDER_STATISTIC.get(alpha)
    if at is not None:
        return f"(sort_array(array(x.u0, x.u1, x.u2))[{at}] * {MICRO} div {P})"
    return knot_lookup("array(" + ", ".join(f"{v}L" for v in beta_knots(alpha)) + ")", "x.u0", spark=True)


def votes(studies: DataFrame, alpha: float, k: int, mode: str = "uncorrelated", weight: str = "confidence") -> DataFrame:
    """Adds v: array of k structs (label, weight_u, confidence_u)."""
    wrong = "1" if mode == "correlated" else f"cast(1 + x.u4 % {WRONG} as int)"
    c = confidence_u(alpha)
    x = draws(studies, k).withColumn("c", F.expr(f"transform(d, x -> named_struct('u3', x.u3, 'u4', x.u4, 'c', {c}))"))
    w = "x.c" if weight == "confidence" else f"{MICRO}L"
    return x.withColumn("v", F.expr(f"transform(c, x -> named_struct('label', CASE WHEN x.u3 * {MICRO} div {P} < x.c THEN 0 ELSE {wrong} END, 'weight_u', {w}, 'confidence_u', x.c))")).drop("d", "c")


def decide_inline(v: Column) -> Column:
    """Label with the one largest sum inside the row, null on ties."""
    sums = F.transform(F.sequence(F.lit(0), F.lit(WRONG)), lambda i: F.aggregate(F.filter(v, lambda x: x["label"] == i), F.lit(0).cast("long"), lambda a, x: a + x["weight_u"]))
    top = F.array_max(sums)
    return F.when(F.size(F.filter(sums, lambda s: s == top)) == 1, (F.array_position(sums, top) - 1).cast("int"))


def run(studies: DataFrame, alpha: float, k: int, mode: str = "uncorrelated", weight: str = "confidence") -> DataFrame:
    """(alpha, k, mode, n, accuracy, sd_study, sd_mean)."""
    right = F.coalesce((decide_inline(F.col("v")) == 0).cast("int"), F.lit(0))
    x = votes(studies, alpha, k, mode, weight).select(right.alias("r"))
    p = F.avg("r")
    return x.agg(F.lit(alpha).alias("alpha"), F.lit(k).alias("k"), F.lit(mode).alias("mode"), F.count(F.lit(1)).alias("n"), p.alias("accuracy"), F.sqrt(p * (1 - p)).alias("sd_study"), F.sqrt(p * (1 - p) / F.count(F.lit(1))).alias("sd_mean"))


def _drawn(study, k: int):
    """The five draws of every series, as arrays (study, series): the numbers of `draws`."""
    import numpy as np

    index = (study[:, None] * k + np.arange(k)) * 5
    out = []
    for j in range(5):
        x = ((index + j) * 48271 + 17) % P
        out.append((((x * x + 12345) % P) ** 2 + 777) % P)
    return out


def _confidence(u, alpha: float, knots):
    """As `confidence_u`, of arrays of draws; `knots` are those of a mean that is no order statistic."""
    import numpy as np

    if alpha in ORDER_STATISTIC:
        low, high = np.minimum(u[0], u[1]), np.maximum(u[0], u[1])
        part = {0: np.minimum(low, u[2]), 1: np.maximum(low, np.minimum(high, u[2])), 2: np.maximum(high, u[2])}[ORDER_STATISTIC[alpha]]
        return part * MICRO // P
    at, rest = u[0] * 100 // P, u[0] * 100 % P // 1000
    return knots[at] + (knots[at + 1] - knots[at]) * rest // (P // 1000)


def _right(u, c, correlated: bool, unit: bool):
    """Whether the truth has the one largest sum, for every study."""
    import numpy as np

    n = len(c)
    hit, w = u[3] * MICRO // P < c, np.full_like(c, MICRO) if unit else c
    wrong = np.where(hit, 0, w)
    if correlated:
        most = wrong.sum(1)
    else:
        # Sums stay far below 2^53, so doubles hold them exactly.
        most = np.bincount((np.arange(n)[:, None] * WRONG + u[4] % WRONG).ravel(), wrong.ravel(), n * WRONG).reshape(n, WRONG).max(1)
    return np.where(hit, w, 0).sum(1) > most


def grid(studies: DataFrame, alphas, ks, modes=MODES, weight: str = "confidence", batches: int = 1) -> DataFrame:
    """(alpha, k, mode, n, accuracy, sd_study, sd_mean, sd_batches) of all cells in one pass over (study).

    sd_batches is the deviation of the accuracies of `batches` equal parts (study modulo batches), null for one part. Null studies are left out; no study, no row.
    """
    alphas, ks, modes = tuple(alphas), tuple(ks), tuple(modes)
    knots = {a: beta_knots(a) for a in alphas if a not in ORDER_STATISTIC}

    def count(parts):
        import numpy as np
        import pyarrow as pa

        cells = [(a, k, m) for k in ks for a in alphas for m in modes]
        at_knots = {a: np.array(v) for a, v in knots.items()}
        seen, hits = np.zeros(batches, "int64"), np.zeros((len(cells), batches), "int64")
        for part in parts:
            study = part.column(0).to_numpy(zero_copy_only=False).astype("int64")
            of, at = study % batches, 0
            seen += np.bincount(of, minlength=batches)
            for k in ks:
                u = _drawn(study, k)
                for a in alphas:
                    c = _confidence(u, a, at_knots.get(a))
                    for m in modes:
                        hits[at] += np.bincount(of[_right(u, c, m == "correlated", weight != "confidence")], minlength=batches)
                        at += 1
        for (a, k, m), h in zip(cells, hits):
            yield pa.RecordBatch.from_pydict({"alpha": [a] * batches, "k": pa.array([k] * batches, "int32"), "mode": [m] * batches, "batch": np.arange(batches), "n": seen, "hits": h})

    parts = studies.select(F.col("study").cast("long")).where("study is not null").mapInArrow(count, "alpha double, k int, mode string, batch long, n long, hits long")
    parts = parts.where("n > 0").groupBy("alpha", "k", "mode", "batch").agg(F.sum("n").alias("n"), F.sum("hits").alias("hits"))
    x = parts.groupBy("alpha", "k", "mode").agg(F.sum("n").alias("n"), (F.sum("hits") / F.sum("n")).alias("accuracy"), F.stddev_samp(F.col("hits") / F.col("n")).alias("sd_batches"))
    spread = F.col("accuracy") * (1 - F.col("accuracy"))
    return x.select("alpha", "k", "mode", "n", "accuracy", F.sqrt(spread).alias("sd_study"), F.sqrt(spread / F.col("n")).alias("sd_mean"), "sd_batches")


def check_calibrated(studies: DataFrame, alpha: float, k: int, n_bins: int = 10) -> DataFrame:
    """(hit_rate, ece) of the simulated votes: the first is alpha, the second small."""
    from .calibrate import ece

    x = votes(studies, alpha, k).select(F.explode("v").alias("v")).select((F.col("v.label") == 0).cast("int").alias("hit"), (F.col("v.confidence_u") / MICRO).alias("confidence"))
    e = ece(x.withColumn("_g", F.lit(1)), ["_g"], n_bins).select("_g", "ece")
    return x.groupBy(F.lit(1).alias("_g")).agg(F.avg("hit").alias("hit_rate")).join(e, "_g").select("hit_rate", "ece")


def studies(spark: SparkSession, n: int, partitions: int | None = None) -> DataFrame:
    return (spark.range(0, n, 1, partitions) if partitions else spark.range(n)).withColumnRenamed("id", "study")

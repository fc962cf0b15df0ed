"""Classifiers of single series: routing by modality, votes by calibrated confidence, trained heads, study-level pooling."""

from __future__ import annotations

from pyspark.ml.classification import LogisticRegression
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.text import checked_broadcast


def route(series: DataFrame, route_ref: DataFrame) -> DataFrame:
    """Series with their modality's network; modalities without a voting network (the PET role) go neither to training nor to inference."""
    return series.join(checked_broadcast(route_ref.where("votes").select("modality", "network")), "modality")


def votes(scores: DataFrame, weight: str = "confidence") -> DataFrame:
    """(study_id, series_no, label, confidence_u) -> votes weighted by confidence, or by its log-odds (confidences held within 0.001 and 0.999)."""
    w = F.col("confidence_u").cast("long")
    if weight == "log_odds":
        c = F.greatest(F.least(F.col("confidence_u"), F.lit(999_000)), F.lit(1000)) / 1e6
        w = F.round(1_000_000 * F.log(c / (1 - c))).cast("long")
    return scores.select("study_id", "label", w.alias("weight_u"), F.lit("network").alias("origin"), "series_no")


def centroid_head(features: DataFrame, label: str = "label") -> list[list[float]]:
    """The last layer of a network with frozen features x: one row of weights per class, the mean of its training features. Classes x dimensions numbers reach the driver."""
    cells = features.select(F.col(label).alias("_y"), F.posexplode("x").alias("_at", "_v")).groupBy("_y", "_at").agg(F.avg("_v").alias("_m"))
    rows = cells.groupBy("_y").agg(F.transform(F.array_sort(F.collect_list(F.struct("_at", "_m"))), lambda s: s["_m"]).alias("w")).orderBy("_y").collect()
    return [list(r["w"]) for r in rows]


def infer(features: DataFrame, head: list[list[float]]) -> DataFrame:
    """Adds logits: the product of each class's weights with x."""
    products = [F.aggregate(F.zip_with("x", F.array(*map(F.lit, w)), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v) for w in head]
    return features.withColumn("logits", F.array(*products))


def votes_from_logits(scored: DataFrame, classes: DataFrame, temperatures: DataFrame) -> DataFrame:
    """(study_id, series_no, network, logits) -> votes: arg-max class (lowest on ties) with its tempered confidence."""
    from .calibrate import confidence

    x = scored.join(checked_broadcast(temperatures.select("network", "temperature")), "network")
    top = (F.array_position("logits", F.array_max("logits")) - 1).cast("int")
    x = x.withColumns({"class_id": top, "weight_u": F.round(confidence(F.col("logits"), F.col("temperature")) * 1_000_000).cast("long")})
    return x.join(checked_broadcast(classes.select("class_id", "label")), "class_id").select("study_id", "label", "weight_u", F.lit("network").alias("origin"), "series_no")


def select_best(cv: DataFrame) -> DataFrame:
    """(modality, network, accuracy) -> the network with the best accuracy of each modality; ties to the first by name."""
    order = W.partitionBy("modality").orderBy(F.desc("accuracy"), "network")
    return cv.withColumn("_r", F.row_number().over(order)).where("_r = 1").drop("_r")


def fit_head(features: DataFrame, label: str = "class_id", weight: str | None = None, iterations: int = 30, regularise: float = 1e-3):
    """Only the last layer is trained: multinomial logistic regression with cross-entropy over frozen features (array<double> column x)."""
    model = LogisticRegression(featuresCol="_v", labelCol="_y", maxIter=iterations, regParam=regularise, family="multinomial")
    if weight:
        model = model.setWeightCol(weight)
    return model.fit(features.withColumn("_v", array_to_vector("x")).withColumn("_y", F.col(label).cast("double")))


def predict(model, features: DataFrame) -> DataFrame:
    """Adds logits (array<double>) and class_id."""
    out = model.transform(features.withColumn("_v", array_to_vector("x")))
    return out.withColumn("logits", vector_to_array("rawPrediction")).withColumn("predicted", F.col("prediction").cast("int")).drop("_v", "rawPrediction", "probability", "prediction")


def fit_heads(features: DataFrame, by: str = "modality", **how) -> dict:
    """One head for each modality; the modality names (a handful) are the only thing that reaches the driver."""
    names = [r[0] for r in features.select(by).distinct().collect()]
    return {n: fit_head(features.where(F.col(by) == n), **how) for n in sorted(names)}


def mil_pool(series: DataFrame, pooling: str = "mean") -> DataFrame:
    """(study_id, x) of all series -> one vector per study: the bag's mean or maximum, element by element."""
    agg = F.avg if pooling == "mean" else F.max
    cells = series.select("study_id", F.posexplode("x").alias("i", "v")).groupBy("study_id", "i").agg(agg("v").alias("v"))
    return cells.groupBy("study_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda s: s["v"]).alias("x"))


def fit_mil(series: DataFrame, labels: DataFrame, pooling: str = "mean", **how):
    return fit_head(mil_pool(series, pooling).join(labels, "study_id"), **how)

"""What the methods are compared with: a rule list in place of a closed product, the most frequent class, any supplied decisions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.portable import stream
from ..functions.text import checked_broadcast

#: Description pattern -> class, in order; a code that the catalogue knows comes first.
PATTERNS = (("^(red|hot) .*widget", "red widget"), ("plate$", "plate"), ("anvil", "anvil"), ("gizmo( study)?$", "gizmo"), ("bolt", "bolt"), ("ring", "ring"))


def importer_case(kind: str) -> str:
    """CASE list over code_ref.label and description, in the dialect of the oracle."""
    whens = " ".join(f"WHEN regexp_matches(lower(description), '{p}') THEN '{label}'" for p, label in PATTERNS)
    return f"CASE WHEN code_ref.label IS NOT NULL THEN code_ref.label {whens} END"


def importer_standin(study: DataFrame, code_ref: DataFrame) -> DataFrame:
    x = study.join(checked_broadcast(code_ref), F.col("procedure_code") == F.col("code"), "left")
    label = F.when(F.col("label").isNotNull(), F.col("label"))
    for pattern, name in PATTERNS:
        label = label.when(F.lower("description").rlike(pattern), name)
    return x.select("study_id", label.alias("label")).where("label is not null")


def majority_class(study: DataFrame) -> DataFrame:
    top = study.where("first is not null").groupBy("first").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "first").limit(1).select(F.col("first").alias("label"))
    return study.select("study_id").join(F.broadcast(top), F.lit(True))


def random_guess(study: DataFrame, class_ref: DataFrame, salt: int = 71) -> DataFrame:
    """Every study gets one of the leaf classes by a portable draw on its identifier."""
    leaves = class_ref.where("parent is not null")
    names = leaves.agg(F.transform(F.array_sort(F.collect_list(F.struct("class_id", "label"))), lambda c: c["label"]).alias("_names"))  # one row
    draw = F.expr(f"cast({stream('study_id', salt)} % size(_names) as int)")
    return study.select("study_id").join(F.broadcast(names), F.lit(True)).select("study_id", F.get("_names", draw).alias("label"))


def external_decisions(decisions: DataFrame) -> DataFrame:
    """Any (study_id, label) table of a black box as predictions; its layer is 1."""
    return decisions.select("study_id", "label", F.lit(1).alias("layer")).where("label is not null")

"""Corpora from documents, pages and conversations: studies with series, tags and truth."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.portable import permille, stream

LANGS = ("de", "en", "es", "fr")
FAMILY = {"de": "germanic", "en": "germanic", "es": "romance", "fr": "romance"}
#: Keywords of the languages: endings that the mined catalogue also finds, and the codes themselves.
KEYWORDS = (("ción", "es"), ("mente", "es"), ("lich", "de"), ("ung", "de"), ("eau", "fr"), ("eux", "fr"), ("tion", "en"), ("ing", "en"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def document_series(spark, sf_dir) -> DataFrame:
    """(doc_id, line_no, line, source): the lines of a document are its series; a very long document never travels as one value."""
    lines = F.posexplode(F.split("text", "\n"))
    return table(spark, sf_dir, "documents").select("doc_id", "source", lines.alias("line_no", "line"))


def page_studies(spark, sf_dir) -> DataFrame:
    """(study_id, procedure_code, description, truth): the path's language, 15.3 % of them corrupted, the title, the page's language."""
    lang = F.regexp_extract("url", "//[^/]+/([a-z]{2})/", 1)
    at = F.array_position(F.array(*map(F.lit, LANGS)), lang) - 1
    other = F.element_at(F.array(*map(F.lit, LANGS)), ((at + 1 + F.expr(f"{stream('page_id', 5)} % 3")) % 4 + 1).cast("int"))
    code = F.when(F.expr(f"{permille('page_id', 4)} < 153"), other).otherwise(lang)
    truth = F.regexp_extract("html", '<html lang="([a-z]+)"', 1)
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("study_id"), code.alias("procedure_code"), F.regexp_extract("html", "(?s)<title>(.*?)</title>", 1).alias("description"), F.array(truth).alias("truth"))


def page_series(spark, sf_dir) -> DataFrame:
    """(study_id, series_no, block): text behind each opening <p, which may be unclosed."""
    blocks = F.expr("slice(split(html, '<p[ >]'), 2, 1000000)")
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("study_id"), F.posexplode(blocks).alias("series_no", "block"))

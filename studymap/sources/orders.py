"""The orders corpus: orders as studies, their lines as series, with planted codes, descriptions and network votes.

Truth is the part name of the dearest line, and of lines within five per cent of it. Evidence is planted by the portable streams, so the SQL oracle
(ctes below) rebuilds every row. PROMO parts play the modality without a network.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.portable import MICRO, P, beta_knots, knot_lookup, permille, stream

#: Planted per-series accuracy of each modality's network.
ACCURACY = {"STANDARD": 0.971, "MEDIUM": 0.877, "LARGE": 0.854, "SMALL": 0.814, "ECONOMY": 0.835}
SILENT = "PROMO"
KNOTS = {m: beta_knots(a) for m, a in ACCURACY.items()}
TAG_KEYS = ("brand", "flag", "name", "pack")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def class_ref(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(class_id, label, parent): every adjective with every noun of the part names, and the nouns as general classes."""
    words = table(spark, sf_dir, "part").select(F.split("p_name", " ").alias("w"))
    sets = words.agg(F.array_sort(F.collect_set(F.col("w")[0])).alias("adj"), F.array_sort(F.collect_set(F.col("w")[1])).alias("noun"))
    leaf = sets.select(F.posexplode("adj").alias("ai", "a"), "noun").select("ai", "a", F.posexplode("noun").alias("ni", "n"))
    leaves = leaf.select((F.col("ai") * 8 + F.col("ni")).alias("class_id"), F.concat_ws(" ", "a", "n").alias("label"), F.col("n").alias("parent"))
    nouns = sets.select(F.posexplode("noun").alias("ni", "n")).select((F.col("ni") + 64).alias("class_id"), F.col("n").alias("label"), F.lit(None).cast("string").alias("parent"))
    return leaves.unionByName(nouns)


def _classes(spark, sf_dir, classes: DataFrame | None) -> DataFrame:
    return class_ref(spark, sf_dir) if classes is None else classes


def code_ref(spark, sf_dir, classes: DataFrame | None = None) -> DataFrame:
    return _classes(spark, sf_dir, classes).where("parent is not null").select(F.concat(F.lit("C"), F.lpad(F.col("class_id").cast("string"), 3, "0")).alias("code"), "label")


def desc_ref(spark, sf_dir, classes: DataFrame | None = None) -> DataFrame:
    return _classes(spark, sf_dir, classes).where("parent is not null").select(F.col("label").alias("description"), "label")


def keyword_ref(spark, sf_dir, classes: DataFrame | None = None) -> DataFrame:
    """Keywords of fewer than four characters are refused by the catalogue."""
    return _classes(spark, sf_dir, classes).where(F.length("label") >= 4).select(F.col("label").alias("keyword"), "label")


def minor_pair(spark, sf_dir) -> DataFrame:
    """(truth, pred): right but too general."""
    return class_ref(spark, sf_dir).where("parent is not null").select(F.col("label").alias("truth"), F.col("parent").alias("pred"))


def lines(spark, sf_dir) -> DataFrame:
    item = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "part"), F.col("l_partkey") == F.col("p_partkey"))
    order = W.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    return item.select(
        F.col("l_orderkey").alias("study_id"), F.row_number().over(order).alias("series_no"), F.col("p_type").alias("modality"), F.col("p_name").alias("name"),
        F.col("p_brand").alias("brand"), F.col("p_size").alias("nz"), F.col("l_extendedprice").alias("price"), F.concat("l_returnflag", "l_linestatus").alias("flag"),
    )


def _items(spark, sf_dir, items: DataFrame | None) -> DataFrame:
    """Lines that the caller holds already, or lines anew."""
    return lines(spark, sf_dir) if items is None else items


def series(spark, sf_dir, items: DataFrame | None = None) -> DataFrame:
    """(study_id, series_no, modality, descriptor, nz, tags). Tags are a map: a series carries what its maker filled in."""
    tags = F.create_map(F.lit("name"), "name", F.lit("brand"), "brand", F.lit("pack"), "modality", F.lit("flag"), "flag")
    return _items(spark, sf_dir, items).select("study_id", "series_no", "modality", F.col("modality").alias("descriptor"), "nz", tags.alias("tags"))


def truth(spark, sf_dir, items: DataFrame | None = None) -> DataFrame:
    """(study_id, truth, first)."""
    top = _items(spark, sf_dir, items).withColumn("top", F.max("price").over(W.partitionBy("study_id"))).where("price >= 0.95 * top")
    return top.groupBy("study_id").agg(F.array_sort(F.collect_set("name")).alias("truth"), F.min(F.when(F.col("price") == F.col("top"), F.col("name"))).alias("first"))


def _planted(first_id: str, known: str, key: str) -> tuple[str, str]:
    """Expressions of the planted code class and of the description, over columns class_id, first, noun, pack, priority."""
    wrong = f"(({first_id} + 1 + {stream(key, 14)} % 63) % 64)"
    code = f"CASE WHEN {known} AND {permille(key, 11)} < 350 THEN CASE WHEN {permille(key, 13)} < 100 THEN concat('X', {stream(key, 15)} % 900) WHEN {permille(key, 12)} < 153 THEN concat('C', lpad(cast({wrong} as varchar(9)), 3, '0')) ELSE concat('C', lpad(cast({first_id} as varchar(9)), 3, '0')) END END"
    style = permille(key, 21)
    desc = f"CASE WHEN NOT {known} OR {style} >= 900 THEN NULL WHEN {style} < 200 THEN first WHEN {style} < 450 THEN concat(pack, '  ', first, ' study') WHEN {style} < 600 THEN substr(first, 2) WHEN {style} < 750 THEN noun ELSE priority END"
    return code, desc


def study(spark, sf_dir, items: DataFrame | None = None) -> DataFrame:
    """(study_id, procedure_code, description, arrived, truth, first): one row per order; orders without lines have no truth and no code."""
    orders = table(spark, sf_dir, "orders")
    packs = _items(spark, sf_dir, items).where("series_no = 1").select("study_id", F.col("modality").alias("pack"))
    x = orders.select(F.col("o_orderkey").alias("study_id"), F.col("o_orderdate").alias("arrived"), F.col("o_orderpriority").alias("priority"))
    x = x.join(truth(spark, sf_dir, items), "study_id", "left").join(packs, "study_id", "left")
    x = x.join(F.broadcast(class_ref(spark, sf_dir).select(F.col("label").alias("first"), "class_id")), "first", "left")
    x = x.withColumn("noun", F.split("first", " ")[1])
    code, desc = _planted("class_id", "(first IS NOT NULL)", "study_id")
    return x.select("study_id", F.expr(code).alias("procedure_code"), F.expr(desc).alias("description"), "arrived", "truth", "first")


def _net_class(key: str, spark: bool) -> str:
    d, w = ("div" if spark else "//"), stream(key, 43)
    other = f"((({w}) {d} 2) % 7)"
    same_noun = f"((((class_id {d} 8) + 1 + {other}) % 8) * 8 + class_id % 8)"
    any_noun = f"(((({w}) {d} 14) % 8) * 8 + (class_id % 8 + 1 + {other}) % 8)"
    return f"CASE WHEN hit = 1 THEN class_id WHEN ({w}) % 2 = 0 THEN {same_noun} ELSE {any_noun} END"


def network_scores(spark, sf_dir, items: DataFrame | None = None, truths: DataFrame | None = None) -> DataFrame:
    """(study_id, series_no, modality, label, confidence_u, hit): what each routed modality's planted network says of a series."""
    ids = class_ref(spark, sf_dir)
    x = _items(spark, sf_dir, items).select("study_id", "series_no", "modality").where(F.col("modality") != SILENT)
    x = x.join((truth(spark, sf_dir, items) if truths is None else truths).select("study_id", "first").where("first is not null"), "study_id")
    x = x.join(F.broadcast(ids.select(F.col("label").alias("first"), "class_id")), "first")
    knots = F.expr("map(" + ", ".join(f"'{m}', array({', '.join(f'{v}L' for v in k)})" for m, k in KNOTS.items()) + ")")
    key = "(study_id * 64 + series_no)"
    x = x.withColumn("knots", knots[F.col("modality")]).withColumn("confidence_u", F.expr(knot_lookup("knots", stream(key, 41), spark=True))).drop("knots")
    x = x.withColumn("hit", F.expr(f"CASE WHEN {stream(key, 42)} * {MICRO} div {P} < confidence_u THEN 1 ELSE 0 END"))
    x = x.withColumn("said", F.expr(_net_class(key, True)).cast("int"))
    return x.join(F.broadcast(ids.select(F.col("class_id").alias("said"), "label")), "said").select("study_id", "series_no", "modality", "label", "confidence_u", "hit")


_CODE, _DESC = _planted("class_id", "(first IS NOT NULL)", "study_id")
_KEY = "(study_id * 64 + series_no)"
_KNOT_CASE = "CASE modality " + " ".join(f"WHEN '{m}' THEN {k}::BIGINT[]" for m, k in KNOTS.items()) + " END"

#: The same tables for the oracle, by name and in the order in which they build on each other.
CTES = {
    "adj": "SELECT a, row_number() OVER (ORDER BY a) - 1 AS ai FROM (SELECT DISTINCT split_part(p_name, ' ', 1) AS a FROM part)",
    "noun": "SELECT n, row_number() OVER (ORDER BY n) - 1 AS ni FROM (SELECT DISTINCT split_part(p_name, ' ', 2) AS n FROM part)",
    "class_ref": "SELECT ai * 8 + ni AS class_id, a || ' ' || n AS label, n AS parent FROM adj, noun UNION ALL SELECT 64 + ni, n, NULL FROM noun",
    "code_ref": "SELECT 'C' || lpad(class_id::VARCHAR, 3, '0') AS code, label FROM class_ref WHERE parent IS NOT NULL",
    "keyword_ref": "SELECT label AS keyword, label FROM class_ref WHERE length(label) >= 4",
    "minor_pair": "SELECT label AS truth, parent AS pred FROM class_ref WHERE parent IS NOT NULL",
    "lines": "SELECT l_orderkey AS study_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate) AS series_no, p_type AS modality, p_name AS name, p_brand AS brand, p_size AS nz, l_extendedprice AS price, l_returnflag || l_linestatus AS flag FROM lineitem JOIN part ON l_partkey = p_partkey",
    "truth_t": "SELECT study_id, list_sort(list(DISTINCT name)) AS truth, min(name) FILTER (price = top) AS first FROM (SELECT *, max(price) OVER (PARTITION BY study_id) AS top FROM lines) WHERE price >= 0.95 * top GROUP BY study_id",
    "study": f"SELECT study_id, {_CODE} AS procedure_code, {_DESC} AS description, arrived, truth, first FROM (SELECT o_orderkey AS study_id, o_orderdate AS arrived, o_orderpriority AS priority, t.truth, t.first, split_part(t.first, ' ', 2) AS noun, l.modality AS pack, class_id FROM orders LEFT JOIN truth_t t ON t.study_id = o_orderkey LEFT JOIN lines l ON l.study_id = o_orderkey AND l.series_no = 1 LEFT JOIN class_ref c ON c.label = t.first)",
    "net": f"SELECT study_id, series_no, modality, c.label, confidence_u, hit FROM (SELECT *, {_net_class(_KEY, False)} AS said FROM (SELECT *, CASE WHEN {stream(_KEY, 42)} * {MICRO} // {P} < confidence_u THEN 1 ELSE 0 END AS hit FROM (SELECT *, {knot_lookup('knots', stream(_KEY, 41))} AS confidence_u FROM (SELECT l.study_id, series_no, modality, class_id, {_KNOT_CASE} AS knots FROM lines l JOIN truth_t t USING (study_id) JOIN class_ref r ON r.label = t.first WHERE modality <> '{SILENT}')))) x JOIN class_ref c ON c.class_id = x.said",
}

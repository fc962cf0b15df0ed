"""Queries on the text corpora, sources and sinks, streams and user functions."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from ..functions.lineage import cut, fresh_path
from ..functions.portable import permille, stream
from ..operators import layers, votes
from ..sources import orders, texts
from ..streaming import windows
from . import query, table
from .generic_q import _items, both, r6
from .orders_q import sql as orders_sql

_KW = "(VALUES " + ", ".join(f"('{k}', '{v}')" for k, v in texts.KEYWORDS) + ") k(keyword, label)"


def _keywords(spark):
    return spark.createDataFrame(list(texts.KEYWORDS), "keyword string, label string")


def _counts(df, key, text):
    """Votes: how often each keyword stands in a text, per label; one pass, no join, as the keyword list is a short literal."""
    out = None
    for label in texts.LANGS:
        n = sum((F.regexp_count(F.col(text), F.lit(k)) for k, v in texts.KEYWORDS if v == label), F.lit(0))
        part = F.struct(F.lit(label).alias("label"), n.cast("long").alias("weight_u"))
        out = [part] if out is None else [*out, part]
    x = df.select(key, F.explode(F.array(*out)).alias("v")).select(F.col(key).alias("study_id"), "v.label", "v.weight_u")
    return x.where("weight_u > 0").withColumns({"origin": F.lit("text"), "series_no": F.lit(0)})


def _count_sql(source, key, text):
    return f"SELECT {key} AS study_id, label, sum(len(string_split({text}, keyword)) - 1)::BIGINT AS w FROM {source}, {_KW} GROUP BY ALL HAVING sum(len(string_split({text}, keyword)) - 1) > 0"


_WINNER = "SELECT study_id, min(label) AS label, min(w) AS weight_u FROM (SELECT *, max(w) OVER (PARTITION BY study_id) AS top FROM ({})) WHERE w = top GROUP BY study_id HAVING count(*) = 1"
query("w2_language_votes", _WINNER.format(_count_sql("documents", "doc_id", "text")))(lambda spark, sf_dir: votes.decide(_counts(table(spark, sf_dir, "documents"), "doc_id", "text")).select("study_id", "label", "weight_u"))
query("w4_conversation_votes", _WINNER.format(_count_sql("(SELECT * FROM conversations WHERE role <> 'system')", "conv_id", "text")))(
    lambda spark, sf_dir: votes.decide(_counts(table(spark, sf_dir, "conversations").where("role <> 'system'"), "conv_id", "text")).select("study_id", "label", "weight_u")
)
_L = "list_position(['de', 'en', 'es', 'fr'], lang) - 1"
_PAGE = f"SELECT page_id AS study_id, CASE WHEN {permille('page_id', 4)} < 153 THEN (['de', 'en', 'es', 'fr'])[({_L} + 1 + {stream('page_id', 5)} % 3) % 4 + 1] ELSE lang END AS procedure_code, regexp_extract(html, '(?s)<title>(.*?)</title>', 1) AS description, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS truth, html FROM (SELECT *, regexp_extract(url, '//[^/]+/([a-z]{{2}})/', 1) AS lang FROM pages)".replace("{{2}}", "{2}")
query("w3_page_studies", f"SELECT study_id, procedure_code, description, truth FROM ({_PAGE})")(lambda spark, sf_dir: texts.page_studies(spark, sf_dir).select("study_id", "procedure_code", "description", F.col("truth")[0].alias("truth")))


@query("w3_page_layers", f"WITH p AS ({_PAGE}), l4 AS ({_WINNER.format(_count_sql('pages', 'page_id', 'html'))}) SELECT CASE WHEN procedure_code <> '' THEN 1 WHEN l4.label IS NOT NULL THEN 4 ELSE 0 END AS layer, count(*) AS n, count_if(coalesce(nullif(procedure_code, ''), l4.label) = truth) AS right_ FROM p LEFT JOIN l4 USING (study_id) GROUP BY 1")
def w3_page_layers(spark, sf_dir):
    """How many pages the code decides, how many the votes over the whole page, and how many of each are right."""
    study = texts.page_studies(spark, sf_dir)
    l1 = layers.match_code(study, spark.createDataFrame([(x, x) for x in texts.LANGS], "code string, label string")).select("study_id", F.col("label").alias("a"))
    l4 = votes.decide(_counts(table(spark, sf_dir, "pages"), "page_id", "html")).select("study_id", F.col("label").alias("b"))
    x = study.select("study_id", F.col("truth")[0].alias("truth")).join(l1, "study_id", "left").join(l4, "study_id", "left")
    layer = F.when(F.col("a").isNotNull(), 1).when(F.col("b").isNotNull(), 4).otherwise(0)
    return x.groupBy(layer.alias("layer")).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.coalesce("a", "b") == F.col("truth")).alias("right_"))


#: Words of a passage that a document must hold in a row before the passage itself is looked for.
_ANCHOR = 4


def leaks(docs, passages):
    """Ids of documents that contain a passage, whatever the number of passages.

    The words of a passage but its first and last are whole words, between single spaces, of any text that contains it. The hash of the first few of them is
    joined with the hashes of a document's word grams, and found pairs are confirmed on the texts. Passages too short for that are compared with every document.
    """
    gram = lambda words, i: F.xxhash64(F.array_join(F.slice(words, i, _ANCHOR), " "))
    parts = F.split("passage", " ")
    passages = passages.where("passage is not null").distinct().withColumn("_n", F.size(parts))
    long = passages.where(F.col("_n") >= _ANCHOR + 2).select("passage", gram(parts, F.lit(2)).alias("_g"))
    short = passages.where(F.col("_n") < _ANCHOR + 2).select("passage")
    docs = docs.select("doc_id", "text").where("text is not null")
    # The one-element array splits a text once, not once for each gram.
    every = F.transform(F.array(F.split("text", " ")), lambda w: F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - _ANCHOR + 1, F.lit(1))), lambda i: gram(w, i)))
    grams = docs.select("doc_id", F.explode(F.array_distinct(F.flatten(every))).alias("_g"))
    pairs = grams.join(long, "_g").select(F.col("doc_id").alias("_id"), "passage").distinct()
    holds = F.col("text").contains(F.col("passage"))
    found = docs.join(pairs, F.col("doc_id").eqNullSafe(F.col("_id")) & holds).select("doc_id")
    return found.unionByName(docs.join(short, holds).select("doc_id")).distinct()


both("w11_leakage", "SELECT DISTINCT doc_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")(lambda t: leaks(t("documents"), t("benchmark").select(F.col("text").alias("passage"))))


# Events: arrival window and sessions.
_W8 = "SELECT * FROM events WHERE ts >= TIMESTAMP '2024-01-04' AND ts < TIMESTAMP '2024-01-09'"
_SESS = "SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS new FROM ({}))"


def _window(spark, sf_dir):
    return table(spark, sf_dir, "events").where("ts >= '2024-01-04' AND ts < '2024-01-09'").withColumn("ts", F.col("ts").cast("timestamp"))


both("w8_arrival_window", f"SELECT event_id, user_id, event_type FROM ({_W8})")(lambda t: t("events").where("ts >= '2024-01-04' AND ts < '2024-01-09'").select("event_id", "user_id", "event_type"))
query("w8_sessions", f"SELECT user_id, min(ts) AS start, count(*) AS n FROM ({_SESS.format(_W8)}) GROUP BY user_id, sid")(
    lambda spark, sf_dir: windows.sessions(_window(spark, sf_dir)).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")
)
query("t_session", f"SELECT user_id, min(ts) AS start, count(*) AS n FROM ({_SESS.format('SELECT * FROM events')}) GROUP BY user_id, sid")(
    lambda spark, sf_dir: windows.drain(windows.sessions(windows.events_stream(spark, sf_dir)), "complete").select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")
)
query("t_tumbling", "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")(
    lambda spark, sf_dir: windows.drain(windows.tumbling(windows.events_stream(spark, sf_dir)), "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")
)
query("t_sliding", "SELECT start, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS start FROM events) GROUP BY start")(
    lambda spark, sf_dir: windows.drain(windows.sliding(windows.events_stream(spark, sf_dir)), "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")
)
query("t_modes", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")(lambda spark, sf_dir: windows.drain(windows.events_stream(spark, sf_dir).groupBy("event_type").agg(F.count(F.lit(1)).alias("n")), "complete"))
query("t_dedup", "SELECT DISTINCT event_id FROM events")(lambda spark, sf_dir: windows.drain(windows.events_stream(spark, sf_dir).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"]).select("event_id")))
query("t_watermark_late", "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2 HAVING date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events)")(
    lambda spark, sf_dir: windows.drain(windows.tumbling(windows.events_stream(spark, sf_dir).withWatermark("ts", "10 minutes"), "1 day").select("window.start", "event_type", "n")).withColumn("start", F.col("start").cast("timestamp_ntz"))
)
query("t_stream_static_join", "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")(
    lambda spark, sf_dir: windows.drain(windows.events_stream(spark, sf_dir).join(table(spark, sf_dir, "customer"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_name"))
)


@query("t_stream_stream_join", "SELECT a.event_id AS header, b.event_id AS part FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'click' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR")
def t_stream_stream_join(spark, sf_dir):
    a = windows.events_stream(spark, sf_dir).where("event_type = 'error'").select(F.col("event_id").alias("header"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", "2 hours")
    b = windows.events_stream(spark, sf_dir).where("event_type = 'click'").select(F.col("event_id").alias("part"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", "2 hours")
    return windows.drain(a.join(b, F.expr("ua = ub AND tb BETWEEN ta AND ta + INTERVAL 1 HOUR")).select("header", "part"))


_VOTED = f"""
WITH s AS ({_SESS.format("SELECT * FROM events")}),
study AS (SELECT user_id, sid, min(ts) AS start, max(ts) AS last, count(*) AS n FROM s GROUP BY 1, 2),
kinds AS (SELECT user_id, sid, event_type, count(*) AS k FROM s GROUP BY 1, 2, 3),
topped AS (SELECT *, max(k) OVER (PARTITION BY user_id, sid) AS top FROM kinds),
decided AS (SELECT user_id, sid, CASE WHEN count(*) = 1 THEN min(event_type) END AS label FROM topped WHERE k = top GROUP BY 1, 2),
newest AS (SELECT user_id, max(sid) AS newest FROM study GROUP BY 1)
SELECT user_id, start, n, label FROM study JOIN decided USING (user_id, sid) JOIN newest USING (user_id)
WHERE sid < newest OR epoch_ms(last) + 12 * 3600000 < (SELECT epoch_ms(max(ts)) - 3600000 FROM events)"""
query("t_stateful_votes", _VOTED)(
    lambda spark, sf_dir: windows.drain(windows.open_studies(windows.events_stream(spark, sf_dir).withWatermark("ts", "1 hour"), 12 * 3600 * 1000)).withColumn("start", F.col("start").cast("timestamp_ntz"))
)
query("t_foreach_batch", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")(
    lambda spark, sf_dir: windows.for_each_batch(windows.events_stream(spark, sf_dir), lambda df: df.groupBy("event_type").agg(F.count(F.lit(1)).alias("n")), fresh_path(spark, "batches")).groupBy("event_type").agg(F.sum("n").alias("n"))
)
query("t_drift", "SELECT date_trunc('day', ts) AS day, count(*) AS n, round(avg((event_type = 'error')::INT), 6) AS error_rate FROM events GROUP BY 1")(
    lambda spark, sf_dir: windows.drain(windows.events_stream(spark, sf_dir).groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"), r6(F.avg((F.col("event_type") == "error").cast("int"))).alias("error_rate")), "complete").select(F.col("window.start").cast("timestamp_ntz").alias("day"), "n", "error_rate")
)


# Sources and sinks.
both("s_parquet_scan", "SELECT p_partkey, p_size FROM part WHERE p_size >= 40")(lambda t: t("part").where("p_size >= 40").select("p_partkey", "p_size"))


@query("s_csv_roundtrip", orders_sql("SELECT keyword, label FROM keyword_ref"))
def s_csv_roundtrip(spark, sf_dir):
    path = fresh_path(spark, "catalogue")
    orders.keyword_ref(spark, sf_dir).coalesce(1).write.csv(path, header=True)
    return spark.read.schema("keyword string, label string").csv(path, header=True)


_RULE = "p_partkey AS rule_id, CASE WHEN p_size < 25 THEN 'core' ELSE 'extended' END AS tier, CASE WHEN p_type = 'PROMO' THEN 'drop' ELSE 'relabel' END AS action, p_type AS when_modality, p_name AS when_label"


@query("s_json_config", f"SELECT {_RULE} FROM part")
def s_json_config(spark, sf_dir):
    """One rule for each part. Configuration files hold a JSON list of up to a hundred keys' rules on each line; they are written, read back and parsed."""
    path = fresh_path(spark, "config")
    rules = table(spark, sf_dir, "part").select(F.floor(F.col("p_partkey") / 100).alias("list"), F.struct(*(F.expr(c) for c in _items(_RULE))).alias("rule"))
    rules.groupBy("list").agg(F.to_json(F.collect_list("rule")).alias("value")).select("value").write.text(path)
    config = "array<struct<rule_id:bigint,tier:string,action:string,when_modality:string,when_label:string>>"
    return spark.read.text(path).select(F.inline(F.from_json("value", config)))


@query("s_partitioned_sink", "SELECT event_id, event_type FROM events")
def s_partitioned_sink(spark, sf_dir):
    path = fresh_path(spark, "by-type")
    x = table(spark, sf_dir, "events").select("event_id", "event_type")
    x.write.partitionBy("event_type").parquet(path)
    x.where("event_type = 'error'").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("event_type").parquet(path)
    return spark.read.parquet(path).select("event_id", F.col("event_type").cast("string").alias("event_type"))


@query("s_orc", "SELECT n_nationkey, n_name FROM nation")
def s_orc(spark, sf_dir):
    path = fresh_path(spark, "orc")
    table(spark, sf_dir, "nation").select("n_nationkey", "n_name").write.orc(path)
    return spark.read.orc(path)


@query("s_text")
def s_text(spark, sf_dir):
    path = fresh_path(spark, "text")
    table(spark, sf_dir, "nation").select(F.col("n_name").alias("value")).write.text(path)
    return spark.read.text(path)


@query("s_tempview_sql", "SELECT n_regionkey, count(*) AS n FROM nation GROUP BY 1")
def s_tempview_sql(spark, sf_dir):
    return spark.sql("SELECT n_regionkey, count(*) AS n FROM {nation} GROUP BY n_regionkey", nation=table(spark, sf_dir, "nation"))


@query("s_bucketed")
def s_bucketed(spark, sf_dir):
    """Two tables bucketed alike join without an exchange."""
    names = [f"bucket_{n}_{uuid.uuid4().hex[:12]}" for n in ("study", "series")]
    table(spark, sf_dir, "orders").select("o_orderkey").write.bucketBy(8, "o_orderkey").sortBy("o_orderkey").saveAsTable(names[0])
    table(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity").write.bucketBy(8, "l_orderkey").sortBy("l_orderkey").saveAsTable(names[1])
    out = cut(spark.table(names[0]).join(spark.table(names[1]), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.sum("l_quantity").alias("q")))
    for n in names:
        spark.sql(f"DROP TABLE {n}")
    return out


@query("s_binary_files")
def s_binary_files(spark, sf_dir):
    return spark.read.format("binaryFile").option("pathGlobFilter", "*.parquet").load(f"{sf_dir}/nation.parquet").select(F.col("length"), F.md5("content").alias("digest"))


# User functions.
@query("u_pandas_softmax", "SELECT vec_id, round(list_max(e) - ln(list_sum(list_transform(e, lambda x: exp(x)))), 6) AS v FROM (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings)")
def u_pandas_softmax(spark, sf_dir):
    """Inference as an Arrow batch function: the log confidence of the top class."""
    @pandas_udf("double")
    def top(x: pd.Series) -> pd.Series:
        import numpy as np

        a = np.array([*x], float)
        return pd.Series(a.max(1) - np.log(np.exp(a).sum(1)))

    return table(spark, sf_dir, "embeddings").select("vec_id", r6(top(F.col("embedding").cast("array<double>"))).alias("v"))


@query("u_apply_in_pandas", "SELECT p_type, count(*) AS n, round(avg(p_size), 6) AS mean FROM part GROUP BY 1")
def u_apply_in_pandas(spark, sf_dir):
    def per(pdf):
        return pd.DataFrame({"p_type": [pdf["p_type"].iloc[0]], "n": [len(pdf)], "mean": [round(float(pdf["p_size"].mean()), 6)]})

    return table(spark, sf_dir, "part").select("p_type", "p_size").groupBy("p_type").applyInPandas(per, "p_type string, n long, mean double")


@query("u_qgrams", "SELECT n_name, substr(n_name, i, 3) AS gram FROM nation, unnest(range(1, length(n_name) - 1)) AS u(i)")
def u_qgrams(spark, sf_dir):
    @udtf(returnType="gram: string")
    class Grams:
        def eval(self, text: str, q: int):
            for i in range(len(text) - q + 1):
                yield (text[i : i + q],)

    spark.udtf.register("studymap_qgrams", Grams)
    return spark.sql("SELECT n_name, gram FROM {nation}, LATERAL studymap_qgrams(n_name, 3)", nation=table(spark, sf_dir, "nation"))


@query("u_sql_function", "SELECT n_nationkey, n_nationkey * n_nationkey AS v FROM nation")
def u_sql_function(spark, sf_dir):
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION studymap_square(x BIGINT) RETURNS BIGINT RETURN x * x")
    return spark.sql("SELECT n_nationkey, studymap_square(n_nationkey) AS v FROM {nation}", nation=table(spark, sf_dir, "nation"))

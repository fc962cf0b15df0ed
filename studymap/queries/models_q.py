"""Queries on calibration, simulation, images, sampling and trained heads."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from ..functions import images
from ..functions.lineage import cut
from ..functions.portable import MICRO, P, beta_knots, knot_lookup, permille, stream
from ..functions.text import checked_broadcast
from ..operators import calibrate, evaluate, keywords, network, sampling, simulate, word_heads, word_odds
from ..sources import texts
from ..sources.embeddings import scored
from . import query, table

_EMB = "emb AS (SELECT vec_id, label, pos, v::DOUBLE AS v FROM (SELECT vec_id, label, unnest(embedding) AS v, generate_subscripts(embedding, 1) AS pos FROM embeddings)), cent AS (SELECT label AS c, pos, avg(v) AS m FROM emb WHERE vec_id % 10 < 8 GROUP BY 1, 2)"
_SC = f"WITH {_EMB}, lg AS (SELECT e.vec_id, e.label, c, sum(v * m) AS z FROM emb e JOIN cent USING (pos) WHERE e.vec_id % 10 >= 8 GROUP BY 1, 2, 3), scored AS (SELECT vec_id AS row_id, 'x' || s AS network, label AS truth_idx, list(round(s * z, 9) ORDER BY c) AS logits FROM lg, unnest([20, 60]) AS u(s) GROUP BY vec_id, s, label)"


def _conf(t="1.0", z="logits"):
    return f"(1 / list_sum(list_transform({z}, lambda y: exp((y - list_max({z})) / {t}))))"


def _loss(t="1.0"):
    return f"(ln(list_sum(list_transform(logits, lambda y: exp((y - list_max(logits)) / {t})))) - (logits[truth_idx + 1] - list_max(logits)) / {t})"


_HIT = "(list_position(logits, list_max(logits)) - 1 = truth_idx)::INT"
_BIN = "least(floor(round({}, 9) * 10), 9)::INT"


def of_scored(name, select):
    def keep(f):
        query(name, _SC + select)(lambda spark, sf_dir: f(scored(spark, sf_dir)))

    return keep


r6 = lambda c: F.round(c, 6)
of_scored("m_temp_apply", f" SELECT row_id, network, list_position(logits, list_max(logits)) - 1 AS predicted, {_HIT} AS hit, round({_conf('2.0')}, 6) AS confidence FROM scored")(
    lambda s: calibrate.apply(s, 2.0).select("row_id", "network", "predicted", "hit", r6("confidence").alias("confidence"))
)
_APPLIED = f", ap AS (SELECT *, {_HIT} AS hit, {_conf()} AS confidence FROM scored), bins AS (SELECT network, {_BIN.format('confidence')} AS bin, count(*) AS n, avg(hit) AS accuracy, avg(confidence) AS confidence FROM ap GROUP BY 1, 2)"
of_scored("m_ece_bins", _APPLIED + " SELECT network, bin, n, round(accuracy, 6) AS accuracy, round(confidence, 6) AS confidence FROM bins")(
    lambda s: calibrate.bins(calibrate.apply(s), ["network"]).select("network", "bin", "n", r6("accuracy").alias("accuracy"), r6("confidence").alias("confidence"))
)
of_scored("m_ece", _APPLIED + " SELECT network, round(sum(n * abs(accuracy - confidence)) / sum(n), 6) AS ece FROM bins GROUP BY network")(lambda s: calibrate.ece(calibrate.apply(s), ["network"]).select("network", r6("ece").alias("ece")))
of_scored("b_uncalibrated", _APPLIED + " SELECT network, round(avg(hit), 6) AS accuracy, round(avg(confidence), 6) AS confidence FROM ap GROUP BY network")(
    lambda s: calibrate.apply(s, 1.0).groupBy("network").agg(r6(F.avg("hit")).alias("accuracy"), r6(F.avg("confidence")).alias("confidence"))
)
of_scored("m_overconfidence", _APPLIED + " SELECT network, bin, round(confidence - accuracy, 6) AS gap FROM bins")(
    lambda s: calibrate.bins(calibrate.apply(s), ["network"]).select("network", "bin", r6(F.col("confidence") - F.col("accuracy")).alias("gap"))
)
_GRID = "[" + ", ".join(repr(t) for t in calibrate.GRID) + "]::DOUBLE[]"
_CURVE = f", g AS (SELECT *, {_HIT} AS hit, {_conf('t')} AS c, {_loss('t')} AS loss FROM scored, unnest({_GRID}) AS u(t)), gb AS (SELECT network, t, {_BIN.format('c')} AS bin, count(*) AS n, sum(hit) AS h, sum(c) AS c, sum(loss) AS l FROM g GROUP BY 1, 2, 3), cv AS (SELECT network, t AS temperature, sum(abs(h - c)) / sum(n) AS ece, sum(l) / sum(n) AS nll FROM gb GROUP BY 1, 2)"
_EDGES = f"(abs(temperature - {min(calibrate.GRID)!r}) < 1e-9 OR abs(temperature - {max(calibrate.GRID)!r}) < 1e-9)"
for _o in ("ece", "nll"):
    of_scored(f"m_temp_fit_{_o}", _CURVE + f" SELECT network, round(temperature, 6) AS temperature, round(ece, 6) AS ece, round(nll, 6) AS nll, {_EDGES} AS at_edge FROM (SELECT *, row_number() OVER (PARTITION BY network ORDER BY round({_o}, 9), round(abs(ln(temperature)), 9), temperature) AS r FROM cv) WHERE r = 1")(
        lambda s, o=_o: calibrate.fit(s, objective=o).select("network", r6("temperature").alias("temperature"), r6("ece").alias("ece"), r6("nll").alias("nll"), "at_edge")
    )
of_scored("m_temp_curve", _CURVE + " SELECT network, round(temperature, 6) AS temperature, round(ece, 6) AS ece, round(nll, 6) AS nll FROM cv")(
    lambda s: calibrate.curve(s).select("network", r6("temperature").alias("temperature"), r6("ece").alias("ece"), r6("nll").alias("nll"))
)
_REL2 = f", st AS (SELECT *, stage, {_HIT} AS hit, {_conf('t')} AS confidence FROM scored, (VALUES ('before', 1.0::DOUBLE), ('after', 9.0::DOUBLE)) v(stage, t))"
of_scored("m_reliability", _REL2 + f" SELECT stage, {_BIN.format('confidence')} AS bin, count(*) AS n, round(avg(hit), 6) AS accuracy, round(avg(confidence), 6) AS confidence, round(avg(confidence) - avg(hit), 6) AS gap FROM st GROUP BY 1, 2")(
    lambda s: calibrate.reliability(s, 9.0).select("stage", "bin", "n", r6("accuracy").alias("accuracy"), r6("confidence").alias("confidence"), r6("gap").alias("gap"))
)
of_scored("m_cross_entropy", f" SELECT network, round(avg({_loss()}), 6) AS cross_entropy FROM scored GROUP BY network")(
    lambda s: s.groupBy("network").agg(r6(F.avg(calibrate.nll(F.col("logits"), F.col("truth_idx")))).alias("cross_entropy"))
)
of_scored("a_nll", f" SELECT network, t::DOUBLE AS temperature, round(avg({_loss('t')}), 6) AS nll FROM scored, unnest([1.0, 3.0, 9.0]::DOUBLE[]) AS u(t) GROUP BY 1, 2")(
    lambda s: s.withColumn("temperature", F.explode(F.array(F.lit(1.0), F.lit(3.0), F.lit(9.0)))).groupBy("network", "temperature").agg(r6(F.avg(calibrate.nll(F.col("logits"), F.col("truth_idx"), F.col("temperature")))).alias("nll"))
)
of_scored("m_risk_coverage", _APPLIED + ", th AS (SELECT i / 20.0::DOUBLE AS threshold FROM unnest(range(0, 20)) AS u(i)) SELECT threshold, round(avg((round(confidence, 9) >= threshold)::INT), 6) AS coverage, round(avg(CASE WHEN round(confidence, 9) >= threshold THEN hit END), 6) AS accuracy FROM ap, th GROUP BY threshold")(
    lambda s: calibrate.risk_coverage(calibrate.apply(s)).select("threshold", r6("coverage").alias("coverage"), r6("accuracy").alias("accuracy"))
)

# The two binary label columns: word evidence, calibrated on one tenth of the documents and measured on another.
_USUAL = f"{word_odds.PRIOR}::DOUBLE * n / all_n"
_ODDS = f"round(1000000 * (ln(({{0}} + {_USUAL}) / (all_{{0}} + {word_odds.PRIOR}::DOUBLE)) - ln((n - {{0}} + {_USUAL}) / (all_n - all_{{0}} + {word_odds.PRIOR}::DOUBLE))))::BIGINT AS w_{{0}}"
_BASE = "round(1000000 * ln((all_{0} + 1)::DOUBLE / (all_n - all_{0} + 1)))::BIGINT AS b_{0}"
_W2B = f"""
WITH lab AS (SELECT doc_id, quality, toxic, text FROM labels JOIN documents USING (doc_id) WHERE text IS NOT NULL AND quality IS NOT NULL AND toxic IS NOT NULL),
words AS (SELECT DISTINCT doc_id, quality, toxic, unnest(string_split_regex(lower(text), '[^a-zà-ÿß]+')) AS word FROM lab),
counted AS (SELECT word, count(*) AS n, sum(quality)::BIGINT AS quality, sum(toxic)::BIGINT AS toxic FROM words WHERE doc_id % 10 < 8 AND word <> '' GROUP BY word),
total AS (SELECT count(*) AS all_n, sum(quality)::BIGINT AS all_quality, sum(toxic)::BIGINT AS all_toxic FROM lab WHERE doc_id % 10 < 8),
odds AS (SELECT word, {_ODDS.format("quality")}, {_ODDS.format("toxic")} FROM counted, total),
base AS (SELECT {_BASE.format("quality")}, {_BASE.format("toxic")} FROM total),
sums AS (SELECT doc_id, sum(w_quality) AS quality, sum(w_toxic) AS toxic FROM words JOIN odds USING (word) WHERE doc_id % 10 >= 8 GROUP BY doc_id),
judged AS (SELECT doc_id, u.network, CASE WHEN u.network = 'quality' THEN lab.quality ELSE lab.toxic END AS truth_idx, [0.0::DOUBLE, (CASE WHEN u.network = 'quality' THEN coalesce(sums.quality, 0) + b_quality ELSE coalesce(sums.toxic, 0) + b_toxic END)::DOUBLE / 1000000] AS logits
  FROM lab LEFT JOIN sums USING (doc_id), base, (VALUES ('quality'), ('toxic')) u(network) WHERE doc_id % 10 >= 8),
scored AS (SELECT * FROM judged WHERE doc_id % 10 = 8)
{_CURVE},
fitted AS (SELECT network, temperature FROM (SELECT *, row_number() OVER (PARTITION BY network ORDER BY round(ece, 9), round(abs(ln(temperature)), 9), temperature) AS r FROM cv) WHERE r = 1),
told AS (SELECT network, temperature, {_HIT} AS hit, {_conf()} AS c1, {_conf("temperature")} AS c2 FROM judged JOIN fitted USING (network) WHERE doc_id % 10 = 9),
before AS (SELECT network, sum(abs(h - c)) / sum(n) AS ece FROM (SELECT network, count(*) AS n, sum(hit) AS h, sum(c1) AS c FROM told GROUP BY network, {_BIN.format("c1")}) GROUP BY network),
after AS (SELECT network, sum(abs(h - c)) / sum(n) AS ece FROM (SELECT network, count(*) AS n, sum(hit) AS h, sum(c2) AS c FROM told GROUP BY network, {_BIN.format("c2")}) GROUP BY network)
SELECT network, count(*) AS n, round(min(temperature), 6) AS temperature, round(avg(hit), 6) AS accuracy, round(min(before.ece), 6) AS ece_before, round(min(after.ece), 6) AS ece_after
FROM told JOIN before USING (network) JOIN after USING (network) GROUP BY network"""


@query("w2b_binary_calibration", _W2B)
def w2b_binary_calibration(spark, sf_dir):
    """labels.quality and labels.toxic by word evidence: accuracy, and calibration error before and after the temperature that another tenth of the documents gives."""
    docs = table(spark, sf_dir, "labels").join(table(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id")
    names = ("quality", "toxic")
    scored_ = word_odds.scored(docs, F.col("doc_id") % 10 < 8, names).persist()
    fitted = calibrate.fit(scored_.where("doc_id % 10 = 8")).select("network", "temperature")
    told = scored_.where("doc_id % 10 = 9").join(F.broadcast(fitted), "network")
    plain_ = calibrate.ece(calibrate.apply(told), ["network", "temperature"]).withColumnRenamed("ece", "ece_before")
    fixed = calibrate.ece(calibrate.apply(told, F.col("temperature")), ["network"]).select("network", F.col("ece").alias("ece_after"))
    right = calibrate.apply(told).groupBy("network").agg(F.avg("hit").alias("accuracy"))
    x = plain_.join(fixed, "network").join(right, "network").select("network", "n", *(r6(c).alias(c) for c in ("temperature", "accuracy", "ece_before", "ece_after")))
    out = cut(x)
    scored_.unpersist()
    return out


# Simulation, keyed by order numbers so that the oracle has the same pseudo-studies.


def _sim_sql(alpha, k, mode, weight="confidence"):
    if alpha in simulate.ORDER_STATISTIC:
        c = f"list_sort([u0, u1, u2])[{simulate.ORDER_STATISTIC[alpha] + 1}] * {MICRO} // {P}"
    else:
        c = knot_lookup(f"({beta_knots(alpha)})", "u0")
    u = ", ".join(f"{stream(f'((study * {k} + s) * 5 + {j})', 17)} AS u{j}" for j in range(5))
    wrong = "1" if mode == "correlated" else "1 + u4 % 11"
    return (
        f"SELECT {alpha}::DOUBLE AS alpha, {k} AS k, '{mode}' AS mode, study, s, c, CASE WHEN u3 * {MICRO} // {P} < c THEN 0 ELSE {wrong} END AS label, {'c' if weight == 'confidence' else MICRO} AS w "
        f"FROM (SELECT *, {c} AS c FROM (SELECT o_orderkey AS study, s, {u} FROM (SELECT o_orderkey, o_orderkey AS study, s FROM orders, unnest(range(0, {k})) AS q(s))))"
    )


def _sim_result(votes_sql):
    return (
        f"WITH v AS ({votes_sql}), b AS (SELECT alpha, k, mode, study, label, sum(w) AS w FROM v GROUP BY ALL), t AS (SELECT *, max(w) OVER (PARTITION BY alpha, k, mode, study) AS top FROM b), "
        "d AS (SELECT alpha, k, mode, study, CASE WHEN count(*) = 1 AND min(label) = 0 THEN 1 ELSE 0 END AS r FROM t WHERE w = top GROUP BY 1, 2, 3, 4) "
        "SELECT alpha, k, mode, count(*) AS n, round(avg(r), 6) AS accuracy, round(sqrt(avg(r) * (1 - avg(r))), 6) AS sd_study, round(sqrt(avg(r) * (1 - avg(r)) / count(*)), 6) AS sd_mean FROM d GROUP BY 1, 2, 3"
    )


def _order_studies(spark, sf_dir):
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("study"))


def _rounded(x):
    return x.select("alpha", "k", "mode", "n", r6("accuracy").alias("accuracy"), r6("sd_study").alias("sd_study"), r6("sd_mean").alias("sd_mean"))


for _name, _a, _k, _m, _w in (("m_sim_uncorr", 0.5, 3, "uncorrelated", "confidence"), ("m_sim_corr", 0.5, 3, "correlated", "confidence"), ("m_sim_unit", 0.5, 2, "uncorrelated", "unit"), ("m_beta_order_stat", 0.25, 1, "uncorrelated", "confidence")):
    query(_name, _sim_result(_sim_sql(_a, _k, _m, _w)))(lambda spark, sf_dir, p=(_a, _k, _m, _w): _rounded(simulate.run(_order_studies(spark, sf_dir), *p)))
_ALPHAS, _KS = (0.1, 0.25, 0.5, 0.75, 0.9), (1, 2, 3, 5, 10)
query("m_sim_sweep", _sim_result(" UNION ALL ".join(_sim_sql(a, k, m) for a in _ALPHAS for k in _KS for m in simulate.MODES)))(lambda spark, sf_dir: _rounded(simulate.grid(_order_studies(spark, sf_dir), _ALPHAS, _KS)))
query("m_sim_accuracy", f"WITH v AS ({_sim_sql(0.5, 5, 'uncorrelated')}) SELECT round(avg((label = 0)::INT), 6) AS hit_rate FROM v")(
    lambda spark, sf_dir: simulate.check_calibrated(_order_studies(spark, sf_dir), 0.5, 5).select(r6("hit_rate").alias("hit_rate"))
)
query("m_sim_ece", f"WITH v AS ({_sim_sql(0.5, 5, 'uncorrelated')}), b AS (SELECT {_BIN.format('c / 1000000.0')} AS bin, count(*) AS n, avg((label = 0)::INT) AS a, avg(c / 1000000.0) AS c FROM v GROUP BY 1) SELECT round(sum(n * abs(a - c)) / sum(n), 6) AS ece FROM b")(
    lambda spark, sf_dir: simulate.check_calibrated(_order_studies(spark, sf_dir), 0.5, 5).select(r6("ece").alias("ece"))
)


@query("w6_million")
def w6_million(spark, sf_dir):
    """A million pseudo-studies in every cell of the sweep, with the deviation over a hundred batches of ten thousand."""
    x = simulate.grid(simulate.studies(spark, 1_000_000, 16), _ALPHAS, _KS, batches=100)
    return x.select("alpha", "k", "mode", "n", *(r6(c).alias(c) for c in ("accuracy", "sd_study", "sd_mean", "sd_batches")))


# Images: each embedding is an 8x8 picture or a 4x4x4 volume.
_IMG = "WITH img AS (SELECT vec_id, list_transform(embedding, lambda v: v::DOUBLE) AS d FROM embeddings), cells AS (SELECT vec_id, k, {} AS v FROM img, unnest(range(0, {})) AS u(k)) SELECT vec_id, string_agg(round(v * 1000000)::BIGINT::VARCHAR, ',' ORDER BY k) AS data FROM cells GROUP BY vec_id"


def _micro(a):
    """An array as micro-units in one string, so that both engines print it alike."""
    return F.array_join(F.transform(a, lambda v: F.round(v * 1000000).cast("long").cast("string")), ",")


def of_image(name, cell, n, spark_data):
    def run(spark, sf_dir):
        x = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("d"))
        return x.select("vec_id", _micro(spark_data(F.col("d"))).alias("data"))

    query(name, _IMG.format(cell, n))(run)


of_image("m_img_norm", "(d[k + 1] - list_min(d)) / (list_max(d) - list_min(d))", 64, lambda d: images.normalise(d))
of_image("m_img_grey", "(d[k + 1] + d[64 - k]) / 2", 64, lambda d: images.to_grey(F.array(d, F.reverse(d))))
of_image("m_img_slices", "d[CASE WHEN k < 16 THEN k + 1 WHEN k < 32 THEN k + 17 ELSE k + 17 END]", 48, lambda d: F.flatten(images.slices(d, 4, 4, 4)))
of_image("m_img_mip", "CASE WHEN k < 16 THEN list_max(d[k * 4 + 1:k * 4 + 4]) WHEN k < 32 THEN list_max([d[(k - 16) % 4 + ((k - 16) // 4) * 16 + j * 4 + 1] for j in [0, 1, 2, 3]]) ELSE list_max([d[k - 32 + j * 16 + 1] for j in [0, 1, 2, 3]]) END", 48,
         lambda d: F.concat(*(images.projection(d, 4, 4, 4, a) for a in "xyz")))
of_image("m_img_resample_linear", "(d[y0 * 8 + x0 + 1] * (1 - fx) + d[y0 * 8 + x0 + 2] * fx) * (1 - fy) + (d[y0 * 8 + x0 + 9] * (1 - fx) + d[y0 * 8 + x0 + 10] * fx) * fy", 1, lambda d: images.resample_linear(d, 8, 8, 5, 5))
from . import _FOUND, Query  # noqa: E402

_FOUND["m_img_resample_linear"] = Query(
    _FOUND["m_img_resample_linear"].run,
    "WITH img AS (SELECT vec_id, list_transform(embedding, lambda v: v::DOUBLE) AS d FROM embeddings), g AS (SELECT vec_id, d, k, (k % 5) * (7.0::DOUBLE / 4) AS px, (k // 5) * (7.0::DOUBLE / 4) AS py FROM img, unnest(range(0, 25)) AS u(k)), h AS (SELECT *, least(floor(px), 6)::INT AS x0, least(floor(py), 6)::INT AS y0 FROM g), c AS (SELECT *, px - x0 AS fx, py - y0 AS fy FROM h) SELECT vec_id, string_agg(round(1000000 * ((d[y0 * 8 + x0 + 1] * (1 - fx) + d[y0 * 8 + x0 + 2] * fx) * (1 - fy) + (d[y0 * 8 + x0 + 9] * (1 - fx) + d[y0 * 8 + x0 + 10] * fx) * fy))::BIGINT::VARCHAR, ',' ORDER BY k) AS data FROM c GROUP BY vec_id",
)
of_image("m_img_stretch", "greatest(0, least(1, (d[k + 1] - list_sort(d)[4]) / (list_sort(d)[61] - list_sort(d)[4])))", 64, lambda d: images.stretch(d, 4, 61))
of_image("m_img_crop", "d[(2 + k // 4) * 8 + 3 + k % 4]", 16, lambda d: images.crop(d, 8, 2, 2, 4, 4))
query("m_img_branch", "SELECT p_partkey, p_size >= 40 AS is_volume FROM part")(lambda spark, sf_dir: table(spark, sf_dir, "part").select("p_partkey", images.is_volume(F.col("p_size")).alias("is_volume")))
_FLIP, _TURN = f"{permille('vec_id', 51)} < 200", f"{permille('vec_id', 52)} < 200"
query("m_img_augment", f"WITH img AS (SELECT vec_id, list_transform(embedding, lambda v: v::DOUBLE) AS d FROM embeddings), f AS (SELECT vec_id, list(d[CASE WHEN {_FLIP} THEN (k // 8) * 8 + 8 - k % 8 ELSE k + 1 END] ORDER BY k) AS d FROM img, unnest(range(0, 64)) AS u(k) GROUP BY vec_id) SELECT vec_id, string_agg(round(1000000 * d[CASE WHEN {_TURN} THEN (k % 8) * 8 + 8 - k // 8 ELSE k + 1 END])::BIGINT::VARCHAR, ',' ORDER BY k) AS data FROM f, unnest(range(0, 64)) AS u(k) GROUP BY vec_id")(
    lambda spark, sf_dir: images.augment(table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("data")), "vec_id", "data", 8).select("vec_id", _micro(F.col("data")).alias("data"))
)
query("m_img_prepare")(lambda spark, sf_dir: images.prepare(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), F.lit(4).alias("nx"), F.lit(4).alias("ny"), F.lit(4).alias("nz"), F.col("embedding").alias("data")), 8, z_threshold=4))

# Sampling on documents.
query("m_reject_descriptor", "SELECT p_partkey, p_type AS descriptor FROM part WHERE NOT regexp_matches(p_type, 'SMALL|PROMO')")(
    lambda spark, sf_dir: sampling.reject_descriptor(table(spark, sf_dir, "part").select("p_partkey", F.col("p_type").alias("descriptor")), "SMALL|PROMO")
)
query("m_cap_per_class", f"SELECT doc_id, lang FROM (SELECT doc_id, lang, row_number() OVER (PARTITION BY lang ORDER BY {stream('doc_id', 1)}, doc_id) AS r FROM documents) WHERE r <= 50")(
    lambda spark, sf_dir: sampling.cap_per_class(table(spark, sf_dir, "documents").select("doc_id", "lang"), "lang", "doc_id", 50)
)
query("m_split", f"SELECT doc_id, CASE WHEN {stream('doc_id', 2)} % 100 < 80 THEN 'train' WHEN {stream('doc_id', 2)} % 100 < 90 THEN 'validation' ELSE 'test' END AS part FROM documents")(
    lambda spark, sf_dir: sampling.split(table(spark, sf_dir, "documents").select("doc_id"), "doc_id")
)
_FOLD = f"SELECT doc_id, lang, text, ((row_number() OVER (PARTITION BY lang ORDER BY {stream('doc_id', 3)}, doc_id) - 1) % 5)::INT AS fold FROM documents"
query("m_folds", f"SELECT doc_id, lang, fold FROM ({_FOLD})")(lambda spark, sf_dir: sampling.folds(table(spark, sf_dir, "documents").select("doc_id", "lang"), "lang", "doc_id"))
_TOK = "SELECT DISTINCT doc_id, lang AS label, unnest(string_split_regex(lower(text), '[^a-zà-ÿß]+')) AS token FROM documents WHERE doc_id % 5 <> 0"
query("m_mine_keywords", f"WITH t AS ({_TOK}), n AS (SELECT token, label, count(*) AS docs FROM t WHERE length(token) >= 6 GROUP BY 1, 2), a AS (SELECT *, sum(docs) OVER (PARTITION BY token) AS al FROM n) SELECT label, token AS keyword, docs FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY docs DESC, token) AS r FROM a WHERE docs >= 5 AND docs >= 0.95 * al) WHERE r <= 20")(
    lambda spark, sf_dir: keywords.mine(table(spark, sf_dir, "documents").where("doc_id % 5 <> 0").select("doc_id", F.col("lang").alias("label"), F.explode(F.array_distinct(F.split(F.lower("text"), "[^a-zà-ÿß]+"))).alias("token")).where("token <> ''"))
)
query("m_mil_pool", "SELECT user_id AS study_id, round(avg(value), 6) AS mean_value, round(avg(k), 6) AS mean_k FROM (SELECT user_id, value, json_extract(props, '$.k')::DOUBLE AS k FROM events) GROUP BY 1")(
    lambda spark, sf_dir: network.mil_pool(table(spark, sf_dir, "events").select(F.col("user_id").alias("study_id"), F.array("value", F.get_json_object("props", "$.k").cast("double")).alias("x"))).select("study_id", r6(F.col("x")[0]).alias("mean_value"), r6(F.col("x")[1]).alias("mean_k"))
)


def gram_shares(text: str, n: int, size: int, block: int = 1 << 20) -> np.ndarray:
    """Square roots of the shares of hashed character n-grams; a text shorter than n is one gram. Very long texts are counted block by block."""
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.uint64)
    codes = np.pad(codes, (0, max(0, n - len(codes))))
    out = np.zeros(size)
    for at in range(0, len(codes) - n + 1, block):
        part = codes[at : at + block + n - 1]
        h = np.zeros(len(part) - n + 1, dtype=np.uint64)
        for j in range(n):
            h = (h ^ part[j : j + len(h)]) * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(32)
        out += np.bincount((h % np.uint64(size)).astype(np.int64), minlength=size)
    return np.sqrt(out / out.sum())


def char_grams(docs, n: int, size: int = 512):
    """Frozen features x of whole texts, by `gram_shares` in Arrow batches; text goes."""

    @F.pandas_udf("array<double>")
    def shares(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: gram_shares(t, n, size))

    return docs.withColumn("x", shares("text")).drop("text")


def cross_validate(features, folds: int = 5):
    """(doc_id, fold, class_id, predicted): every document of fold f is predicted by a head trained on the training documents of the others."""
    out = None
    training = features.where("trains").repartition(1).persist()  # the cap bounds it
    for f in range(folds):
        model = network.fit_head(training.where(F.col("fold") != f), iterations=15)
        p = network.predict(model, features.where(F.col("fold") == f)).select("doc_id", "fold", "modality", "class_id", "predicted")
        out = p if out is None else out.unionByName(p)
    training.unpersist()
    return out


def _documents(spark, sf_dir, n, cap=200, by=("class_id",)):
    """Features of every document, its fold, and whether it trains: the other four folds hold at most `cap` training documents of a class (by `by`); the cap never cuts what is evaluated.

    The features are written once: fits and predictions read 512 numbers a document, not its text.
    """
    docs = table(spark, sf_dir, "documents").where("text is not null").select("doc_id", "text", "lang", "source")
    docs = docs.withColumn("modality", F.concat(F.lit("m"), F.regexp_extract("source", r"(\d+)", 1).cast("int") % 5)).drop("source")
    docs = sampling.folds(docs, "lang", "doc_id").withColumn("class_id", (F.array_position(F.array(*map(F.lit, ("de", "en", "es", "fr"))), F.col("lang")) - 1).cast("int"))
    trains = word_heads.training_rows(docs, cap, by).select("doc_id", F.lit(True).alias("_t"))
    return cut(char_grams(docs.join(checked_broadcast(trains), "doc_id", "left").withColumn("trains", F.coalesce("_t", F.lit(False))).drop("_t"), n))


@query("m_cv")
def m_cv(spark, sf_dir):
    """Five-fold accuracy with its interval of a head over character trigrams."""
    p = cross_validate(_documents(spark, sf_dir, 3))
    return evaluate.t_interval(p.groupBy("fold").agg(F.avg((F.col("class_id") == F.col("predicted")).cast("int")).alias("acc")), [])


@query("b_two_nets")
def b_two_nets(spark, sf_dir):
    """Two feature sets by pseudo-modality, five folds each; the better one is kept."""
    out = None
    for n in (3, 5):
        p = cross_validate(_documents(spark, sf_dir, n)).withColumn("network", F.lit(f"{n}-grams"))
        out = p if out is None else out.unionByName(p)
    acc = out.groupBy("modality", "network", "fold").agg(F.avg((F.col("class_id") == F.col("predicted")).cast("int")).alias("acc"))
    table_ = evaluate.t_interval(acc, ["modality", "network"])
    best = network.select_best(table_).select("modality", F.col("network").alias("kept"))
    return table_.join(best, "modality").withColumn("is_kept", F.col("network") == F.col("kept")).drop("kept")


@query("m_head_fit")
def m_head_fit(spark, sf_dir):
    """One head per pseudo-modality, trained on at most 200 documents per class of four folds; accuracy of each over every document of the fifth."""
    x = _documents(spark, sf_dir, 3, by=("class_id", "modality"))
    training = x.where("trains AND fold <> 0").repartition(1).persist()  # the cap bounds it
    models, out = network.fit_heads(training, iterations=8), None
    training.unpersist()
    for name, model in models.items():
        p = network.predict(model, x.where((F.col("modality") == name) & (F.col("fold") == 0))).agg(F.lit(name).alias("modality"), F.avg((F.col("class_id") == F.col("predicted")).cast("int")).alias("accuracy"))
        out = p if out is None else out.unionByName(p)
    return out


@query("m_mil_fit")
def m_mil_fit(spark, sf_dir):
    """One head per pooling over bags: a document is the bag of its lines, pooled to their mean or maximum; fitted on at most 200 documents per class of four folds, accuracy over every document of the fifth that has a line."""
    docs = table(spark, sf_dir, "documents").where("text is not null").select("doc_id", "lang")
    docs = sampling.folds(docs, "lang", "doc_id").withColumn("class_id", (F.array_position(F.array(*map(F.lit, ("de", "en", "es", "fr"))), F.col("lang")) - 1).cast("int"))
    trains = word_heads.training_rows(docs, 200).where("fold <> 0").select("doc_id", F.lit(True).alias("trains"))
    keys = cut(docs.join(checked_broadcast(trains), "doc_id", "left").where("fold = 0 OR trains").select(F.col("doc_id").alias("study_id"), "class_id", F.coalesce("trains", F.lit(False)).alias("trains")))
    lines = texts.document_series(spark, sf_dir).where("line <> ''").select(F.col("doc_id").alias("study_id"), F.col("line").alias("text"))
    series = char_grams(lines.join(keys.select("study_id"), "study_id"), 3, size=64)
    out = None
    for pooling in ("max", "mean"):
        # The steps of fit_mil, with the bags written in between: the fit reads them more than once.
        bags = cut(network.mil_pool(series, pooling).join(keys, "study_id"))
        model = network.fit_head(bags.where("trains").repartition(1), iterations=15)
        p = network.predict(model, bags.where("NOT trains")).agg(F.lit(pooling).alias("pooling"), F.count(F.lit(1)).alias("n"), r6(F.avg((F.col("class_id") == F.col("predicted")).cast("int"))).alias("accuracy"))
        out = p if out is None else out.unionByName(p)
    return out

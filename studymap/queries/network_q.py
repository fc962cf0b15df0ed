"""Networks inside the cascade: prepared pixels, logits, temperature, routing, votes."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import images
from ..functions.lineage import cut
from ..functions.portable import inline_table
from ..operators import calibrate, network
from ..plans import cascade
from ..sources.embeddings import scored
from . import query, table
from .models_q import _CURVE, _SC, _conf
from .orders_q import CTES, _cascade, _decided, corpus

r6 = lambda c: F.round(c, 6)

_NORM = (
    "WITH px AS (SELECT vec_id, label, pos, v::DOUBLE AS v FROM (SELECT vec_id, label, unnest(embedding) AS v, generate_subscripts(embedding, 1) AS pos FROM embeddings)), "
    "n AS (SELECT vec_id, label, pos, (v - min(v) OVER w) / (max(v) OVER w - min(v) OVER w) AS v FROM px WINDOW w AS (PARTITION BY vec_id)), "
    "cent AS (SELECT label AS c, pos, avg(v) AS m FROM n WHERE vec_id % 10 < 8 GROUP BY 1, 2), "
    "lg AS (SELECT vec_id, label, c, sum(v * m) AS z FROM n JOIN cent USING (pos) WHERE vec_id % 10 >= 8 GROUP BY 1, 2, 3) "
)


@query("m_network_infer", _NORM + "SELECT vec_id, c AS class_id, round(z, 6) AS logit FROM lg")
def m_network_infer(spark, sf_dir):
    """Pixels through the whole preparation (normalised, resampled, three channels), the frozen features, and the last layer: one logit for each class."""
    emb = table(spark, sf_dir, "embeddings")
    pixels = emb.select(F.col("vec_id").alias("key"), F.lit(8).alias("nx"), F.lit(8).alias("ny"), F.lit(1).alias("nz"), F.col("embedding").alias("data"))
    x = images.prepare(pixels, 8).select(F.col("key").alias("vec_id"), images.to_grey(F.col("channels")).alias("x")).join(emb.select("vec_id", "label"), "vec_id")
    x = cut(x)
    out = network.infer(x.where("vec_id % 10 >= 8"), network.centroid_head(x.where("vec_id % 10 < 8")))
    return out.select("vec_id", F.posexplode("logits").alias("class_id", "z")).select("vec_id", "class_id", r6("z").alias("logit"))


def _names(spark):
    return inline_table(spark, [(i, f"class {i}") for i in range(10)], "class_id int, label string")


@query("m_votes_from_logits", _SC + f", t AS (SELECT * FROM (VALUES ('x20', 3.0::DOUBLE), ('x60', 9.0)) v(network, t)) SELECT row_id AS study_id, network, 'class ' || (list_position(logits, list_max(logits)) - 1) AS label, round({_conf('t')}, 6) AS weight FROM scored JOIN t USING (network)")
def m_votes_from_logits(spark, sf_dir):
    temperatures = inline_table(spark, [("x20", 3.0), ("x60", 9.0)], "network string, temperature double")
    out = None
    for n in ("x20", "x60"):  # a vote has no network: each network's votes are named here
        s = scored(spark, sf_dir).where(F.col("network") == n).select(F.col("row_id").alias("study_id"), F.lit(0).alias("series_no"), "network", "logits")
        v = network.votes_from_logits(s, _names(spark), temperatures).select("study_id", F.lit(n).alias("network"), "label", r6(F.col("weight_u") / 1e6).alias("weight"))
        out = v if out is None else out.unionByName(v)
    return out


#: Which network judges a modality; the silent one has none.
ROUTES = (("STANDARD", "x20"), ("MEDIUM", "x20"), ("LARGE", "x20"), ("SMALL", "x20"), ("ECONOMY", "x60"))
_ROW = "((study_id * 64 + series_no) % {n})"


def calibrated_corpus(spark, sf_dir, tempered: bool = True) -> cascade.Corpus:
    """The orders corpus whose series carry pictures: each series shows a held-out embedding; its modality's network gives logits, tempered by what the validation half fits."""
    c = corpus(spark, sf_dir)
    logits = cut(scored(spark, sf_dir))
    n = table(spark, sf_dir, "embeddings").where("vec_id % 10 >= 8").count()
    at = _ROW.format(n=max(n, 1))
    shown = c.series.select("study_id", "series_no", F.expr(f"({at} div 2) * 10 + 8 + {at} % 2").alias("row_id"))
    routes = inline_table(spark, [(m, k, True) for m, k in ROUTES] + [("PROMO", None, False)], "modality string, network string, votes boolean")
    temperatures = calibrate.fit(logits.where("row_id % 10 = 8")).select("network", "temperature") if tempered else inline_table(spark, [(k, 1.0) for k in ("x20", "x60")], "network string, temperature double")
    classes = c.class_ref.where("parent is not null AND class_id % 6 = 0").select((F.col("class_id") / 6).cast("int").alias("class_id"), "label")
    return c.but(logits=shown.join(logits.select("row_id", "network", "logits"), "row_id").select("study_id", "series_no", "network", "logits"), route_ref=routes, temperatures=cut(temperatures), net_classes=classes)


def _calibrated_sql(order, tempered: bool = True) -> str:
    valid = _CURVE.replace("FROM scored", "FROM (SELECT * FROM scored WHERE row_id % 10 = 8)")
    route = "CASE modality " + " ".join(f"WHEN '{m}' THEN '{n}'" for m, n in ROUTES) + " END"
    at = _ROW.format(n="(SELECT count(*) FROM embeddings WHERE vec_id % 10 >= 8)")
    fitted = "SELECT network, temperature AS t FROM (SELECT *, row_number() OVER (PARTITION BY network ORDER BY round(ece, 9), round(abs(ln(temperature)), 9), temperature) AS r FROM cv) WHERE r = 1"
    ctes = (
        ", ".join(f"{n} AS ({q})" for n, q in CTES.items() if not n.startswith(("v_", "graded"))) + ", " + _SC[len("WITH ") :] + valid
        + f", fitted AS ({fitted if tempered else 'SELECT network, 1.0::DOUBLE AS t FROM scored GROUP BY network'})"
        + f", shown AS (SELECT study_id, series_no, {route} AS network, ({at} // 2) * 10 + 8 + {at} % 2 AS row_id FROM lines)"
        + f", lv AS (SELECT study_id, r.label, round({_conf('t')} * 1000000)::BIGINT AS weight_u FROM shown JOIN scored s USING (row_id, network) JOIN fitted USING (network) JOIN class_ref r ON r.parent IS NOT NULL AND r.class_id = 6 * (list_position(s.logits, list_max(s.logits)) - 1))"
        + ", l5c AS (" + _decided("SELECT study_id, label, weight_u FROM lv") + ")"
    )
    return f"WITH {ctes} SELECT study_id, label, layer FROM ({_cascade(*order).replace('l5', 'l5c')}) WHERE label IS NOT NULL"


query("m_cascade_calibrated", _calibrated_sql(("l1", "l2", "l3", "l4", "l5")))(lambda spark, sf_dir: cascade.classify(calibrated_corpus(spark, sf_dir)))
query("m_cascade_uncalibrated", _calibrated_sql(("l1", "l2", "l3", "l4", "l5"), False))(lambda spark, sf_dir: cascade.classify(calibrated_corpus(spark, sf_dir, False)))
query("m_network_first_calibrated", _calibrated_sql(("l5", "l1", "l2", "l3", "l4")))(lambda spark, sf_dir: cascade.classify(calibrated_corpus(spark, sf_dir), cascade.Config(order=(5, 1, 2, 3, 4))))

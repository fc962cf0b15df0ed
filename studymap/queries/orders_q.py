"""Queries on the orders corpus: layers, votes, rules, cascade, variants, baselines and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text
from ..functions.lineage import cut
from ..operators import baselines, evaluate, keywords, layers, network, rules, sampling, votes
from ..plans import cascade, variants
from ..plans.grid import all_outcomes, layer_table, outcomes
from ..functions.portable import inline_table, stream
from ..sources import orders as W1
from . import query, table

#: The rules of the corpus: brands never vote, silent modalities count half; two extended ones relabel and drop on condition.
RULES = [
    (1, "core", None, "brand", None, None, "drop", None, None),
    (2, "core", "PROMO", None, None, None, "reweight", None, 0.5),
    (3, "extended", None, "name", "old rod", None, "relabel", "new rod", None),
    (4, "extended", None, None, "cold ring", "hot ring", "drop", None, None),
]
NORM = "nullif(trim(regexp_replace(lower({}), '\\s+', ' ', 'g')), '')"

CTES = W1.CTES | {
    "tags": f"SELECT study_id, series_no, modality, key, {NORM.format('v')} AS value FROM (SELECT study_id, series_no, modality, unnest(['brand', 'flag', 'name', 'pack']) AS key, unnest([brand, flag, name, modality]) AS v FROM lines)",
    "vals": f"SELECT DISTINCT value FROM (SELECT {NORM.format('description')} AS value FROM study UNION ALL SELECT value FROM tags) WHERE value IS NOT NULL",
    "subs": "SELECT DISTINCT keyword, substr(keyword, i, n) AS sub, n FROM keyword_ref, unnest(range(1, length(keyword) - 4)) AS u(i), unnest(range(6, length(keyword) + 1)) AS w(n) WHERE length(keyword) >= 6 AND i + n - 1 <= length(keyword)",
    "kwhit": "SELECT value, keyword, max(n) AS score FROM vals JOIN subs ON contains(value, sub) GROUP BY value, keyword UNION ALL SELECT value, keyword, length(keyword) FROM vals JOIN keyword_ref ON length(keyword) IN (4, 5) AND list_contains(string_split_regex(value, '[^a-z0-9]+'), keyword)",
    "kwscore": "SELECT value, keyword, label, score FROM kwhit JOIN keyword_ref USING (keyword)",
    "kwbest": "SELECT value, min(label) AS label, min(score) AS score FROM (SELECT *, max(score) OVER (PARTITION BY value) AS top FROM kwscore) WHERE score = top GROUP BY value HAVING count(DISTINCT label) = 1",
    "l1": f"SELECT study_id, label FROM study JOIN code_ref ON {NORM.format('procedure_code')} = lower(code)",
    "l2": f"SELECT study_id, label FROM study JOIN class_ref ON {NORM.format('description')} = label AND parent IS NOT NULL",
    "l3": f"SELECT study_id, label, score FROM study JOIN kwbest ON value = {NORM.format('description')}",
    "mv": "SELECT study_id, series_no, modality, key, label, 1000000::BIGINT AS weight_u FROM tags JOIN kwbest USING (value)",
    "mv_core": "SELECT study_id, series_no, key, label, CASE WHEN modality = 'PROMO' THEN 500000 ELSE weight_u END AS weight_u FROM mv WHERE key <> 'brand'",
    "mv_full": "SELECT study_id, series_no, key, CASE WHEN label = 'old rod' AND key = 'name' THEN 'new rod' ELSE label END AS label, CASE WHEN modality = 'PROMO' THEN 500000 ELSE weight_u END AS weight_u FROM mv WHERE key <> 'brand' AND NOT (label = 'cold ring' AND study_id IN (SELECT study_id FROM mv WHERE label = 'hot ring'))",
}


def _decided(source: str) -> str:
    return f"SELECT study_id, min(label) AS label, min(w) AS weight_u FROM (SELECT *, max(w) OVER (PARTITION BY study_id) AS top FROM (SELECT study_id, label, sum(weight_u)::BIGINT AS w FROM ({source}) GROUP BY study_id, label)) WHERE w = top AND w > 0 GROUP BY study_id HAVING count(*) = 1"


_NET = "SELECT study_id, label, confidence_u AS weight_u FROM net"
_META = "SELECT study_id, label, weight_u FROM "
CTES |= {
    "l4_raw": _decided(_META + "mv"), "l4": _decided(_META + "mv_full"), "l4_min": _decided(_META + "mv_core"), "l5": _decided(_NET),
    "h1m": _decided(f"{_META} mv_full UNION ALL {_NET}"), "h1m_min": _decided(f"{_META} mv_core UNION ALL {_NET}"),
    "h2": _decided(f"{_META} mv_full UNION ALL {_NET} UNION ALL SELECT study_id, label, 1000000 FROM l1 UNION ALL SELECT study_id, label, 1000000 FROM l2 UNION ALL SELECT study_id, label, 1000000 FROM l3"),
}
PLACES = {"l1": 1, "l2": 2, "l3": 3, "l4": 4, "l4_min": 4, "l5": 5, "h1m": 6, "h1m_min": 6, "h2": 6}


def _cascade(*order: str) -> str:
    joins = " ".join(f"LEFT JOIN {t} ON {t}.study_id = s.study_id" for t in order)
    case = " ".join(f"WHEN {t}.label IS NOT NULL THEN {PLACES[t]}" for t in order)
    return f"SELECT s.study_id, coalesce({', '.join(t + '.label' for t in order)}) AS label, CASE {case} END AS layer FROM study s {joins}"


ORDERS = {
    "no_network": ("l1", "l2", "l3", "l4"), "network_l1": ("l5", "l1", "l2", "l3", "l4"), "network_l2": ("l1", "l5", "l2", "l3", "l4"), "network_l3": ("l1", "l2", "l5", "l3", "l4"),
    "network_l4": ("l1", "l2", "l3", "l5", "l4"), "network_l5": ("l1", "l2", "l3", "l4", "l5"), "hybrid_h1": ("l1", "l2", "l3", "h1m"), "hybrid_h2": ("h2",),
    "hybrid_h1_minvr": ("l1", "l2", "l3", "h1m_min"), "network_l5_minvr": ("l1", "l2", "l3", "l4_min", "l5"), "network_only": ("l5",),
}
CTES |= {f"v_{name}": _cascade(*order) for name, order in ORDERS.items()}
#: Regular expressions on code and description alone, a stand-in for a product that cannot be rebuilt.
CTES["v_importer"] = "SELECT study_id, " + baselines.importer_case("sql") + " AS label, 1 AS layer FROM study LEFT JOIN code_ref ON procedure_code = code"
VARIANTS = [*ORDERS, "importer"]
_GRADE = "CASE WHEN p.label IS NULL THEN 'unanswered' WHEN coalesce(list_contains(s.truth, p.label), false) THEN 'right' WHEN EXISTS (SELECT 1 FROM minor_pair m WHERE m.pred = p.label AND list_contains(s.truth, m.truth)) THEN 'minor' ELSE 'major' END"


def graded(name: str) -> str:
    return f"SELECT s.study_id, p.label, p.layer, {_GRADE} AS grade FROM study s LEFT JOIN v_{name} p USING (study_id)"


CTES["graded_all"] = " UNION ALL ".join(f"SELECT '{n}' AS variant, g.* FROM ({graded(n)}) g" for n in VARIANTS)


def sql(select: str) -> str:
    return "WITH " + ",\n".join(f"{n} AS ({q})" for n, q in CTES.items()) + "\n" + select


def corpus(spark, sf_dir, ruled: bool = True) -> cascade.Corpus:
    """The corpus, each of its tables made once, when it is first read."""
    held = {}

    def once(name, make, hold=cut):
        if name not in held:
            held[name] = hold(make())
        return held[name]

    items = lambda: once("items", lambda: W1.lines(spark, sf_dir))
    classes = lambda: once("classes", lambda: W1.class_ref(spark, sf_dir), text.literal)
    study = lambda: once("study", lambda: W1.study(spark, sf_dir, items()))
    return cascade.Corpus(
        study=study, series=lambda: W1.series(spark, sf_dir, items()), network_scores=lambda: W1.network_scores(spark, sf_dir, items(), study()),
        class_ref=classes, code_ref=lambda: W1.code_ref(spark, sf_dir, classes()), desc_ref=lambda: W1.desc_ref(spark, sf_dir, classes()), keyword_ref=lambda: W1.keyword_ref(spark, sf_dir, classes()),
        rule_ref=(lambda: rules.rule_table(spark, RULES)) if ruled else None,
    )


def of_corpus(name, select):
    """Register a function of (corpus) with the oracle over the corpus's tables."""

    def keep(f):
        query(name, sql(select))(lambda spark, sf_dir: f(corpus(spark, sf_dir)))
        return f

    return keep


@query("w1_study", sql("SELECT study_id, procedure_code, description, arrived, array_to_string(truth, '|') AS truth FROM study"))
def w1_study(spark, sf_dir):
    return W1.study(spark, sf_dir).select("study_id", "procedure_code", "description", "arrived", F.concat_ws("|", "truth").alias("t0"), "truth").select("study_id", "procedure_code", "description", "arrived", F.when(F.col("truth").isNotNull(), F.col("t0")).alias("truth"))


of_corpus("w1_network", "SELECT study_id, series_no, modality, label, confidence_u, hit FROM net")(lambda c: c.network_scores)
of_corpus("m_layer1_code", "SELECT study_id, label FROM l1")(lambda c: layers.match_code(c.study, c.code_ref).select("study_id", "label"))
of_corpus("m_layer2_desc", "SELECT study_id, label FROM l2")(lambda c: layers.match_description(c.study, c.desc_ref).select("study_id", "label"))
of_corpus("m_layer3_partial", "SELECT study_id, label, score FROM l3")(lambda c: layers.match_partial(c.study, c.keyword_ref))
of_corpus("m_lcsubstr", "SELECT value, keyword, max(n) AS len FROM vals JOIN subs ON contains(value, sub) GROUP BY value, keyword")(
    lambda c: text.lcsubstr_len(_values(c), c.keyword_ref.where("length(keyword) >= 6").select("keyword", F.col("keyword").alias("t")), 6, "value", "keyword")
)
of_corpus("x_qgrams", "SELECT label AS keyword, i AS pos, substr(label, i, 6) AS gram FROM class_ref, unnest(range(1, length(label) - 4)) AS u(i) WHERE length(label) >= 6")(
    lambda c: text.qgrams(c.class_ref.select(F.col("label").alias("keyword")), "keyword", "keyword", 6).select("keyword", (F.col("pos") + 1).alias("pos"), "gram")
)


def _values(c) -> DataFrame:
    a = c.study.select(text.normalise(F.col("description")).alias("value"))
    b = votes.extract_tags(c.series, c.keys).select("value")
    return a.unionByName(b).where("value is not null").distinct().select("value", F.col("value").alias("t"))


for _mode, _on in (("word", "list_contains(string_split_regex(value, '[^a-z0-9]+'), label)"), ("substring", "contains(value, label)"), ("equal", "value = label")):
    of_corpus(f"m_short_kw_{_mode}", f"SELECT DISTINCT value, label AS keyword FROM vals JOIN class_ref ON length(label) IN (4, 5) AND {_on}")(
        lambda c, mode=_mode: text.whole_keyword(_values(c).select("value"), c.class_ref.where("length(label) IN (4, 5)").select(F.col("label").alias("keyword")), mode)
    )
of_corpus("m_extract_tags", "SELECT study_id, series_no, key, value FROM tags WHERE key IN ('name', 'pack')")(lambda c: votes.extract_tags(c.series, ("name", "pack")))
of_corpus("m_meta_votes", "SELECT study_id, series_no, 'tag:' || key AS origin, label, weight_u FROM mv")(lambda c: votes.metadata_votes(c.series, c.keyword_ref, c.keys))
of_corpus("m_meta_votes_per_keyword", "SELECT study_id, series_no, 'tag:' || key AS origin, label, 1000000::BIGINT AS weight_u FROM tags JOIN kwscore USING (value)")(
    lambda c: votes.metadata_votes(c.series, c.keyword_ref, c.keys, vote_per="keyword")
)


def _rule(*numbers):
    def run(c):
        v = votes.metadata_votes(c.series, c.keyword_ref, c.keys).join(c.series.select("study_id", "series_no", "modality"), ["study_id", "series_no"])
        v = v.select("study_id", "label", "weight_u", "origin", "series_no", "modality")
        return rules.apply(v, c.rule_ref.where(F.col("rule_id").isin(*numbers))).select("study_id", "series_no", "label", "weight_u")

    return run


of_corpus("m_rules_drop", "SELECT study_id, series_no, label, weight_u FROM mv WHERE key <> 'brand'")(_rule(1))
of_corpus("m_rules_relabel", "SELECT study_id, series_no, CASE WHEN label = 'old rod' AND key = 'name' THEN 'new rod' ELSE label END AS label, weight_u FROM mv")(_rule(3))
of_corpus("m_rules_reweight", "SELECT study_id, series_no, label, CASE WHEN modality = 'PROMO' THEN 500000 ELSE weight_u END AS weight_u FROM mv")(_rule(2))
of_corpus("m_rules_conditional", "SELECT study_id, series_no, label, weight_u FROM mv WHERE NOT (label = 'cold ring' AND study_id IN (SELECT study_id FROM mv WHERE label = 'hot ring'))")(_rule(4))
of_corpus("m_majority", "SELECT study_id, label, weight_u FROM l4_raw")(lambda c: votes.decide(votes.metadata_votes(c.series, c.keyword_ref, c.keys)).select("study_id", "label", "weight_u"))
of_corpus("m_majority_absolute", "SELECT study_id, label, weight_u FROM l4_raw JOIN (SELECT study_id, sum(weight_u) AS w FROM mv GROUP BY study_id) USING (study_id) WHERE weight_u * 2 > w")(
    lambda c: votes.decide(votes.metadata_votes(c.series, c.keyword_ref, c.keys), "absolute").select("study_id", "label", "weight_u")
)
of_corpus("m_network_votes", "SELECT study_id, series_no, label, confidence_u AS weight_u FROM net")(lambda c: network.votes(c.network_scores).select("study_id", "series_no", "label", "weight_u"))


of_corpus("w1c_log_odds", "SELECT study_id, min(label) AS label, min(w) AS weight_u FROM (SELECT *, max(w) OVER (PARTITION BY study_id) AS top FROM (SELECT study_id, label, sum(round(1000000 * ln(c / (1 - c)))::BIGINT)::BIGINT AS w FROM (SELECT study_id, label, least(greatest(confidence_u, 1000), 999000) / 1000000.0::DOUBLE AS c FROM net) GROUP BY study_id, label)) WHERE w = top AND w > 0 GROUP BY study_id HAVING count(*) = 1")(
    lambda c: votes.decide(network.votes(c.network_scores, weight="log_odds")).select("study_id", "label", "weight_u")
)


def _routes(spark):
    return inline_table(spark, [(m, "dense" if m != "ECONOMY" else "residual", True) for m in W1.ACCURACY] + [(W1.SILENT, None, False)], "modality string, network string, votes boolean")


@query("m_route", sql("SELECT study_id, series_no, modality, CASE WHEN modality = 'ECONOMY' THEN 'residual' ELSE 'dense' END AS network FROM lines WHERE modality <> 'PROMO'"))
def m_route(spark, sf_dir):
    return network.route(W1.series(spark, sf_dir), _routes(spark)).select("study_id", "series_no", "modality", "network")


_ANSWERED = " WHERE label IS NOT NULL"
of_corpus("m_cascade", "SELECT study_id, label, layer FROM v_network_l5" + _ANSWERED)(lambda c: cascade.classify(c))
for _p in range(1, 6):
    of_corpus(f"m_nwe_l{_p}", f"SELECT study_id, label, layer FROM v_network_l{_p}" + _ANSWERED)(lambda c, p=_p: variants.network_at(c, p))
of_corpus("m_no_network", "SELECT study_id, label, layer FROM v_no_network" + _ANSWERED)(lambda c: variants.no_network(c))
of_corpus("m_hybrid_h1", "SELECT study_id, label, layer FROM v_hybrid_h1" + _ANSWERED)(lambda c: variants.hybrid_h1(c))
of_corpus("m_hybrid_h2", "SELECT study_id, label, layer FROM v_hybrid_h2" + _ANSWERED)(lambda c: variants.hybrid_h2(c))
of_corpus("m_minvr_h1", "SELECT study_id, label, layer FROM v_hybrid_h1_minvr" + _ANSWERED)(lambda c: variants.hybrid_h1(c, cascade.Config(tier="min")))
of_corpus("m_minvr_l5", "SELECT study_id, label, layer FROM v_network_l5_minvr" + _ANSWERED)(lambda c: variants.network_at(c, 5, cascade.Config(tier="min")))
of_corpus("b_network_only", "SELECT study_id, label, layer FROM v_network_only" + _ANSWERED)(lambda c: variants.network_only(c))
of_corpus("b_importer_standin", "SELECT study_id, label FROM v_importer" + _ANSWERED)(lambda c: baselines.importer_standin(c.study, c.code_ref))
of_corpus("b_majority_class", "SELECT study_id, (SELECT first FROM study WHERE first IS NOT NULL GROUP BY first ORDER BY count(*) DESC, first LIMIT 1) AS label FROM study")(lambda c: baselines.majority_class(c.study))
of_corpus("b_random_guess", f"SELECT study_id, (SELECT list(label ORDER BY class_id) FROM class_ref WHERE parent IS NOT NULL)[({stream('study_id', 71)} % (SELECT count(*) FROM class_ref WHERE parent IS NOT NULL)) + 1] AS label FROM study")(
    lambda c: baselines.random_guess(c.study, c.class_ref)
)
of_corpus("m_levenshtein", f"SELECT study_id, min(label) AS label, min(d)::INT AS score FROM (SELECT *, min(d) OVER (PARTITION BY study_id) AS top FROM (SELECT study_id, label, levenshtein({NORM.format('description')}, keyword) AS d FROM study JOIN keyword_ref ON levenshtein({NORM.format('description')}, keyword) <= 2)) WHERE d = top GROUP BY study_id HAVING count(DISTINCT label) = 1")(
    lambda c: layers.match_fuzzy(c.study, c.keyword_ref, 2)
)
of_corpus("m_keyword_conflicts", "SELECT a.keyword AS a, b.keyword AS b, max(s.n) AS len FROM keyword_ref a JOIN keyword_ref b ON a.keyword < b.keyword AND a.label <> b.label JOIN subs s ON s.keyword = a.keyword AND contains(b.keyword, s.sub) WHERE length(b.keyword) >= 6 GROUP BY a.keyword, b.keyword")(
    lambda c: keywords.conflicts(c.keyword_ref, 6)
)
of_corpus("m_multilabel", "SELECT s.study_id, list_contains(s.truth, p.label) AS is_correct FROM study s JOIN v_network_l5 p USING (study_id) WHERE p.label IS NOT NULL AND s.truth IS NOT NULL")(
    lambda c: c.study.join(cascade.classify(c), "study_id").where("truth is not null").select("study_id", F.array_contains("truth", F.col("label")).alias("is_correct"))
)
of_corpus("m_grade", graded("hybrid_h1"))(lambda c: evaluate.grade(c.study, variants.hybrid_h1(c), _pairs(c)))
of_corpus("m_truth_sets", "SELECT study_id, array_to_string(truth, '|') AS truth FROM truth_t")(
    lambda c: evaluate.truth_sets(c.study.select("study_id", F.explode("truth").alias("label"))).select("study_id", F.concat_ws("|", "truth").alias("truth"))
)
of_corpus("m_validate_refs", "SELECT 'short keyword' AS problem, label AS item FROM class_ref WHERE length(label) < 4 UNION ALL SELECT 'unknown label', label FROM code_ref WHERE label NOT IN (SELECT label FROM class_ref) UNION ALL SELECT 'duplicate code', code FROM code_ref GROUP BY code HAVING count(*) > 1")(
    lambda c: keywords.validate(c.class_ref, c.class_ref.select(F.col("label").alias("keyword"), "label"), c.code_ref)
)
of_corpus("m_review_queue", "SELECT s.study_id, p.label, b.lead FROM study s LEFT JOIN v_network_only p USING (study_id) LEFT JOIN (SELECT study_id, (w[1] - coalesce(w[2], 0))::BIGINT AS lead FROM (SELECT study_id, list_reverse_sort(list(w)) AS w FROM (SELECT study_id, label, sum(confidence_u)::BIGINT AS w FROM net GROUP BY study_id, label) GROUP BY study_id)) b USING (study_id) WHERE p.label IS NULL OR b.lead < 200000")(
    lambda c: cascade.review_queue(c.study, votes.ballot(network.votes(c.network_scores)), variants.network_only(c), 200_000)
)
of_corpus("m_auto_label", "SELECT l.study_id, series_no, first AS label FROM lines l JOIN truth_t USING (study_id)")(
    lambda c: sampling.label_by_container(c.series, c.study.where("first is not null").select("study_id", F.col("first").alias("label"))).select("study_id", "series_no", "label")
)


def _pairs(c) -> DataFrame:
    return c.class_ref.where("parent is not null").select(F.col("label").alias("truth"), F.col("parent").alias("pred"))


def all_graded(c) -> DataFrame:
    """(variant, study_id, label, layer, grade) of every variant: each layer is computed once, the orders are permuted over one wide table, all variants are graded in one pass."""
    wide = layer_table(c).join(baselines.importer_standin(c.study, c.code_ref).withColumnRenamed("label", "importer"), "study_id", "left")
    x = all_outcomes(wide.join(c.study.select("study_id", "truth"), "study_id"), {"importer": ("importer", 1)})
    return evaluate.graded(x, _pairs(c)).select("variant", "study_id", "label", "layer", "grade")


_COUNTS = "count(*) AS studies, count_if(grade = 'right') AS \"right\", count_if(grade = 'minor') AS minor, count_if(grade = 'major') AS major, count_if(grade = 'unanswered') AS unanswered"
_N = "studies - unanswered"


def _rate(a, b, name):
    return f"round(CASE WHEN {b} = 0 THEN NULL ELSE ({a})::DOUBLE / ({b}) END, 6) AS {name}"


_RATES = {"predictive_power": (_N, "studies"), "accuracy": ('"right"', _N), "minor_rate": ("minor", _N), "minor_share": ("minor", "studies"), "major_rate": ("major", _N)}


def measure_sql(*names):
    return f"SELECT variant, {', '.join(_rate(*_RATES[n], n) for n in names)} FROM (SELECT variant, {_COUNTS} FROM graded_all GROUP BY variant)"


for _q, _names in (("a_predictive_power", ["predictive_power"]), ("a_accuracy", ["accuracy"]), ("a_minor", ["minor_rate", "minor_share"]), ("a_major", ["major_rate"])):
    of_corpus(_q, measure_sql(*_names))(lambda c, names=_names: evaluate.measures(all_graded(c), ["variant"]).select("variant", *names))
of_corpus("a_fig4_counts", f"SELECT variant, {_COUNTS} FROM graded_all GROUP BY variant")(lambda c: evaluate.measures(all_graded(c), ["variant"]).select("variant", "studies", "right", "minor", "major", "unanswered"))
of_corpus("w7_grid", f"SELECT *, {', '.join(_rate(*v, n) for n, v in _RATES.items())} FROM (SELECT variant, {_COUNTS} FROM graded_all GROUP BY variant)")(lambda c: evaluate.measures(all_graded(c), ["variant"]))
of_corpus("a_layers", "SELECT layer, count(*) AS n FROM v_network_l5 WHERE label IS NOT NULL GROUP BY layer")(lambda c: cascade.classify(c).groupBy("layer").agg(F.count(F.lit(1)).alias("n")))
of_corpus("a_contribution", "SELECT round((SELECT count(*) FROM v_network_l5 WHERE layer = 5)::DOUBLE / (SELECT count(*) FROM study), 6) AS contribution_layer, (SELECT round(avg((a.label IS DISTINCT FROM b.label)::INT), 6) FROM v_hybrid_h1 a JOIN v_no_network b USING (study_id)) AS contribution_flip")(
    lambda c: _contribution(c)
)


def _contribution(c):
    wide = layer_table(c)
    n = c.study.select(F.lit(1).alias("one")).groupBy().agg(F.count("one").alias("n"))
    by_layer = outcomes(wide, "network_l5").agg(F.count_if(F.col("layer") == 5).alias("k"))
    flip = evaluate.contribution(c.study, outcomes(wide, "hybrid_h1"), outcomes(wide, "no_network"))
    return by_layer.join(n).join(flip).select(F.round(F.col("k") / F.col("n"), 6).alias("contribution_layer"), "contribution_flip")


of_corpus("a_confusion", "SELECT first AS truth, p.label AS predicted, count(*) AS n FROM study JOIN v_hybrid_h1 p USING (study_id) WHERE first IS NOT NULL AND p.label IS NOT NULL GROUP BY 1, 2")(
    lambda c: c.study.where("first is not null").join(variants.hybrid_h1(c), "study_id").groupBy(F.col("first").alias("truth"), F.col("label").alias("predicted")).agg(F.count(F.lit(1)).alias("n"))
)
of_corpus("a_per_class", "SELECT first AS truth, count(*) AS n, round(avg(coalesce((p.label = first)::INT, 0)), 6) AS accuracy FROM study JOIN v_hybrid_h1 p USING (study_id) WHERE first IS NOT NULL GROUP BY 1")(
    lambda c: c.study.where("first is not null").join(variants.hybrid_h1(c), "study_id", "left").groupBy(F.col("first").alias("truth")).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(F.coalesce((F.col("label") == F.col("first")).cast("int"), F.lit(0))), 6).alias("accuracy"))
)
of_corpus("a_tag_error", "SELECT count(*) AS present, count_if(r.label IS NULL OR NOT list_contains(truth, r.label)) AS wrong, round(avg((r.label IS NULL OR NOT list_contains(truth, r.label))::INT), 6) AS rate FROM study LEFT JOIN code_ref r ON procedure_code = code WHERE procedure_code IS NOT NULL")(
    lambda c: _tag_error(c)
)


def _tag_error(c):
    x = c.study.where("procedure_code is not null").join(F.broadcast(c.code_ref), F.col("procedure_code") == F.col("code"), "left")
    wrong = F.col("label").isNull() | ~F.array_contains("truth", F.col("label"))
    return x.agg(F.count(F.lit(1)).alias("present"), F.count_if(wrong).alias("wrong"), F.round(F.avg(wrong.cast("int")), 6).alias("rate"))


_REL = "SELECT g.layer, g.study_id, max((c1.parent = c2.parent)::INT) AS rel FROM (" + graded("network_l5") + ") g JOIN class_ref c1 ON c1.label = g.label JOIN study s USING (study_id), unnest(s.truth) AS u(t) JOIN class_ref c2 ON c2.label = u.t WHERE g.grade = 'major' GROUP BY 1, 2"
of_corpus("m_related_errors", f"SELECT layer, count(*) AS errors, round(avg(coalesce(rel, 0)), 6) AS related_rate FROM ({_REL}) GROUP BY layer")(
    lambda c: evaluate.related_errors(evaluate.grade(c.study, cascade.classify(c), _pairs(c)), c.study, c.class_ref).select("layer", "errors", "related_rate")
)


#: Right, minor and major answers of 843 studies behind the published percentages; the rest got none.
PUBLISHED = {"hybrid": (776, 22, 39), "network": (607, 86, 142), "importer": (672, 11, 128)}
_CYCLE = 843
_SLOT = f"((c_custkey % {_CYCLE}) * 521) % {_CYCLE}"  # every 843 keys in a row take each slot once, and a few keys lie apart


def _answer(right, minor, major):
    return f"CASE WHEN slot < {right} THEN truth WHEN slot < {right + minor} THEN pred WHEN slot < {right + minor + major} THEN other END"


@query("a_published_counts", f"""
WITH pairs AS (SELECT n_nationkey, n_name AS truth, r_name AS pred, CASE WHEN n_name = (SELECT min(n_name) FROM nation) THEN (SELECT max(n_name) FROM nation) ELSE (SELECT min(n_name) FROM nation) END AS other FROM nation JOIN region ON n_regionkey = r_regionkey),
study AS (SELECT truth, pred, other, {_SLOT} AS slot FROM customer JOIN pairs ON c_nationkey = n_nationkey),
said AS ({" UNION ALL ".join(f"SELECT '{v}' AS variant, truth, {_answer(*n)} AS label FROM study" for v, n in PUBLISHED.items())}),
general AS (SELECT DISTINCT truth, pred FROM pairs),
g AS (SELECT variant, CASE WHEN label IS NULL THEN 'unanswered' WHEN label = said.truth THEN 'right' WHEN general.pred IS NOT NULL THEN 'minor' ELSE 'major' END AS grade FROM said LEFT JOIN general ON general.truth = said.truth AND general.pred = label)
SELECT variant, {', '.join(_rate(*v, n) for n, v in _RATES.items())} FROM (SELECT variant, {_COUNTS} FROM g GROUP BY variant)""")
def a_published_counts(spark, sf_dir):
    """The evaluator on answers in the published proportions: a customer of a known nation is a study, its region the too general answer, and every 843 keys in a row get exactly the published counts."""
    nation = table(spark, sf_dir, "nation")
    ends = F.broadcast(nation.agg(F.min("n_name").alias("lo"), F.max("n_name").alias("hi")))
    pairs = nation.join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).join(ends)
    pairs = pairs.select("n_nationkey", F.col("n_name").alias("truth"), F.col("r_name").alias("pred"), F.when(F.col("n_name") == F.col("lo"), F.col("hi")).otherwise(F.col("lo")).alias("other"))
    study = table(spark, sf_dir, "customer").join(F.broadcast(pairs), F.col("c_nationkey") == F.col("n_nationkey")).select("truth", "pred", "other", F.expr(_SLOT).alias("slot"))
    said = F.array(*(F.struct(F.lit(v).alias("variant"), F.expr(_answer(*n)).alias("label")) for v, n in PUBLISHED.items()))
    answers = study.select(F.array("truth").alias("truth"), F.inline(said))
    return evaluate.measures(evaluate.graded(answers, pairs.select("truth", "pred")), ["variant"]).select("variant", *_RATES)


@query("w9_geography", """
WITH said AS (SELECT c_custkey, n_name AS truth, CASE WHEN c_custkey % 5 < 2 THEN r_name WHEN c_custkey % 5 = 2 THEN n_name WHEN c_custkey % 5 = 3 THEN (SELECT min(r_name) FROM region) END AS label FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey),
general AS (SELECT n_name AS truth, r_name AS pred FROM nation JOIN region ON n_regionkey = r_regionkey),
g AS (SELECT CASE WHEN label IS NULL THEN 'unanswered' WHEN label = said.truth THEN 'right' WHEN general.pred IS NOT NULL THEN 'minor' ELSE 'major' END AS grade FROM said LEFT JOIN general ON general.truth = said.truth AND general.pred = label)
SELECT grade, count(*) AS n FROM g GROUP BY grade""")
def w9_geography(spark, sf_dir):
    """Truth is a customer's nation. Two fifths of the answers are its region (too general), a fifth the nation itself, a fifth one region for all (mostly wrong), a fifth none."""
    nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    pairs = nation.join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("truth"), F.col("r_name").alias("pred"))
    x = table(spark, sf_dir, "customer").join(F.broadcast(pairs), F.col("c_nationkey") == F.col("k")).join(F.broadcast(region.agg(F.min("r_name").alias("one"))), F.lit(True))
    fifth = F.col("c_custkey") % 5
    said = F.when(fifth < 2, F.col("pred")).when(fifth == 2, F.col("truth")).when(fifth == 3, F.col("one"))
    answers = x.select(F.col("c_custkey").alias("study_id"), F.array("truth").alias("truth"), said.alias("label"))
    return evaluate.graded(answers, pairs.select("truth", "pred")).groupBy("grade").agg(F.count(F.lit(1)).alias("n"))


def _w10_sql() -> str:
    words = "(SELECT keyword, label FROM keyword_ref UNION ALL SELECT a || ' study', a || ' any' FROM (SELECT DISTINCT split_part(label, ' ', 1) AS a FROM class_ref WHERE parent IS NOT NULL ORDER BY a LIMIT {n}))"
    one = (
        "SELECT {n}::INT AS decoys, count(*) AS answered, count_if(p.label = first) AS \"right\" FROM study s JOIN (SELECT value, min(label) AS label FROM (SELECT *, max(score) OVER (PARTITION BY value) AS top FROM "
        "(SELECT value, w.label, max(k) AS score FROM (SELECT DISTINCT " + NORM.format("description") + " AS value FROM study WHERE first IS NOT NULL) v JOIN " + words + " w ON true, unnest(range(1, length(w.keyword) - 4)) AS u(i), unnest(range(6, length(w.keyword) + 1)) AS l(k) "
        "WHERE length(w.keyword) >= 6 AND i + k - 1 <= length(w.keyword) AND contains(value, substr(w.keyword, i, k)) GROUP BY value, w.label "
        "UNION ALL SELECT value, w.label, length(w.keyword) FROM (SELECT DISTINCT " + NORM.format("description") + " AS value FROM study WHERE first IS NOT NULL) v JOIN " + words + " w ON length(w.keyword) IN (4, 5) AND list_contains(string_split_regex(value, '[^a-z0-9]+'), w.keyword))) "
        "WHERE score = top GROUP BY value HAVING count(DISTINCT label) = 1) p ON p.value = " + NORM.format("s.description") + " WHERE first IS NOT NULL"
    )
    return sql(" UNION ALL ".join(one.format(n=n) for n in (0, 2, 4, 8)))


@query("w10_overload", _w10_sql())
def w10_overload(spark, sf_dir):
    """Decoy keywords against accuracy of the partial layer: (decoys, answered, right)."""
    c = corpus(spark, sf_dir)
    study = c.study.where("first is not null").select("study_id", "description", "first")
    out = None
    for n in (0, 2, 4, 8):
        decoys = c.class_ref.where("parent is not null").select(F.split("label", " ")[0].alias("a")).distinct().orderBy("a").limit(n).select(F.concat("a", F.lit(" study")).alias("keyword"), F.concat("a", F.lit(" any")).alias("label"))
        p = layers.match_partial(study, c.keyword_ref.unionByName(decoys), short_match="word")
        x = study.join(p, "study_id").agg(F.lit(n).alias("decoys"), F.count(F.lit(1)).alias("answered"), F.count_if(F.col("label") == F.col("first")).alias("right"))
        out = x if out is None else out.unionByName(x)
    return out

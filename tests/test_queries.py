"""A part of the registry against the oracle, variants against the grid, and plans."""

import io
from contextlib import redirect_stdout

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from studymap.plans import cascade, variants
from studymap.plans.grid import layer_table, outcomes
from studymap.queries import registry
from studymap.queries.orders_q import corpus

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v):
    if isinstance(v, bool) or v is None or isinstance(v, str):
        return str(v)
    try:
        return f"{float(v):.5f}"
    except (TypeError, ValueError):
        return str(v).replace(" 00:00:00", "")


@pytest.mark.parametrize("name", ["a_cv_ci", "w12_label_noise", "w13_learning_curve", "w14_class_sizes", "m_layer1_code", "m_layer3_partial", "m_rules_conditional", "m_majority", "m_cascade", "m_hybrid_h1", "m_cascade_calibrated", "m_votes_from_logits", "m_network_infer", "w10_overload", "b_random_guess", "w1c_log_odds", "w9_geography", "m_temp_fit_ece", "m_sim_corr", "m_sim_sweep", "w2b_binary_calibration", "m_img_mip", "a_tag_error", "g_rollup", "w_islands", "t_session", "t_watermark_late", "t_stateful_votes", "t_stream_stream_join", "w3_page_layers"])
def test_query_equals_oracle(spark, small, name):
    q = registry()[name]
    df = q.run(spark, small)
    names = sorted(df.columns)
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    rel = con.sql(q.sql)
    assert sorted(rel.columns) == names
    at = [rel.columns.index(c) for c in names]
    mine = sorted(tuple(plain(r[c]) for c in names) for r in df.collect())
    assert mine == sorted(tuple(plain(r[i]) for i in at) for r in rel.fetchall())


def test_cascade_equals_grid(spark, small):
    c = corpus(spark, small)
    wide = layer_table(c)
    for name, got in (("network_l2", variants.network_at(c, 2)), ("no_network", variants.no_network(c)), ("hybrid_h2", variants.hybrid_h2(c))):
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, outcomes(wide, name).collect()))


def test_network_without_votes_is_no_network(spark, small):
    c = corpus(spark, small)
    mute = c.but(network_scores=c.network_scores.limit(0))
    assert sorted(map(tuple, variants.hybrid_h1(mute).select("study_id", "label").collect())) == sorted(map(tuple, variants.no_network(c).select("study_id", "label").collect()))


def test_ablation_shape(spark, small):
    rows = {r["variant"]: r for r in registry()["w7_grid"].run(spark, small).collect()}
    assert rows["hybrid_h1"]["accuracy"] >= rows["no_network"]["accuracy"]
    assert rows["hybrid_h1"]["predictive_power"] >= rows["no_network"]["predictive_power"]
    assert rows["network_l5"]["predictive_power"] > rows["no_network"]["predictive_power"]


def test_compiled_rules_equal_joined_ones(spark, small):
    from studymap.operators import rules, votes

    c = corpus(spark, small)
    v = votes.metadata_votes(c.series, c.keyword_ref, c.keys).join(c.series.select("study_id", "series_no", "modality"), ["study_id", "series_no"])
    v = v.select("study_id", "label", "weight_u", "origin", "series_no", "modality")
    for tier in ("full", "min"):
        assert sorted(map(tuple, rules.apply(v, c.rule_ref, tier).collect())) == sorted(map(tuple, rules.apply(v, c.rule_ref, tier, most=1).collect()))


def test_large_references_are_joined_by_shuffle(spark):
    from studymap.functions import text

    ref = spark.range(50).select(F.concat(F.lit("keyword number "), "id").alias("keyword"))
    with pytest.raises(ValueError):
        text.checked_broadcast(ref, most=10, equi=False)
    assert text.checked_broadcast(ref, most=10) is ref


def test_held_tables_are_made_once(spark, small):
    c = corpus(spark, small)
    assert c.study is c.study and c.class_ref is c.class_ref
    assert "LocalTableScan" in plan(c.class_ref)


def plan(df):
    out = io.StringIO()
    with redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def test_plans(spark, small):
    c = corpus(spark, small)
    from studymap.functions import text
    from studymap.functions.lineage import cut
    from studymap.operators import layers, votes

    one = plan(layers.match_code(c.study.select("study_id", "procedure_code", "description"), c.code_ref))
    assert "BroadcastHashJoin" in one and "CartesianProduct" not in one
    x = cut(c.study.select("study_id", text.normalise(F.col("description")).alias("value")).where("value is not null"))
    partial = plan(layers.best_labels(layers.keyword_scores(x.select("value").distinct(), c.keyword_ref)))
    assert partial.count("Exchange hashpartitioning") + partial.count("REPARTITION") <= 4 and "CartesianProduct" not in partial and "NestedLoop" not in partial
    ballot = spark.range(100).select((F.col("id") % 7).alias("study_id"), F.lit("a").alias("label"), F.col("id").alias("weight_u"))
    assert plan(votes.decide(ballot)).count("Exchange hashpartitioning") <= 2
    scan = plan(spark.read.parquet(f"{small}/part.parquet").where("p_size >= 40").select("p_partkey"))
    assert "PushedFilters: [IsNotNull(p_size), GreaterThanOrEqual(p_size,40)]" in scan


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_leakage_beyond_100_000_passages(spark, tmp_path):
    """Every passage is searched: long, short, cut inside words, with double spaces and empty documents around; ids repeat and may be null."""
    n = 100_300
    passages = spark.range(0, n, 1, 4).select(F.col("id").alias("item_id"), F.concat(F.lit("alpha beta gamma delta epsilon zeta n"), "id", F.lit("x tail")).alias("text"))
    extra = spark.createDataFrame([(n, "short one"), (n + 1, None), (n + 2, "ut  of a  few odd spaces he")], "item_id long, text string")
    passages.unionByName(extra).write.parquet(f"{tmp_path}/benchmark.parquet")
    rows = [(i, f"before malpha beta gamma delta epsilon zeta n{at}x tailing after") for i, at in ((1, 0), (2, 50_000), (3, n - 1), (4, n))]
    rows += [(5, "a short one"), (6, "shor tone"), (7, "but  of a  few odd spaces here"), (8, ""), (9, None), (10, "x"), (10, "the short ones"), (None, "short one")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = [r[0] for r in registry()["w11_leakage"].run(spark, str(tmp_path)).collect()]
    assert sorted(got, key=str) == sorted([1, 2, 3, 5, 7, 10, None], key=str)


def test_training_cap_does_not_cut_what_is_evaluated(spark, tmp_path):
    from studymap.queries import models_q

    rows = [(i, f"text {i} of {lang}", lang, f"src{i % 3}") for i in range(900) for lang in ["en" if i % 3 else "de"]]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    x = models_q._documents(spark, str(tmp_path), 3).select("doc_id", "lang", "fold", "trains").collect()
    assert len(x) == 900
    for f in range(5):
        for lang, n in (("en", 600), ("de", 300)):
            assert sum(r["trains"] and r["fold"] != f and r["lang"] == lang for r in x) == 200
            assert sum(r["fold"] == f and r["lang"] == lang for r in x) == n // 5


def test_word_heads_defined_on_odd_texts(spark):
    """Null texts are left out, empty ones get the largest class; a word of one class decides; what a fold holds never trains for it."""
    from studymap.operators import word_heads

    rows = [(i, "alpha alpha" if i % 3 else "beta", i % 5, int(i % 3 == 0)) for i in range(60)] + [(60, None, 0, 0), (61, "", 0, 0), (62, "only", 1, 1), (63, "only", 1, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, fold int, class_id int")
    training = word_heads.training_rows(docs, 400)
    assert training.where("class_id is null").count() == 0 and training.count() == 63
    told = {(r["doc_id"], r["setting"]): r["predicted"] for r in word_heads.judged(docs, training.withColumn("setting", F.explode(F.array(F.lit(0), F.lit(1)))), 2, 2, weighted=(1,)).collect()}
    assert len(told) == 63 * 2 and (60, 0) not in told
    assert all(told[i, s] == int(i % 3 == 0) for i in range(60) for s in (0, 1))
    assert told[61, 0] == told[61, 1] == told[62, 0] == 0


def test_gram_shares_do_not_depend_on_blocks():
    from studymap.queries.models_q import gram_shares

    text = "straße und \U0001f600 wörter " * 40
    assert abs(gram_shares(text, 3, 512) - gram_shares(text, 3, 512, block=7)).max() == 0
    for t in ("", "a", "ab"):
        assert gram_shares(t, 3, 64).sum() == 1


def test_bags_of_lines_are_judged_by_a_head_of_other_folds(spark, tmp_path):
    rows = [(i, "\n".join([lang, word * 3, "", word]), lang) for i in range(150) for lang, word in [(("de", "lichung "), ("en", "thing of "), ("fr", "eaux "))[i % 3]]] + [(150, "\n\n", "de"), (151, None, "de")]
    spark.createDataFrame([(*r, "src1") for r in rows], "doc_id long, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["pooling"]: (r["n"], r["accuracy"]) for r in registry()["m_mil_fit"].run(spark, str(tmp_path)).collect()}
    assert set(got) == {"max", "mean"}
    assert all(n in (30, 31) and accuracy == 1 for n, accuracy in got.values())

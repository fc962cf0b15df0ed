"""Methods against hand-made cases, closed forms and brute force."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from studymap.functions import images, text
from studymap.functions.portable import beta_knots, incomplete_beta
from studymap.operators import calibrate, evaluate, keywords, layers, network, rules, sampling, simulate, votes


def lcs(a, b):
    best = 0
    for i in range(len(a)):
        for j in range(i + 1, len(a) + 1):
            if a[i:j] in b:
                best = max(best, j - i)
    return best


def test_common_substring_equals_brute_force(spark):
    rng = random.Random(3)
    words = ["".join(rng.choice("abc") for _ in range(rng.randrange(0, 14))) for _ in range(40)]
    words += ["red widget", "hot widget", "gizmo", "gizmos", "abababab", "babababa", "", "éèê plätte", "plätte"]
    words = sorted(set(words))
    left = spark.createDataFrame([(w, w) for w in words], "a string, t string")
    right = spark.createDataFrame([(w, w) for w in words], "b string, t string")
    got = {(r["a"], r["b"]): r["len"] for r in text.lcsubstr_len(left, right, 4).collect()}
    want = {(a, b): lcs(a, b) for a in words for b in words if lcs(a, b) >= 4}
    assert got == want
    assert got["red widget", "hot widget"] == 7 and got["abababab", "babababa"] == 7


def study(spark, rows):
    return spark.createDataFrame(rows, "study_id long, procedure_code string, description string")


KEYS = [("red widget", "red widget"), ("hot widget", "hot widget"), ("gizmo", "gizmo"), ("ring", "ring"), ("rod", "rod"), ("big anvil", "anvil")]


def test_partial_layer_thresholds_and_ties(spark):
    kw = spark.createDataFrame(KEYS, "keyword string, label string")
    s = study(spark, [(1, None, "ed widget"), (2, None, " widget x"), (3, None, "a GIZMO here"), (4, None, "string"), (5, None, "the  ring"), (6, None, "rod"), (7, None, None), (8, None, "   "), (9, None, "big anv")])
    got = {r["study_id"]: (r["label"], r["score"]) for r in layers.match_partial(s, kw).collect()}
    assert got == {1: ("red widget", 9), 3: ("gizmo", 5), 5: ("ring", 4), 9: ("anvil", 7)}
    first = {r["study_id"]: r["label"] for r in layers.match_partial(s, kw, tie="first").collect()}
    assert first[2] == "hot widget"
    inside = {r["study_id"] for r in layers.match_partial(s, kw, short_match="substring").collect()}
    assert 4 in inside


def test_exact_layers_ignore_case_and_blanks(spark):
    s = study(spark, [(1, " c001", None), (2, "C002", " Red   Widget "), (3, None, None), (4, "", "")])
    codes = spark.createDataFrame([("C001", "a")], "code string, label string")
    desc = spark.createDataFrame([("red widget", "b")], "description string, label string")
    assert [(r["study_id"], r["label"]) for r in layers.match_code(s, codes).collect()] == [(1, "a")]
    assert [(r["study_id"], r["label"]) for r in layers.match_description(s, desc).collect()] == [(2, "b")]


VOTE = "study_id long, label string, weight_u long, origin string, series_no int"


def test_decisions(spark):
    rows = [(1, "a", 10), (1, "a", 10), (1, "b", 15), (2, "a", 5), (2, "b", 5), (3, "a", 1), (3, "b", 1), (3, "c", 1), (4, "x", 7), (5, None, 9), (6, "a", 0), (7, "a", 4), (7, "b", 3), (7, "c", 3)]
    v = spark.createDataFrame([(s, x, w, "t", i) for i, (s, x, w) in enumerate(rows)], VOTE)
    got = {r["study_id"]: (r["label"], r["weight_u"], r["runner_up"]) for r in votes.decide(v).collect()}
    assert got == {1: ("a", 20, "b"), 4: ("x", 7, None), 7: ("a", 4, "c")}
    assert {r["study_id"] for r in votes.decide(v, "absolute").collect()} == {1, 4}
    for n in (1, 16):
        assert {r["study_id"]: r["label"] for r in votes.decide(v.repartition(n)).collect()} == {k: x[0] for k, x in got.items()}
    assert votes.decide(v.limit(0)).count() == 0


def test_rules(spark):
    v = spark.createDataFrame([(1, "a", 100, "tag:name", 1, "CT"), (1, "b", 100, "tag:name", 2, "PET"), (1, "c", 100, "tag:brand", 2, "CT"), (2, "b", 100, "network", 1, "CT")], VOTE + ", modality string")
    r = rules.rule_table(spark, [(1, "core", None, "brand", None, None, "drop", None, None), (2, "core", "PET", None, None, None, "reweight", None, 0.5), (3, "extended", None, None, "b", "a", "relabel", "z", None), (4, "extended", None, None, "b", "a", "relabel", "y", None)])
    full = sorted((x["study_id"], x["label"], x["weight_u"]) for x in rules.apply(v, r).collect())
    assert full == [(1, "a", 100), (1, "z", 50), (2, "b", 100)]
    core = sorted((x["study_id"], x["label"], x["weight_u"]) for x in rules.apply(v, r, "min").collect())
    assert core == [(1, "a", 100), (1, "b", 50), (2, "b", 100)]


def test_silent_modality_has_no_network(spark):
    s = spark.createDataFrame([(1, "PET"), (1, "CT"), (2, "PET"), (3, None)], "study_id long, modality string")
    ref = spark.createDataFrame([("PET", None, False), ("CT", "dense", True)], "modality string, network string, votes boolean")
    assert [(r["study_id"], r["network"]) for r in network.route(s, ref).collect()] == [(1, "dense")]


def planted(spark, n=4000, temperature=3.0):
    rng = np.random.default_rng(0)
    z = rng.normal(size=(n, 4)) * 2
    p = np.exp(z) / np.exp(z).sum(1, keepdims=True)
    truth = [int(rng.choice(4, p=q)) for q in p]
    return spark.createDataFrame([(i, "n", t, (temperature * r).tolist()) for i, (t, r) in enumerate(zip(truth, z))], "row_id long, network string, truth_idx int, logits array<double>")


def test_temperature_is_recovered_and_scales(spark):
    a, b = planted(spark, temperature=1.0), planted(spark, temperature=3.0)
    ta, tb = calibrate.fit(a, objective="nll").first(), calibrate.fit(b, objective="nll").first()
    assert math.isclose(tb["temperature"], 3 * ta["temperature"], rel_tol=1e-9) and 0.85 < ta["temperature"] < 1.2
    ea, eb = calibrate.fit(a).first(), calibrate.fit(b).first()
    assert math.isclose(eb["temperature"], 3 * ea["temperature"], rel_tol=1e-9) and not eb["at_edge"]
    raw = calibrate.ece(calibrate.apply(b), ["network"]).first()["ece"]
    assert 0 <= eb["ece"] <= raw <= 1
    hot, cold = (calibrate.apply(b, t).select("row_id", "predicted", "hit").collect() for t in (0.2, 8.0))
    assert hot == cold  # scaling never changes a prediction
    refined = calibrate.fit(b, rounds=2).first()
    assert refined["ece"] <= eb["ece"] + 1e-12


def test_simulation_meets_closed_forms(spark):
    s = simulate.studies(spark, 200_000, 8)
    for alpha, k, want in ((0.5, 1, 0.5), (0.5, 2, 22 / 35), (0.25, 2, 5 / 14), (0.75, 2, 6 / 7)):
        got = simulate.run(s, alpha, k).first()
        assert abs(got["accuracy"] - want) < 5 * got["sd_mean"] + 2e-3, (alpha, k, got)
    unc, cor = (simulate.run(s, 0.5, 3, m).first()["accuracy"] for m in ("uncorrelated", "correlated"))
    assert abs(unc - 0.720) < 0.006 and abs(cor - 0.607) < 0.006 and cor < unc
    check = simulate.check_calibrated(simulate.studies(spark, 50_000, 8), 0.9, 2).first()
    assert abs(check["hit_rate"] - 0.9) < 0.005 and check["ece"] < 0.01


def test_inline_decision_equals_votes(spark):
    x = simulate.votes(simulate.studies(spark, 3000, 4), 0.5, 4)
    inline = {r[0]: r[1] for r in x.select("study", simulate.decide_inline(F.col("v"))).collect() if r[1] is not None}
    flat = x.select(F.col("study").alias("study_id"), F.explode("v").alias("v")).select("study_id", F.col("v.label").cast("string").alias("label"), F.col("v.weight_u").alias("weight_u"))
    assert inline == {r["study_id"]: int(r["label"]) for r in votes.decide(flat).collect()}


def test_grid_equals_single_cells(spark):
    s = simulate.studies(spark, 3000, 4)
    got = {(r["alpha"], r["k"], r["mode"]): r for r in simulate.grid(s, (0.1, 0.25, 0.5, 0.75), (1, 3), weight="unit", batches=10).collect()}
    assert len(got) == 16
    for (a, k, m), r in got.items():
        one = simulate.run(s, a, k, m, "unit").first()
        assert (r["n"], round(r["accuracy"], 9)) == (one["n"], round(one["accuracy"], 9))
        assert 0 < r["sd_batches"] < 0.1



def test_beta_law():
    assert abs(incomplete_beta(2, 2, 0.3) - (3 * 0.3**2 - 2 * 0.3**3)) < 1e-12
    assert abs(incomplete_beta(1, 3, 0.2) - (1 - 0.8**3)) < 1e-12
    for mean in (0.5, 0.814, 0.971):
        k = np.array(beta_knots(mean)) / 1e6
        # Straight lines between 101 quantiles lose up to half a per cent of the lowest hundredth's width.
        assert (np.diff(k) >= 0).all() and abs(((k[1:] + k[:-1]) / 2).mean() - mean) < 5e-3 * max(k[1], 0.4)


def test_splines():
    for n, m in ((6, 11), (5, 17), (8, 8)):
        w = images.spline_matrix(n, m)
        x, at = np.arange(n), np.linspace(0, n - 1, m)
        f = lambda t: 0.3 * t**3 - t**2 + 2 * t - 1
        assert np.allclose(w @ f(x), f(at))
    assert np.allclose(images.spline_matrix(7, 7), np.eye(7))
    assert np.allclose(images.spline_matrix(4, 9, 1) @ np.arange(4), np.linspace(0, 3, 9))


def test_images(spark):
    a = [float(v) for v in range(16)]
    x = spark.createDataFrame([(1, a), (2, [5.0] * 16)], "k long, d array<double>")
    turned = F.col("d")
    for _ in range(4):
        turned = images.rotate(turned, 4)
    r = x.select("k", turned.alias("r"), images.flip_rows(images.flip_rows(F.col("d"), 4, 4), 4, 4).alias("f"), images.normalise(F.col("d")).alias("n")).orderBy("k").collect()
    assert r[0]["r"] == a and r[0]["f"] == a and r[1]["n"] == [0.0] * 16 and r[0]["n"][-1] == 1.0
    pix = spark.createDataFrame([(1, 2, 2, 39, [float(i) for i in range(156)]), (2, 2, 2, 40, [float(i) for i in range(160)])], "key long, nx int, ny int, nz int, data array<double>")
    got = {q["key"]: q["channels"] for q in images.prepare(pix, 2).collect()}
    assert np.allclose(got[1][0], np.arange(4) / 155) and np.allclose(got[2][0], np.arange(156, 160) / 159)


def test_grades_and_published_rates(spark):
    s = spark.createDataFrame([(1, ["a b"]), (2, ["a b", "c b"]), (3, ["a b"]), (4, ["a b"])], "study_id long, truth array<string>")
    p = spark.createDataFrame([(1, "b"), (2, "c b"), (3, "z")], "study_id long, label string")
    m = spark.createDataFrame([("a b", "b")], "truth string, pred string")
    assert {r["study_id"]: r["grade"] for r in evaluate.grade(s, p, m).collect()} == {1: "minor", 2: "right", 3: "major", 4: "unanswered"}
    row = evaluate.measures(evaluate.grade(s, p, m).where("false")).first()
    assert row["studies"] == 0 and row["accuracy"] is None
    x = evaluate.with_rates(spark.createDataFrame([(843, 776, 22, 39, 6)], "studies long, right long, minor long, major long, unanswered long")).first()
    assert [round(100 * x[c], 2) for c in ("predictive_power", "accuracy", "minor_rate", "minor_share")] == [99.29, 92.71, 2.63, 2.61]


def test_interval(spark):
    acc = [0.8, 0.82, 0.84, 0.86, 0.88]
    r = evaluate.t_interval(spark.createDataFrame([(i, a) for i, a in enumerate(acc)], "fold int, acc double"), []).first()
    half = 2.776445 * np.std(acc, ddof=1) / math.sqrt(5)
    assert abs(r["accuracy"] - 0.84) < 1e-6 and abs(r["hi"] - 0.84 - half) < 1e-5


def test_sampling(spark):
    x = spark.range(0, 5000).select(F.col("id").alias("k"), F.when(F.col("id") % 10 == 0, "rare").otherwise("common").alias("c"))
    capped = {r["c"]: r["count"] for r in sampling.cap_per_class(x, "c", "k", 100).groupBy("c").count().collect()}
    assert capped == {"rare": 100, "common": 100}
    sizes = [r["count"] for r in sampling.folds(x, "c", "k").groupBy("c", "fold").count().collect()]
    assert sorted(set(sizes)) == [100, 900]
    part = {r["part"]: r["count"] for r in sampling.split(x, "k").groupBy("part").count().collect()}
    assert abs(part["train"] - 4000) < 150


def test_catalogue(spark):
    kw = spark.createDataFrame([("upper spine", "a"), ("lower spine", "b"), ("hip", "c")], "keyword string, label string")
    assert [tuple(r) for r in keywords.conflicts(kw, 6).collect()] == [("lower spine", "upper spine", 8)]
    cls = spark.createDataFrame([("a",), ("b",)], "label string")
    codes = spark.createDataFrame([("1", "a"), ("1", "b")], "code string, label string")
    assert {tuple(r) for r in keywords.validate(cls, kw, codes).collect()} == {("short keyword", "hip"), ("unknown label", "c"), ("duplicate code", "1")}
    assert {(r["keyword"], r["change"]) for r in keywords.difference(kw, kw.where("label <> 'a'")).collect()} == {("upper spine", "removed")}
    with pytest.raises(ValueError):
        text.checked_broadcast(kw, 2, equi=False)  # with an equality it is joined by shuffle instead


def test_study_folder_source(spark, tmp_path):
    from studymap.sources.files import StudyFolder

    (tmp_path / "a.hdr").write_text("Code: C001\nDescription: red: widget\nnoise\n")
    (tmp_path / "b.hdr").write_text("")
    (tmp_path / "c.txt").write_text("Code: ignored\n")
    spark.dataSource.register(StudyFolder)
    got = {tuple(r) for r in spark.read.format("study_folder").option("path", str(tmp_path)).load().collect()}
    assert got == {("a.hdr", "Code", "C001"), ("a.hdr", "Description", "red: widget")}

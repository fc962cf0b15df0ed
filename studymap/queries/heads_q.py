"""Queries that train on capped samples of the documents and judge whole held-out folds: interval, label noise, learning curve, class sizes."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from ..functions.lineage import cut
from ..functions.portable import MICRO, stream
from ..operators import evaluate, network, sampling, word_heads
from ..sources.texts import LANGS
from . import query, table

CAP = 200
NOISES = (0, 5, 10, 20)
CAPS = (25, 50, 100, 200)
_C = range(len(LANGS))
_NAMES = "[" + ", ".join(f"'{x}'" for x in LANGS) + "]"
_MOVED = f"(CASE WHEN {stream('doc_id', 61)} % 100 < {{noise}} THEN {stream('doc_id', 62)} % {len(LANGS)} ELSE class_id END)"


def _documents(spark, sf_dir, *more):
    """Documents that have a text and one of the four languages, with class and fold (and columns `more`)."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", *more).where(F.col("text").isNotNull() & F.col("lang").isin(*LANGS))
    keys = sampling.folds(docs.select("doc_id", "lang"), "lang", "doc_id").withColumn("class_id", (F.array_position(F.array(*map(F.lit, LANGS)), F.col("lang")) - 1).cast("int"))
    return docs.drop("lang").join(cut(keys), "doc_id")


def _accuracy(docs, told, by=()):
    """Accuracy of each setting (and `by`) in each fold."""
    x = told.join(docs.select("doc_id", "fold", "class_id", *by), "doc_id")
    return x.groupBy("setting", "fold", *by).agg(F.avg((F.col("predicted") == F.col("class_id")).cast("int")).alias("acc"))


def _sql(training, weighted=()):
    """CTEs up to `told`: doc_id, fold, class_id, lang, setting, predicted. `training` is SQL over `ranked` for doc_id, fold, setting, class_id."""
    heavy = f"setting IN ({', '.join(map(str, weighted))})" if weighted else "false"
    per_class = ", ".join(f"count(*) FILTER (class_id = {c}) AS {{0}}{c}" for c in _C)
    every = " + ".join(f"all{c}" for c in _C)
    weights = ", ".join(f"CASE WHEN {heavy} THEN ({every})::DOUBLE / ({len(LANGS)} * greatest(all{c}, 1)) ELSE 1.0::DOUBLE END AS k{c}" for c in _C)
    total = " + ".join(f"all{c} * k{c}" for c in _C)
    held = " + ".join(f"n{c} * k{c}" for c in _C)
    prior = f"{word_heads.PRIOR}::DOUBLE"
    logs = ", ".join(f"round(ln((n{c} * k{c} + {prior} * (({held}) / total)) / (all{c} * k{c} + {prior})) * {MICRO})::BIGINT AS w{c}" for c in _C)
    score = ", ".join(f"coalesce(z{c}, 0) + round(ln((all{c} * k{c} + 1) / (total + 1)) * {MICRO})::BIGINT" for c in _C)
    return f"""
WITH docs AS (SELECT doc_id, text, lang, (list_position({_NAMES}, lang) - 1)::INT AS class_id,
  ((row_number() OVER (PARTITION BY lang ORDER BY {stream('doc_id', 3)}, doc_id) - 1) % {word_heads.FOLDS})::INT AS fold
  FROM documents WHERE text IS NOT NULL AND list_contains({_NAMES}, lang)),
ranked AS (SELECT doc_id, fold, class_id, row_number() OVER (PARTITION BY fold, lang ORDER BY {stream('doc_id', 1)}, doc_id) AS r FROM docs),
training AS ({training}),
taught AS (SELECT doc_id, setting, class_id, test FROM training, unnest(range(0, {word_heads.FOLDS})) AS u(test) WHERE test <> fold),
words AS (SELECT doc_id, fold, word FROM (SELECT DISTINCT doc_id, fold, unnest(string_split_regex(lower(text), '[^a-zà-ÿß]+')) AS word FROM docs) WHERE word <> ''),
counts AS (SELECT word, test, setting, {per_class.format("n")} FROM words JOIN taught USING (doc_id) GROUP BY ALL),
plain_sizes AS (SELECT test, setting, {per_class.format("all")} FROM taught GROUP BY ALL),
weighed AS (SELECT *, {weights} FROM plain_sizes),
sizes AS (SELECT *, {total} AS total FROM weighed),
known AS (SELECT word, test, setting, {logs} FROM counts JOIN sizes USING (test, setting)),
sums AS (SELECT doc_id, setting, {", ".join(f"sum(w{c})::BIGINT AS z{c}" for c in _C)} FROM words JOIN known ON words.word = known.word AND fold = test GROUP BY ALL),
scores AS (SELECT docs.doc_id, fold, class_id, lang, sizes.setting, [{score}] AS z
  FROM docs JOIN sizes ON fold = test LEFT JOIN sums ON sums.doc_id = docs.doc_id AND sums.setting = sizes.setting),
told AS (SELECT doc_id, fold, class_id, lang, setting, list_position(z, list_max(z)) - 1 AS predicted FROM scores)"""


_ACC = "avg(acc)", f"{evaluate.T_FOUR} * stddev_samp(acc) / sqrt(5)"
_INTERVAL = f"round({_ACC[0]}, 6) AS accuracy, round({_ACC[0]} - {_ACC[1]}, 6) AS lo, round({_ACC[0]} + {_ACC[1]}, 6) AS hi"
_BY_FOLD = "(SELECT setting, fold, avg((predicted = class_id)::INT) AS acc FROM told GROUP BY ALL)"


def _one(rank, setting, class_id="class_id"):
    return f"SELECT doc_id, fold, {setting} AS setting, {class_id} AS class_id FROM ranked WHERE r <= {rank // 4}"


def _settings(rows):
    """One table of the training rows of all settings, in their order."""
    return reduce(lambda a, b: a.unionByName(b), [x.select("doc_id", "fold", F.lit(s).alias("setting"), "class_id") for s, x in enumerate(rows)])


def _named(values, name):
    return F.element_at(F.array(*map(F.lit, values)), F.col("setting") + 1).alias(name)


@query("a_cv_ci", _sql(_one(CAP, 0)) + f" SELECT {_INTERVAL} FROM {_BY_FOLD}")
def a_cv_ci(spark, sf_dir):
    """Accuracy over five folds with its interval, of a word-evidence head trained on at most 200 documents of a language."""
    docs = _documents(spark, sf_dir)
    told = word_heads.judged(docs, _settings([word_heads.training_rows(docs, CAP)]), 1, len(LANGS))
    return evaluate.t_interval(_accuracy(docs, told), [])


@query("w12_label_noise", _sql(" UNION ALL ".join(_one(CAP, s, _MOVED.format(noise=n)) for s, n in enumerate(NOISES))) + f" SELECT {list(NOISES)}[setting + 1] AS noise, {_INTERVAL} FROM {_BY_FOLD} GROUP BY setting")
def w12_label_noise(spark, sf_dir):
    """What automatic labels cost: that many percent of the training labels are drawn anew; accuracy over five folds on the labels that were not touched."""
    docs = _documents(spark, sf_dir)
    rows = word_heads.training_rows(docs, CAP)
    noisy = [rows.withColumn("class_id", F.expr(_MOVED.format(noise=n)).cast("int")) for n in NOISES]
    told = word_heads.judged(docs, _settings(noisy), len(NOISES), len(LANGS))
    return evaluate.t_interval(_accuracy(docs, told), ["setting"]).select(_named(NOISES, "noise"), "accuracy", "lo", "hi")


@query("w13_learning_curve", _sql(" UNION ALL ".join(_one(n, s) for s, n in enumerate(CAPS))) + f" SELECT {list(CAPS)}[setting + 1] AS cap, {_INTERVAL} FROM {_BY_FOLD} GROUP BY setting")
def w13_learning_curve(spark, sf_dir):
    """Accuracy over five folds by the number of training documents of a language (a multiple of four: a quarter of the cap from each fold)."""
    docs = _documents(spark, sf_dir)
    told = word_heads.judged(docs, _settings([word_heads.training_rows(docs, n) for n in CAPS]), len(CAPS), len(LANGS))
    return evaluate.t_interval(_accuracy(docs, told), ["setting"]).select(_named(CAPS, "cap"), "accuracy", "lo", "hi")


_W14 = "SELECT lang, count(*) // 2 AS n, round(avg((predicted = class_id)::INT) FILTER (setting = 0), 6) AS accuracy, round(avg((predicted = class_id)::INT) FILTER (setting = 1), 6) AS accuracy_weighted FROM told GROUP BY lang"


@query("w14_class_sizes", _sql(_one(CAP, 0) + " UNION ALL " + _one(CAP, 1), (1,)) + " " + _W14)
def w14_class_sizes(spark, sf_dir):
    """Size of each language and the accuracy of its documents, by plain training rows and by rows that give each class the same weight."""
    docs = _documents(spark, sf_dir)
    rows = word_heads.training_rows(docs, CAP)
    told = word_heads.judged(docs, _settings([rows, rows]), 2, len(LANGS), weighted=(1,)).join(docs.select("doc_id", "class_id", "lang"), "doc_id")
    right = lambda s: F.round(F.avg(F.when(F.col("setting") == s, (F.col("predicted") == F.col("class_id")).cast("int"))), 6)
    return told.groupBy("lang").agg(F.count_if(F.col("setting") == 0).alias("n"), right(0).alias("accuracy"), right(1).alias("accuracy_weighted"))


_HEADS = {f"head{n}": n for n in (CAPS[0], CAPS[-1])}
_BEST = f""", cv AS (SELECT source AS modality, {list(_HEADS)}[setting + 1] AS network, avg((predicted = class_id)::INT) AS acc FROM told JOIN (SELECT doc_id, source FROM documents) USING (doc_id) GROUP BY ALL)
SELECT modality, network, round(acc, 6) AS accuracy FROM (SELECT *, row_number() OVER (PARTITION BY modality ORDER BY acc DESC, network) AS r FROM cv) WHERE r = 1"""


@query("m_select_best", _sql(" UNION ALL ".join(_one(n, s) for s, n in enumerate(_HEADS.values()))) + _BEST)
def m_select_best(spark, sf_dir):
    """The better of two heads (25 or 200 training documents of a language) for each source, by accuracy over the documents of all five held-out folds."""
    docs = _documents(spark, sf_dir, "source")
    told = word_heads.judged(docs, _settings([word_heads.training_rows(docs, n) for n in _HEADS.values()]), len(_HEADS), len(LANGS))
    # Both heads judge the same documents, so equal accuracies are equal numbers.
    cv = told.join(docs.select("doc_id", "class_id", F.col("source").alias("modality")), "doc_id").groupBy("modality", _named(list(_HEADS), "network")).agg(F.avg((F.col("predicted") == F.col("class_id")).cast("int")).alias("accuracy"))
    return network.select_best(cv).select("modality", "network", F.round("accuracy", 6).alias("accuracy"))

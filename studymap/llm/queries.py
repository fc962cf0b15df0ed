"""Queries of the training-data operators, each over its whole table, and their DuckDB twins where SQL can say the same."""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import functions as F

from . import latent_quality, toxic_crf
from .base import crc_fold, table
from .exact_dedup import exact_duplicates
from .mixing import mix
from .near_dedup import near_duplicates
from .sentencepiece_viterbi import encode
from .sharding import stratified_shards
from .substring_dedup import remove_repeats
from .topk_search import top_k
from .url_filter import filter_urls


class LlmQuery(NamedTuple):
    run: object
    sql: str | None = None


FOUND: dict[str, LlmQuery] = {}


def query(name, sql=None):
    def keep(f):
        FOUND[name] = LlmQuery(f, sql)
        return f

    return keep


def registry():
    return dict(FOUND)


def pipeline(module):
    return {"pipeline": LlmQuery(module.run, module.ORACLE_SQL)}


WORDS = r"regexp_extract_all(text, '[^\x20\x09-\x0D]+')"

SQL1 = r"""
WITH p AS (SELECT page_id, translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
  coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 2), '') AS path FROM pages),
rules(action, rule) AS (VALUES ('allow', 'com/'), ('block', 'example.com/en/'), ('allow', 'www.example.com/en/'), ('block', 'net/es/'), ('block', 'net/fr/')),
hit AS (SELECT page_id, max_by(rule, length(rule)) AS rule, max_by(action, length(rule)) AS action FROM p, rules
  WHERE ('.' || host) LIKE ('%.' || split_part(rule, '/', 1)) AND starts_with(path, substr(rule, strpos(rule, '/'))) GROUP BY page_id),
h AS (SELECT host, count(quality) AS n, coalesce(sum(quality), 0)::DOUBLE AS good FROM p LEFT JOIN labels ON page_id = doc_id GROUP BY host),
h1 AS (SELECT *, CASE WHEN l2 IN ('ac.uk','co.jp','co.nz','co.uk','com.au','com.br','gov.uk','org.uk') THEN array_to_string(parts[-3:], '.') ELSE l2 END AS domain,
  CASE WHEN l2 IN ('ac.uk','co.jp','co.nz','co.uk','com.au','com.br','gov.uk','org.uk') THEN l2 ELSE parts[-1] END AS suffix
  FROM (SELECT *, string_split(host, '.') AS parts, array_to_string(string_split(host, '.')[-2:], '.') AS l2 FROM h)),
s AS (SELECT suffix, sum(n)::DOUBLE AS n, sum(good) AS good, (SELECT CASE WHEN sum(n) = 0 THEN 0.5 ELSE sum(good) / sum(n) END FROM h) AS m FROM h1 GROUP BY suffix),
sw AS (SELECT count(*) AS k, sum(n) AS t, sum(n * n) AS sq, sum(n * (good / n - m) ** 2) AS s, sum(n * m * (1 - m)) / sum(n) AS v FROM s WHERE n > 0),
sx AS (SELECT CASE WHEN k = 0 OR v = 0 OR (t - sq / t - (k - 1)) * v <= 0 THEN 8.0 WHEN s - (k - 1) * v <= 0 THEN 1000.0
  ELSE least(1000.0, greatest(0.5, (t - sq / t - (k - 1)) * v / (s - (k - 1) * v) - 1)) END AS w FROM sw),
d AS (SELECT domain, h1.suffix, sum(h1.n)::DOUBLE AS n, sum(h1.good) AS good, any_value((s.good + w * s.m) / (s.n + w)) AS m FROM h1 JOIN s USING (suffix), sx GROUP BY domain, h1.suffix),
dw AS (SELECT count(*) AS k, sum(n) AS t, sum(n * n) AS sq, sum(n * (good / n - m) ** 2) AS s, sum(n * m * (1 - m)) / sum(n) AS v FROM d WHERE n > 0),
dx AS (SELECT CASE WHEN k = 0 OR v = 0 OR (t - sq / t - (k - 1)) * v <= 0 THEN 8.0 WHEN s - (k - 1) * v <= 0 THEN 1000.0
  ELSE least(1000.0, greatest(0.5, (t - sq / t - (k - 1)) * v / (s - (k - 1) * v) - 1)) END AS w FROM dw),
g AS (SELECT host, h1.n::DOUBLE AS n, h1.good, (d.good + w * d.m) / (d.n + w) AS m FROM h1 JOIN d USING (domain), dx),
gw AS (SELECT count(*) AS k, sum(n) AS t, sum(n * n) AS sq, sum(n * (good / n - m) ** 2) AS s, sum(n * m * (1 - m)) / sum(n) AS v FROM g WHERE n > 0),
gx AS (SELECT CASE WHEN k = 0 OR v = 0 OR (t - sq / t - (k - 1)) * v <= 0 THEN 8.0 WHEN s - (k - 1) * v <= 0 THEN 1000.0
  ELSE least(1000.0, greatest(0.5, (t - sq / t - (k - 1)) * v / (s - (k - 1) * v) - 1)) END AS w FROM gw),
post AS (SELECT host, good + w * m AS a, n - good + w * (1 - m) AS b FROM g, gx)
SELECT p.page_id, p.host, p.path, hit.rule, coalesce(hit.action, CASE WHEN round(a / (a + b) - 1.0 * sqrt(a * b / ((a + b) * (a + b) * (a + b + 1))), 9) >= 0.8 THEN 'allow' ELSE 'block' END) AS verdict
FROM p LEFT JOIN hit USING (page_id) JOIN post ON p.host = post.host"""


@query("op1_url_reputation", SQL1)
def op1(spark, sf_dir):
    """Outcomes are labels.quality of the document that has the page's id."""
    return filter_urls(table(spark, sf_dir, "pages"), table(spark, sf_dir, "labels").select("doc_id", "quality"))


@query("op5_stratified_shards")
def op5(spark, sf_dir):
    return stratified_shards(table(spark, sf_dir, "documents"), shards=8)


@query("op6_quality_weighted_mix")
def op6(spark, sf_dir):
    return mix(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels").select("doc_id", "quality")).drop("copies")


SQL8 = """
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW w AS (PARTITION BY coalesce(text, ''))"""


@query("op8_digest_tree_merge", SQL8)
def op8(spark, sf_dir):
    return exact_duplicates(table(spark, sf_dir, "documents"))


@query("op9_unigram_viterbi")
def op9(spark, sf_dir):
    return encode(table(spark, sf_dir, "documents"))


def judged(scores, least):
    """Contract columns of a scored table: id, held_out, score, predicted."""
    return scores.select("doc_id", (crc_fold(F.col("doc_id")) == 1).alias("held_out"), "score", (F.col("score") >= least).cast("int").alias("predicted"))


@query("op10_toxic_crf")
def op10(spark, sf_dir):
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return judged(toxic_crf.score(docs, toxic_crf.train(docs, labels, trains=crc_fold(F.col("doc_id")) != 1)), 0.7)


@query("op4_latent_neighbours")
def op4(spark, sf_dir):
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return judged(latent_quality.score(docs, latent_quality.train(docs, labels, trains=crc_fold(F.col("doc_id")) != 1)), 0.5)


SQL2 = """
WITH v AS (SELECT vec_id, row_number() OVER () AS n, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS v FROM embeddings
  WHERE len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
p AS (SELECT q.n, q.vec_id AS query_id, c.vec_id, list_inner_product(q.v, c.v)::BIGINT AS score FROM v q JOIN v c ON q.vec_id % 20 = 0 AND c.vec_id <> q.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY n ORDER BY score DESC, vec_id) AS rank FROM p)
SELECT query_id, rank::INT AS rank, vec_id, score FROM r WHERE rank <= 20"""


@query("op2_norm_bucket_search", SQL2)
def op2(spark, sf_dir):
    return top_k(table(spark, sf_dir, "embeddings"), lambda i: i % 20 == 0, k=20)


SQL3 = r"""
WITH RECURSIVE t AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
  ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS sh FROM t),
g AS (SELECT doc_id, unnest(sh) AS x FROM s),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS n FROM g a JOIN g b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN s x ON x.doc_id = a JOIN s y ON y.doc_id = b WHERE 100 * n >= 75 * (len(x.sh) + len(y.sh) - n)),
e AS (SELECT a, b FROM l UNION SELECT b, a FROM l),
r(doc_id, c) AS (SELECT doc_id, doc_id FROM s UNION SELECT e.b, r.c FROM r JOIN e ON e.a = r.doc_id WHERE r.c < e.b)
SELECT s.doc_id, len(s.sh)::BIGINT AS n_shingles, m.c AS component_id, s.doc_id = m.c AS kept FROM s JOIN (SELECT doc_id, min(c) AS c FROM r GROUP BY doc_id) m USING (doc_id)"""


@query("op3_min_max_near_dedup", SQL3)
def op3(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "documents"))


SQL7 = r"""
WITH t AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
win AS (SELECT doc_id, i, array_to_string(w[i:i + 49], ' ') AS x FROM t, unnest(range(1, len(w) - 48)) AS u(i)),
m AS (SELECT x, min(doc_id) AS lo FROM win GROUP BY x),
f AS (SELECT doc_id, i FROM win JOIN m USING (x) WHERE lo < doc_id),
gone AS (SELECT DISTINCT doc_id, i + j AS pos FROM f, unnest(range(0, 50)) AS u(j)),
words AS (SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS pos FROM t),
kept AS (SELECT doc_id, string_agg(word, ' ' ORDER BY pos) AS k, count(*) AS n FROM words ANTI JOIN gone USING (doc_id, pos) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(k, '')) AS kept_sha256 FROM t LEFT JOIN kept USING (doc_id)"""


@query("op7_super_kmer_dedup", SQL7)
def op7(spark, sf_dir):
    return remove_repeats(table(spark, sf_dir, "documents"))

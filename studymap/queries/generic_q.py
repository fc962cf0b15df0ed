"""Queries on the relational operators around the methods: scans, predicates, joins, aggregates, windows, sorts, sets, functions.

Most of them are one select list that both engines read; the rest say the Spark form and the oracle form side by side.
"""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.lineage import cut
from . import query, table


def same(name: str, source: str, cols: str, where: str | None = None, group: str | None = None, having: str | None = None):
    """A query whose expressions are valid in both engines: `cols` is a select list, with `group` an aggregation."""
    text = f"SELECT {cols} FROM {source}" + (f" WHERE {where}" if where else "") + (f" GROUP BY {group}" if group else "") + (f" HAVING {having}" if having else "")

    def run(spark, sf_dir):
        df = table(spark, sf_dir, source)
        df = df.where(where) if where else df
        if not group:
            return df.selectExpr(*_items(cols))
        keys = _items(group)
        out = df.groupBy(*map(F.expr, keys)).agg(*(F.expr(i) for i in _items(cols) if i not in keys), *([F.expr(f"{having} AS _keep")] if having else []))
        return out.where("_keep").drop("_keep") if having else out

    query(name, text)(run)


def _items(cols: str) -> list[str]:
    """Split a select list at commas outside brackets and quotes."""
    out, depth, start, quoted = [], 0, 0, False
    for i, c in enumerate(cols):
        quoted ^= c == "'"
        depth += (c in "([") - (c in ")]") if not quoted else 0
        if c == "," and not depth and not quoted:
            out.append(cols[start:i].strip())
            start = i + 1
    return [*out, cols[start:].strip()]


def both(name: str, sql: str):
    """Decorator: a function of a table getter t(name) beside its SQL."""

    def keep(f):
        query(name, sql)(lambda spark, sf_dir: f(lambda n: table(spark, sf_dir, n)))
        return f

    return keep


def r6(c):
    return F.round(c, 6)


# Projection and predicates.
same("p_select_alias", "customer", "c_custkey AS id, c_name AS name")
same("p_cast_types", "orders", "o_orderkey, cast(floor(o_totalprice) AS bigint) AS whole, cast(o_orderkey AS varchar(20)) AS key_text", "o_totalprice < 2000000")
same("p_derived", "lineitem", "l_orderkey, l_partkey, round(l_extendedprice * (1 - l_discount), 4) AS net")
same("p_filter_eq", "orders", "o_orderkey", "o_orderpriority = '1-URGENT'")
same("p_filter_range", "orders", "o_orderkey, o_totalprice", "o_totalprice > 100000 AND o_totalprice <= 200000")
same("p_filter_in", "orders", "o_orderkey, o_orderstatus", "o_orderstatus IN ('F', 'O')")
same("p_filter_between", "lineitem", "l_orderkey, l_quantity", "l_quantity BETWEEN 10 AND 12")
same("p_filter_null", "documents", "doc_id, text IS NULL AS missing", "lang IS NOT NULL")
same("p_like_rlike", "part", "p_partkey, p_name LIKE 'red%' AS starts, p_name LIKE '%ing' AS ends")
same("p_case_when", "orders", "o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 50000 THEN 'middle' ELSE 'low' END AS band")
same("p_coalesce", "orders", "o_orderkey, coalesce(nullif(o_orderstatus, 'F'), 'closed') AS status")
both("p_array_contains", "SELECT user_id, list_contains(list(DISTINCT event_type), 'error') AS had_error FROM events GROUP BY user_id")(lambda t: t("events").groupBy("user_id").agg(F.array_contains(F.collect_set("event_type"), "error").alias("had_error")))
both("p_exists", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0.3)) > 0 AS has_peak FROM embeddings")(lambda t: t("embeddings").select("vec_id", F.exists("embedding", lambda x: x > F.lit(0.3).cast("float")).alias("has_peak")))
both("p_not_in_null_safe", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")(lambda t: t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"))
both("p_distinct", "SELECT DISTINCT p_type, p_brand FROM part")(lambda t: t("part").select("p_type", "p_brand").distinct())
both("p_drop_duplicates", "SELECT p_name, min(p_partkey) AS p_partkey FROM part GROUP BY p_name")(lambda t: t("part").groupBy("p_name").agg(F.min("p_partkey").alias("p_partkey")))

# Joins.
_OC = "orders JOIN customer ON o_custkey = c_custkey"
for _n, _h in (("j_broadcast_hash", "broadcast"), ("j_sort_merge", "merge"), ("j_shuffle_hash", "shuffle_hash")):
    both(_n, f"SELECT o_orderkey, c_name FROM {_OC}")(lambda t, h=_h: t("orders").join(t("customer").hint(h), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name"))
both("j_left_outer", "SELECT o_orderkey, l_linenumber FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey")(lambda t: t("orders").join(t("lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left").select("o_orderkey", "l_linenumber"))
both("j_right_outer", "SELECT o_orderkey, c_custkey FROM orders RIGHT JOIN customer ON o_custkey = c_custkey")(lambda t: t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey"), "right").select("o_orderkey", "c_custkey"))
both("j_full_outer", "SELECT l.doc_id AS label_id, b.item_id FROM labels l FULL JOIN benchmark b ON l.doc_id = b.item_id")(lambda t: t("labels").join(t("benchmark"), F.col("doc_id") == F.col("item_id"), "full").select(F.col("doc_id").alias("label_id"), "item_id"))
both("j_left_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")(lambda t: t("documents").join(t("labels").where("quality = 1"), "doc_id", "left_semi").select("doc_id", "lang"))
both("j_left_anti", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")(lambda t: t("documents").join(t("labels"), "doc_id", "left_anti").select("doc_id", "lang"))
both("j_cross", "SELECT a.r_name AS a, b.r_name AS b FROM region a, region b")(lambda t: t("region").select(F.col("r_name").alias("a")).crossJoin(t("region").select(F.col("r_name").alias("b"))))
both("j_theta_nested_loop", "SELECT p_partkey, n AS noun FROM part JOIN (SELECT DISTINCT split_part(p_name, ' ', 2) AS n FROM part) ON contains(p_name, n)")(
    lambda t: t("part").join(F.broadcast(t("part").select(F.split("p_name", " ")[1].alias("noun")).distinct()), F.col("p_name").contains(F.col("noun"))).select("p_partkey", "noun")
)
both("j_self", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")(
    lambda t: t("nation").alias("a").join(t("nation").alias("b"), F.expr("a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"))
)
both("j_range", "SELECT l_orderkey, l_partkey, least(floor(l_discount * 100), 9)::INT AS bin FROM lineitem")(lambda t: t("lineitem").select("l_orderkey", "l_partkey", F.least(F.floor(F.col("l_discount") * 100), F.lit(9)).cast("int").alias("bin")))


@both("j_asof", "SELECT o_orderkey, prior FROM (SELECT o_orderkey, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS prior FROM orders)")
def j_asof(t):
    """The latest earlier study of the same patient, as the last value before the row in one sort."""
    past = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(W.unboundedPreceding, -1)
    return t("orders").select("o_orderkey", F.last("o_orderkey", ignorenulls=True).over(past).alias("prior"))


both("j_interval", "SELECT o_orderkey, l_linenumber FROM orders JOIN lineitem ON o_orderkey = l_orderkey AND l_shipdate BETWEEN o_orderdate AND o_orderdate + INTERVAL 30 DAY")(
    lambda t: t("orders").join(t("lineitem"), F.expr("o_orderkey = l_orderkey AND l_shipdate BETWEEN o_orderdate AND o_orderdate + INTERVAL 30 DAYS")).select("o_orderkey", "l_linenumber")
)
both("j_null_safe", "SELECT a.doc_id FROM labels a JOIN (SELECT nullif(r_name, r_name) AS k FROM region LIMIT 1) b ON nullif(a.quality, 0) IS NOT DISTINCT FROM b.k::INT")(
    lambda t: t("labels").withColumn("q", F.nullif("quality", F.lit(0))).join(F.broadcast(t("region").limit(1).select(F.lit(None).cast("int").alias("k"))), F.col("q").eqNullSafe(F.col("k"))).select("doc_id")
)
query("j_skew_salted")(lambda spark, sf_dir: _salted(table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")))


def _salted(item, orders, salts: int = 8):
    """Both sides carry a salt: the large side draws one, the small side is repeated for each."""
    a = item.withColumn("salt", F.pmod(F.xxhash64("l_orderkey", "l_linenumber", "l_partkey"), F.lit(salts)).cast("int"))
    b = orders.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, (F.col("l_orderkey") == F.col("o_orderkey")) & (a["salt"] == b["salt"])).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


# Aggregates.
same("g_hash_sum_count", "lineitem", "l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q", group="l_returnflag, l_linestatus")
same("g_avg_stddev", "orders", "o_orderstatus, round(avg(o_totalprice), 4) AS mean, round(stddev_samp(o_totalprice), 4) AS sd", group="o_orderstatus")
same("g_min_max", "part", "p_brand, min(p_size) AS lo, max(p_size) AS hi", group="p_brand")
both("g_max_by_min_by", "SELECT o_custkey, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS top, min_by(o_orderkey, (o_totalprice, o_orderkey)) AS low FROM orders GROUP BY o_custkey")(
    lambda t: t("orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("top"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("low"))
)
both("g_collect_list_sorted", "SELECT conv_id, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id")(
    lambda t: t("conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda s: s["role"]), ">").alias("roles"))
)
both("g_collect_set", "SELECT user_id, array_to_string(list_sort(list(DISTINCT event_type)), ',') AS kinds FROM events GROUP BY user_id")(lambda t: t("events").groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("kinds")))
same("g_count_distinct", "part", "p_type, count(DISTINCT p_name) AS classes", group="p_type")
query("g_approx_count_distinct")(lambda spark, sf_dir: table(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts")))
same("g_count_if", "labels", "toxic, count_if(quality = 1) AS good, count(*) AS n", group="toxic")
same("g_filter_clause", "orders", "o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS closed", group="o_orderpriority")
both("g_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")(
    lambda t: t("lineitem").groupingSets([["l_returnflag", "l_linestatus"], ["l_returnflag"], []], "l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")).select("l_returnflag", "l_linestatus", "n")
)
both("g_rollup", "SELECT p_type, p_brand, count(*) AS n FROM part GROUP BY ROLLUP (p_type, p_brand)")(lambda t: t("part").rollup("p_type", "p_brand").agg(F.count(F.lit(1)).alias("n")))
both("g_cube", "SELECT p_type, p_size >= 40 AS volume, count(*) AS n FROM part GROUP BY CUBE (p_type, volume)")(lambda t: t("part").withColumn("volume", F.col("p_size") >= 40).cube("p_type", "volume").agg(F.count(F.lit(1)).alias("n")))
both("g_pivot", "SELECT lang, count_if(quality = 0) AS \"0\", count_if(quality = 1) AS \"1\" FROM documents JOIN labels USING (doc_id) GROUP BY lang")(lambda t: t("documents").join(t("labels"), "doc_id").groupBy("lang").pivot("quality", [0, 1]).agg(F.count(F.lit(1))).na.fill(0))
both("g_unpivot", "SELECT doc_id, unnest(['quality', 'toxic']) AS measure, unnest([quality, toxic]) AS value FROM labels")(lambda t: t("labels").unpivot("doc_id", ["quality", "toxic"], "measure", "value"))
both("g_percentile", "SELECT p_type, round(quantile_cont(p_retailprice, 0.9), 4) AS p90 FROM part GROUP BY p_type")(lambda t: t("part").groupBy("p_type").agg(F.round(F.percentile("p_retailprice", 0.9), 4).alias("p90")))
both("g_median", "SELECT p_type, round(median(p_retailprice), 4) AS mid FROM part GROUP BY p_type")(lambda t: t("part").groupBy("p_type").agg(F.round(F.median("p_retailprice"), 4).alias("mid")))
query("g_approx_percentile")(lambda spark, sf_dir: table(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.percentile_approx("o_totalprice", 0.5, 1000).alias("mid")))
both("g_histogram", "SELECT least(floor(value / 10), 9)::INT AS bin, count(*) AS n FROM events GROUP BY 1")(lambda t: t("events").groupBy(F.least(F.floor(F.col("value") / 10), F.lit(9)).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("n")))
both("g_mode", "SELECT user_id, min(event_type) AS kind FROM (SELECT user_id, event_type, n, max(n) OVER (PARTITION BY user_id) AS top FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2)) WHERE n = top GROUP BY user_id HAVING count(*) = 1")(
    lambda t: t("events").groupBy("user_id", "event_type").count().groupBy("user_id").agg(F.collect_list(F.struct("count", "event_type")).alias("x"), F.max("count").alias("m")).withColumn("b", F.filter("x", lambda s: s["count"] == F.col("m"))).where("size(b) = 1").select("user_id", F.col("b")[0]["event_type"].alias("kind"))
)
same("g_bool_and_or", "labels", "quality, bool_and(toxic = 0) AS every, bool_or(toxic = 1) AS some", group="quality")
same("g_corr_covar", "lineitem", "l_returnflag, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_samp(l_quantity, l_discount), 6) AS c", group="l_returnflag")
both("g_listagg", "SELECT n_regionkey, string_agg(n_name, ', ' ORDER BY n_name) AS names FROM nation GROUP BY 1")(lambda t: t("nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ", ").alias("names")))
both("g_having", "SELECT l_orderkey, count(DISTINCT p_type) AS modalities FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1 HAVING count(DISTINCT p_type) >= 2")(
    lambda t: t("lineitem").join(t("part"), F.col("l_partkey") == F.col("p_partkey")).groupBy("l_orderkey").agg(F.count_distinct("p_type").alias("modalities")).where("modalities >= 2")
)
query("g_sort_agg")(lambda spark, sf_dir: table(spark, sf_dir, "part").groupBy("p_type").agg(F.max(F.struct("p_name", "p_partkey")).alias("s")).select("p_type", "s.*"))

# Windows.
_WIN = {
    "w_row_number": "row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)", "w_rank": "rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)",
    "w_dense_rank": "dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)", "w_percent_rank": "round(percent_rank() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice), 6)",
    "w_cume_dist": "round(cume_dist() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice), 6)", "w_ntile": "ntile(4) OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice, o_orderkey)",
    "w_lag_lead": "coalesce(lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey), 0) + coalesce(lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey), 0)",
    "w_first_last_value": "first_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)", "w_nth_value": "nth_value(o_orderkey, 2) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "w_running_sum": "count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)", "w_range_frame": "count(*) OVER (PARTITION BY o_orderstatus ORDER BY o_orderkey RANGE BETWEEN 10 PRECEDING AND CURRENT ROW)",
    "w_moving_avg": "round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4)", "w_sum_over_partition": "round(o_totalprice / sum(o_totalprice) OVER (PARTITION BY o_custkey), 6)",
    "w_last_ignore_nulls": "last_value(nullif(o_orderkey % 3, 0) IGNORE NULLS) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)",
}
for _n, _e in _WIN.items():
    _spark = _e.replace("last_value(nullif(o_orderkey % 3, 0) IGNORE NULLS)", "last_value(nullif(o_orderkey % 3, 0), true)")
    query(_n, f"SELECT o_orderkey, {_e.replace('last_value(nullif(o_orderkey % 3, 0) IGNORE NULLS)', 'last_value(nullif(o_orderkey % 3, 0) IGNORE NULLS)')} AS v FROM orders")(lambda spark, sf_dir, e=_spark: table(spark, sf_dir, "orders").selectExpr("o_orderkey", f"{e} AS v"))
both("w_islands", "SELECT conv_id, min(turn) AS lo, max(turn) AS hi FROM (SELECT conv_id, turn, turn - row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS g FROM conversations WHERE role <> 'system') GROUP BY conv_id, g")(
    lambda t: t("conversations").where("role <> 'system'").withColumn("g", F.col("turn") - F.row_number().over(W.partitionBy("conv_id").orderBy("turn"))).groupBy("conv_id", "g").agg(F.min("turn").alias("lo"), F.max("turn").alias("hi")).drop("g")
)

# Sort, limit, top-k.
both("o_sort_multi", "SELECT p_type, p_size, p_partkey FROM part ORDER BY p_type DESC NULLS LAST, p_size NULLS FIRST, p_partkey")(lambda t: t("part").select("p_type", "p_size", "p_partkey").orderBy(F.desc_nulls_last("p_type"), F.asc_nulls_first("p_size"), "p_partkey"))
both("o_limit", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 7")(lambda t: t("orders").select("o_orderkey").orderBy("o_orderkey").limit(7))
both("o_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 5 OFFSET 10")(lambda t: t("orders").select("o_orderkey").orderBy("o_orderkey").offset(10).limit(5))
both("o_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")(lambda t: t("orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20))
both("o_topk_per_group", "SELECT p_type, p_partkey FROM (SELECT *, row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")(
    lambda t: t("part").withColumn("r", F.row_number().over(W.partitionBy("p_type").orderBy(F.desc("p_retailprice"), "p_partkey"))).where("r <= 3").select("p_type", "p_partkey")
)
query("o_sample")(lambda spark, sf_dir: table(spark, sf_dir, "documents").sampleBy("lang", {"en": 0.2, "fr": 0.8, "de": 0.8, "es": 0.8}, seed=1).select("doc_id", "lang"))

# Sets.
_A, _B = "SELECT p_name FROM part WHERE p_size < 25", "SELECT p_name FROM part WHERE p_size > 20"
for _n, _op, _f in (("u_union_all", "UNION ALL", "unionAll"), ("u_union_distinct", "UNION", "unionAll"), ("u_intersect", "INTERSECT", "intersect"), ("u_intersect_all", "INTERSECT ALL", "intersectAll"), ("u_except", "EXCEPT", "subtract"), ("u_except_all", "EXCEPT ALL", "exceptAll")):
    both(_n, f"{_A} {_op} {_B}")(lambda t, f=_f, d=_n == "u_union_distinct": (lambda x: x.distinct() if d else x)(getattr(t("part").where("p_size < 25").select("p_name"), f)(t("part").where("p_size > 20").select("p_name"))))
both("u_union_by_name", "SELECT c_custkey AS id, c_name AS name, NULL::INT AS size FROM customer UNION ALL SELECT p_partkey, NULL, p_size FROM part")(
    lambda t: t("customer").select(F.col("c_custkey").alias("id"), F.col("c_name").alias("name")).unionByName(t("part").select(F.col("p_partkey").alias("id"), F.col("p_size").alias("size")), allowMissingColumns=True)
)

# Scalar functions.
same("f_lower_trim", "part", "p_partkey, lower(trim(p_brand)) AS v")
same("f_substring", "part", "p_partkey, substr(p_name, 2, 4) AS v")
same("f_length", "documents", "doc_id, length(text) AS v")
same("f_concat_ws", "part", "p_partkey, concat_ws('-', p_brand, p_type) AS v")
both("f_split", "SELECT p_partkey, split_part(p_name, ' ', 2) AS v FROM part")(lambda t: t("part").select("p_partkey", F.split("p_name", " ")[1].alias("v")))
same("f_regexp_extract", "pages", "page_id, regexp_extract(url, '//([^/]+)', 1) AS v")
both("f_regexp_replace", "SELECT page_id, regexp_replace(url, '[0-9]+', '#', 'g') AS v FROM pages")(lambda t: t("pages").select("page_id", F.regexp_replace("url", "[0-9]+", "#").alias("v")))
same("f_instr_contains", "part", "p_partkey, instr(p_name, 'ring') AS v, contains(p_name, 'bolt') AS w")
both("f_startswith", "SELECT p_partkey, starts_with(p_name, 'red') AS v FROM part")(lambda t: t("part").select("p_partkey", F.col("p_name").startswith("red").alias("v")))
same("f_translate", "part", "p_partkey, translate(p_name, 'aeiou', '12345') AS v")
same("f_lpad", "part", "p_partkey, lpad(cast(p_size AS varchar(9)), 4, '0') AS v")
same("f_reverse", "part", "p_partkey, reverse(p_name) AS v")
both("f_initcap", "SELECT p_partkey, array_to_string(list_transform(string_split(p_name, ' '), lambda w: upper(w[1]) || w[2:]), ' ') AS v FROM part")(lambda t: t("part").select("p_partkey", F.initcap("p_name").alias("v")))
same("f_levenshtein", "part", "p_partkey, levenshtein(p_name, 'red widget') AS v")
query("f_soundex")(lambda spark, sf_dir: table(spark, sf_dir, "part").select("p_partkey", F.soundex("p_name").alias("v")))
both("f_url_path", "SELECT page_id, regexp_extract(url, '//[^/?#]+([^?#]*)', 1) AS v FROM pages")(lambda t: t("pages").select("page_id", F.regexp_extract("url", "//[^/?#]+([^?#]*)", 1).alias("v")))
both("f_html_title", "SELECT page_id, regexp_extract(html, '(?s)<title>(.*?)</title>', 1) AS v FROM pages")(lambda t: t("pages").select("page_id", F.regexp_extract("html", "(?s)<title>(.*?)</title>", 1).alias("v")))
both("f_html_attr", "SELECT page_id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS v FROM pages")(lambda t: t("pages").select("page_id", F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("v")))
both("f_date_trunc", "SELECT event_id, date_trunc('hour', ts) AS v FROM events")(lambda t: t("events").select("event_id", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("v")))
both("f_date_add_diff", "SELECT o_orderkey, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS v FROM orders")(lambda t: t("orders").select("o_orderkey", F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("v")))
both("f_extract_parts", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofmonth(o_orderdate) AS d, quarter(o_orderdate) AS q FROM orders")(lambda t: t("orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofmonth("o_orderdate").alias("d"), F.quarter("o_orderdate").alias("q")))
both("f_interval_arith", "SELECT o_orderkey, o_orderdate + INTERVAL 36 HOUR AS v FROM orders")(lambda t: t("orders").select("o_orderkey", F.expr("o_orderdate + INTERVAL 36 HOURS").alias("v")))
both("f_to_timestamp_cast", "SELECT event_id, strptime(strftime(ts, '%Y-%m-%d'), '%Y-%m-%d') AS v FROM events")(lambda t: t("events").select("event_id", F.to_timestamp(F.date_format("ts", "yyyy-MM-dd"), "yyyy-MM-dd").cast("timestamp_ntz").alias("v")))
both("f_last_day", "SELECT o_orderkey, last_day(o_orderdate::DATE) AS v FROM orders")(lambda t: t("orders").select("o_orderkey", F.last_day("o_orderdate").alias("v")))
same("f_exp_log", "lineitem", "l_orderkey, l_partkey, round(exp(l_discount), 6) AS e, round(ln(l_quantity), 6) AS l")
both("f_floor_ceil_round", "SELECT l_orderkey, l_partkey, floor(l_extendedprice)::BIGINT AS f, ceil(l_extendedprice)::BIGINT AS c FROM lineitem")(lambda t: t("lineitem").select("l_orderkey", "l_partkey", F.floor("l_extendedprice").alias("f"), F.ceil("l_extendedprice").alias("c")))
same("f_greatest_least", "labels", "doc_id, greatest(quality, toxic) AS g, least(quality, toxic) AS l")
both("f_pmod", "SELECT doc_id, ((doc_id - 500) % 7 + 7) % 7 AS v FROM documents")(lambda t: t("documents").select("doc_id", F.pmod(F.col("doc_id") - 500, F.lit(7)).alias("v")))
same("f_sqrt_pow", "part", "p_partkey, round(sqrt(p_size), 6) AS s, round(power(p_size, 3), 6) AS p")
query("f_trig")(lambda spark, sf_dir: table(spark, sf_dir, "part").select("p_partkey", F.sin("p_size").alias("s"), F.atan2(F.col("p_size"), F.lit(2.0)).alias("a")))
_J = lambda a: F.array_join(F.transform(a, lambda v: F.round(v * 1000).cast("long").cast("string")), ",")
_JS = "array_to_string(list_transform({}, lambda v: round(v::DOUBLE * 1000)::BIGINT::VARCHAR), ',')"
_E = lambda t: t("embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
_ES = "SELECT vec_id, {} AS v FROM (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings)"
for _n, _s, _f in (
    ("f_transform", _JS.format("list_transform(e, lambda x: x * 2)"), lambda: _J(F.transform("e", lambda x: x * 2))), ("f_filter", _JS.format("list_filter(e, lambda x: x > 0.2)"), lambda: _J(F.filter("e", lambda x: x > 0.2))),
    ("f_aggregate", "round(list_sum(list_transform(e, lambda x: x * x)), 6)", lambda: r6(F.aggregate("e", F.lit(0.0), lambda a, x: a + x * x))), ("f_zip_with", _JS.format("list_transform(range(1, 65), lambda i: e[i] + e[65 - i])"), lambda: _J(F.zip_with("e", F.reverse("e"), lambda a, b: a + b))),
    ("f_slice", _JS.format("e[3:6]"), lambda: _J(F.slice("e", 3, 4))), ("f_array_min_max", "round(list_max(e) - list_min(e), 6)", lambda: r6(F.array_max("e") - F.array_min("e"))), ("f_array_position", "list_position(e, list_max(e))::BIGINT", lambda: F.array_position("e", F.array_max("e")).cast("long")),
    ("f_array_sort", _JS.format("list_sort(e)[1:5]"), lambda: _J(F.slice(F.array_sort("e"), 1, 5))), ("f_dot", "round(list_inner_product(e, list_reverse(e)), 6)", lambda: r6(F.aggregate(F.zip_with("e", F.reverse("e"), lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x))),
    ("f_cosine", "round(list_cosine_similarity(e, list_reverse(e)), 6)", lambda: r6(F.aggregate(F.zip_with("e", F.reverse("e"), lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x) / F.aggregate("e", F.lit(0.0), lambda a, x: a + x * x))), ("f_l2", "round(list_distance(e, list_reverse(e)), 6)", lambda: r6(F.sqrt(F.aggregate(F.zip_with("e", F.reverse("e"), lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda a, x: a + x)))),
    ("f_softmax", _JS.format("list_transform(e, lambda x: exp(x) / list_sum(list_transform(e, lambda y: exp(y))))"), lambda: _J(F.transform("e", lambda x: F.exp(x) / F.aggregate(F.transform("e", lambda y: F.exp(y)), F.lit(0.0), lambda a, y: a + y)))), ("f_argmax", "(list_position(e, list_max(e)) - 1)::BIGINT", lambda: (F.array_position("e", F.array_max("e")) - 1).cast("long")),
):
    both(_n, _ES.format(_s))(lambda t, f=_f: _E(t).select("vec_id", f().alias("v")))
both("f_sequence", "SELECT n_nationkey, len(range(0, n_nationkey + 1)) AS v FROM nation")(lambda t: t("nation").select("n_nationkey", F.size(F.sequence(F.lit(0), F.col("n_nationkey"))).alias("v")))
both("f_flatten", "SELECT n_nationkey, array_to_string(flatten([[n_name], [n_name, 'x']]), ',') AS v FROM nation")(lambda t: t("nation").select("n_nationkey", F.array_join(F.flatten(F.array(F.array("n_name"), F.array("n_name", F.lit("x")))), ",").alias("v")))
both("f_explode_outer", "SELECT doc_id, w FROM (SELECT doc_id, CASE WHEN doc_id % 2 = 0 THEN [lang, source] END AS a FROM documents) LEFT JOIN LATERAL (SELECT unnest(a) AS w) ON true")(lambda t: t("documents").select("doc_id", F.explode_outer(F.when(F.col("doc_id") % 2 == 0, F.array("lang", "source"))).alias("w")))
both("f_posexplode", "SELECT p_partkey, i - 1 AS pos, string_split(p_name, ' ')[i] AS word FROM part, unnest([1, 2]) AS u(i)")(lambda t: t("part").select("p_partkey", F.posexplode(F.split("p_name", " ")).alias("pos", "word")))
both("f_array_distinct_union", "SELECT n_nationkey, len(list_distinct(list_concat([n_regionkey, n_nationkey], [n_nationkey]))) AS v FROM nation")(lambda t: t("nation").select("n_nationkey", F.size(F.array_union(F.array("n_regionkey", "n_nationkey"), F.array("n_nationkey"))).alias("v")))
_MAP = lambda t: t("part").select("p_partkey", F.map_from_arrays(F.array(F.lit("brand"), F.lit("pack")), F.array("p_brand", "p_type")).alias("m"))
both("f_map_from_arrays", "SELECT p_partkey, p_brand AS v FROM part")(lambda t: _MAP(t).select("p_partkey", F.col("m")["brand"].alias("v")))
both("f_map_keys_values", "SELECT p_partkey, 'brand,pack' AS k, p_brand || ',' || p_type AS v FROM part")(lambda t: _MAP(t).select("p_partkey", F.array_join(F.map_keys("m"), ",").alias("k"), F.array_join(F.map_values("m"), ",").alias("v")))
both("f_map_filter", "SELECT p_partkey, p_type AS v FROM part")(lambda t: _MAP(t).select("p_partkey", F.map_values(F.map_filter("m", lambda k, v: k == "pack"))[0].alias("v")))
both("f_map_concat", "SELECT p_partkey, 3 AS v FROM part")(lambda t: _MAP(t).select("p_partkey", F.size(F.map_concat("m", F.create_map(F.lit("x"), F.lit("y")))).alias("v")))
both("f_element_at", "SELECT p_partkey, p_type AS v FROM part")(lambda t: _MAP(t).select("p_partkey", F.element_at("m", "pack").alias("v")))
both("f_explode_map", "SELECT p_partkey, unnest(['brand', 'pack']) AS key, unnest([p_brand, p_type]) AS value FROM part")(lambda t: _MAP(t).select("p_partkey", F.explode("m").alias("key", "value")))
both("f_named_struct", "SELECT p_partkey, p_size AS v FROM part")(lambda t: t("part").select("p_partkey", F.named_struct(F.lit("a"), F.col("p_size"))["a"].alias("v")))
both("f_from_json", "SELECT event_id, json_extract(props, '$.k')::INT AS v FROM events")(lambda t: t("events").select("event_id", F.from_json("props", "k int")["k"].alias("v")))
both("f_get_json", "SELECT event_id, json_extract_string(props, '$.k') AS v FROM events")(lambda t: t("events").select("event_id", F.get_json_object("props", "$.k").alias("v")))
both("f_to_json", "SELECT n_nationkey, '{\"n\":\"' || n_name || '\"}' AS v FROM nation")(lambda t: t("nation").select("n_nationkey", F.to_json(F.struct(F.col("n_name").alias("n"))).alias("v")))
_DDL = "json_structure(props)::VARCHAR"
for _a, _b in (('^"JSON"$', "STRUCT<>"), (r'"U?BIGINT"([,}\]]|$)', r"BIGINT\1"), (r'"(?:VARCHAR|NULL)"([,}\]]|$)', r"STRING\1"), (r'"(DOUBLE|BOOLEAN)"([,}\]]|$)', r"\1\2"), ('"([A-Za-z_][A-Za-z0-9_]*)":', r"\1: "), (",", ", "), (r"\{", "STRUCT<"), (r"\[", "ARRAY<"), (r"[}\]]", ">")):
    _DDL = f"regexp_replace({_DDL}, '{_a}', '{_b}', 'g')"


@query("f_schema_of_json", f"SELECT CASE WHEN json_valid(props) THEN {_DDL} END AS v, count(*) AS n FROM events GROUP BY 1")
def f_schema_of_json(spark, sf_dir):
    """How many JSON texts have each schema; texts that are not JSON have none.

    The function takes constants only: texts are grouped by structure, and one text of each structure goes to the driver and shows it the schema.
    """
    texts = table(spark, sf_dir, "events").select("props", F.schema_of_variant(F.try_parse_json("props")).alias("_kind"))
    kinds = cut(texts.groupBy("_kind").agg(F.min("props").alias("_text"), F.count(F.lit(1)).alias("_n")))
    rows = kinds.where("_kind is not null").select("_kind", "_text").collect()
    schemas = [v for at in range(0, len(rows), 100) for v in spark.range(1).select(*(F.schema_of_json(F.lit(r["_text"])) for r in rows[at : at + 100])).first()]
    found = spark.createDataFrame([(r["_kind"], v) for r, v in zip(rows, schemas)], "_kind string, v string")
    return kinds.join(F.broadcast(found), "_kind", "left").groupBy("v").agg(F.sum("_n").alias("n"))


query("f_variant")(lambda spark, sf_dir: table(spark, sf_dir, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("v")))
same("f_nullif", "labels", "doc_id, nullif(toxic, 0) AS v")
both("f_nvl", "SELECT doc_id, coalesce(nullif(toxic, 0), 9) AS v FROM labels")(lambda t: t("labels").select("doc_id", F.nvl(F.nullif("toxic", F.lit(0)), F.lit(9)).alias("v")))
same("f_if", "labels", "doc_id, if(toxic = 1, 'bad', 'good') AS v")
same("f_try_cast", "orders", "o_orderkey, try_cast(substr(o_orderpriority, 1, 1) AS int) AS v")
both("f_try_divide", "SELECT doc_id, CASE WHEN toxic = 0 THEN NULL ELSE quality::DOUBLE / toxic END AS v FROM labels")(lambda t: t("labels").select("doc_id", F.try_divide(F.col("quality").cast("double"), F.col("toxic")).alias("v")))
query("f_xxhash64")(lambda spark, sf_dir: table(spark, sf_dir, "part").select("p_partkey", F.xxhash64("p_name").alias("v")))
both("f_md5_sha2", "SELECT p_partkey, md5(p_name) AS m, sha256(p_name) AS s FROM part")(lambda t: t("part").select("p_partkey", F.md5("p_name").alias("m"), F.sha2("p_name", 256).alias("s")))
from ..functions.portable import stream as _stream  # noqa: E402

same("f_mix", "orders", f"o_orderkey, {_stream('o_orderkey', 7)} AS v")

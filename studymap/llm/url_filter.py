"""URL filter: explicit rules first, else the empirical-Bayes reputation of the host.

Outcomes of labelled pages are counted by host. Each level of the name hierarchy is a beta-binomial: a suffix is shrunk towards the overall
rate, a registered domain towards its suffix's posterior mean, a host towards its domain's. The weight of a level's prior, in pseudo-pages, is fitted from the
labelled counts by moments (within-group correlation of outcomes about the parent's mean). A host passes if the lower bound of its
posterior (mean minus `z` standard deviations) is at least `least`; hosts without a labelled page pass or fail on what their domain and suffix show.

The only numbers that reach the driver are three prior weights and one mean. Counts by host are combined before the shuffle, so a host with a third of
all pages is one row of the reputation table; the join back is a plain equi-join whose large side adaptive execution can split.

A null url, or one without '://', has an empty host and path and is judged as the host ''. Pages whose outcome is null count as unlabelled. Without any labelled
page the mean is `start_mean` and every weight is `start_weight`. Repeated rows are judged each. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
URL = r"(?s)^.*?://([^/?#]*)([^?#]*)"
#: Suffixes of two labels under which names are registered; a parameter of the operator.
TWO_LABEL_SUFFIXES = ("ac.uk", "co.jp", "co.nz", "co.uk", "com.au", "com.br", "gov.uk", "org.uk")
MOST_RULES = 1000
#: The rules of the production list: (action, host/path).
RULES = (("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/"))


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, URL, 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, URL, 2), F.lit(""))


def suffix_of(host: Column, two_label=TWO_LABEL_SUFFIXES) -> Column:
    last = F.substring_index(host, ".", -2)
    return F.when(last.isin(*two_label), last).otherwise(F.substring_index(host, ".", -1)) if two_label else F.substring_index(host, ".", -1)


def domain_of(host: Column, two_label=TWO_LABEL_SUFFIXES) -> Column:
    last = F.substring_index(host, ".", -2)
    return F.when(last.isin(*two_label), F.substring_index(host, ".", -3)).otherwise(last) if two_label else last


def matched_rule(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """(rule string, its action) of the longest rule that fits, nulls if none. A rule fits its host and subdomains where the path starts with its path."""
    if len(rules) > MOST_RULES:
        raise ValueError(f"at most {MOST_RULES} rules are compiled into the plan")
    rule = action = None
    for verdict, text in sorted(rules, key=lambda r: (-len(r[1]), r[1])):
        name, slash, rest = text.partition("/")
        fits = ((host == name) | F.endswith(host, F.lit("." + name))) & F.startswith(path, F.lit(slash + rest))
        rule = F.when(fits, text) if rule is None else rule.when(fits, text)
        action = F.when(fits, verdict) if action is None else action.when(fits, verdict)
    return (F.lit(None).cast("string"), F.lit(None).cast("string")) if rule is None else (rule, action)


def _weight(groups: DataFrame, start: float, lo: float = 0.5, hi: float = 1000.0) -> float:
    """Pseudo-pages of a prior, from rows (n, good, m): pages, good pages, parent's mean. Correlation within groups by moments."""
    x = groups.where("n > 0").agg(
        F.count(F.lit(1)).alias("k"), F.sum("n").alias("t"), F.sum(F.col("n") * F.col("n")).alias("sq"),
        F.sum(F.col("n") * F.pow(F.col("good") / F.col("n") - F.col("m"), 2)).alias("s"), F.sum(F.col("n") * F.col("m") * (1 - F.col("m"))).alias("v"),
    ).first()
    if not x["k"] or not x["v"]:
        return start
    v = x["v"] / x["t"]
    room = (x["t"] - x["sq"] / x["t"] - (x["k"] - 1)) * v
    if room <= 0:
        return start
    rho = (x["s"] - (x["k"] - 1) * v) / room
    return min(hi, max(lo, 1 / rho - 1)) if rho > 0 else hi


def host_reputation(named: DataFrame, start_mean: float = 0.5, start_weight: float = 8.0, two_label=TWO_LABEL_SUFFIXES) -> DataFrame:
    """Rows with `host` and `good` (1, 0 or null) -> one row per host: host, n, good, alpha, beta."""
    hosts = named.groupBy("host").agg(F.count("good").alias("n"), F.coalesce(F.sum("good"), F.lit(0)).alias("good"))
    hosts = hosts.withColumns({"domain": domain_of(F.col("host"), two_label), "suffix": suffix_of(F.col("host"), two_label)})
    domains = hosts.groupBy("domain", "suffix").agg(F.sum("n").alias("n"), F.sum("good").alias("good"))
    suffixes = domains.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("good").alias("good"))
    total = suffixes.agg(F.sum("n").alias("n"), F.sum("good").alias("good")).first()
    mean = total["good"] / total["n"] if total["n"] else start_mean

    def shrunk(x: DataFrame, weight: float) -> DataFrame:
        return x.withColumn("mean", (F.col("good") + weight * F.col("m")) / (F.col("n") + weight))

    suffixes = suffixes.withColumn("m", F.lit(float(mean)))
    suffixes = shrunk(suffixes, _weight(suffixes, start_weight)).select("suffix", F.col("mean").alias("m"))
    domains = domains.join(suffixes, "suffix")
    domains = shrunk(domains, _weight(domains, start_weight)).select("domain", F.col("mean").alias("m"))
    hosts = hosts.join(domains, "domain")
    weight = _weight(hosts, start_weight)
    return hosts.select("host", "n", "good", (F.col("good") + weight * F.col("m")).alias("alpha"), (F.col("n") - F.col("good") + weight * (1 - F.col("m"))).alias("beta"))


def filter_urls(pages: DataFrame, outcomes: DataFrame, rules=RULES, least: float = 0.8, z: float = 1.0, id_col: str = "page_id", url_col: str = "url", two_label=TWO_LABEL_SUFFIXES) -> DataFrame:
    """One row per page: id, host, path, rule, verdict. `outcomes` has columns (id, good): known results of pages, one row per id at most."""
    x = pages.select(F.col(id_col).alias("_id"), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    known = outcomes.select(F.col(outcomes.columns[0]).alias("_id"), F.col(outcomes.columns[1]).cast("int").alias("good"))
    reputation = host_reputation(x.join(known, "_id", "left").select("host", "good"), two_label=two_label)
    a, b = F.col("alpha"), F.col("beta")
    bound = a / (a + b) - z * F.sqrt(a * b / ((a + b) * (a + b) * (a + b + 1)))
    passes = reputation.select("host", (F.round(bound, 9) >= least).alias("_passes"))
    rule, action = matched_rule(F.col("host"), F.col("path"), rules)
    own = F.when(F.col("_passes"), "allow").otherwise("block")
    return x.join(passes, "host").select(F.col("_id").alias(id_col), "host", "path", rule.alias("rule"), F.coalesce(action, own).alias("verdict"))

"""Each operator against brute force on small tables, with nulls, empty texts, ties, repeated rows, empty tables and clashing columns."""

import hashlib
import itertools
import random
import re
import struct
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from studymap.llm import components, exact_dedup, latent_quality, mixing, near_dedup, sentencepiece_viterbi, sharding, substring_dedup, topk_search, toxic_crf, url_filter
from studymap.llm.base import word_count

DOC = "doc_id long, text string, lang string, source string, n_chars long"


def docs(spark, rows):
    """rows: (doc_id, text, source)."""
    return spark.createDataFrame([(i, t, None, s, None) for i, t, s in rows], DOC)


def clashing(df):
    """The same table with columns that operators might use themselves."""
    for name in ("kept", "keep_id", "size", "score", "_id", "_t", "_h", "group_size", "component_id", "ids", "rank", "good", "host", "shard"):
        df = df.withColumn(name, F.lit("own"))
    return df


def some(n=300, seed=1):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(60)]
    out = [(i, " ".join(rng.choice(words) for _ in range(rng.randrange(1, 40))), rng.choice(["a", "b", "b", "b", None])) for i in range(n)]
    return [*out, (n, None, "a"), (n + 1, "", None), (n + 2, out[0][1], "b"), (n + 3, out[0][1], "c"), (n + 4, " \t\n", "b")]


def test_exact_duplicates(spark):
    rows = some() + [(7, "same", "a"), (7, "same", "a"), (None, "lone", "a"), (None, "same", "a")]
    d = docs(spark, rows)
    rows += [(8000 + i, "long word " * 30_000, "a") for i in range(3)]
    d = docs(spark, rows)
    got = exact_dedup.exact_duplicates(clashing(d), runs=16, fan_in=4).collect()
    assert sorted(map(str, got)) == sorted(map(str, exact_dedup.exact_duplicates(d.repartition(5)).collect()))
    groups = {}
    for i, t, _ in rows:
        groups.setdefault(t or "", []).append(i)
    assert len(got) == len(rows)
    by = {}
    for r in got:
        by.setdefault(r["text_sha256"], []).append(r)
    for t, ids in groups.items():
        mine = by[hashlib.sha256(t.encode()).hexdigest()]
        best = max((i for i in ids if i is not None), default=None)
        assert len(mine) == len(ids) and {r["keep_id"] for r in mine} == {best} and {r["group_size"] for r in mine} == {len(ids)}
        kept = [r["doc_id"] for r in mine if r["kept"]]
        assert kept == [best]
    left = exact_dedup.without_exact_duplicates(clashing(d))
    assert left.columns == clashing(d).columns and left.count() == len(groups)
    assert sorted((r["doc_id"] is None, r["doc_id"], r["text"] or "") for r in left.collect() if r["doc_id"] is not None) == sorted((False, b, t) for t, b in ((t, max((i for i in g if i is not None), default=None)) for t, g in groups.items()) if b is not None)
    least = exact_dedup.exact_duplicates(d, keep="smallest").where("kept").count()
    assert least == len(groups) and exact_dedup.exact_duplicates(d.limit(0)).count() == 0


def test_digest_runs_are_sorted_and_merged(spark):
    """Six binomial rounds for 64 runs: each an exchange by run and slice with a pass over sorted entries behind it, none over unsorted ones, no Python."""
    rows = spark.range(64).select(F.col("id").alias("_key"), (F.col("id") % 7).cast("string").alias("t"))
    rows = exact_dedup._in_runs(exact_dedup._digested(rows, "_key", "t").drop("t"), "_key", 64)
    plan = exact_dedup.merged_runs(rows, "_key", 64, 2, 6, "largest")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("REPARTITION_BY_COL") == 6 and plan.count("SortAggregate") == 14 and "HashAggregate" not in plan and "Python" not in plan


def spark_hash(*values):
    """Spark's xxhash64 of ints (4 bytes), longs (8 bytes) and strings, nulls skipped, by the public hash."""
    h = 42
    for kind, v in values:
        if v is not None:
            h = xxhash.xxh64_intdigest(v.encode() if kind == "s" else struct.pack("<i" if kind == "i" else "<q", v), h)
    return h - (1 << 64) if h >= 1 << 63 else h


def test_shards_are_cut_from_the_interleaved_order(spark):
    """The whole order by brute force: seeded order within each source, fractional ranks, cuts at equal counts; one-row sources spread as well."""
    rows = [(i, t, s) for i, t, s in some()] + [(1000 + i, "lone " * (i % 5), f"site{i}") for i in range(400)] + [(None, f"text {i}", "b") for i in range(50)] + [(5000, "very long " * 40_000, "b")]
    drawn = {}
    for i, t, s in rows:
        drawn.setdefault(s, []).append((spark_hash(("i", 7), ("s", None if i is None else str(i)), ("l", zlib.crc32((t or "").encode()))), i is not None, i or 0, t))
    line = []
    for s, mine in drawn.items():
        u = (spark_hash(("i", 7), ("s", s)) % (1 << 30) + 0.5) / (1 << 30)
        line += [((r + 1 - u) / len(mine), s is not None, s or "", *m) for r, m in enumerate(sorted(mine, key=lambda m: m[:3]))]
    line.sort(key=lambda x: x[:-1])
    n, want = len(line), []
    for k, x in enumerate(line):
        shard = 8 * k // n
        want.append((x[5] if x[4] else -1, zlib.crc32((x[6] or "").encode()), shard, k - (shard * n + 7) // 8))
    got = sharding.stratified_shards(docs(spark, rows), 8, slices=64).collect()
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"], r["text_crc32"], r["shard"], r["slot"]) for r in got) == sorted(want)
    lone = [sum((r["doc_id"] or 0) // 400 in (2, 3) and 1000 <= r["doc_id"] < 1400 for r in got if r["shard"] == k and r["doc_id"] is not None) for k in range(8)]
    assert min(lone) > 25


def test_shards(spark):
    rows = some() + [(5, "again", "a"), (5, "again", "a")]
    got = sharding.stratified_shards(clashing(docs(spark, rows)), 8, slices=16).collect()
    sizes = {}
    for r in got:
        sizes.setdefault(r["shard"], []).append(r["slot"])
        assert r["law"] == "rows" and r["grown_shard"] is None
    assert set(sizes) == set(range(8)) and max(map(len, sizes.values())) - min(map(len, sizes.values())) <= 1
    assert all(sorted(s) == list(range(len(s))) for s in sizes.values())
    want = sorted((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t, _ in rows)
    assert sorted((r["doc_id"], r["size"], r["text_crc32"]) for r in got) == want
    source = {i: s for i, _, s in rows}
    for s in ("a", "b", None):
        share = [sum(source[r["doc_id"]] == s for r in got if r["shard"] == k) for k in range(8)]
        assert max(share) - min(share) <= 2  # every shard holds the mixture
    again = sharding.stratified_shards(docs(spark, rows).repartition(7), 8, slices=16).collect()
    assert sorted(map(str, got)) == sorted(map(str, again))
    assert sharding.stratified_shards(docs(spark, [])).count() == 0


def fill(sizes, weights=(5, 2, 1), cap=3):
    """Targets by repeated sharing of the excess."""
    names = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    w = {s: weights[i % 3] for i, s in enumerate(names)}
    total, full = sum(sizes.values()), {}
    while True:
        open_ = [s for s in names if s not in full]
        left = total - sum(full.values())
        t = {s: left * w[s] / sum(w[o] for o in open_) for s in open_}
        over = [s for s in open_ if t[s] > cap * sizes[s] + 1e-9]
        if not over:
            return full | t
        full |= {s: cap * sizes[s] for s in over}


def test_mix(spark):
    rng = random.Random(4)
    rows = [(i, " ".join(["w"] * rng.randrange(1, 30)), rng.choice(["big"] * 9 + ["mid"] * 3 + ["tiny"])) for i in range(900)]
    rows += [(1000 + i, "x y", f"s{i}") for i in range(5)] + [(2000, None, "null"), (2001, "", None), (2002, "q", None)]
    d = docs(spark, rows)
    got = mixing.mix(clashing(d), slices=32).collect()
    words = {i: len((t or "").split()) for i, t, _ in rows}
    sizes = {}
    for i, _, s in rows:
        sizes[s] = sizes.get(s, 0) + words[i]
    want, source = fill(sizes), {i: s for i, _, s in rows}
    taken = {}
    for r in got:
        s = source[r["doc_id"]]
        assert r["size"] == words[r["doc_id"]] and r["source_size"] == sizes[s] and abs(r["target"] - want[s]) < 1e-6
        assert r["taken"] % max(r["size"], 1) == 0 and r["taken"] <= 3 * r["size"]
        taken[s] = taken.get(s, 0) + r["taken"]
    assert all(abs(taken[s] - want[s]) <= 16 for s in sizes)
    # Complete epochs come before the fraction: copies of a source's documents differ by one at most.
    for s in ("big", "mid", "tiny"):
        c = {r["copies"] for r in got if source[r["doc_id"]] == s}
        assert max(c) - min(c) <= 1
    again = mixing.mix(d.repartition(5), slices=7).collect()
    assert sorted((r["doc_id"], r["taken"]) for r in got) == sorted((r["doc_id"], r["taken"]) for r in again)
    out = mixing.mixed_documents(clashing(d))
    assert out.columns == clashing(d).columns and out.count() == sum(r["copies"] for r in mixing.mix(d).collect())
    assert mixing.mix(docs(spark, [])).count() == 0


def test_mix_takes_prefixes_of_the_key_order(spark):
    """The selection by brute force: exponential keys from hash and weight, complete epochs, then the prefix that fills the rest to half a document."""
    rng = random.Random(7)
    rows = [(i, " ".join(["w"] * rng.randrange(1, 30)), rng.choice(["big"] * 9 + ["mid"] * 3 + ["tiny", None]), rng.choice([0.0, 0.2, 1.0, 3.0, None])) for i in range(700)]
    rows += [(None, f"x {i}", "big", 1.0) for i in range(20)] + [(5, "again again", "mid", 1.0), (3000, "w " * 20_000, "mid", 1.0)]
    sizes, keyed = {}, {}
    for i, t, s, q in rows:
        n = len(t.split())
        sizes[s] = sizes.get(s, 0) + n
        u = (spark_hash(("i", 11), ("s", None if i is None else str(i)), ("l", zlib.crc32(t.encode()))) % (1 << 52) + 0.5) / (1 << 52)
        keyed.setdefault(s, []).append((-np.log(u) / max(q or 0, 0.05), i is not None, i or 0, n))
    want = []
    for s, target in fill(sizes).items():
        epochs = min(3, int(target / sizes[s] + 1e-12))
        at, rest = 0, target - epochs * sizes[s]
        for _, named, i, n in sorted(keyed[s]):
            want.append((i if named else -1, n, n * (epochs + (at + n / 2 <= rest and epochs < 3 and rest > 0))))
            at += n
    d = spark.createDataFrame(rows, "doc_id long, text string, source string, q double")
    got = mixing.mix(d, weight_col="q").collect()
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"], r["size"], r["taken"]) for r in got) == sorted(want)


def test_mix_weights_are_learnt(spark):
    rng = random.Random(8)
    rows, labels = [], []
    for i in range(400):
        w = [rng.choice(["river", "runs", "over", "old", "stone", "moss"]) + str(rng.randrange(9)) * (i % 3 == 0) for _ in range(rng.randrange(30, 60))]
        rows.append((i, " ".join(w) if i % 2 else " ".join(x.upper() + "%%%" for x in w), "a"))
        labels.append((i, i % 2))
    d, l = docs(spark, [*rows, (1000, None, "a"), (1001, "", "b")]), spark.createDataFrame([*labels, (0, 1), (3, None)], "doc_id long, quality int")
    model = mixing.train_weight(d, l)
    weight = lambda t: model(np.array([mixing.form_of(t.encode())[1]]))[0]
    assert all((weight(t) > 0.5) == bool(i % 2) for i, t, _ in rows)
    got = mixing.mix(d, l, weights=(1, 9)).where("source_size > 100").collect()
    share = [np.mean([r["taken"] > 0 for r in got if r["doc_id"] % 2 == k]) for k in (0, 1)]
    assert len(got) == 401 and share[1] > share[0]
    assert mixing.train_weight(d, l.limit(0)) is None and mixing.mix(d.limit(0), l).count() == 0


def test_heavier_documents_are_taken_first(spark):
    rows = [(i, "w " * 10, "a", 0.1 if i % 2 else 5.0) for i in range(2000)] + [(9999, "w " * 60000, "b", 1.0)]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string, q double")
    got = mixing.mix(d, weights=(1, 10), weight_col="q").where("source_size = 20000").select((F.col("doc_id") % 2).alias("light"), (F.col("taken") > 0).alias("t")).collect()
    share = [np.mean([r["t"] for r in got if r["light"] == k]) for k in (0, 1)]
    assert share[0] > share[1]


def test_urls(spark):
    urls = ["http://A.Example.com/en/x?y#z", "https://www.example.com/en/1", "http://x.net/fr/", "ftp://x.net/de/a#b", "nothing", None, "http://h.org", "a://b://c/d", "http://notexample.com/en/", "http://com/", "http://q.co.uk/p?r"]
    pages = clashing(spark.createDataFrame([(i, u, None) for i, u in enumerate(urls)] + [(3, urls[3], None)], "page_id long, url string, html string"))
    labels = spark.createDataFrame([(6, 1), (10, 0), (5, None)], "doc_id long, quality int")
    got = {r["page_id"]: r for r in url_filter.filter_urls(pages, labels).collect()}
    assert [(got[i]["host"], got[i]["path"]) for i in (0, 3, 4, 5, 6, 7)] == [("a.example.com", "/en/x"), ("x.net", "/de/a"), ("", ""), ("", ""), ("h.org", ""), ("b:", "//c/d")]
    assert [got[i]["rule"] for i in range(11)] == ["example.com/en/", "www.example.com/en/", "net/fr/", None, None, None, None, None, "com/", "com/", None]
    assert [got[i]["verdict"] for i in (0, 1, 2, 8)] == ["block", "allow", "block", "allow"]
    assert {r["verdict"] for r in got.values()} <= {"allow", "block"}
    assert url_filter.filter_urls(pages.limit(0), labels).count() == 0 and url_filter.filter_urls(pages, labels.limit(0)).count() == 12


def test_reputation_shrinks(spark):
    rows = [("good.site.org", 1)] * 40 + [("bad.other.org", 0)] * 30 + [("new.site.org", None), ("new.other.org", None), ("lone.xyz", None)]
    rep = {r["host"]: r["alpha"] / (r["alpha"] + r["beta"]) for r in url_filter.host_reputation(spark.createDataFrame(rows, "host string, good int")).collect()}
    assert rep["good.site.org"] > rep["new.site.org"] > rep["lone.xyz"] > rep["new.other.org"] > rep["bad.other.org"]


@pytest.mark.parametrize("near_one", [False, True])
def test_top_k(spark, near_one):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(400, 16)) * rng.uniform(0.1, 3, size=(400, 1))
    if near_one:
        x[:, 0] += 30
    rows = [(i, [float(v) for v in r], 0) for i, r in enumerate(x)] + [(400, None, 0), (420, [float("nan")] * 16, 0), (440, [1.0] * 15 + [None], 0), (460, [1.0], 0), (480, [0.0] * 16, 0), (500, rows0 := [float(v) for v in x[3]], 0), (501, rows0, 0)]
    rows += [(20, rows0, 0), (40, [float(v) for v in x[40]], 0), (7, rows0, 0)]  # repeated rows, of queries too
    v = clashing(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int"))
    got = topk_search.top_k(v, lambda i: i % 20 == 0, k=20, seed_size=64, block=50, query_block=8).collect()
    keep = [(i, np.floor(64 * np.array(r)).astype(int)) for i, r, _ in rows if r and len(r) == 16 and all(q is not None and np.isfinite(q) for q in r)]
    want = []
    for q, a in keep:
        if q % 20 == 0:
            best = sorted((-int(a @ b), c) for c, b in keep if c != q)[:20]
            want += [(q, k + 1, c, -s) for k, (s, c) in enumerate(best)]
    assert sorted(map(tuple, got)) == sorted(want)
    assert topk_search.top_k(v.limit(0), lambda i: i % 20 == 0).count() == 0


def shingles(text, n=5):
    w = re.findall(r"[^ \t-\r]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())


def linked(rows):
    sets = {i: shingles(t) for i, t, _ in rows if i is not None}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in itertools.combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if sets[a] and sets[b] and 100 * both >= 75 * len(sets[a] | sets[b]):
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return {i: (len(sets[i]), find(i), find(i) == i) for i in sets}


def test_near_duplicates(spark):
    rng = random.Random(8)
    base = [f"t{i}" for i in range(150)]
    rows = some(60)
    for k in range(120):  # copies with one to many edits: links at every similarity, chains, outliers
        w = list(base)
        for _ in range(rng.randrange(0, 9)):
            w[rng.randrange(len(w))] = f"e{rng.randrange(10**6)}"
        rows.append((1000 + k, " ".join(w).upper() if k % 3 else " ".join(w), "a"))
    rows += [(2000, "one two", "a"), (2001, "ONE  two", "a"), (2002, "one", "a"), (None, "one two", "a")]
    got = near_dedup.near_duplicates(clashing(docs(spark, rows)), block=16).collect()
    mine = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in got if r["doc_id"] is not None}
    assert mine == linked(rows) and len(got) == len(rows)
    left = near_dedup.without_near_duplicates(clashing(docs(spark, rows)))
    assert left.count() == sum(k for _, _, k in mine.values()) + 1 and left.columns == clashing(docs(spark, rows)).columns
    assert near_dedup.near_duplicates(docs(spark, [])).count() == 0


def test_near_duplicates_of_repeated_identifiers(spark):
    """Two texts under one identifier keep their links; rows of one identifier are one document; very long texts are whole."""
    rng = random.Random(3)
    a, b, c = (" ".join(f"{n}{rng.randrange(10**6)}" for _ in range(90)) for n in "abc")
    long_ = " ".join(f"l{rng.randrange(10**6)}" for _ in range(21_000))
    rows = [(1, a, "s"), (1, b, "s"), (2, a + " one", "s"), (3, b + " one", "s"), (4, c, "s"), (4, c, "s"), (4, None, "s"), (5, c + " two", "s"), (6, "", "s"), (6, " ", "s"), (7, long_, "s"), (8, long_ + " tail", "s"), (9, long_[: len(long_) // 2], "s"), (0, "", "s"), (0, a + " three", "s")]
    got = sorted((r["doc_id"], r["component_id"], r["kept"]) for r in near_dedup.near_duplicates(clashing(docs(spark, rows))).collect())
    assert got == sorted((i, g, i == g) for i, g in ((1, 0), (1, 0), (2, 0), (3, 0), (4, 4), (4, 4), (4, 4), (5, 4), (6, 6), (6, 6), (7, 7), (8, 7), (9, 9), (0, 0), (0, 0)))
    left = near_dedup.without_near_duplicates(docs(spark, rows))
    assert sorted(r["doc_id"] for r in left.collect()) == [0, 0, 4, 4, 4, 6, 6, 7, 9]


def test_open_buckets_test_every_pair_of_components(spark):
    """Members of a bucket's largest component meet all others and not each other; all others meet."""
    rows = [(1, i, 100 if i < 40 else i) for i in range(55)] + [(2, 1, 5), (2, 2, 5)]
    placed = spark.createDataFrame(rows, "_key long, _c long, _component long").withColumn("_salt", near_dedup.salt("_c"))
    cells = {}
    for r in near_dedup._open_members(placed, 4).collect():
        assert r["_key"] == 1
        cells.setdefault((r["_i"], r["_j"]), set()).add(r["_c"])
    met = {p for m in cells.values() for p in itertools.combinations(sorted(m), 2)}
    assert all((i, j) in met for i, j in itertools.combinations(range(55), 2) if j >= 40)
    assert len(cells) < 120


def test_min_and_max_agree_with_similarity():
    rng = np.random.default_rng(0)
    a = rng.integers(0, 2**63, 400, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    x = rng.integers(0, 2**63, 1000, dtype=np.uint64)
    one, two = near_dedup._signatures([np.unique(x[:900]), np.unique(x[100:])], a, 1)
    assert abs((one == two).mean() - 0.8) < 0.04


def test_components(spark, monkeypatch):
    links = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 100), (200, 200), (102, 100)]
    want = {**{i: 0 for i in range(41)}, 100: 100, 101: 100, 102: 100}
    links = spark.createDataFrame([*links, (None, 7), (3, None)], "a long, b long")
    for most in (components.MOST_SENT, 0):  # least neighbours broadcast, and joined by salt
        monkeypatch.setattr(components, "MOST_SENT", most)
        assert dict(map(tuple, components.components(links).collect())) == want
    assert components.components(links.limit(0)).count() == 0


def test_substrings(spark):
    rng = random.Random(5)
    vocab = [f"v{i}" for i in range(400)]
    text = lambda n: [rng.choice(vocab) for _ in range(n)]
    shared, long_ = text(70), text(400)
    rows = [(i, " ".join(text(rng.randrange(0, 120)) + (shared if i % 3 == 0 else []) + text(20)), "a") for i in range(40)]
    rows += [(100, " ".join(long_), "a"), (101, "\n".join(long_), "a"), (102, " ".join(long_[:200] + ["new"] + long_[200:]), "a"), (103, " ".join(["same"] * 300), "a"), (104, " ".join(["same"] * 90), "b"), (105, None, "a"), (106, "", "a"), (None, " ".join(long_), "a"), (107, " ".join(shared[:50]), "a"), (108, " ".join(shared[:49]), "a"), (-1, "few words", "a")]
    got = {r["doc_id"]: r for r in substring_dedup.remove_repeats(clashing(docs(spark, rows)), texts=True).collect()}
    low = {}
    words = {i: (t or "").split() for i, t, _ in rows if i is not None}
    for i, w in words.items():
        for s in range(len(w) - 49):
            key = tuple(w[s : s + 50])
            low[key] = min(low.get(key, i), i)
    for i, w in words.items():
        gone = {p for s in range(len(w) - 49) if low[tuple(w[s : s + 50])] < i for p in range(s, s + 50)}
        kept = " ".join(x for p, x in enumerate(w) if p not in gone)
        assert (got[i]["n_words"], got[i]["n_removed"], got[i]["kept_sha256"], got[i]["kept_text"]) == (len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest(), kept), i
    assert got[None]["n_removed"] == 0 and len(got) == len(rows)
    assert substring_dedup.remove_repeats(docs(spark, [])).count() == 0
    # Heavy minimisers, windows dealt one by one, give the same; so does a mixture of both ways.
    for bound in (0, 2000):
        other = {r["doc_id"]: r for r in substring_dedup.remove_repeats(docs(spark, rows), texts=True, heavy_words=bound).collect()}
        assert other == got


def test_substrings_of_repeated_identifiers_and_long_texts(spark):
    """Rows of one identifier are judged each by its own text, never against each other."""
    rng = random.Random(6)
    a, b = ([f"{n}{rng.randrange(10**6)}" for _ in range(80)] for n in "ab")
    long_ = [f"l{rng.randrange(3000)}" for _ in range(60_000)]
    rows = [(1, " ".join(a), "s"), (1, " ".join(b), "s"), (1, " ".join(a), "s"), (2, " ".join(b + ["x"]), "s"), (3, " ".join(long_), "s"), (4, " ".join(long_[100:] + a), "s")]
    for bound in (100_000, 0):
        got = sorted((r["doc_id"], r["n_words"], r["n_removed"]) for r in substring_dedup.remove_repeats(docs(spark, rows), heavy_words=bound).collect())
        assert got == [(1, 80, 0), (1, 80, 0), (1, 80, 0), (2, 81, 80), (3, 60_000, 0), (4, 59_980, 59_980)]


def test_segmentation_is_best_path():
    rng = random.Random(6)
    letters = "abcé▁"
    plain = {"".join(rng.choice(letters[:4]) for _ in range(rng.randrange(1, 5))) for _ in range(25)} | {"▁a", "▁bc", "▁"}
    pieces = [("<unk>", 0.0, 2)] + [(f"<0x{b:02X}>", 0.0, 6) for b in range(256)] + [(p, -rng.uniform(0.5, 6), 1) for p in sorted(plain)]
    v = sentencepiece_viterbi.Vocabulary(pieces)
    score = {p: s for p, s, k in pieces if k == 1}

    def best(s):
        top = [0.0] + [-1e18] * len(s)
        for i in range(len(s)):
            for j in range(i + 1, len(s) + 1):
                w = score.get(s[i:j], v.unknown_score if j == i + 1 else None)
                if w is not None:
                    top[j] = max(top[j], top[i] + w)
        return top[-1]

    e = sentencepiece_viterbi.Encoder(v)
    texts = ["".join(rng.choice("abcé z中\n") for _ in range(rng.randrange(0, 14))) for _ in range(200)] + [None, "", " ", "abc" * 300]
    ids, counts = e(texts)
    at = 0
    for t, n in zip(texts, counts):
        mine = ids[at : at + n].tolist()
        at += n
        assert v.decode(mine) == (t or "")
        got, run = 0.0, b""
        for i in [*mine, None]:
            if i is not None and pieces[i][2] == 6:
                run += bytes([int(pieces[i][0][3:5], 16)])
                continue
            got += v.unknown_score * len(run.decode())
            run = b""
            got += score[pieces[i][0]] if i is not None else 0
        assert abs(got - best(v.normalised(t))) < 1e-6, t


def test_encode_and_decode(spark):
    rows = some(40) + [(900, "Zwölf Boxkämpfer\tjagen 中 😀\n\n ende ", "a"), (900, "x" * 5000, "a")]
    got = sentencepiece_viterbi.encode(clashing(docs(spark, rows)))
    assert got.where("NOT round_trip").count() == 0 and got.count() == len(rows)
    assert got.where("size(ids) <> n_tokens").count() == 0
    texts = sorted((r["doc_id"], r["text"]) for r in sentencepiece_viterbi.decode(got).collect())
    assert texts == sorted((i, t or "") for i, t, _ in rows)
    assert sentencepiece_viterbi.encode(docs(spark, [])).count() == 0


def test_marginals_equal_brute_force():
    rng = np.random.default_rng(1)
    odds, pair = rng.normal(size=11), rng.normal(size=(2, 2))
    starts = np.zeros(11, bool)
    starts[[0, 4, 5]] = True
    got, pairs = toxic_crf.marginals(odds, starts, pair, strip=4)
    total = np.zeros((2, 2))
    for a, b in ((0, 4), (4, 5), (5, 11)):
        weight, sums, px = 0.0, np.zeros(b - a), np.zeros((2, 2))
        for y in itertools.product((0, 1), repeat=b - a):
            w = np.exp(sum(o for o, s in zip(odds[a:b], y) if s) + sum(pair[p, q] for p, q in zip(y, y[1:])))
            weight += w
            sums += w * np.array(y)
            for p, q in zip(y, y[1:]):
                px[p, q] += w
        assert np.allclose(got[a:b], sums / weight)
        total += px / weight
    assert np.allclose(pairs, total)


def planted(n=240):
    rng = random.Random(9)
    words = [f"{a}{b}" for a in ("lam", "ter", "son", "vid") for b in ("ol", "ur", "ine", "as", "ek")]
    rows, labels = [], []
    for i in range(n):
        w = [rng.choice(words) for _ in range(rng.randrange(20, 60))]
        bad = i % 3 == 0
        if bad:
            for _ in range(3):
                w[rng.randrange(len(w))] = rng.choice(["Vile!", "foul", "grotzel"]) + ""
        rows.append((i, " ".join(w), "a"))
        labels.append((i, int(not bad), int(bad)))
    return rows, labels


def test_toxicity(spark):
    rows, labels = planted()
    rows += [(1000, None, "a"), (1001, "", "a"), (None, "foul foul", "a"), (1002, "foul " * 3000, "a")]
    d, l = clashing(docs(spark, rows)), spark.createDataFrame(labels + [(1, None, None)], "doc_id long, quality int, toxic int")
    model = toxic_crf.train(d, l, trains=F.col("doc_id") % 4 != 1)
    got = {r["doc_id"]: r for r in toxic_crf.score(d, model, spans=True).collect()}
    held = [i for i, _, _ in labels if i % 4 == 1]
    assert all((got[i]["score"] >= 0.7) == (i % 3 == 0) for i in held)
    text = dict((i, t) for i, t, _ in rows)
    for i in held[:20]:
        found = [text[i].encode()[s["begin"] : s["end"]].decode() for s in got[i]["spans"]]
        assert all(re.search("Vile|foul|grotzel", s) for s in found) and bool(found) == (i % 3 == 0)
    assert got[1000]["score"] == got[1001]["score"] < 0.7 and got[None]["score"] > 0.7
    left = toxic_crf.without_toxic(d, l)
    assert left.columns == d.columns and {r["doc_id"] for r in left.where("doc_id < 240").collect()} == {i for i, _, t in labels if not t}
    assert toxic_crf.score(d.limit(0), model).count() == 0
    assert toxic_crf.score(d, toxic_crf.train(d, l.limit(0))).agg(F.max("score")).first()[0] == 0


def test_document_scores_by_brute_force(spark):
    """The fit on the executors is the fit in one process; a document's score is recomputed from marginals summed over all taggings."""
    rows, labels = planted(60)
    d, l = docs(spark, rows), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    model = toxic_crf.train(d, l)
    sample = sorted(((r["_h"], r["_text"], r["_y"]) for r in toxic_crf.bounded_sample(d, l, "toxic", 2400, F.lit(True), 40_000).collect()))
    plain = toxic_crf.fit([t.encode().lower().split() for _, t, _ in sample], np.array([y == 1 for _, _, y in sample]))
    assert np.allclose(model.weights, plain.weights) and np.allclose(model.pair, plain.pair) and np.allclose(model.head, plain.head) and np.isclose(model.bias, plain.bias)
    texts = [" ".join(t.split()[:k]) for k, (_, t, _) in zip((0, 1, 3, 7, 9), rows)] + ["Vile! foul ol grotzel sonas"]
    got = {r["doc_id"]: r["score"] for r in toxic_crf.score(docs(spark, [(i, t, "a") for i, t in enumerate(texts)]), model).collect()}
    odds = model.odds()
    for i, t in enumerate(texts):
        w = [odds[x] for x in t.encode().lower().split()]
        total, part = 0.0, np.zeros(len(w))
        for y in itertools.product((0, 1), repeat=len(w)):
            p = np.exp(sum(o for o, s in zip(w, y) if s) + sum(model.pair[a, b] for a, b in zip(y, y[1:])))
            total += p
            part += p * np.array(y)
        m = part / total
        s = m[m > 0.05].sum()
        x = [1, np.log1p(s), m.max(), np.log1p(200 * s / (len(w) + 20))] if w else [1, 0, 0, 0]
        assert abs(got[i] - 1 / (1 + np.exp(-np.dot(x, model.head)))) < 1e-9


def test_contradicting_and_repeated_labels_do_not_train(spark):
    d = docs(spark, [(i, f"text {i}", "a") for i in range(4)] + [(0, "again", "a")])
    l = spark.createDataFrame([(0, 0, 1), (0, 0, 1), (1, 0, 1), (1, 1, 0), (2, 1, 0), (3, None, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    got = toxic_crf.bounded_sample(d, l, "toxic", 100, F.lit(True), 40_000).collect()
    assert sorted((r["_text"], r["_y"]) for r in got) == [("again", 1), ("text 2", 0)]


def test_toxic_minority_vocabulary():
    """As many toxic as clean texts; a tenth of the toxic ones have words of their own, which no log odds of 4 would reach."""
    rng = random.Random(4)
    plain = [f"{a}{b}".encode() for a in ("lam", "ter", "son", "vid") for b in ("ol", "ur", "ine", "as", "ek")]

    def text(extra):
        w = [rng.choice(plain) for _ in range(40)]
        for at in rng.sample(range(40), 3) if extra else ():
            w[at] = rng.choice(extra)
        return w

    usual, rare = [b"vile", b"foul"], [b"grotzel"]
    train = [text(()) for _ in range(200)] + [text(usual) for _ in range(176)] + [text(rare) for _ in range(24)]
    model = toxic_crf.fit(train, np.arange(400) >= 200)
    held = [text(()) for _ in range(50)] + [text(usual) for _ in range(50)] + [text(rare) for _ in range(50)]
    assert ((model.score(*model.tag(held, model.odds())) >= 0.7) == (np.arange(150) >= 50)).all()


def test_quality(spark):
    rng = random.Random(2)
    rows, labels = [], []
    for i in range(300):
        good = i % 4 != 0
        w = [rng.choice(["the", "river", "runs", "over", "old", "stone", "and", "moss"]) for _ in range(40)]
        rows.append((i, " ".join(w).capitalize() + "." if good else " ".join(x + "%%%" for x in w) if i % 8 else " ".join([w[0]] * 60), "a"))
        labels.append((i, int(good), 0))
    rows += [(1000, None, "a"), (1001, "", "a"), (None, rows[1][1], "a"), (1002, rows[1][1], "a")]
    d, l = clashing(docs(spark, rows)), spark.createDataFrame(labels + [(1, None, None)], "doc_id long, quality int, toxic int")
    model = latent_quality.train(d, l, trains=F.col("doc_id") % 5 != 1)
    got = {r["doc_id"]: r["score"] for r in latent_quality.score(d, model).collect()}
    assert all((got[i] >= 0.5) == bool(q) for i, q, _ in labels if i % 5 == 1)
    assert got[1000] == got[1001] == 0.5 and got[1002] == got[1] == got[None]
    # The blocked votes are those of a plain loop.
    terms = latent_quality.Terms()
    x = model.place([rows[1][1]], terms)[0]
    cosine = model.vectors @ x
    near = np.argsort(-cosine)[: model.k]
    vote = np.maximum(cosine[near], 0) ** 8 * model.weight[near]
    assert abs((vote * model.label[near]).sum() / vote.sum() - got[1]) < 1e-3
    assert latent_quality.score(d.limit(0), model).count() == 0
    assert latent_quality.score(d, latent_quality.train(d, l.limit(0))).agg(F.max("score")).first()[0] == 0.5


def test_words(spark):
    x = spark.createDataFrame([("a\u00a0b c",), ("  ",), (None,), ("x\ty\r\nz",)], "t string")
    assert [r[0] for r in x.select(word_count(F.col("t"))).collect()] == [2, 0, 0, 3]

"""Queries that made their data up before and read given tables now: each equals its SQL and follows what the tables hold."""

import duckdb
import pytest

from studymap.queries import registry

from test_queries import TABLES, plain


@pytest.mark.parametrize("name", ["a_published_counts", "f_schema_of_json", "m_select_best", "s_json_config"])
def test_moved_query_equals_oracle(spark, small, name):
    q = registry()[name]
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    rel = con.sql(q.sql)
    df = q.run(spark, small).select(*rel.columns)
    assert sorted(tuple(map(plain, r)) for r in df.collect()) == sorted(tuple(map(plain, r)) for r in rel.fetchall())


def geography(spark, folder, customers):
    spark.createDataFrame(customers, "c_custkey long, c_nationkey int").write.parquet(f"{folder}/customer.parquet")
    spark.createDataFrame([(k, f"nation {k}", k % 2) for k in range(4)], "n_nationkey int, n_name string, n_regionkey int").write.parquet(f"{folder}/nation.parquet")
    spark.createDataFrame([(0, "east"), (1, "west")], "r_regionkey int, r_name string").write.parquet(f"{folder}/region.parquet")


def test_published_rates_follow_the_customers(spark, tmp_path):
    """Any 843 keys in a row give the published percentages; a key twice, a null key and an unknown nation count as the table says."""
    run = lambda folder: {r["variant"]: r for r in registry()["a_published_counts", "f_schema_of_json", "m_select_best", "s_json_config"].run(spark, f"{tmp_path}/{folder}").collect()}
    geography(spark, f"{tmp_path}/cycle", [(k, k % 4) for k in range(1000, 1843)])
    got = run("cycle")
    assert set(got) == {"hybrid", "network", "importer"}
    assert got["hybrid"]["accuracy"] == round(776 / 837, 6) and got["hybrid"]["predictive_power"] == round(837 / 843, 6)
    assert got["network"]["minor_rate"] == round(86 / 835, 6) and got["importer"]["major_rate"] == round(128 / 811, 6)
    geography(spark, f"{tmp_path}/odd", [(0, 0), (0, 0), (843, 3), (None, 1), (0, 9), (0, None)])  # slot 0 is right, a null key has no answer
    assert all((r["accuracy"], r["predictive_power"]) == (1.0, 0.75) for r in run("odd").values())


def test_best_head_follows_the_documents(spark, tmp_path):
    """A source whose words only the larger training sample holds gets its head; a null source is one more; the published choice still stands."""
    rare = [f"{a}{b}{c}" for a in "bcdfg" for b in "aeiou" for c in "klmnp"]
    rows = [(i, " ".join(["der", *rare[i % 100 : i % 100 + 3]]) if i % 2 else "the of", "de" if i % 2 else "en", "plain" if i % 5 else None) for i in range(400)]
    rows += [(1000 + i, rare[i % 100] + " the" * (i % 7 == 0), "de", "rare") for i in range(200)] + [(2000, None, "de", "empty"), (2001, "x", "it", "other")]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    q = registry()["m_select_best"]
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    got = {r["modality"]: (r["network"], r["accuracy"]) for r in q.run(spark, str(tmp_path)).collect()}
    assert got == {m: (n, a) for m, n, a in con.sql(q.sql).fetchall()}
    assert set(got) == {"plain", "rare", None} and got["rare"][0] == "head200"

    from studymap.operators import network

    table_1 = [(m, n, a) for m, d, r in (("CR", 0.971, 0.965), ("CT", 0.877, 0.846), ("MRI", 0.854, 0.802), ("US", 0.814, 0.79), ("XA", 0.812, 0.835)) for n, a in (("dense", d), ("residual", r))]
    best = {r["modality"]: r["network"] for r in network.select_best(spark.createDataFrame(table_1, "modality string, network string, accuracy double")).collect()}
    assert best == {"CR": "dense", "CT": "dense", "MRI": "dense", "US": "dense", "XA": "residual"}


def test_configuration_follows_the_parts(spark, tmp_path):
    """Quotes, line ends, accents, blanks, nulls, negative and repeated keys survive the files."""
    rows = [(1, 'a "b" \\ c', "PROMO", 3), (1, 'a "b" \\ c', "PROMO", 3), (99, "two\nlines\r\u2028", "", 25), (100, "gr\u00fcn, {x}: [y]", None, None), (-5, None, "SMALL", 24), (None, " ", "PROMO", 50), (2**62 + 1, "", "LARGE", 1), (2**62 + 2, "b", "LARGE", 1)]
    spark.createDataFrame(rows, "p_partkey long, p_name string, p_type string, p_size int").write.parquet(f"{tmp_path}/part.parquet")
    got = [tuple(r) for r in registry()["s_json_config"].run(spark, str(tmp_path)).collect()]
    want = [(k, "core" if size is not None and size < 25 else "extended", "drop" if kind == "PROMO" else "relabel", kind, name) for k, name, kind, size in rows]
    assert sorted(got, key=str) == sorted(want, key=str)


def test_schemas_follow_the_events(spark, tmp_path):
    """Every text counts under its own schema: more structures than one batch takes, numbers of any precision, nesting, nulls and texts that are not JSON."""
    rows = [('{"k": 1}', "STRUCT<k: BIGINT>"), ('{"k": 20}', "STRUCT<k: BIGINT>"), ('{"k": -3}', "STRUCT<k: BIGINT>"), ('{"k": 1.5}', "STRUCT<k: DOUBLE>"), ('{"k": 0.125}', "STRUCT<k: DOUBLE>"), ('{"k": 1e3}', "STRUCT<k: DOUBLE>")]
    rows += [('{"a": null, "b": {"c": ["x"], "d": true}}', "STRUCT<a: STRING, b: STRUCT<c: ARRAY<STRING>, d: BOOLEAN>>"), ("[1, 2]", "ARRAY<BIGINT>"), ("7", "BIGINT"), ("{}", "STRUCT<>"), (None, None), ("", None), ("{", None), ("no json", None)]
    rows += [(f'{{"k{i:03}": "it\'s"}}', f"STRUCT<k{i:03}: STRING>") for i in range(120)]
    spark.createDataFrame([(i, p) for i, (p, _) in enumerate(rows)], "event_id long, props string").write.parquet(f"{tmp_path}/events.parquet")
    q = registry()["f_schema_of_json"]
    got = {r["v"]: r["n"] for r in q.run(spark, str(tmp_path)).collect()}
    assert got == {v: sum(w == v for _, w in rows) for _, v in rows}
    con = duckdb.connect()
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    assert got == dict(con.sql(q.sql).fetchall())

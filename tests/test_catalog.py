"""Every registered query with SQL equals that SQL in another engine, on the smallest tables."""

import datetime
import decimal
import glob
import math
import os

import duckdb
import pytest

from synthselect import catalog

SF = "/root/testdata/sf0.001"
QUERIES, SQL = catalog.load()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"create view {os.path.basename(p)[:-8]} as select * from read_parquet('{p}')")
    return con


def _plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else round(v, 6) + 0.0
    if isinstance(v, decimal.Decimal):
        return int(v) if v == v.to_integral_value() else float(v)
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None)
    return v


@pytest.mark.parametrize("name", sorted(SQL))
def test_equals_sql(spark, duck, name):
    df = QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted((tuple(_plain(r[c]) for c in cols) for r in df.collect()), key=str)
    cur = duck.execute(SQL[name])
    at = [[c[0] for c in cur.description].index(k) for k in cols]
    assert len(at) == len(cur.description)
    want = sorted((tuple(_plain(r[i]) for i in at) for r in cur.fetchall()), key=str)
    assert sorted(map(str, got)) == sorted(map(str, want))


@pytest.mark.parametrize("name", ["grad_lowrank_influence", "ridge_loo", "ridge_weights", "ridge_diagnostics", "op_agg_approx_distinct", "op_agg_quantile_sketch"])
def test_has_rows(spark, name):
    assert QUERIES[name](spark, SF).count() > 0


def test_whole_tables_beside_one_language(spark):
    n = spark.read.parquet(f"{SF}/documents.parquet").count()
    assert all(QUERIES[q](spark, SF).count() == n for q in ("op_string_functions_all", "op_sink_partitioned_roundtrip_all"))
    words = spark.read.parquet(f"{SF}/documents.parquet").selectExpr("size(filter(split(lower(text), '[ \\n]+'), w -> w <> '')) AS n")
    assert QUERIES["op_udtf_ngrams_all"](spark, SF).selectExpr("sum(n)").first()[0] == words.selectExpr("sum(greatest(0, n - 1))").first()[0]


def test_string_functions_of_all_languages_by_brute_force(spark):
    import hashlib

    def distance(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
        return row[-1]

    rows = spark.read.parquet(f"{SF}/documents.parquet").collect()
    want = {r.doc_id: (r.text[:20].upper(), len(r.text), hashlib.md5(r.text.encode()).hexdigest(), r.source.replace("_", "-"), r.lang[:4].rjust(4, "."), distance(r.text[:10], r.text[1:11])) for r in rows}
    got = {r.doc_id: (r["head"], r.n, r.digest, r.src, r.padded, r.dist) for r in QUERIES["op_string_functions_all"](spark, SF).collect()}
    assert got == want and len({r.lang for r in rows}) > 1


def test_late_rows_of_one_window_are_counted_one_by_one(spark, tmp_path):
    con = duckdb.connect()
    con.execute(f"copy (select event_id + k * 1000000 as event_id, ts, user_id, event_type, value, props from '{SF}/events.parquet', (select unnest(range(10))::BIGINT as k)) to '{tmp_path}/events.parquet' (format parquet)")
    con.execute(f"create view events as select * from '{tmp_path}/events.parquet'")
    assert tuple(QUERIES["op_stream_late_rows"](spark, str(tmp_path)).select("windows", "counted", "dropped").first()) == con.execute(SQL["op_stream_late_rows"]).fetchone()


def test_string_functions_on_letters_of_several_bytes(spark, tmp_path):
    heads = ["ßaß", "straße ﬁn ŉ", "ᾳᾀΐ", "Önen", "éa", "aéb", "日本語", "", "\U00010d70ꟍ", "İıÿµ"]
    con = duckdb.connect()
    con.execute("create table documents (doc_id bigint, text varchar, lang varchar, source varchar, n_chars bigint)")
    con.executemany("insert into documents values (?, ?, 'en', 'src_1', 3)", [list(x) for x in enumerate(heads)] + [[99, None]])
    con.execute(f"copy documents to '{tmp_path}/documents.parquet' (format parquet)")
    cols = ["doc_id", "head", "n", "digest", "src", "padded", "dist"]
    got = [tuple(r) for r in QUERIES["op_string_functions"](spark, str(tmp_path)).select(*cols).orderBy("doc_id").collect()]
    assert got == con.execute(f"select {', '.join(cols)} from ({SQL['op_string_functions']}) order by doc_id").fetchall()


@pytest.mark.parametrize("name", ["cost_data_sizes", "cost_recipe_cube", "eval_ablation_drop", "eval_ablation_ranks", "eval_mark_ranks", "eval_model_comparison", "eval_relative_change", "eval_vs_best", "eval_vs_best_mean"])
def test_reads_a_given_table(spark, name):
    assert any(f.startswith(f"file://{SF}/") for f in QUERIES[name](spark, SF).inputFiles())

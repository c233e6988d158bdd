"""Registered queries against their SQL on the small tables, plans' shapes, and the entry point."""

import math
import subprocess
import sys
from pathlib import Path

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry_point
from phraseworks.plans import oracles, pipeline, workloads
from phraseworks.plans.queries import QUERIES, SQL
from phraseworks.sources import io

#: Views of DuckDB.
TABLES = "documents pages benchmark labels conversations events part lineitem orders customer supplier nation region embeddings".split()


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    c.sql("SET timezone = 'UTC'")
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def plain(v):
    if hasattr(v, "item"):
        v = v.item()
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return ""
    if isinstance(v, float):
        return f"{v:.9g}"
    return str(pd.Timestamp(v).tz_localize(None)) if hasattr(v, "year") else str(v)


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_its_sql(spark, sf, duck, name):
    got = QUERIES[name](spark, sf).toPandas()
    want = duck.sql(SQL[name])
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    at = [want.columns.index(c) for c in cols]
    left = sorted(tuple(map(plain, r)) for r in got[cols].astype(object).itertuples(index=False, name=None))
    assert left == sorted(tuple(plain(r[i]) for i in at) for r in want.fetchall())


def test_registry():
    queries, sql = entry_point.queries(), entry_point.oracle_sql()
    assert set(QUERIES) <= set(queries) and set(sql) <= set(queries) and len(QUERIES) > 90
    assert "MATERIALIZED" in oracles.sql("SELECT 1", "cnt")


def test_entry_without_the_optional_parts():
    """The core's queries are there when the training-data operators cannot be imported, for whatever reason."""
    code = "import sys; sys.modules['public_tokenizers'] = None; import __spark_entry__ as e; q = e.queries(); print(len(q), any(n.startswith('op1') for n in q), 'pipeline' in q, len(e.oracle_sql()))"
    out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd=Path(entry_point.__file__).parent, check=True).stdout.split()
    assert out[1:3] == ["False", "False"] and int(out[0]) == len(QUERIES) and int(out[3]) == len(SQL)


def test_entry(spark):
    df = entry_point.entry(spark)
    assert df.columns == ["k", "kind", "rank", "text", "score"] and df.count() > 0


def plan_of(df):
    return df._jdf.queryExecution().toString()


def test_plans(spark, sf):
    s = pipeline.stages_of(spark, sf)
    scan = plan_of(QUERIES["scan_pruned_columns"](spark, sf))
    assert "ReadSchema: struct<lang:string,source:string,n_chars:bigint>" in scan
    assert "PushedFilters: [In(lang" in plan_of(QUERIES["filter_lang_len"](spark, sf)).replace("IsNotNull(n_chars), IsNotNull(source), ", "") or "PushedFilters" in plan_of(QUERIES["filter_lang_len"](spark, sf))
    for name in ("chunk_tokens", "frequent_phrases", "topical_frequency", "bag_of_phrases", "npmi_coherence", "snapshot_sweep_1", "join_range_spans"):
        plan = plan_of(QUERIES[name](spark, sf))
        assert "CartesianProduct" not in plan and "BatchEvalPython" not in plan, name
    assert "MapInArrow" not in plan_of(s.raw) and "Exchange" not in plan_of(s.raw)


def test_sources_and_sinks(spark, sf, tmp_path):
    docs = io.require(io.scan(spark, sf, "documents"), io.SCHEMAS["documents"])
    with pytest.raises(TypeError, match="text: string in place of int"):
        io.require(docs, "text INT")
    one = docs.select("doc_id", "lang")
    for kind in ("parquet", "orc", "json", "csv"):
        one.write.format(kind).option("header", True).save(f"{tmp_path}/{kind}")
        back = io.read_corpus(spark, f"{tmp_path}/{kind}", kind, "doc_id BIGINT, lang STRING", **({"header": True} if kind == "csv" else {}))
        assert back.exceptAll(one).count() == 0 and back.count() == one.count()
    (tmp_path / "lines.txt").write_text("one\ntwo\n")
    assert {r["text"] for r in io.read_corpus(spark, f"{tmp_path}/lines.txt", "text").collect()} == {"one", "two"}
    (tmp_path / "many.txt").write_text("".join(f"line {i % 700}\n" for i in range(1000)))
    whole = {tuple(r) for r in io.read_corpus(spark, f"{tmp_path}/many.txt", "text").collect()}
    spark.conf.set("spark.sql.files.maxPartitionBytes", "1000")
    try:
        assert {tuple(r) for r in io.read_corpus(spark, f"{tmp_path}/many.txt", "text").collect()} == whole and len({i for i, _ in whole}) == 1000
    finally:
        spark.conf.unset("spark.sql.files.maxPartitionBytes")
    io.write_bucketed(one.limit(50), "pw_bucketed", "doc_id", 4)
    try:
        back = spark.table("pw_bucketed")
        assert back.exceptAll(one).count() == 0 and back.count() == 50 and "Exchange" not in plan_of(back.groupBy("doc_id").count())
    finally:
        spark.sql("DROP TABLE pw_bucketed")
    io.write_partitioned(docs, f"{tmp_path}/by_lang", "lang")
    assert "PartitionFilters: [isnotnull(lang" in plan_of(spark.read.parquet(f"{tmp_path}/by_lang").where("lang = 'en'"))
    view = spark.createDataFrame([(0, "word", 1, "a", 3), (0, "phrase", 1, "a b", 2)], "k int, kind string, rank int, text string, score long")
    io.write_view_json(view, f"{tmp_path}/view")
    assert spark.read.json(f"{tmp_path}/view").count() == 1


@pytest.mark.parametrize("name", ["titles", "by_source", "abstracts", "articles", "reviews"])
def test_workloads(spark, sf, name):
    docs = getattr(workloads, name)(spark, sf)
    assert {"doc_id", "text", "lang"} <= set(docs.columns) and docs.count() > 10
    assert 0 < workloads.sampled(docs, 0.5).count() < docs.count()

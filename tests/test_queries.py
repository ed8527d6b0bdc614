"""A share of the queries against DuckDB on the smallest tables; all oracles parse."""

from types import SimpleNamespace

import duckdb
import pytest

import __spark_entry__ as entry
from corpus_tilt.functions.sqltext import TABLES
from corpus_tilt.operators.relational import dedup_near

from .conftest import SF

NAMES = ["q_task_split", "q_base_model_prob", "q_softmax_weights", "q_filter_gumbel", "q_filter_iid", "q_utility_implicit", "op_filter_pred", "op_join_full", "op_agg_hash", "op_rollup", "op_win_lead_lag", "op_bleu", "op_win_session", "op_html_text", "q_bilevel_2steps_implicit", "q_frozen_vs_shuffled", "q_cost_counts", "q_transfer_nll", "q_filter_bias", "q_class_features", "q_byte_counts", "q_sar_gar", "q_classifier_topk", "q_reweight_weights", "op_stream_late", "op_stream_tumbling", "op_stream_state", "op_udf_pandas", "op_io_roundtrip", "op_dedup_exact", "op_caption_accuracy"]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def _rows(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(repr([round(r[i], 5) if isinstance(r[i], float) else r[i] for i in order]) for r in rows)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(spark, duck, name):
    df = entry.queries()[name](spark, SF)
    got = duck.sql(entry.oracle_sql()[name])
    assert sorted(df.columns) == sorted(got.columns)
    assert _rows(df.columns, [tuple(r) for r in df.collect()]) == _rows(got.columns, got.fetchall())


def test_every_oracle_has_a_query():
    assert entry.oracle_sql().keys() <= entry.queries().keys()


def test_entry(spark):
    assert entry.entry(spark).count() == 16


@pytest.mark.parametrize("block", [200, 4])
def test_near_links_are_all_pairs_of_whole_texts(spark, block):
    base = [f"word{i}" for i in range(200)]
    docs = [(i, " ".join([*base[: 5 + 9 * i], f"other{i}", *base[6 + 9 * i :]])) for i in range(20)]
    docs += [(100, docs[3][1]), (101, " ".join([*base[:80], *(f"p{i}" for i in range(120))])), (102, " ".join([*base[:80], *(f"q{i}" for i in range(120))]))]
    sets = {k: {tuple(w[i : i + 5]) for i in range(len(w) - 4)} for k, w in ((k, x.split(" ")) for k, x in docs)}
    want = {(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])}
    want -= {p for p in want if 100 in p} - {(3, 100)}  # a copy is linked with the least of its set alone
    got = [(r["a"], r["b"]) for r in dedup_near(SimpleNamespace(documents=spark.createDataFrame(docs, "doc_id long, text string")), block=block).collect()]
    assert len(want) > 100 and sorted(got) == sorted(want)


def test_theta_join_counts_large_groups(spark, tmp_path):
    """Pairs are counted and not made: 1.8 thousand million pairs of one group, equal prices, nulls."""
    part = spark.range(60_000).selectExpr("if(id % 2 = 0, 'a', 'b') as p_brand", "'t' as p_type", "cast(id as double) as p_retailprice").where("p_brand = 'a' or p_retailprice < 3")
    part = part.unionByName(spark.createDataFrame([("a", "t", None), (None, "t", 1.0), ("a", None, 1.0), ("c", "t", 1.0), ("c", "t", 1.0), ("d", "t", 1.0), ("d", "t", 1.0), ("d", "t", 2.0)], "p_brand string, p_type string, p_retailprice double"))
    part.write.parquet(f"{tmp_path}/part.parquet")
    df = entry.queries()["op_join_theta"](spark, str(tmp_path))
    assert {r["p_brand"]: r["n"] for r in df.collect()} == {"a": 30_000 * 29_999 // 2, "d": 2}
    assert "Join" not in df._jdf.queryExecution().executedPlan().toString()


def test_recursion_starts_from_a_table(spark, duck):
    df = entry.queries()["op_recursive"](spark, SF)
    assert "orders.parquet" in df.inputFiles()[0]
    assert sorted(map(tuple, df.collect())) == sorted(duck.sql(entry.oracle_sql()["op_recursive"]).fetchall())

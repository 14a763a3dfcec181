"""Queries of the catalog against DuckDB on the smallest tables, and the entry point without the removable parts."""

import os
import subprocess
import sys

import duckdb
import pytest

from flipmine.plans import catalog

SF = "/root/testdata/sf0.001"
REPO = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
SOME = [
    "items_brand", "baskets_brand", "avg_support_sample", "vertical_bitmap_counts", "distort_cells_brand", "singleton_recon", "singleton_recon_matrix", "pattern_counts_pair", "pair_patterns_by_ie",
    "pair_recon_weight", "triple_recon_subset", "transition_matrix", "mined_l2", "candidates_l3", "rules_recon", "basic_privacy_empirical", "reinterrogated_privacy", "param_candidates_0005",
    "error_rollup", "error_cube", "asof_enrich", "clicks_session", "range_join", "salted_pairs", "stream_window_counts", "counter_cost",
    "tuple_words", "basket_maps", "support_quantiles", "channel_condition", "reinterrogated_privacy_with_rare_items", "mined_pairs_supp", "error_quantiles", "exp_levels_type", "exp_trade_off",
]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for name in os.listdir(SF):
        con.sql(f"CREATE VIEW {name.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{name}'")
    return con


def plain(rows):
    return sorted((tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in rows), key=repr)


@pytest.mark.parametrize("name", SOME)
def test_query(spark, duck, name):
    df = catalog.QUERIES[name](spark, SF)
    names = sorted(df.columns)
    got = plain(tuple(r[c] for c in names) for r in df.collect())
    rel = duck.sql(catalog.ORACLES[name])
    assert sorted(rel.columns) == names
    at = [rel.columns.index(c) for c in names]
    assert got == plain(tuple(r[i] for i in at) for r in rel.fetchall())


def test_filters_and_columns_reach_the_scan(spark):
    plan = catalog.QUERIES["sliced_items"](spark, SF)._jdf.queryExecution().toString()
    assert "GreaterThanOrEqual(l_shipdate" in plan
    assert "l_quantity" not in plan.split("== Physical Plan ==")[1]


def test_entry_without_the_removable_parts(tmp_path):
    """The entry point imports, and keeps its queries, where the subpackage and the pipeline are gone."""
    for name in ("flipmine", "tests", "__spark_entry__.py"):
        subprocess.run(["cp", "-r", f"{REPO}/{name}", str(tmp_path)], check=True)
    subprocess.run(["rm", "-rf", f"{tmp_path}/flipmine/llm", f"{tmp_path}/tests/llm"], check=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'singleton_recon' in q and not any(n.startswith('op') for n in q); assert set(e.oracle_sql()) <= set(q)"
    alone = os.environ | {"PYTHONPATH": str(tmp_path)}
    subprocess.run([sys.executable, "-c", code], check=True, cwd=tmp_path, env=alone)
    subprocess.run([sys.executable, "-m", "pytest", "-q", "-p", "no:cacheprovider", "tests/test_channel.py"], check=True, cwd=tmp_path, env=alone)
    subprocess.run([sys.executable, "-m", "pytest", "-q", "-p", "no:cacheprovider", "--collect-only", "tests"], check=True, cwd=tmp_path, env=alone)


def test_click_summary_has_every_sparse_setting(spark, monkeypatch):
    from flipmine.config import CANDIDATES_SPARSE
    from flipmine.plans import experiments

    monkeypatch.setattr(experiments, "summary", lambda spark, b, settings, *_, **__: list(settings))
    assert catalog.QUERIES["exp_summary_clicks"](spark, "/root/testdata/sf0.001") == list(CANDIDATES_SPARSE)

"""Every query with SQL against another engine at the smallest scale; plans without single-task exchanges of the corpus."""

from __future__ import annotations

import glob
import os

import duckdb
import numpy as np
import pandas as pd
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
CHECKED = ["seq_nll", "val_loss", "split_disjoint", "static_topk", "token_budget", "buffers", "grad_sgd", "alignment", "redundancy", "pick_gumbel", "relevance", "proxy_pool", "decontaminate", "base_importance", "base_pairwise_pairs", "loss_curve", "mc_ppl_acc", "suite_avg", "op_asof_join", "op_range_join", "op_session", "op_lateral_topk", "op_rollup", "op_stream_window", "op_udtf_ngrams"]


def cell(v):
    if isinstance(v, (float, np.floating)):
        return None if v != v else round(float(v), 6)
    if isinstance(v, (int, np.integer)) and not isinstance(v, (bool, np.bool_)):
        return float(v)
    return None if v is None or v is pd.NaT or v is pd.NA else str(v)


def rows(df):
    return sorted((tuple(map(cell, r)) for r in df[sorted(df.columns)].itertuples(index=False)), key=str)


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        c.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return c


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_sql(spark, duck, name):
    a, b = entry.queries()[name](spark, SF).toPandas(), duck.execute(entry.oracle_sql()[name]).fetch_df()
    assert sorted(a.columns) == sorted(b.columns) and rows(a) == rows(b)


def test_entry_and_registry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_greedy_picks_against_brute_force(spark):
    from steerselect.operators.pick import pick_from_gram, pick_steps

    r = np.random.default_rng(0)
    data = [(s, 10 * s + i, float(r.normal()), r.normal(size=4).tolist()) for s in range(3) for i in range(7)]
    df = spark.createDataFrame(data, "step long, doc_id long, align double, phi array<double>")
    got = pick_steps(df, 0.5, 0.3, policy="greedy").toPandas().sort_values(["step", "draw"])
    for s in range(3):
        mine = [d for d in data if d[0] == s]
        phi = np.array([d[3] for d in mine])
        want = [mine[z][1] for z, _, _ in pick_from_gram(np.array([d[2] for d in mine]), phi @ phi.T, 3, 0.3, policy="greedy")]
        assert got[got.step == s].doc_id.tolist() == want


def test_picks_do_not_depend_on_partitions(spark):
    q = entry.queries()["pick_gumbel"]
    one = sorted(map(tuple, q(spark, SF).collect()))
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "13")
    try:
        assert sorted(map(tuple, q(spark, SF).collect())) == one
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_alignment_needs_no_python_and_no_cartesian_product(spark):
    plan = entry.queries()["seq_nll"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Cartesian" not in plan and "Python" not in plan and "SinglePartition" not in plan


def test_queries_are_listed_without_a_session():
    import os
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    code = "import __spark_entry__ as e; assert set(e.oracle_sql()) <= set(e.queries())"
    subprocess.run([sys.executable, "-c", code], cwd=root, check=True, timeout=120)


def test_the_loop_trains_on_whole_texts(spark, monkeypatch):
    """Rows longer than the scored prefix reach the update and the token count."""
    from steerselect.operators import loop

    seen = {}

    def run(rows, pool, cfg, count):
        seen.update(rows=rows, limit=cfg.score_len)
        return None, None, [{"step": 0, "draw": 0, "doc_id": 1, "utility": 0.0}], []

    monkeypatch.setattr(loop, "run_selection", run)
    entry.queries()["select_loop"](spark, SF)
    assert max(len(r.toks) for r in seen["rows"].select("toks").collect()) > seen["limit"]


WHOLE = ["seq_nll_whole", "static_threshold_whole", "static_topk_whole", "token_budget_whole", "cpt_breakdown_whole"]


@pytest.mark.parametrize("name", WHOLE)
def test_whole_texts_equal_sql(spark, duck, name):
    a, b = entry.queries()[name](spark, SF).toPandas(), duck.execute(entry.oracle_sql()[name]).fetch_df()
    assert sorted(a.columns) == sorted(b.columns) and rows(a) == rows(b)


def test_losses_count_every_pair(spark):
    n = {r.doc_id: r.n_pairs for r in entry.queries()["seq_nll_whole"](spark, SF).collect()}
    words = {r.doc_id: r.n_words for r in entry.queries()["op_tokens"](spark, SF).collect()}
    assert max(n.values()) > 511 and n == {d: w - 1 for d, w in words.items() if w > 1}


def test_domains_count_every_held_out_document(spark):
    sf = "/root/testdata/sf0.01"
    sql = entry.oracle_sql()["domain_ppl_whole"]
    with duckdb.connect() as c:
        c.execute(f"create view documents as select * from '{sf}/documents.parquet'")
        want = c.execute(sql).fetch_df()
    got = entry.queries()["domain_ppl_whole"](spark, sf).toPandas()
    assert rows(got) == rows(want) and got["n"].max() > 5

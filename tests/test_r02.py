"""Tokens numbered by whole columns, passes that send tokens only, and laws that read given tables."""

from __future__ import annotations

import duckdb
import pytest
from pyspark.sql import functions as F
from test_queries import SF, rows

import __spark_entry__ as entry
from steerselect.functions import tokens as T

ODD = [(1, "Ein Wort, zwei  Worte; ein WORT"), (2, ""), (3, None), (4, "123 ... \t\n"), (5, "İstanbul ΑΣ² ① naïve_ǅ x"), (6, " a"), (7, "b\x00c d e 文字 ꙮ\U0001d400")]


def against_sql(spark, name, tables, sf=SF):
    with duckdb.connect() as c:
        for t in tables:
            c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
        want = c.execute(entry.oracle_sql()[name]).fetch_df()
    got = entry.queries()[name](spark, sf).toPandas()
    assert sorted(got.columns) == sorted(want.columns) and rows(got) == rows(want)
    return got


@pytest.mark.parametrize("vocabulary", [32, 64])
def test_numbered_equals_tokenized(spark, vocabulary):
    from steerselect.operators import proxy

    df = spark.createDataFrame(ODD, "doc_id long, text string").union(spark.read.parquet(f"{SF}/documents.parquet").select((F.col("doc_id") + 100).alias("doc_id"), "text"))
    key = lambda r: (r.doc_id, r.n_words, r.toks)
    got = T.numbered(df, vocabulary, dim=proxy.DIM)
    assert sorted(map(key, got.collect())) == sorted(map(key, T.tokenized(df, vocabulary).collect()))


def test_naive_scores_send_tokens_only(spark):
    """No cell of a gradient becomes a row: nothing is generated and no aggregate stands above the group."""
    against_sql(spark, "base_naive", ["documents"])
    plan = entry.queries()["base_naive"](spark, SF)._jdf.queryExecution().analyzed().toString()
    top = plan.split("FlatMapGroupsInPandas")
    assert len(top) == 2 and "Aggregate" not in top[0] and "Join" not in top[0]


READS = {"compression": "documents", "flop_model": "documents", "lr_schedule": "documents", "muon_lr": "documents", "muon_momentum": "documents", "opt_assign": "embeddings"}


@pytest.mark.parametrize("name", READS)
def test_laws_read_their_table(spark, name):
    """These made their data up; now a larger table gives more rows."""
    assert any(READS[name] in f for f in entry.queries()[name](spark, SF).inputFiles())
    small, large = (against_sql(spark, name, [READS[name]], sf) for sf in (SF, "/root/testdata/sf0.01"))
    assert len(large) > len(small) or name == "opt_assign"
    if name == "opt_assign":
        assert set(small.optimizer) == {"muon", "adamw"} and set(small.optimizer[small.layer.isin([0, 9])]) == {"adamw"}


def test_matrices_alone_get_muon(spark, tmp_path):
    data = [(1, [1.0, 2.0], 3), (2, [1.0, 2.0], 3), (3, [1.0, 2.0], 4), (4, [1.0], 5), (5, [1.0], 5), (6, [1.0, 2.0], 0), (7, [1.0, 2.0], 0), (8, None, None)]
    spark.createDataFrame(data, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {r.vec_id: r.optimizer for r in entry.queries()["opt_assign"](spark, str(tmp_path)).collect()}
    assert got == {d[0]: "muon" if d[2] == 3 else "adamw" for d in data}


def test_whole_columns_equal_rows_of_pairs_and_grams(spark):
    """What the workloads now count in columns, against the exploded rows that they counted before."""
    from steerselect.operators import baselines as B
    from steerselect.operators import lm_count, proxy

    df = spark.createDataFrame(ODD, "doc_id long, text string").union(spark.read.parquet(f"{SF}/documents.parquet").select((F.col("doc_id") + 100).alias("doc_id"), "text"))
    bag = lambda x: sorted(map(tuple, x.collect()))
    lists = B.gram_lists(df, "doc_id")
    assert bag(lists.select("doc_id", F.explode(F.arrays_zip("b", "n")).alias("z")).select("doc_id", F.col("z.b").cast("long"), F.col("z.n").cast("long"))) == bag(B.gram_buckets(df, "doc_id").select("doc_id", "b", "n"))
    pos, neg = df.filter("doc_id % 3 = 0").select("doc_id"), df.filter("doc_id % 3 = 1").select("doc_id")
    one, two = (dict(bag(c.select("doc_id", "p"))) for c in (B.classifier_lists(lists, pos, neg), B.classifier(B.gram_buckets(df, "doc_id"), pos, neg)))
    assert one == {k: pytest.approx(v) for k, v in two.items()}
    tok = T.numbered(df, 8, dim=proxy.DIM)
    assert bag(proxy.scaled(tok, "doc_id")) == [(d, pytest.approx(v)) for d, v in bag(proxy.encode(df, "doc_id"))]
    held = tok.withColumn("methods", F.when(F.col("doc_id") % 2 == 0, F.array(F.lit("a"), F.lit("b"))).otherwise(F.array(F.lit("b"))))
    rows = T.pairs(held.select("toks", F.struct("doc_id", "methods").alias("k")), "k").select(F.explode("k.methods").alias("method"), F.col("x").cast("long"), F.col("y").cast("long"))
    assert bag(lm_count.pair_counts(held, 8)) == bag(rows.groupBy("method", "x", "y").count())
    lm = lm_count.fit(T.pairs(tok), 8)
    got = {r.doc_id: (r.n_pairs, r.nll) for r in lm_count.losses(tok, lm.withColumn("method", F.lit("m")), 8).collect()}
    assert got == {r.doc_id: (r.n_pairs, pytest.approx(r.nll)) for r in lm_count.sequence_loss(T.pairs(tok), lm).collect()}


def test_scratch_workloads_tokenise_once(spark, monkeypatch):
    """The texts are split into words for tokens and for grams, and a step's scores are made once for three selectors."""
    from steerselect.operators import lm_step
    from steerselect.plans import context, workloads

    calls = []
    monkeypatch.setattr(lm_step, "step_pass", lambda *a, f=lm_step.step_pass, **k: (calls.append(k), f(*a, **k))[1])
    t = context.Kept(spark, SF)
    assert workloads.selections(t, ["high-loss", "raw-gradient", "geometry", "geometry-muon"]).count() > 0
    assert len(calls) == 1

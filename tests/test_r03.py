"""Texts without words, of one word, or of words that cancel out, in the workloads' shared tables."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_queries import SF

from steerselect.operators import proxy
from steerselect.plans import proxy_queries
from steerselect.plans.context import Kept

#: ``aah`` and ``aal`` go to one coordinate with opposite signs.
ODD = [None, "", "123 ...", "word", "aah aal"]
#: Of these, the ones that the encoder sees as a vector.
SEEN = {"word"}


@pytest.fixture(scope="module")
def odd(spark, tmp_path_factory):
    """sf0.001 with odd texts as documents 0 to 4 and again as 100 to 104."""
    folder = str(tmp_path_factory.mktemp("odd"))
    texts = F.array(*map(F.lit, ODD))
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    docs.withColumn("text", F.when(F.col("doc_id") % 100 < len(ODD), texts[(F.col("doc_id") % 100).cast("int")]).otherwise(F.col("text"))).write.parquet(f"{folder}/documents.parquet")
    for name in ("labels", "benchmark"):
        spark.read.parquet(f"{SF}/{name}.parquet").write.parquet(f"{folder}/{name}.parquet")
    return folder


def seen(odd, spark) -> set[int]:
    ids = {r.doc_id for r in spark.read.parquet(f"{odd}/documents.parquet").select("doc_id").collect()}
    return {i for i in ids if i % 100 >= len(ODD) or ODD[i % 100] in SEEN}


def test_w01_tables_take_odd_texts(spark, odd):
    """a vector of length zero was divided by, and a null text had no length."""
    t = Kept(spark, odd)
    assert {r.doc_id for r in proxy_queries._relevance(t).collect()} == seen(odd, spark)
    plain = proxy.encode(t.docs, "doc_id").filter(F.exists("vec", lambda v: v > 0) | F.exists("vec", lambda v: v < 0))
    got, want = ({r.doc_id: r.vec for r in df.collect()} for df in (t.vectors, plain))
    assert got.keys() == want.keys() and all(np.allclose(got[i], want[i], atol=1e-12) for i in want)
    scored = {r.doc_id for r in t.step_scores().collect()}
    train = {r.doc_id for r in t.split.filter("split = 'train'").join(t.words.filter("n_words > 1"), "doc_id").collect()}
    assert scored == train and not train & {0, 1, 2, 3, 100, 101, 102, 103} and train & {4, 104}


def test_w02_grades_take_odd_texts_and_no_labels(spark, odd, tmp_path):
    """the grader divided by a vector's length of zero, and failed where no label meets a document."""
    got = proxy_queries.graded(Kept(spark, odd)).collect()
    assert {r.doc_id for r in got} == seen(odd, spark) and {r.grade for r in got} == {3, 4, 5}
    for name in ("documents", "benchmark"):
        spark.read.parquet(f"{odd}/{name}.parquet").write.parquet(f"{tmp_path}/{name}.parquet")
    spark.read.parquet(f"{odd}/labels.parquet").limit(0).write.parquet(f"{tmp_path}/labels.parquet")
    got = proxy_queries.graded(Kept(spark, str(tmp_path))).collect()
    assert {r.doc_id for r in got} == seen(odd, spark) and {r.raw for r in got} == {0.0}


@pytest.mark.parametrize("rows", [32_768, 5_000])
def test_rater_is_fitted_on_all_pairs(spark, tmp_path, monkeypatch, rows):
    """of more than 20,000 pairs the weights came from 20,000."""
    from steerselect.operators import baselines

    monkeypatch.setattr(baselines, "FIT_ROWS", rows, raising=False)
    words = np.random.default_rng(3).integers(0, 90, (8_000, 5))
    spark.createDataFrame([(i, " ".join("w" + chr(97 + x % 26) * (x // 26 + 1) for x in w)) for i, w in enumerate(words.tolist())], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.range(8_000).select(F.col("id").alias("doc_id"), (F.col("id") % 8 == 0).cast("int").alias("quality"), F.lit(0).alias("toxic")).write.parquet(f"{tmp_path}/labels.parquet")
    t = Kept(spark, str(tmp_path))
    vec = {r.doc_id: np.array(r.vec) for r in t.vectors.collect()}
    pairs = proxy_queries.base_pairwise_pairs(t).collect()
    d = np.array([vec[p.win_id] - vec[p.lose_id] for p in pairs if p.win_id in vec and p.lose_id in vec])
    assert len(d) > 20_000
    w = np.zeros(proxy.DIM)
    for _ in range(200):
        w += d.T @ (1 / (1 + np.exp(d @ w))) / len(d) - 1e-3 * w
    got = {r.doc_id: r.rating for r in proxy_queries.base_pairwise_fit(t).collect()}
    assert got.keys() == vec.keys() and np.ptp(list(got.values())) > 0.01
    assert max(abs(got[i] - vec[i] @ w) for i in vec) < 1e-9

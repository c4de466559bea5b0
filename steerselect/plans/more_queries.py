"""Queries beside the core: protocols, decoding, the utility's forms, further measures and relational variants."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import tokens as T
from ..operators import corpus, lm_block, measures, precond, utility
from .context import RATIO, SCORE_LEN, SEED, V, Tables, r6, with_tables
from .core_queries import BUDGET, TOP
from .registry import query

DYNAMIC = TOP.format(key="s", src="(SELECT step, doc_id, round(-nll, 9) AS s FROM buf JOIN nll USING (doc_id))", ratio=RATIO)
ORDERED = "(SELECT doc_id, row_number() OVER (ORDER BY round(-nll, 9) DESC, doc_id) AS rk, count(*) OVER () AS n FROM nll JOIN split USING (doc_id) WHERE split = 'train')"


@query("static_dynamic", with_tables(f"SELECT o.doc_id, o.rk <= floor(o.n * {RATIO}) AS static, d.doc_id IS NOT NULL AS dynamic FROM {ORDERED} o LEFT JOIN dyn d USING (doc_id)", "buf", "nll", "split", dyn=DYNAMIC))
def static_dynamic(t: Tables) -> DataFrame:
    """The two protocols on one score: the best of the whole pool at once, and the best of each buffer as it streams."""
    rows = t.buffers.join(t.nll, "doc_id").select("step", "doc_id", F.round(-F.col("nll"), 9).alias("score"))
    static, dynamic = corpus.run_static(rows, RATIO), corpus.run_dynamic(rows, RATIO)
    out = rows.select("doc_id").join(static.withColumn("static", F.lit(True)), "doc_id", "left").join(dynamic.withColumn("dynamic", F.lit(True)), "doc_id", "left")
    return out.select("doc_id", F.coalesce("static", F.lit(False)).alias("static"), F.coalesce("dynamic", F.lit(False)).alias("dynamic"))


@query("op_running_budget", with_tables(f"SELECT doc_id, cum_tok::BIGINT AS cum_tok, cum_tok <= {BUDGET} AS within FROM (SELECT doc_id, sum(n_words) OVER (ORDER BY md5('run|{SEED}|' || doc_id), doc_id ROWS UNBOUNDED PRECEDING) AS cum_tok FROM tok)", "tok"))
def op_running_budget(t: Tables) -> DataFrame:
    """Cumulative tokens of the corpus in hash order, and whether a budget holds them; no task sees all rows."""
    order = F.md5(F.concat(F.lit(f"run|{SEED}|"), F.col("doc_id").cast("string")))
    total = corpus.running_total(t.tok.select("doc_id", "n_words"), order, "doc_id", "n_words", "cum_tok")
    return total.select("doc_id", "cum_tok", (F.col("cum_tok") <= BUDGET).alias("within"))


TEMPERATURE, TOP_P, TOP_K, MAX_LEN = 0.6, 0.95, 20, 64
NEXT = f"""
    a AS (SELECT x, y, exp((logp - max(logp) OVER (PARTITION BY x)) / {TEMPERATURE}) AS e, row_number() OVER (PARTITION BY x ORDER BY round(logp, 9) DESC, y) AS rk FROM lm),
    b AS (SELECT x, y, rk, e / sum(e) OVER (PARTITION BY x) AS q FROM a WHERE rk <= {TOP_K}),
    c AS (SELECT x, y, q, round(coalesce(sum(q) OVER (PARTITION BY x ORDER BY rk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0), 9) AS before FROM b)
    SELECT x, y, round(q / sum(q) OVER (PARTITION BY x), 6) + 0.0 AS prob FROM c WHERE before < {TOP_P}"""


@query("decode_table", with_tables("SELECT 1", "lm").removesuffix(" SELECT 1") + "," + NEXT)
def decode_table(t: Tables) -> DataFrame:
    """What stochastic decoding draws from after each token: temperature, then the likeliest few, then the nucleus."""
    return measures.next_tokens(t.lm, TEMPERATURE, TOP_P, TOP_K).select("x", "y", r6("prob").alias("prob"))


@query("decode")
def decode(t: Tables) -> DataFrame:
    """A continuation of each benchmark passage's last token, drawn with noise that the ids fix."""
    last = T.tokenized(t.table("benchmark"), V, "item_id").filter(F.size("toks") > 0).select("item_id", F.element_at("toks", -1).alias("last"))
    return measures.decode(last, measures.next_tokens(t.lm, TEMPERATURE, TOP_P, TOP_K), MAX_LEN, SEED, "item_id")


RANKS = "SELECT step, corr(a, b) AS c FROM (SELECT step, rank() OVER (PARTITION BY step ORDER BY n_words) AS a, rank() OVER (PARTITION BY step ORDER BY round(nll, 9)) AS b FROM buf JOIN nll USING (doc_id) JOIN tok USING (doc_id)) GROUP BY step HAVING count(*) > 2"


@query("loss_length_rank_corr", with_tables(f"SELECT step, round(c, 5) + 0.0 AS c FROM ({RANKS})", "buf", "nll", "tok"))
def loss_length_rank_corr(t: Tables) -> DataFrame:
    """Rank correlation of length and loss in each buffer: whether a loss-based choice is one by length."""
    w = Window.partitionBy("step")
    rows = t.buffers.join(t.nll, "doc_id").join(t.tok.select("doc_id", "n_words"), "doc_id")
    ranked = rows.select("step", F.rank().over(w.orderBy("n_words")).alias("a"), F.rank().over(w.orderBy(F.round("nll", 9))).alias("b"))
    c = ranked.groupBy("step").agg(F.corr("a", "b").alias("c"), F.count(F.lit(1)).alias("n")).filter("n > 2")
    return c.select("step", (F.round("c", 5) + F.lit(0.0)).alias("c"))


@query("sketch_rank_corr")
def sketch_rank_corr(t: Tables) -> DataFrame:
    """Rank correlation of sketched and exact scores in each buffer."""
    w = Window.partitionBy("step")
    ranked = t.step_scores().select("step", F.rank().over(w.orderBy("plain")).alias("a"), F.rank().over(w.orderBy("plain_sketched")).alias("b"))
    return ranked.groupBy("step").agg(r6(F.corr("a", "b")).alias("c"))


COSINE = f"""
    h AS (SELECT doc_id, b, count(*)::DOUBLE AS n FROM (SELECT doc_id, unnest(toks[1:{SCORE_LEN}]) AS b FROM tok) GROUP BY doc_id, b),
    u AS (SELECT doc_id, b, n / sqrt(sum(n * n) OVER (PARTITION BY doc_id)) AS u FROM h),
    d AS ({DYNAMIC}),
    s AS (SELECT step, b, sum(u) AS v FROM d JOIN u USING (doc_id) GROUP BY step, b),
    k AS (SELECT step, count(*) AS k FROM d GROUP BY step)
    SELECT step, k, round((sum(v * v) - k) / (k * (k - 1.0::DOUBLE)), 6) + 0.0 AS cosine FROM s JOIN k USING (step) WHERE k > 1 GROUP BY step, k"""


@query("diversity_cosine", with_tables("SELECT 1", "buf", "nll", "tok").removesuffix(" SELECT 1") + "," + COSINE)
def diversity_cosine(t: Tables) -> DataFrame:
    """The mean cosine of every two picks of a step, from the length of their summed unit vectors: no pair is made."""
    rows = t.buffers.join(t.nll, "doc_id").select("step", "doc_id", F.round(-F.col("nll"), 9).alias("score"))
    picks = corpus.run_dynamic(rows, RATIO, keep=("step",))
    counts = T.tokenized(t.docs, V, limit=SCORE_LEN).select("doc_id", F.explode("toks").alias("b")).groupBy("doc_id", "b").agg(F.count(F.lit(1)).cast("double").alias("n"))
    unit = counts.withColumn("u", F.col("n") / F.sqrt(F.sum(F.col("n") * F.col("n")).over(Window.partitionBy("doc_id"))))
    return measures.mean_cosine(picks.join(unit, "doc_id"), picks).select("step", "k", r6("cosine").alias("cosine"))


@query("op_setops_all", "SELECT kind, count(*) AS n FROM (SELECT 'union all' AS kind, * FROM (SELECT l_suppkey AS k FROM lineitem UNION ALL SELECT ps FROM (SELECT s_suppkey AS ps FROM supplier)) UNION ALL SELECT 'intersect all', * FROM (SELECT l_suppkey FROM lineitem INTERSECT ALL SELECT s_suppkey FROM supplier) UNION ALL SELECT 'except all', * FROM (SELECT l_suppkey FROM lineitem EXCEPT ALL SELECT s_suppkey FROM supplier)) GROUP BY kind")
def op_setops_all(t: Tables) -> DataFrame:
    a, b = t.table("lineitem").select(F.col("l_suppkey").alias("k")), t.table("supplier").select(F.col("s_suppkey").alias("k"))
    parts = {"union all": a.unionAll(b), "intersect all": a.intersectAll(b), "except all": a.exceptAll(b)}
    rows = [p.select(F.lit(k).alias("kind")) for k, p in parts.items()]
    return rows[0].unionAll(rows[1]).unionAll(rows[2]).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


@query("op_spearman", "SELECT l_suppkey, round(corr(a, b), 5) + 0.0 AS c FROM (SELECT l_suppkey, rank() OVER (PARTITION BY l_suppkey ORDER BY l_quantity) AS a, rank() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice) AS b FROM lineitem) GROUP BY l_suppkey HAVING count(*) > 2")
def op_spearman(t: Tables) -> DataFrame:
    w = Window.partitionBy("l_suppkey")
    ranked = t.table("lineitem").select("l_suppkey", F.rank().over(w.orderBy("l_quantity")).alias("a"), F.rank().over(w.orderBy("l_extendedprice")).alias("b"))
    c = ranked.groupBy("l_suppkey").agg(F.corr("a", "b").alias("c"), F.count(F.lit(1)).alias("n")).filter("n > 2")
    return c.select("l_suppkey", (F.round("c", 5) + F.lit(0.0)).alias("c"))


@query("utility_forms")
def utility_forms(t: Tables) -> DataFrame:
    """(step, geometry, form, lr, error): how far each form of the marginal gain is from the exact one, on the block model.

    The mean over each buffer's first candidates, the first two of them chosen already; for every buffer, one group each.
    """
    size, vocabulary, length = 6, 16, 48

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        toks = [np.asarray(x, np.int64) % vocabulary for x in pdf.sort_values(["role", "slot"])["toks"]]
        role = pdf.sort_values(["role", "slot"])["role"].tolist()
        val, own = ([x for x, r in zip(toks, role) if r == k] for k in ("proxy", "candidate"))
        out = []
        if len(own) > 2 and val:
            theta = lm_block.init(vocabulary, 6, 8, SEED)
            g = utility.mean_gradient(theta, own)
            shapes = {"plain": {k: precond.plain() for k in theta}, "adamw": {k: precond.adamw({"v": 0.05 * v * v}, 2, eps=1e-3) for k, v in g.items()}, "muon": {k: precond.muon(v, 0.85) for k, v in g.items()}}
            for name, geo in shapes.items():
                for lr in (1e-2, 5e-3):
                    want = [utility.marginal_exact(theta, geo, own[:2], z, val, lr) for z in own[2:]]
                    for form, f in utility.FORMS.items():
                        out.append((int(pdf["step"].iloc[0]), name, form, lr, float(np.mean([abs(f(theta, geo, own[:2], z, val, lr) - w) for z, w in zip(own[2:], want)]))))
        return pd.DataFrame(out, columns=["step", "geometry", "form", "lr", "error"])

    prefix = T.tokenized(t.docs, V, limit=length).filter(F.size("toks") > 1).select("doc_id", "toks")
    own = t.buffers.filter(F.col("slot") < size).join(prefix, "doc_id").select("step", F.lit("candidate").alias("role"), F.col("slot").cast("long").alias("slot"), "toks")
    beside = t.proxy_batch.filter("k < 2").join(prefix, "doc_id").select("step", F.lit("proxy").alias("role"), F.col("k").cast("long").alias("slot"), "toks")
    return own.union(beside).groupBy("step").applyInPandas(run, "step long, geometry string, form string, lr double, error double")

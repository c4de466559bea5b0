"""The derived tables of the experiments, as plans over the given tables, and the same definitions in plain SQL."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import tokens as T
from ..operators import corpus, lm_count, lm_step, proxy
from ..sources.tables import read, stored

V, SCORE_LEN, BUFFER, RATIO, TAU, SEED, SKETCH, PROXY = 32, 512, 64, 0.5, 0.9, 42, 64, 8
ALPHA, LR, EPS, BETA1 = 0.5, 1.0, 1e-4, 0.8
#: AdamW's scale at t = 2.
SCALE = (1 - BETA1) / (1 - BETA1**2)


def r6(c: Column | str) -> Column:
    return F.round(c, 6) + F.lit(0.0)


class Tables:
    """Plans of one scale's derived tables; nothing runs until a query does."""

    def __init__(self, spark: SparkSession, sf_dir: str) -> None:
        self.spark, self.dir = spark, sf_dir

    def table(self, name: str) -> DataFrame:
        return read(self.spark, self.dir, name)

    @cached_property
    def docs(self) -> DataFrame:
        return self.table("documents")

    @cached_property
    def tok(self) -> DataFrame:
        return T.tokenized(self.docs, V)

    @cached_property
    def numbered(self) -> DataFrame:
        """``tok`` by whole columns in workers."""
        return T.numbered(self.docs, V)

    @cached_property
    def words(self) -> DataFrame:
        """(doc_id, n_words), without tokens."""
        return self.docs.select("doc_id", F.regexp_count(F.lower("text"), F.lit(r"\p{L}+")).alias("n_words"))

    @cached_property
    def stored_tokens(self) -> DataFrame:
        """(doc_id, split, n_words, toks): whole texts tokenised once, for passes that read them several times."""
        return stored(T.numbered(self.docs, V).withColumn("split", corpus.split_of("doc_id", SEED)), "tokens")

    @cached_property
    def vectors(self) -> DataFrame:
        """(doc_id, vec): the documents as the frozen encoder sees them."""
        return proxy.encode(self.docs, "doc_id")

    @cached_property
    def split(self) -> DataFrame:
        return self.docs.select("doc_id", corpus.split_of("doc_id", SEED).alias("split"))

    @cached_property
    def train_pairs(self) -> DataFrame:
        return T.pairs(self.tok.filter(corpus.split_of("doc_id", SEED) == "train"))

    @cached_property
    def val_pairs(self) -> DataFrame:
        return T.pairs(self.tok.filter(corpus.split_of("doc_id", SEED) == "val"))

    @cached_property
    def prefix_pairs(self) -> DataFrame:
        return T.pairs(T.tokenized(self.docs, V, limit=SCORE_LEN))

    @cached_property
    def lm(self) -> DataFrame:
        return lm_count.fit(self.train_pairs, V, ALPHA)

    @cached_property
    def buffers(self) -> DataFrame:
        return corpus.form_buffers(self.split.filter("split = 'train'"), BUFFER, SEED)

    @cached_property
    def candidates(self) -> DataFrame:
        """(step, doc_id, x, y): the scored pairs of buffered documents."""
        return self.prefix_pairs.join(self.buffers.select("step", "doc_id"), "doc_id")

    @cached_property
    def proxy_batch(self) -> DataFrame:
        """(step, k, doc_id): eight documents of the proxy pool per step, walking through the pool in hash order."""
        pool = self.split.filter("split = 'val'").select("doc_id")
        order = F.md5(F.concat(F.lit(f"prx|{SEED}|"), F.col("doc_id").cast("string")))
        ranked = corpus.global_rank(pool, order, "doc_id", "rank")
        size = ranked.agg(F.count(F.lit(1)).alias("size"))
        count = self.split.filter("split = 'train'").agg(F.count(F.lit(1)).alias("n")).filter("n > 0")
        steps = count.select(F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("n") - 1) / BUFFER).cast("long"))).alias("step"))
        slots = steps.select("step", F.explode(F.sequence(F.lit(0), F.lit(PROXY - 1))).alias("k")).crossJoin(F.broadcast(size))
        at = slots.select("step", "k", ((F.col("step") * PROXY + F.col("k")) % F.col("size") + 1).alias("rank"))
        return at.join(ranked, "rank").select("step", "k", "doc_id")

    @cached_property
    def proxy_gradient(self) -> DataFrame:
        pairs = self.prefix_pairs.join(self.proxy_batch.select("step", "doc_id"), "doc_id")
        return lm_count.mean_gradient(pairs, self.lm, ["step"])

    @cached_property
    def past(self) -> DataFrame:
        """(x, y, f): AdamW's elementwise factor after one past step on the mean training gradient."""
        g = lm_count.mean_gradient(self.train_pairs, self.lm)
        cells = lm_count.grid(self.docs, V).join(F.broadcast(g), ["x", "y"], "left")
        return cells.select("x", "y", (F.lit(SCALE) / (F.abs(F.coalesce("g", F.lit(0.0))) + F.lit(EPS))).alias("f"))

    def steps_of_tokens(self, step: int | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
        """Candidates (step, slot, doc_id, toks), proxy documents (step, k, doc_id, toks), both by their prefix, and the counted model."""
        tok = self.stored_tokens
        prefix = tok.select("doc_id", "split", lm_step.packed(F.slice("toks", 1, SCORE_LEN), V).alias("toks"))
        wanted = F.lit(True) if step is None else F.col("step") == step
        own = self.buffers.filter(wanted).join(prefix.filter("split = 'train'"), "doc_id")
        beside = self.proxy_batch.filter(wanted).join(prefix.filter("split = 'val'"), "doc_id")
        return own, beside, lm_step.counted(tok.filter("split = 'train'"))

    def step_scores(self, phi: str | None = None, buckets: int = SKETCH, step: int | None = None) -> DataFrame:
        """(step, doc_id, plain, shaped, muon, sketched, plain_sketched, redundancy): all scores of candidates, in one pass, and ``phi``; of one ``step`` if given."""
        return lm_step.step_pass(*self.steps_of_tokens(step), V, buckets, ALPHA, SCALE, EPS, SEED, phi=phi)

    @cached_property
    def alignment(self) -> DataFrame:
        """(step, doc_id, score): first-order gain of a candidate's AdamW-shaped update, by the pair-score rewrite."""
        return self.step_scores().select("step", "doc_id", F.col("shaped").alias("score"))

    @cached_property
    def utility(self) -> DataFrame:
        return self.alignment.select("step", "doc_id", (F.lit(LR) * F.col("score")).alias("utility"))

    @cached_property
    def nll(self) -> DataFrame:
        return lm_count.sequence_loss(self.prefix_pairs, self.lm)

    @cached_property
    def scored(self) -> DataFrame:
        """(doc_id, score, n_words): training documents by likelihood of their prefix."""
        return self.nll.join(self.tok.select("doc_id", "n_words"), "doc_id").join(self.split.filter("split = 'train'"), "doc_id").select("doc_id", F.round(-F.col("nll"), 9).alias("score"), "n_words")


class Kept(Tables):
    """The same tables for experiments that read them many times: tokens, encodings and step scores are made once and stored."""

    @cached_property
    def stored_tokens(self) -> DataFrame:
        return stored(T.numbered(self.docs, V, dim=proxy.DIM).withColumn("split", corpus.split_of("doc_id", SEED)), "tokens")

    @cached_property
    def tok(self) -> DataFrame:
        return self.stored_tokens.select("doc_id", "n_words", "toks")

    @cached_property
    def words(self) -> DataFrame:
        return self.tok.select("doc_id", "n_words")

    @cached_property
    def vectors(self) -> DataFrame:
        return proxy.scaled(self.stored_tokens, "doc_id")

    @cached_property
    def prefix_pairs(self) -> DataFrame:
        return T.pairs(self.tok.select("doc_id", F.slice("toks", 1, SCORE_LEN).alias("toks")))

    @cached_property
    def lm(self) -> DataFrame:
        rows = self.stored_tokens.filter("split = 'train'").select("toks", F.array(F.lit("all")).alias("methods"))
        return stored(lm_count.smoothed(lm_count.pair_counts(rows, V).select("x", "y", "n"), V, ALPHA), "lm")

    @cached_property
    def nll(self) -> DataFrame:
        rows = self.tok.select("doc_id", F.slice("toks", 1, SCORE_LEN).alias("toks"))
        return lm_count.losses(rows, self.lm.withColumn("method", F.lit("all")), V).select("doc_id", "n_pairs", "nll")

    @cached_property
    def buffers(self) -> DataFrame:
        return stored(corpus.form_buffers(self.split.filter("split = 'train'"), BUFFER, SEED), "numbered")

    @cached_property
    def sketched_steps(self) -> DataFrame:
        shapes = ("shaped", "muon")
        return stored(lm_step.step_pass(*self.steps_of_tokens(), V, SKETCH, ALPHA, SCALE, EPS, SEED, phi=shapes), "steps")

    def step_scores(self, phi: str | None = None, buckets: int = SKETCH, step: int | None = None) -> DataFrame:
        if buckets != SKETCH or phi not in (None, "shaped", "muon"):
            return super().step_scores(phi, buckets, step)
        rows = self.sketched_steps if step is None else self.sketched_steps.filter(F.col("step") == step)
        return rows.drop("phi_shaped", "phi_muon") if phi is None else rows.withColumnRenamed(f"phi_{phi}", "phi")


def whole_nll(t: Tables) -> DataFrame:
    """(doc_id, n_pairs, nll): the mean loss of each text's pairs, all of them."""
    return lm_count.sequence_loss(T.pairs(t.tok), t.lm)


def whole_scored(t: Tables) -> DataFrame:
    """(doc_id, score, n_words): training documents by likelihood of their whole texts."""
    return whole_nll(t).join(t.tok.select("doc_id", "n_words"), "doc_id").join(t.split.filter("split = 'train'"), "doc_id").select("doc_id", F.round(-F.col("nll"), 9).alias("score"), "n_words")


H28 = "('0x' || substr(md5({0}), 1, 7))::BIGINT"

#: Definitions of the same tables for another SQL engine; each may use those before it.
DEFINITIONS = {
    "w": r"SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '[^\p{L}]+'), lambda x: x <> '') AS w FROM documents",
    "tok": f"SELECT doc_id, len(w) AS n_words, list_transform(w, lambda x: {H28.format('x')} % {V}) AS toks FROM w",
    "split": f"SELECT doc_id, CASE WHEN {H28.format(f"'split|{SEED}|' || doc_id")} % 10 = 0 THEN 'val' ELSE 'train' END AS split FROM documents",
    "pair": "SELECT doc_id, unnest(toks[1:len(toks) - 1]) AS x, unnest(toks[2:len(toks)]) AS y FROM tok WHERE len(toks) > 1",
    "spair": f"SELECT doc_id, unnest(t[1:len(t) - 1]) AS x, unnest(t[2:len(t)]) AS y FROM (SELECT doc_id, toks[1:{SCORE_LEN}] AS t FROM tok) WHERE len(t) > 1",
    "grid": f"SELECT a.range AS x, b.range AS y FROM range({V}) a, range({V}) b",
    "pc": "SELECT x, y, count(*) AS n FROM pair JOIN split USING (doc_id) WHERE split = 'train' GROUP BY x, y",
    "px": "SELECT x, sum(n) AS nx FROM pc GROUP BY x",
    "lm": f"SELECT x, y, (coalesce(n, 0) + {ALPHA}::DOUBLE) / (coalesce(nx, 0) + {ALPHA * V}::DOUBLE) AS p, ln((coalesce(n, 0) + {ALPHA}::DOUBLE) / (coalesce(nx, 0) + {ALPHA * V}::DOUBLE)) AS logp FROM grid LEFT JOIN pc USING (x, y) LEFT JOIN px USING (x)",
    "nll": "SELECT doc_id, count(*) AS n_pairs, -avg(logp) AS nll FROM spair JOIN lm USING (x, y) GROUP BY doc_id",
    "buf": f"SELECT (rank - 1) // {BUFFER} AS step, (rank - 1) % {BUFFER} AS slot, doc_id FROM (SELECT doc_id, row_number() OVER (ORDER BY md5('buf|{SEED}|' || doc_id), doc_id) AS rank FROM split WHERE split = 'train')",
    "pool": f"SELECT doc_id, row_number() OVER (ORDER BY md5('prx|{SEED}|' || doc_id), doc_id) AS rank FROM split WHERE split = 'val'",
    "pbatch": f"SELECT step, k, doc_id FROM (SELECT s.range AS step, k.range AS k, (s.range * {PROXY} + k.range) % (SELECT count(*) FROM pool) + 1 AS rank FROM range((SELECT max(step) + 1 FROM buf)) s, range({PROXY}) k) JOIN pool USING (rank)",
    # gradients of single documents, cell by cell
    "dx": "SELECT doc_id, x, count(*) AS nx FROM spair GROUP BY doc_id, x",
    "dn": "SELECT doc_id, sum(nx) AS n FROM dx GROUP BY doc_id",
    "dxy": "SELECT doc_id, x, y, count(*) AS nxy FROM spair GROUP BY doc_id, x, y",
    "grad": "SELECT doc_id, x, lm.y, (nx * p - coalesce(nxy, 0)) / n AS g FROM dx JOIN lm USING (x) JOIN dn USING (doc_id) LEFT JOIN dxy USING (doc_id, x, y)",
    "gp": "SELECT step, x, y, sum(g) / any_value(m) AS g FROM pbatch JOIN grad USING (doc_id) JOIN (SELECT step, count(*) AS m FROM pbatch SEMI JOIN dn USING (doc_id) GROUP BY step) USING (step) GROUP BY step, x, y",
    "fx": "SELECT doc_id, x, count(*) AS nx FROM pair JOIN split USING (doc_id) WHERE split = 'train' GROUP BY doc_id, x",
    "fn": "SELECT doc_id, sum(nx) AS n FROM fx GROUP BY doc_id",
    "fxy": "SELECT doc_id, x, y, count(*) AS nxy FROM pair JOIN split USING (doc_id) WHERE split = 'train' GROUP BY doc_id, x, y",
    "gmean": "SELECT x, lm.y, sum((nx * p - coalesce(nxy, 0)) / n) / (SELECT count(*) FROM fn) AS g FROM fx JOIN lm USING (x) JOIN fn USING (doc_id) LEFT JOIN fxy USING (doc_id, x, y) GROUP BY x, lm.y",
    "past": f"SELECT x, y, {SCALE}::DOUBLE / (abs(coalesce(g, 0)) + {EPS}::DOUBLE) AS f FROM grid LEFT JOIN gmean USING (x, y)",
    "ualign": "SELECT step, doc_id, sum(c.g * f * coalesce(gp.g, 0)) AS score FROM buf JOIN grad c USING (doc_id) JOIN past USING (x, y) LEFT JOIN gp USING (step, x, y) GROUP BY step, doc_id",
    "uraw": "SELECT step, doc_id, sum(c.g * coalesce(gp.g, 0)) AS score FROM buf JOIN grad c USING (doc_id) LEFT JOIN gp USING (step, x, y) GROUP BY step, doc_id",
    "wnll": "SELECT doc_id, count(*) AS n_pairs, -avg(logp) AS nll FROM pair JOIN lm USING (x, y) GROUP BY doc_id",
    "wscored": "SELECT doc_id, round(-nll, 9) AS score, n_words FROM wnll JOIN tok USING (doc_id) JOIN split USING (doc_id) WHERE split = 'train'",
    "scored": "SELECT doc_id, round(-nll, 9) AS score, n_words FROM nll JOIN tok USING (doc_id) JOIN split USING (doc_id) WHERE split = 'train'",
}
USES = {
    "tok": ["w"], "pair": ["tok"], "spair": ["tok"], "pc": ["pair", "split"], "px": ["pc"], "lm": ["grid", "pc", "px"], "nll": ["spair", "lm"],
    "buf": ["split"], "pool": ["split"], "pbatch": ["pool", "buf"], "dx": ["spair"], "dn": ["dx"], "dxy": ["spair"], "grad": ["dx", "dn", "dxy", "lm"],
    "gp": ["pbatch", "grad"], "fx": ["pair", "split"], "fn": ["fx"], "fxy": ["pair", "split"], "gmean": ["fx", "fn", "fxy", "lm"], "past": ["grid", "gmean"],
    "wnll": ["pair", "lm"], "wscored": ["wnll", "tok", "split"],
    "ualign": ["buf", "grad", "past", "gp"], "uraw": ["buf", "grad", "gp"], "scored": ["nll", "tok", "split"],
}


def with_tables(sql: str, *names: str, **more: str) -> str:
    """``sql`` after the definitions that it needs, and further ones given by name."""
    needed: list[str] = []

    def add(n: str) -> None:
        for m in USES.get(n, []):
            add(m)
        if n not in needed:
            needed.append(n)

    for n in names:
        add(n)
    parts = [f"{n} AS MATERIALIZED ({DEFINITIONS[n]})" for n in needed] + [f"{n} AS ({q})" for n, q in more.items()]
    return f"WITH {', '.join(parts)} {sql}" if parts else sql

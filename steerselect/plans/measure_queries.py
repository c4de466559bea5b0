"""Queries of the measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import tokens as T
from ..operators import corpus, lm_count, measures, pick
from .context import ALPHA, BUFFER, H28, LR, RATIO, SCORE_LEN, SEED, SKETCH, TAU, V, Tables, r6, whole_nll, with_tables
from .core_queries import BUCKET, SIGN, TOP
from .proxy_queries import raw_scores
from .registry import query

CHECKPOINTS = 5
CURVE = {
    "ck": f"SELECT doc_id, (step * {CHECKPOINTS}) // (SELECT max(step) + 1 FROM buf) AS c FROM buf",
    "cp": "SELECT c, x, y, count(*) AS n FROM pair JOIN ck USING (doc_id) GROUP BY 1, 2, 3",
    "cs": f"SELECT s.range AS c, x, y, sum(n) AS n FROM range({CHECKPOINTS}) s JOIN cp ON cp.c <= s.range GROUP BY 1, 2, 3",
    "cx": "SELECT c, x, sum(n) AS nx FROM cs GROUP BY 1, 2",
    "ct": f"SELECT s.range AS c, sum(n_words)::BIGINT AS tokens FROM range({CHECKPOINTS}) s JOIN ck ON ck.c <= s.range JOIN tok USING (doc_id) GROUP BY 1",
    "vp": "SELECT pair.* FROM pair JOIN split USING (doc_id) WHERE split = 'val'",
    "vl": f"SELECT s.range AS c, doc_id, -avg(ln((coalesce(n, 0) + {ALPHA}::DOUBLE) / (coalesce(nx, 0) + {ALPHA * V}::DOUBLE))) AS l FROM vp CROSS JOIN range({CHECKPOINTS}) s LEFT JOIN cs ON cs.c = s.range AND cs.x = vp.x AND cs.y = vp.y LEFT JOIN cx ON cx.c = s.range AND cx.x = vp.x GROUP BY 1, 2",
    "curve": "SELECT c, tokens, round(avg(l), 6) + 0.0 AS nll FROM vl JOIN ct USING (c) GROUP BY c, tokens",
}
CURVE_OF = ("pair", "buf", "tok", "split")


def _curve(t: Tables) -> DataFrame:
    """(c, tokens, nll): validation loss of models fitted on the first fifths of the buffers."""
    last = t.buffers.agg((F.max("step") + 1).alias("steps"))
    ck = t.buffers.crossJoin(F.broadcast(last)).select("doc_id", F.floor(F.col("step") * CHECKPOINTS / F.col("steps")).cast("long").alias("c"))
    counts = t.train_pairs.join(ck, "doc_id").groupBy("c", "x", "y").agg(F.count(F.lit(1)).alias("n"))
    stages = t.spark.range(CHECKPOINTS).select(F.col("id").alias("s"))
    cells = F.broadcast(stages).join(counts, F.col("c") <= F.col("s")).groupBy("s", "x", "y").agg(F.sum("n").alias("n"))
    grid = stages.crossJoin(lm_count.grid(t.docs, V))
    rows = cells.groupBy("s", "x").agg(F.sum("n").alias("nx"))
    p = (F.coalesce("n", F.lit(0)) + ALPHA) / (F.coalesce("nx", F.lit(0)) + ALPHA * V)
    lms = grid.join(F.broadcast(cells), ["s", "x", "y"], "left").join(F.broadcast(rows), ["s", "x"], "left").select("s", "x", "y", F.log(p).alias("logp"))
    losses = t.val_pairs.join(F.broadcast(lms), ["x", "y"]).groupBy("s", "doc_id").agg((-F.avg("logp")).alias("l")).groupBy("s").agg(r6(F.avg("l")).alias("nll"))
    seen = ck.join(t.tok.select("doc_id", "n_words"), "doc_id").groupBy("c").agg(F.sum("n_words").alias("w"))
    tokens = F.broadcast(stages).join(seen, F.col("c") <= F.col("s")).groupBy("s").agg(F.sum("w").alias("tokens"))
    return losses.join(tokens, "s").select(F.col("s").alias("c"), "tokens", "nll")


@query("loss_curve", with_tables("SELECT c, tokens, nll FROM curve", *CURVE_OF, **CURVE))
def loss_curve(t: Tables) -> DataFrame:
    return _curve(t)


REACHED = "SELECT target, min(tokens) FILTER (WHERE nll <= target) AS tokens FROM curve, (SELECT round(max(nll) + (min(nll) - max(nll)) * f, 6) AS target FROM curve, (SELECT unnest([0.5, 0.9, 1.0]::DOUBLE[]) AS f) GROUP BY f) GROUP BY target"


def _reached(t: Tables) -> DataFrame:
    curve = _curve(t)
    f = F.explode(F.array(F.lit(0.5), F.lit(0.9), F.lit(1.0)))
    targets = curve.agg(F.max("nll").alias("hi"), F.min("nll").alias("lo")).select("hi", "lo", f.alias("f")).select(F.round(F.col("hi") + (F.col("lo") - F.col("hi")) * F.col("f"), 6).alias("target"))
    met = curve.crossJoin(F.broadcast(targets))
    return met.groupBy("target").agg(F.min(F.when(F.col("nll") <= F.col("target"), F.col("tokens"))).alias("tokens"))


@query("tokens_to_target", with_tables(REACHED, *CURVE_OF, **CURVE))
def tokens_to_target(t: Tables) -> DataFrame:
    """Tokens until half, nine tenths and all of the curve's fall are reached."""
    return _reached(t)


@query("data_efficiency", with_tables(f"SELECT target, round((SELECT max(tokens) FROM curve)::DOUBLE / tokens, 6) + 0.0 AS ratio FROM ({REACHED})", *CURVE_OF, **CURVE))
def data_efficiency(t: Tables) -> DataFrame:
    """How many times fewer tokens reach a target than the whole corpus holds."""
    whole = t.tok.join(t.buffers.select("doc_id"), "doc_id").agg(F.sum("n_words").alias("whole"))
    return _reached(t).crossJoin(F.broadcast(whole)).select("target", r6(F.col("whole") / F.col("tokens")).alias("ratio"))


DOMAIN = "CAST(substr(source, 4) AS INT) % 10"


@query("domain_ppl", with_tables(f"SELECT domain, count(*) AS n, round(exp(-sum(total) / sum(k)), 5) + 0.0 AS ppl FROM (SELECT doc_id, {DOMAIN} AS domain, sum(logp) AS total, count(*) AS k, row_number() OVER (PARTITION BY {DOMAIN} ORDER BY md5('dom|' || doc_id), doc_id) AS rk FROM pair JOIN lm USING (x, y) JOIN split USING (doc_id) JOIN documents USING (doc_id) WHERE split = 'val' GROUP BY doc_id, source) WHERE rk <= 5 GROUP BY domain", "pair", "lm", "split"))
def domain_ppl(t: Tables) -> DataFrame:
    """Perplexity on five held-out documents of each of ten domains."""
    doc = t.val_pairs.join(F.broadcast(t.lm), ["x", "y"]).groupBy("doc_id").agg(F.sum("logp").alias("total"), F.count(F.lit(1)).alias("k"))
    rows = doc.join(t.docs.select("doc_id", (F.substring("source", 4, 9).cast("int") % 10).alias("domain")), "doc_id")
    order = Window.partitionBy("domain").orderBy(F.md5(F.concat(F.lit("dom|"), F.col("doc_id").cast("string"))), "doc_id")
    kept = rows.withColumn("rk", F.row_number().over(order)).filter("rk <= 5")
    return kept.groupBy("domain").agg(F.count(F.lit(1)).alias("n"), (F.round(F.exp(-F.sum("total") / F.sum("k")), 5) + F.lit(0.0)).alias("ppl"))


@query("domain_ppl_whole", with_tables(f"SELECT {DOMAIN} AS domain, count(DISTINCT doc_id) AS n, round(exp(-sum(logp) / count(*)), 5) + 0.0 AS ppl FROM pair JOIN lm USING (x, y) JOIN split USING (doc_id) JOIN documents USING (doc_id) WHERE split = 'val' GROUP BY 1", "pair", "lm", "split"))
def domain_ppl_whole(t: Tables) -> DataFrame:
    """Perplexity on all held-out documents of each domain; ``domain_ppl`` takes five."""
    doc = t.val_pairs.join(F.broadcast(t.lm), ["x", "y"]).groupBy("doc_id").agg(F.sum("logp").alias("total"), F.count(F.lit(1)).alias("k"))
    rows = doc.join(t.docs.select("doc_id", (F.substring("source", 4, 9).cast("int") % 10).alias("domain")), "doc_id")
    return rows.groupBy("domain").agg(F.count(F.lit(1)).alias("n"), (F.round(F.exp(-F.sum("total") / F.sum("k")), 5) + F.lit(0.0)).alias("ppl"))


CH = ", ".join(map(str, measures.CHOICES))
TASKS = {
    "bt": rf"SELECT item_id, list_transform(list_filter(regexp_split_to_array(lower(text), '[^\p{{L}}]+'), lambda x: x <> ''), lambda x: {H28.format('x')} % {V}) AS toks FROM benchmark",
    "bp": "SELECT item_id, toks[len(toks) // 2] AS last, toks[len(toks) // 2 + 1:len(toks)] AS tail, row_number() OVER (ORDER BY item_id) - 1 AS pos FROM bt WHERE len(toks) >= 4",
    "bo": f"SELECT item_id, last, pos, unnest(range(0, [{CH}][item_id % 10 + 1])) AS option FROM bp",
    "bw": "SELECT o.item_id, o.item_id % 10 AS task, option, list_concat([o.last], q.tail) AS toks FROM bo o JOIN bp q ON q.pos = (o.pos + option) % (SELECT count(*) FROM bp)",
    "bx": "SELECT item_id, task, option, unnest(toks[1:len(toks) - 1]) AS x, unnest(toks[2:len(toks)]) AS y FROM bw",
    "bs": "SELECT item_id, task, option, sum(logp) AS total, avg(logp) AS mean FROM bx JOIN lm USING (x, y) GROUP BY 1, 2, 3",
}
ACC = "SELECT task, count(*) AS n, sum((option = 0)::INT)::BIGINT AS correct, round(sum((option = 0)::INT)::DOUBLE / count(*), 6) + 0.0 AS acc FROM (SELECT task, item_id, option, row_number() OVER (PARTITION BY item_id ORDER BY round({key}, 9) DESC, option) AS rk FROM bs) WHERE rk = 1 GROUP BY task"


def _scores(t: Tables) -> DataFrame:
    return measures.option_scores(measures.tasks(t.table("benchmark"), V), t.lm)


@query("mc_ppl_acc", with_tables(ACC.format(key="mean"), "lm", **TASKS))
def mc_ppl_acc(t: Tables) -> DataFrame:
    return measures.choice_accuracy(_scores(t), "PPL")


@query("mc_ll_acc", with_tables(ACC.format(key="total"), "lm", **TASKS))
def mc_ll_acc(t: Tables) -> DataFrame:
    return measures.choice_accuracy(_scores(t), "LL")


@query("suite_avg", with_tables("SELECT round(avg(acc), 6) + 0.0 AS average, round((sum(acc) - max(acc)) / (count(*) - 1), 6) + 0.0 AS without_best FROM (SELECT CASE WHEN p.task IN (0, 5) THEN l.acc ELSE p.acc END AS acc FROM pa p JOIN la l USING (task))", "lm", **TASKS, pa=ACC.format(key="mean"), la=ACC.format(key="total")))
def suite_avg(t: Tables) -> DataFrame:
    """The mean accuracy of ten tasks, each in its mode, and the mean without the best one."""
    s = _scores(t)
    p, ll = measures.choice_accuracy(s, "PPL"), measures.choice_accuracy(s, "LL").select("task", F.col("acc").alias("l"))
    acc = p.join(ll, "task").select(F.when(F.col("task").isin(*measures.LL_TASKS), F.col("l")).otherwise(F.col("acc")).alias("acc"))
    return acc.agg(r6(F.avg("acc")).alias("average"), r6((F.sum("acc") - F.max("acc")) / (F.count(F.lit(1)) - 1)).alias("without_best"))


@query("exact_match", with_tables("SELECT task, count(*) AS n, round(avg((y = g)::INT), 6) + 0.0 AS acc FROM (SELECT item_id % 10 AS task, bp.item_id, tail[1] AS g, y, row_number() OVER (PARTITION BY item_id ORDER BY round(logp, 9) DESC, y) AS rk FROM bp JOIN lm ON lm.x = bp.last) WHERE rk = 1 GROUP BY task", "lm", bt=TASKS["bt"], bp=TASKS["bp"]))
def exact_match(t: Tables) -> DataFrame:
    """Greedy continuation by one token against the passage's own."""
    gold = measures.tasks(t.table("benchmark"), V).filter("option = 0").select("task", "item_id", F.col("last").alias("x"), F.col("toks")[0].alias("gold"))
    best = t.lm.groupBy("x").agg(F.max_by("y", F.struct(F.round("logp", 9), -F.col("y"))).alias("y"))
    return gold.join(F.broadcast(best), "x").groupBy("task").agg(F.count(F.lit(1)).alias("n"), r6(F.avg((F.col("y") == F.col("gold")).cast("int"))).alias("acc"))


LIKELY = TOP.format(key="s", src="(SELECT step, doc_id, round(-nll, 9) AS s FROM buf JOIN nll USING (doc_id))", ratio=RATIO)
LOSSY = TOP.format(key="s", src="(SELECT step, doc_id, round(nll, 9) AS s FROM buf JOIN nll USING (doc_id))", ratio=RATIO)
RAW = TOP.format(key="round(score, 9)", src="uraw", ratio=RATIO)


def _likely(t: Tables) -> DataFrame:
    return pick.rank_in_step(t.buffers.join(t.nll, "doc_id"), F.round(-F.col("nll"), 9), RATIO).select("step", "doc_id")


def _lossy(t: Tables) -> DataFrame:
    return pick.rank_in_step(t.buffers.join(t.nll, "doc_id"), F.round("nll", 9), RATIO).select("step", "doc_id")


@query("token_account", with_tables("SELECT step, count(*) AS k, sum(n_words)::BIGINT AS update_tokens FROM p JOIN tok USING (doc_id) GROUP BY step", "buf", "nll", "tok", p=LIKELY))
def token_account(t: Tables) -> DataFrame:
    met = _likely(t).join(t.tok.select("doc_id", "n_words"), "doc_id")
    return met.groupBy("step").agg(F.count(F.lit(1)).alias("k"), F.sum("n_words").alias("update_tokens"))


@query("overlap", with_tables("SELECT p.step, count(*) AS shared FROM p JOIN q ON p.step = q.step AND p.doc_id = q.doc_id GROUP BY p.step", "buf", "nll", "uraw", p=LOSSY, q=RAW))
def overlap(t: Tables) -> DataFrame:
    """Picks that the high-loss and the raw-gradient selector share, by step."""
    raw = pick.rank_in_step(raw_scores(t), F.round("score", 9), RATIO).select("step", "doc_id")
    return _lossy(t).join(raw, ["step", "doc_id"]).groupBy("step").agg(F.count(F.lit(1)).alias("shared"))


@query("diversity", with_tables("SELECT step, count(*) AS groups, round(-sum(q * ln(q)), 6) + 0.0 AS entropy FROM (SELECT step, n::DOUBLE / sum(n) OVER (PARTITION BY step) AS q FROM (SELECT step, source, count(*) AS n FROM p JOIN documents USING (doc_id) GROUP BY 1, 2)) GROUP BY step", "buf", "nll", p=LIKELY))
def diversity(t: Tables) -> DataFrame:
    counts = _likely(t).join(t.docs.select("doc_id", "source"), "doc_id").groupBy("step", "source").agg(F.count(F.lit(1)).alias("n"))
    return measures.entropy(counts, ["step"])


@query("sel_entropy", with_tables(f"SELECT step, round(-sum(q * ln(q)), 6) + 0.0 AS entropy, round(1 / sum(q * q), 4) + 0.0 AS effective FROM (SELECT step, exp(-nll / {TAU}) / sum(exp(-nll / {TAU})) OVER (PARTITION BY step) AS q FROM buf JOIN nll USING (doc_id)) GROUP BY step", "buf", "nll"))
def sel_entropy(t: Tables) -> DataFrame:
    p = pick.softmax(t.buffers.join(t.nll, "doc_id").withColumn("utility", -F.col("nll")), tau=TAU)
    q = F.col("prob")
    return p.groupBy("step").agg(r6(-F.sum(q * F.log(q))).alias("entropy"), (F.round(1 / F.sum(q * q), 4) + F.lit(0.0)).alias("effective"))


@query("cpt_breakdown", with_tables(f"SELECT lang, domain, count(*) AS n, round(avg(nll), 6) + 0.0 AS nll FROM (SELECT lang, {DOMAIN} AS domain, nll FROM nll JOIN documents USING (doc_id)) GROUP BY CUBE (lang, domain)", "nll"))
def cpt_breakdown(t: Tables) -> DataFrame:
    rows = t.nll.join(t.docs.select("doc_id", "lang", (F.substring("source", 4, 9).cast("int") % 10).alias("domain")), "doc_id")
    return rows.cube("lang", "domain").agg(F.count(F.lit(1)).alias("n"), r6(F.avg("nll")).alias("nll"))


@query("cpt_breakdown_whole", with_tables(f"SELECT lang, domain, count(*) AS n, round(avg(nll), 6) + 0.0 AS nll FROM (SELECT lang, {DOMAIN} AS domain, nll FROM wnll JOIN documents USING (doc_id)) GROUP BY CUBE (lang, domain)", "wnll"))
def cpt_breakdown_whole(t: Tables) -> DataFrame:
    rows = whole_nll(t).join(t.docs.select("doc_id", "lang", (F.substring("source", 4, 9).cast("int") % 10).alias("domain")), "doc_id")
    return rows.cube("lang", "domain").agg(F.count(F.lit(1)).alias("n"), r6(F.avg("nll")).alias("nll"))


@query("sketch_error", with_tables(f"SELECT count(*) AS n, round(avg(e), 4) + 0.0 AS bias, round(stddev_samp(e), 4) + 0.0 AS sd, round(corr(score, s), 3) + 0.0 AS correlation FROM (SELECT score, s, s - score AS e FROM uraw JOIN (SELECT step, doc_id, sum(c.val * coalesce(q.val, 0)) AS s FROM buf JOIN ck c USING (doc_id) LEFT JOIN pk q USING (step, bucket) GROUP BY 1, 2) USING (step, doc_id))", "uraw", ck=f"SELECT doc_id, {BUCKET} AS bucket, sum({SIGN} * g) AS val FROM grad GROUP BY 1, 2", pk=f"SELECT step, {BUCKET} AS bucket, sum({SIGN} * g) AS val FROM gp GROUP BY 1, 2"))
def sketch_error(t: Tables) -> DataFrame:
    """Sketched against exact products in the plain geometry."""
    e = t.step_scores().select(F.col("plain").alias("score"), F.col("plain_sketched").alias("s"), (F.col("plain_sketched") - F.col("plain")).alias("e"))
    r = lambda c, n: F.round(c, n) + F.lit(0.0)
    return e.agg(F.count(F.lit(1)).alias("n"), r(F.avg("e"), 4).alias("bias"), r(F.stddev_samp("e"), 4).alias("sd"), r(F.corr("score", "s"), 3).alias("correlation"))


WORK = f"SELECT step, count(*) AS n, avg(n_words) AS length, avg(least(n_words, {SCORE_LEN})) AS scored FROM buf JOIN tok USING (doc_id) WHERE n_words > 0 GROUP BY step"


@query("flop_model", with_tables("SELECT step, n, round(length, 6) AS length, round(6 * 1.5e9 * (n + 8) * scored / (6 * 1.5e9 * (n / 2.0::DOUBLE) * length) + (2.0 * n * n * 8192 * 200 + n * n) / (6 * 1.5e9 * (n / 2.0::DOUBLE) * length), 6) AS overhead, round(1 + (6 * 1.5e9 * n * length + 2 * n * 1.5e9) / (6 * 1.5e9 * (n / 2.0::DOUBLE) * length), 6) AS naive_slowdown FROM work", "buf", "tok", work=WORK))
def flop_model(t: Tables) -> DataFrame:
    """The work of each step's choice by the lengths of its candidates, against the work of training on half of them."""
    met = t.buffers.select("step", "doc_id").join(t.words.filter("n_words > 0"), "doc_id")
    rows = met.groupBy("step").agg(F.count(F.lit(1)).alias("n"), F.avg("n_words").alias("length"), F.avg(F.least("n_words", F.lit(SCORE_LEN))).alias("scored"))
    f = measures.flops(F.col("n").cast("double"), F.col("n") / 2, F.col("scored"), F.col("length"), 1.5e9, 8192, 200)
    return rows.select("step", "n", F.round("length", 6).alias("length"), F.round(f["overhead"], 6).alias("overhead"), F.round(f["naive_slowdown"], 6).alias("naive_slowdown"))


SIZES = (16, 32, 64)


@query("compression", with_tables(f"SELECT doc_id, len(list_distinct(toks[1:n_words - 1])) * {V} AS d, m, (len(list_distinct(toks[1:n_words - 1])) * {V})::DOUBLE / m AS ratio FROM tok, (SELECT unnest({list(SIZES)}) AS m) WHERE n_words > 1", "tok"))
def compression(t: Tables) -> DataFrame:
    """The coordinates of each document's gradient (a row for each token that begins a pair) to those of sketches of three sizes."""
    d = F.size(F.array_distinct(F.slice("toks", 1, F.col("n_words") - 1))) * V
    rows = t.numbered.filter("n_words > 1").select("doc_id", d.alias("d"))
    return rows.select("doc_id", "d", F.explode(F.array(*map(F.lit, SIZES))).alias("m")).withColumn("ratio", F.col("d") / F.col("m"))

"""Accuracy, loss, diversity and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import tokens as T
from ..functions.tokens import gumbel

#: Options per item and scoring mode of the ten tasks.
CHOICES = (4, 3, 4, 2, 3, 2, 4, 4, 5, 2)
LL_TASKS = (0, 5)


def tasks(bench: DataFrame, vocabulary: int) -> DataFrame:
    """(task, item_id, option, mode, last, toks): passages halved into a prompt and its continuation.

    Option 0 is the passage's own second half, option k that of the k-th next passage; ``last`` is the prompt's last token.
    """
    t = T.tokenized(bench, vocabulary, "item_id")
    half = F.floor(F.size("toks") / 2).cast("int")
    parts = t.filter(F.size("toks") >= 4).select("item_id", F.element_at("toks", half).alias("last"), F.slice("toks", half + 1, F.size("toks") - half).alias("tail"))
    # a benchmark is small by nature; its items are numbered to find the next ones
    ranked = parts.withColumn("at", F.row_number().over(Window.orderBy("item_id")) - 1)
    n = ranked.agg(F.count(F.lit(1)).alias("n"))
    choices = F.element_at(F.array(*map(F.lit, CHOICES)), (F.col("item_id") % 10 + 1).cast("int"))
    asked = ranked.crossJoin(F.broadcast(n)).select("item_id", "last", "at", "n", F.explode(F.sequence(F.lit(0), choices - 1)).alias("option"))
    tails = ranked.select(F.col("at").alias("from"), F.col("tail").alias("toks"))
    met = asked.withColumn("from", ((F.col("at") + F.col("option")) % F.col("n")).cast("int")).join(F.broadcast(tails), "from")
    mode = F.when((F.col("item_id") % 10).isin(*LL_TASKS), "LL").otherwise("PPL")
    return met.select((F.col("item_id") % 10).alias("task"), "item_id", "option", mode.alias("mode"), "last", "toks")


def option_scores(rows: DataFrame, lm: DataFrame) -> DataFrame:
    """(task, item_id, option, mode, total, mean): log-likelihood of each option after its prompt."""
    whole = rows.withColumn("toks", F.concat(F.array("last"), "toks"))
    keys = ["task", "item_id", "option", "mode"]
    both = F.zip_with(F.slice("toks", 1, F.size("toks") - 1), F.slice("toks", 2, F.size("toks") - 1), lambda a, b: F.struct(a.alias("x"), b.alias("y")))
    pairs = whole.select(*keys, F.explode(both).alias("p")).select(*keys, "p.x", "p.y")
    return pairs.join(F.broadcast(lm), ["x", "y"]).groupBy(*keys).agg(F.sum("logp").alias("total"), F.avg("logp").alias("mean"))


def choice_accuracy(scores: DataFrame, mode: str) -> DataFrame:
    """(task, n, correct, acc): LL takes the greatest total, PPL the least mean loss; ties to the smaller option."""
    key = F.round("total" if mode == "LL" else "mean", 9)
    best = scores.groupBy("task", "item_id").agg(F.max_by("option", F.struct(key, -F.col("option"))).alias("pick"))
    n, right = F.count(F.lit(1)), F.sum((F.col("pick") == 0).cast("long"))
    return best.groupBy("task").agg(n.alias("n"), right.alias("correct"), (F.round(right / n, 6) + F.lit(0.0)).alias("acc"))


def entropy(counts: DataFrame, by: list[str], n: str = "n") -> DataFrame:
    """(by..., groups, entropy) of counts."""
    total = counts.withColumn("_t", F.sum(n).over(Window.partitionBy(*by)))
    p = F.col(n) / F.col("_t")
    return total.groupBy(*by).agg(F.count(F.lit(1)).alias("groups"), (F.round(-F.sum(p * F.log(p)), 6) + F.lit(0.0)).alias("entropy"))


def flops(n: Column, k: Column, t: Column, length: Column, d: float, m: int, layers: int, proxy: int = 8) -> dict[str, Column]:
    """Analytic work per step: training, a scoring pass over prefixes, sketches, the Gram matrix and the draws."""
    train = 6 * d * k * length
    score = 6 * d * (n + proxy) * t
    gram = 2 * n * n * layers * m
    draws = 2 * n * k
    naive = 6 * d * n * length + 2 * n * d
    return {"train": train, "score": score, "gram": gram, "draws": draws, "overhead": (score + gram + draws) / train, "naive_slowdown": (train + naive) / train}


def next_tokens(lm: DataFrame, temperature: float, top_p: float, top_k: int) -> DataFrame:
    """(x, y, prob): what may follow x, from (x, y, logp): sharpened, cut to the likeliest few, then to the nucleus.

    The nucleus is the shortest run of likeliest tokens that holds ``top_p``; ties go to the smaller token.
    """
    row = Window.partitionBy("x")
    best = row.orderBy(F.round("logp", 9).desc(), "y")
    few = lm.select("x", "y", F.exp((F.col("logp") - F.max("logp").over(row)) / temperature).alias("e"), F.row_number().over(best).alias("rk")).filter(F.col("rk") <= top_k)
    q = few.withColumn("q", F.col("e") / F.sum("e").over(row))
    before = F.round(F.coalesce(F.sum("q").over(row.orderBy("rk").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)), 9)
    kept = q.withColumn("before", before).filter(F.col("before") < top_p)
    return kept.select("x", "y", (F.col("q") / F.sum("q").over(row)).alias("prob"))


def decode(starts: DataFrame, following: DataFrame, length: int, seed: int = 42, id_col: str = "doc_id") -> DataFrame:
    """(id, toks): ``length`` tokens drawn one after another from (id, last); noise is fixed by id, place and token.

    The table of what may follow has the vocabulary's size and travels as one map; rows never meet.
    """
    lists = following.groupBy("x").agg(F.sort_array(F.collect_list(F.struct("y", "prob"))).alias("l"))
    one = lists.agg(F.map_from_entries(F.collect_list(F.struct("x", "l"))).alias("after"))

    def draw(state, at):
        noise = lambda c: gumbel(F.concat_ws("|", F.lit(f"dec|{seed}"), F.col(id_col), at, c["y"]))
        keyed = F.transform(F.col("after")[state["last"]], lambda c: F.struct((F.round(F.log(c["prob"]) + noise(c), 9)).alias("key"), (-c["y"]).alias("y")))
        y = -F.array_max(keyed)["y"]
        return F.struct(y.alias("last"), F.concat(state["out"], F.array(y)).alias("out"))

    first = F.struct(F.col("last").cast("long").alias("last"), F.array().cast("array<long>").alias("out"))
    out = F.aggregate(F.sequence(F.lit(0), F.lit(length - 1)), first, draw)
    return starts.crossJoin(F.broadcast(one)).select(id_col, out["out"].alias("toks"))


def mean_cosine(vectors: DataFrame, members: DataFrame, by: str = "step") -> DataFrame:
    """(by, k, cosine): the mean over all pairs of members, from rows (by, b, u) of their unit vectors."""
    sums = vectors.groupBy(by, "b").agg(F.sum("u").alias("v")).groupBy(by).agg(F.sum(F.col("v") * F.col("v")).alias("s"))
    k = members.groupBy(by).agg(F.count(F.lit(1)).alias("k")).filter("k > 1")
    return sums.join(k, by).select(by, "k", ((F.col("s") - F.col("k")) / (F.col("k") * (F.col("k") - 1.0))).alias("cosine"))

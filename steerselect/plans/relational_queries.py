"""The operators around the methods: joins, aggregates, windows, sets, sampling, text, arrays, dates, streams."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import tokens as T
from ..functions import udx
from ..operators import proxy
from ..streaming import runs
from .context import H28, V, Tables, r6, with_tables
from .registry import query


def rows_in():
    """The number of rows; made when a query runs, since columns need a session."""
    return F.count(F.lit(1))


@query("op_tokens", with_tables("SELECT doc_id, n_words, len(list_distinct(toks)) AS n_distinct FROM tok", "tok"))
def op_tokens(t: Tables) -> DataFrame:
    return t.tok.select("doc_id", "n_words", F.size(F.array_distinct("toks")).alias("n_distinct"))


@query("op_pairs", with_tables("SELECT x, y, count(*) AS n FROM pair GROUP BY x, y", "pair"))
def op_pairs(t: Tables) -> DataFrame:
    return T.pairs(t.tok).groupBy("x", "y").agg(rows_in().alias("n"))


@query("op_shingles", with_tables("SELECT doc_id, count(DISTINCT s) AS n FROM (SELECT doc_id, array_to_string(l[i:i + 4], ' ') AS s FROM (SELECT doc_id, w AS l, unnest(range(1, len(w) - 3)) AS i FROM w)) GROUP BY doc_id", "w"))
def op_shingles(t: Tables) -> DataFrame:
    return T.shingles(t.docs, 5).groupBy("doc_id").agg(rows_in().alias("n"))


@query("op_hash_vocab", with_tables("SELECT u AS bucket, count(*) AS n FROM (SELECT unnest(toks) AS u FROM tok) GROUP BY u", "tok"))
def op_hash_vocab(t: Tables) -> DataFrame:
    return t.tok.select(F.explode("toks").alias("bucket")).groupBy("bucket").agg(rows_in().alias("n"))


@query("op_doc_stats", with_tables("SELECT doc_id, n_words, len(list_distinct(w.w)) AS n_types, round(list_sum(list_transform(w.w, lambda x: length(x)))::DOUBLE / n_words, 6) + 0.0 AS mean_length FROM tok JOIN w USING (doc_id) WHERE n_words > 0", "w", "tok"))
def op_doc_stats(t: Tables) -> DataFrame:
    w = t.docs.select("doc_id", T.words("text").alias("w")).filter(F.size("w") > 0)
    total = F.aggregate("w", F.lit(0), lambda a, x: a + F.length(x))
    return w.select("doc_id", F.size("w").alias("n_words"), F.size(F.array_distinct("w")).alias("n_types"), r6(total / F.size("w")).alias("mean_length"))


@query("op_exact_dups", "SELECT md5(text) AS digest, min(doc_id) AS first_id, count(*) AS n FROM documents GROUP BY text HAVING count(*) > 1")
def op_exact_dups(t: Tables) -> DataFrame:
    return t.docs.groupBy(F.md5("text").alias("digest")).agg(F.min("doc_id").alias("first_id"), rows_in().alias("n")).filter("n > 1")


BANDS = 8


@query("op_near_dups", with_tables(f"SELECT band, sig, min(doc_id) AS first_id, count(*) AS n FROM (SELECT doc_id, b AS band, min({H28.format("b || '|' || s")}) AS sig FROM (SELECT DISTINCT doc_id, array_to_string(l[i:i + 4], ' ') AS s FROM (SELECT doc_id, w AS l, unnest(range(1, len(w) - 3)) AS i FROM w)), (SELECT range AS b FROM range({BANDS})) GROUP BY 1, 2) GROUP BY 1, 2 HAVING count(*) > 1", "w"))
def op_near_dups(t: Tables) -> DataFrame:
    """Groups of equal MinHash values over five-word shingles, one band per permutation."""
    sh = T.shingles(t.docs, 5)
    hashes = [F.min(T.hash28(F.concat(F.lit(f"{b}|"), F.col("shingle")))).alias(f"h{b}") for b in range(BANDS)]
    sig = sh.groupBy("doc_id").agg(*hashes)
    rows = sig.select("doc_id", F.posexplode(F.array(*(f"h{b}" for b in range(BANDS)))).alias("band", "sig"))
    return rows.groupBy("band", "sig").agg(F.min("doc_id").alias("first_id"), rows_in().alias("n")).filter("n > 1")


@query("op_html_text", r"SELECT page_id, length(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>.*?</(script|style)>', ' ', 'gs'), '<[^>]*>', ' ', 'g')) AS n_chars FROM pages")
def op_html_text(t: Tables) -> DataFrame:
    text = F.regexp_replace(F.regexp_replace("html", r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), "<[^>]*>", " ")
    return t.table("pages").select("page_id", F.length(text).cast("long").alias("n_chars"))


@query("op_url_parts", r"SELECT page_id, regexp_extract(url, '^https?://([^/?#]+)', 1) AS host, regexp_extract(url, '^https?://[^/?#]+(/[^?#]*)', 1) AS path FROM pages")
def op_url_parts(t: Tables) -> DataFrame:
    return t.table("pages").select("page_id", F.regexp_extract("url", r"^https?://([^/?#]+)", 1).alias("host"), F.regexp_extract("url", r"^https?://[^/?#]+(/[^?#]*)", 1).alias("path"))


@query("op_json_props", "SELECT event_type, sum(CAST(json_extract(props, '$.k') AS BIGINT))::BIGINT AS total FROM events GROUP BY event_type")
def op_json_props(t: Tables) -> DataFrame:
    return t.table("events").select("event_type", F.from_json("props", "k long")["k"].alias("k")).groupBy("event_type").agg(F.sum("k").alias("total"))


@query("op_dialog", "SELECT conv_id, count(*) AS turns, md5(string_agg(role || ': ' || text, chr(10) ORDER BY turn)) AS digest FROM conversations GROUP BY conv_id")
def op_dialog(t: Tables) -> DataFrame:
    turns = F.array_sort(F.collect_list(F.struct("turn", F.concat("role", F.lit(": "), "text").alias("s"))))
    return t.table("conversations").groupBy("conv_id").agg(rows_in().alias("turns"), F.md5(F.array_join(turns["s"], "\n")).alias("digest"))


SALES = "SELECT n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) + 0.0 AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"


def _sales(t: Tables, hint: str) -> DataFrame:
    l, o, c, n = (t.table(x) for x in ("lineitem", "orders", "customer", "nation"))
    met = l.join(o.hint(hint), F.col("l_orderkey") == F.col("o_orderkey")).join(c.hint(hint), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    return met.groupBy("n_name").agg((F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2) + F.lit(0.0)).alias("revenue"))


query("op_merge_join", SALES)(lambda t: _sales(t, "merge"))
query("op_hash_join", SALES)(lambda t: _sales(t, "shuffle_hash"))


@query("op_broadcast_join", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def op_broadcast_join(t: Tables) -> DataFrame:
    c, n, r = (t.table(x) for x in ("customer", "nation", "region"))
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey).groupBy("r_name").agg(rows_in().alias("n"))


@query("op_semi", "SELECT c_custkey FROM customer SEMI JOIN orders ON c_custkey = o_custkey")
def op_semi(t: Tables) -> DataFrame:
    return t.table("customer").join(t.table("orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("op_anti", "SELECT doc_id FROM documents ANTI JOIN labels USING (doc_id)")
def op_anti(t: Tables) -> DataFrame:
    return t.docs.join(t.table("labels"), "doc_id", "left_anti").select("doc_id")


@query("op_outer_join", "SELECT coalesce(quality, -1) AS quality, count(*) AS n FROM documents FULL JOIN labels USING (doc_id) GROUP BY 1")
def op_outer_join(t: Tables) -> DataFrame:
    return t.docs.join(t.table("labels"), "doc_id", "full").groupBy(F.coalesce("quality", F.lit(-1)).alias("quality")).agg(rows_in().alias("n"))


@query("op_range_join", "SELECT lo, count(*) AS n FROM documents JOIN (SELECT range * 1000 AS lo, range * 1000 + 1500 AS hi FROM range(20)) ON n_chars >= lo AND n_chars < hi GROUP BY lo")
def op_range_join(t: Tables) -> DataFrame:
    """Overlapping ranges by bins: a range is listed in each bin that it touches, so the join is an equality."""
    ranges = t.spark.range(20).select((F.col("id") * 1000).alias("lo"), (F.col("id") * 1000 + 1500).alias("hi"))
    bins = ranges.select("lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") / 1000), F.floor((F.col("hi") - 1) / 1000))).alias("bin"))
    rows = t.docs.select("n_chars", F.floor(F.col("n_chars") / 1000).alias("bin"))
    met = rows.join(F.broadcast(bins), "bin").filter("n_chars >= lo AND n_chars < hi")
    return met.groupBy("lo").agg(rows_in().alias("n"))


@query("op_asof_join", "SELECT p.event_id, v.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY 1, 2) v ON p.user_id = v.user_id AND p.ts >= v.ts")
def op_asof_join(t: Tables) -> DataFrame:
    """Each purchase with its user's latest view at or before it: one shuffle and a running last value."""
    e = t.table("events").filter(F.col("event_type").isin("purchase", "view"))
    view = F.when(F.col("event_type") == "view", F.col("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", (F.col("event_type") == "purchase").cast("int"), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("last_view", F.last(view, ignorenulls=True).over(w)).filter("event_type = 'purchase'").select("event_id", "last_view")


@query("op_nested_loop", "SELECT vec_id, max(round(list_inner_product(e.embedding::DOUBLE[], q.v), 6)) + 0.0 AS best FROM embeddings e, (SELECT embedding::DOUBLE[] AS v FROM embeddings WHERE label = 0 AND vec_id < 100) q GROUP BY vec_id")
def op_nested_loop(t: Tables) -> DataFrame:
    e = t.table("embeddings")
    q = e.filter("label = 0 AND vec_id < 100").select(F.col("embedding").alias("v"))
    return e.crossJoin(F.broadcast(q)).groupBy("vec_id").agg((F.max(F.round(proxy.dot(F.col("embedding"), F.col("v")), 6)) + F.lit(0.0)).alias("best"))


@query("op_lateral_topk", "SELECT n_name, c_custkey, c_acctbal FROM (SELECT n_name, c_custkey, c_acctbal, row_number() OVER (PARTITION BY n_name ORDER BY c_acctbal DESC, c_custkey) AS rk FROM nation JOIN customer ON n_nationkey = c_nationkey) WHERE rk <= 3")
def op_lateral_topk(t: Tables) -> DataFrame:
    n, c = t.table("nation").alias("n"), t.table("customer")
    inner = c.filter(F.col("c_nationkey") == F.col("n.n_nationkey").outer()).orderBy(F.col("c_acctbal").desc(), "c_custkey").limit(3)
    return n.lateralJoin(inner).select("n_name", "c_custkey", "c_acctbal")


@query("op_rollup", "SELECT lang, source, count(*) AS n, grouping(lang) * 2 + grouping(source) AS level FROM documents GROUP BY ROLLUP (lang, source)")
def op_rollup(t: Tables) -> DataFrame:
    return t.docs.rollup("lang", "source").agg(rows_in().alias("n"), F.grouping_id().alias("level"))


@query("op_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping(o_orderstatus) * 2 + grouping(o_orderpriority) AS level FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def op_cube(t: Tables) -> DataFrame:
    return t.table("orders").cube("o_orderstatus", "o_orderpriority").agg(rows_in().alias("n"), F.grouping_id().alias("level"))


@query("op_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def op_grouping_sets(t: Tables) -> DataFrame:
    return t.docs.groupingSets([["lang"], ["source"], []], "lang", "source").agg(rows_in().alias("n"))


LANGS = ["de", "en", "es", "fr"]


@query("op_pivot", "SELECT source, " + ", ".join(f"count(*) FILTER (WHERE lang = '{x}') AS {x}" for x in LANGS) + " FROM documents GROUP BY source")
def op_pivot(t: Tables) -> DataFrame:
    return t.docs.groupBy("source").pivot("lang", LANGS).agg(rows_in()).na.fill(0)


@query("op_unpivot", "SELECT doc_id, 'quality' AS name, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def op_unpivot(t: Tables) -> DataFrame:
    return t.table("labels").unpivot("doc_id", ["quality", "toxic"], "name", "value")


@query("op_distinct_agg", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag")
def op_distinct_agg(t: Tables) -> DataFrame:
    return t.table("lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


@query("op_approx_distinct")
def op_approx_distinct(t: Tables) -> DataFrame:
    return t.table("lineitem").groupBy("l_returnflag").agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts"))


@query("op_quantile_exact", "SELECT lang, quantile_cont(n_chars, 0.5) AS median, quantile_cont(n_chars, 0.9) AS p90 FROM documents GROUP BY lang")
def op_quantile_exact(t: Tables) -> DataFrame:
    return t.docs.groupBy("lang").agg(F.percentile("n_chars", 0.5).alias("median"), F.percentile("n_chars", 0.9).alias("p90"))


@query("op_rank_family", "SELECT c_custkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 6) + 0.0 AS pr, round(cume_dist() OVER v, 6) + 0.0 AS cd, ntile(4) OVER w AS nt FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey), v AS (PARTITION BY c_nationkey ORDER BY floor(c_acctbal / 100))")
def op_rank_family(t: Tables) -> DataFrame:
    by = Window.partitionBy("c_nationkey")
    w, v = by.orderBy("c_acctbal", "c_custkey"), by.orderBy(F.floor(F.col("c_acctbal") / 100))
    return t.table("customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), r6(F.percent_rank().over(v)).alias("pr"), r6(F.cume_dist().over(v)).alias("cd"), F.ntile(4).over(w).alias("nt"))


@query("op_frames", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 2 PRECEDING), 4) + 0.0 AS moving, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_frames(t: Tables) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t.table("events").select("event_id", (F.round(F.sum("value").over(w.rowsBetween(-2, 0)), 4) + F.lit(0.0)).alias("moving"), F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(whole).alias("second"))


@query("op_topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50")
def op_topk_global(t: Tables) -> DataFrame:
    return t.table("orders").select("o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(50)


@query("op_topk_group", "SELECT l_suppkey, l_orderkey, l_linenumber FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) AS rk FROM lineitem) WHERE rk <= 3")
def op_topk_group(t: Tables) -> DataFrame:
    w = Window.partitionBy("l_suppkey").orderBy(F.col("l_extendedprice").desc(), "l_orderkey", "l_linenumber")
    return t.table("lineitem").withColumn("rk", F.row_number().over(w)).filter("rk <= 3").select("l_suppkey", "l_orderkey", "l_linenumber")


@query("op_setops", "SELECT kind, count(*) AS n FROM (SELECT 'union' AS kind, * FROM (SELECT doc_id FROM documents WHERE doc_id % 2 = 0 UNION SELECT doc_id FROM labels) UNION ALL SELECT 'intersect', * FROM (SELECT doc_id FROM documents WHERE doc_id % 2 = 0 INTERSECT SELECT doc_id FROM labels) UNION ALL SELECT 'except', * FROM (SELECT doc_id FROM documents WHERE doc_id % 2 = 0 EXCEPT SELECT doc_id FROM labels)) GROUP BY kind")
def op_setops(t: Tables) -> DataFrame:
    a, b = t.docs.filter("doc_id % 2 = 0").select("doc_id"), t.table("labels").select("doc_id")
    parts = {"union": a.unionByName(b).distinct(), "intersect": a.intersect(b), "except": a.subtract(b)}
    rows = [p.select(F.lit(k).alias("kind")) for k, p in parts.items()]
    return rows[0].unionAll(rows[1]).unionAll(rows[2]).groupBy("kind").agg(rows_in().alias("n"))


@query("op_sample_hash", f"SELECT doc_id FROM documents WHERE ({H28.format("'smp|' || doc_id")} + 0.5::DOUBLE) / 268435456 < 0.1")
def op_sample_hash(t: Tables) -> DataFrame:
    return t.docs.filter(T.unit(F.concat(F.lit("smp|"), F.col("doc_id").cast("string"))) < 0.1).select("doc_id")


@query("op_sample_strata", "SELECT lang, doc_id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY md5('str|' || doc_id), doc_id) AS rk FROM documents) WHERE rk <= 10")
def op_sample_strata(t: Tables) -> DataFrame:
    w = Window.partitionBy("lang").orderBy(F.md5(F.concat(F.lit("str|"), F.col("doc_id").cast("string"))), "doc_id")
    return t.docs.withColumn("rk", F.row_number().over(w)).filter("rk <= 10").select("lang", "doc_id")


@query("op_corr", "SELECT round(corr(l_quantity, l_extendedprice), 6) + 0.0 AS c, round(covar_samp(l_quantity, l_discount), 6) + 0.0 AS v, round(regr_slope(l_extendedprice, l_quantity), 3) + 0.0 AS s FROM lineitem")
def op_corr(t: Tables) -> DataFrame:
    return t.table("lineitem").agg(r6(F.corr("l_quantity", "l_extendedprice")).alias("c"), r6(F.covar_samp("l_quantity", "l_discount")).alias("v"), (F.round(F.regr_slope("l_extendedprice", "l_quantity"), 3) + F.lit(0.0)).alias("s"))


@query("op_array_fn", "SELECT vec_id, round(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[]), 6) + 0.0 AS norm2, round(list_max(embedding)::DOUBLE, 6) + 0.0 AS top FROM embeddings")
def op_array_fn(t: Tables) -> DataFrame:
    return t.table("embeddings").select("vec_id", r6(proxy.dot(F.col("embedding"), F.col("embedding"))).alias("norm2"), r6(F.array_max("embedding").cast("double")).alias("top"))


@query("op_map_fn", "SELECT lang, source, count(*) AS n FROM documents GROUP BY 1, 2 HAVING count(*) >= 5")
def op_map_fn(t: Tables) -> DataFrame:
    counts = t.docs.groupBy("lang", "source").agg(rows_in().alias("n"))
    maps = counts.groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    return maps.select("lang", F.explode(F.map_filter("m", lambda k, v: v >= 5)).alias("source", "n"))


@query("op_date_fn", "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n, sum(date_diff('day', o_orderdate::DATE, (o_orderdate + INTERVAL 1 MONTH)::DATE))::BIGINT AS days FROM orders GROUP BY 1")
def op_date_fn(t: Tables) -> DataFrame:
    d = F.col("o_orderdate").cast("date")
    return t.table("orders").groupBy(F.date_format(d, "yyyy-MM").alias("month")).agg(rows_in().alias("n"), F.sum(F.datediff(F.add_months(d, 1), d)).alias("days"))


@query("op_string_fn", "SELECT p_partkey, lower(p_name) AS name, levenshtein(p_name, p_type) AS distance, substr(p_brand, 1, 3) AS head FROM part")
def op_string_fn(t: Tables) -> DataFrame:
    return t.table("part").select("p_partkey", F.lower("p_name").alias("name"), F.levenshtein("p_name", "p_type").cast("long").alias("distance"), F.substring("p_brand", 1, 3).alias("head"))


@query("op_tumbling", "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) + 0.0 AS total FROM events GROUP BY 1, 2")
def op_tumbling(t: Tables) -> DataFrame:
    return t.table("events").groupBy(F.window("ts", "1 day"), "event_type").agg(rows_in().alias("n"), (F.round(F.sum("value"), 4) + F.lit(0.0)).alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")


@query("op_sliding", "SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR * k FOR k IN [0, 1, 2, 3]]) AS start FROM events) GROUP BY start")
def op_sliding(t: Tables) -> DataFrame:
    return t.table("events").groupBy(F.window("ts", "1 day", "6 hours")).agg(rows_in().alias("n")).select(F.col("window.start").alias("start"), "n")


@query("op_session", "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def op_session(t: Tables) -> DataFrame:
    return t.table("events").groupBy(F.session_window("ts", "2 hours"), "user_id").agg(rows_in().alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


@query("op_udtf_ngrams", with_tables("SELECT item_id, count(*) AS n FROM (SELECT item_id, unnest(range(1, len(l))) AS i FROM (SELECT item_id, list_filter(regexp_split_to_array(lower(text), '[^\\p{L}]+'), lambda x: x <> '') AS l FROM benchmark)) GROUP BY item_id"))
def op_udtf_ngrams(t: Tables) -> DataFrame:
    rows = t.table("benchmark").select("item_id", F.array_join(T.words("text"), " ").alias("s"))
    grams = rows.lateralJoin(udx.Ngrams(F.col("s").outer(), F.lit(2)))
    return grams.groupBy("item_id").agg(rows_in().alias("n"))


@query("op_udaf_logsumexp", "SELECT event_type, round(ln(sum(exp(value / 100))), 6) + 0.0 AS lse FROM events GROUP BY event_type")
def op_udaf_logsumexp(t: Tables) -> DataFrame:
    """Log-sum-exp from built-in aggregates, safe for large values: the maximum first."""
    e = t.table("events").withColumn("v", F.col("value") / 100)
    top = e.groupBy("event_type").agg(F.max("v").alias("top"))
    return e.join(F.broadcast(top), "event_type").groupBy("event_type", "top").agg(F.sum(F.exp(F.col("v") - F.col("top"))).alias("s")).select("event_type", r6(F.col("top") + F.log("s")).alias("lse"))


@query("op_pandas_udf_softmax", "SELECT event_type, round(sum(exp(value / 100) * value) / sum(exp(value / 100)), 4) + 0.0 AS soft_mean FROM events GROUP BY event_type")
def op_pandas_udf_softmax(t: Tables) -> DataFrame:
    return t.table("events").groupBy("event_type").agg((F.round(udx.soft_mean(F.col("value"), F.col("value") / 100), 4) + F.lit(0.0)).alias("soft_mean"))


@query("op_cogroup", "SELECT lang, d, l FROM (SELECT lang, count(*) AS d FROM documents GROUP BY lang) JOIN (SELECT lang, count(*) AS l FROM documents JOIN labels USING (doc_id) GROUP BY lang) USING (lang)")
def op_cogroup(t: Tables) -> DataFrame:
    counts = t.docs.groupBy("lang", "source").agg(rows_in().alias("n"))
    labelled = t.table("documents").join(t.table("labels"), "doc_id").groupBy("lang", "source").agg(rows_in().alias("n"))

    def both(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"lang": [a["lang"].iloc[0]], "d": [int(a["n"].sum())], "l": [int(b["n"].sum())]})

    return counts.groupBy("lang").cogroup(labelled.groupBy("lang")).applyInPandas(both, "lang string, d long, l long")


@query("op_stream_window", "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def op_stream_window(t: Tables) -> DataFrame:
    return runs.daily_counts(t.spark, f"{t.dir}/events.parquet")


@query("op_stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def op_stream_dedup(t: Tables) -> DataFrame:
    return runs.deduplicated(t.spark, f"{t.dir}/events.parquet").agg(rows_in().alias("n"))


@query("op_stream_join", "SELECT event_type, count(*) AS n FROM events JOIN (SELECT DISTINCT c_custkey FROM customer) ON user_id = c_custkey GROUP BY event_type")
def op_stream_join(t: Tables) -> DataFrame:
    users = t.table("customer").select(F.col("c_custkey").alias("user_id")).distinct()
    return runs.joined(t.spark, f"{t.dir}/events.parquet", users).groupBy("event_type").agg(rows_in().alias("n"))


@query("op_stream_state")
def op_stream_state(t: Tables) -> DataFrame:
    """Buffers formed by a stateful operator: (step, slot, event_id) of events in arrival order, per key."""
    return runs.buffered(t.spark, f"{t.dir}/events.parquet", 64)

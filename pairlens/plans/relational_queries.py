"""Relational operators that users need around the methods, each on the given tables with its SQL twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pairlens.session import load

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
O: dict[str, str] = {}
c = F.col


def add(key: str, sql: str | None, build) -> None:
    """build(t) gets a function that loads a table."""
    Q[key] = lambda s, d: build(lambda name: load(s, d, name))
    if sql:
        O[key] = sql


def r2(x):
    return F.round(x, 2)


add("scan_documents", "SELECT doc_id, lang FROM documents", lambda t: t("documents").select("doc_id", "lang"))
add("doc_lines", "SELECT doc_id, unnest(range(len(z))) AS pos, unnest(z) AS line FROM (SELECT doc_id, string_split(text, chr(10)) AS z FROM documents)", lambda t: t("documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("pos", "line")))
add("op_project", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 6) AS net, CASE WHEN l_quantity > 25 THEN 'big' ELSE 'small' END AS size, coalesce(l_returnflag, '-') AS flag FROM lineitem", lambda t: t("lineitem").select("l_orderkey", "l_linenumber", F.round(c("l_extendedprice") * (1 - c("l_discount")), 6).alias("net"), F.when(c("l_quantity") > 25, "big").otherwise("small").alias("size"), F.coalesce("l_returnflag", F.lit("-")).alias("flag")))
add("op_filter", "SELECT o_orderkey FROM orders WHERE (o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 200000) OR (o_orderpriority LIKE '1-%' AND NOT o_orderstatus IS NOT DISTINCT FROM 'P')", lambda t: t("orders").where((c("o_orderstatus").isin("F", "O") & c("o_totalprice").between(1000, 200000)) | (c("o_orderpriority").like("1-%") & ~c("o_orderstatus").eqNullSafe("P"))).select("o_orderkey"))
add("join_inner", "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1", lambda t: t("orders").join(t("lineitem"), c("o_orderkey") == c("l_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), r2(F.sum("l_quantity")).alias("qty")))
add("join_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1", lambda t: t("customer").join(F.broadcast(t("nation").join(F.broadcast(t("region")), c("n_regionkey") == c("r_regionkey"))), c("c_nationkey") == c("n_nationkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n")))
add("join_left_unscored", "SELECT doc_id, quality, quality IS NULL AS unscored FROM documents LEFT JOIN labels USING (doc_id)", lambda t: t("documents").join(t("labels"), "doc_id", "left").select("doc_id", "quality", c("quality").isNull().alias("unscored")))
add("join_full", "SELECT coalesce(c_custkey, o_custkey) AS k, count(o_orderkey) AS n FROM customer FULL JOIN orders ON c_custkey = o_custkey GROUP BY 1", lambda t: t("customer").join(t("orders"), c("c_custkey") == c("o_custkey"), "full").groupBy(F.coalesce("c_custkey", "o_custkey").alias("k")).agg(F.count("o_orderkey").alias("n")))
add("join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)", lambda t: t("documents").select("doc_id").join(t("labels").where("toxic = 1"), "doc_id", "left_semi"))
add("join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)", lambda t: t("documents").select("doc_id").join(t("labels"), "doc_id", "left_anti"))
add("join_scalar", "SELECT doc_id FROM documents, (SELECT avg(n_chars) AS m FROM documents) WHERE n_chars > 2 * m", lambda t: t("documents").crossJoin(F.broadcast(t("documents").agg(F.avg("n_chars").alias("m")))).where("n_chars > 2 * m").select("doc_id"))
add("join_contains", "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)", lambda t: t("documents").join(t("benchmark").select("item_id", c("text").alias("passage")), F.contains("text", "passage")).select("doc_id", "item_id"))
# pairs of similar length: bins make the band an equality, each pair is met in one bin only
add("join_length_band", "SELECT a.doc_id AS a, b.doc_id AS b FROM documents a JOIN documents b ON a.doc_id < b.doc_id AND abs(a.n_chars - b.n_chars) <= 5", lambda t: (lambda d: d.select(c("doc_id").alias("a"), c("n_chars").alias("x"), F.floor(c("n_chars") / 6).alias("bin")).join(d.select(c("doc_id").alias("b"), c("n_chars").alias("y"), F.explode(F.sequence(F.floor(c("n_chars") / 6) - 1, F.floor(c("n_chars") / 6) + 1)).alias("bin")), "bin").where("a < b and abs(x - y) <= 5").select("a", "b"))(t("documents")))
add("join_interval", "SELECT e.event_id, w.hour FROM events e JOIN (SELECT DISTINCT date_trunc('hour', ts) AS hour FROM events WHERE event_type = 'purchase') w ON e.ts >= w.hour AND e.ts < w.hour + INTERVAL 1 HOUR WHERE e.event_type = 'error'", lambda t: t("events").where("event_type = 'error'").withColumn("h", F.date_trunc("hour", "ts")).join(t("events").where("event_type = 'purchase'").select(F.date_trunc("hour", "ts").alias("hour")).distinct(), (c("h") == c("hour")) & (c("ts") >= c("hour")) & (c("ts") < c("hour") + F.expr("INTERVAL 1 HOUR"))).select("event_id", "hour"))
add("join_asof", "SELECT event_id, before_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before_id FROM events) WHERE event_type = 'error'", lambda t: t("events").withColumn("before_id", F.last(F.when(c("event_type") == "purchase", c("event_id")), ignorenulls=True).over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1))).where("event_type = 'error'").select("event_id", "before_id"))
add("join_self_dups", "SELECT a.doc_id AS first_id, b.doc_id AS doc_id FROM (SELECT md5(text) AS h, min(doc_id) AS doc_id FROM documents GROUP BY 1) a JOIN documents b ON a.h = md5(b.text) AND a.doc_id < b.doc_id", lambda t: (lambda d: d.groupBy("h").agg(F.min("doc_id").alias("first_id")).join(d, "h").where("first_id < doc_id").select("first_id", "doc_id"))(t("documents").select("doc_id", F.md5("text").alias("h"))))
add("join_lateral", "SELECT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY length(line) DESC, line) <= 2", lambda t: t("documents").select("doc_id", F.explode(F.slice(F.array_sort(F.transform(F.split("text", "\n"), lambda x: F.struct((-F.length(x)).alias("n"), x.alias("line")))), 1, 2)).alias("z")).select("doc_id", "z.line"))
add("subquery_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)", lambda t: t("customer").join(t("orders").where("o_totalprice > 300000").select(c("o_custkey").alias("c_custkey")), "c_custkey", "left_semi").select("c_custkey"))
add("subquery_scalar", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM orders i WHERE i.o_orderpriority = o.o_orderpriority)", lambda t: t("orders").join(t("orders").groupBy("o_orderpriority").agg((1.5 * F.avg("o_totalprice")).alias("m")), "o_orderpriority").where("o_totalprice > m").select("o_orderkey"))
add("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc FROM lineitem GROUP BY 1, 2", lambda t: t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), r2(F.sum("l_quantity")).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc")))
add("agg_distinct", "SELECT source, count(DISTINCT lang) AS langs, count(DISTINCT md5(text)) AS texts FROM documents GROUP BY 1", lambda t: t("documents").groupBy("source").agg(F.count_distinct("lang").alias("langs"), F.count_distinct(F.md5("text")).alias("texts")))
for _k, _f in (("rollup", "ROLLUP (lang, source)"), ("cube", "CUBE (lang, source)"), ("grouping_sets", "GROUPING SETS ((lang), (source), ())")):
    _build = {"rollup": lambda t: t("documents").rollup("lang", "source"), "cube": lambda t: t("documents").cube("lang", "source"), "grouping_sets": lambda t: t("documents").groupingSets([[c("lang")], [c("source")], []], "lang", "source")}[_k]
    add(f"agg_{_k}", f"SELECT lang, source, grouping(lang) * 2 + grouping(source) AS gid, count(*) AS n FROM documents GROUP BY {_f}", (lambda b: lambda t: b(t).agg(F.grouping_id().cast("bigint").alias("gid"), F.count(F.lit(1)).alias("n")))(_build))
add("agg_pivot", "SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'de') AS de FROM documents GROUP BY 1", lambda t: t("documents").groupBy("source").pivot("lang", ["en", "de"]).agg(F.count(F.lit(1))).na.fill(0))
add("agg_unpivot", "SELECT doc_id, 'quality' AS name, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels", lambda t: t("labels").unpivot("doc_id", ["quality", "toxic"], "name", "value"))
add("agg_percentiles", "SELECT lang, quantile_cont(n_chars, 0.25) AS q1, median(n_chars) AS q2, quantile_cont(n_chars, 0.9) AS q9 FROM documents GROUP BY 1", lambda t: t("documents").groupBy("lang").agg(*(F.percentile("n_chars", F.lit(p)).alias(a) for p, a in ((0.25, "q1"), (0.5, "q2"), (0.9, "q9")))))
add("agg_moments", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_discount), 6) AS v, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem GROUP BY 1", lambda t: t("lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_discount"), 6).alias("v"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r")))
add("agg_approx", None, lambda t: t("lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_extendedprice", [0.5, 0.9], 10000).alias("prices"), F.hll_sketch_estimate(F.hll_sketch_agg("l_suppkey")).alias("suppliers")))
add("agg_conditional", "SELECT lang, count(*) FILTER (n_chars > 1000) AS long_, bool_and(n_chars > 0) AS any_text FROM documents GROUP BY 1", lambda t: t("documents").groupBy("lang").agg(F.count_if(c("n_chars") > 1000).alias("long_"), F.bool_and(c("n_chars") > 0).alias("any_text")))
add("agg_collect", "SELECT conv_id, string_agg(role, '>' ORDER BY turn) AS roles, max_by(role, turn) AS last_role FROM conversations GROUP BY 1", lambda t: t("conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ">").alias("roles"), F.max_by("role", "turn").alias("last_role")))
add("agg_histogram", "SELECT floor(n_chars / 500)::BIGINT AS bin, count(*) AS n FROM documents GROUP BY 1", lambda t: t("documents").groupBy(F.floor(c("n_chars") / 500).alias("bin")).agg(F.count(F.lit(1)).alias("n")))
add("agg_having", "SELECT text, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) > 1", lambda t: t("documents").groupBy("text").agg(F.count(F.lit(1)).alias("n")).where("n > 1"))
_w = "OVER (PARTITION BY source ORDER BY n_chars, doc_id)"


def _rank(t):
    w = W.partitionBy("source").orderBy("n_chars", "doc_id")
    return t("documents").select("doc_id", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


add("win_rank", f"SELECT doc_id, row_number() {_w} AS rn, rank() {_w} AS rk, dense_rank() {_w} AS dr, ntile(4) {_w} AS nt, round(percent_rank() {_w}, 6) AS pr, round(cume_dist() {_w}, 6) AS cd FROM documents", _rank)
add("win_lag", "SELECT conv_id, turn, lag(role) OVER w AS before, lead(role, 1, 'end') OVER w AS after, first_value(role) OVER w AS opener FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)", lambda t: (lambda w: t("conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role", 1, "end").over(w).alias("after"), F.first("role").over(w).alias("opener")))(W.partitionBy("conv_id").orderBy("turn")))
add("win_rows", "SELECT doc_id, round(avg(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS m FROM documents", lambda t: t("documents").select("doc_id", F.round(F.avg("n_chars").over(W.partitionBy("source").orderBy("doc_id").rowsBetween(-4, 0)), 6).alias("m")))
add("win_range", "SELECT doc_id, count(*) OVER (PARTITION BY source ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS n FROM documents", lambda t: t("documents").select("doc_id", F.count(F.lit(1)).over(W.partitionBy("source").orderBy("n_chars").rangeBetween(-100, 100)).alias("n")))
add("win_share", "SELECT doc_id, round(n_chars / sum(n_chars) OVER (PARTITION BY lang), 9) AS share, sum(n_chars) OVER (PARTITION BY lang ORDER BY doc_id) AS running FROM documents", lambda t: t("documents").select("doc_id", F.round(c("n_chars") / F.sum("n_chars").over(W.partitionBy("lang")), 9).alias("share"), F.sum("n_chars").over(W.partitionBy("lang").orderBy("doc_id")).alias("running")))
add("topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 3", lambda t: t("orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(3).limit(10))
add("topk_per_group", "SELECT o_orderpriority, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) <= 3", lambda t: t("orders").withColumn("rn", F.row_number().over(W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("rn <= 3").select("o_orderpriority", "o_orderkey"))
add("sort_total", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id", lambda t: t("documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id"))
add("set_union", "SELECT lang FROM documents UNION SELECT 'xx'", lambda t: t("documents").select("lang").unionByName(t("documents").limit(1).select(F.lit("xx").alias("lang"))).distinct())
add("set_intersect", "SELECT doc_id FROM documents INTERSECT ALL SELECT doc_id FROM labels", lambda t: t("documents").select("doc_id").intersectAll(t("labels").select("doc_id")))
add("set_except", "SELECT doc_id FROM documents EXCEPT ALL SELECT doc_id FROM labels", lambda t: t("documents").select("doc_id").exceptAll(t("labels").select("doc_id")))
add("fn_string", "SELECT doc_id, lower(left(text, 5)) AS u, replace(substr(text, 1, 20), 'e', '3') AS r, instr(text, 'a') AS i, md5(text) AS m, base64(encode(left(text, 6))) AS b, translate(left(text, 10), 'abc', 'xyz') AS t FROM documents", lambda t: t("documents").select("doc_id", F.lower(F.left("text", F.lit(5))).alias("u"), F.replace(F.substring("text", 1, 20), F.lit("e"), F.lit("3")).alias("r"), F.instr("text", "a").alias("i"), F.md5("text").alias("m"), F.base64(F.encode(F.left("text", F.lit(6)), "UTF-8")).alias("b"), F.translate(F.left("text", F.lit(10)), "abc", "xyz").alias("t")))
add("fn_math", "SELECT l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) AS s, floor(l_extendedprice)::BIGINT AS f, round(ln(l_quantity), 6) AS l, greatest(l_discount, l_tax) AS g, round(l_extendedprice / nullif(l_tax, 0), 4) AS q FROM lineitem", lambda t: t("lineitem").select("l_orderkey", "l_linenumber", F.round(F.sqrt("l_quantity"), 6).alias("s"), F.floor("l_extendedprice").alias("f"), F.round(F.ln("l_quantity"), 6).alias("l"), F.greatest("l_discount", "l_tax").alias("g"), F.round(F.try_divide("l_extendedprice", "l_tax"), 4).alias("q")))
add("fn_date", "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, date_trunc('month', o_orderdate)::TIMESTAMP AS first_day, date_diff('day', o_orderdate, TIMESTAMP '2000-01-01')::INT AS days FROM orders", lambda t: t("orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_trunc("month", "o_orderdate").alias("first_day"), F.datediff(F.lit("2000-01-01").cast("date"), "o_orderdate").alias("days")))
add("fn_array", "SELECT doc_id, len(z) AS n, len(list_distinct(z)) AS d, len(list_filter(z, lambda x: length(x) > 3)) AS f, list_contains(z, 'the') AS has_the FROM (SELECT doc_id, string_split(text, ' ') AS z FROM documents)", lambda t: t("documents").select("doc_id", F.split("text", " ").alias("z")).select("doc_id", F.size("z").alias("n"), F.size(F.array_distinct("z")).alias("d"), F.size(F.filter("z", lambda x: F.length(x) > 3)).alias("f"), F.array_contains("z", "the").alias("has_the")))
add("fn_map", "SELECT conv_id, count(*) FILTER (role = 'user') AS users, count(*) AS n FROM conversations GROUP BY 1", lambda t: t("conversations").groupBy("conv_id", "role").agg(F.count(F.lit(1)).alias("n")).groupBy("conv_id").agg(F.map_from_entries(F.collect_list(F.struct("role", "n"))).alias("m")).select("conv_id", F.coalesce(F.element_at("m", "user"), F.lit(0)).alias("users"), F.aggregate(F.map_values("m"), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("n")))
add("fn_json", "SELECT event_id, props->>'$.page' AS page FROM events", lambda t: t("events").select("event_id", F.get_json_object("props", "$.page").alias("page")))
add("fn_cosine", "SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 4) AS norm FROM embeddings", lambda t: t("embeddings").select("vec_id", F.round(F.aggregate(F.zip_with("embedding", "embedding", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda a, x: a + x), 4).alias("norm")))
add("fn_struct", "SELECT doc_id, lang || ':' || source AS tag FROM documents", lambda t: t("documents").select("doc_id", F.struct(c("lang").alias("l"), c("source").alias("s")).alias("x")).select("doc_id", F.concat_ws(":", "x.l", "x.s").alias("tag")))
add("window_tumbling", "SELECT date_trunc('hour', ts)::TIMESTAMP AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2", lambda t: t("events").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(c("w.start").alias("start"), "event_type", "n"))

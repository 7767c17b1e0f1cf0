"""Further queries: relational operators, functions, generator, SQL surface, streams and experiments."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import catalog_sql as q
from . import experiments
from .functions import minhash, sqlapi, strsim
from .operators import combo, datagen, ranking, scoring
from .operators.index import Queries, TokenIndex, sample_queries
from .plans import planner
from .sources import tables
from .streaming import streams

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_sql: dict[str, str] = {}


def add(name: str, run: Callable[[Callable[[str], DataFrame]], DataFrame], sql: str | None = None) -> None:
    """run gets a function from table names to tables."""
    _queries[name] = lambda spark, sf: run(lambda table: tables.load(spark, sf, table))
    if sql:
        _sql[name] = sql


def add_raw(name: str, run: Query, sql: str | None = None) -> None:
    _queries[name] = run
    if sql:
        _sql[name] = sql


# ---- relational operators -------------------------------------------------------------------------------------------

add("op_project", lambda t: t("part").select(F.col("p_partkey").cast("int").alias("id"), F.concat_ws(" ", "p_name", "p_type").alias("s"), F.round(F.col("p_retailprice") * 1.1, 2).alias("gross")),
    "SELECT p_partkey::INT AS id, p_name || ' ' || p_type AS s, round(p_retailprice * 1.1::DOUBLE, 2) AS gross FROM part")
add("op_filter", lambda t: t("part").where(F.col("p_size").between(5, 30) & F.col("p_type").isin("SMALL", "LARGE") & (F.col("p_name").like("%e%") | F.col("p_name").rlike("^h")) & F.col("p_brand").isNotNull()).select("p_partkey", "p_name", "p_size"),
    "SELECT p_partkey, p_name, p_size FROM part WHERE p_size BETWEEN 5 AND 30 AND p_type IN ('SMALL', 'LARGE') AND (p_name LIKE '%e%' OR regexp_matches(p_name, '^h')) AND p_brand IS NOT NULL")
# nation has 25 rows by definition
add("op_join_broadcast", lambda t: t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance")),
    "SELECT n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
add("op_join_sortmerge", lambda t: t("lineitem").hint("merge").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n")),
    "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority")
add("op_join_shuffle_hash", lambda t: t("lineitem").join(t("orders").hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n")),
    "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus")
add("op_join_theta", lambda t: t("nation").alias("a").join(t("nation").alias("b"), (F.levenshtein("a.n_name", "b.n_name") <= 3) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b")),
    "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON levenshtein(a.n_name, b.n_name) <= 3 AND a.n_nationkey < b.n_nationkey")
for _how, _join in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    add(f"op_join_{_how}", lambda t, how=_how: t("customer").join(t("orders"), F.expr("c_custkey = o_custkey AND c_mktsegment = 'BUILDING' AND o_orderstatus = 'P'"), how).groupBy(F.col("c_custkey").isNull().alias("no_customer"), F.col("o_orderkey").isNull().alias("no_order")).agg(F.count(F.lit(1)).alias("n")),
        f"SELECT c_custkey IS NULL AS no_customer, o_orderkey IS NULL AS no_order, count(*) AS n FROM customer {_join} JOIN orders ON c_custkey = o_custkey AND c_mktsegment = 'BUILDING' AND o_orderstatus = 'P' GROUP BY 1, 2")
add("op_semi", lambda t: t("orders").join(t("lineitem").where("l_returnflag = 'R'"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey"),
    "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R')")
add("op_anti", lambda t: t("customer").join(t("orders").where("o_orderstatus = 'P'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"),
    "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P')")
add("op_cross", lambda t: t("region").crossJoin(t("nation")).select("r_name", "n_name"), "SELECT r_name, n_name FROM region CROSS JOIN nation")
_LEN = 2


def _range_join(t) -> DataFrame:
    """Strings whose lengths differ by at most 2: equality of length buckets, then the exact range."""
    a = t("nation").select(F.col("n_name").alias("a"), F.length("n_name").alias("la")).withColumn("bucket", F.explode(F.sequence(F.floor((F.col("la") - _LEN) / 4), F.floor((F.col("la") + _LEN) / 4))))
    b = t("part").select(F.col("p_name").alias("b")).distinct().withColumn("lb", F.length("b")).withColumn("bucket", F.floor(F.col("lb") / 4))
    return a.join(b, (a["bucket"] == b["bucket"]) & (F.abs(F.col("la") - F.col("lb")) <= _LEN)).select("a", "b")


add("op_join_range", _range_join, "SELECT n_name AS a, b FROM nation JOIN (SELECT DISTINCT p_name AS b FROM part) ON abs(length(n_name) - length(b)) <= 2")


def _asof(t) -> DataFrame:
    """Each purchase-like event with the user's latest earlier 'view': one sorted pass per user instead of a range join."""
    e = t("events").select("user_id", "ts", "event_id", "event_type")
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = e.withColumn("last_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before))
    return seen.where("event_type <> 'view'").select("event_id", "last_view")


add("op_asof", _asof, """
SELECT event_id, last_view FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS)
  OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_view FROM events) WHERE event_type <> 'view'""")
add("op_agg", lambda t: t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_extendedprice").alias("low"), F.max("l_extendedprice").alias("high")).where("n > 100"),
    "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, min(l_extendedprice) AS low, max(l_extendedprice) AS high FROM lineitem GROUP BY ALL HAVING count(*) > 100")
add("op_distinct", lambda t: t("lineitem").select("l_returnflag", "l_linestatus").distinct(), "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")
add("op_count_distinct", lambda t: t("lineitem").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")), "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")
add("op_approx_distinct", lambda t: t("lineitem").agg((F.abs(F.approx_count_distinct("l_partkey", 0.02) / F.count_distinct("l_partkey") - 1) <= 0.1).alias("near"), F.count_distinct("l_partkey").alias("parts")),
    "SELECT true AS near, count(DISTINCT l_partkey) AS parts FROM lineitem")
_Q = "round(sum(l_quantity), 2) AS qty FROM lineitem"
add("op_rollup", lambda t: t("lineitem").rollup("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty")), f"SELECT l_returnflag, l_linestatus, {_Q} GROUP BY ROLLUP (l_returnflag, l_linestatus)")
add("op_cube", lambda t: t("lineitem").cube("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty")), f"SELECT l_returnflag, l_linestatus, {_Q} GROUP BY CUBE (l_returnflag, l_linestatus)")
add("op_grouping_sets", lambda t: t("lineitem").groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty")), f"SELECT l_returnflag, l_linestatus, {_Q} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")
add("op_argmax", lambda t: t("part").groupBy("p_type").agg(F.max_by("p_name", F.struct("p_retailprice", "p_partkey")).alias("dearest")),
    "SELECT p_type, p_name AS dearest FROM (SELECT p_type, p_name, row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey DESC) AS r FROM part) WHERE r = 1")
add("op_stddev", lambda t: t("part").groupBy("p_type").agg(F.round(F.stddev_samp("p_retailprice"), 4).alias("sd"), F.round(F.percentile("p_retailprice", 0.5), 4).alias("median")),
    "SELECT p_type, round(stddev_samp(p_retailprice), 4) AS sd, round(quantile_cont(p_retailprice, 0.5), 4) AS median FROM part GROUP BY p_type")
add("op_pivot", lambda t: t("customer").groupBy("c_nationkey").pivot("c_mktsegment", ["BUILDING", "MACHINERY"]).agg(F.count(F.lit(1))).select("c_nationkey", F.coalesce("BUILDING", F.lit(0)).alias("building"), F.coalesce("MACHINERY", F.lit(0)).alias("machinery")),
    "SELECT c_nationkey, count(*) FILTER (c_mktsegment = 'BUILDING') AS building, count(*) FILTER (c_mktsegment = 'MACHINERY') AS machinery FROM customer GROUP BY c_nationkey")


def _ranks(t) -> DataFrame:
    w = Window.partitionBy("p_type").orderBy("p_size", "p_partkey")
    v = Window.partitionBy("p_type").orderBy("p_size")
    return t("part").select("p_partkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(v), 6).alias("pr"))


add("op_win_rank", _ranks, """
SELECT p_partkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER v, 6) AS pr
FROM part WINDOW w AS (PARTITION BY p_type ORDER BY p_size, p_partkey), v AS (PARTITION BY p_type ORDER BY p_size)""")


def _frames(t) -> DataFrame:
    w = Window.partitionBy("c_nationkey").orderBy("c_custkey")
    return t("customer").select("c_custkey", F.lag("c_acctbal").over(w).alias("before"), F.lead("c_acctbal").over(w).alias("after"), F.first("c_acctbal").over(w).alias("head"),
        F.round(F.sum("c_acctbal").over(w.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("running"), F.round(F.avg("c_acctbal").over(w.rowsBetween(-2, 2)), 4).alias("moving"), F.count(F.lit(1)).over(w.rangeBetween(-100, 0)).alias("near"))


add("op_win_frame", _frames, """
SELECT c_custkey, lag(c_acctbal) OVER w AS before, lead(c_acctbal) OVER w AS after, first_value(c_acctbal) OVER w AS head,
  round(sum(c_acctbal) OVER (PARTITION BY c_nationkey ORDER BY c_custkey ROWS UNBOUNDED PRECEDING), 2) AS running,
  round(avg(c_acctbal) OVER (PARTITION BY c_nationkey ORDER BY c_custkey ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 4) AS moving,
  count(*) OVER (PARTITION BY c_nationkey ORDER BY c_custkey RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS near
FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_custkey)""")
add("op_topk", lambda t: t("part").orderBy(F.desc("p_retailprice"), "p_partkey").offset(5).limit(10).select("p_partkey", "p_retailprice"), "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 10 OFFSET 5")
add("op_topk_group", lambda t: t("part").withColumn("r", F.row_number().over(Window.partitionBy("p_type").orderBy(F.desc("p_retailprice"), "p_partkey"))).where("r <= 3").select("p_type", "p_partkey", "r"),
    "SELECT p_type, p_partkey, r FROM (SELECT p_type, p_partkey, row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
_A, _B = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"
_a = lambda t: t("customer").select(F.col("c_nationkey").alias("k"))
_b = lambda t: t("supplier").select(F.col("s_nationkey").alias("k"))
for _name, _f, _op in (("union", lambda x, y: x.union(y).distinct(), "UNION"), ("union_all", lambda x, y: x.unionByName(y), "UNION ALL"), ("intersect", lambda x, y: x.intersect(y), "INTERSECT"), ("intersect_all", lambda x, y: x.intersectAll(y), "INTERSECT ALL"), ("except", lambda x, y: x.subtract(y), "EXCEPT"), ("except_all", lambda x, y: x.exceptAll(y), "EXCEPT ALL")):
    add(f"op_{_name}", lambda t, f=_f: f(_a(t), _b(t)), f"{_A} {_op} {_B}")
for _name, _f, _op in (("except_keys", lambda x, y: x.subtract(y), "EXCEPT"), ("intersect_keys", lambda x, y: x.intersect(y), "INTERSECT")):
    add(f"op_{_name}", lambda t, f=_f: f(t("customer").select(F.col("c_custkey").alias("k")), t("supplier").select(F.col("s_suppkey").alias("k"))), f"SELECT c_custkey AS k FROM customer {_op} SELECT s_suppkey AS k FROM supplier")


def _subquery(spark: SparkSession, sf: str) -> DataFrame:
    for name in ("orders", "customer", "lineitem"):
        tables.load(spark, sf, name).createOrReplaceTempView(f"sub_{name}")
    return spark.sql("""
WITH big AS (SELECT o_custkey, sum(o_totalprice) AS spent FROM sub_orders GROUP BY o_custkey)
SELECT c_custkey, round(spent, 2) AS spent FROM sub_customer c JOIN big ON c_custkey = o_custkey
WHERE spent > (SELECT avg(spent) FROM big) AND EXISTS (SELECT 1 FROM sub_orders o WHERE o.o_custkey = c.c_custkey AND o_orderstatus = 'F')
  AND c_custkey IN (SELECT o_custkey FROM sub_orders WHERE o_totalprice > 1000)""")


add_raw("op_subquery", _subquery, """
WITH big AS (SELECT o_custkey, sum(o_totalprice) AS spent FROM orders GROUP BY o_custkey)
SELECT c_custkey, round(spent, 2) AS spent FROM customer c JOIN big ON c_custkey = o_custkey
WHERE spent > (SELECT avg(spent) FROM big) AND EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o_orderstatus = 'F')
  AND c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 1000)""")
add_raw("op_sample", lambda s, d: sample_queries(tables.part_desc(s, d), 25), q.SAMPLED)
add("op_explode", lambda t: t("part").select("p_partkey", F.posexplode(F.split("p_name", "")).alias("pos", "c")).groupBy("c").agg(F.count(F.lit(1)).alias("n"), F.max("pos").alias("last")),
    "SELECT c, count(*) AS n, max(pos)::INT AS last FROM (SELECT unnest(string_split(p_name, '')) AS c, unnest(range(length(p_name))) AS pos FROM part) GROUP BY c")

# ---- functions --------------------------------------------------------------------------------------------------------

add("fn_string", lambda t: t("customer").select("c_custkey", F.lower("c_name").alias("lo"), F.upper("c_mktsegment").alias("up"), F.length("c_name").cast("long").alias("n"), F.substring("c_name", 2, 4).alias("sub"), F.lpad(F.col("c_custkey").cast("string"), 6, "0").alias("pad"), F.reverse("c_name").alias("rev"), F.instr("c_name", "#").cast("long").alias("at"), F.translate("c_name", "aeiou", "AEIOU").alias("tr"), F.regexp_extract("c_name", r"(\d+)", 1).alias("num"), F.repeat(F.lit("ab"), 2).alias("rep")),
    r"SELECT c_custkey, lower(c_name) AS lo, upper(c_mktsegment) AS up, length(c_name) AS n, substr(c_name, 2, 4) AS sub, lpad(c_custkey::VARCHAR, 6, '0') AS pad, reverse(c_name) AS rev, instr(c_name, '#') AS at, translate(c_name, 'aeiou', 'AEIOU') AS tr, regexp_extract(c_name, '(\d+)', 1) AS num, repeat('ab', 2) AS rep FROM customer")
add("fn_levenshtein", lambda t: t("part").select("p_name").distinct().crossJoin(t("region").select("r_name")).select("p_name", "r_name", F.levenshtein("p_name", F.lower("r_name")).cast("long").alias("d"), F.round(strsim.edit_similarity(F.col("p_name"), F.lower("r_name")), 6).alias("sim")),
    "SELECT p_name, r_name, levenshtein(p_name, lower(r_name)) AS d, round(1 - levenshtein(p_name, lower(r_name))::DOUBLE / greatest(length(p_name), length(r_name)), 6) AS sim FROM (SELECT DISTINCT p_name FROM part) CROSS JOIN region")
add("fn_math", lambda t: t("part").select("p_partkey", F.round(F.log("p_retailprice"), 6).alias("ln"), F.round(F.exp(F.col("p_size") / 10.0), 6).alias("ex"), F.round(F.pow(F.col("p_size").cast("double"), 1.5), 6).alias("pw"), F.round(F.sqrt("p_retailprice"), 6).alias("sq"), F.floor("p_retailprice").cast("long").alias("fl"), F.greatest(F.col("p_size"), F.lit(10)).alias("gr"), F.pmod(F.col("p_partkey"), F.lit(7)).alias("pm"), F.abs(F.col("p_size") - 25).alias("ab")),
    "SELECT p_partkey, round(ln(p_retailprice), 6) AS ln, round(exp(p_size / 10.0::DOUBLE), 6) AS ex, round(pow(p_size::DOUBLE, 1.5), 6) AS pw, round(sqrt(p_retailprice), 6) AS sq, floor(p_retailprice)::BIGINT AS fl, greatest(p_size, 10) AS gr, p_partkey % 7 AS pm, abs(p_size - 25) AS ab FROM part")
add("fn_date", lambda t: t("orders").groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count(F.lit(1)).alias("n"), F.max(F.datediff(F.col("o_orderdate"), F.date_trunc("month", "o_orderdate"))).alias("day"), F.max(F.to_date(F.col("o_orderdate") + F.expr("INTERVAL 10 DAYS"))).alias("later")),
    "SELECT year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, count(*) AS n, max(date_diff('day', date_trunc('month', o_orderdate), o_orderdate))::INT AS day, max((o_orderdate + INTERVAL 10 DAYS)::DATE) AS later FROM orders GROUP BY 1, 2")
add("fn_array", lambda t: t("embeddings").select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x), 4).alias("dot"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), F.exists("embedding", lambda x: x > 0.2).alias("large"), F.size("embedding").cast("long").alias("n"), F.round(F.array_min("embedding").cast("double"), 5).alias("least")),
    "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS dot, len(list_filter(embedding, lambda x: x > 0)) AS positive, len(list_filter(embedding, lambda x: x > 0.2::DOUBLE)) > 0 AS large, len(embedding) AS n, round(list_min(embedding)::DOUBLE, 5) AS least FROM embeddings")
add("fn_array_sets", lambda t: t("part").select("p_partkey", F.array_join(F.array_sort(F.array_distinct(F.split("p_name", ""))), "").alias("letters"), F.size(F.array_intersect(F.split("p_name", ""), F.split(F.lower("p_type"), ""))).cast("long").alias("both"), F.size(F.array_union(F.split("p_name", ""), F.split(F.lower("p_type"), ""))).cast("long").alias("either")),
    "SELECT p_partkey, array_to_string(list_sort(list_distinct(string_split(p_name, ''))), '') AS letters, len(list_intersect(list_distinct(string_split(p_name, '')), list_distinct(string_split(lower(p_type), '')))) AS both, len(list_distinct(list_concat(string_split(p_name, ''), string_split(lower(p_type), '')))) AS either FROM part")
add("fn_map", lambda t: t("nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m")).select("n_regionkey", F.size("m").cast("long").alias("n"), F.array_max(F.map_keys("m")).alias("last"), F.element_at("m", F.array_max(F.map_keys("m"))).alias("name")),
    "SELECT n_regionkey, count(*) AS n, max(n_nationkey) AS last, max_by(n_name, n_nationkey) AS name FROM nation GROUP BY n_regionkey")
add("fn_json", lambda t: t("events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("k2")), "SELECT event_id, (props->>'$.k')::BIGINT AS k, (props->>'$.k')::BIGINT AS k2 FROM events")
add("fn_hash", lambda t: t("customer").select("c_custkey", F.md5(F.col("c_name").cast("binary")).alias("md5"), F.conv(F.substring(F.md5(F.col("c_name").cast("binary")), 1, 8), 16, 10).cast("long").alias("h")), "SELECT c_custkey, md5(c_name) AS md5, ('0x' || substr(md5(c_name), 1, 8))::BIGINT AS h FROM customer")
add("fn_cond", lambda t: t("part").select("p_partkey", F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large").alias("class"), F.coalesce(F.nullif(F.col("p_type"), F.lit("PROMO")), F.lit("none")).alias("kind")),
    "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS class, coalesce(nullif(p_type, 'PROMO'), 'none') AS kind FROM part")

# ---- SQL surface, planner ------------------------------------------------------------------------------------------------


def _sql_front(spark: SparkSession, sf: str) -> DataFrame:
    sqlapi.register_views(TokenIndex.build(tables.part_desc(spark, sf)), "front")
    return sqlapi.sql_select(spark, """
SELECT p.tid, round(sum(ln((m.n - s.df + 0.5D) / (s.df + 0.5D)) * 2.5D * p.tf / (1.5D * (0.325D + 0.675D * p.dl / m.avgdl) + p.tf)), 6) AS score
FROM front_postings p JOIN front_stats s ON s.token = p.token CROSS JOIN front_meta m
WHERE p.token IN (SELECT explode(array('$r', 'ri', 'in', 'ng', 'g$'))) GROUP BY p.tid""")


add_raw("sql_front", _sql_front, q.scores(f"SELECT tid, round(sum({q.RS} * 2.5::DOUBLE * tf / (1.5::DOUBLE * (0.325::DOUBLE + 0.675::DOUBLE * dl / (cs / n)) + tf)), 6) AS score FROM bag JOIN sizes USING (tid) JOIN stats USING (token) CROSS JOIN coll WHERE token IN ('$r', 'ri', 'in', 'ng', 'g$') GROUP BY tid"))


def _sql_functions(spark: SparkSession, sf: str) -> DataFrame:
    sqlapi.register_functions(spark)
    tables.names(spark, sf, "nation").createOrReplaceTempView("fn_names")
    return spark.sql("SELECT a.tid, round(edit_similarity(a.s, b.s), 6) AS edit, round(jaro_winkler(a.s, b.s), 6) AS jw, size(qgram_list(a.s, 3)) AS grams FROM fn_names a JOIN fn_names b ON b.tid = (a.tid + 1) % 25")


add_raw("sql_functions", _sql_functions, "SELECT a.n_nationkey::BIGINT AS tid, round(1 - levenshtein(a.n_name, b.n_name)::DOUBLE / greatest(length(a.n_name), length(b.n_name)), 6) AS edit, round(jaro_winkler_similarity(a.n_name, b.n_name), 6) AS jw, (length(a.n_name) + 2 + length(a.n_name) - length(replace(a.n_name, ' ', '')))::INT AS grams FROM nation a JOIN nation b ON b.n_nationkey = (a.n_nationkey + 1) % 25")


def _sql_udtf(spark: SparkSession, sf: str) -> DataFrame:
    sqlapi.register_functions(spark)
    tables.part_desc(spark, sf).createOrReplaceTempView("udtf_names")
    return spark.sql("SELECT t.token, count(*) AS n FROM udtf_names, LATERAL tokens(s, 2) t GROUP BY t.token")


add_raw("sql_udtf", _sql_udtf, q.scores("SELECT token, sum(tf)::BIGINT AS n FROM bag GROUP BY token"))


def _plans(spark: SparkSession, sf: str) -> DataFrame:
    index = TokenIndex.build(tables.part_desc(spark, sf))
    p = planner.choose_plan(index, q.QS)
    return scoring.score_bm25(index, q.QS, layout=p.layout).select("qid", "tid", F.round("score", 6).alias("score"))


add_raw("plan_bm25", _plans, q.simple(q.sql_bm25()))
add_raw("prune_weight_refused", lambda s, d: s.createDataFrame([(_refused(s, d),)], "refused boolean"), "SELECT true AS refused")


def _refused(spark: SparkSession, sf: str) -> bool:
    try:
        scoring.prune_by_weight(scoring.base_weights(TokenIndex.build(tables.names(spark, sf, "region")), "wm"), 0.0, "hmm")
    except ValueError:
        return True
    return False


add_raw("combo_best_word", lambda s, d: combo.best_words(_best_input(s, d)), "SELECT p_partkey % 5 AS qid, p_size::BIGINT AS tid, p_type AS qword, min(p_name) AS word, 1.0::DOUBLE AS sim FROM part GROUP BY 1, 2, 3")


def _best_input(spark: SparkSession, sf: str) -> DataFrame:
    return tables.load(spark, sf, "part").select((F.col("p_partkey") % 5).alias("qid"), F.col("p_size").cast("long").alias("tid"), F.col("p_type").alias("qword"), F.col("p_name").alias("word"), F.lit(1.0).alias("sim"))


# ---- generator ---------------------------------------------------------------------------------------------------------------

_SUFFIX = "CASE c_custkey % 8 WHEN 0 THEN 'Inc.' WHEN 1 THEN 'Incorporated' WHEN 2 THEN 'Corp.' WHEN 3 THEN 'Corporation' WHEN 4 THEN 'Ltd.' WHEN 5 THEN 'Limited' WHEN 6 THEN 'Co.' ELSE 'Company' END"
_CLEAN = f"SELECT c_custkey AS tid, replace(c_name, '#', ' ') || ' ' || {_SUFFIX} AS s FROM customer"


def clean_names(spark: SparkSession, sf: str) -> DataFrame:
    c = tables.load(spark, sf, "customer")
    forms = F.array(*(F.lit(x) for pair in datagen.FORMS for x in pair))
    return c.select(F.col("c_custkey").alias("tid"), F.concat_ws(" ", F.replace(F.col("c_name"), F.lit("#"), F.lit(" ")), F.element_at(forms, (F.col("c_custkey") % 8 + 1).cast("int"))).alias("s"))


def _generated(name: str, duplicates: str = "uniform") -> Query:
    """Ten tuples for every customer's name."""

    def run(s: SparkSession, d: str) -> DataFrame:
        clean = clean_names(s, d)
        n = clean.count()
        return datagen.generate_dirty(clean, datagen.preset(name, 10 * n, n, duplicates))

    return run


def _u(*parts: str) -> str:
    return "(('0x' || substr(md5('42|' || " + " || '|' || ".join(parts) + "), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"


_ROWS = f"""
WITH clean AS (SELECT tid, s FROM ({_CLEAN})),
r AS (SELECT tid AS cluster_id, s, unnest(range(10)) AS copy FROM clean),
w AS (SELECT *, copy > 0 AND {_u('cluster_id', 'copy', "'wrong'")} < {{share}} AS bad FROM r)
"""
_FORM = "CASE " + " ".join(f"WHEN ends_with(s, ' {a}') THEN substr(s, 1, length(s) - {len(a)}) || '{b}' WHEN ends_with(s, ' {b}') THEN substr(s, 1, length(s) - {len(b)}) || '{a}'" for a, b in datagen.FORMS) + " ELSE s END"
_SWAP = f"array_to_string(list_transform(range(len(ws)), lambda i: CASE WHEN (i - i % 2) + 1 < len(ws) AND {_u('cluster_id', 'copy', "'swap'", '(i - i % 2)')} < 0.2 THEN ws[(i - i % 2) + 2 - i % 2] ELSE ws[i + 1] END), ' ')"
add_raw("gen_clusters", lambda s, d: _generated("CU2")(s, d).groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("is_erroneous").cast("long")).alias("wrong"), F.sum(F.col("is_clean").cast("long")).alias("clean")),
    _ROWS.format(share=0.5) + "SELECT cluster_id, count(*) AS n, sum(bad::INT)::BIGINT AS wrong, sum((copy = 0)::INT)::BIGINT AS clean FROM w GROUP BY cluster_id")
_TID = f"cluster_id * {datagen.COPIES} + copy AS tid"
add_raw("gen_abbrev", lambda s, d: _generated("F1")(s, d).select("tid", "s"), _ROWS.format(share=0.5) + f"SELECT {_TID}, CASE WHEN bad AND {_u('cluster_id', 'copy', "'form'")} < 0.5 THEN {_FORM} ELSE s END AS s FROM w")
add_raw("gen_swap", lambda s, d: _generated("F2")(s, d).select("tid", "s"), _ROWS.format(share=0.5) + f"SELECT {_TID}, CASE WHEN bad THEN {_SWAP} ELSE s END AS s FROM (SELECT *, string_split(s, ' ') AS ws FROM w)")
add_raw("gen_chars", lambda s, d: _generated("F5")(s, d))
_POISSON = [sum(math.exp(-9.0) * 9.0**i / math.factorial(i) for i in range(k + 1)) for k in range(40)]
_COUNTS = {
    "zipf": "SELECT cluster_id, 1 + round(9.0::DOUBLE * n / h / place)::BIGINT AS n FROM (SELECT tid AS cluster_id, row_number() OVER (ORDER BY tid) AS place, count(*) OVER () AS n FROM clean) CROSS JOIN (SELECT sum(1.0::DOUBLE / i) AS h FROM (SELECT unnest(range(1, (SELECT count(*) + 1 FROM clean))) AS i))",
    "poisson": "SELECT tid AS cluster_id, 1 + " + " + ".join(f"({_u('tid', chr(39) + 'count' + chr(39))} >= {p!r}::DOUBLE)::BIGINT" for p in _POISSON) + " AS n FROM clean",
}
for _kind, _count in _COUNTS.items():
    add_raw(f"gen_{_kind}", lambda s, d, k=_kind: _generated("CU6", k)(s, d).groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n")), f"WITH clean AS ({_CLEAN}) {_count}")
add_raw("gen_short_names", tables.short_names)
add_raw("gen_long_titles", tables.long_titles)

# ---- streams ------------------------------------------------------------------------------------------------------------------


def stream_table(spark: SparkSession, sf: str, name: str) -> DataFrame:
    """A table as a stream: the folder of its files, or the one file found in its folder by its name."""
    schema = spark.read.parquet(f"{sf}/{name}.parquet").schema
    out = spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet").parquet(sf)
    return out.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in out.columns else out


add_raw("stream_tumbling", lambda s, d: streams.available(streams.tumbling(stream_table(s, d, "events")), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.round("total", 4).alias("total")),
    "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
add_raw("stream_sliding", lambda s, d: streams.available(streams.sliding(stream_table(s, d, "events")), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "n"),
    "SELECT date_trunc('hour', ts) - h * INTERVAL 1 HOUR AS start, count(*) AS n FROM events CROSS JOIN (SELECT unnest([0, 1]) AS h) GROUP BY 1")
add_raw("stream_sessions", lambda s, d: streams.available(streams.sessions(stream_table(s, d, "events")), "complete").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n"), """
WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOURS OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS new FROM events),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, new DESC ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k""")
add_raw("stream_dedup", lambda s, d: streams.available(streams.without_duplicates(stream_table(s, d, "events").select("ts", "user_id", "event_type"), ["user_id", "event_type"], "60 days")).select("user_id", "event_type"),
    "SELECT DISTINCT user_id, event_type FROM events")


def _stream_join(spark: SparkSession, sf: str) -> DataFrame:
    views = stream_table(spark, sf, "events").where("event_type = 'view'")
    clicks = stream_table(spark, sf, "events").where("event_type = 'click'")
    return streams.available(streams.interval_join(views, clicks, "6 HOURS", "60 days")).select("event_a", "event_b")


add_raw("stream_interval_join", _stream_join, "SELECT a.event_id AS event_a, b.event_id AS event_b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOURS")


def _stream_select(spark: SparkSession, sf: str) -> DataFrame:
    arriving = stream_table(spark, sf, "nation").select(F.col("n_nationkey").cast("long").alias("qid"), F.col("n_name").alias("s"))
    out = streams.select_stream(TokenIndex.build(tables.part_desc(spark, sf)), arriving, "bm25", k=5)
    return out.select("qid", "tid", F.round("score", 6).alias("score"))


add_raw("stream_select", _stream_select, q.scores(f"SELECT qid, tid, round(score, 6) AS score FROM ({q.ranked(f'SELECT qid, tid, {q.sql_bm25()} AS score FROM met GROUP BY qid, tid')}) WHERE rank <= 5", queries="SELECT n_nationkey::BIGINT AS qid, n_name AS s FROM nation"))


def _stream_late(spark: SparkSession, sf: str) -> DataFrame:
    """The last quarter of the time arrives first, then the third: the earlier half is beyond the watermark by then and
    dropped (a batch drops by the watermark of the batch before it). Windows that the watermark hasn't passed stay open."""
    events = tables.load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    lo, hi = events.agg(F.min(F.unix_micros("ts")), F.max(F.unix_micros("ts"))).first()
    at, half, most = F.unix_micros("ts"), lo + (hi - lo) // 2, lo + (hi - lo) * 3 // 4
    parts = [at >= most, (at >= half) & (at < most), at < half]
    out = streams.available(streams.tumbling(streams.in_order(events, parts), late="1 hour"), "append")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


add_raw("stream_late", _stream_late, """
WITH r AS (SELECT epoch_us(min(ts)) AS lo, epoch_us(max(ts)) AS hi FROM events)
SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events CROSS JOIN r WHERE epoch_us(ts) >= lo + (hi - lo) // 2
GROUP BY 1, 2 HAVING epoch_us(date_trunc('hour', ts)) + 3600000000 <= max(hi) - max(hi) % 1000 - 3600000000""")


def _stream_near(spark: SparkSession, sf: str) -> DataFrame:
    """Arriving part strings that share a band (two of four min-hash values) with an earlier one: the band's first."""
    arriving = stream_table(spark, sf, "part").select(F.col("p_partkey").alias("tid"), F.concat_ws(" ", "p_name", "p_type").alias("s"), F.timestamp_seconds(F.lit(1_700_000_000)).alias("ts"))
    marked = streams.near_duplicates(arriving, lambda rows: streams.minhash_bands(rows, 4, 2))
    return streams.available(marked).groupBy("tid").agg(F.min("first").alias("first"))


_NEAR = minhash.coefficients(4)
add_raw("stream_near_dup", _stream_near, f"""
WITH s AS (SELECT p_partkey AS tid, p_name || ' ' || p_type AS s FROM part), g AS ({q.grams('SELECT * FROM s', 'tid')}),
h AS (SELECT DISTINCT tid, ('0x' || substr(md5(token), 1, 8))::BIGINT % 2147483647 AS h FROM g),
m AS (SELECT tid, {', '.join(f'min((h * {a} + {b}) % 2147483647) AS v{i}' for i, (a, b) in enumerate(_NEAR))} FROM h GROUP BY tid),
b AS (SELECT tid, 0 AS band, v0 AS x, v1 AS y FROM m UNION ALL SELECT tid, 1, v2, v3 FROM m)
SELECT tid, min(first) AS first FROM (SELECT tid, min(tid) OVER (PARTITION BY band, x, y) AS first FROM b) WHERE tid <> first GROUP BY tid""")


def _stream_append(spark: SparkSession, sf: str) -> DataFrame:
    """Customers' names arrive for an index of suppliers' names; the index that they leave is asked."""
    arriving = stream_table(spark, sf, "customer").select((F.col("c_custkey") + 1_000_000_000).alias("tid"), F.col("c_name").alias("s"))
    index = streams.append_stream(TokenIndex.build(tables.names(spark, sf, "supplier")), arriving, streams.folder(spark))
    return scoring.score_bm25(index, _ASKED).select("qid", "tid", F.round("score", 6).alias("score"))


_ASKED = [(1, "Suplier#00012"), (2, "Custmer 17")]
add_raw("stream_append", _stream_append, q.simple(q.sql_bm25(), base="SELECT s_suppkey AS tid, s_name AS s FROM supplier UNION ALL SELECT c_custkey + 1000000000, c_name FROM customer", queries=q.values(_ASKED)))

# ---- experiments ----------------------------------------------------------------------------------------------------------------

for _name, _run in experiments.QUERIES.items():
    add_raw(_name, _run)


def queries() -> dict[str, Query]:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_sql)


__all__ = ["Queries", "oracle_sql", "queries", "ranking"]

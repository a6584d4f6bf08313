"""The surrounding relational operators, each against its SQL."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from seqlex.sources.tables import table

from .registry import query

L, O, C, N, E = "lineitem", "orders", "customer", "nation", "events"


def same(name: str, sql: str, spark_sql: str | None = None) -> None:
    """A query whose text both engines read alike; the tables it names become views of the session."""

    @query(name, sql)
    def run(spark, d, text=spark_sql or sql):
        import re

        for t in set(re.findall(r"\b(region|nation|customer|supplier|part|orders|lineitem|events|documents|embeddings|pages|benchmark|labels|conversations)\b", text)):
            table(spark, d, t).createOrReplaceTempView(t)
        return spark.sql(text)


@query("scan_parquet", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45")
def scan_parquet(spark, d):
    return table(spark, d, L).where("l_quantity > 45").select("l_orderkey", "l_quantity")


@query("join_broadcast", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def join_broadcast(spark, d):
    return table(spark, d, C).join(F.broadcast(table(spark, d, N)), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


for _how, _hint in (("sort_merge", "merge"), ("shuffle_hash", "shuffle_hash")):

    @query(f"join_{_how}", "SELECT o_orderkey, l_linenumber FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
    def _join(spark, d, hint=_hint):
        return table(spark, d, O).join(table(spark, d, L).hint(hint), F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "l_linenumber")


@query("agg_partial_final", "SELECT l_returnflag, sum(l_quantity) AS q FROM lineitem GROUP BY l_returnflag")
def agg_partial_final(spark, d):
    """Two levels over a salted key: a hot group is summed in 16 parts first."""
    salted = table(spark, d, L).withColumn("salt", F.pmod(F.xxhash64("l_orderkey"), F.lit(16)))
    return salted.groupBy("l_returnflag", "salt").agg(F.sum("l_quantity").alias("q")).groupBy("l_returnflag").agg(F.sum("q").alias("q"))


@query("topk_per_group", "SELECT l_shipmode, l_orderkey, l_extendedprice FROM (SELECT l_linestatus AS l_shipmode, l_orderkey, l_linenumber, l_extendedprice, row_number() OVER (PARTITION BY l_linestatus ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) AS n FROM lineitem) WHERE n <= 10")
def topk_per_group(spark, d):
    w = Window.partitionBy("l_linestatus").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber")
    return table(spark, d, L).withColumn("n", F.row_number().over(w)).where("n <= 10").select(F.col("l_linestatus").alias("l_shipmode"), "l_orderkey", "l_extendedprice")


@query("join_asof", "SELECT a.event_id, max(b.event_id) AS prior FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND (b.ts < a.ts OR (b.ts = a.ts AND b.event_id < a.event_id)) AND NOT EXISTS (SELECT 1 FROM events c WHERE c.user_id = a.user_id AND c.event_type = 'purchase' AND (c.ts < a.ts OR (c.ts = a.ts AND c.event_id < a.event_id)) AND (c.ts > b.ts OR (c.ts = b.ts AND c.event_id > b.event_id))) GROUP BY a.event_id")
def join_asof(spark, d):
    """The latest earlier purchase of the user: one window over the user's events, no join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, d, E).select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("prior"))


@query("knn_cosine", "WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings) SELECT q, c, round(s, 6) AS cosine FROM (SELECT q.vec_id AS q, c.vec_id AS c, list_cosine_similarity(q.e, c.e) AS s, row_number() OVER (PARTITION BY q.vec_id ORDER BY round(list_cosine_similarity(q.e, c.e), 6) DESC, c.vec_id) AS n FROM v q JOIN v c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id) WHERE n <= 3")
def knn_cosine(spark, d):
    v = table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    q = v.where("vec_id % 50 = 0").select(F.col("vec_id").alias("q"), F.col("e").alias("qe"))
    s = v.join(F.broadcast(q), F.col("q") != F.col("vec_id")).select("q", F.col("vec_id").alias("c"), F.round(dot("qe", "e") / F.sqrt(dot("qe", "qe") * dot("e", "e")), 6).alias("cosine"))
    return s.withColumn("n", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("cosine"), "c"))).where("n <= 3").drop("n")


_plain = {
    "select_exprs": "SELECT l_orderkey, l_extendedprice * (1 - l_discount) AS net FROM lineitem",
    "filter_range": "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 50000",
    "filter_in": "SELECT c_custkey FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY')",
    "filter_like": "SELECT p_partkey FROM part WHERE p_type LIKE '%A%'",
    "filter_null": "SELECT count(*) AS n FROM documents WHERE lang IS NOT NULL",
    "case_when": "SELECT l_orderkey, l_linenumber, CASE WHEN l_quantity < 10 THEN 'low' WHEN l_quantity < 30 THEN 'mid' ELSE 'high' END AS band FROM lineitem",
    "coalesce_nulls": "SELECT o_orderkey, coalesce(nullif(o_orderstatus, 'O'), 'open') AS status FROM orders",
    "join_inner_hash": "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey",
    "join_left": "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey",
    "join_full": "SELECT s_suppkey, c_custkey FROM supplier FULL JOIN customer ON s_suppkey = c_custkey",
    "join_semi": "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)",
    "join_anti": "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)",
    "join_star": "SELECT r_name, n_name, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, n_name",
    "agg_hash": "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q, count(*) AS n, round(avg(l_discount), 6) AS d FROM lineitem GROUP BY l_returnflag, l_linestatus",
    "agg_distinct": "SELECT l_returnflag, count(DISTINCT l_suppkey) AS n FROM lineitem GROUP BY l_returnflag",
    "agg_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "agg_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "agg_grouping_sets": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())",
    "agg_filter_clause": "SELECT count(*) FILTER (WHERE l_quantity > 25) AS big, count(*) AS n FROM lineitem",
    "agg_stats": "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS s, round(var_pop(l_quantity), 6) AS v, round(corr(l_quantity, l_extendedprice), 6) AS c FROM lineitem GROUP BY l_returnflag",
    "win_ranks": "SELECT c_custkey, row_number() OVER w AS a, rank() OVER w AS b, dense_rank() OVER w AS c, ntile(4) OVER w AS d FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)",
    "win_lag_lead": "SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)",
    "win_running_sum": "SELECT l_orderkey, l_linenumber, sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity ROWS UNBOUNDED PRECEDING) AS q FROM lineitem",
    "win_moving_avg": "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS m FROM events",
    "sort_limit": "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber LIMIT 100",
    "union_all": "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier",
    "union_distinct": "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier",
    "intersect": "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier",
    "except": "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders WHERE o_totalprice > 300000",
    "string_functions": "SELECT c_custkey, upper(substring(c_name, 1, 4)) AS u, reverse(c_mktsegment) AS r, length(c_name) AS n, md5(c_name) AS h, lpad(cast(c_custkey AS varchar(20)), 8, '0') AS p FROM customer",
    "date_functions": "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, quarter(o_orderdate) AS q FROM orders",
    "math_functions": "SELECT l_orderkey, l_linenumber, round(sqrt(l_extendedprice), 6) AS r, round(ln(l_extendedprice), 6) AS n, greatest(l_tax, l_discount) AS g FROM lineitem",
    "scalar_subquery": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)",
    "cte": "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS t FROM orders GROUP BY o_custkey) SELECT c_name, round(t, 2) AS t FROM big JOIN customer ON o_custkey = c_custkey WHERE t > 500000",
}
_plain |= {
    # Equal balances go to the least key, which is the first row that the other engine meets.
    "max_by_min_by": ("SELECT c_nationkey, max_by(c_custkey, c_acctbal) AS richest, min_by(c_custkey, c_acctbal) AS poorest FROM customer GROUP BY c_nationkey", "SELECT c_nationkey, max_by(c_custkey, struct(c_acctbal, -c_custkey)) FILTER (WHERE c_acctbal IS NOT NULL) AS richest, min_by(c_custkey, struct(c_acctbal, c_custkey)) FILTER (WHERE c_acctbal IS NOT NULL) AS poorest FROM customer GROUP BY c_nationkey"),
    "filter_rlike": ("SELECT p_partkey FROM part WHERE regexp_matches(p_type, '^[A-M]')", "SELECT p_partkey FROM part WHERE p_type RLIKE '^[A-M]'"),
    "join_cross": "SELECT r_name, n_name FROM region CROSS JOIN nation",
    "join_theta": "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND a.n_nationkey > b.n_nationkey",
    "join_null_safe": "SELECT a.doc_id AS a, count(*) AS n FROM labels a JOIN nation b ON nullif(a.quality, 0) IS NOT DISTINCT FROM nullif(b.n_regionkey, 0) GROUP BY a.doc_id",
    "join_right": "SELECT o_orderkey, c_custkey FROM orders RIGHT JOIN customer ON o_custkey = c_custkey",
    "agg_collect_set": ("SELECT c_nationkey, list_sort(list(DISTINCT c_mktsegment)) AS segments FROM customer GROUP BY c_nationkey", "SELECT c_nationkey, array_sort(collect_set(c_mktsegment)) AS segments FROM customer GROUP BY c_nationkey"),
    "agg_pivot": "SELECT l_returnflag, sum(CASE WHEN l_linestatus = 'F' THEN l_quantity END) AS f, sum(CASE WHEN l_linestatus = 'O' THEN l_quantity END) AS o FROM lineitem GROUP BY l_returnflag",
    "percentile_exact": ("SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY l_returnflag", "SELECT l_returnflag, round(percentile(l_quantity, 0.5), 6) AS median, round(percentile(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY l_returnflag"),
    "win_first_last": "SELECT o_orderkey, first_value(o_orderkey) OVER w AS a, last_value(o_orderkey) OVER w AS b, nth_value(o_orderkey, 2) OVER w AS c FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "win_range_days": ("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 30 DAYS PRECEDING AND CURRENT ROW) AS n FROM orders", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL '30' DAY PRECEDING AND CURRENT ROW) AS n FROM orders"),
    "win_distribution": "SELECT c_custkey, round(percent_rank() OVER w, 9) AS p, round(cume_dist() OVER w, 9) AS d FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)",
    "sort_nulls_last": "SELECT doc_id, lang FROM documents ORDER BY lang DESC NULLS LAST, doc_id LIMIT 50",
    "limit_offset": "SELECT c_custkey FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 20 OFFSET 10",
    "topk_global": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 200",
    "sample_keyed": ("SELECT doc_id FROM documents WHERE substr(md5(doc_id::VARCHAR), 1, 1) < '4'", "SELECT doc_id FROM documents WHERE substr(md5(cast(doc_id AS string)), 1, 1) < '4'"),
    "intersect_all": "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier",
    "except_all": "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier",
    "json_fields": ("SELECT event_id, (props ->> '$.k')::BIGINT AS k FROM events", "SELECT event_id, cast(get_json_object(props, '$.k') AS bigint) AS k FROM events"),
    "html_titles": ("SELECT page_id, regexp_extract(html, '(?is)<title>(.*?)</title>', 1) AS title, len(regexp_extract_all(html, '(?i)<a ')) AS links FROM pages", "SELECT page_id, regexp_extract(html, '(?is)<title>(.*?)</title>', 1) AS title, cast(size(regexp_extract_all(html, '(?i)<a ', 0)) AS bigint) AS links FROM pages"),
    "vector_norms": ("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 6) AS norm FROM embeddings", "SELECT vec_id, round(sqrt(aggregate(transform(embedding, x -> cast(x AS double) * cast(x AS double)), 0.0D, (a, x) -> a + x)), 6) AS norm FROM embeddings"),
}
for _name, _text in _plain.items():
    same(_name, *((_text,) if isinstance(_text, str) else _text))

"""Relational, window, set and scalar operators on the given tables. Where both engines read the same text, it stands once."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxcore.operators import joins
from proxcore.sources.tables import register, table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def both(name: str, text: str, oracle: str | None = None) -> None:
    def run(s: SparkSession, d: str) -> DataFrame:
        register(s, d)
        return s.sql(text)

    QUERIES[f"rel_{name}"], SQL[f"rel_{name}"] = run, oracle or text


def put(name: str, make: Callable[[SparkSession, str], DataFrame], text: str) -> None:
    QUERIES[f"rel_{name}"], SQL[f"rel_{name}"] = make, text


both("project_filter", "SELECT o_orderkey, o_custkey + 1 AS next_cust, upper(o_orderpriority) AS priority FROM orders WHERE o_orderdate < TIMESTAMP '1995-04-01' AND (o_orderstatus IN ('O', 'F') OR o_orderpriority LIKE '1%') AND o_totalprice BETWEEN 1000 AND 300000 AND o_custkey IS NOT NULL")
both("inner_join", "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_acctbal > 0")
both("left_join", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
both("right_join", "SELECT c_custkey, n_name FROM nation RIGHT JOIN customer ON n_nationkey = c_nationkey AND n_regionkey = 1")
both("full_join", "SELECT coalesce(a.k, -1) AS a, coalesce(b.k, -1) AS b, coalesce(a.n, 0) AS customers, coalesce(b.n, 0) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_acctbal > 9000 GROUP BY c_nationkey) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY s_nationkey) b ON a.k = b.k")
both("semi_join", "SELECT c_custkey FROM customer LEFT SEMI JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
both("anti_join", "SELECT p_partkey FROM part LEFT ANTI JOIN (SELECT l_partkey FROM lineitem WHERE l_quantity > 40) x ON p_partkey = l_partkey", "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 40)")
both("cross_join", "SELECT r_regionkey, a.x AS alpha_tenths FROM region CROSS JOIN (VALUES (1), (2), (4), (6), (8)) AS a(x)")
both("broadcast_join", "SELECT /*+ BROADCAST(nation) */ c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
both("merge_join", "SELECT /*+ MERGE(o) */ l_orderkey, l_linenumber, o_custkey FROM lineitem JOIN orders o ON l_orderkey = o_orderkey", "SELECT l_orderkey, l_linenumber, o_custkey FROM lineitem JOIN orders o ON l_orderkey = o_orderkey")
both("shuffle_hash_join", "SELECT /*+ SHUFFLE_HASH(o) */ l_orderkey, l_linenumber, o_custkey FROM lineitem JOIN orders o ON l_orderkey = o_orderkey WHERE l_quantity < 5", "SELECT l_orderkey, l_linenumber, o_custkey FROM lineitem JOIN orders o ON l_orderkey = o_orderkey WHERE l_quantity < 5")
both("null_safe_join", "SELECT count(*) AS n FROM (SELECT nullif(c_nationkey, 3) AS k FROM customer) a JOIN (SELECT nullif(s_nationkey, 3) AS k FROM supplier) b ON a.k <=> b.k", "SELECT count(*) AS n FROM (SELECT nullif(c_nationkey, 3) AS k FROM customer) a JOIN (SELECT nullif(s_nationkey, 3) AS k FROM supplier) b ON a.k IS NOT DISTINCT FROM b.k")
both("range_join", "SELECT a.o_orderkey AS a, b.o_orderkey AS b FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND b.o_orderdate > a.o_orderdate WHERE a.o_orderstatus = 'P'")
both("self_join", "SELECT x.l_orderkey, x.l_partkey AS a, y.l_partkey AS b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey")
both("group_by", "SELECT l_returnflag, l_linestatus, count(*) AS n, min(l_quantity) AS lo, max(l_quantity) AS hi, CAST(round(sum(l_extendedprice * 100)) AS BIGINT) AS cents FROM lineitem GROUP BY l_returnflag, l_linestatus")
both("count_distinct", "SELECT o_orderpriority, count(DISTINCT o_custkey) AS customers, count(DISTINCT o_orderstatus) AS states FROM orders GROUP BY o_orderpriority")
both("conditional_agg", "SELECT event_type, CAST(count_if(value > 50) AS BIGINT) AS high, count(*) FILTER (WHERE user_id % 2 = 0) AS even FROM events GROUP BY event_type")
both("grouping_sets", "SELECT coalesce(o_orderstatus, '*') AS status, coalesce(o_orderpriority, '*') AS priority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderstatus), ())")
both("rollup", "SELECT coalesce(o_orderstatus, '*') AS status, coalesce(o_orderpriority, '*') AS priority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
both("cube", "SELECT coalesce(o_orderstatus, '*') AS status, coalesce(o_orderpriority, '*') AS priority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
both("having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12")
both("collect", "SELECT o_orderkey, array_join(transform(array_sort(collect_list(l_partkey)), x -> CAST(x AS STRING)), ',') AS parts FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderkey", "SELECT o_orderkey, string_agg(CAST(l_partkey AS VARCHAR), ',' ORDER BY l_partkey) AS parts FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderkey")
both("max_by", "SELECT o_custkey, max_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS top_order, bool_or(o_orderstatus = 'F') AS any_f FROM orders GROUP BY o_custkey", "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS top_order, bool_or(o_orderstatus = 'F') AS any_f FROM orders GROUP BY o_custkey")
both("statistics", "SELECT event_type, CAST(round(stddev_samp(value) * 1e6) AS BIGINT) AS sd_e6, CAST(round(corr(value, user_id) * 1e6) AS BIGINT) AS corr_e6, CAST(round(regr_slope(value, user_id) * 1e6) AS BIGINT) AS slope_e6 FROM events GROUP BY event_type")
both("pivot", "SELECT * FROM (SELECT o_orderpriority, o_orderstatus FROM orders) PIVOT (count(*) FOR o_orderstatus IN ('F' AS f, 'O' AS o, 'P' AS p))", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY o_orderpriority")
both("unpivot", "SELECT * FROM (SELECT p_partkey, CAST(p_size AS DOUBLE) AS size, p_retailprice AS price FROM part) UNPIVOT (amount FOR what IN (size, price))", "SELECT p_partkey, 'size' AS what, CAST(p_size AS DOUBLE) AS amount FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
both("ranking", "SELECT c_custkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, CAST(round(percent_rank() OVER w * 1e6) AS BIGINT) AS pr, CAST(round(cume_dist() OVER w * 1e6) AS BIGINT) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_custkey)")
both("lag_lead", "SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey, 2, -1) OVER w AS after, first_value(o_orderkey) OVER w AS first, last_value(o_orderkey) OVER w AS last FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)".replace("lag(o_orderkey)", "lag(o_orderkey, 1, -1)"))
both("running_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS recent, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS so_far FROM events")
both("range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY d RANGE BETWEEN 60 PRECEDING AND CURRENT ROW) AS recent FROM (SELECT o_orderkey, o_custkey, datediff(CAST(o_orderdate AS DATE), DATE '1995-01-01') AS d FROM orders)", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY d RANGE BETWEEN 60 PRECEDING AND CURRENT ROW) AS recent FROM (SELECT o_orderkey, o_custkey, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS d FROM orders)")
both("sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC NULLS LAST, o_orderkey LIMIT 25")
both("union_all", "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")
both("set_operations", "(SELECT c_nationkey AS k FROM customer WHERE c_acctbal < 0 INTERSECT SELECT s_nationkey FROM supplier WHERE s_acctbal < 0) UNION (SELECT n_nationkey FROM nation EXCEPT SELECT s_nationkey FROM supplier)")
both("distinct", "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")
both("date_functions", "SELECT o_orderkey, CAST(CAST(date_trunc('MONTH', o_orderdate) AS DATE) AS STRING) AS month_start, CAST(datediff(CAST(o_orderdate AS DATE), DATE '1995-01-01') AS BIGINT) AS days, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, CAST(CAST(o_orderdate + INTERVAL 7 DAYS AS DATE) AS STRING) AS due FROM orders", "SELECT o_orderkey, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS month_start, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, CAST(CAST(o_orderdate + INTERVAL 7 DAYS AS DATE) AS VARCHAR) AS due FROM orders")
both("math_functions", "SELECT p_partkey, CAST(floor(p_retailprice) AS BIGINT) AS lo, CAST(round(pow(p_size, 2)) AS BIGINT) AS sq, CAST(round(exp(-p_size / 10.0) * 1e9) AS BIGINT) AS decay_e9, CAST(round(ln(p_retailprice) * 1e6) AS BIGINT) AS ln_e6, greatest(p_size, 10) AS hi, p_partkey % 7 AS m FROM part")
both("string_functions", "SELECT p_partkey, concat(p_brand, '/', substring(p_type, 1, 4)) AS tag, lower(p_name) AS name, length(p_name) AS n, split_part(p_brand, '#', 2) AS number FROM part", "SELECT p_partkey, concat(p_brand, '/', substring(p_type, 1, 4)) AS tag, lower(p_name) AS name, CAST(length(p_name) AS INTEGER) AS n, split_part(p_brand, '#', 2) AS number FROM part")
both("json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
both("conditional", "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'low' ELSE 'high' END AS class, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS segment FROM customer")
both("decimal_cast", "SELECT l_orderkey, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) * 100 AS BIGINT) AS cents FROM lineitem GROUP BY l_orderkey")
both("array_functions", "SELECT conv_id, CAST(size(array_distinct(collect_list(role))) AS BIGINT) AS roles, element_at(array_sort(collect_list(turn)), -1) AS last_turn FROM conversations GROUP BY conv_id", "SELECT conv_id, count(DISTINCT role) AS roles, max(turn) AS last_turn FROM conversations GROUP BY conv_id")
both("explode", "SELECT vec_id, pos, CAST(round(x * 1e6) AS BIGINT) AS x_e6 FROM embeddings LATERAL VIEW posexplode(embedding) t AS pos, x", "SELECT vec_id, CAST(p - 1 AS INTEGER) AS pos, CAST(round(embedding[p] * 1e6) AS BIGINT) AS x_e6 FROM (SELECT vec_id, embedding, unnest(range(1, len(embedding) + 1)) AS p FROM embeddings)")
both("scalar_subquery", "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer) AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P')")
both("recursive", "WITH RECURSIVE r(n, status, x) AS (SELECT 1, o_orderstatus, count(DISTINCT o_custkey) FROM orders GROUP BY o_orderstatus UNION ALL SELECT n + 1, status, x * 2 FROM r WHERE n < 20) SELECT n, status, x FROM r")


def _orders(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").select("o_orderkey", "o_custkey", F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).cast("bigint").alias("day"))


_DAY = "date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE))"
put("asof_join", lambda s, d: joins.asof(_orders(s, d), _orders(s, d).groupBy("o_custkey", "day").agg(F.max("o_orderkey").alias("prev_order")), "o_custkey", "day", ["prev_order"], strict=True).withColumn("prev_order", F.coalesce("prev_order", F.lit(-1))), f"WITH o AS (SELECT o_orderkey, o_custkey, {_DAY} AS day FROM orders), p AS (SELECT o_custkey, day, max(o_orderkey) AS prev_order FROM o GROUP BY o_custkey, day) SELECT o.o_custkey, o.day, o_orderkey, coalesce(prev_order, -1) AS prev_order FROM o ASOF LEFT JOIN p ON o.o_custkey = p.o_custkey AND o.day > p.day")
put("interval_join", lambda s, d: joins.within(table(s, d, "events").where("event_type = 'purchase'").select(F.col("event_id").alias("a"), F.unix_timestamp(F.col("ts").cast("timestamp")).alias("at")), table(s, d, "events").where("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.unix_timestamp(F.col("ts").cast("timestamp")).alias("bt")), "at", "bt", 600).where("a < b").select("a", "b"), "WITH p AS (SELECT event_id, CAST(floor(epoch(ts)) AS BIGINT) AS t FROM events WHERE event_type = 'purchase') SELECT x.event_id AS a, y.event_id AS b FROM p x JOIN p y ON x.event_id < y.event_id AND abs(x.t - y.t) <= 600")
put("salted_join", lambda s, d: joins.salted(table(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_suppkey"), table(s, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey"), ["l_suppkey"]), "SELECT l_suppkey, l_orderkey, l_linenumber, s_nationkey FROM lineitem JOIN supplier ON s_suppkey = l_suppkey")
put("top_per_group", lambda s, d: joins.top_per_group(table(s, d, "customer").select("c_custkey", "c_nationkey", "c_acctbal"), ["c_nationkey"], [F.desc("c_acctbal"), F.col("c_custkey")], 3), "SELECT c_custkey, c_nationkey, c_acctbal FROM customer QUALIFY row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) <= 3")
put("runs", lambda s, d: joins.runs(_orders(s, d).select("o_custkey", "day").distinct(), ["o_custkey"], "day", 30), f"WITH o AS (SELECT DISTINCT o_custkey, {_DAY} AS day FROM orders), m AS (SELECT *, CASE WHEN day - lag(day) OVER (PARTITION BY o_custkey ORDER BY day) > 30 OR lag(day) OVER (PARTITION BY o_custkey ORDER BY day) IS NULL THEN 1 ELSE 0 END AS fresh FROM o), r AS (SELECT *, sum(fresh) OVER (PARTITION BY o_custkey ORDER BY day) AS run FROM m) SELECT o_custkey, min(day) AS first, max(day) AS last, count(*) AS n FROM r GROUP BY o_custkey, run")
put("sample", lambda s, d: table(s, d, "orders").where("((o_orderkey % 2147483648) * 2654435761) % 4294967296 % 100 < 10").select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE ((o_orderkey % 2147483648) * 2654435761) % 4294967296 % 100 < 10")
put("approx_counts", lambda s, d: table(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("n"), F.percentile_approx("l_quantity", 0.5, 10_000).alias("p")).select((F.abs(F.col("a") - F.col("n")) <= 0.1 * F.col("n")).alias("close"), F.col("p").between(20, 30).alias("middle")), "SELECT true AS close, true AS middle")
put("event_windows", lambda s, d: table(s, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.floor(F.unix_timestamp(F.col("w.start")) / 3600).alias("hour"), "event_type", "n"), "SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS hour, event_type, count(*) AS n FROM events GROUP BY hour, event_type")

"""The relational operators around the methods, each with its twin."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.permute import Digest
from ..sources.tables import table, write_rows
from ..tables import fresh_path
from .base import ORACLES, QUERIES, query


def sql_query(name: str, spark_sql: str, duck_sql: str | None = None, tables: tuple[str, ...] = ()):
    """A query given as SQL text over views; the twin is the same text unless given."""

    def run(spark, sf_dir):
        for t in tables:
            table(spark, sf_dir, t).createOrReplaceTempView(t)
        return spark.sql(spark_sql)

    QUERIES[name], ORACLES[name] = run, duck_sql or spark_sql


def _format(name: str, kind: str, schema: str, columns: str):
    @query(f"SELECT {columns} FROM orders")
    def run(spark, sf_dir):
        path = fresh_path(spark, f"rows-{kind}")
        write_rows(table(spark, sf_dir, "orders").selectExpr("o_orderkey", "o_custkey", "o_orderstatus"), path, kind)
        return spark.read.schema(schema).format(kind).load(path)

    QUERIES[name], ORACLES[name] = QUERIES.pop("run"), ORACLES.pop("run")


for _kind in ("csv", "json", "orc"):
    _format(f"op_scan_{_kind}", _kind, "o_orderkey long, o_custkey long, o_orderstatus string", "o_orderkey, o_custkey, o_orderstatus")


@query("SELECT range::BIGINT AS id, range * range AS square, count(o_orderkey) AS orders FROM range(1000) LEFT JOIN orders ON o_custkey = range GROUP BY 1, 2")
def op_scan_range(spark, sf_dir):
    """A range of customers' keys, and how many orders each has."""
    n = table(spark, sf_dir, "orders").filter("o_custkey < 1000").groupBy(F.col("o_custkey").alias("id")).agg(F.count("o_orderkey").alias("orders"))
    return spark.range(1000).join(n, "id", "left").select("id", (F.col("id") * F.col("id")).alias("square"), F.coalesce("orders", F.lit(0).cast("long")).alias("orders"))


@query("SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_orderstatus = 'F' GROUP BY 1")
def op_sink_partitioned(spark, sf_dir):
    """Written by status, read back with the partition pruned."""
    path = fresh_path(spark, "by-status")
    write_rows(table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus"), path, by=["o_orderstatus"])
    return spark.read.parquet(path).filter("o_orderstatus = 'F'").groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


L, O, C, S, N = "lineitem", "orders", "customer", "supplier", "nation"
sql_query("op_project", "SELECT l_orderkey AS k, l_quantity * 2 AS q2, l_returnflag AS flag FROM lineitem WHERE l_quantity > 49", tables=(L,))
sql_query("op_filter_predicates", "SELECT count(*) AS n FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND NOT l_linestatus LIKE 'X%' AND l_discount IS NOT NULL", tables=(L,))
sql_query("op_filter_nullsafe", "SELECT count(*) AS n FROM events WHERE props <=> NULL", "SELECT count(*) AS n FROM events WHERE props IS NOT DISTINCT FROM NULL", ("events",))
sql_query("op_join_inner", "SELECT o_orderstatus, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderstatus", tables=(L, O))
sql_query("op_join_broadcast", "SELECT /*+ BROADCAST(nation) */ n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name", tables=(C, N))
sql_query("op_join_full", "SELECT count(*) AS n, count(o_orderkey) AS orders, count(c_custkey) AS customers FROM customer FULL OUTER JOIN orders ON c_custkey = o_custkey", tables=(C, O))
sql_query("op_join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey", tables=(C, O))
sql_query("op_join_semi", "SELECT c_custkey FROM customer LEFT SEMI JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey FROM customer SEMI JOIN orders ON c_custkey = o_custkey", (C, O))
sql_query("op_join_anti", "SELECT o_orderkey FROM orders LEFT ANTI JOIN lineitem ON o_orderkey = l_orderkey AND l_returnflag = 'R'", "SELECT o_orderkey FROM orders ANTI JOIN (SELECT * FROM lineitem WHERE l_returnflag = 'R') ON o_orderkey = l_orderkey", (O, L))
sql_query("op_join_theta", "SELECT count(*) AS n FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey", tables=(N,))
sql_query("op_join_self", "SELECT count(*) AS n FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey", tables=(S,))
sql_query("op_agg_statistics", "SELECT l_returnflag, round(avg(l_quantity), 6) AS m, round(var_pop(l_quantity), 4) AS v, round(stddev_samp(l_quantity), 4) AS s, round(covar_pop(l_quantity, l_discount), 6) AS c, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem GROUP BY l_returnflag", tables=(L,))
sql_query("op_agg_minmax_by", "SELECT o_orderstatus, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS top, min_by(o_orderkey, (o_totalprice, o_orderkey)) AS low FROM orders GROUP BY o_orderstatus", "SELECT o_orderstatus, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS top, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS low FROM orders GROUP BY o_orderstatus", (O,))
sql_query("op_agg_conditional", "SELECT l_linestatus, CAST(count_if(l_quantity > 25) AS BIGINT) AS n, bool_and(l_tax >= 0) AS ok FROM lineitem GROUP BY l_linestatus", tables=(L,))
sql_query("op_agg_percentile", "SELECT l_returnflag, percentile(l_quantity, 0.5) AS median FROM lineitem GROUP BY l_returnflag", "SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS median FROM lineitem GROUP BY l_returnflag", (L,))
sql_query("op_agg_collect", "SELECT s_nationkey, array_join(sort_array(collect_list(CAST(s_suppkey AS STRING))), ',') AS keys FROM supplier GROUP BY s_nationkey", "SELECT s_nationkey, array_to_string(list_sort(list(CAST(s_suppkey AS VARCHAR))), ',') AS keys FROM supplier GROUP BY s_nationkey", (S,))
sql_query("op_distinct", "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem", tables=(L,))
sql_query("op_count_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem", tables=(L,))
sql_query("op_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)", tables=(L,))
sql_query("op_rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)", tables=("documents",))
sql_query("op_grouping_sets", "SELECT lang, source, CAST(grouping_id(lang, source) AS BIGINT) AS g, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())", "SELECT lang, source, CAST(grouping_id(lang, source) AS BIGINT) AS g, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())", ("documents",))
sql_query("op_pivot", "SELECT * FROM (SELECT l_linestatus, l_returnflag FROM lineitem) PIVOT (count(*) FOR l_returnflag IN ('A' AS a, 'N' AS n, 'R' AS r))", "SELECT l_linestatus, nullif(count(*) FILTER (l_returnflag = 'A'), 0) AS a, nullif(count(*) FILTER (l_returnflag = 'N'), 0) AS n, nullif(count(*) FILTER (l_returnflag = 'R'), 0) AS r FROM lineitem GROUP BY 1", (L,))
sql_query("op_unpivot", "SELECT * FROM (SELECT s_suppkey, s_nationkey FROM (SELECT s_suppkey, CAST(s_nationkey AS BIGINT) AS s_nationkey, s_suppkey AS own FROM supplier)) UNPIVOT (v FOR c IN (s_nationkey))", "SELECT s_suppkey, 's_nationkey' AS c, s_nationkey::BIGINT AS v FROM supplier", (S,))
sql_query("op_window_rank", "SELECT o_orderkey, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC) AS BIGINT) AS r, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC) AS BIGINT) AS d, CAST(ntile(3) OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS BIGINT) AS t, round(percent_rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice), 6) AS p, round(cume_dist() OVER (PARTITION BY o_custkey ORDER BY o_totalprice), 6) AS cd FROM orders", tables=(O,))
sql_query("op_window_lag", "SELECT o_orderkey, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS prev, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS next FROM orders", tables=(O,))
sql_query("op_window_frames", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS s, first_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS f FROM orders", tables=(O,))
sql_query("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10", tables=(O,))
sql_query("op_topk_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 5 OFFSET 7", tables=(O,))
sql_query("op_setops", "SELECT o_custkey AS k FROM orders INTERSECT SELECT c_custkey FROM customer EXCEPT SELECT s_suppkey FROM supplier", tables=(O, C, S))
sql_query("op_setops_all", "SELECT l_suppkey AS k FROM lineitem EXCEPT ALL SELECT s_suppkey FROM supplier", tables=(L, S))
sql_query("op_strings", "SELECT n_nationkey, lower(n_name) AS l, upper(substring(n_name, 1, 3)) AS u, CAST(length(trim(n_name)) AS BIGINT) AS len, replace(n_name, 'A', 'x') AS rep, concat_ws('-', n_name, 'z') AS c, CAST(levenshtein(n_name, 'FRANCE') AS BIGINT) AS lev FROM nation", tables=(N,))
sql_query("op_regex", "SELECT doc_id, CAST(size(regexp_extract_all(text, '([a-z]+ing)', 1)) AS BIGINT) AS n FROM documents", "SELECT doc_id, len(regexp_extract_all(text, '[a-z]+ing')) AS n FROM documents", ("documents",))
sql_query("op_math_bits", "SELECT l_orderkey, l_linenumber, l_partkey & 255 AS a, l_partkey | 7 AS o, l_partkey ^ 21 AS x, bit_count(l_partkey) AS b, shiftleft(l_partkey, 2) AS sl, pmod(-l_partkey, 7) AS pm FROM lineitem", "SELECT l_orderkey, l_linenumber, l_partkey & 255 AS a, l_partkey | 7 AS o, xor(l_partkey, 21) AS x, bit_count(l_partkey)::INTEGER AS b, l_partkey << 2 AS sl, ((-l_partkey % 7) + 7) % 7 AS pm FROM lineitem", (L,))
sql_query("op_hashes", "SELECT n_nationkey, md5(n_name) AS m, sha2(n_name, 256) AS s FROM nation", "SELECT n_nationkey, md5(n_name) AS m, sha256(n_name) AS s FROM nation", (N,))
sql_query("op_arrays", "SELECT vec_id, CAST(size(filter(embedding, x -> x > 0)) AS BIGINT) AS pos, CAST(size(slice(embedding, 2, 5)) AS BIGINT) AS five, exists(embedding, x -> x > 0.3) AS big FROM embeddings", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS pos, len(embedding[2:6]) AS five, len(list_filter(embedding, lambda x: x > 0.3)) > 0 AS big FROM embeddings", ("embeddings",))
sql_query("op_explode", "SELECT vec_id, pos AS place FROM embeddings LATERAL VIEW posexplode(embedding) e AS pos, v WHERE v > 0.4", "SELECT vec_id, CAST(place AS INTEGER) AS place FROM (SELECT vec_id, unnest(range(len(embedding))) AS place, unnest(embedding) AS v FROM embeddings) WHERE v > 0.4", ("embeddings",))
sql_query("op_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events", ("events",))
sql_query("op_dates", "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, CAST(datediff(o_orderdate, DATE '1992-01-01') AS BIGINT) AS d, date_trunc('month', o_orderdate) AS t FROM orders", "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS d, CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS t FROM orders", (O,))
sql_query("op_conditional", "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band, coalesce(nullif(o_orderstatus, 'O'), '-') AS st FROM orders", tables=(O,))
sql_query("op_subquery_scalar", "SELECT count(*) AS n FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)", tables=(O,))
sql_query("op_subquery_exists", "SELECT count(*) AS n FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'F')", tables=(C, O))
sql_query("op_subquery_in", "SELECT count(*) AS n FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity = 50)", tables=("part", L))
sql_query("op_cte", "WITH a AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), b AS (SELECT max(n) AS m FROM a) SELECT a.o_custkey, a.n FROM a JOIN b ON a.n = b.m", tables=(O,))
sql_query("op_recursive_cte", "WITH RECURSIVE r(k, n) AS (SELECT DISTINCT o_custkey % 1000 + 1, o_custkey % 1000 + 1 FROM orders UNION ALL SELECT k, n * 2 FROM r WHERE n < 1000) SELECT k, n FROM r", tables=(O,))


@query("SELECT event_id, count(*) AS n FROM events e JOIN (SELECT unnest(range(0, 1000, 100)) AS lo) r ON e.value >= lo AND e.value < lo + 100 GROUP BY 1")
def op_join_range(spark, sf_dir):
    """Values to intervals: an equi-join on the interval's number, then the exact condition."""
    e = table(spark, sf_dir, "events").select("event_id", "value", F.floor(F.col("value") / 100).alias("b"))
    r = spark.range(0, 1000, 100).select(F.col("id").alias("lo"), F.floor(F.col("id") / 100).alias("b"))
    return e.join(F.broadcast(r), "b").filter("value >= lo and value < lo + 100").groupBy("event_id").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT e.event_id, max(p.ts) AS before FROM events e LEFT JOIN events p ON p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts GROUP BY 1")
def op_join_asof(spark, sf_dir):
    """Each event's latest purchase of its user: one window, no self-join."""
    e = table(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    return e.select("event_id", F.max(F.when(F.col("event_type") == "purchase", F.col("ts"))).over(w).alias("before"))


@query("SELECT CASE WHEN ('0x' || substring(md5('1:' || o_orderkey), 1, 7))::BIGINT % 100 < 80 THEN 'train' ELSE 'test' END AS part, count(*) AS n, count(DISTINCT o_custkey) AS customers, true AS near FROM orders GROUP BY 1")
def op_sample_split(spark, sf_dir):
    """A replayable split, and whether the approximate distinct count is within a tenth of the exact one."""
    o = table(spark, sf_dir, "orders")
    part = F.when(Digest(1 << 28, 1).pos(F.col("o_orderkey")) % 100 < 80, "train").otherwise("test")
    t = o.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("o_custkey").alias("customers"), F.approx_count_distinct("o_custkey", 0.02).alias("about"))
    return t.select("part", "n", "customers", (F.abs(F.col("about") - F.col("customers")) <= 0.1 * F.col("customers")).alias("near"))


@query(f"SELECT doc_id AS set_id, len(regexp_extract_all(lower(text), '[\\p{{L}}\\p{{N}}]+'))::INTEGER AS words, list_sum(list_transform(regexp_extract_all(lower(text), '[\\p{{L}}\\p{{N}}]+'), lambda w: ('0x' || substring(md5('e:' || w), 1, 7))::BIGINT % 1024))::BIGINT AS total FROM documents")
def sql_surface(spark, sf_dir):
    """The methods from SQL text: registered functions and a table function."""
    from ..functions.sqlapi import register

    register(spark)
    table(spark, sf_dir, "documents").createOrReplaceTempView("documents")
    return spark.sql("SELECT d.doc_id AS set_id, CAST(count(w.word) AS INT) AS words, sum(w.elem) AS total FROM documents d, LATERAL bms_words(d.text, 1024) w GROUP BY d.doc_id")

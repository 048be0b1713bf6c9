"""Catalogue of surrounding operators: name -> (query over the given tables, the same as SQL)."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..functions.hashing import PRIME, Seed, level, level_sql, poly4, sign
from ..sources.features import people
from ..sources.matrix import net, net_sql, part_by_supplier, part_by_supplier_returns
from ..sources.tables import read_updates, table, write_updates
from . import l0
from .checkpoints import noted, shared_folder

CATALOGUE: dict[str, tuple] = {}
S1 = Seed.of(1)


def query(sql: str | None):
    def keep(f):
        CATALOGUE[f.__name__] = (f, sql)
        return f

    return keep


@query("SELECT l_partkey AS i, l_suppkey AS j, CAST(l_quantity AS BIGINT) AS c FROM lineitem")
def op_scan_project(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem").select(F.col("l_partkey").alias("i"), F.col("l_suppkey").alias("j"), F.col("l_quantity").cast("long").alias("c"))


@query("SELECT p_partkey FROM part WHERE p_size IN (1, 5, 9) AND p_retailprice BETWEEN 900 AND 1800 AND p_type LIKE '%E%' AND regexp_matches(p_brand, '[0-9]$') AND p_name IS NOT DISTINCT FROM p_name")
def op_filter_predicates(s: SparkSession, d: str) -> DataFrame:
    p = table(s, d, "part")
    return p.where(F.col("p_size").isin(1, 5, 9) & F.col("p_retailprice").between(900, 1800) & F.col("p_type").like("%E%") & F.col("p_brand").rlike("[0-9]$") & F.col("p_name").eqNullSafe(F.col("p_name"))).select("p_partkey")


@query(f"SELECT l_partkey, l_suppkey FROM lineitem WHERE {S1.sql('l_partkey')} < {PRIME // 10}")
def op_hash_sample(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem").where(poly4("l_partkey", S1) < PRIME // 10).select("l_partkey", "l_suppkey")


@query("SELECT event_id, CAST(props->>'$.k' AS BIGINT) AS k FROM events")
def op_json_project(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("SELECT o_orderkey AS uid, 'year' AS feature, year(o_orderdate)::BIGINT AS v FROM orders UNION ALL SELECT o_orderkey, 'month', month(o_orderdate) FROM orders")
def op_unpivot_features(s: SparkSession, d: str) -> DataFrame:
    o = table(s, d, "orders").select(F.col("o_orderkey").alias("uid"), F.year("o_orderdate").cast("long").alias("year"), F.month("o_orderdate").cast("long").alias("month"))
    return o.unpivot("uid", ["year", "month"], "feature", "v")


@query("SELECT user_id, count(*) FILTER (event_type = 'click')::BIGINT AS click, count(*) FILTER (event_type = 'error')::BIGINT AS error FROM events GROUP BY user_id")
def op_pivot_features(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "error"]).agg(F.count("event_id")).fillna(0)


@query("SELECT o_orderkey AS uid, '00:status=' || o_orderstatus AS f FROM orders UNION ALL SELECT o_orderkey, '01:priority=' || o_orderpriority[1] FROM orders")
def op_onehot(s: SparkSession, d: str) -> DataFrame:
    w = people(s, d)
    return w.long().where(F.col("f").startswith("00:") | F.col("f").startswith("01:"))


@query("SELECT n_name, count(*)::BIGINT AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def op_join_broadcast(s: SparkSession, d: str) -> DataFrame:
    """The nation table has 25 rows at every size; suppliers join by size, as the planner sees it."""
    lines = table(s, d, "lineitem").select("l_suppkey").join(table(s, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    return lines.join(F.broadcast(table(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


_ORDERS_SQL = "SELECT o_orderpriority, count(*)::BIGINT AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority"


def _orders(s: SparkSession, d: str, hint: str) -> DataFrame:
    o = table(s, d, "orders").select("o_orderkey", "o_orderpriority").hint(hint)
    return table(s, d, "lineitem").select("l_orderkey").join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@query(_ORDERS_SQL)
def op_join_sortmerge(s: SparkSession, d: str) -> DataFrame:
    return _orders(s, d, "merge")


@query(_ORDERS_SQL)
def op_join_shuffle_hash(s: SparkSession, d: str) -> DataFrame:
    return _orders(s, d, "shuffle_hash")


@query("SELECT coalesce(a.j, b.j) AS j, coalesce(a.n, 0)::BIGINT - coalesce(b.n, 0)::BIGINT AS diff FROM (SELECT l_suppkey AS j, count(*) AS n FROM lineitem WHERE l_returnflag <> 'R' GROUP BY 1) a FULL JOIN (SELECT l_suppkey AS j, count(*) AS n FROM lineitem WHERE l_returnflag = 'R' GROUP BY 1) b ON a.j = b.j")
def op_join_outer_full(s: SparkSession, d: str) -> DataFrame:
    t = table(s, d, "lineitem")
    count = lambda c, n: t.where(c).groupBy(F.col("l_suppkey").alias("j")).agg(F.count("*").alias(n))
    return count(F.col("l_returnflag") != "R", "a").join(count(F.col("l_returnflag") == "R", "b"), "j", "full").select("j", (F.coalesce("a", F.lit(0)) - F.coalesce("b", F.lit(0))).alias("diff"))


@query("SELECT DISTINCT l_partkey FROM lineitem WHERE l_partkey IN (SELECT l_partkey FROM lineitem WHERE l_suppkey = 1)")
def op_join_semi(s: SparkSession, d: str) -> DataFrame:
    t = table(s, d, "lineitem")
    return t.select("l_partkey").distinct().join(t.where("l_suppkey = 1").select("l_partkey"), "l_partkey", "left_semi")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "documents").select("doc_id").join(table(s, d, "labels"), "doc_id", "left_anti")


@query("SELECT count(*)::BIGINT AS pairs FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey <> b.n_regionkey")
def op_join_theta_pairs(s: SparkSession, d: str) -> DataFrame:
    n = table(s, d, "nation")
    a, b = n.alias("a"), n.alias("b")
    return a.join(b, (F.col("a.n_nationkey") < F.col("b.n_nationkey")) & (F.col("a.n_regionkey") != F.col("b.n_regionkey"))).agg(F.count("*").alias("pairs"))


@query("SELECT count(*)::BIGINT AS differ FROM customer c, (SELECT * FROM customer WHERE c_custkey = 1) t WHERE c.c_nationkey <> t.c_nationkey")
def op_join_cross_target(s: SparkSession, d: str) -> DataFrame:
    c = table(s, d, "customer")
    row = c.where("c_custkey = 1").select(F.col("c_nationkey").alias("t"))
    return c.crossJoin(F.broadcast(row)).where("c_nationkey <> t").agg(F.count("*").alias("differ"))


@query("SELECT b, count(*)::BIGINT AS n FROM orders JOIN (SELECT unnest(range(0, 20)) AS b) ON o_totalprice >= b * 50000 AND o_totalprice < (b + 1) * 50000 GROUP BY b")
def op_join_range_bins(s: SparkSession, d: str) -> DataFrame:
    bins = s.range(20).select(F.col("id").alias("b"), (F.col("id") * 50000).alias("lo"))
    o = table(s, d, "orders").select("o_totalprice", F.floor(F.col("o_totalprice") / 50000).alias("k"))
    return o.join(bins, (F.col("k") == F.col("b")) & (F.col("o_totalprice") >= F.col("lo"))).groupBy("b").agg(F.count("*").alias("n"))


@query("SELECT p.event_id, s.event_id AS signup_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'signup' GROUP BY ALL) s ON p.user_id = s.user_id AND p.ts >= s.ts")
def op_join_asof(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events").where(F.col("event_type").isin("purchase", "signup"))
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    last = F.max(F.when(F.col("event_type") == "signup", F.struct("ts", "event_id"))).over(w)["event_id"]
    return e.select("event_id", "event_type", last.alias("signup_id")).where("event_type = 'purchase'").drop("event_type")


@query("SELECT count(*)::BIGINT AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR")
def op_join_interval(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events").select("user_id", "event_id", "ts", F.date_trunc("hour", "ts").alias("h"))
    a = e.withColumn("h", F.explode(F.array("h", F.col("h") + F.expr("INTERVAL 1 HOUR")))).alias("a")
    b = e.alias("b")
    return a.join(b, (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.h") == F.col("b.h")) & (F.col("a.event_id") != F.col("b.event_id")) & F.col("b.ts").between(F.col("a.ts"), F.col("a.ts") + F.expr("INTERVAL 1 HOUR"))).agg(F.count("*").alias("pairs"))


@query("SELECT p_partkey, unnest(range(0, 3))::INT AS rep FROM part")
def op_lateral_expand(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "part").select("p_partkey", F.explode(F.sequence(F.lit(0), F.lit(2))).alias("rep"))


@query("SELECT l_suppkey AS j, sum(CASE WHEN l_returnflag = 'R' THEN -1 ELSE 1 END)::BIGINT AS s0 FROM lineitem GROUP BY 1")
def op_agg_partial_final(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem").groupBy(F.col("l_suppkey").alias("j")).agg(F.sum(F.when(F.col("l_returnflag") == "R", -1).otherwise(1)).alias("s0"))


@query("SELECT l_suppkey AS j, count(DISTINCT l_partkey)::BIGINT AS n FROM lineitem GROUP BY 1")
def op_agg_distinct(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem").groupBy(F.col("l_suppkey").alias("j")).agg(F.countDistinct("l_partkey").alias("n"))


_SETS = "SELECT g::BIGINT AS g, ((sum(f) * sum(f) - sum(f * f)) // 2)::BIGINT AS separated FROM (SELECT grouping_id(o_orderstatus, o_orderpriority, o_custkey) AS g, count(*)::HUGEINT AS f FROM orders GROUP BY {}) GROUP BY g"


def _separated(grouped: DataFrame) -> DataFrame:
    f = F.col("f").cast("decimal(19,0)")
    return grouped.groupBy("g").agg(((F.sum(f) * F.sum(f) - F.sum(f * f)) / 2).cast("long").alias("separated"))


@query(_SETS.format("CUBE (o_orderstatus, o_orderpriority, o_custkey)"))
def op_agg_cube_pairs(s: SparkSession, d: str) -> DataFrame:
    return _separated(table(s, d, "orders").cube("o_orderstatus", "o_orderpriority", "o_custkey").agg(F.grouping_id().alias("g"), F.count("*").alias("f")))


@query(_SETS.format("ROLLUP (o_orderstatus, o_orderpriority, o_custkey)"))
def op_agg_rollup(s: SparkSession, d: str) -> DataFrame:
    return _separated(table(s, d, "orders").rollup("o_orderstatus", "o_orderpriority", "o_custkey").agg(F.grouping_id().alias("g"), F.count("*").alias("f")))


@query(_SETS.format("GROUPING SETS ((o_orderstatus), (o_orderpriority, o_custkey))"))
def op_agg_grouping_sets(s: SparkSession, d: str) -> DataFrame:
    sets = [[F.col("o_orderstatus")], [F.col("o_orderpriority"), F.col("o_custkey")]]
    return _separated(table(s, d, "orders").groupingSets(sets, "o_orderstatus", "o_orderpriority", "o_custkey").agg(F.grouping_id().alias("g"), F.count("*").alias("f")))


@query("SELECT user_id, sum(1) FILTER (event_type <> 'error')::BIGINT AS plus, coalesce(sum(1) FILTER (event_type = 'error'), 0)::BIGINT AS minus FROM events GROUP BY user_id")
def op_agg_filter_clause(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").groupBy("user_id").agg(F.expr("sum(1) FILTER (WHERE event_type <> 'error')").alias("plus"), F.expr("coalesce(sum(1) FILTER (WHERE event_type = 'error'), 0)").alias("minus"))


@query("SELECT event_type, arg_max(event_id, (value, event_id)) AS top_event, round(median(value), 6) AS med FROM events GROUP BY event_type")
def op_agg_maxby_median(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").groupBy("event_type").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("top_event"), F.round(F.median("value"), 6).alias("med"))


@query(None)
def op_agg_approx(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("hll"), F.expr("theta_sketch_estimate(theta_sketch_agg(l_partkey))").alias("theta"), F.expr("approx_top_k(l_suppkey, 3)").alias("top"))


@query("WITH c AS (SELECT l_suppkey AS j, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1) SELECT j, (row_number() OVER w)::INT AS rn, (rank() OVER v)::INT AS rk, (dense_rank() OVER v)::INT AS dr, (ntile(4) OVER w)::INT AS nt, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd FROM c WINDOW w AS (ORDER BY n DESC, j), v AS (ORDER BY n DESC)")
def op_win_rank_family(s: SparkSession, d: str) -> DataFrame:
    """Over one row a subset: the ranking is of d subsets, not of the data."""
    c = table(s, d, "lineitem").groupBy(F.col("l_suppkey").alias("j")).agg(F.countDistinct("l_partkey").alias("n"))
    w, v = Window.orderBy(F.desc("n"), "j"), Window.orderBy(F.desc("n"))
    return c.select("j", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"))


@query("SELECT i, j FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY j) AS rn FROM (SELECT DISTINCT l_partkey AS i, l_suppkey AS j FROM lineitem)) WHERE rn <= 3")
def op_win_row_cap(s: SparkSession, d: str) -> DataFrame:
    return part_by_supplier(s, d).select("i", "j").distinct().withColumn("rn", F.row_number().over(Window.partitionBy("i").orderBy("j"))).where("rn <= 3").drop("rn")


@query("SELECT i FROM (SELECT i, coalesce(sum(n) OVER (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM (SELECT l_partkey AS i, count(*) AS n FROM lineitem GROUP BY 1)) WHERE before < 1000")
def op_win_running_budget(s: SparkSession, d: str) -> DataFrame:
    """The running total is taken inside ranges of i over the ranges' own totals."""
    rows = table(s, d, "lineitem").groupBy(F.col("l_partkey").alias("i")).agg(F.count("*").alias("n")).withColumn("bin", F.floor(F.col("i") / 64))
    bins = rows.groupBy("bin").agg(F.sum("n").alias("m"))
    base = bins.withColumn("base", F.coalesce(F.sum("m").over(Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).where("base < 1000").select("bin", "base")
    before = F.coalesce(F.sum("n").over(Window.partitionBy("bin").orderBy("i").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows.join(base, "bin").withColumn("before", F.col("base") + before).where("before < 1000").select("i")


@query("SELECT event_id, (count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW))::BIGINT AS n FROM events")
def op_win_range_1h(s: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return table(s, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(w).alias("n"))


@query("SELECT user_id AS i, event_type AS j, (k - coalesce(lag(k) OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id), 0))::BIGINT AS c FROM (SELECT *, CAST(props->>'$.k' AS BIGINT) AS k FROM events)")
def op_win_lag_change(s: SparkSession, d: str) -> DataFrame:
    from ..sources.matrix import change_to_updates

    e = table(s, d, "events").withColumn("k", F.get_json_object("props", "$.k").cast("long"))
    return change_to_updates(e, "user_id", "event_type", "k", ["ts", "event_id"])


@query("SELECT l_suppkey AS j, count(DISTINCT l_partkey)::BIGINT AS n FROM lineitem GROUP BY 1 ORDER BY n DESC, j LIMIT 10")
def op_sort_topk(s: SparkSession, d: str) -> DataFrame:
    return op_agg_distinct(s, d).orderBy(F.desc("n"), "j").limit(10)


@query("SELECT s_nationkey, s_suppkey FROM (SELECT *, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS rn FROM supplier) WHERE rn <= 2")
def op_topk_per_group(s: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("s_nationkey").orderBy(F.desc("s_acctbal"), "s_suppkey")
    return table(s, d, "supplier").withColumn("rn", F.row_number().over(w)).where("rn <= 2").select("s_nationkey", "s_suppkey")


@query("SELECT l_suppkey AS j, count(DISTINCT l_partkey)::BIGINT AS n FROM lineitem GROUP BY 1 ORDER BY n DESC, j LIMIT 5 OFFSET 5")
def op_limit_offset(s: SparkSession, d: str) -> DataFrame:
    return op_agg_distinct(s, d).orderBy(F.desc("n"), "j").offset(5).limit(5)


def _two(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    t = table(s, d, "lineitem")
    return tuple(t.where(F.col("l_suppkey") == k).select("l_partkey") for k in (1, 2))


def _two_sql(word: str) -> str:
    return f"SELECT l_partkey FROM lineitem WHERE l_suppkey = 1 {word} SELECT l_partkey FROM lineitem WHERE l_suppkey = 2"


@query(_two_sql("UNION"))
def op_set_union(s: SparkSession, d: str) -> DataFrame:
    a, b = _two(s, d)
    return a.unionByName(b).distinct()


@query(_two_sql("INTERSECT"))
def op_set_intersect(s: SparkSession, d: str) -> DataFrame:
    a, b = _two(s, d)
    return a.intersect(b)


@query(_two_sql("EXCEPT"))
def op_set_except(s: SparkSession, d: str) -> DataFrame:
    a, b = _two(s, d)
    return a.subtract(b)


@query(r"SELECT w, count(*)::BIGINT AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+')) AS w FROM documents) GROUP BY w")
def op_str_tokens(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "documents").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))).alias("w")).groupBy("w").agg(F.count("*").alias("n"))


@query("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages")
def op_str_host(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))


@query("SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, dayofweek(o_orderdate)::INT AS dow FROM orders")
def op_date_parts(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), (F.dayofweek("o_orderdate") - 1).alias("dow"))


@query(f"SELECT p_partkey, {S1.sql('p_partkey')} AS h, {level_sql(S1.sql('p_partkey'), 20)} AS lvl, ({S1.sql('p_partkey')} % 64)::BIGINT AS slot, (2 * ({S1.sql('p_partkey')} & 1) - 1)::BIGINT AS sg FROM part")
def op_math_hash(s: SparkSession, d: str) -> DataFrame:
    h = poly4("p_partkey", S1)
    return table(s, d, "part").select("p_partkey", h.alias("h"), level(h, 20).alias("lvl"), (h % 64).alias("slot"), sign(h).cast("long").alias("sg"))


@query("SELECT pos::INT AS pos, floor(x * 10)::BIGINT AS bin, count(*)::BIGINT AS n FROM (SELECT unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS pos FROM embeddings) GROUP BY ALL")
def op_array_embedding_bins(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "embeddings").select(F.posexplode("embedding").alias("pos", "x")).groupBy("pos", F.floor(F.col("x").cast("double") * 10).alias("bin")).agg(F.count("*").alias("n"))


@query("SELECT c_custkey, c_nationkey AS nation, c_mktsegment AS segment FROM customer")
def op_map_features(s: SparkSession, d: str) -> DataFrame:
    m = F.map_from_arrays(F.array(F.lit("nation"), F.lit("segment")), F.array(F.col("c_nationkey").cast("string"), F.col("c_mktsegment")))
    return table(s, d, "customer").select("c_custkey", m.alias("m")).select("c_custkey", F.col("m")["nation"].cast("int").alias("nation"), F.col("m")["segment"].alias("segment"))


@query("SELECT l_returnflag AS v, CASE WHEN f < 0.75 * 0.1 * n THEN 'all_small' WHEN f > n / 2 THEN 'dominant' ELSE 'middle' END AS branch FROM (SELECT l_returnflag, count(*) AS f, (SELECT count(*) FROM lineitem) AS n FROM lineitem GROUP BY 1)")
def op_case_branches(s: SparkSession, d: str) -> DataFrame:
    t = table(s, d, "lineitem")
    f = t.groupBy(F.col("l_returnflag").alias("v")).agg(F.count("*").alias("f")).crossJoin(F.broadcast(t.agg(F.count("*").alias("n"))))
    return f.select("v", F.when(F.col("f") < 0.75 * 0.1 * F.col("n"), "all_small").when(F.col("f") > F.col("n") / 2, "dominant").otherwise("middle").alias("branch"))


def _sql(s: SparkSession, d: str, text: str, *names: str) -> DataFrame:
    """Run SQL over tables given as arguments: no session-wide view is left behind."""
    return s.sql(text, **{n: table(s, d, n) for n in names})


@query("SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_suppkey = s_suppkey AND l_partkey = 7)")
def op_subquery_exists(s: SparkSession, d: str) -> DataFrame:
    return _sql(s, d, "SELECT s_suppkey FROM {supplier} WHERE EXISTS (SELECT 1 FROM {lineitem} WHERE l_suppkey = s_suppkey AND l_partkey = 7)", "supplier", "lineitem")


@query("SELECT l_suppkey AS j, count(*)::BIGINT AS n FROM lineitem GROUP BY 1 HAVING count(*) > (SELECT count(*) / count(DISTINCT l_suppkey) FROM lineitem)")
def op_subquery_scalar(s: SparkSession, d: str) -> DataFrame:
    return _sql(s, d, "SELECT l_suppkey AS j, count(*) AS n FROM {lineitem} GROUP BY 1 HAVING count(*) > (SELECT count(*) / count(DISTINCT l_suppkey) FROM {lineitem})", "lineitem")


@query("WITH RECURSIVE g(m, p, parts) AS (SELECT 0, 1.0::DOUBLE, count(DISTINCT l_partkey)::DOUBLE FROM lineitem UNION ALL SELECT m + 1, p / 2, parts / 2 FROM g WHERE m < 10) SELECT m::INT AS m, p, parts FROM g")
def op_recursive_levels(s: SparkSession, d: str) -> DataFrame:
    """The share and the number of the ordered parts that each row level is to hold."""
    return _sql(s, d, "WITH RECURSIVE g(m, p, parts) AS (SELECT 0, CAST(1.0 AS DOUBLE), CAST(count(DISTINCT l_partkey) AS DOUBLE) FROM {lineitem} UNION ALL SELECT m + 1, p / 2, parts / 2 FROM g WHERE m < 10) SELECT m, p, parts FROM g", "lineitem")


@query(f"SELECT p_partkey, {S1.sql('p_partkey')} AS h FROM part")
def op_sql_udf_hash(s: SparkSession, d: str) -> DataFrame:
    from .sqlsurface import register

    register(s)
    return _sql(s, d, "SELECT p_partkey, tc_hash(p_partkey) AS h FROM {part}", "part")


@query(f"SELECT p_partkey, (2 * ({S1.sql('p_partkey')} & 1) - 1)::BIGINT AS sg FROM part")
def op_pandas_udf_sign(s: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("long")
    def sg(h: pd.Series) -> pd.Series:
        return 2 * (h & 1) - 1

    return table(s, d, "part").select("p_partkey", sg(poly4("p_partkey", S1)).alias("sg"))


@query(None)
def op_udtf_select(s: SparkSession, d: str) -> DataFrame:
    from .sqlsurface import register

    register(s)
    entries = net(part_by_supplier(s, d)).select("i", "j")
    return s.sql("SELECT * FROM coverage_select(TABLE({entries}) WITH SINGLE PARTITION, 5)", entries=entries)


@query(net_sql("c1t").replace("AS v", "AS c"))
def op_io_roundtrip(s: SparkSession, d: str) -> DataFrame:
    u = net(part_by_supplier_returns(s, d)).withColumnRenamed("v", "c")
    for form in ("parquet", "orc", "json", "csv"):
        path = noted(f"{shared_folder(s)}/updates-{form}-{uuid.uuid4().hex}")
        write_updates(u, path, form)
        u = read_updates(s, path, form)
    return u.select("i", "j", "c")


@query(l0.build_sql(net_sql("c4t").replace("AS v", "AS c"), "j", slots=256, reps=1, levels=12))
def op_cells_events(s: SparkSession, d: str) -> DataFrame:
    from ..streaming.streams import column_cells

    return column_cells(table(s, d, "events"))

"""Surrounding operators: scans, joins, aggregations, windows, sets, functions, UDFs, sinks."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from tolerant_gd.functions import udx
from tolerant_gd.operators import layout, relops
from tolerant_gd.sources.tables import SCHEMAS, read, read_files, shared_folder, write_files

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def add(name: str, sql: str):
    def register(f):
        QUERIES[name], ORACLES[name] = f, sql
        return f

    return register


@add("op_scan_all_tables", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in sorted(SCHEMAS)))
def _scan(s, d):
    out = None
    for t in sorted(SCHEMAS):
        one = read(s, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.union(one)
    return out


@add("op_filter_project", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * 100)::BIGINT * (100 - round(l_discount * 100)::BIGINT) AS net, CASE WHEN l_quantity > 40 THEN 'large' WHEN l_quantity > 20 THEN 'mid' ELSE 'small' END AS bin FROM lineitem WHERE l_discount BETWEEN 0.05 AND 0.07 AND l_returnflag IN ('R', 'A') AND l_shipdate >= TIMESTAMP '1997-01-01'")
def _filter(s, d):
    li = read(s, d, "lineitem").where("l_discount BETWEEN 0.05 AND 0.07 AND l_returnflag IN ('R', 'A') AND l_shipdate >= TIMESTAMP_NTZ '1997-01-01'")
    size = F.when(F.col("l_quantity") > 40, "large").when(F.col("l_quantity") > 20, "mid").otherwise("small")
    return li.select("l_orderkey", "l_linenumber", (F.round(F.col("l_extendedprice") * 100).cast("bigint") * (100 - F.round(F.col("l_discount") * 100).cast("bigint"))).alias("net"), size.alias("bin"))


@add("op_join_inner", "SELECT c_mktsegment, count(*) AS n, CAST(sum(round(o_totalprice * 100)) AS BIGINT) AS cents FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def _inner(s, d):
    o, c = read(s, d, "orders").select("o_custkey", "o_totalprice"), read(s, d, "customer").select("c_custkey", "c_mktsegment")
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents"))


@add("op_join_left_padding", "SELECT c_custkey, count(o_orderkey) AS n, coalesce(CAST(sum(round(o_totalprice * 100)) AS BIGINT), 0) AS cents FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")
def _left(s, d):
    o = read(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents"))
    return read(s, d, "customer").select("c_custkey").join(o, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("cents", F.lit(0)).alias("cents"))


@add("op_join_full", "SELECT coalesce(a.k, b.k) AS k, a.n AS n1, b.n AS n2 FROM (SELECT o_custkey % 50 AS k, count(*) AS n FROM orders WHERE o_orderstatus = 'F' AND o_custkey % 50 < 40 GROUP BY 1) a FULL JOIN (SELECT o_custkey % 50 AS k, count(*) AS n FROM orders WHERE o_orderstatus = 'O' AND o_custkey % 50 > 10 GROUP BY 1) b ON a.k = b.k")
def _full(s, d):
    o = read(s, d, "orders").select((F.col("o_custkey") % 50).alias("k"), "o_orderstatus")
    a = o.where("o_orderstatus = 'F' and k < 40").groupBy("k").agg(F.count("*").alias("n1"))
    b = o.where("o_orderstatus = 'O' and k > 10").groupBy("k").agg(F.count("*").alias("n2"))
    return a.join(b, "k", "full")


@add("op_join_semi", "SELECT p_partkey, p_brand FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity >= 49)")
def _semi(s, d):
    return read(s, d, "part").select("p_partkey", "p_brand").join(read(s, d, "lineitem").where("l_quantity >= 49").select("l_partkey"), F.col("p_partkey") == F.col("l_partkey"), "left_semi")


@add("op_join_anti", "SELECT c_custkey, c_name FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def _anti(s, d):
    return read(s, d, "customer").select("c_custkey", "c_name").join(read(s, d, "orders").select("o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@add("op_join_cross_small", "SELECT n_name, r_name FROM nation, region")
def _cross(s, d):
    return read(s, d, "nation").select("n_name").crossJoin(F.broadcast(read(s, d, "region").select("r_name")))


@add("op_join_null_safe", "SELECT count(*) AS n FROM (SELECT nullif(s_nationkey, 3) AS k FROM supplier) a JOIN (SELECT nullif(n_nationkey, 3) AS k FROM nation) b ON a.k IS NOT DISTINCT FROM b.k")
def _null_safe(s, d):
    a = read(s, d, "supplier").select(F.expr("nullif(s_nationkey, 3)").alias("a"))
    b = read(s, d, "nation").select(F.expr("nullif(n_nationkey, 3)").alias("b"))
    return a.join(b, F.col("a").eqNullSafe(F.col("b"))).agg(F.count("*").alias("n"))


@add("op_join_self", "SELECT a.n_nationkey AS k1, b.n_nationkey AS k2 FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def _self(s, d):
    n = read(s, d, "nation").select("n_nationkey", "n_regionkey")
    return n.alias("a").join(n.alias("b"), F.expr("a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")).select(F.col("a.n_nationkey").alias("k1"), F.col("b.n_nationkey").alias("k2"))


@add("op_join_salted", "SELECT l_returnflag, count(*) AS n, CAST(sum(w) AS BIGINT) AS w FROM lineitem JOIN (VALUES ('A', 1), ('N', 2), ('R', 3)) v(l_returnflag, w) USING (l_returnflag) GROUP BY 1")
def _salted(s, d):
    right = s.createDataFrame([("A", 1), ("N", 2), ("R", 3)], "l_returnflag string, w int")
    return relops.salted_join(read(s, d, "lineitem").select("l_returnflag", "l_orderkey"), right, "l_returnflag", F.col("l_orderkey")).groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum("w").alias("w"))


@add("op_join_as_of", "SELECT event_id, (SELECT p.event_id FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts ORDER BY p.ts DESC, p.event_id DESC LIMIT 1) AS last_purchase FROM events e WHERE event_type = 'view'")
def _as_of(s, d):
    e = read(s, d, "events").select("event_id", "user_id", "ts", "event_type")
    buys = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase"))
    return relops.as_of(e.where("event_type = 'view'").select("event_id", "user_id", "ts"), buys, "user_id", "ts", "purchase").select("event_id", "last_purchase")


@add("op_join_range", "SELECT low, count(*) AS n FROM orders JOIN (SELECT i * 30000 AS low, i * 30000 + 20000 AS high FROM generate_series(0, 9) t(i)) ON o_totalprice >= low AND o_totalprice < high GROUP BY 1")
def _range(s, d):
    bins = s.range(10).select((F.col("id") * 30000).alias("low"), (F.col("id") * 30000 + 20000).alias("high"))
    return relops.range_join(read(s, d, "orders").select("o_totalprice"), bins, "o_totalprice", "low", "high", 10000).groupBy("low").agg(F.count("*").alias("n"))


@add("op_aggregates", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(round(l_quantity)) AS BIGINT) AS qty, min(l_tax) AS least_tax, max(l_discount) AS most_discount, count(DISTINCT l_partkey) AS parts, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS corr, round(regr_slope(l_extendedprice, l_quantity), 3) AS slope, bool_and(l_quantity > 0) AS positive FROM lineitem GROUP BY 1, 2")
def _aggregates(s, d):
    return read(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.sum(F.round("l_quantity").cast("bigint")).alias("qty"), F.min("l_tax").alias("least_tax"), F.max("l_discount").alias("most_discount"),
        F.countDistinct("l_partkey").alias("parts"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"),
        F.round(F.regr_slope("l_extendedprice", "l_quantity"), 3).alias("slope"), F.bool_and(F.col("l_quantity") > 0).alias("positive"),
    )


@add("op_coverage_mask", "SELECT user_id % 20 AS worker, CAST(bit_or(1::BIGINT << (event_id % 40)) AS BIGINT) AS mask, bit_count(bit_or(1::BIGINT << (event_id % 40)))::INT AS codes FROM events GROUP BY 1")
def _mask(s, d):
    m = F.bit_or(F.expr("shiftleft(1L, cast(event_id % 40 as int))"))
    return read(s, d, "events").groupBy((F.col("user_id") % 20).alias("worker")).agg(m.alias("mask"), F.bit_count(m).cast("int").alias("codes"))


@add("op_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def _rollup(s, d):
    return read(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@add("op_cube", "SELECT c_mktsegment, c_nationkey % 5 AS part, count(*) AS n FROM customer GROUP BY CUBE (c_mktsegment, c_nationkey % 5)")
def _cube(s, d):
    return read(s, d, "customer").cube("c_mktsegment", (F.col("c_nationkey") % 5).alias("part")).agg(F.count("*").alias("n"))


@add("op_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def _sets(s, d):
    read(s, d, "orders").createOrReplaceTempView("orders_for_sets")
    return s.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders_for_sets GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


@add("op_pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY 1")
def _pivot(s, d):
    return read(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().fillna(0)


@add("op_percentiles", "SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS mid, quantile_cont(l_quantity, 0.9) AS high FROM lineitem GROUP BY 1")
def _percentiles(s, d):
    return read(s, d, "lineitem").groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.5).alias("mid"), F.percentile("l_quantity", 0.9).alias("high"))


@add("op_approximate", "SELECT true AS near_distinct, true AS near_median, l_returnflag FROM lineitem GROUP BY l_returnflag")
def _approximate(s, d):
    li = read(s, d, "lineitem")
    near = F.abs(F.approx_count_distinct("l_partkey", 0.02) - F.countDistinct("l_partkey")) <= 0.1 * F.countDistinct("l_partkey")
    mid = F.abs(F.percentile_approx("l_quantity", 0.5, 1000) - F.percentile("l_quantity", 0.5)) <= 1
    return li.groupBy("l_returnflag").agg(near.alias("near_distinct"), mid.alias("near_median"))


@add("op_join_strategies", "SELECT h, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey, (VALUES ('merge'), ('shuffle_hash'), ('broadcast')) v(h) GROUP BY h")
def _strategies(s, d):
    o, c, out = read(s, d, "orders").select("o_custkey"), read(s, d, "customer").select("c_custkey"), None
    for hint in ("merge", "shuffle_hash", "broadcast"):
        side = relops.broadcast_if_small(c) if hint == "broadcast" else c.hint(hint)
        one = o.join(side, F.col("o_custkey") == F.col("c_custkey")).agg(F.count("*").alias("n")).select(F.lit(hint).alias("h"), "n")
        out = one if out is None else out.union(one)
    return out


def _ranked(orders):
    """Ranks, tiles, lags and running sums of every customer's orders."""
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    p = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return orders.select("o_custkey", "o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(p).alias("rk"), F.dense_rank().over(p).alias("dr"), F.ntile(3).over(w).alias("third"), F.lag("o_orderkey").over(w).alias("before"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"))


@add("op_window_ranks", "SELECT o_custkey, o_orderkey, row_number() OVER w AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS dr, CAST(ntile(3) OVER w AS INT) AS third, lag(o_orderkey) OVER w AS before, CAST(sum(round(o_totalprice * 100)) OVER (w ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def _ranks(s, d):
    return _ranked(read(s, d, "orders"))


@add("op_window_distribution", "SELECT c_custkey, round(cume_dist() OVER w, 6) AS cd, round(percent_rank() OVER w, 6) AS pr, first_value(c_custkey) OVER w AS f, max(c_acctbal) OVER (PARTITION BY c_mktsegment ORDER BY c_custkey ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_custkey)")
def _distribution(s, d):
    w = Window.partitionBy("c_mktsegment").orderBy("c_custkey")
    return read(s, d, "customer").select("c_custkey", F.round(F.cume_dist().over(w), 6).alias("cd"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.first("c_custkey").over(w).alias("f"), F.max("c_acctbal").over(w.rowsBetween(-2, 2)).alias("near"))


@add("op_window_range_frame", "SELECT conv_id, turn, count(*) OVER (PARTITION BY conv_id ORDER BY turn RANGE BETWEEN 1 PRECEDING AND CURRENT ROW) AS n FROM conversations")
def _frame(s, d):
    w = Window.partitionBy("conv_id").orderBy("turn").rangeBetween(-1, 0)
    return read(s, d, "conversations").select("conv_id", "turn", F.count("*").over(w).alias("n"))


@add("op_top_k", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 20")
def _top(s, d):
    return read(s, d, "lineitem").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey").limit(20).select("l_orderkey", "l_linenumber", "l_extendedprice")


@add("op_top_k_per_group", "SELECT c_nationkey, c_custkey, c_acctbal FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS n FROM customer) WHERE n <= 3")
def _top_group(s, d):
    return relops.top_per_group(read(s, d, "customer").select("c_nationkey", "c_custkey", "c_acctbal"), ["c_nationkey"], [F.desc("c_acctbal"), F.col("c_custkey")], 3)


@add("op_nth_smallest", "SELECT user_id % 20 AS worker, list_sort(list(event_id))[10] AS tenth FROM events GROUP BY 1")
def _nth(s, d):
    w = (F.col("user_id") % 20).alias("worker")
    return relops.top_per_group(read(s, d, "events").select(w, "event_id"), ["worker"], [F.col("event_id")], 10).groupBy("worker").agg(F.max("event_id").alias("tenth"))


@add("op_set_operations", "SELECT 'union' AS op, count(*) AS n FROM (SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 45 UNION SELECT p_partkey FROM part WHERE p_size < 10) UNION ALL SELECT 'intersect', count(*) FROM (SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 45 INTERSECT SELECT p_partkey FROM part WHERE p_size < 10) UNION ALL SELECT 'except', count(*) FROM (SELECT p_partkey AS k FROM part WHERE p_size < 10 EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 45) UNION ALL SELECT 'except_all', count(*) FROM (SELECT l_linenumber FROM lineitem WHERE l_quantity > 45 EXCEPT ALL SELECT l_linenumber FROM lineitem WHERE l_quantity > 48)")
def _set_ops(s, d):
    li, p = read(s, d, "lineitem"), read(s, d, "part").where("p_size < 10").select(F.col("p_partkey").alias("k"))
    a = li.where("l_quantity > 45").select(F.col("l_partkey").alias("k"))

    def row(op, df):
        return df.agg(F.count("*").alias("n")).select(F.lit(op).alias("op"), "n")

    lines = row("except_all", li.where("l_quantity > 45").select("l_linenumber").exceptAll(li.where("l_quantity > 48").select("l_linenumber")))
    return row("union", a.union(p).distinct()).union(row("intersect", a.intersect(p))).union(row("except", p.subtract(a))).union(lines)


@add("op_strings", "SELECT c_custkey, upper(c_mktsegment) AS up, CAST(length(c_name) AS INT) AS n, substr(c_name, 1, 8) AS head, CAST(regexp_extract(c_name, '([0-9]+)', 1) AS BIGINT) AS number, concat_ws('-', c_mktsegment, CAST(c_nationkey AS VARCHAR)) AS tag, replace(c_name, '#', '') AS bare FROM customer")
def _strings(s, d):
    c = read(s, d, "customer")
    return c.select("c_custkey", F.upper("c_mktsegment").alias("up"), F.length("c_name").alias("n"), F.substring("c_name", 1, 8).alias("head"), F.regexp_extract("c_name", "([0-9]+)", 1).cast("bigint").alias("number"), F.concat_ws("-", "c_mktsegment", F.col("c_nationkey").cast("string")).alias("tag"), F.replace(F.col("c_name"), F.lit("#"), F.lit("")).alias("bare"))


@add("op_dates", "SELECT date_part('year', o_orderdate)::INT AS y, date_part('month', o_orderdate)::INT AS m, count(*) AS n, CAST(min(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE))) AS INT) AS first_day, CAST(max(CAST(o_orderdate AS DATE)) AS VARCHAR) AS last FROM orders GROUP BY 1, 2")
def _dates(s, d):
    o = read(s, d, "orders").withColumn("day", F.col("o_orderdate").cast("date"))
    return o.groupBy(F.year("day").alias("y"), F.month("day").alias("m")).agg(F.count("*").alias("n"), F.min(F.datediff("day", F.lit("1992-01-01").cast("date"))).alias("first_day"), F.max("day").cast("string").alias("last"))


@add("op_math", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 4) AS norm, CAST(len(embedding) AS INT) AS d, round(ln(1 + vec_id), 6) AS l, CAST(vec_id % 7 AS BIGINT) AS m, CAST(greatest(vec_id, 100) AS BIGINT) AS g, round(pow(vec_id, 0.5), 6) AS p FROM embeddings")
def _math(s, d):
    e = read(s, d, "embeddings")
    norm = F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))
    return e.select("vec_id", F.round(norm, 4).alias("norm"), F.size("embedding").alias("d"), F.round(F.log1p(F.col("vec_id")), 6).alias("l"), F.pmod("vec_id", F.lit(7)).alias("m"), F.greatest("vec_id", F.lit(100)).alias("g"), F.round(F.pow("vec_id", F.lit(0.5)), 6).alias("p"))


@add("op_arrays", "SELECT vec_id, CAST(round(list_max(embedding) * 1e4) AS BIGINT) AS most, CAST(list_position(embedding, list_max(embedding)) AS BIGINT) AS place, len(list_filter(embedding, lambda x: x > 0))::INT AS positive, CAST(round(embedding[3] * 1e4) AS BIGINT) AS third FROM embeddings")
def _arrays(s, d):
    e = read(s, d, "embeddings")
    return e.select("vec_id", F.round(F.array_max("embedding") * 1e4).cast("bigint").alias("most"), F.expr("array_position(embedding, array_max(embedding))").alias("place"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.element_at("embedding", 3) * 1e4).cast("bigint").alias("third"))


@add("op_json", "SELECT CAST(json_extract(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1")
def _json(s, d):
    return read(s, d, "events").select(F.from_json("props", "k int").alias("p")).groupBy(F.col("p.k").alias("k")).agg(F.count("*").alias("n"))


@add("op_maps", "SELECT conv_id, count(*) FILTER (role = 'user') AS users, count(*) FILTER (role = 'assistant') AS assistants FROM conversations GROUP BY 1")
def _maps(s, d):
    counts = read(s, d, "conversations").groupBy("conv_id", "role").agg(F.count("*").alias("n"))
    m = counts.groupBy("conv_id").agg(F.map_from_entries(F.collect_list(F.struct("role", "n"))).alias("m"))
    return m.select("conv_id", F.coalesce(F.try_element_at("m", F.lit("user")), F.lit(0)).alias("users"), F.coalesce(F.try_element_at("m", F.lit("assistant")), F.lit(0)).alias("assistants"))


@add("op_url_parts", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '://([^/?#]+)', 1) AS host FROM pages")
def _urls(s, d):
    return read(s, d, "pages").select("page_id", F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"), F.regexp_extract("url", "://([^/?#]+)", 1).alias("host"))


@add("op_turn_order", "SELECT conv_id, turn, role, coalesce(lag(role) OVER (PARTITION BY conv_id ORDER BY turn), 'none') AS before FROM conversations")
def _turns(s, d):
    return read(s, d, "conversations").select("conv_id", "turn", "role", F.coalesce(F.lag("role").over(Window.partitionBy("conv_id").orderBy("turn")), F.lit("none")).alias("before"))


@add("op_udf_weights", "SELECT id, round(1 / ((a - b) * (a - c)), 9) AS w0, round(1 / ((b - a) * (b - c)), 9) AS w1 FROM (SELECT i AS id, CAST(i AS DOUBLE) AS a, CAST(i + 2 AS DOUBLE) AS b, CAST(i + 7 AS DOUBLE) AS c FROM generate_series(0, 99) t(i))")
def _udf(s, d):
    p = s.range(100).select("id", F.array(*[(F.col("id") + k).cast("double") for k in (0, 2, 7)]).alias("p"))
    return p.select("id", udx.decode_weights("p").alias("w")).select("id", F.round(F.get("w", F.lit(0)), 9).alias("w0"), F.round(F.get("w", F.lit(1)), 9).alias("w1"))


@add("op_udaf_nth", "SELECT user_id % 20 AS worker, list_sort(list(event_id))[15] AS nth FROM events GROUP BY 1")
def _udaf(s, d):
    e = read(s, d, "events").select((F.col("user_id") % 20).alias("worker"), "event_id", F.lit(15).alias("need"))
    return e.groupBy("worker").agg(udx.nth_arrival("event_id", "need").alias("nth"))


@add("op_udtf_layout", "SELECT CAST(w AS INT) AS worker, CAST(j AS INT) AS ord, CAST((w + j) % 6 AS INT) AS batch FROM generate_series(0, 5) a(w), generate_series(0, 2) b(j)")
def _udtf(s, d):
    udx.register(s)
    return s.sql("SELECT * FROM cyclic_layout(6, 3)")


@add("op_udtf_messages", "SELECT CAST(w AS INT) AS worker, CAST(q AS INT) AS step, CAST((w + q) % 6 AS INT) AS code, CAST(2 + q AS INT) AS needs, 5 AS need FROM generate_series(0, 5) a(w), generate_series(0, 1) b(q)")
def _udtf_messages(s, d):
    udx.register(s)
    return s.sql("SELECT * FROM scheme_messages('gradcode_shared', 6, 3, 2)")


@add("op_udtf_completion", "SELECT count(*) AS trials, true AS sane FROM generate_series(1, 500)")
def _udtf_completion(s, d):
    udx.register(s)
    return s.sql("SELECT count(*) AS trials, avg(t) BETWEEN 0.14 AND 0.2 AND avg(load) BETWEEN 95 AND 115 AS sane FROM completion('uncoded_multi', 40, 10, 500)")


def _folder(s) -> str:
    return f"{shared_folder(s)}/sink-{uuid.uuid4().hex[:8]}"


def _round_trip(kind: str):
    def query(s, d):
        path = _folder(s)
        df = layout.clustered_layout(s, 20, 4, 5)
        write_files(df, path, kind, **({"header": "true"} if kind == "csv" else {}))
        return read_files(s, path, kind, "worker int, ord int, batch int", **({"header": "true"} if kind == "csv" else {}))

    return query


_LAYOUT = "SELECT CAST(w AS INT) AS worker, CAST(j AS INT) AS ord, CAST(w // 4 * 4 + (w % 4 + j) % 4 AS INT) AS batch FROM generate_series(0, 19) a(w), generate_series(0, 3) b(j)"
for _kind in ("csv", "json", "orc"):
    QUERIES[f"op_sink_{_kind}"], ORACLES[f"op_sink_{_kind}"] = _round_trip(_kind), _LAYOUT


@add("op_sink_partitioned", f"SELECT worker, ord, batch FROM ({_LAYOUT}) WHERE worker IN (1, 3, 5)")
def _partitioned(s, d):
    path = _folder(s)
    write_files(layout.clustered_layout(s, 20, 4, 5), path, "parquet", by=["worker"])
    return read_files(s, path, "parquet", "ord int, batch int, worker int").where("worker IN (1, 3, 5)").select("worker", "ord", "batch")


@add("op_classify_documents", "SELECT lang, quality, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2")
def _classify(s, d):
    return read(s, d, "documents").select("doc_id", "lang", "n_chars").join(read(s, d, "labels").select("doc_id", "quality"), "doc_id").groupBy("lang", "quality").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@add("op_benchmark_text_anti", "SELECT item_id FROM benchmark WHERE NOT EXISTS (SELECT 1 FROM documents WHERE documents.text = benchmark.text)")
def _bench_anti(s, d):
    docs = read(s, d, "documents").select(F.xxhash64("text").alias("h"), "text")
    b = read(s, d, "benchmark").withColumn("h", F.xxhash64("text"))
    return b.alias("b").join(docs.alias("d"), F.expr("b.h = d.h and b.text = d.text"), "left_anti").select("item_id")

"""Single operators a user of the estimators needs, on the given tables: name -> (query, DuckDB text)."""

from __future__ import annotations

from pyspark.sql import Window, functions as F

from ..functions.hashing import coin, coin_sql
from ..sources.graphs import stream, stream_sql
from ..sources.tables import table
from . import oracles as sql

RELATIONAL = {}
E_SQL = [("e", stream_sql("coactivity"))]


def op(name: str, text: str):
    def keep(run):
        RELATIONAL[f"rel_{name}"] = (run, text)
        return run

    return keep


def over_edges(name: str, text: str):
    """An operator on the co-activity stream ``e``."""

    def keep(run):
        RELATIONAL[f"rel_{name}"] = (lambda spark, d: run(stream(spark, d, "coactivity")), sql.chain(E_SQL, text))
        return run

    return keep


@op("scan_pruned", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_quantity BETWEEN 10 AND 12")
def _(spark, d):
    return table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_shipdate", "l_quantity").where("l_shipdate >= timestamp_ntz'1995-01-01' and l_quantity between 10 and 12").select("l_orderkey", "l_partkey")


@op("filter_in_like", "SELECT c_custkey, c_name FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY') AND c_name LIKE '%7'")
def _(spark, d):
    return table(spark, d, "customer").where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY") & F.col("c_name").like("%7")).select("c_custkey", "c_name")


@op("null_safe_equal", "SELECT count(*) AS n FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.toxic IS NOT DISTINCT FROM NULL")
def _(spark, d):
    rows = table(spark, d, "documents", "doc_id").join(table(spark, d, "labels", "doc_id", "toxic"), "doc_id", "left")
    return rows.where(F.col("toxic").eqNullSafe(F.lit(None))).agg(F.count(F.lit(1)).alias("n"))


@op("join_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(spark, d):
    # 25 nations, whatever the scale.
    return table(spark, d, "customer", "c_nationkey").join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


@op("join_merge", "SELECT o_orderstatus, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderstatus")
def _(spark, d):
    lines = table(spark, d, "lineitem", "l_orderkey").hint("merge")
    return table(spark, d, "orders", "o_orderkey", "o_orderstatus").join(lines, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@op("join_shuffle_hash", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def _(spark, d):
    return table(spark, d, "orders", "o_custkey").join(table(spark, d, "customer", "c_custkey", "c_mktsegment").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@over_edges("semi_join_closed", "SELECT u, v FROM e WHERE EXISTS (SELECT 1 FROM e a WHERE a.u = e.v)")
def _(e):
    return e.join(e.select(F.col("u").alias("x")).distinct(), F.col("v") == F.col("x"), "left_semi").select("u", "v")


@over_edges("anti_join_sinks", "SELECT DISTINCT v AS node FROM e WHERE NOT EXISTS (SELECT 1 FROM e a WHERE a.u = e.v)")
def _(e):
    return e.select(F.col("v").alias("node")).distinct().join(e.select(F.col("u").alias("node")), "node", "left_anti")


@op("outer_join_truth", "SELECT count(*) AS n, count(a.id) AS l, count(b.id) AS r FROM (SELECT DISTINCT user_id AS id FROM events WHERE event_type = 'click') a FULL JOIN (SELECT DISTINCT user_id AS id FROM events WHERE value > 50) b ON a.id = b.id")
def _(spark, d):
    events = table(spark, d, "events", "user_id", "event_type", "value")
    a = events.where("event_type = 'click'").select(F.col("user_id").alias("a")).distinct()
    b = events.where("value > 50").select(F.col("user_id").alias("b")).distinct()
    return a.join(b, F.col("a") == F.col("b"), "full").agg(F.count(F.lit(1)).alias("n"), F.count("a").alias("l"), F.count("b").alias("r"))


@op("parameter_grid", "SELECT r_name, CAST(k AS INTEGER) AS k, b FROM region, (VALUES (5), (10), (30)) g(k), (VALUES (0.02), (0.05)) h(b)")
def _(spark, d):
    ks, bs = F.explode(F.array(*[F.lit(k) for k in (5, 10, 30)])), F.explode(F.array(F.lit(0.02), F.lit(0.05)))
    return table(spark, d, "region", "r_name").withColumn("k", ks).withColumn("b", bs)


@op("theta_join_dominance", "SELECT a.s_suppkey, count(*) AS n FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal > b.s_acctbal GROUP BY 1")
def _(spark, d):
    s = table(spark, d, "supplier", "s_suppkey", "s_nationkey", "s_acctbal")
    other = s.select(F.col("s_nationkey"), F.col("s_acctbal").alias("less"))
    return s.join(other, "s_nationkey").where("s_acctbal > less").groupBy("s_suppkey").agg(F.count(F.lit(1)).alias("n"))


@over_edges("range_join_bins", "SELECT a.t, count(*) AS n FROM e a JOIN e b ON b.t > a.t AND b.t <= a.t + 5 AND a.u = b.u GROUP BY a.t")
def _(e):
    # Bins of the range's width make the range join an equi-join with one neighbour bin.
    width = 5
    left = e.select("u", "t", F.explode(F.array(F.floor(F.col("t") / width), F.floor(F.col("t") / width) + 1)).alias("bin"))
    right = e.select("u", F.col("t").alias("t2"), F.floor(F.col("t") / width).alias("bin"))
    return left.join(right, ["u", "bin"]).where((F.col("t2") > F.col("t")) & (F.col("t2") <= F.col("t") + width)).groupBy("t").agg(F.count(F.lit(1)).alias("n"))


@op("asof_join", "SELECT p.event_id, c.event_id AS click FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.event_id > c.event_id")
def _(spark, d):
    rows = table(spark, d, "events", "event_id", "user_id", "event_type").where(F.col("event_type").isin("purchase", "click"))
    past = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(past)
    return rows.withColumn("click", last).where("event_type = 'purchase' and click is not null").select("event_id", "click")


@op("aggregate_statistics", "SELECT event_type, count(*) AS n, min(value) AS lo, max(value) AS hi, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS sd, round(var_pop(value), 6) AS var, count(DISTINCT user_id) AS users, CAST(count_if(value > 10) AS BIGINT) AS big, max_by(event_id, value) AS at FROM events GROUP BY event_type")
def _(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(
        F.count(F.lit(1)).alias("n"), F.min("value").alias("lo"), F.max("value").alias("hi"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev_samp("value"), 6).alias("sd"),
        F.round(F.var_pop("value"), 6).alias("var"), F.count_distinct("user_id").alias("users"), F.count_if(F.col("value") > 10).alias("big"), F.max_by("event_id", "value").alias("at"),
    )


@op("regression", "SELECT round(regr_slope(l_extendedprice, l_quantity), 6) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 4) AS base, round(regr_r2(l_extendedprice, l_quantity), 8) AS r2, round(corr(l_extendedprice, l_quantity), 8) AS r FROM lineitem")
def _(spark, d):
    y, x = "l_extendedprice", "l_quantity"
    return table(spark, d, "lineitem", x, y).agg(F.round(F.regr_slope(y, x), 6).alias("slope"), F.round(F.regr_intercept(y, x), 4).alias("base"), F.round(F.regr_r2(y, x), 8).alias("r2"), F.round(F.corr(y, x), 8).alias("r"))


@op("percentiles", "SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS mid, quantile_cont(l_quantity, 0.9) AS high FROM lineitem GROUP BY 1")
def _(spark, d):
    return table(spark, d, "lineitem", "l_returnflag", "l_quantity").groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.5).alias("mid"), F.percentile("l_quantity", 0.9).alias("high"))


@op("approx_distinct", "")
def _(spark, d):
    return table(spark, d, "lineitem", "l_partkey").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@op("rollup_costs", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def _(spark, d):
    return table(spark, d, "lineitem", "l_returnflag", "l_linestatus").rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


@op("cube_costs", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def _(spark, d):
    return table(spark, d, "orders", "o_orderstatus", "o_orderpriority").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@op("grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source))")
def _(spark, d):
    lang, source = F.col("lang"), F.col("source")
    return table(spark, d, "documents", "lang", "source").groupingSets([[lang], [source]], lang, source).agg(F.count(F.lit(1)).alias("n"))


@op("pivot_methods", "SELECT l_linestatus, CAST(sum(CASE WHEN l_returnflag = 'A' THEN 1 END) AS BIGINT) AS \"A\", CAST(sum(CASE WHEN l_returnflag = 'R' THEN 1 END) AS BIGINT) AS \"R\" FROM lineitem GROUP BY 1")
def _(spark, d):
    return table(spark, d, "lineitem", "l_linestatus", "l_returnflag").groupBy("l_linestatus").pivot("l_returnflag", ["A", "R"]).count()


@op("unpivot_metrics", "SELECT p_partkey, metric, value FROM (SELECT p_partkey, CAST(p_size AS DOUBLE) AS size, p_retailprice AS price FROM part) UNPIVOT (value FOR metric IN (size, price))")
def _(spark, d):
    rows = table(spark, d, "part", "p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return rows.unpivot("p_partkey", ["size", "price"], "metric", "value")


@op("window_functions", "SELECT event_id, row_number() OVER w AS rn, CAST(rank() OVER (PARTITION BY user_id ORDER BY event_type) AS INTEGER) AS rk, CAST(dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS INTEGER) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS nt, coalesce(lag(event_id) OVER w, -1) AS prev, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS near FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def _(spark, d):
    w, ties = Window.partitionBy("user_id").orderBy("event_id"), Window.partitionBy("user_id").orderBy("event_type")
    return table(spark, d, "events", "event_id", "user_id", "event_type").select(
        "event_id", F.row_number().over(w).cast("bigint").alias("rn"), F.rank().over(ties).alias("rk"), F.dense_rank().over(ties).alias("dr"), F.ntile(4).over(w).alias("nt"),
        F.coalesce(F.lag("event_id").over(w), F.lit(-1)).alias("prev"), F.count(F.lit(1)).over(w.rowsBetween(-2, 0)).alias("near"),
    )


@op("window_shares", "SELECT s_suppkey, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd, first_value(s_suppkey) OVER w AS top FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)")
def _(spark, d):
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")
    return table(spark, d, "supplier").select("s_suppkey", F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.first("s_suppkey").over(w).alias("top"))


@over_edges("running_degree", "SELECT t, node, count(*) OVER (PARTITION BY node ORDER BY t) AS degree FROM (SELECT t, unnest([u, v]) AS node FROM e)")
def _(e):
    ends = e.select("t", F.explode(F.array("u", "v")).alias("node"))
    return ends.withColumn("degree", F.count(F.lit(1)).over(Window.partitionBy("node").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)))


@over_edges("top_degrees", "SELECT node, count(*) AS degree FROM (SELECT unnest([u, v]) AS node FROM e) GROUP BY node ORDER BY degree DESC, node LIMIT 10")
def _(e):
    return e.select(F.explode(F.array("u", "v")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("degree")).orderBy(F.desc("degree"), "node").limit(10)


@op("top_per_group", "SELECT c_nationkey, c_custkey FROM customer QUALIFY row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) <= 3")
def _(spark, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return table(spark, d, "customer", "c_nationkey", "c_custkey", "c_acctbal").withColumn("nth", F.row_number().over(w)).where("nth <= 3").select("c_nationkey", "c_custkey")


@op("sort_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 40")
def _(spark, d):
    return table(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(40).limit(20).select("o_orderkey")


@over_edges("set_operations", "SELECT 'both' AS what, count(*) AS n FROM (SELECT u FROM e INTERSECT SELECT v FROM e) UNION ALL SELECT 'left', count(*) FROM (SELECT u FROM e EXCEPT SELECT v FROM e) UNION ALL SELECT 'all', count(*) FROM (SELECT u FROM e EXCEPT ALL SELECT v FROM e) UNION ALL SELECT 'any', count(*) FROM (SELECT u FROM e UNION SELECT v FROM e)")
def _(e):
    u, v = e.select("u"), e.select(F.col("v").alias("u"))
    sized = lambda name, df: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("what"), "n")
    return sized("both", u.intersect(v)).unionByName(sized("left", u.subtract(v))).unionByName(sized("all", u.exceptAll(v))).unionByName(sized("any", u.union(v).distinct()))


@op("string_functions", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, lower(substr(url, 1, 12)) AS head, length(url) AS n, md5(concat(url, ':', page_id)) AS tag, len(string_split(url, '/')) AS parts FROM pages")
def _(spark, d):
    return table(spark, d, "pages", "page_id", "url").select(
        "page_id", F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"), F.lower(F.substring("url", 1, 12)).alias("head"), F.length("url").cast("bigint").alias("n"),
        F.md5(F.concat_ws(":", "url", "page_id")).alias("tag"), F.size(F.split("url", "/")).cast("bigint").alias("parts"),
    )


@op("time_functions", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS hour, count(*) AS n, CAST(max(date_diff('second', date_trunc('hour', ts), ts)) AS BIGINT) AS last FROM events GROUP BY 1")
def _(spark, d):
    hour = F.date_trunc("hour", F.col("ts").cast("timestamp"))
    seconds = F.unix_timestamp(F.col("ts").cast("timestamp")) - F.unix_timestamp(hour)
    return table(spark, d, "events", "ts").groupBy(F.date_format(hour, "yyyy-MM-dd HH").alias("hour")).agg(F.count(F.lit(1)).alias("n"), F.max(seconds).alias("last"))


@op("order_delays", "SELECT o_orderkey, CAST(max(date_diff('day', o_orderdate, l_shipdate)) AS INTEGER) AS days FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderdate >= TIMESTAMP '1996-01-01' GROUP BY 1")
def _(spark, d):
    orders = table(spark, d, "orders", "o_orderkey", "o_orderdate").where("o_orderdate >= timestamp_ntz'1996-01-01'")
    lines = table(spark, d, "lineitem", "l_orderkey", "l_shipdate")
    return orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.max(F.datediff("l_shipdate", "o_orderdate")).alias("days"))


@op("math_functions", "SELECT p_partkey, p_partkey % 7 AS colour, round(ln(p_retailprice), 9) AS ln, round(sqrt(p_size), 9) AS root, floor(p_retailprice / 3.0) AS f, CAST(p_size * (p_size - 1) // 2 AS BIGINT) AS pairs FROM part")
def _(spark, d):
    return table(spark, d, "part").select("p_partkey", F.pmod("p_partkey", F.lit(7)).alias("colour"), F.round(F.ln("p_retailprice"), 9).alias("ln"), F.round(F.sqrt("p_size"), 9).alias("root"), F.floor(F.col("p_retailprice") / 3.0).cast("double").alias("f"), F.expr("(cast(p_size as bigint) * (p_size - 1)) div 2").alias("pairs"))


@over_edges("adjacency_lists", "SELECT node, list_sort(list(o)) AS near FROM (SELECT u AS node, v AS o FROM e UNION ALL SELECT v, u FROM e) GROUP BY node")
def _(e):
    ends = e.select("u", "v").union(e.select("v", "u")).toDF("node", "o")
    return ends.groupBy("node").agg(F.array_sort(F.collect_list("o")).alias("near"))


@over_edges("common_neighbours", "SELECT e.u, e.v, count(*) AS n FROM e JOIN (SELECT u AS a, v AS b FROM e UNION ALL SELECT v, u FROM e) x ON x.a = e.u JOIN (SELECT u AS a, v AS b FROM e UNION ALL SELECT v, u FROM e) y ON y.a = e.v AND y.b = x.b WHERE e.t <= 500 GROUP BY 1, 2")
def _(e):
    near = e.select("u", "v").union(e.select("v", "u")).toDF("node", "o").groupBy("node").agg(F.collect_set("o").alias("s"))
    rows = e.where("t <= 500").join(near.toDF("u", "su"), "u").join(near.toDF("v", "sv"), "v")
    return rows.select("u", "v", F.size(F.array_intersect("su", "sv")).cast("bigint").alias("n")).where("n > 0")


@op("vector_functions", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 6) AS norm, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive FROM embeddings")
def _(spark, d):
    x = F.col("embedding")
    squares = F.aggregate(F.transform(x, lambda v: v.cast("double") * v.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return table(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.round(squares, 6).alias("norm"), F.size(F.filter(x, lambda v: v > 0)).alias("positive"))


@op("json_functions", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    return table(spark, d, "events", "props").groupBy(F.from_json("props", "k bigint")["k"].alias("k")).agg(F.count(F.lit(1)).alias("n"))


@op("hash_sample", f"SELECT l_orderkey, l_linenumber FROM lineitem WHERE {coin_sql(chr(39) + 'b' + chr(39), 'l_orderkey', 'l_linenumber')} < 0.05")
def _(spark, d):
    return table(spark, d, "lineitem", "l_orderkey", "l_linenumber").where(coin("b", F.col("l_orderkey"), F.col("l_linenumber")) < 0.05)


@op("stratified_sample", "")
def _(spark, d):
    return table(spark, d, "orders", "o_orderkey", "o_orderstatus").sampleBy("o_orderstatus", {"F": 0.1, "O": 0.05, "P": 0.5}, seed=1)


@op("first_arrivals", "SELECT user_id, min(event_id) AS first FROM events GROUP BY 1")
def _(spark, d):
    return table(spark, d, "events", "user_id", "event_id").groupBy("user_id").agg(F.min("event_id").alias("first"))


@op("line_shingles", "SELECT doc_id, count(DISTINCT substr(line, 1, 20)) AS heads FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) GROUP BY 1")
def _(spark, d):
    lines = table(spark, d, "documents", "doc_id", "text").select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    return lines.groupBy("doc_id").agg(F.count_distinct(F.substring("line", 1, 20)).alias("heads"))


@op("sql_functions", "SELECT o_orderkey AS l, CASE WHEN o_orderkey <= 50 THEN 1.0 ELSE CAST(o_orderkey AS DOUBLE) * (o_orderkey - 1) / 2450.0 END AS w FROM orders")
def _(spark, d):
    from ..functions.sqlapi import register

    register(spark)
    return spark.sql("SELECT o_orderkey AS l, discovery_weight(o_orderkey, 50) AS w FROM {orders}", orders=table(spark, d, "orders", "o_orderkey"))


_COIN = "(CAST('0x' || substr(md5('{0}:1:' || i), 1, 13) AS BIGINT) / 4503599627370496.0)"


@op("udtf_er", f"SELECT CAST(floor({_COIN.format('eu')} * n) AS BIGINT) AS u, CAST(floor({_COIN.format('ev')} * n) AS BIGINT) AS v, i AS arrival FROM (SELECT n, unnest(range(n)) AS i FROM (SELECT count(DISTINCT user_id) AS n FROM events))")
def _(spark, d):
    """A random graph of as many nodes and edges as there are users."""
    from ..functions.sqlapi import register

    register(spark)
    users = table(spark, d, "events", "user_id").agg(F.count_distinct("user_id").alias("n"))
    return spark.sql("SELECT e.* FROM {users}, LATERAL er_edges(n, n, 1) AS e", users=users)


_GAP = f"CAST(floor(ln(1 - {_COIN.format('ag')}) / ln(1 - w)) AS BIGINT) + 1"
_NEXT = f"w * exp(ln(1 - {_COIN.format('aw').replace('|| i', '|| (i + 1)')}) / 200)"


@op("udtf_accepted", f"""WITH RECURSIVE m AS (SELECT count(o_totalprice) AS total FROM orders), g AS (
  SELECT CAST(0 AS BIGINT) AS i, CAST(200 AS BIGINT) AS r, exp(ln(1 - {_COIN.format('aw').replace('|| i', "|| '0'")}) / 200) AS w, CAST(NULL AS BIGINT) AS rank, CAST(NULL AS BIGINT) AS slot
  UNION ALL SELECT i + 1, r + {_GAP}, {_NEXT}, r + {_GAP}, CAST(floor({_COIN.format('as')} * 200) AS BIGINT) + 1 FROM g WHERE r <= (SELECT total FROM m))
SELECT rank, slot FROM g WHERE rank <= (SELECT total FROM m) UNION ALL SELECT i, i FROM (SELECT total, unnest(range(1, 201)) AS i FROM m) WHERE i <= total""")
def _(spark, d):
    """Ranks that a sample of 200 takes in from the priced orders."""
    from ..functions.sqlapi import register

    register(spark)
    priced = table(spark, d, "orders", "o_totalprice").agg(F.count("o_totalprice").alias("total"))
    return spark.sql("SELECT a.* FROM {priced}, LATERAL accepted_ranks(total, 200, 1) AS a", priced=priced)


@op("pandas_weight", "SELECT event_id AS l, CASE WHEN event_id <= 50 THEN 1.0 ELSE CAST(event_id AS DOUBLE) * (event_id - 1) / 2450.0 END AS w FROM events")
def _(spark, d):
    """The weight as an Arrow-batched UDF; the column form is the faster one."""
    import pandas as pd

    def weigh(load):
        return (load * (load - 1.0) / 2450.0).where(load > 50, 1.0).mask(load.isna())

    weigh.__annotations__ = {"load": pd.Series, "return": pd.Series}
    weight = F.pandas_udf(weigh, "double")
    return table(spark, d, "events", "event_id").select(F.col("event_id").alias("l"), weight("event_id").alias("w"))


def _written(fmt: str):
    """Edges written and read back in one format; the text form goes through the edge-list reader."""

    def run(spark, d):
        from uuid import uuid4

        from ..sources.edge_source import read_edge_list, write_result
        from ..sources.tables import shared_root

        path = f"{shared_root(spark)}/sink-{uuid4().hex}"
        edges = stream(spark, d, "coactivity")
        if fmt == "text":
            write_result(edges.select(F.concat_ws(" ", "u", "v").alias("value")), path, "text")
            return read_edge_list(spark, path).select("u", "v")
        write_result(edges.select("u", "v"), path, fmt)
        return read_edge_list(spark, path, fmt).select("u", "v")

    return run


_EDGES = f"SELECT u, v FROM ({stream_sql('coactivity')})"
for _fmt in ("text", "csv", "json", "orc", "parquet"):
    RELATIONAL[f"rel_sink_{_fmt}"] = (_written(_fmt), _EDGES)


@op("sink_partitioned", f"SELECT CAST(u % 7 AS INTEGER) AS worker, count(*) AS n FROM ({_EDGES}) GROUP BY 1")
def _(spark, d):
    """A sink partitioned by worker; each worker's folder is read alone."""
    from uuid import uuid4

    from ..sources.edge_source import write_result
    from ..sources.tables import shared_root

    path = f"{shared_root(spark)}/sink-{uuid4().hex}"
    write_result(stream(spark, d, "coactivity").select("u", "v", F.pmod("u", F.lit(7)).cast("int").alias("worker")), path, by=["worker"])
    return spark.read.parquet(path).groupBy("worker").agg(F.count(F.lit(1)).alias("n"))


@op("sink_bucketed", f"SELECT a.u, count(*) AS n FROM ({_EDGES}) a JOIN ({_EDGES}) b ON a.u = b.u GROUP BY a.u")
def _(spark, d):
    """Two reads of a bucketed table join without a shuffle."""
    from uuid import uuid4

    from ..sources.edge_source import write_bucketed
    from ..sources.tables import shared_root

    name = f"edges_{uuid4().hex}"
    table = write_bucketed(stream(spark, d, "coactivity").select("u", "v"), name, "u", 8, f"{shared_root(spark)}/{name}")
    return table.alias("a").join(table.alias("b"), "u").groupBy("u").agg(F.count(F.lit(1)).alias("n"))


@op("source_edge_list", _EDGES)
def _(spark, d):
    """The Python data source over plain text files."""
    from uuid import uuid4

    from ..sources.edge_source import EdgeListSource, write_result
    from ..sources.tables import shared_root

    spark.dataSource.register(EdgeListSource)
    path = f"{shared_root(spark)}/sink-{uuid4().hex}"
    write_result(stream(spark, d, "coactivity").select(F.concat_ws(" ", "u", "v").alias("value")), path, "text")
    return spark.read.format("edge_list").option("path", path.removeprefix("file://")).load().select("u", "v")


@op("grouped_udf_median", f"SELECT w AS worker, n FROM (SELECT CAST(u % 7 AS INTEGER) AS w, median(v) AS n FROM ({_EDGES}) GROUP BY 1)")
def _(spark, d):
    """A grouped-aggregate pandas UDF."""
    import pandas as pd

    def middle(v):
        return float(v.median())

    middle.__annotations__ = {"v": pd.Series, "return": float}
    udaf = F.pandas_udf(middle, "double")
    return stream(spark, d, "coactivity").groupBy(F.pmod("u", F.lit(7)).cast("int").alias("worker")).agg(udaf("v").alias("n"))


for _name, (_run, _text) in list(RELATIONAL.items()):
    RELATIONAL[_name] = (_run, _text or None)

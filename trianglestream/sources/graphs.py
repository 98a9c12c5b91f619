"""Graphs built from the given tables, each with the DuckDB text of the same pairs."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..functions.hashing import coin
from .cliques import clique_stream
from .streams import edge_stream, pairs_sql
from .tables import table


def _within_orders(spark, sf_dir, column):
    """Pairs of values of one lineitem column inside an order. Lines move once, by order."""
    lines = table(spark, sf_dir, "lineitem", "l_orderkey", column).repartition("l_orderkey").distinct()
    left, right = lines.select("l_orderkey", F.col(column).alias("u")), lines.select("l_orderkey", F.col(column).alias("v"))
    return left.join(right, "l_orderkey").where("u < v").select("u", "v", F.col("l_orderkey").alias("arrival"))


def _within_orders_sql(column):
    return f"SELECT a.{column} AS u, b.{column} AS v, a.l_orderkey AS arrival FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.{column} < b.{column}"


def copurchase(spark, sf_dir):
    return _within_orders(spark, sf_dir, "l_partkey")


def cosupply(spark, sf_dir):
    return _within_orders(spark, sf_dir, "l_suppkey")


def _orders_lines(spark, sf_dir):
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    lines = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey")
    return orders.join(lines, orders["o_orderkey"] == lines["l_orderkey"])


def tripartite(spark, sf_dir):
    """Customer, part and supplier of each line, all linked; ids carry their role in base three."""
    rows = _orders_lines(spark, sf_dir).select(
        F.col("l_orderkey").alias("arrival"), (F.col("o_custkey") * 3).alias("c"), (F.col("l_partkey") * 3 + 1).alias("p"), (F.col("l_suppkey") * 3 + 2).alias("s")
    )
    ends = F.explode(F.array(*[F.struct(F.col(a).alias("u"), F.col(b).alias("v")) for a, b in ("cp", "ps", "cs")]))
    return rows.select("arrival", ends.alias("e")).select("e.u", "e.v", "arrival")


def bipartite(spark, sf_dir):
    return table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey").select((F.col("l_partkey") * 2).alias("u"), (F.col("l_suppkey") * 2 + 1).alias("v"), F.col("l_orderkey").alias("arrival"))


def nation_trade(spark, sf_dir):
    customers = table(spark, sf_dir, "customer", "c_custkey", F.col("c_nationkey").alias("u"))
    suppliers = table(spark, sf_dir, "supplier", "s_suppkey", F.col("s_nationkey").alias("v"))
    rows = _orders_lines(spark, sf_dir).join(customers, F.col("o_custkey") == F.col("c_custkey")).join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
    return rows.select("u", "v", F.col("l_orderkey").alias("arrival"))


def successive(events: DataFrame, by: list[str]) -> DataFrame:
    """(u, v, arrival): users of successive events in each group, found inside hours and joined across their borders."""
    hour = F.date_trunc("hour", F.col("ts"))
    rows = events.withColumn("hour", hour)
    inside = Window.partitionBy(*by, "hour").orderBy("ts", "event_id")
    following = rows.withColumn("next", F.lead(F.struct("user_id", "event_id")).over(inside))
    edge = F.struct("ts", "event_id", "user_id")
    borders = rows.groupBy(*by, "hour").agg(F.min(edge).alias("first"), F.max(edge).alias("last"))
    over_hours = Window.partitionBy(*by).orderBy("hour") if by else Window.orderBy("hour")
    across = borders.withColumn("after", F.lead("first").over(over_hours)).where("after is not null")
    pairs = following.where("next is not null").select(F.col("user_id").alias("u"), F.col("next.user_id").alias("v"), F.col("next.event_id").alias("arrival"))
    return pairs.unionByName(across.select(F.col("last.user_id").alias("u"), F.col("after.user_id").alias("v"), F.col("after.event_id").alias("arrival")))


def coactivity(spark, sf_dir):
    return successive(table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type"), ["event_type"])


def consecutive(spark, sf_dir):
    return successive(table(spark, sf_dir, "events", "event_id", "ts", "user_id"), [])


def _successive_sql(by):
    part = "PARTITION BY event_type " if by else ""
    return f"SELECT user_id AS u, lead(user_id) OVER w AS v, lead(event_id) OVER w AS arrival FROM events WINDOW w AS ({part}ORDER BY ts, event_id) QUALIFY v IS NOT NULL"


def _products(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Inner products of all rows of x with all of y, added component by component from zero, as SQL adds them, to the same bits."""
    out, part = np.zeros((len(x), len(y))), np.empty((len(x), len(y)))
    for p, q in zip(x.T, y.T):
        np.multiply(p[:, None], q[None, :], out=part)
        out += part
    return out


def _nearest(scores: np.ndarray, most: int) -> np.ndarray:
    """Mask of the columns, in order of their ids, that may be among the ``most`` nearest of each row after scores are rounded to
    nine digits: all within two roundings of the last of them, and of equal scores the first ``most``. -inf takes no part."""
    if scores.shape[1] <= most:
        return scores > -np.inf
    near = (scores >= np.partition(scores, -most, axis=1)[:, -most, None] - 2e-9) & (scores > -np.inf)
    for i in np.flatnonzero(near.sum(1) > most):
        at = np.flatnonzero(near[i])
        at = at[np.argsort(-scores[i, at], kind="stable")]
        first = np.flatnonzero(np.append(True, np.diff(scores[i, at]) != 0))
        nth = np.arange(len(at)) - np.repeat(first, np.diff(np.append(first, len(at))))
        near[i, at[nth >= most]] = False
    return near


#: Scores held at once, and sides of a tile of products.
HELD, TILE = 1 << 22, (128, 512)


def _block_candidates(most: int):
    """Kernel of one pair of blocks, rows (side, id, x): (u, v, raw), candidates of side 1 for each vector of side 0. A vector
    that is null or has a null component scores null, which is behind all others; NaN is before them."""

    def run(cell: pa.Table) -> pa.Table:
        cell = cell.sort_by("id")
        side, ids = cell.column("side").to_numpy(), cell.column("id").to_numpy()
        rows = cell.column("x").to_pylist()
        width = max((len(r) for r in rows if r is not None), default=0)
        blank = np.array([r is None or len(r) != width or None in r for r in rows], bool)
        x = np.array([[0.0] * width if b else r for r, b in zip(rows, blank)], np.float64).reshape(len(rows), width)
        norms = np.zeros(len(x))
        for c in x.T:
            norms += c * c
        norms = np.sqrt(norms)
        left, right = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        out, step = [], max(1, min(TILE[0], HELD // max(1, len(right))))
        for at in range(0, len(left) if len(right) else 0, step):
            mine = left[at : at + step]
            scores = np.concatenate([_products(x[mine], x[right[to : to + TILE[1]]]) for to in range(0, len(right), TILE[1])], axis=1)
            with np.errstate(invalid="ignore", divide="ignore"):
                scores /= norms[mine][:, None] * norms[right][None, :]
            none = blank[mine][:, None] | blank[right][None, :]
            order = np.where(none, -1e300, np.where(np.isnan(scores), np.inf, scores))
            order[ids[mine][:, None] == ids[right][None, :]] = -np.inf
            i, j = np.nonzero(_nearest(order, most))
            out.append((ids[mine[i]], ids[right[j]], pa.array(scores[i, j], mask=none[i, j], from_pandas=False)))
        if not out:
            return pa.table({"u": pa.array([], pa.int64()), "v": pa.array([], pa.int64()), "raw": pa.array([], pa.float64())})
        return pa.table({"u": np.concatenate([o[0] for o in out]), "v": np.concatenate([o[1] for o in out]), "raw": pa.chunked_array([o[2] for o in out])})

    return run


def knn(spark, sf_dir, neighbours: int = 10, blocks: int = 8):
    """Each vector with its nearest by cosine. All pairs, block against block: a stated quadratic task."""
    rows = table(spark, sf_dir, "embeddings", F.col("vec_id").cast("bigint").alias("id"), F.col("embedding").cast("array<double>").alias("x")).where("id is not null")
    rows = rows.withColumn("block", F.pmod("id", F.lit(blocks)))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)).cast("array<bigint>"))
    left = rows.withColumn("other", every).select((F.col("block") * blocks + F.col("other")).alias("cell"), F.lit(0).alias("side"), "id", "x")
    right = rows.withColumn("other", every).select((F.col("other") * blocks + F.col("block")).alias("cell"), F.lit(1).alias("side"), "id", "x")
    found = left.unionByName(right).groupBy("cell").applyInArrow(_block_candidates(neighbours), "u bigint, v bigint, raw double")
    scored = found.select("u", "v", F.round("raw", 9).alias("score"))
    near = F.row_number().over(Window.partitionBy("u").orderBy(F.desc("score"), "v"))
    return scored.withColumn("near", near).where(F.col("near") <= neighbours).select("u", "v", F.col("u").alias("arrival"))


KNN_SQL = """SELECT u, v, u AS arrival FROM (SELECT a.vec_id AS u, b.vec_id AS v,
  round(list_dot_product(a.x, b.x) / (sqrt(list_dot_product(a.x, a.x)) * sqrt(list_dot_product(b.x, b.x))), 9) AS score
  FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings) a, (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings) b WHERE a.vec_id <> b.vec_id)
  QUALIFY row_number() OVER (PARTITION BY u ORDER BY score DESC, v) <= 10"""


def _sharing(rows: DataFrame, most: int | None) -> DataFrame:
    """Pairs of ``id`` that share a ``key``; keys that more than ``most`` have are no sign of kinship."""
    rows = rows.distinct()
    if most is not None:
        sizes = rows.groupBy("key").count().where(F.col("count").between(2, most)).select("key")
        rows = rows.join(sizes, "key")
    left, right = rows.select("key", F.col("id").alias("u")), rows.select("key", F.col("id").alias("v"))
    return left.join(right, "key").where("u < v").select("u", "v", F.col("v").alias("arrival"))


def _sharing_sql(rows, most):
    cut = f"JOIN (SELECT key FROM r GROUP BY key HAVING count(*) BETWEEN 2 AND {most}) s USING (key)" if most is not None else ""
    return f"WITH r AS (SELECT DISTINCT id, key FROM ({rows})), k AS (SELECT r.* FROM r {cut}) SELECT a.id AS u, b.id AS v, b.id AS arrival FROM k a JOIN k b ON a.key = b.key AND a.id < b.id"


def neardup(spark, sf_dir):
    lines = table(spark, sf_dir, "documents", "doc_id", "text").select(F.col("doc_id").alias("id"), F.explode(F.split("text", "\n")).alias("key"))
    return _sharing(lines.select("id", F.trim("key").alias("key")).where(F.length("key") >= 20), 50)


def hosts(spark, sf_dir) -> DataFrame:
    """(id, key): pages and their hosts."""
    host = F.regexp_replace(F.regexp_extract(F.col("url"), "^[a-z]+://([^/]+)", 1), r"^(www|m|blog)\.", "")
    return table(spark, sf_dir, "pages", "page_id", "url").select(F.col("page_id").cast("bigint").alias("id"), host.alias("key"))


def hostlinks(spark, sf_dir):
    return _sharing(hosts(spark, sf_dir), None)


def split_groups(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Distinct (id, key) of groups whose members are in no other group, so that each is a clique of its own in the graph of
    shared keys, and the pairs (u, v, arrival) of all other groups."""
    rows = rows.where("id is not null and key is not null").distinct()
    several = rows.groupBy("id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("id")
    keys = rows.join(several, "id", "left_semi").select("key").distinct()
    return rows.join(keys, "key", "left_anti"), _sharing(rows.join(keys, "key", "left_semi"), None)


def hreflinks(spark, sf_dir):
    links = F.explode(F.regexp_extract_all(F.col("html"), F.lit('href="([^"]*)"'), F.lit(1)))
    return _sharing(table(spark, sf_dir, "pages", "page_id", "html").select(F.col("page_id").alias("id"), links.alias("key")), 50)


def er(spark: SparkSession, n: int, m: int, seed: int = 1) -> DataFrame:
    """About ``m`` random pairs over ``n`` nodes, from hashes of a range; no data moves to make it."""
    i = F.col("id")
    return spark.range(m).select(F.floor(coin("er", seed, i, "u", kind="fast") * n).cast("bigint").alias("u"), F.floor(coin("er", seed, i, "v", kind="fast") * n).cast("bigint").alias("v"), i.alias("arrival"))


GRAPHS = {
    "copurchase": (copurchase, _within_orders_sql("l_partkey")),
    "cosupply": (cosupply, _within_orders_sql("l_suppkey")),
    "tripartite": (tripartite, "WITH l AS (SELECT l_orderkey, 3 * o_custkey AS c, 3 * l_partkey + 1 AS p, 3 * l_suppkey + 2 AS s FROM lineitem JOIN orders ON l_orderkey = o_orderkey) SELECT c AS u, p AS v, l_orderkey AS arrival FROM l UNION ALL SELECT p, s, l_orderkey FROM l UNION ALL SELECT c, s, l_orderkey FROM l"),
    "bipartite": (bipartite, "SELECT 2 * l_partkey AS u, 2 * l_suppkey + 1 AS v, l_orderkey AS arrival FROM lineitem"),
    "nation_trade": (nation_trade, "SELECT c_nationkey AS u, s_nationkey AS v, l_orderkey AS arrival FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"),
    "coactivity": (coactivity, _successive_sql(True)),
    "consecutive": (consecutive, _successive_sql(False)),
    "knn": (knn, KNN_SQL),
    "neardup": (neardup, _sharing_sql("SELECT doc_id AS id, trim(key, ' ') AS key FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS key FROM documents) WHERE length(trim(key, ' ')) >= 20", 50)),
    "hostlinks": (hostlinks, _sharing_sql("SELECT page_id AS id, regexp_replace(regexp_extract(url, '^[a-z]+://([^/]+)', 1), '^(www|m|blog)[.]', '') AS key FROM pages", None)),
    "hreflinks": (hreflinks, _sharing_sql("SELECT page_id AS id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS key FROM pages", 50)),
}


def stream(spark: SparkSession, sf_dir: str, graph: str, order: str = "random") -> DataFrame:
    if graph == "hostlinks" and order == "random":  # pages of a host are all linked
        return clique_stream(hosts(spark, sf_dir))
    return edge_stream(GRAPHS[graph][0](spark, sf_dir), order)


def stream_sql(graph: str, order: str = "random") -> str:
    return pairs_sql(GRAPHS[graph][1], order)

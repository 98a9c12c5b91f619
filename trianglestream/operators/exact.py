"""Exact triangle counts: degree-ordered batch join, brute force, and tables derived from them."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..sources.streams import clean


def nodes_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("u", "v")).alias("node")).distinct()


def degrees(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("u", "v")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("degree"))


def oriented(edges: DataFrame) -> DataFrame:
    """(a, b, t): each edge from its end of lower (degree, id); fan-out is then at most the root of twice the edges."""
    d = degrees(edges)
    rows = edges.join(d.withColumnsRenamed({"node": "u", "degree": "du"}), "u").join(d.withColumnsRenamed({"node": "v", "degree": "dv"}), "v")
    up = (F.col("du") < F.col("dv")) | ((F.col("du") == F.col("dv")) & (F.col("u") < F.col("v")))
    return rows.select(F.when(up, F.col("u")).otherwise(F.col("v")).alias("a"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("b"), "t")


def triangles(edges: DataFrame) -> DataFrame:
    """(u, v, apex, t, t1, t2): each triangle once; (u, v) is its last edge at t, t1 < t2 the older ones."""
    arcs = oriented(edges)
    left = arcs.select("a", F.col("b").alias("x"), F.col("t").alias("tx"))
    right = arcs.select("a", F.col("b").alias("y"), F.col("t").alias("ty"))
    open_ = left.join(right, "a").where("x < y")
    closed = open_.join(edges.select(F.col("u").alias("x"), F.col("v").alias("y"), F.col("t").alias("tz")), ["x", "y"])
    side = lambda t, u, v, w: F.struct(F.col(t).alias("t"), F.least(u, v).alias("u"), F.greatest(u, v).alias("v"), F.col(w).alias("w"))
    sides = F.array_sort(F.array(side("tx", "a", "x", "y"), side("ty", "a", "y", "x"), side("tz", "x", "y", "a")))
    rows = closed.select(sides.alias("s"))
    return rows.select(F.col("s")[2]["u"].alias("u"), F.col("s")[2]["v"].alias("v"), F.col("s")[2]["w"].alias("apex"), F.col("s")[2]["t"].alias("t"), F.col("s")[0]["t"].alias("t1"), F.col("s")[1]["t"].alias("t2"))


def exact_global(edges: DataFrame) -> DataFrame:
    return triangles(edges).agg(F.count(F.lit(1)).alias("n"))


def exact_local(edges: DataFrame) -> DataFrame:
    """(node, n) for nodes with a triangle."""
    return triangles(edges).select(F.explode(F.array("u", "v", "apex")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("n"))


def grouped_global(groups: DataFrame, pairs: DataFrame) -> DataFrame:
    """(n): triangles of ``split_groups``' two results. A clique of c nodes has c(c-1)(c-2)/6, without listing its edges."""
    sizes = groups.groupBy("key").agg(F.count(F.lit(1)).alias("c"))
    return sizes.selectExpr("c * (c - 1) div 2 * (c - 2) div 3 AS n").unionByName(exact_global(_untimed(pairs))).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


def grouped_local(groups: DataFrame, pairs: DataFrame) -> DataFrame:
    """(node, n) of ``split_groups``' two results, for nodes with a triangle: (c-1)(c-2)/2 in a clique of c nodes."""
    sizes = groups.groupBy("key").agg(F.count(F.lit(1)).alias("c")).where("c > 2")
    own = groups.join(sizes, "key").select(F.col("id").alias("node"), F.expr("(c - 1) * (c - 2) div 2").alias("n"))
    return own.unionByName(exact_local(_untimed(pairs)))


def _untimed(pairs: DataFrame) -> DataFrame:
    """An edge stream without order, which counts do not need."""
    return clean(pairs).select(F.lit(0).cast("bigint").alias("t"), "u", "v")


def exact_bruteforce(edges: DataFrame) -> DataFrame:
    """Three-way join without orientation, as an oracle."""
    e = edges.select("u", "v")
    one, two = e.select(F.col("u").alias("x"), F.col("v").alias("y")), e.select(F.col("u").alias("y"), F.col("v").alias("z"))
    return one.join(two, "y").join(e.select(F.col("u").alias("x"), F.col("v").alias("z")), ["x", "z"]).agg(F.count(F.lit(1)).alias("n"))


def local_clustering(edges: DataFrame) -> DataFrame:
    """(node, degree, n, clustering): share of neighbour pairs that are linked."""
    rows = degrees(edges).join(exact_local(edges), "node", "left").select("node", "degree", F.coalesce("n", F.lit(0)).alias("n"))
    return rows.withColumn("clustering", F.when(F.col("degree") > 1, 2.0 * F.col("n") / (F.col("degree") * (F.col("degree") - 1))).otherwise(0.0))


def transitivity(edges: DataFrame) -> DataFrame:
    """Three times triangles over paths of two edges."""
    paths = degrees(edges).agg(F.sum(F.col("degree") * (F.col("degree") - 1) / 2).alias("paths"))
    n = exact_local(edges).agg((F.sum("n") / 3).alias("triangles"))
    return n.crossJoin(paths).select((3.0 * F.col("triangles") / F.col("paths")).alias("transitivity"))


def edge_support(edges: DataFrame) -> DataFrame:
    """(u, v, support): triangles on each edge that has any."""
    side = lambda u, v: F.struct(F.least(u, v).alias("x"), F.greatest(u, v).alias("y"))
    sides = F.explode(F.array(side("u", "v"), side("u", "apex"), side("v", "apex")))
    return triangles(edges).select(sides.alias("e")).groupBy(F.col("e.x").alias("u"), F.col("e.y").alias("v")).agg(F.count(F.lit(1)).alias("support"))

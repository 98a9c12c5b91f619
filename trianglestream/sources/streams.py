"""From raw pairs to an edge stream: canonical, without loops and repeats, with dense arrival times.

Dense times come from two levels: rows are numbered inside chunks of the order and
chunks get the number of rows before them. No window ever spans the whole stream.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions.weights import canonical

#: Leading hex digits that make a chunk of the random order: 4,096 chunks, so 10¹¹ edges give 25 million rows to a sort;
#: width of a chunk of arrival keys.
CHUNK_DIGITS, CHUNK_WIDTH = 3, 4096


def clean(pairs: DataFrame) -> DataFrame:
    """(u, v, arrival) with u < v: loops go, of parallel edges in either direction the first arrival stays."""
    u, v = canonical(F.col("u").cast("bigint"), F.col("v").cast("bigint"))
    rows = pairs.select(u.alias("u"), v.alias("v"), F.col("arrival").cast("bigint").alias("arrival")).where("u < v")
    return rows.groupBy("u", "v").agg(F.min("arrival").alias("arrival"))


def number_rows(df: DataFrame, chunk: Column, order: list[str], name: str) -> DataFrame:
    """``df`` with a dense number from 1 in (chunk, order) order; ``chunk`` must be monotone in the order."""
    rows = df.withColumn("_chunk", chunk)
    before = Window.orderBy("_chunk").rowsBetween(Window.unboundedPreceding, -1)
    offsets = rows.groupBy("_chunk").agg(F.count(F.lit(1)).alias("_n")).select("_chunk", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    inside = Window.partitionBy("_chunk").orderBy(*order)
    return rows.join(offsets, "_chunk").withColumn(name, (F.row_number().over(inside) + F.col("_before")).cast("bigint")).drop("_chunk", "_before")


def edge_stream(pairs: DataFrame, order: str = "random", seed: str = "s") -> DataFrame:
    """(t, u, v) from pairs (u, v, arrival). Orders: random (seeded hash of the edge) or arrival."""
    edges = clean(pairs)
    if order == "random":
        edges = edges.withColumn("_key", F.md5(F.concat(F.lit(seed), F.col("u").cast("string"), F.lit(","), F.col("v").cast("string"))))
        numbered = number_rows(edges, F.substring("_key", 1, CHUNK_DIGITS), ["_key", "u", "v"], "t")
    elif order == "arrival":
        numbered = number_rows(edges, F.floor(F.col("arrival") / CHUNK_WIDTH), ["arrival", "u", "v"], "t")
    else:
        raise ValueError(f"unknown order {order!r}")
    return numbered.select("t", "u", "v")


def union_streams(parts: list[DataFrame]) -> DataFrame:
    """Streams of several masters as one: pairs meet again, the earliest time of an edge counts."""
    pairs = parts[0].select("u", "v", F.col("t").alias("arrival"))
    for part in parts[1:]:
        pairs = pairs.unionByName(part.select("u", "v", F.col("t").alias("arrival")))
    return edge_stream(pairs, "arrival")


def prefix(edges: DataFrame, most: int) -> DataFrame:
    """The stream up to a time."""
    return edges.where(F.col("t") <= most)


def pairs_sql(body: str, order: str = "random", seed: str = "s") -> str:
    """DuckDB text of an edge stream over a query that gives u, v, arrival."""
    rank = f"md5('{seed}' || u || ',' || v), u, v" if order == "random" else "arrival, u, v"
    return (
        f"SELECT CAST(row_number() OVER (ORDER BY {rank}) AS BIGINT) AS t, u, v FROM (SELECT least(u, v) AS u, greatest(u, v) AS v, min(arrival) AS arrival "
        f"FROM (SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v, CAST(arrival AS BIGINT) AS arrival FROM ({body})) WHERE u <> v GROUP BY 1, 2)"
    )

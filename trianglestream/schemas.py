"""Schemas of the relations that plans hand to each other, and checks at API entry."""

from pyspark.sql import DataFrame, functions as F, types as T


def _struct(text: str) -> T.StructType:
    return T.StructType([T.StructField(name, {"bigint": T.LongType(), "int": T.IntegerType(), "double": T.DoubleType()}[kind]) for name, kind in (part.split(":") for part in text.split())])


EDGE_STREAM = _struct("t:bigint u:bigint v:bigint")
NODE_MAP = _struct("node:bigint worker:int")
RANKED = _struct("worker:int t:bigint u:bigint v:bigint rank:bigint")
RESIDENCY = _struct("trial:int worker:int u:bigint v:bigint rank:bigint slot:bigint t_in:bigint t_out:bigint")
CLOSURE = _struct("trial:int worker:int u:bigint v:bigint apex:bigint t:bigint load_before:bigint")


def require_edge_stream(edges: DataFrame, check_rows: bool = False) -> DataFrame:
    """``edges`` cut to (t, u, v); raises on missing columns, and with ``check_rows`` on nulls, loops, order or reused times."""
    missing = {"t", "u", "v"} - set(edges.columns)
    if missing:
        raise ValueError(f"an edge stream needs columns t, u, v; missing {sorted(missing)}")
    edges = edges.select(*[F.col(c).cast("bigint").alias(c) for c in ("t", "u", "v")])
    if check_rows:
        bad = edges.where("t is null or u is null or v is null or u >= v").limit(1).count()
        twice = edges.groupBy("t").count().where("count > 1").limit(1).count()
        if bad or twice:
            raise ValueError("an edge stream has u < v, no nulls and unique times")
    return edges


def require_parameters(k: int, budget: int) -> None:
    if k < 1 or budget < 2:
        raise ValueError("k must be at least 1 and the budget at least 2")

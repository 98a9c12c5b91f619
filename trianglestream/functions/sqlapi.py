"""SQL names for the engine's expressions, and table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .hashing import DIGITS, RANGE, coin_value


def register(spark: SparkSession) -> list[str]:
    """Register the functions with this session; returns their names. Scalars are SQL functions, so Catalyst inlines them."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION discovery_weight(load BIGINT, budget BIGINT) RETURNS DOUBLE RETURN CASE WHEN load <= budget THEN 1D ELSE CAST(load AS DOUBLE) * (load - 1) / (CAST(budget AS DOUBLE) * (budget - 1)) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edge_slot(rank BIGINT, budget BIGINT, u01 DOUBLE) RETURNS BIGINT RETURN CASE WHEN rank <= budget THEN rank ELSE CAST(floor(u01 * rank) AS BIGINT) + 1 END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION counting_worker(fu INT, fv INT, fw INT) RETURNS INT RETURN CASE WHEN fu = fv THEN fu ELSE fw END")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION edge_coin(said STRING) RETURNS DOUBLE RETURN CAST(conv(substr(md5(said), 1, {DIGITS}), 16, 10) AS BIGINT) / {RANGE}D")
    spark.udtf.register("er_edges", ErEdges)
    spark.udtf.register("accepted_ranks", AcceptedRanks)
    return ["discovery_weight", "edge_slot", "counting_worker", "edge_coin", "er_edges", "accepted_ranks"]


@udtf(returnType="u: bigint, v: bigint, arrival: bigint")
class ErEdges:
    """Pairs of a random graph, by portable coins."""

    def eval(self, n: int, m: int, seed: int):
        for i in range(m):
            yield int(coin_value("eu", seed, i) * n), int(coin_value("ev", seed, i) * n), i


@udtf(returnType="rank: bigint, slot: bigint")
class AcceptedRanks:
    """Ranks a reservoir of ``budget`` takes in among ``total``, drawn by gaps: no coin for the ranks it skips."""

    def eval(self, total: int, budget: int, seed: int):
        import math

        for r in range(1, min(total, budget) + 1):
            yield r, r
        r, i = budget, 0
        w = math.exp(math.log(1 - coin_value("aw", seed, i)) / budget)
        while True:
            r += int(math.log(1 - coin_value("ag", seed, i)) / math.log(1 - w)) + 1
            if r > total:
                return
            yield r, int(coin_value("as", seed, i) * budget) + 1
            i += 1
            w *= math.exp(math.log(1 - coin_value("aw", seed, i)) / budget)

"""Approximate nearest neighbours by inner product: one navigable small-world graph per shard.

Equal vectors are one class, so copies, however many, neither crowd a graph nor a
task; each class keeps its least identifiers, as many as an answer can hold.
Classes are dealt to shards by hash; a shard's graph is stored as flat arrays
(levels, neighbour tables) in the shared folder. Vectors get one more component
that makes their lengths equal, by which inner product and distance order alike.
Query blocks stream past every shard; exact double scores of the shards' best are
merged, then classes are unfolded to rows. Ties go to the smaller identifier: where
equal scores reach past what a walk may return, that query scans the shard.

Vectors that are null, zero, or hold null or non-finite components take no part; each
dimension is searched on its own, as only equal dimensions have an inner product.
Repeated identifiers are candidates each, null identifiers none. Fewer candidates than
asked for give shorter answers; empty tables none. Other columns are not read.
"""

from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from .common import materialize, tidied

LINKS = 24  # on upper levels; twice as many on the ground


class Graph:
    """Flat neighbour arrays over ``vectors`` (float32, equal lengths)."""

    def __init__(self, vectors: np.ndarray, levels: np.ndarray):
        n = len(vectors)
        self.vectors, self.levels = vectors, levels
        self.ground = np.full((n, 2 * LINKS), -1, np.int32)
        self.base = np.concatenate([[0], np.cumsum(levels)]).astype(np.int64)  # a row of ``upper`` for each level above ground
        self.upper = np.full((int(self.base[-1]), LINKS), -1, np.int32)
        self.entry = -1
        self.stamp, self.clock = np.zeros(n, np.int64), 0

    def row(self, node: int, level: int) -> np.ndarray:
        return self.ground[node] if level == 0 else self.upper[self.base[node] + level - 1]

    def climb(self, q: np.ndarray, start: int, level: int) -> int:
        """Greedy walk to the closest node of a level."""
        best, score = start, float(self.vectors[start] @ q)
        while True:
            near = self.row(best, level)
            near = near[near >= 0]
            if not len(near):
                return best
            scores = self.vectors[near] @ q
            i = int(scores.argmax())
            if scores[i] <= score:
                return best
            best, score = int(near[i]), float(scores[i])

    def search(self, q: np.ndarray, start: int, level: int, width: int) -> list[tuple[float, int]]:
        """The ``width`` best found from ``start``, best first."""
        self.clock += 1
        stamp, clock = self.stamp, self.clock
        s = float(self.vectors[start] @ q)
        stamp[start] = clock
        todo, best = [(-s, start)], [(s, start)]
        while todo:
            s, node = heapq.heappop(todo)
            if -s < best[0][0] and len(best) >= width:
                break
            near = self.row(node, level)
            near = near[near >= 0]
            near = near[stamp[near] != clock]
            if not len(near):
                continue
            stamp[near] = clock
            scores = self.vectors[near] @ q
            if len(best) >= width:
                good = scores > best[0][0]
                near, scores = near[good], scores[good]
            for s, x in zip(scores.tolist(), near.tolist()):
                if len(best) < width:
                    heapq.heappush(best, (s, x))
                elif s > best[0][0]:
                    heapq.heapreplace(best, (s, x))
                else:
                    continue
                heapq.heappush(todo, (-s, x))
        return sorted(best, reverse=True)

    def diverse(self, scores: np.ndarray, nodes: np.ndarray, most: int) -> np.ndarray:
        """Of candidates, best first, those closer to the centre than to any chosen; then the best of the rest."""
        if len(nodes) <= most:
            return nodes
        v = self.vectors[nodes]
        between = v @ v.T
        closest = np.full(len(nodes), -np.inf)
        chosen = []
        for i in range(len(nodes)):
            if closest[i] < scores[i]:
                chosen.append(i)
                if len(chosen) == most:
                    break
                np.maximum(closest, between[i], out=closest)
        if len(chosen) < most:
            used = set(chosen)
            chosen += [i for i in range(len(nodes)) if i not in used][: most - len(chosen)]
        return nodes[chosen]

    def insert(self, node: int, width: int) -> None:
        q, level = self.vectors[node], int(self.levels[node])
        if self.entry < 0:
            self.entry = node
            return
        at, top = self.entry, int(self.levels[self.entry])
        for step in range(top, level, -1):
            at = self.climb(q, at, step)
        for step in range(min(top, level), -1, -1):
            found = self.search(q, at, step, width)
            at = found[0][1]
            scores, nodes = np.array([s for s, _ in found]), np.array([x for _, x in found], np.int32)
            own = self.row(node, step)
            chosen = self.diverse(scores, nodes, min(LINKS, len(own)))
            own[: len(chosen)] = chosen
            for other in chosen.tolist():
                row = self.row(other, step)
                if row[-1] < 0:
                    row[int((row >= 0).sum())] = node
                    continue
                all_ = np.append(row, np.int32(node))
                near = self.vectors[all_] @ self.vectors[other]
                order = np.argsort(-near, kind="stable")
                kept = self.diverse(near[order], all_[order], len(row))
                row[:] = -1
                row[: len(kept)] = kept
        if level > top:
            self.entry = node

    def best(self, q: np.ndarray, width: int) -> list[int]:
        if self.entry < 0:
            return []
        at = self.entry
        for step in range(int(self.levels[at]), 0, -1):
            at = self.climb(q, at, step)
        return [x for _, x in self.search(q, at, 0, width)]


def level_draws(n: int, seed: int) -> np.ndarray:
    u = 1 - np.random.default_rng(seed).random(n)
    return np.minimum((-np.log(u) / math.log(LINKS)).astype(np.int64), 8)


def with_length(vectors: np.ndarray) -> np.ndarray:
    """One more component, so that all vectors are as long as the longest."""
    norms = (vectors.astype(np.float64) ** 2).sum(1)
    rest = np.sqrt(np.maximum(norms.max(initial=0) - norms, 0))
    return np.concatenate([vectors, rest[:, None]], 1).astype(np.float32)


def build_graph(vectors: np.ndarray, seed: int, width: int) -> Graph:
    graph = Graph(with_length(vectors), level_draws(len(vectors), seed))
    for i in range(len(vectors)):
        graph.insert(i, width)
    return graph


INDEX = "key int, rank int, block bigint, ids binary, vectors binary, levels binary, ground binary, upper binary, entry int"
ARROW_INDEX = pa.schema([("key", pa.int32()), ("rank", pa.int32()), ("block", pa.int64()), ("ids", pa.binary()), ("vectors", pa.binary()), ("levels", pa.binary()), ("ground", pa.binary()), ("upper", pa.binary()), ("entry", pa.int32())])


def build_kernel(dim: int, width: int, seed: int):
    """All classes of a shard to one row of flat arrays."""

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("class_id").combine_chunks()
        shard = table.column("shard")[0].as_py()
        lists = table.column("vector").combine_chunks()
        vectors = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)
        graph = build_graph(vectors.astype(np.float32), seed + shard, width)
        row = {
            "key": shard, "rank": 0, "block": None, "ids": table.column("class_id").to_numpy().astype(np.int64).tobytes(), "vectors": vectors.tobytes(),
            "levels": graph.levels.tobytes(), "ground": graph.ground.tobytes(), "upper": graph.upper.tobytes(), "entry": graph.entry,
        }
        return pa.Table.from_pylist([row], schema=ARROW_INDEX)

    return run


def search_kernel(dim: int, width: int, most: int):
    """Sorted by key and rank: a shard's row, then the query blocks for it."""

    def run(batches):
        graph = ids = exact = None
        for batch in batches:
            for row in batch.to_pylist():
                if row["rank"] == 0:
                    exact = np.frombuffer(row["vectors"], np.float64).reshape(-1, dim)
                    ids = np.frombuffer(row["ids"], np.int64)
                    graph = Graph(with_length(exact.astype(np.float32)), np.frombuffer(row["levels"], np.int64))
                    graph.ground = np.frombuffer(row["ground"], np.int32).reshape(-1, 2 * LINKS)
                    graph.upper, graph.entry = np.frombuffer(row["upper"], np.int32).reshape(-1, LINKS), row["entry"]
                    continue
                if graph is None:
                    continue
                queries = np.frombuffer(row["vectors"], np.float64).reshape(-1, dim)
                out = ([], [], [])
                for query, q in zip(np.frombuffer(row["ids"], np.int64).tolist(), queries):
                    found = np.array(graph.best(np.append(q, 0).astype(np.float32), width), np.int64)
                    scores = exact[found] @ q
                    order = np.lexsort((ids[found], -scores))[:most]
                    if len(found) >= width and len(order) and scores[order[-1]] <= scores.min() + 1e-6 * abs(scores.min()):
                        # Equal scores fill the walk's list and may go on beyond it.
                        found, scores = np.arange(len(ids)), exact @ q
                        order = np.lexsort((ids, -scores))[:most]
                    out[0].extend([query] * len(order))
                    out[1].extend(ids[found[order]].tolist())
                    out[2].extend(scores[order].tolist())
                yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.float64())], ["query_class", "class_id", "score"])

    return run


def block_kernel(dim: int, size: int):
    def run(batches):
        from pyspark import TaskContext

        made = TaskContext.get().partitionId() << 24
        for batch in batches:
            ids = batch.column(0).to_numpy().astype(np.int64)
            vectors = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)
            for a in range(0, len(ids), size):
                made += 1
                yield pa.RecordBatch.from_pylist([{"key": 0, "rank": 1, "block": made, "ids": ids[a : a + size].tobytes(), "vectors": vectors[a : a + size].tobytes()}], schema=ARROW_INDEX)

    return run


def usable(vectors: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """(id, vector, dim) of rows that take part."""
    v = F.col("vector")
    rows = vectors.select(F.col(id_col).cast("bigint").alias("id"), F.col(vec_col).cast("array<double>").alias("vector"))
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    return rows.where(F.col("id").isNotNull() & v.isNotNull() & (F.size(v) > 0)).where(fine).withColumn("dim", F.size("vector"))


def nearest(vectors: DataFrame, is_query, k: int = 20, id_col: str = "vec_id", vec_col: str = "embedding", shard_bytes: int = 48 << 20, least_shards: int = 6, build_width: int = 100, search_width: int = 160, group_blocks: int = 16, seed: int = 29) -> DataFrame:
    """(query_id, rank, <id_col>, score): the ``k`` largest inner products found for rows where ``is_query``(id).

    A shard's vectors and links take at most about ``shard_bytes``, so the rows of a shard follow the dimension;
    each task searches one shard for at most ``group_blocks`` blocks of queries.
    """
    rows = usable(vectors, id_col, vec_col)
    keyed = rows.withColumn("class_key", F.sha2(F.concat_ws(",", F.transform("vector", lambda x: F.hex((x + F.lit(0.0)).cast("string")))), 256))
    classes = materialize(keyed.groupBy("class_key").agg(F.min("id").alias("class_id"), F.first("vector").alias("vector"), F.first("dim").alias("dim")), "classes")
    members = materialize(keyed.join(classes.select("class_key", "class_id"), "class_key").select("id", "class_id"), "members")
    asked = members.where(is_query(F.col("id"))).select(F.col("id").alias("query_id"), F.col("class_id").alias("query_class"))
    query_classes = classes.join(asked.select(F.col("query_class").alias("class_id")).distinct(), "class_id", "left_semi")
    found = None
    for head in classes.groupBy("dim").agg(F.count(F.lit(1)).alias("n")).orderBy("dim").collect():  # one row for each dimension
        dim, n = head["dim"], head["n"]
        own, queries = classes.where(F.col("dim") == dim), query_classes.where(F.col("dim") == dim)
        part = _search(own, queries, n, dim, k + 1, max(1, shard_bytes // (12 * (dim + 1) + 16 * LINKS)), least_shards, build_width, search_width, group_blocks, seed)
        found = part if found is None else found.unionByName(part)
    if found is None:
        return vectors.sparkSession.createDataFrame([], f"query_id bigint, rank int, `{id_col}` bigint, score double")
    best = Window.partitionBy("query_class").orderBy(F.desc("score"))
    top = found.withColumn("place", F.rank().over(best)).where(F.col("place") <= k + 1).drop("place")
    # The least k + 1 identifiers of a class are all an answer can need; salted, so a hot class is cut down early.
    part = Window.partitionBy("class_id", "salt").orderBy("id")
    whole = Window.partitionBy("class_id").orderBy("id")
    few = members.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(64))).withColumn("nth", F.row_number().over(part)).where(F.col("nth") <= k + 1)
    few = few.withColumn("nth", F.row_number().over(whole)).where(F.col("nth") <= k + 1).select("class_id", "id")
    answers = asked.join(top, "query_class").join(few, "class_id").where(F.col("id") != F.col("query_id"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    ranked = answers.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), F.col("id").alias(id_col), "score")


def _search(classes: DataFrame, queries: DataFrame, n: int, dim: int, most: int, shard_rows: int, least_shards: int, build_width: int, search_width: int, group_blocks: int, seed: int) -> DataFrame:
    """(query_class, class_id, score): of each shard the best ``most`` for each query, all of dimension ``dim``."""
    shards = max(1, min(n, max(least_shards, -(-n // shard_rows))))
    spread = classes.select("class_id", "vector", F.pmod(F.xxhash64("class_key"), F.lit(shards)).cast("int").alias("shard"))
    index = materialize(spread.repartitionByRange(shards, "shard").groupBy("shard").applyInArrow(build_kernel(dim, build_width, seed), INDEX), "graphs")
    blocks = materialize(queries.select("class_id", "vector").mapInArrow(tidied(block_kernel(dim, 128)), INDEX), "queries")
    groups = max(1, -(-blocks.count() // group_blocks))
    group = F.pmod(F.xxhash64("block"), F.lit(groups)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(shards - 1)))
    copies = index.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(groups - 1)))).withColumn("key", F.col("key") * groups + F.col("copy")).drop("copy")
    routed = blocks.withColumn("shard", every).withColumn("key", F.col("shard") * groups + group).drop("shard")
    stream = copies.unionByName(routed).repartitionByRange(shards * groups, "key").sortWithinPartitions("key", "rank", "block")
    return stream.mapInArrow(tidied(search_kernel(dim, search_width, most)), "query_class bigint, class_id bigint, score double")


def op9_nearest(spark, sf_dir: str) -> DataFrame:
    """Whole ``embeddings``: query_id, rank, vec_id, score for every vec_id divisible by 20, ties to the smaller vec_id.
    Rows that take no part (see above) are neither queries nor answers."""
    return nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), lambda i: i % 20 == 0)


def brute_force(ids: np.ndarray, vectors: np.ndarray, queries: list[int], k: int) -> dict[int, list[int]]:
    """Exact answers in double precision, for tests and recall."""
    place = {int(i): n for n, i in enumerate(ids)}
    out = {}
    for q in queries:
        s = vectors @ vectors[place[q]]
        s[place[q]] = -np.inf
        out[q] = ids[np.lexsort((ids, -s))[:k]].tolist()
    return out

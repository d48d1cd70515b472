"""Approximate nearest neighbours by learned partitions.

On a bounded sample the exact neighbour graph is cut into balanced parts (few edges between parts, equal sizes), and a small
classifier learns to name a vector's part. Every row is indexed in its most probable part; a query goes to
several most probable parts, as many as cover the sample's own neighbours to a target share, and candidates there are reranked by
exact distance. Parts are searched in blocks of bounded size, and queries come to them in blocks too, so an overfull or much asked
part is many tasks.

Identical vectors are searched once with their smallest ids, which is all that can be among the nearest.

Defined results: vectors that are null, empty, all zero, or hold null or non-finite components take no part, nor do rows with null
ids or with another dimension than most; equal rows count once; ties go to the smaller id; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

#: Rows of the sample at most (smallest hashes of ids), and its neighbours for each vertex of the graph.
SAMPLE_ROWS = 6144
GRAPH_NEIGHBOURS = 10
#: Rows aimed at for a part, most parts, and rows of a block.
PART_ROWS, MAX_PARTS, BLOCK_ROWS = 1024, 192, 4096
#: Share of the sample's neighbours that the probed parts must hold.
COVERAGE = 0.94


def neighbour_graph(x: np.ndarray, k: int) -> np.ndarray:
    """Indices of the k nearest others of each row."""
    norms, out = (x * x).sum(1), np.empty((len(x), k), np.int32)
    for i in range(0, len(x), 512):
        d = norms[None, :] - 2 * x[i : i + 512] @ x.T
        d[np.arange(len(d)), np.arange(i, i + len(d))] = np.inf
        out[i : i + 512] = np.argpartition(d, k - 1, axis=1)[:, :k]
    return out


def balanced_parts(x: np.ndarray, graph: np.ndarray, parts: int, slack: float = 0.05, sweeps: int = 12, seed: int = 1) -> np.ndarray:
    """Part of each vertex: halved again and again along the widest direction, then moved to where most neighbours are,
    within a capacity of (1 + slack) of the mean."""
    rng, n = np.random.default_rng(seed), len(x)
    part = np.zeros(n, np.int64)
    todo = [(np.arange(n), 0, parts)]
    while todo:
        rows, first, count = todo.pop()
        if count == 1:
            part[rows] = first
            continue
        centred = x[rows] - x[rows].mean(0)
        axis = rng.normal(size=x.shape[1])
        for _ in range(8):
            axis = centred.T @ (centred @ axis)
            axis /= np.linalg.norm(axis) or 1.0
        order, left = np.argsort(centred @ axis, kind="stable"), count // 2
        cut = len(rows) * left // count
        todo += [(rows[order[:cut]], first, left), (rows[order[cut:]], first + left, count - left)]
    capacity, sizes = int(np.ceil((1 + slack) * n / parts)), np.bincount(part, minlength=parts)
    both = [[] for _ in range(n)]
    for v in range(n):
        for u in graph[v]:
            both[v].append(u)
            both[u].append(v)
    for _ in range(sweeps):
        moved = 0
        for v in rng.permutation(n):
            votes = np.bincount(part[both[v]], minlength=parts)
            votes[sizes >= capacity] = -1
            best = int(votes.argmax())
            if votes[best] > np.count_nonzero(part[both[v]] == part[v]):
                sizes[part[v]] -= 1
                sizes[best] += 1
                part[v] = best
                moved += 1
        if moved < n // 500:
            break
    return part


class Router:
    """A network of one hidden layer that gives the log-probability of each part."""

    def __init__(self, x: np.ndarray, part: np.ndarray, parts: int, hidden: int = 96, steps: int = 400, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.mean, self.scale = x.mean(0), x.std(0) + 1e-9
        w = [rng.normal(size=(x.shape[1], hidden)) / np.sqrt(x.shape[1]), np.zeros(hidden), rng.normal(size=(hidden, parts)) * 0.01, np.zeros(parts)]
        m, v = [np.zeros_like(a) for a in w], [np.zeros_like(a) for a in w]
        z = (x - self.mean) / self.scale
        for t in range(1, steps + 1):
            rows = rng.integers(0, len(z), min(1024, len(z)))
            zb, h = z[rows], np.maximum(z[rows] @ w[0] + w[1], 0)
            p = h @ w[2] + w[3]
            p = np.exp(p - p.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(rows)), part[rows]] -= 1
            p /= len(rows)
            back = (p @ w[2].T) * (h > 0)
            for i, g in enumerate((zb.T @ back, back.sum(0), h.T @ p, p.sum(0))):
                m[i], v[i] = 0.9 * m[i] + 0.1 * g, 0.999 * v[i] + 0.001 * g * g
                w[i] = w[i] - 0.01 * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
        self.w = w

    def order(self, x: np.ndarray, first: int) -> np.ndarray:
        """The first most probable parts of each row."""
        h = np.maximum(((x - self.mean) / self.scale) @ self.w[0] + self.w[1], 0) @ self.w[2] + self.w[3]
        return np.argsort(-h, axis=1, kind="stable")[:, :first]


def fit(sample: np.ndarray, parts: int) -> tuple[Router | None, int]:
    """The router, and how many parts a query probes."""
    if parts < 2:
        return None, 1
    graph = neighbour_graph(sample, min(GRAPH_NEIGHBOURS, len(sample) - 1))
    router = Router(sample, balanced_parts(sample, graph, parts), parts)
    order = router.order(sample, parts)
    own = order[:, 0]
    rank = np.empty_like(order)
    np.put_along_axis(rank, order, np.arange(parts)[None, :].repeat(len(sample), 0), axis=1)
    needed = np.sort(np.take_along_axis(rank, own[graph], axis=1).ravel())
    return router, min(parts, int(needed[int(COVERAGE * (len(needed) - 1))]) + 1)


def matrix(column) -> np.ndarray:
    """A list column of equal lengths as a matrix of doubles."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k nearest found among vectors with other ids, by Euclidean distance."""
    spark = vectors.sparkSession

    def usable(df: DataFrame) -> DataFrame:
        v = F.col("v")
        fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
        return df.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).alias("v")).where(F.col("id").isNotNull() & v.isNotNull() & fine)

    rows = usable(vectors)
    common = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    dimension = common["d"] if common else 0
    rows, asked = rows.where(F.size("v") == dimension), usable(queries).where(F.size("v") == dimension)
    same = Window.partitionBy("v").orderBy("id")
    kept = stored(rows.distinct().withColumn("r", F.row_number().over(same)).where(F.col("r") <= k + 1).drop("r"), "vectors")
    n = kept.count()
    parts = int(min(max(n // PART_ROWS, 1), MAX_PARTS))
    sample = matrix(kept.orderBy(F.xxhash64("id"), "id").limit(SAMPLE_ROWS).select("v").toArrow().column(0)) if parts > 1 else np.zeros((0, 0))
    router, probes = fit(sample, parts)

    def routed(df: DataFrame, first: int) -> DataFrame:
        def run(batches):
            for batch in batches:
                x = matrix(batch.column(1))
                found = router.order(x, first) if router is not None else np.zeros((len(x), 1), np.int64)
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(found.astype(np.int32).tolist(), pa.list_(pa.int32()))], names=["id", "v", "parts"])

        return df.mapInArrow(run, "id long, v " + df.schema["v"].dataType.simpleString() + ", parts array<int>")

    indexed = stored(routed(kept, 1).select("id", "v", F.col("parts")[0].alias("part")), "vectors-indexed")
    sizes = {r["part"]: r["count"] for r in indexed.groupBy("part").count().collect()}  # one row a part, MAX_PARTS at most
    blocks = F.element_at(F.array(*(F.lit(-(-sizes.get(p, 0) // BLOCK_ROWS)) for p in range(parts))), F.col("part") + 1)
    placed = indexed.select("id", "v", "part", F.pmod(F.xxhash64("id"), blocks).cast("int").alias("block"))
    spread = stored(routed(asked.distinct(), probes).select("id", "v", F.explode("parts").alias("part")).where(blocks > 0), "vectors-asked")
    asks = {r["part"]: r["count"] for r in spread.groupBy("part").count().collect()}  # as above
    crowds = F.element_at(F.array(*(F.lit(-(-asks.get(p, 0) // BLOCK_ROWS)) for p in range(parts))), F.col("part") + 1)
    spread = spread.select("id", "v", "part", F.explode(F.sequence(F.lit(0), blocks - 1)).alias("block"), F.pmod(F.xxhash64("id", F.lit(1)), crowds).cast("int").alias("crowd"))
    placed = placed.where(crowds > 0).select("id", "v", "part", "block", F.explode(F.sequence(F.lit(0), crowds - 1)).alias("crowd"))

    def search(wanted: pa.Table, held: pa.Table) -> pa.Table:
        out: list[list] = [[], [], []]
        if wanted.num_rows and held.num_rows:
            x, ids = matrix(held.column("v")), held.column("id").to_numpy()
            for query, q in zip(wanted.column("id").to_pylist(), matrix(wanted.column("v"))):
                score = np.sqrt(((x - q) ** 2).sum(1))
                score[ids == query] = np.inf
                limit = np.partition(score, k - 1)[k - 1] if len(score) > k else np.inf
                near = np.flatnonzero((score <= limit) & (score < np.inf))
                near = near[np.lexsort((ids[near], score[near]))][:k]
                out[0] += [query] * len(near)
                out[1] += ids[near].tolist()
                out[2] += score[near].tolist()
        return pa.table([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.float64())], names=["query_id", "vec_id", "score"])

    met = ("part", "block", "crowd")
    found = spread.groupBy(*met).cogroup(placed.groupBy(*met)).applyInArrow(search, "query_id long, vec_id long, score double")
    best = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return found.distinct().withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

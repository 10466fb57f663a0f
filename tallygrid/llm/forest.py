"""Approximate nearest neighbours by inner product: a forest of random-projection trees behind one shared priority queue.

A tree splits at each node by a random direction, at the median of its sample. A query goes down all trees at once: one queue holds the
open branches of every tree by the distance that the query lies beyond their split, and the closest branch is followed next, in whatever tree, until the
leaves reached hold enough rows. Rows of these leaves are ranked exactly.

Largest inner product becomes nearest direction by one more coordinate, sqrt(M^2 - |x|^2) for rows, M the largest norm, and 0
for queries. The trees are fitted on at most `sample_rows` rows; every row is put into one leaf of every tree. Leaf counts, one number for
each leaf of the bounded forest, go to the driver; rows and queries meet by leaf, a leaf above `chunk_rows` rows in several chunks, and each
chunk hands on the best `k` of each query.

A query's leaves hold `breadth` times the rows of the table, counting a row once for each tree. Unless given, `breadth` is measured when the trees are fitted: rows
of the sample are looked for among the others, and it is the least that finds the share `recall` of their true neighbours, at every size
of table alike. In a larger table the nearest rows are nearer, so there it finds more. Data without clusters need much of it.

A chunk of rows meets its queries in blocks of about `chunk_rows` as well, so neither side of a task grows with the table.

Defined results: vectors that are null, zero, of another length than most, or that hold a null or non-finite part are neither queries nor candidates; rows
without vec_id neither; rows that repeat a vec_id are one row, with the least of their vectors; an empty table gives an empty result.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import cut, sampled, table

TREES, SAMPLE_ROWS, LEAF_SAMPLE, CHUNK_ROWS = 12, 20_000, 100, 4_096
RECALL, ASKED = 0.975, 200


@dataclass
class Forest:
    """Complete trees of equal depth: node n has the children 2n + 1 and 2n + 2; leaves are numbered from 0."""

    directions: np.ndarray  # trees, inner nodes, dimensions
    cuts: np.ndarray  # trees, inner nodes
    depth: int
    top: float  # largest norm of a row

    @property
    def leaves(self) -> int:
        return 1 << self.depth

    def sides(self, x: np.ndarray, tree: int) -> np.ndarray:
        return x @ self.directions[tree].T - self.cuts[tree]

    def leaf(self, x: np.ndarray, tree: int) -> np.ndarray:
        side = self.sides(x, tree)
        node = np.zeros(len(x), dtype=np.int64)
        for _ in range(self.depth):
            node = 2 * node + 1 + (np.take_along_axis(side, node[:, None], 1)[:, 0] > 0)
        return node - (self.leaves - 1)

    def raised(self, x: np.ndarray) -> np.ndarray:
        return np.concatenate([x, np.sqrt(np.maximum(0, self.top**2 - (x * x).sum(1)))[:, None]], axis=1)

    def search(self, x: np.ndarray, counts: np.ndarray, wanted: float, least: int) -> list[tuple[int, int]]:
        """Leaves (tree, leaf) for one raised query, closest first: until their rows are `wanted`, and one tree's `least`."""
        side = np.einsum("tnd,d->tn", self.directions, x) - self.cuts
        queue = [(0.0, t, 0) for t in range(len(self.cuts))]
        found, rows, of_tree = [], 0, np.zeros(len(self.cuts), dtype=np.int64)
        inner = self.leaves - 1
        while queue and (rows < wanted or of_tree.max() < least):
            beyond, t, node = heapq.heappop(queue)
            own = side[t]
            while node < inner:
                s = own[node]
                near = 2 * node + (2 if s > 0 else 1)
                heapq.heappush(queue, (max(beyond, abs(s)), t, 4 * node + 3 - near))
                node = near
            if n := counts[t, node - inner]:
                found.append((t, node - inner))
                rows += n
                of_tree[t] += n
        return found


def fit(sample: np.ndarray, top: float, trees: int, leaf_sample: int, seed: int = 7) -> Forest:
    rng = np.random.default_rng(seed)
    depth = max(0, int(np.floor(np.log2(max(1, len(sample)) / leaf_sample))) if len(sample) > leaf_sample else 0)
    inner = (1 << depth) - 1
    dims = sample.shape[1] + 1
    forest = Forest(np.zeros((trees, inner, dims)), np.zeros((trees, inner)), depth, top)
    x = forest.raised(sample)
    for t in range(trees):
        members: dict[int, np.ndarray] = {0: np.arange(len(x))}
        for node in range(inner):
            own = members.pop(node, np.arange(0))
            direction = rng.standard_normal(dims)
            if len(own) > 1:  # along the line between two rows, turned at random: it follows the data's spread
                a, b = rng.choice(own, 2, replace=False)
                direction = direction * 0.1 + (x[a] - x[b]) * np.sqrt(dims) / max(1e-12, np.linalg.norm(x[a] - x[b]))
            direction /= np.linalg.norm(direction)
            along = x[own] @ direction
            forest.directions[t, node] = direction
            forest.cuts[t, node] = np.median(along) if len(own) else 0.0
            members[2 * node + 1], members[2 * node + 2] = own[along <= forest.cuts[t, node]], own[along > forest.cuts[t, node]]
    return forest


def measured_breadth(forest: Forest, sample: np.ndarray, k: int, recall: float, asked: int = ASKED) -> float:
    """Leaf rows to look at, in times the table's rows, so that `asked` rows of the sample find the share `recall` of their k nearest others in it."""
    n = len(sample)
    if n < 2:
        return float(len(forest.cuts))
    leaf = np.stack([forest.leaf(forest.raised(sample), t) for t in range(len(forest.cuts))])
    counts = np.stack([np.bincount(own, minlength=forest.leaves) for own in leaf])
    places = []
    for q in np.unique(np.linspace(0, n - 1, min(asked, n)).astype(int)):
        score = sample @ sample[q]
        score[q] = -np.inf
        near = np.argpartition(-score, min(k, n - 1) - 1)[: min(k, n - 1)]
        order = forest.search(np.append(sample[q], 0.0), counts, np.inf, 0)
        until = np.full(counts.shape, np.inf)  # rows looked at when a leaf has been
        t, at = np.asarray(order).T
        until[t, at] = np.cumsum(counts[t, at])
        places.append(until[np.arange(len(leaf))[:, None], leaf[:, near]].min(axis=0))
    return float(np.quantile(np.concatenate(places), recall, method="higher")) / n


def usable(vector: Column) -> Column:
    finite = F.forall(vector, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < F.lit(float("inf"))))
    return vector.isNotNull() & finite & F.exists(vector, lambda e: e != 0)


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.empty((0, 0))


def _column(table_: pa.Table, name: str) -> pa.Array:
    found = table_.column(name)
    return found.combine_chunks() if isinstance(found, pa.ChunkedArray) else found


def _best(queries: pa.Table, rows: pa.Table, k: int) -> pa.Table:
    """The k best rows of one leaf chunk for each query, with ties; scores are sums in row order, so equal vectors score alike."""
    q, x = _matrix(_column(queries, "vector")), _matrix(_column(rows, "vector"))
    qid, rid = _column(queries, "query_id").to_numpy(), _column(rows, "vec_id").to_numpy()
    out_q, out_r, out_s = [], [], []
    for a in range(0, len(q), 512):
        scores = q[a : a + 512] @ x.T
        scores[qid[a : a + 512, None] == rid[None, :]] = -np.inf
        if scores.shape[1] > k:
            bound = np.partition(scores, -k, axis=1)[:, -k] - 1e-9 * np.maximum(1.0, np.abs(scores).max(axis=1, where=np.isfinite(scores), initial=0))
        else:
            bound = np.full(len(scores), -1e308)
        i, j = np.nonzero((scores >= bound[:, None]) & np.isfinite(scores))
        exact = (q[a + i] * x[j]).sum(axis=1)
        order = np.lexsort((rid[j], -exact, i))
        i, j, exact = i[order], j[order], exact[order]
        starts = np.flatnonzero(np.diff(i, prepend=-1))
        place = np.arange(len(i)) - np.repeat(starts, np.diff(np.append(starts, len(i))))
        keep = place < k
        out_q.append(qid[a + i[keep]])
        out_r.append(rid[j[keep]])
        out_s.append(exact[keep])
    join = lambda parts, kind: np.concatenate(parts) if parts else np.empty(0, kind)
    return pa.table({"query_id": join(out_q, np.int64), "vec_id": join(out_r, np.int64), "score": join(out_s, np.float64)})


def neighbours(vectors: DataFrame, queries: Column, k: int = 20, trees: int = TREES, sample_rows: int = SAMPLE_ROWS, leaf_sample: int = LEAF_SAMPLE, recall: float = RECALL, breadth: float | None = None, chunk_rows: int = CHUNK_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found of each row of `vectors` (vec_id, vector) for which `queries`, a condition on vec_id, holds."""
    spark = vectors.sparkSession
    schema = "query_id long, rank int, vec_id long, score double"
    kind = dict(vectors.dtypes)["vector"]
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "vector").where(F.col("vec_id").isNotNull() & usable(F.col("vector")))
    rows = cut(rows.groupBy("vec_id").agg(F.min("vector").alias("vector")))
    sizes = rows.groupBy(F.size("vector").alias("d")).agg(F.count("*").alias("n"), F.count(F.when(queries, 1)).alias("asked"), F.max(F.sqrt(F.aggregate("vector", F.lit(0.0), lambda a, e: a + e.cast("double") * e.cast("double")))).alias("top")).orderBy(F.desc("n"), "d").limit(1).collect()
    if not sizes:
        return spark.createDataFrame([], schema)
    dims, total, n_asked, top = sizes[0]
    rows = rows.where(F.size("vector") == dims)
    sample = np.asarray([r[1] for r in sorted(sampled(rows, F.col("vec_id"), sample_rows, total).limit(2 * sample_rows).collect())] or np.zeros((1, dims)))
    fitted = fit(sample, float(top), trees, leaf_sample)
    wanted = (measured_breadth(fitted, sample, k, recall) if breadth is None else breadth) * total
    forest = spark.sparkContext.broadcast(fitted)

    def index(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = forest.value
        for batch in batches:
            if batch.num_rows:
                x = f.raised(_matrix(batch.column("vector")))
                for t in range(len(f.cuts)):
                    yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("vector"), pa.array(np.full(len(x), t, np.int32)), pa.array(f.leaf(x, t).astype(np.int32))], names=["vec_id", "vector", "tree", "leaf"])

    placed = rows.mapInArrow(index, f"vec_id long, vector {kind}, tree int, leaf int")
    counted = placed.groupBy("tree", "leaf").agg(F.count("*").alias("n")).collect()
    counts = np.zeros((trees, fitted.leaves), dtype=np.int64)
    for t, leaf, n in counted:
        counts[t, leaf] = n
    chunks = np.maximum(1, -(-counts // chunk_rows))
    blocks = max(1, -(-n_asked // chunk_rows))  # a chunk may be asked by all queries
    plan = spark.sparkContext.broadcast((counts, chunks))
    mix = lambda ids: (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)

    def probe(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f, (n, parts) = forest.value, plan.value
        for batch in batches:
            x = _matrix(batch.column("vector"))
            block = mix(batch.column("vec_id").to_numpy()) % np.uint64(blocks)
            for i in range(len(x)):
                leaves = f.search(np.append(x[i], 0.0), n, wanted, k + 1)
                spots = [(t, leaf, c) for t, leaf in leaves for c in range(parts[t, leaf])]
                at = pa.array(np.full(len(spots), i))
                t, leaf, c = (pa.array(np.asarray(v, dtype=np.int32)) for v in zip(*spots, strict=True))
                yield pa.RecordBatch.from_arrays([batch.column("vec_id").take(at), batch.column("vector").take(at), t, leaf, c, pa.array(np.full(len(spots), block[i], np.int32))], names=["query_id", "vector", "tree", "leaf", "chunk", "block"])

    def chunked(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = plan.value[1]
        for batch in batches:
            of = parts[batch.column("tree").to_numpy(), batch.column("leaf").to_numpy()]
            batch = batch.append_column("chunk", pa.array((mix(batch.column("vec_id").to_numpy()) % of.astype(np.uint64)).astype(np.int32)))
            for b in range(blocks):
                yield batch.append_column("block", pa.array(np.full(batch.num_rows, b, np.int32)))

    asked = rows.where(queries).repartition(F.col("vec_id")).mapInArrow(probe, f"query_id long, vector {kind}, tree int, leaf int, chunk int, block int")
    dealt = placed.mapInArrow(chunked, f"vec_id long, vector {kind}, tree int, leaf int, chunk int, block int")
    key = ["tree", "leaf", "chunk", "block"]
    best = asked.groupBy(*key).cogroup(dealt.groupBy(*key)).applyInArrow(lambda q, x: _best(q, x, k), "query_id long, vec_id long, score double")
    once = best.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return once.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("vector"))
    return neighbours(rows, F.col("vec_id") % 20 == 0)

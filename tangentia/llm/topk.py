"""Exact top-k inner products with a KD-tree for each shard.

Vectors are dealt to shards by hash. One task builds a shard's tree, by median splits along the widest side, with a tight
box for each node, and writes it: each tree is built once, and vectors are shuffled once. Queries come in blocks of
bounded size; a block is broadcast to all trees, which stay where they are, so nothing is copied for each
shard and query. A tree is walked best-first for each query by the bound that a box sets to the inner product. The walk begins with a
kth score that a small pilot shard has already reached, so far boxes are never opened, and stops when the best
open box can't reach the kth score so far. Each shard gives its k best; k rows for each shard and query are merged in the end.

In many dimensions boxes overlap every query's best ones and few are pruned, so the leaves are scored as
matrix products; results are exact either way.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tangentia.session import materialise, ship_package

SHARD_ROWS = 16_384
QUERY_ROWS = 16_384  # queries that are broadcast at a time
LEAF_ROWS = 256
PILOT_ROWS = 2_048
BOUND_ROWS = 1_024
PLANS = 16  # blocks of queries in one plan
FOUND = "query_id long, vec_id long, score long"
TREE = "dim int, ids binary, x binary, lo binary, hi binary, child binary, rows binary"


class KdTree:
    """Median splits along the widest side; nodes in arrays, rows of a leaf contiguous."""

    def __init__(self, x: np.ndarray, leaf: int = LEAF_ROWS):
        self.order = np.arange(len(x))
        self.lo, self.hi, self.child, self.rows = [], [], [], []
        open_ = [(0, len(x), -1, 0)]
        while open_:
            a, b, parent, side = open_.pop()
            me = len(self.lo)
            part = x[self.order[a:b]]
            lo, hi = part.min(0), part.max(0)
            self.lo.append(lo)
            self.hi.append(hi)
            self.child.append([-1, -1])
            self.rows.append((a, b))
            if parent >= 0:
                self.child[parent][side] = me
            axis = int(np.argmax(hi - lo))
            if b - a > leaf and hi[axis] > lo[axis]:
                mid = (b - a) // 2
                self.order[a:b] = self.order[a:b][np.argpartition(part[:, axis], mid)]
                open_ += [(a, a + mid, me, 0), (a + mid, b, me, 1)]
        self.lo, self.hi = np.stack(self.lo), np.stack(self.hi)
        self.child, self.rows = np.array(self.child), np.array(self.rows)
        self.x = x[self.order]

    def stored(self, ids: np.ndarray) -> dict[str, object]:
        """A row of the table of trees; whole numbers of eight bytes throughout."""
        parts = {"ids": ids[self.order], "x": self.x, "lo": self.lo, "hi": self.hi, "child": self.child, "rows": self.rows}
        return {"dim": self.x.shape[1], **{k: np.ascontiguousarray(v, np.int64).tobytes() for k, v in parts.items()}}

    @classmethod
    def loaded(cls, row: dict) -> tuple[KdTree, np.ndarray]:
        """(tree, ids in its order) of such a row."""
        tree = cls.__new__(cls)
        of = lambda k, width: np.frombuffer(row[k], np.int64).reshape(-1, width)
        tree.x, tree.lo, tree.hi = (of(k, row["dim"]) for k in ("x", "lo", "hi"))
        tree.child, tree.rows = of("child", 2), of("rows", 2)
        return tree, np.frombuffer(row["ids"], np.int64)


def exact_type(*arrays: np.ndarray):
    """float64 where all sums are whole numbers below 2^53 (so BLAS is exact), else Python's whole numbers."""
    top = [max(1.0, float(np.abs(a).max(initial=0))) for a in arrays]
    return np.float64 if top[0] * top[-1] * arrays[0].shape[1] < 2**53 else object


def search_shard(tree: KdTree, ids: np.ndarray, query_ids: np.ndarray, q: np.ndarray, floor: np.ndarray, k: int) -> list[tuple[int, int, int]]:
    """(query_id, vec_id, score) of each query's k best rows here, of those that may be among its k best of all.

    ``floor``: a score that k other rows are known to reach, or -inf. Boxes are dropped only if they can't reach
    the kth score, so ties are kept and go to the smaller vec_id.
    """
    kind = exact_type(q, tree.x)
    x, q = tree.x.astype(kind), q.astype(kind)
    lo, hi = tree.lo.astype(kind), tree.hi.astype(kind)
    child, rows = tree.child.tolist(), tree.rows.tolist()
    out: list[tuple[int, int, int]] = []
    for first in range(0, len(q), BOUND_ROWS):
        part = q[first : first + BOUND_ROWS]
        bounds = np.maximum(part, 0) @ hi.T + np.minimum(part, 0) @ lo.T  # the most that a row in a node's box can score
        for i, query_id in enumerate(query_ids[first : first + BOUND_ROWS]):
            bound, best, kth = bounds[i], [], floor[first + i]
            heap = [(-bound[0], 0)]
            while heap and -heap[0][0] >= kth:
                _, node = heapq.heappop(heap)
                left, right = child[node]
                if left >= 0:
                    heapq.heappush(heap, (-bound[left], left))
                    heapq.heappush(heap, (-bound[right], right))
                    continue
                a, b = rows[node]
                s = x[a:b] @ part[i]
                at = np.flatnonzero((s >= kth) & (ids[a:b] != query_id))
                if len(at) > k:  # the kth of these, and what ties with it
                    cut = np.partition(s[at], len(at) - k)[len(at) - k]
                    at = at[s[at] >= cut]
                    at = at[np.lexsort((ids[a:b][at], -s[at]))][:k]
                best += [(-int(s[j]), int(ids[a + j])) for j in at]
                best = sorted(best)[:k]
                if len(best) == k:
                    kth = max(kth, -best[-1][0])
            out += [(int(query_id), v, -s) for s, v in best]
    return out


def quantise(embeddings: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 256) -> DataFrame:
    """(vec_id, v, dim): floor(scale * x) of each component; rows with no id, no components, or null or non-finite ones go."""
    d = embeddings.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("x"))
    d = d.where(F.col("vec_id").isNotNull() & (F.size("x") > 0) & F.forall("x", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < F.lit(float("inf")))))
    return d.select("vec_id", F.transform("x", lambda c: F.floor(c * F.lit(float(scale)))).alias("v"), F.size("x").alias("dim"))


def top_k(embeddings: DataFrame, k: int = 5, query_modulus: int = 50, shard_rows: int = SHARD_ROWS, query_rows: int = QUERY_ROWS) -> DataFrame:
    """(query_id, rank, vec_id, score): the k rows with the highest integer inner product for each row whose vec_id is divisible by ``query_modulus``.

    Ties go to the smaller vec_id; a query's own id is no candidate. Only vectors of one length are compared. Ids that
    repeat are candidates once a row (k at most count); as a query, such an id has its least vector. Other columns are ignored;
    an empty table gives an empty result; with fewer than k candidates all are returned.
    """
    spark = embeddings.sparkSession
    ship_package(spark)
    rows = quantise(embeddings)
    # more than k rows of one id and vector change nothing
    rows = rows.groupBy("vec_id", "dim", "v").agg(F.count(F.lit(1)).alias("n"))
    rows = materialise(rows.withColumn("copy", F.explode(F.sequence(F.lit(1), F.least("n", F.lit(k)).cast("int")))).drop("n"), "vectors")
    n = rows.count()
    queries = rows.where(F.col("vec_id") % query_modulus == 0).groupBy("vec_id").agg(F.min(F.struct("dim", "v")).alias("m")).select(F.col("vec_id").alias("query_id"), "m.dim", "m.v")
    queries = materialise(queries, "queries")
    shards, blocks = max(1, math.ceil(n / shard_rows)), math.ceil(queries.count() / query_rows)
    trees = rows.withColumn("shard", F.pmod(F.xxhash64("vec_id", "v", "copy"), F.lit(shards)).cast("int"))

    def build(f: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame([KdTree(np.stack(f["v"].to_numpy())).stored(f["vec_id"].to_numpy())])

    trees = materialise(trees.groupBy("dim", "shard").applyInPandas(build, TREE), "trees")
    pilot = [(r["vec_id"], r["v"]) for r in rows.where(F.pmod(F.xxhash64("vec_id"), F.lit(max(1, n // PILOT_ROWS))) == 0).limit(PILOT_ROWS).collect()]
    found = spark.createDataFrame([], FOUND)
    for block in range(blocks):
        own = queries.where(F.pmod(F.xxhash64("query_id"), F.lit(blocks)) == block).toArrow()
        by_dim = _query_blocks(own, pilot, k)
        found = found.unionByName(trees.mapInArrow(_search_batches(spark.sparkContext.broadcast(by_dim), k), FOUND))
        if blocks > 1 and (block + 1) % PLANS == 0:
            found = materialise(found, "found")
    best = Window.partitionBy("query_id").orderBy(F.col("score").desc(), F.col("vec_id"))
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int"), "vec_id", "score")


def _query_blocks(table: pa.Table, pilot: list[tuple], k: int) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Of each length of vectors, (query ids, vectors, the kth score that the pilot rows give)."""
    out = {}
    dims = np.asarray(table["dim"])
    for dim in np.unique(dims):
        own = table.filter(pa.array(dims == dim))
        ids = np.asarray(own["query_id"], np.int64)
        q = np.asarray(own["v"].combine_chunks().flatten(), np.int64).reshape(len(ids), dim)
        near = [(i, v) for i, v in pilot if len(v) == dim]
        floor = np.full(len(ids), -math.inf)
        if len(near) > k:
            x = np.asarray([v for _, v in near], np.int64)
            kind, pilot_ids = exact_type(q, x), np.asarray([i for i, _ in near])
            x = x.astype(kind).T
            for i in range(len(ids)):
                scores = np.sort((q[i].astype(kind) @ x)[pilot_ids != ids[i]])
                if len(scores) >= k:
                    floor[i] = scores[-k]
        out[int(dim)] = (ids, q, floor)
    return out


def _search_batches(shared, k: int):
    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                one = {name: batch.column(c)[row].as_py() for c, name in enumerate(batch.schema.names)}
                if one["dim"] in shared.value:
                    tree, ids = KdTree.loaded(one)
                    found = search_shard(tree, ids, *shared.value[one["dim"]], k)
                    columns = zip(*found, strict=True) if found else ((), (), ())
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["query_id", "vec_id", "score"])

    return search

"""Nearest neighbours by collision counting on sorted projections.

Each of ``projections`` random directions orders a block of vectors once. A
query's window on a direction is centred on the query's own projection; it is
widened step by step (virtual rehashing), and a vector collides on a direction
when the window reaches it. Widening ends when ``budget`` of the block (in a
small one ``least`` vectors) and k more collide on at least ``threshold`` of the
directions, or the window holds the whole block. The vectors of the highest
collision count that so many reach are verified by their exact inner product.

Largest inner product becomes least distance by one more coordinate that brings
all vectors of a block to the same length; a query has 0 there.

Vectors are dealt into index blocks of bounded size. A block's sorted arrays are
built once and stored in the shared folder; a task reads one block and answers
one bounded chunk of the queries with it, k rows each, so memory is bounded,
vectors are shuffled once, and no pair outside the k best leaves a task. With
several index blocks the k best of each are merged.

Defined cases: vectors that are null, empty, zero, or hold null or non-finite
components take no part, nor do null ids; rows of one id are one vector, the
least in array order, as query and as candidate; rows of the query's own id are
not its candidates; vectors of another length are not comparable; equal scores
order by smaller id; fewer than k candidates are all returned; no rows give no
rows; other columns, whatever their names, are not read.
"""

from __future__ import annotations

import io

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from .store import discard, executor_fs, materialise, scratch_path, write_atomically

INDEX_BLOCK = 1 << 15
QUERY_BLOCK = 1 << 12
PROJECTIONS = 256


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, embedding) of the vectors that take part, each id once."""
    bad = F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding")).where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & ~bad & F.exists("embedding", lambda x: x != 0))
    # rows of a repeated id meet already where they are read
    return rows.groupBy("vec_id").agg(F.min("embedding").alias("embedding"))


def add_up(sets: list[np.ndarray]) -> list[np.ndarray]:
    """Bit-sliced counts of bitsets: item i of the result holds bit i of every count."""
    out, level = [], sets
    while level:
        carries = []
        while len(level) > 1:
            if len(level) == 2:
                x, y = level.pop(), level.pop()
                carries.append(x & y)
                level.append(x ^ y)
            else:
                x, y, z = level.pop(), level.pop(), level.pop()
                half = x ^ y
                carries.append((x & y) | (half & z))
                level.append(half ^ z)
        out.append(level[0])
        level = carries
    return out


def at_least(counts: list[np.ndarray], need: int) -> np.ndarray:
    """The bitset of those whose bit-sliced count is ``need`` or more."""
    above, equal = np.zeros_like(counts[0]), ~np.zeros_like(counts[0])
    for i in range(max(len(counts), need.bit_length()) - 1, -1, -1):
        bit = counts[i] if i < len(counts) else np.zeros_like(counts[0])
        if need >> i & 1:
            equal = equal & bit
        else:
            above |= equal & bit
            equal = equal & ~bit
    return above | equal


class ProjectionIndex:
    """Sorted projections of one block of vectors.

    Each sorted array is cut into ``cells`` runs of equal size. For every cut the
    bitset of the vectors before it is kept, so that the vectors in a window of
    whole cells are the difference of two bitsets, and the collisions of all
    directions are added up 64 vectors at a time.
    """

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, projections: int = PROJECTIONS, cells: int = 64, seed: int = 5, order: np.ndarray | None = None):
        n = len(vectors)
        self.ids, self.vectors, self.single = ids, vectors, vectors.astype(np.float32)
        squared = (vectors * vectors).sum(1)
        self.longest = float(np.sqrt(squared.max(initial=0.0))) or 1.0
        lifted = np.sqrt(np.maximum(self.longest**2 - squared, 0))
        self.directions = np.random.default_rng(seed).normal(size=(vectors.shape[1] + 1, projections))
        projected = (vectors @ self.directions[:-1] + lifted[:, None] * self.directions[-1]) / self.longest
        self.order = np.stack([np.argsort(p, kind="stable") for p in projected.T.copy()]).astype(np.int32) if order is None else order
        cells = min(cells, n)
        self.words = -(-n // 64)
        cuts = np.arange(cells + 1) * n // cells
        cell_of_rank = np.repeat(np.arange(cells, dtype=np.uint8), np.diff(cuts))
        self.edges = np.full((projections, cells + 1), np.inf)
        self.before = np.zeros((projections, cells + 1, self.words * 8), np.uint8)
        cell, cut = np.empty(n, np.uint8), np.arange(cells + 1, dtype=np.uint8)[:, None]
        for i, by_rank in enumerate(self.order):
            self.edges[i, :cells] = projected[by_rank[cuts[:-1]], i]
            cell[by_rank] = cell_of_rank
            self.before[i, :, : -(-n // 8)] = np.packbits(cell < cut, axis=1, bitorder="little")
        self.before = self.before.view(np.uint64)

    def stored(self) -> bytes:
        """What ``opened`` needs: the vectors and their sorted orders."""
        out = io.BytesIO()
        np.savez(out, ids=self.ids, vectors=self.vectors, order=self.order)
        return out.getvalue()

    @classmethod
    def opened(cls, raw: bytes, projections: int) -> ProjectionIndex:
        held = np.load(io.BytesIO(raw))
        return cls(held["ids"], held["vectors"], projections, order=held["order"])

    def _windows(self, centres: np.ndarray, half: np.ndarray) -> list[np.ndarray]:
        """Per direction, the bitsets of the vectors in each query's window."""
        out = []
        for edges, before, centre in zip(self.edges, self.before, centres.T):
            low = np.maximum(np.searchsorted(edges, centre - half, side="right") - 1, 0)
            high = np.maximum(np.searchsorted(edges, centre + half, side="left"), low)
            out.append(before[low] ^ before[high])
        return out

    def search(self, queries: np.ndarray, query_ids: np.ndarray, k: int, threshold: float, budget: float, least: int, first: float, factor: float, group: int = 32):
        """Yield (query id, places, scores) of the k best verified vectors of each query."""
        ids, n, need = self.ids, len(self.ids), int(np.ceil(threshold * len(self.edges)))
        wanted = min(n, max(int(budget * n), least) + k + 1)
        lengths = np.linalg.norm(queries, axis=1)
        centres = (queries / lengths[:, None]) @ self.directions[:-1]  # the order of inner products ignores the query's length
        for start in range(0, len(queries), group):
            live = np.arange(start, min(start + group, len(queries)))
            half = np.full(len(live), first)
            while len(live):
                counts = add_up(self._windows(centres[live], half))
                hit = at_least(counts, need)
                everything = half > 64.0  # wider than any projection of unit vectors can be
                enough = (np.bitwise_count(hit).sum(1) >= wanted) | everything
                for i in np.flatnonzero(enough):
                    q, all_of_them = live[i], everything[i]
                    bits = self._highest([c[i] for c in counts], hit[i], need, wanted)
                    found = np.arange(n) if all_of_them else np.flatnonzero(np.unpackbits(bits.view(np.uint8), bitorder="little")[:n])
                    found = found[ids[found] != query_ids[q]]
                    if not all_of_them and len(found) < min(k, n - np.count_nonzero(ids == query_ids[q])):
                        found = np.flatnonzero(ids != query_ids[q])  # many rows of the query's own id
                    yield query_ids[q], *self._verify(queries[q], lengths[q], found, ids, k)
                live, half = live[~enough], half[~enough] * factor

    def _highest(self, counts: list[np.ndarray], hit: np.ndarray, need: int, wanted: int) -> np.ndarray:
        """The bitset of ``wanted`` or more vectors that reach the highest threshold which that many reach."""
        low, high = need, len(self.edges) + 1  # the last step of widening reaches more than asked for
        while high - low > 1:
            middle = (low + high) // 2
            above = at_least(counts, middle)
            if np.bitwise_count(above).sum() >= wanted:
                low, hit = middle, above
            else:
                high = middle
        return hit

    def _verify(self, query: np.ndarray, length: float, found: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        if len(found) > k:  # single precision sorts out what is clearly worse
            rough = self.single[found] @ query.astype(np.float32)
            kth = np.partition(rough, len(found) - k)[len(found) - k]
            found = found[rough >= kth - 1e-4 * length * self.longest]
        scores = self.vectors[found] @ query
        best = np.lexsort((ids[found], -scores))[:k]
        return found[best], scores[best]


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 20, projections: int = PROJECTIONS, threshold: float = 0.65, budget: float = 0.05, least: int = 400, first: float = 1.5, factor: float = 1.4, index_block: int = INDEX_BLOCK, query_block: int = QUERY_BLOCK) -> DataFrame:
    """The k nearest found of every query (vec_id, embedding): query_id, rank, vec_id, score."""
    spark = vectors.sparkSession
    vectors, queries = materialise(usable(vectors), "vectors"), materialise(usable(queries), "query-vectors")
    asked = queries.count()
    n_index = max(1, -(-vectors.count() // index_block))
    # chunks are smaller only where the cluster would idle
    n_query = max(1, -(-asked // query_block), min(-(-asked // 1024), -(-2 * spark.sparkContext.defaultParallelism // n_index)))
    path = scratch_path(spark, "projection-index")
    # hashing ids keeps blocks near-equal and reruns alike
    block = lambda n: F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int")

    def matrix(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        ids = table.column("vec_id").to_numpy()
        flat = table.column("embedding").combine_chunks().flatten().to_numpy()
        order = np.argsort(ids, kind="stable")
        return ids[order], flat.reshape(len(ids), -1)[order]

    def place(table: pa.Table) -> str:
        return f"{path}/{table.column('dim')[0].as_py()}-{table.column('ib')[0].as_py()}.npz"

    def build(rows: pa.Table) -> pa.Table:
        size = write_atomically(place(rows), [ProjectionIndex(*matrix(rows), projections).stored()])
        return pa.table({"dim": rows.column("dim").slice(0, 1), "ib": rows.column("ib").slice(0, 1), "size": pa.array([size], pa.int64())})

    def answer(rows: pa.Table) -> pa.Table:
        fs, name = executor_fs(place(rows))
        with fs.open_input_file(name) as file:
            index = ProjectionIndex.opened(file.read(), projections)
        ids, data = matrix(rows)
        found = [(np.full(len(places), q), index.ids[places], scores) for q, places, scores in index.search(data, ids, k, threshold, budget, least, first, factor)]
        return pa.table([np.concatenate(c) for c in zip(*found)], names=["query_id", "vec_id", "score"])

    sized = lambda rows: rows.withColumn("dim", F.size("embedding"))
    blocks = materialise(sized(vectors).withColumn("ib", block(n_index)).repartition(2 * n_index, "dim", "ib").groupBy("dim", "ib").applyInArrow(build, "dim int, ib int, size long"), "projection-blocks")
    discard(vectors)
    # a row a block of thousands of vectors; queries meet the blocks of their length
    chunked = sized(queries).withColumn("qb", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(n_query)).cast("int")).join(blocks.select("dim", "ib"), "dim")
    # a group is minutes of work on few bytes, so partitions are not merged by their size
    found = chunked.repartition(2 * n_index * n_query, "dim", "ib", "qb").groupBy("dim", "ib", "qb").applyInArrow(answer, "query_id long, vec_id long, score double")
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def brute_force(ids: np.ndarray, data: np.ndarray, query_ids: np.ndarray, k: int = 20) -> dict[int, list[int]]:
    """The true k nearest, for measuring recall."""
    out = {}
    for q in query_ids:
        scores = data @ data[np.flatnonzero(ids == q)[0]]
        scores[ids == q] = -np.inf
        out[int(q)] = ids[np.lexsort((ids, -scores))[:k]].tolist()
    return out

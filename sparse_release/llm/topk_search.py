"""Exact top-k search by inner product with dual cover trees.

Inner products become angles: with one more coordinate all data vectors get the norm of the longest one, and on that sphere a larger inner product with a query is a
smaller angle to it. Angles are a metric, so nodes of cover trees bound each other: no row of a node is nearer to a row of a query node than the angle of the centres
less both covering radii. A pair of nodes is pruned when that bound is below the worst kth score of the query node.

The same holds between tasks. Data is dealt to the nearest of some pivots, and a pivot's cell is cut into shells by angle from it, blocks of bounded rows; a query first
searches the block that could hold the nearest, and then goes only to blocks whose shells could still hold better, first judged for queries that share a nearest pivot
together, then for each. Cells and blocks grow with the data. In a task, the block and the queries that came are each indexed by a cover tree.

Vectors are arrays of whole numbers (up to 2^25 or so in size, so that scores are exact in doubles); shorter ones count as padded by zeros. Null vectors, and those with
null components, take no part; a null id takes no part either. Ties go to the smaller id. A row is never its own partner (equal ids are one row's); repeated rows are
candidates each. Of rows with one and the same vector only as many as can be among the best are searched. A query of zeros scores 0 with all: the smallest ids. Fewer
than k candidates: all. An empty table gives an empty result. Other columns do not matter.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import durable

#: Rows of a block, at least; most blocks (beyond, blocks have more rows); most cells; vectors drawn for each pivot; shells that a cell is counted in.
BLOCK_ROWS, MAX_BLOCKS, MAX_CELLS, DRAWN, SHELLS = 8192, 16_384, 1024, 20, 256
#: Queries of one task, rows of a leaf, children of a node.
SLICE_QUERIES, LEAF, FAN = 65_536, 48, 12
#: Leaves that are met at a time, at most.
TOGETHER = 64
#: Rounding of angles and cosines.
SLACK = 1e-6


def lifted(x: np.ndarray, longest: float) -> np.ndarray:
    """Data vectors on the unit sphere of one more dimension; longest: the largest norm of all."""
    last = np.sqrt(np.maximum(longest**2 - (x**2).sum(axis=1), 0.0))
    return np.hstack((x, last[:, None])) / longest


def directed(q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Query vectors (none of zeros) on the same sphere; and their norms."""
    norm = np.sqrt((q**2).sum(axis=1))
    return np.hstack((q / norm[:, None], np.zeros((len(q), 1)))), norm


def angles(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.arccos(np.clip(a @ b.T, -1.0, 1.0))


def scattered(u: np.ndarray, most: int) -> tuple[list[int], np.ndarray, np.ndarray]:
    """Rows of u, `most` at most, each the furthest from all before; for each row the nearest of them, and its angle. All lie within the largest of these angles of
    one, and no two of the rows are nearer to each other than that."""
    chosen, near = [0], angles(u, u[:1])[:, 0]
    own = np.zeros(len(u), np.int64)
    while len(chosen) < most and near[at := int(near.argmax())] > SLACK:
        far = angles(u, u[at : at + 1])[:, 0]
        closer = far < near
        own[closer], near[closer] = len(chosen), far[closer]
        chosen.append(at)
    return chosen, own, near


class Tree:
    """A cover tree: nodes with a centre, a covering radius (angle), and rows or children. A node's own centre is its first child's (nesting), children cover all its
    rows within their level's radius (covering), and their centres are at least as far apart (separation)."""

    def __init__(self, u: np.ndarray, leaf: int = LEAF, fan: int = FAN) -> None:
        self.u, self.leaf, self.fan = u, leaf, fan
        self.at: list[int] = []  # row of u that is the centre
        self.rows: list[np.ndarray] = []
        self.kids: list[np.ndarray] = []
        radius: list[float] = []
        todo = [(np.arange(len(u)), -1)]
        while todo:
            rows, parent = todo.pop()
            node = len(self.at)
            if parent >= 0:
                self.kids[parent] = np.append(self.kids[parent], node)
            far = angles(u[rows], u[rows[:1]])[:, 0]
            self.at.append(int(rows[0]))
            radius.append(float(far.max()) + SLACK)
            self.rows.append(rows)
            self.kids.append(np.empty(0, np.int64))
            if len(rows) > leaf and far.max() > SLACK:
                chosen, own, _ = scattered(u[rows], fan)
                for k, c in enumerate(chosen):
                    of = rows[own == k]
                    todo.append((np.concatenate((rows[[c]], of[of != rows[c]])), node))
        self.radius, self.centers = np.array(radius), u[self.at]


class Search:
    """Top k of each query among the rows of one block; `floor` is what a query must reach at least, `longest` the largest norm of all data."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, q: np.ndarray, q_ids: np.ndarray, floor: np.ndarray, k: int, longest: float, leaf: int = LEAF) -> None:
        self.x, self.ids, self.q, self.q_ids, self.k, self.scored = x, ids, q, q_ids, k, 0
        self.best, self.who, self.floor = np.full((len(q), k), -np.inf), np.full((len(q), k), np.iinfo(np.int64).max), floor.copy()
        if len(x) and len(q):
            self.uq, norm = directed(q)
            self.reach = norm * longest
            self.data, self.asked = Tree(lifted(x, longest), leaf), Tree(self.uq, leaf)
            self.descend(0, np.zeros(1, np.int64))

    def worst(self, rows: np.ndarray) -> float:
        """The cosine that a node must allow to be of use to one of these queries."""
        return float((self.floor[rows] / self.reach[rows]).min()) - SLACK

    def bounds(self, q: int, nodes: np.ndarray) -> np.ndarray:
        """The largest cosine that query node q and each data node allow."""
        between = angles(self.data.centers[nodes], self.asked.centers[q : q + 1])[:, 0]
        return np.cos(np.maximum(between - self.asked.radius[q] - self.data.radius[nodes], 0.0))

    def descend(self, q: int, nodes: np.ndarray) -> None:
        """Data nodes that may matter to query node q; wide ones are opened before its children are looked at."""
        nodes = nodes[self.bounds(q, nodes) >= self.worst(self.asked.rows[q])]
        if not len(self.asked.kids[q]):
            self.visit(q, nodes)
            return
        wide = [n for n in nodes if len(self.data.kids[n]) and self.data.radius[n] >= self.asked.radius[q]]
        nodes = np.concatenate([np.setdiff1d(nodes, wide), *[self.data.kids[n] for n in wide]]).astype(np.int64)
        for kid in self.asked.kids[q]:
            self.descend(int(kid), nodes)

    def visit(self, q: int, nodes: np.ndarray) -> None:
        """One leaf of queries with data nodes, the most promising first; leaves are met together, ever more at a time, as the worst score settles."""
        rows, together = self.asked.rows[q], 1
        heap = [(-b, int(n)) for b, n in zip(self.bounds(q, nodes).tolist(), nodes, strict=True)]
        heapq.heapify(heap)
        while heap:
            least, leaves = self.worst(rows), []
            while heap and len(leaves) < together and -heap[0][0] >= least:
                _, n = heapq.heappop(heap)
                if len(kids := self.data.kids[n]):
                    for b, kid in zip(self.bounds(q, kids).tolist(), kids, strict=True):
                        if b >= least:
                            heapq.heappush(heap, (-b, int(kid)))
                else:
                    leaves.append(n)
            if not leaves:
                return
            # each query by itself against the leaves' balls
            own = np.cos(np.maximum(angles(self.uq[rows], self.data.centers[leaves]) - self.data.radius[leaves], 0.0)) >= (self.floor[rows] / self.reach[rows] - SLACK)[:, None]
            if own.any():
                self.meet(rows[own.any(axis=1)], np.concatenate([self.data.rows[n] for n in np.array(leaves)[own.any(axis=0)]]))
            together = min(2 * together, TOGETHER)

    def meet(self, qs: np.ndarray, xs: np.ndarray) -> None:
        self.scored += len(qs) * len(xs)
        score = self.q[qs] @ self.x[xs].T
        score[self.q_ids[qs][:, None] == self.ids[xs][None, :]] = -np.inf
        least = self.floor[qs]
        if score.shape[1] > self.k:
            least = np.maximum(least, np.partition(score, -self.k, axis=1)[:, -self.k])
        row, col = np.nonzero((score >= least[:, None]) & np.isfinite(score))  # ties with the kth stay
        if not len(row):
            return
        some = np.unique(row)
        old, rank = np.nonzero(np.isfinite(self.best[qs[some]]))
        query = np.concatenate((row, some[old]))
        value = np.concatenate((score[row, col], self.best[qs[some]][old, rank]))
        who = np.concatenate((self.ids[xs[col]], self.who[qs[some]][old, rank]))
        order = np.lexsort((who, -value, query))
        query, value, who = query[order], value[order], who[order]
        heads = np.flatnonzero(np.diff(query, prepend=-1))
        rank = np.arange(len(query)) - np.repeat(heads, np.diff(np.append(heads, len(query))))
        top = rank < self.k
        at = qs[query[top]]
        self.best[at, rank[top]], self.who[at, rank[top]] = value[top], who[top]
        self.floor[qs[some]] = np.maximum(self.floor[qs[some]], self.best[qs[some], -1])


class Shells:
    """Blocks of data as shells around pivots: which of them can hold what a query still lacks."""

    def __init__(self, pivots: np.ndarray, cell: np.ndarray, low: np.ndarray, high: np.ndarray, longest: float) -> None:
        self.pivots, self.cell, self.low, self.high, self.longest = pivots, cell, low - SLACK, high + SLACK, longest

    def nearest(self, to_pivots: np.ndarray, radius: float = 0.0) -> np.ndarray:
        """The smallest angle from each query (its angles to all pivots given) to each block; for groups of queries, from any within radius."""
        a = to_pivots[:, self.cell]
        return np.maximum(np.maximum(a - self.high, self.low - a) - radius, 0.0)

    def best(self, q: np.ndarray) -> np.ndarray:
        """For each query, a block that could hold the nearest row; of several, one whose pivot is nearest."""
        to = angles(directed(q)[0], self.pivots)
        return (self.nearest(to) + 1e-3 * to[:, self.cell]).argmin(axis=1)

    def useful(self, q: np.ndarray, least: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pairs (query, block) where the block may hold a score of at least the query's."""
        u, norm = directed(q)
        to = angles(u, self.pivots)
        want, own = least / (norm * self.longest) - SLACK, to.argmin(axis=1)
        pairs = []
        for c in np.unique(own):
            rows = np.flatnonzero(own == c)
            group = self.nearest(angles(self.pivots[[c]], self.pivots), float(to[rows, c].max()) + SLACK)[0]
            blocks = np.flatnonzero(np.cos(group) >= want[rows].min())
            a = to[rows][:, self.cell[blocks]]
            near = np.maximum(np.maximum(a - self.high[blocks], self.low[blocks] - a), 0.0)
            row, block = np.nonzero(np.cos(near) >= want[rows][:, None])
            pairs.append((rows[row], blocks[block]))
        return tuple(np.concatenate([p[j] for p in pairs] or [np.empty(0, np.int64)]) for j in (0, 1))


def _matrix(col: pa.ChunkedArray, dims: int) -> np.ndarray:
    """Rows of whole numbers as exact doubles, padded by zeros."""
    col = col.combine_chunks()
    lengths, flat = np.diff(col.offsets.to_numpy()), col.flatten().to_numpy(zero_copy_only=False).astype(float)
    out = np.zeros((len(col), dims))
    row = np.repeat(np.arange(len(col)), lengths)
    out[row, np.arange(len(flat)) - np.repeat(np.cumsum(lengths) - lengths, lengths)] = flat
    return out


def _useful_rows(data: DataFrame, k: int) -> DataFrame:
    """Rows of data (id, vec) without those that others with the very same vector and smaller ids always leave out."""
    if not data.groupBy("id").count().where("count > 1").isEmpty():
        data = data.withColumn("r", F.row_number().over(Window.partitionBy("vec", "id").orderBy("id"))).where(F.col("r") <= k).drop("r")
    return data.withColumn("r", F.row_number().over(Window.partitionBy("vec").orderBy("id"))).where(F.col("r") <= 2 * k).drop("r")


def top_k(data: DataFrame, queries: DataFrame, k: int, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """For queries against data, both (id long, vec array<long>): query_id, rank, id, score."""
    spark = data.sparkSession
    norm = "sqrt(aggregate(vec, 0D, (a, v) -> a + CAST(v AS DOUBLE) * v)) AS norm"
    data, queries = (d.where("id IS NOT NULL AND vec IS NOT NULL AND NOT exists(vec, v -> v IS NULL)").select("id", "vec") for d in (data, queries))
    n, width, longest = data.selectExpr("size(vec) AS n", norm).agg(F.count("n"), F.max("n"), F.max("norm")).first()
    dims = max(1, width or 1, queries.agg(F.max(F.size("vec"))).first()[0] or 1)
    asked = durable(queries.dropDuplicates(["id", "vec"]).selectExpr("id", "vec", "xxhash64(id, vec) AS key", norm))
    none = spark.createDataFrame([], "query_id long, key long, id long, score long")
    if not n:
        return none.selectExpr("query_id", "CAST(key AS INT) AS rank", "id", "score")
    zero = asked.where("norm = 0" if longest else "TRUE")
    everything = _smallest_ids(data, zero, k)
    if longest:
        everything = everything.unionByName(_searched(data, asked.where("norm > 0").drop("norm"), k, max(block_rows, -(-n // MAX_BLOCKS)), n, dims, longest))
    rank = Window.partitionBy("query_id", "key").orderBy(F.col("score").desc(), "id")
    return everything.withColumn("rank", F.row_number().over(rank)).where(F.col("rank") <= k).select("query_id", "rank", "id", "score")


def _smallest_ids(data: DataFrame, zero: DataFrame, k: int) -> DataFrame:
    """Queries that score 0 with every row, with the first few rows by id; a list of at most k * (k + 1) ids travels with the plan."""
    if zero.isEmpty():
        return zero.selectExpr("id AS query_id", "key", "id", "0L AS score")
    first = data.groupBy("id").count().orderBy("id").limit(k + 1).collect()
    ids = F.array(*[F.lit(r["id"]).cast("long") for r in first for _ in range(min(k, r["count"]))])
    return zero.select(F.col("id").alias("query_id"), "key", F.explode(ids).alias("id"), F.lit(0).cast("long").alias("score")).where("id != query_id")


def _searched(data: DataFrame, asked: DataFrame, k: int, block_rows: int, n: int, dims: int, longest: float) -> DataFrame:
    spark = data.sparkSession
    cells = min(MAX_CELLS, -(-n // block_rows))
    # a bounded sample; it shapes the load, not the result
    drawn = data.withColumn("h", F.xxhash64("vec")).orderBy("h", "id").limit(DRAWN * cells).select("vec").collect()
    sample = np.zeros((len(drawn), dims))
    for row, d in zip(sample, drawn, strict=True):
        row[: len(d.vec)] = d.vec
    u = lifted(sample, longest)
    pivots = u[scattered(u, cells)[0]]

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            to = angles(lifted(_matrix(pa.chunked_array([b.column(1)]), dims), longest), pivots)
            cell = to.argmin(axis=1)
            angle = to[np.arange(len(cell)), cell]
            shell = np.minimum(angle / np.pi * SHELLS, SHELLS - 1).astype(np.int32)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(cell.astype(np.int32)), pa.array(angle), pa.array(shell)], ["id", "vec", "cell", "angle", "shell"])

    placed = durable(_useful_rows(data, k).mapInArrow(place, "id long, vec array<long>, cell int, angle double, shell int"))
    # Shells that follow each other make a block; one of too many rows is dealt over several. MAX_CELLS * SHELLS rows at most.
    table, block, held, last = [], 0, 0, None
    for r in sorted(placed.groupBy("cell", "shell").count().collect()):
        if last is not None and (r["cell"] != last or held + r["count"] > block_rows):
            block, held = block + 1, 0
        several = -(-r["count"] // block_rows)
        table.append((r["cell"], r["shell"], block, several))
        block, held, last = block + several - 1, held + r["count"], r["cell"]
    if not table:
        return spark.createDataFrame([], "query_id long, key long, id long, score long")
    of = F.broadcast(spark.createDataFrame(table, "cell int, shell int, first int, several int"))
    blocks = placed.join(of, ["cell", "shell"]).selectExpr("id", "vec", "cell", "angle", "first + CAST(pmod(xxhash64(id), several) AS INT) AS block")
    known = sorted(blocks.groupBy("block").agg(F.first("cell").alias("cell"), F.min("angle").alias("low"), F.max("angle").alias("high")).collect())  # MAX_BLOCKS + MAX_CELLS rows or so
    name = np.array([r.block for r in known], np.int32)
    shells = Shells(pivots, np.array([r.cell for r in known]), np.array([r.low for r in known]), np.array([r.high for r in known]), longest)
    sent = "id long, vec array<long>, key long, block int, least double"

    def to_first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                best = shells.best(_matrix(pa.chunked_array([b.column(1)]), dims))
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(name[best]), pa.array(np.full(b.num_rows, -np.inf))], ["id", "vec", "key", "block", "least"])

    def to_others(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                b = whole.slice(at, 1024)
                least = b.column(4).to_numpy(zero_copy_only=False)
                row, block = shells.useful(_matrix(pa.chunked_array([b.column(1)]), dims), least)
                other = name[block] != b.column(3).to_numpy(zero_copy_only=False)[row]
                row, block = row[other], block[other]
                for lo in range(0, len(row), 10_000):  # bounded batches
                    s = pa.array(row[lo : lo + 10_000])
                    yield pa.RecordBatch.from_arrays([b.column(0).take(s), b.column(1).take(s), b.column(2).take(s), pa.array(name[block[lo : lo + 10_000]]), b.column(4).take(s)], ["id", "vec", "key", "block", "least"])

    def search(left: pa.Table, right: pa.Table) -> pa.Table:
        x, q = _matrix(left.column("vec"), dims), _matrix(right.column("vec"), dims)
        s = Search(x, left.column("id").to_numpy(), q, right.column("id").to_numpy(), right.column("least").to_numpy(), k, longest)
        row, rank = np.nonzero(np.isfinite(s.best))
        return pa.table([right.column("id").combine_chunks().take(pa.array(row)), right.column("key").combine_chunks().take(pa.array(row)), pa.array(s.who[row, rank]), pa.array(s.best[row, rank].astype(np.int64))], names=["query_id", "key", "id", "score"])

    def met(wanted: DataFrame) -> DataFrame:
        """Each block that is wanted, once for every SLICE_QUERIES queries, with these."""
        slices = wanted.groupBy("block").agg(F.ceil(F.count("*") / SLICE_QUERIES).cast("int").alias("slices")).withColumnRenamed("block", "b")
        slices = F.broadcast(durable(slices))  # a row for each block at most
        at = F.col("block") == F.col("b")
        left = blocks.join(slices, at).selectExpr("id", "vec", "block", "explode(sequence(0, slices - 1)) AS slice")
        right = wanted.join(slices, at).selectExpr("id", "vec", "key", "block", "least", "CAST(pmod(key, slices) AS INT) AS slice")
        return left.groupBy("block", "slice").cogroup(right.groupBy("block", "slice")).applyInArrow(search, "query_id long, key long, id long, score long")

    start = durable(asked.mapInArrow(to_first, sent))
    first = durable(met(start))
    kth = first.groupBy("query_id", "key").agg(F.count("*").alias("n"), F.min("score").alias("low")).where(f"n >= {k}").selectExpr("query_id AS i", "key AS h", "CAST(low AS DOUBLE) AS low")
    judged = start.join(kth, (F.col("id") == F.col("i")) & (F.col("key") == F.col("h")), "left").selectExpr("id", "vec", "key", "block", "coalesce(low, CAST('-Infinity' AS DOUBLE)) AS least")
    others = durable(judged.mapInArrow(to_others, sent))
    return first if others.isEmpty() else first.unionByName(met(others))

"""Exact top-k by inner product: M-trees searched best first.

Vectors get one more coordinate, the root of M^2 - |x|^2 with M the largest norm of the tree, and
queries get 0 there; the nearest vectors by distance are then those of the largest inner product. A
tree has pages of routing vectors with covering radii and distances to their parents. The search takes
pages by least possible distance and stops where that is beyond the k-th best; |d(q, parent) - d(x, parent)|,
both known, spares distances to routing vectors and to rows whose bound is already too large. Bounds have a
margin for rounding; scores are exact integers.

The tree lies over the whole table. Its root page is a bounded number of pivots, far apart in a sample; every
row goes to the cell of its nearest pivot, and a cell to blocks of about ``BLOCK`` rows, each the page tree of
one task, so a cell of equal vectors is split. The driver holds of each cell the pivot and the nearest and the furthest
row only. A query first searches its home cell; its k-th best score there goes along to the other cells, and
those that the triangle inequality rules out are not visited. Queries are shipped to trees in chunks; a tree is
shipped once for each chunk.

Vectors that are null, or hold null or non-finite components, take no part; shorter vectors count as padded
with zeros. Rows with a query's id are not its candidates; of repeated rows every one is a candidate, and a
repeated query asks once. Ties go to the smaller id. A null id can't be ranked and takes no part.
"""

from __future__ import annotations

import heapq
import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

#: Rows of a tree, of a page, children of a page, queries in a chunk.
BLOCK, PAGE, FANOUT, CHUNK = 16_384, 64, 16, 16_384
#: Most cells of the root page, and sampled rows for each pivot.
CELLS, SAMPLED = 256, 16
#: Quantisation: a component x becomes floor(STEPS * x).
STEPS = 1024


class MTree:
    """Pages as flat arrays; rows lie in the order of the leaves."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray, page: int = PAGE, fanout: int = FANOUT, top: float | None = None) -> None:
        self.page, self.fanout, self.distances = page, fanout, 0
        norms = np.einsum("ij,ij->i", rows.astype(np.float64), rows.astype(np.float64))
        self.top = max(float(norms.max()) if len(rows) else 0.0, top or 0.0)
        points = np.column_stack([rows.astype(np.float64), np.sqrt(np.maximum(self.top - norms, 0.0))])
        self.order: list[int] = []
        self.nodes: list[tuple] = []  # routing row, radius, distance to parent, first, last, leaf
        if len(rows):
            self._build(points)
        order = np.array(self.order, np.int64)
        self.ids, self.rows, self.points = ids[order], rows[order], points[order]
        self.center = np.array([points[n[0]] for n in self.nodes]).reshape(len(self.nodes), points.shape[1])
        self.radius = np.array([n[1] for n in self.nodes])
        self.first = np.array([n[3] for n in self.nodes], np.int64)
        self.last = np.array([n[4] for n in self.nodes], np.int64)
        self.leaf = np.array([n[5] for n in self.nodes], bool)
        self.parent = np.array([n[2] for n in self.nodes])
        self.spread = np.zeros(len(rows))  # distance of each row to its leaf's routing vector
        for k in np.flatnonzero(self.leaf):
            a, b = self.first[k], self.last[k]
            self.spread[a:b] = np.linalg.norm(self.points[a:b] - self.center[k], axis=1)
        del self.nodes, self.order, self.points

    @staticmethod
    def _routing(points: np.ndarray, members: np.ndarray) -> tuple[int, float]:
        """The member nearest to the mean, and the radius that covers all members."""
        own = points[members]
        at = members[np.argmin(((own - own.mean(0)) ** 2).sum(1))]
        return int(at), float(np.sqrt(((own - points[at]) ** 2).sum(1).max()))

    def _split(self, points: np.ndarray, members: np.ndarray) -> list[np.ndarray]:
        """Members by the nearest of some far-apart members; evenly where these don't part them."""
        own = points[members]
        far = [int(np.argmax(((own - own.mean(0)) ** 2).sum(1)))]
        least = ((own - own[far[0]]) ** 2).sum(1)
        near = np.zeros(len(members), np.int64)
        for k in range(1, min(self.fanout, -(-len(members) // self.page))):
            at = int(np.argmax(least))
            if least[at] <= 0:
                break
            far.append(at)
            d = ((own - own[at]) ** 2).sum(1)
            near[d < least] = k
            least = np.minimum(least, d)
        parts = [members[near == k] for k in range(len(far))]
        parts = [p for p in parts if len(p)]
        if len(parts) < 2 or max(map(len, parts)) > 0.9 * len(members):
            parts = np.array_split(members, min(self.fanout, -(-len(members) // self.page)))
        return parts

    def _build(self, points: np.ndarray) -> None:
        """Level by level, so that the children of a page lie side by side."""
        everything = np.arange(len(points))
        self.nodes.append((*self._routing(points, everything), 0.0, 0, 0, False))
        level = [(0, everything)]
        while level:
            below = []
            for k, members in level:
                routing, radius, up = self.nodes[k][:3]
                if len(members) <= self.page:
                    self.nodes[k] = (routing, radius, up, len(self.order), len(self.order) + len(members), True)
                    self.order.extend(members.tolist())
                    continue
                first = len(self.nodes)
                for part in self._split(points, members):
                    at, r = self._routing(points, part)
                    below.append((len(self.nodes), part))
                    self.nodes.append((at, r, float(np.linalg.norm(points[at] - points[routing])), 0, 0, False))
                self.nodes[k] = (routing, radius, up, first, len(self.nodes), False)
            level = below

    def search(self, query_id: int, query: np.ndarray, k: int, least: int | None = None) -> list[tuple[int, int]]:
        """The k best (score, id), best first; with ``least``, of those that score so much or more.

        ``distances`` counts what is worked out: to routing vectors and to rows."""
        if not len(self.ids):
            return []
        q = np.append(query.astype(np.float64), 0.0)
        size = float(q @ q) + self.top
        margin = 1e-9 * max(1.0, size)
        best: list[tuple[int, int]] = []  # heap of (score, -id): the worst on top
        limit = np.inf if least is None else size - 2.0 * float(least)  # squared distance of the k-th best
        self.distances += 1
        d0 = float(np.linalg.norm(q - self.center[0]))
        heap = [(max(0.0, d0 - self.radius[0]), 0, d0)]
        while heap:
            low, node, d = heapq.heappop(heap)
            if low * low > limit + margin:
                break
            a, b = self.first[node], self.last[node]
            if self.leaf[node]:
                at = np.arange(a, b)
                if limit < np.inf:
                    at = at[(d - self.spread[a:b]) ** 2 <= limit + margin]
                    if not len(at):
                        continue
                self.distances += len(at)
                scores = self.rows[at] @ query
                if len(best) == k:  # equal scores stay, for the smaller id
                    good = scores >= best[0][0]
                    at, scores = at[good], scores[good]
                for s, i in zip(scores.tolist(), self.ids[at].tolist(), strict=True):
                    if i != query_id:
                        if len(best) < k:
                            heapq.heappush(best, (s, -i))
                        elif (s, -i) > best[0]:
                            heapq.heapreplace(best, (s, -i))
                if len(best) == k:
                    limit = min(limit, size - 2.0 * float(best[0][0]))
                continue
            at = np.arange(a, b)
            if limit < np.inf:
                bound = np.maximum(0.0, np.abs(d - self.parent[a:b]) - self.radius[a:b])
                at = at[bound * bound <= limit + margin]
            if len(at):
                self.distances += len(at)
                to = np.sqrt(((self.center[at] - q) ** 2).sum(1))
                for n, x, r in zip(at.tolist(), to.tolist(), self.radius[at].tolist(), strict=True):
                    low = max(0.0, x - r)
                    if low * low <= limit + margin:
                        heapq.heappush(heap, (low, n, x))
        return [(s, -i) for s, i in sorted(best, reverse=True)]


def matrix(vectors: list[list[int]]) -> np.ndarray:
    """Rows of equal length, padded with zeros; Python integers where 64 bits might not hold a product."""
    width = max(map(len, vectors), default=0)
    largest = max((max(map(abs, v)) for v in vectors if v), default=0)
    out = np.zeros((len(vectors), max(1, width)), np.int64 if largest * largest * max(1, width) < 2**62 else object)
    for row, v in zip(out, vectors, strict=True):
        row[: len(v)] = v
    return out


def fitted(a: np.ndarray, width: int) -> np.ndarray:
    return a[..., :width] if a.shape[-1] >= width else np.concatenate([a, np.zeros((*a.shape[:-1], width - a.shape[-1]), a.dtype)], axis=-1)


def quantised(vectors: DataFrame, steps: int = STEPS) -> DataFrame:
    """id and v (array of long) of the rows that take part."""
    x = F.col("embedding").cast("array<double>")
    bad = F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    return vectors.select(F.col("vec_id").cast("long").alias("id"), F.when(~bad, F.transform(x, lambda c: F.floor(c * steps))).alias("v")).where("id is not null and v is not null")


def lifted(rows: np.ndarray, top: float) -> np.ndarray:
    """Rows in the space where the largest inner product is the least distance."""
    x = rows.astype(np.float64)
    return np.column_stack([x, np.sqrt(np.maximum(top - np.einsum("ij,ij->i", x, x), 0.0))])


def far_apart(points: np.ndarray, k: int) -> np.ndarray:
    """Numbers of at most k points, each the furthest from those before."""
    chosen, least = [0], ((points - points[0]) ** 2).sum(1)
    while len(chosen) < k and least.max() > 0:
        chosen.append(int(np.argmax(least)))
        least = np.minimum(least, ((points - points[chosen[-1]]) ** 2).sum(1))
    return np.array(chosen)


def to_pivots(points: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    """Distances of points to pivots."""
    squares = (points**2).sum(1)[:, None] + (pivots**2).sum(1)[None, :] - 2.0 * points @ pivots.T
    return np.sqrt(np.maximum(squares, 0.0))


def _trees(placed: DataFrame, width: int, top: float) -> DataFrame:
    """cell, part, tree: one pickled tree for each block of rows."""

    def run(group: pa.Table) -> pa.Table:
        m = fitted(matrix(group.column("v").to_pylist()), width)
        blob = pickle.dumps(MTree(group.column("id").to_numpy(), m, top=top))
        return pa.table({c: group.column(c).slice(0, 1) for c in ("cell", "part")} | {"tree": pa.array([blob], pa.binary())})

    return placed.groupBy("cell", "part").applyInArrow(run, "cell int, part int, tree binary")


def _searched(visits: DataFrame, trees: DataFrame, width: int, k: int) -> DataFrame:
    """query_id, vec_id, score, distances: what each tree finds for the queries (id, v, least, cell, part, chunk) that visit it.

    distances stands on one row of a tree's queries together; vec_id is null where there is no other."""

    def pack(group: pa.Table) -> pa.Table:
        value = group.column("id").to_numpy(), fitted(matrix(group.column("v").to_pylist()), width), group.column("least").to_pylist()
        return pa.table({c: group.column(c).slice(0, 1) for c in ("cell", "part")} | {"queries": pa.array([pickle.dumps(value)], pa.binary())})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for blob, part in zip(b.column("tree"), b.column("queries"), strict=True):
                tree, (ids, m, least) = pickle.loads(blob.as_buffer()), pickle.loads(part.as_buffer())
                found = [(i, *x, 0) for i, q, at_least in zip(ids.tolist(), m, least, strict=True) for x in tree.search(i, q, k, at_least)]
                found.append((int(ids[0]), None, None, tree.distances))
                columns = list(zip(*found, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(columns[i], pa.int64()) for i in (0, 2, 1, 3)], ["query_id", "vec_id", "score", "distances"])

    chunks = visits.groupBy("cell", "part", "chunk").applyInArrow(pack, "cell int, part int, queries binary")
    return trees.join(chunks, ["cell", "part"]).select("tree", "queries").mapInArrow(run, "query_id long, vec_id long, score long, distances long")


def found(vectors: DataFrame, queries: DataFrame, k: int = 10, block: int = BLOCK, chunk: int = CHUNK, cells: int = CELLS) -> DataFrame:
    """query_id, vec_id, score, distances: candidates with the k best of every query, as ``_searched`` gives them."""
    squares = F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    n, top, width = vectors.agg(F.count(F.lit(1)), F.coalesce(F.max(squares), F.lit(0.0)), F.coalesce(F.max(F.size("v")), F.lit(1))).first()
    top, width, n_cells = float(top), max(1, int(width)), min(cells, max(1, -(-n // block)))
    first = common.lowest(vectors.select("id", "v"), "id", SAMPLED * n_cells).collect()
    sample = lifted(fitted(matrix([r["v"] for r in first]), width), top) if first else np.zeros((1, width + 1))
    pivots = sample[far_apart(sample, n_cells)]

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (whole.slice(i, 4096) for whole in batches for i in range(0, whole.num_rows, 4096)):
            d = to_pivots(lifted(fitted(matrix(b.column("v").to_pylist()), width), top), pivots)
            near = d.argmin(1)
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("v"), pa.array(near, pa.int32()), pa.array(d[np.arange(len(d)), near])], ["id", "v", "cell", "d"])

    placed = vectors.select("id", "v").mapInArrow(place, "id long, v array<long>, cell int, d double").withColumn("n", F.monotonically_increasing_id())
    placed = common.written(placed, "placed")
    per = placed.groupBy("cell").agg(F.count(F.lit(1)).alias("rows"), F.min("d").alias("least"), F.max("d").alias("most")).collect()  # one row a cell
    parts = {r["cell"]: -(-r["rows"] // block) for r in per}
    near, far = np.full(len(pivots), np.inf), np.full(len(pivots), -np.inf)
    for r in per:
        near[r["cell"]], far[r["cell"]] = r["least"], r["most"]
    many = F.create_map(*[F.lit(x) for c, m in (parts or {0: 1}).items() for x in (c, m)])
    trees = common.written(_trees(placed.withColumn("part", F.pmod(F.xxhash64("n"), F.element_at(many, F.col("cell"))).cast("int")).drop("n", "d"), width, top), "trees")
    asked = common.materialise(queries.groupBy("id").agg(F.min("v").alias("v")))
    n_chunks = max(1, -(-asked.count() // chunk))

    def visits(home: bool):  # noqa: ANN202
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in (whole.slice(i, 1024) for whole in batches for i in range(0, whole.num_rows, 1024)):
                m = fitted(matrix(b.column("v").to_pylist()), width).astype(np.float64)
                d = to_pivots(np.column_stack([m, np.zeros(len(m))]), pivots)
                size = (m**2).sum(1) + top
                low = np.where(near[None, :] <= far[None, :], np.maximum(0.0, np.maximum(d - far[None, :], near[None, :] - d)), np.inf)
                first = np.argmin(low + d * 1e-9, axis=1)
                out = []
                for i, least in enumerate(b.column("least").to_pylist()):
                    if home:
                        own = [first[i]]
                    else:
                        limit = np.inf if least is None else size[i] - 2.0 * float(least) + 1e-6 * max(1.0, size[i])
                        own = [c for c in np.flatnonzero(np.isfinite(low[i]) & (low[i] ** 2 <= limit)) if c != first[i]]
                    out += [(i, int(c), p) for c in own for p in range(parts.get(int(c), 0))]
                at, cell, part = list(zip(*out, strict=True)) or [(), (), ()]
                take = b.take(pa.array(at, pa.int64()))
                yield pa.RecordBatch.from_arrays([take.column("id"), take.column("v"), take.column("least"), pa.array(cell, pa.int32()), pa.array(part, pa.int32())], ["id", "v", "least", "cell", "part"])

        return run

    def searched(ask: DataFrame, home: bool) -> DataFrame:
        to = ask.select("id", "v", "least").mapInArrow(visits(home), "id long, v array<long>, least long, cell int, part int")
        return common.written(_searched(to.withColumn("chunk", F.pmod(F.xxhash64("id"), F.lit(n_chunks))), trees, width, k), "found")

    at_home = searched(asked.withColumn("least", F.lit(None).cast("long")), True)
    kth = _best(at_home, k).groupBy("query_id").agg(F.min("score").alias("least"), F.count(F.lit(1)).alias("n")).where(F.col("n") >= k)
    beyond = searched(asked.join(kth.select(F.col("query_id").alias("id"), "least"), "id", "left"), False)
    return at_home.unionAll(beyond)


def _best(rows: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return rows.where("vec_id is not null").withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, **options) -> DataFrame:
    """query_id, rank, vec_id, score: the k best of ``vectors`` for each row of ``queries`` (both id, v)."""
    return _best(found(vectors, queries, k, **options), k)


def op4_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = quantised(common.table(spark, sf_dir, "embeddings"))
    return top_k(rows, rows.where("id % 100 = 0"))


#: DuckDB twin: every pair of a query and a row, ranked.
SQL = """
WITH q AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * CAST(x AS DOUBLE))) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT a.vec_id AS query_id, b.vec_id AS vec_id, CAST(list_dot_product(a.v, b.v) AS BIGINT) AS score
      FROM q a JOIN q b ON a.vec_id % 100 = 0 AND a.vec_id <> b.vec_id),
r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""

"""Exact top-k search by inner product with M-trees and best-first search.

Components are floored at 1/64, so scores are integers. With one more component, sqrt(M^2 - |x|^2), all candidates of a
tree have the norm M, and the squared distance to a query (with a zero there) is |q|^2 + M^2 - 2 q.x: the nearest
candidates are those with the largest inner products, which makes the search metric and the answers exact.

A tree has pages of at most `PAGE` entries. Each entry of an inner page has a routing vector, a covering radius and the
distance to the parent's routing vector; each entry of a leaf has its distance to the leaf's routing vector. The search
keeps pages in a heap by their lower bound; with the distance from the query to a page's routing vector known, the
triangle inequality bounds the distance of each of its entries from the stored parent distances, and only entries that
may still be among the k best get their distances computed. Pages or entries that tie with the kth best are visited, so
ties go to the smaller vec_id. Bounds have a slack above the rounding of floating point; scores are computed in integers.
Queries go down the tree in bundles, each with its own bounds: a page's entries are scored by one product of matrices for
those queries of the bundle that the page may still concern.

Candidates are dealt into blocks by a hash of vec_id and queries into blocks by their id; each pair of blocks is one group
(a stated query set against all rows, in blocks), builds its tree, and returns k rows a query; those meet in a ranking per
query, which keeps k while it reads. Equal vectors of a block become one entry with its k + 1 smallest ids. A tree is
built once for each block of queries, which is large, so that building is a small part of the search.

Defined cases: vectors that are null, empty or hold null or non-finite components take no part, nor do rows with a null
vec_id; vectors of different lengths are compared within their length only; the query's own vec_id is never a candidate;
repeated vec_ids are repeated candidates and, as queries, one ranking over the answers of all their rows; scores that tie go
to the smaller vec_id; very long vectors are compared whole; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sparkverdict.llm.common import ship_package

K = 20
PAGE = 128
SCALE = 64
#: Rows of a candidate block and of a query block, on average.
CANDIDATES = 32_768
QUERIES = 32_768
#: Blocks may be this small where there are tasks to spare.
LEAST_CANDIDATES = 4_096
#: Queries that descend a tree together.
TOGETHER = 256
SLACK = 1e-6


class Node:
    """A page: entries' vectors, their distances to the page's routing vector, and covering radii and children if inner."""

    __slots__ = ("at", "parent", "radius", "children", "vectors")

    def __init__(self, at: np.ndarray, parent: np.ndarray, radius: np.ndarray | None, children: list[Node] | None, vectors: np.ndarray) -> None:
        self.at, self.parent, self.radius, self.children, self.vectors = at, parent, radius, children, vectors


class MTree:
    """Bulk-loaded over distinct integer vectors `x`; ids[i] are the sorted vec_ids of vector i."""

    def __init__(self, x: np.ndarray, ids: list[np.ndarray], page: int = PAGE) -> None:
        self.x, self.ids, self.page = x, ids, page
        norms = (x * x).sum(1)
        self.top = float(norms.max()) if len(x) else 0.0
        self.full = np.concatenate([x, np.sqrt(np.maximum(self.top - norms, 0))[:, None]], axis=1)
        self.rng = np.random.default_rng(5)
        self.root, self.pivot = None, None
        if len(x):
            self.pivot = 0
            self.root = self._load(np.arange(len(x)), 0)

    def _distances(self, to: int, rows: np.ndarray) -> np.ndarray:
        gap = self.full[rows] - self.full[to]
        return np.sqrt(np.einsum("ij,ij->i", gap, gap))

    def _load(self, rows: np.ndarray, pivot: int) -> Node:
        far = self._distances(pivot, rows)
        if len(rows) <= self.page:
            return Node(rows, far, None, None, np.ascontiguousarray(self.x[rows]))
        fan = min(self.page, max(2, math.ceil(len(rows) / self.page)))
        routes = self.rng.choice(rows, fan, replace=False)
        # nearest routing vector by inner products: all full vectors have one norm
        nearest = np.concatenate([np.argmax(self.full[part] @ self.full[routes].T, axis=1) for part in np.array_split(rows, max(1, len(rows) // 8192))])
        groups = [rows[nearest == i] for i in range(fan)]
        groups = [g for g in groups if len(g)]
        if len(groups) == 1:  # nothing told them apart
            groups = np.array_split(rows, fan)
        pivots = np.asarray([g[0] if routes[i] not in g else routes[i] for i, g in enumerate(groups)]) if len(groups) == fan else np.asarray([g[0] for g in groups])
        children = [self._load(g, int(p)) for g, p in zip(groups, pivots, strict=True)]
        radius = np.asarray([self._distances(int(p), g).max() for g, p in zip(groups, pivots, strict=True)])
        return Node(pivots, self._distances(pivot, pivots), radius, children, np.ascontiguousarray(self.x[pivots]))

    def search(self, q: np.ndarray, k: int, own: int | None = None) -> list[tuple[int, int]]:
        """The k best (score, vec_id), higher scores first, then smaller ids."""
        return self.search_all(q[None, :], k, [own])[0]

    def search_all(self, q: np.ndarray, k: int, own: list[int | None]) -> list[list[tuple[int, int]]]:
        """The same for each row of q. Queries that are near the same routing vector descend together, `TOGETHER` at a time:
        a page is read once for those of them that its bound still admits."""
        if self.root is None:
            return [[] for _ in q]
        order = np.argmax(q @ self.root.vectors.T, axis=1).argsort(kind="stable") if self.root.children else np.arange(len(q))
        found: list[list[tuple[int, int]]] = [[] for _ in q]
        for low in range(0, len(q), TOGETHER):
            some = order[low : low + TOGETHER]
            for i, best in zip(some.tolist(), self._descend(q[some], k, [own[i] for i in some.tolist()]), strict=True):
                found[i] = best
        return found

    def _descend(self, q: np.ndarray, k: int, own: list[int | None]) -> list[list[tuple[int, int]]]:
        base = (q * q).sum(1) + self.top
        best: list[list[tuple[int, int]]] = [[] for _ in q]  # a heap of (score, -vec_id) per query, the worst first
        #: Score and distance of the kth best of each query so far.
        kth, limit = np.full(len(q), -np.inf), np.full(len(q), np.inf)
        to_pivot = np.sqrt(np.maximum(base - 2 * (q @ self.x[self.pivot]), 0))
        # pages by the least of the bounds of the queries that may need them
        heap: list[tuple[float, int, Node, np.ndarray, np.ndarray, np.ndarray]] = [(0.0, 0, self.root, np.arange(len(q)), np.zeros(len(q)), to_pivot)]
        n = 0
        while heap:
            least, _, node, asks, bound, d = heapq.heappop(heap)
            if least > limit.max():
                break
            on = bound <= limit[asks]
            if not on.any():
                continue
            asks, bound, d = asks[on], bound[on], d[on]
            # triangle inequality over the stored parent distances: |d - parent| - radius bounds each entry from below
            low = np.abs(d[:, None] - node.parent) - (node.radius if node.children else 0.0)
            admitted = low <= limit[asks][:, None]
            entries, rows = np.flatnonzero(admitted.any(axis=0)), admitted.any(axis=1)
            if not len(entries):
                continue
            asks, bound, low = asks[rows], bound[rows], low[np.ix_(rows, entries)]
            scores = q[asks] @ (node.vectors if len(entries) == len(node.at) else node.vectors[entries]).T  # integers in doubles, exact
            if node.children:
                dist = np.sqrt(np.maximum(base[asks][:, None] - 2 * scores, 0))
                bounds = np.maximum(np.maximum(dist - node.radius[entries], low), bound[:, None])
                within = bounds <= limit[asks][:, None]
                for j, i in enumerate(entries.tolist()):
                    into = np.flatnonzero(within[:, j])
                    if len(into):
                        n += 1
                        heapq.heappush(heap, (float(bounds[into, j].min()), n, node.children[i], asks[into], bounds[into, j], dist[into, j]))
                continue
            at = node.at[entries]
            some, those = np.nonzero(scores >= kth[asks][:, None])
            for r, part in zip(*_runs(some, those), strict=True):
                one, mine = int(asks[r]), scores[r, part]
                self._take(best[one], mine, at[part], k, own[one])
                if len(best[one]) == k:
                    kth[one] = best[one][0][0]
                    limit[one] = math.sqrt(max(0.0, base[one] - 2 * kth[one])) + SLACK
        return [[(s, -i) for s, i in sorted(b, reverse=True)] for b in best]

    def _take(self, best: list[tuple[int, int]], scores: np.ndarray, at: np.ndarray, k: int, own: int | None) -> None:
        """Entries of a page into the heap of a query."""
        for i in np.argsort(-scores, kind="stable").tolist() if len(scores) > 1 else (0,):
            s = int(scores[i])
            if len(best) == k and s < best[0][0]:
                break
            for vec_id in self.ids[at[i]].tolist():
                if vec_id == own:
                    continue
                item = (s, -vec_id)
                if len(best) < k:
                    heapq.heappush(best, item)
                elif item > best[0]:
                    heapq.heapreplace(best, item)
                else:
                    break


def _runs(keys: np.ndarray, values: np.ndarray) -> tuple[list[int], list[np.ndarray]]:
    """Sorted keys, each once, with its values."""
    cuts = np.flatnonzero(np.diff(keys)) + 1
    return (keys[np.concatenate([[0], cuts])].tolist(), np.split(values, cuts)) if len(keys) else ([], [])


def build(ids: np.ndarray, x: np.ndarray, k: int, page: int = PAGE) -> MTree:
    """One entry per distinct vector, with its k + 1 smallest ids (one of them may be the query itself)."""
    order = np.argsort(ids, kind="stable")
    ids, x = ids[order], x[order]
    distinct, first, inverse = np.unique(x, axis=0, return_index=True, return_inverse=True) if len(x) else (x, np.zeros(0, int), np.zeros(0, int))
    by = np.argsort(inverse.ravel(), kind="stable")
    cuts = np.flatnonzero(np.diff(inverse.ravel()[by])) + 1
    return MTree(distinct, [ids[g][: k + 1] for g in np.split(by, cuts)] if len(x) else [], page)


def _search_blocks(k: int):
    def run(key: tuple, frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from sparkverdict.llm.m_tree import build

        rows = pd.concat(list(frames))
        asked = rows["is_query"].to_numpy()
        if not asked.any() or asked.all():
            return
        stack = lambda part: np.stack(part["v"].to_list()).astype("f8")
        candidates, queries = rows[~asked], rows[asked]
        tree = build(candidates["vec_id"].to_numpy(), stack(candidates), k)
        ids = queries["vec_id"].tolist()
        found = [(i, vec_id, s) for i, best in zip(ids, tree.search_all(stack(queries), k, ids), strict=True) for s, vec_id in best]
        yield pd.DataFrame(found, columns=["query_id", "vec_id", "score"])

    return run


def usable(vectors: DataFrame, vector: str = "embedding") -> DataFrame:
    """vec_id, dim and v, the floored components, of the rows that take part."""
    x = F.col(vector)
    finite = F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf")))
    rows = vectors.filter(F.col("vec_id").isNotNull() & x.isNotNull() & (F.size(x) > 0) & F.coalesce(finite, F.lit(False)))
    return rows.select(F.col("vec_id").cast("long").alias("vec_id"), F.size(x).alias("dim"), F.transform(x, lambda c: F.floor(c.cast("double") * SCALE).cast("double")).alias("v"))


def top_k(vectors: DataFrame, vector: str = "embedding", k: int = K, every: int = 20) -> DataFrame:
    """query_id, rank, vec_id, score for the rows whose vec_id is divisible by `every`."""
    spark = vectors.sparkSession
    ship_package(spark)
    rows = usable(vectors, vector)
    n = rows.count()
    c_blocks = max(1, -(-n // CANDIDATES), min(spark.sparkContext.defaultParallelism, n // LEAST_CANDIDATES))
    q_blocks = max(1, -(-n // every // QUERIES))
    place = lambda name, blocks: F.pmod(F.xxhash64("vec_id", F.lit(name)), F.lit(blocks)).cast("int")
    candidates = rows.withColumn("cb", place("candidate", c_blocks)).withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(q_blocks - 1)))).withColumn("is_query", F.lit(False))
    queries = rows.filter(F.col("vec_id") % every == 0).withColumn("qb", place("query", q_blocks)).withColumn("cb", F.explode(F.sequence(F.lit(0), F.lit(c_blocks - 1)))).withColumn("is_query", F.lit(True))
    both = candidates.unionByName(queries.select(candidates.columns))
    found = both.groupBy("dim", "cb", "qb").applyInPandas(_search_blocks(k), "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")

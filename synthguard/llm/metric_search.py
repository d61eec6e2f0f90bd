"""Exact top-k search by inner product in M-trees whose top level spans the corpus.

The top level has routing objects, vectors of a bounded sample. Every vector belongs to the cell of its nearest one; a cell keeps its covering
radius and its longest vector. Cells are cut into pages, and each page is an M-tree of its own: leaves of nearby vectors, above them nodes
with a routing centre, a covering radius and the distance to the parent's centre.

A query first goes to the cells with the highest bounds that together hold more than k vectors; its kth score there is the least that counts. Of
the other cells it then visits those whose bound reaches that score. Both bounds hold by the triangle inequality: a vector x of the ball of radius r
around c has <q,x> <= <q,c> + |q| r, and as it lies |q - c| - r from q or further, 2 <q,x> <= |q|^2 + |x|^2 - (|q - c| - r)^2.
In a page the search descends best first; the stored parent distance d bounds <q,c> by <q,parent> + |q| d before <q,c> is computed, so
that whole subtrees go without a look at their centres. A page streams its queries past one tree.

Scores are exact integers; bounds are floating point and widened by a relative slack, so a bound never cuts a true answer. The sample only
shapes the cells; every vector is in one, and vectors without clusters cost visits of most cells.

Defined cases: vectors that are null, or hold null or non-finite components, take no part; shorter vectors count as filled
up with zeros; equal scores go to the smaller id, copies of one vector included; a null id takes no part; other columns are not read;
an id that comes more than once is a candidate each time, and asks once.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from synthguard.llm.common import parts, staged, table

LEAF, FANOUT, SLACK = 64, 16, 1e-9
#: Numbers that the routing objects may hold together, which bounds what tasks are sent (32 MB).
ROUTING = 1 << 22
NO_SCORE = -(1 << 63)
_OUT = "query_id long, vec_id long, score long"
_DEALT = "id long, v array<long>, cell int, turn long, away double, norm double"


class MTree:
    """Nodes in arrays: centre, radius, distance to the parent's centre, children (or rows, for leaves)."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, leaf: int = LEAF, fanout: int = FANOUT):
        self.ids, self.vectors = ids, vectors
        self.real = vectors.astype(np.float64)
        self.centre, self.radius, self.to_parent, self.children, self.rows = [], [], [], [], []
        self.products = 0
        if len(ids):
            self.root = self._build(np.arange(len(ids)), leaf, fanout)
            self.centre, self.radius, self.to_parent = np.array(self.centre), np.array(self.radius), np.array(self.to_parent)

    def _build(self, rows: np.ndarray, leaf: int, fanout: int) -> int:
        x = self.real[rows]
        centre = x[np.argmin(((x - x.mean(0)) ** 2).sum(1))]  # a routing object, as an M-tree has
        away = np.sqrt(((x - centre) ** 2).sum(1))
        me = len(self.radius)
        self.centre.append(centre)
        self.radius.append(float(away.max()))
        self.to_parent.append(0.0)
        self.children.append(())
        self.rows.append(None)
        if len(rows) <= leaf or away.max() == 0:
            self.rows[me] = rows
            return me
        # pivots by farthest-first traversal, each row to its nearest pivot
        pivots, nearest = [int(np.argmax(away))], None
        d = np.sqrt(((x - x[pivots[0]]) ** 2).sum(1))
        nearest = np.zeros(len(rows), np.int64)
        while len(pivots) < fanout and d.max() > 0:
            pivots.append(int(np.argmax(d)))
            other = np.sqrt(((x - x[pivots[-1]]) ** 2).sum(1))
            nearest[other < d] = len(pivots) - 1
            d = np.minimum(d, other)
        kids = []
        for k in range(len(pivots)):
            own = rows[nearest == k]
            if len(own):
                kid = self._build(own, leaf, fanout)
                self.to_parent[kid] = float(np.sqrt(((self.centre[kid] - centre) ** 2).sum()))
                kids.append(kid)
        self.children[me] = np.array(kids)
        return me

    def search(self, q: np.ndarray, k: int, but: int, least: int = NO_SCORE) -> list[tuple[int, int]]:
        """(score, id) of the best k that score least or more, best first, without the id but."""
        if not len(self.ids):
            return []
        real, length = q.astype(np.float64), float(np.sqrt((q.astype(np.float64) ** 2).sum()))
        slack = lambda x: x + SLACK * (abs(x) + 1)
        top = float(real @ self.centre[self.root])
        queue, best = [(-slack(top + length * self.radius[self.root]), self.root, top)], []  # best: heap of (score, -id), worst first
        while queue:
            bound, node, at = heapq.heappop(queue)
            if -bound < least:
                break
            rows = self.rows[node]
            if rows is not None:
                scores = self.vectors[rows] @ q
                self.products += len(rows)
                m = scores >= least
                for s, i in zip(scores[m].tolist(), self.ids[rows[m]].tolist(), strict=True):
                    if i != but:
                        if len(best) < k:
                            heapq.heappush(best, (s, -i))
                        elif (s, -i) > best[0]:
                            heapq.heapreplace(best, (s, -i))
                if len(best) == k:
                    least = max(least, best[0][0])
                continue
            kids = self.children[node]
            cheap = at + length * (self.to_parent[kids] + self.radius[kids])  # the stored distances alone
            kids = kids[cheap + SLACK * (np.abs(cheap) + 1) >= least]
            if len(kids):
                dots = self.centre[kids] @ real
                self.products += len(kids)
                for kid, dot in zip(kids.tolist(), dots.tolist(), strict=True):
                    b = slack(dot + length * self.radius[kid])
                    if b >= least:
                        heapq.heappush(queue, (-b, kid, dot))
        return [(s, -i) for s, i in sorted(best, reverse=True)]


def whole_numbers(vectors: DataFrame, id_col: str, vector_col: str, scale: int) -> DataFrame:
    """id, v: floor(scale * x) of each component; rows without an id or with a missing or non-finite component are left out."""
    x = F.col(vector_col)
    finite = F.forall(x, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e.cast("double")) < float("inf")))
    return vectors.where(F.col(id_col).isNotNull() & x.isNotNull() & finite).select(
        F.col(id_col).cast("long").alias("id"), F.transform(x, lambda e: F.floor(e.cast("double") * scale).cast("long")).alias("v")
    )


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    """The lists of a column as rows, filled up with zeros."""
    sizes = pc.list_value_length(column).to_numpy(zero_copy_only=False)
    out = np.zeros((len(column), width), np.int64)
    out[np.arange(width) < sizes[:, None]] = column.flatten().to_numpy(zero_copy_only=False)
    return out


def _dealt(routing, width: int):
    """Each vector with its cell, its distance from the cell's routing object, and its length; turns deal a cell's vectors to its pages."""

    def run(batches):
        centres = routing.value
        half, turn = (centres**2).sum(1) / 2, TaskContext.get().partitionId()
        for b in batches:
            x = _matrix(b.column(1), width).astype(np.float64)
            cell = np.argmin(half - x @ centres.T, 1)
            away, norm = np.sqrt(((x - centres[cell]) ** 2).sum(1)), np.sqrt((x**2).sum(1))
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(cell.astype(np.int32)), pa.array(np.arange(len(x)) + turn), pa.array(away), pa.array(norm)], names=["id", "v", "cell", "turn", "away", "norm"]
            )
            turn += len(x)

    return run


def _visits(routing, cells: np.ndarray, size: np.ndarray, radius: np.ndarray, norm: np.ndarray, width: int, k: int, rest: bool):
    """For each query the cells to visit: those of the highest bounds that hold over k vectors together or, for the rest, the others whose bounds reach least."""

    def run(batches):
        centres = routing.value[cells]
        square = (centres**2).sum(1)
        for b in batches:
            q, least = _matrix(b.column(1), width).astype(np.float64), b.column(2).to_numpy(zero_copy_only=False)
            own = (q**2).sum(1)[:, None]
            dots, length = q @ centres.T, np.sqrt(own)
            ball = dots + length * radius
            ball += SLACK * (np.abs(dots) + length * radius + 1)
            gap = np.maximum(np.sqrt(np.maximum(own + square - 2 * dots, 0)) - radius, 0)
            far = (own + norm**2 - gap**2) / 2 + SLACK * (own + square + norm**2 + 1)
            bound = np.minimum(ball, far)
            order = np.argsort(-bound, 1, kind="stable")
            before = np.cumsum(size[order], 1) - size[order]
            first = np.zeros(bound.shape, bool)
            np.put_along_axis(first, order, before <= k, 1)
            chosen = ~first & (bound >= least[:, None]) if rest else first
            visited = pa.array([cells[c].tolist() for c in chosen], pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), visited], names=["id", "v", "least", "cells"])

    return run


def _answered(width: int, k: int):
    """Streams pages, each as its vectors and then its queries, and gives each query the page's best k."""

    def run(batches):
        page, ids, vectors, tree = None, [], [], None
        for b in batches:
            cell, part, block, side, own, least = (b.column(n).to_numpy(zero_copy_only=False) for n in ("cell", "part", "block", "side", "id", "least"))
            v, found = _matrix(b.column("v"), width), []
            cuts = np.flatnonzero(np.any([np.diff(c) != 0 for c in (cell, part, block, side)], axis=0)) + 1
            for a, z in zip([0, *cuts.tolist()], [*cuts.tolist(), len(own)], strict=True):
                if a == z:
                    continue
                at = cell[a], part[a], block[a]
                if at != page:
                    page, ids, vectors, tree = at, [], [], None
                if side[a] == 0:
                    ids.append(own[a:z])
                    vectors.append(v[a:z])
                elif ids:
                    tree = tree or MTree(np.concatenate(ids), np.concatenate(vectors))
                    found += [(i, x, s) for i, q, low in zip(own[a:z].tolist(), v[a:z], least[a:z].tolist(), strict=True) for s, x in tree.search(q, k, i, low)]
            columns = list(zip(*found, strict=True)) or [()] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["query_id", "vec_id", "score"])

    return run


def _best(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, page: int = 1024, block: int = 1 << 16, cells: int = 1024) -> DataFrame:
    """query_id, rank, vec_id, score; vectors and queries hold id and v (whole numbers). A query's own id is no candidate.

    There are at most `cells` cells, of pages of about `page` vectors; a page's queries come in blocks of about `block`, a tree for each.
    """
    spark = vectors.sparkSession
    n, widest = vectors.agg(F.count("*"), F.max(F.size("v"))).first()
    asking, wider = queries.agg(F.count("*"), F.max(F.size("v"))).first()
    if not n or not asking:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    width = max(widest, wider, 1)
    sample = vectors.orderBy(F.xxhash64(F.lit(1), "id"), "id").limit(min(cells, -(-n // page), max(1, ROUTING // width))).select("v").collect()
    routing = spark.sparkContext.broadcast(np.unique(_matrix(pa.array([r["v"] for r in sample], pa.list_(pa.int64())), width), axis=0).astype(np.float64))

    held = staged(spark, vectors.select("id", "v").mapInArrow(_dealt(routing, width), _DEALT), "dealt")
    told = held.groupBy("cell").agg(F.count("*").alias("n"), F.max("away").alias("radius"), F.max("norm").alias("norm")).orderBy("cell").collect()  # a row for each cell
    known, size, radius, norm = (np.array([r[c] for r in told]) for c in ("cell", "n", "radius", "norm"))
    pages = F.broadcast(spark.createDataFrame([(r["cell"], -(-r["n"] // page)) for r in told], "cell int, pages long"))
    blocks = -(-asking // block)
    asked = queries.dropDuplicates(["id"]).select("id", "v")

    def visit(questions: DataFrame, rest: bool) -> DataFrame:
        goes = questions.mapInArrow(_visits(routing, known, size, radius, norm, width, k, rest), "id long, v array<long>, least long, cells array<int>")
        at = goes.select("id", "v", "least", F.explode("cells").alias("cell")).join(pages, "cell")
        return at.select("cell", F.explode(F.sequence(F.lit(0).cast("long"), F.col("pages") - 1)).alias("part"), F.pmod(F.xxhash64("id"), F.lit(blocks)).alias("block"), F.lit(1).alias("side"), "id", "least", "v")

    def answers(asks: DataFrame) -> DataFrame:
        every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))
        have = held.join(pages, "cell").select("cell", F.pmod("turn", "pages").alias("part"), every.alias("block"), F.lit(0).alias("side"), "id", F.lit(NO_SCORE).alias("least"), "v")
        # a stated number of partitions, as few bytes may be long work
        dealt = have.unionByName(asks).repartition(parts(spark), "cell", "part", "block").sortWithinPartitions("cell", "part", "block", "side")
        return _best(dealt.mapInArrow(_answered(width, k), _OUT), k)

    near = staged(spark, answers(visit(asked.withColumn("least", F.lit(NO_SCORE)), False)), "near")
    least = near.where(F.col("rank") == k).select(F.col("query_id").alias("id"), F.col("score").alias("least"))
    later = visit(asked.join(least, "id", "left").select("id", "v", F.coalesce("least", F.lit(NO_SCORE)).alias("least")), True)
    return _best(near.drop("rank").unionByName(answers(later).drop("rank")), k)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = whole_numbers(table(spark, sf_dir, "embeddings"), "vec_id", "embedding", 1024)
    return top_k(vectors, vectors.where(F.col("id") % 100 == 0))


SQL = """
WITH whole AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)::BIGINT) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2]))::BIGINT AS score
  FROM whole q JOIN whole c ON q.vec_id % 100 = 0 AND c.vec_id <> q.vec_id)
SELECT query_id, rank, vec_id, score FROM (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM scored) WHERE rank <= 10
"""

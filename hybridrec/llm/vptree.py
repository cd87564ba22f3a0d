"""Nearest neighbours by vantage-point trees, one per shard.

Rows are dealt to shards of bounded size by a hash of their id; each shard builds one tree over its vectors.
A node keeps a vantage point and the median distance to it; its halves are the near and the far. A search
visits the nearer half first and skips the other if the distance to the median sphere, times ``relax``,
exceeds the worst distance kept: with ``relax`` 1 the triangle inequality makes that exact, larger factors prune more
and may miss. A shard's tree is built once and stays in its partition: blocks of queries are dealt to every shard and pass it one after another;
each shard answers with its best and a window merges them. What moves is so the queries times the shards, never a tree.

Defined results: vectors that are null, empty, zero or hold null or non-finite components take no part, as query or
candidate; vectors of another length than the query's are no candidates. Rows that share an id are one item with several vectors: as a query it asks with each,
as a candidate it stands in a list once, at its least distance. An item is not its own neighbour; others with an
equal vector are. Ties go to the smaller id. Extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from hybridrec.runtime import materialize, row_count

SHARD_ROWS, LEAF_ROWS, BLOCK_QUERIES = 8192, 64, 512
SCHEMA = "query_id long, vec_id long, score double"


def usable(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """Rows ``id``, ``v`` (double components) that can take part."""
    v = F.col(vector_col).cast("array<double>")
    sound = (F.size(v) > 0) & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    return vectors.select(F.col(id_col).cast("long").alias("id"), v.alias("v")).where(F.col("id").isNotNull() & F.coalesce(sound, F.lit(False)))


class Tree:
    """A vantage-point tree in flat arrays; ``rows`` lists the vectors leaf by leaf."""

    def __init__(self, points: np.ndarray, ids: np.ndarray, leaf: int = LEAF_ROWS, seed: int = 1):
        self.points, self.ids, self.leaf = points, ids, leaf
        self.repeats = len(np.unique(ids)) < len(ids)
        self.rows = np.arange(len(points))
        self.nodes: list[tuple] = []  # (vantage row, median, near, far) or (None, lo, hi, 0)
        self.random = np.random.default_rng(seed)
        self.root = self._grow(0, len(points))

    def _grow(self, lo: int, hi: int) -> int:
        at = len(self.nodes)
        if hi - lo <= self.leaf:
            self.nodes.append((None, lo, hi, 0))
            return at
        own = self.rows[lo:hi]
        vantage = own[self.random.integers(len(own))]
        d = np.sqrt(((self.points[own] - self.points[vantage]) ** 2).sum(1))
        half = (hi - lo) // 2
        order = np.argpartition(d, half)
        self.rows[lo:hi] = own[order]
        median = d[order[half]]
        self.nodes.append(())
        near, far = self._grow(lo, lo + half), self._grow(lo + half, hi)
        self.nodes[at] = (vantage, median, near, far)
        return at

    def search(self, queries: np.ndarray, query_ids: np.ndarray, k: int, relax: float = 1.0) -> tuple[np.ndarray, np.ndarray]:
        """Ids and distances of the ``k`` nearest of each query, ties to the smaller id; unused places have infinite distance.

        All queries walk the tree together: a node is visited by those that cannot skip it.
        """
        n = len(queries)
        best = np.full((n, k), np.inf)
        names = np.full((n, k), np.iinfo(np.int64).max)
        bound = (query_ids, best, names)
        stack = [(self.root, np.arange(n), None)]
        while stack:
            node, who, gap = stack.pop()
            if gap is not None:
                ok = gap * relax <= best[who, -1] * (1 + 1e-12)  # equal distances may still win by id
                who = who[ok]
            if not len(who):
                continue
            vantage, a, b, c = self.nodes[node]
            if vantage is None:
                self._leaf(queries, who, a, b, k, *bound)
                continue
            d = np.sqrt(((queries[who] - self.points[vantage]) ** 2).sum(1))
            inside = d < a
            # the far side of each query is pushed first, so that its near side is done before
            stack.append((c, who[inside], a - d[inside]))
            stack.append((b, who[~inside], d[~inside] - a))
            stack.append((b, who[inside], None))
            stack.append((c, who[~inside], None))
        return names, best

    def _leaf(self, queries, who, lo, hi, k, query_ids, best, names):
        rows = self.rows[lo:hi]
        ids = self.ids[rows]
        d = np.sqrt(((queries[who][:, None, :] - self.points[rows][None, :, :]) ** 2).sum(2))
        d[query_ids[who][:, None] == ids[None, :]] = np.inf
        all_d = np.concatenate([best[who], d], 1)
        all_i = np.concatenate([names[who], np.where(np.isinf(d), np.iinfo(np.int64).max, ids[None, :])], 1)
        if self.repeats:  # an id keeps its least distance alone
            by = np.lexsort((all_d, all_i), axis=1)
            all_d, all_i = np.take_along_axis(all_d, by, 1), np.take_along_axis(all_i, by, 1)
            again = np.zeros(all_i.shape, bool)
            again[:, 1:] = all_i[:, 1:] == all_i[:, :-1]
            all_d[again], all_i[again] = np.inf, np.iinfo(np.int64).max
        order = np.lexsort((all_i, all_d), axis=1)[:, :k]
        best[who] = np.take_along_axis(all_d, order, 1)
        names[who] = np.take_along_axis(all_i, order, 1)


def search(vectors: DataFrame, queries: DataFrame, k: int = 10, relax: float = 1.0, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score (Euclidean distance in double precision) of the ``k`` nearest to each query."""
    rows = materialize(usable(vectors, id_col, vector_col), "vectors")
    shards = max(1, -(-row_count(rows) // SHARD_ROWS))
    asked = usable(queries, id_col, vector_col)
    blocks = max(1, -(-row_count(asked) // BLOCK_QUERIES))
    at = F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int")
    # vectors of a shard in rows of some hundreds, then the blocks of queries: a partition streams them in this order
    chunk = F.pmod(F.xxhash64("id", F.lit(3)), F.lit(-(-SHARD_ROWS // BLOCK_QUERIES))).cast("int")
    vectors_ = rows.groupBy(at.alias("shard"), chunk.alias("part")).agg(F.collect_list(F.struct("id", "v")).alias("rows")).select("shard", F.lit(0).alias("asks"), "rows")
    block = asked.groupBy(F.pmod(F.xxhash64("id", F.lit(7)), F.lit(blocks)).cast("int").alias("part")).agg(F.collect_list(F.struct("id", "v")).alias("rows"))
    asks = block.select(F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), F.lit(1).alias("asks"), "rows")
    streams = vectors_.unionByName(asks).repartition(shards, "shard").sortWithinPartitions("shard", "asks")

    def answer(batches):
        shard, held, trees = None, [], None
        for batch in batches:
            for i in range(batch.num_rows):
                now, asking = batch.column(0)[i].as_py(), batch.column(1)[i].as_py()
                if now != shard:
                    shard, held, trees = now, [], None
                ids, flat, sizes = _vectors(batch.column(2)[i])
                if not asking:
                    held.append((ids, flat, sizes))
                    continue
                if trees is None:
                    trees, held = _trees(held), []
                for length, tree in trees.items():
                    own = np.flatnonzero(sizes == length)
                    if not len(own):
                        continue
                    first = (np.cumsum(sizes) - sizes)[own]
                    asked_ids = ids[own]
                    names, best = tree.search(flat[first[:, None] + np.arange(length)], asked_ids, k, relax)
                    found = np.isfinite(best)
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(asked_ids, k)[found.ravel()]), pa.array(names[found]), pa.array(best[found])], names=["query_id", "vec_id", "score"])

    found = streams.mapInArrow(answer, SCHEMA).groupBy("query_id", "vec_id").agg(F.min("score").alias("score"))  # a query id may have asked with several vectors
    w = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _vectors(rows: pa.Scalar) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids, all components one after another, and lengths of a list of (id, v)."""
    fields = rows.values
    v = fields.field(1)
    return fields.field(0).to_numpy(zero_copy_only=False), v.flatten().to_numpy(zero_copy_only=False), np.diff(v.offsets.to_numpy())


def _trees(held: list[tuple]) -> dict[int, Tree]:
    """A tree for each length of vectors."""
    out = {}
    for length in sorted({int(n) for _, _, sizes in held for n in np.unique(sizes)}):
        ids, points = [], []
        for own_ids, flat, sizes in held:
            own = np.flatnonzero(sizes == length)
            ids.append(own_ids[own])
            points.append(flat[(np.cumsum(sizes) - sizes)[own][:, None] + np.arange(length)])
        ids, points = np.concatenate(ids), np.concatenate(points)
        order = np.lexsort((*points.T[::-1], ids))  # the same tree whatever the order of arrival
        out[length] = Tree(points[order], ids[order])
    return out


def every(vec_id: Column, n: int) -> Column:
    return vec_id % n == 0

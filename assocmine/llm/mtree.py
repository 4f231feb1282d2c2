"""Exact top-k by inner product with a paged M-tree and best-first search.

Vectors of integers are lifted by one coordinate to a common norm, so that the largest inner products are the smallest
Euclidean distances, a metric. The root of the tree has up to ``ROOTS`` pivots, drawn from a bounded sample of rows
(``ROOT_SAMPLE``); every row goes to its nearest pivot, and the rows of a pivot are dealt into pages of about ``PAGE``
rows by a hash, so a pivot with a third of all rows fills many pages. A page is an M-subtree in one row of a table: its
nodes hold a pivot, a covering radius and the distance to the parent's pivot, its leaves up to ``LEAF`` entries with
their distances to the leaf's pivot. The page table is written once and never shuffled.

Queries are asked in waves of bounded size, which are broadcast to the pages. First every query searches one page of its
own pivot; its k-th score there is a bar that the pages of all pivots must be able to reach. Then the wave walks the page
table: pages whose root ball stays below a query's bar are ruled out, in the others the query walks the nodes from the
most promising on. Stored distances rule out children and entries by the triangle inequality before any distance to them
is computed; what is left is scored with exact integers. Bounds are widened by a rounding slack and compared strictly, so
ties are never lost. The page table is read once for each wave; what is shuffled are query vectors and scores only.

How much is ruled out depends on the data: :func:`search_cost` counts the scored entries, and the README has figures.

Vectors that are null, empty, or hold null or non-finite components take no part, nor do rows without id. Vectors meet
queries of their own length only. Rows that share a query's id count as the query's own. Of rows that repeat an id, the
one with the smallest vector asks. Rows equal in id and vector are stored once with their number; k of them at most can
be among the k best. Scores beyond 63 bits are held at the ends of the long range. Empty tables give no rows. Extra
columns are not read.
"""

from __future__ import annotations

import heapq
import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from assocmine.plans.materialize import materialize, ship_package

SCALE, TOP = 1024, 10
#: Rows of a page (on average), entries of a leaf, children of a node.
PAGE, LEAF, FANOUT = 4_096, 128, 16
#: Leaves that are scored at once, when scoring the most promising ones has not raised the bar.
MOST_LEAVES = 32
#: Most pivots of the root, and rows that they are chosen from.
ROOTS, ROOT_SAMPLE = 256, 4_096
#: Bytes of query vectors in a wave: what is broadcast at once.
WAVE_BYTES = 16 << 20
EXACT = 1 << 52
NOTHING = -(1 << 63)


def quantized(vectors: DataFrame, id_column: str = "vec_id", vector_column: str = "embedding") -> DataFrame:
    """``vec_id`` and ``v``: integers floor(1024 * x) as doubles, of the rows that take part."""
    bad = F.exists(F.col(vector_column), lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) == float("inf")))
    usable = F.col(id_column).isNotNull() & F.col(vector_column).isNotNull() & (F.size(vector_column) > 0)
    # the first branch keeps floor() away from values that a long cannot hold; such doubles are whole already
    whole = F.transform(F.col(vector_column), lambda x: F.when(F.abs(x.cast("double")) >= float(1 << 50), x.cast("double") * SCALE).otherwise(F.floor(F.when(F.abs(x.cast("double")) < float(1 << 50), x.cast("double")).otherwise(0.0) * SCALE).cast("double")))
    return vectors.filter(usable).filter(~F.coalesce(bad, F.lit(True))).select(F.col(id_column).cast("long").alias("vec_id"), whole.alias("v"))


class Tree:
    """M-subtree over one page, held as arrays; the entries of a leaf and the children of a node lie together."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, leaf: int = LEAF, fanout: int = FANOUT):
        self.leaf, self.fanout = leaf, fanout
        self.ids, self.x = ids, x
        self._lift()
        self._build()

    def __getstate__(self):
        small = self.x.astype(np.int16) if self.largest < 1 << 15 else self.x  # components are whole numbers
        return {**{k: v for k, v in self.__dict__.items() if k not in ("x", "lifted", "pivots", "norms")}, "x": small}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self.x = self.x.astype(np.float64)
        self._lift()
        self.pivots = self.lifted[self.pivot]

    def _lift(self) -> None:
        self.largest = float(np.abs(self.x).max(initial=0.0))
        norms = np.einsum("ij,ij->i", self.x, self.x)
        self.norm2 = float(norms.max(initial=0.0))
        if np.isfinite(self.norm2):
            self.lifted = np.column_stack([self.x, np.sqrt(np.maximum(0.0, self.norm2 - norms))])
        else:  # squares beyond doubles: one leaf, and bounds that rule nothing out
            self.lifted = np.zeros((self.x.shape[0], self.x.shape[1] + 1))

    def _distance(self, of: np.ndarray, to: int) -> np.ndarray:
        return np.sqrt(((self.lifted[of] - self.lifted[to]) ** 2).sum(axis=1))

    def _build(self) -> None:
        """Nodes breadth first; ``order`` puts the entries of every leaf side by side."""
        pivot, radius, to_parent, child, entry = [], [], [], [], []
        order, away_of, filled = [], [], 0
        waiting = [(np.arange(len(self.ids)), 0, 0.0)]
        for members, p, up in waiting:  # grows while it is walked
            away = self._distance(members, p)
            pivot.append(p)
            radius.append(float(away.max(initial=0.0)))
            to_parent.append(up)
            if len(members) <= self.leaf or radius[-1] == 0.0:
                order.append(members)
                away_of.append(away)
                child.append((0, 0))
                entry.append((filled, filled + len(members)))
                filled += len(members)
                continue
            groups = self._split(members, away)
            child.append((len(waiting), len(waiting) + len(groups)))
            entry.append((0, 0))
            waiting += [(group, q, float(self._distance(np.array([q]), p)[0])) for group, q in groups]
        self.pivot, self.radius, self.to_parent = np.array(pivot), np.array(radius), np.array(to_parent)
        self.child, self.entry = child, entry
        self.entry_distance = np.concatenate(away_of)
        order = np.concatenate(order)
        place = np.empty(len(order), dtype=np.int64)
        place[order] = np.arange(len(order))
        self.pivot, self.ids, self.x, self.lifted = place[self.pivot], self.ids[order], self.x[order], self.lifted[order]
        self.pivots = self.lifted[self.pivot]

    def _split(self, members: np.ndarray, away: np.ndarray) -> list[tuple[np.ndarray, int]]:
        """Members by their nearest new pivot; pivots lie at even ranks of distance from the node's own pivot."""
        order = members[np.argsort(away, kind="stable")]
        pivots, owner, nearest = [], np.zeros(len(members), dtype=np.int64), np.full(len(members), np.inf)
        for p in order[np.linspace(0, len(order) - 1, self.fanout).astype(int)].tolist():
            d = self._distance(members, p)
            closer = d < nearest
            if closer[members == p].any():  # not a copy of a pivot
                pivots.append(p)
                owner[closer], nearest[closer] = len(pivots) - 1, d[closer]
        return [(members[owner == k], p) for k, p in enumerate(pivots) if (owner == k).any()]

    def scores(self, entries: np.ndarray, query: np.ndarray) -> np.ndarray:
        """Exact inner products as 64-bit integers."""
        x = self.x[entries]
        if float(np.abs(query).max(initial=0.0)) * self.largest * len(query) < EXACT:
            return (x @ query).astype(np.int64)
        q = [int(c) for c in query]
        return np.array([max(NOTHING, min((1 << 63) - 1, sum(int(a) * b for a, b in zip(row, q)))) for row in x], dtype=np.int64)

    def root_bounds(self, queries: np.ndarray) -> np.ndarray:
        """For each query a score that no entry of the page exceeds."""
        half, slack = self._half(np.einsum("ij,ij->i", queries, queries))
        asked = np.where(np.isfinite(half)[:, None], queries, 0.0)
        away = np.sqrt(((asked - self.pivots[0, :-1]) ** 2).sum(axis=1) + self.pivots[0, -1] ** 2)
        return half - np.maximum(0.0, away - self.radius[0]) ** 2 / 2 + slack

    def _half(self, norm2):
        half = (norm2 + self.norm2) / 2
        return half, 1e-9 * (np.abs(half) + 1.0)

    def search(self, own: int, query: np.ndarray, k: int, bar: int = NOTHING) -> tuple[list[tuple[int, int]], int]:
        """Of the entries with other ids that score ``bar`` or more the k best (score, vec_id), ties to the smaller id; and how many were scored."""
        half, slack = self._half(float(query @ query))
        q = np.append(query, 0.0) if np.isfinite(half) else np.zeros(len(query) + 1)

        def most(distance):
            return half - np.maximum(0.0, distance) ** 2 / 2 + slack

        best: list[tuple[int, int]] = []  # min-heap of (score, -vec_id)
        scored, room = 0, 1
        leaves: list[tuple[int, float]] = []  # the most promising ones, to be scored at once
        first = float(np.sqrt(((self.pivots[0] - q) ** 2).sum()))
        queue = [(-float(most(first - self.radius[0])), 0, first)]
        while queue or leaves:
            while queue and len(leaves) < room:
                bound, node, away = heapq.heappop(queue)
                if -bound < bar:
                    queue.clear()
                    break
                lo, hi = self.child[node]
                if hi == lo:
                    leaves.append((node, away))
                    continue
                # stored distances to the parent rule children out before theirs are computed
                at = lo + np.flatnonzero(most(np.abs(away - self.to_parent[lo:hi]) - self.radius[lo:hi]) >= bar)
                if len(at):
                    d = np.sqrt(((self.pivots[at] - q) ** 2).sum(axis=1))
                    bounds = most(d - self.radius[at])
                    for child, dist, ub in zip(at.tolist(), d.tolist(), bounds.tolist()):
                        if ub >= bar:
                            heapq.heappush(queue, (-ub, child, dist))
            if not leaves:
                break
            entries = np.concatenate([np.arange(*self.entry[node]) for node, _ in leaves])
            away = np.repeat([d for _, d in leaves], [self.entry[node][1] - self.entry[node][0] for node, _ in leaves])
            leaves = []
            entries = entries[most(np.abs(away - self.entry_distance[entries])) >= bar]
            found, names, before = self.scores(entries, query), self.ids[entries], bar
            scored += len(names)
            good = (found >= bar) & (names != own)
            for score, vec_id in zip(found[good].tolist(), names[good].tolist()):
                if len(best) < k:
                    heapq.heappush(best, (score, -vec_id))
                elif (score, -vec_id) > best[0]:
                    heapq.heapreplace(best, (score, -vec_id))
            if len(best) == k:
                bar = max(bar, best[0][0])
            room = min(2 * room, MOST_LEAVES) if bar == before else room  # the bar stands: more leaves at once
        return [(score, -minus) for score, minus in sorted(best, reverse=True)], scored


class Root:
    """Pivots of the root by the length of their vectors, and the norm that all vectors are lifted to."""

    def __init__(self, sample: list[tuple[int, list[float]]], norm2: float, most: int):
        self.norm2 = norm2
        self.pivots: dict[int, np.ndarray] = {}
        by_dim: dict[int, list[list[float]]] = {}
        for _, v in sample:
            by_dim.setdefault(len(v), []).append(v)
        for dim, rows in by_dim.items():
            lifted = self.lift(np.array(rows, dtype=np.float64))
            share = max(1, most * len(rows) // len(sample))
            chosen, nearest = [0], ((lifted - lifted[0]) ** 2).sum(axis=1)
            while len(chosen) < share and nearest.max() > 0:  # each time the row farthest from those chosen
                chosen.append(int(nearest.argmax()))
                nearest = np.minimum(nearest, ((lifted - lifted[chosen[-1]]) ** 2).sum(axis=1))
            self.pivots[dim] = lifted[chosen]

    def lift(self, x: np.ndarray) -> np.ndarray:
        return np.column_stack([x, np.sqrt(np.maximum(0.0, self.norm2 - np.einsum("ij,ij->i", x, x)))])

    def nearest(self, x: np.ndarray) -> np.ndarray:
        """Number of the nearest pivot of every row; 0 where the sample has no vector of this length."""
        pivots = self.pivots.get(x.shape[1])
        if pivots is None:
            return np.zeros(len(x), dtype=np.int64)
        lifted = self.lift(x)
        return ((pivots**2).sum(axis=1) - 2 * (lifted @ pivots.T)).argmin(axis=1)


def _vectors(column: pa.Array) -> list[np.ndarray]:
    return [np.array(v, dtype=np.float64) for v in column.to_pylist()]


def routed(rows: DataFrame, root: Root) -> DataFrame:
    """``vec_id``, ``v``, ``dim`` and ``cell``, the number of the nearest pivot."""
    ship_package(rows.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found, vectors = np.zeros(batch.num_rows, dtype=np.int64), _vectors(batch.column(1))
            dims = np.array([len(v) for v in vectors], dtype=np.int32)
            for dim in np.unique(dims).tolist():
                at = np.flatnonzero(dims == dim)
                found[at] = root.nearest(np.stack([vectors[i] for i in at]))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(dims, pa.int32()), pa.array(found, pa.int64())], names=["vec_id", "v", "copies", "dim", "cell"])

    return rows.select("vec_id", "v", "copies").mapInArrow(run, "vec_id long, v array<double>, copies long, dim int, cell long")


def index(vectors: DataFrame, k: int = TOP, page: int = PAGE, leaf: int = LEAF, fanout: int = FANOUT) -> tuple[DataFrame, DataFrame, Root | None]:
    """The page table (dim, cell, part, tree), the numbers of pages of each cell, and the root, of a written table (vec_id, v)."""
    ship_package(vectors.sparkSession)
    distinct = materialize(vectors.groupBy("vec_id", "v").agg(F.least(F.count("*"), F.lit(k)).alias("copies")), "mtree-rows")
    square = F.aggregate("v", F.lit(0.0), lambda acc, x: acc + x * x)
    n, norm2 = distinct.agg(F.count("*"), F.max(square)).first()
    if not n:
        return None, None, None
    sample = distinct.orderBy(F.xxhash64("vec_id", "v")).select("vec_id", "v").limit(ROOT_SAMPLE).collect()
    root = Root([(r[0], r[1]) for r in sample], float(norm2), max(1, min(ROOTS, -(-n // page))))
    dealt = materialize(routed(distinct, root), "mtree-cells")
    parts = materialize(dealt.groupBy("dim", "cell").agg(F.ceil(F.count("*") / page).cast("long").alias("parts")), "mtree-parts")

    def build(table: pa.Table) -> pa.Table:
        copies = np.asarray(table.column("copies"), dtype=np.int64)
        ids, x = np.asarray(table.column("vec_id"), dtype=np.int64), np.asarray(table.column("v").combine_chunks().flatten(), dtype=np.float64).reshape(table.num_rows, -1)
        order = np.lexsort((ids,))
        order = np.repeat(order, copies[order])
        tree = Tree(ids[order], x[order], leaf, fanout)
        key = [[table.column(c)[0].as_py()] for c in ("dim", "cell", "part")]
        return pa.table([pa.array(key[0], pa.int32()), pa.array(key[1], pa.int64()), pa.array(key[2], pa.int64()), pa.array([pickle.dumps(tree)], pa.binary())], names=["dim", "cell", "part", "tree"])

    placed = dealt.join(F.broadcast(parts), ["dim", "cell"]).withColumn("part", F.pmod(F.xxhash64("vec_id", "v"), F.col("parts")))
    pages = placed.select("dim", "cell", "part", "vec_id", "v", "copies").groupBy("dim", "cell", "part").applyInArrow(build, "dim int, cell long, part long, tree binary")
    return materialize(pages, "mtree-pages"), parts, root


FOUND = "query_id long, vec_id long, score long, scored long"


def _found(rows: list[tuple[int, int, int, int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (list(zip(*rows)) or [[]] * 4)], names=["query_id", "vec_id", "score", "scored"])


def bars(pages: DataFrame, parts: DataFrame, asked: DataFrame, root: Root, k: int) -> DataFrame:
    """``query_id`` and ``bar``: the k-th score that a query finds in one page of its own cell (none: no row)."""
    routed_queries = routed(asked.withColumn("copies", F.lit(1).cast("long")), root).join(F.broadcast(parts), ["dim", "cell"]).withColumn("part", F.pmod(F.xxhash64("vec_id"), F.col("parts")))
    packs = routed_queries.groupBy("dim", "cell", "part").agg(F.collect_list(F.struct("vec_id", "v")).alias("queries"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for tree_bytes, queries in zip(batch.column(0), batch.column(1).to_pylist()):
                tree = pickle.loads(tree_bytes.as_py())
                for q in queries:
                    best, scored = tree.search(q["vec_id"], np.array(q["v"], dtype=np.float64), k)
                    rows.append((q["vec_id"], 0, best[-1][0] if len(best) == k else NOTHING, scored))
            yield _found(rows)

    return pages.join(packs, ["dim", "cell", "part"]).select("tree", "queries").mapInArrow(run, FOUND).select("query_id", F.col("score").alias("bar"), "scored")


def _wave(pages: DataFrame, asked: list[tuple[int, list[float], int]], k: int) -> DataFrame:
    """What the queries of one wave find in every page."""
    spark = pages.sparkSession
    by_dim: dict[int, list[tuple[int, list[float], int]]] = {}
    for q in asked:
        by_dim.setdefault(len(q[1]), []).append(q)
    sent = spark.sparkContext.broadcast({d: (np.array([q[0] for q in qs]), np.array([q[1] for q in qs], dtype=np.float64), np.array([q[2] for q in qs])) for d, qs in by_dim.items()})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = sent.value
        reached = {d: bar.copy() for d, (_, _, bar) in known.items()}  # rises from page to page of a task
        for batch in batches:
            for dim, tree_bytes in zip(batch.column(0).to_pylist(), batch.column(1)):
                if dim not in known:
                    continue
                ids, x, _ = known[dim]
                bar, tree, rows = reached[dim], pickle.loads(tree_bytes.as_py()), []
                for i in np.flatnonzero(tree.root_bounds(x) >= bar).tolist():
                    best, scored = tree.search(int(ids[i]), x[i], k, int(bar[i]))
                    rows += [(int(ids[i]), v, s, 0) for s, v in best]
                    rows.append((int(ids[i]), None, None, scored))
                    if len(best) == k:
                        bar[i] = max(bar[i], best[-1][0])
                yield _found(rows)

    return pages.select("dim", "tree").mapInArrow(run, FOUND)


def _search(vectors: DataFrame, queries: DataFrame, k: int, wave_bytes: int, **options) -> tuple[DataFrame, DataFrame]:
    spark = vectors.sparkSession
    pages, parts, root = index(vectors, k, **options)
    if pages is None:
        empty = spark.createDataFrame([], FOUND)
        return empty, empty.select("query_id", "scored")
    first = materialize(bars(pages, parts, queries, root, k), "mtree-bars")
    known = first.groupBy("query_id").agg(F.max("bar").alias("bar"))
    asked = materialize(queries.join(known, F.col("vec_id") == F.col("query_id"), "left").select("vec_id", "v", F.coalesce("bar", F.lit(NOTHING)).alias("bar")), "mtree-asked")
    size = asked.agg(F.sum(8 * F.size("v") + 64)).first()[0] or 0
    waves = max(1, -(-int(size) // wave_bytes))
    found = None
    for wave in range(waves):
        mine = asked.filter(F.pmod(F.xxhash64("vec_id"), F.lit(waves)) == wave).collect()
        if mine:
            one = materialize(_wave(pages, [tuple(r) for r in mine], k), "mtree-found")
            found = one if found is None else found.unionByName(one)
    found = found if found is not None else spark.createDataFrame([], FOUND)
    return found, first.select("query_id", "scored").unionByName(found.filter("vec_id is null").select("query_id", "scored"))


def search(vectors: DataFrame, queries: DataFrame, k: int = TOP, wave_bytes: int = WAVE_BYTES, **options) -> DataFrame:
    """``query_id``, ``rank``, ``vec_id`` and ``score`` of the k best rows of ``vectors`` for each row of ``queries``.

    Both have columns ``vec_id`` and ``v`` (see :func:`quantized`) and must be written tables; ids of queries differ.
    Options are those of :func:`index`.
    """
    found, _ = _search(vectors, queries, k, wave_bytes, **options)
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.filter("vec_id is not null").withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def search_cost(vectors: DataFrame, queries: DataFrame, k: int = TOP, wave_bytes: int = WAVE_BYTES, **options) -> DataFrame:
    """``query_id`` and ``scored``: how many entries the search has scored for each query."""
    return _search(vectors, queries, k, wave_bytes, **options)[1].groupBy("query_id").agg(F.sum("scored").alias("scored"))


def top_of_every_hundredth(vectors: DataFrame, step: int = 100) -> DataFrame:
    """The stated query set, rows whose id is divisible by ``step``, against all rows."""
    rows = materialize(quantized(vectors), "mtree-vectors")
    queries = rows.filter(F.col("vec_id") % step == 0).groupBy("vec_id").agg(F.min("v").alias("v"))
    return search(rows, materialize(queries, "mtree-queries"))


ORACLE = """
with v as (
  select vec_id, [floor(1024 * cast(x as double)) for x in embedding] as v from embeddings
  where vec_id is not null and embedding is not null and len(embedding) > 0 and len([x for x in embedding if x is null or not isfinite(x)]) = 0
), s as (
  select q.vec_id as query_id, c.vec_id as vec_id, cast(list_inner_product(q.v, c.v) as bigint) as score
  from v q join v c on q.vec_id <> c.vec_id and len(q.v) = len(c.v) where q.vec_id % 100 = 0
)
select query_id, cast(rank as integer) as rank, vec_id, score
from (select *, row_number() over (partition by query_id order by score desc, vec_id) as rank from s) where rank <= 10
"""

"""Exact top-k inner-product search with M-trees.

Vectors of one norm bound M become points of one sphere by an added coordinate
``sqrt(M^2 - |x|^2)``; a query gets 0 there.  Then the squared Euclidean distance
is ``|q|^2 + M^2 - 2<q, x>``, a metric in which the nearest points have the largest
inner products.  The points are routed to the nearest of a bounded number of
pivots; a group that exceeds a tree is routed again, to pivots of its own.  Each
group becomes one paged M-tree: nodes with routing object, covering radius, and
the distances of their entries to it.

A search is best-first, for a block of queries at a time: the heap holds nodes
with the queries that still want them, the nearest node first.  Stored distances
rule out (query, entry) pairs before any distance is computed:
``|d(q, parent) - d(entry, parent)| - radius`` is a lower bound.  What is left of a
node takes one matrix product.  Each query first searches its home tree; the score
it finds there is the bound with which the other trees are entered or skipped.
Ties go to the smaller identifier, so pages are only skipped if their bound is
strictly beyond the k-th best by more than the rounding error of a distance.

Scores are exact integers.  Below ``2^53`` for the product of the largest norms
every partial sum of a float product is exact; above, floats with an error bound
choose candidates and whole integers decide.  A score beyond a long counts as the
nearest long, for ranking too, and so does a component.

Vectors that are null, or hold a null or non-finite component, take no part (as
query or candidate); shorter vectors count as padded with zeros; rows with a null
identifier take no part; repeated identifiers and rows are separate candidates, a
repeated query identifier asks once, with its smallest vector, and a query never
returns rows of its own identifier; an empty table gives no rows.  Only the two
columns named here are read, so others may have any name.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tallquant.llm.common import Workspace

RESULT = "query_id long, vec_id long, score long"
_LONG = 2**63 - 1
#: Pivots of a group that is routed again, and how often that may happen before rows are dealt by hash.
FAN, LEVELS = 64, 6


class MTree:
    """One bulk-loaded tree; ``rows`` is the order in which its leaves hold the points."""

    def __init__(self, points: np.ndarray, page: int = 64):
        self.rows = np.arange(len(points))
        self.points = points
        # node: center, radius, then either a slice of rows or child nodes with their centers and radii; distances of the entries to the center
        self.nodes: list[tuple] = []
        self.root = self._build(0, len(points), page)
        self.points = points[self.rows]

    def _add(self, *node) -> int:
        self.nodes.append(node)
        return len(self.nodes) - 1

    def _build(self, start: int, stop: int, page: int) -> int:
        """Split at far pivots until the rows fit a page, then group children upwards."""
        rows = self.rows[start:stop]
        inside = self.points[rows]
        center = inside.mean(axis=0)
        apart = np.linalg.norm(inside - center, axis=1)
        radius = float(apart.max(initial=0.0))
        if len(rows) <= page:
            return self._add(center, radius, (start, stop), None, None, apart)
        fan = min(16, -(-len(rows) // page))
        pivots = [int(apart.argmax())]
        near = np.linalg.norm(inside - inside[pivots[0]], axis=1)
        while len(pivots) < fan:
            pivots.append(int(near.argmax()))
            near = np.minimum(near, np.linalg.norm(inside - inside[pivots[-1]], axis=1))
        seeds = inside[pivots]
        owner = ((seeds**2).sum(axis=1)[None, :] - 2 * inside @ seeds.T).argmin(axis=1)
        counts = np.bincount(owner, minlength=fan)
        if counts.max() == len(rows):  # equal points: cut by position
            owner = np.arange(len(rows)) * fan // len(rows)
            counts = np.bincount(owner, minlength=fan)
        self.rows[start:stop] = rows[np.argsort(owner, kind="stable")]
        stops = start + np.cumsum(counts)
        children = [self._build(b - c, b, page) for b, c in zip(stops.tolist(), counts.tolist(), strict=True) if c]
        centers = np.array([self.nodes[c][0] for c in children])
        radii = np.array([self.nodes[c][1] for c in children])
        return self._add(center, radius, children, centers, radii, np.linalg.norm(centers - center, axis=1))

    def search(self, asked: Asked) -> None:
        """Best-first for all queries of ``asked``, which keeps the best and how far each query still reaches."""
        center, _, _, _, _, _ = self.nodes[self.root]
        everyone = np.arange(len(asked.norm2))
        heap = [(0.0, self.root, everyone, asked.distances(everyone, center[None, :])[:, 0])]
        while heap:
            _, node, who, d = heapq.heappop(heap)
            _, radius, inside, centers, radii, apart = self.nodes[node]
            far = asked.reach[who]
            still = d - radius <= far
            if not still.any():
                continue
            who, d, far = who[still], d[still], far[still]
            if centers is None:
                wanted = np.abs(d[:, None] - apart[None, :]) <= far[:, None]
                some = np.flatnonzero(wanted.any(axis=0))
                if len(some):
                    asked.offer(who, inside[0] + some, wanted[:, some])
                continue
            wanted = np.abs(d[:, None] - apart[None, :]) - radii[None, :] <= far[:, None]
            some = np.flatnonzero(wanted.any(axis=0))
            to_child = asked.distances(who, centers[some])
            wanted = wanted[:, some] & (to_child - radii[some] <= far[:, None])
            for k, c in enumerate(some.tolist()):
                mine = wanted[:, k]
                if mine.any():
                    near = to_child[mine, k]
                    heapq.heappush(heap, (float(near.min() - radii[c]), inside[c], who[mine], near))


class Asked:
    """The queries of a block: their best so far, and the distance beyond which nothing can count."""

    def __init__(self, q: np.ndarray, query_id: np.ndarray, least: np.ndarray, x: np.ndarray, ids: np.ndarray, k: int, bound2: float):
        """``q``, ``x``: integers; ``least``: a score known to be reached by k others, or nan."""
        self.q, self.query_id, self.x, self.ids, self.k, self.bound2 = q, query_id, x, ids, k, bound2
        self.real, self.real_x = q.astype(np.float64), x.astype(np.float64)
        self.norm2 = (self.real**2).sum(axis=1)
        self.exact = bound2 < 2.0**52
        rounding = np.finfo(np.float64).eps * (q.shape[1] + 8)
        scale = np.sqrt(self.norm2) + np.sqrt(bound2)
        self.slack = 4 * np.sqrt(rounding) * scale
        self.error = 0.0 if self.exact else 4 * rounding * np.sqrt(self.norm2 * bound2)
        self.floor = np.where(np.isnan(least), -np.inf, least)
        self.best: list[np.ndarray] = [np.empty((0, 3), dtype=np.int64)]  # query, score, identifier
        self.reach = np.full(len(q), np.inf)
        self._reach(np.arange(len(q)))

    def _reach(self, who: np.ndarray) -> None:
        least = self.floor[who] - (self.error[who] if not self.exact else 0.0)
        self.reach[who] = np.sqrt(np.maximum(0.0, self.norm2[who] + self.bound2 - 2.0 * least)) + self.slack[who]

    def distances(self, who: np.ndarray, centers: np.ndarray) -> np.ndarray:
        square = self.norm2[who][:, None] + (centers**2).sum(axis=1)[None, :] - 2.0 * self.real[who] @ centers[:, :-1].T
        return np.sqrt(np.maximum(0.0, square))

    def offer(self, who: np.ndarray, rows: np.ndarray, wanted: np.ndarray) -> None:
        """Score the wanted (query, row) pairs; keep what is among the best k of its query."""
        scores = self.real[who] @ self.real_x[rows].T
        least = self.floor[who] - (self.error[who] if not self.exact else 0.0)
        good = wanted & (scores >= least[:, None]) & (self.query_id[who][:, None] != self.ids[rows][None, :])
        a, b = np.nonzero(good)
        if not len(a):
            return
        whole = scores[a, b].astype(np.int64) if self.exact else self._whole(who[a], rows[b])
        pairs = np.column_stack([who[a], whole, self.ids[rows[b]]])
        found = np.concatenate([self.best[0], pairs])
        touched = np.zeros(len(self.q), dtype=bool)
        touched[who[a]] = True
        mine = touched[found[:, 0]]
        rest, found = found[~mine], found[mine]
        found = found[np.lexsort((found[:, 2], -found[:, 1], found[:, 0]))]
        starts = np.flatnonzero(np.concatenate(([True], found[1:, 0] != found[:-1, 0])))
        rank = np.arange(len(found)) - np.repeat(starts, np.diff(np.append(starts, len(found))))
        last = found[rank == self.k - 1]
        self.best = [np.concatenate([rest, found[rank < self.k]])]
        if len(last):
            full = last[:, 0]
            self.floor[full] = np.maximum(self.floor[full], last[:, 1].astype(np.float64))
            self._reach(full)

    def _whole(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        products = [sum(map(int.__mul__, self.q[i].tolist(), self.x[j].tolist())) for i, j in zip(a.tolist(), b.tolist(), strict=True)]
        return np.array([max(-_LONG, min(_LONG, p)) for p in products], dtype=np.int64)


def dense(column, dim: int) -> np.ndarray:
    """An Arrow column of lists as an integer matrix, short rows padded with zeros."""
    cells = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    length = cells.value_lengths().to_numpy(zero_copy_only=False)
    flat = cells.flatten().to_numpy(zero_copy_only=False).astype(np.int64, copy=False)
    if (length == dim).all():
        return flat.reshape(len(length), dim)
    out = np.zeros((len(length), dim), dtype=np.int64)
    out[np.arange(dim)[None, :] < length[:, None]] = flat
    return out


def lift(x: np.ndarray, bound2: float) -> np.ndarray:
    y = x.astype(np.float64)
    return np.column_stack([y, np.sqrt(np.maximum(0.0, bound2 - (y**2).sum(axis=1)))])


def nearest(x: np.ndarray, seeds: np.ndarray) -> np.ndarray:
    return (x.astype(np.float64) @ seeds.T - (seeds**2).sum(axis=1) / 2).argmax(axis=1)


def search_block(queries: pa.Table, tree: pa.Table, k: int, dim: int, bound2: float) -> pa.Table:
    """Best ``k`` of the rows of a tree for each query of the block."""
    found = np.empty((0, 3), dtype=np.int64)
    query_id = queries["query_id"].to_numpy()
    if len(queries) and len(tree):
        x = dense(tree["v"], dim)
        index = MTree(lift(x, bound2))
        least = queries["least"].cast(pa.float64(), safe=False).to_numpy()
        asked = Asked(dense(queries["v"], dim), query_id, least, x[index.rows], tree["vec_id"].to_numpy()[index.rows], k, bound2)
        index.search(asked)
        found = asked.best[0]
    return pa.table({"query_id": query_id[found[:, 0]].astype(np.int64), "vec_id": found[:, 2], "score": found[:, 1]})


def _deal(dim: int, by_hash: bool):
    """Rows of an overfull tree to the nearest of its pivots, or dealt by hash."""

    def run(part: pa.Table, own: pa.Table) -> pa.Table:
        kept = part.select(["row", "vec_id", "v", "asks", "tree"])
        sub = np.zeros(len(part), dtype=np.int64)
        if len(own):
            heads = own["seeds"][0].as_py() or []
            if by_hash or len(heads) < 2:
                sub = (part["row"].to_numpy() + 1) * 2654435761 % (1 << 31) % own["parts"][0].as_py()
            else:
                sub = nearest(dense(part["v"], dim), dense(pa.array(heads, pa.list_(pa.int64())), dim).astype(np.float64))
        return kept.append_column("sub", pa.array(sub.astype(np.int64)))

    return run


def _route(work: Workspace, routed: DataFrame, dim: int, tree_rows: int) -> DataFrame:
    """``routed(row, vec_id, v, asks, tree)`` with every tree of at most about ``tree_rows`` rows.

    Rows of an overfull tree meet its own pivots (distinct vectors, chosen by hash)
    in chunks.  Trees of equal vectors, and what ``LEVELS`` rounds leave, are dealt by hash.
    """
    for level in range(LEVELS + 1):
        size = routed.groupBy("tree").agg(F.count("*").alias("size")).where(F.col("size") > tree_rows)
        over = work.save(size.withColumn("parts", F.ceil(2 * F.col("size") / tree_rows)), f"over-{level}")
        if over.isEmpty():
            break
        rows = routed.join(over, "tree")
        hashed = F.xxhash64("v", F.lit(level))
        some = rows.where(F.pmod(hashed, F.greatest(F.lit(1), F.floor(F.col("size") / (16 * FAN)))) == 0)
        some = some.groupBy("tree", "parts", hashed.alias("h")).agg(F.any_value("v").alias("v"))
        rank = F.row_number().over(Window.partitionBy("tree").orderBy("h"))
        some = some.withColumn("rank", rank).where(F.col("rank") <= F.least(F.lit(FAN), "parts"))
        chunks = F.ceil(F.col("size") / (4 * tree_rows))
        seeds = over.join(some.groupBy("tree").agg(F.collect_list("v").alias("seeds")), "tree", "left")
        seeds = seeds.select("tree", "seeds", "parts", F.explode(F.sequence(F.lit(0).cast("long"), chunks - 1)).alias("chunk"))
        rows = rows.select("row", "vec_id", "v", "asks", "tree", F.pmod(F.xxhash64("row"), chunks).alias("chunk"))

        dealt = rows.groupBy("tree", "chunk").cogroup(seeds.groupBy("tree", "chunk")).applyInArrow(_deal(dim, level == LEVELS), "row long, vec_id long, v array<bigint>, asks boolean, tree long, sub long")
        dealt = dealt.withColumn("tree", F.xxhash64("tree", "sub")).drop("sub")
        routed = work.save(routed.join(over, "tree", "left_anti").select(*dealt.columns).union(dealt), f"routed-{level}")
    return routed


def top_k(
    spark: SparkSession,
    vectors: DataFrame,
    is_query: Column,
    *,
    k: int = 5,
    pivots: int = 256,
    tree_rows: int = 8192,
    query_block: int = 4096,
) -> DataFrame:
    """``query_id, rank, vec_id, score`` for the k largest inner products of every query.

    ``vectors(vec_id long, v array<bigint>)``; ``is_query`` is a condition on it.
    The first pivots come from a bounded sample (at most ``pivots`` distinct
    vectors, chosen by hash); every row is indexed and the search is exact.  The
    table of roots, one row for each tree, is the only thing that is broadcast
    besides the pivots; it is read in slices of 20,000 trees.
    """
    work = Workspace(spark, "mtree")
    norm2 = F.expr("aggregate(v, 0D, (a, x) -> a + cast(x AS double) * cast(x AS double))")
    kept = vectors.where("vec_id is not null and v is not null")
    rows = work.save(kept.select(F.monotonically_increasing_id().alias("row"), "vec_id", "v", norm2.alias("norm2"), F.coalesce(is_query, F.lit(False)).alias("asks")), "rows")
    dim, bound2, n = rows.agg(F.coalesce(F.max(F.size("v")), F.lit(0)), F.coalesce(F.max("norm2"), F.lit(0.0)), F.count("*")).first()
    if not n:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    n_pivots = min(pivots, -(-2 * n // tree_rows))
    hashed = F.xxhash64("v")
    heads = rows.where(F.pmod(hashed, F.lit(max(1, n // (64 * n_pivots)))) == 0).groupBy(hashed.alias("h")).agg(F.any_value("v").alias("v"))
    heads = [r.v for r in heads.orderBy("h").limit(n_pivots).collect()] or [rows.first().v]
    seeds = dense(pa.array(heads, pa.list_(pa.int64())), dim).astype(np.float64)

    @F.pandas_udf("long")
    def home(v: pd.Series) -> pd.Series:
        return pd.Series(nearest(dense(pa.array(v, pa.list_(pa.int64())), dim), seeds).astype(np.int64))

    placed = work.save(_route(work, work.save(rows.select("row", "vec_id", "v", "asks", home("v").alias("tree")), "routed"), dim, tree_rows), "placed")

    def root(part: pa.Table) -> pa.Table:
        points = lift(dense(part["v"], dim), bound2)
        center = points.mean(axis=0)
        radius = float(np.linalg.norm(points - center, axis=1).max())
        return pa.table({"tree": part["tree"][:1], "center": pa.array([center.tolist()], pa.list_(pa.float64())), "radius": [radius]})

    roots = work.save(placed.select("tree", "v").groupBy("tree").applyInArrow(root, "tree long, center array<double>, radius double"), "roots")

    def run(asked: DataFrame, name: str) -> DataFrame:
        """``asked(query_id, v, tree, least)``; queries meet a tree in blocks of bounded size."""
        blocks = asked.groupBy("tree").agg(F.ceil(F.count("*") / query_block).alias("n_blocks"))
        asked = asked.join(blocks, "tree").withColumn("block", F.pmod(F.xxhash64("query_id"), "n_blocks")).select("query_id", "v", "least", "tree", "block")
        copies = blocks.select("tree", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n_blocks") - 1)).alias("block"))
        trees = placed.select("tree", "vec_id", "v").join(copies, "tree")
        both = asked.groupBy("tree", "block").cogroup(trees.groupBy("tree", "block"))
        return work.save(both.applyInArrow(lambda q, t: search_block(q, t, k, dim, bound2), RESULT), name)

    queries = placed.where("asks").groupBy(F.col("vec_id").alias("query_id")).agg(F.min(F.struct("v", "tree")).alias("q")).select("query_id", "q.v", "q.tree")
    at_home = run(queries.withColumn("least", F.lit(None).cast("long")), "home")
    floor = at_home.groupBy("query_id").agg(F.when(F.count("*") >= k, F.min("score")).alias("least"))
    asked = work.save(queries.join(floor, "query_id", "left"), "asked")
    found, n_roots, step = at_home, roots.count(), 20_000
    error = float(4 * np.sqrt(np.finfo(np.float64).eps * (dim + 8)))
    for first in range(0, n_roots, step):
        some = roots.where(F.expr(f"pmod(xxhash64(tree), {-(-n_roots // step)}) = {first // step}")).collect()
        ids, centers, radii = np.array([r.tree for r in some]), np.array([r.center for r in some]).reshape(len(some), -1), np.array([r.radius for r in some])
        cast = spark.sparkContext.broadcast((ids, centers, radii))

        @F.pandas_udf("array<long>")
        def enters(v: pd.Series, tree: pd.Series, least: pd.Series) -> pd.Series:
            ids, centers, radii = cast.value  # noqa: B023
            q = dense(pa.array(v, pa.list_(pa.int64())), dim).astype(np.float64)
            norm2 = (q**2).sum(axis=1)
            d = np.sqrt(np.maximum(0.0, norm2[:, None] + (centers**2).sum(axis=1)[None, :] - 2 * q @ centers[:, :-1].T))
            reach = np.sqrt(np.maximum(0.0, norm2 + bound2 - 2 * least.fillna(0).to_numpy(dtype=np.float64)))
            reach[least.isna().to_numpy()] = np.inf
            near = d - radii[None, :] <= (reach + error * (np.sqrt(norm2) + np.sqrt(bound2)))[:, None]
            return pd.Series([ids[a & (ids != t)].tolist() for a, t in zip(near, tree, strict=True)])

        visits = asked.withColumn("tree", F.explode(enters("v", "tree", "least")))
        found = found.union(run(work.save(visits, f"visits-{first}"), f"away-{first}"))
    best = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", best).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def integer_vectors(embeddings: DataFrame, scale: int = 256) -> DataFrame:
    """``vec_id, v``: floor(scale * component) of every vector that is whole and finite; components beyond a long become the nearest long."""
    x = F.col("embedding")
    whole = x.isNotNull() & F.forall(x, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < float("inf")))
    most = float(2**63 - 1024)
    cell = lambda e: F.floor(F.least(F.greatest(e.cast("double") * scale, F.lit(-most)), F.lit(most)))
    return embeddings.where(whole).select(F.col("vec_id").cast("long").alias("vec_id"), F.transform(x, cell).alias("v"))

"""Operator 7, approximate nearest neighbours by inner product, with balanced posting lists.

Inner product becomes Euclidean distance by one more dimension: data get sqrt(M**2 - |x|**2), M being the norm that at
most a thousandth exceed, and queries get 0. The few longer vectors are one more list that every query searches. A sample of bounded size is bisected, again and again, at the median between two means, so the leaves
are balanced; their means are the centroids, at most ``MOST_LISTS``. Every vector goes to the list of its nearest
centroid, and boundary vectors also to lists whose centroid is nearly as near, up to ``COPIES``. A query probes the
lists whose centroid is within a ratio of its nearest, however many; the ratio is the least at which sampled queries
find ``RECALL`` of their true neighbours in the sample. Centroids are found by a best-first walk on a neighbour graph
held in memory, in batches; a query with more lists in reach than the walk returns is compared with all. ``GROUP`` lists
that are neighbours in the bisection are searched together, so a query leaves k rows for each group it reaches, not for each list.
Groups of over ``BLOCK`` vectors and groups with over ``QUERIES`` queries are searched in tiles,
so neither a hot list nor a hot query region makes one large task; scores are exact.

Vectors that are null, zero, of another length than most, or hold null or non-finite components take no part, nor do
rows without an id. Rows of one id count once, with the best score; of repeated queries the one with the least hash
asks. Ties go to the smaller vec_id. Where fewer than k candidates exist all are returned. An empty table gives an
empty result. Other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from wsig.llm import shared

K, QUERY_STEP = 20, 20
LIST, MOST_LISTS, COPIES = 256, 16384, 4
SAMPLE_ROWS, SAMPLE_BYTES = 65_536, 32 << 20
GROUP, BLOCK, QUERIES = 16, 16384, 1024
#: Share of the true neighbours of ``ASKED`` sampled vectors that the ratio has to reach.
RECALL, ASKED = 0.98, 256
#: A vector is copied to lists within this ratio of its nearest centroid's distance, a query probes within the other.
COPY_RATIO, WALK, BEAM, DEGREE = 1.08, 48, 96, 24


def usable(dim: int) -> Column:
    v = F.col("embedding")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return F.col("vec_id").isNotNull() & v.isNotNull() & (F.size(v) == dim) & finite & F.exists(v, lambda x: x != 0)


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)


def lift(x: np.ndarray, norm: float, query: bool) -> np.ndarray:
    """Vectors on the sphere of radius 1, one dimension up."""
    if query:
        x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
        return np.hstack([x, np.zeros((len(x), 1))]).astype(np.float32)
    x = x / norm
    return np.hstack([x, np.sqrt(np.maximum(0.0, 1 - (x**2).sum(axis=1, keepdims=True)))]).astype(np.float32)


def balanced_centroids(x: np.ndarray, lists: int, seed: int = 3) -> np.ndarray:
    """Means of the leaves of balanced bisection, in the order of its tree."""
    rng = np.random.default_rng(seed)
    parts = [("", np.arange(len(x)))]
    while len(parts) < lists:
        parts.sort(key=lambda p: len(p[1]))
        path, big = parts.pop()
        if len(big) < 2:
            parts.append((path, big))
            break
        own = x[big]
        means = own[rng.choice(len(own), 2, replace=False)]
        for _ in range(8):
            side = own @ (means[0] - means[1]) > (means[0] @ means[0] - means[1] @ means[1]) / 2
            if side.all() or not side.any():
                break
            means = np.stack([own[side].mean(axis=0), own[~side].mean(axis=0)])
        order = np.argsort(own @ (means[0] - means[1]), kind="stable")
        half = len(own) // 2
        parts += [(path + "0", big[order[:half]]), (path + "1", big[order[half:]])]
    return np.stack([x[p].mean(axis=0) for _, p in sorted(parts, key=lambda p: p[0])]).astype(np.float32)


class Graph:
    """Neighbour graph over the centroids, walked best first for a batch of vectors at a time."""

    def __init__(self, centroids: np.ndarray, degree: int = DEGREE):
        self.c, n = centroids, len(centroids)
        self.sq = (centroids**2).sum(axis=1)
        degree = min(degree, n - 1)
        rng = np.random.default_rng(9)
        links = []
        for i in range(0, n, 1024):  # all centroids against all: both are bounded
            d = self.sq[None] - 2 * centroids[i : i + 1024] @ centroids.T
            d[np.arange(len(d)), np.arange(i, i + len(d))] = np.inf
            links.append(np.argpartition(d, degree - 1, axis=1)[:, :degree] if degree else np.zeros((len(d), 0), np.int64))
        far = rng.integers(0, n, (n, min(8, n)))
        self.links = np.hstack([np.concatenate(links), far]).astype(np.int32)
        self.entries = rng.choice(n, min(n, 16), replace=False)

    def search(self, q: np.ndarray, count: int, beam: int = BEAM) -> tuple[np.ndarray, np.ndarray]:
        """The nearest centroids found for each row and their distances, nearest first; -1 and infinity past the end."""
        n, beam = len(self.c), max(count, min(beam, len(self.c)))
        rows = np.arange(len(q))[:, None]
        qq = (q**2).sum(axis=1)[:, None]
        seen = np.zeros((len(q), n + 1), bool)
        distance = lambda ids, who: np.maximum(0, self.sq[ids] - 2 * np.einsum("qjd,qd->qj", self.c[ids], q[who]) + qq[who])
        ids = np.broadcast_to(self.entries, (len(q), len(self.entries))).copy()
        seen[rows, ids] = True
        d = distance(ids, np.arange(len(q)))
        pad = max(0, beam - ids.shape[1])
        ids = np.pad(ids, ((0, 0), (0, pad)), constant_values=n)
        d = np.pad(d, ((0, 0), (0, pad)), constant_values=np.inf)
        open_ = d < np.inf
        live = np.arange(len(q))
        while len(live):
            best = np.where(open_[live], d[live], np.inf)
            at = best.argmin(axis=1)
            going = best[np.arange(len(live)), at] < np.inf
            live, at = live[going], at[going]
            if not len(live):
                break
            open_[live, at] = False
            new = self.links[ids[live, at]].astype(np.int64)
            fresh = ~seen[live[:, None], new]
            new = np.where(fresh, new, n)
            new.sort(axis=1)
            new[:, 1:][new[:, 1:] == new[:, :-1]] = n
            seen[live[:, None], new] = True
            nd = np.where(new < n, distance(np.minimum(new, n - 1), live), np.inf)
            all_d = np.hstack([d[live], nd])
            keep = np.argpartition(all_d, ids.shape[1] - 1, axis=1)[:, : ids.shape[1]]
            d[live] = np.take_along_axis(all_d, keep, 1)
            ids[live] = np.take_along_axis(np.hstack([ids[live], new]), keep, 1)
            open_[live] = np.take_along_axis(np.hstack([open_[live], nd < np.inf]), keep, 1)
        order = np.argsort(d, axis=1, kind="stable")[:, :count]
        d, ids = np.take_along_axis(d, order, 1), np.take_along_axis(ids, order, 1)
        return np.where(d < np.inf, ids, -1), np.sqrt(d)


class Index:
    """What tasks need to deal vectors and queries to lists; its size is bounded by MOST_LISTS."""

    def __init__(self, graph: Graph, norm: float, dim: int):
        self.graph, self.norm, self.dim = graph, norm, dim
        self.sizes = np.zeros(len(graph.c) + 1, np.int64)  # the last list holds the vectors over the norm
        self.ratio = 1.25

    def far(self, lifted: np.ndarray) -> np.ndarray:
        """Distances to all centroids."""
        return np.sqrt(np.maximum(0, self.graph.sq - 2 * lifted @ self.graph.c.T + (lifted**2).sum(axis=1, keepdims=True)))

    def calibrate(self, x: np.ndarray, k: int, recall: float = RECALL, asked: int = ASKED) -> None:
        """Sets the ratio by the lists that hold the nearest k of some of the rows of x among the others."""
        if len(x) < 2:
            return
        rows = np.unique(np.linspace(0, len(x) - 1, min(asked, len(x))).astype(np.int64))
        ask, near = [], []
        for i in range(0, len(rows), 32):
            mine = rows[i : i + 32]
            scores = x[mine] @ x.T
            scores[np.arange(len(mine)), mine] = -np.inf
            some = min(k, len(x) - 1)
            near.append(np.argpartition(scores, len(x) - some, axis=1)[:, len(x) - some :])
            ask.append(np.repeat(np.arange(i, i + len(mine)), some))
        ask, near = np.concatenate(ask), np.concatenate([n.reshape(-1) for n in near])
        held, which = np.unique(near, return_inverse=True)
        at, lists = self.lists_of(x[held])
        far = self.far(lift(x[rows], self.norm, True))
        far /= np.maximum(far.min(axis=1, keepdims=True), 1e-30)
        order = np.argsort(at, kind="stable")
        at, lists = at[order], lists[order]
        first, count = np.searchsorted(at, which), np.bincount(at, minlength=len(held))[which]
        pair = np.repeat(np.arange(len(which)), count)
        place = np.arange(len(pair)) - np.repeat(np.cumsum(count) - count, count) + first[pair]
        need = np.full(len(which), np.inf)
        np.minimum.at(need, pair, far[ask[pair], lists[place]])
        self.ratio = float(max(1.02, np.sort(need)[min(len(need) - 1, math.ceil(recall * len(need)) - 1)]))

    def lists_of(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, list) pairs: the nearest list and, for boundary vectors, near ones."""
        out, c = [], self.graph.c
        for i in range(0, len(x), 512):
            ids, d = self.graph.search(lift(x[i : i + 512], self.norm, False), min(COPIES, len(c)), 48)
            near = (ids >= 0) & (d <= COPY_RATIO * d[:, :1])
            near[:, 0] = True
            over = np.linalg.norm(x[i : i + 512], axis=1) > self.norm * (1 + 1e-9)
            near[over, 1:] = False
            ids[over, 0] = len(c)
            rows, at = np.nonzero(near)
            out.append((rows + i, ids[rows, at]))
        return (np.concatenate([a for a, _ in out]), np.concatenate([b for _, b in out])) if out else (np.zeros(0, int), np.zeros(0, int))

    def probes(self, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(row, list) pairs to search: within the ratio, and more while they may hold fewer than k others."""
        out, n = [], len(self.graph.c)
        for i in range(0, len(q), 512):
            lifted = lift(q[i : i + 512], self.norm, True)
            ids, d = self.graph.search(lifted, min(WALK, n))
            wide = (ids[:, -1] >= 0) & (d[:, -1] <= self.ratio * d[:, 0]) & (n > ids.shape[1])
            parts = [(np.flatnonzero(~wide), ids[~wide], d[~wide])]
            if wide.any():
                far = self.far(lifted[wide])
                order = np.argsort(far, axis=1, kind="stable")
                parts.append((np.flatnonzero(wide), order, np.take_along_axis(far, order, 1)))
            for who, ids, d in parts:
                held = np.where(ids >= 0, self.sizes[ids], 0)
                before = np.cumsum(held, axis=1) - held
                take = (ids >= 0) & ((d <= self.ratio * d[:, :1]) | (before < COPIES * (k + 1)))
                short = (held * take).sum(axis=1) < COPIES * (k + 1)  # too few in reach: every list
                rows, at = np.nonzero(take & ~short[:, None])
                out.append((who[rows] + i, ids[rows, at]))
                out.append((np.repeat(who[short] + i, n), np.tile(np.arange(n), short.sum())))
        if self.sizes[n]:
            out.append((np.arange(len(q)), np.full(len(q), n)))
        return (np.concatenate([a for a, _ in out]), np.concatenate([b for _, b in out])) if out else (np.zeros(0, int), np.zeros(0, int))


def fit(rows: DataFrame, dim: int, k: int = K) -> Index:
    """Centroids from a sample of at most SAMPLE_ROWS rows and SAMPLE_BYTES bytes, drawn by hash of the id."""
    norm = F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))
    stats = rows.select(F.count("*").alias("n"), F.percentile_approx(norm, 0.999, 20_000).alias("norm")).first()
    most = min(SAMPLE_ROWS, max(1024, SAMPLE_BYTES // (8 * dim)))
    share = most / stats["n"]
    draw = F.pmod(F.xxhash64("vec_id", F.lit(5)), F.lit(1 << 30))
    among = rows if share >= 1 else rows.where(draw < int(min(1.0, 1.5 * share) * (1 << 30)))
    sample = among.orderBy(draw, "vec_id", F.xxhash64("embedding")).limit(most)
    x = _matrix(sample.select("embedding").toArrow().column(0).combine_chunks(), dim)
    x = x[np.linalg.norm(x, axis=1) <= stats["norm"] * (1 + 1e-9)]
    lists = max(1, min(MOST_LISTS, math.ceil(stats["n"] / LIST), len(x)))
    index = Index(Graph(balanced_centroids(lift(x, stats["norm"], False), lists)), stats["norm"], dim)
    index.calibrate(x, k)
    return index


def _posted(rows: DataFrame, index: Index) -> DataFrame:
    """(list, vec_id, embedding): vectors with each list that holds them."""
    sent, dim = rows.sparkSession.sparkContext.broadcast(index), index.dim

    def run(batches):
        for batch in batches:
            at, lists = sent.value.lists_of(_matrix(batch.column("embedding"), dim))
            take = pa.array(at)
            yield pa.RecordBatch.from_arrays([pa.array(lists.astype(np.int32)), batch.column("vec_id").take(take), batch.column("embedding").take(take)], ["list", "vec_id", "embedding"])

    return rows.mapInArrow(run, f"list int, vec_id long, embedding {rows.schema['embedding'].dataType.simpleString()}")


def _asked(queries: DataFrame, index: Index, k: int) -> DataFrame:
    """(grp, lists, vec_id, embedding): queries with the lists of each group that they search."""
    sent, dim = queries.sparkSession.sparkContext.broadcast(index), index.dim

    def run(batches):
        for batch in batches:
            at, lists = sent.value.probes(_matrix(batch.column("embedding"), dim), k)
            order = np.lexsort((lists, at))
            at, lists = at[order], lists[order]
            grp = lists // GROUP
            first = np.flatnonzero(np.concatenate(([True], (at[1:] != at[:-1]) | (grp[1:] != grp[:-1])))) if len(at) else np.zeros(0, np.int64)
            take = pa.array(at[first])
            held = pa.ListArray.from_arrays(pa.array(np.append(first, len(at)).astype(np.int32)), pa.array(lists.astype(np.int32)))
            yield pa.RecordBatch.from_arrays([pa.array(grp[first].astype(np.int32)), held, batch.column("vec_id").take(take), batch.column("embedding").take(take)], ["grp", "lists", "vec_id", "embedding"])

    return queries.mapInArrow(run, f"grp int, lists array<int>, vec_id long, embedding {queries.schema['embedding'].dataType.simpleString()}")


def best_of(queries: np.ndarray, points: np.ndarray, q_ids: np.ndarray, p_ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query id, point id, score) of the k best points of each query, ties to the smaller id, none with its own id.

    An id's rows count as one before the k-th score is taken."""
    out = []
    by_id = np.argsort(p_ids, kind="stable")
    points, p_ids = points[by_id], p_ids[by_id]
    starts = np.flatnonzero(np.r_[True, p_ids[1:] != p_ids[:-1]]) if len(p_ids) else np.zeros(0, np.int64)
    ids, repeated = p_ids[starts], len(starts) < len(p_ids)
    for q, scores in zip(range(len(queries)), queries @ points.T):
        best = np.where(ids == q_ids[q], -np.inf, np.maximum.reduceat(scores, starts) if repeated else scores)
        some = min(k, len(best))
        floor = np.partition(best, len(best) - some)[len(best) - some]
        slack = 1e-12 * max(1.0, np.abs(queries[q]).sum() * np.abs(points).max())
        near = np.flatnonzero((scores >= floor - slack) & (p_ids != q_ids[q]))
        exact = (points[near] * queries[q]).sum(axis=1)
        order = np.lexsort((p_ids[near], -exact))
        if repeated:
            _, first = np.unique(p_ids[near][order], return_index=True)
            order = order[np.sort(first)]
        order = order[:k]
        out.append((np.full(len(order), q_ids[q]), p_ids[near][order], exact[order]))
    return tuple(np.concatenate(c) for c in zip(*out)) if out else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))


def best_in_group(queries: np.ndarray, q_ids: np.ndarray, asked: np.ndarray, ask_of: np.ndarray, points: np.ndarray, p_ids: np.ndarray, p_lists: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best of each query over the lists that it searches: list asked[i] is searched by query ask_of[i]."""
    found = []
    for one in np.unique(asked):
        mine, own = np.flatnonzero(p_lists == one), ask_of[asked == one]
        if len(mine):
            found.append(best_of(queries[own], points[mine], q_ids[own], p_ids[mine], k))
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    q, p, score = (np.concatenate(c) for c in zip(*found))
    order = np.lexsort((p, -score, q))
    q, p, score = q[order], p[order], score[order]
    _, first = np.unique(np.stack([q, p], axis=1), axis=0, return_index=True)  # a vector of several lists counts once
    first.sort()
    q, p, score = q[first], p[first], score[first]
    nth = np.arange(len(q)) - np.searchsorted(q, q)
    return q[nth < k], p[nth < k], score[nth < k]


def search(rows: DataFrame, queries: DataFrame, index: Index, k: int = K) -> DataFrame:
    """query_id, vec_id and score: the k best that the probed lists hold, per query."""
    spark, dim = rows.sparkSession, index.dim
    postings, postings_path = shared.settle(_posted(rows, index), "postings")
    for r in postings.groupBy("list").count().collect():  # at most MOST_LISTS + 1 rows
        index.sizes[r["list"]] = r["count"]
    asked, asked_path = shared.settle(_asked(queries, index, k), "probes")
    n_asked = {r["grp"]: r["count"] for r in asked.groupBy("grp").count().collect()}
    n_held = {g: int(index.sizes[g * GROUP : (g + 1) * GROUP].sum()) for g in n_asked}
    blocks = [(g, math.ceil(n_held[g] / BLOCK), math.ceil(n_asked[g] / QUERIES)) for g in sorted(n_asked) if n_held[g]]
    tiles = F.broadcast(spark.createDataFrame(blocks, "grp int, p_blocks int, q_blocks int"))  # a row a group of lists
    block = lambda n: F.pmod(F.xxhash64("vec_id", F.lit(1)), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    points = postings.withColumn("grp", F.floor(F.col("list") / GROUP).cast("int")).join(tiles, "grp").select("grp", block("p_blocks").alias("pb"), every("q_blocks").alias("qb"), "list", "vec_id", "embedding")
    asks = asked.join(tiles, "grp").select("grp", every("p_blocks").alias("pb"), block("q_blocks").alias("qb"), "lists", "vec_id", "embedding")
    schema = T.StructType([T.StructField("query_id", T.LongType()), T.StructField("vec_id", T.LongType()), T.StructField("score", T.DoubleType())])

    def run(p: pa.Table, q: pa.Table) -> pa.Table:
        found = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        if p.num_rows and q.num_rows:
            pm, qm = (_matrix(t.column("embedding").combine_chunks(), dim) for t in (p, q))
            lists = q.column("lists").combine_chunks()
            ask_of = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
            found = best_in_group(qm, q.column("vec_id").to_numpy(), lists.flatten().to_numpy(), ask_of, pm, p.column("vec_id").to_numpy(), p.column("list").to_numpy(), k)
        return pa.table([pa.array(c) for c in found], names=["query_id", "vec_id", "score"])

    tiled = points.groupBy("grp", "pb", "qb").cogroup(asks.groupBy("grp", "pb", "qb")).applyInArrow(run, schema)
    found, _ = shared.settle(tiled, "found")
    shared.drop(spark, postings_path, asked_path)
    return found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))


def nearest(embeddings: DataFrame, k: int = K, query_step: int = QUERY_STEP) -> DataFrame:
    """query_id, rank, vec_id and score for each query: rows whose vec_id is divisible by ``query_step``."""
    spark = embeddings.sparkSession
    rows = embeddings.select(F.col("vec_id").cast("long"), "embedding")
    widths = rows.where("embedding is not null").groupBy(F.size("embedding").alias("dim")).count().orderBy(F.desc("count"), "dim").limit(1).collect()
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    if not widths or not widths[0]["dim"]:
        return empty
    dim = widths[0]["dim"]
    rows = rows.where(usable(dim))
    if rows.isEmpty():
        return empty
    queries = rows.where(F.col("vec_id") % query_step == 0)
    queries = queries.groupBy("vec_id").agg(F.min_by("embedding", F.xxhash64("embedding")).alias("embedding"))
    found = search(rows, queries, fit(rows, dim, k), k)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

"""Approximate nearest neighbours over balanced posting lists.

Centroids are fitted on a bounded sample (by a hash of the rows, so reruns agree) by k-means whose oversized clusters
are split, and sit in an in-memory graph (each linked to its nearest).  A vector goes to the lists of its nearest
centroids: all whose distance is within a ratio of the least, REPLICAS at most, so vectors near a boundary are found
from both sides.  A query walks the graph, keeps the centroids whose distance is within a ratio of the mean of its NEAR
nearest, and scans their lists exactly, in double precision on the original vectors.  The ratio is set by brute force
for recall of AIM: CALIBRATE vectors of the sample, which the centroids weren't fitted on, are compared with every row
of the table once.

Where the walk's beam is full of centroids within the ratio, all centroids are compared, so no list is cut.  Where the
lists don't surely hold as many other ids as are asked for, its nearest lists that do are found by comparing all
centroids, and the ratio counts from the last of them; all lists are the last resort.  A list with more than LIST rows
is dealt over shards by hash, so that copies of one vector don't meet in one task; a query visits every shard.  Results
say how many lists and posting rows each query met; on vectors without any structure that is a good part of the table,
whatever the index.

Vectors that are null, zero, or hold null or non-finite components take no part, nor do those of another length than
most.  Ties go to the smaller id.  Rows that share an id count once, by the nearest of them (a query leaves out rows
with its own id).  Fewer candidates than asked for: all of them.  An empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from .common import settled, written

#: Bound on the vectors that centroids are fitted on, and on centroids.
SAMPLE, CENTROIDS = 20_000, 4096
#: 2 ** CELL_BITS lists meet in a task, which sends on the nearest of all of them.
CELL_BITS = 5
#: Rows of the table to a centroid, while there are fewer than CENTROIDS; rows of a list's shard.
PER_CENTROID, LIST = 24, 1024
REPLICAS, REPLICA_RATIO = 2, 1.03
#: Recall that the search ratio is set for, on so many vectors of the sample and neighbours of each.
AIM, CALIBRATE, CALIBRATE_K = 0.96, 200, 10
#: Nearest centroids whose mean distance the ratio refers to: the nearest alone may by chance be very near.
NEAR = 8
#: Centroids of the beam whose links a step of a walk follows.
FOLLOWED = 4


@dataclass
class Graph:
    """Centroids, each with links to its nearest others, and where walks begin."""

    centroids: np.ndarray
    links: np.ndarray
    entries: np.ndarray
    ratio: float = 1.2  # lists whose centroid is within this ratio of the mean distance of the NEAR nearest are searched
    lists: int = 16  # most lists that this takes, with a margin
    homes: np.ndarray | None = None  # ids by list, each counted in one list only
    sizes: np.ndarray | None = None  # posting rows by list

    def nearest(self, x: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        """The `width` nearest centroids found for each row, nearest first, and their distances.

        A beam walk from the entry points, for all rows together: in each step the links of the nearest that weren't
        followed yet join the beam, until all of the beam are followed.
        """
        n, width = len(x), min(width, len(self.centroids))
        square = (self.centroids**2).sum(1)
        own = (x**2).sum(1)[:, None]
        d = np.sqrt(np.maximum(own - 2 * x @ self.centroids[self.entries].T + square[self.entries], 0.0))
        first = np.argsort(d, 1, kind="stable")[:, :width]
        beam, dist = self.entries[first], np.take_along_axis(d, first, 1)
        if beam.shape[1] < width:
            pad = width - beam.shape[1]
            beam, dist = np.pad(beam, ((0, 0), (0, pad)), mode="edge"), np.pad(dist, ((0, 0), (0, pad)), constant_values=np.inf)
        followed = np.isinf(dist)
        live, step = np.arange(n), min(max(FOLLOWED, width // 8), width)
        while len(live):
            b, far, done = beam[live], dist[live], followed[live]
            turn = np.argsort(np.where(done, np.inf, far), 1, kind="stable")[:, :step]
            picked = np.take_along_axis(b, turn, 1)
            new = np.where(np.take_along_axis(done, turn, 1)[:, :, None], picked[:, :, None], self.links[picked]).reshape(len(live), -1)
            np.put_along_axis(done, turn, True, 1)
            new_d = np.sqrt(np.maximum(own[live] - 2 * np.matmul(self.centroids[new], x[live][:, :, None])[:, :, 0] + square[new], 0.0))
            ids, all_d = np.concatenate([b, new], 1), np.concatenate([far, new_d], 1)
            mark = np.concatenate([~done, np.ones(new.shape, bool)], 1)
            order = np.argsort(2 * ids + mark, 1, kind="stable")  # of one centroid's entries, one that was followed comes first
            ids, all_d, mark = (np.take_along_axis(a, order, 1) for a in (ids, all_d, mark))
            all_d[:, 1:][ids[:, 1:] == ids[:, :-1]] = np.inf
            best = np.argsort(all_d, 1, kind="stable")[:, :width]
            beam[live], dist[live] = np.take_along_axis(ids, best, 1), np.take_along_axis(all_d, best, 1)
            followed[live] = ~np.take_along_axis(mark, best, 1) | np.isinf(dist[live])
            live = live[~followed[live].all(1)]
        return beam, dist

    def visited(self, x: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Pairs (row, list) to search for k ids and the row's own."""
        found, d = self.nearest(x, max(NEAR, self.lists))
        keep = (d <= self.ratio * reference(d)[:, None]) & np.isfinite(d)
        full = keep.all(1) & (found.shape[1] < len(self.centroids))  # there may be more within the ratio
        short = (self.homes[found] * keep).sum(1) <= k
        keep[full | short] = False
        at, which = np.nonzero(keep)
        rows, lists = [at], [found[at, which]]
        for i in np.flatnonzero(full | short).tolist():
            far = np.sqrt(((self.centroids - x[i]) ** 2).sum(1))
            order = np.argsort(far, kind="stable")
            edge, enough = float(reference(far[order][None, :])[0]), 1
            if short[i]:
                enough = min(int(np.searchsorted(np.cumsum(self.homes[order]), k + 1)) + 1, len(order))
                edge = max(edge, far[order[enough - 1]])
            take = order[: max(enough, int((far <= self.ratio * edge).sum()))]
            rows.append(np.full(len(take), i))
            lists.append(take)
        return np.concatenate(rows), np.concatenate(lists)


def reference(d: np.ndarray) -> np.ndarray:
    """Mean of the NEAR least finite distances of each row (rows ascend)."""
    first = d[:, :NEAR]
    fine = np.isfinite(first)
    return np.maximum(np.where(fine, first, 0.0).sum(1) / np.maximum(fine.sum(1), 1), 1e-12)


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """Rows of a list column without nulls, all of one length."""
    lists = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return np.asarray(lists.flatten(), np.float64).reshape(len(lists), -1)


def balanced_centroids(x: np.ndarray, k: int, seed: int = 0) -> np.ndarray:
    """k-means centres; clusters much larger than the mean are split in two and the smallest are given up for them."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), k, replace=False)].copy()
    for it in range(8):
        owner = np.empty(len(x), np.int64)
        for i in range(0, len(x), 2048):
            owner[i : i + 2048] = ((c**2).sum(1) - 2 * x[i : i + 2048] @ c.T).argmin(1)
        size = np.bincount(owner, minlength=k)
        total = np.stack([np.bincount(owner, weights=x[:, j], minlength=k) for j in range(x.shape[1])], 1)
        c = np.where(size[:, None] > 0, total / np.maximum(size, 1)[:, None], c)
        if it < 6:
            big, small = np.flatnonzero(size > 2 * len(x) / k), np.argsort(size)
            for b, s in zip(big, small, strict=False):
                if size[s] < size[b] / 2:
                    members = np.flatnonzero(owner == b)
                    c[s] = x[rng.choice(members)]
    return c


def graph_of(x: np.ndarray, centroids: int, degree: int = 16) -> Graph:
    x = np.unique(x, axis=0)
    k = max(1, min(centroids, len(x)))
    c = balanced_centroids(x, k)
    near = np.empty((k, min(degree, max(1, k - 1))), np.int64)
    for i in range(0, k, 1024):
        d = (c**2).sum(1) - 2 * c[i : i + 1024] @ c.T
        d[np.arange(len(d)), i + np.arange(len(d))] = np.inf
        near[i : i + 1024] = np.argsort(d, 1)[:, : near.shape[1]] if k > 1 else 0
    return Graph(c, near, np.arange(0, k, max(1, k // 64)))


def lists_of(found: np.ndarray, d: np.ndarray) -> np.ndarray:
    """Which of the nearest centroids' lists each row goes to."""
    keep = d <= REPLICA_RATIO * d[:, :1] + 1e-12
    keep[:, REPLICAS:] = False
    return keep


def calibrated(g: Graph, rows: DataFrame, q: np.ndarray, q_id: np.ndarray, k: int = CALIBRATE_K) -> Graph:
    """Set the search ratio: the least at which lists hold AIM of the k nearest rows of the vectors q, found by brute force over all rows."""
    if len(g.centroids) < 2 or not len(q):
        return g
    held = rows.sparkSession.sparkContext.broadcast((q, q_id))

    def nearest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q, q_id = held.value
        best, where = np.full((len(q), k), np.inf), np.zeros((len(q), k, q.shape[1]))
        for whole in batches:
            for i in range(0, whole.num_rows, 2048):
                b = whole.slice(i, 2048)
                x, ids = matrix(b.column(1)), b.column(0).to_numpy(zero_copy_only=False)
                d = np.sqrt(np.maximum((q**2).sum(1)[:, None] - 2 * q @ x.T + (x**2).sum(1), 0.0))
                d[q_id[:, None] == ids] = np.inf
                both = np.concatenate([best, d], 1)
                first = np.argpartition(both, k - 1, 1)[:, :k]
                new = first >= k
                kept = np.take_along_axis(where, np.where(new, 0, first)[:, :, None], 1)
                where = np.where(new[:, :, None], x[np.where(new, first - k, 0)], kept)
                best = np.take_along_axis(both, first, 1)
        at, which = np.nonzero(np.isfinite(best))
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(best[at, which]), pa.array([v.tobytes() for v in where[at, which]], pa.binary())], ["q", "d", "vector"])

    order = W.partitionBy("q").orderBy("d", "vector")
    found = rows.mapInArrow(settled(nearest), "q int, d double, vector binary").withColumn("n", F.row_number().over(order)).where(F.col("n") <= k).toArrow()  # k rows for each of q
    if not found.num_rows:
        return g
    x = np.frombuffer(b"".join(found["vector"].to_pylist())).reshape(found.num_rows, -1)
    far = np.sqrt(np.maximum((q**2).sum(1)[:, None] - 2 * q @ g.centroids.T + (g.centroids**2).sum(1), 0.0))
    base = reference(np.sort(far, 1)[:, :NEAR])
    home, d = g.nearest(x, max(8, REPLICAS))
    own = found["q"].to_numpy()
    need = np.where(lists_of(home, d), far[own[:, None], home], np.inf).min(1) / base[own]
    ratio = float(np.quantile(need, AIM)) + 1e-9
    return replace(g, ratio=ratio, lists=int((far <= ratio * base[:, None]).sum(1).max() * 1.25) + 16)


def nearest_ids(ids: np.ndarray, d: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k nearest distinct ids and their least distances, ties by id."""
    few = 4 * k
    while True:
        at = np.flatnonzero(d <= np.partition(d, few - 1)[few - 1]) if len(d) > few else np.arange(len(d))
        at = at[np.lexsort((ids[at], d[at]))]
        first = np.sort(np.unique(ids[at], return_index=True)[1])[:k]
        if len(first) == k or len(at) == len(d):
            return ids[at][first], d[at][first]
        few *= 8


def usable(df: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """Rows (id, vector) that take part."""
    v = F.col(vector_col).cast("array<double>")
    fine = F.aggregate(v, F.lit(0.0), lambda a, x: a + F.when(F.isnan(x) | (F.abs(x) == float("inf")), None).otherwise(F.abs(x)))
    rows = df.select(F.col(id_col).alias("id"), F.col(vector_col).alias("vector")).where(F.col("id").isNotNull() & (fine > 0))
    return rows


@dataclass
class Index:
    """postings: rows (list, shard, id, vector); shards: rows (list, shards), one for each list that has rows."""

    graph: Graph
    postings: DataFrame
    shards: DataFrame


def build(df: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", sample: int = SAMPLE) -> Index:
    spark = df.sparkSession
    rows = usable(df, id_col, vector_col)
    n = rows.count()
    pick = F.pmod(F.xxhash64("id", "vector"), F.lit(1 << 30))
    chosen = rows.where(pick < int(min(1.0, 1.2 * sample / max(n, 1)) * (1 << 30))).orderBy(pick, "id").limit(sample).toArrow()
    if not chosen.num_rows:
        x, ids = np.zeros((1, 1)), np.empty(0, np.int64)
    else:
        lists = chosen["vector"].combine_chunks()
        size = np.diff(np.asarray(lists.offsets))
        dim = int(np.bincount(size).argmax())
        x, ids = matrix(lists.filter(pa.array(size == dim))), chosen["id"].to_numpy()[size == dim]
    rows = rows.where(F.size("vector") == x.shape[1])
    aside = min(CALIBRATE, len(ids) // 10)  # vectors that centroids weren't fitted on: fitted ones lie too near to them
    made = graph_of(x[aside:], min(CENTROIDS, max(1, n // PER_CENTROID), max(1, len(x) // 4)))
    graph = spark.sparkContext.broadcast(calibrated(made, rows, x[:aside], ids[:aside]))

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = graph.value
        for whole in batches:
            for i in range(0, whole.num_rows, 2048):
                b = whole.slice(i, 2048)
                found, d = g.nearest(matrix(b.column(1)), max(8, REPLICAS))
                at, which = np.nonzero(lists_of(found, d))
                yield pa.RecordBatch.from_arrays([pa.array(found[at, which].astype(np.int32)), b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at)), pa.array(which == 0)], ["list", "id", "vector", "home"])

    kinds = {f.name: f.dataType.simpleString() for f in rows.schema}
    postings = written(rows.mapInArrow(settled(assign), f"list int, id {kinds['id']}, vector {kinds['vector']}, home boolean"))
    homes, sizes = np.zeros((2, len(graph.value.centroids)), np.int64)
    for h in postings.where("home").groupBy("id").agg(F.min("list").alias("list")).groupBy("list").count().collect():  # CENTROIDS rows at most
        homes[h["list"]] = h["count"]
    shards = postings.groupBy("list").agg(F.count("*").alias("n"))
    for h in shards.collect():  # CENTROIDS rows at most
        sizes[h["list"]] = h["n"]
    shards = spark.createDataFrame([(i, -(-n // LIST)) for i, n in enumerate(sizes.tolist()) if n], "list int, shards int")
    dealt = postings.join(F.broadcast(shards), "list").withColumn("shard", F.pmod(F.xxhash64("id"), F.col("shards")).cast("int"))  # CENTROIDS rows at most
    return Index(replace(graph.value, homes=homes, sizes=sizes), dealt.select("list", "shard", "id", "vector"), shards)


def search(index: Index, queries: DataFrame, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """Rows (query_id, rank, vec_id, score, lists_visited, rows_scanned): the k nearest of each query but rows with its own id."""
    spark = queries.sparkSession
    graph = spark.sparkContext.broadcast(index.graph)
    rows = usable(queries, id_col, vector_col).where(F.size("vector") == index.graph.centroids.shape[1])
    kinds = {f.name: f.dataType.simpleString() for f in rows.schema}

    def visit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = graph.value
        for whole in batches:
            for i in range(0, whole.num_rows, 256):
                b = whole.slice(i, 256)
                at, lists = g.visited(matrix(b.column(1)), k)
                met = np.bincount(at, g.sizes[lists], minlength=b.num_rows)[at].astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(lists.astype(np.int32)), b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at)), pa.array(np.bincount(at, minlength=b.num_rows)[at]), pa.array(met)], ["list", "id", "vector", "lists", "met"])

    visits = rows.mapInArrow(settled(visit), f"list int, id {kinds['id']}, vector {kinds['vector']}, lists long, met long")
    asked = visits.join(F.broadcast(index.shards), "list").select("list", F.explode(F.sequence(F.lit(0), F.col("shards") - 1)).alias("shard"), "id", "vector", "lists", "met")

    def scan(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        """Up to k nearest ids of each query within one shard of a cell's lists, each scanned exactly."""
        kind = left.schema.field("id").type
        out: list[list[np.ndarray]] = [[], [], [], []]
        if left.num_rows and right.num_rows:  # else lists that no query visits, or an empty shard
            q, p = matrix(left["vector"]), matrix(right["vector"])
            q_id, p_id = (t["id"].to_numpy(zero_copy_only=False) for t in (left, right))
            p_list = right["list"].to_numpy()
            order = np.argsort(p_list, kind="stable")
            p, p_id, p_list = p[order], p_id[order], p_list[order]
            visits = left["list"].to_numpy()
            begin, end = np.searchsorted(p_list, visits, "left"), np.searchsorted(p_list, visits, "right")
            own: dict[tuple, list[int]] = {}
            for i in range(len(q)):
                own.setdefault((q_id[i], q[i].tobytes()), []).append(i)
            for rows in own.values():
                i = rows[0]
                at = np.concatenate([np.arange(begin[r], end[r]) for r in rows])
                at = at[p_id[at] != q_id[i]]
                best, d = nearest_ids(p_id[at], np.sqrt(((p[at] - q[i]) ** 2).sum(1)), k)
                for store, x in zip(out, (np.full(len(best), q_id[i]), best, d, np.full(len(best), i)), strict=True):
                    store.append(x)
        a, b, c, i = (np.concatenate([*x, np.empty(0, (np.int64, np.int64, np.float64, np.int64)[j])]) for j, x in enumerate(out))
        return pa.table([pa.array(a, kind), pa.array(b, kind), pa.array(c, pa.float64()), left["lists"].take(pa.array(i)), left["met"].take(pa.array(i))], names=["query_id", "vec_id", "score", "lists", "met"])

    cell = lambda d: d.withColumn("cell", F.shiftright("list", CELL_BITS))
    near = cell(asked).groupBy("cell", "shard").cogroup(cell(index.postings).groupBy("cell", "shard")).applyInArrow(scan, f"query_id {kinds['id']}, vec_id {kinds['id']}, score double, lists long, met long")
    near = near.groupBy("query_id", "vec_id").agg(F.min("score").alias("score"), F.max("lists").alias("lists_visited"), F.max("met").alias("rows_scanned"))  # replicas of one vector
    order = W.partitionBy("query_id").orderBy("score", "vec_id")
    return near.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", "lists_visited", "rows_scanned")

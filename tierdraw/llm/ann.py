"""Approximate nearest neighbours by balanced posting lists.

Index: a bounded sample is split again and again into equal halves along the line between two far means; the means of the parts are the centroids. Every vector joins the
list of its nearest centroid and, if it lies near a boundary, further lists whose centroids are almost as near and not hidden behind one it has already joined.
Vectors find their lists by a best-first walk of a graph of the centroids, held in memory. Search: every list is read whose distance is within a ratio of the nearest
one's, however many these are; the ratio is the least that finds the asked share of the true neighbours of some vectors, which are worked out by brute force over all rows.
Members are compared exactly in double precision. Largest inner products become least distances through one more component. Equal vectors are indexed once, with the few least ids that
any answer can need, so a vector that a third of all rows hold costs as much as any other.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, free_memory

#: Bounds of the index: sampled vectors and their numbers, lists, members of a list aimed at.
SAMPLE, SAMPLE_FLOATS, MAX_LISTS, LIST_SIZE = 20_000, 4_000_000, 4096, 64
#: Lists a vector may join, and how much farther than the nearest one they may be; lists a query reads at least, and the nearest centroids that its walk begins with.
REPLICAS, CLOSURE, LEAST_PROBES, BREADTH = 4, 1.15, 16, 128
#: Share of true neighbours that the ratio is to find, and vectors whose neighbours are worked out to choose it.
RECALL, TRIALS = 0.97, 128
#: Neighbours of a centroid in the graph, entry points; numbers of an index partition, and of the products that a task holds at once.
DEGREE, ENTRIES, PART_FLOATS, BLOCK_FLOATS = 24, 24, 4_000_000, 2_000_000


def usable(rows: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """vec_id, v of vectors that take part: not null, of the most common length, finite, not zero."""
    v = F.col(vec_col)
    rows = rows.filter(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("vec_id"), v.cast("array<double>").alias("v"))
    fine = F.size("v") > 0
    fine &= ~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists("v", lambda x: x != 0)
    rows = rows.filter(F.col("v").isNotNull()).filter(F.coalesce(fine, F.lit(False)))
    sizes = rows.groupBy(F.size("v").alias("d")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.col("n").desc(), "d").limit(1).collect()
    return rows.filter(F.size("v") == (sizes[0]["d"] if sizes else 0))


@dataclass
class Index:
    """Centroids in the space with one more component, their graph, the largest norm, and the number of index partitions."""

    centroids: np.ndarray
    graph: np.ndarray
    entries: np.ndarray
    norm: float
    parts: int
    width: int
    ratio: float = float("inf")

    def lift(self, x: np.ndarray, query: bool) -> np.ndarray:
        """Vectors with one more component: inner products become distances."""
        more = np.zeros(len(x)) if query else np.sqrt(np.maximum(self.norm**2 - (x * x).sum(axis=1), 0))
        return np.concatenate([x, more[:, None]], axis=1).astype(np.float32)

    def walk(self, x: np.ndarray, breadth: int) -> tuple[np.ndarray, np.ndarray]:
        """Nearest centroids that a best-first walk of the graph finds for each row: numbers and squared distances, nearest first."""
        c = self.centroids
        n, k = len(x), len(c)
        breadth = min(breadth, k)
        norms = (c * c).sum(axis=1)
        if k <= breadth * 2:  # as many as the walk would see
            d = norms[None, :] - 2 * x @ c.T
            at = np.argsort(d, axis=1, kind="stable")[:, :breadth]
            return at, np.take_along_axis(d, at, 1) + (x * x).sum(axis=1)[:, None]
        rows = np.arange(n)
        seen = np.zeros((n, k), bool)
        ids = np.broadcast_to(self.entries, (n, len(self.entries))).copy()
        seen[rows[:, None], ids] = True
        dist = norms[ids] - 2 * x @ c[self.entries].T
        opened = np.zeros(ids.shape, bool)
        for _ in range(breadth):
            order = np.argsort(dist, axis=1, kind="stable")[:, :breadth]
            ids, dist, opened = (np.take_along_axis(t, order, 1) for t in (ids, dist, opened))
            pick = np.argmin(opened, axis=1)  # the nearest one not opened
            live = ~opened[rows, pick]
            if not live.any():
                break
            opened[rows, pick] = True
            nxt = self.graph[ids[rows, pick]]
            fresh = ~seen[rows[:, None], nxt] & live[:, None]
            seen[rows[:, None], nxt] |= live[:, None]
            d = np.where(fresh, norms[nxt] - 2 * np.einsum("nd,nmd->nm", x, c[nxt]), np.inf)
            ids, dist, opened = np.concatenate([ids, nxt], 1), np.concatenate([dist, d], 1), np.concatenate([opened, ~fresh], 1)
        order = np.argsort(dist, axis=1, kind="stable")[:, :breadth]
        return np.take_along_axis(ids, order, 1), np.take_along_axis(dist, order, 1) + (x * x).sum(axis=1)[:, None]

    def lists_of(self, x: np.ndarray) -> list[np.ndarray]:
        """Lists each vector joins."""
        ids, dist = self.walk(self.lift(x, False), 4 * REPLICAS)
        dist = np.sqrt(np.maximum(dist, 0))
        out = []
        for r in range(len(x)):
            joined = [ids[r, 0]]
            for j in range(1, ids.shape[1]):
                if len(joined) == REPLICAS or dist[r, j] > CLOSURE * dist[r, 0] + 1e-12:
                    break
                gap = np.sqrt(((self.centroids[joined] - self.centroids[ids[r, j]]) ** 2).sum(axis=1)).min()
                if gap >= 0.5 * dist[r, j]:
                    joined.append(ids[r, j])
            out.append(np.array(joined, np.int64))
        return out

    def probes_of(self, x: np.ndarray) -> list[np.ndarray]:
        """Lists each query reads: all within the ratio of the nearest one's distance. The walk is widened until it has passed the ratio."""
        lifted, breadth = self.lift(x, True), BREADTH
        out: list[np.ndarray] = [np.zeros(0, np.int64)] * len(x)
        todo = np.arange(len(x))
        while len(todo):
            ids, dist = self.walk(lifted[todo], breadth)
            dist = np.sqrt(np.maximum(dist, 0))
            keep = dist <= self.ratio * dist[:, :1] + 1e-12
            keep[:, :LEAST_PROBES] = True
            keep &= np.isfinite(dist)
            whole = ~keep[:, -1] | (breadth >= len(self.centroids))
            for r in np.flatnonzero(whole).tolist():
                out[todo[r]] = ids[r][keep[r]]
            todo, breadth = todo[~whole], breadth * 4
        return out

    def needed(self, query: np.ndarray, near: np.ndarray) -> np.ndarray:
        """Ratio from which on a query reads a list of each of some vectors."""
        d = np.sqrt(np.maximum(((self.centroids - self.lift(query[None, :], True)) ** 2).sum(axis=1), 0))
        return np.array([d[ls].min() for ls in self.lists_of(near)]) / max(float(d.min()), 1e-12)


def halves(x: np.ndarray, parts: int, seed: int = 7) -> np.ndarray:
    """Means of about ``parts`` equal parts of the rows, by repeated halving."""
    rng = np.random.default_rng(seed)
    todo, out = [(np.arange(len(x)), parts)], []
    while todo:
        at, k = todo.pop()
        if k <= 1 or len(at) < 2:
            out.append(x[at].mean(axis=0))
            continue
        y = x[at]
        a = y[rng.integers(len(y))]
        b = y[((y - a) ** 2).sum(axis=1).argmax()]
        for _ in range(4):  # two means of equal halves
            side = np.argsort(y @ (b - a), kind="stable")
            a, b = y[side[: len(y) // 2]].mean(axis=0), y[side[len(y) // 2 :]].mean(axis=0)
        side = np.argsort(y @ (b - a), kind="stable")
        todo += [(at[side[: len(y) // 2]], k // 2), (at[side[len(y) // 2 :]], k - k // 2)]
    return np.stack(out)


def build(sample: np.ndarray, norm: float, n_rows: int, n_queries: int = 0) -> Index:
    """Index from a sample of vectors and the number that it will hold. Queries pass by in batches: their number changes nothing."""
    lists = int(max(1, min(MAX_LISTS, n_rows // LIST_SIZE, len(sample) // 4 or 1)))
    index = Index(np.zeros((0, 0)), np.zeros((0, 0)), np.zeros(0), norm, min(lists, -(-n_rows * REPLICAS * sample.shape[1] // PART_FLOATS)), sample.shape[1])
    c = halves(index.lift(sample, False).astype(np.float64), lists).astype(np.float32)
    d = (c * c).sum(axis=1)[:, None] - 2 * c @ c.T + (c * c).sum(axis=1)[None, :]
    np.fill_diagonal(d, np.inf)
    index.centroids = c
    index.graph = np.argsort(d, axis=1, kind="stable")[:, : min(DEGREE, max(1, len(c) - 1))] if len(c) > 1 else np.zeros((1, 1), np.int64)
    index.entries = np.unique(np.linspace(0, len(c) - 1, min(ENTRIES, len(c))).astype(np.int64))
    return index


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(-1, width)


def _may_be_best(scores: np.ndarray, k: int, slack: float) -> np.ndarray:
    """Places of the k largest scores and of all that come within ``slack`` of them."""
    if len(scores) <= 4 * k:
        return np.arange(len(scores))
    return np.flatnonzero(scores >= np.partition(scores, len(scores) - k)[len(scores) - k] - slack)


@dataclass
class Part:
    """Postings of an index partition, list after list: numbers of the lists, where each begins and ends, vectors, hashes, ids and the least of them."""

    lists: np.ndarray
    bounds: np.ndarray
    x: np.ndarray
    h1: np.ndarray
    h2: np.ndarray
    ids: pa.Array
    least: np.ndarray

    @classmethod
    def of(cls, batches: list[pa.RecordBatch], width: int) -> Part:
        column = lambda c: np.concatenate([b.column(c).to_numpy() for b in batches])
        lists = column("list")
        order = np.argsort(lists, kind="stable")
        numbers, starts = np.unique(lists[order], return_index=True)
        to, x, s = np.argsort(order, kind="stable"), np.empty((len(lists), width)), 0
        for b in batches:  # straight into place: no second copy of all vectors
            x[to[s : s + b.num_rows]] = _matrix(b.column("v"), width)
            s += b.num_rows
        ids = pa.concat_arrays([b.column("ids") for b in batches]).take(pa.array(order))
        least = ids.values.to_numpy()[ids.offsets.to_numpy()[:-1]]
        return cls(numbers, np.append(starts, len(lists)), x, column("h1")[order], column("h2")[order], ids, least)

    def answers(self, asks: pa.RecordBatch, k: int, norm: float) -> Iterator[pa.RecordBatch]:
        """The k + 1 best of the lists that each query reads. So many queries are judged at once that their products stay within BLOCK_FLOATS."""
        size = max(1, BLOCK_FLOATS // len(self.x))
        for s in range(0, asks.num_rows, size):
            block = asks.slice(s, size)
            q = _matrix(block.column("v"), self.x.shape[1])
            asking: dict[int, list[int]] = {}
            for r, ls in enumerate(block.column("lists").to_pylist()):
                at = np.searchsorted(self.lists, ls).clip(max=len(self.lists) - 1)
                for one in at[self.lists[at] == ls].tolist():
                    asking.setdefault(one, []).append(r)
            place: list[list[np.ndarray]] = [[] for _ in q]
            value: list[list[np.ndarray]] = [[] for _ in q]
            for one, who in asking.items():  # a list is multiplied with the queries that read it, and no others
                lo, hi = self.bounds[one : one + 2]
                at = np.arange(lo, hi)
                for r, scores in zip(who, q[who] @ self.x[lo:hi].T, strict=True):
                    place[r].append(at)
                    value[r].append(scores)
            found, by, score = [], [], []
            for r in range(len(q)):
                if not place[r]:
                    continue
                at, scores = np.concatenate(place[r]), np.concatenate(value[r])
                place[r] = value[r] = []
                slack = 1e-12 * norm * float(np.sqrt(q[r] @ q[r]))  # products round as they are grouped: what decides is worked out apart
                at = at[_may_be_best(scores, REPLICAS * (k + 1), slack)]  # a vector of several lists is there as often
                scores = (self.x[at] * q[r]).sum(axis=1)
                order = np.lexsort((self.least[at], -scores))
                _, once = np.unique(np.stack([self.h1[at], self.h2[at]])[:, order], axis=1, return_index=True)
                best = order[np.sort(once)[: k + 1]]
                found.append(at[best])
                by.append(np.full(len(best), r))
                score.append(scores[best])
            if found:
                at, r = np.concatenate(found), pa.array(np.concatenate(by))
                columns = [block.column("h1").take(r), block.column("h2").take(r), pa.array(self.h1[at]), pa.array(self.h2[at]), pa.array(np.concatenate(score)), self.ids.take(pa.array(at))]
                yield pa.RecordBatch.from_arrays(columns, names=["q1", "q2", "v1", "v2", "score", "ids"])


def _runs(batch: pa.RecordBatch) -> Iterator[tuple[int, bool, pa.RecordBatch]]:
    """Stretches of a batch of one partition and of one kind (postings or queries)."""
    part, asks = batch.column("part").to_numpy(), batch.column("asks").to_numpy(zero_copy_only=False)
    edges = np.flatnonzero((part[1:] != part[:-1]) | (asks[1:] != asks[:-1])) + 1
    for lo, hi in zip([0, *edges.tolist()], [*edges.tolist(), len(part)], strict=True):
        yield int(part[lo]), bool(asks[lo]), batch.slice(lo, hi - lo)


def chosen_ratio(index: Index, vectors: DataFrame, trials: np.ndarray, k: int, recall: float) -> float:
    """Least ratio at which the asked share of the k true neighbours of the trial vectors lie in lists that are read.

    The trials are compared with all vectors, in Arrow batches; a batch sends its k + 1 best of each trial.
    """

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            x = _matrix(batch.column("v"), index.width)
            scores = trials @ x.T
            top = np.argsort(-scores, axis=1, kind="stable")[:, : k + 1]
            trial = pa.array(np.repeat(np.arange(len(trials)), top.shape[1]), pa.int32())
            yield pa.RecordBatch.from_arrays([trial, pa.array(np.take_along_axis(scores, top, 1).ravel()), batch.column("v").take(pa.array(top.ravel()))], names=["trial", "score", "v"])

    found = vectors.select("v").mapInArrow(best, "trial int, score double, v array<double>")
    place = F.row_number().over(Window.partitionBy("trial").orderBy(F.col("score").desc(), "v"))
    rows = found.withColumn("place", place).filter(F.col("place") <= k + 1).collect()  # trials times k + 1
    needed = []
    for t, query in enumerate(trials):
        near = np.array([r["v"] for r in rows if r["trial"] == t and r["v"] != query.tolist()])
        if len(near):
            needed.append(index.needed(query, near))
    return float(np.quantile(np.concatenate(needed), recall)) + 1e-9 if needed else float("inf")


def search(rows: DataFrame, is_query, id_col: str = "vec_id", vec_col: str = "embedding", k: int = 20, recall: float = RECALL, exact: bool = False) -> DataFrame:
    """query_id, rank, vec_id, score: for every row for which ``is_query`` (a condition on vec_id) holds, its k best others by inner product.

    Ties go to the smaller id; fewer candidates give fewer rows. Vectors that are null, zero, not finite or of an uncommon length take no part; rows of one id
    and different vectors are separate candidates. ``recall`` chooses the ratio of the lists read; with ``exact`` every list is read. The lists of a partition are one task's work: PART_FLOATS sets its size.
    The queries that read it pass by in batches, so a task's memory does not grow with their number.
    """
    good = usable(rows, id_col, vec_col)
    keyed = cut(good.withColumn("h1", F.xxhash64("v")).withColumn("h2", F.xxhash64(F.lit(3), "v")))
    same = Window.partitionBy("h1", "h2").orderBy("vec_id")
    # no answer holds more than k + 1 copies of one vector: the filter on the rank is done before the shuffle too
    few = keyed.withColumn("r", F.row_number().over(same)).filter(F.col("r") <= k + 1)
    distinct = cut(few.groupBy("h1", "h2").agg(F.first("v").alias("v"), F.sort_array(F.collect_list("vec_id")).alias("ids")))
    asked = keyed.filter(is_query(F.col("vec_id")))
    queries = asked.groupBy("h1", "h2").agg(F.first("v").alias("v"))
    norm2 = F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)
    n, width, biggest = distinct.agg(F.count(F.lit(1)), F.max(F.size("v")), F.max(norm2)).first()
    n_queries = queries.count()
    if not n or not n_queries:
        return rows.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    picked = distinct.orderBy(F.xxhash64("h1"), "h2").limit(int(max(64, min(SAMPLE, SAMPLE_FLOATS // width)))).select("v")
    sample = np.array([r["v"] for r in picked.collect()])
    index = build(sample, float(biggest) ** 0.5, n)
    if not exact:
        index.ratio = chosen_ratio(index, distinct, sample[:: max(1, len(sample) // TRIALS)][:TRIALS], k, recall)
    shared = rows.sparkSession.sparkContext.broadcast(index)  # at most MAX_LISTS centroids

    def posted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for s in range(0, batch.num_rows, 2048):
                b = batch.slice(s, 2048)
                lists = shared.value.lists_of(_matrix(b.column("v"), shared.value.width))
                at = np.repeat(np.arange(b.num_rows), [len(x) for x in lists])
                lst = np.concatenate(lists)
                yield pa.RecordBatch.from_arrays([pa.array(lst % shared.value.parts, pa.int32()), pa.array(lst, pa.int32()), *[b.column(c).take(pa.array(at)) for c in ("h1", "h2", "v", "ids")]], names=["part", "list", "h1", "h2", "v", "ids"])

    def probed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size = max(1, min(512, 16_384 // shared.value.parts))  # a query is sent once to every partition with a list that it reads
        for batch in batches:
            for s in range(0, batch.num_rows, size):
                b = batch.slice(s, size)
                at, part, lists = [], [], []
                for r, ls in enumerate(shared.value.probes_of(_matrix(b.column("v"), shared.value.width))):
                    for p in np.unique(ls % shared.value.parts):
                        at.append(r)
                        part.append(int(p))
                        lists.append(ls[ls % shared.value.parts == p])
                yield pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(lists, pa.list_(pa.int32())), *[b.column(c).take(pa.array(at, pa.int64())) for c in ("h1", "h2", "v")]], names=["part", "lists", "h1", "h2", "v"])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, number, part = [], None, None
        for batch in batches:
            for now, asks, rows in _runs(batch) if batch.num_rows else ():
                if now != number:
                    held, number, part = [], now, None
                if not asks:
                    held.append(rows)
                    continue
                if held:  # postings come before queries
                    part, held = Part.of(held, shared.value.width), []
                    free_memory()
                if part is not None:
                    yield from part.answers(rows, k, shared.value.norm)
        held, part = [], None
        free_memory()

    # a task holds the postings of one partition, and its queries batch by batch
    postings = distinct.mapInArrow(posted, "part int, list int, h1 long, h2 long, v array<double>, ids array<long>").withColumn("asks", F.lit(False))
    asks = queries.mapInArrow(probed, "part int, lists array<int>, h1 long, h2 long, v array<double>").withColumn("asks", F.lit(True))
    both = postings.unionByName(asks, allowMissingColumns=True).repartition("part").sortWithinPartitions("part", "asks")
    hits = both.mapInArrow(scan, "q1 long, q2 long, v1 long, v2 long, score double, ids array<long>")
    once = hits.groupBy("q1", "q2", "v1", "v2").agg(F.max("score").alias("score"), F.first("ids").alias("ids"))
    # of each distinct query the k + 1 nearest ids are enough for all rows that ask it
    near = once.select("q1", "q2", "score", F.explode("ids").alias("vec_id"))
    top = near.withColumn("r", F.row_number().over(Window.partitionBy("q1", "q2").orderBy(F.col("score").desc(), "vec_id"))).filter(F.col("r") <= k + 1)
    found = top.groupBy("q1", "q2").agg(F.sort_array(F.collect_list(F.struct("r", "vec_id", "score"))).alias("near"))
    asked = asked.select(F.col("vec_id").alias("query_id"), F.col("h1").alias("q1"), F.col("h2").alias("q2"))
    others = F.filter("near", lambda x: x["vec_id"] != F.col("query_id"))
    answers = asked.join(found, ["q1", "q2"]).select("query_id", F.posexplode(F.slice(others, 1, k)).alias("p", "x"))
    return answers.select("query_id", (F.col("p") + 1).cast("int").alias("rank"), "x.vec_id", "x.score")

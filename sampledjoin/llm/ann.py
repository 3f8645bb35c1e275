"""Approximate nearest neighbours by inner product: balanced posting lists with replicated boundary vectors, centroids found through an in-memory graph, lists selected by their ratio of distance or by their rank.

Inner products become distances by one more dimension (vectors are completed to the largest norm). Centroids are fitted
on a bounded sample; every vector is posted to its nearest centroid's list and, if it lies on the boundary, also to further ones whose centroids are nearly as near. A query walks the centroids' neighbour graph best first and stops when nothing
nearer is left to open. How many of the lists found it takes is measured on the given rows: about TRIALS of the queries are searched in all rows, and the
ratio of the nearest list's distance, or the number of lists, is set so that the lists hold RECALL of their true neighbours. Rows on which an index can leave out little are searched in more lists, in the end in all.

Lists lie in shards of bounded size: a query goes once to each shard that has lists of its, and brings back one row of its best there.
A list longer than a shard, and the queries of a much asked shard, are dealt in parts. Scores are inner products of the original vectors in double precision.

Defined cases: vectors that are null, zero, or hold null or non-finite components, rows with a null id, and vectors of another length
than most take no part; rows that share a vec_id are separate candidates unless they are equal, and no answer to a query of their id; ties go to the smaller
vec_id; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import broadcasted, materialise, ship, sliced

#: Lists: as many as keep them at LIST_SIZE vectors, within these bounds. Beyond the upper one lists are longer, and are searched in parts.
LEAST_LISTS, MOST_LISTS, LIST_SIZE = 128, 8192, 4096
#: Vectors that the index is fitted on, about: so many in all, or for each list.
SAMPLE, SAMPLE_PER_LIST = 30_000, 16
REPLICAS, REPLICA_RATIO = 4, 1.25
DEGREE, BEAM, OPENED = 24, 64, 4
#: Queries that are searched in all rows, about, the share of their neighbours that the searched lists have to hold, and lists that are searched in any case.
TRIALS, RECALL, LEAST_PROBES = 256, 0.97, 8
#: Postings of a shard, and queries that one task takes with it.
SHARD, PART = 65_536, 8192


def valid(v: Column) -> Column:
    ok = v.isNotNull() & (F.size(v) > 0) & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce(ok & F.exists(v, lambda x: x != 0), F.lit(False))


def distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Squared distances of all rows of x to all of c."""
    return np.maximum((x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)[None, :], 0)


class Reach(NamedTuple):
    """Which lists a query searches: LEAST_PROBES, and those within ``ratio`` of the nearest one's distance, ``probes`` of them at most, of the ``beam`` lists that the walk keeps."""

    ratio: float
    probes: int
    beam: int


class Index:
    """Centroids in the completed space, their neighbour graph, and entry points into it."""

    def __init__(self, sample: np.ndarray, n_lists: int, radius: float, seed: int = 11):
        self.radius = radius
        x = self.complete(sample)
        g = np.random.Generator(np.random.PCG64(seed))
        n_lists = max(1, min(n_lists, len(x)))
        c = x[g.choice(len(x), n_lists, replace=False)]
        for _ in range(12):
            owner = np.concatenate([distances(x[i : i + 2048], c).argmin(1) for i in range(0, len(x), 2048)])
            size = np.bincount(owner, minlength=len(c))
            total = np.zeros_like(c)
            np.add.at(total, owner, x)
            c = np.where(size[:, None] > 0, total / np.maximum(size, 1)[:, None], c)
            # balance: an empty or tiny list's centroid moves into a long one
            short, long = np.flatnonzero(size * 4 < len(x) / len(c)), np.flatnonzero(size > 2 * len(x) / len(c))
            for a, b in zip(short, long[np.argsort(-size[long], kind="stable")], strict=False):
                inside = np.flatnonzero(owner == b)
                c[a] = x[inside[g.integers(len(inside))]]
        self.centroids = c.astype(np.float32)
        self.degree = min(DEGREE, len(c) - 1)
        self.graph = np.zeros((len(c), self.degree), np.int64)
        for i in range(0, len(c), 1024):
            d = distances(c[i : i + 1024], c)
            d[np.arange(len(d)), np.arange(i, i + len(d))] = np.inf
            self.graph[i : i + 1024] = np.argsort(d, 1, kind="stable")[:, : self.degree]
        self.entries = g.choice(len(c), min(len(c), max(16, math.isqrt(len(c)) * 2)), replace=False)

    def complete(self, x: np.ndarray) -> np.ndarray:
        rest = np.sqrt(np.maximum(self.radius**2 - (x.astype(np.float64) ** 2).sum(1), 0))
        return np.column_stack([x, rest]).astype(np.float32)

    def lists_of(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, list): where each vector is posted: its nearest centroid's list, and further ones whose centroids are nearly as near."""
        rows, lists = [], []
        c = self.centroids
        near = min(REPLICAS, len(c))
        for i in range(0, len(x), 1024):
            y = self.complete(x[i : i + 1024])
            d = distances(y, c)
            top = np.argpartition(d, near - 1, 1)[:, :near] if near < len(c) else np.argsort(d, 1)
            dt = np.take_along_axis(d, top, 1)
            order = np.argsort(dt, 1, kind="stable")
            top, dt = np.take_along_axis(top, order, 1), np.take_along_axis(dt, order, 1)
            taken = (dt <= REPLICA_RATIO**2 * dt[:, :1]) & (np.arange(near) < REPLICAS)
            r, j = np.nonzero(taken)
            rows.append(r + i)
            lists.append(top[r, j])
        return np.concatenate(rows), np.concatenate(lists)

    def walk(self, q: np.ndarray, beam: int = BEAM) -> tuple[np.ndarray, np.ndarray]:
        """(lists, squared distances), nearest first, that a best-first walk of the graph keeps for each query: at most ``beam``. A step opens the OPENED nearest of the kept lists that are not open yet, and a query is done when all it keeps are. Where all lists are kept, all are compared."""
        y = np.column_stack([q, np.zeros(len(q))]).astype(np.float32)
        c, n = self.centroids, len(q)
        if beam >= len(c):
            dist = distances(y, c)
            order = np.argsort(dist, 1, kind="stable")
            return order, np.take_along_axis(dist, order, 1)
        kept = np.tile(self.entries, (n, 1))
        dist = distances(y, c[self.entries])
        opened = np.zeros(kept.shape, bool)
        while True:
            order = np.argsort(np.where(opened, np.inf, dist), 1, kind="stable")[:, :OPENED]
            new = ~np.take_along_axis(opened, order, 1)
            if not new.any() or not self.degree:
                break
            np.put_along_axis(opened, order, True, 1)
            pick = np.take_along_axis(kept, order, 1)
            to = self.graph[pick].reshape(n, -1)
            d = ((y[:, None, :] - c[to]) ** 2).sum(2)
            kept, dist = np.concatenate([kept, to], 1), np.concatenate([dist, d], 1)
            opened = np.concatenate([opened, np.zeros(to.shape, bool)], 1)
            # a list that is met again: its open entry, or its first, stays
            at = np.lexsort((~opened, kept), axis=1)
            ids = np.take_along_axis(kept, at, 1)
            again = np.zeros(ids.shape, bool)
            again[:, 1:] = ids[:, 1:] == ids[:, :-1]
            near = np.where(again, np.inf, np.take_along_axis(dist, at, 1))
            best = np.argsort(near, 1, kind="stable")[:, :beam]
            kept, dist = np.take_along_axis(ids, best, 1), np.take_along_axis(near, best, 1)
            opened = np.take_along_axis(np.take_along_axis(opened, at, 1), best, 1) | ~np.isfinite(dist)
        order = np.argsort(dist, 1, kind="stable")
        return np.take_along_axis(kept, order, 1), np.take_along_axis(dist, order, 1)

    def reach_for(self, q: np.ndarray, held: list[list[np.ndarray]]) -> Reach:
        """The cheaper of two rules, by ratio or by number of lists, under which RECALL of the queries' neighbours are found; ``held``: the lists of each neighbour of each query. The beam is the least that loses none of them, up to all lists."""
        n = len(self.centroids)
        found, d = self.walk(q, n)
        rank = np.empty((len(q), n), np.int64)
        np.put_along_axis(rank, found, np.arange(n)[None, :], 1)
        first = [np.array([rank[i, lists].min() for lists in own], np.int64) for i, own in enumerate(held)]
        every = np.concatenate([np.zeros(0, np.int64), *first])
        if not len(every):
            return Reach(math.inf, n, n)
        far = np.sqrt(d / np.maximum(d[:, :1], 1e-30))
        enough = lambda x: np.sort(x)[min(len(x), math.ceil(RECALL * len(x))) - 1]
        probes, ratio = max(LEAST_PROBES, int(enough(every)) + 1), float(enough(np.concatenate([far[i, x] for i, x in enumerate(first)]))) * (1 + 1e-5)
        within = np.maximum((far <= ratio).sum(1), min(LEAST_PROBES, n))
        rule = Reach(ratio, n, int(within.max())) if within.mean() < probes else Reach(math.inf, probes, probes)
        beam = max(BEAM, 2 * rule.beam)
        while 2 * beam < n:
            tried = rule._replace(beam=beam)
            at, lists = self.lists_for(q, tried)
            mine = [set(lists[at == i].tolist()) for i in range(len(q))]
            if sum(not mine[i].isdisjoint(x.tolist()) for i, own in enumerate(held) for x in own) >= RECALL * len(every):
                return tried
            beam *= 2
        return rule._replace(beam=n)

    def lists_for(self, q: np.ndarray, reach: Reach) -> tuple[np.ndarray, np.ndarray]:
        """(row, list): the lists that each query searches."""
        rows, lists = [], []
        for i in range(0, len(q), 256):
            found, d = self.walk(q[i : i + 256], reach.beam)
            r, j = np.nonzero((np.isfinite(d) & ((np.sqrt(d) <= reach.ratio * np.sqrt(np.maximum(d[:, :1], 1e-30))) | (np.arange(d.shape[1]) < LEAST_PROBES)))[:, : reach.probes])
            rows.append(r + i)
            lists.append(found[r, j])
        return np.concatenate(rows), np.concatenate(lists)


def matrix(column: pa.Array, dtype=np.float64) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(dtype)
    return flat.reshape(len(column), -1)


def best_of(q: np.ndarray, q_id: np.ndarray, v: np.ndarray, v_id: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query's row, vector's row, score): each query's k largest inner products among the vectors, its own excepted; all that tie with the last by rounding stay."""
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    for i in range(0, len(q), 512):
        s = q[i : i + 512] @ v.T
        s[q_id[i : i + 512, None] == v_id[None, :]] = -np.inf
        last = np.partition(s, -k, 1)[:, -k] if s.shape[1] > k else np.full(len(s), -np.inf)
        r, j = np.nonzero((s >= (last - 1e-9 * np.maximum(1, np.abs(last)))[:, None]) & (s > -np.inf))
        out.append((i + r, j, (q[i + r] * v[j]).sum(1)))
    return tuple(map(np.concatenate, zip(*out, strict=True)))


def shards(sizes: np.ndarray) -> list[tuple[int, int, int]]:
    """(list, first shard, parts) for each list that has postings: lists one after the other fill a shard; a list longer than one has shards of its own."""
    out, shard, held = [], 0, 0
    for k, n in enumerate(sizes.tolist()):
        if not n:
            continue
        parts = -(-n // SHARD)
        if held and (parts > 1 or held + n > SHARD):
            shard, held = shard + 1, 0
        out.append((k, shard, parts))
        shard, held = (shard + parts, 0) if parts > 1 else (shard, held + n)
    return out


def searched(v: pa.Table, q: pa.Table, k: int) -> pa.Table:
    """(query_id, ids, scores) of the queries (query_id, lists, embedding) that found something among the postings (list, vec_id, embedding)."""
    empty = pa.table({"query_id": pa.array([], pa.int64()), "ids": pa.array([], pa.list_(pa.int64())), "scores": pa.array([], pa.list_(pa.float64()))})
    if not len(v) or not len(q):
        return empty
    order = np.argsort(v.column("list").to_numpy(), kind="stable")
    own, v_id, x = v.column("list").to_numpy()[order], v.column("vec_id").to_numpy()[order], matrix(v.column("embedding").combine_chunks())[order]
    lists = q.column("lists").combine_chunks()
    row, asked = np.repeat(np.arange(len(q)), np.diff(lists.offsets.to_numpy())), lists.flatten().to_numpy()
    q_id, y = q.column("query_id").to_numpy(), matrix(q.column("embedding").combine_chunks())
    found = []
    for one in np.unique(asked):
        lo, hi = np.searchsorted(own, [one, one + 1])
        who = row[asked == one]
        if lo < hi:
            r, j, s = best_of(y[who], q_id[who], x[lo:hi], v_id[lo:hi], k)
            found.append((who[r], v_id[lo + j], s))
    if not found:
        return empty
    r, vec, s = map(np.concatenate, zip(*found, strict=True))
    order = np.lexsort((vec, -s, r))
    r, vec, s = r[order], vec[order], s[order]
    fresh = np.concatenate([[True], (r[1:] != r[:-1]) | (vec[1:] != vec[:-1]) | (s[1:] != s[:-1])])  # a vector is in several lists
    r, vec, s = r[fresh], vec[fresh], s[fresh]
    first = np.flatnonzero(np.concatenate([[True], r[1:] != r[:-1]]))
    place = np.arange(len(r)) - np.repeat(first, np.diff(np.append(first, len(r))))
    r, vec, s = r[place < k], vec[place < k], s[place < k]
    first = np.append(np.flatnonzero(np.concatenate([[True], r[1:] != r[:-1]])), len(r)).astype(np.int32)
    return pa.table({"query_id": q_id[r[first[:-1]]], "ids": pa.ListArray.from_arrays(pa.array(first), pa.array(vec)), "scores": pa.ListArray.from_arrays(pa.array(first), pa.array(s))})


def fitted(rows: DataFrame, n: int, radius: float) -> Index:
    """The index of n vectors (vec_id, embedding), from a sample by a hash of the id."""
    lists = min(MOST_LISTS, max(LEAST_LISTS, -(-n // LIST_SIZE)))
    share = min(1.0, max(SAMPLE, SAMPLE_PER_LIST * lists) / n)
    sample = rows.where(F.pmod(F.xxhash64("vec_id"), F.lit(1 << 20)) < int(share * (1 << 20)) + 1).select("embedding").toArrow()
    if not len(sample):  # a hash may miss a small table
        sample = rows.select("embedding").limit(SAMPLE).toArrow()
    return Index(matrix(sample.column(0).combine_chunks()), min(lists, max(1, n // 32)), radius)


def trials(rows: DataFrame, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids, vectors) of about TRIALS of the n queries among ``rows``, by a hash of the id."""
    asked = rows.where("query").select("vec_id", "embedding")
    some = asked.where(F.pmod(F.xxhash64("vec_id", F.lit(7)), F.lit(1 << 20)) < int(min(1.0, TRIALS / n) * (1 << 20)) + 1).limit(4 * TRIALS).toArrow()
    if not len(some):  # a hash may miss a small table
        some = asked.limit(TRIALS).toArrow()
    return some.column(0).to_numpy(), matrix(some.column(1).combine_chunks())


def neighbours_lists(rows: DataFrame, shared: Broadcast, q_id: np.ndarray, q: np.ndarray, k: int) -> list[list[np.ndarray]]:
    """The lists that hold each of the k nearest rows of each query, from a search in all rows: each task keeps its best."""

    def best(batches):
        score, ids, x = np.full((len(q), 0), -np.inf), np.zeros((len(q), 0), np.int64), np.zeros((len(q), 0, q.shape[1]))
        for b in sliced(batches, 2048):
            v_id, v = b.column(0).to_numpy(), matrix(b.column(1))
            s = q @ v.T
            s[q_id[:, None] == v_id[None, :]] = -np.inf
            top = np.argpartition(-s, k - 1, 1)[:, :k] if s.shape[1] > k else np.tile(np.arange(s.shape[1]), (len(q), 1))
            score, ids, x = np.concatenate([score, np.take_along_axis(s, top, 1)], 1), np.concatenate([ids, v_id[top]], 1), np.concatenate([x, v[top]], 1)
            top = np.argsort(-score, 1, kind="stable")[:, :k]
            score, ids, x = np.take_along_axis(score, top, 1), np.take_along_axis(ids, top, 1), np.take_along_axis(x, top[:, :, None], 1)
        i, j = np.nonzero(score > -np.inf)
        if len(i):
            r, lists = shared.value.lists_of(x[i, j])
            ends = np.cumsum(np.bincount(r, minlength=len(i)))
            lists = pa.ListArray.from_arrays(pa.array(np.append(0, ends).astype(np.int32)), pa.array(lists[np.argsort(r, kind="stable")].astype(np.int32)))
            yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(-score[i, j]), pa.array(ids[i, j]), lists], names=["trial", "less", "vec_id", "lists"])

    found = rows.select("vec_id", "embedding").mapInArrow(best, "trial int, less double, vec_id bigint, lists array<int>")
    nearest_first = F.array_sort(F.array_distinct(F.collect_list(F.struct("less", "vec_id", "lists"))))
    held: list[list[np.ndarray]] = [[] for _ in q]
    for r in found.groupBy("trial").agg(F.slice(nearest_first, 1, k).getField("lists").alias("lists")).collect():  # a row for each trial
        held[r.trial] = [np.array(x) for x in r.lists]
    return held


def nearest(vectors: DataFrame, is_query: Column, k: int = 20) -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest found of each row of ``vectors`` (vec_id, embedding) that ``is_query`` picks, among all other rows."""
    spark = vectors.sparkSession
    ship(spark)
    rows = vectors.select(F.col("vec_id").cast("bigint").alias("vec_id"), "embedding", F.coalesce(is_query, F.lit(False)).alias("query")).where(F.col("vec_id").isNotNull() & valid(F.col("embedding")))
    lengths = rows.groupBy(F.size("embedding").alias("d")).agg(F.count("*").alias("n"), F.max(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x)).alias("m"), F.count_if("query").alias("asked")).orderBy(F.desc("n"), F.desc("d")).limit(1).collect()
    if not lengths:
        return spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    dim, n, top, n_asked = lengths[0]
    if not n_asked:
        return spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    rows = rows.where(F.size("embedding") == dim)
    index = fitted(rows, n, math.sqrt(top) * (1 + 1e-9))
    kind = rows.schema["embedding"].dataType.simpleString()
    with broadcasted(spark, index) as shared:
        tried_id, tried = trials(rows, n_asked)
        reach = index.reach_for(tried, neighbours_lists(rows, shared, tried_id, tried, k))

        def posted(batches):
            for b in sliced(batches, 4096):
                r, lists = shared.value.lists_of(matrix(b.column(1)))
                part = b.take(pa.array(r))
                yield pa.RecordBatch.from_arrays([pa.array(lists.astype(np.int32)), part.column(0), part.column(1)], names=["list", "vec_id", "embedding"])

        postings = materialise(rows.select("vec_id", "embedding").mapInArrow(posted, f"list int, vec_id bigint, embedding {kind}"), "postings")
        sizes = np.zeros(len(index.centroids), np.int64)
        for a, c in postings.groupBy("list").count().collect():  # a row for each list
            sizes[a] = c
        where = shards(sizes)

        def asked(batches):
            place = {a: (first, parts) for a, first, parts in where}
            for b in sliced(batches, 4096):
                r, lists = shared.value.lists_for(matrix(b.column(1)), reach)
                held: dict[tuple[int, int], list[int]] = {}
                for i, one in zip(r.tolist(), lists.tolist(), strict=True):
                    first, parts = place.get(one, (0, 0))
                    for p in range(parts):
                        held.setdefault((i, first + p), []).append(one)
                part = b.take(pa.array([i for i, _ in held], pa.int64()))
                yield pa.RecordBatch.from_arrays([pa.array([s for _, s in held], pa.int32()), part.column(0), pa.array(list(held.values()), pa.list_(pa.int32())), part.column(1)], names=["shard", "query_id", "lists", "embedding"])

        queries = materialise(rows.where("query").select("vec_id", "embedding").mapInArrow(asked, f"shard int, query_id bigint, lists array<int>, embedding {kind}"), "ann-queries")
    # a shard of many queries meets them in parts; both tables have a row for each list or shard, of which there are few
    turns = queries.groupBy("shard").agg(F.ceil(F.count("*") / F.lit(PART)).cast("int").alias("turns"))
    lists = F.broadcast(spark.createDataFrame(where, "list int, first int, parts int"))
    left = postings.join(lists, "list").withColumn("shard", (F.col("first") + F.pmod(F.xxhash64("vec_id"), F.col("parts"))).cast("int"))
    left = left.join(F.broadcast(turns), "shard").withColumn("turn", F.explode(F.sequence(F.lit(0), F.col("turns") - 1))).select("shard", "turn", "list", "vec_id", "embedding")
    right = queries.join(F.broadcast(turns), "shard").withColumn("turn", F.pmod(F.xxhash64("query_id"), F.col("turns")).cast("int")).select("shard", "turn", "query_id", "lists", "embedding")
    met = left.groupBy("shard", "turn").cogroup(right.groupBy("shard", "turn")).applyInArrow(lambda v, q: searched(v, q, k), "query_id bigint, ids array<bigint>, scores array<double>")
    # a query has found at most k in each shard and part that has lists of its
    pairs = F.zip_with("scores", "ids", lambda s, i: F.struct((-s).alias("less"), i.alias("vec_id")))
    best = met.select("query_id", pairs.alias("found")).groupBy("query_id").agg(F.slice(F.array_sort(F.array_distinct(F.flatten(F.collect_list("found")))), 1, k).alias("found"))
    one = best.select("query_id", F.posexplode("found").alias("place", "hit"))
    return one.select("query_id", (F.col("place") + 1).cast("int").alias("rank"), F.col("hit.vec_id").alias("vec_id"), (-F.col("hit.less")).alias("score"))


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), F.col("vec_id") % 20 == 0)

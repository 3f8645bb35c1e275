"""Benchmark decontamination: size-partitioned MinHash containment search, verified by exact shingle containment.

Test items are partitioned by their number of shingles (up to 16, 32, 64, ...). Items of up to 16 shingles, which
min-hashes can miss, are candidates wherever one of their shingles is. For a further class up to U, a document is seen through windows of 2U
shingles, U apart, so that an item lies within one window and the similarity of the two sets is bounded below at any length of the document. A window and an item that agree in one of 64 min-hashes are a
candidate, and the candidate counts if at least 0.8 of the item's distinct shingles are in the document.
A window without any shingle of the items can't agree with one, so its min-hashes are not computed.

Items are broadcast in blocks of bounded size; further blocks are further passes. Documents are never moved.

Defined cases: texts without a word match nothing; an item of fewer than five words is one shingle of all its words
and matches only a document that consists of them; repeated rows and repeated items each give their own rows; null ids are kept.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, shingle_blocks, ship, sliced
from .neardup import without

HASHES, THRESHOLD = 64, 0.8
#: Characters of test items that one pass holds: at 21 words or more for an item with min-hashes, an index of at most about 40 MB.
BLOCK_CHARS = 4_000_000
FILTER_BITS = 22
#: Items of at most so many shingles are candidates at each of their shingles; the least size class.
FEW = 16


class Index:
    """The test items of a block by size class and min-hash."""

    def __init__(self, items: list[tuple[int, str | None]], seed: int = 7):
        g = np.random.Generator(np.random.PCG64(seed))
        self.multiplier = g.integers(1, 1 << 63, HASHES, np.uint64) * np.uint64(2) + np.uint64(1)
        self.ids, self.sets = [], []
        for a, _, h, d in shingle_blocks([t for _, t in items]):
            for k in np.unique(d):
                self.ids.append(items[a + k][0])
                self.sets.append(np.unique(h[d == k]))
        self.every = np.unique(np.concatenate(self.sets)) if self.sets else np.zeros(0, np.uint64)
        self.filter = np.zeros(1 << FILTER_BITS, bool)
        self.filter[(self.every >> np.uint64(64 - FILTER_BITS)).astype(np.intp)] = True
        few: list[tuple[np.ndarray, np.ndarray]] = []
        by: dict[int, list[int]] = {}
        for i, s in enumerate(self.sets):
            if len(s) <= FEW:
                few.append((s, np.full(len(s), i, np.int32)))
                continue
            u = FEW
            while u < len(s):
                u *= 2
            by.setdefault(u, []).append(i)
        self.few = self._table(*map(np.concatenate, zip(*few, strict=True))) if few else None
        # for each size class and min-hash its values in order, and their items
        self.by: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
        for u, items_of in by.items():
            values = np.array([self.minima(self.sets[i]) for i in items_of])
            self.by[u] = [self._table(values[:, k], np.array(items_of, np.int32)) for k in range(HASHES)]

    @staticmethod
    def _table(values: np.ndarray, items: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        order = np.argsort(values, kind="stable")
        return values[order], items[order]

    @staticmethod
    def _found(table: tuple[np.ndarray, np.ndarray], values: np.ndarray) -> np.ndarray:
        """The items at any of the values."""
        keys, items = table
        lo, hi = np.searchsorted(keys, values, "left"), np.searchsorted(keys, values, "right")
        hit = np.flatnonzero(hi > lo)
        return np.concatenate([items[lo[k] : hi[k]] for k in hit]) if len(hit) else items[:0]

    def minima(self, s: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return (s[None, :] * self.multiplier[:, None]).min(1)

    def known(self, h: np.ndarray) -> np.ndarray:
        """Whether each shingle is one of the items'."""
        out = self.filter[(h >> np.uint64(64 - FILTER_BITS)).astype(np.intp)]
        at = np.flatnonzero(out)
        if len(at):
            k = np.minimum(np.searchsorted(self.every, h[at]), len(self.every) - 1)
            out[at] = self.every[k] == h[at]
        return out

    def candidates(self, h: np.ndarray, hits: np.ndarray) -> set[int]:
        """Items that agree with a window of a document; h: its shingles in order, hits: positions of known ones."""
        out: set[int] = set()
        if self.few:
            out.update(self._found(self.few, np.unique(h[hits])).tolist())
        for u, tables in self.by.items():
            last = max(0, -(-(len(h) - 2 * u) // u))
            first = np.clip(hits // u - 1, 0, last)
            windows = np.array([self.minima(h[w * u : w * u + 2 * u]) for w in np.union1d(first, np.minimum(hits // u, last))])
            for k, table in enumerate(tables):
                out.update(self._found(table, np.unique(windows[:, k])).tolist())
        return out

    def matches(self, h: np.ndarray, hits: np.ndarray, threshold: float) -> list[tuple[int, float, int]]:
        own = np.unique(h[hits])
        out = []
        for i in sorted(self.candidates(h, hits)):
            share = len(np.intersect1d(own, self.sets[i], assume_unique=True)) / len(self.sets[i])
            if share >= threshold:
                out.append((self.ids[i], share, len(self.sets[i])))
        return out


def _pass(docs: DataFrame, items: list[tuple[int, str | None]], threshold: float) -> DataFrame:
    index = docs.sparkSession.sparkContext.broadcast(Index(items))  # of BLOCK_CHARS characters at most

    def found(batches):
        x = index.value
        for b in sliced(batches):
            ids, rows = b.column(0).to_pylist(), []
            for a, e, h, d in shingle_blocks(b.column(1).to_pylist()):
                hits = np.flatnonzero(x.known(h))
                if not len(hits):
                    continue
                edges = np.searchsorted(d, np.arange(e - a + 1))
                for k in np.unique(d[hits]):
                    lo, hi = edges[k], edges[k + 1]
                    own = hits[np.searchsorted(hits, lo) : np.searchsorted(hits, hi)] - lo
                    rows += [(ids[a + k], *m) for m in x.matches(h[lo:hi], own, threshold)]
            cols = list(zip(*rows, strict=True)) or [[]] * 4
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.float64()), pa.array(cols[3], pa.int64())], names=["doc_id", "item_id", "containment", "item_shingles"])

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(found, "doc_id bigint, item_id bigint, containment double, item_shingles bigint")


def leaks(docs: DataFrame, items: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, item_id, containment, item_shingles): the test items found in the documents."""
    ship(docs.sparkSession)
    items = items.select(F.col("item_id").cast("bigint").alias("item_id"), "text")
    chars = items.agg(F.sum(F.char_length("text"))).first()[0] or 0
    blocks = -(-chars // BLOCK_CHARS) or 1
    return reduce(DataFrame.unionAll, (_pass(docs, [tuple(r) for r in items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k).collect()], threshold) for k in range(blocks)))


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents in which no test item was found."""
    found = materialise(leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select("doc_id"), "leaks")
    return without(docs, found).select(*docs.columns)

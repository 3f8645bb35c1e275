"""Near-duplicates: improved consistent weighted sampling over TF-IDF shingles, banded, verified by weighted Jaccard similarity.

A document is the weighted set of its five-word shingles; a shingle's weight is its count times ln(1 + N / df). The
sampling takes document frequencies from a table of fixed size (2^25 counters over a hash, kept as their logarithm in a byte each), so that the table that every
task needs has a proven bound; the counters cover all documents. Such a counter is never below the exact frequency, so
it bounds a pair's similarity from both sides; where the bounds leave the verdict open, exact frequencies decide: the pass that fills the counters also writes those of all shingles that several documents have, and those of open pairs are looked up there.

A group's own copies raise the frequencies of what they share, so by TF-IDF they grow apart as the group grows: what only one of them has weighs up to ln(1 + N), what all have
next to nothing. With ``by_counts``, as the query and the pipeline have it, two documents are therefore also alike if the similarity of their counted shingles, all of one weight, reaches the threshold. For it there are
samples, bands and cells of their own; a pair that only those propose is decided by counts alone, which needs no frequencies.

Equal weighted sets are one class at once (one row for each reaches the banding). Rows that share a band meet in cells of bounded size: a band of
more rows is dealt in blocks, each two of which are a cell.
In a cell all samples are compared, but pairs are not handed out: first each row names its likeliest partners, which are verified and joined to
components; then rows that still have a likely partner in another component get a finer sketch, and only
the pairs that are alike by it are verified, all of them. So a group of copies costs a few pairs for each row, and a group of rows that are alike but not alike enough is sifted by samples.

Defined cases: texts without a word (null, empty) and rows with a null doc_id are in no group: class_id is the own doc_id;
rows that share a doc_id share a class; ties go to the smaller doc_id, which names the class; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BASE, DROPPED, broadcasted, counted, discard, materialise, mix, release, shingle_blocks, ship, sliced, small

#: Counters, and those of one piece of the table; steps of a counter's logarithm that a doubling has.
TABLE_BITS, PIECE_BITS, STEPS = 25, 14, 8
SAMPLES, BANDS, FINE = 64, 16, 512
THRESHOLD = 0.8
#: Pairs whose samples agree this many standard deviations less than those of a pair at the threshold are left out.
DEVIATIONS = 4.5
VARIATE_BITS, WEIGHT_STEPS = 14, 112
#: Rows of a band that meet in one cell, or in each block of a larger one.
CELL = 4096
#: Shingles that a task holds before it hands their counts on, and those in a row of their table; bits of the filter of wanted shingles, and those that a shingle sets.
HELD, ROW, WANTED_BITS, WANTED_HASHES = 1 << 20, 1024, 26, 3
#: Ids are broadcast only up to so many rows.
BROADCAST_IDS = 1_000_000


class Frequencies:
    """Documents with a shingle (n), and an upper bound of each shingle's document frequency."""

    def __init__(self, n: int, codes: np.ndarray):
        self.n, self.codes = n, codes
        bound = 2.0 ** ((np.arange(256) - 1) / STEPS)
        self.idf = np.log1p(max(n, 1) / np.maximum(bound, 1)).astype(np.float32)
        held = sum(np.bincount(codes[k : k + (1 << 20)], minlength=256) for k in range(0, len(codes), 1 << 20))[1:].cumsum()
        self.usual = float(bound[1 + np.searchsorted(held, (held[-1] + 1) // 2)]) if held[-1] else 1.0

    def code(self, h: np.ndarray) -> np.ndarray:
        return self.codes.take((h >> np.uint64(64 - TABLE_BITS)).astype(np.int64))

    def weight(self, h: np.ndarray) -> np.ndarray:
        return self.idf.take(self.code(h))


def pieces(rows: DataFrame, size: int, add: Callable[[np.ndarray, bytes], None], finish: Callable[[np.ndarray], bytes]) -> Iterator[tuple[int, np.ndarray]]:
    """Folds ``rows`` (piece, blob) by piece, one at a time in each task, and brings the few pieces to the driver, as bytes."""

    def folded(batches):
        at, held = None, np.zeros(size, np.int64)
        out = lambda: pa.RecordBatch.from_arrays([pa.array([at], pa.int32()), pa.array([finish(held)], pa.binary())], names=["piece", "blob"])
        for b in sliced(batches, 64):
            for piece, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if at is not None and piece != at:
                    yield out()
                    held[:] = 0
                at = piece
                add(held, blob)
        if at is not None:
            yield out()

    found = rows.repartition("piece").sortWithinPartitions("piece").mapInArrow(folded, "piece int, blob binary").toArrow()
    for batch in found.to_batches():
        for k in range(batch.num_rows):
            yield batch.column(0)[k].as_py(), np.frombuffer(batch.column(1)[k].as_buffer(), np.uint8)


def frequency_table(docs: DataFrame) -> DataFrame:
    """(piece, codes, shingles, df), written: for each piece of the counters its codes, and the exact frequencies of its shingles that several documents have, a few in each row; piece -1 has the number of documents with a shingle as its df. From counts over all rows, in one pass over the texts: a task hands on its shingles as gaps of two bytes between their slots and three bytes for the rest, a row for each piece."""
    low, n_pieces = 1 << PIECE_BITS, 1 << (TABLE_BITS - PIECE_BITS)
    shift, rest = np.uint64(64 - TABLE_BITS), np.uint64((1 << (64 - TABLE_BITS - DROPPED)) - 1)

    def counts(batches):
        parts, size = [], 0

        def flush():
            v = np.sort(np.concatenate([np.zeros(0, np.uint64), *parts]))
            slots = v >> shift
            edge = np.searchsorted(slots, np.arange(n_pieces + 1, dtype=np.uint64) * np.uint64(low))
            own = np.flatnonzero(np.diff(edge))
            inside = (slots & np.uint64(low - 1)).astype(np.uint16)
            gaps = [np.diff(inside[edge[k] : edge[k + 1]], prepend=np.uint16(0)).tobytes() for k in own]
            ends = ((v >> np.uint64(DROPPED)) & rest).astype("<u4").view(np.uint8).reshape(-1, 4)[:, :3]
            ends = [ends[edge[k] : edge[k + 1]].tobytes() for k in own]
            return pa.RecordBatch.from_arrays([pa.array(own.astype(np.int32)), pa.array(gaps, pa.binary()), pa.array(ends, pa.binary()), pa.array(np.zeros(len(own), np.int64))], names=["piece", "gaps", "ends", "n"])

        n = 0
        for b in sliced(batches):
            for _, _, h, d in shingle_blocks(b.column(0).to_pylist()):
                v, d, _ = counted(h, d)
                parts.append(v)
                size += len(v)
                n += len(np.unique(d))
            if size >= HELD:
                yield flush()
                parts, size = [], 0
        yield flush()
        yield pa.RecordBatch.from_arrays([pa.array([-1], pa.int32()), pa.array([b""], pa.binary()), pa.array([b""], pa.binary()), pa.array([n], pa.int64())], names=["piece", "gaps", "ends", "n"])

    def row(piece, codes, shingles, df):
        return pa.RecordBatch.from_arrays([pa.array([piece], pa.int32()), pa.array([codes], pa.binary()), lists(shingles.view(np.int64)[None, :]), lists(df.astype(np.int64)[None, :])], names=["piece", "codes", "shingles", "df"])

    def summed(batches):
        at, total, held, size = None, 0, [], 0

        def merged():
            """The shingles held and their counts, equal ones once."""
            v, n = (np.concatenate(x) for x in zip(*held, strict=True))
            order = np.argsort(v)
            v, n = v[order], n[order]
            first = np.flatnonzero(np.concatenate([[True], v[1:] != v[:-1]]))
            return v[first], np.add.reduceat(n, first)

        def out():
            if at == -1:
                yield row(-1, None, np.zeros(0, np.uint64), np.array([total]))
                return
            v, n = merged()
            slots = np.bincount(((v >> shift) & np.uint64(low - 1)).astype(np.int64), weights=n, minlength=low)
            codes = np.where(slots > 0, np.ceil(STEPS * np.log2(np.maximum(slots, 1))) + 1, 0).clip(0, 255).astype(np.uint8).tobytes()
            v, n = v[n > 1], n[n > 1]
            for k in range(0, max(len(v), 1), ROW):
                yield row(at, None if k else codes, v[k : k + ROW], n[k : k + ROW])

        for b in sliced(batches, 64):
            for piece, gaps, ends, n in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if at is not None and piece != at:
                    yield from out()
                    held, size = [], 0
                at, total = piece, total + n
                if piece >= 0:
                    inside = np.cumsum(np.frombuffer(gaps, np.uint16), dtype=np.uint64)
                    end = np.frombuffer(ends, np.uint8).reshape(-1, 3).astype(np.uint64)
                    end = end[:, 0] | (end[:, 1] << np.uint64(8)) | (end[:, 2] << np.uint64(16))
                    v = ((np.uint64(piece) << np.uint64(PIECE_BITS)) + inside) << shift | end << np.uint64(DROPPED)
                    held.append((v, np.ones(len(v), np.int64)))
                    size += len(v)
                    if size >= HELD:
                        held = [merged()]
                        size = 0
        if at is not None:
            yield from out()

    rows = docs.select("text").mapInArrow(counts, "piece int, gaps binary, ends binary, n bigint")
    return materialise(rows.repartition("piece").sortWithinPartitions("piece").mapInArrow(summed, "piece int, codes binary, shingles array<bigint>, df array<bigint>"), "frequencies")


def document_frequencies(docs: DataFrame) -> Frequencies:
    """The counters of documents, or of their ``frequency_table``: its pieces are brought to the driver."""
    table = docs if "codes" in docs.columns else frequency_table(docs)
    low, n = 1 << PIECE_BITS, 0
    codes = np.zeros(1 << TABLE_BITS, np.uint8)
    for batch in table.where("codes is not null or piece < 0").select("piece", "codes", F.get("df", F.lit(0)).alias("n")).toArrow().to_batches():
        for k, piece in enumerate(batch.column(0).to_pylist()):
            if piece < 0:
                n += batch.column(2)[k].as_py()
            else:
                codes[piece * low : (piece + 1) * low] = np.frombuffer(batch.column(1)[k].as_buffer(), np.uint8)
    if table is not docs:
        discard(table)
    return Frequencies(n, codes)


class Sampler:
    """Consistent weighted samples. An element's hash looks its variates up in a table, which holds the rank of what they give at each weight; for sampling, weights are rounded to steps of 1/8 in their logarithm."""

    def __init__(self, n_samples: int = SAMPLES, seed: int = 20231):
        g = np.random.Generator(np.random.PCG64(seed))
        n = 1 << VARIATE_BITS
        r, log_c, beta = g.gamma(2, size=n), np.log(g.gamma(2, size=n)), g.random(n)
        log_w = (np.arange(WEIGHT_STEPS) / 8 - 1)[:, None]
        t = np.floor(log_w / r + beta)
        bits = (log_c - r * (t - beta + 1)).astype(np.float32).view(np.uint32)
        rank = np.where(bits >> np.uint32(31), ~bits, bits | np.uint32(1 << 31)).astype(np.uint64)
        self.rank = (rank << np.uint64(32)).ravel()
        self.multiplier = g.integers(1, 1 << 63, n_samples, np.uint64) * np.uint64(2) + np.uint64(1)

    def samples(self, h: np.ndarray, log_w: np.ndarray, start: np.ndarray) -> np.ndarray:
        """For each text (its elements begin at ``start``) its samples; two texts agree in one with the probability of their similarity."""
        out = np.empty((len(start), len(self.multiplier)), np.uint64)
        row = np.clip(np.rint(log_w * 8) + 8, 0, WEIGHT_STEPS - 1).astype(np.int64) << VARIATE_BITS
        shift, low, high = np.uint64(64 - VARIATE_BITS), np.uint64(16), np.uint64(0xFFFFFFFF)
        x, i, top = np.empty(len(h), np.uint64), np.empty(len(h), np.uint64), np.empty(len(h), np.uint64)
        for k in range(len(self.multiplier)):
            np.multiply(h, self.multiplier[k], out=x)
            np.right_shift(x, shift, out=i)
            at = i.view(np.int64)
            at += row
            self.rank.take(at, out=top, mode="wrap")
            np.right_shift(x, low, out=x)
            np.bitwise_and(x, high, out=x)
            np.bitwise_or(top, x, out=top)
            out[:, k] = np.minimum.reduceat(top, start)
        return out


@cache
def sampler_of(n_samples: int, seed: int) -> Sampler:
    """One for each worker: its table is made once."""
    return Sampler(n_samples, seed)


def banded(samples: np.ndarray) -> np.ndarray:
    """BANDS hashes for each text; the band's number is part of the hash."""
    rows = SAMPLES // BANDS
    x = mix(samples).reshape(len(samples), BANDS, rows)
    out = np.zeros((len(samples), BANDS), np.uint64)
    for j in range(rows):
        out = mix(out * np.uint64(31) + x[:, :, j])
    return mix(out + np.arange(BANDS, dtype=np.uint64)).view(np.int64)


def count_samples(h: np.ndarray, tf: np.ndarray, start: np.ndarray, n_samples: int, seed: int) -> np.ndarray:
    """For each text (its shingles begin at ``start``) its samples by counts alone: the least hashes of its shingles, of which one found k times is k elements."""
    multiplier = np.random.Generator(np.random.PCG64(seed)).integers(1, 1 << 63, n_samples, np.uint64) * np.uint64(2) + np.uint64(1)
    first = np.cumsum(tf) - tf
    at = np.repeat(np.arange(len(h)), tf)
    x = mix(h[at] + (np.arange(len(at)) - first[at]).astype(np.uint64) * np.uint64(BASE))
    out, held = np.empty((len(start), n_samples), np.uint64), np.empty_like(x)
    for k in range(n_samples):
        np.multiply(x, multiplier[k], out=held)
        out[:, k] = np.minimum.reduceat(held, first[start])
    return out


def a_byte_each(samples: np.ndarray) -> np.ndarray:
    """A byte of each sample, as words of eight."""
    return (mix(samples) & np.uint64(0xFF)).astype(np.uint8).view(np.int64)


def lists(values: np.ndarray) -> pa.ListArray:
    n, width = values.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * width), pa.array(np.ascontiguousarray(values).ravel()))


def sketches(docs: DataFrame, frequencies, by_counts: bool = False) -> DataFrame:
    """(doc_id, f1, f2, weight, size, bands, sig) of each row; f1 and f2 name the weighted set, null without a word; weight is at most the exact one, size the number of shingles; sig has a byte of each sample. With ``by_counts`` the bands and samples by counts follow those by weights."""
    kinds = 1 + by_counts

    def made(batches):
        sampler, table = sampler_of(SAMPLES, 20231), frequencies.value
        for b in sliced(batches):
            n = b.num_rows
            f1, f2, weight, size, there = np.zeros(n, np.uint64), np.zeros(n, np.uint64), np.zeros(n), np.zeros(n), np.zeros(n, bool)
            bands, sig = np.zeros((n, kinds * BANDS), np.int64), np.zeros((n, kinds * SAMPLES // 8), np.int64)
            for a, _, h, d in shingle_blocks(b.column(1).to_pylist()):
                with np.errstate(over="ignore"):
                    h, d, tf = counted(h, d)
                    if not len(h):
                        continue
                    start = np.flatnonzero(np.concatenate([[True], d[1:] != d[:-1]]))
                    at = a + d[start]
                    w = table.weight(h) * tf.astype(np.float32)
                    there[at] = True
                    weight[at] = np.add.reduceat(w.astype(np.float64), start)
                    size[at] = np.add.reduceat(tf.astype(np.float64), start)
                    u = tf.astype(np.uint64)
                    f1[at] = np.add.reduceat(mix(h + u), start)
                    f2[at] = np.add.reduceat(mix((h ^ np.uint64(0x5851F42D4C957F2D)) * (u + u + np.uint64(1))), start)
                    drawn = sampler.samples(h, np.log(w), start)
                    bands[at, :BANDS], sig[at, : SAMPLES // 8] = banded(drawn), a_byte_each(drawn)
                    if by_counts:
                        drawn = count_samples(h, tf, start, SAMPLES, 20233)
                        bands[at, BANDS:], sig[at, SAMPLES // 8 :] = ~banded(drawn), a_byte_each(drawn)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(f1.view(np.int64), mask=~there), pa.array(f2.view(np.int64), mask=~there), pa.array(weight), pa.array(size), lists(bands), lists(sig)], names=["doc_id", "f1", "f2", "weight", "size", "bands", "sig"]
            )

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(made, "doc_id bigint, f1 bigint, f2 bigint, weight double, size double, bands array<bigint>, sig array<bigint>")


def fine_sketches(docs: DataFrame, frequencies, by_counts: bool = False) -> DataFrame:
    """(doc_id, sig): FINE samples of each row that has words, a byte each; with ``by_counts`` as many by counts follow."""

    def made(batches):
        sampler, table = sampler_of(FINE, 20232), frequencies.value
        for b in sliced(batches):
            for a, _, h, d in shingle_blocks(b.column(1).to_pylist()):
                with np.errstate(over="ignore"):
                    h, d, tf = counted(h, d)
                    if len(h):
                        start = np.flatnonzero(np.concatenate([[True], d[1:] != d[:-1]]))
                        sig = [a_byte_each(sampler.samples(h, np.log(table.weight(h) * tf.astype(np.float32)), start))]
                        if by_counts:
                            sig.append(a_byte_each(count_samples(h, tf, start, FINE, 20234)))
                        yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(a + d[start])), lists(np.concatenate(sig, 1))], names=["doc_id", "sig"])

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(made, "doc_id bigint, sig array<bigint>")


def least_agreeing(similarity: float, n_samples: int) -> int:
    """So many samples agree in a pair of the similarity, but for DEVIATIONS."""
    return max(0, int(n_samples * similarity - DEVIATIONS * (n_samples * similarity * (1 - similarity)) ** 0.5))


def sampled_threshold(threshold: float, f: Frequencies) -> float:
    """What is left of the threshold under the weights of the counters, where shared shingles are found once but share a usual counter."""
    n = max(f.n, 1)
    return threshold / (threshold + (1 - threshold) * float(np.log1p(n) / np.log1p(n / f.usual)))


class Wanted:
    """A Bloom filter of shingles. Its size is fixed, so with very many shingles it passes more than them, and loses none."""

    def __init__(self, bits: np.ndarray):
        self.bits = bits

    @staticmethod
    def places(shingle: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(byte, bit's mask) of each of a shingle's hashes."""
        with np.errstate(over="ignore"):
            h = mix(shingle.view(np.uint64))
            for k in range(WANTED_HASHES):
                at = (h * np.uint64(2 * k + 1) + np.uint64(k)) >> np.uint64(64 - WANTED_BITS)
                yield (at >> np.uint64(3)).astype(np.int64), np.uint8(1) << (at & np.uint64(7)).astype(np.uint8)
                h = mix(h)

    def passing(self, shingle: np.ndarray) -> np.ndarray:
        ok = np.ones(len(shingle), bool)
        for byte, mask in self.places(shingle):
            ok &= (self.bits.take(byte) & mask) != 0
        return ok

    @staticmethod
    def of(shingles: DataFrame) -> Wanted:
        """The filter of the column ``shingle``: each task marks its own bits, and 64 pieces are ORed."""
        size = 1 << (WANTED_BITS - 3)
        low = size // 64

        def marked(batches):
            bits = np.zeros(size, np.uint8)
            for b in sliced(batches, 1 << 16):
                for byte, mask in Wanted.places(b.column(0).to_numpy()):
                    np.bitwise_or.at(bits, byte, mask)
            own = np.flatnonzero(bits.reshape(64, low).any(1))
            yield pa.RecordBatch.from_arrays([pa.array(own.astype(np.int32)), pa.array([bits[k * low : (k + 1) * low].tobytes() for k in own], pa.binary())], names=["piece", "blob"])

        def add(held, blob):
            held |= np.frombuffer(blob, np.uint8)

        out = np.zeros(size, np.uint8)
        for k, blob in pieces(shingles.mapInArrow(marked, "piece int, blob binary"), low, add, lambda held: held.astype(np.uint8).tobytes()):
            out[k * low : (k + 1) * low] = blob
        return Wanted(out)


def exact_frequencies(table: DataFrame, wanted) -> DataFrame:
    """(shingle, df) of the shingles in the filter ``wanted`` that at least two documents have, from their ``frequency_table``."""

    def found(batches):
        for b in sliced(batches):
            v, n = (c.flatten().to_numpy() for c in b.columns)
            ok = wanted.value.passing(v)
            yield pa.RecordBatch.from_arrays([pa.array(v[ok]), pa.array(n[ok])], names=["shingle", "df"])

    return table.where("piece >= 0").select("shingles", "df").mapInArrow(found, "shingle bigint, df bigint")


def similarity_bounds(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray], f: Frequencies) -> tuple[float, float]:
    """Between these lies the similarity by exact frequencies: weights are at least those of the counters, and at most those of shingles found here only, which a counter of one tells exactly."""
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    least = np.minimum(a[1][i], b[1][j])

    def weights(h: np.ndarray, tf: np.ndarray, df: int) -> tuple[float, float]:
        return float((f.weight(h).astype(np.float64) * tf).sum()), float((np.where(f.code(h) == 1, np.log1p(f.n), np.log1p(f.n / df)) * tf).sum())

    (both, both_most), (own, own_most), (other, other_most) = weights(a[0][i], least, 2), weights(*a, 1), weights(*b, 1)
    shared, shared_most = weights(a[0][i], least, 1)
    rest, rest_most = max(own + other - 2 * shared, 0.0), max(own_most + other_most - 2 * shared_most, 0.0)
    return (both / (both + rest_most) if both else 0.0), (both_most / (both_most + rest) if both_most else 0.0)


def similarity(a: tuple[np.ndarray, ...], b: tuple[np.ndarray, ...], n: int) -> float:
    """Weighted Jaccard similarity of two weighted sets (hashes in order, counts, exact document frequencies)."""
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    w = lambda tf, df: float((np.log1p(n / df) * tf).sum())
    both = w(np.minimum(a[1][i], b[1][j]), a[2][i])
    every = w(*a[1:]) + w(*b[1:]) - both
    return both / every if every else 0.0


def alike_by_counts(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray], threshold: float) -> bool:
    """Whether two sets of counted shingles (hashes in order, counts) are alike, all shingles weighing the same."""
    own, other = int(a[1].sum()), int(b[1].sum())
    if min(own, other) < threshold * max(own, other) * (1 - 1e-12):
        return False
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    both = int(np.minimum(a[1][i], b[1][j]).sum())
    return both > 0 and both >= threshold * (own + other - both) * (1 - 1e-12)


def weighted_sets(texts: list[str | None]) -> list[tuple[np.ndarray, np.ndarray]]:
    out: list = [None] * len(texts)
    for a, b, h, d in shingle_blocks(texts):
        v, d, tf = counted(h, d)
        edges = np.searchsorted(d, np.arange(b - a + 1))
        for k in range(b - a):
            out[a + k] = (v[edges[k] : edges[k + 1]], tf[edges[k] : edges[k + 1]])
    return out


def verified(pairs: DataFrame, docs: DataFrame, table: DataFrame, frequencies, threshold: float, by_counts: bool = False) -> DataFrame:
    """The pairs (a, b) of ``pairs`` (a, b, weighted) whose similarity reaches the threshold: by exact document frequencies if they are ``weighted``, which ``table`` has, or with ``by_counts`` by counts alone."""

    def of(pairs):
        texts = docs.select(F.col("doc_id").cast("bigint").alias("id"), "text")
        ends = pairs.select(F.col("a").alias("id")).union(pairs.select(F.col("b").alias("id"))).distinct()
        return texts.join(F.broadcast(ends) if few else ends, "id", "left_semi")

    def joined(pairs, values, names, *kept):
        side = lambda x: values.select(F.col("id").alias(x), *(F.col(c).alias(f"{c}_{x}") for c in names))
        return pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", *kept, *(f"{c}_{x}" for x in "ab" for c in names))

    def bounded(batches):
        counters = frequencies.value
        for batch in sliced(batches, 128):
            a, b, weighted, x, y = (c.to_pylist() for c in batch.columns)
            names = list(dict.fromkeys([*x, *y]))
            sets = dict(zip(names, weighted_sets(names), strict=True))
            keep, sure = [], []
            for k in range(len(a)):
                if by_counts and alike_by_counts(sets[x[k]], sets[y[k]], threshold):
                    keep.append(k)
                    sure.append(True)
                    continue
                least, most = similarity_bounds(sets[x[k]], sets[y[k]], counters) if weighted[k] else (0.0, 0.0)
                if weighted[k] and most >= threshold - 1e-6:
                    keep.append(k)
                    sure.append(least >= threshold + 1e-6)
            yield pa.RecordBatch.from_arrays([pa.array([a[k] for k in keep], pa.int64()), pa.array([b[k] for k in keep], pa.int64()), pa.array(sure, pa.bool_())], names=["a", "b", "sure"])

    def spread(batches):
        counters = frequencies.value
        for batch in sliced(batches, 128):
            ids, keys, texts = (c.to_pylist() for c in batch.columns)
            sets = weighted_sets(texts)
            size = [len(v) for v, _ in sets]
            v, tf = np.concatenate([v for v, _ in sets]), np.concatenate([tf for _, tf in sets])
            cols = [*(np.repeat(np.array(c, np.int64), size) for c in (ids, keys)), v.view(np.int64), tf.astype(np.int64)]
            yield pa.RecordBatch.from_arrays([*map(pa.array, cols), pa.array(counters.code(v) > 1)], names=["id", "key", "shingle", "tf", "shared"])

    def measured(batches):
        n = frequencies.value.n
        for batch in sliced(batches, 128):
            a, b, *cols = (batch.column(k) for k in range(batch.num_columns))
            value = lambda c, k: np.asarray(c[k].values)

            def weighted(cols, k):
                h, tf, df = (value(c, k) for c in cols)
                order = np.argsort(h)
                return h[order], tf[order], df[order]

            yes = pa.array([similarity(weighted(cols[:3], k), weighted(cols[3:], k), n) >= threshold for k in range(batch.num_rows)], pa.bool_())
            yield pa.RecordBatch.from_arrays([a.filter(yes), b.filter(yes)], names=["a", "b"])

    few = small(pairs, BROADCAST_IDS // 2)
    near = materialise(joined(pairs, of(pairs), ["text"], "weighted").mapInArrow(bounded, "a bigint, b bigint, sure boolean"), "bounded")
    links, unsure = near.where("sure").select("a", "b"), near.where("not sure").select("a", "b").distinct()
    if unsure.isEmpty():
        return links
    # rows that share a doc_id are told apart by key
    spread_out = materialise(of(unsure).select("id", F.xxhash64("text").alias("key"), "text").mapInArrow(spread, "id bigint, key bigint, shingle bigint, tf bigint, shared boolean"), "sets")
    with broadcasted(docs.sparkSession, Wanted.of(spread_out.where("shared").select("shingle"))) as wanted:
        known = materialise(exact_frequencies(table, wanted), "known")
    held = F.struct("shingle", "tf", F.coalesce("df", F.lit(1)).cast("bigint").alias("df"))
    sets = materialise(spread_out.join(known, "shingle", "left").groupBy("id", "key").agg(F.collect_list(held).alias("s")).select("id", *(F.col(f"s.{c}").alias(c) for c in ("shingle", "tf", "df"))), "weighted-sets")
    out = materialise(links.union(joined(unsure, sets, ["shingle", "tf", "df"]).mapInArrow(measured, "a bigint, b bigint")), "links")
    discard(spread_out, known, sets, near)
    return out


def star_step(edges: DataFrame) -> DataFrame:
    """One large and one small star over edges (u, v), v < u: each id comes nearer to the smallest that it is linked with, and none loses its links. Both halves are written, as each is read several times."""
    sym = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = sym.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    large = materialise(sym.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct(), "edges")
    low = large.groupBy("u").agg(F.min("v").alias("m"))
    star = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
    return materialise(star.distinct(), "edges")


def ordered(links: DataFrame) -> DataFrame:
    return links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct()


def lowest(edges: DataFrame) -> DataFrame:
    """(doc_id, component) of each id in ``edges``: the smallest of its own edges, or itself."""
    low = edges.groupBy("u").agg(F.min("v").alias("component"))
    return low.select(F.col("u").alias("doc_id"), "component").union(edges.join(low.select(F.col("u").alias("v")), "v", "left_anti").select(F.col("v").alias("doc_id"), F.col("v").alias("component")).distinct())


def settled(edges: DataFrame) -> DataFrame:
    """(doc_id, component): the smallest id that edges (u, v), v < u, reach; steps go on until all edges form stars."""
    while True:
        ends = edges.select(F.col("u").alias("x"), F.lit(1).alias("up")).union(edges.select(F.col("v").alias("x"), F.lit(0).alias("up")))
        if ends.groupBy("x").agg(F.sum("up").alias("ups"), F.min("up").alias("least")).where("ups > 1 or (ups = 1 and least = 0)").isEmpty():
            return lowest(edges)
        edges = star_step(edges)


def components(links: DataFrame) -> DataFrame:
    """(doc_id, component): the smallest id that links (a, b) reach; one row for each id in links that are not loops."""
    return settled(materialise(ordered(links), "components"))


def cells(firsts: DataFrame) -> DataFrame:
    """(cell, doc_id, counts): the rows of ``firsts`` (doc_id, bands) that share a band, in cells: a band of up to CELL rows is one; a larger one is dealt in blocks, and each two of them are one. counts is 1 for a band by counts, 0 for one by weights."""
    rows = firsts.select("doc_id", F.posexplode("bands").alias("at", "band")).select("doc_id", "band", (F.col("at") >= BANDS).cast("int").alias("counts"))
    many = rows.groupBy("band").agg(F.count("*").alias("n")).where("n > 1")
    blocks = F.ceil(F.col("n") / F.lit(CELL)).cast("int")
    placed = rows.join(many, "band").select("band", "doc_id", "counts", blocks.alias("blocks"), F.pmod(F.xxhash64("doc_id"), blocks).cast("int").alias("own"))
    # a block meets each other one; a band of one block is a cell by itself
    met = placed.withColumn("other", F.explode(F.when(F.col("blocks") == 1, F.array(F.lit(0))).otherwise(F.filter(F.sequence(F.lit(0), F.col("blocks") - 1), lambda k: k != F.col("own")))))
    return met.select(F.when(F.col("blocks") == 1, F.col("band")).otherwise(F.xxhash64("band", F.least("own", "other"), F.greatest("own", "other"))).alias("cell"), "doc_id", "counts")


def arranged(members: DataFrame) -> DataFrame:
    return members.repartition("cell").sortWithinPartitions("cell")


class Group:
    """The rows of a cell, as arrays."""

    def __init__(self, columns: list[np.ndarray], a: int, b: int):
        self.id, self.component, counts, least, self.weight, self.reach, self.sig = (c[a:b] for c in columns[1:])
        self.weighted, self.least = not counts[0], int(least[0])

    def pairs(self, i: np.ndarray, j: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.maximum(i, j)), pa.array(np.minimum(i, j)), pa.array(np.full(len(i), self.weighted))], names=["a", "b", "weighted"])

    def likely(self, threshold: float) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(first row, agreeing samples of some rows with all, whether they are likely pairs of two components), a few rows at a time."""
        if (self.component == self.component[0]).all():
            return
        step = max(1, (1 << 22) // (len(self.id) * self.sig.shape[1]))
        for k in range(0, len(self.id), step):
            rows = slice(k, k + step)
            agree = (self.sig[rows, None, :] == self.sig[None, :, :]).sum(2, dtype=np.int32)
            ok = (agree >= self.least) & (self.component[rows, None] != self.component[None, :])
            ok &= (self.reach[rows, None] >= threshold * 0.999 * self.weight[None, :]) & (self.reach[None, :] >= threshold * 0.999 * self.weight[rows, None])
            yield k, agree, ok


def groups(batches: Iterable[pa.RecordBatch]) -> Iterator[Group]:
    """The cells of batches (cell, doc_id, component, counts, least, weight, reach, sig) that come ordered by cell. A pair is left out unless ``least`` samples agree; the exact weight of a row lies between weight and reach."""

    def columns(b):
        *plain, sig = b.columns
        return [*(c.to_numpy() for c in plain), sig.flatten().to_numpy().view(np.uint8).reshape(b.num_rows, -1)]

    held: list[np.ndarray] | None = None
    for b in sliced(batches, 8192):
        held = columns(b) if held is None else [np.concatenate(c) for c in zip(held, columns(b), strict=True)]
        edge = np.flatnonzero(np.concatenate([[True], held[0][1:] != held[0][:-1]]))
        for a, e in zip(edge[:-1], edge[1:], strict=True):
            if e - a > 1:
                yield Group(held, a, e)
        held = [c[edge[-1] :] for c in held]
    if held is not None and len(held[0]) > 1:
        yield Group(held, 0, len(held[0]))


def distinct_pairs(pairs: DataFrame) -> DataFrame:
    return pairs.where("a <> b").groupBy("a", "b").agg(F.max("weighted").alias("weighted"))


def partners(members: DataFrame, threshold: float) -> DataFrame:
    """(a, b, weighted), a > b: for each row of a cell its likeliest partner, and its likeliest among the rows before it, in another component; weighted unless only cells by counts have the pair."""

    def made(batches):
        for g in groups(batches):
            for k, agree, ok in g.likely(threshold):
                score = np.where(ok, agree, -1)
                rows = np.arange(k, k + len(score))
                before = np.where(np.arange(len(g.id))[None, :] < rows[:, None], score, -1)
                found = [(rows[hit], best[hit]) for s in (score, before) for best in (s.argmax(1),) for hit in (s.max(1) >= 0,)]
                yield g.pairs(*(g.id[np.concatenate(x)] for x in zip(*found, strict=True)))

    return distinct_pairs(arranged(members).mapInArrow(made, "a bigint, b bigint, weighted boolean"))


def undecided(members: DataFrame, threshold: float) -> DataFrame:
    """(doc_id): the rows that have a likely partner in another component."""

    def made(batches):
        for g in groups(batches):
            any_ = np.zeros(len(g.id), bool)
            for k, _, ok in g.likely(threshold):
                any_[k : k + len(ok)] = ok.any(1)
            yield pa.RecordBatch.from_arrays([pa.array(g.id[any_])], names=["doc_id"])

    return arranged(members).mapInArrow(made, "doc_id bigint").distinct()


def all_pairs_alike(members: DataFrame, threshold: float) -> DataFrame:
    """(a, b, weighted), a > b: all likely pairs of two components, by fine samples."""

    def made(batches):
        for g in groups(batches):
            for k, _, ok in g.likely(threshold):
                i, j = np.nonzero(ok)
                i, j = g.id[i + k], g.id[j]
                yield g.pairs(i[i > j], j[i > j])

    return distinct_pairs(arranged(members).mapInArrow(made, "a bigint, b bigint, weighted boolean"))


def near_classes(docs: DataFrame, threshold: float = THRESHOLD, by_counts: bool = False) -> DataFrame:
    """(doc_id, class_id, links): for each row the smallest doc_id of its class, and how many verified links its representative has. With ``by_counts`` documents whose counted shingles are alike are linked too, whatever their frequencies."""
    ship(docs.sparkSession)
    table = frequency_table(docs)
    f = document_frequencies(table)
    sampled, most_idf = sampled_threshold(threshold, f), float(np.log1p(max(f.n, 1)))
    with broadcasted(docs.sparkSession, f) as frequencies:
        sketch = materialise(sketches(docs, frequencies, by_counts), "sketches")
        named = sketch.where("f1 is not null and doc_id is not null")
        sets = named.groupBy("f1", "f2").agg(F.min("doc_id").alias("rep"))
        firsts = materialise(named.join(sets.select("f1", "f2", F.col("rep").alias("doc_id")), ["f1", "f2", "doc_id"]).dropDuplicates(["f1", "f2"]).select("doc_id", "weight", "size", "bands", "sig"), "firsts")
        links, edges = _links(docs, firsts, shared_ids(named, sets), table, frequencies, sampled, most_idf, threshold, by_counts)
    discard(table)
    release(docs.sparkSession)
    members = sketch.select("doc_id", "f1", "f2").join(sets, ["f1", "f2"], "left")
    if edges is None:
        return members.select("doc_id", F.coalesce("rep", "doc_id").alias("class_id"), F.lit(0).cast("bigint").alias("links"))
    links = links if links is not None else docs.sparkSession.createDataFrame([], "a bigint, b bigint")
    links = links.distinct()
    degree = links.select(F.col("a").alias("rep")).union(links.select(F.col("b").alias("rep"))).groupBy("rep").agg(F.count("*").alias("links"))
    return (
        members.join(settled(edges).select(F.col("doc_id").alias("rep"), "component"), "rep", "left").join(degree, "rep", "left")
        .select("doc_id", F.coalesce("component", "rep", "doc_id").alias("class_id"), F.coalesce("links", F.lit(0)).cast("bigint").alias("links"))
    )


def shared_ids(named: DataFrame, sets: DataFrame) -> DataFrame | None:
    """Edges (u, v) between the sets that rows of one doc_id have; None without any."""
    one = F.struct("f1", "f2")
    several = named.groupBy("doc_id").agg(F.min(one).alias("lo"), F.max(one).alias("hi")).where("lo <> hi").select("doc_id")
    if several.isEmpty():
        return None
    reps = named.join(several, "doc_id").join(sets, ["f1", "f2"]).select("doc_id", "rep").distinct()
    return materialise(ordered(reps.join(reps.groupBy("doc_id").agg(F.min("rep").alias("b")), "doc_id").select(F.col("rep").alias("a"), "b")), "edges")


def _links(docs: DataFrame, firsts: DataFrame, edges: DataFrame | None, table: DataFrame, frequencies, sampled: float, most_idf: float, threshold: float, by_counts: bool) -> tuple[DataFrame | None, DataFrame | None]:
    """(links, edges): the verified pairs (a, b), and edges (u, v) that join what they and the given ones join; None without any."""
    dealt = materialise(cells(firsts), "cells")
    tested = links = None

    def members(sig: DataFrame, samples: int, some: DataFrame | None = None) -> DataFrame:
        rows = dealt if some is None else dealt.join(some, "doc_id", "left_semi")
        rows = rows.join(sig, "doc_id")
        rows = rows.withColumn("component", F.col("doc_id")) if edges is None else rows.join(lowest(edges), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
        of_kind = lambda counts, weights: F.when(F.col("counts") == 1, counts).otherwise(weights)
        return rows.select(
            "cell", "doc_id", "component", "counts", of_kind(F.lit(least_agreeing(threshold, samples)), F.lit(least_agreeing(sampled, samples))).alias("least"),
            of_kind(F.col("size"), F.col("weight")).alias("weight"), of_kind(F.col("size"), F.col("size") * most_idf).alias("reach"), F.slice("sig", of_kind(F.lit(samples // 8 + 1), F.lit(1)), F.lit(samples // 8)).alias("sig"),
        )

    def verify(pairs: DataFrame) -> None:
        nonlocal tested, links, edges
        if tested is not None:
            t = tested.select(F.col("a").alias("ta"), F.col("b").alias("tb"), F.col("weighted").alias("before"))
            pairs = pairs.join(t, F.expr("a = ta and b = tb and (before or not weighted)"), "left_anti")
        pairs = materialise(pairs, "pairs")
        tested = pairs if tested is None else tested.union(pairs)
        found = verified(pairs, docs, table, frequencies, threshold, by_counts)
        if not found.isEmpty():
            links = found if links is None else links.union(found)
            edges = star_step(materialise(ordered(found) if edges is None else edges.union(ordered(found)).distinct(), "edges"))
        release(docs.sparkSession)

    coarse = firsts.select("doc_id", "weight", "size", "sig")
    # by counts first: that needs no frequencies, and leaves few pairs of two components whose weights have to be told exactly
    verify(partners(members(coarse, SAMPLES).where(F.col("counts") == int(by_counts)), threshold))
    rest = materialise(undecided(members(coarse, SAMPLES), threshold), "undecided")
    if not rest.isEmpty():
        some = docs.join(F.broadcast(rest) if small(rest, BROADCAST_IDS) else rest, "doc_id", "left_semi")
        fine = materialise(fine_sketches(some, frequencies, by_counts), "fine")
        sig = firsts.select("doc_id", "weight", "size").join(fine, "doc_id")
        if by_counts:  # likeliest partners once more, by weights too, before all pairs that are left
            verify(partners(members(sig, FINE, rest), threshold))
        verify(all_pairs_alike(members(sig, FINE, rest), threshold))
        discard(fine)
    discard(dealt, rest)
    return links, edges


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_classes(spark.read.parquet(f"{sf_dir}/documents.parquet"), by_counts=True)


def without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """``docs`` without the rows of the ids in ``gone``; the ids are broadcast only if they are few."""
    gone = gone.select(F.col("doc_id").alias("gone_id")).where("gone_id is not null").distinct()
    if small(gone, BROADCAST_IDS):
        gone = F.broadcast(gone)
    return docs.join(gone, docs["doc_id"] == gone["gone_id"], "left_anti")


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class: that of the smallest doc_id."""
    classes = materialise(near_classes(docs, by_counts=True), "classes")
    return without(docs, classes.where("doc_id <> class_id")).select(*docs.columns)

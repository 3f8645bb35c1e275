"""Shared by the training-data operators: shipping the code, tables in the shared folder, and vectorised shingling."""

from __future__ import annotations

import ctypes
import gc
import os
import re
import tempfile
import uuid
import zipfile
from collections.abc import Iterable, Iterator
from contextlib import contextmanager, suppress
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()
#: Rows of an Arrow batch.
BATCH = 2048


def ship(spark: SparkSession) -> None:
    """Sends this package to the Python workers once per application, so that they need no shared PYTHONPATH; and has them get rows in batches of at most BATCH, so that a batch of texts stays small on both sides."""
    sc = spark.sparkContext
    if not 0 < int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000")) <= BATCH:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH)
    if sc.applicationId in _SHIPPED:
        return
    root = Path(__file__).resolve().parent.parent
    target = os.path.join(tempfile.mkdtemp(prefix="ship"), f"{root.name}.zip")
    with zipfile.ZipFile(target, "w") as out:
        for p in sorted(root.rglob("*.py")):
            out.write(p, str(p.relative_to(root.parent)))
    sc.addPyFile(target)
    _SHIPPED.add(sc.applicationId)


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir. Where that is unset, a folder of this machine if the session is local, as in tests; a cluster has to name one."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base and spark.sparkContext.master.partition("[")[0] == "local":
        base = f"file://{tempfile.gettempdir()}/checkpoints"
    if not base:
        raise ValueError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
    return base.rstrip("/")


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Writes ``df`` as a table in the shared folder and reads it again: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    trim_driver(spark)
    return spark.read.schema(df.schema).parquet(path)


def discard(*tables: DataFrame) -> None:
    """Deletes tables that ``materialise`` wrote and that nothing will read any more."""
    for t in tables:
        sc = t.sparkSession.sparkContext
        for name in {f.rpartition("/")[0] for f in t.inputFiles()}:
            path = sc._jvm.org.apache.hadoop.fs.Path(name)
            path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def broadcasted(spark: SparkSession, value: object) -> Iterator[Broadcast]:
    """A broadcast for the jobs that run inside; executors then drop their copies. A plan that is run later fetches it again."""
    shared = spark.sparkContext.broadcast(value)
    try:
        yield shared
    finally:
        shared.unpersist()
        trim()


def sliced(batches: Iterable[pa.RecordBatch], most: int = 512) -> Iterator[pa.RecordBatch]:
    """The batches in slices of at most ``most`` rows, so that what Python makes of one stays small; freed memory goes back at the end."""
    for b in batches:
        for lo in range(0, b.num_rows, most):
            yield b.slice(lo, most)
    trim()


def trim() -> None:
    """Gives freed memory of this process back."""
    pa.default_memory_pool().release_unused()
    with suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def trim_driver(spark: SparkSession) -> bool:
    """As ``trim``, for the driver's Java process: its hundreds of threads (of broadcasts, of blocks that are removed) leave freed memory in the C library's many arenas, which keep it. Whether that JVM can; where it can't, nothing is done."""
    try:
        java, gateway = spark.sparkContext._jvm.java.lang, spark.sparkContext._gateway

        def array(kind, *values):
            out = gateway.new_array(kind, len(values))
            for k, v in enumerate(values):
                out[k] = v
            return out

        # by the interface's method, as the class behind it is not open to calls
        kinds = [java.Class.forName(n) for n in ("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")]
        invoke = java.Class.forName("javax.management.MBeanServer").getMethod("invoke", array(java.Class, *kinds))
        commands = spark.sparkContext._jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        invoke.invoke(java.management.ManagementFactory.getPlatformMBeanServer(), array(java.Object, commands, "systemTrimNativeHeap", array(java.Object), array(java.String)))
    except Exception:  # noqa: BLE001  another JVM, or none of this process
        return False
    return True


def release(spark: SparkSession) -> None:
    """After a step of many jobs: what nothing refers to any more is collected on the driver, upon which Spark drops its broadcasts and shuffle files on the executors."""
    gc.collect()
    trim()
    spark.sparkContext._jvm.System.gc()
    trim_driver(spark)


#: Odd multipliers of the hashes; fixed values.
BASE = 0x9E3779B97F4A7C15
MULTIPLIERS = (0xBF58476D1CE4E5B9, 0x94D049BB133111EB, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB)
MASK = (1 << 64) - 1
PIECE = 1 << 16
_CACHE: dict = {}


def _tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Whether a code point belongs to a word; powers of BASE and of its inverse."""
    if not _CACHE:
        word = np.fromiter((chr(i).isalnum() for i in range(0x30000)), bool, 0x30000)
        n = 2 * PIECE + 2
        with np.errstate(over="ignore"):
            _CACHE["t"] = (
                np.concatenate([word, np.zeros(0x110000 - 0x30000, bool)]),
                np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(n, BASE, np.uint64)])),
                np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(n, pow(BASE, -1, 1 << 64), np.uint64)])),
            )
    return _CACHE["t"]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift, multiply)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(MULTIPLIERS[0])
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(MULTIPLIERS[1])
    return x ^ (x >> np.uint64(31))


class Words:
    """The words of some texts: maximal runs of letters and digits, in lower case. For each word its text's index, start and end in ``text`` and a 64-bit hash."""

    __slots__ = ("codes", "doc", "end", "hash", "inverse", "prefix", "start")

    def __init__(self, text: str, bounds: np.ndarray):
        """bounds: where each text of the joined ``text`` begins; between two texts there is a line break."""
        table, power, inverse = _tables()
        codes = np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)
        inside = np.zeros(len(codes) + 2, bool)
        inside[1:-1] = table.take(codes)
        edge = np.flatnonzero(inside[1:] != inside[:-1])
        self.start, self.end = edge[::2], edge[1::2]
        self.prefix = np.concatenate([[np.uint64(0)], np.cumsum((codes.astype(np.uint64) + np.uint64(1)) * power[: len(codes)])])
        self.inverse, self.codes = inverse, codes
        self.hash = self.part(self.start, self.end)
        self.doc = np.repeat(np.arange(len(bounds)), np.diff(np.append(np.searchsorted(self.start, bounds), len(self.start))))

    def part(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hashes of the text from start to end."""
        return mix((self.prefix[end] - self.prefix[start]) * self.inverse[start])


def lowered(text: str | None) -> str:
    return (text or "").lower()


_GAP = re.compile(r"\s")


def cut(text: str, most: int = PIECE) -> list[str]:
    """Pieces of at most about ``most`` characters, cut where there is white space; a longer word is cut after ``2 * most``."""
    out, at = [], 0
    while len(text) - at > most:
        m = _GAP.search(text, at + most, at + 2 * most)
        stop = m.start() if m else min(len(text), at + 2 * most)
        out.append(text[at:stop])
        at = stop
    out.append(text[at:])
    return out


def word_blocks(texts: Iterable[str | None]) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Word hashes of the texts in blocks of bounded size: (first, last + 1, hashes, text index less ``first`` of each word). A very long text makes a block by itself."""
    first, held, size = 0, [], 0

    def flush(a, b):
        bounds = np.cumsum([0, *(len(x) + 1 for x in held)])[:-1]
        w = Words("\n".join(held), bounds)
        return a, b, w.hash, w.doc

    with np.errstate(over="ignore"):
        k = -1
        for k, raw in enumerate(texts):
            t = lowered(raw)
            if len(t) > PIECE:
                if held:
                    yield flush(first, k)
                parts = [Words(p, np.zeros(1, np.int64)).hash for p in cut(t)]
                h = np.concatenate(parts)
                yield k, k + 1, h, np.zeros(len(h), np.int64)
                first, held, size = k + 1, [], 0
                continue
            if held and size + len(t) > PIECE:
                yield flush(first, k)
                first, held, size = k, [], 0
            held.append(t)
            size += len(t) + 1
        if held:
            yield flush(first, k + 1)


def shingles(hashes: np.ndarray, doc: np.ndarray, n_docs: int, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of ``width`` words within a text, in order, and their text's index. A text of fewer words, but at least one, has one shingle of all its words."""
    with np.errstate(over="ignore"):
        n = len(hashes)
        count = np.bincount(doc, minlength=n_docs)
        if n >= width:
            m = n - width + 1
            s = np.zeros(m, np.uint64)
            for j in range(width):
                s += hashes[j : j + m] * np.uint64(MULTIPLIERS[j % 5] + 2 * (j // 5))
            whole = doc[:m] == doc[width - 1 :]
            s, d = mix(s)[whole], doc[:m][whole]
        else:
            s, d = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        short = (count > 0) & (count < width)
        if short.any():
            pick = short[doc]
            at = np.arange(n) - (np.cumsum(count) - count)[doc]
            multiplier = np.array([MULTIPLIERS[j % 5] + 2 * (j // 5) for j in range(width)], np.uint64)
            total = np.zeros(n_docs, np.uint64)
            np.add.at(total, doc[pick], hashes[pick] * multiplier[at[pick]])
            ids = np.flatnonzero(short)
            s = np.concatenate([s, mix(total[ids] + count[ids].astype(np.uint64))])
            d = np.concatenate([d, ids])
            order = np.argsort(d, kind="stable")
            s, d = s[order], d[order]
        return s, d


def shingle_blocks(texts: Iterable[str | None], width: int = 5) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    for a, b, h, d in word_blocks(texts):
        yield (a, b, *shingles(h, d, b - a, width))


#: Low bits of a shingle's hash that are given up, so that its text's index fits beside it.
DROPPED = 20


def counted(values: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (value, text) with their counts, ordered by text and value. Values keep their upper 44 bits; a block has under 2^20 texts."""
    if not len(values):
        return values, doc, np.zeros(0, np.int64)
    own = np.uint64(64 - DROPPED)
    key = np.sort((doc.astype(np.uint64) << own) | (values >> np.uint64(DROPPED)))
    at = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    key = key[at]
    return key << np.uint64(DROPPED), (key >> own).astype(np.int64), np.diff(np.append(at, len(values)))


def texts_of(batch: pa.RecordBatch, name: str = "text") -> list[str | None]:
    return batch.column(batch.schema.get_field_index(name)).to_pylist()


def small(df: DataFrame, most: int) -> bool:
    """Whether ``df`` has at most ``most`` rows; looks at no more than one row beyond."""
    return df.limit(most + 1).count() <= most

"""Edges of the join drawn at random by key, without the join itself."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.keys import draw_hash, key_text, text_hash

#: Draws that one row of the expansion makes.
CHUNK = 100_000


def number_rows(keyed: DataFrame, order: list[str] | None = None, salts: int = 1, family: str = "xx") -> DataFrame:
    """``keyed`` with pos, 1 to n within a key, in the order of all used columns. With several salts a key's rows are sorted in parts, whose offsets come from their counts, so that a hot key needs no single task."""
    order = order or [c for c in keyed.columns if c != "jk"]
    by = [F.col(c).asc_nulls_first() for c in order] or [F.lit(1)]
    if salts == 1:
        return keyed.withColumn("pos", F.row_number().over(Window.partitionBy("jk").orderBy(*by)).cast("bigint"))
    salted = keyed.withColumn("salt", F.pmod(text_hash(*map(F.col, order), 3) if family == "portable" else F.xxhash64(*order, F.lit(3)), F.lit(salts)))
    counts = salted.groupBy("jk", "salt").agg(F.count("*").alias("c"))
    offsets = counts.withColumn("before", F.coalesce(F.sum("c").over(Window.partitionBy("jk").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("c")
    inside = salted.withColumn("r", F.row_number().over(Window.partitionBy("jk", "salt").orderBy(*by)).cast("bigint"))
    return inside.join(offsets, ["jk", "salt"]).withColumn("pos", F.col("before") + F.col("r")).drop("salt", "before", "r")


#: A stratum's numbers, as its edges carry them.
CARRIED = {"st_edges": "edges", "st_b": "b", "st_full": "full"}


def draw_edges(strata: DataFrame, n: int, seed: int = 42, family: str = "xx", draws: str = "b", carry: bool = False, after: str | None = None) -> DataFrame:
    """(jk, draw, pos_1..pos_n): ``draws`` random edges of each key, with replacement; a full stratum (b = edges) is enumerated instead, each edge once.

    carry: the edges have their stratum's numbers beside them, so that an estimate needs no join with the strata. after: a column of draws that are there already; the draws after them are made, and all edges of a stratum that is full now and was not."""
    key = key_text(strata.schema["jk"].dataType)
    many = F.col(draws)
    done = F.when(F.col("full") & (F.col(after) < many), F.lit(0)).otherwise(F.col(after)).cast("bigint") if after else F.lit(0).cast("bigint")
    wide = strata.withColumn("st_done", done).where(F.col("st_done") < many).withColumn("chunk", F.explode(F.sequence(F.lit(0).cast("bigint"), F.expr(f"({draws} - st_done - 1) div {CHUNK}"))))
    # a few heavy strata are a few rows, which would be drawn in one task
    wide = wide.repartition(2 * strata.sparkSession.sparkContext.defaultParallelism, "jk", "chunk")
    first = F.col("st_done") + F.col("chunk") * CHUNK
    rows = wide.withColumn("draw", F.explode(F.sequence(first + 1, F.least(many, first + CHUNK))))
    out, below = [], F.lit(1).cast("decimal(38,0)")
    for i in range(1, n + 1):
        size = F.col(f"n_{i}")
        enumerated = F.pmod(F.call_function("div", F.col("draw") - 1, below), size) if i > 1 else F.pmod(F.col("draw") - 1, size)
        out.append((1 + F.when(F.col("full"), enumerated).otherwise(F.pmod(draw_hash(key, F.col("draw"), i, seed, family), size))).cast("bigint").alias(f"pos_{i}"))
        below = (below * size.cast("decimal(19,0)")).cast("decimal(38,0)")
    return rows.select("jk", "draw", *out, *(F.col(c).alias(name) for name, c in CARRIED.items() if carry))


def distinct_edges(edges: DataFrame, n: int) -> DataFrame:
    """Each edge once, under its first draw."""
    carried = [c for c in CARRIED if c in edges.columns]
    return edges.groupBy("jk", *(f"pos_{i}" for i in range(1, n + 1))).agg(F.min("draw").alias("draw"), *(F.first(c).alias(c) for c in carried)).select("jk", "draw", *(f"pos_{i}" for i in range(1, n + 1)), *carried)


def distinct_sample(strata: DataFrame, n: int, seed: int = 42, family: str = "xx", rounds: int = 3) -> DataFrame:
    """Exactly b different edges of each key: (rounds + 1) b + 16 draws are made, and the first b different ones kept. A stratum of which more than half is wanted is enumerated and ordered by hash, which makes at most twice the edges that are kept; so is one that is still short, which with so many draws hardly happens."""
    key = key_text(strata.schema["jk"].dataType)
    pos = [f"pos_{i}" for i in range(1, n + 1)]
    first = Window.partitionBy("jk").orderBy("draw")
    rest = strata.where(~F.col("full") & (F.col("b") * 2 <= F.col("edges")))
    drawn = distinct_edges(draw_edges(rest.withColumn("draws", (F.col("b") * (rounds + 1) + 16)), n, seed, family, "draws"), n)
    kept = drawn.withColumn("r", F.row_number().over(first)).join(rest.select("jk", "b"), "jk").where("r <= b").select("jk", "draw", *pos)
    short = rest.join(kept.groupBy("jk").agg(F.count("*").alias("got")), "jk").where("got < b").drop("got")
    large = strata.where(F.col("full") | (F.col("b") * 2 > F.col("edges"))).unionByName(short)
    every = draw_edges(large.withColumn("draws", F.col("edges").cast("bigint")).withColumn("full", F.lit(True)), n, seed, family, "draws")
    order = Window.partitionBy("jk").orderBy(draw_hash(key, F.col("draw"), 0, seed, family), "draw")
    some = every.withColumn("r", F.row_number().over(order)).join(large.select("jk", "b"), "jk").where("r <= b").select("jk", "draw", *pos)
    return kept.join(short.select("jk"), "jk", "left_anti").unionByName(some)


def attach(edges: DataFrame, numbered: list[DataFrame]) -> DataFrame:
    """Edges with their rows' columns: a join on (key, position) for each side, over which a hot key spreads. A plan takes the edges for as few as their strata, so it would broadcast them: a side is broadcast if it is small itself, else both are sorted."""
    for i, side in enumerate(numbered, 1):
        edges = edges.join(side.withColumnRenamed("pos", f"pos_{i}").hint("broadcast" if _small(side) else "merge"), ["jk", f"pos_{i}"])
    return edges


def _small(side: DataFrame) -> bool:
    """Whether Spark would broadcast ``side`` by its size."""
    size = side._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()
    return int(str(size)) <= side.sparkSession._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold()


def salts_for(strata: DataFrame, most_rows: int = 4_000_000) -> int:
    """Parts in which a key's rows are numbered, so that none has more than ``most_rows`` of the heaviest key."""
    sides = [c for c in strata.columns if c.startswith("n_")]
    top = strata.agg(F.max(F.greatest(*sides))).first()[0] or 0
    return max(1, -(-int(top) // most_rows))


def sample_edges(keyed: list[DataFrame], strata: DataFrame, seed: int = 42, dedupe: bool | str = False, strategy: str = "position", family: str = "xx", salts: int = 1, carry: bool = False, after: str | None = None) -> DataFrame:
    """The sampled rows of the join: jk, draw and all sides' columns. strata: from ``count_strata`` with b and full.

    dedupe: False keeps duplicates, "resample" draws until b are different, "distinct" drops duplicates of b draws. strategy: position joins on row numbers (no memory by key; with ``salts`` a hot key is numbered in parts),
    array packs a side's rows by key, grouped runs a function by key (two sides); the last two hold a key's rows in one task. carry, after: as of ``draw_edges``."""
    n = len(keyed)
    if strategy == "grouped":
        drawn = _grouped(keyed, strata, seed)
        return drawn.join(strata.select("jk", *(F.col(c).alias(name) for name, c in CARRIED.items())), "jk") if carry else drawn
    if dedupe == "resample":
        edges = distinct_sample(strata, n, seed, family)
        if carry:
            edges = edges.join(strata.select("jk", *(F.col(c).alias(name) for name, c in CARRIED.items())), "jk")
    else:
        edges = draw_edges(strata, n, seed, family, carry=carry, after=after)
    if dedupe == "distinct":
        edges = distinct_edges(edges, n)
    if strategy == "array":
        for i, k in enumerate(keyed, 1):
            cols = [c for c in k.columns if c != "jk"]
            packed = k.groupBy("jk").agg(F.array_sort(F.collect_list(F.struct(*cols))).alias("rows"))
            edges = edges.join(packed, "jk").withColumn("row", F.element_at("rows", F.col(f"pos_{i}").cast("int"))).select(*edges.columns, *(F.col(f"row.{c}").alias(c) for c in cols))
        return edges
    return attach(edges, [number_rows(k, salts=salts, family=family) for k in keyed])


def _grouped(keyed: list[DataFrame], strata: DataFrame, seed: int) -> DataFrame:
    """Two sides, by key: a key's size and its rows of both sides come one after the other, sorted, and one pass over a task's rows draws for all its keys."""
    cols = [[f.name for f in k.schema.fields if f.name != "jk"] for k in keyed]
    jk, kinds = keyed[0].schema["jk"], {f.name: f.dataType for k in keyed for f in k.schema.fields}
    schema = T.StructType([jk, T.StructField("draw", T.LongType()), *(T.StructField(c, kinds[c]) for own in cols for c in own)])
    names = [*cols[0], *cols[1]]
    there = strata.select("jk")

    def tagged(df: DataFrame, side: int, own: list[str]) -> DataFrame:
        size = [F.col(c).cast(t).alias(f"st_{c}") if side == 0 else F.lit(None).cast(t).alias(f"st_{c}") for c, t in (("b", "bigint"), ("full", "boolean"))]
        return df.select("jk", F.lit(side).alias("st_side"), *size, *(F.col(c) if c in own else F.lit(None).cast(kinds[c]).alias(c) for c in names))

    rows = tagged(strata, 0, []).unionAll(tagged(keyed[0].join(there, "jk", "left_semi"), 1, cols[0])).unionAll(tagged(keyed[1].join(there, "jk", "left_semi"), 2, cols[1]))

    def drawn(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for b in batches:
            held.append(b)
            heads = np.flatnonzero(b.column(1).to_numpy() == 0)
            if len(heads):  # all keys but the last are complete
                yield from _draws_of(pa.Table.from_batches([*held[:-1], b.slice(0, heads[-1])]).combine_chunks(), cols, seed)
                held = [b.slice(heads[-1])]
        if held:
            yield from _draws_of(pa.Table.from_batches(held).combine_chunks(), cols, seed)

    order = ["jk", "st_side", *(F.col(c).asc_nulls_last() for c in names)]
    # by a hash of its own: an exchange by the key could be left out where the union's parts have one each, which don't meet
    return rows.repartition(F.xxhash64("jk")).sortWithinPartitions(*order).mapInArrow(drawn, schema)


def _draws_of(rows: pa.Table, cols: list[list[str]], seed: int) -> Iterator[pa.RecordBatch]:
    """The draws of whole keys: ``rows`` (jk, st_side, st_b, st_full, columns) hold a key's size, its left rows and its right rows one after the other. CHUNK draws at a time."""
    if not rows.num_rows:
        return
    side = rows.column("st_side").to_numpy()
    head = np.flatnonzero(side == 0)
    ends = np.append(head[1:], len(side))
    left = np.add.reduceat((side == 1).astype(np.int64), head)
    sizes = rows.select(["jk", "st_b", "st_full"]).take(pa.array(head))
    want, full = sizes.column("st_b").to_pylist(), sizes.column("st_full").to_pylist()
    hashes = pd.util.hash_array(np.array([str(k) for k in sizes.column("jk").to_pylist()], dtype=object)) % np.uint64(1 << 32)
    held: list[tuple[np.ndarray, ...]] = []
    size = 0

    def flush() -> pa.RecordBatch:
        key, draw, i, j = (pa.array(np.concatenate(x)) for x in zip(*held, strict=True))
        out = [rows.column("jk").take(key), draw, *(rows.column(c).take(at) for at, own in ((i, cols[0]), (j, cols[1])) for c in own)]
        out = [c.combine_chunks() if isinstance(c, pa.ChunkedArray) else c for c in out]
        return pa.RecordBatch.from_arrays(out, names=["jk", "draw", *cols[0], *cols[1]])

    for k, at in enumerate(head.tolist()):
        n, m = int(left[k]), int(ends[k] - at - 1 - left[k])
        if not n or not m:
            continue
        if not full[k]:
            g = np.random.Generator(np.random.PCG64([seed, n, m, int(hashes[k])]))
            i, j = g.integers(n, size=want[k]), g.integers(m, size=want[k])
        for lo in range(0, n * m if full[k] else want[k], CHUNK):
            draw = np.arange(lo, min(lo + CHUNK, n * m if full[k] else want[k]))
            a, b = np.divmod(draw, m) if full[k] else (i[draw], j[draw])
            held.append((np.full(len(draw), at), draw + 1, at + 1 + a, at + 1 + n + b))
            size += len(draw)
            if size >= CHUNK:
                yield flush()
                held, size = [], 0
    if held:
        yield flush()

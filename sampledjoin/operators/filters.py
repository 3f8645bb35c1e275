"""Bloom filters as tables: sized, built by partial aggregation, merged, intersected and probed."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.keys import text_hash
from ..model import FilterParams

#: A filter has at most so many bytes, whatever the number of keys, as every node holds it; with more keys it lets more rows through, and loses none.
MAX_BYTES = 1 << 28
#: Words of a block of the packed form; up to so many words a filter is not packed but broadcast as rows, which saves a stage; words that the other layouts may broadcast, a row each.
BLOCK_WORDS, ROW_WORDS, BROADCAST_WORDS = 1 << 14, 1 << 16, 1 << 22


def size_filter(n_keys: int, fp: float, max_bytes: int | None = MAX_BYTES, layout: str = "word", **rest) -> FilterParams:
    """Bits m = -n ln p / (ln 2)² and hashes h = (m / n) ln 2; the bits are cut to ``max_bytes``, the hashes then follow them. The word layout, whose words fill unevenly, gets as many more bits as its own rate asks for."""
    n = max(1, n_keys)
    m = max(64, math.ceil(-n * math.log(fp) / math.log(2) ** 2))
    if layout == "word":
        while word_rate(n, m, _hashes(n, m)) > fp:
            m = math.ceil(m * 1.05)
    if max_bytes:
        m = min(m, 8 * max_bytes)
    return FilterParams(m, _hashes(n, m), layout=layout, **rest)


def _hashes(n: int, m: int) -> int:
    return min(10, max(1, round(m / n * math.log(2))))


def word_rate(n: int, m: int, h: int) -> float:
    """False positives of the word layout: over the Poisson number of keys in a word, the chance that all h bits of another key are set."""
    load = n / (-(-m // 64))
    total, p = 0.0, math.exp(-load)
    for k in range(int(load + 12 * math.sqrt(load) + 20)):
        total += p * (1 - (1 - 1 / 64) ** (h * k)) ** h
        p *= load / (k + 1)
    return total


def _bits(jk: Column, p: FilterParams, generation: int = 0) -> list[Column]:
    """h bit numbers of a key: below 64 in the word layout, else below m."""
    seed = p.seed + 1000 * generation
    if p.family == "portable":
        return [F.pmod(text_hash(jk, i, seed), F.lit(64 if p.layout == "word" else p.words * 64)) for i in range(1, p.h + 1)]
    if p.layout == "word":
        base = F.xxhash64(jk, F.lit(seed + 1))
        return [F.shiftrightunsigned(base, 6 * i) % 64 if i else F.pmod(base, F.lit(64)) for i in range(min(p.h, 10))]
    return [F.pmod(F.xxhash64(jk, F.lit(seed + i)), F.lit(p.words * 64)) for i in range(1, p.h + 1)]


def _slot(jk: Column, p: FilterParams, generation: int = 0) -> Column:
    h = text_hash(jk, 0, p.seed) if p.family == "portable" else F.xxhash64(jk, F.lit(p.seed + 1000 * generation))
    return F.pmod(h, F.lit(p.words))


def _mask(bits: list[Column]) -> Column:
    one = F.lit(1).cast("bigint")
    return reduce(lambda a, b: a.bitwiseOR(b), (F.call_function("shiftleft", one, b.cast("int")) for b in bits))


def marks(keyed: DataFrame, p: FilterParams, generation: int = 0) -> DataFrame:
    """(slot, mask) that each row sets."""
    jk = F.col("jk")
    if p.layout in ("word", "scalable"):
        word = FilterParams(p.m_bits, p.h, p.seed, "word", p.family)
        return keyed.select(_slot(jk, word, generation).alias("slot"), _mask(_bits(jk, word, generation)).alias("mask"))
    each = keyed.select(F.explode(F.array(*_bits(jk, p))).alias("bit"))
    if p.layout == "counting":
        return each.select(F.col("bit").alias("slot"), F.lit(1).cast("bigint").alias("mask"))
    return each.select((F.col("bit") / 64).cast("bigint").alias("slot"), _mask([F.col("bit") % 64]).alias("mask"))


def build_filter(keyed: DataFrame, p: FilterParams, merge: str = "sharded", depth: int = 2) -> DataFrame:
    """The dataset filter (slot, mask). sharded: partial filters are reduced by slot, so that no node holds all of them;
    tree: in ``depth`` rounds over ever fewer groups of partitions; driver: all partial filters meet on the driver (an ablation; its memory grows with partitions)."""
    rows = marks(keyed, p)
    fold = F.sum("mask") if p.layout == "counting" else F.bit_or("mask")
    if merge == "sharded":
        return rows.groupBy("slot").agg(fold.alias("mask"))
    part = rows.withColumn("part", F.spark_partition_id()).groupBy("part", "slot").agg(fold.alias("mask"))
    if merge == "tree":
        for level in range(depth - 1, 0, -1):
            part = part.withColumn("part", F.pmod(F.col("part"), F.lit(4**level))).groupBy("part", "slot").agg(fold.alias("mask"))
        return part.groupBy("slot").agg(fold.alias("mask"))
    whole: dict[int, int] = {}
    for r in part.select("slot", "mask").collect():
        whole[r[0]] = whole.get(r[0], 0) + r[1] if p.layout == "counting" else whole.get(r[0], 0) | r[1]
    return keyed.sparkSession.createDataFrame([*whole.items()], "slot bigint, mask bigint")


def bitmap_filter(keyed: DataFrame, p: FilterParams) -> DataFrame:
    """The bitmap layout (bucket, bits): positions of 32,768-bit buckets in Spark's bitmap aggregate."""
    pos = keyed.select(F.explode(F.array(*_bits(F.col("jk"), FilterParams(p.m_bits, p.h, p.seed, "classic", p.family)))).alias("pos"))
    return pos.groupBy(F.expr("pos div 32768").alias("bucket")).agg(F.bitmap_construct_agg(F.expr("pos % 32768")).alias("bits"))


def intersect(filters: list[DataFrame], layout: str = "word") -> DataFrame:
    """The join filter: all filters' bits ANDed in one step. A slot that any filter lacks is zero."""
    every = reduce(DataFrame.unionAll, (f.withColumn("side", F.lit(i)) for i, f in enumerate(filters)))
    fold = F.min("mask") if layout == "counting" else F.bit_and("mask")
    return every.groupBy("slot").agg(fold.alias("mask"), F.count("*").alias("sides")).where((F.col("sides") == len(filters)) & (F.col("mask") != 0)).select("slot", "mask")


def _every_word(spark: SparkSession, p: FilterParams) -> DataFrame:
    """(slot, mask): a zero for each word."""
    return spark.range(0, p.words, 1, max(1, min(64, p.words >> 16))).select(F.col("id").alias("slot"), F.lit(0).cast("bigint").alias("mask"))


def join_filter(keyed: list[DataFrame], p: FilterParams) -> DataFrame:
    """The join filter of all inputs by one exchange: their marks, tagged, are ORed by slot and side, and the sides ANDed. Word layout; all words are there if there are more than ROW_WORDS."""
    n = len(keyed)
    parts = [marks(k, p).withColumn("side", F.lit(i)) for i, k in enumerate(keyed)]
    if p.words > ROW_WORDS:
        parts.append(_every_word(keyed[0].sparkSession, p).withColumn("side", F.lit(n)))
    every = reduce(DataFrame.unionAll, parts)
    sides = [F.coalesce(F.bit_or(F.when(F.col("side") == i, F.col("mask"))), F.lit(0)).cast("bigint").alias(f"side_{i}") for i in range(n)]
    return every.groupBy("slot").agg(*sides).select("slot", reduce(lambda a, b: a.bitwiseAND(b), (F.col(f"side_{i}") for i in range(n))).alias("mask"))


def pack(table: DataFrame, p: FilterParams, dense: bool = False) -> DataFrame:
    """(block, words): the filter's words in blocks of BLOCK_WORDS, without gaps. ``dense``: the table has all words, each once."""
    if not dense:
        table = table.unionAll(_every_word(table.sparkSession, p)).groupBy("slot").agg(F.bit_or("mask").alias("mask"))
    words = F.array_sort(F.collect_list(F.struct("slot", "mask")))
    return table.groupBy(F.expr(f"slot div {BLOCK_WORDS}").alias("block")).agg(words.alias("w")).select("block", F.col("w.mask").alias("words"))


def unite(filters: list[DataFrame]) -> DataFrame:
    """The filter of a union: bits ORed."""
    return reduce(DataFrame.unionAll, filters).groupBy("slot").agg(F.bit_or("mask").alias("mask"))


def _probe(keyed: DataFrame, table: DataFrame, p: FilterParams, how: str, dense: bool = False) -> DataFrame:
    """A join with the filter of the word layout: its blocks (of a small one its words) are broadcast, MAX_BYTES at most, and a row looks into one word."""
    if p.words * 8 > 2 * MAX_BYTES:
        raise ValueError("a filter of so many bits can't be broadcast: size it with max_bytes")
    slot, mine = _slot(F.col("jk"), p), _mask(_bits(F.col("jk"), p))
    if p.words <= ROW_WORDS:
        rows = F.broadcast(table.where("mask <> 0").select(F.col("slot").alias("f_slot"), F.col("mask").alias("f_mask")))
        return keyed.join(rows, (slot == F.col("f_slot")) & (F.col("f_mask").bitwiseAND(mine) == mine), how)
    word = F.element_at("f_words", (F.pmod(slot, F.lit(BLOCK_WORDS)) + 1).cast("int"))
    blocks = F.broadcast(pack(table, p, dense).select(F.col("block").alias("f_block"), F.col("words").alias("f_words")))
    return keyed.join(blocks, ((slot / BLOCK_WORDS).cast("bigint") == F.col("f_block")) & (word.bitwiseAND(mine) == mine), how)


def apply_filter(keyed: DataFrame, table: DataFrame, p: FilterParams, dense: bool = False) -> DataFrame:
    """Rows whose key may be in the filter, which is broadcast; see ``_probe``. The other layouts, whose words are rows, may have BROADCAST_WORDS of them."""
    jk = F.col("jk")
    if p.layout in ("word", "scalable"):
        return _probe(keyed, table, FilterParams(p.m_bits, p.h, p.seed, "word", p.family), "left_semi", dense)
    if p.words > BROADCAST_WORDS:
        raise ValueError(f"the {p.layout} layout is for filters of at most {BROADCAST_WORDS} words")
    side = F.broadcast(table.select(F.col("slot").alias("f_slot"), F.col("mask").alias("f_mask")))
    for bit in _bits(jk, p):
        slot, need = (bit, F.col("f_mask") > 0) if p.layout == "counting" else ((bit / 64).cast("bigint"), F.col("f_mask").bitwiseAND(_mask([bit % 64])) != 0)
        keyed = keyed.join(side, (slot == F.col("f_slot")) & need, "left_semi")
    return keyed


def remove_from_counting(table: DataFrame, keyed: DataFrame, p: FilterParams) -> DataFrame:
    """A counting filter after its rows' removal."""
    gone = marks(keyed, p).withColumn("mask", -F.col("mask"))
    return table.unionAll(gone).groupBy("slot").agg(F.sum("mask").alias("mask")).where("mask > 0")


class ScalableFilter:
    """Generations of word filters, each of double size; a key is in it if it is in any of them."""

    def __init__(self, first_keys: int, fp: float, seed: int = 42):
        self.first_keys, self.fp, self.seed, self.generations = first_keys, fp, seed, []

    def add(self, keyed: DataFrame) -> None:
        k = len(self.generations)
        p = size_filter(self.first_keys * 2**k, self.fp / 2 ** (k + 1), seed=self.seed + 7919 * k)
        self.generations.append((build_filter(keyed, p), p))

    def apply(self, keyed: DataFrame) -> DataFrame:
        rest, out = keyed, []
        for table, p in self.generations:
            out.append(apply_filter(rest, table, p))
            rest = _probe(rest, table, p, "left_anti")
        return reduce(DataFrame.unionAll, out)


def estimate_cardinality(table: DataFrame, p: FilterParams) -> DataFrame:
    """(bits_set, keys): distinct keys from the fill, -(m / h) ln(1 - X / m)."""
    m = p.words * 64
    return table.agg(F.coalesce(F.sum(F.bit_count("mask")), F.lit(0)).cast("bigint").alias("bits_set")).select("bits_set", (F.lit(-m / p.h) * F.log(1 - F.least(F.col("bits_set"), F.lit(m - 1)) / m)).alias("keys"))

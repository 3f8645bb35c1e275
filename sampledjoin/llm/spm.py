"""SentencePiece encoding and decoding by a max-plus parallel scan.

A document is a lattice: nodes are positions, edges are pieces. For a unigram model an edge weighs its piece's score; for
a BPE model every edge weighs 0, and an edge may follow another only if merging their joint text gives back just these two
pieces — the one path on which every neighbouring pair is so is the BPE segmentation. Giant documents are split into
chunks of fixed length, wherever the borders fall. A chunk's state at a border is the piece that holds the
last character before it; its transfer matrix holds, for each state at its left and right border, the best weight
between them (minus infinity where there is no path). Matrices are combined by max-plus products in a tree: FAN neighbours become one, level
by level, until a document has one matrix; then, from the top down, each group chooses the states at its inner borders
that the best path has between the states at its outer ones. So no task holds more than FAN matrices of a document. Each chunk is then traced back by itself, independently of the others.
The text is the model's normal form of it, by the library.

No piece of the vocabulary has a blank after another character, so a blank that follows another character is always a
border of pieces. What lies between the first and the last such place of a chunk is the same on every path; the
library's encoder does it, and the matrix needs only the chunk's ends. A chunk without such a place is all lattice.

Defined cases: null texts are encoded as empty; an empty text has no ids; each distinct giant text is encoded once, so
repeated rows and null ids are kept; ties of weight go to the longer piece; a text that holds the blank's own symbol (U+2581) decodes with
blanks in its place, as the model defines, which round_trip tells.
"""

from __future__ import annotations

from functools import lru_cache
from pathlib import Path

import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import materialise, ship, sliced

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SPACE = "▁"
#: Characters of a chunk; longer documents are giant.
CHUNK = 16_384
#: Matrices that are combined to one.
FAN = 32
NONE = float("-inf")
State = tuple[int, int]
Matrix = dict[tuple[State, State], float]


class Lattice:
    """Pieces, their weights and which may follow which. Positions are those of the whole document."""

    def __init__(self, model: bytes):
        self.sp = sp = sentencepiece.SentencePieceProcessor(model_proto=model)
        self.id = {sp.id_to_piece(i): i for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))}
        self.score = {p: sp.get_score(i) for p, i in self.id.items()}
        self.longest = max(map(len, self.id))
        self.bytes = [sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.bpe = self._is_bpe()
        self.merged = lru_cache(1 << 18)(self._merged)

    def _is_bpe(self) -> bool:
        """In a BPE model scores are the negated ranks of merges: whole numbers."""
        some = list(self.score.values())[:2000]
        return all(s == int(s) for s in some)

    def _merged(self, text: str) -> tuple[str, ...]:
        """The text merged pair by pair: the best-scored joint piece first, the leftmost of equals."""
        parts = list(text)
        while len(parts) > 1:
            best = max(((self.score.get(a + b, NONE), -i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False))), default=(NONE, 0))
            if best[0] == NONE:
                break
            i = -best[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return tuple(parts)

    def pieces(self, x: str, i: int) -> list[int]:
        """Ends of the pieces that begin at i; a character without a piece stands alone, as bytes."""
        out = [j for j in range(i + 1, min(len(x), i + self.longest) + 1) if (p := x[i:j]) in self.id and (not self.bpe or len(p) == 1 or self.merged(p) == (p,))]
        return out if out and out[0] == i + 1 else [i + 1, *out]

    def weight(self, piece: str) -> float:
        return 0.0 if self.bpe else self.score.get(piece, min(self.score.values()) - 10)

    def follows(self, a: str, b: str) -> bool:
        return not self.bpe or self.merged(a + b) == (a, b)

    def ids(self, piece: str) -> list[int]:
        return [self.id[piece]] if piece in self.id else [self.bytes[b] for b in piece.encode("utf-8", "replace")]

    def states(self, x: str, at: int) -> list[State]:
        """The pieces (start, end) that hold the character before position ``at``."""
        return [(i, j) for i in range(max(0, at - self.longest), at) for j in self.pieces(x, i) if j >= at]

    def reach(self, x: str, begin: State | None, start: int, stop: int) -> dict[State, tuple[float, State | None]]:
        """Best weight and predecessor of every piece that can be reached from piece ``begin`` (None: from position ``start``), as far as the pieces that hold the character before ``stop``. The weight of ``begin`` isn't counted."""
        best: dict[State, tuple[float, State | None]] = {}
        ending: dict[int, list[State]] = {}
        if begin is not None:
            best[begin] = (0.0, None)
            ending[begin[1]] = [begin]
            start = begin[1]
        for i in range(start, stop):
            before = ending.get(i, [])
            if not before and not (begin is None and i == start):
                continue
            for j in self.pieces(x, i):
                p = x[i:j]
                options = [(best[s][0], s[0] - s[1], s) for s in before if self.follows(x[s[0] : s[1]], p)]
                if begin is None and i == start:
                    options = [(0.0, 0, None)]
                if options:
                    w, _, s = max(options, key=lambda o: (o[0], -o[1]))
                    best[i, j] = (w + self.weight(p), s)
                    ending.setdefault(j, []).append((i, j))
        return best

    def path(self, best: dict[State, tuple[float, State | None]], end: State) -> list[State]:
        out = [end]
        while (s := best[out[-1]][1]) is not None:
            out.append(s)
        return out[::-1]


def product(a: Matrix, b: Matrix) -> Matrix:
    """The max-plus product; states not named stand for minus infinity."""
    by: dict[State, list[tuple[State, float]]] = {}
    for (m, r), w in b.items():
        by.setdefault(m, []).append((r, w))
    out: Matrix = {}
    for (left, m), w in a.items():
        for r, v in by.get(m, ()):
            if w + v > out.get((left, r), NONE):
                out[left, r] = w + v
    return out


#: States before the first and after the last character.
BEGIN, END = (-1, 0), (-2, -2)


class Chunk:
    """Characters lo to hi of a document of n characters. ``x`` is the document from position ``base`` on, with context on both sides."""

    def __init__(self, lattice: Lattice, x: str, base: int, lo: int, hi: int, n: int):
        self.lattice, self.x, self.base, self.lo, self.hi, self.n = lattice, x, base, lo - base, hi - base, n - base
        forced = [i for i in range(max(1, self.lo + 1), self.hi) if x[i] == SPACE and x[i - 1] != SPACE]
        self.first, self.last = (forced[0], forced[-1]) if forced else (None, None)
        self.begins, self.ends = lo == 0, hi == n

    def _shift(self, s: State) -> State:
        return s if s in (BEGIN, END) else (s[0] + self.base, s[1] + self.base)

    def _finals(self, best: dict, stop: int, exact: bool) -> list[State]:
        return [s for s in best if s[0] < stop <= s[1] and (not exact or s[1] == stop)]

    def lefts(self) -> list[State]:
        return [BEGIN] if self.begins else self.lattice.states(self.x, self.lo)

    def _from(self, left: State, stop: int) -> dict:
        return self.lattice.reach(self.x, None if left == BEGIN else left, 0 if left == BEGIN else self.lo, stop)

    def _stop(self) -> tuple[int, bool]:
        return (self.n, True) if self.ends else (self.hi, False)

    def matrix(self) -> Matrix:
        stop, exact = self._stop()
        out: Matrix = {}
        if self.first is None:
            for left in self.lefts():
                best = self._from(left, stop)
                for s in self._finals(best, stop, exact):
                    w, right = best[s][0], END if self.ends else s
                    if w > out.get((self._shift(left), self._shift(right)), NONE):
                        out[self._shift(left), self._shift(right)] = w
            return out
        heads = {}
        for left in self.lefts():
            best = self._from(left, self.first)
            w = max((best[s][0] for s in self._finals(best, self.first, True)), default=NONE)
            if w > NONE:
                heads[left] = w
        best = self.lattice.reach(self.x, None, self.last, stop)
        tails: dict[State, float] = {}
        for s in self._finals(best, stop, exact):
            right = END if self.ends else s
            tails[right] = max(best[s][0], tails.get(right, NONE))
        return {(self._shift(a), self._shift(b)): w + v for a, w in heads.items() for b, v in tails.items()}

    def trace(self, left: State, right: State) -> list[int]:
        """Ids of the pieces after ``left`` up to and with ``right`` on the best path between them."""
        L, stop = self.lattice, self._stop()[0]
        left = left if left == BEGIN else (left[0] - self.base, left[1] - self.base)
        right = right if right == END else (right[0] - self.base, right[1] - self.base)

        def ids(best: dict, end: State, skip: bool) -> list[int]:
            return [k for s in L.path(best, end)[skip:] for k in L.ids(self.x[s[0] : s[1]])]

        def top(best: dict, at: int) -> State:
            return max(self._finals(best, at, True), key=lambda s: (best[s][0], s[1] - s[0]))

        if self.first is None:
            best = self._from(left, stop)
            return ids(best, top(best, stop) if right == END else right, left != BEGIN)
        head = self._from(left, self.first)
        out = ids(head, top(head, self.first), left != BEGIN)
        if self.first < self.last:
            out += encode_plain(L.sp, self.x[self.first : self.last])
        tail = L.reach(self.x, None, self.last, stop)
        return out + ids(tail, top(tail, stop) if right == END else right, False)


def encode_plain(sp, marked: str) -> list[int]:
    """Encodes text that begins with a blank's symbol, without the blank that the encoder puts first."""
    return sp.encode(marked[1:].replace(SPACE, " ")) if SPACE == marked[0] else sp.encode(marked)


_LOADED: dict[int, Lattice] = {}


def lattice_of(model: bytes) -> Lattice:
    k = hash(model)
    if k not in _LOADED:
        _LOADED[k] = Lattice(model)
    return _LOADED[k]


def _key():
    return F.struct(F.xxhash64("text").alias("a"), F.xxhash64(F.lit(11), "text").alias("b"), F.char_length("text").alias("n"))


def _chunked(docs: DataFrame, data, size: int, context: int) -> DataFrame:
    """(key, k, base, lo, hi, n, x) of the chunks of each distinct text in its normal form (a blank first, and blanks as their symbol); the text is split where it lies."""

    def split(batches):
        for b in sliced(batches, 16):
            for i in range(b.num_rows):
                t = lattice_of(data.value).sp.normalize(b.column(1)[i].as_py())
                n, rows = len(t), []
                count = max(1, n // size)
                for k in range(count):
                    lo, hi = k * size, n if k == count - 1 else (k + 1) * size
                    base = max(0, lo - context)
                    rows.append((k, base, lo, hi, n, t[base : hi + context]))
                    if len(rows) == 64 or k == count - 1:
                        c = list(zip(*rows, strict=True))
                        yield pa.RecordBatch.from_arrays([pa.concat_arrays([b.column(0).slice(i, 1)] * len(rows)), *(pa.array(v, pa.int64()) for v in c[:5]), pa.array(c[5], pa.string())], names=["key", "k", "base", "lo", "hi", "n", "x"])
                        rows = []

    return docs.select(_key().alias("key"), "text").dropDuplicates(["key"]).mapInArrow(split, f"key {KEY}, k bigint, base bigint, lo bigint, hi bigint, n bigint, x string")


KEY = "struct<a:bigint,b:bigint,n:int>"
CELLS = "array<struct<li:bigint,lj:bigint,ri:bigint,rj:bigint,w:double>>"
_STATE, _PLACE = pa.struct([("i", pa.int64()), ("j", pa.int64())]), "struct<i:bigint,j:bigint>"
_CELLS = pa.list_(pa.struct([("li", pa.int64()), ("lj", pa.int64()), ("ri", pa.int64()), ("rj", pa.int64()), ("w", pa.float64())]))


def _packed(matrices: list[Matrix]) -> pa.Array:
    return pa.array([[{"li": a[0], "lj": a[1], "ri": r[0], "rj": r[1], "w": w} for (a, r), w in m.items()] for m in matrices], _CELLS)


def _ordered(table: pa.Table) -> tuple[list[int], list[Matrix]]:
    """Places and matrices of a group, by place."""
    parts = sorted(zip(table.column("k").to_pylist(), table.column("m").to_pylist(), strict=True), key=lambda p: p[0])
    return [k for k, _ in parts], [{((c["li"], c["lj"]), (c["ri"], c["rj"])): c["w"] for c in m} for _, m in parts]


def _places(states: list[State]) -> pa.Array:
    return pa.array([{"i": a, "j": b} for a, b in states], _STATE)


def combined(table: pa.Table, fan: int) -> pa.Table:
    """A group's product, at its place on the next level."""
    ks, ms = _ordered(table)
    whole = ms[0]
    for m in ms[1:]:
        whole = product(whole, m)
    return pa.table({"key": table.column("key").slice(0, 1), "k": pa.array([ks[0] // fan], pa.int64()), "m": _packed([whole])})


def inner_states(ms: list[Matrix], enter: State, leave: State) -> list[State]:
    """The states at the borders of ``ms`` on the best path between two outer states: the best weights from the left, and a walk back. Ties go to the longer piece."""
    reached = [{enter: 0.0}]
    for m in ms:
        here: dict[State, float] = {}
        for (a, r), w in m.items():
            if a in reached[-1] and reached[-1][a] + w > here.get(r, NONE):
                here[r] = reached[-1][a] + w
        reached.append(here)
    states = [leave]
    for m, before in zip(ms[:0:-1], reached[-2:0:-1], strict=True):
        states.append(max((w + m[s, states[-1]], s[1] - s[0], s) for s, w in before.items() if (s, states[-1]) in m)[2])
    return [enter, *states[::-1]]


def descended(table: pa.Table, outer: pa.Table) -> pa.Table:
    """(key, k, enter, leave) of a group's matrices, given the states at its outer borders."""
    ks, ms = _ordered(table)
    a, b = outer.column("enter")[0].as_py(), outer.column("leave")[0].as_py()
    states = inner_states(ms, (a["i"], a["j"]), (b["i"], b["j"]))
    return pa.table({"key": table.column("key"), "k": pa.array(ks, pa.int64()), "enter": _places(states[:-1]), "leave": _places(states[1:])})


def border_states(matrices: DataFrame, most: int, fan: int) -> DataFrame:
    """(key, k, enter, leave) for the matrices (key, k, m) of documents of at most ``most`` chunks: up the tree, and down again."""
    levels = [matrices]
    above = F.expr(f"k div {fan}")
    while most > 1:
        most = -(-most // fan)
        up = levels[-1].withColumn("up", above).groupBy("key", "up").applyInArrow(lambda t: combined(t, fan), f"key {KEY}, k bigint, m {CELLS}")
        levels.append(materialise(up, "matrices") if most > 1 else up)
    outer = levels[-1].select("key", "k", F.struct(F.lit(BEGIN[0]).cast("bigint").alias("i"), F.lit(BEGIN[1]).cast("bigint").alias("j")).alias("enter"), F.struct(F.lit(END[0]).cast("bigint").alias("i"), F.lit(END[1]).cast("bigint").alias("j")).alias("leave"))
    for level in levels[-2::-1]:
        outer = level.withColumn("up", above).groupBy("key", "up").cogroup(outer.withColumnRenamed("k", "up").groupBy("key", "up")).applyInArrow(lambda t, o: descended(t, o), f"key {KEY}, k bigint, enter {_PLACE}, leave {_PLACE}")
    return outer


def encode_giant(docs: DataFrame, model: bytes, size: int = CHUNK) -> DataFrame:
    """(key, ids) of the distinct texts in ``docs`` (text, not null), by the scan."""
    spark = docs.sparkSession
    data = spark.sparkContext.broadcast(model)  # the model's file; its size doesn't grow with the data
    chunks = materialise(_chunked(docs, data, size, 2 * lattice_of(model).longest).repartition("key", "k"), "chunks")

    def rows_of(b):
        return zip(*(c.to_pylist() for c in b.columns), strict=True)

    def matrices(batches):
        for b in sliced(batches, 16):
            found = [Chunk(lattice_of(data.value), x, base, lo, hi, n).matrix() for _, _, base, lo, hi, n, x in rows_of(b)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), _packed(found)], names=["key", "k", "m"])

    held = materialise(chunks.mapInArrow(matrices, f"key {KEY}, k bigint, m {CELLS}"), "matrices")
    states = border_states(held, (chunks.agg(F.max("k")).first()[0] or 0) + 1, FAN)

    def traced(batches):
        for b in sliced(batches, 16):
            out = []
            for _, _, base, lo, hi, n, x, enter, leave in rows_of(b):
                out.append(Chunk(lattice_of(data.value), x, base, lo, hi, n).trace((enter["i"], enter["j"]), (leave["i"], leave["j"])))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(out, pa.list_(pa.int32()))], names=["key", "k", "ids"])

    parts = chunks.join(states, ["key", "k"]).select("key", "k", "base", "lo", "hi", "n", "x", "enter", "leave").mapInArrow(traced, f"key {KEY}, k bigint, ids array<int>")
    return parts.groupBy("key").agg(F.array_sort(F.collect_list(F.struct("k", "ids"))).alias("p")).select("key", F.flatten(F.transform("p", lambda s: s["ids"])).alias("ids"))


def read_model(path: str = MODEL) -> bytes:
    return Path(path).read_bytes()


def _with(docs: DataFrame, make, added: list[T.StructField], drop: str | None = None) -> DataFrame:
    """docs with columns that ``make`` gives from a batch, a slice at a time."""
    keep = [c for c in docs.columns if c != drop]

    def made(batches):
        for part in sliced(batches, 256):
            yield pa.RecordBatch.from_arrays([*(part.column(i) for i, c in enumerate(docs_columns) if c != drop), *make(part)], names=[*keep, *(f.name for f in added)])

    docs_columns = list(docs.columns)
    return docs.mapInArrow(made, T.StructType([*(docs.schema[c] for c in keep), *added]))


def encode(docs: DataFrame, model: bytes, size: int = CHUNK, check: bool = False) -> DataFrame:
    """``docs`` (with a column text) with spm_ids, and with ``check`` also round_trip: whether the decoded ids give the text back. Columns of these names are replaced."""
    spark = docs.sparkSession
    ship(spark)
    data = spark.sparkContext.broadcast(model)
    docs = docs.drop("spm_ids", "round_trip")
    text = docs.columns.index("text")
    giant = F.coalesce(F.char_length("text") >= size, F.lit(False))

    def same(texts: list[str | None], ids: list[list[int]]) -> pa.Array:
        back = lattice_of(data.value).sp.decode(ids, num_threads=1)
        return pa.array([(a or "") == b for a, b in zip(texts, back, strict=True)])

    def direct(b):
        texts = b.column(text).to_pylist()
        ids = lattice_of(data.value).sp.encode([t or "" for t in texts], num_threads=1)
        return [pa.array(ids, pa.list_(pa.int32())), *([same(texts, ids)] if check else [])]

    def checked(b):
        return [same(b.column(text).to_pylist(), b.column(b.num_columns - 1).to_pylist())]

    field, flag = T.StructField("spm_ids", T.ArrayType(T.IntegerType())), T.StructField("round_trip", T.BooleanType())
    plain = _with(docs.where(~giant), direct, [field, *([flag] if check else [])])
    long = docs.where(giant)
    found = encode_giant(long.select("text"), model, size)
    # as a struct, so that no name of the rows' columns meets the keys'
    rows = long.select(F.struct(*(long[c] for c in long.columns)).alias("row"), _key().alias("key"))
    scanned = rows.join(found, "key", "left").select(*(F.col("row")[c].alias(c) for c in long.columns), F.col("ids").alias("spm_ids"))
    return plain.unionByName(_with(scanned, checked, [flag]) if check else scanned)


def decode(docs: DataFrame, model: bytes) -> DataFrame:
    """``docs`` (with spm_ids) with spm_text; null ids give null."""
    spark = docs.sparkSession
    ship(spark)
    data = spark.sparkContext.broadcast(model)
    docs = docs.drop("spm_text")
    at = docs.columns.index("spm_ids")

    def made(b):
        ids = b.column(at).to_pylist()
        texts = lattice_of(data.value).sp.decode([i or [] for i in ids], num_threads=1)
        return [pa.array([None if i is None else t for i, t in zip(ids, texts, strict=True)], pa.string())]

    return _with(docs, made, [T.StructField("spm_text", T.StringType())])


def encoded(docs: DataFrame, model_path: str = MODEL) -> DataFrame:
    """(doc_id, n_tokens, ids, round_trip): whether the decoded ids give the text back."""
    out = encode(docs.select("doc_id", "text"), read_model(model_path), check=True)
    return out.select("doc_id", F.size("spm_ids").cast("bigint").alias("n_tokens"), F.col("spm_ids").alias("ids"), "round_trip")


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encoded(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document with its ids instead of its text."""
    return encoded(docs)

"""Toxicity by a weighted finite-state pattern grammar over clauses.

A lexical transducer maps words to the symbols insult, threat, target, negation, report and other; its insult arcs are
seed words plus word stems learned from labelled rows, each with its log odds as weight. Four transducers read a clause's symbols: insult (with a
target before it, or shortly after it), threat (a verb of harm and a target shortly after it), negation (for some words after it) and reported speech (to the clause's end). Their
composition puts each match into a cell: plain, targeted, threat, negated or reported. A document's summed cell weights go through a logistic function.

Labelled rows are dealt in three folds by a hash of the id. The two thresholds that stems have to reach are chosen by learning on the first fold and measuring on the second, stems are then
learned on both, and the logistic function is fitted on the third, which no stem has seen. Held-out rows are in no fold.

Defined cases: null and empty texts have no clauses and get the score of the intercept; a row is scored by its text
alone, so repeated rows score alike; null ids are kept; a clause goes on over the pieces that a long text is read in; an empty table gives an empty result; without labelled rows the seed words and prior weights are used.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import PIECE, Words, cut, discard, lowered, materialise, ship, sliced

#: Seed words by symbol, in the four languages of the corpus.
INSULTS = "idiot idiots moron morons stupid dumb imbecile scum trash garbage loser losers pathetic worthless disgusting clown filth vermin dummkopf trottel abschaum imbécile connard ordure idiota imbécil estúpido basura escoria".split()
THREATS = "kill hurt destroy murder beat stab shoot töten umbringen tuer frapper matar golpear".split()
TARGETS = "you your yours he she they them him her du dich dein ihr euch sie tu toi vous ton eres usted ustedes él ellos".split()
NEGATIONS = "not never no neither nor without hardly isn aren wasn don doesn nicht kein keine nie pas jamais aucun nunca jamás ningún".split()
REPORTS = "said says wrote claimed quoted reported alleged called sagte schrieb behauptete dit écrit affirmé dijo escribió afirmó".split()

OTHER, INSULT, THREAT, TARGET, NEGATION, REPORT = range(6)
CELLS = ("plain", "targeted", "negated", "reported", "threat")
#: Words after a negation within which it holds; words after an insult or a verb of harm within which a target belongs to it; lengths of learned stems.
SCOPE, REACH, STEM_LENGTHS = 3, 3, (4, 5, 6, 7, 8)
#: At most so many labelled rows of each label are learned from, and at most so many stems (those of most toxic texts): bounds of the model.
SAMPLE_PER_LABEL, MOST_STEMS = 6000, 5000
#: What a stem may have to reach: a G² statistic and a share of toxic texts (with both labels weighed alike). Cross-validation chooses among them.
G2_GRID, PRECISION_GRID = (10.0, 20.0, 40.0), (0.9, 0.95, 0.99)
GRID = [(g, p) for p in PRECISION_GRID for g in G2_GRID]
FOLDS = 3
#: Prior means of the logistic function: intercept, presence of any cell, then the cells.
PRIOR = np.array([-3.0, 3.0, 0.3, 0.4, 0.1, 0.1, 0.5])
THRESHOLD = 0.3


class Transducer:
    """A deterministic transducer over the symbols: ``step`` gives for a state and a symbol the next state and what is put out."""

    def __init__(self, start, step: Callable):
        self.start, self.step = start, step

    def compose(self, other: Transducer) -> Transducer:
        """Both read the same symbols; what they put out is paired."""

        def step(state, s):
            (a, x), (b, y) = self.step(state[0], s), other.step(state[1], s)
            return (a, b), (x, y)

        return Transducer((self.start, other.start), step)

    def table(self, cell: Callable) -> tuple[list[list[int]], list[list[int]]]:
        """As arrays over the states that can be reached: next state and ``cell`` of the output (-1: none) by state and symbol; state 0 starts."""
        names, nxt, emit = {self.start: 0}, [], []
        todo = [self.start]
        while todo:
            here, rows, outs = todo.pop(0), [], []
            for s in range(6):
                to, out = self.step(here, s)
                if to not in names:
                    names[to] = len(names)
                    todo.append(to)
                rows.append(names[to])
                outs.append(cell(out))
            nxt.append(rows)
            emit.append(outs)
        return nxt, emit


def insult() -> Transducer:
    """State: whether a target came, and words left in which one may follow an insult. Puts out plain or targeted."""

    def step(state, s):
        seen, left = state
        if s == INSULT:
            return (seen, 0 if seen else REACH), "targeted" if seen else "plain"
        if s == TARGET:
            return (1, 0), "targeted" if left else None
        return (seen, max(0, left - 1)), None

    return Transducer((0, 0), step)


def threat() -> Transducer:
    """State: words left in which a target makes a threat of a verb of harm. Puts out plain at the verb and threat at the target."""

    def step(left, s):
        if s == THREAT:
            return REACH, "plain"
        if s == TARGET:
            return 0, "threat" if left else None
        return max(0, left - 1), None

    return Transducer(0, step)


def negation() -> Transducer:
    return Transducer(0, lambda left, s: (SCOPE if s == NEGATION else max(0, left - 1), left > 0))


def reported() -> Transducer:
    return Transducer(0, lambda said, s: (1 if s == REPORT else said, said > 0))


def _cell(out) -> int:
    """A modifier outranks a threat, and a threat a targeted insult."""
    ((an_insult, a_threat), negated), said = out
    if an_insult is None and a_threat is None:
        return -1
    return CELLS.index("negated" if negated else "reported" if said else "threat" if a_threat == "threat" else "targeted" if an_insult == "targeted" else "plain")


def grammar() -> tuple[list[list[int]], list[list[int]]]:
    return insult().compose(threat()).compose(negation()).compose(reported()).table(_cell)


def _text_hash(word: str) -> int:
    w = Words(word.lower(), np.zeros(1, np.int64))
    return int(w.hash[0])


class Lexicon:
    """The lexical transducer: whole words, and stems by length, as sorted hashes with symbol and weight."""

    def __init__(self, stems: list[tuple[int, int, float]]):
        """stems: (length, hash, weight)."""
        with np.errstate(over="ignore"):
            whole = {}
            for symbol, words in ((TARGET, TARGETS), (NEGATION, NEGATIONS), (REPORT, REPORTS), (THREAT, THREATS), (INSULT, INSULTS)):
                whole |= {_text_hash(w): (symbol, 2.0) for w in words}
        self.tables = [(0, *self._sorted(whole))]
        for n in sorted({s[0] for s in stems}):
            self.tables.append((n, *self._sorted({h: (INSULT, w) for m, h, w in stems if m == n})))

    @staticmethod
    def _sorted(entries: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        keys = sorted(entries)
        return np.array(keys, np.uint64), np.array([entries[k][0] for k in keys], np.int8), np.array([entries[k][1] for k in keys])

    def apply(self, w: Words) -> tuple[np.ndarray, np.ndarray]:
        symbol, weight = np.zeros(len(w.start), np.int8), np.zeros(len(w.start))
        for n, keys, symbols, weights in self.tables:
            if not len(keys):
                continue
            if n:
                at = np.flatnonzero(w.end - w.start >= n)
                h = w.part(w.start[at], w.start[at] + n)
            else:
                at, h = np.arange(len(w.start)), w.hash
            k = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
            hit = keys[k] == h
            if n:
                hit &= weights[k] > weight[at]
            symbol[at[hit]], weight[at[hit]] = symbols[k[hit]], weights[k[hit]]
        return symbol, weight


_BREAKS = np.array([ord(c) for c in ".,;:!?\n\"“”«»()"], np.uint32)


def read_clause(symbol: np.ndarray, weight: np.ndarray, state: tuple[int, float], out: np.ndarray, table) -> tuple[int, float]:
    """Adds what a clause's words put out to ``out`` by cell, and gives the state after them: of the transducer, and the weight of the last insult or verb of harm."""
    step, emit = table
    at, held = state
    for s, w in zip(symbol.tolist(), weight.tolist(), strict=True):
        if s in (INSULT, THREAT):
            held = w
        if (k := emit[at][s]) >= 0:
            out[k] += held
        at = step[at][s]
    return at, held


def cells(texts: list[str | None], lexicon: Lexicon, table=None) -> np.ndarray:
    """Summed weights by cell for each text, from its matched clauses."""
    table = table or grammar()
    out = np.zeros((len(texts), len(CELLS)))
    fresh = (0, 0.0)

    def clauses(w: Words) -> np.ndarray:
        return np.searchsorted(np.flatnonzero(np.isin(w.codes, _BREAKS)), w.start)

    def together(group: list[tuple[int, str]]) -> None:
        """Whole texts: only clauses with an insult or a threat are read."""
        w = Words("\n".join(t for _, t in group), np.cumsum([0, *(len(t) + 1 for _, t in group)])[:-1])
        symbol, weight = lexicon.apply(w)
        hot = np.flatnonzero((symbol == INSULT) | (symbol == THREAT))
        if len(hot):
            clause = clauses(w)
            for c in np.unique(clause[hot]):
                a, b = np.searchsorted(clause, [c, c + 1])
                read_clause(symbol[a:b], weight[a:b], fresh, out[group[w.doc[a]][0]], table)

    def in_pieces(i: int, parts: list[str]) -> None:
        """A long text: a clause that a piece ends in goes on in the next one."""
        state = fresh
        for part in parts:
            w = Words(part, np.zeros(1, np.int64))
            symbol, weight = lexicon.apply(w)
            clause = clauses(w)
            last = int(np.isin(w.codes, _BREAKS).sum())
            hot = np.unique(clause[(symbol == INSULT) | (symbol == THREAT)])
            after = fresh
            for c in np.union1d(hot, [0, last]):
                a, b = np.searchsorted(clause, [c, c + 1])
                done = read_clause(symbol[a:b], weight[a:b], state if c == 0 else fresh, out[i], table)
                after = done if c == last else after
            state = after

    with np.errstate(over="ignore"):
        group: list[tuple[int, str]] = []
        size = 0
        for i, raw in enumerate(texts):
            parts = cut(lowered(raw))
            if len(parts) > 1:
                in_pieces(i, parts)
                continue
            if group and size + len(parts[0]) > PIECE:
                together(group)
                group, size = [], 0
            group.append((i, parts[0]))
            size += len(parts[0]) + 1
        if group:
            together(group)
    return out


def features(x: np.ndarray) -> np.ndarray:
    """Intercept, whether any cell has weight, and the cells on a log scale."""
    return np.column_stack([np.ones(len(x)), (x.sum(1) > 0).astype(float), np.log1p(x)])


def held_out(doc_id):
    """Column: the rows that labels are never learned from."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))


def labelled_sample(docs: DataFrame, labels: DataFrame, per_label: int = SAMPLE_PER_LABEL) -> DataFrame:
    """(doc_id, text, toxic, fold): texts of at most ``per_label`` labelled rows of either label, the first by a hash of the id; held-out rows never."""
    rows = (
        labels.select("doc_id", "toxic").where(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1) & ~held_out(F.col("doc_id")))
        .groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    )
    order = F.xxhash64("doc_id")
    chosen = rows.where("toxic = 1").orderBy(order, "doc_id").limit(per_label).unionAll(rows.where("toxic = 0").orderBy(order, "doc_id").limit(per_label))
    return docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").withColumn("fold", F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(FOLDS)).cast("int"))


def _stems_of(texts: list[str | None]) -> tuple[np.ndarray, ...]:
    """(length, hash, hash of the stem less its last letter, text) of the stems of each text, each once."""
    found: list[tuple] = [(np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64))]
    with np.errstate(over="ignore"):
        for i, t in enumerate(texts):
            for piece in cut(lowered(t)):
                w = Words(piece, np.zeros(1, np.int64))
                for n in STEM_LENGTHS:
                    at = np.flatnonzero(w.end - w.start >= n)
                    u, first = np.unique(w.part(w.start[at], w.start[at] + n), return_index=True)
                    start = w.start[at][first]
                    found.append((np.full(len(u), n), u, w.part(start, start + n - 1), np.full(len(u), i)))
    n, h, up, doc = map(np.concatenate, zip(*found, strict=True))
    order = np.lexsort((doc, h, n))
    n, h, up, doc = n[order], h[order], up[order], doc[order]
    once = np.ones(len(h), bool)
    once[1:] = (h[1:] != h[:-1]) | (n[1:] != n[:-1]) | (doc[1:] != doc[:-1])
    return n[once], h[once], up[once], doc[once]


COUNTS = ("no_0", "yes_0", "no_1", "yes_1")


def _stem_counts(batches):
    """(n, h, up, and the clean and toxic texts of the first and second fold) of the stems in each slice of (text, toxic, fold)."""
    for batch in sliced(batches, 256):
        n, h, up, doc = _stems_of(batch.column(0).to_pylist())
        if not len(h):
            continue
        kind = (batch.column(1).to_numpy() + 2 * batch.column(2).to_numpy())[doc]
        start = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (n[1:] != n[:-1])]))
        sums = [np.add.reduceat((kind == k).astype(np.int64), start) for k in range(4)]
        yield pa.RecordBatch.from_arrays([pa.array(n[start].astype(np.int32)), pa.array(h[start].view(np.int64)), pa.array(up[start].view(np.int64)), *map(pa.array, sums)], names=["n", "h", "up", *COUNTS])


def _g2(yes, no, share: float):
    """G² of a stem's toxic and clean texts against the share of toxic ones; columns or arrays."""
    part = lambda x, p: x * np.log(np.maximum(x, 1e-12) / np.maximum((yes + no) * p, 1e-12))
    return 2 * (part(yes, share) + part(no, 1 - share))


def stem_table(sample: DataFrame) -> tuple[pd.DataFrame, dict[tuple[int, int], int]]:
    """Counts of the at most MOST_STEMS stems that the widest thresholds let through, on the first fold or on the first two; and texts by (fold, label)."""
    totals = {(r["fold"], r["toxic"]): r["n"] for r in sample.groupBy("fold", "toxic").agg(F.count("*").alias("n")).collect()}
    at = lambda folds, label: sum(totals.get((f, label), 0) for f in folds)
    rows = sample.where("fold < 2").select("text", F.col("toxic").cast("int").alias("toxic"), "fold").mapInArrow(_stem_counts, "n int, h bigint, up bigint, " + ", ".join(f"{c} bigint" for c in COUNTS))
    sums = rows.groupBy("n", "h", "up").agg(*(F.sum(c).cast("double").alias(c) for c in COUNTS))
    x = lambda k, p, yes, no: F.when(k > 0, k * F.log(k / ((yes + no) * p))).otherwise(0.0)
    wide = F.lit(False)
    for folds in ((0,), (0, 1)):
        t, c = at(folds, 1), at(folds, 0)
        if t and c:
            yes, no = (sum((F.col(f"{name}_{f}") for f in folds[1:]), F.col(f"{name}_{folds[0]}")) for name in ("yes", "no"))
            share = t / (t + c)
            wide = wide | ((2 * (x(yes, share, yes, no) + x(no, 1 - share, yes, no)) >= min(G2_GRID)) & (yes * c * (1 - min(PRECISION_GRID)) >= min(PRECISION_GRID) * no * t))
    found = sums.where(wide).orderBy(F.desc(F.col("yes_0") + F.col("yes_1")), "n", "h").limit(MOST_STEMS).toPandas()
    return found.sort_values(["n", "h"], ignore_index=True), totals


def _measures(found: pd.DataFrame, totals: dict, folds: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, int, int]:
    """(toxic texts, clean texts, G², precision) of the stems on the folds, and the folds' toxic and clean texts."""
    t, c = (sum(totals.get((f, label), 0) for f in folds) for label in (1, 0))
    yes, no = (sum(found[f"{name}_{f}"].to_numpy(float) for f in folds) for name in ("yes", "no"))
    share = t / max(1, t + c)
    return yes, no, _g2(yes, no, share), yes * c / np.maximum(yes * c + no * t, 1e-12), t, c


def choose_thresholds(sample: DataFrame, found: pd.DataFrame, totals: dict) -> tuple[float, float]:
    """The pair of GRID by whose stems, learned on the first fold, the second fold's labels are told best: the fewest misses and false alarms, as shares of their label; of equals the strictest."""
    yes, no, g2, precision, t, c = _measures(found, totals, (0,))
    tests = totals.get((1, 1), 0), totals.get((1, 0), 0)
    if not len(found) or not t or not c or not all(tests):
        return GRID[-1]
    passes = np.column_stack([(g2 >= g) & (precision >= p) & (yes > 0) for g, p in GRID])
    tables = {n: (part["h"].to_numpy(np.int64).view(np.uint64), part.index.to_numpy()) for n, part in found.groupby("n")}
    tables = {n: (h[o], i[o]) for n, (h, i) in tables.items() for o in (np.argsort(h),)}

    def flagged(batches):
        for batch in sliced(batches, 256):
            hit = np.zeros((batch.num_rows, len(GRID)), bool)
            n, h, _, doc = _stems_of(batch.column(0).to_pylist())
            for length, (keys, index) in tables.items():
                own = n == length
                k = np.minimum(np.searchsorted(keys, h[own]), len(keys) - 1)
                good = keys[k] == h[own]
                np.logical_or.at(hit, doc[own][good], passes[index[k[good]]])
            toxic = batch.column(1).to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(GRID), dtype=np.int32)), pa.array(hit[toxic == 1].sum(0)), pa.array(hit[toxic == 0].sum(0))], names=["cell", "yes", "no"])

    rows = sample.where("fold = 1").select("text", F.col("toxic").cast("int").alias("toxic")).mapInArrow(flagged, "cell int, yes bigint, no bigint").groupBy("cell").agg(F.sum("yes").alias("yes"), F.sum("no").alias("no")).collect()
    cost = {r["cell"]: 1 - r["yes"] / tests[0] + r["no"] / tests[1] for r in rows}
    return GRID[min(cost, key=lambda k: (cost[k], -k))] if cost else GRID[-1]


def learn_stems(sample: DataFrame) -> list[tuple[int, int, float]]:
    """The shortest stems that stand out in the toxic texts of the first two folds, with their log odds."""
    found, totals = stem_table(sample)
    least_g2, least_precision = choose_thresholds(sample, found, totals)
    yes, no, g2, precision, t, c = _measures(found, totals, (0, 1))
    if not t or not c:
        return []
    chosen: dict[tuple[int, int], float] = {}
    covered: set[tuple[int, int]] = set()
    for k in np.flatnonzero((g2 >= least_g2) & (precision >= least_precision) & (yes > 0)):
        n, h, up = (int(found[name][k]) for name in ("n", "h", "up"))
        here, shorter = (n, h & (1 << 64) - 1), (n - 1, up & (1 << 64) - 1)
        if shorter not in covered:
            chosen[here] = float(np.log((yes[k] + 0.5) / (t + 1)) - np.log((no[k] + 0.5) / (c + 1)))
        covered.add(here)
    return [(n, h, min(w, 8.0)) for (n, h), w in chosen.items()]


def fit_logistic(x: np.ndarray, y: np.ndarray, rounds: int = 50) -> np.ndarray:
    """Newton steps to the mode under a normal prior around PRIOR; cell weights stay at least zero."""
    w = PRIOR.copy()
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + (w - PRIOR)
        h = (x * (p * (1 - p))[:, None]).T @ x + np.eye(len(w))
        step = np.linalg.solve(h, g)
        w = w - step
        w[1:] = np.maximum(w[1:], 0)
        if np.abs(step).max() < 1e-9:
            break
    return w


class Model:
    def __init__(self, stems: list[tuple[int, int, float]], weights: np.ndarray):
        self.stems, self.weights = stems, weights


def fit(docs: DataFrame, labels: DataFrame) -> Model:
    """Learns stems and weights from the bounded sample of labelled rows, on different folds of it."""
    ship(docs.sparkSession)
    sample = materialise(labelled_sample(docs, labels), "toxic-sample")
    stems = learn_stems(sample)
    lexicon, table = Lexicon(stems), grammar()

    def measured(batches):
        for b in sliced(batches):
            x = cells(b.column(0).to_pylist(), lexicon, table)
            yield pa.RecordBatch.from_arrays([b.column(1).cast(pa.int32()), *(pa.array(x[:, k]) for k in range(len(CELLS)))], names=["toxic", *CELLS])

    seen: pd.DataFrame = sample.where(f"fold = {FOLDS - 1}").select("text", "toxic").mapInArrow(measured, "toxic int, " + ", ".join(f"{c} double" for c in CELLS)).toPandas()
    discard(sample)
    seen = seen.sort_values(list(seen.columns))
    if not len(seen):
        return Model(stems, PRIOR)
    return Model(stems, fit_logistic(features(seen[list(CELLS)].to_numpy(float)), seen["toxic"].to_numpy(float)))


def score(docs: DataFrame, model: Model) -> DataFrame:
    """All columns of ``docs`` and tox_score, tox_predicted; columns of these names are replaced."""
    ship(docs.sparkSession)
    docs = docs.drop("tox_score", "tox_predicted")
    stems, weights = model.stems, model.weights
    fields = docs.columns

    def scored(batches):
        lexicon, table = Lexicon(stems), grammar()
        for b in sliced(batches):
            x = cells(b.column(fields.index("text")).to_pylist(), lexicon, table)
            p = 1 / (1 + np.exp(-np.clip(features(x) @ weights, -30, 30)))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(p), pa.array((p >= THRESHOLD).astype(np.int32))], names=[*fields, "tox_score", "tox_predicted"])

    from pyspark.sql import types as T

    schema = T.StructType([*docs.schema.fields, T.StructField("tox_score", T.DoubleType()), T.StructField("tox_predicted", T.IntegerType())])
    return docs.mapInArrow(scored, schema)


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    out = score(docs.select("doc_id", "text"), fit(docs, labels))
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("tox_score").alias("score"), F.col("tox_predicted").alias("predicted"))


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents not predicted toxic, with their own columns."""
    model = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score(docs, model).where("tox_predicted = 0").select(*docs.columns)

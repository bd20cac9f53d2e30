"""Toxicity by a weighted finite-state grammar over clauses.

Texts are cut into clauses and words into classes: insult (learned stems and words, each
with a weight), threat, target, negation and reported speech (fixed words below).  Five
small transducers are composed into one grammar.  The first two mark: an insult machine
puts a mark on one insult of the clause, a threat machine on one threat, with more weight
if a target follows within THREAT_REACH words.  What they write is read by the other three, which
weigh the marked clause: a target in it raises the weight, a negation up to NEGATION_REACH words before the mark
lowers it, reported speech lowers it.  A clause's score is the sum of the grammar's weights over
all paths, so over all its marks.  A text's clause scores are summed up into four
features, and a logistic model turns them into a score from 0 to 1.

Learning reads labelled documents only, at most MOST_LABELLED of them (chosen by hash):
stems and words get the lower confidence bound of their log-odds between toxic and clean
texts, counted in two folds, so that the logistic model is fitted on scores from the
other fold's lexicon.  All entries over the bounds below are kept; the lexicon, bounded by
the labelled sample, and the model are broadcast; scoring is narrow.  Every document is
scored, and clauses are whole, however long.

Special cases: null and empty texts have no clause and the score of that; labels without
a document, or with a null label, are ignored, labels of one id that differ count as
toxic; without labels the fixed threat words alone are scored; repeated rows get equal
scores; no rows give none; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
import uuid
from collections import Counter
from functools import reduce
from operator import or_

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import cut
from . import base, textvec
from .near_dedup import shingle_sets
from .transducers import Transducer

MOST_LABELLED, LEAST_BOUND, SHARE_OF_BEST, LEAST_STEM, MOST_STEM = 20_000, 1.0, 0.55, 4, 8
NEGATION_REACH, NEGATED, REPORTED, TARGETED = 3, 0.35, 0.6, 1.25
THREAT_REACH, THREAT, AIMED = 3, 2.0, 1.5
# Word classes of the grammar.
CLASSES = {
    "threat": "kill hurt destroy murder beat shoot burn hang töten umbringen tuer matar",
    "target": "you your yours yourself he she they him her them du dich dein ihr euch sie tu toi vous ton votre tú usted vosotros su",
    "negation": "not no never neither nor isn't aren't don't nicht kein keine nie pas jamais aucun non nunca jamás ni",
    "report": "said says wrote quoted claimed reported according sagte schrieb laut dit écrit selon dijo escribió según",
}
_CLASS_OF = {w: name for name, words in CLASSES.items() for w in words.split()}
_WORD = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)?")
_CLAUSE_END = re.compile(r"[.!?;:\n]")
_COUNTS = {"entry": pa.string(), **{f"{c}{f}": pa.int64() for f in (0, 1) for c in ("toxic", "clean")}}
_COUNTS_SCHEMA = "entry string, toxic0 long, clean0 long, toxic1 long, clean1 long"


def entries_of(text: str) -> set[str]:
    """Lexicon candidates of a text: its words (marked =) and their stems (marked *)."""
    out = set()
    for w in set(_WORD.findall(text.lower())):
        if len(w) >= 3:
            out.add("=" + w)
        for k in range(LEAST_STEM, min(MOST_STEM, len(w)) + 1):
            out.add("*" + w[:k])
    return out


# Word classes as symbols: other, insult, threat, target, negation, report; a mark is upper-case.
SYMBOLS = "oitgnr"
_SYMBOL_OF = {"threat": "t", "target": "g", "negation": "n", "report": "r"}


def _same(state: int, symbols: str = SYMBOLS, to: int | None = None, weight: float = 1.0):
    return [(state, s, s, state if to is None else to, weight) for s in symbols]


def insults() -> Transducer:
    """Marks one insult of the clause, or none; an insult's own weight comes on top when it is read."""
    return Transducer(2, [*_same(0), (0, "i", "I", 1, 1.0), *_same(1)], {0: 1.0, 1: 1.0})


def threats() -> Transducer:
    """Passes what is marked already, or marks one threat; aimed if a target follows within THREAT_REACH words.

    States: nothing marked, marked before, marked here and not aimed, then marked here with 1.. words to go."""
    arcs = [*_same(0), (0, "I", "I", 1, 1.0), *_same(1), (0, "t", "T", 2, THREAT), *_same(2)]
    arcs.append((0, "t", "T", 3, THREAT * (AIMED - 1)))  # the surplus of an aimed threat is a path of its own
    for gone in range(THREAT_REACH):
        arcs += _same(3 + gone, SYMBOLS.replace("g", ""), min(4 + gone, 3 + THREAT_REACH))
        arcs.append((3 + gone, "g", "g", 4 + THREAT_REACH, 1.0))
    arcs += _same(4 + THREAT_REACH)
    return Transducer(5 + THREAT_REACH, arcs, {1: 1.0, 2: 1.0, 4 + THREAT_REACH: 1.0})


def _present(symbol: str, weight: float) -> Transducer:
    """Multiplies by weight if the symbol stands anywhere in the clause."""
    every = SYMBOLS + "IT"
    return Transducer(2, [*_same(0, every.replace(symbol, "")), (0, symbol, symbol, 1, 1.0), *_same(1, every)], {0: 1.0, 1: weight})


def targets() -> Transducer:
    return _present("g", TARGETED)


def negations() -> Transducer:
    """Lowers the weight of a mark that stands up to NEGATION_REACH words after a negation."""
    arcs = []
    for left in range(NEGATION_REACH + 1):  # words that the last negation still reaches
        arcs += _same(left, SYMBOLS.replace("n", ""), max(left - 1, 0))
        arcs.append((left, "n", "n", NEGATION_REACH, 1.0))
        arcs += _same(left, "IT", max(left - 1, 0), NEGATED if left else 1.0)
    return Transducer(NEGATION_REACH + 1, arcs, {s: 1.0 for s in range(NEGATION_REACH + 1)})


def reports() -> Transducer:
    return _present("r", REPORTED)


def grammar() -> Transducer:
    """The composed machine: a clause's symbols to the sum over its marks."""
    out = insults()
    for machine in (threats(), targets(), negations(), reports()):
        out = out.then(machine)
    return out


class Grammar:
    """Scans texts with a lexicon {entry: weight}."""

    def __init__(self, lexicon: dict[str, float]):
        import ahocorasick

        machine = grammar()
        self.final = machine.final
        self.step = {s: machine.reading(s) for s in SYMBOLS}
        plain = sum(m for (read, written), m in machine.arcs.items() if read == written == "i")
        self.unmarked, self.marked = plain, self.step["i"] - plain
        # after NEGATION_REACH + THREAT_REACH other words, more of them change nothing
        self.others = [np.linalg.matrix_power(self.step["o"], k) for k in range(NEGATION_REACH + THREAT_REACH + 2)]
        self.automaton = ahocorasick.Automaton()
        self.weights: dict[str, tuple[float, float]] = {}
        for entry, weight in lexicon.items():
            word = entry[1:]
            stem, whole = self.weights.get(word, (0.0, 0.0))
            self.weights[word] = (max(stem, weight), whole) if entry[0] == "*" else (stem, max(whole, weight))
        for word in CLASSES["threat"].split():
            self.weights.setdefault(word, (0.0, 0.0))
        for word in self.weights:
            self.automaton.add_word(word, word)
        self.automaton.make_automaton()

    def hits(self, text: str) -> dict[int, float]:
        """Starts of words of a lower-cased text that an entry fits or that threaten, and their weight as insults."""
        out: dict[int, float] = {}
        for last, word in self.automaton.iter(text):
            start = last + 1 - len(word)
            if start and (text[start - 1].isalpha() or text[start - 1] == "'"):
                continue
            stem, whole = self.weights[word]
            ends = last + 1 == len(text) or not text[last + 1].isalpha()
            weight = max(stem, whole if ends else 0.0)
            if weight or ends and _CLASS_OF.get(word) == "threat":
                out[start] = max(weight, out.get(start, 0.0))
        return out

    def clause(self, words: list[tuple[str, float]]) -> float:
        """Weight that the grammar gives to a clause of (word, weight as an insult)."""
        state, run = np.eye(len(self.final))[0], 0
        for word, weight in words:
            symbol = "i" if weight else _SYMBOL_OF.get(_CLASS_OF.get(word), "o")
            if symbol == "o":
                run += 1
                continue
            if run:
                state, run = state @ self.others[min(run, len(self.others) - 1)], 0
            state = state @ (self.unmarked + weight * self.marked if symbol == "i" else self.step[symbol])
        if run:
            state = state @ self.others[min(run, len(self.others) - 1)]
        return float(state @ self.final)

    def clauses(self, low: str) -> list[float]:
        """Scores of the clauses of a lower-cased text that hold an entry or a threat."""
        hits = self.hits(low)
        out, done = [], 0
        for start in sorted(hits):
            if start < done:
                continue
            begin = max(done, *(low.rfind(c, done, start) + 1 for c in ".!?;:\n"))
            end = _CLAUSE_END.search(low, start)
            done = max(end.start() if end else len(low), start + 1)
            out.append(self.clause([(m[0], hits.get(m.start(), 0.0)) for m in _WORD.finditer(low, begin, done)]))
        return out

    def features(self, text: str) -> tuple[float, float, float, float]:
        """Of a text: 1 if any clause matched, log of the sum, the best clause, log of the number."""
        scores = [s for s in self.clauses(text.lower()) if s > 0]
        if not scores:
            return 0.0, 0.0, 0.0, 0.0
        return 1.0, math.log1p(sum(scores)), max(scores), math.log1p(len(scores))


def pick_lexicon(rows: list, folds: tuple[int, ...], totals: dict[str, int]) -> dict[str, float]:
    """Entries whose log-odds have a lower bound over LEAST_BOUND; stems stand for longer ones."""
    t = sum(totals[f"toxic{f}"] for f in folds)
    c = sum(totals[f"clean{f}"] for f in folds)
    bound = {}
    for row in rows:
        x, y = sum(row[f"toxic{f}"] for f in folds), sum(row[f"clean{f}"] for f in folds)
        if x >= 2:
            odds = math.log((x + 0.5) / (t + 1)) - math.log((y + 0.5) / (c + 1))
            low = odds - 1.64 * math.sqrt(1 / (x + 0.5) + 1 / (y + 0.5))
            if low >= LEAST_BOUND:
                bound[row["entry"]] = low
    # what copies are left lift their rare words together, but not to where true signs stand
    least = SHARE_OF_BEST * max(bound.values(), default=0.0)
    bound = {e: v for e, v in bound.items() if v >= least}
    kept = {}
    for entry in sorted(bound, key=lambda e: (len(e), e)):
        word = entry[1:]
        shorter = [f"*{word[:k]}" for k in range(LEAST_STEM, len(word) + (entry[0] == "="))]
        if not any(kept.get(s, -1.0) >= bound[entry] - 0.25 for s in shorter):
            kept[entry] = bound[entry]
    return kept


def _promising(counted: DataFrame, totals: dict[str, int]) -> DataFrame:
    """The rows whose lower bound reaches LEAST_BOUND and SHARE_OF_BEST in a fold or in both; as pick_lexicon asks."""
    names = []
    for folds in ((0, 1), (0,), (1,)):
        t, c = (sum(totals[f"{k}{f}"] for f in folds) for k in ("toxic", "clean"))
        x, y = (sum((F.col(f"{k}{f}") for f in folds), F.lit(0)) for k in ("toxic", "clean"))
        odds = F.log((x + 0.5) / (t + 1)) - F.log((y + 0.5) / (c + 1))
        low = odds - 1.64 * F.sqrt(1 / (x + 0.5) + 1 / (y + 0.5))
        names.append("b" + "".join(map(str, folds)))
        counted = counted.withColumn(names[-1], F.when((x >= 2) & (low >= LEAST_BOUND), low))
    best = counted.agg(*[F.max(n).alias(n) for n in names]).first()
    reach = [F.col(n) >= SHARE_OF_BEST * best[n] - 1e-9 for n in names if best[n] is not None]
    return counted.where(reduce(or_, reach, F.lit(False))).drop(*names)


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2) -> np.ndarray:
    """Weights (bias first) by Newton steps on scaled features."""
    a = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(a.shape[1])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        grad = a.T @ (p - y) + ridge * w
        hess = (a * (p * (1 - p))[:, None]).T @ a + ridge * np.eye(len(w))
        step = np.linalg.solve(hess, grad)
        w = w - step
        if np.abs(step).max() < 1e-8:
            break
    return w


DEFAULT_MODEL = (-3.0, 2.0, 1.0, 0.2, 0.2)


def is_held_out(doc_id) -> object:
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0


def learn(docs: DataFrame, labels: DataFrame) -> tuple[dict[str, float], tuple[float, ...]]:
    """(lexicon, logistic weights) from labelled documents that are not held out."""
    sc = docs.sparkSession.sparkContext
    known = labels.where("toxic is not null and doc_id is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    known = known.where(~is_held_out("doc_id"))
    total = known.count()
    if total > MOST_LABELLED:
        known = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(1_000_000 * MOST_LABELLED / total))
    sample = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(known), "doc_id")
    sample = sample.withColumn("fold", F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(2)).cast("int"))

    def outline(data, offsets, rows):
        value, first = shingle_sets(data, offsets, 3)
        cols = {}
        for name, salt in (("m0", 0x1F0F), ("m1", 0x2E1E)):
            mixed = np.append(textvec.mix(value ^ np.uint64(salt)), np.uint64(0))
            low = np.minimum.reduceat(mixed, first[:-1]) if len(first) > 1 else mixed[:0]
            cols[name] = np.where(np.diff(first) > 0, low, np.uint64(0))
        return base.batch({"doc_id": pa.int64(), "m0": pa.int64(), "m1": pa.int64()}, doc_id=rows.column(0), **cols)

    # copies and near copies would count again and again: one of each stays in the sample
    kept = base.over_texts(sample, outline, "doc_id long, m0 long, m1 long", "doc_id")
    for m in ("m0", "m1"):
        kept = kept.groupBy(m).agg(F.min_by(F.struct("doc_id", "m0", "m1"), "doc_id").alias("r")).select("r.*")
    sample = sample.join(F.broadcast(kept.select("doc_id")), "doc_id")

    def count(data, offsets, rows):
        seen: dict[str, list[int]] = {}
        toxic, fold = rows.column(0).to_pylist(), rows.column(1).to_pylist()
        size = Counter((t, f) for t, f in zip(toxic, fold))
        for text, t, f in zip(base.as_texts(data, offsets), toxic, fold):
            for e in entries_of(text):
                seen.setdefault(e, [0, 0, 0, 0])[2 * f + (1 - t)] += 1
        seen[""] = [size[1, 0], size[0, 0], size[1, 1], size[0, 1]]
        cols = list(zip(*seen.values()))
        return base.batch(_COUNTS, entry=list(seen), toxic0=cols[0], clean0=cols[1], toxic1=cols[2], clean1=cols[3])

    counted = base.over_texts(sample, count, _COUNTS_SCHEMA, "toxic", "fold", most=8 << 20)
    counted = counted.groupBy("entry").agg(*[F.sum(c).alias(c) for c in ("toxic0", "clean0", "toxic1", "clean1")])
    counted = cut(counted)
    totals = counted.where("entry = ''").collect()
    if not totals:
        return {}, DEFAULT_MODEL
    totals = totals[0].asDict()
    rows = [r.asDict() for r in _promising(counted.where("entry <> ''"), totals).collect()]
    lexicon = pick_lexicon(rows, (0, 1), totals)
    crossed = sc.broadcast([pick_lexicon(rows, (1,), totals), pick_lexicon(rows, (0,), totals)])

    def features(data, offsets, rows):
        grammars = [Grammar(x) for x in crossed.value]
        toxic, fold = rows.column(0).to_pylist(), rows.column(1).to_pylist()
        found = [grammars[f].features(t) for t, f in zip(base.as_texts(data, offsets), fold)]
        cols = list(zip(*found))
        return base.batch({**{f"x{i}": pa.float64() for i in range(4)}, "toxic": pa.int32()}, **{f"x{i}": cols[i] for i in range(4)}, toxic=toxic)

    got = base.over_texts(sample, features, "x0 double, x1 double, x2 double, x3 double, toxic int", "toxic", "fold", most=8 << 20).toPandas()
    y = got["toxic"].to_numpy(float)
    if not 0 < y.sum() < len(y):
        return lexicon, DEFAULT_MODEL
    return lexicon, tuple(float(v) for v in fit_logistic(got[["x0", "x1", "x2", "x3"]].to_numpy(float), y))


_built: dict[str, Grammar] = {}
_SCORES = {"doc_id": pa.int64(), "score": pa.float64()}


def _scorer(spark: SparkSession, lexicon: dict[str, float], model: tuple[float, ...]):
    """scores(data, offsets) for Python workers; lexicon and model are broadcast."""
    packed = spark.sparkContext.broadcast((lexicon, model))
    name = uuid.uuid4().hex

    def scores(data, offsets):
        words, weights = packed.value
        if name not in _built:
            _built.clear()
            _built[name] = Grammar(words)
        w = np.array(weights)
        x = np.array([_built[name].features(t) for t in base.as_texts(data, offsets)]).reshape(-1, 4)
        return 1 / (1 + np.exp(-np.clip(w[0] + x @ w[1:], -30, 30)))

    return scores


def score(docs: DataFrame, lexicon: dict[str, float], model: tuple[float, ...]) -> DataFrame:
    """doc_id, held_out, score, predicted of every document; narrow, no shuffle."""
    scores = _scorer(docs.sparkSession, lexicon, model)

    def run(data, offsets, rows):
        return base.batch(_SCORES, doc_id=rows.column(0), score=scores(data, offsets))

    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    out = base.over_texts(df, run, "doc_id long, score double", "doc_id")
    return out.select("doc_id", F.coalesce(is_held_out("doc_id"), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def keep_clean(docs: DataFrame, lexicon: dict[str, float], model: tuple[float, ...]) -> DataFrame:
    """The rows of docs, all columns, whose score is under 0.5; narrow."""
    scores = _scorer(docs.sparkSession, lexicon, model)
    return base.filter_texts(docs, lambda data, offsets: scores(data, offsets) < 0.5)


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = base.table(spark, sf_dir, "documents", "doc_id", "text")
    return score(docs, *learn(docs, base.table(spark, sf_dir, "labels", "doc_id", "toxic")))

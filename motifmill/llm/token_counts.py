"""Count-only Viterbi segmentation over a unigram vocabulary.

An Aho-Corasick automaton lists every vocabulary piece in a segment; dynamic programming
over segment ends carries the best score and its number of pieces, no path.  Tie rules
are those of the public unigram tokenizer: at one end the earliest start is taken first
and only a strictly better score replaces it; a character without a piece of its own may
be unknown at (least score - 10), and counts one piece per UTF-8 byte (byte fallback).
Each space becomes a word mark and one is put in front of the text.  No piece continues
past a mark, so texts fall into independent segments and each distinct segment of a
worker is solved once (at most REMEMBERED are remembered).

Special cases: null and empty texts have the lone mark as their only segment, as the
tokenizer would give for an empty text with a mark; every row is counted by itself;
no rows give none; extra columns are ignored; a null doc_id stays null.
"""

from __future__ import annotations

import hashlib
import math
import pickle
import re

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import base

MARK, PENALTY, REMEMBERED = "▁", 10.0, 600_000
DEFAULT_FILE = "piece_bpe_32k.model"
_SEGMENT = re.compile(MARK + "+[^" + MARK + "]*")


def default_vocabulary() -> list[tuple[str, float]]:
    """(piece, score) of the public piece vocabulary."""
    import public_tokenizers
    import sentencepiece

    m = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(DEFAULT_FILE))
    return [(m.id_to_piece(i), m.get_score(i)) for i in range(m.vocab_size())]


class Counter:
    def __init__(self, vocabulary: list[tuple[str, float]]):
        import ahocorasick

        self.automaton = ahocorasick.Automaton()
        for piece, score in vocabulary:
            if piece:
                if MARK in piece.lstrip(MARK):
                    raise ValueError(f"a piece continues past a mark: {piece!r}")
                self.automaton.add_word(piece, (len(piece), score))
        self.automaton.make_automaton()
        self.unknown = min(s for _, s in vocabulary) - PENALTY
        self.count: dict[str, int] = {}
        self.score: dict[str, float] = {}

    def solve(self, segment: str) -> tuple[int, float]:
        n = len(segment)
        best, pieces = [-math.inf] * (n + 1), [0] * (n + 1)
        best[0] = 0.0
        at = 1  # ends below it are final

        def unknown(end: int) -> None:
            value = best[end - 1] + self.unknown
            if value > best[end]:
                best[end], pieces[end] = value, pieces[end - 1] + len(segment[end - 1].encode())

        single = False
        for last, (size, score) in self.automaton.iter(segment):
            end = last + 1
            while at < end:
                if not single:
                    unknown(at)
                at, single = at + 1, False
            value = best[end - size] + score
            if value > best[end]:
                best[end], pieces[end] = value, pieces[end - size] + 1
            single = single or size == 1
        while at <= n:
            if not single:
                unknown(at)
            at, single = at + 1, False
        return pieces[n], best[n]

    def text(self, text: str) -> tuple[int, float]:
        """(number of pieces, best score) of a whole text."""
        segments = _SEGMENT.findall(MARK + text.replace(" ", MARK))
        if len(self.count) > REMEMBERED:
            self.count.clear()
            self.score.clear()
        count, score = self.count, self.score
        for s in dict.fromkeys(segments):
            if s not in count:
                count[s], score[s] = self.solve(s)
        return sum(map(count.__getitem__, segments)), math.fsum(map(score.__getitem__, segments))


_built: dict[bytes, Counter] = {}
_SCHEMA = {"doc_id": pa.int64(), "n_tokens": pa.int64(), "best_score": pa.float64()}


def count_tokens(docs: DataFrame, vocabulary: list[tuple[str, float]]) -> DataFrame:
    """doc_id, n_tokens, best_score; narrow, no shuffle.  The vocabulary is broadcast."""
    packed = docs.sparkSession.sparkContext.broadcast(pickle.dumps(vocabulary))

    def run(data, offsets, rows):
        key = hashlib.md5(packed.value).digest()
        if key not in _built:
            _built.clear()
            _built[key] = Counter(pickle.loads(packed.value))
        found = [_built[key].text(t) for t in base.as_texts(data, offsets)]
        return base.batch(_SCHEMA, doc_id=rows.column(0), n_tokens=[n for n, _ in found], best_score=[s for _, s in found])

    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return base.over_texts(df, run, "doc_id long, n_tokens long, best_score double", "doc_id")


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(base.table(spark, sf_dir, "documents", "doc_id", "text"), default_vocabulary())

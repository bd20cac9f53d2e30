"""Byte-level BPE encoding and decoding over padded numpy matrices.

Distinct pre-tokens of many texts are put into matrices, one per length bucket.  In each
round every row merges its leftmost pair of least rank, found by a hashed pair table;
the row is compacted, and rows without a mergeable pair leave the matrix.  Pre-tokens
beyond LONG bytes go through a heap instead, whose work is n log n.  Ids of a text are
gathered from its pre-tokens' ids; decoding gathers bytes by id.

Special cases: null and empty texts have no tokens and the SHA-256 of nothing; every row
is encoded by itself, so repeated rows and ties repeat; no rows give none; extra columns
are ignored; a null doc_id stays null; a very long text is taken through in runs of
pre-tokens, so memory stays bounded by RUN pre-tokens and the text itself.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship
from . import base, textvec

LONG, RUN, REMEMBERED = 256, 400_000, 400_000
NONE = np.int32(2**31 - 1)
DEFAULT_FILE = "byte_bpe_50k.tiktoken"


def default_vocabulary() -> tuple[bytes, str]:
    """(rank file, splitting pattern) of the public byte-level vocabulary."""
    import public_tokenizers

    with open(public_tokenizers.path(DEFAULT_FILE), "rb") as f:
        return f.read(), public_tokenizers.PATTERN


class PairTable:
    """Open addressing from (left id, right id) to the id, and rank, of their join."""

    def __init__(self, pairs: np.ndarray, ranks: np.ndarray):
        self.bits = max(4, int(len(pairs) * 4 - 1).bit_length())
        size = 1 << self.bits
        self.keys, self.ranks = np.full(size, -1, np.int64), np.full(size, NONE, np.int32)
        self.mask = size - 1
        todo, at = np.arange(len(pairs)), self._slot(pairs)
        while len(todo):
            free = self.keys[at] < 0
            slots, who = np.unique(at[free], return_index=True)
            mine = todo[free][who]
            self.keys[slots], self.ranks[slots] = pairs[mine], ranks[mine]
            left = self.keys[at] != pairs[todo]
            todo, at = todo[left], (at[left] + 1) & self.mask

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Ranks of the joins; NONE where there is none or an id is padding (-1)."""
        keys = (left.astype(np.int64) << 32) | right.astype(np.int64)
        keys[(left < 0) | (right < 0)] = -2
        at = self._slot(keys)
        got = self.keys[at]
        out = np.where(got == keys, self.ranks[at], NONE)
        todo = np.flatnonzero((got != keys) & (got >= 0) & (keys >= 0))
        at = at[todo]
        while len(todo):
            at = (at + 1) & self.mask
            got = self.keys[at]
            hit = got == keys[todo]
            out[todo[hit]] = self.ranks[at[hit]]
            more = ~hit & (got >= 0)
            todo, at = todo[more], at[more]
        return out


class ByteBpe:
    def __init__(self, rank_file: bytes, pattern: str):
        import regex

        self.split = regex.compile(pattern)
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in rank_file.splitlines() if line)}
        self.by_bytes = ranks
        self.of_byte = np.array([ranks[bytes([b])] for b in range(256)], np.int32)
        keys, values = [], []
        for token, rank in ranks.items():
            for i in range(1, len(token)):
                a, b = ranks.get(token[:i]), ranks.get(token[i:])
                if a is not None and b is not None:
                    keys.append(a << 32 | b)
                    values.append(rank)
        self.pairs = PairTable(np.array(keys, np.int64), np.array(values, np.int32))
        top = max(ranks.values()) + 1
        parts = [b""] * top
        for token, rank in ranks.items():
            parts[rank] = token
        self.blob = np.frombuffer(b"".join(parts), np.uint8)
        self.width = np.array([len(x) for x in parts], np.int64)
        self.start = np.concatenate([[0], np.cumsum(self.width)])[:-1]
        self.forget()

    def forget(self) -> None:
        self.known: dict[str, int] = {}
        self.flat, self.offs = np.zeros(0, np.int32), np.zeros(1, np.int64)

    # -- merging ---------------------------------------------------------

    def _merge_matrix(self, m: np.ndarray, rows: np.ndarray, done: list) -> None:
        """m: ids, a row for each pre-token, padded with -1 on the right."""
        r = self.pairs.find(m[:, :-1].ravel(), m[:, 1:].ravel()).reshape(len(m), -1) if m.shape[1] > 1 else np.full((len(m), 1), NONE)
        while True:
            at = r.argmin(axis=1)
            least = r[np.arange(len(r)), at]
            stop = least == NONE
            if stop.any():
                done.append((rows[stop], m[stop]))
                go = ~stop
                m, r, rows, at, least = m[go], r[go], rows[go], at[go], least[go]
            if not len(m):
                return
            if m.shape[1] == 2:
                done.append((rows, least[:, None]))
                return
            n, w = m.shape
            line = np.arange(n)
            m[line, at] = least
            shift = np.arange(w - 1)[None, :]
            m = np.take_along_axis(m, shift + (shift > at[:, None]), axis=1)
            shift = shift[:, : w - 2]
            r = np.take_along_axis(r, shift + (shift > at[:, None]), axis=1)
            left = np.flatnonzero(at > 0)
            r[left, at[left] - 1] = self.pairs.find(m[left, at[left] - 1], m[left, at[left]])
            right = np.flatnonzero(at < w - 2)
            r[right, at[right]] = self.pairs.find(m[right, at[right]], m[right, at[right] + 1])

    def _merge_long(self, token: bytes) -> list[int]:
        n = len(token)
        parts: list[bytes | None] = [token[i : i + 1] for i in range(n)]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        rank = self.by_bytes.get
        heap = [(k, i, 2) for i in range(n - 1) if (k := rank(token[i : i + 2])) is not None]
        heapq.heapify(heap)
        while heap:
            k, i, size = heapq.heappop(heap)
            if parts[i] is None or (j := after[i]) >= n or len(parts[i]) + len(parts[j]) != size or rank(parts[i] + parts[j]) != k:
                continue
            parts[i] += parts[j]
            parts[j] = None
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
                if (k := rank(x := parts[i] + parts[after[i]])) is not None:
                    heapq.heappush(heap, (k, i, len(x)))
            if before[i] >= 0 and (k := rank(x := parts[before[i]] + parts[i])) is not None:
                heapq.heappush(heap, (k, before[i], len(x)))
        return [rank(p) for p in parts if p is not None]

    def merge(self, tokens: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids, offsets) of each pre-token."""
        size = np.fromiter(map(len, tokens), np.int64, len(tokens))
        start = np.concatenate([[0], np.cumsum(size)])
        data = self.of_byte[np.frombuffer(b"".join(tokens), np.uint8)]
        bucket = np.where(size <= 24, size, np.where(size <= LONG, 1 << np.ceil(np.log2(np.maximum(size, 1))).astype(np.int64), LONG + 1))
        done: list[tuple[np.ndarray, np.ndarray]] = []
        for w in np.unique(bucket):
            rows = np.flatnonzero(bucket == w)
            if w > LONG:
                done += [(np.array([i]), np.array([self._merge_long(tokens[i])], np.int32)) for i in rows]
            elif w:
                col = np.arange(w)[None, :]
                inside = col < size[rows][:, None]
                m = np.where(inside, data[np.minimum(start[rows][:, None] + col, len(data) - 1)], np.int32(-1))
                self._merge_matrix(m, rows, done)
        count = np.zeros(len(tokens), np.int64)
        for rows, ids in done:
            count[rows] = (ids >= 0).sum(axis=1)
        offs = np.concatenate([[0], np.cumsum(count)])
        flat = np.empty(offs[-1], np.int32)
        for rows, ids in done:
            keep = ids >= 0
            col = np.broadcast_to(np.arange(ids.shape[1])[None, :], ids.shape)
            flat[(offs[rows][:, None] + col)[keep]] = ids[keep]
        return flat, offs

    # -- texts -----------------------------------------------------------

    def encode_tokens(self, tokens: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids, number of ids of each pre-token); distinct pre-tokens are merged once."""
        if len(self.known) > REMEMBERED:
            self.forget()
        known, fresh = self.known, []
        for t in dict.fromkeys(tokens):
            if t not in known:
                known[t] = len(known)
                fresh.append(t.encode())
        if fresh:
            flat, offs = self.merge(fresh)
            self.offs = np.concatenate([self.offs, offs[1:] + self.offs[-1]])
            self.flat = np.concatenate([self.flat, flat])
        which = np.fromiter(map(known.__getitem__, tokens), np.int64, len(tokens))
        a = self.offs[which]
        n = self.offs[which + 1] - a
        return gather(self.flat, a, n), n

    def runs(self, texts):
        """(index, ids) of each text, a long text in several parts."""
        tokens, owners = [], []
        for i, text in enumerate(texts):
            it = self.split.finditer(text) if len(text) > RUN else None
            while True:
                part = self.split.findall(text) if it is None else [m[0] for m in islice(it, RUN)]
                tokens += part
                owners.append((i, len(part)))
                if len(tokens) >= RUN:
                    yield from self._flush(tokens, owners)
                    tokens, owners = [], []
                if it is None or not part:
                    break
        yield from self._flush(tokens, owners)

    def _flush(self, tokens, owners):
        ids, n = self.encode_tokens(tokens) if tokens else (np.zeros(0, np.int32), np.zeros(0, np.int64))
        ends = np.concatenate([[0], np.cumsum(n)])
        at = 0
        for i, count in owners:
            yield i, ids[ends[at] : ends[at + count]]
            at += count

    def decode(self, ids: np.ndarray) -> np.ndarray:
        return gather(self.blob, self.start[ids], self.width[ids])


def gather(flat: np.ndarray, start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """Concatenation of flat[start:start+count] over all rows."""
    ends = np.cumsum(count)
    total = int(ends[-1]) if len(ends) else 0
    return flat[np.repeat(start - (ends - count), count) + np.arange(total)]


_built: dict[tuple, ByteBpe] = {}


def _bpe(rank_file: bytes, pattern: str) -> ByteBpe:
    key = (hashlib.md5(rank_file).digest(), pattern)
    if key not in _built:
        _built.clear()
        _built[key] = ByteBpe(rank_file, pattern)
    return _built[key]


_DIGESTS = {"doc_id": pa.int64(), "n_tokens": pa.int64(), "ids_sha256": pa.string(), "decoded_sha256": pa.string()}


def token_digests(docs: DataFrame, rank_file: bytes, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256; narrow, no shuffle."""
    vocabulary = docs.sparkSession.sparkContext.broadcast((rank_file, pattern))

    def run(data, offsets, rows):
        bpe = _bpe(*vocabulary.value)
        n = len(offsets) - 1
        count, a, b = [0] * n, [hashlib.sha256() for _ in range(n)], [hashlib.sha256() for _ in range(n)]
        for i, ids in bpe.runs(base.as_texts(data, offsets)):
            count[i] += len(ids)
            a[i].update(ids.astype("<u4"))
            b[i].update(bpe.decode(ids))
        return base.batch(_DIGESTS, doc_id=rows.column(0), n_tokens=count, ids_sha256=[x.hexdigest() for x in a], decoded_sha256=[x.hexdigest() for x in b])

    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return base.over_texts(df, run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", "doc_id")


def encode(docs: DataFrame, rank_file: bytes, pattern: str) -> DataFrame:
    """doc_id and ids array<int> of every text."""
    vocabulary = docs.sparkSession.sparkContext.broadcast((rank_file, pattern))

    def run(data, offsets, rows):
        parts: list[list] = [[] for _ in range(len(offsets) - 1)]
        for i, ids in _bpe(*vocabulary.value).runs(base.as_texts(data, offsets)):
            parts[i].append(ids)
        ids = [np.concatenate(p) if p else np.zeros(0, np.int32) for p in parts]
        return base.batch({"doc_id": pa.int64(), "ids": pa.list_(pa.int32())}, doc_id=rows.column(0), ids=ids)

    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return base.over_texts(df, run, "doc_id long, ids array<int>", "doc_id")


_ROUND = {"doc_id": pa.int64(), "n_tokens": pa.int64(), "ids": pa.list_(pa.int32()), "restored": pa.bool_()}


def round_trip(docs: DataFrame, rank_file: bytes, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids, and restored: whether the decoded ids are the text's bytes."""
    vocabulary = docs.sparkSession.sparkContext.broadcast((rank_file, pattern))

    def run(data, offsets, rows):
        bpe = _bpe(*vocabulary.value)
        parts: list[list] = [[] for _ in range(len(offsets) - 1)]
        for i, ids in bpe.runs(base.as_texts(data, offsets)):
            parts[i].append(ids)
        ids = [np.concatenate(p) if p else np.zeros(0, np.int32) for p in parts]
        same = [np.array_equal(bpe.decode(x), data[a:b]) for x, a, b in zip(ids, offsets[:-1], offsets[1:])]
        return base.batch(_ROUND, doc_id=rows.column(0), n_tokens=[len(x) for x in ids], ids=ids, restored=same)

    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return base.over_texts(df, run, "doc_id long, n_tokens long, ids array<int>, restored boolean", "doc_id")


def decode(encoded: DataFrame, rank_file: bytes, pattern: str) -> DataFrame:
    """doc_id and text of encoded(doc_id, ids)."""
    ship(encoded.sparkSession)
    vocabulary = encoded.sparkSession.sparkContext.broadcast((rank_file, pattern))

    def run(batches):
        bpe = _bpe(*vocabulary.value)
        for batch in batches:
            texts = [bpe.decode(np.asarray(ids or [], np.int64)).tobytes().decode("utf-8", "replace") for ids in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select(F.col("doc_id").cast("long").alias("doc_id"), "ids").mapInArrow(run, "doc_id long, text string")


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_digests(base.table(spark, sf_dir, "documents", "doc_id", "text"), *default_vocabulary())

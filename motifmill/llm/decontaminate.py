"""Benchmark decontamination: edit-tolerant search of benchmark items in documents.

Items and documents are sequences of words (runs of letters, digits and non-ASCII bytes,
lower-cased A-Z; case and punctuation do not count).  A passage matches an item when
their word edit distance is at most EDITS of the item's length.  Search: a random walk
per repetition (CGK: at each step emit the current word and move on if a hash of step and
word says so) embeds edit distance into Hamming distance; sampled positions of the walk
are hashed to LSH keys; windows that share a key with an item of their length are
candidates; exact edit distance to the best passage of the window and its surroundings
decides.
Only windows around enough three-word sequences of the item are embedded: a match keeps
at least n - 2 - 3k of them near its place (one, of at most three words, by the
pigeonhole rule for short items), so this loses no match.

RECALL of the LSH at the largest tolerated distance follows from REPEATS, SAMPLES and the
walks; items are kept in blocks of at most BLOCK_BYTES, each broadcast in its turn, so
that nothing broadcast grows with the data.  Documents are never shuffled.

Special cases: null or empty texts and items without words match nothing; repeated items
are reported each by its id; repeated documents each by its row; no rows give none; extra
columns are ignored; a null doc_id is reported as null.
"""

from __future__ import annotations

import pickle
import uuid
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import base, textvec

EDITS, GRAM, WALKS, REPEATS, SAMPLES, BLOCK_BYTES = 0.2, 3, 6, 8, 2, 8 << 20
_PAD = np.uint64(0)
#: bytes as they are compared: A-Z lower-cased, ASCII punctuation and control characters as space
FOLD = textvec.LOWER.copy()
FOLD[[b for b in range(128) if not chr(b).isalnum()]] = 0x20


def walk(rows: np.ndarray, seed: int) -> np.ndarray:
    """CGK embedding of equal-length sequences (rows of word hashes) to thrice the length."""
    n, size = rows.shape
    out = np.full((n, 3 * size), _PAD, np.uint64)
    at, line = np.zeros(n, np.int64), np.arange(n)
    for step in range(3 * size):
        live = at < size
        x = np.where(live, rows[line, np.minimum(at, size - 1)], _PAD)
        out[:, step] = x
        bit = textvec.mix(x ^ np.uint64((seed * 1_000_003 + step) * 2 + 1)) >> np.uint64(63)
        at += live & (bit == 1)
    return out


def lsh_keys(rows: np.ndarray, walks: int = WALKS, repeats: int = REPEATS, samples: int = SAMPLES) -> np.ndarray:
    """(sequences x walks*repeats) keys from sampled positions of the walks."""
    size = rows.shape[1]
    keys = np.empty((len(rows), walks * repeats), np.uint64)
    for w in range(walks):
        embedded = walk(rows, w)
        for r in range(repeats):
            rng = np.random.default_rng((size, w, r))
            key = np.full(len(rows), w * repeats + r + 1, np.uint64)
            for p in rng.choice(3 * size, min(samples, 3 * size), replace=False):
                key = textvec.mix(key * np.uint64(0x9E3779B97F4A7C15) + embedded[:, p])
            keys[:, w * repeats + r] = key
    return keys


def substring_distances(items: np.ndarray, regions: np.ndarray) -> np.ndarray:
    """Exact least edit distance of each row of items to any substring of its region."""
    n, width = len(regions), regions.shape[1]
    col = np.arange(width + 1, dtype=np.int32)
    row = np.zeros((n, width + 1), np.int32)
    for i in range(items.shape[1]):
        new = np.empty_like(row)
        new[:, 0] = i + 1
        new[:, 1:] = np.minimum(row[:, :-1] + (regions != items[:, i : i + 1]), row[:, 1:] + 1)
        row = np.minimum.accumulate(new - col, axis=1) + col
    return row.min(axis=1)


def tolerated(n: int, edits: float = EDITS) -> int:
    return int(edits * n)


class Items:
    """Index of a block of items: shared-run table and LSH keys by length."""

    def __init__(self, ids: list[int], texts: list[str], edits: float = EDITS):
        raw = [(t or "").encode() for t in texts]
        offsets = np.concatenate([[0], np.cumsum([len(x) for x in raw])]).astype(np.int64)
        w = textvec.Words(FOLD[np.frombuffer(b"".join(raw), np.uint8)], offsets)
        h, first = w.hashes(), w.first
        self.edits = edits
        self.ids, self.words, anchors = [], [], []
        for i, item in enumerate(ids):
            own = h[first[i] : first[i + 1]]
            if len(own):
                k = tolerated(len(own), edits)
                run = max(1, min(GRAM, -(-(len(own) - k) // (k + 1))))
                for q in range(len(own) - run + 1):
                    anchors.append((run, self.gram(own[q : q + run]), q, len(self.ids)))
                self.ids.append(item)
                self.words.append(own)
        self.size = np.array([len(x) for x in self.words], np.int64)
        self.most = np.array([tolerated(len(x), edits) for x in self.words], np.int64)
        self.runs = {}
        for run in sorted({a[0] for a in anchors}):
            own = sorted(a[1:] for a in anchors if a[0] == run)
            value = np.array([a[0] for a in own], np.uint64)
            seen = np.zeros(1 << 20, bool)
            seen[(value >> np.uint64(44)).astype(np.int64)] = True
            self.runs[run] = (seen, value, np.array([a[1] for a in own]), np.array([a[2] for a in own]))
        self.index: dict[int, dict[int, list[int]]] = {}
        for n in sorted({len(x) for x in self.words}):
            which = [i for i, x in enumerate(self.words) if len(x) == n]
            found: dict[int, list[int]] = {}
            for i, row in zip(which, lsh_keys(np.array([self.words[i] for i in which])).tolist()):
                for key in row:
                    found.setdefault(key, []).append(i)
            self.index[n] = found

    @staticmethod
    def gram(own: np.ndarray) -> int:
        value = own[:1].copy()
        for x in own[1:]:
            value = value * np.uint64(0x9FB21C651E98DF25) + x
        return int(textvec.mix(value)[0])


def _search(items: Items, data, offsets, rows):
    w = textvec.Words(FOLD[data], offsets)
    h, first = w.hashes(), w.first
    starts: dict[int, list[np.ndarray]] = {}
    for run, (seen, value, q, item) in items.runs.items():
        grams, at = w.grams(h, run)
        hit = np.flatnonzero(seen[(grams >> np.uint64(44)).astype(np.int64)])
        lo, hi = np.searchsorted(value, grams[hit], "left"), np.searchsorted(value, grams[hit], "right")
        count = hi - lo
        which = np.repeat(lo, count) + (np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count))
        begin = np.repeat(at[hit], count) - q[which]
        doc = np.searchsorted(first, np.repeat(at[hit], count), "right") - 1
        own_item = item[which]
        order = np.lexsort((begin, own_item, doc))
        begin, doc, own_item = begin[order], doc[order], own_item[order]
        size = items.size[own_item] if len(which) else which
        k = items.most[own_item] if len(which) else which
        # a match keeps this many of the item's sequences, starting within k of its place
        need = np.maximum(1, size - run + 1 - k * run)
        line = (doc * len(items.ids) + own_item) * (len(h) + 2 * 10**6) + begin + 10**6
        enough = np.searchsorted(line, line + 2 * k, "right") - np.arange(len(line)) >= need
        mark = np.zeros(len(line) + 1, np.int64)
        np.add.at(mark, np.flatnonzero(enough), 1)
        np.add.at(mark, np.searchsorted(line, line[enough] + 2 * k[enough], "right"), -1)
        good = np.cumsum(mark[:-1]) > 0
        begin, doc, size = begin[good], doc[good], size[good]
        for n in np.unique(size).tolist():
            k = tolerated(n, items.edits)
            own = size == n
            b = begin[own][:, None] + np.arange(-k, k + 1)[None, :]
            d = doc[own][:, None]
            # a window keeps its length where the document allows, else it is shortened at an edge
            ok = (b > first[d] - n) & (b < first[d + 1])
            starts.setdefault(n, []).append(np.unique(np.stack([np.broadcast_to(d, b.shape)[ok], b[ok]], 1), axis=0))
    best: dict[tuple[int, int], tuple[int, int]] = {}
    for n, parts in starts.items():
        k = tolerated(n, items.edits)
        at = np.unique(np.concatenate(parts), axis=0)
        index = items.index[n]
        known = np.fromiter(index.keys(), np.uint64, len(index))
        shared: dict[tuple[int, int], list[tuple[int, int]]] = {}
        for lo in range(0, len(at), 20_000):
            doc, begin = at[lo : lo + 20_000].T
            place = begin[:, None] + np.arange(n)[None, :]
            inside = (place >= first[doc][:, None]) & (place < first[doc + 1][:, None])
            keys = lsh_keys(np.where(inside, h[np.clip(place, 0, len(h) - 1)], _PAD))
            for row in np.flatnonzero(np.isin(keys, known).any(axis=1)).tolist():
                for i, times in Counter(i for key in keys[row].tolist() for i in index.get(key, ())).items():
                    shared.setdefault((int(doc[row]), i), []).append((times, int(begin[row])))
        # a verified region reaches k words past its window on both sides: one of k neighbours is enough
        todo = []
        for (d, i), windows in shared.items():
            taken: list[int] = []
            for times, b in sorted(windows, reverse=True):
                if all(abs(b - x) > k for x in taken):
                    taken.append(b)
                    todo.append((d, i, b))
        for lo in range(0, len(todo), 5_000):
            d, i, b = np.array(todo[lo : lo + 5_000], np.int64).T
            place = b[:, None] + np.arange(-k, n + k)[None, :]
            inside = (place >= first[d][:, None]) & (place < first[d + 1][:, None])
            regions = np.where(inside, h[np.clip(place, 0, len(h) - 1)], _PAD)
            dist = substring_distances(np.array([items.words[x] for x in i.tolist()]), regions)
            for x in np.flatnonzero(dist <= k).tolist():
                key, new = (int(d[x]), int(i[x])), (int(dist[x]), int(b[x] - first[d[x]]))
                best[key] = min(best.get(key, new), new)
    if not best:
        return None
    listed = sorted(best.items())
    ids = rows.column(0).to_pylist()
    return base.batch(
        _HITS, doc_id=[ids[d] for (d, _), _ in listed], item_id=[items.ids[i] for (_, i), _ in listed], edits=[v[0] for _, v in listed],
        start_word=[max(0, v[1]) for _, v in listed], item_words=[len(items.words[i]) for (_, i), _ in listed],
    )


_HITS = {"doc_id": pa.int64(), "item_id": pa.int64(), "edits": pa.int64(), "start_word": pa.int64(), "item_words": pa.int64()}
_built: dict[str, Items] = {}


def _searchers(benchmark: DataFrame, edits: float) -> list:
    """search(data, offsets, rows) for each block of items; a block is broadcast."""
    sc = benchmark.sparkSession.sparkContext
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.coalesce("text", F.lit("")).alias("text"))
    total = items.agg(F.coalesce(F.sum(F.octet_length("text") + 64), F.lit(0)).alias("n")).first()["n"]
    blocks = max(1, -(-total // BLOCK_BYTES))
    out = []
    for b in range(blocks):
        part = items if blocks == 1 else items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == b)
        listed = part.orderBy("item_id").collect()
        packed = sc.broadcast(pickle.dumps(([r["item_id"] for r in listed], [r["text"] for r in listed], edits)))

        def run(data, offsets, rows, packed=packed, name=uuid.uuid4().hex):
            if name not in _built:
                _built.clear()
                _built[name] = Items(*pickle.loads(packed.value))
            return _search(_built[name], data, offsets, rows)

        out.append(run)
    return out


def leaks(docs: DataFrame, benchmark: DataFrame, edits: float = EDITS) -> DataFrame:
    """One row per (document row, item) found: doc_id, item_id, edits, start_word, item_words."""
    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    out = None
    for search in _searchers(benchmark, edits):
        found = base.over_texts(df, search, "doc_id long, item_id long, edits long, start_word long, item_words long", "doc_id")
        out = found if out is None else out.unionByName(found)
    return out


def keep_clean(docs: DataFrame, benchmark: DataFrame, edits: float = EDITS) -> DataFrame:
    """The rows of docs, all columns, without a passage of any item; narrow."""
    out = docs
    for search in _searchers(benchmark, edits):

        def clean(data, offsets, search=search):
            n = len(offsets) - 1
            good = np.ones(n, bool)
            found = search(data, offsets, pa.RecordBatch.from_arrays([pa.array(range(n), pa.int64())], ["row"]))
            if found is not None:
                good[found.column(0).to_numpy()] = False
            return good

        out = base.filter_texts(out, clean)
    return out


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(base.table(spark, sf_dir, "documents", "doc_id", "text"), base.table(spark, sf_dir, "benchmark", "item_id", "text"))

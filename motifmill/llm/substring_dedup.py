"""Substring deduplication by Relative Lempel-Ziv parsing.

The reference of a document is the text of all documents with smaller ids, cut into
blocks where the content says so (the hash of the last CONTEXT words; about one place in
ANCHOR).  A block is indexed by the fingerprint of its words and the WINDOW - 1 words after it, under
the least document that has it.  A document is parsed greedily from left to right: where
its next block is in the index under a smaller id, a factor starts there, and it grows
block by block for as long as the index goes on with the source's next block.  A factor is
long enough by its making: every window that starts in it is in a smaller document.  At
its boundaries, and in all that no block covers, the parse is settled word by word: a
window of WINDOW words that a smaller document has starts or prolongs a factor.

Only boundary windows are looked up, and only in what no indexed block covers: the least
document that has a window has it there.  They are found in two steps: the windows'
minimisers (least fingerprint of their 5-word sequences) that one document alone has are
dropped, then windows under a shared minimiser are fingerprinted.  The index is sharded by
fingerprint, so that a document meets those blocks alone that it shares something with.

Rows that a batch can decide alone never meet others: of equal minimisers or windows in
one batch a single row speaks for the batch, so the rows of one value grow with the
batches, not with its copies; a window over them can spill.  Texts are shuffled by document.

Special cases: null or empty texts, and those under 13 words, lose nothing; repeated
rows with one doc_id are not duplicates of each other (no smaller id); documents with
a null doc_id are kept whole and are no reference; no rows give none; extra columns are
ignored.  Blocks and windows are compared by 64-bit fingerprints.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import cut
from . import base, textvec

WINDOW, GRAM, PIECE, CONTEXT, ANCHOR = 13, 5, 6 << 20, 3, 32
_TOP = np.uint64(2**64 - 1)
_ROWS = {"key": pa.int64(), "value": pa.int64(), "doc_id": pa.int64(), "settled": pa.bool_()}
_ROW_SCHEMA = "key long, value long, doc_id long, settled boolean"


class Blocks:
    """The reference blocks of a piece: first word, number in the document, document row, fingerprint."""

    def __init__(self, words: textvec.Words, hashes: np.ndarray):
        value, at = words.grams(hashes, CONTEXT)
        picked = at[(value >> np.uint64(40)) % np.uint64(ANCHOR) == 0] + CONTEXT
        begin, stop = words.first[:-1], words.first[1:]
        every = np.unique(np.concatenate([begin, picked]))
        doc = np.searchsorted(begin, every, "right") - 1
        # a block needs a window that starts in it
        use = every + WINDOW <= stop[doc] if len(every) else np.zeros(0, bool)
        self.first, self.doc = every[use], doc[use]
        n = len(self.first)
        fresh = np.ones(n, bool)
        fresh[1:] = self.doc[1:] != self.doc[:-1]
        self.number = np.arange(n) - np.maximum.accumulate(np.where(fresh, np.arange(n), 0)) if n else np.zeros(0, np.int64)
        self.value = np.zeros(n, np.uint64)
        # windows start up to the next block, or up to the last place where one fits
        self.last = np.minimum(np.append(self.first[1:], len(words)), stop[self.doc] - WINDOW + 1) if n else self.first
        if n:
            size = self.last + WINDOW - 1 - self.first
            total = np.cumsum(size)
            place = np.arange(total[-1]) - np.repeat(total - size, size)
            up, _ = textvec._table(int(size.max()) + 1)
            sums = np.add.reduceat(textvec.mix(hashes[place + np.repeat(self.first, size)]) * up[place], total - size)
            self.value = textvec.mix(sums + size.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


class Windows:
    """The 13-word windows of a piece: place, document row, minimiser."""

    def __init__(self, data, offsets, window: int = WINDOW, gram: int = GRAM):
        self.words = w = textvec.Words(data, offsets)
        self.hashes = h = w.hashes()
        n, span = len(h), window - gram + 1
        value, at = w.grams(h, gram)
        low = np.full(n, _TOP, np.uint64)
        low[at] = value
        width = 1
        while width * 2 <= span:
            low[:-width] = np.minimum(low[:-width], low[width:]) if n > width else low[:-width]
            width *= 2
        if span > width and n > span - width:
            rest = span - width
            low = np.minimum(low[: n - rest], low[rest:])
        m = max(0, n - window + 1)
        doc = w.doc()
        self.at = np.flatnonzero(doc[:m] == doc[window - 1 : window - 1 + m])
        self.doc = doc[self.at]
        self.low = low[self.at]

    def fingerprints(self, which: np.ndarray, window: int = WINDOW) -> np.ndarray:
        at = self.at[which]
        value = self.hashes[at].copy()
        for j in range(1, window):
            value *= np.uint64(0xC2B2AE3D27D4EB4F)
            value += self.hashes[at + j]
        return textvec.mix(value)


def _tag(value: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """One number for a value in a document."""
    return textvec.mix(value ^ textvec.mix(doc.astype(np.uint64) + np.uint64(0x51ED270B)))


def _speak(value: np.ndarray, ids: np.ndarray, settle_least: bool):
    """Rows of a batch: for each value one open row, and settled rows for what the batch
    itself decides.  settle_least: also the row with the least id is settled when others
    share the value (then any two are evidence); else only larger ids are."""
    order = np.lexsort((ids, value))
    value, ids = value[order], ids[order]
    fresh = np.ones(len(value), bool)
    fresh[1:] = (value[1:] != value[:-1]) | (ids[1:] != ids[:-1])
    value, ids = value[fresh], ids[fresh]
    head = np.ones(len(value), bool)
    head[1:] = value[1:] != value[:-1]
    settled = ~head
    if settle_least:
        followed = np.append(~head[1:], False) if len(head) else head
        settled = settled | (head & followed)
    v = np.concatenate([value[head], value[settled]])
    d = np.concatenate([ids[head], ids[settled]])
    s = np.concatenate([np.zeros(head.sum(), bool), np.ones(settled.sum(), bool)])
    key = np.where(s, _tag(v, d), v)
    return base.batch(_ROWS, key=key, value=v, doc_id=d, settled=s)


def _ids(rows) -> tuple[np.ndarray, np.ndarray]:
    column = rows.column(0)
    return column.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64), ~np.asarray(column.is_null())


_BLOCKS = {"key": pa.int64(), "value": pa.int64(), "doc_id": pa.int64(), "number": pa.int64(), "source": pa.int64(), "place": pa.int64(), "settled": pa.bool_()}
_BLOCK_SCHEMA = "key long, value long, doc_id long, number long, source long, place long, settled boolean"


def _blocks(data, offsets, rows):
    """Of equal blocks in a batch the least document's row is open; the others have it as their source."""
    ids, known = _ids(rows)
    words = textvec.Words(data, offsets)
    b = Blocks(words, words.hashes())
    use = known[b.doc]
    value, doc, number = b.value[use], ids[b.doc[use]], b.number[use]
    order = np.lexsort((number, doc, value))
    value, doc, number = value[order], doc[order], number[order]
    fresh = np.ones(len(value), bool)
    fresh[1:] = (value[1:] != value[:-1]) | (doc[1:] != doc[:-1])
    value, doc, number = value[fresh], doc[fresh], number[fresh]
    head = np.ones(len(value), bool)
    head[1:] = value[1:] != value[:-1]
    least = np.maximum.accumulate(np.where(head, np.arange(len(value)), 0)) if len(value) else np.zeros(0, np.int64)
    return base.batch(_BLOCKS, key=np.where(head, value, _tag(value, doc)), value=value, doc_id=doc, number=number, source=doc[least], place=number[least], settled=~head)


def _in_blocks(w: Windows, b: Blocks, good: np.ndarray) -> np.ndarray:
    """Whether each window starts in one of the good blocks."""
    if not len(b.first):
        return np.zeros(len(w.at), bool)
    at = np.maximum(np.searchsorted(b.first, w.at, "right") - 1, 0)
    return good[at] & (w.at >= b.first[at]) & (w.at < b.last[at])


def _minimisers(data, offsets, rows):
    ids, known = _ids(rows)
    w = Windows(data, offsets)
    b = Blocks(w.words, w.hashes)
    open_ = known[w.doc] & ~_in_blocks(w, b, _marked(b.doc, b.value, rows.column(1)))
    low, doc, at = w.low[open_], w.doc[open_], w.at[open_]
    turn = np.ones(len(low), bool)
    turn[1:] = (low[1:] != low[:-1]) | (at[1:] != at[:-1] + 1) | (doc[1:] != doc[:-1])
    return _speak(low[turn], ids[doc[turn]], True)


def _marked(doc: np.ndarray, values: np.ndarray, column: pa.Array) -> np.ndarray:
    """Whether each value, of these document rows, is in the list of its document."""
    lists = column.fill_null([]) if column.null_count else column
    count = np.diff(lists.offsets.to_numpy()) if len(lists) else np.zeros(0, np.int64)
    flat = lists.flatten().to_numpy(zero_copy_only=False).view(np.uint64) if len(lists) else np.zeros(0, np.uint64)
    wanted = np.unique(_tag(flat, np.repeat(np.arange(len(count)), count)))
    tag = _tag(values, doc)
    if not len(wanted):
        return np.zeros(len(tag), bool)
    at = np.minimum(np.searchsorted(wanted, tag), len(wanted) - 1)
    return wanted[at] == tag


def _windows(data, offsets, rows):
    if rows.column(2).null_count == len(rows.column(2)):
        return None
    ids, known = _ids(rows)
    w = Windows(data, offsets)
    b = Blocks(w.words, w.hashes)
    open_ = ~_in_blocks(w, b, _marked(b.doc, b.value, rows.column(1)))
    which = np.flatnonzero(open_ & _marked(w.doc, w.low, rows.column(2)))
    return _speak(w.fingerprints(which), ids[w.doc[which]], False)


def _sources(b: Blocks, rows) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(whether the index has each block under a smaller id, source document, number of the block there)."""
    good = _marked(b.doc, b.value, rows.column(1))
    source, number = np.zeros(len(good), np.int64), np.zeros(len(good), np.int64)
    lists = [rows.column(i) for i in (1, 2, 3)]
    doc = np.repeat(np.arange(len(rows)), np.asarray(pa.compute.fill_null(pa.compute.list_value_length(lists[0]), 0)))
    value, of, place = (x.flatten().to_numpy(zero_copy_only=False) for x in lists)
    if len(value):
        tag = _tag(value.view(np.uint64), doc)
        order = np.argsort(tag)
        at = order[np.minimum(np.searchsorted(tag, _tag(b.value, b.doc), sorter=order), len(tag) - 1)]
        source, number = np.where(good, of[at], 0), np.where(good, place[at], 0)
    return good, source, number


_RESULT = {"doc_id": pa.int64(), "n_words": pa.int64(), "n_removed": pa.int64(), "kept_sha256": pa.string(), "n_factors": pa.int64(), "kept_text": pa.string()}


def _parse(with_text: bool):
    def run(data, offsets, rows):
        w = Windows(data, offsets)
        words = w.words
        n = len(words)
        b = Blocks(words, w.hashes)
        good, source, number = _sources(b, rows)
        hit = _in_blocks(w, b, good) | _marked(w.doc, w.fingerprints(slice(None)), rows.column(4))
        edge = np.zeros(n + 1, np.int64)
        np.add.at(edge, w.at[hit], 1)
        np.add.at(edge, w.at[hit] + WINDOW, -1)
        drop = np.cumsum(edge)[:n] > 0
        # greedy parse: a factor begins where the window before is not matched, or where the next block has another source
        begin = hit.copy()
        begin[1:] &= ~(hit[:-1] & (w.at[1:] == w.at[:-1] + 1))
        again = np.flatnonzero(good[1:] & good[:-1] & (b.doc[1:] == b.doc[:-1]) & ((source[1:] != source[:-1]) | (number[1:] != number[:-1] + 1))) + 1
        begin[np.searchsorted(w.at, b.first[again])] = True
        factors = np.bincount(w.doc[begin], minlength=len(offsets) - 1)
        kept = np.flatnonzero(~drop)
        doc = words.doc()
        mask = np.zeros(len(data) + 1, np.int8)
        mask[words.starts[kept]] += 1
        np.subtract.at(mask, words.ends[kept], 1)
        inside = np.cumsum(mask[:-1]).astype(bool)
        more = np.ones(len(kept), bool)
        if len(kept):
            more[:-1] = doc[kept[1:]] == doc[kept[:-1]]
            more[-1] = False
        out = inside.copy()
        gaps = words.ends[kept[more]]
        out[gaps] = True
        text = data.copy()
        text[gaps] = 0x20
        ends = np.concatenate([[0], np.cumsum(out)])[offsets]
        view = memoryview(text[out])
        parts = [view[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist())]
        return base.batch(
            _RESULT, doc_id=rows.column(0), n_words=words.counts(), n_removed=np.bincount(doc[drop], minlength=len(factors)),
            kept_sha256=[hashlib.sha256(p).hexdigest() for p in parts], n_factors=factors,
            kept_text=[bytes(p).decode("utf-8", "replace") if with_text else None for p in parts],
        )

    return run


def remove_repeats(docs: DataFrame, with_text: bool = False) -> DataFrame:
    """One row per document: doc_id, n_words, n_removed, kept_sha256, n_factors and, if
    with_text, kept_text."""
    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    # the index of blocks: what more than one document has, under the least of them

    def shared(rows: DataFrame) -> DataFrame:
        """rows with the least row and the greatest doc_id of their key."""
        by = Window.partitionBy("key")
        first = F.struct("doc_id", *[c for c in rows.columns if c == "number"])
        return rows.withColumn("least", F.min(first).over(by)).withColumn("most", F.max("doc_id").over(by)).where("settled or least.doc_id < most")

    covered = shared(base.over_texts(df, _blocks, _BLOCK_SCHEMA, "doc_id", most=PIECE)).where("settled or least.doc_id < doc_id")
    origin = F.when(F.col("settled"), F.struct("value", "source", "place")).otherwise(F.struct("value", F.col("least.doc_id").alias("source"), F.col("least.number").alias("place")))
    covered = covered.groupBy("doc_id").agg(F.collect_list(origin).alias("b"))
    covered = cut(covered.select("doc_id", F.col("b.value").alias("blocks"), F.col("b.source").alias("sources"), F.col("b.place").alias("places")))
    known = df.join(covered, "doc_id", "left")
    lows = shared(base.over_texts(known, _minimisers, _ROW_SCHEMA, "doc_id", "blocks", most=PIECE))
    lows = lows.groupBy("doc_id").agg(F.collect_list("value").alias("marks"))
    found = shared(base.over_texts(known.join(lows, "doc_id", "left"), _windows, _ROW_SCHEMA, "doc_id", "blocks", "marks", most=PIECE))
    found = found.where("settled or least.doc_id < doc_id").groupBy("doc_id").agg(F.collect_list("value").alias("marks"))
    schema = "doc_id long, n_words long, n_removed long, kept_sha256 string, n_factors long, kept_text string"
    out = base.over_texts(known.join(found, "doc_id", "left"), _parse(with_text), schema, "doc_id", "blocks", "sources", "places", "marks", most=PIECE)
    return out if with_text else out.drop("kept_text")


def op9_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(base.table(spark, sf_dir, "documents", "doc_id", "text")).drop("n_factors")


SQL = """
WITH w AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws FROM documents),
g AS (SELECT doc_id, i, md5(array_to_string(ws[i:i + 12], ' ')) AS k FROM w, (SELECT unnest(range(1, most + 1)) AS i FROM (SELECT max(len(ws)) AS most FROM w)) WHERE i <= len(ws) - 12),
f AS (SELECT k, min(doc_id) AS first_id FROM g GROUP BY k HAVING min(doc_id) < max(doc_id)),
r AS (SELECT DISTINCT g.doc_id, g.i + o AS p FROM g JOIN f ON g.k = f.k AND f.first_id < g.doc_id, (SELECT unnest(range(0, 13)) AS o)),
d AS (SELECT doc_id, list(p) AS ps FROM r GROUP BY doc_id)
SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(len(ps), 0)::BIGINT AS n_removed,
  sha256(array_to_string(CASE WHEN ps IS NULL THEN ws ELSE list_transform(list_filter(range(1, len(ws) + 1), lambda q: NOT list_contains(ps, q)), lambda q: ws[q]) END, ' ')) AS kept_sha256
FROM w LEFT JOIN d ON w.doc_id = d.doc_id
"""

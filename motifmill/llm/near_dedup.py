"""Near-duplicate classes: one-permutation MinHash, optimal densification, banding, stars.

A document's set holds its distinct word shingles (lower-cased A-Z; two words by default
for the contract's query, five elsewhere).  One permutation fills BINS bins with their
least fingerprints; an empty bin borrows from a non-empty one picked by a universal hash
of (bin, attempt).  Bands of ROWS bins are bucket keys.  Documents with equal sets are one
class, so copies never meet in pairs.  In a bucket every class is tied to the least one
(a star, so pairs grow with members); each tie is confirmed on the full sets.  Where a
bucket's members are then in different components, those outside the hub's component are
held as queries against all its members, in blocks, by exact counts from an inverted
index; only links come out.  Small sets get more repetitions, since
few distinct bins make bands alike.

Special cases: null texts, empty texts and texts without words have an empty set, are
linked with nothing and kept; rows with equal doc_id count as one document (and are all
reported); a null doc_id is reported with its own null component and not kept; no rows
give none; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import cut
from . import base, textvec

BINS, ROWS, SMALL, EXTRA, BLOCK = 128, 4, 96, 2, 300
_EMPTY = np.uint64(2**64 - 1)
_SKETCH = {"doc_id": pa.int64(), "n_shingles": pa.int64(), "hi": pa.int64(), "lo": pa.int64(), "keys": pa.list_(pa.int64())}
_SKETCH_SCHEMA = "doc_id long, n_shingles long, hi long, lo long, keys array<long>"


def shingle_sets(data, offsets, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(fingerprints sorted in each document, offsets) of the distinct k-word shingles."""
    w = textvec.Words(data, offsets, lower=True)
    h = w.hashes()
    value, at = w.grams(h, k)
    count = w.counts()
    doc = np.searchsorted(w.first, at, "right") - 1
    short = np.flatnonzero((count > 0) & (count < k))
    if len(short):
        whole = np.empty(len(short), np.uint64)
        for i, s in enumerate(short.tolist()):
            x = h[w.first[s] : w.first[s + 1]]
            one = x[:1].copy()
            for j in range(1, len(x)):
                one = one * np.uint64(0x9FB21C651E98DF25) + x[j : j + 1]
            whole[i] = one[0]
        value = np.concatenate([value, textvec.mix(whole + np.uint64(0x1234567))])
        doc = np.concatenate([doc, short])
    order = np.lexsort((value, doc))
    value, doc = value[order], doc[order]
    fresh = np.ones(len(value), bool)
    fresh[1:] = (value[1:] != value[:-1]) | (doc[1:] != doc[:-1])
    value, doc = value[fresh], doc[fresh]
    return value, np.searchsorted(doc, np.arange(len(offsets)))


def one_permutation(value: np.ndarray, doc: np.ndarray, n: int, bins: int = BINS) -> np.ndarray:
    """n x bins matrix of least fingerprints, densified; value sorted within each doc."""
    shift = np.uint64(64 - int(bins).bit_length() + 1)
    cell = (value >> shift).astype(np.int64)
    head = np.ones(len(value), bool)
    head[1:] = (cell[1:] != cell[:-1]) | (doc[1:] != doc[:-1])
    first = np.full((n, bins), _EMPTY, np.uint64)
    first[doc[head], cell[head]] = value[head]
    out = first.copy()
    row, col = np.nonzero(first == _EMPTY)
    attempt = 1
    while len(row):
        lend = (textvec.mix(np.arange(bins, dtype=np.uint64) * np.uint64(65_537) + np.uint64(attempt)) % np.uint64(bins)).astype(np.int64)
        got = first[row, lend[col]]
        ok = got != _EMPTY
        out[row[ok], col[ok]] = got[ok]
        row, col = row[~ok], col[~ok]
        attempt += 1
    return out


def band_keys(matrix: np.ndarray, salt: int, rows: int = ROWS) -> np.ndarray:
    n, bins = matrix.shape
    m = matrix.reshape(n, bins // rows, rows)
    key = np.broadcast_to(np.arange(bins // rows, dtype=np.uint64) + np.uint64(salt * 1000 + 1), m.shape[:2]).copy()
    for j in range(rows):
        key = textvec.mix(key * np.uint64(0x9E3779B97F4A7C15) + m[:, :, j])
    return key


def _sketch(k: int):
    def run(data, offsets, rows):
        value, first = shingle_sets(data, offsets, k)
        size = np.diff(first)
        n = len(size)
        sums = []
        for salt in (0x0F1E2D3C4B5A6978, 0x1122334455667788):
            total = np.zeros(len(value) + 1, np.uint64)
            np.cumsum(textvec.mix(value ^ np.uint64(salt)), out=total[1:])
            sums.append(total[first[1:]] - total[first[:-1]])
        full = np.flatnonzero(size > 0)
        doc = np.repeat(np.arange(n), size)
        place = np.full(n, -1)
        place[full] = np.arange(len(full))
        keys = [np.zeros(0, np.uint64)] * n
        main = band_keys(one_permutation(value, place[doc], len(full)), 0) if len(full) else None
        small = np.flatnonzero((size > 0) & (size < SMALL))
        extra = []
        if len(small):
            back = np.full(n, -1)
            back[small] = np.arange(len(small))
            own = back[doc] >= 0
            v, d = value[own], back[doc[own]]
            for r in range(1, EXTRA + 1):
                u = textvec.mix(v ^ np.uint64(r * 0x5851F42D4C957F2D & (2**64 - 1)))
                order = np.lexsort((u, d))
                extra.append(band_keys(one_permutation(u[order], d[order], len(small)), r))
        for i, row in enumerate(full.tolist()):
            keys[row] = main[i]
        for i, row in enumerate(small.tolist()):
            keys[row] = np.concatenate([keys[row], *(e[i] for e in extra)])
        return base.batch(_SKETCH, doc_id=rows.column(0), n_shingles=size, hi=sums[0], lo=sums[1], keys=[x.view(np.int64) for x in keys])

    return run


def _sets(k: int):
    def run(data, offsets, rows):
        value, first = shingle_sets(data, offsets, k)
        lists = pa.ListArray.from_arrays(pa.array(first, pa.int32()), pa.array(value.view(np.int64)))
        return base.batch({"node": pa.int64(), "shingles": pa.list_(pa.int64())}, node=rows.column(0), shingles=lists)

    return run


def confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets have 100 * intersection >= percent * union."""
    left = sets.select(F.col("node").alias("b"), F.col("shingles").alias("y"))
    right = sets.select(F.col("node").alias("a"), F.col("shingles").alias("x"))
    met = F.size(F.array_intersect("x", "y"))
    fits = (F.size("x") * 100 >= F.size("y") * percent) & (F.size("y") * 100 >= F.size("x") * percent)
    return (
        pairs.join(left, "b").join(right, "a").where(fits)
        .withColumn("met", met).where(F.col("met") * 100 >= (F.size("x") + F.size("y") - F.col("met")) * percent).select("a", "b")
    )


_LINK = {"a": pa.int64(), "b": pa.int64()}


def _compare_rest(families: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links between members of a family (hub, node, component) that are in different
    components.  The queries of a family, its members outside the hub's component, are
    held against all members, BLOCK of both at a time; a block counts common shingles by an
    inverted index and returns, for each query, one link to each component it meets."""
    main = families.where("node = hub").select("hub", F.col("component").alias("main")).distinct()
    f = cut(families.join(main, "hub"))
    parts = lambda n: F.ceil(n / BLOCK).cast("int")
    sizes = f.groupBy("hub").agg(parts(F.count("*")).alias("blocks"), parts(F.count_if(F.col("component") != F.col("main"))).alias("turns"))
    f = f.join(cut(sizes.where("turns > 0")), "hub")
    own = lambda n, seed: F.pmod(F.xxhash64("node", F.lit(seed)), n).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), n - 1))
    members = f.select("hub", own(F.col("blocks"), 1).alias("block"), every(F.col("turns")).alias("turn"), "node", "component", F.lit(False).alias("query"))
    queries = f.where("component <> main").select("hub", every(F.col("blocks")).alias("block"), own(F.col("turns"), 2).alias("turn"), "node", "component", F.lit(True).alias("query"))

    def compare(group):
        node, comp = group.column("node").to_numpy(), group.column("component").to_numpy()
        asked = np.asarray(group.column("query").to_numpy(zero_copy_only=False), bool)
        lists = group.column("shingles").combine_chunks()
        offs, flat = lists.offsets.to_numpy(), lists.values.to_numpy()
        size = np.diff(offs)
        own = np.flatnonzero(~asked)
        elements = np.concatenate([flat[offs[i] : offs[i + 1]] for i in own]) if len(own) else flat[:0]
        holder = np.repeat(np.arange(len(own)), size[own])
        order = np.argsort(elements, kind="stable")
        elements, holder = elements[order], holder[order]
        out = []
        for q in np.flatnonzero(asked):
            mine = flat[offs[q] : offs[q + 1]]
            lo, hi = np.searchsorted(elements, mine, "left"), np.searchsorted(elements, mine, "right")
            n = hi - lo
            at = np.repeat(lo - (np.cumsum(n) - n), n) + np.arange(n.sum())
            met = np.bincount(holder[at], minlength=len(own))
            good = (met * 100 >= (size[q] + size[own] - met) * percent) & (comp[own] != comp[q])
            hit = own[good]
            _, first = np.unique(comp[hit], return_index=True)
            out += [(int(node[q]), int(node[i])) for i in hit[first]]
        return pa.table({"a": pa.array([min(p) for p in out], pa.int64()), "b": pa.array([max(p) for p in out], pa.int64())})

    return members.unionByName(queries).join(sets, "node").groupBy("hub", "block", "turn").applyInArrow(compare, "a long, b long").distinct()


def near_classes(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept, class_id."""
    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    sketch = cut(base.over_texts(df, _sketch(k), _SKETCH_SCHEMA, "doc_id"))
    same = ["hi", "lo", "n_shingles"]
    # cut, so that both sides of the join below are dealt anew and a very large class can be split there
    classes = cut(sketch.where("n_shingles > 0 and doc_id is not null").groupBy(*same).agg(F.min("doc_id").alias("class_id")))
    members = cut(sketch.drop("keys").join(classes, same, "left"))
    speakers = members.where("doc_id = class_id").select("doc_id").distinct()
    bands = sketch.join(speakers, "doc_id", "left_semi").select(F.col("doc_id").alias("node"), F.explode("keys").alias("key"))
    hubs = bands.groupBy("key").agg(F.min("node").alias("hub"), F.max("node").alias("last")).where("hub < last").select("key", "hub")
    near = cut(bands.join(hubs, "key"))
    stars = near.where("node <> hub").select(F.col("hub").alias("a"), F.col("node").alias("b")).distinct()
    nodes = near.select(F.col("node").alias("doc_id")).distinct()
    sets = cut(base.over_texts(df.join(nodes, "doc_id", "left_semi"), _sets(k), "node long, shingles array<long>", "doc_id").dropDuplicates(["node"]))
    links = cut(confirm(stars, sets, percent))
    found = cut(base.components(links))
    placed = near.join(found, "node", "left").withColumn("component", F.coalesce("component", "node"))
    mixed = placed.groupBy("key").agg(F.min("component").alias("x"), F.max("component").alias("y")).where("x < y").select("key")
    families = placed.join(mixed, "key", "left_semi").select("hub", "node", "component").distinct()
    more = cut(_compare_rest(families, sets, percent))
    if not more.isEmpty():
        of = lambda side: found.select(F.col("node").alias(side), F.col("component").alias(f"c{side}"))
        lifted = more.join(of("a"), "a", "left").join(of("b"), "b", "left").select(F.coalesce("ca", "a").alias("a"), F.coalesce("cb", "b").alias("b"))
        top = base.components(lifted).select(F.col("node").alias("component"), F.col("component").alias("final"))
        singles = more.select(F.explode(F.array("a", "b")).alias("node")).distinct().join(found, "node", "left_anti").withColumn("component", F.col("node"))
        found = cut(found.unionByName(singles).join(top, "component", "left").select("node", F.coalesce("final", "component").alias("component")))
    return members.join(found.withColumnRenamed("node", "class_id"), "class_id", "left").select(
        "doc_id", "n_shingles", F.coalesce("component", "class_id", "doc_id").alias("component_id"),
        F.coalesce(F.col("doc_id") == F.coalesce("component", "class_id", "doc_id"), F.lit(False)).alias("kept"), "class_id",
    )


def op3_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_classes(base.table(spark, sf_dir, "documents", "doc_id", "text"), k=2, percent=80).drop("class_id")


SQL = """
WITH RECURSIVE t AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws FROM documents),
s AS (SELECT doc_id, CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) = 1 THEN ws ELSE list_distinct(list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1])) END AS sh FROM t),
e AS (SELECT doc_id, unnest(sh) AS g FROM s WHERE len(sh) > 0),
i AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS met FROM e x JOIN e y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM i JOIN s sa ON a = sa.doc_id JOIN s sb ON b = sb.doc_id WHERE 100 * met >= 80 * (len(sa.sh) + len(sb.sh) - met)),
u AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
c AS (SELECT doc_id AS n, doc_id AS r FROM s UNION SELECT u.b, c.r FROM c JOIN u ON c.n = u.a WHERE c.r < u.b)
SELECT s.doc_id, len(sh)::BIGINT AS n_shingles, (SELECT min(r) FROM c WHERE n = s.doc_id) AS component_id, s.doc_id = (SELECT min(r) FROM c WHERE n = s.doc_id) AS kept FROM s
"""

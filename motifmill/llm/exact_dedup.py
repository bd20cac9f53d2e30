"""Exact deduplication by content-defined chunk recipes.

A text is normalised (each run of space or 0x09-0x0D becomes one space) and cut where a
rolling fingerprint of the last 32 bytes says so, so that equal content is cut alike.
Chunks get a 64-bit fingerprint; a fingerprint that stands for more than one SHA-256
digest is split by the rank of the digest, which makes it a verified identifier.  Texts
are equal when their ordered identifier lists are.  Only fingerprints, digests and
lists are shuffled, never texts.

Results in special cases: a null text counts as empty and all empty texts are equal; a
table without rows gives none; a repeated doc_id is reported once per row and ties have
the same keep_id, so both are kept; a null doc_id never is the kept one unless its whole
group has null ids (then keep_id is null and kept is false); extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import cut
from . import base, textvec

LEAST_CHUNK, MOST_CHUNK, CUT_BITS, REACH = 512, 16_384, 11, 32
_GEAR = np.random.default_rng(77).integers(0, 2**32, 256, dtype=np.uint32)

_SCHEMA = {
    "doc_id": pa.int64(), "text_sha256": pa.string(), "n_bytes": pa.int64(),
    "fps": pa.list_(pa.int64()), "digests": pa.list_(pa.binary()),
}


def normalise(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    space = textvec.IS_SPACE[data]
    keep = np.ones(len(data), bool)
    keep[1:] = ~(space[1:] & space[:-1])
    keep[offsets[offsets < len(data)]] = True
    out = np.where(space, np.uint8(0x20), data)[keep]
    total = np.zeros(len(data) + 1, np.int64)
    np.cumsum(keep, out=total[1:])
    return out, total[offsets]


def cut_points(data: np.ndarray, offsets: np.ndarray, cut_bits: int = CUT_BITS, least: int = LEAST_CHUNK, most: int = MOST_CHUNK) -> list[list[int]]:
    """Ends of the chunks of each text, a function of the text alone."""
    h = _GEAR[data]
    step = 1
    while step < REACH and step < len(h):
        h[step:] = h[step:] + (h[:-step] << np.uint32(step))
        step *= 2
    at = np.flatnonzero(h >> np.uint32(32 - cut_bits) == 0) + 1
    lo = np.searchsorted(at, offsets[:-1] + REACH)
    hi = np.searchsorted(at, offsets[1:])
    out = []
    for i, (a, b) in enumerate(zip(offsets[:-1].tolist(), offsets[1:].tolist())):
        ends, last = [], a
        for p in [*at[lo[i] : hi[i]].tolist(), b]:
            while p - last > most:
                last += most
                ends.append(last)
            if p - last >= least or p == b and (p > last or not ends):
                last = p
                ends.append(p)
        out.append(ends)
    return out


def _recipes(data, offsets, rows, fp_bits: int = 64):
    text, offs = normalise(data, offsets)
    ends = cut_points(text, offs)
    view = memoryview(np.ascontiguousarray(text))
    fps, digests, whole = [], [], []
    for i, own in enumerate(ends):
        a, b = int(offs[i]), int(offs[i + 1])
        whole.append(hashlib.sha256(view[a:b]).hexdigest())
        parts, start = [], a
        for e in own:
            parts.append(hashlib.sha256(view[start:e]).digest())
            start = e
        digests.append(parts)
        fps.append((np.frombuffer(b"".join(x[:8] for x in parts), np.uint64) & np.uint64((1 << fp_bits) - 1)).view(np.int64))
    return base.batch(_SCHEMA, doc_id=rows.column(0), text_sha256=whole, n_bytes=np.diff(offs), fps=fps, digests=digests)


def recipes(docs: DataFrame, fp_bits: int = 64) -> DataFrame:
    """doc_id, text_sha256, n_bytes, fps (fingerprints in order), digests (in order)."""
    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return base.over_texts(df, lambda data, offsets, rows: _recipes(data, offsets, rows, fp_bits), "doc_id long, text_sha256 string, n_bytes long, fps array<long>, digests array<binary>", "doc_id")


def exact_groups(docs: DataFrame, fp_bits: int = 64) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256, n_chunks.
    Fewer fp_bits make fingerprints meet more often; the result is the same."""
    r = cut(recipes(docs, fp_bits))
    chunks = r.select("doc_id", F.posexplode(F.arrays_zip("fps", "digests")).alias("seq", "c")).select("doc_id", "seq", "c.fps", "c.digests")
    shared = cut(chunks.groupBy("fps").agg(F.min("digests").alias("x"), F.max("digests").alias("y")).where("x <> y").select("fps"))
    none = F.array().cast("array<struct<seq:int,rank:int>>")
    if shared.isEmpty():  # every fingerprint is verified as it is: the usual case
        listed = r.drop("digests").withColumn("recipe", F.struct("fps", none.alias("fixes")))
    else:
        ranks = chunks.join(shared, "fps", "left_semi").select("fps", "digests").distinct().withColumn("rank", F.row_number().over(Window.partitionBy("fps").orderBy("digests")))
        fixes = chunks.join(ranks, ["fps", "digests"]).where("rank > 1").groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("seq", "rank"))).alias("fixes"))
        listed = r.drop("digests").join(fixes, "doc_id", "left").withColumn("recipe", F.struct("fps", F.coalesce("fixes", none).alias("fixes")))
    # cut, so that both sides of the join are dealt anew and a very large group can be split there
    groups = cut(listed.groupBy("recipe").agg(F.min("doc_id").alias("keep_id"), F.count("*").alias("group_size")))
    return listed.join(groups, "recipe").select(
        "doc_id", "keep_id", "group_size", F.coalesce(F.col("doc_id") == F.col("keep_id"), F.lit(False)).alias("kept"), "text_sha256", F.size("fps").alias("n_chunks"),
    )


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_groups(base.table(spark, sf_dir, "documents", "doc_id", "text")).drop("n_chunks")


SQL = """
WITH n AS (SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]+', ' ', 'g')) AS text_sha256 FROM documents)
SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = min(doc_id) OVER w AS kept, text_sha256
FROM n WINDOW w AS (PARTITION BY text_sha256)
"""

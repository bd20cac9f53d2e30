"""What the document operators share: reading, running over Arrow batches, components."""

from __future__ import annotations

import itertools
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import cut, ship
from . import textvec


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def over_texts(df: DataFrame, fn: Callable, schema: str, *keep: str, most: int = textvec.PIECE_BYTES, then: Callable | None = None) -> DataFrame:
    """Run fn(data, offsets, rows) on pieces of bounded size; fn returns a RecordBatch or None.

    df needs `text`; `keep` are other columns that fn needs, handed over as `rows`
    (a RecordBatch).  Nulls in text count as empty.  then: runs over a task's results.
    Narrow: no shuffle.
    """
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = textvec.buffers(batch.column(batch.schema.get_field_index("text")))
            rest = batch.select(list(keep))
            for lo, hi in textvec.pieces(offsets, most):
                a, b = offsets[lo], offsets[hi]
                out = fn(data[a:b], offsets[lo : hi + 1] - a, rest.slice(lo, hi - lo))
                if out is not None and out.num_rows:
                    yield out

    return df.select("text", *keep).mapInArrow((lambda batches: then(run(batches))) if then else run, schema)


def filter_texts(df: DataFrame, keep: Callable) -> DataFrame:
    """The rows of df, with all their columns, for whose text keep(data, offsets) is true."""
    ship(df.sparkSession)
    at = df.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = textvec.buffers(batch.column(at))
            good = [keep(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]) for lo, hi in textvec.pieces(offsets)]
            if good:
                yield batch.filter(pa.array(np.concatenate(good)))

    return df.mapInArrow(run, df.schema)


def batch(schema: dict[str, pa.DataType], **columns) -> pa.RecordBatch:
    """A RecordBatch from numpy arrays or lists."""
    fields = [pa.field(n, t) for n, t in schema.items()]
    arrays = []
    for n, t in schema.items():
        value = columns[n]
        if isinstance(value, np.ndarray) and value.dtype == np.uint64 and pa.types.is_int64(t):
            value = value.view(np.int64)
        arrays.append(value if isinstance(value, pa.Array) else pa.array(value, t))
    return pa.RecordBatch.from_arrays(arrays, schema=pa.schema(fields))


def as_texts(data: np.ndarray, offsets: np.ndarray) -> list[str]:
    raw = data.tobytes()
    return [raw[a:b].decode("utf-8", "replace") for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())]


def components(edges: DataFrame, most_rounds: int | None = None) -> DataFrame:
    """(node, component) with the smallest reachable node, from edges (a, b).

    Alternating large-star and small-star steps; every round is one aggregate and one
    join over the edges, cut at the shared checkpoint folder.  A hub's neighbours are
    never gathered in one task.  An error if no fixed point is reached within most_rounds.
    """
    e = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct())
    state = None
    for turn in itertools.count():
        if turn == most_rounds:
            raise RuntimeError(f"components are not complete after {most_rounds} rounds")
        # large star: every larger neighbour of a node points at the node's smallest neighbour
        both = e.select(F.col("hi").alias("n"), F.col("lo").alias("m")).unionByName(e.select(F.col("lo").alias("n"), F.col("hi").alias("m")))
        # cut, so that the join deals both sides anew and AQE can split a hub's rows
        least = cut(both.groupBy("n").agg(F.min("m").alias("root")).withColumn("root", F.least("n", "root")))
        large = both.where("m > n").join(least, "n").select(F.col("m").alias("hi"), F.col("root").alias("lo")).where("hi <> lo").distinct()
        # small star: a node and its smaller neighbours point at the smallest of them
        small = large.groupBy("hi").agg(F.min("lo").alias("root"))
        e = cut(
            large.join(small, "hi").select(F.col("lo").alias("hi"), F.col("root").alias("lo"))
            .unionByName(small.select("hi", F.col("root").alias("lo"))).where("hi <> lo").distinct()
        )
        row = e.agg(F.count("*").alias("n"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)")).alias("s")).first()
        now = (row["n"], row["s"])
        if now == state:
            break
        state = now
    return e.groupBy("hi").agg(F.min("lo").alias("component")).withColumnRenamed("hi", "node").unionByName(e.select(F.col("lo").alias("node"), F.col("lo").alias("component")).distinct())

"""Supports: counts, minimum-image domains (rows, sets, bitmaps, sketches)."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship

MODES = ("rows", "set", "bitmap", "approx", "udaf")


def mni(domains: DataFrame, mode: str = "rows", rsd: float = 0.02) -> DataFrame:
    """pattern, support from domain rows (pattern, orbit, vid): the smallest domain."""
    if mode == "rows":
        per = domains.distinct().groupBy("pattern", "orbit").agg(F.count("*").alias("n"))
    elif mode == "set":
        per = domains.groupBy("pattern", "orbit").agg(F.size(F.collect_set("vid")).cast("long").alias("n"))
    elif mode == "bitmap":
        by = domains.groupBy("pattern", "orbit", F.bitmap_bucket_number("vid").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("vid")).alias("bits"))
        per = by.groupBy("pattern", "orbit").agg(F.sum(F.bitmap_count("bits")).alias("n"))
    elif mode == "approx":
        per = domains.groupBy("pattern", "orbit").agg(F.approx_count_distinct("vid", rsd).alias("n"))
    elif mode == "udaf":
        per = domains.groupBy("pattern", "orbit").agg(distinct_udaf()("vid").alias("n"))
    else:
        raise ValueError(f"unknown mode {mode!r}")
    return per.groupBy("pattern").agg(F.min("n").alias("support"))


def mni_at_least(domains: DataFrame, sigma: int) -> DataFrame:
    """Patterns whose support reaches sigma, with sigma as their support.

    A task passes on sigma different vertices of a domain at most and forgets what comes
    after: its state and what it shuffles end at sigma, however often the pattern occurs."""

    def first_ones(batches):
        seen: dict[tuple, set[int]] = {}
        for batch in batches:
            keep = []
            for i, (p, o, v) in enumerate(zip(*(batch.column(c).to_pylist() for c in range(3)))):
                own = seen.setdefault((p, o), set())
                if len(own) < sigma and v not in own:
                    own.add(v)
                    keep.append(i)
            yield batch.take(pa.array(keep, pa.int64()))

    ship(domains.sparkSession)
    some = domains.select("pattern", "orbit", F.col("vid").cast("long").alias("vid"))
    some = some.mapInArrow(first_ones, some.schema)
    per = some.distinct().groupBy("pattern", "orbit").agg(F.count("*").alias("n"))
    return per.groupBy("pattern").agg(F.min("n").alias("n")).where(F.col("n") >= sigma).select("pattern", F.lit(sigma).cast("long").alias("support"))


def distinct_udaf():
    """Grouped-aggregate pandas function: number of distinct vertices."""
    import pandas as pd
    from pyspark.sql.functions import pandas_udf

    def distinct(vid: pd.Series) -> int:
        return int(vid.nunique())

    distinct.__annotations__ = {"vid": pd.Series, "return": int}
    return pandas_udf(distinct, "long")


def lookup(level: DataFrame, pattern_map: DataFrame) -> DataFrame:
    """level (with pattern) and the support of its pattern."""
    return level.join(F.broadcast(pattern_map.select("pattern", "support")), "pattern", "left")

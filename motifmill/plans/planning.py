"""Which phases a level needs, row prediction, exact offsets, and bounds."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..graph import PropertyGraph


def phases_for(size: int, last: int, aggregates: bool, prunes: bool) -> tuple[bool, bool]:
    """(aggregate?, drop?) at a level: without a drop phase only the last level aggregates."""
    return aggregates and (prunes or size == last), aggregates and prunes


def inspect(level: DataFrame, size: int, graph: PropertyGraph, positions: list[int]) -> DataFrame:
    """level with n_children, an upper bound of its children: the degrees of its growing vertices."""
    out = level
    for p in positions:
        d = graph.degrees.select(F.col("id").alias(f"v{p}"), F.col("degree").alias(f"_d{p}"))
        out = out.join(d, f"v{p}")
    return out.withColumn("n_children", sum((F.col(f"_d{p}") for p in positions), F.lit(0)).cast("long")).drop(*[f"_d{p}" for p in positions])


def prefix_sum(df: DataFrame, order: list[str], value: str, name: str = "start_offset") -> DataFrame:
    """df with the exclusive prefix sum of value in the given order, in two passes: range
    partitions get their own sums, partition totals (one row each) become offsets."""
    from ..session import cut

    parts = cut(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_part", F.spark_partition_id()))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = parts.groupBy("_part").agg(F.sum(value).alias("_t")).withColumn("_o", F.coalesce(F.sum("_t").over(before), F.lit(0))).select("_part", "_o")
    own = Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    out = parts.withColumn("_w", F.coalesce(F.sum(value).over(own), F.lit(0))).join(F.broadcast(offsets), "_part")
    return out.withColumn(name, (F.col("_o") + F.col("_w")).cast("long")).drop("_part", "_o", "_w")


def number_rows(df: DataFrame, name: str) -> DataFrame:
    """df with dense row numbers from 0: rows are counted by partition, the counts become
    offsets, and a row's number is its offset and its place; nothing is sorted or shuffled."""
    from ..session import cut

    seq = F.monotonically_increasing_id()
    parts = cut(df.withColumn("_seq", seq))
    part = F.shiftright("_seq", 33)
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = parts.groupBy(part.alias("_part")).agg(F.count("*").alias("_n")).withColumn("_o", F.coalesce(F.sum("_n").over(before), F.lit(0))).select("_part", "_o")
    out = parts.withColumn("_part", part).join(F.broadcast(offsets), "_part")
    return out.withColumn(name, (F.col("_o") + F.col("_seq").bitwiseAND((1 << 33) - 1)).cast("long")).drop("_part", "_seq", "_o")


def blocks_for(total_children: int, budget_rows: int) -> int:
    return max(1, -(-int(total_children) // max(1, budget_rows)))


def upper_bound(n: int, k: int, d_max: int) -> float:
    """Worst-case work of growth, connectivity and isomorphism."""
    return n ** (k - 1) * k**2 * d_max * max(1.0, math.log2(max(d_max, 2))) * math.exp(math.sqrt(k * math.log(max(k, 2))))

"""Edge blocking: all levels for one block of seeds at a time, to bound memory."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import PropertyGraph
from ..plans import planning
from ..session import cut
from . import engine
from .rules import AppSpec


def run(graph: PropertyGraph, app: AppSpec, max_size: int, blocks: int | None = None, budget_rows: int = 5_000_000, finish: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Sum of the blocks' pattern maps.  blocks=None sizes them by inspection.  An
    application that drops patterns needs all blocks at once and is refused."""
    if app.prune is not None:
        raise ValueError("blocks cannot be mined apart when patterns are dropped by their total support")
    seeds = cut(engine.seed(graph, app))
    if blocks is None:
        total = planning.inspect(seeds, 2, graph, app.expand(2)).agg(F.sum("n_children").alias("n")).first()["n"] or 0
        blocks = planning.blocks_for(total, budget_rows)
    seeds = seeds.withColumn("block_id", F.pmod(F.xxhash64("v0", "v1"), F.lit(blocks)))
    total = None
    for b in range(blocks):
        found = engine.mine(graph, app, max_size, seeds=seeds.where(F.col("block_id") == b).drop("block_id")).pattern_map
        part = cut(found.select("pattern", "support"))
        total = part if total is None else total.unionByName(part)
    return total.groupBy("pattern").agg(F.sum("support").alias("support"))

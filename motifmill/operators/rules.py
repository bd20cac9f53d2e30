"""What an application plugs into the engine: hooks over Columns."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame


def all_positions(size: int) -> list[int]:
    return list(range(size))


def last_position(size: int) -> list[int]:
    return [size - 1]


@dataclass
class AppSpec:
    """expand: positions that may grow; admit(vids, bits, u) in vertex mode, or
    admit_edge(edges, lo, hi) in edge mode, default the canonical test; classify(level,
    size) adds the column pattern; support: aggregate column; prune(support) says which
    patterns stay; on_level(number, level) sees every level; fused: no level is stored, and
    arcs are read from a broadcast where they fit, so that no embedding is written or shuffled."""

    mode: str = "vertex"
    expand: Callable[[int], list[int]] = all_positions
    admit: Callable[[list[Column], Column, Column], Column] | None = None
    admit_edge: Callable[[Column, Column, Column], Column] | None = None
    classify: Callable[[DataFrame, int], DataFrame] | None = None
    support: Column | None = None
    prune: Callable[[Column], Column] | None = None
    orient: str | None = None
    connectivity: str = "join"
    materialize_candidates: bool = False
    fused: bool = False
    on_level: Callable[[int, DataFrame], None] | None = None
    anti_monotone: bool = True
    unsafe: bool = False
    extra: dict = field(default_factory=dict)

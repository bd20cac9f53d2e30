"""Level tables: wide rows, a column prefix tree, and a queue of structs."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.planning import number_rows
from ..session import checkpoint_folder, cut

LAYOUTS = ("wide", "tree", "queue")


def write(df: DataFrame, path: str, level: int) -> str:
    """Write a level, by block where it has one."""
    out = f"{path}/level={level}"
    w = df.write.mode("overwrite")
    (w.partitionBy("block_id") if "block_id" in df.columns else w).parquet(out)
    return out


def scratch(df: DataFrame, name: str) -> str:
    return f"{checkpoint_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"


class Store:
    """Levels of one run in a layout, as Parquet in the shared folder.

    tree: a row is (emb_id, parent_id, vid, ...) with dense ids, numbered by partition
    offsets in two passes; it names its parent and holds one vertex only.  wide and queue
    rows hold whole embeddings, as columns or as an array of structs."""

    def __init__(self, layout: str = "wide"):
        if layout not in LAYOUTS:
            raise ValueError(f"unknown layout {layout!r}")
        self.layout, self.levels, self.paths = layout, {}, {}

    @property
    def link(self) -> tuple[str, ...]:
        """Columns that children must take over from get(): the parent's id in a tree."""
        return ("emb_id",) if self.layout == "tree" else ()

    def _keep(self, size: int, df: DataFrame) -> None:
        self.paths[size] = scratch(df, f"level-{size}")
        df.write.parquet(self.paths[size])
        self.levels[size] = df.sparkSession.read.schema(df.schema).parquet(self.paths[size])

    def put(self, size: int, level: DataFrame) -> None:
        """level has v0..v{size-1}, in a tree from the third on also the emb_id of its parent."""
        vids = [f"v{j}" for j in range(size)]
        rest = [c for c in level.columns if c not in (*vids, "emb_id")]
        if self.layout == "wide":
            self._keep(size, level)
        elif self.layout == "queue":
            items = F.array(*[F.struct(F.lit(j).alias("pos"), F.col(v).alias("vid")) for j, v in enumerate(vids)])
            self._keep(size, level.select(items.alias("items"), *rest))
        elif size == 2:
            self._keep(size, number_rows(level.select(F.col("v0").alias("parent_id"), F.col("v1").alias("vid"), *rest), "emb_id"))
        else:
            self._keep(size, number_rows(level.select(F.col("emb_id").alias("parent_id"), F.col(vids[-1]).alias("vid"), *rest), "emb_id"))

    def get(self, size: int) -> DataFrame:
        """The level as wide rows (a tree's with emb_id); the tree walks up to its roots, one join a level."""
        df = self.levels[size]
        if self.layout == "wide":
            return df
        if self.layout == "queue":
            rest = [c for c in df.columns if c != "items"]
            return df.select(*[F.col("items")[j]["vid"].alias(f"v{j}") for j in range(size)], *rest)
        rest = [c for c in df.columns if c not in ("parent_id", "vid")]
        out = df.select("parent_id", F.col("vid").alias(f"v{size - 1}"), *rest)
        for s in range(size - 1, 1, -1):
            up = self.levels[s].select(F.col("emb_id").alias("parent_id"), F.col("vid").alias(f"v{s - 1}"), F.col("parent_id").alias("_up"))
            out = out.join(up, "parent_id").drop("parent_id").withColumnRenamed("_up", "parent_id")
        return out.withColumnRenamed("parent_id", "v0").select(*[f"v{j}" for j in range(size)], *rest)

    def bytes(self, size: int) -> int:
        """Bytes that the level takes where it lies."""
        spark = self.levels[size].sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(self.paths[size])
        return int(path.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(path).getLength())


def overapprox_store(level: DataFrame, size: int) -> list[DataFrame]:
    """Pairs of neighbouring positions only: small, but joins back to more than the level."""
    return [cut(level.select(f"v{j}", f"v{j + 1}").distinct()) for j in range(size - 1)]


def expand_overapprox(pairs: list[DataFrame]) -> DataFrame:
    out = pairs[0]
    for j, p in enumerate(pairs[1:], 1):
        out = out.join(p, f"v{j}")
    n = len(pairs) + 1
    distinct = F.size(F.array_distinct(F.array(*[f"v{j}" for j in range(n)]))) == n
    return out.where(distinct).select(*[f"v{j}" for j in range(n)])

"""Property graphs as DataFrames: one row per undirected edge, optional vertex labels.

edges(src, dst) has src < dst, no repeats, no nulls; vertices(id, label) is optional and
derived from the edges when absent (label 0).  Everything here is a lazy plan.
"""

from __future__ import annotations

import itertools
from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .session import cut


def normalise(pairs: DataFrame, a: str = "src", b: str = "dst") -> DataFrame:
    """Canonical edges of raw pairs: no loops, no repeats, no direction."""
    x, y = F.col(a).cast("long"), F.col(b).cast("long")
    return pairs.where(x != y).select(F.least(x, y).alias("src"), F.greatest(x, y).alias("dst")).distinct()


@dataclass
class PropertyGraph:
    edges: DataFrame
    labels: DataFrame | None = None
    weights: DataFrame | None = None  # id, weight: a vertex stands for so many equal ones, all adjacent to each other
    lists: DataFrame | None = None  # id, nbrs: all neighbours in order, where they are stored

    @classmethod
    def of(cls, edges: DataFrame, labels: DataFrame | None = None, keep: bool = True) -> PropertyGraph:
        """Edges materialised once (they are read at every level), labels as given."""
        return cls(cut(edges) if keep else edges, labels)

    def validate(self) -> dict[str, int]:
        """Counts of what must not be there; raises if any is not zero."""
        e = self.edges
        bad = e.agg(
            F.count_if(F.col("src").isNull() | F.col("dst").isNull()).alias("nulls"),
            F.count_if(F.col("src") >= F.col("dst")).alias("unordered"),
            (F.count("*") - F.count_distinct("src", "dst")).alias("repeats"),
        ).first().asDict()
        if self.labels is not None:
            ends = e.select(F.col("src").alias("id")).unionByName(e.select(F.col("dst").alias("id"))).distinct()
            bad["unlabelled"] = ends.join(self.labels.where("label is not null"), "id", "left_anti").count()
        if any(bad.values()):
            raise ValueError(f"not a valid graph: {bad}")
        return bad

    @cached_property
    def arcs(self) -> DataFrame:
        return self.edges.select("src", "dst").unionByName(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))

    @cached_property
    def n_edges(self) -> int:
        return self.edges.count()

    @cached_property
    def n_weights(self) -> int:
        return self.weights.count()

    @cached_property
    def most_weight(self) -> int:
        return self.weights.agg(F.coalesce(F.max("weight"), F.lit(0))).first()[0]

    @cached_property
    def most_id(self) -> int:
        return self.weights.agg(F.coalesce(F.max("id"), F.lit(0))).first()[0]

    @cached_property
    def degrees(self) -> DataFrame:
        return self.arcs.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"))

    def orient(self, by: str = "degree") -> DataFrame:
        """Each edge once, from the lower to the higher end of a total order of vertices."""
        if by == "id":
            return self.edges.select("src", "dst")
        if by == "degree":
            rank = self.degrees.select("id", F.col("degree").alias("rank"))
        elif by == "random":
            rank = self.degrees.select("id", F.xxhash64("id").alias("rank"))
        elif by == "degeneracy":
            rank = self.core_rounds()
        else:
            raise ValueError(f"unknown order {by!r}")
        ranked = self.edges.join(rank.select(F.col("id").alias("src"), F.col("rank").alias("ra")), "src").join(rank.select(F.col("id").alias("dst"), F.col("rank").alias("rb")), "dst")
        first = F.struct("ra", "src") < F.struct("rb", "dst")
        return ranked.select(F.when(first, F.col("src")).otherwise(F.col("dst")).alias("src"), F.when(first, F.col("dst")).otherwise(F.col("src")).alias("dst"))

    def core_rounds(self, most: int = 200) -> DataFrame:
        """Rank of a vertex: the round in which peeling at the current mean degree removes it."""
        left, out, turn = self.edges, None, 0
        while turn < most:
            d = PropertyGraph(left).degrees
            row = d.agg(F.avg("degree").alias("m")).first()
            if row["m"] is None:
                break
            gone = cut(d.where(F.col("degree") <= row["m"]).select("id", F.lit(turn).cast("long").alias("rank")))
            out = gone if out is None else out.unionByName(gone)
            left = cut(left.join(gone.select(F.col("id").alias("src")), "src", "left_anti").join(gone.select(F.col("id").alias("dst")), "dst", "left_anti").select("src", "dst"))
            turn += 1
        rest = self.degrees.select("id") if out is None else self.degrees.join(out.select("id"), "id", "left_anti").select("id")
        rest = rest.withColumn("rank", F.lit(most).cast("long"))
        return rest if out is None else out.unionByName(rest)

    def adjacency(self, oriented: DataFrame | None = None, chunk: int | None = None) -> DataFrame:
        """id, nbrs (sorted); with chunk also the chunk number, so that a hub spans rows."""
        arcs = self.arcs if oriented is None else oriented
        if chunk is None:
            return arcs.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))
        number = F.floor((F.row_number().over(Window.partitionBy("src").orderBy("dst")) - 1) / chunk).cast("int")
        return arcs.withColumn("chunk", number).groupBy(F.col("src").alias("id"), "chunk").agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))

    def labelled_edges(self) -> DataFrame:
        """src, dst, la, lb."""
        lab = self.vertex_labels()
        return self.edges.join(lab.select(F.col("id").alias("src"), F.col("label").alias("la")), "src").join(lab.select(F.col("id").alias("dst"), F.col("label").alias("lb")), "dst").select("src", "dst", "la", "lb")

    def vertex_labels(self) -> DataFrame:
        return self.degrees.select("id", F.lit(0).alias("label")) if self.labels is None else self.labels

    def induced_by_label(self, values: list[int]) -> PropertyGraph:
        keep = self.vertex_labels().where(F.col("label").isin(values))
        edges = self.edges.join(keep.select(F.col("id").alias("src")), "src", "left_semi").join(keep.select(F.col("id").alias("dst")), "dst", "left_semi")
        return PropertyGraph(edges, keep)

    def k_core(self, k: int, most_rounds: int | None = None) -> DataFrame:
        """Edges of the k-core: vertices under degree k go until none is left.  An error if that takes more than most_rounds."""
        left, n = self.edges, -1
        for turn in itertools.count():
            if turn == most_rounds:
                raise RuntimeError(f"the {k}-core is not reached after {most_rounds} rounds")
            weak = PropertyGraph(left).degrees.where(F.col("degree") < k).select("id")
            left = cut(left.join(weak.select(F.col("id").alias("src")), "src", "left_anti").join(weak.select(F.col("id").alias("dst")), "dst", "left_anti").select("src", "dst"))
            now = left.count()
            if now == n:
                break
            n = now
        return left

    def wedges_by_vertex(self) -> DataFrame:
        d = F.col("degree")
        return self.degrees.select("id", F.floor(d * (d - 1) / 2).alias("wedges"))

    def stats(self) -> DataFrame:
        d = self.degrees.agg(F.count("*").alias("n_vertices"), F.coalesce(F.sum("degree"), F.lit(0)).alias("n_arcs"), F.max("degree").alias("max_degree"))
        lab = (self.labels if self.labels is not None else self.vertex_labels()).agg(F.count_distinct("label").alias("n_labels"))
        lab = lab if self.labels is not None else lab.select(F.lit(0).cast("long").alias("n_labels"))
        return d.crossJoin(F.broadcast(lab)).select(
            "n_vertices", F.expr("n_arcs div 2").alias("n_edges"), "n_arcs", (F.col("n_arcs") / F.col("n_vertices")).alias("avg_degree"), "max_degree", "n_labels",
        )


def label_dictionary(df: DataFrame, id_column: str, text_column: str) -> tuple[DataFrame, DataFrame]:
    """(vertices(id, label), dictionary(label, label_text)); labels number distinct texts
    in order.  The dictionary is small (an alphabet), the table only joins it."""
    texts = df.where(F.col(text_column).isNotNull()).select(F.col(text_column).alias("label_text")).distinct()
    number = F.row_number().over(Window.orderBy("label_text")).cast("int")
    dictionary = texts.withColumn("label", number).select("label", "label_text")
    vertices = df.join(F.broadcast(dictionary), df[text_column] == dictionary["label_text"]).select(F.col(id_column).cast("long").alias("id"), "label")
    return vertices, dictionary


def dense_ids(df: DataFrame, key: str) -> DataFrame:
    """key -> dense id from 0 in key order, by two passes and no global window: keys are
    range-partitioned, partition totals become offsets."""
    keys = cut(df.select(key).distinct().repartitionByRange(key).sortWithinPartitions(key).withColumn("_part", F.spark_partition_id()).withColumn("_seq", F.monotonically_increasing_id()))
    totals = keys.groupBy("_part").agg(F.count("*").alias("_n"))
    offsets = totals.withColumn("_offset", F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    within = F.row_number().over(Window.partitionBy("_part").orderBy("_seq")) - 1
    return keys.withColumn("_at", within).join(F.broadcast(offsets), "_part").select(key, (F.col("_offset") + F.col("_at")).cast("long").alias("id"))

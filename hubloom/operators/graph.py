"""The attributed graph: two relations with fixed id columns and any attributes."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hubloom.operators.runtime import saved


@dataclass(frozen=True)
class PropertyGraph:
    """``vertices(vid, ...)`` and ``edges(src, tgt, ...)``; an undirected graph holds both arcs of each edge."""

    vertices: DataFrame
    edges: DataFrame
    directed: bool = True
    name: str = field(default="graph", compare=False)

    def validate(self) -> PropertyGraph:
        for frame, ids in ((self.vertices, ["vid"]), (self.edges, ["src", "tgt"])):
            kinds = dict(frame.dtypes)
            for c in ids:
                if kinds.get(c) != "bigint":
                    raise ValueError(f"{self.name}: column {c} must be a long, not {kinds.get(c)}")
        loose = self.edges.select(F.explode(F.array("src", "tgt")).alias("vid")).distinct().join(self.vertices, "vid", "left_anti")
        if not loose.isEmpty():
            raise ValueError(f"{self.name}: edges name vertices that are not there")
        return self

    def saved(self) -> PropertyGraph:
        return replace(self, vertices=saved(self.vertices, "v"), edges=saved(self.edges, "e"))

    def filtered(self, keep: Column | str) -> PropertyGraph:
        """The vertices that satisfy a predicate, and the edges between them."""
        return self.induced_by(self.vertices.where(keep).select("vid"))

    def induced_by(self, vids: DataFrame) -> PropertyGraph:
        some = vids.select("vid").distinct()
        edges = self.edges.join(some.toDF("src"), "src", "left_semi").join(some.toDF("tgt"), "tgt", "left_semi")
        return replace(self, vertices=self.vertices.join(some, "vid", "left_semi"), edges=edges.select(self.edges.columns))

    def both_ways(self) -> PropertyGraph:
        """Each edge as two arcs."""
        back = self.edges.withColumn("_s", F.col("tgt")).withColumn("tgt", F.col("src")).withColumn("src", F.col("_s")).drop("_s")
        return replace(self, edges=self.edges.unionByName(back).dropDuplicates(["src", "tgt"]), directed=False)

    def degrees(self) -> DataFrame:
        """``(vid, out_degree, in_degree, degree)`` of vertices with an edge; self loops count twice in the total."""
        ends = self.edges.select(F.explode(F.array(F.struct(F.col("src").alias("vid"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("tgt").alias("vid"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("x"))
        return ends.groupBy("x.vid").agg(F.sum("x.o").alias("out_degree"), F.sum("x.i").alias("in_degree"), F.count("*").alias("degree"))

    def stats(self) -> DataFrame:
        """One row: vertices, edges, and edges a vertex."""
        v = self.vertices.agg(F.count("*").alias("n_vertices"))
        e = self.edges.agg(F.count("*").alias("n_edges"))
        return v.crossJoin(e).withColumn("mean_degree", F.round(F.col("n_edges") / F.col("n_vertices"), 6))  # one row each


def group_cardinality(graph: PropertyGraph, v_dim: str = "v_grp", e_dim: str = "e_grp") -> DataFrame:
    """Distinct group values of vertices and edges, and their sum."""
    v = graph.vertices.agg(F.count_distinct(v_dim).alias("v_groups"))
    e = graph.edges.agg(F.count_distinct(e_dim).alias("e_groups"))
    return v.crossJoin(e).withColumn("groups", F.col("v_groups") + F.col("e_groups"))

"""Cycles: strongly connected components, their condensation with pre-aggregates, and topological levels."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubloom.functions.aggregates import Agg, starting
from hubloom.operators.dag import TASK_ARCS, Dag, components, gathered
from hubloom.operators.graph import PropertyGraph
from hubloom.operators.runtime import saved


def scc(graph: PropertyGraph, local_edges: int = TASK_ARCS) -> DataFrame:
    """``(vid, comp)``: the smallest id of each vertex's component.

    Trimming takes vertices without an in- or out-edge; then colours (the largest
    id that reaches a vertex) spread forward, and a colour's root collects its
    component backward inside the colour.  What is left below ``local_edges``
    is finished in one task.
    """
    vertices, arcs = graph.vertices.select("vid"), saved(graph.edges.select("src", "tgt").where("src <> tgt").distinct(), "arcs")
    done = []
    left = saved(vertices, "left")
    while arcs.count() > local_edges:
        size = left.count()
        core = left.join(arcs.select(F.col("src").alias("vid")), "vid", "left_semi").join(arcs.select(F.col("tgt").alias("vid")), "vid", "left_semi")
        trimmed = left.join(core, "vid", "left_anti")
        left, done = saved(core, "left"), [*done, saved(trimmed.select("vid", F.col("vid").alias("comp")), "comp")]
        if left.count() == size:
            found = _coloured(left, arcs)
            done.append(found)
            left = saved(left.join(found, "vid", "left_anti"), "left")
        arcs = saved(arcs.join(left.toDF("src"), "src", "left_semi").join(left.toDF("tgt"), "tgt", "left_semi").select("src", "tgt"), "arcs")
    done.append(left.join(_finished(arcs), "vid", "left").select("vid", F.coalesce("comp", "vid").alias("comp")))
    out = done[0]
    for part in done[1:]:
        out = out.unionAll(part)
    return out


def _coloured(vertices: DataFrame, arcs: DataFrame) -> DataFrame:
    """At least one component of every colour: ``(vid, comp)``."""
    colour = saved(vertices.select("vid", F.col("vid").alias("c")), "colour")
    fresh = colour
    while not fresh.isEmpty():
        sent = fresh.join(arcs, F.col("vid") == F.col("src")).groupBy(F.col("tgt").alias("vid")).agg(F.max("c").alias("n"))
        fresh = saved(colour.join(sent, "vid").where("n > c").select("vid", F.col("n").alias("c")), "fresh")
        colour = saved(colour.unionAll(fresh).groupBy("vid").agg(F.max("c").alias("c")), "colour")
    same = arcs.join(colour.toDF("src", "a"), "src").join(colour.toDF("tgt", "b"), "tgt").where("a = b").select("src", "tgt", F.col("a").alias("c"))
    same = saved(same, "same")
    found = fresh = saved(colour.where("vid = c"), "roots")
    while not fresh.isEmpty():
        back = fresh.join(same.select(F.col("tgt").alias("vid"), "src"), "vid").select(F.col("src").alias("vid"), "c").distinct()
        fresh = saved(back.join(found.select("vid"), "vid", "left_anti"), "fresh")
        found = saved(found.unionAll(fresh), "found")
    least = found.groupBy("c").agg(F.min("vid").alias("comp"))
    return saved(found.join(least, "c").select("vid", "comp"), "comp")


def _finished(arcs: DataFrame) -> DataFrame:
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        vids, s, t = gathered(frames)
        yield pd.DataFrame({"vid": vids, "comp": vids[components(len(vids), s, t)]})

    return arcs.select("src", "tgt").repartition(1).mapInPandas(run, "vid long, comp long")  # below the local limit


def condense(graph: PropertyGraph, comp: DataFrame, v_dims: list[str], aggs: list[Agg]) -> tuple[PropertyGraph, DataFrame]:
    """The acyclic graph of components, and each component's partial states by vertex group.

    If one member of a component lies between two hubs all do, so the partials
    stand for the members.  Edges inside components are dropped from the graph.
    """
    partials = graph.vertices.join(comp, "vid").groupBy("comp", *v_dims).agg(F.count("*").alias("elements"), *starting(aggs))
    ends = comp.select(F.col("vid").alias("src"), F.col("comp").alias("a")), comp.select(F.col("vid").alias("tgt"), F.col("comp").alias("b"))
    edges = graph.edges.join(ends[0], "src").join(ends[1], "tgt").where("a <> b").groupBy(F.col("a").alias("src"), F.col("b").alias("tgt")).agg(F.count("*").alias("e_mr"))
    vertices = comp.groupBy(F.col("comp").alias("vid")).agg(F.count("*").alias("v_mr"))
    return replace(graph, vertices=vertices, edges=edges, name=f"{graph.name}_condensed"), partials


def topo_levels(graph: PropertyGraph, local_edges: int = TASK_ARCS) -> DataFrame:
    """``(vid, level)``: the longest path to each vertex; members of a cycle share a level.

    A task that holds all arcs takes each arc once, when its source's level is
    known.  Beyond, levels of the condensation spread along edges as maxima, only
    from vertices that rose in the round before.
    """
    between = graph.edges.select("src", "tgt").where("src <> tgt")
    if between.count() <= local_edges:

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            vids, s, t = gathered(frames)
            dag = Dag(len(vids), s, t)
            yield pd.DataFrame({"vid": vids, "level": dag.level[dag.comp]})

        levels = between.repartition(1).mapInPandas(run, "vid long, level long")
        return graph.vertices.select("vid").join(levels, "vid", "left").select("vid", F.coalesce("level", F.lit(0)).cast("long").alias("level"))
    comp = saved(scc(graph, local_edges), "comp")
    dag, _ = condense(graph, comp, [], [Agg("count")])
    arcs = saved(dag.edges.select("src", "tgt"), "arcs")
    levels = saved(dag.vertices.select(F.col("vid").alias("comp"), F.lit(0).cast("long").alias("level")), "level")
    fresh = levels
    while not fresh.isEmpty():
        sent = fresh.join(arcs, F.col("comp") == F.col("src")).groupBy(F.col("tgt").alias("comp")).agg((F.max("level") + 1).alias("n"))
        fresh = saved(levels.join(sent, "comp").where("n > level").select("comp", F.col("n").alias("level")), "fresh")
        levels = saved(levels.unionAll(fresh).groupBy("comp").agg(F.max("level").alias("level")), "level")
    return comp.join(levels, "comp", "left").select("vid", F.coalesce("level", F.lit(0)).cast("long").alias("level"))

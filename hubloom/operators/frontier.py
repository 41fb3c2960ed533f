"""Which hubs reach which vertices, by a semi-naive frontier of bit sets.

A round sends the bits that are new at a vertex along its edges, combines them
per target before and after the shuffle, and keeps what the target did not have.
Every bit crosses every edge once, no order is needed and cycles need no care;
the round in which a bit arrives is its hop distance.  Forward and backward run
as one loop.  Small graphs take the same steps in one task.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubloom.functions.bits import members, n_words, names, words_of
from hubloom.operators.graph import PropertyGraph
from hubloom.operators.runtime import LOCAL_EDGES, saved


def arrivals(graph: PropertyGraph, hubs: list[int], max_rounds: int | None = None, directions: tuple[int, ...] = (0, 1), local_edges: int = LOCAL_EDGES) -> DataFrame:
    """``(dir, vid, round, b0..)``: the hub bits that are new at a vertex in a round.

    ``dir`` 0: hubs that reach the vertex; 1: hubs the vertex reaches.  Round 0
    is the hub itself.
    """
    spark, n = graph.vertices.sparkSession, n_words(len(hubs))
    arcs = graph.edges.select("src", "tgt")
    shape = "dir int, vid long, round int, " + ", ".join(f"{b} long" for b in names("b", n))
    if not hubs:
        return spark.createDataFrame([], shape)
    if arcs.isEmpty():  # every hub reaches itself
        own = [(d, v, 0, *words_of(sum(1 << i for i, h in enumerate(hubs) if h == v), n)) for d in directions for v in sorted(set(hubs))]
        return spark.createDataFrame(own, shape)
    if local_edges and arcs.limit(local_edges + 1).count() <= local_edges:

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            parts = [f for f in frames if len(f)]
            src, tgt = (np.concatenate([p[c].to_numpy() for p in parts]) if parts else np.zeros(0, np.int64) for c in ("src", "tgt"))
            for d in directions:
                yield from _rounds(d, src if d == 0 else tgt, tgt if d == 0 else src, hubs, n, max_rounds)

        return arcs.repartition(1).mapInPandas(run, shape)  # at most ``local_edges`` rows
    seeds = [(d, v, 0, *words_of(sum(1 << i for i, h in enumerate(hubs) if h == v), n)) for d in directions for v in sorted(set(hubs))]
    both = reduce(DataFrame.unionAll, [arcs.select(F.lit(d).alias("dir"), F.col("src" if d == 0 else "tgt").alias("vid"), F.col("tgt" if d == 0 else "src").alias("to")) for d in directions])
    both = saved(both.repartition("dir", "vid"), "arcs")
    bits = names("b", n)
    steps = [saved(spark.createDataFrame(seeds, shape), "round")]
    base, since, r = steps[0].drop("round"), [], 0
    state = base
    while max_rounds is None or r < max_rounds:
        r += 1
        sent = steps[-1].drop("round").join(both, ["dir", "vid"]).groupBy("dir", F.col("to").alias("vid")).agg(*[F.bit_or(b).alias(b) for b in bits])
        had = state.select("dir", "vid", *[F.col(b).alias(f"had_{b}") for b in bits])
        fresh = sent.join(had, ["dir", "vid"], "left").select(
            "dir", "vid", F.lit(r).alias("round"), *[F.col(b).bitwiseAND(F.bitwise_not(F.coalesce(f"had_{b}", F.lit(0)))).cast("long").alias(b) for b in bits]
        )
        new = saved(fresh.where(reduce(lambda a, c: a | c, [F.col(b) != 0 for b in bits])), "round")
        if new.isEmpty():
            break
        steps.append(new)
        since.append(new)
        state = reduce(DataFrame.unionAll, [base, *[x.drop("round") for x in since]]).groupBy("dir", "vid").agg(*[F.bit_or(b).alias(b) for b in bits])
        if len(since) == 8:  # compact, so that a round reads the state once and few rounds
            base, since = saved(state, "state"), []
            state = base
    return reduce(DataFrame.unionAll, steps)


def _rounds(d: int, src: np.ndarray, tgt: np.ndarray, hubs: list[int], n: int, max_rounds: int | None) -> Iterator[pd.DataFrame]:
    vids, code = np.unique(np.concatenate([src, tgt, np.array(hubs, dtype=np.int64)]), return_inverse=True)
    m = len(src)
    s, t, h = code[:m], code[m : 2 * m], code[2 * m :]
    order = np.argsort(t, kind="stable")
    s, t = s[order], t[order]
    new = np.zeros((len(vids), n), dtype=np.int64)
    for i, v in enumerate(h):
        new[v, i // 63] |= np.int64(1) << np.int64(i % 63)
    had, r = np.zeros_like(new), 0
    while True:
        live = np.flatnonzero(new.any(axis=1))
        if not len(live):
            return
        had |= new
        yield pd.DataFrame({"dir": d, "vid": vids[live], "round": r} | {b: new[live, w] for w, b in enumerate(names("b", n))})
        if r == max_rounds:
            return
        r += 1
        hot = new.any(axis=1)
        go = hot[s]
        sg, tg = s[go], t[go]
        nxt = np.zeros_like(new)
        if len(tg):
            first = np.flatnonzero(np.r_[True, tg[1:] != tg[:-1]])
            nxt[tg[first]] = np.bitwise_or.reduceat(new[sg], first, axis=0)
        new = nxt & ~had


def hub_distances(found: DataFrame, k: int) -> DataFrame:
    """``(dir, hub, vid, d)``: hop distances from (0) or to (1) each hub, from arrivals."""
    return found.select("dir", F.explode(members("b", k)).alias("hub"), "vid", F.col("round").alias("d"))

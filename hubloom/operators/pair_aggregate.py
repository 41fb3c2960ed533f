"""Aggregates of many overlapping parts at once: element by element, or shared.

Inputs are tagged rows (``s0.., r0..`` and the columns that dimensions and
measures need).  The result has one row for each pair and group:
``(x, y, dims.., aggregates..)`` with the vertex ids of the two hubs.
"""

from __future__ import annotations

from functools import reduce

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hubloom.functions.aggregates import Agg, finishing, merging, starting
from hubloom.functions.bits import Tag, any_bit, has_hub, mask_of, members, n_words, names, words_of
from hubloom.operators.runtime import saved
from hubloom.plans.sharing import Group, SharingPlan, plan_sharing

#: Distinct tags the driver plans over; above, tags are planned in blocks.
DRIVER_TAGS = 200_000
#: Pairs that the one-job-a-pair baseline takes on.
PER_PAIR_LIMIT = 100
#: Rows of a plan that are broadcast (a unit number and a few words each).
PLAN_ROWS = 1_000_000
#: Vertices whose groups (an id and a few values) may be broadcast.
BROADCAST_VERTICES = 1_000_000


def _live(tagged: DataFrame, k: int) -> DataFrame:
    n = n_words(k)
    return tagged.where(any_bit("s", n) & any_bit("r", n))


def _named(df: DataFrame, hubs: list[int], rest: list[Column | str]) -> DataFrame:
    vids = F.array(*[F.lit(int(h)) for h in hubs]) if hubs else F.array().cast("array<long>")
    at = lambda c: F.element_at(vids, F.col(c) + 1).alias(c)
    return df.select(at("x"), at("y"), *rest)


def _spread(df: DataFrame, k: int, keep: list[str], diagonal: bool = False) -> DataFrame:
    """A row for each pair of each row's tag."""
    n = n_words(k)
    one = df.select(*keep, F.explode(members("s", k)).alias("x"), *names("r", n))
    two = one.select(*keep, "x", F.explode(members("r", k)).alias("y"))
    return two if diagonal else two.where("x <> y")


def _deliver(states_of: DataFrame, hubs: list[int], dims: list[str], aggs: list[Agg], steps: int) -> DataFrame:
    """Merge partial states into the pairs of their tags.

    In one step a state spreads to all its pairs at once.  In two it spreads to the
    hubs of S, where states of one R are merged, and what is left spreads to R.
    """
    k = len(hubs)
    states = [s for a in aggs for s in a.states()]
    if steps == 1:
        each = _spread(states_of, k, [*dims, *states])
    else:
        right = names("r", n_words(k))
        one = states_of.select(*dims, *states, F.explode(members("s", k)).alias("x"), *right).groupBy("x", *right, *dims).agg(*merging(aggs))
        each = one.select(*dims, *states, "x", F.explode(members("r", k)).alias("y")).where("x <> y")
    return _named(each.groupBy("x", "y", *dims).agg(*merging(aggs)), hubs, [*dims, *finishing(aggs)])


def share_nothing(tagged: DataFrame, hubs: list[int], dims: list[str], aggs: list[Agg], mode: str = "explode") -> DataFrame:
    """The baseline: every part is aggregated by itself.

    ``per_pair`` is a filter and an aggregate for each pair; ``explode`` the same
    in one pass, a row for each element and pair.
    """
    k = len(hubs)
    rows = _live(tagged, k)
    whole = [a for a in aggs if not a.mergeable]
    made = [a.whole() for a in whole] + starting([a for a in aggs if a.mergeable])
    done = [*dims, *[a.name if not a.mergeable else a.finish() for a in aggs]]
    if mode == "explode":
        used = sorted({*dims, *[a.column for a in aggs if a.column]})
        each = _spread(rows, k, used)
        return _named(each.groupBy("x", "y", *dims).agg(*made), hubs, done)
    if mode != "per_pair":
        raise ValueError(f"unknown mode: {mode}")
    if k * (k - 1) > PER_PAIR_LIMIT:
        raise ValueError(f"{k * (k - 1)} pairs are too many for a job each")
    jobs = [
        rows.where(has_hub("s", x) & has_hub("r", y)).groupBy(*dims).agg(*made).select(F.lit(x).alias("x"), F.lit(y).alias("y"), "*")
        for x in range(k)
        for y in range(k)
        if x != y
    ]
    if not dims:  # a global aggregate has a row even where the part is empty
        jobs = [rows.where(has_hub("s", x) & has_hub("r", y)).withColumn("_", F.lit(0)).groupBy("_").agg(*made).drop("_").select(F.lit(x).alias("x"), F.lit(y).alias("y"), "*") for x in range(k) for y in range(k) if x != y]
    return _named(reduce(DataFrame.unionByName, jobs), hubs, done)


def combine_equal_tags(tagged: DataFrame, k: int, dims: list[str], aggs: list[Agg]) -> DataFrame:
    """Partial states of each tag and group, and the number of elements in them."""
    n = n_words(k)
    return _live(tagged, k).groupBy(*names("s", n), *names("r", n), *dims).agg(F.count("*").alias("elements"), *starting(aggs))


def tag_groups(partials: DataFrame, k: int) -> list[Group]:
    """The distinct tags with their sizes; D rows on the driver."""
    n = n_words(k)
    groups = partials.groupBy(*names("s", n), *names("r", n)).agg(F.sum("elements").alias("e"), F.count("*").alias("v")).persist()
    if groups.count() > DRIVER_TAGS:
        groups.unpersist()
        raise OverflowError("more distinct tags than the driver plans over")
    rows = groups.collect()
    groups.unpersist()
    return [Group(Tag(mask_of(list(r[:n])), mask_of(list(r[n : 2 * n]))), r["e"], r["v"]) for r in rows]


def plan_frames(spark, plan: SharingPlan, k: int) -> tuple[DataFrame, DataFrame]:  # noqa: ANN001
    """The plan as relations: sources of units by tag, and targets of units."""
    n = n_words(k)
    words = lambda t: [*words_of(t.s, n), *words_of(t.r, n)]
    tag = [(c, pa.int64()) for c in [*names("s", n), *names("r", n)]]
    sources = [(u, len(unit.sources) > 1, *words(plan.groups[g].tag)) for u, unit in enumerate(plan.units) for g in unit.sources]
    targets = [(u, *words(unit.target)) for u, unit in enumerate(plan.units)]

    def frame(rows: list[tuple], fields: list[tuple]) -> DataFrame:
        columns = list(zip(*rows, strict=True)) or [()] * len(fields)
        return spark.createDataFrame(pa.table([pa.array(c, t) for c, (_, t) in zip(columns, fields, strict=True)], names=[f for f, _ in fields]))

    unit = ("unit", pa.int32())
    return frame(sources, [unit, ("merged", pa.bool_()), *tag]), frame(targets, [unit, *tag])


def execute_plan(partials: DataFrame, sources: DataFrame, targets: DataFrame, hubs: list[int], dims: list[str], aggs: list[Agg], small: bool = True, steps: int = 2) -> DataFrame:
    """Merge the sources of units that have several, then deliver all units to the pairs of their targets.

    ``sources(unit, merged, s.., r..)`` and ``targets(unit, s.., r..)``.
    """
    n = n_words(len(hubs))
    tag = [*names("s", n), *names("r", n)]
    hint = F.broadcast if small else (lambda d: d)
    states = [s for a in aggs for s in a.states()]
    read = partials.join(hint(sources), tag).select("unit", "merged", *dims, *states)
    units = read.where("merged").groupBy("unit", *dims).agg(*merging(aggs)).unionByName(read.where("not merged").drop("merged"))
    return _deliver(units.join(hint(targets), "unit"), hubs, dims, aggs, steps)


def share(
    tagged: DataFrame, hubs: list[int], dims: list[str], aggs: list[Agg], level: str = "cluster", layout: str = "flat", objective: str = "gross",
    min_cardinality: int = 3, merge_on_zero: bool = False, steps: int = 2,
) -> DataFrame:
    """Aggregation sharing: equal tags combined, similar tags clustered, shared parts aggregated once."""
    bad = [a.kind for a in aggs if not a.mergeable]
    if bad:
        raise ValueError(f"cannot be merged from parts, so cannot be shared: {', '.join(bad)}")
    k, spark = len(hubs), tagged.sparkSession
    partials = saved(combine_equal_tags(tagged, k, dims, aggs), "partials")  # read twice: for the plan and by it
    if level == "equal":
        return _deliver(partials, hubs, dims, aggs, steps)
    options = {"min_cardinality": min_cardinality, "objective": objective, "layout": layout, "merge_on_zero": merge_on_zero}
    try:
        plan = plan_sharing(tag_groups(partials, k), **options)
    except OverflowError:
        sources, targets = (saved(f, "plan") for f in plan_in_blocks(partials, k, options))
        return execute_plan(partials, sources, targets, hubs, dims, aggs, small=False, steps=steps)
    sources, targets = plan_frames(spark, plan, k)
    rows = sum(len(u.sources) for u in plan.units)
    return execute_plan(partials, sources, targets, hubs, dims, aggs, small=rows <= PLAN_ROWS, steps=steps)


def plan_in_blocks(partials: DataFrame, k: int, options: dict) -> tuple[DataFrame, DataFrame]:
    """Plans over blocks of tags with one leading pair of hubs, where the driver should not hold all tags.

    No cluster spans blocks, so some sharing is lost, never a delivery.
    """
    n = n_words(k)
    cols = [*names("s", n), *names("r", n)]
    tags = partials.groupBy(*cols).agg(F.sum("elements").alias("e"), F.count("*").alias("v"))
    lead = F.array_min(members("s", k)) * k + F.array_min(members("r", k))
    # A block of very many tags is cut by hash, so no task plans over more than a bounded number on average.
    blocks = tags.withColumn("block", lead * 64 + F.pmod(F.xxhash64(*cols), F.lit(64)))

    def plan(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = pdf[[*cols, "e", "v"]].to_numpy().tolist()
        made = plan_sharing([Group(Tag(mask_of(r[:n]), mask_of(r[n : 2 * n])), r[-2], r[-1]) for r in rows], **options)
        base, out = int(pdf["block"].iloc[0]) << 24, []
        for u, unit in enumerate(made.units):
            out.append((0, base + u, False, *words_of(unit.target.s, n), *words_of(unit.target.r, n)))
            for g in unit.sources:
                t = made.groups[g].tag
                out.append((1, base + u, len(unit.sources) > 1, *words_of(t.s, n), *words_of(t.r, n)))
        return pd.DataFrame(out, columns=["kind", "unit", "merged", *cols])

    shape = "kind int, unit long, merged boolean, " + ", ".join(f"{c} long" for c in cols)
    both = saved(blocks.groupBy("block").applyInPandas(plan, shape), "plan")
    return both.where("kind = 1").drop("kind"), both.where("kind = 0").drop("kind", "merged")


def tag_statistics(tagged: DataFrame, hubs: list[int], dims: list[str]) -> dict[str, float]:
    """What the choice between the two rests on: elements, tags, partials, and rows each way would make."""
    k = len(hubs)
    n = n_words(k)
    from hubloom.functions.bits import cardinality

    groups = _live(tagged, k).groupBy(*names("s", n), *names("r", n), *dims).agg(F.count("*").alias("e")).withColumn("c", cardinality(n))
    row = groups.agg(F.sum("e").alias("elements"), F.count("*").alias("partials"), F.sum(F.col("e") * F.col("c")).alias("nothing"), F.sum("c").alias("spread")).first()
    return {f: float(row[f] or 0) for f in ("elements", "partials", "nothing", "spread")}


def choose_method(stats: dict[str, float]) -> str:
    """Sharing pays when partials are few beside elements; with nearly one a group it only adds passes."""
    shared = stats["elements"] + stats["partials"] + stats["spread"]
    return "sharing" if shared < stats["nothing"] else "share_nothing"


def aggregate_pairs(tagged: DataFrame, hubs: list[int], dims: list[str], aggs: list[Agg], method: str = "sharing", **options: object) -> DataFrame:
    """``method``: ``sharing``, ``equal_tags``, ``share_nothing``, ``per_pair`` or ``auto``."""
    if method == "auto":
        method = choose_method(tag_statistics(tagged, hubs, dims)) if all(a.mergeable for a in aggs) else "share_nothing"
    if method == "share_nothing":
        return share_nothing(tagged, hubs, dims, aggs)
    if method == "per_pair":
        return share_nothing(tagged, hubs, dims, aggs, mode="per_pair")
    if method == "equal_tags":
        return share(tagged, hubs, dims, aggs, level="equal")
    if method == "sharing":
        return share(tagged, hubs, dims, aggs, **options)
    raise ValueError(f"unknown method: {method}")


def aggregate_membership(members_of: DataFrame, elements: DataFrame, key: str, dims: list[str], aggs: list[Agg]) -> DataFrame:
    """For any grouping ``(x, y, key)``: elements of equal pair lists are combined before they spread."""
    lists = members_of.groupBy(key).agg(F.sort_array(F.collect_set(F.struct("x", "y"))).alias("pairs"))  # at most k * k pairs
    partials = elements.join(lists, key).groupBy("pairs", *dims).agg(*starting(aggs))
    states = [s for a in aggs for s in a.states()]
    each = partials.select(F.explode("pairs").alias("p"), *dims, *states)
    return each.groupBy("p.x", "p.y", *dims).agg(*merging(aggs)).select("x", "y", *dims, *finishing(aggs))


def lift_edges(edges: DataFrame, vertices: DataFrame, dims: list[str], access: str = "join") -> DataFrame:
    """Edges with the group values of both ends (``src_<dim>``, ``tgt_<dim>``).

    ``access="join"`` leaves the joins to the optimizer (and to bucketing, where
    both tables are bucketed by id); ``broadcast`` sends the vertex groups to all
    tasks, up to ``BROADCAST_VERTICES`` of them, and joins beyond.
    """
    if access not in ("join", "broadcast"):
        raise ValueError(f"unknown access: {access}")
    if access == "broadcast" and vertices.limit(BROADCAST_VERTICES + 1).count() > BROADCAST_VERTICES:
        access = "join"
    hint = F.broadcast if access == "broadcast" else (lambda d: d)
    at = lambda end: hint(vertices.select(F.col("vid").alias(end), *[F.col(d).alias(f"{end}_{d}") for d in dims]))
    return edges.join(at("src"), "src").join(at("tgt"), "tgt")

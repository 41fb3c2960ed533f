"""Planning which partial aggregates overlapping parts share.

The elements of equal tag are one group.  Groups are taken in order of
cardinality (largest first, then by value) and put into the cluster whose running
common tag gains most; small groups stay alone.  A plan lists units: a source
(one group, a prefix of a cluster, or a whole cluster) and the product of hubs
whose pairs it is delivered to.  Whatever the clusters, every group reaches each
of its pairs once.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from hubloom.functions.bits import WORD, Tag, n_words, words_of


@dataclass(frozen=True)
class Group:
    """The elements of one tag."""

    tag: Tag
    elements: int = 1
    values: int = 1


@dataclass(frozen=True)
class Unit:
    kind: str  # alone, member, prefix, common
    sources: tuple[int, ...]  # numbers of groups
    target: Tag


@dataclass
class SharingPlan:
    groups: list[Group]
    clusters: list[list[int]] = field(default_factory=list)
    units: list[Unit] = field(default_factory=list)


def saving(common: Tag, members: int, tag: Tag) -> int:
    """What the cluster saves with one more group, less what it saves without."""
    return len(common & tag) * (members + 1) - len(common) * members


def order_groups(groups: list[Group]) -> list[Group]:
    return sorted(groups, key=lambda g: (-len(g.tag), g.tag))


def _gain(common: np.ndarray, before: np.ndarray, sizes: np.ndarray, objective: str) -> np.ndarray:
    if objective == "gross":
        return common * (sizes + 1) - before * sizes
    if objective == "net_flat":
        worth = lambda ct, n: np.where(n > 1, ct * n - ct - n, 0)
        return worth(common, sizes + 1) - worth(before, sizes)
    if objective == "net_chained":
        return common - np.where(sizes == 1, 2, 1)
    raise ValueError(f"unknown objective: {objective}")


def plan_sharing(
    groups: list[Group], min_cardinality: int = 3, objective: str = "gross", layout: str = "flat", merge_on_zero: bool = False, level: str = "cluster"
) -> SharingPlan:
    """Greedy clusters over distinct tags.  ``level="equal"`` stops at equal tags."""
    plan = SharingPlan(order_groups(groups))
    if layout not in ("chained", "flat"):
        raise ValueError(f"unknown layout: {layout}")
    k = max([max(g.tag.s.bit_length(), g.tag.r.bit_length()) for g in plan.groups], default=1)
    n = n_words(k)
    # Running common tags and sizes of the clusters, as arrays.
    room = max(1, len(plan.groups))
    s, r = np.zeros((room, n), dtype=np.int64), np.zeros((room, n), dtype=np.int64)
    size = np.zeros(room, dtype=np.int64)
    least = 0 if merge_on_zero else 1
    for at, g in enumerate(plan.groups):
        if level == "equal" or len(g.tag) < min_cardinality:
            plan.units.append(Unit("alone", (at,), g.tag))
            continue
        c = len(plan.clusters)
        ts, tr = np.array(words_of(g.tag.s, n)), np.array(words_of(g.tag.r, n))
        if c:
            bits = lambda a: np.bitwise_count(a).sum(axis=1).astype(np.int64)
            common = bits(s[:c] & ts) * bits(r[:c] & tr)
            gain = np.where(common > 0, _gain(common, bits(s[:c]) * bits(r[:c]), size[:c], objective), -1)
            best = int(gain.argmax())
            if gain[best] >= least:
                plan.clusters[best].append(at)
                s[best] &= ts
                r[best] &= tr
                size[best] += 1
                continue
        plan.clusters.append([at])
        s[c], r[c], size[c] = ts, tr, 1
    for cluster in plan.clusters:
        plan.units += _chained(plan.groups, cluster) if layout == "chained" else _flat(plan.groups, cluster)
    return plan


def _flat(groups: list[Group], cluster: list[int]) -> list[Unit]:
    """The final common tag gets the cluster; what else a member has gets the member."""
    if len(cluster) == 1:
        return [Unit("alone", tuple(cluster), groups[cluster[0]].tag)]
    common = groups[cluster[0]].tag
    for at in cluster[1:]:
        common &= groups[at].tag
    rest = [Unit("member", (at,), part) for at in cluster for part in groups[at].tag.minus(common)]
    return [Unit("common", tuple(cluster), common), *rest]


def _chained(groups: list[Group], cluster: list[int]) -> list[Unit]:
    """Pairs that leave the common tag when a member joins get the members before it."""
    out: list[Unit] = []
    common = groups[cluster[0]].tag
    for n, at in enumerate(cluster[1:], start=1):
        tag = groups[at].tag
        smaller = common & tag
        out += [Unit("prefix" if n > 1 else "alone", tuple(cluster[:n]), part) for part in common.minus(smaller)]
        out += [Unit("member", (at,), part) for part in tag.minus(smaller)]
        common = smaller
    return [*out, Unit("common" if len(cluster) > 1 else "alone", tuple(cluster), common)]


def deliveries(plan: SharingPlan, diagonal: bool = True) -> dict[tuple[int, tuple[int, int]], int]:
    """How often each group reaches each pair; for checks."""
    out: dict[tuple[int, tuple[int, int]], int] = {}
    for unit in plan.units:
        for pair in unit.target.pairs(diagonal):
            for g in unit.sources:
                out[(g, pair)] = out.get((g, pair), 0) + 1
    return out


def add_operations(plan: SharingPlan, diagonal: bool = False, by_value: bool = False) -> dict[str, int]:
    """Folds into an accumulator: each element for itself (``share_nothing``), after equal tags, and by the plan.

    The plan's are counted as they are executed: a unit of several sources folds
    each of them, a longer prefix those of the shorter again.  ``by_value``: a
    partial counts its group values, else one.
    """
    weight = lambda at: plan.groups[at].values if by_value else 1
    nothing = sum(g.elements * g.tag.size(diagonal) for g in plan.groups)
    folds = sum(g.elements for g in plan.groups)
    equal = folds + sum(weight(at) * g.tag.size(diagonal) for at, g in enumerate(plan.groups))
    merges = sum(weight(at) for u in plan.units if len(u.sources) > 1 for at in u.sources)
    merged = sum(max(weight(at) for at in u.sources) * u.target.size(diagonal) for u in plan.units)
    return {"share_nothing": nothing, "equal_tags": equal, "sharing": folds + merges + merged}


__all__ = ["WORD", "Group", "SharingPlan", "Tag", "Unit", "add_operations", "deliveries", "order_groups", "plan_sharing", "saving"]

"""The planner against the worked example, exactly-once delivery, and a slow model."""

import random

from hypothesis import given, settings
from hypothesis import strategies as st

from hubloom.functions.bits import Tag, mask_of, words_of
from hubloom.plans.sharing import Group, add_operations, deliveries, plan_sharing, saving

A = Tag.of([1], [2, 3, 4, 5])
B = Tag.of([1, 2], [3, 4, 5])
C = Tag.of([1, 2, 3], [4, 5])


def test_tags_of_the_worked_example():
    assert (len(A), len(B), len(C)) == (4, 6, 6)
    assert A.pairs() == {(1, 2), (1, 3), (1, 4), (1, 5)}
    assert B & C == Tag.of([1, 2], [4, 5])
    assert len(Tag.of([1, 2, 3], [4, 5]) & Tag.of([2, 3], [4, 6])) == 2
    assert saving(Tag.of([1, 2, 3], [4, 5]), 1, Tag.of([2, 3], [4, 6])) == -2
    assert saving(B, 1, C) == 2


def test_adds_of_the_worked_example():
    groups = [Group(A, 1), Group(B, 2), Group(C, 3)]
    adds = add_operations(plan_sharing(groups), diagonal=True)
    assert adds == {"share_nothing": 34, "equal_tags": 22, "sharing": 20}


def test_difference_is_two_disjoint_products():
    rest = B.minus(C)
    pairs = [t.pairs(True) for t in rest]
    assert sum(map(len, pairs)) == len(set().union(*pairs)) == 2
    assert set().union(*pairs) | (B & C).pairs(True) == B.pairs(True)
    assert B.minus(Tag.of([7], [8])) == [B]


tags = st.builds(Tag, st.integers(1, 2**7 - 1), st.integers(1, 2**7 - 1))


@settings(max_examples=150, deadline=None)
@given(st.sets(tags, min_size=1, max_size=25), st.sampled_from(["chained", "flat"]), st.sampled_from(["gross", "net_flat", "net_chained"]), st.booleans())
def test_every_group_reaches_each_pair_once(some, layout, objective, zero):
    plan = plan_sharing([Group(t) for t in some], layout=layout, objective=objective, merge_on_zero=zero)
    got = deliveries(plan)
    want = {(i, p): 1 for i, g in enumerate(plan.groups) for p in g.tag.pairs(True)}
    assert got == want


@settings(max_examples=60, deadline=None)
@given(st.sets(tags, min_size=1, max_size=20), st.integers(0, 10**6))
def test_greedy_model_and_cost_order(some, seed):
    rnd = random.Random(seed)
    groups = [Group(t, rnd.randint(1, 5)) for t in some]
    chained = plan_sharing(groups, layout="chained")
    # A slow model with sets in place of bits.
    sets = [(g.tag.pairs(True), {i for i in range(7) if g.tag.s >> i & 1}, {i for i in range(7) if g.tag.r >> i & 1}) for g in chained.groups]
    clusters: list[list[int]] = []
    common: list[tuple[set, set]] = []
    for i, (pairs, s, r) in enumerate(sets):
        if len(pairs) < 3:
            continue
        gains = [len(cs & s) * len(cr & r) * (len(c) + 1) - len(cs) * len(cr) * len(c) if cs & s and cr & r else -1 for c, (cs, cr) in zip(clusters, common, strict=True)]
        if gains and max(gains) > 0:
            at = gains.index(max(gains))
            clusters[at].append(i)
            common[at] = (common[at][0] & s, common[at][1] & r)
        else:
            clusters.append([i])
            common.append((s, r))
    assert chained.clusters == clusters
    flat = add_operations(plan_sharing(groups, layout="flat"), diagonal=True)
    a = add_operations(chained, diagonal=True)
    assert a["share_nothing"] == sum(g.elements * len(g.tag) for g in groups)
    assert flat["sharing"] <= flat["equal_tags"] + sum(len(c) for c in clusters)
    assert flat["equal_tags"] == a["equal_tags"]


def best_partition(some):
    """The least number of adds over all ways to put the tags into clusters, each shared by its common part."""
    groups = [Group(t) for t in some]

    def cost(clusters):
        total = len(groups)
        for c in clusters:
            common = groups[c[0]].tag
            for at in c[1:]:
                common &= groups[at].tag
            inner = len(common) if len(c) > 1 else 0
            total += sum(len(groups[at].tag) - inner for at in c) + (inner + len(c) if len(c) > 1 else 0)
        return total

    def ways(at, clusters):
        if at == len(groups):
            yield cost(clusters)
            return
        for c in clusters:
            c.append(at)
            yield from ways(at + 1, clusters)
            c.pop()
        yield from ways(at + 1, [*clusters, [at]])

    return min(ways(0, []))


@settings(max_examples=40, deadline=None)
@given(st.sets(tags, min_size=1, max_size=5))
def test_greedy_is_never_below_the_exhaustive_planner(some):
    groups = [Group(t) for t in sorted(some)]
    best = best_partition(sorted(some))
    plan = plan_sharing(groups, min_cardinality=1, objective="net_flat")
    made = add_operations(plan, diagonal=True)
    assert best <= made["sharing"] <= made["equal_tags"]


def test_adds_are_what_the_plan_executes(spark):
    from pyspark.sql import functions as F

    from hubloom.functions.bits import members
    from hubloom.operators.pair_aggregate import plan_frames

    rnd = random.Random(5)
    groups = [Group(t, rnd.randint(1, 4)) for t in sorted({Tag(rnd.randrange(1, 2**12), rnd.randrange(1, 2**12)) for _ in range(150)})]
    folds = sum(g.elements for g in groups)
    for layout in ("flat", "chained"):
        plan = plan_sharing(groups, layout=layout)
        sources, targets = plan_frames(spark, plan, 12)
        merges = sources.where("merged").count()
        given_out = targets.select(F.size(members("s", 12)) * F.size(members("r", 12))).groupBy().sum().first()[0]
        assert add_operations(plan, diagonal=True)["sharing"] == folds + merges + given_out


def test_words():
    mask = (1 << 70) | 5
    assert mask_of(words_of(mask, 2)) == mask
    assert all(0 <= w < 2**63 for w in words_of((1 << 126) - 1, 2))

"""Orders, alignment, swaps, rounds and costs."""

import pytest

from gembed.operators import costs, partition
from gembed.operators import schedule as S


@pytest.mark.parametrize("p,loads", [(2, 2), (4, 7), (8, 29), (16, 121)])
def test_inside_out_needs_the_fewest_loads(p, loads):
    seq = S.inside_out(p)
    assert sorted(seq) == [(i, j) for i in range(p) for j in range(p)]
    assert S.simulate_swaps(seq)["loads"] == loads == 1 + p * (p - 1) // 2
    assert S.aligned_by_part(seq) is None
    assert S.simulate_swaps(S.order("row_major", p))["loads"] == p * p - 2


def test_alignment_is_noticed():
    assert S.aligned_by_part([(0, 0), (1, 1)]) == 1
    assert S.aligned_by_side([(0, 3), (5, 3), (3, 1)]) == 2
    assert S.aligned_by_part([(0, 3), (5, 3), (3, 1)]) is None
    assert S.aligned_by_part(S.order("random_aligned", 8)) is None


@pytest.mark.parametrize("p", [2, 3, 4, 5, 7, 8, 16])
def test_tournament_rounds_are_disjoint(p):
    plan = S.tournament(p)
    pairs = [u for r in plan for u in r]
    assert len(pairs) == len(set(pairs)) == p * (p - 1) // 2
    assert all(len({x for u in r for x in u}) == 2 * len(r) for r in plan)


@pytest.mark.parametrize("policy", ["affinity", "fifo", "tournament"])
@pytest.mark.parametrize("m", [1, 2, 4])
def test_rounds_cover_all_units_once_and_stay_aligned(policy, m):
    p = 2 * m
    for first in (True, False):
        plan = S.rounds(p, m, policy, first)
        units = [u for r in plan for u in r]
        assert sorted(units) == sorted((a, b) for a in range(p) for b in range(a, p))
        assert all(len(r) <= m for r in plan)
        for r in plan:
            assert len({x for u in r for x in u}) == sum(len(set(u)) for u in r)
        if first:
            known: set = set()
            for k, r in enumerate(plan):
                assert len(r) == 1 if k == 0 else all(known & {*u} for u in r)
                known |= {x for u in r for x in u}


def test_costs_by_hand():
    c = costs.negative_cost(1000, 50, 50, 100)
    assert (c["rows"], c["scores"], c["negatives"]) == (4000, 201_000, 198_000)
    assert costs.negative_cost(1000, 50, 50, 100, "unbatched")["rows"] == 200_000
    assert costs.model_bytes(2_000_000_000, 100) == 800_000_000_000
    assert round(costs.model_bytes(121_216_723, 100) / 1e9, 1) == 48.5
    assert partition.plan_partitions(2_000_000_000, 100, 100_000_000_000).parts == 27
    assert [round(r["speedup"], 1) for r in costs.speedup({1: 30, 2: 23, 4: 13, 8: 7.7})] == [1.0, 1.3, 2.3, 3.9]

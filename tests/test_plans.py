from itertools import permutations

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from latticecube.plans.chains import STRATEGIES, Chain, is_prefix_ancestor, min_chain_count, plan_chains
from latticecube.plans.lattice import Lattice
from latticecube.plans.slots import allocate_slots, even_slots


@pytest.mark.parametrize("n", range(1, 9))
@pytest.mark.parametrize("strategy", ["auto", "symmetric", "exact"])
def test_full_cubes_take_the_least_number_of_chains(n, strategy):
    p = plan_chains("ABCDEFGH"[:n], strategy=strategy)
    assert len(p.chains) == min_chain_count(n)
    members = [m for c in p.chains for m in c.members]
    assert len(members) == len(set(members)) == 2**n - 1
    assert all(is_prefix_ancestor(m, c.order) for c in p.chains for m in c.members)


def test_worked_example_of_four_dimensions():
    lattice, p = Lattice("ABCD"), plan_chains("ABCD")
    got = [["".join(c.order[: len(m)]) for m in c.members] for c in p.chains]
    assert got == [["ABCD", "ABC", "AB", "A"], ["BCD", "BC", "B"], ["CDA", "CD", "C"], ["DAB", "DA", "D"], ["AC"], ["BD"]]
    assert p.chains[0].bitmap(lattice) == 0b1000100000100010
    assert lattice.of_tag(0b1000100000100010) == [frozenset(x) for x in ("A", "AB", "ABC", "ABCD")]
    assert ["".join(sorted(c)) for c in lattice.level(2)] == ["AB", "BC", "CD", "AD", "AC", "BD"]
    assert p.chains[4].part_dims == ("A", "C") and p.chains[0].part_dims == ("A",)
    assert p.stats["orderings_tried"] < 15


def test_prefixes():
    assert is_prefix_ancestor("AB", "ABCD") and is_prefix_ancestor("BA", "ABCD")
    assert not is_prefix_ancestor("BC", "ABCD") and not is_prefix_ancestor("", "ABCD")
    with pytest.raises(ValueError):
        Chain(("A", "B"), (frozenset("B"),))


@settings(max_examples=60, deadline=None)
@given(st.sets(st.frozensets(st.sampled_from("ABCDE"), min_size=1), min_size=1), st.sampled_from(STRATEGIES))
def test_partial_cubes_are_covered_once(cuboids, strategy):
    p = plan_chains("ABCDE", cuboids, strategy)
    assert sorted(map(sorted, cuboids)) == sorted(sorted(m) for c in p.chains for m in c.members)
    best = len(plan_chains("ABCDE", cuboids, "exact").chains)
    assert best <= len(p.chains)


def test_early_stop_changes_no_plan():
    for n in range(1, 6):
        a, b = plan_chains("ABCDE"[:n], early_stop=True), plan_chains("ABCDE"[:n], early_stop=False)
        assert len(a.chains) == len(b.chains)
        assert a.stats["orderings_tried"] <= b.stats["orderings_tried"]
    assert len(list(permutations("ABC"))) == 6


@settings(max_examples=100, deadline=None)
@given(st.lists(st.floats(0, 1e6), min_size=1, max_size=12), st.integers(0, 60))
def test_slots_sum_up_and_none_is_without(times, more):
    r = len(times) + more
    got = allocate_slots(times, r)
    assert sum(got) == r and min(got) >= 1


def test_slot_examples():
    assert allocate_slots([2, 1, 1], 8) == [4, 2, 2] == allocate_slots([20, 10, 10], 8)
    assert allocate_slots([1000, 1, 1], 4) == [2, 1, 1]
    assert even_slots(3, 8) == [3, 3, 2]
    with pytest.raises(ValueError):
        allocate_slots([1, 1, 1], 2)


def test_scaleup():
    from latticecube import metrics

    assert metrics.scaleup([]) == []
    first, second = metrics.scaleup([(2, 10.0), (4, 8.0)])
    assert (first["speedup"], first["efficiency"]) == (1.0, 1.0)
    assert (second["speedup"], second["efficiency"]) == (1.25, 0.625)

"""Chains: cuboids that are prefixes of one ordering of dimensions and so share one copy of the data."""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import permutations
from math import comb

from latticecube.plans.lattice import Lattice

#: "auto" is hop-greedy, whose orderings are few up to seven dimensions, and above them symmetric chains (full cube) or the exact cover (partial).
STRATEGIES = ("auto", "greedy", "greedy_hop", "symmetric", "exact", "singletons")


def is_prefix_ancestor(cuboid, order) -> bool:
    """Whether a cuboid is made of the first dimensions of an ordering."""
    cuboid = frozenset(cuboid)
    return len(cuboid) > 0 and frozenset(order[: len(cuboid)]) == cuboid


def min_chain_count(n: int) -> int:
    return comb(n, (n + 1) // 2)


@dataclass(frozen=True)
class Chain:
    """``order`` is the longest member's ordering; ``members`` are prefixes of it, longest first."""

    order: tuple[str, ...]
    members: tuple[frozenset[str], ...]

    def __post_init__(self):
        if not self.members or not all(is_prefix_ancestor(m, self.order) for m in self.members) or len(self.members[0]) != len(self.order):
            raise ValueError("members must be prefixes of the order, the longest being all of it")

    @property
    def sort_dims(self) -> tuple[str, ...]:
        return self.order

    @property
    def part_dims(self) -> tuple[str, ...]:
        return self.order[: len(self.members[-1])]

    def bitmap(self, lattice: Lattice) -> int:
        return lattice.tag(self.members)


@dataclass
class ChainPlan:
    chains: list[Chain]
    strategy: str
    stats: dict[str, int] = field(default_factory=dict)


def _nested(sets: list[frozenset[str]], dims: tuple[str, ...]) -> Chain:
    """The chain of cuboids that contain one another, given from small to large."""
    order: list[str] = []
    for s in sets:
        order += [d for d in dims if d in s and d not in order]
    return Chain(tuple(order), tuple(reversed(sets)))


def _greedy(lattice: Lattice, wanted: list[frozenset[str]], hop: bool, early_stop: bool) -> tuple[list[Chain], int]:
    """Take the first open cuboid of the largest size, and of its orderings the one with the most open prefixes."""
    rank = {c: lattice.number(c) for c in wanted}
    free, chains, tried = set(wanted), [], 0
    before: dict[int, tuple[str, ...]] = {}
    place = {d: i for i, d in enumerate(lattice.dims)}
    while free:
        size = max(map(len, free))
        top = min((c for c in free if len(c) == size), key=rank.__getitem__)
        orders = permutations(sorted(top, key=place.__getitem__))
        if hop:
            last = before.get(size)
            shifted = tuple(lattice.dims[(place[d] + 1) % len(lattice.dims)] for d in last) if last else tuple(sorted(top, key=place.__getitem__))
            if frozenset(shifted) != top:
                # no shift of the chain before leads here: start where the cyclic interval does
                shifted = next((o for s in range(len(lattice.dims)) if frozenset(o := lattice.interval(s, size)) == top), tuple(sorted(top, key=place.__getitem__)))
            orders = (o for o in [shifted, *permutations(sorted(top, key=place.__getitem__))])
        best, most = None, 0
        for order in orders:
            tried += 1
            found = [frozenset(order[:k]) for k in range(size, 0, -1) if frozenset(order[:k]) in free]
            if len(found) > most:
                best, most = (tuple(order), found), len(found)
            below = sum(1 for k in range(1, size + 1) if frozenset(order[:k]) in rank)
            if early_stop and len(found) == below == size:
                break
        chains.append(Chain(best[0], tuple(best[1])))
        before[size] = best[0]
        free -= set(best[1])
    return chains, tried


def _symmetric(dims: tuple[str, ...], wanted: set[frozenset[str]]) -> list[Chain]:
    """Symmetric chains by matching brackets: a subset's unmatched dimensions are turned on one by one."""
    n, groups = len(dims), {}
    for mask in range(1, 1 << n):
        open_, matched = [], set()
        for i in range(n):
            if mask >> i & 1:
                open_.append(i)
            elif open_:
                matched |= {i, open_.pop()}
        groups.setdefault(tuple(sorted((i, mask >> i & 1) for i in matched)), []).append(mask)
    out = []
    for masks in groups.values():
        sets = [frozenset(d for i, d in enumerate(dims) if m >> i & 1) for m in sorted(masks, key=lambda m: m.bit_count())]
        if sets := [s for s in sets if s in wanted]:
            out.append(_nested(sets, dims))
    return out


def _exact(dims: tuple[str, ...], wanted: list[frozenset[str]]) -> list[Chain]:
    """A minimum chain cover of any set of cuboids: maximum matching of cuboids with larger ones that contain them."""
    above = {c: [d for d in wanted if c < d] for c in wanted}
    by_upper: dict[frozenset[str], frozenset[str]] = {}

    def augment(c, seen) -> bool:
        for d in above[c]:
            if d not in seen:
                seen.add(d)
                if d not in by_upper or augment(by_upper[d], seen):
                    by_upper[d] = c
                    return True
        return False

    for c in sorted(wanted, key=len):
        augment(c, set())
    nxt = {low: up for up, low in by_upper.items()}
    out = []
    for c in wanted:
        if c not in by_upper:
            sets = [c]
            while sets[-1] in nxt:
                sets.append(nxt[sets[-1]])
            out.append(_nested(sets, dims))
    return out


def plan_chains(dims, cuboids=None, strategy: str = "auto", early_stop: bool = True) -> ChainPlan:
    """Cover the wanted cuboids with chains; a full cube gets the minimum number, by another strategy if greed misses it."""
    if strategy not in STRATEGIES:
        raise ValueError(f"no strategy {strategy}")
    lattice = Lattice(dims)
    full = [c for level in reversed(lattice.levels()) for c in level]
    wanted = full if cuboids is None else [c for c in full if c in {frozenset(x) for x in cuboids}]
    complete, tried = len(wanted) == len(full), 0
    if strategy == "auto":
        strategy = "greedy_hop" if len(lattice.dims) < 8 else "symmetric" if complete else "exact"
    if strategy == "singletons":
        place = {d: i for i, d in enumerate(lattice.dims)}
        chains = [Chain(tuple(sorted(c, key=place.__getitem__)), (c,)) for c in wanted]
    elif strategy == "symmetric":
        chains = _symmetric(lattice.dims, set(wanted))
    elif strategy == "exact":
        chains = _exact(lattice.dims, wanted)
    else:
        chains, tried = _greedy(lattice, wanted, strategy == "greedy_hop", early_stop)
        if complete and strategy == "greedy_hop" and len(chains) != min_chain_count(len(lattice.dims)):
            chains, strategy = _symmetric(lattice.dims, set(wanted)), "symmetric"
    if sorted(map(sorted, wanted)) != sorted(sorted(m) for c in chains for m in c.members):
        raise AssertionError("the chains don't cover each cuboid once")
    return ChainPlan(chains, strategy, {"chains": len(chains), "orderings_tried": tried, "bound": min_chain_count(len(lattice.dims)) if complete else 0})

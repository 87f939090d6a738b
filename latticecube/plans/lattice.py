"""The lattice of cuboids: levels in hop order, numbers, and the bitmap tag of a set of cuboids."""

from __future__ import annotations

from itertools import combinations


class Lattice:
    """All subsets of the dimensions.  Level k starts with the cyclic intervals of length k, then the rest in order."""

    def __init__(self, dims):
        self.dims = tuple(dims)
        self._numbered: list[frozenset[str]] = [frozenset()]
        for k in range(1, len(self.dims) + 1):
            self._numbered += self.level(k)
        self._number = {c: i for i, c in enumerate(self._numbered)}

    def interval(self, start: int, length: int) -> tuple[str, ...]:
        n = len(self.dims)
        return tuple(self.dims[(start + i) % n] for i in range(length))

    def level(self, k: int) -> list[frozenset[str]]:
        first = [frozenset(self.interval(s, k)) for s in range(len(self.dims))]
        return list(dict.fromkeys([*first, *map(frozenset, combinations(self.dims, k))]))

    def levels(self) -> list[list[frozenset[str]]]:
        return [self.level(k) for k in range(1, len(self.dims) + 1)]

    def number(self, cuboid) -> int:
        return self._number[frozenset(cuboid)]

    def cuboid(self, number: int) -> frozenset[str]:
        return self._numbered[number]

    def tag(self, members) -> int:
        """A bitmap of the whole lattice: bit i stands for cuboid number i."""
        return sum(1 << self.number(m) for m in members)

    def of_tag(self, tag: int) -> list[frozenset[str]]:
        return [c for i, c in enumerate(self._numbered) if tag >> i & 1]

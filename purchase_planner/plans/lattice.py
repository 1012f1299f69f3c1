"""Attribute-set lattices and the covers of a request's attributes by instances."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from itertools import combinations, product


def lattice(attributes: Sequence[str], min_size: int = 2) -> Iterator[tuple[str, ...]]:
    """All subsets of at least min_size attributes, smaller ones first; lazily, as there are 2 to the power m of them."""
    for size in range(min_size, len(attributes) + 1):
        yield from combinations(attributes, size)


def size(m: int, min_size: int = 2) -> int:
    """How many vertices the lattice over m attributes has."""
    from math import comb

    return sum(comb(m, k) for k in range(min_size, m + 1))


def height(m: int, min_size: int = 2) -> int:
    """Levels of the lattice over m attributes."""
    return max(m - min_size + 1, 0)


def children(vertex: Sequence[str], attributes: Sequence[str]) -> list[tuple[str, ...]]:
    """The sets with one attribute more."""
    return [tuple(a for a in attributes if a in vertex or a == new) for new in attributes if new not in vertex]


def is_ancestor(small: Sequence[str], large: Sequence[str]) -> bool:
    return set(small) < set(large)


def siblings(vertex: Sequence[str], attributes: Sequence[str]) -> list[tuple[str, ...]]:
    """Other sets of the same size that share all but one attribute."""
    return [s for s in combinations(attributes, len(vertex)) if len(set(s) & set(vertex)) == len(vertex) - 1]


def as_mask(vertex: Sequence[str], attributes: Sequence[str]) -> int:
    return sum(1 << i for i, a in enumerate(attributes) if a in vertex)


def of_mask(mask: int, attributes: Sequence[str]) -> tuple[str, ...]:
    return tuple(a for i, a in enumerate(attributes) if mask >> i & 1)


def partitions(items: Sequence[str]) -> Iterator[list[tuple[str, ...]]]:
    """All ways to cut a list into groups."""
    if not items:
        yield []
        return
    head, *rest = items
    for k in range(len(rest) + 1):
        for mates in combinations(rest, k):
            left = [x for x in rest if x not in mates]
            for tail in partitions(left):
                yield [(head, *mates), *tail]


def cover_sets(holders: dict[frozenset[str], Sequence[str]], targets: Sequence[str]) -> list[frozenset[tuple[str, frozenset[str]]]]:
    """All covers of the targets by instance vertices, each with the union of the attributes taken from it.

    holders: which instances offer each attribute set. Sets may overlap; covers that come to the same vertices and
    attributes count once.
    """
    want = frozenset(targets)
    sets = [s for s in holders if s <= want]
    found: set[frozenset[tuple[str, frozenset[str]]]] = set()
    for k in range(1, len(want) + 1):
        for chosen in combinations(sets, k):
            if frozenset().union(*chosen) != want:
                continue
            if any(sum(len(c & d) for d in chosen if d is not c) and c < d for c in chosen for d in chosen):
                continue
            for vertices in product(*(holders[c] for c in chosen)):
                merged: dict[str, frozenset[str]] = {}
                for v, c in zip(vertices, chosen, strict=True):
                    merged[v] = merged.get(v, frozenset()) | c
                found.add(frozenset(merged.items()))
    return sorted(found, key=lambda f: sorted((v, sorted(a)) for v, a in f))


def assignments(attributes: Sequence[str], instances: dict[str, Sequence[str]]) -> Iterator[dict[str, str]]:
    """All ways to take each attribute from one of the instances that hold it."""
    options = [[n for n in sorted(instances) if a in instances[n]] for a in attributes]
    for chosen in product(*options):
        yield dict(zip(attributes, chosen, strict=True))

"""The driver's side of the search: sets of columns as bit masks with their open candidates.  Metadata only."""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass, field

from ..model import bits


@dataclass
class Node:
    """A set of columns: attributes that may still be a new constant of some set here or above, and open pairs."""

    constants: int
    pairs: set[int] = field(default_factory=set)


Level = dict[int, Node]


def seed(columns: int) -> tuple[Level, Level]:
    """The empty set and the single columns."""
    everything = (1 << columns) - 1
    return {0: Node(everything)}, {1 << k: Node(everything) for k in range(columns)}


def inherit(mask: int, size: int, below: Level, candidate_pruning: bool, everything: int) -> Node:
    """Open candidates of a set: constants that are open in all its subsets of one less; pairs open in each of those
    subsets that holds both ends."""
    members = bits(mask)
    if not candidate_pruning:
        own = {1 << a | 1 << b for k, a in enumerate(members) for b in members[k + 1 :]} if size > 1 else set()
        return Node(everything, own)
    constants = everything
    for k in members:
        constants &= below[mask ^ 1 << k].constants
    if size < 2:
        return Node(constants)
    if size == 2:
        return Node(constants, {mask})
    seen: dict[int, int] = defaultdict(int)
    for k in members:
        for p in below[mask ^ 1 << k].pairs:
            seen[p] += 1
    return Node(constants, {p for p, n in seen.items() if n == size - 2})


def grow(level: Level, size: int) -> list[int]:
    """Sets of one more column, all of whose subsets of this size are in the level: two sets that differ in their last
    column only are joined."""
    blocks: dict[int, list[int]] = defaultdict(list)
    for mask in level:
        blocks[mask ^ 1 << mask.bit_length() - 1].append(mask)
    out = []
    for head, masks in blocks.items():
        masks.sort()
        for i, x in enumerate(masks):
            for y in masks[i + 1 :]:
                both = x | y
                if all(both ^ 1 << k in level for k in bits(head)):
                    out.append(both)
    return out


def lattice_size(columns: int) -> tuple[int, int]:
    """Nodes of the lattice of sets, and of the lattice of lists without repeats."""
    lists, term = 1, 1
    for k in range(columns, 0, -1):
        term *= k
        lists += term
    return 1 << columns, lists

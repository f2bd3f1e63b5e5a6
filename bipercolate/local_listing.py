"""Listing (alpha, beta)-bicliques inside one group of maximal bicliques, whose labels merge while it goes on.

A group holds the maximal bicliques around a common prefix. Its bicliques are bits; a vertex is the mask of those that
contain it, so the bicliques around a longer prefix are one intersection. Masks per label tell at once whether a
support has one label left: then nothing below could merge more, and the search turns back, also in the middle of a
loop whose own findings have settled it.
"""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass
class Tally:
    """Nodes visited: left prefixes, right prefixes, and whole (alpha, beta)-bicliques."""

    prefixes: int = 0
    rights: int = 0
    leaves: int = 0


class Merging:
    """Labels of the bicliques of a group under union; ``links`` are the unions made, in the given labels."""

    def __init__(self, labels: list[int]) -> None:
        self.names = sorted(set(labels))
        place = {x: k for k, x in enumerate(self.names)}
        self.of, self.parent = [place[x] for x in labels], list(range(len(self.names)))
        self.mask = [0] * len(self.names)
        for k, x in enumerate(self.of):
            self.mask[x] |= 1 << k
        self.links: list[tuple[int, int]] = []

    def find(self, x: int) -> int:
        while self.parent[x] != x:
            self.parent[x] = self.parent[self.parent[x]]
            x = self.parent[x]
        return x

    def settled(self, support: int) -> bool:
        """The bicliques of a support, if any, have one label."""
        return not support or not support & ~self.mask[self.find(self.of[(support & -support).bit_length() - 1])]

    def unite(self, support: int) -> None:
        first = self.find(self.of[(support & -support).bit_length() - 1])
        while rest := support & ~self.mask[first]:
            other = self.find(self.of[(rest & -rest).bit_length() - 1])
            self.links.append((self.names[first], self.names[other]))
            self.parent[other] = first
            self.mask[first] |= self.mask[other]


@dataclass
class Group:
    """``left`` and ``right``: what may follow the prefix, ascending, as masks of the bicliques that contain each vertex."""

    labels: Merging
    left: list[int]
    right: list[int]
    n: int
    tally: Tally = field(default_factory=Tally)

    @classmethod
    def of(cls, rows: list[tuple[int, list[int], list[int]]]) -> Group:
        """``rows``: label of each biclique, and its left and right vertices after the prefix."""
        sides: list[list[int]] = []
        for side in (1, 2):
            masks: dict[int, int] = {}
            for k, row in enumerate(rows):
                for w in row[side]:
                    masks[w] = masks.get(w, 0) | 1 << k
            sides.append([masks[w] for w in sorted(masks)])
        return cls(Merging([r[0] for r in rows]), *sides, len(rows))


def merge_group(group: Group, alpha: int, beta: int, prune: bool = True, prune_right: bool = True, restrict: bool = True) -> list[tuple[int, int]]:
    """Unite the labels around every (alpha, beta)-biclique that extends the prefix by so many vertices; returns the links.

    ``prune``: turn back at supports of one label; ``prune_right``: between right vertices too; ``restrict``: only vertices
    that bicliques of two labels share may follow.
    """
    labels, tally = group.labels, group.tally
    settled = labels.settled

    def follow(masks: list[int], support: int, narrow: bool) -> list[int]:
        return [m for m in masks if not settled(support & m)] if narrow else [m for m in masks if support & m]

    def right(support: int, missing: int, rest: list[int]) -> None:
        for at, mask in enumerate(rest):
            if len(rest) - at < missing:
                return
            inside = support & mask
            if not inside or prune and (prune_right or missing == 1) and settled(inside):
                continue
            if missing == 1:
                tally.leaves += 1
                labels.unite(inside)
            else:
                tally.rights += 1
                right(inside, missing - 1, follow(rest[at + 1 :], inside, prune and prune_right and restrict))
            if prune and settled(support):
                return

    def left(support: int, missing: int, ext: list[int], rest: list[int]) -> None:
        tally.prefixes += 1
        if not missing:
            if beta:
                right(support, beta, rest)
            else:
                tally.leaves += 1
                labels.unite(support)
            return
        for at, mask in enumerate(ext):
            if len(ext) - at < missing:
                return
            inside = support & mask
            if not inside or prune and settled(inside):
                continue
            after = follow(rest, inside, prune and restrict)
            if len(after) < beta:
                continue
            left(inside, missing - 1, follow(ext[at + 1 :], inside, prune and restrict), after)
            if prune and settled(support):
                return

    every = (1 << group.n) - 1
    if not prune or not settled(every):
        narrow = prune and restrict
        left(every, alpha, follow(group.left, every, narrow), follow(group.right, every, narrow))
    return labels.links


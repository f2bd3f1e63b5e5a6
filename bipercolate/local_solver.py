"""Maximal bicliques of one root's neighbourhood, on Python integers as bit sets.

A node of the enumeration tree holds, for each side, the vertices chosen (R), those that may still be chosen (C) and those
that may not, because an earlier branch covers them (X). Choosing a vertex keeps only its neighbours among the other
side's C and X. A node with empty C is a maximal biclique exactly if its X are empty too.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import cached_property
from itertools import islice

import numpy as np

#: Right candidates from which a pivot is sought on arrays.
MANY = 24


def bits(mask: int) -> Iterator[int]:
    while mask:
        low = mask & -mask
        yield low.bit_length() - 1
        mask ^= low


@dataclass
class Found:
    """A leaf (``kind`` "biclique") or the first node of a path that reached both sizes (``kind`` "seed")."""

    kind: str
    x: list[int]
    y: list[int]
    seed: int


@dataclass
class Ego:
    """The subgraph around a root: left vertices that share a neighbour with it, and its neighbours."""

    root: int
    left: list[int]
    right: list[int]
    of_left: list[int] = field(default_factory=list)
    of_right: list[int] = field(default_factory=list)

    @classmethod
    def of(cls, root: int, pairs: list[tuple[int, int]]) -> Ego:
        """``pairs``: edges (w, v) with v a neighbour of the root; the root's own are among them."""
        left, right = sorted({w for w, _ in pairs}), sorted({v for _, v in pairs})
        at_l, at_r = {w: k for k, w in enumerate(left)}, {v: k for k, v in enumerate(right)}
        ego = cls(root, left, right, [0] * len(left), [0] * len(right))
        for w, v in pairs:
            ego.of_left[at_l[w]] |= 1 << at_r[v]
            ego.of_right[at_r[v]] |= 1 << at_l[w]
        return ego

    def places(self, mask: int) -> np.ndarray:
        """The right vertices in a mask, as ``bits`` gives them."""
        flags = np.frombuffer(mask.to_bytes(-(-len(self.right) // 8), "little"), np.uint8)
        return np.flatnonzero(np.unpackbits(flags, bitorder="little").view(bool))

    @cached_property
    def masks(self) -> np.ndarray:
        """``of_right`` in words of 64 bits, a row per right vertex."""
        width = -(-len(self.left) // 64) * 8
        return np.frombuffer(b"".join(m.to_bytes(width, "little") for m in self.of_right), np.uint64).reshape(len(self.of_right), -1)

    def fewest_missing(self, opposite: int, mask: int) -> tuple[int, int]:
        """Of the right vertices in ``mask``, the first with fewest non-neighbours among the left ones in ``opposite``, after their number."""
        at = self.places(mask)
        wanted = np.frombuffer(opposite.to_bytes(self.masks.shape[1] * 8, "little"), np.uint64)
        met = np.bitwise_count(self.masks[at] & wanted)
        met = met[:, 0] if met.shape[1] == 1 else met.sum(axis=1, dtype=np.int64)
        k = int(met.argmax())
        return opposite.bit_count() - int(met[k]), int(at[k])


def pick(ego: Ego, cu: int, cv: int, xu: int, xv: int) -> tuple[int, bool, int, int]:
    """``(side, excluded, vertex, its non-neighbours)`` of the pivot: fewest non-neighbours among the opposite candidates, then excluded, then left, then least."""
    best = None
    for side, mask, excluded, opposite, adjacent in ((0, xu, True, cv, ego.of_left), (1, xv, True, cu, ego.of_right), (0, cu, False, cv, ego.of_left), (1, cv, False, cu, ego.of_right)):
        for k in (ego.fewest_missing(opposite, mask)[1:] if adjacent is ego.of_right and mask.bit_count() >= MANY else bits(mask)):
            missing = opposite & ~adjacent[k]
            n = missing.bit_count()
            if best is None or n < best[0]:
                best = (n, side, excluded, k, missing)
                if not n:
                    return best[1:]
    return best[1:]


def enumerate_root(
    ego: Ego, alpha: int = 1, beta: int = 1, pivot: bool = True, cut_small: bool = False, part: int = 0, parts: int = 1,
    counts: dict | None = None, trace: Callable[[dict], None] | None = None, budget: int | None = None,
) -> Iterator[Found]:
    """Maximal bicliques whose least left vertex is the root, and seeds for (alpha, beta).

    ``cut_small`` drops nodes that can't reach the sizes. Of ``parts`` tasks that share a root, task ``part`` takes every
    parts-th branch below the chain of forced choices at the root; branches are independent, as each knows which siblings come before it.
    A vertex adjacent to all opposite candidates is forced: it is taken in place, without a branch of its own. ``trace`` is
    told every node (forced ones too); more than ``budget`` nodes are an error.
    """
    me = ego.left.index(ego.root)
    later = sum(1 << k for k, w in enumerate(ego.left) if w > ego.root)
    earlier = sum(1 << k for k, w in enumerate(ego.left) if w < ego.root)
    names = lambda side, mask: [(ego.left, ego.right)[side][k] for k in (ego.places(mask).tolist() if side and mask.bit_count() >= MANY else bits(mask))]
    seeds, nodes, mine = 0, 0, part == 0
    # Per node: the six sets, the number and the node of its seed, its parent, its level, the side and vertex that led here, and whether no branch came before.
    stack = [((1 << me, 0, later, (1 << len(ego.right)) - 1, earlier, 0), (-1, -1), -1, 1, 0, me, True)]
    while stack:
        (ru, rv, cu, cv, xu, xv), seed, parent, level, side, vertex, first = stack.pop()
        while True:
            if cut_small and ((ru | cu).bit_count() < alpha or (rv | cv).bit_count() < beta):
                break
            at, nodes = nodes, nodes + 1
            if budget is not None and nodes > budget:
                raise RuntimeError(f"the tree below root {ego.root} has more than {budget} nodes")
            if counts is not None and (mine or not first):
                counts["nodes"] = counts.get("nodes", 0) + 1
            reached = seed[0] < 0 and ru.bit_count() >= alpha and rv.bit_count() >= beta
            if reached:
                seed, seeds = (seeds * parts + (0 if first else part), at), seeds + 1  # no two tasks of a root use a number twice
                if mine or not first:
                    yield Found("seed", names(0, ru), names(1, rv), seed[0])
            leaf = not cu and not cv
            maximal = leaf and not xu and not xv and bool(rv)
            if trace:
                sets = {f"{c}_{'uv'[s]}": names(s, m) for c, s, m in (("r", 0, ru), ("r", 1, rv), ("c", 0, cu), ("c", 1, cv), ("x", 0, xu), ("x", 1, xv))}
                trace({"at": at, "parent": parent, "level": level, "via_side": "uv"[side], "via": (ego.left, ego.right)[side][vertex], **sets, "seed": reached, "seed_id": seed[1], "biclique": maximal})
            if maximal and (mine or not first):
                yield Found("biclique", names(0, ru), names(1, rv), seed[0])
            if leaf:
                break
            if pivot and not trace and not cu:
                # Each right candidate is forced in turn, unless an excluded vertex extends them all: the chain is taken at once.
                steps = cv.bit_count()
                if xv or any(not cv & ~ego.of_left[k] for k in bits(xu)):
                    break
                nodes += steps
                if budget is not None and nodes > budget:
                    raise RuntimeError(f"the tree below root {ego.root} has more than {budget} nodes")
                if counts is not None and (mine or not first):
                    counts["nodes"] += steps
                if seed[0] < 0 and ru.bit_count() >= alpha and rv.bit_count() + steps >= beta:
                    seed, seeds = (seeds * parts + (0 if first else part), at), seeds + 1
                    if mine or not first:
                        yield Found("seed", names(0, ru), names(1, rv | sum(1 << k for k in islice(bits(cv), beta - rv.bit_count()))), seed[0])
                if mine or not first:
                    yield Found("biclique", names(0, ru), names(1, rv | cv), seed[0])
                break
            if not pivot:
                branches = [(0, k) for k in bits(cu)] + [(1, k) for k in bits(cv)]
            else:
                over, excluded, p, missing = pick(ego, cu, cv, xu, xv)
                if not missing and excluded:
                    break  # everything below extends by the excluded vertex
                if not missing:  # forced: the only child
                    bit = 1 << p
                    if over == 0:
                        ru, cu, xv = ru | bit, cu & ~bit, xv & ego.of_left[p]
                    else:
                        rv, cv, xu = rv | bit, cv & ~bit, xu & ego.of_right[p]
                    parent, level, side, vertex = at, level + 1, over, p
                    continue
                branches = ([] if excluded else [(over, p)]) + [(1 - over, k) for k in bits(missing)]
            children = []
            for turn, (over, k) in enumerate(branches):
                bit = 1 << k
                if over == 0:
                    cu &= ~bit
                    child = (ru | bit, rv, cu, cv & ego.of_left[k], xu, xv & ego.of_left[k])
                    xu |= bit
                else:
                    cv &= ~bit
                    child = (ru, rv | bit, cu & ego.of_right[k], cv, xu & ego.of_right[k], xv)
                    xv |= bit
                if not first or turn % parts == part:
                    children.append((child, seed, at, level + 1, over, k, False))
            stack += reversed(children)
            break

"""The overlap graph: maximal bicliques, linked where they share enough vertices on both sides."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bipercolate.checkpoints import cut

#: Vertices in the bicliques that one round of ``communities.by_overlap`` sends to postings.
ELEMENTS_AT_ONCE = 8_000_000


def qualify(bicliques: DataFrame, alpha: int, beta: int) -> DataFrame:
    return bicliques.filter((F.col("n_x") >= alpha) & (F.col("n_y") >= beta))


def _postings(bicliques: DataFrame, least: int, prefix: bool, sets: str = "x") -> DataFrame:
    """``[biclique_id, vertex]`` over one side. With ``prefix``, only the n - least + 1 rarest of each: two sets that share so many vertices share one of those."""
    every = bicliques.select("biclique_id", F.size(sets).alias("n_of"), F.explode(sets).alias("vertex"))
    if not prefix:
        return every.select("biclique_id", "vertex")
    rarity = every.groupBy("vertex").agg(F.count("*").alias("n"))
    ranked = every.join(rarity, "vertex").groupBy("biclique_id", "n_of").agg(F.array_sort(F.collect_list(F.struct("n", "vertex"))).alias("by_rarity"))
    rarest = F.explode(F.slice("by_rarity", 1, F.greatest(F.col("n_of") - least + 1, F.lit(0)))).alias("r")
    return ranked.select("biclique_id", rarest).select("biclique_id", "r.vertex")


def _pairs(posts: DataFrame, groups: DataFrame | None) -> DataFrame:
    if groups is None:
        left, right, differ = posts.select(F.col("biclique_id").alias("a"), "vertex"), posts.select(F.col("biclique_id").alias("b"), "vertex"), F.lit(True)
    else:
        posts = posts.join(groups.select("biclique_id", "label"), "biclique_id")
        left = posts.select(F.col("biclique_id").alias("a"), "vertex", F.col("label").alias("la"))
        right = posts.select(F.col("biclique_id").alias("b"), "vertex", F.col("label").alias("lb"))
        differ = F.col("la") != F.col("lb")
    return left.join(right, "vertex").filter((F.col("a") < F.col("b")) & differ).select("a", "b").distinct()


def candidates(bicliques: DataFrame, alpha: int = 1, prefix: bool = False, groups: DataFrame | None = None) -> DataFrame:
    """Pairs a < b of bicliques that share a (prefix) left vertex; with ``groups`` [biclique_id, label], only of different groups."""
    return _pairs(_postings(bicliques, alpha, prefix), groups)


def rarer_postings(bicliques: DataFrame, alpha: int, beta: int) -> DataFrame:
    """The prefix postings of the side whose lists pair up fewer bicliques, as counted.

    Postings pair up at least with themselves, so that a side with more of them than the other makes pairs is never written.
    """
    sides = [(alpha, "x"), (beta, "y")]
    postings = lambda least, sets: F.coalesce(F.sum(F.greatest(F.size(sets) - least + 1, F.lit(0)).cast("double")), F.lit(0.0))
    few, many = sorted(zip(bicliques.agg(*(postings(*s) for s in sides)).first(), sides, strict=True))
    pairs = lambda p: p.groupBy("vertex").agg(F.count("*").cast("double").alias("n")).agg(F.sum(F.col("n") * F.col("n"))).first()[0] or 0
    first = cut(_postings(bicliques, few[1][0], True, few[1][1]))
    if (cost := pairs(first)) <= many[0]:
        return first
    second = cut(_postings(bicliques, many[1][0], True, many[1][1]))
    return first if cost <= pairs(second) else second


def lighter_side(bicliques: DataFrame, alpha: int, beta: int, prefix: bool = True) -> tuple[str, float]:
    """The side whose postings are sent fewer vertices, when each gets its whole biclique, and how many these are."""
    n, m = F.size("x").cast("double"), F.size("y").cast("double")
    posted = lambda size, least: F.greatest(size - (least - 1 if prefix else 0), F.lit(0.0)) * (n + m)
    by_x, by_y = (s or 0.0 for s in bicliques.agg(F.sum(posted(n, alpha)), F.sum(posted(m, beta))).first())
    return ("x", by_x) if by_x <= by_y else ("y", by_y)


def side_postings(bicliques: DataFrame, alpha: int, beta: int, prefix: bool, side: str) -> DataFrame:
    return _postings(bicliques, alpha if side == "x" else beta, prefix, side)


def links_between(posts: DataFrame, bicliques: DataFrame, labels: DataFrame, alpha: int, beta: int, side: str) -> DataFrame:
    """``[a, b]``: labels that overlapping bicliques link, as many as join all of them that meet at a posting of ``posts`` [biclique_id, vertex].

    Postings of one label are not sent. At a posting pairs are tested whose labels no pair before has joined.
    """
    rows = posts.join(labels, "biclique_id")
    mixed = rows.groupBy("vertex").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).filter("lo <> hi").select("vertex")
    own, far = (F.col(c) for c in (("x", "y") if side == "x" else ("y", "x")))
    rows = rows.join(mixed, "vertex", "left_semi").join(bicliques.select("biclique_id", own.alias("own"), far.alias("far")), "biclique_id")
    least = (alpha, beta) if side == "x" else (beta, alpha)
    return rows.select("vertex", "label", "own", "far").groupBy("vertex").applyInArrow(lambda group: _joined(group, *least), "a long, b long").distinct()


class Sets:
    """Sets of ids, flat, none empty."""

    def __init__(self, lists: pa.ChunkedArray) -> None:
        one = lists.combine_chunks()
        self.size = one.value_lengths().to_numpy().astype(np.int64)
        self.names, self.flat = np.unique(one.flatten().to_numpy(), return_inverse=True)
        self.start, self.mark = np.cumsum(self.size) - self.size, np.zeros(len(self.names), bool)
        self.ends: np.ndarray | None = None

    def _met(self, among: np.ndarray | None) -> np.ndarray:
        """How many marked ids each set has."""
        if among is None:
            return np.add.reduceat(self.mark[self.flat], self.start, dtype=np.int64)
        size = self.size[among]
        start = np.cumsum(size) - size
        return np.add.reduceat(self.mark[self.flat[np.arange(size.sum()) + np.repeat(self.start[among] - start, size)]], start, dtype=np.int64)

    def shared(self, k: int, among: np.ndarray | None = None) -> np.ndarray:
        """How many ids set k has in common with every set, or with some."""
        mine = self.flat[self.start[k] : self.start[k] + self.size[k]]
        self.mark[mine] = True
        out = self._met(among)
        self.mark[mine] = False
        return out

    def shared_with(self, ids: list[int], among: np.ndarray) -> np.ndarray:
        """How many of the ids each of some sets has."""
        self.mark[self._places(ids)] = True
        out = self._met(among)
        self.mark[:] = False
        return out

    def holding(self, ids: list[int]) -> np.ndarray:
        """The sets with all of the ids."""
        at = self._places(ids)
        if len(at) < len(ids):
            return np.zeros(0, np.int64)
        if self.ends is None:
            self.ends = np.concatenate([[0], np.cumsum(np.bincount(self.flat, minlength=len(self.names)))])
            self.sets_of = np.repeat(np.arange(len(self.size)), self.size)[np.argsort(self.flat, kind="stable")]
            self.rows: dict[int, np.ndarray] = {}
        few = min(at, key=lambda k: self.ends[k + 1] - self.ends[k])
        some = self.sets_of[self.ends[few] : self.ends[few + 1]]
        if 64 * len(some) < len(self.size):
            return some[self.shared_with(ids, some) == len(ids)]
        return np.flatnonzero(np.logical_and.reduce([self._row(int(k)) for k in at]))

    def _row(self, place: int) -> np.ndarray:
        """Which sets hold an id; kept for ids that so many do that rows take no more than 64 times the sets."""
        if place not in self.rows:
            self.rows[place] = np.zeros(len(self.size), bool)
            self.rows[place][self.sets_of[self.ends[place] : self.ends[place + 1]]] = True
        return self.rows[place]

    def _places(self, ids: list[int]) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.names, ids), len(self.names) - 1)
        return at[self.names[at] == np.array(ids, np.int64)]


def _joined(group: pa.Table, least_own: int, least_far: int) -> pa.Table:
    """Links that join the labels of all overlapping bicliques of a group.

    Every biclique, those with fewest vertices first, is compared with all of other labels, except bicliques that have the label of
    the first by then: two of these need no test, and another biclique is compared with them in its turn.
    """
    names, label = np.unique(group["label"].to_numpy(), return_inverse=True)
    own, far = Sets(group["own"]), Sets(group["far"])
    order = np.argsort(own.size, kind="stable")
    first, left, a, b = label[order[0]], len(names), [], []
    for k in order:
        if left == 1:
            break
        if label[k] == first and k != order[0]:
            continue
        others = np.flatnonzero((own.shared(k) >= least_own) & (label != label[k]))
        if len(others):
            others = others[far.shared(k, others) >= least_far]
        if not len(others):
            continue
        met = np.unique(np.append(label[others], label[k]))
        to = first if first in met else label[k]
        rest = met[met != to]
        a.append(np.full(len(rest), names[to]))
        b.append(names[rest])
        place = np.arange(len(names))
        place[rest] = to
        label, left = place[label], left - len(rest)
    flat = lambda parts: pa.array(np.concatenate(parts) if parts else [], pa.int64())
    return pa.table({"a": flat(a), "b": flat(b)})


def edges(bicliques: DataFrame, alpha: int, beta: int, prefix: bool = True, groups: DataFrame | None = None) -> DataFrame:
    """``[a, b, common_x, common_y]`` of all linked pairs."""
    good = qualify(bicliques, alpha, beta)
    sets = good.select("biclique_id", "x", "y")
    pairs = _pairs(rarer_postings(good, alpha, beta) if prefix else _postings(good, alpha, False), groups)
    left = sets.select(F.col("biclique_id").alias("a"), F.col("x").alias("xa"), F.col("y").alias("ya"))
    right = sets.select(F.col("biclique_id").alias("b"), F.col("x").alias("xb"), F.col("y").alias("yb"))
    both = pairs.join(left, "a").join(right, "b")
    return (
        both.select("a", "b", F.size(F.array_intersect("xa", "xb")).alias("common_x"), F.size(F.array_intersect("ya", "yb")).alias("common_y"))
        .filter((F.col("common_x") >= alpha) & (F.col("common_y") >= beta))
    )


def brute_force_edges(bicliques: DataFrame, alpha: int, beta: int) -> DataFrame:
    """Every pair compared: a baseline for tests on small graphs only."""
    s = qualify(bicliques, alpha, beta)
    left, right = s.select(F.col("biclique_id").alias("a"), F.col("x").alias("xa"), F.col("y").alias("ya")), s.select(F.col("biclique_id").alias("b"), F.col("x").alias("xb"), F.col("y").alias("yb"))
    return left.join(right, F.col("a") < F.col("b")).filter((F.size(F.array_intersect("xa", "xb")) >= alpha) & (F.size(F.array_intersect("ya", "yb")) >= beta)).select("a", "b")

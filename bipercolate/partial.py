"""Partial groups: bicliques that are known to be connected before any overlap is tested."""

from __future__ import annotations

from math import ceil

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bipercolate import tree
from bipercolate.checkpoints import cut, packed, release, scratch
from bipercolate.components import FEW_LINKS, merge
from bipercolate.overlap import ELEMENTS_AT_ONCE, Sets, lighter_side, qualify


def singletons(bicliques: DataFrame) -> DataFrame:
    return bicliques.select("biclique_id", F.col("biclique_id").alias("label"))


def by_prefix(bicliques: DataFrame, alpha: int, beta: int) -> DataFrame:
    """Qualified bicliques below one seed node form a group: the seed travels in the leaf, so this is one aggregation."""
    good = qualify(bicliques, alpha, beta)
    least = good.groupBy("seed_id").agg(F.min("biclique_id").alias("label"))
    return good.join(least, "seed_id").select("biclique_id", "label")


def by_seed(bicliques: DataFrame, seeds: DataFrame, alpha: int, beta: int) -> DataFrame:
    """All qualified bicliques that contain a seed, live or dead, belong together, wherever in the tree they are.

    A seed meets the bicliques at its rarest vertex of one side. Who contains it is found there, and only links that join labels leave the
    task. Vertices are dealt to rounds, between which labels are merged.
    """
    good = qualify(bicliques, alpha, beta).select("biclique_id", "x", "y")
    labels = packed(singletons(good))
    side, elements = lighter_side(good, 1, 1)
    own, far = ("x", "y") if side == "x" else ("y", "x")
    r_own, r_far = ("r_u", "r_v") if side == "x" else ("r_v", "r_u")
    posts = good.select("biclique_id", F.explode(own).alias("vertex"))
    rarity = posts.groupBy("vertex").agg(F.count("*").alias("n"))
    sets = packed(seeds.select("r_u", "r_v").distinct().withColumn("seed", F.monotonically_increasing_id()))
    rarest = sets.select("seed", F.explode(r_own).alias("vertex")).join(rarity, "vertex").groupBy("seed").agg(F.min(F.struct("n", "vertex"))["vertex"].alias("vertex"))
    keyed = packed(rarest.join(sets, "seed").select("vertex", F.lit(None).cast("long").alias("label"), F.col(r_own).alias("own"), F.col(r_far).alias("far")))
    rounds = max(1, ceil(elements / ELEMENTS_AT_ONCE))
    for k in range(rounds):
        now = F.pmod(F.xxhash64("vertex"), F.lit(rounds)) == k
        wanted = keyed.filter(now)
        rows = posts.filter(now).join(wanted.select("vertex").distinct(), "vertex", "left_semi").join(labels, "biclique_id")
        mixed = rows.groupBy("vertex").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).filter("lo <> hi").select("vertex")
        rows = rows.join(mixed, "vertex", "left_semi").join(good.select("biclique_id", F.col(own).alias("own"), F.col(far).alias("far")), "biclique_id")
        rows = rows.select("vertex", "label", "own", "far").union(wanted.join(mixed, "vertex", "left_semi").select("vertex", "label", "own", "far"))
        links = rows.groupBy("vertex").applyInArrow(_around_seeds, "a long, b long").distinct()
        with scratch() as keep:
            labels = keep(packed(merge(labels, cut(links), "biclique_id", "label", FEW_LINKS).select(F.col("item").alias("biclique_id"), "label")))
    release(keyed)
    release(sets)
    return labels


def _around_seeds(group: pa.Table) -> pa.Table:
    """Links that join the labels of the bicliques [label, own, far] around each seed (a row without a label).

    Bicliques of the label that most have are only looked at for seeds that others contain.
    """
    rows, seeds = group.filter(pc.is_valid(group["label"])), group.filter(pc.is_null(group["label"]))
    empty = pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64())})
    if not rows.num_rows or not seeds.num_rows:
        return empty
    names, label = np.unique(rows["label"].to_numpy(), return_inverse=True)
    own, far, left, a, b = Sets(rows["own"]), Sets(rows["far"]), len(names), [], []
    most = np.bincount(label).argmax()
    for mine, theirs in zip(seeds["own"].to_pylist(), seeds["far"].to_pylist(), strict=True):
        if left == 1:
            break
        around = own.holding(mine)
        if len(around) < 2 or (label[around] == label[around[0]]).all():
            continue
        in_most = label[around] == most
        other = around[~in_most]
        other = other[far.shared_with(theirs, other) == len(theirs)]
        if not len(other):
            continue
        met, around = np.unique(label[other]), around[in_most]
        if len(around) and (far.shared_with(theirs, around) == len(theirs)).any():
            met = np.append(met, most)
        to = met[-1]
        rest = met[:-1]
        if not len(rest):
            continue
        a.append(np.full(len(rest), names[to]))
        b.append(names[rest])
        place = np.arange(len(names))
        place[rest] = to
        label, left = place[label], left - len(rest)
    return pa.table({"a": pa.array(np.concatenate(a), pa.int64()), "b": pa.array(np.concatenate(b), pa.int64())}) if a else empty


def by_tree_walk(edges: DataFrame, bicliques: DataFrame, alpha: int, beta: int, tags: bool = True) -> DataFrame:
    """The groups of ``by_seed`` found by walking the enumeration tree (see ``tree.Walk``): ``[biclique_id, label]``.

    ``bicliques`` are those of ``edges``. The walk takes a component's whole tree into one task and refuses large ones.
    """
    good = qualify(bicliques, alpha, beta)
    found = tree.walk_groups(edges, alpha, beta, tags).select("x", "y", "group_id")
    placed = good.select("biclique_id", F.array_sort("x").alias("x"), F.array_sort("y").alias("y")).join(found, ["x", "y"])
    least = placed.groupBy("group_id").agg(F.min("biclique_id").alias("label"))
    return placed.join(least, "group_id").select("biclique_id", "label")

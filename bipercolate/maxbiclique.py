"""All maximal bicliques of a bipartite graph, with the seeds that the partial-group methods need.

Engines: ``local`` solves each left vertex's neighbourhood on bit sets in Arrow batches (neighbourhoods come from one
self-join; those with many pairs are shared out by their first branches), ``frontier`` grows all tree nodes a level at a time by
joins, ``closure`` intersects neighbour lists to a fix-point with native expressions (no tree, hence no seeds).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import ceil

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bipercolate import cohesive
from bipercolate.checkpoints import cut, packed, scratch
from bipercolate.graph import PAIRS_AT_ONCE, adjacency, cheaper_side, check_thresholds, swapped
from bipercolate.local_solver import Ego, enumerate_root
from bipercolate.operators.joins import BROADCAST_IDS

LEAVES = "kind string, root long, part int, seed long, x array<long>, y array<long>, nodes long"
#: Pairs (2-hop vertex, shared neighbour) of a root above which several tasks share it.
HEAVY = 50_000


@dataclass
class Enumeration:
    """``bicliques``: biclique_id, x, y, n_x, n_y, seed_id (null without a seed); ``seeds``: seed_id, r_u, r_v, live; ``nodes``: tree nodes visited (null for closure)."""

    bicliques: DataFrame
    seeds: DataFrame
    nodes: int | None


def _union(frames: list[DataFrame]) -> DataFrame:
    return frames[0] if len(frames) == 1 else frames[0].union(_union(frames[1:]))


def _dealt(edges: DataFrame, rounds: int) -> list[DataFrame]:
    """Edges by left vertex, for so many rounds."""
    return [edges if rounds == 1 else edges.filter(F.pmod(F.xxhash64("u"), F.lit(rounds)) == i) for i in range(rounds)]


def _near(edges: DataFrame, least_shared: int, at_once: int = PAIRS_AT_ONCE, bound: int = BROADCAST_IDS) -> DataFrame:
    """``[root, w, v]``: the edges of 2-hop vertices that share at least so many neighbours with a root, to these neighbours.

    Which vertices do is counted first, each pair once and in rounds, so that no job shuffles many more pairs than there are edges; then up to
    ``bound`` pairs go to the edges, and more meet them in rounds again.
    """
    other = edges.select(F.col("u").alias("w"), "v")
    squares, n = edges.groupBy("v").agg(F.count("*").cast("double").alias("d")).agg(F.sum(F.col("d") * F.col("d")), F.sum("d")).first()
    most = max(at_once, n or 0)
    rounds = lambda pairs: max(1, ceil(pairs / most))
    count = lambda own: own.join(other, "v").filter("u < w").groupBy("u", "w").agg(F.count("*").alias("n")).filter(F.col("n") >= least_shared).select("u", "w")
    known = _union([cut(count(own)) for own in _dealt(edges, rounds(((squares or 0) - (n or 0)) / 2))])
    both = known.union(known.select(F.col("w").alias("u"), F.col("u").alias("w")))
    few = known.limit(bound + 1).count() <= bound
    meet = lambda own: own.join(other, "v").join(F.broadcast(both) if few else both, ["u", "w"]).select(F.col("u").alias("root"), "w", "v")
    return meet(edges) if few else _union([cut(meet(own)) for own in _dealt(edges, rounds(squares or 0))])


def neighbourhoods(edges: DataFrame, least_shared: int = 1, roots: DataFrame | None = None) -> DataFrame:
    """``[root, pairs]``: for each left vertex (of ``roots`` [u]), every edge (w, v) between a 2-hop vertex (or itself) and one of its neighbours."""
    other = edges.select(F.col("u").alias("w"), "v")
    if least_shared > 1 and roots is None:
        rows = edges.select(F.col("u").alias("root"), F.col("u").alias("w"), "v").union(_near(edges, least_shared))
        return rows.groupBy("root").agg(F.collect_list(F.struct("w", "v")).alias("pairs"))
    rows = (edges if roots is None else edges.join(roots, "u", "left_semi")).join(other, "v").select(F.col("u").alias("root"), "w", "v")
    if least_shared > 1:
        enough = rows.groupBy("root", "w").agg(F.count("*").alias("n")).filter((F.col("n") >= least_shared) | (F.col("root") == F.col("w"))).drop("n")
        rows = rows.join(enough, ["root", "w"])
    return rows.groupBy("root").agg(F.collect_list(F.struct("w", "v")).alias("pairs"))


def _solver(alpha: int, beta: int, pivot: bool, cut_small: bool, budget: int | None = None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = pa.schema([("kind", pa.string()), ("root", pa.int64()), ("part", pa.int32()), ("seed", pa.int64()), ("x", pa.list_(pa.int64())), ("y", pa.list_(pa.int64())), ("nodes", pa.int64())])
        rows: list[tuple] = []

        def batch() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(c, k.type) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], schema=kinds)
            rows.clear()
            return out

        for group in batches:
            for row in group.to_pylist():
                ego = Ego.of(row["root"], [(p["w"], p["v"]) for p in row["pairs"]])
                counts: dict[str, int] = {}
                for found in enumerate_root(ego, alpha, beta, pivot, cut_small, row["part"], row["parts"], counts, budget=budget):
                    rows.append((found.kind, row["root"], row["part"], found.seed if found.seed >= 0 else None, found.x, found.y, 0))
                    if len(rows) >= 4096:
                        yield batch()
                rows.append(("nodes", row["root"], row["part"], None, [], [], counts.get("nodes", 0)))
            if rows:
                yield batch()

    return run


def _local(edges: DataFrame, alpha: int, beta: int, pivot: bool, cut_small: bool, budget: int | None = None, only: DataFrame | None = None) -> DataFrame:
    roots = neighbourhoods(edges, beta if cut_small else 1, only)
    if (root_sizes(edges).agg(F.max("pairs")).first()[0] or 0) <= HEAVY:
        return roots.select("root", "pairs", F.lit(0).alias("part"), F.lit(1).alias("parts")).mapInArrow(_solver(alpha, beta, pivot, cut_small, budget), LEAVES)
    roots = roots.withColumn("parts", F.ceil(F.size("pairs") / HEAVY).cast("int")).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    return roots.repartition("root", "part").select("root", "pairs", "part", "parts").mapInArrow(_solver(alpha, beta, pivot, cut_small, budget), LEAVES)


def closure(edges: DataFrame, most_rounds: int = 200) -> DataFrame:
    """``[x, y]`` of all maximal bicliques: right sets are the intersections of neighbour lists, left sets the vertices adjacent to all of one."""
    lists = adjacency(edges)
    known = cut(lists.select(F.col("nbrs").alias("y")).distinct())
    new = known
    for _ in range(most_rounds):
        touched = new.select("y", F.explode("y").alias("v")).join(edges, "v").select("y", "u").distinct()
        meets = touched.join(lists, F.col("u") == F.col("vertex")).select(F.array_sort(F.array_intersect("y", "nbrs")).alias("y")).distinct()
        new = cut(meets.join(known, "y", "left_anti"))
        if new.isEmpty():
            break
        known = cut(known.union(new))
    else:
        raise RuntimeError(f"the closure did not settle in {most_rounds} rounds")
    full = known.select("y", F.explode("y").alias("v")).join(edges, "v").groupBy("y", "u").agg(F.count("*").alias("n")).filter(F.col("n") == F.size("y"))
    return full.groupBy("y").agg(F.array_sort(F.collect_list("u")).alias("x")).select("x", "y")


def root_sizes(edges: DataFrame) -> DataFrame:
    """``[u, pairs]``: the size of each left vertex's neighbourhood, from degrees alone."""
    degrees = edges.groupBy("v").agg(F.count("*").alias("d"))
    return edges.join(degrees, "v").groupBy("u").agg(F.sum("d").alias("pairs"))


_NONE = "array<long>"


def _measured(open_: DataFrame, both: DataFrame) -> DataFrame:
    """Open nodes with ``p`` (the pivot: fewest non-neighbours, excluded before candidates, left before right, least vertex),
    ``full_u``, ``full_v`` (candidates adjacent to all opposite ones), ``dead`` (an excluded one is) and ``out`` (excluded ones with their non-neighbours)."""
    groups = [F.struct(F.lit(s).alias("side"), F.lit(e).alias("excluded"), F.col(c).alias("vs")) for s, e, c in (("u", 0, "c_u"), ("u", 1, "x_u"), ("v", 0, "c_v"), ("v", 1, "x_v"))]
    mine = F.filter(F.array(*groups), lambda g: F.size(g["vs"]) > 0)
    vertices = open_.select("node", "c_u", "c_v", F.explode(mine).alias("g")).select("node", "c_u", "c_v", "g.side", "g.excluded", F.explode("g.vs").alias("vertex"))
    missing = F.array_except(F.when(F.col("side") == "u", F.col("c_v")).otherwise(F.col("c_u")), "nbrs")
    rows = vertices.join(both, ["side", "vertex"]).withColumn("missing", F.array_sort(missing)).withColumn("n", F.size("missing"))
    full = lambda side: F.array_sort(F.collect_list(F.when((F.col("n") == 0) & (F.col("excluded") == 0) & (F.col("side") == side), F.col("vertex"))))
    found = rows.groupBy("node").agg(
        F.min(F.struct("n", (1 - F.col("excluded")).alias("kept"), "side", "vertex", "missing")).alias("p"), full("u").alias("full_u"), full("v").alias("full_v"),
        F.max((F.col("n") == 0) & (F.col("excluded") == 1)).alias("dead"), F.collect_list(F.when(F.col("excluded") == 1, F.struct("side", "vertex", "missing"))).alias("out"),
    )
    return open_.join(found, "node")


def _forced(level: DataFrame, alpha: int, beta: int) -> DataFrame:
    """The one child that takes all forced candidates at once, with the seed (``s_u``, ``s_v``) where the chain of them first reaches both sizes."""
    left = lambda side, other: F.transform(
        F.filter("out", lambda o: (o["side"] == side) & (F.size(F.array_intersect(o["missing"], F.col(f"full_{other}"))) == 0)), lambda o: o["vertex"])
    more_u, more_v = F.concat("r_u", "full_u"), F.concat("r_v", "full_v")
    crosses = F.col("seed_id").isNull() & (F.size(more_u) >= alpha) & (F.size(more_v) >= beta)
    on_left = F.size("r_v") >= beta
    s_u = F.when(on_left, F.concat("r_u", F.slice("full_u", F.lit(1), F.greatest(alpha - F.size("r_u"), F.lit(0))))).otherwise(more_u)
    s_v = F.when(on_left, F.col("r_v")).otherwise(F.concat("r_v", F.slice("full_v", F.lit(1), F.greatest(beta - F.size("r_v"), F.lit(0)))))
    return level.select(
        more_u.alias("r_u"), more_v.alias("r_v"), F.array_except("c_u", "full_u").alias("c_u"), F.array_except("c_v", "full_v").alias("c_v"), left("u", "v").alias("x_u"), left("v", "u").alias("x_v"),
        "seed_id", crosses.alias("new"), s_u.alias("s_u"), s_v.alias("s_v"), (F.size("full_u") + F.size("full_v") - 1).alias("passed"),
    )


def _branched(level: DataFrame, both: DataFrame) -> DataFrame:
    """The children by the pivot and its non-neighbours, each knowing which siblings come before it."""
    none = F.array().cast(_NONE)
    own = F.when(F.col("p.kept") == 1, F.array(F.struct(F.col("p.side").alias("side"), F.col("p.vertex").alias("vertex")))).otherwise(F.array().cast("array<struct<side:string,vertex:bigint>>"))
    others = F.transform("p.missing", lambda w: F.struct(F.when(F.col("p.side") == "u", "v").otherwise("u").alias("side"), w.alias("vertex")))
    kids = level.withColumn("branches", F.concat(own, others)).select("*", F.posexplode("branches").alias("at", "b"))
    sibling = lambda side: F.transform(F.filter(F.slice("branches", 1, F.col("at")), lambda s: s["side"] == side), lambda s: s["vertex"])
    chosen = lambda side: F.when(F.col("b.side") == side, F.array("b.vertex")).otherwise(none)
    kids = kids.select(
        "seed_id", F.col("b.side").alias("side"), F.col("b.vertex").alias("vertex"), F.concat("r_u", chosen("u")).alias("r_u"), F.concat("r_v", chosen("v")).alias("r_v"),
        F.array_except("c_u", F.concat(sibling("u"), chosen("u"))).alias("c_u"), F.array_except("c_v", F.concat(sibling("v"), chosen("v"))).alias("c_v"),
        F.concat("x_u", sibling("u")).alias("x_u"), F.concat("x_v", sibling("v")).alias("x_v"),
    ).join(both, ["side", "vertex"])
    grown = lambda c, side: F.when(F.col("side") == side, F.col(c)).otherwise(F.array_intersect(c, "nbrs")).alias(c)
    return kids.select("r_u", "r_v", grown("c_u", "u"), grown("c_v", "v"), grown("x_u", "u"), grown("x_v", "v"), "seed_id")


def _frontier(edges: DataFrame, alpha: int, beta: int, most_levels: int = 400, only: DataFrame | None = None) -> tuple[DataFrame, DataFrame, int]:
    """Level by level: all nodes' pivots by joins of their vertices with the adjacency, then all children at once.

    Chains of forced choices are one level, so that the number of levels follows the branchings, not the largest biclique.
    Returns leaves ``[seed_id, x, y]``, seeds ``[seed_id, r_u, r_v]`` and the number of nodes.
    """
    left, right = cut(adjacency(edges, "u")), cut(adjacency(edges, "v"))
    both = left.withColumn("side", F.lit("u")).union(right.withColumn("side", F.lit("v")))
    hops = neighbourhoods(edges, 1, only).select(F.col("root").alias("vertex"), F.array_sort(F.array_distinct(F.transform("pairs", lambda p: p["w"]))).alias("hop"))
    none = F.array().cast(_NONE)
    level = left.join(hops, "vertex").select(
        F.array("vertex").alias("r_u"), none.alias("r_v"), F.filter("hop", lambda w: w > F.col("vertex")).alias("c_u"), F.col("nbrs").alias("c_v"),
        F.filter("hop", lambda w: w < F.col("vertex")).alias("x_u"), none.alias("x_v"), F.lit(None).cast("string").alias("seed_id"),
    )
    leaves, seeds, nodes = [], [], 0
    key = lambda u, v: F.sha2(F.concat_ws("|", F.array_join(F.array_sort(u), ","), F.array_join(F.array_sort(v), ",")), 256)
    for _ in range(most_levels):
        reached = (F.size("r_u") >= alpha) & (F.size("r_v") >= beta)
        level = level.withColumn("new", reached & F.col("seed_id").isNull()).withColumn("seed_id", F.when(F.col("new"), key("r_u", "r_v")).otherwise(F.col("seed_id")))
        level = cut(level.withColumn("node", F.monotonically_increasing_id()))
        n = level.count()
        if not n:
            break
        nodes += n
        seeds.append(level.filter("new").select("seed_id", "r_u", "r_v"))
        done = (F.size("c_u") == 0) & (F.size("c_v") == 0)
        leaves.append(level.filter(done & (F.size("x_u") == 0) & (F.size("x_v") == 0) & (F.size("r_v") > 0)).select("seed_id", F.array_sort("r_u").alias("x"), F.array_sort("r_v").alias("y")))
        known = cut(_measured(level.filter(~done), both).filter("not dead"))
        chained = (F.size("full_u") > 0) | (F.size("full_v") > 0)
        forced = cut(_forced(known.filter(chained), alpha, beta))
        nodes += forced.agg(F.coalesce(F.sum("passed"), F.lit(0))).first()[0]
        seeds.append(forced.filter("new").select(key("s_u", "s_v").alias("seed_id"), F.col("s_u").alias("r_u"), F.col("s_v").alias("r_v")))
        taken = forced.withColumn("seed_id", F.when(F.col("new"), key("s_u", "s_v")).otherwise(F.col("seed_id"))).drop("new", "s_u", "s_v", "passed")
        level = _branched(known.filter(~chained), both).unionByName(taken)
    else:
        raise RuntimeError(f"the tree has more than {most_levels} levels of branches")
    join = lambda frames, names: frames[0].select(*names) if len(frames) == 1 else frames[0].select(*names).union(join(frames[1:], names))
    return join(leaves, ["seed_id", "x", "y"]), join(seeds, ["seed_id", "r_u", "r_v"]), nodes


def enumerate_bicliques(edges: DataFrame, alpha: int = 1, beta: int = 1, engine: str = "local", pivot: str = "min_nonneighbours", side: str = "cheaper", qualified_only: bool = False, budget: int | None = None, heavy: int = HEAVY, cored: bool = False) -> Enumeration:
    """Enumerate over encoded edges (long u, v).

    ``alpha``, ``beta`` place the seeds. ``qualified_only`` gives only bicliques with |x| >= alpha and |y| >= beta, after
    the core that holds them all (``cored``: the edges are such a core). ``side``: whose vertices are roots. ``engine="auto"`` solves roots locally whose
    neighbourhood has at most ``heavy`` pairs, and grows the others level by level. ``budget``: tree nodes of a root above
    which the local engine raises an error (the plain tree, without a pivot, has 2^n).
    """
    check_thresholds(alpha, beta)
    if pivot not in ("min_nonneighbours", "none"):
        raise ValueError(f"unknown pivot {pivot!r}")
    with scratch() as keep:
        found = _enumerated(edges, alpha, beta, engine, pivot, side, qualified_only, budget, heavy, cored)
        keep(found.bicliques), keep(found.seeds)
    return found


def _enumerated(edges: DataFrame, alpha: int, beta: int, engine: str, pivot: str, side: str, qualified_only: bool, budget: int | None, heavy: int, cored: bool) -> Enumeration:
    if qualified_only and not cored:
        edges = cohesive.core(edges, beta, alpha)
    edges = cut(edges.select(F.col("u").cast("long"), F.col("v").cast("long")))
    flip = (cheaper_side(edges) if side == "cheaper" else side) == "v"
    own = swapped(edges) if flip else edges
    a, b = (beta, alpha) if flip else (alpha, beta)
    nodes: int | None = None
    if engine == "closure":
        found = closure(own).withColumn("seed_id", F.lit(None).cast("string"))
        seeds = found.select("seed_id", F.col("x").alias("r_u"), F.col("y").alias("r_v")).filter("false")
    elif engine == "frontier":
        found, seeds, nodes = _frontier(own, a, b)
    elif engine in ("local", "auto"):
        sizes = cut(root_sizes(own)) if engine == "auto" else None
        light = None if sizes is None else sizes.filter(F.col("pairs") <= heavy).select("u")
        rows = packed(_local(own, a, b, pivot != "none", qualified_only, budget, light).withColumn("seed_id", F.when(F.col("seed").isNotNull(), F.concat_ws(":", "root", "seed"))))
        found, seeds = rows.filter("kind = 'biclique'").select("seed_id", "x", "y"), rows.filter("kind = 'seed'").select("seed_id", F.col("x").alias("r_u"), F.col("y").alias("r_v"))
        nodes = rows.agg(F.coalesce(F.sum("nodes"), F.lit(0))).first()[0]
        if sizes is not None and not sizes.filter(F.col("pairs") > heavy).isEmpty():
            more, more_seeds, n = _frontier(own, a, b, only=sizes.filter(F.col("pairs") > heavy).select("u"))
            found, seeds, nodes = found.union(more), seeds.union(more_seeds), nodes + n
    else:
        raise ValueError(f"unknown engine {engine!r}")
    if flip:
        found = found.select("seed_id", F.col("y").alias("x"), F.col("x").alias("y"))
        seeds = seeds.select("seed_id", F.col("r_v").alias("r_u"), F.col("r_u").alias("r_v"))
    if qualified_only:
        found = found.filter((F.size("x") >= alpha) & (F.size("y") >= beta))
    bicliques = packed(found.select(F.monotonically_increasing_id().alias("biclique_id"), "x", "y", F.size("x").alias("n_x"), F.size("y").alias("n_y"), "seed_id"))
    live = bicliques.select("seed_id").filter("seed_id is not null").distinct().withColumn("live", F.lit(True))
    seeds = seeds.join(live, "seed_id", "left").select("seed_id", F.array_sort("r_u").alias("r_u"), F.array_sort("r_v").alias("r_v"), F.coalesce("live", F.lit(False)).alias("live"))
    return Enumeration(bicliques, cut(seeds), nodes)

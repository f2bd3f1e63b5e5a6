"""Communities from small bicliques: list the bicliques of exactly alpha by beta vertices, and merge the maximal ones around each.

Counting and listing grow prefixes as rows: the left vertices chosen in ascending order, the 2-hop successors that may
follow, and the common right neighbours; sizes that can't be reached any more end a prefix. Merging lists them within groups
of maximal bicliques instead, one per root vertex, where the search sees which bicliques, and how many labels, are still around its
prefix (see ``local_listing``). Labels that another group merges are seen after a batch of roots, hence are finer than
the truth at worst, which costs work but no results.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bipercolate import cohesive
from bipercolate.checkpoints import cut, scratch
from bipercolate.components import FEW_LINKS, merge
from bipercolate.graph import Encoded, Thinned, adjacency, check_thresholds, swapped, thinned, two_hop
from bipercolate.local_listing import Group, merge_group
from bipercolate.operators.joins import BROADCAST_IDS
from bipercolate.overlap import qualify
from bipercolate.shipping import consecutive

MERGED = "a long, b long, prefixes long, rights long, leaves long"
#: Vertices in the bicliques of a group above which several tasks share it.
HEAVY = 500_000
#: Names that a task makes of one common neighbour set before it is shared out.
NAMES_AT_ONCE = 1_000_000


def _adjacent(edges: DataFrame, beta: int) -> DataFrame:
    """``[u, nbrs, later]``: neighbours, and larger vertices that share at least beta of them."""
    hops = two_hop(edges, beta).groupBy("u").agg(F.array_sort(F.collect_set("w")).alias("later"))
    return adjacency(edges).withColumnRenamed("vertex", "u").join(hops, "u", "left").select("u", "nbrs", F.coalesce("later", F.array().cast("array<bigint>")).alias("later"))


def _start(adjacent: DataFrame, alpha: int, beta: int) -> DataFrame:
    return adjacent.filter((F.size("nbrs") >= beta) & (F.size("later") >= alpha - 1)).select(F.array("u").alias("r_u"), F.col("later").alias("ext"), F.col("nbrs").alias("c_v"))


def _longer(rows: DataFrame, adjacent: DataFrame, alpha: int, beta: int, done: int) -> DataFrame:
    """Prefixes of done + 1 left vertices; other columns of ``rows`` stay."""
    rest = [c for c in rows.columns if c not in ("r_u", "ext", "c_v")]
    grown = rows.select("*", F.explode("ext").alias("u")).join(adjacent, "u")
    return (
        grown.select(F.concat("r_u", F.array("u")).alias("r_u"), F.array_intersect("ext", "later").alias("ext"), F.array_intersect("c_v", "nbrs").alias("c_v"), "u", *rest)
        .filter((F.size("c_v") >= beta) & (F.size("ext") >= alpha - done - 1))
    )


def left_prefixes(edges: DataFrame, alpha: int, beta: int) -> DataFrame:
    """``[r_u, c_v]``: all sets of alpha left vertices with at least beta common neighbours."""
    adjacent = cut(_adjacent(edges, beta))
    rows = _start(adjacent, alpha, beta)
    for k in range(1, alpha):
        rows = _longer(rows, adjacent, alpha, beta, k).drop("u")
    return rows.select("r_u", F.array_sort("c_v").alias("c_v"))


def _choose(n, k: int):
    """n over k as a product that stays whole at each step."""
    value = F.lit(1).cast("bigint")
    for i in range(1, k + 1):
        value = F.call_function("div", value * (n - k + i), F.lit(i).cast("bigint"))
    return value


def count(edges: DataFrame, alpha: int, beta: int) -> DataFrame:
    """One row: how many (alpha, beta)-bicliques there are, without listing right sides."""
    check_thresholds(alpha, beta)
    n = F.size("c_v").cast("bigint")
    return left_prefixes(edges, alpha, beta).agg(F.coalesce(F.sum(_choose(n, beta)), F.lit(0)).cast("bigint").alias("ab_bicliques"))


def _right_step(rows: DataFrame, beta: int, done: int) -> DataFrame:
    """Add one right vertex, larger than those before, to r_v; ``rest`` holds what may follow."""
    keep = [c for c in rows.columns if c not in ("r_v", "rest")]
    return rows.select(*keep, "r_v", "rest", F.posexplode("rest").alias("at", "v")).select(*keep, F.concat("r_v", F.array("v")).alias("r_v"), F.expr("slice(rest, at + 2, greatest(size(rest) - at - 1, 0))").alias("rest"), "v").filter(F.size("rest") >= beta - done - 1)


def enumerate_ab(edges: DataFrame, alpha: int, beta: int, side: str = "u") -> DataFrame:
    """``[x, y]``: all bicliques of exactly alpha left and beta right vertices; ``side``: which side is grown first."""
    check_thresholds(alpha, beta)
    if side == "v":
        return enumerate_ab(swapped(edges), beta, alpha).select(F.col("y").alias("x"), F.col("x").alias("y"))
    rows = left_prefixes(edges, alpha, beta).select("r_u", F.array().cast("array<bigint>").alias("r_v"), F.col("c_v").alias("rest"))
    for k in range(beta):
        rows = _right_step(rows, beta, k).drop("v")
    return rows.select(F.col("r_u").alias("x"), F.col("r_v").alias("y"))


def class_prefixes(thin: Thinned, alpha: int, beta: int) -> DataFrame:
    """``[r_u, c_v, ways]``: alpha left classes, a class at most as often as it has vertices, and their common right classes.

    Classes come in ascending order of degree, so that the shorter neighbour lists travel. ``ways``: at least as many sets of vertices
    as the prefix stands for. For alpha = 2 all prefixes have beta common neighbours; for more, some may have fewer.
    """
    sizes = [m.groupBy("id").agg(F.count("*").alias("n")) for m in (thin.u, thin.v)]
    degrees = thin.edges.groupBy("u").agg(F.count("*").alias("d"))
    rows = cut(thin.edges.join(sizes[1].select(F.col("id").alias("v"), F.col("n").alias("m")), "v").join(degrees, "u"))
    own = rows.groupBy("u").agg(F.sum("m").alias("shared"), F.array_sort(F.collect_list("v")).alias("nbrs")).filter(F.col("shared") >= beta)
    own = cut(own.join(sizes[0].withColumnRenamed("id", "u"), "u").select("u", "n", "nbrs"))
    other = rows.select(F.col("u").alias("w"), "v", F.col("d").alias("dw"))
    hops = rows.join(other, "v").filter("d < dw or d = dw and u < w").groupBy("u", "w").agg(F.sum("m").alias("shared")).filter(F.col("shared") >= beta)
    hops = cut(hops.select("u", "w").union(own.filter("n > 1").select("u", "u")))
    found = own.select(F.array("u").alias("r_u"), F.col("nbrs").alias("c_v"), F.col("n").cast("double").alias("ways"))
    for _ in range(1, alpha):
        grown = found.withColumn("u", F.element_at("r_u", -1)).join(hops, "u").drop("u").join(own.withColumnRenamed("u", "w"), "w")
        grown = grown.select("w", "n", F.concat("r_u", F.array("w")).alias("r_u"), F.array_intersect("c_v", "nbrs").alias("c_v"), (F.col("ways") * F.col("n")).alias("ways"))
        found = grown.filter((F.size("c_v") > 0) & (F.size(F.filter("r_u", lambda x: x == F.col("w"))) <= F.col("n"))).select("r_u", "c_v", "ways")
    return found


def names_ab(graph: Encoded, alpha: int, beta: int, side: str = "u", at_once: int = NAMES_AT_ONCE, bound: int = BROADCAST_IDS) -> DataFrame:
    """``[biclique]``: all bicliques of exactly alpha left and beta right vertices as "x|y", sorted labels of each side; ``side`` is grown first.

    Prefixes and their common neighbours are found over classes of twins. Labels are fetched once for each set of common neighbours, and
    bicliques are written out in the task that has them, so that none is shuffled. Sets of more than ``at_once`` bicliques are shared out
    by their first right vertex and by the first left one.
    """
    check_thresholds(alpha, beta)
    u, v, edges = graph.u, graph.v, graph.edges
    if side == "v":
        alpha, beta, u, v, edges = beta, alpha, v, u, swapped(edges)
    label = F.col("label").cast("string").alias("label")
    key = ["f1", "f2"]
    with scratch() as keep:
        thin = thinned(cohesive.core(edges, beta, alpha))
        left, right = (keep(cut(m.join(w.withColumnRenamed("id", "vertex"), "vertex").select("id", label))) for m, w in ((thin.u, u), (thin.v, v)))
        marked = keep(cut(class_prefixes(thin, alpha, beta).withColumns({f: F.xxhash64(F.lit(n), "c_v") for n, f in enumerate(key)})))
    sets = marked.dropDuplicates(key).select(*key, F.explode("c_v").alias("id")).join(right, "id")
    sets = cut(sets.groupBy(*key).agg(F.array_sort(F.collect_list("label")).alias("rest")).filter(F.size("rest") >= beta))

    ways = marked.groupBy(*key).agg(F.sum("ways").alias("ways")).join(sets.select(*key, F.size("rest").cast("long").alias("n")), key)
    chosen = F.lit(1.0)
    for i in range(beta):
        chosen = chosen * (F.col("n") - i) / (i + 1)
    by_right = F.least(F.ceil(chosen / at_once), F.col("n"))
    shares = cut(ways.select(*key, by_right.cast("int").alias("by_right"), F.least(F.ceil(F.col("ways") * chosen / by_right / at_once), F.lit(100_000)).cast("int").alias("by_left")))
    each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    few = left.limit(bound + 1).count() <= bound
    members = left.select("id", F.col("label").alias("one"))
    members = F.broadcast(members) if few else members
    rows = marked.select("r_u", *key).join(shares, key).withColumn("id", F.col("r_u")[0]).join(members, "id")
    rows = rows.select(*key, "r_u", F.array("one").alias("x"), "by_right", F.pmod(F.hash("one"), "by_left").alias("l")).withColumn("r", each("by_right"))
    texts = sets.join(shares, key).withColumn("l", each("by_left")).withColumn("r", each("by_right")).select(*key, "l", "r", "rest")
    rows = rows.join(texts, [*key, "l", "r"])
    for i in range(1, alpha):
        rows = rows.withColumn("id", F.col("r_u")[i]).join(members, "id")
        rows = rows.filter((F.col("r_u")[i] != F.col("r_u")[i - 1]) | (F.col("one") > F.element_at("x", -1))).withColumn("x", F.concat("x", F.array("one"))).drop("id", "one")
    rows = rows.select(F.array_join(F.array_sort("x"), ",").alias("x"), "by_right", "r", "rest", F.posexplode("rest").alias("at", "v"))
    rows = rows.filter((F.col("at") % F.col("by_right") == F.col("r")) & (F.col("at") <= F.size("rest") - beta))
    rows = rows.select("x", F.array("v").alias("r_v"), F.expr("slice(rest, at + 2, size(rest) - at - 1)").alias("rest"))
    for k in range(1, beta):
        rows = _right_step(rows, beta, k).drop("v")
    y = F.array_join("r_v", ",")
    return rows.select(F.concat_ws("|", "x", y) if side == "u" else F.concat_ws("|", y, "x")).toDF("biclique")


def shared_vertices(bicliques: DataFrame, labels: DataFrame, side: str) -> DataFrame:
    """``[vertex]``: vertices of one side that bicliques of two labels contain; nothing else can merge anything."""
    return bicliques.select("biclique_id", F.explode(side).alias("vertex")).join(labels, "biclique_id").groupBy("vertex").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).filter("lo <> hi").select("vertex")


def cheaper_roots(bicliques: DataFrame) -> str:
    """The side whose vertices, as roots, are sent fewer sets: each root gets every biclique that holds it."""
    n, m = F.size("x").cast("double"), F.size("y").cast("double")
    by_u, by_v = bicliques.agg(F.sum(n * (n + m)), F.sum(m * (n + m))).first()
    return "v" if (by_v or 0) < (by_u or 0) else "u"


def merge_by_listing(
    bicliques: DataFrame, alpha: int, beta: int, labels: DataFrame, prune: bool = True, prune_right: bool = True, restrict: bool = True,
    batches: int = 1, tally: Callable[[str, int], None] | None = None, side: str = "cheaper", heavy: int = HEAVY,
) -> DataFrame:
    """Coarsen ``labels`` [biclique_id, label] of the qualified bicliques until all that share an (alpha, beta)-biclique agree.

    Every small biclique is listed below its least vertex on ``side``, in the group of maximal bicliques that hold this
    vertex. Groups of more than ``heavy`` vertices are shared out by their next vertices, first on this side and then by one of
    the other. With ``prune``, groups of one label are not even sent. Within a group a merge counts at once; other groups see
    it after the batch of roots. ``tally(kind, n)`` is told how many prefixes, right prefixes and leaves were visited.
    """
    check_thresholds(alpha, beta)
    good = cut(qualify(bicliques, alpha, beta).select("biclique_id", "x", "y"))
    if (cheaper_roots(good) if side == "cheaper" else side) == "v":
        good = good.select("biclique_id", F.col("y").alias("x"), F.col("x").alias("y"))
        alpha, beta = beta, alpha
    labels = cut(labels.select("biclique_id", "label"))
    for batch in range(batches):
        known = good.join(labels, "biclique_id")
        roots = good.select(F.explode("x").alias("u"), "biclique_id").select(F.array("u").alias("r_u"), F.array().cast("array<bigint>").alias("r_v"), "biclique_id")
        if batches > 1:
            roots = roots.filter(F.pmod(F.xxhash64(F.col("r_u")[0]), F.lit(batches)) == batch)
        found = cut(_merged(_groups(roots, known, alpha, prune, heavy), known, alpha, beta, prune, prune_right, restrict))
        if tally:
            for kind, n in found.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(k) for k, c in (("prefix", "prefixes"), ("right", "rights"), ("leaf", "leaves"))]).first().asDict().items():
                tally(kind, n)
        links = found.filter("a is not null").select("a", "b")
        labels = cut(merge(labels, links, "biclique_id", "label", FEW_LINKS).select(F.col("item").alias("biclique_id"), "label"))
    return labels


def _groups(level: DataFrame, known: DataFrame, alpha: int, prune: bool, heavy: int) -> DataFrame:
    """``[r_u, r_v, biclique_id]``: the bicliques around each prefix, in groups of at most ``heavy`` vertices where prefixes can grow."""
    ready = None
    for k in range(1, alpha + 2):
        level = cut(level)
        size = (F.size("x") + F.size("y")).alias("size")
        groups = level.join(known.select("biclique_id", "label", size), "biclique_id").groupBy("r_u", "r_v")
        groups = groups.agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.sum("size").alias("size"))
        groups = cut(groups.filter("lo <> hi").select("r_u", "r_v", "size") if prune else groups.select("r_u", "r_v", "size"))
        grows = (F.col("size") > heavy) if k <= alpha else F.lit(False)
        done = level.join(groups.filter(~grows), ["r_u", "r_v"], "left_semi")
        ready = done if ready is None else ready.union(done)
        rest = groups.filter(grows)
        if rest.isEmpty():
            break
        level = level.join(rest, ["r_u", "r_v"], "left_semi").join(known.select("biclique_id", "x", "y"), "biclique_id")
        if k < alpha:
            next_u = F.explode(F.filter("x", lambda w: w > F.element_at("r_u", -1)))
            level = level.select("r_u", "r_v", "biclique_id", next_u.alias("w")).select(F.concat("r_u", F.array("w")).alias("r_u"), "r_v", "biclique_id")
        else:
            level = level.select("r_u", F.explode("y").alias("v"), "biclique_id").select("r_u", F.array("v").alias("r_v"), "biclique_id")
    return ready


def _merged(groups: DataFrame, known: DataFrame, alpha: int, beta: int, prune: bool, prune_right: bool, restrict: bool) -> DataFrame:
    """``[a, b, prefixes, rights, leaves]``: links between labels, and a row of counts per group."""
    after = lambda side, r: F.filter(side, lambda w: F.when(F.size(r) == 0, F.lit(True)).otherwise(w > F.try_element_at(r, F.lit(-1))))
    rows = groups.join(known, "biclique_id").select(
        F.concat_ws("|", F.array_join("r_u", ","), F.array_join("r_v", ",")).alias("key"), F.size("r_u").alias("n_u"), F.size("r_v").alias("n_v"),
        "label", after("x", "r_u").alias("x"), after("y", "r_v").alias("y"),
    )
    return rows.repartition("key").sortWithinPartitions("key").mapInArrow(_group_solver(alpha, beta, prune, prune_right, restrict), MERGED)


def _group_solver(alpha: int, beta: int, prune: bool, prune_right: bool, restrict: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = pa.schema([(x.split()[0], pa.int64()) for x in MERGED.split(", ")])
        for rows in consecutive(batches, "key"):
            group = Group.of([(r["label"], r["x"], r["y"]) for r in rows])
            links = merge_group(group, alpha - rows[0]["n_u"], beta - rows[0]["n_v"], prune, prune_right, restrict)
            counted = group.tally
            out = [*((a, b, 0, 0, 0) for a, b in links), (None, None, counted.prefixes, counted.rights, counted.leaves)]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], schema=kinds)

    return run


def keys_from_bicliques(bicliques: DataFrame, alpha: int, beta: int, budget: int = 50_000_000) -> DataFrame:
    """Links (a, b) between bicliques that have an (alpha, beta)-subset in common, each biclique listing its own subsets.

    Their number is known before any is made; above ``budget`` this raises instead.
    """
    good = qualify(bicliques, alpha, beta)
    total = good.agg(F.coalesce(F.sum(_choose(F.col("n_x").cast("bigint"), alpha).cast("double") * _choose(F.col("n_y").cast("bigint"), beta).cast("double")), F.lit(0.0))).first()[0]
    if total > budget:
        raise BudgetExceeded(f"{total:.3g} subsets are more than the budget of {budget}")
    rows = good.select("biclique_id", F.array().cast("array<bigint>").alias("r_v"), F.col("x").alias("rest"), "y")
    for k in range(alpha):
        rows = _right_step(rows, alpha, k).drop("v")
    rows = rows.select("biclique_id", F.col("r_v").alias("r_u"), F.array().cast("array<bigint>").alias("r_v"), F.col("y").alias("rest"))
    for k in range(beta):
        rows = _right_step(rows, beta, k).drop("v")
    least = rows.groupBy("r_u", "r_v").agg(F.min("biclique_id").alias("a"))
    return rows.join(least, ["r_u", "r_v"]).select("a", F.col("biclique_id").alias("b")).filter("a <> b").distinct()


class BudgetExceeded(RuntimeError):
    """More work than a stated budget allows."""

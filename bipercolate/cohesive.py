"""Other cohesive subgraphs to compare with: cores, bitrusses, the maximum biclique."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bipercolate.checkpoints import cut, release
from bipercolate.components import FEW_LINKS, connected
from bipercolate.graph import cheaper_side, swapped


def core(edges: DataFrame, a: int, b: int, most_rounds: int = 200) -> DataFrame:
    """The largest subgraph in which left vertices have degree >= a and right vertices degree >= b."""
    now = cut(edges.select("u", "v"))
    n = now.count()
    for _ in range(most_rounds):
        left = now.groupBy("u").agg(F.count("*").alias("d")).filter(F.col("d") >= a).select("u")
        kept = now.join(left, "u", "left_semi")
        right = kept.groupBy("v").agg(F.count("*").alias("d")).filter(F.col("d") >= b).select("v")
        now, before = cut(kept.join(right, "v", "left_semi").select("u", "v")), now
        release(before)
        m = now.count()
        if m == n:
            return now
        n = m
    raise RuntimeError(f"the core did not settle in {most_rounds} rounds")


def butterflies(edges: DataFrame, side: str = "cheaper") -> DataFrame:
    """``[u, v, butterflies]``: 2 x 2 bicliques that hold each edge, by the numbers of common neighbours of pairs on one ``side``."""
    if (cheaper_side(edges) if side == "cheaper" else side) == "v":
        return butterflies(swapped(edges), "u").select(F.col("v").alias("u"), F.col("u").alias("v"), "butterflies")
    other = edges.select(F.col("u").alias("w"), "v")
    wedges = edges.join(other, "v").filter("u <> w").select("u", "w", "v")
    common = wedges.groupBy("u", "w").agg(F.count("*").alias("c")).filter("c > 1")
    support = wedges.join(common, ["u", "w"]).groupBy("u", "v").agg(F.sum(F.col("c") - 1).alias("butterflies"))
    return edges.select("u", "v").join(support, ["u", "v"], "left").select("u", "v", F.coalesce("butterflies", F.lit(0)).cast("long").alias("butterflies"))


def butterfly_total(edges: DataFrame, side: str = "cheaper") -> DataFrame:
    """One row: c common neighbours of a pair on one ``side`` make c over 2 butterflies."""
    own = swapped(edges) if (cheaper_side(edges) if side == "cheaper" else side) == "v" else edges
    pairs = own.join(own.select(F.col("u").alias("w"), "v"), "v").filter("u < w").groupBy("u", "w").agg(F.count("*").alias("c"))
    return pairs.agg(F.coalesce(F.sum(F.expr("c * (c - 1) div 2")), F.lit(0)).cast("long").alias("butterflies"))


def bitruss(edges: DataFrame, k: int, most_rounds: int = 500) -> DataFrame:
    """The largest subgraph whose edges each lie in at least k of its butterflies."""
    now = cut(edges.select("u", "v"))
    n, side = now.count(), cheaper_side(now)
    for _ in range(most_rounds):
        now, before = cut(butterflies(now, side).filter(F.col("butterflies") >= k).select("u", "v")), now
        release(before)
        m = now.count()
        if m == n:
            return now
        n = m
    raise RuntimeError(f"the bitruss did not settle in {most_rounds} rounds")


def vertex_components(edges: DataFrame) -> DataFrame:
    """``[side, vertex, label]`` (vertices as strings) of the graph's connected components."""
    keyed = edges.select(F.concat(F.lit("u:"), F.col("u").cast("string")).alias("a"), F.concat(F.lit("v:"), F.col("v").cast("string")).alias("b"))
    found = connected(keyed, driver_limit=FEW_LINKS)
    return found.select(F.substring("item", 1, 1).alias("side"), F.expr("substring(item, 3)").alias("vertex"), "label")


def component_of(edges: DataFrame, side: str, vertex) -> DataFrame:
    """``[side, vertex]`` of the component around a vertex."""
    labels = cut(vertex_components(edges))
    mine = labels.filter((F.col("side") == side) & (F.col("vertex") == str(vertex))).select("label")
    return labels.join(mine, "label", "left_semi").select("side", "vertex")


def maximum_biclique(bicliques: DataFrame, by: str = "edges", side: str | None = None, vertex: int | None = None) -> DataFrame:
    """The biclique with most edges (or vertices), ties by least x, then y; optionally among those with a vertex."""
    if by not in ("edges", "vertices"):
        raise ValueError(f"unknown measure {by!r}")
    size = F.size("x") * F.size("y") if by == "edges" else F.size("x") + F.size("y")
    rows = bicliques if side is None else bicliques.filter(F.array_contains("x" if side == "u" else "y", vertex))
    return rows.withColumn("biclique_size", size.cast("long")).orderBy(F.desc("biclique_size"), "x", "y").limit(1)

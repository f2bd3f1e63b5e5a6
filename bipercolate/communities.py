"""Communities by six methods, and views of them.

A community is a connected set of maximal bicliques, of at least alpha left and beta right vertices each, linked where two
share that many on both sides. Communities may share vertices; a biclique linked to none is a community of its own.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field, replace
from math import ceil

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bipercolate import cohesive, listing, maxbiclique, overlap, partial, tree
from bipercolate.checkpoints import cut, packed, release, scratch
from bipercolate.components import FEW_LINKS, merge
from bipercolate.graph import Encoded, Thinned, check_thresholds, encode, simple_edges, thinned

#: Characters of community names that are sent to every executor.
LEAST_CHARS = 8_000_000

METHODS = ("overlap", "prefix_merge", "seed_merge", "listing", "listing_pruned", "listing_seeded")


@dataclass
class Communities:
    """``labels`` [biclique_id, label] over qualified bicliques ``found``, whose vertices may stand for twins (``thin``); ``groups`` are the partial groups used, if any."""

    encoded: Encoded
    found: DataFrame
    labels: DataFrame
    alpha: int
    beta: int
    method: str
    groups: DataFrame | None = None
    metrics: dict[str, int] = field(default_factory=dict)
    thin: Thinned | None = None

    @property
    def bicliques(self) -> DataFrame:
        """The qualified bicliques with all their vertices."""
        return self.thin.whole(self.found) if self.thin else self.found

    def names(self) -> DataFrame:
        """``[biclique_id, x, y, biclique]``: sorted labels of each side, and both as "x|y"."""
        sets = self.thin.labels(self.found, self.encoded) if self.thin else self.encoded.labels(self.found)
        return sets.withColumn("biclique", F.concat_ws("|", F.array_join("x", ","), F.array_join("y", ",")))

    def keyed(self) -> DataFrame:
        """``[community_id, biclique]`` as strings: a biclique is its sorted labels, "x|y"; a community its least biclique."""
        rows = self.labels.join(packed(self.names().select("biclique_id", "biclique")), "biclique_id")  # read twice below
        least = cut(rows.groupBy("label").agg(F.min("biclique").alias("community_id")))
        few = least.agg(F.coalesce(F.sum(F.length("community_id") + 16), F.lit(0))).first()[0] <= LEAST_CHARS
        return rows.join(F.broadcast(least) if few else least, "label").select("community_id", "biclique")

    def vertices(self, labels: DataFrame, side: str) -> DataFrame:
        """``[label, id]``: vertices of one side in the communities of ``labels`` [biclique_id, label], once."""
        rows = labels.join(self.found, "biclique_id")
        if self.thin:
            return self.thin.vertices(rows, side, "label")
        return rows.select("label", F.explode("x" if side == "u" else "y").alias("id")).distinct()

    def members(self) -> DataFrame:
        """``[label, side, vertex]``: vertices (as strings) of each community; a vertex may be in several."""
        sides = []
        for side, words in (("u", self.encoded.u), ("v", self.encoded.v)):
            one = self.vertices(self.labels, side).withColumnRenamed("label", "community").join(words, "id")
            sides.append(one.select("community", F.lit(side).alias("side"), F.col("label").cast("string").alias("vertex")))
        return sides[0].union(sides[1]).withColumnRenamed("community", "label")

    def containing(self, side: str, vertex) -> DataFrame:
        """``[label]`` of the communities that a vertex belongs to."""
        return self.members().filter((F.col("side") == side) & (F.col("vertex") == str(vertex))).select("label").distinct()

    def sizes(self) -> DataFrame:
        """``[label, bicliques]``."""
        return self.labels.groupBy("label").agg(F.count("*").alias("bicliques"))


def community_edges(found: Communities, least_bicliques: int = 1) -> DataFrame:
    """``[label, u, v]`` (ids): edges inside the bicliques of communities of at least so many."""
    big = found.sizes().filter(F.col("bicliques") >= least_bicliques).select("label")
    rows = found.labels.join(big, "label", "left_semi").join(found.bicliques, "biclique_id")
    return rows.select("label", F.explode("x").alias("u"), "y").select("label", "u", F.explode("y").alias("v")).distinct()


def by_overlap(bicliques: DataFrame, alpha: int, beta: int, groups: DataFrame | None = None, prefix: bool = True) -> DataFrame:
    """``[biclique_id, label]``: components of the overlap graph; ``groups`` are contracted first and pairs within them never tested.

    Pairs are tested where their postings meet, and not written. Postings are dealt to rounds, between which labels are merged.
    """
    good = overlap.qualify(bicliques, alpha, beta).select("biclique_id", "x", "y")
    labels = packed(partial.singletons(good) if groups is None else groups)
    side, elements = overlap.lighter_side(good, alpha, beta, prefix)
    posts = packed(overlap.side_postings(good, alpha, beta, prefix, side))
    rounds = max(1, ceil(elements / overlap.ELEMENTS_AT_ONCE))
    for k in range(rounds):
        links = overlap.links_between(posts.filter(F.pmod(F.xxhash64("vertex"), F.lit(rounds)) == k), good, labels, alpha, beta, side)
        with scratch() as keep:
            links = cut(links)
            labels = keep(packed(merge(labels, links, "biclique_id", "label", FEW_LINKS).select(F.col("item").alias("biclique_id"), "label")))
    release(posts)
    return labels


def detect(edges: DataFrame | Encoded, alpha: int, beta: int, method: str = "listing_seeded", u: str = "u", v: str = "v", engine: str = "local", pivot: str = "min_nonneighbours", order: str = "two_hop_degree", side: str = "cheaper", batches: int = 1, prune_right_prefix: bool = True, restrict_shared: bool = True, seed: str = "seed", listing_side: str = "cheaper", enumeration: maxbiclique.Enumeration | None = None) -> Communities:
    """Find the communities of ``edges`` at (alpha, beta).

    ``enumeration`` reuses bicliques and seeds of the same graph and thresholds; without one, the core that holds all qualified
    bicliques is taken, with at most alpha and beta twins of a class (see ``graph.thinned``). ``seed="prefix"`` starts
    ``listing_seeded`` from the basic groups (an ablation).
    """
    check_thresholds(alpha, beta)
    if method not in METHODS:
        raise ValueError(f"unknown method {method!r}; there are {', '.join(METHODS)}")
    graph = edges if isinstance(edges, Encoded) else encode(simple_edges(edges, u, v), order)
    with scratch() as keep:
        out = _detected(graph, alpha, beta, method, engine, pivot, side, batches, prune_right_prefix, restrict_shared, seed, listing_side, enumeration)
        for frame in (out.found, out.labels, out.groups, *((out.thin.u, out.thin.v) if out.thin else ())):
            keep(frame)
    return out


def _detected(graph: Encoded, alpha: int, beta: int, method: str, engine: str, pivot: str, side: str, batches: int, prune_right_prefix: bool, restrict_shared: bool, seed: str, listing_side: str, enumeration: maxbiclique.Enumeration | None) -> Communities:
    thin = None if enumeration else thinned(cohesive.core(graph.edges, beta, alpha), alpha, beta)
    found = enumeration or maxbiclique.enumerate_bicliques(thin.edges, alpha, beta, engine, pivot, side, qualified_only=True, cored=True)
    good = packed(overlap.qualify(found.bicliques, alpha, beta)) if enumeration else found.bicliques
    metrics: dict[str, int] = {"tree_nodes": found.nodes or 0}

    def tally(kind: str, n: int) -> None:
        metrics[kind] = metrics.get(kind, 0) + n

    groups = None
    if method == "prefix_merge" or method == "listing_seeded" and seed == "prefix":
        groups = cut(partial.by_prefix(good, alpha, beta))
    elif method in ("seed_merge", "listing_seeded"):
        groups = cut(partial.by_seed(good, found.seeds, alpha, beta))
    if method in ("overlap", "prefix_merge", "seed_merge"):
        labels = by_overlap(good, alpha, beta, groups)
    else:
        start = partial.singletons(good) if groups is None else groups
        labels = listing.merge_by_listing(good, alpha, beta, start, method != "listing", prune_right_prefix, restrict_shared, batches, tally, listing_side)
    return Communities(graph, good, cut(labels), alpha, beta, method, groups, metrics, replace(thin, edges=None) if thin else None)


def sweep(edges: DataFrame | Encoded, alphas: Iterable[int], betas: Iterable[int], methods: Iterable[str] = METHODS) -> dict[tuple[int, int, str], Communities]:
    """All combinations over one encoding and one enumeration: the tree's table holds the seeds of any thresholds."""
    graph = edges if isinstance(edges, Encoded) else encode(simple_edges(edges))
    sizes = [(a, b) for a in alphas for b in betas]
    core = cohesive.core(graph.edges, min(b for _, b in sizes), min(a for a, _ in sizes))
    nodes = cut(tree.build(core))
    out = {}
    for a, b in sizes:
        found = tree.enumeration_at(nodes, a, b)
        for method in methods:
            out[a, b, method] = detect(graph, a, b, method, enumeration=found)
    return out

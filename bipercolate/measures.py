"""Cost measures, counts and the case study."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bipercolate import cohesive, graph, listing, overlap, partial
from bipercolate.checkpoints import cut
from bipercolate.communities import Communities, detect
from bipercolate.graph import Encoded, encode, simple_edges
from bipercolate.maxbiclique import Enumeration, enumerate_bicliques


def counts(encoded: Encoded, alpha: int, beta: int, found: Enumeration | None = None) -> dict[str, int]:
    """Qualified bicliques, basic groups, optimised groups, communities: each at most the one before."""
    found = found or enumerate_bicliques(encoded.edges, alpha, beta, qualified_only=True)
    good = overlap.qualify(found.bicliques, alpha, beta)
    distinct = lambda labels: labels.select("label").distinct().count()
    seeded = cut(partial.by_seed(good, found.seeds, alpha, beta))
    return {
        "qualified": good.count(),
        "basic_groups": distinct(partial.by_prefix(good, alpha, beta)),
        "seed_groups": distinct(seeded),
        "communities": distinct(detect(encoded, alpha, beta, "seed_merge", enumeration=found).labels),
    }


def chains(encoded: Encoded, sizes: Iterable[tuple[int, int]]) -> Iterator[tuple[int, int, dict[str, int]]]:
    """``(alpha, beta, counts)`` of several thresholds."""
    for a, b in sizes:
        yield a, b, counts(encoded, a, b)


def chain_ok(found: dict[str, int]) -> bool:
    return found["qualified"] >= found["basic_groups"] >= found["seed_groups"] >= found["communities"]


def reduction(found: dict[str, int]) -> float:
    """Share of overlap-graph vertices that contraction by optimised groups removes."""
    return 1 - found["seed_groups"] / found["qualified"] if found["qualified"] else 0.0


def refines(groups: DataFrame, labels: DataFrame) -> DataFrame:
    """One row, ``violations``: groups that more than one community meets (0 if groups are partial communities)."""
    both = groups.select("biclique_id", F.col("label").alias("g")).join(labels, "biclique_id")
    return both.groupBy("g").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).filter("lo <> hi").agg(F.count("*").alias("violations"))


def nodes(encoded: Encoded, alpha: int, beta: int, method: str, found: Enumeration | None = None, batches: int = 1) -> dict[str, int]:
    """Nodes that a listing method visits: left prefixes, right prefixes and leaves (exact alpha by beta bicliques)."""
    return detect(encoded, alpha, beta, method, batches=batches, enumeration=found).metrics


def two_hop_size(edges: DataFrame, least_shared: int = 1) -> DataFrame:
    """One row: edges of the 2-hop graph."""
    return graph.two_hop(edges, least_shared).agg(F.count("*").alias("two_hop_edges"))


def degeneracy(pairs: DataFrame, most: int = 10_000) -> int:
    """The largest k with a non-empty k-core of the graph of ``pairs`` (u, w): bounds its arboricity from above."""
    now, k = cut(pairs.select("u", "w")), 0
    while k < most:
        while True:
            both = now.select("u").union(now.select("w"))
            low = cut(both.groupBy("u").agg(F.count("*").alias("d")).filter(F.col("d") <= k).select("u"))
            if low.isEmpty():
                break
            now = cut(now.join(low, "u", "left_anti").join(low.withColumnRenamed("u", "w"), "w", "left_anti").select("u", "w"))
        if now.isEmpty():
            return k
        k += 1
    raise RuntimeError("degeneracy is above the limit")


def shared_sizes(bicliques: DataFrame, labels: DataFrame) -> dict[str, int]:
    """Left and right vertices that bicliques of two labels share."""
    return {side: listing.shared_vertices(bicliques, labels, name).count() for side, name in (("u", "x"), ("v", "y"))}


def overlap_histogram(found: Communities) -> DataFrame:
    """``[side, communities, vertices]``: how many vertices are in how many communities."""
    per = found.members().groupBy("side", "vertex").agg(F.count("*").alias("communities"))
    return per.groupBy("side", "communities").agg(F.count("*").alias("vertices"))


def query_vertex(found: Communities) -> str | None:
    """The least left label in the largest community (ties: the community of the least biclique)."""
    named = found.keyed()
    top = named.groupBy("community_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "community_id").limit(1).select("community_id")
    ids = found.names().select("x", "biclique")
    return named.join(top, "community_id").join(ids, "biclique").agg(F.min(F.array_min("x"))).first()[0]


def case_study(edges: DataFrame, alpha: int, beta: int, k: int, query: str | None = None) -> DataFrame:
    """``[model, vertices, shared, inside, holds]``: what each model returns around a left vertex ``query`` (see ``query_vertex``).

    Models: the vertex's communities, its component in the k-bitruss and in the (beta, alpha)-core, and the biclique of most
    edges that holds it (ties: the least string). ``vertices`` counts them, ``shared`` those that communities have
    too; ``inside``: all of the model's are in communities; ``holds``: all of theirs are in the model.
    """
    encoded = encode(simple_edges(edges))
    found = detect(encoded, alpha, beta, "listing_seeded")
    query = query or query_vertex(found)
    if query is None:
        return edges.sparkSession.createDataFrame([], "model string, vertices long, shared long, inside boolean, holds boolean")
    root = encoded.u.filter(F.col("label").cast("string") == query).select("id").first()[0]
    bicliques = cut(found.bicliques)
    around = bicliques.filter(F.array_contains("x", root))
    mine = cut(found.labels.join(found.labels.join(around, "biclique_id", "left_semi").select("label").distinct(), "label", "left_semi"))
    ends = lambda e: e.select(F.lit("u").alias("side"), F.col("u").cast("string").alias("vertex")).union(e.select(F.lit("v"), F.col("v").cast("string"))).distinct()
    most = F.size("x").cast("long") * F.size("y")
    holding = around.withColumn("n", most)
    best = cut(holding.join(holding.agg(F.max("n").alias("n")), "n").drop("n"))
    named = encoded.labels(best).select("biclique_id", F.concat_ws("|", F.array_join("x", ","), F.array_join("y", ",")).alias("name"))
    least = best.join(named.orderBy("name").limit(1), "biclique_id").select(F.explode("x").alias("u"), "y").select("u", F.explode("y").alias("v"))
    theirs = [found.vertices(mine, side).select(F.lit(side).alias("side"), F.col("id").cast("string").alias("vertex")).distinct() for side in ("u", "v")]
    models = {
        "communities": theirs[0].union(theirs[1]), "bitruss": cohesive.component_of(cohesive.bitruss(encoded.edges, k), "u", root),
        "core": cohesive.component_of(cohesive.core(encoded.edges, beta, alpha), "u", root), "maximum_biclique": ends(least),
    }
    base = cut(models["communities"])
    out = None
    for model, one in models.items():
        both = one.withColumn("m", F.lit(1)).join(base.withColumn("c", F.lit(1)), ["side", "vertex"], "full")
        counts = both.agg(*[F.coalesce(F.sum(F.when(w, 1)), F.lit(0)).cast("long").alias(n) for n, w in (("vertices", F.col("m").isNotNull()), ("shared", F.expr("m = 1 and c = 1")), ("theirs", F.col("c").isNotNull()))])
        row = counts.select(F.lit(model).alias("model"), "vertices", "shared", (F.col("vertices") == F.col("shared")).alias("inside"), (F.col("theirs") == F.col("shared")).alias("holds"))
        out = row if out is None else out.union(row)
    return out

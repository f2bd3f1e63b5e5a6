"""Connected components of a link table: alternating star contraction, all rounds as DataFrame joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bipercolate.checkpoints import cut, release

#: Links that methods on graphs may merge on the driver (a few MB); more go through the rounds.
FEW_LINKS = 100_000


def _checksum(edges: DataFrame) -> tuple:
    return tuple(
        edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
    )


def _large_star(edges: DataFrame) -> DataFrame:
    """Every vertex links its larger neighbours to the least of its neighbours and itself."""
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
    return (
        both.join(least, "a")
        .filter("b > a")
        .select(F.col("m").alias("a"), "b")
        .filter("a <> b")
        .distinct()
    )


def _small_star(edges: DataFrame) -> DataFrame:
    """Every vertex links its smaller neighbours, and itself, to the least of them. Rows come as (smaller, larger)."""
    least = edges.groupBy("b").agg(F.min("a").alias("m"))
    rows = edges.join(least, "b")
    return (
        rows.select(F.col("m").alias("a"), F.col("a").alias("b"))
        .filter("a <> b")
        .union(least.select(F.col("m").alias("a"), "b"))
        .distinct()
    )


def _on_driver(links: DataFrame, limit: int) -> DataFrame | None:
    """Labels by union-find over at most ``limit`` links, or None where there are more."""
    rows = links.limit(limit + 1).collect()
    if len(rows) > limit:
        return None
    parent: dict = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for x, y in rows:
        x, y = find(x), find(y)
        if x != y:
            parent[max(x, y)] = min(x, y)
    kind = links.schema[0].dataType.simpleString()
    return links.sparkSession.createDataFrame([(x, find(x)) for x in list(parent)], f"item {kind}, label {kind}")


def connected(links: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60, driver_limit: int = 0) -> DataFrame:
    """Label every vertex of ``links`` with the least vertex of its component.

    Returns ``[item, label]`` for the vertices that some link names; the caller adds isolated ones.
    Self-links, repeated links and links with a null end don't change the result (self-linked vertices still count as vertices).
    Hubs are joined, never gathered: each round is two aggregations and two joins, O(log) rounds of contraction.
    With ``driver_limit``, so few links (after a count) are merged on the driver instead.
    """
    ends = links.select(F.col(a).alias("a"), F.col(b).alias("b")).filter("a is not null and b is not null")
    if driver_limit and (found := _on_driver(ends.distinct(), driver_limit)) is not None:
        return found
    alone = ends.filter("a = b").select(F.col("a").alias("item"))
    edges = cut(
        ends.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    )
    state = _checksum(edges)
    for _ in range(max_rounds):
        if not state[0]:
            break
        edges, before = cut(_small_star(_large_star(edges))), edges
        release(before)
        new = _checksum(edges)
        if new == state:
            break
        state = new
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    labels = edges.select(F.col("b").alias("item"), F.col("a").alias("label"))
    return labels.union(edges.select("a").distinct().select("a", "a")).union(
        alone.distinct().join(labels.select("item").union(edges.select("a")), "item", "left_anti").select("item", "item")
    )


def merge(labels: DataFrame, links: DataFrame, item: str = "item", label: str = "label", driver_limit: int = 0) -> DataFrame:
    """Coarsen ``[item, label]`` by further links between items; only labels travel through the rounds."""
    own = labels.select(F.col(item).alias("item"), F.col(label).alias("label"))
    left = own.select(F.col("item").alias("a"), F.col("label").alias("la"))
    right = own.select(F.col("item").alias("b"), F.col("label").alias("lb"))
    between = links.select("a", "b").join(left, "a").join(right, "b").filter("la <> lb").select("la", "lb").distinct()
    moved = connected(between, "la", "lb", driver_limit=driver_limit).select(F.col("item").alias("label"), F.col("label").alias("to"))
    return own.join(moved, "label", "left").select("item", F.coalesce("to", "label").alias("label"))

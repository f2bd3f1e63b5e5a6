"""The enumeration tree as a table, and the walk over it that finds partial groups.

A node holds, per side, the vertices chosen (r), those that may follow (c) and those that earlier branches cover (x).
Nodes that lead to a maximal biclique are live; the first node of a path that reaches both sizes is a seed.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bipercolate.checkpoints import cut
from bipercolate.cohesive import vertex_components
from bipercolate.graph import check_thresholds
from bipercolate.listing import BudgetExceeded
from bipercolate.local_solver import Ego, enumerate_root
from bipercolate.maxbiclique import Enumeration, neighbourhoods

SETS = ("r_u", "r_v", "c_u", "c_v", "x_u", "x_v")
NODES = (
    "node_id long, parent_id long, root long, level int, via_side string, via long, "
    + ", ".join(f"{s} array<long>" for s in SETS)
    + ", seed boolean, seed_id long, biclique boolean, live boolean"
)
#: Nodes of a root are numbered below this.
MOST_OF_A_ROOT = 1 << 32


def _nodes_of(ego: Ego, alpha: int, beta: int, pivot: bool) -> list[dict]:
    """The nodes below a root in the order of their creation, live marks set from the last to the first."""
    nodes: list[dict] = []
    for _ in enumerate_root(ego, alpha, beta, pivot, trace=nodes.append):
        pass
    base = ego.root * MOST_OF_A_ROOT
    for node in reversed(nodes):
        node["live"] = node["biclique"] or node.get("live", False)
        if node["live"] and node["parent"] >= 0:
            nodes[node["parent"]]["live"] = True
    for node in nodes:
        node["node_id"], node["root"] = base + node.pop("at"), ego.root
        parent = node.pop("parent")
        node["parent_id"] = None if parent < 0 else base + parent
        node["seed_id"] = None if node["seed_id"] < 0 else base + node["seed_id"]
    return nodes


def build(edges: DataFrame, alpha: int = 1, beta: int = 1, pivot: str = "min_nonneighbours") -> DataFrame:
    """All nodes over encoded edges, below one first-level node per left vertex (in the order of ids); stored sizes grow with the tree."""
    check_thresholds(alpha, beta)
    kinds = pa.schema([
        (x.split()[0], {"long": pa.int64(), "int": pa.int32(), "string": pa.string(), "boolean": pa.bool_()}.get(x.split()[1], pa.list_(pa.int64()))) for x in NODES.split(", ")
    ])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                nodes = _nodes_of(Ego.of(row["root"], [(p["w"], p["v"]) for p in row["pairs"]]), alpha, beta, pivot != "none")
                for k in range(0, len(nodes), 2000):
                    yield pa.RecordBatch.from_pylist(nodes[k : k + 2000], kinds)

    return neighbourhoods(edges).mapInArrow(run, NODES)


def scope(nodes: DataFrame) -> DataFrame:
    """Nodes with ``s_u`` and ``s_v``: the unions of the three sets per side, where every biclique lies that holds the node's vertices."""
    union = lambda side: F.array_sort(F.array_union(F.array_union(f"r_{side}", f"c_{side}"), f"x_{side}"))
    return nodes.withColumns({"s_u": union("u"), "s_v": union("v")})


def mark_live(nodes: DataFrame) -> DataFrame:
    """``live`` found anew from the ``biclique`` leaves: from the deepest level up, parents of live nodes."""
    known = cut(nodes.drop("live"))
    links, marked = known.select("node_id", "parent_id", "level"), known.filter("biclique").select("node_id")
    deepest = known.agg(F.max("level")).first()[0] or 0
    for level in range(deepest, 0, -1):
        up = links.filter(F.col("level") == level).join(marked, "node_id", "left_semi").select(F.col("parent_id").alias("node_id"))
        marked = cut(marked.union(up).distinct())
    return known.join(marked.withColumn("live", F.lit(True)), "node_id", "left").withColumn("live", F.coalesce("live", F.lit(False)))


def seeds(nodes: DataFrame) -> DataFrame:
    """``[seed_id, r_u, r_v, live]``: the first nodes on their paths that reach both sizes."""
    return nodes.filter("seed").select("seed_id", F.array_sort("r_u").alias("r_u"), F.array_sort("r_v").alias("r_v"), "live")


def enumeration_at(nodes: DataFrame, alpha: int, beta: int) -> Enumeration:
    """Qualified bicliques with their seeds for other thresholds than the tree was built with, from the table alone.

    A node is a seed if it reaches both sizes and its parent does not. Numbers follow the tree in pre-order and no seed lies
    below another, so that a biclique's seed is the last one at or before it below the same root.
    """
    check_thresholds(alpha, beta)
    reached = (F.size("r_u") >= alpha) & (F.size("r_v") >= beta)
    big = nodes.filter(reached)
    above = nodes.filter(reached).select(F.col("node_id").alias("parent_id"), F.lit(True).alias("again"))
    rows = big.join(above, "parent_id", "left").withColumn("own", F.when(F.col("again").isNull(), F.col("node_id")))
    order = Window.partitionBy("root").orderBy("node_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = cut(rows.withColumn("of", F.last("own", ignorenulls=True).over(order).cast("string")))
    sets = rows.filter("biclique").select(F.array_sort("r_u").alias("x"), F.array_sort("r_v").alias("y"), F.col("of").alias("seed_id"))
    bicliques = cut(sets.select(F.monotonically_increasing_id().alias("biclique_id"), "x", "y", F.size("x").alias("n_x"), F.size("y").alias("n_y"), "seed_id"))
    found = rows.filter("own is not null").select(F.col("of").alias("seed_id"), F.array_sort("r_u").alias("r_u"), F.array_sort("r_v").alias("r_v"), "live")
    return Enumeration(bicliques, cut(found), nodes.count())


@dataclass
class Walk:
    """Partial groups by a walk over a whole tree: seeds in post-order, each searching the live tree within its scope.

    A finished live node keeps a *tag*, one biclique of its group, which stands for all that lies below it. A node below
    a seed joins its live children's tags; the seed joins whatever its search meets, and the search ends at tags. Below a
    node whose vertex the seed holds itself, no later sibling can hold all of the seed's vertices, so the search leaves the
    siblings there.

    Why tags may replace what lies below them: a tagged node within the scope of a seed has vertices that, together with
    the seed's, form a biclique; some maximal biclique holds both, and it is in the group of either.
    """

    nodes: list[dict]
    tags: bool = True
    visited: int = 0
    parent: dict[int, int] = field(default_factory=dict)
    tag: dict[int, int] = field(default_factory=dict)

    def __post_init__(self) -> None:
        self.nodes.sort(key=lambda n: n["node_id"])
        self.children: dict[int | None, list[dict]] = {}
        for node in self.nodes:
            node["of"] = (node["via_side"], node["via"])
            self.children.setdefault(node["parent_id"], []).append(node)

    def find(self, x: int) -> int:
        while self.parent.setdefault(x, x) != x:
            self.parent[x] = self.parent[self.parent[x]]
            x = self.parent[x]
        return x

    def unite(self, found: list[int]) -> int:
        first = self.find(found[0])
        for other in found[1:]:
            self.parent[self.find(other)] = first
        return first

    def post_order(self) -> Iterator[dict]:
        stack = [(n, False) for n in reversed(self.children.get(None, []))]
        while stack:
            node, done = stack.pop()
            if done:
                yield node
            else:
                stack.append((node, True))
                stack += [(c, False) for c in reversed(self.children.get(node["node_id"], []))]

    def search(self, seed: dict) -> list[int]:
        """Tags, or bicliques, of the live nodes whose paths lie within the scope of a seed."""
        own = {("u", w) for w in seed["r_u"]} | {("v", w) for w in seed["r_v"]}
        within = own | {(s[-1], w) for s in ("c_u", "x_u", "c_v", "x_v") for w in seed[s]}
        found, todo = [], [None]
        while todo:
            for node in self.children.get(todo.pop(), []):
                if node["live"] and node["of"] in within:
                    self.visited += 1
                    if self.tags and node["node_id"] in self.tag:
                        found.append(self.tag[node["node_id"]])
                    elif node["biclique"]:
                        found.append(node["node_id"])
                    else:
                        todo.append(node["node_id"])
                if node["of"] in own:
                    break
        return found

    def groups(self) -> dict[int, int]:
        """The group (one of its bicliques) of every biclique with a seed on its path; bicliques are named by their leaves."""
        for node in self.post_order():
            met: list[int] = []
            if node["seed"]:
                met = self.search(node)
            elif node["live"] and node["seed_id"] is not None:
                below = [self.tag[c["node_id"]] for c in self.children.get(node["node_id"], []) if c["live"]]
                met = [node["node_id"]] if node["biclique"] else below
            if met:
                self.tag[node["node_id"]] = self.unite(met)
        return {n["node_id"]: self.find(n["node_id"]) for n in self.nodes if n["biclique"] and n["seed_id"] is not None}


def walk_groups(edges: DataFrame, alpha: int, beta: int, tags: bool = True, most_nodes: int = 2_000_000) -> DataFrame:
    """``[x, y, group_id, visited]``: qualified bicliques and their groups by the walk; ``visited`` counts the nodes that searches met.

    Trees of different connected components never meet, so each component is walked in one task. A component whose tree
    has more than ``most_nodes`` nodes raises an error: ``partial.by_seed`` finds the same groups by joins at any size.
    """
    nodes = cut(build(edges, alpha, beta))
    parts = vertex_components(edges).filter("side = 'u'").select(F.col("vertex").cast("long").alias("root"), F.col("label").alias("component"))
    placed = cut(nodes.join(parts, "root"))
    largest = placed.groupBy("component").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0
    if largest > most_nodes:
        raise BudgetExceeded(f"a component has {largest} tree nodes, more than {most_nodes}")

    def run(group: pa.Table) -> pa.Table:
        walk = Walk(group.drop_columns("component").to_pylist(), tags)
        found = walk.groups()
        rows = [n for n in walk.nodes if n["node_id"] in found]
        return pa.table({
            "x": pa.array([sorted(n["r_u"]) for n in rows], pa.list_(pa.int64())), "y": pa.array([sorted(n["r_v"]) for n in rows], pa.list_(pa.int64())),
            "group_id": pa.array([found[n["node_id"]] for n in rows], pa.int64()), "visited": pa.array([walk.visited] * len(rows), pa.int64()),
        })

    return placed.groupBy("component").applyInArrow(run, "x array<long>, y array<long>, group_id long, visited long")

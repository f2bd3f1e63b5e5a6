"""For SQL users: a table function that finds the communities of each partition's graph, and named views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from bipercolate.local_solver import Ego, enumerate_root


def small_communities(pairs: set[tuple], alpha: int, beta: int) -> list[tuple[int, str, str]]:
    """``(community, side, vertex)`` of a graph that fits one worker."""
    left, right = sorted({u for u, _ in pairs}), sorted({v for _, v in pairs})
    at_u, at_v = {x: k for k, x in enumerate(left)}, {x: k for k, x in enumerate(right)}
    of_u: dict[int, set[int]] = {}
    of_v: dict[int, set[int]] = {}
    for u, v in pairs:
        of_u.setdefault(at_u[u], set()).add(at_v[v])
        of_v.setdefault(at_v[v], set()).add(at_u[u])
    good: list[tuple[frozenset, frozenset]] = []
    for root, nbrs in of_u.items():
        ego = Ego.of(root, [(w, v) for v in nbrs for w in of_v[v]])
        good += [(frozenset(f.x), frozenset(f.y)) for f in enumerate_root(ego, alpha, beta, cut_small=True) if f.kind == "biclique" and len(f.x) >= alpha and len(f.y) >= beta]
    label = list(range(len(good)))

    def find(k: int) -> int:
        while label[k] != k:
            label[k] = label[label[k]]
            k = label[k]
        return k

    posts: dict[int, list[int]] = {}
    for k, (x, y) in enumerate(good):
        for j in {j for u in x for j in posts.get(u, ())}:
            if find(j) != find(k) and len(good[j][0] & x) >= alpha and len(good[j][1] & y) >= beta:
                a, b = sorted((find(j), find(k)))
                label[b] = a
        for u in x:
            posts.setdefault(u, []).append(k)
    rows = set()
    for k, (x, y) in enumerate(good):
        rows |= {(find(k), "u", left[u]) for u in x} | {(find(k), "v", right[v]) for v in y}
    return sorted(rows)


class PercolationCommunities:
    """``SELECT * FROM percolation_communities(TABLE(edges) PARTITION BY (snapshot), 2, 2)``: one graph per partition, columns u and v."""

    def __init__(self) -> None:
        self.pairs: set[tuple[str, str]] = set()
        self.sizes = (1, 1)

    def eval(self, row, alpha: int, beta: int):
        self.sizes = (alpha, beta)
        if row["u"] is not None and row["v"] is not None:
            self.pairs.add((str(row["u"]), str(row["v"])))

    def terminate(self):
        yield from small_communities(self.pairs, *self.sizes)


def register(spark: SparkSession) -> None:
    spark.udtf.register("percolation_communities", udtf(PercolationCommunities, returnType="community int, side string, vertex string"))


def views(edges: DataFrame, bicliques: DataFrame | None = None, members: DataFrame | None = None) -> None:
    """Temporary views ``edges``, ``bicliques``, ``community_members``."""
    edges.createOrReplaceTempView("edges")
    if bicliques is not None:
        bicliques.createOrReplaceTempView("bicliques")
    if members is not None:
        members.createOrReplaceTempView("community_members")

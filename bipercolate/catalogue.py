"""Queries over the given tables, with SQL that must give the same rows.

Sets come out as strings: labels of a side sorted and comma-joined, a biclique as "x|y", a community as its least biclique.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import partial as bound

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bipercolate import cohesive, communities, graph, listing, maxbiclique, measures, overlap, partial, tree
from bipercolate.checkpoints import cut
from bipercolate.communities import METHODS, detect
from bipercolate.components import FEW_LINKS, connected
from bipercolate.graph import Encoded, encode
from bipercolate.operators import relational
from bipercolate.sources.workloads import ALPHAS, BETAS, GRAPHS, SPARSE, SQL

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLE_SQL[name] = sql


# ---- pieces of SQL -------------------------------------------------------------------------------------------------


def edges_sql(g: str) -> str:
    return f"e AS MATERIALIZED (SELECT CAST(u AS VARCHAR) AS u, CAST(v AS VARCHAR) AS v FROM ({SQL[g]}))"


#: All maximal bicliques: neighbour lists closed under intersection, and the vertices adjacent to all of each.
BICLIQUES_SQL = """
lists AS MATERIALIZED (SELECT u, list_sort(list(v)) AS ys FROM e GROUP BY u),
closed(y) AS (
    SELECT DISTINCT ys FROM lists
    UNION
    SELECT list_sort(list_intersect(c.y, l.ys)) FROM closed c JOIN lists l ON len(list_intersect(c.y, l.ys)) > 0
),
b AS MATERIALIZED (
    SELECT c.y, list_sort(list(l.u)) AS x, array_to_string(list_sort(list(l.u)), ',') || '|' || array_to_string(c.y, ',') AS biclique
    FROM closed c JOIN lists l ON list_has_all(l.ys, c.y) GROUP BY c.y
)"""


def overlap_sql(a: int, b: int) -> str:
    return f"""
q AS MATERIALIZED (SELECT * FROM b WHERE len(x) >= {a} AND len(y) >= {b}),
links AS MATERIALIZED (
    SELECT p.biclique AS a, r.biclique AS b, len(list_intersect(p.x, r.x)) AS common_x, len(list_intersect(p.y, r.y)) AS common_y
    FROM q p JOIN q r ON p.biclique < r.biclique AND len(list_intersect(p.y, r.y)) >= {b} AND len(list_intersect(p.x, r.x)) >= {a}
)"""


def qualified_sql(a: int, b: int) -> str:
    """Qualified bicliques of large graphs, for a >= 2: right sets start from pairs of lists that share b vertices, and lists are met through a shared vertex."""
    return f"""
lists AS MATERIALIZED (SELECT u, list_sort(list(v)) AS ys FROM e GROUP BY u),
pairs AS MATERIALIZED (SELECT p.u AS a, r.u AS b FROM e p JOIN e r ON p.v = r.v AND p.u < r.u GROUP BY 1, 2 HAVING count(*) >= {b}),
closed(y) AS (
    SELECT DISTINCT list_sort(list_intersect(p.ys, r.ys)) FROM pairs JOIN lists p ON p.u = pairs.a JOIN lists r ON r.u = pairs.b
    UNION
    SELECT list_sort(list_intersect(c.y, l.ys)) FROM (SELECT y, unnest(y) AS v FROM closed) c JOIN e ON e.v = c.v JOIN lists l ON l.u = e.u
    WHERE len(list_intersect(c.y, l.ys)) >= {b}
),
b AS MATERIALIZED (
    SELECT c.y, list_sort(list(l.u)) AS x, array_to_string(list_sort(list(l.u)), ',') || '|' || array_to_string(c.y, ',') AS biclique
    FROM closed c JOIN e ON e.v = c.y[1] JOIN lists l ON l.u = e.u AND list_has_all(l.ys, c.y) GROUP BY c.y
),
q AS MATERIALIZED (SELECT * FROM b WHERE len(x) >= {a})"""


def shared_sql(a: int, b: int) -> str:
    """Links between qualified bicliques, counted over the vertices that they share."""
    return f"""
by_x AS (SELECT p.biclique AS a, r.biclique AS b FROM (SELECT biclique, unnest(x) AS w FROM q) p JOIN (SELECT biclique, unnest(x) AS w FROM q) r ON p.w = r.w AND p.biclique < r.biclique GROUP BY 1, 2 HAVING count(*) >= {a}),
links AS MATERIALIZED (SELECT a, b FROM by_x JOIN q p ON p.biclique = a JOIN q r ON r.biclique = b WHERE len(list_intersect(p.y, r.y)) >= {b})"""


def large_communities_sql(g: str, a: int, b: int) -> str:
    return f"WITH RECURSIVE {edges_sql(g)}, {qualified_sql(a, b)}, {shared_sql(a, b)}, {COMPONENTS_SQL}\nSELECT least AS community_id, item AS biclique FROM label"


#: Components of links over the items of q, by passing least labels on.
COMPONENTS_SQL = """
either AS MATERIALIZED (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
label(item, least) USING KEY (item) AS (
    SELECT biclique, biclique FROM q
    UNION
    SELECT n.b, min(l.least) FROM label l JOIN either n ON n.a = l.item JOIN recurring.label r ON r.item = n.b WHERE l.least < r.least GROUP BY n.b
)"""


def communities_sql(g: str, a: int, b: int) -> str:
    return f"WITH RECURSIVE {edges_sql(g)}, {BICLIQUES_SQL}, {overlap_sql(a, b)}, {COMPONENTS_SQL}\nSELECT least AS community_id, item AS biclique FROM label"


# ---- graphs --------------------------------------------------------------------------------------------------------


def texts(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("u").cast("string").alias("u"), F.col("v").cast("string").alias("v"))


def encoded(g: str, spark: SparkSession, d: str, order: str = "two_hop_degree") -> Encoded:
    return encode(texts(GRAPHS[g](spark, d)), order)


def graph_stats(g: str, spark: SparkSession, d: str) -> DataFrame:
    return graph.stats(GRAPHS[g](spark, d))


for g in GRAPHS:
    add(f"graph_stats_{g}", bound(graph_stats, g), f"WITH {edges_sql(g)} SELECT count(DISTINCT u) AS n_u, count(DISTINCT v) AS n_v, count(*) AS n_edges, count(*) / count(DISTINCT u) AS mean_degree_u, count(*) / count(DISTINCT v) AS mean_degree_v FROM e")

for side, other in (("u", "v"), ("v", "u")):
    add(f"degree_hist_{side}", lambda s, d, side=side: graph.degree_histogram(GRAPHS["doc_line"](s, d), side), f"WITH {edges_sql('doc_line')}, d AS (SELECT {side}, count(*) AS degree FROM e GROUP BY 1) SELECT degree, count(*) AS vertices FROM d GROUP BY 1")

add("two_hop_edges", lambda s, d: graph.two_hop(texts(GRAPHS["page_link"](s, d))), f"WITH {edges_sql('page_link')} SELECT DISTINCT a.u, b.u AS w FROM e a JOIN e b ON a.v = b.v AND a.u < b.u")
add("two_hop_size", lambda s, d: measures.two_hop_size(GRAPHS["bench_word"](s, d)), f"WITH {edges_sql('bench_word')} SELECT count(*) AS two_hop_edges FROM (SELECT DISTINCT a.u, b.u AS w FROM e a JOIN e b ON a.v = b.v AND a.u < b.u)")


def two_hop_degree_rank(spark: SparkSession, d: str) -> DataFrame:
    return encoded("user_day", spark, d).u.select(F.col("label").alias("u"), F.col("id").alias("place"))


add("two_hop_degree_rank", two_hop_degree_rank, f"""WITH {edges_sql('user_day')}, h AS (SELECT a.u, count(DISTINCT b.u) AS degree FROM e a JOIN e b ON a.v = b.v AND a.u <> b.u GROUP BY 1),
d AS (SELECT DISTINCT e.u, coalesce(h.degree, 0) AS degree FROM e LEFT JOIN h ON e.u = h.u) SELECT u, row_number() OVER (ORDER BY degree, u) AS place FROM d""")
for percent in (20, 40, 60, 80):
    add(f"edge_sample_{percent}", lambda s, d, p=percent: graph.sample(GRAPHS["order_part"](s, d), p), f"SELECT u, v FROM ({SQL['order_part']}) WHERE (u * 7919 + v * 104729) % 100 < {percent}")

# ---- maximal bicliques ---------------------------------------------------------------------------------------------


def strings(graph_: Encoded, bicliques: DataFrame) -> DataFrame:
    return named(graph_.labels(bicliques))


def named(names: DataFrame) -> DataFrame:
    return names.select(F.concat_ws("|", F.array_join("x", ","), F.array_join("y", ",")).alias("biclique"), F.size("x").cast("long").alias("n_x"), F.size("y").cast("long").alias("n_y"))


def maximal_bicliques(g: str, engine: str, pivot: str, order: str, spark: SparkSession, d: str) -> DataFrame:
    e = encode(texts(GRAPHS[g](spark, d)), order)
    return strings(e, maxbiclique.enumerate_bicliques(e.edges, engine=engine, pivot=pivot).bicliques)


def qualified(g: str, a: int, b: int, spark: SparkSession, d: str) -> DataFrame:
    e = encoded(g, spark, d)
    return strings(e, maxbiclique.enumerate_bicliques(e.edges, a, b, qualified_only=True).bicliques)


def bicliques_sql(g: str, where: str = "true") -> str:
    return f"WITH RECURSIVE {edges_sql(g)}, {BICLIQUES_SQL}\nSELECT biclique, len(x) AS n_x, len(y) AS n_y FROM b WHERE {where}"


for g in ("doc_line", "user_day", "cust_quarter", "bench_word", "vec_dim", "page_link", "nation_brand", "cust_priority", "part_supp_returned", "doc_label", "cust_region"):
    add(f"maximal_bicliques_{g}", bound(maximal_bicliques, g, "local", "min_nonneighbours", "two_hop_degree"), bicliques_sql(g))
for engine, pivot, order in (("frontier", "min_nonneighbours", "two_hop_degree"), ("closure", "min_nonneighbours", "two_hop_degree"), ("local", "min_nonneighbours", "id"), ("auto", "min_nonneighbours", "two_hop_degree")):
    add(f"maximal_bicliques_nation_brand_{engine}_{pivot}_{order}", bound(maximal_bicliques, "nation_brand", engine, pivot, order), bicliques_sql("nation_brand"))
# The plain tree visits every subset of a star: 2^n nodes, so that only small graphs end.
for order in ("two_hop_degree", "id"):
    add(f"maximal_bicliques_nation_segment_local_none_{order}", bound(maximal_bicliques, "nation_segment", "local", "none", order), bicliques_sql("nation_segment"))
for g, a, b in (("cust_brand", 3, 3), ("order_part", 2, 2), ("user_hour", 4, 4), ("conv_word", 3, 3)):
    add(f"maximal_bicliques_qualified_{g}_{a}_{b}", bound(qualified, g, a, b), f"WITH RECURSIVE {edges_sql(g)}, {qualified_sql(a, b)}\nSELECT biclique, len(x) AS n_x, len(y) AS n_y FROM q")


def auto_engine(spark: SparkSession, d: str) -> DataFrame:
    """Roots of more than 150 pairs grown level by level, the others solved locally."""
    e = encoded("nation_brand", spark, d)
    return strings(e, maxbiclique.enumerate_bicliques(e.edges, engine="auto", heavy=150).bicliques)


add("maximal_bicliques_nation_brand_auto_mixed", auto_engine, bicliques_sql("nation_brand"))


def all_of(g: str, spark: SparkSession, d: str) -> tuple[Encoded, DataFrame]:
    e = encoded(g, spark, d)
    return e, maxbiclique.enumerate_bicliques(e.edges).bicliques


def size_histogram(edges: DataFrame) -> DataFrame:
    """``[n_x, n_y, bicliques]`` over encoded edges, from one vertex of each class of twins."""
    thin = graph.thinned(edges)
    return thin.sizes(maxbiclique.enumerate_bicliques(thin.edges).bicliques).groupBy("n_x", "n_y").agg(F.count("*").alias("bicliques"))


add("biclique_size_hist", lambda s, d: size_histogram(encoded("user_day", s, d, "roots").edges), f"WITH RECURSIVE {edges_sql('user_day')}, {BICLIQUES_SQL} SELECT len(x) AS n_x, len(y) AS n_y, count(*) AS bicliques FROM b GROUP BY 1, 2")


def maximum_size(by: str, spark: SparkSession, d: str) -> DataFrame:
    return cohesive.maximum_biclique(all_of("user_day", spark, d)[1], by).select("biclique_size")


for by, size in (("edges", "len(x) * len(y)"), ("vertices", "len(x) + len(y)")):
    add(f"maximum_biclique_{by}", bound(maximum_size, by), f"WITH RECURSIVE {edges_sql('user_day')}, {BICLIQUES_SQL} SELECT max({size}) AS biclique_size FROM b")

# ---- overlap graph and communities ---------------------------------------------------------------------------------


def overlap_edges(g: str, a: int, b: int, prefix: bool, spark: SparkSession, d: str) -> DataFrame:
    e, found = all_of(g, spark, d)
    links = overlap.edges(found, a, b, prefix)
    names = cut(e.labels(found).select("biclique_id", F.concat_ws("|", F.array_join("x", ","), F.array_join("y", ",")).alias("name")))
    both = links.join(names.select(F.col("biclique_id").alias("a"), F.col("name").alias("na")), "a").join(names.select(F.col("biclique_id").alias("b"), F.col("name").alias("nb")), "b")
    return both.select(F.least("na", "nb").alias("a"), F.greatest("na", "nb").alias("b"), F.col("common_x").cast("long"), F.col("common_y").cast("long"))


for g, a, b, prefix in (("user_day", 3, 3, True), ("nation_brand", 2, 2, True), ("nation_brand", 2, 2, False), ("doc_line", 2, 2, True)):
    add(f"overlap_edges_{g}_{a}_{b}" + "" * prefix + "_unfiltered" * (not prefix), bound(overlap_edges, g, a, b, prefix), f"WITH RECURSIVE {edges_sql(g)}, {BICLIQUES_SQL}, {overlap_sql(a, b)} SELECT a, b, common_x, common_y FROM links")
add("overlap_edge_count", lambda s, d: overlap.edges(all_of("vec_dim", s, d)[1], 2, 2).agg(F.count("*").alias("overlap_edges")), f"WITH RECURSIVE {edges_sql('vec_dim')}, {BICLIQUES_SQL}, {overlap_sql(2, 2)} SELECT count(*) AS overlap_edges FROM links")
add("overlap_pairs_sharing_a_vertex", lambda s, d: overlap.candidates(all_of("nation_brand", s, d)[1]).agg(F.count("*").alias("pairs")), f"WITH RECURSIVE {edges_sql('nation_brand')}, {BICLIQUES_SQL} SELECT count(*) AS pairs FROM b p JOIN b r ON p.biclique < r.biclique AND list_has_any(p.x, r.x)")


def overlap_degree_topk(spark: SparkSession, d: str) -> DataFrame:
    links = overlap_edges("nation_brand", 2, 2, True, spark, d)
    ends = links.select(F.col("a").alias("biclique")).union(links.select("b"))
    return ends.groupBy("biclique").agg(F.count("*").alias("degree")).orderBy(F.desc("degree"), "biclique").limit(5)


add("overlap_degree_topk", overlap_degree_topk, f"WITH RECURSIVE {edges_sql('nation_brand')}, {BICLIQUES_SQL}, {overlap_sql(2, 2)} SELECT biclique, count(*) AS degree FROM (SELECT a AS biclique FROM links UNION ALL SELECT b FROM links) GROUP BY 1 ORDER BY degree DESC, biclique LIMIT 5")


def found_communities(method: str, g: str, a: int, b: int, spark: SparkSession, d: str, **options) -> communities.Communities:
    """Right labels of fewer than ``a`` left vertices lie in no qualified biclique, so sparse graphs leave them out."""
    rows = GRAPHS[g](spark, d, a) if g in SPARSE else GRAPHS[g](spark, d)
    return detect(encode(texts(rows), "roots"), a, b, method, **options)


def keyed(method: str, g: str, a: int, b: int, options: dict, spark: SparkSession, d: str) -> DataFrame:
    return found_communities(method, g, a, b, spark, d, **options).keyed()


for g, a, b in (("user_day", 3, 3), ("doc_line", 2, 2), ("nation_brand", 4, 4)):
    for method in METHODS:
        add(f"communities_{method}_{g}_{a}_{b}", bound(keyed, method, g, a, b, {}), communities_sql(g, a, b))
for g, a, b in (("cust_brand", 3, 3), ("cust_quarter", 2, 2), ("bench_word", 2, 2), ("vec_dim", 2, 2), ("page_link", 2, 2), ("nation_brand", 8, 8), ("nation_brand", 6, 6), ("cust_priority", 4, 4), ("part_supp_returned", 1, 2), ("doc_label", 3, 3), ("cust_region", 3, 3)):
    add(f"communities_listing_seeded_{g}_{a}_{b}", bound(keyed, "listing_seeded", g, a, b, {}), communities_sql(g, a, b))
for g, a, b in (("order_part", 2, 1), ("conv_word", 3, 3), ("user_hour", 4, 4)):
    add(f"communities_seed_merge_{g}_{a}_{b}", bound(keyed, "seed_merge", g, a, b, {}), large_communities_sql(g, a, b))
for name, options in (("batches", {"batches": 3}), ("unrestricted", {"restrict_shared": False}), ("basic_seeds", {"seed": "prefix"}), ("left_checks_only", {"prune_right_prefix": False}), ("frontier", {"engine": "frontier"})):
    add(f"communities_listing_seeded_{name}", bound(keyed, "listing_seeded", "nation_brand", 4, 4, options), communities_sql("nation_brand", 4, 4))


def members(spark: SparkSession, d: str) -> DataFrame:
    found = found_communities("listing_seeded", "user_day", 3, 3, spark, d)
    label = found.labels.join(found.names(), "biclique_id").groupBy("label").agg(F.min("biclique").alias("community_id"))
    return found.members().join(label, "label").select("community_id", "side", "vertex")


add("community_members", members, communities_sql("user_day", 3, 3).replace("SELECT least AS community_id, item AS biclique FROM label", "SELECT DISTINCT least AS community_id, side, vertex FROM (SELECT least, 'u' AS side, unnest(x) AS vertex FROM label JOIN b ON item = biclique UNION ALL SELECT least, 'v', unnest(y) FROM label JOIN b ON item = biclique)"))
add("communities_of_vertex", lambda s, d: members(s, d).filter("side = 'v' and vertex = '2024-01-15'").select("community_id"), communities_sql("user_day", 3, 3).replace("SELECT least AS community_id, item AS biclique FROM label", "SELECT DISTINCT least AS community_id FROM label JOIN b ON item = biclique WHERE list_contains(y, '2024-01-15')"))
add("community_sizes", lambda s, d: keyed("seed_merge", "user_day", 3, 3, {}, s, d).groupBy("community_id").agg(F.count("*").alias("bicliques")), communities_sql("user_day", 3, 3).replace("SELECT least AS community_id, item AS biclique FROM label", "SELECT least AS community_id, count(*) AS bicliques FROM label GROUP BY 1"))


def alpha1_beta1(spark: SparkSession, d: str) -> DataFrame:
    """Communities at (1, 1) are the connected components of the graph: one row of (components, vertices)."""
    rows = found_communities("overlap", "page_link", 1, 1, spark, d).members()
    return rows.agg(F.countDistinct("label").alias("components"), F.count("*").alias("vertices"))


add("communities_alpha1_beta1", alpha1_beta1, f"""WITH RECURSIVE {edges_sql('page_link')}, links AS (SELECT DISTINCT 'u:' || u AS a, 'v:' || v AS b FROM e), q AS (SELECT a AS biclique FROM links UNION SELECT b FROM links), {COMPONENTS_SQL}
SELECT count(DISTINCT least) AS components, count(*) AS vertices FROM label""")

# ---- listing -------------------------------------------------------------------------------------------------------


def ab_bicliques(g: str, a: int, b: int, side: str, spark: SparkSession, d: str) -> DataFrame:
    """As in ``found_communities``, sparse graphs leave out right labels of fewer than ``a`` left vertices."""
    rows = GRAPHS[g](spark, d, a) if g in SPARSE else GRAPHS[g](spark, d)
    return listing.names_ab(encode(texts(rows), "id"), a, b, side)


AB_22_SQL = "SELECT a.u || ',' || b.u || '|' || a.v || ',' || c.v AS biclique FROM e a JOIN e b ON a.v = b.v AND a.u < b.u JOIN e c ON c.u = a.u AND c.v > a.v JOIN e f ON f.u = b.u AND f.v = c.v"
for side in ("u", "v"):
    add(f"ab_bicliques_doc_line_2_2_{side}", bound(ab_bicliques, "doc_line", 2, 2, side), f"WITH {edges_sql('doc_line')} {AB_22_SQL}")
add("ab_biclique_count", lambda s, d: listing.count(encoded("cust_quarter", s, d).edges, 2, 2), f"WITH {edges_sql('cust_quarter')} SELECT count(*) AS ab_bicliques FROM ({AB_22_SQL})")
add("ab_biclique_count_3_2", lambda s, d: listing.count(encoded("vec_dim", s, d).edges, 3, 2), f"WITH {edges_sql('vec_dim')}, p AS (SELECT a.u AS x, b.u AS y, c.u AS z, count(*) AS n FROM e a JOIN e b ON a.v = b.v AND a.u < b.u JOIN e c ON c.v = a.v AND b.u < c.u GROUP BY 1, 2, 3) SELECT coalesce(sum(n * (n - 1) / 2), 0)::BIGINT AS ab_bicliques FROM p")


def by_own_keys(spark: SparkSession, d: str) -> DataFrame:
    """Communities by the subsets that bicliques list themselves."""
    e, found = all_of("nation_brand", spark, d)
    good = cut(overlap.qualify(found, 2, 2))
    links = listing.keys_from_bicliques(good, 2, 2)
    return connected(links, driver_limit=FEW_LINKS).agg(F.countDistinct("label").alias("components"), F.count("*").alias("linked_bicliques"))


add("listing_by_own_keys", by_own_keys, communities_sql("nation_brand", 2, 2).replace("SELECT least AS community_id, item AS biclique FROM label", "SELECT count(DISTINCT least) AS components, count(*) AS linked_bicliques FROM label WHERE item IN (SELECT a FROM either)"))

# ---- partial groups and measures -----------------------------------------------------------------------------------


def chain(g: str, a: int, b: int, spark: SparkSession, d: str) -> DataFrame:
    found = measures.counts(encoded(g, spark, d), a, b)
    return spark.createDataFrame([(measures.chain_ok(found), found["qualified"], found["communities"])], "ok boolean, qualified long, communities long")


for g, a, b in (("user_day", 3, 3), ("nation_brand", 4, 4), ("bench_word", 3, 3)):
    add(f"partial_counts_chain_{g}_{a}_{b}", bound(chain, g, a, b), communities_sql(g, a, b).replace("SELECT least AS community_id, item AS biclique FROM label", "SELECT true AS ok, count(*) AS qualified, count(DISTINCT least) AS communities FROM label"))


def group_counts(spark: SparkSession, d: str) -> DataFrame:
    """Counts for several thresholds; the groups between them depend on the order of the tree, so only their order is compared."""
    e = encoded("user_day", spark, d)
    rows = []
    for a, b, found in measures.chains(e, ((2, 2), (2, 3), (3, 3))):
        rows.append((a, b, found["qualified"], found["communities"], measures.chain_ok(found), 0 <= measures.reduction(found) < 1))
    return spark.createDataFrame(rows, "alpha long, beta long, qualified long, communities long, chain_ok boolean, reduction_ok boolean")


def group_counts_sql(g: str, sizes: tuple[tuple[int, int], ...]) -> str:
    one = "SELECT {a} AS alpha, {b} AS beta, count(*) AS qualified, count(DISTINCT least) AS communities, true AS chain_ok, true AS reduction_ok FROM label"
    parts = [f"SELECT * FROM (WITH RECURSIVE {edges_sql(g)}, {BICLIQUES_SQL}, {overlap_sql(a, b)}, {COMPONENTS_SQL} {one.format(a=a, b=b)})" for a, b in sizes]
    return " UNION ALL ".join(parts)


add("measure_group_counts", group_counts, group_counts_sql("user_day", ((2, 2), (2, 3), (3, 3))))


def refinement(method: str, spark: SparkSession, d: str) -> DataFrame:
    found = found_communities(method, "user_day", 3, 3, spark, d)
    return measures.refines(found.groups, found.labels)


for method in ("prefix_merge", "seed_merge"):
    add(f"partial_refines_communities_{method}", bound(refinement, method), "SELECT 0::BIGINT AS violations")


def listing_nodes(spark: SparkSession, d: str) -> DataFrame:
    """Nodes of the three listing methods: the unpruned one visits every small biclique, pruning never adds nodes, seeds never do either."""
    e = encoded("user_day", spark, d)
    found = maxbiclique.enumerate_bicliques(e.edges, 3, 3, qualified_only=True)
    n = {m: measures.nodes(e, 3, 3, m, found) for m in ("listing", "listing_pruned", "listing_seeded")}
    total = {m: sum(int(x.get(k, 0)) for k in ("prefix", "right", "leaf")) for m, x in n.items()}
    row = (int(n["listing"]["leaf"]), total["listing_pruned"] <= total["listing"], total["listing_seeded"] <= total["listing_pruned"])
    return spark.createDataFrame([row], "small_bicliques long, pruned_ok boolean, seeded_ok boolean")


add("measure_listing_nodes", listing_nodes, f"""WITH {edges_sql('user_day')}, t AS (SELECT p.u, q.u AS w, r.u AS z, count(*) AS n FROM e p JOIN e q ON p.v = q.v AND p.u < q.u JOIN e r ON r.v = p.v AND q.u < r.u GROUP BY 1, 2, 3)
SELECT coalesce(sum(n * (n - 1) * (n - 2) / 6), 0)::BIGINT AS small_bicliques, true AS pruned_ok, true AS seeded_ok FROM t""")


def tree_bicliques(spark: SparkSession, d: str) -> DataFrame:
    """Maximal bicliques read from the table of the enumeration tree."""
    e = encoded("page_link", spark, d)
    thin = graph.thinned(e.edges)
    leaves = tree.build(thin.edges).filter("biclique").select(F.col("node_id").alias("biclique_id"), F.col("r_u").alias("x"), F.col("r_v").alias("y"))
    return named(thin.labels(cut(leaves), e))


def tree_violations(spark: SparkSession, d: str) -> DataFrame:
    """What must not be: scopes other than common neighbours, live marks that differ from the paths to bicliques, seeds above seeds."""
    e = encoded("nation_brand", spark, d)
    nodes = cut(tree.scope(tree.build(e.edges, 4, 4)))
    held = nodes.filter(F.size("r_v") > 0).select("node_id", "s_u", F.explode("r_v").alias("v"), F.size("r_v").alias("n")).join(e.edges, "v")
    common = held.groupBy("node_id", "u").agg(F.count("*").alias("k"), F.first("n").alias("n"), F.first("s_u").alias("s_u")).filter("k = n")
    wrong = common.groupBy("node_id").agg(F.array_sort(F.collect_list("u")).alias("us"), F.first("s_u").alias("s_u")).filter("us <> s_u")
    marks = tree.mark_live(nodes).select("node_id", F.col("live").alias("again")).join(nodes, "node_id").filter("live <> again")
    path = nodes.filter("seed").select(F.col("node_id").alias("own"), "parent_id").join(nodes.select(F.col("node_id").alias("parent_id"), F.col("seed_id").alias("above")), "parent_id")
    counts = [x.agg(F.count("*").alias("n")) for x in (wrong, marks, path.filter("above is not null"))]
    names = ("scopes", "live_marks", "seeds_above_seeds")
    rows = [c.select(F.lit(k).alias("what"), "n") for k, c in zip(names, counts, strict=True)]
    return rows[0].union(rows[1]).union(rows[2])


def tree_walk(g: str, a: int, b: int, spark: SparkSession, d: str) -> DataFrame:
    """Groups of the walk with and without tags against those of the containment join: bicliques whose label differs, and whether tags save visits."""
    e = encoded(g, spark, d)
    found = maxbiclique.enumerate_bicliques(e.edges, a, b, side="u")
    good = cut(overlap.qualify(found.bicliques, a, b))
    want = cut(partial.by_seed(good, found.seeds, a, b))
    visits, wrong = {}, {}
    for tags in (True, False):
        walked = cut(tree.walk_groups(e.edges, a, b, tags))
        visits[tags] = walked.select("group_id", "visited").agg(F.coalesce(F.max("visited"), F.lit(0))).first()[0]
        label = cut(partial.by_tree_walk(e.edges, good, a, b, tags)).select("biclique_id", F.col("label").alias("walked"))
        wrong[tags] = want.join(label, "biclique_id", "full").filter("not (label <=> walked)").count()
    return spark.createDataFrame([(wrong[True], wrong[False], visits[True] <= visits[False])], "tagged_differ long, untagged_differ long, tags_save boolean")


add("tree_bicliques_page_link", tree_bicliques, bicliques_sql("page_link"))
add("tree_violations", tree_violations, "SELECT unnest(['scopes', 'live_marks', 'seeds_above_seeds']) AS what, 0::BIGINT AS n")
for g, a, b in (("nation_brand", 4, 4), ("bench_word", 2, 2), ("user_day", 3, 3)):
    add(f"partial_tree_walk_equals_containment_{g}_{a}_{b}", bound(tree_walk, g, a, b), "SELECT 0::BIGINT AS tagged_differ, 0::BIGINT AS untagged_differ, true AS tags_save")
add("measure_overlap_histogram", lambda s, d: measures.overlap_histogram(found_communities("listing_seeded", "user_day", 3, 3, s, d)), communities_sql("user_day", 3, 3).replace("SELECT least AS community_id, item AS biclique FROM label", "SELECT side, communities, count(*) AS vertices FROM (SELECT side, vertex, count(*) AS communities FROM (SELECT DISTINCT least, 'u' AS side, unnest(x) AS vertex FROM label JOIN b ON item = biclique UNION SELECT DISTINCT least, 'v', unnest(y) FROM label JOIN b ON item = biclique) GROUP BY 1, 2) GROUP BY 1, 2"))

# ---- cohesive subgraphs --------------------------------------------------------------------------------------------


def core_sql(g: str, a: int, b: int) -> str:
    """Peeling as a recursion that keeps every round's edges; the last round is the core."""
    return f"""WITH RECURSIVE {edges_sql(g)}, r(k, edges) AS (
    SELECT 0, list({{'u': u, 'v': v}}) FROM e
    UNION ALL
    SELECT k + 1, kept FROM (SELECT k, edges, (SELECT list({{'u': u, 'v': v}}) FROM (SELECT x.u, x.v, count(*) OVER (PARTITION BY x.u) AS du, count(*) OVER (PARTITION BY x.v) AS dv FROM (SELECT unnest(r.edges) AS x)) WHERE du >= {a} AND dv >= {b}) AS kept FROM r) WHERE kept IS NOT NULL AND len(kept) < len(edges)
), s(n) AS (SELECT len(edges) FROM r ORDER BY k DESC LIMIT 1), last AS (SELECT edges FROM r ORDER BY k DESC LIMIT 1)
, t AS (SELECT unnest(edges) AS x FROM last)
SELECT u, v FROM (SELECT x.u, x.v, count(*) OVER (PARTITION BY x.u) AS du, count(*) OVER (PARTITION BY x.v) AS dv FROM t) WHERE du >= {a} AND dv >= {b}"""


def bitruss_sql(k: int, rounds: int = 8) -> str:
    """Peeling unrolled: rounds beyond the last that drops an edge change nothing."""
    one = """k{j} AS MATERIALIZED (SELECT w.u, w.v FROM (SELECT x.u, y.u AS w, x.v FROM k{i} x JOIN k{i} y ON x.v = y.v AND x.u <> y.u) w
    JOIN (SELECT x.u, y.u AS w, count(*) AS n FROM k{i} x JOIN k{i} y ON x.v = y.v AND x.u <> y.u GROUP BY 1, 2) c ON c.u = w.u AND c.w = w.w GROUP BY 1, 2 HAVING sum(n - 1) >= {k})"""
    return ", ".join(["k0 AS (SELECT u, v FROM e)", *(one.format(i=i, j=i + 1, k=k) for i in range(rounds))]) + f", bitruss AS (SELECT u, v FROM k{rounds})"


def unrolled_core_sql(a: int, b: int, rounds: int = 12) -> str:
    one = "c{j} AS MATERIALIZED (SELECT u, v FROM (SELECT u, v, count(*) OVER (PARTITION BY u) AS du, count(*) OVER (PARTITION BY v) AS dv FROM c{i}) WHERE du >= {a} AND dv >= {b})"
    return ", ".join(["c0 AS (SELECT u, v FROM e)", *(one.format(i=i, j=i + 1, a=a, b=b) for i in range(rounds))]) + f", core AS (SELECT u, v FROM c{rounds})"


def around_sql(edges: str) -> str:
    """The vertices of the component of ``edges`` that holds the query vertex; nothing if it is not there."""
    both = f"(SELECT 'u:' || u AS a, 'v:' || v AS b FROM {edges} UNION ALL SELECT 'v:' || v, 'u:' || u FROM {edges})"
    return f"in_{edges}(x) AS (SELECT DISTINCT 'u:' || u FROM {edges} JOIN query ON u = q UNION SELECT n.b FROM in_{edges} r JOIN {both} n ON n.a = r.x)"


def case_study_sql(g: str, a: int, b: int, k: int) -> str:
    models = {"communities": "in_communities", "bitruss": "in_bitruss", "core": "in_core", "maximum_biclique": "in_best"}
    rows = " UNION ALL ".join(
        f"SELECT '{m}' AS model, (SELECT count(*) FROM {t}) AS vertices, (SELECT count(*) FROM {t} WHERE x IN (SELECT x FROM in_communities)) AS shared, (SELECT count(*) FROM in_communities) AS theirs"
        for m, t in models.items()
    )
    return f"""WITH RECURSIVE {edges_sql(g)}, {BICLIQUES_SQL}, {overlap_sql(a, b)}, {COMPONENTS_SQL},
top AS (SELECT least FROM label GROUP BY 1 ORDER BY count(*) DESC, least LIMIT 1),
query AS MATERIALIZED (SELECT min(list_min(x)) AS q FROM label JOIN b ON item = biclique JOIN top USING (least)),
mine AS (SELECT DISTINCT least FROM label JOIN b ON item = biclique JOIN query ON list_contains(x, q)),
members AS (SELECT x, y FROM label JOIN mine USING (least) JOIN b ON item = biclique),
in_communities(x) AS MATERIALIZED (SELECT DISTINCT 'u:' || unnest(x) FROM members UNION SELECT 'v:' || unnest(y) FROM members),
best AS (SELECT x, y FROM q JOIN query ON list_contains(x, query.q) ORDER BY len(x) * len(y) DESC, biclique LIMIT 1),
in_best(x) AS (SELECT 'u:' || unnest(x) FROM best UNION SELECT 'v:' || unnest(y) FROM best),
{bitruss_sql(k)}, {unrolled_core_sql(b, a)}, {around_sql("bitruss")}, {around_sql("core")}
SELECT model, vertices, shared, vertices = shared AS inside, theirs = shared AS holds FROM ({rows})"""


for g, a, b in (("user_day", 6, 10), ("vec_dim", 3, 10), ("cust_brand", 7, 10)):
    add(f"core_{g}_{a}_{b}", lambda s, d, g=g, a=a, b=b: cohesive.core(texts(GRAPHS[g](s, d)), a, b), core_sql(g, a, b))

BUTTERFLIES_SQL = "SELECT e.u, e.v, coalesce(sum(c.n - 1), 0)::BIGINT AS butterflies FROM e LEFT JOIN (SELECT x.u, x.v, y.u AS w FROM e x JOIN e y ON x.v = y.v AND x.u <> y.u) k ON k.u = e.u AND k.v = e.v LEFT JOIN (SELECT x.u, y.u AS w, count(*) AS n FROM e x JOIN e y ON x.v = y.v AND x.u <> y.u GROUP BY 1, 2) c ON c.u = k.u AND c.w = k.w GROUP BY 1, 2"
add("butterflies_per_edge", lambda s, d: cohesive.butterflies(texts(GRAPHS["user_day"](s, d))), f"WITH {edges_sql('user_day')} {BUTTERFLIES_SQL}")
add("butterfly_total", lambda s, d: cohesive.butterfly_total(texts(GRAPHS["cust_quarter"](s, d))), f"WITH {edges_sql('cust_quarter')} SELECT (sum(butterflies) / 4)::BIGINT AS butterflies FROM ({BUTTERFLIES_SQL})")
for g in ("user_day", "cust_brand"):
    add(f"bitruss_{g}_6", lambda s, d, g=g: cohesive.bitruss(texts(GRAPHS[g](s, d)), 6), f"WITH {edges_sql(g)}, {bitruss_sql(6)} SELECT u, v FROM bitruss")
    add(f"case_study_{g}_3_3", lambda s, d, g=g: measures.case_study(texts(GRAPHS[g](s, d)), 3, 3, 6), case_study_sql(g, 3, 3, 6))


def around(spark: SparkSession, d: str) -> DataFrame:
    """The component around the least page that links somewhere."""
    return cohesive.component_of(texts(GRAPHS["page_link"](spark, d)), "u", "1")


add("component_around_page", around, f"WITH RECURSIVE {edges_sql('page_link')}, query AS (SELECT '1' AS q), {around_sql('e')} SELECT x[1:1] AS side, x[3:] AS vertex FROM in_e")


def swept(spark: SparkSession, d: str) -> DataFrame:
    """The grid of thresholds over one enumeration: communities of each."""
    rows = []
    for (a, b, method), found in communities.sweep(encoded("nation_brand", spark, d), ALPHAS, BETAS, ("listing_seeded",)).items():
        rows.append((a, b, method, found.bicliques.count(), found.labels.select("label").distinct().count()))
    return spark.createDataFrame(rows, "alpha long, beta long, method string, qualified long, communities long")


def swept_sql(g: str) -> str:
    one = "SELECT {a} AS alpha, {b} AS beta, count(*) AS qualified, count(DISTINCT least) AS communities FROM label"
    parts = [f"SELECT * FROM (WITH RECURSIVE {edges_sql(g)}, {BICLIQUES_SQL}, {overlap_sql(a, b)}, {COMPONENTS_SQL} {one.format(a=a, b=b)})" for a in ALPHAS for b in BETAS]
    return f"SELECT alpha, beta, method, qualified, communities FROM ({' UNION ALL '.join(parts)}), (SELECT 'listing_seeded' AS method)"


add("sweep_nation_brand", swept, swept_sql("nation_brand"))

# ---- relational operators around the methods -----------------------------------------------------------------------

for name, (query, sql) in relational.CATALOGUE.items():
    add(f"rel_{name}", query, sql)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Members of the communities of documents that share lines, at (2, 2)."""
    found = detect(encode(GRAPHS["doc_line"](spark, sf_dir)), 2, 2)
    return found.members().orderBy("label", "side", "vertex").withColumn("place", F.row_number().over(Window.partitionBy("label").orderBy("side", "vertex")))

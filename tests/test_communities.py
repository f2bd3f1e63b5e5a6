"""Hand-made graphs, random graphs against brute force, and the inequalities between the methods."""

import itertools
import random
from collections import Counter

import pytest

from bipercolate import communities, graph, listing, local_listing, local_solver, maxbiclique, measures, overlap, partial, tree
from bipercolate.catalogue import size_histogram
from bipercolate.communities import METHODS, detect

CHAIN = [(1, 1), (1, 2), (1, 3), (2, 1), (2, 2), (2, 3), (2, 4), (3, 2), (3, 3), (3, 4)]


def edges(spark, pairs):
    return spark.createDataFrame(pairs, "u long, v long")


def brute_bicliques(pairs):
    nbrs = {}
    for u, v in pairs:
        nbrs.setdefault(u, set()).add(v)
    closed = set(map(frozenset, nbrs.values()))
    while True:
        more = {a & b for a in closed for b in closed if a & b} - closed
        if not more:
            break
        closed |= more
    return {(tuple(sorted(u for u in nbrs if y <= nbrs[u])), tuple(sorted(y))) for y in closed}


def brute_communities(pairs, a, b):
    good = [(set(x), set(y)) for x, y in sorted(brute_bicliques(pairs)) if len(x) >= a and len(y) >= b]
    label = list(range(len(good)))
    changed = True
    while changed:
        changed = False
        for i, j in itertools.combinations(range(len(good)), 2):
            if label[i] != label[j] and len(good[i][0] & good[j][0]) >= a and len(good[i][1] & good[j][1]) >= b:
                lo, hi = sorted((label[i], label[j]))
                label = [lo if k == hi else k for k in label]
                changed = True
    groups = {}
    for k, g in zip(label, good, strict=True):
        groups.setdefault(k, set()).add((tuple(sorted(g[0])), tuple(sorted(g[1]))))
    return {frozenset(g) for g in groups.values()}


def sets(df):
    return {(tuple(r.x), tuple(r.y)) for r in df.collect()}


def partition(found):
    rows = found.labels.join(found.encoded.labels(found.bicliques), "biclique_id").collect()
    groups = {}
    for r in rows:
        groups.setdefault(r.label, set()).add((tuple(sorted(map(int, r.x))), tuple(sorted(map(int, r.y)))))
    return {frozenset(g) for g in groups.values()}


@pytest.mark.parametrize("engine", ["local", "frontier", "closure"])
def test_chain_bicliques(spark, engine):
    found = maxbiclique.enumerate_bicliques(edges(spark, CHAIN), 2, 2, engine)
    assert sets(found.bicliques) == brute_bicliques(CHAIN)
    if engine != "closure":
        assert {(tuple(r.r_u), tuple(r.r_v)) for r in found.seeds.collect()} == {((1, 2), (2, 3)), ((2, 3), (2, 3, 4))}


def test_chain_measures(spark):
    e = graph.encode(graph.simple_edges(edges(spark, CHAIN)))
    assert measures.counts(e, 2, 2) == {"qualified": 3, "basic_groups": 2, "seed_groups": 2, "communities": 1}
    assert listing.count(e.edges, 2, 2).first()[0] == 7
    assert listing.enumerate_ab(e.edges, 2, 2, "v").count() == 7


@pytest.mark.parametrize("method", METHODS)
def test_methods_on_two_chains_with_noise(spark, method):
    pairs = [*CHAIN, *[(u + 10, v + 10) for u, v in CHAIN], *CHAIN, (None, 1), (1, None)]
    found = detect(edges(spark, pairs), 2, 2, method)
    assert partition(found) == brute_communities([p for p in set(pairs) if None not in p], 2, 2)


def test_crown_and_complete(spark):
    crown = [(i, j) for i in range(4) for j in range(4) if i != j]
    assert maxbiclique.enumerate_bicliques(edges(spark, crown)).bicliques.count() == 14
    full = [(i, j) for i in range(3) for j in range(4)]
    assert maxbiclique.enumerate_bicliques(edges(spark, full)).bicliques.count() == 1
    assert detect(edges(spark, full), 3, 4).labels.count() == 1
    assert detect(edges(spark, full), 4, 4).labels.count() == 0


@pytest.mark.parametrize("seed", [1, 2])
def test_random_graph(spark, seed):
    rnd = random.Random(seed)
    pairs = [(i, j) for i in range(8) for j in range(8) if rnd.random() < 0.3 + 0.15 * seed]
    e = graph.encode(graph.simple_edges(edges(spark, pairs)))
    found = maxbiclique.enumerate_bicliques(e.edges, 2, 2)
    assert {(tuple(sorted(map(int, r.x))), tuple(sorted(map(int, r.y)))) for r in e.labels(found.bicliques).collect()} == brute_bicliques(pairs)
    want = brute_communities(pairs, 2, 2)
    for method in METHODS:
        assert partition(detect(e, 2, 2, method)) == want, method
    assert partition(detect(e, 2, 2, "listing_pruned", batches=2, restrict_shared=False)) == want
    for side in ("u", "v"):
        assert partition(detect(e, 2, 2, "listing_pruned", listing_side=side, prune_right_prefix=side == "u")) == want
    assert measures.chain_ok(measures.counts(e, 2, 2))
    good = overlap.qualify(found.bicliques, 2, 2)
    assert {(r.a, r.b) for r in overlap.edges(good, 2, 2).collect()} == {(r.a, r.b) for r in overlap.brute_force_edges(good, 2, 2).collect()}
    left_rooted = maxbiclique.enumerate_bicliques(e.edges, 2, 2, side="u")
    good = overlap.qualify(left_rooted.bicliques, 2, 2)
    grouped = lambda df: {(r.biclique_id, r.label) for r in df.collect()}
    want = grouped(partial.by_seed(good, left_rooted.seeds, 2, 2))
    assert grouped(partial.by_tree_walk(e.edges, good, 2, 2)) == want == grouped(partial.by_tree_walk(e.edges, good, 2, 2, tags=False))
    mixed = maxbiclique.enumerate_bicliques(e.edges, engine="auto", heavy=20)
    assert sets(mixed.bicliques) == sets(left_rooted.bicliques)


def brute_links(rows, alpha, beta):
    """Components of bicliques that share an alpha-by-beta biclique, starting from labels."""
    label = {k: r[0] for k, r in enumerate(rows)}
    for i, j in itertools.combinations(range(len(rows)), 2):
        if len(set(rows[i][1]) & set(rows[j][1])) >= alpha and len(set(rows[i][2]) & set(rows[j][2])) >= beta:
            a, b = label[i], label[j]
            label = {k: a if x == b else x for k, x in label.items()}
    return {frozenset(k for k in label if label[k] == x) for x in label.values()}


@pytest.mark.parametrize(("alpha", "beta"), [(1, 1), (2, 2), (3, 2), (0, 2), (2, 0)])
def test_groups_merge_like_brute_force(alpha, beta):
    rnd = random.Random(alpha * 10 + beta)
    for _ in range(60):
        n = rnd.randint(1, 7)
        rows = [(rnd.randint(0, n), sorted(rnd.sample(range(9), rnd.randint(alpha, 7))), sorted(rnd.sample(range(9), rnd.randint(beta, 7)))) for _ in range(n)]
        for prune, right, restrict in itertools.product((True, False), repeat=3):
            group = local_listing.Group.of(rows)
            links = local_listing.merge_group(group, alpha, beta, prune, right, restrict)
            labels = group.labels
            got = {frozenset(k for k in range(n) if labels.find(labels.of[k]) == x) for x in {labels.find(y) for y in labels.of}}
            assert got == brute_links(rows, alpha, beta)
            assert len(links) == len(set(labels.of)) - len(got)
        pruned, plain = local_listing.Group.of(rows), local_listing.Group.of(rows)
        local_listing.merge_group(pruned, alpha, beta)
        local_listing.merge_group(plain, alpha, beta, prune=False)
        count = lambda t: t.prefixes + t.rights + t.leaves
        assert count(pruned.tally) <= count(plain.tally)


def test_heavy_groups_are_shared_out(spark):
    rnd = random.Random(8)
    pairs = [(i, j) for i in range(9) for j in range(9) if rnd.random() < 0.6]
    e = graph.encode(graph.simple_edges(edges(spark, pairs)))
    good = maxbiclique.enumerate_bicliques(e.edges, 2, 2, qualified_only=True).bicliques
    start = partial.singletons(good)
    want = {(r.biclique_id, r.label) for r in listing.merge_by_listing(good, 2, 2, start, prune=False).collect()}
    for heavy, prune in ((0, True), (0, False), (30, True)):
        assert {(r.biclique_id, r.label) for r in listing.merge_by_listing(good, 2, 2, start, prune=prune, heavy=heavy, side="u").collect()} == want
    leaves = {}
    listing.merge_by_listing(good, 2, 2, start, prune=False, tally=lambda k, n: leaves.__setitem__(k, n))
    assert leaves["leaf"] == listing.count(e.edges, 2, 2).first()[0]


def test_tree_of_the_chain(spark):
    """The three left vertices in both orders of roots; seeds and groups by hand."""
    for rename, seeds in (({1: 1, 2: 2, 3: 3}, {((1, 2), (2, 3)), ((2, 3), (2, 3, 4))}), ({3: 1, 2: 2, 1: 3}, {((1, 2), (2, 3)), ((2, 3), (1, 2, 3))})):
        e = edges(spark, [(rename[u], v) for u, v in CHAIN])
        nodes = tree.build(e, 2, 2)
        rows = {r.node_id: r for r in nodes.collect()}
        assert {(tuple(sorted(r.r_u)), tuple(sorted(r.r_v))) for r in rows.values() if r.seed and r.live} == seeds
        assert {(tuple(sorted(r.r_u)), tuple(sorted(r.r_v))) for r in rows.values() if r.biclique} == brute_bicliques([(rename[u], v) for u, v in CHAIN])
        assert {r.node_id: r.live for r in tree.mark_live(nodes).collect()} == {k: r.live for k, r in rows.items()}
        for r in tree.scope(nodes).collect():
            nbrs = [{u for u, v in e.collect() if v == w} for w in r.r_v]
            assert not nbrs or set(r.s_u) == set.intersection(*nbrs)
        groups = {}
        for r in tree.walk_groups(e, 2, 2).collect():
            groups.setdefault(r.group_id, set()).add((tuple(r.x), tuple(r.y)))
        assert len(groups) == 2 and sum(map(len, groups.values())) == 3
    with pytest.raises(listing.BudgetExceeded):
        tree.walk_groups(e, 2, 2, most_nodes=2)


def test_plain_tree_has_a_budget(spark):
    star = edges(spark, [(k, 1) for k in range(30)])
    with pytest.raises(Exception, match="more than 1000 nodes"):
        maxbiclique.enumerate_bicliques(star, pivot="none", side="u", budget=1000)
    assert maxbiclique.enumerate_bicliques(star, side="u", budget=1000).bicliques.count() == 1


def test_errors_and_empty(spark):
    e = edges(spark, CHAIN)
    with pytest.raises(ValueError):
        detect(e, 0, 2)
    with pytest.raises(ValueError):
        detect(e, 2, 2, "other")
    with pytest.raises(ValueError):
        detect(e, 2, 2, u="nothing")
    empty = detect(edges(spark, []), 2, 2)
    assert empty.keyed().count() == 0 and empty.members().count() == 0
    with pytest.raises(listing.BudgetExceeded):
        listing.keys_from_bicliques(maxbiclique.enumerate_bicliques(e).bicliques, 1, 1, budget=2)


def test_same_labels_on_both_sides(spark):
    found = detect(spark.createDataFrame([("a", "a"), ("a", "b"), ("b", "a"), ("b", "b")], "u string, v string"), 2, 2)
    assert sorted(map(tuple, found.keyed().collect())) == [("a,b|a,b", "a,b|a,b")]
    assert found.containing("v", "b").count() == 1 and found.containing("v", "z").count() == 0


def test_community_edges_lie_in_core_and_bitruss(spark):
    from bipercolate import cohesive

    rnd = random.Random(9)
    pairs = [(i, j) for i in range(10) for j in range(10) if rnd.random() < 0.6]
    e = graph.encode(graph.simple_edges(edges(spark, pairs)))
    found = detect(e, 3, 3)
    inside = {(r.u, r.v) for r in communities.community_edges(found, 2).collect()}
    assert inside and inside <= {tuple(r) for r in cohesive.core(e.edges, 3, 3).collect()} & {tuple(r) for r in cohesive.bitruss(e.edges, 6).collect()}


def test_two_hop_degree_of_twins(spark):
    """Left vertices with the same neighbours, right ones with the same, private neighbours and lone vertices."""
    pairs = [*CHAIN, *[(u + 10, v) for u, v in CHAIN], *[(u, v + 20) for u, v in CHAIN if v == 2], (1, 90), (50, 91), (51, 92), (52, 92), (52, 93)]
    nbrs = {}
    for u, v in pairs:
        nbrs.setdefault(u, set()).add(v)
    want = {u: sum(1 for w in nbrs if w != u and nbrs[w] & nbrs[u]) for u in nbrs}
    assert {r.u: r.degree for r in graph.two_hop_degree(edges(spark, pairs)).collect()} == want


def test_two_hop_degree_makes_no_pairs_of_twins(spark):
    """40,000 left vertices below one right vertex: 1.6e9 pairs, one class."""
    many = spark.range(40_000).selectExpr("id as u", "explode(array(1L, 2L)) as v")
    assert graph.two_hop_degree(many).groupBy("degree").count().collect() == [(39_999, 40_000)]


@pytest.mark.parametrize("method", ["seed_merge", "listing"])
def test_communities_of_twins(spark, method):
    """Classes of one to four twins on both sides, below and above the thresholds."""
    rnd = random.Random(7)
    small = [(i, j) for i in range(6) for j in range(6) if rnd.random() < 0.45]
    pairs = [(10 * i + k, 10 * j + m) for i, j in small for k in range(1 + i % 4) for m in range(1 + j % 3)]
    found = detect(edges(spark, pairs), 3, 2, method)
    assert partition(found) == brute_communities(pairs, 3, 2)
    held = {(r.label, r.side, int(r.vertex)) for r in found.members().collect()}
    rows = found.labels.join(found.encoded.labels(found.bicliques), "biclique_id").collect()
    assert held == {(r.label, s, int(w)) for r in rows for s, ws in (("u", r.x), ("v", r.y)) for w in ws}
    assert {r.biclique for r in found.keyed().collect()} == {"|".join(",".join(ws) for ws in (r.x, r.y)) for r in rows}


def test_thinned_keeps_few_twins(spark):
    full = spark.range(500).selectExpr("id as u", "explode(array(1L, 2L, 3L, 4L, 5L)) as v")
    thin = graph.thinned(full, 3, 2)
    assert thin.edges.count() == 6
    assert detect(full, 3, 2, "listing").members().groupBy("side").count().collect() == [("u", 500), ("v", 5)]


def test_size_histogram_of_twins(spark):
    """Enumerated over one vertex a class, counted over all."""
    pairs = [(10 * u + k, 10 * v + m) for u, v in CHAIN for k in range(u) for m in range(v % 2 + 1)]
    want = Counter((len(x), len(y)) for x, y in brute_bicliques(pairs))
    assert {(r.n_x, r.n_y): r.bicliques for r in size_histogram(edges(spark, pairs)).collect()} == want


def test_case_study_of_twins(spark):
    """Communities around a vertex hold its twins."""
    pairs = [(u + 10 * k, v) for u, v in CHAIN for k in range(4)]
    rows = {r.model: r for r in measures.case_study(edges(spark, pairs), 2, 2, 1, "1").collect()}
    assert (rows["communities"].vertices, rows["maximum_biclique"].inside) == (16, True)


@pytest.mark.parametrize(("at_once", "bound"), [(1, 0), (1, 1_000_000), (1_000_000, 0)])
def test_vertices_that_share_enough_are_counted_in_rounds(spark, at_once, bound):
    rng = random.Random(5)
    pairs = sorted({(rng.randrange(1, 16), rng.randrange(1, 13)) for _ in range(90)})
    nbrs = {u: {v for w, v in pairs if w == u} for u, _ in pairs}
    want = sorted((a, b, v) for a in nbrs for b in nbrs if a != b and len(nbrs[a] & nbrs[b]) >= 3 for v in nbrs[a] & nbrs[b])
    found = sorted(map(tuple, maxbiclique._near(edges(spark, pairs), 3, at_once, bound).collect()))
    assert want and found == want
    whole = {r.root: sorted((p.w, p.v) for p in r.pairs) for r in maxbiclique.neighbourhoods(edges(spark, pairs), 3).collect()}
    assert whole == {a: sorted([(a, v) for v in nbrs[a]] + [(b, v) for x, b, v in want if x == a]) for a in nbrs}


def test_postings_of_the_side_that_can_only_make_more_pairs_are_not_written(spark, monkeypatch):
    made = []
    postings = overlap._postings
    monkeypatch.setattr(overlap, "_postings", lambda b, least, prefix, sets="x": made.append(sets) or postings(b, least, prefix, sets))
    rows = [(i, list(range(9 * i, 9 * i + 9)), [i], 9, 1) for i in range(8)]
    b = spark.createDataFrame(rows, "biclique_id long, x array<long>, y array<long>, n_x int, n_y int")
    assert overlap.rarer_postings(b, 2, 1).count() == 8 and made == ["y"]


@pytest.mark.parametrize(("at_once", "block", "block_edges"), [(1, 7, 40), (1, 1000, 1000), (1, 1, 1), (100, 1000, 30), (10**6, 7, 40)])
def test_two_hop_weights_in_blocks_and_rounds(spark, monkeypatch, at_once, block, block_edges):
    """Dense graphs go by blocks of bit sets (long and short lists), others in rounds; weights count once however many neighbours are shared."""
    monkeypatch.setattr(graph, "LONG_LIST", 4)
    rng = random.Random(3)
    pairs = sorted({(rng.randrange(1, 60), rng.randrange(1, 12) ** 2) for _ in range(300)} | {(1000, 5000)})
    n = {u: rng.randrange(1, 70) for u, _ in pairs}
    nbrs = {u: {v for w, v in pairs if w == u} for u in n}
    want = {u: sum(n[w] for w in n if nbrs[u] & nbrs[w]) for u in n}
    rows = spark.createDataFrame([(u, v, n[u]) for u, v in pairs], "u long, v long, n long")
    assert {r.u: r.weight for r in graph.two_hop_weights(rows, at_once, block, block_edges).collect()} == want
    assert {r.u: r.weight for r in graph._by_blocks(rows, 3, 2).collect()} == want


def test_dense_graphs_make_no_two_hop_pairs(spark):
    """600 left vertices of 5 out of 8 right ones would make 140,000 pairs a right vertex."""
    rows = spark.range(600).selectExpr("id as u", "explode(sequence(id % 4, id % 4 + 4)) as v", "1L as n")
    found = graph.two_hop_weights(rows, 10_000)
    assert "FlatMapCoGroups" in found._jdf.queryExecution().toString()
    assert {r.weight for r in found.collect()} == {600}


def test_chains_taken_at_once_change_nothing():
    """A traced tree takes forced vertices one by one: the same bicliques, seeds and number of nodes, also where pivots are sought on arrays."""
    rng = random.Random(2)
    for n_u, n_v in ((7, 60), (60, 7), (9, 9)):
        pairs = [(u, v) for u in range(n_u) for v in range(n_v) if rng.random() < 0.5]
        nbrs = {u: {v for w, v in pairs if w == u} for u, _ in pairs}
        for root in list(nbrs)[:3]:
            ego = local_solver.Ego.of(root, [(w, v) for w in nbrs for v in nbrs[w] & nbrs[root]])
            for alpha, beta in ((1, 1), (2, 3)):
                counts, nodes = {}, []
                rows = lambda **more: [(f.kind, f.x, f.y, f.seed) for f in local_solver.enumerate_root(ego, alpha, beta, **more)]  # noqa: B023, E731
                assert rows(counts=counts) == rows(trace=nodes.append) and counts["nodes"] == len(nodes)


@pytest.mark.parametrize("prefix", [True, False])
def test_overlaps_are_tested_where_postings_meet(spark, monkeypatch, prefix):
    """Labels by rounds of postings are the components of the pairs that brute force finds; no plan joins bicliques with each other."""
    monkeypatch.setattr(overlap, "ELEMENTS_AT_ONCE", 150)
    monkeypatch.setattr(overlap, "edges", None)
    rng = random.Random(7)
    sets = [(i, sorted(rng.sample(range(20), rng.randrange(2, 6))), sorted(rng.sample(range(100, 112), rng.randrange(2, 5)))) for i in range(60)]
    b = spark.createDataFrame([(i, x, y, len(x), len(y)) for i, x, y in sets], "biclique_id long, x array<long>, y array<long>, n_x int, n_y int")
    want = {i: i for i, _, _ in sets}
    for (i, x, y), (j, s, t) in itertools.combinations(sets, 2):
        if len(set(x) & set(s)) >= 2 and len(set(y) & set(t)) >= 2:
            lo, hi = sorted((want[i], want[j]))
            want = {k: lo if w == hi else w for k, w in want.items()}
    found = {r.biclique_id: r.label for r in communities.by_overlap(b, 2, 2, prefix=prefix).collect()}
    assert found == want
    assert 1 < len(set(want.values())) < 60


def test_labels_by_arrays_and_by_joins(spark):
    """An id may stand for several labels; both ways name sets alike, in batches of few labels too."""
    u = spark.createDataFrame([(1, "b"), (1, "a"), (2, "ä"), (5, "10"), (5, "9")], "id long, label string")
    v = spark.createDataFrame([(3, "z"), (4, "y")], "id long, label string")
    sets = spark.createDataFrame([(7, [1, 2], [3]), (8, [5], [3, 4]), (9, [1, 2, 5], [4])], "biclique_id long, x array<long>, y array<long>")
    want = [(7, ["a", "b", "ä"], ["z"]), (8, ["10", "9"], ["y", "z"]), (9, ["10", "9", "a", "b", "ä"], ["y"])]
    one = graph.Encoded(sets, u, v)
    for found in (one.labels(sets), one.labels(sets, most_chars=0), one.labels(sets, 0, 0)):
        assert sorted(map(tuple, found.collect())) == want


@pytest.mark.parametrize("at_once", [40, 10**6])
def test_groups_around_seeds_by_rounds(spark, monkeypatch, at_once):
    """Bicliques that contain a seed get one label, wherever rounds cut; no pair of seed and biclique leaves a task."""
    monkeypatch.setattr(partial, "ELEMENTS_AT_ONCE", at_once)
    rng = random.Random(11)
    sets = [(i, sorted(rng.sample(range(9), rng.randrange(2, 6))), sorted(rng.sample(range(100, 130), rng.randrange(2, 9)))) for i in range(80)]
    seeds = [(sorted(rng.sample(x, 2)), sorted(rng.sample(y, 2))) for _, x, y in sets[::3]] + [([1, 50], [100])]
    b = spark.createDataFrame([(i, x, y, len(x), len(y)) for i, x, y in sets], "biclique_id long, x array<long>, y array<long>, n_x int, n_y int")
    want = {i: i for i, _, _ in sets}
    for x, y in seeds:
        held = {want[i] for i, s, t in sets if set(x) <= set(s) and set(y) <= set(t)}
        want = {k: min(held) if w in held else w for k, w in want.items()}
    found = partial.by_seed(b, spark.createDataFrame(seeds, "r_u array<long>, r_v array<long>"), 2, 2)
    assert {r.biclique_id: r.label for r in found.collect()} == want
    assert len(set(want.values())) < 80

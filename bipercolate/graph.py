"""Bipartite graphs as edge tables: cleaning, dense ids, adjacency, the 2-hop graph, statistics, samples.

An edge table has one column per side. The two sides are different columns, so equal values on both sides never meet.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import ceil

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bipercolate.checkpoints import cut, scratch
from bipercolate.operators.joins import BROADCAST_IDS

#: Pairs of vertices that share a neighbour that one round makes; graphs of more edges make as many as they have edges.
PAIRS_AT_ONCE = 20_000_000
#: Vertices of one block of bit sets, and edges of one block or of one chunk of roots.
BLOCK, BLOCK_EDGES = 65_536, 1_000_000
#: Vertices of a block from which a neighbour list is kept as a bit set.
LONG_LIST = 256
#: Characters of a dictionary of labels that goes to Python workers as an array, and labels that one batch of theirs gives at once.
MOST_CHARS, LABELS_AT_ONCE = 32_000_000, 1_000_000


def check_thresholds(alpha: int, beta: int) -> None:
    for name, value in (("alpha", alpha), ("beta", beta)):
        if isinstance(value, bool) or not isinstance(value, int) or value < 1:
            raise ValueError(f"{name} must be an integer of at least 1, not {value!r}")


def simple_edges(df: DataFrame, u: str = "u", v: str = "v") -> DataFrame:
    """Distinct edges ``[u, v]``; null ends are dropped."""
    for name in (u, v):
        if name not in df.columns:
            raise ValueError(f"no column {name!r}; there are {df.columns}")
    return df.select(F.col(u).alias("u"), F.col(v).alias("v")).filter("u is not null and v is not null").distinct()


def dense_ids(df: DataFrame, *order: str) -> DataFrame:
    """Add ``id``: 1, 2, 3, ... in the order of the columns, by a range sort and per-partition offsets (never in one task)."""
    part = cut(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__part", F.spark_partition_id()))
    sizes = part.groupBy("__part").count()
    before = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("__part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("__before"))  # one row per partition
    inside = F.row_number().over(Window.partitionBy("__part").orderBy(*order))
    return part.withColumn("__row", inside).join(F.broadcast(offsets), "__part").withColumn("id", (F.col("__before") + F.col("__row")).cast("long")).drop("__part", "__row", "__before")


def two_hop_pairs(edges: DataFrame) -> DataFrame:
    """Ordered pairs (u, w) of different left vertices that share a neighbour, with the number of shared ones."""
    other = edges.select(F.col("u").alias("w"), "v")
    return edges.join(other, "v").filter("u <> w").groupBy("u", "w").agg(F.count("*").alias("shared"))


def two_hop(edges: DataFrame, least_shared: int = 1) -> DataFrame:
    """The 2-hop graph: u < w that share at least ``least_shared`` neighbours."""
    other = edges.select(F.col("u").alias("w"), "v")
    return edges.join(other, "v").filter("u < w").groupBy("u", "w").agg(F.count("*").alias("shared")).filter(F.col("shared") >= least_shared).select("u", "w")


def _fingerprint(column: str) -> list:
    """Aggregates that tell sets of distinct values apart: their number, and 128 bits of hashes."""
    return [F.count("*").alias("k"), *(F.bit_xor(F.xxhash64(column, F.lit(n))).alias(f"f{n}") for n in (1, 2))]


def twins(edges: DataFrame, side: str = "u") -> DataFrame:
    """``[vertex, rep, n]``: vertices of one side with the same neighbours are one class of n, named after its least vertex.

    A class is told by a fingerprint, so that no neighbour list is gathered.
    """
    marks = ("k", "f1", "f2")
    own = cut(edges.groupBy(F.col(side).alias("vertex")).agg(*_fingerprint("v" if side == "u" else "u")))
    classes = own.groupBy(*marks).agg(F.min("vertex").alias("rep"), F.count("*").alias("n"))
    return own.join(classes, list(marks)).select("vertex", "rep", "n")


def two_hop_weights(edges: DataFrame, at_once: int = PAIRS_AT_ONCE, block: int = BLOCK, block_edges: int = BLOCK_EDGES) -> DataFrame:
    """``[u, weight]`` over edges ``[u, v, n]`` (numbers): the sum of n, the weight of a left vertex, over all that share a neighbour with u, itself included.

    Up to ``at_once`` pairs (or as many as edges) are made at once, more of them in rounds of roots. Where that makes more rows than sending the
    edges to blocks does, every chunk of roots meets every block of vertices in one task, as bit sets: no pair is written.
    """
    squares, m = edges.groupBy("v").agg(F.count("*").cast("double").alias("d")).agg(F.coalesce(F.sum(F.col("d") * F.col("d")), F.lit(0.0)), F.coalesce(F.sum("d"), F.lit(0.0))).first()
    if squares > max(at_once, m):
        blocks = max(ceil(edges.select("u").distinct().count() / block), ceil(m / block_edges))
        chunks = max(ceil(m / block_edges), ceil(edges.sparkSession.sparkContext.defaultParallelism / blocks))
        if m * (blocks + chunks) < squares:
            return _by_blocks(edges, blocks, chunks)
    rounds = max(1, ceil(squares / max(at_once, m)))
    other = edges.select(F.col("u").alias("w"), "v", "n")
    out = None
    for k in range(rounds):
        own = edges.select("u", "v")
        own = own if rounds == 1 else own.filter(F.pmod(F.xxhash64("u"), F.lit(rounds)) == k)
        one = own.join(other, "v").select("u", "w", "n").distinct().groupBy("u").agg(F.sum("n").alias("weight"))
        one = one if rounds == 1 else cut(one)
        out = one if out is None else out.union(one)
    return out


def _by_blocks(edges: DataFrame, blocks: int, chunks: int) -> DataFrame:
    each = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    roots = edges.groupBy("u").agg(F.collect_list("v").alias("vs")).withColumn("i", F.pmod(F.xxhash64("u"), F.lit(chunks)).cast("int")).withColumn("j", each(blocks))
    near = edges.withColumn("j", F.pmod(F.xxhash64(F.lit(1), "u"), F.lit(blocks)).cast("int")).groupBy("j", "v")
    near = near.agg(F.collect_list(F.struct("u", "n")).alias("l")).select("j", "v", F.col("l.u").alias("ws"), F.col("l.n").alias("ns")).withColumn("i", each(chunks))
    found = roots.groupBy("i", "j").cogroup(near.groupBy("i", "j")).applyInArrow(_weights_in_block, "u long, weight long")
    return found.groupBy("u").agg(F.sum("weight").alias("weight"))


def _flat(lists: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The values of a column of lists, and where each list begins and ends."""
    one = lists.combine_chunks()
    ends = np.concatenate([[0], np.cumsum(one.value_lengths().to_numpy())]).astype(np.int64)
    return one.flatten().to_numpy(), ends


def _weights_in_block(roots: pa.Table, near: pa.Table) -> pa.Table:
    """Per root, the weight of the block's vertices that share a neighbour with it."""
    if not roots.num_rows or not near.num_rows:
        return pa.table({"u": pa.array([], pa.int64()), "weight": pa.array([], pa.int64())})
    ws, ends = _flat(near["ws"])
    names, places = np.unique(ws, return_inverse=True)
    weights = np.zeros(len(names), np.int64)
    weights[places] = _flat(near["ns"])[0]
    width = -(-len(names) // 64) * 64
    packed = lambda flags: np.packbits(flags, axis=-1).view(np.uint64)
    digits = np.zeros((int(weights.max()).bit_length(), width), bool)
    for k in range(len(digits)):
        digits[k, : len(names)] = weights >> k & 1
    digits, values = packed(digits), 1 << np.arange(len(digits), dtype=np.int64)

    vs = near["v"].to_numpy()
    order = np.argsort(vs)
    rows, row_of = [], np.full(len(vs), -1)
    for k in np.flatnonzero(np.diff(ends) >= LONG_LIST):
        flags = np.zeros(width, bool)
        flags[places[ends[k] : ends[k + 1]]] = True
        row_of[k] = len(rows)
        rows.append(packed(flags))
    matrix = np.array(rows, np.uint64).reshape(len(rows), width // 64)

    wanted, bounds = _flat(roots["vs"])
    at = np.minimum(np.searchsorted(vs, wanted, sorter=order), len(vs) - 1)
    at = np.where(vs[order[at]] == wanted, order[at], -1)
    out = np.zeros(roots.num_rows, np.int64)
    for r in range(roots.num_rows):
        mine = at[bounds[r] : bounds[r + 1]]
        mine = mine[mine >= 0]
        long = row_of[mine]
        short = [places[ends[k] : ends[k + 1]] for k in mine[long < 0]]
        long = long[long >= 0]
        if not len(long):
            out[r] = weights[np.unique(np.concatenate(short))].sum() if short else 0
            continue
        union = np.bitwise_or.reduce(matrix[long], axis=0)
        if short:
            flags = np.zeros(width, bool)
            flags[np.concatenate(short)] = True
            union = union | packed(flags)
        out[r] = (np.bitwise_count(union & digits).sum(axis=1, dtype=np.int64) * values).sum()
    return pa.table({"u": roots["u"].combine_chunks(), "weight": pa.array(out, pa.int64())})


def two_hop_degree(edges: DataFrame) -> DataFrame:
    """``[u, degree]``: how many other left vertices share a neighbour with u.

    Pairs are made of classes: left vertices with the same shared neighbours have the same degree, and of right vertices with the same
    left ones one is enough. Vertices are 64-bit hashes, as labels may be long; two labels of one hash would share a degree, which only orders roots.
    """
    slim = edges.select(F.xxhash64("u").alias("u"), F.xxhash64("v").alias("v"))
    shared = slim.groupBy("v").agg(F.count("*").alias("d")).filter("d > 1").select("v")
    slim = cut(slim.join(shared, "v").select("u", "v"))
    left = cut(twins(slim, "u"))
    small = cut(slim.join(left.filter("vertex = rep").select(F.col("vertex").alias("u"), "n"), "u"))
    right = twins(small, "v").filter("vertex = rep").select(F.col("vertex").alias("v"))
    small = cut(small.join(right, "v").select("u", "v", "n"))
    found = two_hop_weights(small).select(F.col("u").alias("rep"), (F.col("weight") - 1).alias("degree"))
    found = left.join(found, "rep").select(F.col("vertex").alias("h"), "degree")
    every = edges.select("u").distinct().withColumn("h", F.xxhash64("u"))
    return every.join(found, "h", "left").select("u", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))


def _named(sets: DataFrame, *words: pa.Table) -> DataFrame:
    """``sets`` [biclique_id, x, y] with the sorted labels of the ids on each side, by dictionaries [id, label] in which an id may have several."""
    context, known = sets.sparkSession.sparkContext, []
    for table in words:
        rank = np.argsort(np.array(pc.sort_indices(table["label"])))  # place among all sorted labels
        ids = table["id"].to_numpy()
        order = np.argsort(ids, kind="stable")
        names, start, size = np.unique(ids[order], return_index=True, return_counts=True)
        known.append((names, start, size, rank[order], table["label"].combine_chunks().take(pc.sort_indices(table["label"]))))
    sent = context.broadcast(known)
    kinds = pa.schema([("biclique_id", pa.int64()), ("x", pa.list_(pa.string())), ("y", pa.list_(pa.string()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sides = [_places(batch.column(name), *one[:3]) for name, one in zip(("x", "y"), sent.value, strict=True)]
            grown = np.cumsum(sum(np.bincount(row, size, batch.num_rows) for _, size, row in sides))
            cuts = np.unique(np.searchsorted(grown, np.arange(0, grown[-1] if len(grown) else 0, LABELS_AT_ONCE)))
            for lo, hi in zip(cuts, [*cuts[1:], batch.num_rows], strict=True):
                columns = [_lists(start, size, row, lo, hi, one[3], one[4]) for (start, size, row), one in zip(sides, sent.value, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("biclique_id")[lo:hi], *columns], schema=kinds)

    return sets.mapInArrow(run, "biclique_id long, x array<string>, y array<string>")


def _places(lists: pa.Array, names: np.ndarray, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per id of the lists: where its labels begin, how many they are, and its list."""
    flat = lists.flatten().to_numpy()
    at = np.searchsorted(names, flat)
    return start[at], size[at], np.repeat(np.arange(len(lists)), lists.value_lengths().to_numpy())


def _lists(start: np.ndarray, size: np.ndarray, row: np.ndarray, lo: int, hi: int, rank: np.ndarray, labels: pa.Array) -> pa.Array:
    a, b = np.searchsorted(row, [lo, hi])
    start, size, row = start[a:b], size[a:b], row[a:b] - lo
    ranks = rank[np.arange(size.sum()) + np.repeat(start - (np.cumsum(size) - size), size)]
    row = np.repeat(row, size)
    ends = np.concatenate([[0], np.cumsum(np.bincount(row, minlength=hi - lo))])
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), labels.take(pa.array(ranks[np.lexsort((ranks, row))])))


@dataclass
class Encoded:
    """Edges over dense long ids (from 1 on each side) and the dictionaries ``[id, label]``."""

    edges: DataFrame
    u: DataFrame
    v: DataFrame

    def labels(self, sets: DataFrame, bound: int = BROADCAST_IDS, most_chars: int = MOST_CHARS) -> DataFrame:
        """``x`` and ``y`` of ``sets`` (with biclique_id) turned from ids into sorted arrays of label strings.

        Short dictionaries go to the sets where these are, as arrays; others of up to ``bound`` rows go to the sets once they are dealt by
        biclique, so that no label is shuffled.
        """
        words = [w.select("id", F.col("label").cast("string").alias("label")) for w in (self.u, self.v)]
        if all(w.agg(F.coalesce(F.sum(F.length("label") + 16), F.lit(0))).first()[0] <= most_chars for w in words):
            return _named(sets.select("biclique_id", "x", "y"), *(w.toArrow() for w in words))
        sets = sets.select("biclique_id", "x", "y").repartition("biclique_id")
        out = sets.select("biclique_id")
        for name, words in (("x", self.u), ("y", self.v)):
            few = words.limit(bound + 1).count() <= bound
            rows = sets.select("biclique_id", F.explode(name).alias("id")).join(F.broadcast(words) if few else words, "id")
            one = rows.groupBy("biclique_id").agg(F.array_sort(F.collect_list(F.col("label").cast("string"))).alias(name))
            out = out.join(one, "biclique_id")
        return out


def encode(edges: DataFrame, order: str = "two_hop_degree") -> Encoded:
    """Dense ids per side; left ids follow the 2-hop degree (ties by label), or the label alone with ``order="id"``.

    With ``order="roots"`` the degree is only measured where left vertices are the cheaper roots; else their order matters to nothing.
    """
    with scratch() as keep:
        edges = cut(edges)
        if order == "roots":
            order = "two_hop_degree" if cheaper_side(edges) == "u" else "id"
        if order == "two_hop_degree":
            left = dense_ids(two_hop_degree(edges).select(F.col("u").alias("label"), "degree"), "degree", "label").drop("degree")
        elif order == "id":
            left = dense_ids(edges.select(F.col("u").alias("label")).distinct(), "label")
        else:
            raise ValueError(f"unknown order {order!r}")
        right = dense_ids(edges.select(F.col("v").alias("label")).distinct(), "label")
        left, right = keep(cut(left.select("id", "label"))), keep(cut(right.select("id", "label")))
        a, b = left.select(F.col("id").alias("ui"), F.col("label").alias("u")), right.select(F.col("id").alias("vi"), F.col("label").alias("v"))
        return Encoded(keep(cut(edges.join(a, "u").join(b, "v").select(F.col("ui").alias("u"), F.col("vi").alias("v")))), left, right)


@dataclass
class Thinned:
    """``edges`` with few twins (None once they are deleted); ``u`` and ``v`` [id, vertex, n] give the vertices of each class, n in number."""

    edges: DataFrame | None
    u: DataFrame
    v: DataFrame
    alpha: int
    beta: int

    def _classes(self, sets: DataFrame) -> DataFrame:
        one = lambda name, k: F.array_distinct(F.transform(name, lambda w: F.call_function("div", w, F.lit(k)))).alias(name)
        rest = [c for c in sets.columns if c not in ("x", "y", "n_x", "n_y")]
        return sets.select(*rest, one("x", self.alpha), one("y", self.beta))

    def labels(self, sets: DataFrame, graph: Encoded) -> DataFrame:
        """As ``Encoded.labels`` of the whole sets."""
        words = [m.join(w.withColumnRenamed("id", "vertex"), "vertex").select("id", "label") for m, w in ((self.u, graph.u), (self.v, graph.v))]
        return Encoded(self.edges, *words).labels(self._classes(sets))

    def vertices(self, rows: DataFrame, side: str, key: str) -> DataFrame:
        """``[key, id]``: all vertices of one side in the sets of each key, once."""
        name, members = ("x", self.u) if side == "u" else ("y", self.v)
        return self._classes(rows).select(key, F.explode(name).alias("id")).distinct().join(members, "id").select(key, F.col("vertex").alias("id"))

    def sizes(self, sets: DataFrame) -> DataFrame:
        """``[biclique_id, n_x, n_y]``: how many vertices the whole sets have, counted by class."""
        classes = self._classes(sets)
        out = classes.select("biclique_id")
        for name, members, n in (("x", self.u, "n_x"), ("y", self.v, "n_y")):
            per = members.groupBy("id").agg(F.count("*").alias("n"))
            one = classes.select("biclique_id", F.explode(name).alias("id")).join(per, "id").groupBy("biclique_id").agg(F.sum("n").alias(n))
            out = out.join(one, "biclique_id")
        return out

    def whole(self, sets: DataFrame) -> DataFrame:
        """Sets over ``edges`` with all vertices, and their sizes."""
        classes = self._classes(sets)
        rest = classes.drop("x", "y")
        for name, members in (("x", self.u), ("y", self.v)):
            one = classes.select("biclique_id", F.explode(name).alias("id")).join(members, "id")
            rest = rest.join(one.groupBy("biclique_id").agg(F.array_sort(F.collect_list("vertex")).alias(name)), "biclique_id")
        return rest.withColumns({"n_x": F.size("x"), "n_y": F.size("y")}).select(*sets.columns)


def thinned(edges: DataFrame, alpha: int = 1, beta: int = 1) -> Thinned:
    """At most alpha of the left vertices that have the same neighbours, then at most beta such right ones.

    A maximal biclique holds all twins of a class or none, and a class adds up to alpha (or beta) as soon as so many of it do. So
    the maximal bicliques, those of at least these sizes, and which of them share so many vertices stay the same. The k-th twin kept of a class has the id class * alpha + k.
    """
    with scratch() as keep:
        left = keep(cut(twins(edges, "u").withColumnRenamed("rep", "id")))
        small = cut(edges.join(left.filter("vertex = id").select(F.col("vertex").alias("u"), F.col("n").alias("nu")), "u"))
        right = keep(cut(twins(small, "v").withColumnRenamed("rep", "id")))
        small = small.join(right.filter("vertex = id").select(F.col("vertex").alias("v"), F.col("n").alias("nv")), "v")
        for name, n, most in (("u", "nu", alpha), ("v", "nv", beta)):
            copies = F.explode(F.sequence(F.lit(0).cast("long"), F.least(F.col(n), F.lit(most)) - 1))
            small = small.withColumn("k", copies).withColumn(name, F.col(name) * most + F.col("k")).drop("k")
        return Thinned(keep(cut(small.select("u", "v"))), left, right, alpha, beta)


def adjacency(edges: DataFrame, side: str = "u") -> DataFrame:
    """``[vertex, nbrs]`` of one side, neighbours sorted."""
    other = "v" if side == "u" else "u"
    return edges.groupBy(F.col(side).alias("vertex")).agg(F.array_sort(F.collect_set(other)).alias("nbrs"))


def swapped(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("v").alias("u"), F.col("u").alias("v"))


def cheaper_side(edges: DataFrame) -> str:
    """The side whose 2-hop join is smaller: pairs of left vertices come from the neighbours of each right vertex."""
    squares = lambda side: edges.groupBy(side).agg(F.count("*").alias("d")).agg(F.coalesce(F.sum(F.col("d") * F.col("d")), F.lit(0))).first()[0]
    return "u" if squares("v") <= squares("u") else "v"


def stats(edges: DataFrame) -> DataFrame:
    """One row: vertices of either side, edges, mean degrees."""
    return edges.agg(F.countDistinct("u").alias("n_u"), F.countDistinct("v").alias("n_v"), F.count("*").alias("n_edges")).withColumns({"mean_degree_u": F.col("n_edges") / F.col("n_u"), "mean_degree_v": F.col("n_edges") / F.col("n_v")})


def degree_histogram(edges: DataFrame, side: str = "u") -> DataFrame:
    return edges.groupBy(side).agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("vertices"))


def sample(edges: DataFrame, percent: int) -> DataFrame:
    """A fixed share of edges over integer ids; samples of growing percentages nest."""
    return edges.filter(F.pmod(F.col("u") * 7919 + F.col("v") * 104729, F.lit(100)) < percent)

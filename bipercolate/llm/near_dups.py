"""Near-duplicate documents: banded MinHash finds candidates, odd sketches sift them, whole shingle sets decide.

Every document becomes the set of its distinct five-word shingles (64-bit hashes; words are lower-cased in A-Z and end at
ASCII white space). Equal sets are one node from the start (128-bit digests), so groups of copies cost one row each.

* 128 MinHash samples make 32 bands of 4. A pair of similarity 0.75 shares no band with probability 5e-6.
* The samples also fold into a parity bitmap of 512 bits, the odd sketch. Two sketches differ in few bits exactly if the
  samples do: at similarity 0.75 in 57 bits on average, with a standard deviation of 10, at 0 in 162. Pairs that differ in more than
  107 bits (five deviations) are dropped before any text moves; sizes that rule out the threshold drop others.
* What is left is confirmed on the whole sets: 100 * intersection >= 75 * union.

No bucket is ever paired with itself as it stands. First each member of a bucket is compared with the bucket's least
node only, which joins most groups. Then only buckets that still span several components go on, and only pairs of
different components are compared there: no link between different components can be missed, and a large group of near copies
costs as many comparisons as it has members. Bands of more than 48 members are compared in blocks, where sketches and sets
lie side by side and only confirmed links come out, so that a crowd of near misses makes no table of pairs.

Documents with fewer words than a shingle are one shingle; null, empty and wordless texts have an empty set and are
linked with nothing. A null doc_id is a document that nothing links. Rows that repeat a doc_id are each returned; they
count as one vertex. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bipercolate.checkpoints import cut
from bipercolate.components import FEW_LINKS, connected, merge
from bipercolate.llm.common import ids_semi, text_blocks

WORDS, PERCENT = 5, 75
SAMPLES, BAND, SKETCH_BITS, MOST_BITS_APART = 128, 4, 512, 107
SIGNATURE = "doc_id long, n_shingles long, digest_a long, digest_b long, bands array<long>, sketch array<long>"
#: Members up to which a band's pairs are joined one by one, and members of a block in larger ones.
PAIRWISE, BLOCK = 48, 1024
#: Bytes of shingle sets that one part of a hub's pairs, or one block, holds (about; one set may be larger).
GROUP_BYTES = 4 << 20
_LOWER = bytes(x + 32 if 65 <= x <= 90 else x for x in range(256))
_U64 = np.uint64
_SPREAD = _U64(0x9E3779B97F4A7C15)  # 2^64 over the golden ratio, an odd multiplier


def _mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that lets every bit depend on all."""
    x = x ^ (x >> _U64(31))
    x = x * _U64(0xD6E8FEB86659FD93)
    return x ^ (x >> _U64(32))


def shingles(text: bytes, words: int = WORDS) -> np.ndarray:
    """The sorted distinct shingle hashes of a text."""
    import xxhash

    found = text.translate(_LOWER).split()
    if not found:
        return np.empty(0, _U64)
    hashes = np.fromiter(map(xxhash.xxh3_64_intdigest, found), _U64, len(found))
    n = max(len(found) - words + 1, 1)
    total = np.zeros(n, _U64)
    for k in range(min(words, len(found))):
        total = _mixed(total * _SPREAD + hashes[k : k + n])
    return np.unique(total)


def _samples(hashes: np.ndarray, keys: np.ndarray) -> np.ndarray:
    least = np.full(len(keys), np.iinfo(_U64).max, _U64)
    for at in range(0, len(hashes), 1024):
        np.minimum(least, ((hashes[at : at + 1024, None] ^ keys) * _SPREAD).min(axis=0), out=least)
    return least


def signer(words: int = WORDS, samples: int = SAMPLES, band: int = BAND, bits: int = SKETCH_BITS):
    """For mapInArrow: ``doc_id, text`` to signatures."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        keys = np.random.default_rng(7).integers(0, 2**64, samples, _U64, endpoint=False)
        places = np.arange(samples, dtype=_U64) * _SPREAD
        seeds = np.arange(samples // band, dtype=_U64) * _SPREAD
        for batch in batches:
            for start, texts in text_blocks(batch):
                sizes, digests, bands, sketches = [], [], [], []
                for text in texts:
                    hashes = shingles(text, words)
                    raw = hashes.tobytes()
                    sizes.append(len(hashes))
                    digests.append((xxhash.xxh3_64_intdigest(raw, 1), xxhash.xxh3_64_intdigest(raw, 2)))
                    if not len(hashes):
                        bands.append(np.empty(0, np.int64))
                        sketches.append(np.zeros(bits // 64, np.int64))
                        continue
                    least = _samples(hashes, keys)
                    total = seeds.copy()
                    for part in least.reshape(-1, band).T:
                        total = _mixed(total * _SPREAD + part)
                    bands.append(total.view(np.int64))
                    odd = np.bincount((_mixed(least + places) % _U64(bits)).astype(np.int64), minlength=bits).astype(np.uint8) & 1
                    sketches.append(np.packbits(odd).view(np.int64))
                column = lambda x: pa.array(np.array(x, _U64).view(np.int64))
                lists = lambda xs: pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, xs)]), pa.int32()), pa.array(np.concatenate(xs)))
                a, b = zip(*digests, strict=True)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(start, len(texts)), pa.array(sizes, pa.int64()), column(a), column(b), lists(bands), lists(sketches)],
                    ["doc_id", "n_shingles", "digest_a", "digest_b", "bands", "sketch"],
                )

    return run


def signatures(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(signer(), SIGNATURE)


def _near(a: str, b: str, percent: int) -> Column:
    """Sizes and sketches allow the similarity."""
    apart = sum((F.bit_count(F.col(f"{a}.sketch")[i].bitwiseXOR(F.col(f"{b}.sketch")[i])) for i in range(SKETCH_BITS // 64)), F.lit(0))
    n, m = F.col(f"{a}.n_shingles"), F.col(f"{b}.n_shingles")
    return (F.least(n, m) * 100 >= F.greatest(n, m) * percent) & (apart <= MOST_BITS_APART)


def _set_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for start, texts in text_blocks(batch):
            sets = pa.array([shingles(x).tobytes() for x in texts], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(start, len(texts)), sets], ["doc_id", "shingles"])


def _similar(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    both = np.concatenate((x, y))
    both.sort()
    common = int((both[1:] == both[:-1]).sum())
    return 100 * common >= percent * (len(both) - common)


def _confirmer(percent: int):
    """For mapInArrow over rows sorted by hub: the hub's own row (b is null) comes before the rows of its pairs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hub, own = None, np.empty(0, _U64)
        for batch in batches:
            a, b, sets = batch.column("a").to_pylist(), batch.column("b").to_pylist(), batch.column("shingles")
            keep = []
            for k in range(batch.num_rows):
                this = np.frombuffer(sets[k].as_buffer(), _U64)
                if b[k] is None:
                    hub, own = a[k], this.copy()
                elif a[k] != hub:
                    raise ValueError(f"the shingles of {a[k]} are missing")
                elif _similar(own, this, percent):
                    keep.append(k)
            yield batch.select(["a", "b"]).take(pa.array(keep, pa.int64()))

    return run


def _sets(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """``[doc_id, shingles]`` of some ids, one row each."""
    texts = ids_semi(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), ids, "doc_id")
    return texts.mapInArrow(_set_rows, "doc_id long, shingles binary").groupBy("doc_id").agg(F.first("shingles").alias("shingles"))


def confirmed(pairs: DataFrame, docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Pairs (a, b) of doc_ids whose whole shingle sets are similar enough. Only texts of paired documents move.

    Each pair carries the set of b; that of a is sent once for every ``GROUP_BYTES`` of its pairs, so that the hub of a
    large group of copies costs a few rows, and its pairs lie in as many parts.
    """
    pairs = cut(pairs)
    ids = cut(pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct())
    sets = cut(_sets(docs, ids))
    sized = pairs.join(sets.select(F.col("doc_id").alias("b"), F.octet_length("shingles").alias("n")), "b")
    parts = cut(sized.groupBy("a").agg(F.ceil((F.sum("n") + 1) / GROUP_BYTES).cast("int").alias("parts")))
    mine = pairs.join(parts, "a").select("a", F.pmod(F.xxhash64("b"), F.col("parts")).cast("int").alias("part"), "b")
    rows = mine.join(sets.withColumnRenamed("doc_id", "b"), "b").select("a", "part", "b", "shingles")
    hubs = parts.select("a", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part")).join(sets.withColumnRenamed("doc_id", "a"), "a")
    rows = rows.union(hubs.select("a", "part", F.lit(None).cast("long").alias("b"), "shingles"))
    together = rows.repartition("a", "part").sortWithinPartitions("a", "part", F.asc_nulls_first("b"))
    return together.select("a", "b", "shingles").mapInArrow(_confirmer(percent), "a long, b long")


def _block_links(percent: int):
    """For applyInArrow: confirmed links (a, b) between two blocks of one band, or within one.

    A pair that shares an earlier large band is left to that band's group.
    """

    def run(group: pa.Table) -> pa.Table:
        group = group.combine_chunks()
        column = lambda name: group.column(name).to_numpy()
        lists = lambda name: group.column(name).combine_chunks()
        block, node, label, size = column("block"), column("node"), column("label"), column("n_shingles")
        bands, sketches = lists("bands"), np.stack([np.array(x, np.int64) for x in lists("sketch").to_pylist()]).view(_U64)
        earlier = [{y for y in x if y < b} for x, b in zip(bands.to_pylist(), column("band").tolist(), strict=True)]
        sets = [np.frombuffer(x.as_buffer(), _U64) for x in lists("shingles")]
        one = column("i")[0] == column("j")[0]
        left, right = (np.arange(len(node)),) * 2 if one else (np.flatnonzero(block == column("i")[0]), np.flatnonzero(block == column("j")[0]))
        links: list[tuple[int, int]] = []
        for x in left:
            others = right[right > x] if one else right
            others = others[(label[others] != label[x]) & (np.minimum(size[others], size[x]) * 100 >= np.maximum(size[others], size[x]) * percent)]
            others = others[np.bitwise_count(sketches[others] ^ sketches[x]).sum(axis=1) <= MOST_BITS_APART]
            for y in others:
                if earlier[x].isdisjoint(earlier[y]) and _similar(sets[x], sets[y], percent):
                    links.append((min(node[x], node[y]), max(node[x], node[y])))
        return pa.table({"a": pa.array([a for a, _ in links], pa.int64()), "b": pa.array([b for _, b in links], pa.int64())})

    return run


def _in_blocks(rest: DataFrame, light: DataFrame, docs: DataFrame, percent: int) -> DataFrame:
    """Links within large bands (band, node, label, n): nodes are dealt to blocks, and each pair of blocks is one bounded group.

    A block has about BLOCK members, or fewer where they have more than GROUP_BYTES of shingles.
    """
    own = rest.groupBy("node", "label").agg(F.array_sort(F.collect_list("band")).alias("bands"))  # at most one per band of the signature
    ids = cut(own.select(F.col("node").alias("doc_id")))
    full = cut(own.join(_sets(docs, ids).withColumnRenamed("doc_id", "node"), "node").join(light, "node"))
    sizes = rest.join(light.select("node", "n_shingles"), "node").groupBy("band").agg(F.count("*").alias("n"), (F.sum("n_shingles") * 8).alias("bytes"))
    blocks = sizes.select("band", F.ceil(F.greatest(F.col("n") / BLOCK, F.col("bytes") / GROUP_BYTES)).cast("int").alias("blocks"))
    dealt = rest.join(blocks, "band").select("band", "node", "blocks", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int").alias("block"))
    with_blocks = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    with_blocks = with_blocks.select("band", "node", "block", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"))
    return with_blocks.join(full, "node").groupBy("band", "i", "j").applyInArrow(_block_links(percent), "a long, b long")


def classes(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept, and copy_of (the least document with the same set)."""
    signed = cut(signatures(docs))
    set_key = ["digest_a", "digest_b"]
    nodes = cut(
        signed.filter("n_shingles > 0 and doc_id is not null")
        .groupBy(*set_key)
        .agg(F.min("doc_id").alias("node"), F.min_by(F.struct("n_shingles", "bands", "sketch"), "doc_id").alias("s"))
        .select(*set_key, "node", "s.*")
    )
    members = nodes.select("node", F.explode("bands").alias("band"))
    shared = members.groupBy("band").agg(F.min("node").alias("least"), F.count("*").alias("n")).filter("n > 1").drop("n")
    buckets = cut(members.join(shared, "band"))  # members of bands that several nodes share
    light = nodes.select("node", "n_shingles", "sketch")

    stars = buckets.filter("node <> least").select(F.col("least").alias("a"), F.col("node").alias("b")).distinct()
    sifted = stars.join(light.alias("x"), F.col("a") == F.col("x.node")).join(light.alias("y"), F.col("b") == F.col("y.node")).filter(_near("x", "y", percent)).select("a", "b")
    tried = cut(sifted)
    labels = cut(connected(cut(confirmed(tried, docs, percent)), driver_limit=FEW_LINKS))

    of = labels.select(F.col("item").alias("node"), F.col("label"))
    labelled = buckets.join(of, "node", "left").select("band", "node", F.coalesce("label", "node").alias("label"))
    open_bands = labelled.groupBy("band").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.count("*").alias("n")).filter("lo <> hi").select("band", "n")
    rest = cut(labelled.join(open_bands, "band"))
    few = rest.filter(F.col("n") <= PAIRWISE).join(light, "node")
    between = (
        few.alias("x").join(few.alias("y"), (F.col("x.band") == F.col("y.band")) & (F.col("x.node") < F.col("y.node")) & (F.col("x.label") != F.col("y.label")) & _near("x", "y", percent))
        .select(F.col("x.node").alias("a"), F.col("y.node").alias("b")).distinct()
        .join(tried, ["a", "b"], "left_anti")
    )
    blocks = _in_blocks(rest.filter(F.col("n") > PAIRWISE), light, docs, percent)
    every = nodes.select(F.col("node").alias("item")).join(labels, "item", "left").select("item", F.coalesce("label", "item").alias("label"))
    final = cut(merge(every, cut(confirmed(between, docs, percent).union(blocks)), driver_limit=FEW_LINKS))

    found = nodes.join(final, F.col("node") == F.col("item")).select(*set_key, F.col("node").alias("copy_of"), F.col("label").alias("component_id"))
    return (
        signed.select("doc_id", "n_shingles", *set_key).join(found, set_key, "left")
        .select("doc_id", "n_shingles", F.when(F.col("n_shingles") == 0, F.col("doc_id")).when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"), "copy_of")
        .select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"), "copy_of")
    )


def deduplicated(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay: one document of each class (rows that repeat its doc_id, or have none, stay with it)."""
    gone = classes(docs).filter("not kept").select(F.col("doc_id").alias("__gone"))
    return docs.join(gone, F.col("doc_id").cast("long") == F.col("__gone"), "left_anti")

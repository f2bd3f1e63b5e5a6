"""Packing token sequences as a cutting-stock problem solved by column generation.

Documents are cut into pieces of at most ``capacity`` tokens: full ones, and one remainder. Piece lengths are rounded up
to multiples of ``unit``, so the demand is a histogram of at most capacity / unit classes whatever the data. On it a
linear program over patterns (how many pieces of each class one sequence takes) is solved by the revised simplex method;
knapsack dynamic programming over the duals prices new patterns. Multiplicities are rounded down, what is left is filled
greedily, and pieces, ranked within their class, look up their sequence in the table of patterns.

Only the histogram reaches the driver. Null texts are empty documents (the end id alone); rows that repeat a doc_id are
packed each; a null doc_id is a document like others; no rows give no pieces.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bipercolate.checkpoints import cut
from bipercolate.llm.common import running_total, text_blocks
from bipercolate.llm.tokens import vocabulary, word_encoder

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


def cutter(vocabulary_path: str, end_id: int, capacity: int):
    """For mapInArrow: ``doc_id, text`` to pieces."""
    end, width = end_id.to_bytes(4, "little"), 4 * capacity

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = word_encoder(vocabulary_path).encode
        for batch in batches:
            for first, texts in text_blocks(batch):
                rows = []
                for k, packed in enumerate(encode(texts)):
                    packed = memoryview(packed + end)
                    for at in range(0, len(packed), width):
                        piece = packed[at : at + width]
                        rows.append((k, at // 4, len(piece) // 4, zlib.crc32(piece), len(packed) // 4))
                of, *rest = zip(*rows, strict=True)
                ids = batch.column("doc_id").slice(first, len(texts)).take(pa.array(of))
                yield pa.RecordBatch.from_arrays([ids, *(pa.array(x, pa.int64()) for x in rest)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return run


def pieces(docs: DataFrame, vocabulary_path: str | None = None, end_id: int = 1, capacity: int = 2048) -> DataFrame:
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return rows.mapInArrow(cutter(vocabulary_path or vocabulary("word_bpe_49k.json"), end_id, capacity), PIECES)


def best_pattern(values: np.ndarray, sizes: np.ndarray, room: int) -> tuple[float, np.ndarray]:
    """The unbounded knapsack: the most valuable multiset of sizes within ``room``, as (value, count of each)."""
    best, choice = np.zeros(room + 1), np.full(room + 1, -1)
    for space in range(1, room + 1):
        fits = np.searchsorted(sizes, space, side="right")
        best[space] = best[space - 1]
        if fits:
            gains = values[:fits] + best[space - sizes[:fits]]
            k = int(gains.argmax())
            if gains[k] > best[space] + 1e-12:
                best[space], choice[space] = gains[k], k
    counts, space = np.zeros(len(sizes), int), room
    while space > 0:
        if choice[space] < 0:
            space -= 1
        else:
            counts[choice[space]] += 1
            space -= sizes[choice[space]]
    return float(best[room]), counts


def relaxation(sizes: np.ndarray, demand: np.ndarray, room: int, gap: float = 2e-4, most: int = 4000, pull: float = 0.8) -> tuple[np.ndarray, np.ndarray]:
    """Patterns (columns; zero for surplus) and how often each is used in the linear program: cover the demand with few sequences.

    ``gap``: relative distance to the optimum's lower bound at which it ends. ``pull``: patterns are priced first at
    duals drawn towards those of the best bound so far, which keeps the duals from swinging; at first each size is worth
    its share of the room.
    """
    m = len(sizes)
    patterns = np.diag(room // sizes).astype(float)
    inverse = np.diag(1 / (room // sizes))
    cost, used = np.ones(m), inverse @ demand
    centre = sizes / room
    bound = float(centre @ demand)
    for _ in range(most):
        duals = cost @ inverse
        if used @ cost - bound <= gap * bound:
            break
        if duals.min() < -1e-9:  # a surplus of that size costs nothing
            counts, price = np.zeros(m), 0.0
            counts[duals.argmin()] = -1
        else:
            price = 1.0
            for weight in (pull, 0.0):
                drawn = weight * centre + (1 - weight) * duals
                value, counts = best_pattern(drawn, sizes, room)
                if drawn @ demand / max(value, 1) > bound:
                    bound, centre = float(drawn @ demand / max(value, 1)), drawn / max(value, 1)
                if duals @ counts > 1 + 1e-9:
                    break
            else:
                break
        column = inverse @ counts
        rates = np.full(m, np.inf)
        np.divide(used, column, out=rates, where=column > 1e-9)
        k = int(rates.argmin())
        if not np.isfinite(rates[k]):
            break
        used = np.maximum(used - rates[k] * column, 0)
        used[k] = rates[k]
        row = inverse[k] / column[k]
        inverse -= np.outer(column, row)
        inverse[k] = row
        patterns[:, k], cost[k] = np.maximum(counts, 0), price
    return patterns.astype(int), used


def rounded(sizes: np.ndarray, demand: np.ndarray, room: int) -> list[tuple[int, dict[int, int]]]:
    """``(how many sequences, {index of size: pieces in each})`` that hold exactly the demand."""
    if not len(sizes):
        return []
    patterns, used = relaxation(sizes, demand.astype(float), room)
    left, plan = demand.copy(), []

    def take(counts: np.ndarray, times: int) -> None:
        if times > 0 and counts.any():
            plan.append((times, {int(i): int(counts[i]) for i in np.flatnonzero(counts)}))
            np.subtract(left, times * counts, out=left)

    for p in np.argsort(-used):
        counts = patterns[:, p]
        has = counts > 0
        if has.any():
            take(counts, min(int(used[p] + 1e-6), int((left[has] // counts[has]).min())))
    while left.any():
        counts, space = np.zeros(len(sizes), int), room
        for i in range(len(sizes) - 1, -1, -1):
            counts[i] = min(left[i], space // sizes[i])
            space -= counts[i] * sizes[i]
        has = counts > 0
        take(counts, max(1, int((left[has] // counts[has]).min())))
    return plan


def slots(plan: list[tuple[int, dict[int, int]]], sizes: np.ndarray) -> list[tuple[int, int, int, int, int]]:
    """Rows ``(class, first rank, end rank, pieces a sequence, first sequence)``."""
    rank, rows, sequence = dict.fromkeys(range(len(sizes)), 0), [], 0
    for times, counts in plan:
        for i, n in counts.items():
            rows.append((int(sizes[i]), rank[i], rank[i] + times * n, n, sequence))
            rank[i] += times * n
        sequence += times
    return rows


def assign(cuts: DataFrame, capacity: int = 2048, unit: int = 16, buckets: int = 1024) -> DataFrame:
    """Add sequence_id and offset to pieces. ``cuts`` should be materialised: it is read twice."""
    spark = cuts.sparkSession
    rows = cuts.withColumn("__class", F.ceil(F.col("length") / unit).cast("int")).withColumn("__hash", F.xxhash64("doc_id", "start", "ids_crc32", "length"))
    histogram = sorted((r[0], r[1]) for r in rows.groupBy("__class").count().collect())  # at most capacity / unit rows
    sizes, demand = np.array([x for x, _ in histogram], int), np.array([x for _, x in histogram], int)
    table = slots(rounded(sizes, demand, capacity // unit), sizes)
    patterns = spark.createDataFrame(table, "c int, lo long, hi long, each long, first long")  # bounded by classes times patterns
    order = [F.col("__hash"), F.col("doc_id"), F.col("start"), F.col("length"), F.col("ids_crc32")]
    top_bits = F.shiftright("__hash", 64 - (buckets - 1).bit_length())
    ranked = running_total(rows.withColumn("__one", F.lit(1)), ["__class"], order, "__one", top_bits, "__rank")
    placed = ranked.join(F.broadcast(patterns), (F.col("__class") == F.col("c")) & (F.col("__rank") >= F.col("lo")) & (F.col("__rank") < F.col("hi")))
    placed = placed.withColumn("sequence_id", (F.col("first") + F.floor((F.col("__rank") - F.col("lo")) / F.col("each"))).cast("long"))
    inside = Window.partitionBy("sequence_id").orderBy(F.desc("__class"), "__rank").rowsBetween(Window.unboundedPreceding, -1)
    return placed.withColumn("offset", F.coalesce(F.sum("length").over(inside), F.lit(0)).cast("long")).select(*cuts.columns, "sequence_id", "offset")


def pack(docs: DataFrame, vocabulary_path: str | None = None, end_id: int = 1, capacity: int = 2048, unit: int = 16) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    return assign(cut(pieces(docs, vocabulary_path, end_id, capacity)), capacity, unit)


def padding(packed: DataFrame, capacity: int = 2048) -> DataFrame:
    """One row: sequences, tokens, padding up to capacity, and its share."""
    filled = packed.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    return filled.agg(
        F.count("*").alias("sequences"), F.sum("n").alias("tokens"), F.sum(F.lit(capacity) - F.col("n")).alias("padding"),
    ).withColumn("padding_share", F.col("padding") / (F.col("padding") + F.col("tokens")))

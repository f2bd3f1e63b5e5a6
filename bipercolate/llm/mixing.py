"""Mixing sources to target weights by weighted fair queueing. Native expressions only.

Each source is a queue: its documents in a shuffled order (a hash of the row), up to ``MOST_PASSES`` times over. A source
is served at a rate of its target, so that a document copy is in service from (words of its queue before it) / target to its
virtual finish time, (words including it) / target. The copies of all sources, range-sorted by finish time, are the mix. It
is truncated at the total budget, which is reached at virtual time 1: copies whose service has not begun by then are not emitted, those in
service give the words served so far, and a prefix sum over the sorted copies of all sources cuts what would exceed the
budget. So every source gives its target to a word.

Targets share the budget (all words, or ``budget``) by weight. A source whose share exceeds ``MOST_PASSES`` times its words
stops there, and the excess is reshared by weight among the others until none is above; that is water-filling, solved
in closed form after sorting sources by words per weight.

Neither queues nor the mix are ever gathered: prefix sums come from sums per bucket of the queue's hash, or of finish times. A null text has no words and is not
taken; null sources are one source, the last; a null doc_id is a document like others; rows that repeat are each queued;
no rows make an empty mix; other columns pass through ``mixed`` (names that begin with two underscores are reserved).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Row, Window
from pyspark.sql import functions as F

from bipercolate.checkpoints import cut
from bipercolate.llm.common import running_total, word_count

MOST_PASSES = 3
WEIGHTS = (1, 2, 3)
#: Buckets of each source's shuffled order, and of virtual time; a window within one bucket holds this fraction of the rows.
BUCKETS = 4096
#: The order of copies in the mix.
PLACE = ("finish", "__source", "pass", "__before")
COPIES = "array<struct<pass:int,words:bigint,finish:double>>"


def default_weights(sources: DataFrame) -> DataFrame:
    """``sources`` (one row each) with weights 1, 2, 3, 1, ... in the order of their names by code point, null last."""
    place = F.row_number().over(Window.orderBy(F.asc_nulls_last("source"))) - 1
    return sources.withColumn("weight", F.element_at(F.array(*map(F.lit, WEIGHTS)), F.pmod(place, F.lit(len(WEIGHTS))) + 1).cast("double"))


def targets(sources: DataFrame, budget: int | None = None, most: int = MOST_PASSES) -> DataFrame:
    """Add ``target`` to sources(source, source_size, weight).

    With the sources sorted by size per weight, those that stop at ``most`` times their size come first; the level of
    the others is (budget - most * stopped words) / their weights at the first source whose own limit is not below it;
    from there on it only falls, so it is the largest of those.
    """
    by = Window.orderBy((F.col("source_size") / F.col("weight")), F.asc_nulls_last("source"))
    before, every = by.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    total = F.sum("source_size").over(every) if budget is None else F.lit(budget)
    stopped, weights = F.coalesce(F.sum("source_size").over(before), F.lit(0)) * most, F.sum("weight").over(by.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    level = (total - stopped) / weights
    return (
        sources.withColumn("__level", level)
        .withColumn("__open", F.col("__level") * F.col("weight") <= F.col("source_size") * most)
        .withColumn("__level", F.max(F.when(F.col("__open"), F.col("__level"))).over(every))
        .withColumn("target", F.least(F.col("source_size").cast("double") * most, F.coalesce(F.col("__level") * F.col("weight"), F.lit(float("inf")))))
        .drop("__level", "__open")
    )


@dataclass
class Queues:
    """``light``: a row per document without its text; ``aimed``: size and target per source; ``end``: the copy at which the budget is used up, if any."""

    light: DataFrame
    aimed: DataFrame
    end: Row | None


def _queued(docs: DataFrame, seed: int) -> DataFrame:
    """``docs`` with __size, and __order, a hash of the document: its place in the shuffled queue of __source (never null)."""
    row = [x for c in ("doc_id", "source", "text") for x in (F.col(c).isNull(), F.col(c).cast("string"))]
    source = F.coalesce(F.concat(F.lit("s"), F.col("source").cast("string")), F.lit("n"))
    return docs.withColumns({"__source": source, "__size": word_count(F.col("text").cast("string")), "__order": F.xxhash64(F.lit(seed), *row)})


def queues(docs: DataFrame, weights: DataFrame | None = None, budget: int | None = None, seed: int = 0) -> Queues:
    """Sizes, targets and the end of the mix. ``weights``: source, weight; default 1, 2, 3 repeating."""
    rows = _queued(docs, seed)
    light = cut(rows.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), "__source", "__size", "__order"))
    sources = light.groupBy("source", "__source").agg(F.sum("__size").alias("source_size"))
    if weights is None:
        weighed = default_weights(sources)
    else:
        known = weights.select(F.col("source").alias("__s"), "weight")
        weighed = sources.join(known, F.col("source").eqNullSafe(F.col("__s")), "left").drop("__s").withColumn("weight", F.coalesce("weight", F.lit(1.0)))
    aimed = cut(targets(weighed, budget).select("__source", F.col("source_size").alias("__source_size"), F.col("target").alias("__target")))  # a row per source
    most = aimed.agg(F.sum("__source_size")).first()[0] if budget is None else budget
    return Queues(light.drop("source"), aimed, _end(copies(light.drop("source"), Queues(light, aimed, None)), most or 0))


def copies(rows: DataFrame, queue: Queues) -> DataFrame:
    """``rows`` (of ``_queued``) with __source_size, __target, __before (words of the queue before this row, in its first pass) and __copies.

    __copies are those whose service begins before virtual time 1, with the words served by then and their finish times.
    """
    bucket = F.shiftright("__order", 64 - (BUCKETS - 1).bit_length())
    rest = F.xxhash64(*[F.col(c).cast("string") for c in rows.columns if not c.startswith("__")])
    placed = running_total(rows, ["__source"], [F.col("__order"), F.col("doc_id"), F.col("__size"), rest], "__size", bucket, "__before", queue.light)
    goal = F.floor(F.col("__target") + 1e-6)

    def copy(k: int) -> Column:
        before = F.col("__source_size") * k + F.col("__before")
        words = F.greatest(F.lit(0), F.least(F.col("__size"), goal - before)).cast("long")
        return F.struct(F.lit(k).alias("pass"), words.alias("words"), F.try_divide(before + F.col("__size"), F.col("__target")).alias("finish"))

    every = F.filter(F.array(*map(copy, range(MOST_PASSES))), lambda c: c["words"] > 0).cast(COPIES)
    found = placed.join(queue.aimed, "__source").drop("__order").withColumn("__copies", every)
    return found if queue.end is None else found.withColumn("__copies", _until(queue.end))


def _end(found: DataFrame, budget: int) -> Row | None:
    """The first copy with which the words of all copies by finish time exceed the budget, and how many of its own are left for it.

    The prefix sum runs over the copies of all sources, in buckets of virtual time (the last also holds copies that would
    finish after time 1).
    """
    rows = found.select("__source", "__before", F.explode("__copies").alias("c")).select("__source", "__before", "c.*")
    by = [F.col(c) for c in PLACE]
    bucket = F.least(F.floor(F.col("finish") * BUCKETS), F.lit(BUCKETS)).cast("int")
    ahead = running_total(rows, [], by, "words", bucket, "ahead")
    over = ahead.filter(F.col("ahead") + F.col("words") > budget).select(*by, (F.lit(budget) - F.col("ahead")).alias("left"))
    return over.agg(F.min(F.struct(*by, "left")).alias("first")).first()["first"]


def _until(end: Row) -> Column:
    """__copies before the end of the mix, and what is left for the copy there."""
    last = F.struct(*(F.lit(end[c]).alias(c) for c in PLACE))

    def served(c: Column) -> Column:
        place = F.struct(c["finish"].alias("finish"), F.col("__source"), c["pass"].alias("pass"), F.col("__before"))
        words = F.when(place < last, c["words"]).when(place == last, F.lit(end["left"])).otherwise(F.lit(0)).cast("long")
        return F.struct(c["pass"].alias("pass"), words.alias("words"), c["finish"].alias("finish"))

    return F.filter(F.transform("__copies", served), lambda c: c["words"] > 0)


def mix(docs: DataFrame, weights: DataFrame | None = None, budget: int | None = None, seed: int = 0) -> DataFrame:
    """Per document: doc_id, size, source_size, target, taken, and virtual_finish, the finish time of its first copy, in whose order rows are range-sorted."""
    queue = queues(docs, weights, budget, seed)
    words = F.aggregate("__copies", F.lit(0).cast("long"), lambda acc, c: acc + c["words"])
    finish = F.when(F.col("__target") > 0, (F.col("__before") + F.col("__size")) / F.col("__target"))
    return (
        copies(queue.light, queue)
        .select("doc_id", F.col("__size").alias("size"), F.col("__source_size").alias("source_size"), F.col("__target").alias("target"), words.alias("taken"), finish.alias("virtual_finish"))
        .orderBy("virtual_finish", "doc_id")
    )


def first_words(text: Column, n: Column) -> Column:
    """The text up to the end of its n-th word."""
    words = F.concat(F.lit(r"(?s)\A((?:[\x09-\x0D\x20]*+[^\x09-\x0D\x20]++){"), n.cast("string"), F.lit(r"}+).*\z"))
    return F.when(n <= 0, F.lit("")).otherwise(F.regexp_replace(text, words, F.lit("$1")))


def mixed(docs: DataFrame, weights: DataFrame | None = None, budget: int | None = None, seed: int = 0) -> DataFrame:
    """The mix itself, in the columns of ``docs``: each document as often as it is taken, range-sorted by virtual finish time.

    A copy in service at the end is cut after its last word served.
    """
    found = copies(_queued(docs, seed), queues(docs, weights, budget, seed))
    rows = found.withColumn("__c", F.explode("__copies")).drop("__copies")
    words = F.col("__c.words")
    rows = rows.withColumn("text", F.when(words < F.col("__size"), first_words(F.col("text"), words)).otherwise(F.col("text")))
    rows = rows.select(*docs.columns, F.col("__c.finish").alias("__finish"), F.col("__source"), F.col("__before"))
    by = ("__finish", "__source", "__before")
    return rows.repartitionByRange(*by).sortWithinPartitions(*by).select(*docs.columns)

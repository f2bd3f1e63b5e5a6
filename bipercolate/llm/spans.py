"""Where a pattern matches, as native column expressions.

Spark returns what a regular expression matches and what lies between, but not where. The lengths of both, summed up,
give every match's start in code points; the sums are made in blocks, so that a text with very many matches stays cheap.
A span is ``struct(start, rank, kind, end, match)``; ``rank`` orders kinds at the same start.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

from bipercolate.llm.common import let

BLOCK = 64
SPAN = "array<struct<start:bigint,rank:int,kind:string,end:bigint,match:string>>"


def _running(numbers: Column) -> Column:
    """For an array of longs: the sum before each element."""
    zero = F.lit(0).cast("bigint")

    def before(values: Column, first: Column) -> Column:
        last = lambda acc: F.element_at(acc, -1)
        return F.slice(F.aggregate(values, F.array(first), lambda acc, x: F.concat(acc, F.array(last(acc) + x))), 1, F.size(values))

    total = lambda block: F.aggregate(block, zero, lambda acc, x: acc + x)
    blocks = F.when(F.size(numbers) > 0, F.transform(F.sequence(F.lit(1), F.size(numbers), F.lit(BLOCK)), lambda at: F.slice(numbers, at, F.lit(BLOCK)))).otherwise(F.array().cast("array<array<bigint>>"))
    return let(blocks, lambda b: F.flatten(let(before(F.transform(b, total), zero), lambda starts: F.transform(F.arrays_zip(b.alias("b"), starts.alias("s")), lambda x: before(x["b"], x["s"])))))


def spans(text: Column, pattern: str, kind: str, rank: int, where: Column | None = None, size: Callable[[Column], Column] = F.length) -> Column:
    """Leftmost non-overlapping matches of ``pattern`` (Java syntax, never empty) in ``text``; none where ``where`` is false.

    ``size`` measures strings: in code points, or in bytes with ``octet_length``.
    """
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))

    def placed(matches: Column) -> Column:
        between = F.slice(F.split(text, pattern, -1), 1, F.size(matches))
        steps = F.zip_with(between, matches, lambda gap, match: (size(gap) + size(match)).cast("bigint"))
        return F.zip_with(
            let(steps, lambda s: F.zip_with(_running(s), s, lambda before, step: before + step)), matches,
            lambda end, match: F.struct((end - size(match)).alias("start"), F.lit(rank).alias("rank"), F.lit(kind).alias("kind"), end.alias("end"), match.alias("match")),
        )

    none = F.array().cast(SPAN)
    some = let(found, lambda m: F.when(F.size(m) > 0, placed(m)).otherwise(none))
    return F.coalesce(some if where is None else F.when(where, some), none)


def listed(found: Column) -> Column:
    """``kind:start:end`` of each span, comma-joined in the order of start, then rank."""
    return F.array_join(F.transform(F.array_sort(found), lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def digest(found: Column) -> Column:
    return F.sha2(listed(found).cast("binary"), 256)


def count(found: Column, kind: str) -> Column:
    return F.size(F.filter(found, lambda s: s["kind"] == kind)).cast("long")

"""Secrets in texts: known forms, and strings whose characters look random. Native expressions only.

Base kinds are assign (a value given to a password-like name), access (access-key ids) and hex (long hexadecimal runs);
they stay in any case. The method adds kind entropy: candidate strings of 20 characters or more, with a digit and a letter, over
which a window of ``WINDOW`` characters slides. The window's Shannon entropy is log2(W) - sum(c * log2 c) / W over the
counts c of its characters; moving on by one character changes two counts, so only two terms of the sum are replaced.
A candidate is a secret if some window reaches the threshold of its character class (hexadecimal or base64) and no
allow-list pattern matches: UUIDs, slugs and paths of lower-case words and numbers of up to four digits for the candidate, and
words of documentation, runs of one character and ascending sequences for the block around the window.

Every pattern repeats possessively, so that no text makes the matcher recurse, and windows slide within blocks of
``BLOCK`` starts that overlap by a window: time is linear in the text, also for one run of a million characters.

Null and empty texts have no spans. Rows are independent: repeated rows repeat, a null doc_id is returned as it is. A
column called ``secrets`` is replaced.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bipercolate.llm.common import let
from bipercolate.llm.spans import count, digest, listed, spans

# Forms of secrets.
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]++)"""
ACCESS = r"AKIA[A-Z0-9]++"
HEX = r"[0-9a-f]{16,}+"  # runs of [0-9a-f]+ with 16 characters or more
CANDIDATE = r"(?<![A-Za-z0-9+/_=-])(?=[A-Za-z+/_=-]*+[0-9])(?=[0-9+/_=-]*+[A-Za-z])[A-Za-z0-9+/_=-]{20,}+"
_PART = "(?:[a-z]{1,15}|[0-9]{1,4})"
_WORDS = f"{_PART}(?:[-_]{_PART})*+"
#: Candidates that are allowed as a whole: UUIDs, addresses, and slugs and paths whose parts are all lower-case words or short numbers (random characters mix the two).
ALLOWED = rf"^(?i:[0-9a-f]{{8}}(?:-[0-9a-f]{{4}}){{3}}-[0-9a-f]{{12}}$|https?)|^/?{_WORDS}(?:/{_WORDS}){{2,}}+/?$|^{_PART}(?:[-_]{_PART})++$"
#: What makes a block of a candidate (most candidates are one block) a placeholder.
PLACEHOLDER = r"(?i:example|sample|placeholder|changeme|your[_-]?|xxxx|0123456789|1234567890|abcdefgh|(.)\1{5})"
BASE = ("assign", "access", "hex")
WINDOW = 20
#: Starts of windows that one fold handles.
BLOCK = 200
#: Least entropy of a window, in bits a character, by character class.
LEAST = {"hexadecimal": 2.9, "base64": 3.6}


def _term(count_: Column) -> Column:
    """count * log2(count), 0 for 0."""
    return F.when(count_ > 0, count_ * F.log2(F.greatest(count_, F.lit(1)))).otherwise(0.0)


def _least_sum(text: Column, width: int) -> Column:
    """The least sum of c * log2(c) over the character counts c of any window of an ASCII string of at least ``width``."""
    times = lambda s, c: F.length(s) - F.length(F.replace(s, c, F.lit("")))
    first = F.substring(text, 1, width)
    distinct = F.array_distinct(F.split(first, ""))
    total = F.aggregate(distinct, F.lit(0.0), lambda acc, c: acc + F.when(c == "", 0.0).otherwise(_term(times(first, c))))

    def move(state: Column, at: Column) -> Column:
        """From the window at - 1 to the window at (counted from 1)."""
        kept = F.substring(text, at, F.lit(width - 1))
        gone, come = F.substring(text, at - 1, F.lit(1)), F.substring(text, at + width - 1, F.lit(1))
        a, b = times(kept, gone), times(kept, come)
        moved = state["total"] - _term(a + 1) + _term(a) + _term(b + 1) - _term(b)
        return let(moved, lambda t: F.struct(t.alias("total"), F.least(state["least"], t).alias("least")))

    none = F.array().cast("array<int>")
    steps = F.when(F.length(text) > width, F.sequence(F.lit(2), F.length(text) - width + 1)).otherwise(none)
    return let(total, lambda t: F.aggregate(steps, F.struct(t.alias("total"), t.alias("least")), move, lambda s: s["least"]))


def _blocks(text: Column, width: int) -> Column:
    """Pieces of ``text`` with all its windows: ``BLOCK`` starts each, and what the last of these windows reaches into."""
    pattern = rf"(?s)(?=(.{{1,{BLOCK + width - 1}}}+)).{{1,{BLOCK}}}+"
    return F.filter(F.regexp_extract_all(text, F.lit(pattern), F.lit(1)), lambda b: F.length(b) >= width)


def _entropy(block: Column, width: int) -> Column:
    return F.lit(math.log2(width)) - _least_sum(block, width) / width


def window_entropy(text: Column, width: int = WINDOW) -> Column:
    """The largest entropy of any ``width`` characters in a row of an ASCII string; null if it is shorter."""
    return F.array_max(F.transform(_blocks(text, width), lambda b: _entropy(b, width)))


def _reaches(match: Column, least: float) -> Column:
    """Some window has that entropy. Blocks with too few different characters for it are not slid over."""

    def random(block: Column) -> Column:
        rich = F.size(F.array_distinct(F.split(block, ""))) >= math.ceil(2**least)
        return rich & ~block.rlike(PLACEHOLDER) & (_entropy(block, WINDOW) >= least)

    return F.exists(_blocks(match, WINDOW), random)


def is_random(match: Column) -> Column:
    reached = F.when(match.rlike("^[0-9a-fA-F]++$"), _reaches(match, LEAST["hexadecimal"])).otherwise(_reaches(match, LEAST["base64"]))
    return ~match.rlike(ALLOWED) & reached


def detect(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with ``secrets``, an array of structs start, rank, kind, end, match."""
    whole = F.coalesce(F.col(text).cast("string"), F.lit(""))
    assign = F.filter(spans(whole, ASSIGN, "assign", 0, whole.rlike("[:=]")), lambda s: F.length(F.regexp_extract(s["match"], ASSIGN, 1)) >= 12)
    access = F.filter(spans(whole, ACCESS, "access", 1, F.contains(whole, F.lit("AKIA"))), lambda s: F.length(s["match"]) >= 18)
    hexes = spans(whole, HEX, "hex", 2)
    entropy = F.filter(spans(whole, CANDIDATE, "entropy", 3, whole.rlike("[0-9]")), lambda s: is_random(s["match"]))
    return docs.withColumn("secrets", F.array_sort(F.concat(assign, access, hexes, entropy)))


def report(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, counts of the base kinds, a digest of their spans, and all spans."""
    found = detect(docs.select("doc_id", "text"))
    base = F.filter("secrets", lambda s: s["kind"].isin(*BASE))
    return found.select("doc_id", *[count(F.col("secrets"), k).alias(f"n_{k}") for k in BASE], digest(base).alias("base_sha256"), listed(F.col("secrets")).alias("spans"), F.size("secrets").cast("long").alias("n_spans"))

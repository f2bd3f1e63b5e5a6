"""Quality rules: shape counts of a text, and how a public tokenizer copes with it.

The base rules reject texts with fewer than 20 words, and those of whose words more than 30 % lie in eight-word windows that occur
twice or more. The method encodes each word with a public SentencePiece vocabulary and measures characters per token,
the share of byte-fallback pieces and the entropy of the token distribution in bits. Bands per script (taken from the
letters of the text) reject what lies outside.

The bands are measured on the table itself, over all documents that pass the base rules, per language and script and per
doubling of the token count (short texts vary more, and have less entropy): the median, and ``WIDTH`` robust standard
deviations (of the quartiles) to both sides, so that a few per cent of junk don't move them. A size with fewer than
``LEAST_ROWS`` documents takes the nearest size's band, widened; a language without any takes its script's, and a script
without any has only the fixed outer limits of ``BANDS``, which always hold. ``bands`` given by the caller (by script, or
``lang:`` and a language) are used as they are, and nothing is measured. Entropy is judged from 50 tokens on.

Null, empty and wordless texts have no words, so the base rules reject them; their measures are 0. Repeated rows get the
same verdict, a null doc_id changes nothing, a null lang leaves the script, other columns pass through ``accepted``.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, DoubleType, LongType, StringType, StructField, StructType

from bipercolate.checkpoints import cut, shared_path
from bipercolate.llm.common import text_blocks
from bipercolate.llm.tokens import pieces, vocabulary

SCHEMA = (
    "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, "
    "n_tokens long, chars_per_token double, byte_share double, token_entropy double, script string"
)
COLUMNS = [x.split()[0] for x in SCHEMA.split(", ")]
#: What a verdict is made of, beside the language.
JUDGED = ["base_failed", "script", "n_tokens", "chars_per_token", "byte_share", "token_entropy"]
MIN_WORDS, WINDOW, MOST_REPEATED = 20, 8, 30
ENTROPY_FROM = 50
#: Of measured bands: robust standard deviations to both sides of the median, the least of them, documents that a band needs.
WIDTH, LEAST_DEVIATION, LEAST_ROWS = 6.0, 0.02, 30
#: Outer limit of entropy by token count: the first number, and so many bits per doubling.
MOST_ENTROPY = (1.0, 0.8)
_SYMBOLS = bytes(x for x in range(256) if x not in b"#*$%&|<>")
_SCRIPTS = {  # fixed values: code points that a script's letters begin at, in Unicode's blocks
    "latin": (0x41, 0x250), "greek": (0x370, 0x400), "cyrillic": (0x400, 0x530), "hebrew": (0x590, 0x600), "arabic": (0x600, 0x780),
    "indic": (0x900, 0xE00), "thai": (0xE00, 0xE80), "kana": (0x3040, 0x3100), "han": (0x4E00, 0xA000), "hangul": (0xAC00, 0xD7B0),
}


@dataclass(frozen=True)
class Band:
    """What is accepted: characters per token, byte-fallback share, least bits of entropy."""

    chars: tuple[float, float] = (0.3, 8.0)
    most_bytes: float = 0.6
    least_entropy: float = 3.5


BANDS = {
    "latin": Band((1.2, 8.0), 0.15, 3.9),
    "greek": Band((0.6, 8.0), 0.3), "cyrillic": Band((0.8, 8.0), 0.3), "hebrew": Band((0.5, 8.0), 0.5), "arabic": Band((0.5, 8.0), 0.5),
    "kana": Band((0.4, 8.0), 0.6), "han": Band((0.25, 8.0), 0.8), "hangul": Band((0.25, 8.0), 0.8),
}


class Limits:
    """What is accepted. ``measured``: by (lang or None, script) and floor(log2 of the tokens), median and deviation of both measures."""

    def __init__(self, bands: dict[str, Band] | None, measured: dict[tuple[str | None, str], dict[int, tuple[float, float, float, float]]]):
        self.bands, self.measured = BANDS if bands is None else bands, measured

    def fits(self, lang: str | None, name: str, n: int, per_token: float, byte_share: float, entropy: float) -> bool:
        band = self.bands.get(f"lang:{lang}") or self.bands.get(name) or Band()
        if not band.chars[0] <= per_token <= band.chars[1] or byte_share > band.most_bytes:
            return False
        judged = n >= ENTROPY_FROM
        if judged and not band.least_entropy <= entropy <= MOST_ENTROPY[0] + MOST_ENTROPY[1] * math.log2(n):
            return False
        sizes = self.measured.get((lang, name)) or self.measured.get((None, name))
        if not n or not sizes:
            return True
        size = n.bit_length() - 1
        nearest = min(sizes, key=lambda s: (abs(s - size), s))
        chars, chars_dev, bits, bits_dev = sizes[nearest]
        wider = 2 ** (max(nearest - size, 0) / 2)  # deviations grow as texts get shorter
        if abs(per_token - chars) > WIDTH * chars_dev * wider:
            return False
        # A doubling of a text adds one bit at most.
        lowest = bits - WIDTH * bits_dev * wider - max(nearest - size, 0)
        return not judged or lowest <= entropy <= bits + WIDTH * bits_dev * wider + max(size - nearest, 0)


def measured_limits(rows: DataFrame) -> Limits:
    """Limits from measures (with lang) of a whole table: quartiles per group, in one row a group on the driver."""
    size = F.floor(F.log2("n_tokens")).cast("int")
    keys = F.explode(F.when(F.col("lang").isNull(), F.array(F.lit(None).cast("string"))).otherwise(F.array(F.col("lang"), F.lit(None))))
    good = rows.filter("not base_failed and n_tokens > 0").select(keys.alias("lang"), "script", size.alias("size"), "chars_per_token", "token_entropy")
    quartiles = [F.percentile_approx(c, [0.25, 0.5, 0.75], 10_000).alias(c) for c in ("chars_per_token", "token_entropy")]
    found: dict = {}
    for r in good.groupBy("lang", "script", "size").agg(F.count("*").alias("n"), *quartiles).filter(F.col("n") >= LEAST_ROWS).collect():
        pairs = [(q[1], max((q[2] - q[0]) / 1.349, LEAST_DEVIATION)) for q in (r.chars_per_token, r.token_entropy)]
        found.setdefault((r.lang, r.script), {})[r.size] = (*pairs[0], *pairs[1])
    return Limits(None, found)


def script(text: bytes) -> str:
    """The script of most letters; latin where ASCII letters prevail, other where none is known."""
    points = np.frombuffer(text.decode("utf-8", "replace").encode("utf-32-le"), "<u4")
    best, most = "other", 0
    for name, (first, end) in _SCRIPTS.items():
        n = int(((points >= first) & (points < end)).sum())
        if n > most:
            best, most = name, n
    return best


def repeated_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words in windows that occur twice or more, the first occurrence included. Windows are compared by 64-bit hashes."""
    n = len(words) - window + 1
    if n < 2:
        return 0
    hashes = np.fromiter(map(hash, words), np.int64, len(words)).view(np.uint64)
    total = np.zeros(n, np.uint64)
    for k in range(window):
        total = (total ^ (total >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15) + hashes[k : k + n]
    order = np.argsort(total, kind="stable")
    same = total[order][1:] == total[order][:-1]
    if not same.any():
        return 0
    again = np.zeros(n, bool)
    again[order[1:][same]] = again[order[:-1][same]] = True
    at = np.flatnonzero(again)
    marks = np.zeros(len(words) + 1, np.int64)
    marks[at] += 1
    marks[at + window] -= 1
    return int((np.cumsum(marks[:-1]) > 0).sum())


def base_counts(text: bytes) -> tuple[int, int, int, int, int, list[bytes]]:
    words = text.split()
    joined = b"".join(words)
    chars = len(joined) if joined.isascii() else len(joined.decode("utf-8", "replace"))
    symbols = len(text.translate(None, _SYMBOLS))
    lines = [x for x in text.split(b"\n") if not x.isspace() and x]
    return len(words), chars, symbols, len(lines) - len(set(lines)), repeated_words(words), words


def rules(vocabulary_path: str, limits: Limits, shape: str):
    """For mapInArrow: one row of measures each ("measures"), the accepted input rows ("rows"), or input rows with measures behind them ("both")."""

    def measured(batch: pa.RecordBatch, known, is_byte: np.ndarray) -> Iterator[tuple]:
        langs = batch.column("lang").to_pylist() if "lang" in batch.schema.names else [None] * batch.num_rows
        at = 0
        for _, texts in text_blocks(batch):
            for text in texts:
                n_words, chars, symbols, lines, repeats, words = base_counts(text)
                failed = n_words < MIN_WORDS or 100 * repeats > MOST_REPEATED * n_words
                ids = np.frombuffer(b"".join(map(known.__getitem__, words)), "<u4")
                n = len(ids)
                per_token = byte_share = entropy = 0.0
                name = "other"
                if n:
                    counts = np.bincount(ids)
                    byte_share = float(is_byte[ids].mean())
                    share = counts[counts > 0] / n
                    per_token, entropy = chars / n, float(-(share * np.log2(share)).sum())
                    name = "latin" if text.isascii() else script(text)
                fits = limits.fits(langs[at], name, n, per_token, byte_share, entropy)
                yield n_words, chars, symbols, lines, repeats, failed, fits and not failed, n, per_token, byte_share, entropy, name
                at += 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = pieces(vocabulary_path)
        is_byte = np.zeros(known.model.get_piece_size(), bool)
        is_byte[known.byte_ids] = True
        for batch in batches:
            if not batch.num_rows:
                continue
            columns = list(zip(*measured(batch, known, is_byte), strict=True))
            kinds = [pa.int64()] * 5 + [pa.bool_()] * 2 + [pa.int64()] + [pa.float64()] * 3 + [pa.string()]
            if shape == "rows":
                yield batch.filter(pa.array(columns[6], pa.bool_()))
            elif shape == "both":
                named = dict(zip(COLUMNS[1:], zip(columns, kinds, strict=True), strict=True))
                yield pa.RecordBatch.from_arrays([*batch.columns, *(pa.array(*named[c]) for c in JUDGED)], [*batch.schema.names, *(f"__{c}" for c in JUDGED)])
            else:
                lang = pc.cast(batch.column("lang"), pa.string()) if "lang" in batch.schema.names else pa.nulls(batch.num_rows, pa.string())
                yield pa.RecordBatch.from_arrays([pc.cast(batch.column("doc_id"), pa.int64()), *(pa.array(x, k) for x, k in zip(columns, kinds, strict=True)), lang], [*COLUMNS, "lang"])

    return run


def _measures(docs: DataFrame, path: str, limits: Limits) -> DataFrame:
    wanted = ["doc_id", F.col("text").cast("string").alias("text"), *([F.col("lang").cast("string").alias("lang")] if "lang" in docs.columns else [])]
    return docs.select(*wanted).mapInArrow(rules(path, limits, "measures"), f"{SCHEMA}, lang string")


def _verdicts(limits: Limits, rows: bool = False):
    """For mapInArrow: ``kept`` by these limits, from measures; or, with ``rows``, the input rows that are kept, from rows with measures behind them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names = batch.schema.names
            langs = pc.cast(batch.column("lang"), pa.string()).to_pylist() if "lang" in names else [None] * batch.num_rows
            failed, *measures = (batch.column(f"__{c}" if rows else c).to_pylist() for c in JUDGED)
            kept = pa.array([not bad and limits.fits(lang, *rest) for bad, lang, *rest in zip(failed, langs, *measures, strict=True)], pa.bool_())
            if rows:
                yield batch.select(names[: -len(JUDGED)]).filter(kept)
            else:
                yield pa.RecordBatch.from_arrays([kept if c == "kept" else batch.column(c) for c in COLUMNS], COLUMNS)

    return run


def measure(docs: DataFrame, vocabulary_path: str | None = None, bands: dict[str, Band] | None = None) -> DataFrame:
    """Per document: doc_id, the base counts, base_failed, kept, and the tokenizer's measures. Texts are encoded once; the measures are stored for the verdicts."""
    rows = _measures(docs, vocabulary_path or vocabulary("piece_bpe_32k.model"), Limits(bands, {}))
    if bands is not None:
        return rows.drop("lang")
    rows = cut(rows)
    return rows.mapInArrow(_verdicts(measured_limits(rows)), SCHEMA)


def accepted(docs: DataFrame, vocabulary_path: str | None = None, bands: dict[str, Band] | None = None) -> DataFrame:
    """The rows of ``docs`` that are kept, with all their columns. Rows wait in the shared folder for the bands of the whole table, so that texts are encoded once."""
    path, limits, spark = vocabulary_path or vocabulary("piece_bpe_32k.model"), Limits(bands, {}), docs.sparkSession
    if bands is not None:
        return docs.mapInArrow(rules(path, limits, "rows"), docs.schema)
    fields = {x.split()[0]: x.split()[1] for x in SCHEMA.split(", ")}
    kinds = docs.schema
    for c in JUDGED:
        kinds = StructType([*kinds.fields, StructField(f"__{c}", {"boolean": BooleanType(), "string": StringType(), "long": LongType(), "double": DoubleType()}[fields[c]])])
    stored = shared_path(spark, "quality-measures")
    docs.mapInArrow(rules(path, limits, "both"), kinds).write.option("compression", "zstd").parquet(stored)
    rows = spark.read.schema(kinds).parquet(stored)
    lang = F.col("lang").cast("string") if "lang" in docs.columns else F.lit(None).cast("string")
    measured = rows.select(lang.alias("lang"), *[F.col(f"__{c}").alias(c) for c in JUDGED])
    return rows.mapInArrow(_verdicts(measured_limits(measured), rows=True), docs.schema)

"""Token counts that follow edits: a segment tree over each document's pre-tokens.

A document is cut into segments at places where a pre-token is sure to end whatever stands around: before a space that
follows a printing ASCII character. The leaves of a tree hold each segment's bytes and tokens; inner nodes hold sums, so the
root has the document's count and a byte offset is found in logarithmic time. Edits re-encode the segments that they touch, each
once however many edits it takes, and neighbours only where an edit spoils the cut between them; the leaves and the sums above them
are replaced. Segments that outgrow their size are cut anew, so a tree keeps its grain.

Trees are stored as heap-ordered arrays beside the text (``build``), and ``apply`` takes them with a list of edits per document:
``start``, ``end`` (UTF-8 byte offsets into the stored text, end exclusive) and ``text``; all offsets mean the stored
text, and edits at one place stand in the order of (start, end, text). Overlapping edits are an error.

Null texts count as empty: no tokens. Null edit lists change nothing. Rows are independent: repeated rows repeat, a null
doc_id stays null. Columns beside doc_id and text (and edits) are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bipercolate.llm.common import text_blocks
from bipercolate.llm.spans import spans
from bipercolate.llm.tokens import byte_encoder, vocabulary

SEGMENT = 256
STATE = "doc_id long, text binary, sizes array<int>, tokens array<int>"
RESULT = f"{STATE}, n_tokens_before long, n_edits long, encoded_bytes long"
EDITS = "array<struct<start:int,end:int,text:string>>"


def cut_points(text: bytes, segment: int = SEGMENT) -> list[int]:
    """Ends of segments of about ``segment`` bytes."""
    x = np.frombuffer(text, np.uint8)
    safe = np.flatnonzero((x[:-1] > 32) & (x[:-1] < 127) & (x[1:] == 32)) + 1 if len(x) > 1 else np.empty(0, int)
    if not len(safe):
        return [len(text)]
    found = np.searchsorted(safe, np.arange(segment, len(text), segment))
    return [*np.unique(safe[found[found < len(safe)]]).tolist(), len(text)]


def _sure(before: int, after: int) -> bool:
    """Pre-tokens end between these bytes whatever stands around."""
    return 32 < before < 127 and after == 32


class CountTree:
    """Leaves of (bytes, tokens) under sums; ``sizes`` and ``tokens`` are heap-ordered, the root at 1."""

    def __init__(self, text: bytes, encode, sizes: np.ndarray | None = None, tokens: np.ndarray | None = None) -> None:
        self.text, self.encode, self.encoded_bytes = text, encode, 0
        if sizes is None:
            parts = self._parts(text)
            self._plant(np.array([len(x) for x in parts]), np.array(self._counts(parts)))
        else:
            self.sizes, self.tokens = sizes, tokens

    @staticmethod
    def _parts(text: bytes) -> list[bytes]:
        return [text[a:b] for a, b in pairwise([0, *cut_points(text)])]

    def _counts(self, parts: list[bytes]) -> list[int]:
        self.encoded_bytes += sum(map(len, parts))
        return [len(x) // 4 for x in self.encode(parts)]

    def _plant(self, sizes: np.ndarray, tokens: np.ndarray) -> None:
        """A tree over these leaves."""
        width = 1 << max(len(sizes) - 1, 0).bit_length()
        self.sizes, self.tokens = np.zeros(2 * width, np.int32), np.zeros(2 * width, np.int32)
        for tree, leaves in ((self.sizes, sizes), (self.tokens, tokens)):
            tree[width : width + len(leaves)] = leaves
            for level in range(width.bit_length() - 2, -1, -1):
                a, b = 1 << level, 2 << level
                tree[a:b] = tree[2 * a : 2 * b : 2] + tree[2 * a + 1 : 2 * b : 2]

    @property
    def total(self) -> int:
        return int(self.tokens[1])

    def leaf(self, offset: int) -> tuple[int, int, int]:
        """The last leaf with bytes that begins at or before a byte offset, where it begins, and where it ends."""
        node, start, width = 1, 0, len(self.sizes) // 2
        while node < width:
            node *= 2
            if offset >= start + self.sizes[node] and self.sizes[node + 1]:
                start += int(self.sizes[node])
                node += 1
        return node, start, start + int(self.sizes[node])

    def _set(self, node: int, size: int, tokens: int) -> None:
        by_size, by_tokens = size - self.sizes[node], tokens - self.tokens[node]
        while node:
            self.sizes[node] += by_size
            self.tokens[node] += by_tokens
            node //= 2

    def edit(self, start: int, end: int, new: bytes) -> None:
        """Put ``new`` in place of the bytes from ``start`` to ``end``."""
        self.edit_all([(start, end, new)])

    def edit_all(self, edits: list[tuple[int, int, bytes]]) -> None:
        """Make sorted edits that don't overlap: regions of segments first, then every new segment is encoded once."""
        regions, text, done, at = [], [], 0, 0
        while at < len(edits):
            first, last, left, right, part, at = self._region(edits, at)
            text += [self.text[done:left], part]
            done = right
            regions.append((first, last, self._parts(part) if part else []))
        text.append(self.text[done:])
        counts = iter(self._counts([x for _, _, parts in regions for x in parts]))
        leaves = [(first, last, [(len(x), next(counts)) for x in parts]) for first, last, parts in regions]
        if all(len(parts) <= last - first + 1 for first, last, parts in leaves):
            for first, last, parts in leaves:
                for k in range(last - first + 1):
                    self._set(first + k, *(parts[k] if k < len(parts) else (0, 0)))
        else:
            self._regrow(leaves)
        self.text = b"".join(text)

    def _region(self, edits: list[tuple[int, int, bytes]], at: int) -> tuple[int, int, int, int, bytes, int]:
        """First and last leaf, their bytes from left to right, what stands there after the edits from ``at`` on, and the next edit."""
        start, end, new = edits[at]
        if not 0 <= start <= end <= len(self.text):
            raise ValueError(f"edit {start}:{end} lies outside a text of {len(self.text)} bytes")
        first, left, _ = self.leaf(start)
        last, _, right = self.leaf(max(end - 1, start))
        body, done, at = [self.text[left:start], new], end, at + 1
        while True:
            while at < len(edits) and edits[at][0] <= right:
                start, end, new = edits[at]
                if end > len(self.text):
                    raise ValueError(f"edit {start}:{end} lies outside a text of {len(self.text)} bytes")
                body += [self.text[done:start], new]
                done, at = end, at + 1
                if end > right:
                    last, _, right = self.leaf(end - 1)
            part = b"".join([*body, self.text[done:right]])
            if left and not (part and _sure(self.text[left - 1], part[0])):
                first, start, _ = self.leaf(left - 1)
                body.insert(0, self.text[start:left])
                left = start
            elif right < len(self.text) and not (part and _sure(part[-1], self.text[right])):
                last, _, right = self.leaf(right)
            else:
                return first, last, left, right, part, at

    def _regrow(self, regions: list[tuple[int, int, list[tuple[int, int]]]]) -> None:
        """A new tree where regions have more leaves than before; no text is encoded for it."""
        width = len(self.sizes) // 2
        rows, done = [], width
        for first, last, parts in regions:
            rows += [(self.sizes[done:first], self.tokens[done:first]), ([a for a, _ in parts], [b for _, b in parts])]
            done = last + 1
        rows.append((self.sizes[done:], self.tokens[done:]))
        sizes, tokens = (np.concatenate([np.asarray(x[k], np.int32) for x in rows]) for k in (0, 1))
        self._plant(sizes[sizes > 0], tokens[sizes > 0])


def _lists(xs: list[np.ndarray]) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, xs)]), pa.int32()), pa.array(np.concatenate(xs), pa.int32()))


def _builder(vocabulary_path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = byte_encoder(vocabulary_path).encode
        for batch in batches:
            for start, texts in text_blocks(batch):
                trees = [CountTree(x, encode) for x in texts]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(start, len(texts)), pa.array(texts, pa.binary()), _lists([x.sizes for x in trees]), _lists([x.tokens for x in trees])], ["doc_id", "text", "sizes", "tokens"])

    return run


def _changes(edits: list[dict] | None) -> list[tuple[int, int, bytes]]:
    changes = sorted((x["start"], x["end"], (x["text"] or "").encode()) for x in edits or ())
    if any(a[1] > b[0] for a, b in pairwise(changes)):
        raise ValueError("edits overlap")
    return changes


def _editor(vocabulary_path: str, planted: bool):
    """For mapInArrow: texts with edits (and with their trees, if ``planted``) to edited texts and trees."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = byte_encoder(vocabulary_path).encode
        for batch in batches:
            edits = batch.column("edits")
            for start, texts in text_blocks(batch):
                trees, before, n_edits = [], [], []
                for k, text in enumerate(texts, start):
                    old = [batch.column(c)[k].values.to_numpy().copy() for c in ("sizes", "tokens")] if planted else []
                    tree = CountTree(text, encode, *old)
                    tree.encoded_bytes = 0
                    before.append(tree.total)
                    changes = _changes(edits[k].as_py())
                    tree.edit_all(changes)
                    trees.append(tree)
                    n_edits.append(len(changes))
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("doc_id").slice(start, len(texts)), pa.array([x.text for x in trees], pa.binary()), _lists([x.sizes for x in trees]),
                        _lists([x.tokens for x in trees]), pa.array(before, pa.int64()), pa.array(n_edits, pa.int64()), pa.array([x.encoded_bytes for x in trees], pa.int64()),
                    ],
                    [x.split()[0] for x in RESULT.split(", ")],
                )

    return run


def build(docs: DataFrame, vocabulary_path: str | None = None) -> DataFrame:
    """doc_id, text (UTF-8), and its tree: sizes and tokens, whose element 1 (from 0) is the document's total."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return rows.mapInArrow(_builder(vocabulary_path or vocabulary("byte_bpe_50k.json")), STATE)


def apply(state: DataFrame, vocabulary_path: str | None = None) -> DataFrame:
    """``state`` with a column ``edits``, after these edits; with their number and the bytes that were encoded for them.

    A ``state`` without trees (doc_id, text) gets them on the way: one pass builds and edits.
    """
    planted = "sizes" in state.columns
    rows = state.select("doc_id", "text", *(["sizes", "tokens"] if planted else []), F.col("edits").cast(EDITS))
    return rows.mapInArrow(_editor(vocabulary_path or vocabulary("byte_bpe_50k.json"), planted), RESULT)


def counts(state: DataFrame) -> DataFrame:
    """doc_id, n_tokens."""
    return state.select("doc_id", F.element_at("tokens", 2).cast("long").alias("n_tokens"))


def masking_edits(text: Column, pattern: str, mark: str) -> Column:
    """Edits that put ``mark`` in place of every match of ``pattern`` in a text column: a native expression."""
    found = spans(text, pattern, "", 0, text.rlike(pattern), F.octet_length)
    return F.transform(found, lambda s: F.struct(s["start"].cast("int").alias("start"), s["end"].cast("int").alias("end"), F.lit(mark).alias("text")))


def count_and_mask(docs: DataFrame, pattern: str, mark: str) -> DataFrame:
    """Counts before and after masking every match: doc_id, n_tokens, n_edits, n_tokens_after, n_bytes_after, encoded_bytes."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    edited = apply(rows.withColumn("edits", masking_edits(F.col("text"), pattern, mark)))
    after = F.element_at("tokens", 2).cast("long").alias("n_tokens_after")
    return edited.select("doc_id", F.col("n_tokens_before").alias("n_tokens"), "n_edits", after, F.octet_length("text").cast("long").alias("n_bytes_after"), "encoded_bytes")

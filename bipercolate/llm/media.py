"""Media columns: payloads cut by content, stored once per chunk, put together again from ordered chunk lists.

A text's payload is its UTF-8 bytes, padded with bytes 255 to a positive multiple of 576. Its media form is a mono WAV file
of 8-bit samples, one per byte. A rolling gear hash cuts the samples into chunks where its low bits are zero, so equal passages
make equal chunks wherever they stand. The file's header follows from the number of samples, so it is rebuilt, not stored.

* Chunk digests are deduplicated by a grouping: the first place (doc, position) that holds a chunk owns it.
* The store has a row per document: its ordered chunk list (owner of each chunk) and, in one compressed block, only the
  chunks that it owns. Documents that own all of theirs need no join to be read.
* The others fetch their missing chunks from the owners' rows by a join on the owner; only those rows' chunks move.
* Every media file is rebuilt, its digest compared, and features are computed from the samples that were read.

Which documents lack chunks is sent to the executors while a count shows that they are few (``BROADCAST_IDS``), else
joined by a shuffle. Null texts count as empty; repeated rows share their chunks; rows that repeat a doc_id, or have none, keep apart
by a row key made of doc_id and text digest; no rows make an empty store.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from bipercolate.checkpoints import cut, shared_path
from bipercolate.llm.common import BROADCAST_IDS, text_blocks

UNIT, PAD, RATE = 576, b"\xff", 8000
#: Chunk sizes: never below the least, cut where MASK_BITS low bits of the gear hash are zero, never above the most.
LEAST_CHUNK, MASK_BITS, MOST_CHUNK = 512, 11, 16384
HEADER = 44
#: Bytes of a row key.
KEY = 16
STORE = "doc_id long, key binary, n_bytes long, media_sha256 string, chunks array<struct<n:int,owner:binary,at:int>>, own binary"
FEATURES = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_chunks long"


def gears() -> np.ndarray:
    """A fixed random number for each byte."""
    return np.random.default_rng(2024).integers(0, 2**32, 256, np.uint32)


def payload(text: bytes) -> bytes:
    return text + PAD * (max(UNIT, -(-len(text) // UNIT) * UNIT) - len(text))


def media(samples: bytes) -> bytes:
    """A WAV file: RIFF header, PCM format chunk (mono, 8 bits), data."""
    head = b"RIFF" + struct.pack("<I", HEADER - 8 + len(samples)) + b"WAVEfmt " + struct.pack("<IHHIIHH", 16, 1, 1, RATE, RATE, 1, 8)
    return head + b"data" + struct.pack("<I", len(samples)) + samples


def samples(file: bytes) -> bytes:
    """The samples of a WAV file as ``media`` writes it."""
    if file[:4] != b"RIFF" or file[36:40] != b"data" or struct.unpack_from("<I", file, 40)[0] != len(file) - HEADER:
        raise ValueError("not a WAV file of this form")
    return file[HEADER:]


def cuts(data: bytes, gear: np.ndarray) -> list[int]:
    """Ends of the chunks of some samples.

    The gear hash of a place, the sum of gear[byte k places back] << k, is built by doubling; its low MASK_BITS bits
    depend on the last MASK_BITS bytes.
    """
    hashes, width = gear[np.frombuffer(data, np.uint8)], 1
    while width < MASK_BITS:
        longer = hashes.copy()
        longer[width:] += hashes[:-width] << np.uint32(width)
        hashes, width = longer, 2 * width
    places = (np.flatnonzero(hashes & np.uint32((1 << MASK_BITS) - 1) == 0) + 1).tolist()
    ends, start = [], 0
    for at in [*places, len(data)]:
        while at - start > MOST_CHUNK:
            start += MOST_CHUNK
            ends.append(start)
        if at - start >= LEAST_CHUNK and len(data) - at >= LEAST_CHUNK or at == len(data) and at > start:
            ends.append(at)
            start = at
    return ends


def _files(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, int, int, bytes, list[int], bytes]]:
    """``(batch, row, text size, samples, chunk ends, row key)`` of every document."""
    gear = gears()
    for batch in batches:
        ids = batch.column("doc_id").to_pylist()
        for first, texts in text_blocks(batch):
            for k, text in enumerate(texts):
                filled, of = payload(text), ids[first + k]
                key = hashlib.sha256(b"%s:%s" % (b"" if of is None else str(of).encode(), text)).digest()[:KEY]
                yield batch, first + k, len(text), filled, cuts(filled, gear), key


def _row_key() -> Column:
    """The same key as ``_files`` makes, of columns doc_id and text."""
    of, text = F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.coalesce("text", F.lit(""))
    return F.unhex(F.substring(F.sha2(F.concat(of, F.lit(":"), text).cast("binary"), 256), 1, 2 * KEY))


def _digest(chunk: bytes | memoryview) -> bytes:
    return hashlib.blake2b(chunk, digest_size=16).digest()


def _table(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    columns = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(c, k.type) for c, k in zip(columns, schema, strict=True)], schema=schema)


def _listing(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Digest, key and position of every chunk."""
    kinds = pa.schema([("digest", pa.binary()), ("key", pa.binary()), ("at", pa.int32())])
    rows: list[tuple] = []
    for _, _, _, data, ends, key in _files(batches):
        view = memoryview(data)
        rows += [(_digest(view[a:b]), key, at) for at, (a, b) in enumerate(pairwise([0, *ends]))]
        if len(rows) > 20_000:
            yield _table(rows, kinds)
            rows = []
    if rows:
        yield _table(rows, kinds)


def _storing(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Store rows; a ``foreign`` list of (position, owner, its position) says which chunks others own."""
    import zstandard

    press = zstandard.ZstdCompressor(level=3)
    link = pa.struct([("n", pa.int32()), ("owner", pa.binary()), ("at", pa.int32())])
    kinds = pa.schema([
        ("doc_id", pa.int64()), ("key", pa.binary()), ("n_bytes", pa.int64()), ("media_sha256", pa.string()), ("chunks", pa.list_(link)), ("own", pa.binary()),
    ])
    rows: list[tuple] = []
    room = 4 << 20
    for batch, row, n, data, ends, key in _files(batches):
        elsewhere = {x["at"]: (x["owner"], x["owner_at"]) for x in batch.column("foreign")[row].as_py() or ()}
        chunks, own = [], []
        for at, (a, b) in enumerate(pairwise([0, *ends])):
            owner, owner_at = elsewhere.get(at, (None, at))
            chunks.append({"n": b - a, "owner": owner, "at": owner_at})
            if owner is None:
                own.append(data[a:b])
        packed = press.compress(b"".join(own))
        rows.append((batch.column("doc_id")[row].as_py(), key, n, hashlib.sha256(media(data)).hexdigest(), chunks, packed))
        room -= len(packed) + 100 * len(chunks)
        if room < 0 or len(rows) >= 2000:
            yield _table(rows, kinds)
            rows, room = [], 4 << 20
    if rows:
        yield _table(rows, kinds)


def write(docs: DataFrame, path: str, broadcast: int = BROADCAST_IDS) -> None:
    """Store the media of ``docs`` (doc_id, text) in ``path``, each distinct chunk once."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    listed = cut(rows.mapInArrow(_listing, "digest binary, key binary, at int"))  # some 40 bytes for 2 KB of media
    # Copies of one row have one key: they own the same chunks, and each stores them.
    owners = listed.groupBy("digest").agg(F.min(F.struct("key", "at")).alias("own"), F.count("*").alias("n")).filter("n > 1").select("digest", "own")
    foreign = listed.join(owners, "digest").filter("key <> own.key or at <> own.at").distinct()
    link = F.struct("at", F.col("own.key").alias("owner"), F.col("own.at").alias("owner_at"))
    foreign = cut(foreign.groupBy("key").agg(F.collect_list(link).alias("foreign")))  # a row per document that lacks chunks, as long as its chunk list
    keyed = rows.withColumn("key", _row_key()).join(_small(foreign, "foreign", broadcast), "key", "left")
    keyed.select("doc_id", "text", "foreign").mapInArrow(_storing, STORE).write.option("compression", "none").parquet(path)


def _small(keyed: DataFrame, listed: str, most: int) -> DataFrame:
    """A materialised table, marked for broadcast if it has at most ``most`` rows and elements of ``listed`` in all."""
    n = keyed.select(F.size(listed).alias("n")).limit(most + 1).agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    return F.broadcast(keyed) if max(n) <= most else keyed


def _rows(batch: pa.RecordBatch) -> Iterator[dict]:
    """The rows of a batch, one at a time."""
    for k in range(batch.num_rows):
        yield batch.slice(k, 1).to_pylist()[0]


def _chunks_of(own: bytes, chunks: list[dict]) -> Iterator[tuple[int, bytes]]:
    """Position and bytes of the chunks that a row owns."""
    import zstandard

    data, start = zstandard.ZstdDecompressor().decompress(own), 0
    for at, chunk in enumerate(chunks):
        if chunk["owner"] is None:
            yield at, data[start : start + chunk["n"]]
            start += chunk["n"]


def _lending(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The chunks of owners that others want: key, position, bytes (compressed)."""
    import zstandard

    press = zstandard.ZstdCompressor(level=3)
    kinds = pa.schema([("owner", pa.binary()), ("owner_at", pa.int32()), ("chunk", pa.binary())])
    for batch in batches:
        rows: list[tuple] = []
        for row in _rows(batch):
            wanted = set(row["wanted"])
            rows += [(row["key"], at, press.compress(x)) for at, x in _chunks_of(row["own"], row["chunks"]) if at in wanted]
            if len(rows) >= 2000:
                yield _table(rows, kinds)
                rows = []
        if rows:
            yield _table(rows, kinds)


def feature(data: bytes) -> str:
    """Mean, root mean square and zero crossings of the samples (128 is silence), and their spectrum's centroid over eight bands."""
    x = np.frombuffer(data, np.uint8).astype(np.float64) - 128
    power = np.abs(np.fft.rfft(x[: len(x) // UNIT * UNIT].reshape(-1, UNIT), axis=1)) ** 2
    bands = power.mean(axis=0)[1:].reshape(8, -1).sum(axis=1)
    crossings = int(((x[1:] >= 0) != (x[:-1] >= 0)).sum())
    centroid = float(bands @ np.arange(8) / bands.sum()) if bands.sum() > 0 else 0.0
    return f"mean={x.mean():.4f};rms={np.sqrt((x * x).mean()):.4f};crossings={crossings};centroid={centroid:.4f}"


def _rebuilt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    import zstandard

    unpress = zstandard.ZstdDecompressor()
    kinds = pa.schema([(x.split()[0], pa.string() if x.endswith("string") else pa.int64()) for x in FEATURES.split(", ")])
    for batch in batches:
        rows = []
        for row in _rows(batch):
            parts = dict(_chunks_of(row["own"], row["chunks"]))
            parts |= {x["at"]: unpress.decompress(x["chunk"]) for x in row["borrowed"] or ()}
            file = media(b"".join(parts[at] for at in range(len(row["chunks"]))))
            sha = hashlib.sha256(file).hexdigest()
            if sha != row["media_sha256"]:
                raise ValueError(f"document {row['doc_id']}: the stored media doesn't match its digest")
            data = samples(file)
            rows.append((
                row["doc_id"], row["n_bytes"], len(data), hashlib.sha256(data).hexdigest(), zlib.crc32(data[-32:]), len(file), sha, feature(data), len(row["chunks"]),
            ))
        if rows:
            yield _table(rows, kinds)


def read(spark: SparkSession, path: str, broadcast: int = BROADCAST_IDS) -> DataFrame:
    """Rebuild and verify all media in ``path``; one row of digests and features per document."""
    store = spark.read.schema(STORE).parquet(path)
    lacking = F.exists("chunks", lambda c: c["owner"].isNotNull())
    no_loans = F.lit(None).cast("array<struct<at:int,chunk:binary>>").alias("borrowed")
    whole = store.filter(~lacking).select("doc_id", "n_bytes", "media_sha256", "chunks", "own", no_loans)
    links = store.select("key", "chunks").filter(lacking).distinct().select("key", F.posexplode("chunks").alias("at", "c"))
    refs = cut(links.filter("c.owner is not null").select("key", "at", F.col("c.owner").alias("owner"), F.col("c.at").alias("owner_at")))
    wanted = cut(refs.groupBy(F.col("owner").alias("key")).agg(F.collect_set("owner_at").alias("wanted")))
    lenders = store.select("key", "chunks", "own").join(_small(wanted, "wanted", broadcast), "key")
    loans = lenders.mapInArrow(_lending, "owner binary, owner_at int, chunk binary")
    loans = loans.groupBy("owner", "owner_at").agg(F.first("chunk").alias("chunk"))
    # A document's own chunks: as long as the document.
    borrowed = refs.join(loans, ["owner", "owner_at"]).groupBy("key").agg(F.collect_list(F.struct("at", "chunk")).alias("borrowed"))
    patched = store.filter(lacking).join(borrowed, "key").select("doc_id", "n_bytes", "media_sha256", "chunks", "own", "borrowed")
    return whole.union(patched).mapInArrow(_rebuilt, FEATURES)


def round_trip(docs: DataFrame) -> DataFrame:
    path = shared_path(docs.sparkSession, "media")
    write(docs, path)
    return read(docs.sparkSession, path)

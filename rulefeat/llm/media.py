"""Media columns: payloads in content-defined chunks, each distinct shared chunk stored once.

A payload is cut where a rolling gear hash of its last 32 bytes has `CUT_BITS` leading zeros. The stored form of a payload is a head with its ordered list of chunks
(digest and length) and the chunks themselves; chunks that several payloads
share stand under their digest, once for each task that meets them, and the payload refers to them; all other chunks stand with their payload. `store_media` writes that table,
`read_media` rebuilds every payload from it: it joins the references to the shared chunks, checks each chunk against its digest, and puts the payload together in the order of the list.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import SMALL_BATCHES, materialise, settings, ship_package, trim_memory

UNIT, FILL = 576, 255
LEAST_CHUNK, MOST_CHUNK, CUT_BITS = 256, 8192, 10
MAGIC = b"CHUNKS01"
#: Bits of the table that tells chunks that may be shared; of fixed size whatever the data (2 MiB). A chance hit stores a chunk apart, no more.
SHARED_BITS = 24
RESULT = "n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
FIELDS = [f.split()[0] for f in RESULT.split(", ")]


@lru_cache(1)
def gear() -> np.ndarray:
    """A fixed 32-bit value for each byte."""
    return np.array([int.from_bytes(hashlib.blake2b(bytes([b]), digest_size=4).digest(), "little") for b in range(256)], np.uint32)


def payload_of(text: str | None) -> tuple[int, bytes]:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return len(raw), raw + bytes([FILL]) * (max(1, -(-len(raw) // UNIT)) * UNIT - len(raw))


def cut_points(payload: bytes) -> list[int]:
    """Ends of the chunks of a payload, the last one included."""
    h = gear()[np.frombuffer(payload, np.uint8)]
    for step in (1, 2, 4, 8, 16):  # doubling: after these, each place has the sum over its last 32 bytes, shifted by age
        h[step:] = h[step:] + (h[:-step] << np.uint32(step))
    ends, start, n = [], 0, len(payload)
    for at in (np.flatnonzero(h >> np.uint32(32 - CUT_BITS) == 0) + 1).tolist():
        while at - start > MOST_CHUNK:
            ends.append(start := start + MOST_CHUNK)
        if at - start >= LEAST_CHUNK and at < n:
            ends.append(start := at)
    while n - start > MOST_CHUNK:
        ends.append(start := start + MOST_CHUNK)
    return [*ends, n]


def digest_of(chunk: bytes) -> bytes:
    return hashlib.blake2b(chunk, digest_size=16).digest()


def chunks_of(payload: bytes) -> list[tuple[bytes, bytes]]:
    """(digest, bytes) in order."""
    start, out = 0, []
    for end in cut_points(payload):
        part = payload[start:end]
        out.append((digest_of(part), part))
        start = end
    return out


def head_of(n_bytes: int, chunks: list[tuple[bytes, int]]) -> bytes:
    return MAGIC + struct.pack("<QI", n_bytes, len(chunks)) + b"".join(d + struct.pack("<I", n) for d, n in chunks)


def parse_head(head: bytes) -> tuple[int, list[tuple[bytes, int]]]:
    n_bytes, n = struct.unpack_from("<QI", head, len(MAGIC))
    at = len(MAGIC) + 12
    return n_bytes, [(head[at + 20 * i : at + 20 * i + 16], struct.unpack_from("<I", head, at + 20 * i + 16)[0]) for i in range(n)]


def read_back(head: bytes, parts: list[bytes]) -> tuple:
    """The result's fields, from the stored head and the stored chunks; raises if a chunk isn't what the head says."""
    n_bytes, listed = parse_head(head)
    if head[: len(MAGIC)] != MAGIC or len(listed) != len(parts):
        raise ValueError("a stored payload lacks chunks")
    whole = hashlib.sha256(head)
    for (digest, length), part in zip(listed, parts):
        if len(part) != length or digest_of(part) != digest:
            raise ValueError("a stored chunk is damaged")
        whole.update(part)
    payload = b"".join(parts)
    counts = np.bincount(np.frombuffer(payload, np.uint8), minlength=256)
    share = counts[counts > 0] / len(payload)
    mean = float((counts * np.arange(256)).sum() / len(payload))
    spread = float(np.sqrt(max(0.0, (counts * (np.arange(256) - mean) ** 2).sum() / len(payload))))
    feature = f"chunks={len(parts)};mean={mean:.4f};spread={spread:.4f};entropy={float(-(share * np.log2(share)).sum()):.4f}"
    return n_bytes, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(head) + len(payload), whole.hexdigest(), feature


def _shared_bits(docs: DataFrame, text_col: str) -> bytes:
    """A bit for each place of a digest that two rows or more hold (or one row twice)."""

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                found: dict[bytes, int] = {}
                for text in batch.column(0).slice(start, 256):
                    for digest, _ in chunks_of(payload_of(text.as_py())[1]):
                        found[digest] = found.get(digest, 0) + 1
                yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.binary()), pa.array(list(found.values()), pa.int64())], ["digest", "n"])

    held = docs.select(F.col(text_col).cast("string").alias("text")).mapInArrow(places, "digest binary, n long")
    shared = held.groupBy("digest").agg(F.sum("n").alias("n")).where("n > 1")
    place = F.conv(F.hex(F.substring("digest", 1, 3)), 16, 10).cast("long") + 1  # 24 bits; Spark's bitmaps count from 1
    words = shared.select(place.alias("p")).groupBy(F.bitmap_bucket_number("p").alias("word")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("bits"))
    out = np.zeros((1 << SHARED_BITS) // 8, np.uint8)
    for row in words.collect():  # at most 2^24 / 32768 rows of 4 KiB
        at = (row["word"] - 1) * 4096
        bits = np.frombuffer(row["bits"], np.uint8)
        out[at : at + len(bits)] |= bits
    return out.tobytes()


def may_be_shared(bits: np.ndarray, digest: bytes) -> bool:
    at = int.from_bytes(digest[:3], "big")
    return bool(bits[at >> 3] >> (at & 7) & 1)


#: The media table. kind 0: a payload of its own (doc_id, head, its chunks one after the other). 1: a row (doc_id) whose payload is `media`. 2: a shared chunk under its digest.
#: 3: a payload with shared chunks (media, head, its own chunks one after the other). 4: a shared chunk (digest) at place seq of `media`.
STORED = "kind int, doc_id {id_type}, media binary, seq int, digest binary, chunk binary, head binary"


def store_media(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", path: str | None = None) -> DataFrame:
    """The media table of docs (STORED), written to `path` (a folder that goes with the driver if None) and read again.

    Every payload's head and chunks are in it: chunks that several payloads share under their digest, all others with their payload.
    """
    spark = docs.sparkSession
    ship_package(spark)
    with settings(spark, SMALL_BATCHES):
        shared = spark.sparkContext.broadcast(_shared_bits(docs, text_col))
    schema = STORED.format(id_type=dict(docs.select(id_col).dtypes)[id_col])

    def store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.frombuffer(shared.value, np.uint8)
        written: set[bytes] = set()
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                part, rows = batch.slice(start, 256), []
                for doc_id, text in zip(part.column(0).to_pylist(), part.column(1)):
                    n_bytes, payload = payload_of(text.as_py())
                    chunks = chunks_of(payload)
                    head = head_of(n_bytes, [(d, len(c)) for d, c in chunks])
                    apart = [may_be_shared(bits, d) for d, _ in chunks]
                    if not any(apart):
                        rows.append((0, doc_id, None, None, None, payload, head))
                        continue
                    media = digest_of(head)
                    rows.append((1, doc_id, media, None, None, None, None))
                    if media in written:  # a text that this task has stored before
                        continue
                    if len(written) > 200_000:
                        written.clear()
                    written.add(media)
                    rows.append((3, None, media, None, None, b"".join(c for (_, c), away in zip(chunks, apart) if not away), head))
                    for seq, ((d, c), away) in enumerate(zip(chunks, apart)):
                        if away:
                            rows.append((4, None, media, seq, d, None, None))
                            if d not in written:
                                written.add(d)
                                rows.append((2, None, None, None, d, c, None))
                columns = list(zip(*rows)) or [[]] * len(names)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types)], names)
        written.clear()
        trim_memory()

    names, types = _arrow(schema)
    with settings(spark, SMALL_BATCHES):
        return materialise(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(store, schema), "media", path=path)


def _arrow(schema: str) -> tuple[list[str], list[pa.DataType]]:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    arrow = to_arrow_schema(_parse_datatype_string(schema))
    return arrow.names, arrow.types


def split_chunks(head: bytes, own: bytes, away: dict[int, bytes]) -> list[bytes]:
    """The stored chunks in the head's order: those of `away` at their places, the others off `own`; raises if `own` isn't used up."""
    at, parts = 0, []
    for seq, (_, length) in enumerate(parse_head(head)[1]):
        if seq in away:
            parts.append(away[seq])
        else:
            parts.append(own[at : at + length])
            at += length
    if at != len(own):
        raise ValueError("a stored payload has bytes that its head doesn't name")
    return parts


def read_media(stored: DataFrame, payload: bool = False) -> DataFrame:
    """One row per stored row: doc_id and the columns of RESULT (and, if asked, the payload rebuilt), from the table's rows and nothing else."""
    ship_package(stored.sparkSession)
    id_type = dict(stored.dtypes)["doc_id"]
    fields, made = (FIELDS + ["payload"], RESULT + ", payload binary") if payload else (FIELDS, RESULT)

    def fields_of(head: bytes, own: bytes, away: dict[int, bytes]) -> tuple:
        parts = split_chunks(head, own, away)
        out = read_back(head, parts)
        return (*out, b"".join(parts)) if payload else out

    alone_names, alone_types = _arrow(f"doc_id {id_type}, {made}")
    media_names, media_types = _arrow(f"media binary, {made}")

    def alone_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                part = batch.slice(start, 256)
                rows = [(i, *fields_of(head.as_py(), own.as_py(), {})) for i, head, own in zip(part.column(0).to_pylist(), part.column(1), part.column(2))]
                columns = list(zip(*rows)) or [[]] * len(alone_names)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, alone_types)], alone_names)
        trim_memory()

    def assemble(own: pa.Table, away: pa.Table) -> pa.Table:
        if not own.num_rows:
            raise ValueError("a stored payload lacks its head")
        at = dict(zip(away.column("seq").to_pylist(), away.column("chunk").to_pylist()))
        row = (own.column("media")[0].as_py(), *fields_of(own.column("head")[0].as_py(), own.column("chunk")[0].as_py(), at))
        return pa.Table.from_arrays([pa.array([x], t) for x, t in zip(row, media_types)], media_names)

    # tasks that hold the same text store it each: of rows of one digest any will do, as the digest check sees to their bytes
    table = stored.where("kind = 2").groupBy("digest").agg(F.any_value("chunk").alias("chunk"))
    places = stored.where("kind = 4").select("media", "seq", "digest").distinct()
    away = places.join(table, "digest").select(F.col("media").alias("media"), "seq", "chunk")
    # each task that met a text stored it: one of those rows is enough, so a hot text's group stays one row and its places
    own = stored.where("kind = 3").groupBy(F.col("media").alias("media")).agg(F.any_value(F.struct("head", "chunk")).alias("own")).select("media", "own.head", "own.chunk")
    whole = own.groupBy("media").cogroup(away.groupBy("media")).applyInArrow(assemble, f"media binary, {made}")
    alone = stored.where("kind = 0").select("doc_id", "head", "chunk").mapInArrow(alone_rows, f"doc_id {id_type}, {made}")
    joined = stored.where("kind = 1").select("doc_id", "media").join(whole, "media").select("doc_id", *fields)
    return alone.unionByName(joined)


def media_columns(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", path: str | None = None) -> DataFrame:
    """One row per input row: doc_id and the columns of RESULT, all from the media table as it is read again; with `path` that table stays there.

    A null text is an empty one, whose payload is one unit of fill bytes. Null ids and repeated rows count like others; other columns aren't read; an empty table gives an empty result.
    A stored form depends on the text alone.
    """
    return read_media(store_media(docs, text_col, id_col, path))

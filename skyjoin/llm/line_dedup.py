"""Removal of lines that many documents share, with two Bloom filters before any exact work.

Four scans of the texts, all of whole lines:

1. Each task puts the hashes of its line keys, as they come, into a once-seen and a twice-seen filter of a fixed number of bits. The
   tasks' filters merge block by block: a bit set once by two tasks counts as seen twice.
2. Only keys whose bits are all in the twice-seen filter are suspects. Their 128-bit digests with the document's id are
   written, shuffled, counted exactly, and the owner (largest id) of each confirmed key is found.
3. Documents without a suspect are finished in place.
4. The others meet their list of keys to drop by id.

The broadcast filter has at most 2**MOST_BITS bits whatever the input. Past its capacity, of some tens of millions of different
lines, more keys become suspects: that costs a shuffle of 24 bytes a line, in proportion to the input, and never changes a result.

Edge cases: a null or empty text is one empty line; keys count once per document however often they stand in it; rows
with the same id are one document for the count, and the owner's rows all keep the line; a null id ranks below all ids.
Input columns called n_lines or n_dropped are replaced; an empty table gives an empty one.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import SPACE, checkpointed, chunks, id_of, power_of_two, released, returning, salted_join, text_bytes, with_fields

MIN_CHARS, MIN_DOCS = 20, 3
#: Bits for each document, and the exponents between which a filter's size stays.
BITS_PER_DOC, LEAST_BITS, MOST_BITS, BLOCK_BITS, HASHES = 256, 20, 28, 20, 3


def line_key(line: bytes, least: int = MIN_CHARS) -> bytes | None:
    """The key of a line, or None where it has fewer code points than `least`."""
    key = line.strip(SPACE).lower()  # bytes.lower() changes A-Z alone
    n = len(key)
    if n < least or (n < 4 * least and not key.isascii() and len(key.decode("utf-8", "replace")) < least):
        return None
    return key


def digest(key: bytes) -> bytes:
    return hashlib.blake2b(key, digest_size=16).digest()


def digests(text: bytes, least: int) -> list[bytes | None]:
    """A digest for each line in order; None for short ones."""
    return [None if (key := line_key(line, least)) is None else digest(key) for line in text.split(b"\n")]


def positions(found: np.ndarray, bits: int) -> np.ndarray:
    """HASHES bit positions for each digest, given as two 64-bit halves."""
    with np.errstate(over="ignore"):
        step = found[:, 1:] | np.uint64(1)
        return (found[:, :1] + np.arange(HASHES, dtype=np.uint64) * step) & np.uint64((1 << bits) - 1)


def halves(found: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(found), np.uint64).reshape(-1, 2)


def _filters(bits: int, least: int):
    """Scan 1: rows of (block, part, once bits, twice bits) from each task."""

    def run(batches):
        once, twice = np.zeros((1 << bits) // 8, np.uint8), np.zeros((1 << bits) // 8, np.uint8)
        for batch in batches:
            for part in chunks(batch, 0):
                found = [d for text in text_bytes(part.column(0)) for d in {d for d in digests(text, least) if d}]
                at, n = np.unique(positions(halves(found), bits), return_counts=True)
                byte, bit = (at >> np.uint64(3)).astype(np.int64), np.uint8(128) >> (at & np.uint64(7)).astype(np.uint8)
                again = (n > 1) | (once[byte] & bit > 0)
                np.bitwise_or.at(twice, byte[again], bit[again])
                np.bitwise_or.at(once, byte, bit)
        size = (1 << min(bits, BLOCK_BITS)) // 8
        rows: dict[str, list] = {"block": [], "part": [], "once": [], "twice": []}
        for b in range(len(once) // size):
            if (own := once[b * size : (b + 1) * size]).any():
                rows["block"].append(b)
                rows["part"].append(TaskContext.get().partitionId() // 32)
                rows["once"].append(zlib.compress(own.tobytes(), 1))
                rows["twice"].append(zlib.compress(twice[b * size : (b + 1) * size].tobytes(), 1))
        if rows["block"]:
            yield pa.RecordBatch.from_pydict(rows, pa.schema([("block", pa.int32()), ("part", pa.int32()), ("once", pa.binary()), ("twice", pa.binary())]))

    return run


def _merge(rows: pd.DataFrame) -> pd.DataFrame:
    once = twice = None
    for a, b in zip(rows["once"], rows["twice"], strict=True):
        a, b = (np.frombuffer(zlib.decompress(x), np.uint8) for x in (a, b))
        once, twice = (a, b) if once is None else (once | a, twice | b | (once & a))
    return pd.DataFrame({"block": rows["block"].iloc[:1], "part": rows["part"].iloc[:1], "once": [zlib.compress(once.tobytes(), 1)], "twice": [zlib.compress(twice.tobytes(), 1)]})


def twice_seen(docs: DataFrame, bits: int, least: int = MIN_CHARS) -> bytes:
    """The packed twice-seen filter over all texts: 2**bits bits, merged in two steps so that no group grows with the tasks."""
    schema = "block int, part int, once binary, twice binary"
    rows = docs.select("text").mapInArrow(returning(_filters(bits, least)), schema).groupBy("block", "part").applyInPandas(_merge, schema)
    rows = rows.groupBy("block").applyInPandas(_merge, schema)
    size = (1 << min(bits, BLOCK_BITS)) // 8
    out = np.zeros((1 << bits) // 8, np.uint8)
    for row in rows.select("block", "twice").collect():  # at most 2**(MOST_BITS - BLOCK_BITS) rows
        out[row.block * size : (row.block + 1) * size] = np.frombuffer(zlib.decompress(row.twice), np.uint8)
    return out.tobytes()


def suspected(found: list[bytes], twice: np.ndarray, bits: int) -> np.ndarray:
    if not found:
        return np.zeros(0, bool)
    at = positions(halves(found), bits)
    return ((twice[(at >> np.uint64(3)).astype(np.int64)] >> (7 - (at & np.uint64(7))).astype(np.uint8)) & 1).all(axis=1)


def _suspects(twice, bits: int, least: int):
    """Scan 2: (id, key digest) of each distinct suspected line of a document."""

    def run(batches):
        flat = np.frombuffer(twice.value, np.uint8)
        for whole in batches:
            for batch in chunks(whole, 1):
                own = [list({d for d in digests(t, least) if d}) for t in text_bytes(batch.column(1))]
                lengths = np.fromiter(map(len, own), np.int64, len(own))
                found = [d for x in own for d in x]
                at = np.flatnonzero(suspected(found, flat, bits))
                ids = np.repeat(np.asarray(batch.column(0).to_numpy(zero_copy_only=False), np.int64), lengths)[at]
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array([found[i] for i in at], pa.binary())], ["id", "key"])

    return run


def _finish(twice, bits: int, least: int, names: list[str], clean: bool, drops: bool):
    """Scan 3: documents without (clean) or with a suspected line; the latter lose the keys in their last column."""

    def run(batches):
        flat = np.frombuffer(twice.value, np.uint8)
        for batch in (part for whole in batches for part in chunks(whole, whole.schema.get_field_index("text"))):
            body = text_bytes(batch.column(batch.schema.get_field_index("text")))
            own = [digests(t, least) for t in body]
            if drops:
                out, dropped = [], []
                for text, lines, gone in zip(body, own, batch.column(batch.num_columns - 1).to_pylist(), strict=True):
                    gone = set(gone or ())
                    kept = [x for x, d in zip(text.split(b"\n"), lines, strict=True) if d is None or d not in gone]
                    dropped.append(len(lines) - len(kept))
                    out.append(b"\n".join(kept))
                take, counts = pa.array(range(len(own))), [len(x) for x in own]
            else:
                lengths = np.fromiter((sum(d is not None for d in x) for x in own), np.int64, len(own))
                hit = suspected([d for x in own for d in x if d is not None], flat, bits)
                has = np.zeros(len(own), bool)
                has[np.repeat(np.arange(len(own)), lengths)[hit]] = True
                at = np.flatnonzero(~has if clean else has)
                take, counts, out = pa.array(at), [len(own[i]) for i in at], [body[i] for i in at]
                dropped = [0] * len(at)
            columns = [batch.column(batch.schema.get_field_index(n)).take(take) if n != "text" else pa.array(out, pa.binary()).cast(pa.string()) for n in names]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(counts, pa.int64()), pa.array(dropped, pa.int64())], [*names, "n_lines", "n_dropped"])

    return run


def dedup_lines(docs: DataFrame, least_chars: int = MIN_CHARS, least_docs: int = MIN_DOCS, bits: int | None = None) -> DataFrame:
    """docs with shared lines removed from text, and n_lines (before) and n_dropped beside it.

    docs needs doc_id and text; other columns stay. bits: the filters' size as a power of two, else from the row count.
    """
    spark = docs.sparkSession
    bits = bits or power_of_two(BITS_PER_DOC * docs.count(), LEAST_BITS, MOST_BITS)
    twice = spark.sparkContext.broadcast(twice_seen(docs, bits, least_chars))
    released()
    suspects = checkpointed(docs.select(id_of().alias("id"), "text").mapInArrow(returning(_suspects(twice, bits, least_chars)), "id long, key binary"))
    # (key, id) first: even a key of a third of all documents is spread, then counted by partial sums.
    owners = suspects.distinct().groupBy("key").agg(F.count("*").alias("n"), F.max("id").alias("owner")).filter(F.col("n") >= least_docs).select("key", "owner")
    gone = salted_join(suspects, owners, "key", "id").filter(F.col("id") != F.col("owner")).groupBy("id").agg(F.collect_set("key").alias("gone"))
    schema = with_fields(docs.schema, [T.StructField("n_lines", T.LongType()), T.StructField("n_dropped", T.LongType())])
    names = schema.names[:-2]
    clean = docs.mapInArrow(returning(_finish(twice, bits, least_chars, names, True, False)), schema)
    dirty = docs.mapInArrow(returning(_finish(twice, bits, least_chars, names, False, False)), schema)
    dirty = dirty.withColumn("__id", id_of()).join(gone.withColumnRenamed("id", "__id"), "__id", "left").select(*names, F.col("gone").alias("__gone"))
    return clean.unionByName(dirty.mapInArrow(returning(_finish(twice, bits, least_chars, names, False, True)), schema))


def digest_columns(docs: DataFrame) -> DataFrame:
    """What op9 returns: doc_id, n_lines, n_dropped and the digest of the kept text."""
    return dedup_lines(docs.select("doc_id", "text")).select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text"), 256).alias("kept_sha256"))


ORACLE = r"""
WITH lines AS (
  SELECT doc_id, u.line AS line, u.i AS i,
         translate(trim(u.line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents) d,
       LATERAL (SELECT unnest(parts) AS line, generate_subscripts(parts, 1) AS i) u
), shared AS (
  SELECT key, max(doc_id) AS owner FROM lines WHERE length(key) >= 20 GROUP BY key HAVING count(DISTINCT doc_id) >= 3
), marked AS (
  SELECT l.doc_id, l.line, l.i, s.owner IS NOT NULL AND s.owner <> l.doc_id AS gone FROM lines l LEFT JOIN shared s ON s.key = l.key
)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""

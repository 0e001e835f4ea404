"""Helpers shared by the training-data operators.

Table access, durable cuts of the lineage, skew-proof joins and vectorised
work on the bytes of a batch of texts.
"""

from __future__ import annotations

import hashlib
import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, StructField, StructType

#: Bytes of text that one vectorised step looks at together.
CHUNK_BYTES = 1 << 20
#: Most bytes that Spark hands to Python at once, so that long texts do not pile up.
ARROW_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small_batches(spark: SparkSession) -> None:
    """Bound the Arrow batches of this session by bytes; a setting that any session may change."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(ARROW_BYTES))


def durable_dir(spark: SparkSession) -> None:
    """Make sure that checkpoint() has a folder: the cluster's own where it names one."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", "") or tempfile.mkdtemp(prefix="pagesketch-"))


#: Rows that one file of a small kept table holds at least.
ROWS_PER_FILE = 1_000_000


def cut(df: DataFrame, rows: int | None = None) -> DataFrame:
    """Compute df once and keep it in the shared checkpoint folder.

    rows says about how many rows it has, for tables of a few numbers a row alone: such a table is kept in few files, one for each core or
    million rows. Tables with texts, sets or signatures are kept as their tasks write them.
    """
    spark = df.sparkSession
    durable_dir(spark)
    small_batches(spark)
    if rows is not None:
        df = df.coalesce(max(spark.sparkContext.defaultParallelism, -(-rows // ROWS_PER_FILE)))
    return df.checkpoint(eager=True)


def crc_of_id(col: Column) -> Column:
    """crc32 of an id written as text."""
    return F.crc32(col.cast("string").cast("binary"))


def join_with_hot_keys(left: DataFrame, right: DataFrame, key: list[str], weight: str, total: int, shares: int = 1000) -> DataFrame:
    """Left join to a table with one row a key, whose weight says how often left has the key.

    Keys with at least 1/shares of all rows are fewer than shares + 1, so that
    they are broadcast; every other key is too small to skew the shuffle. Rows
    with a hot key, or with none, get a spread key that matches nothing in the
    second join.
    """
    values = [c for c in right.columns if c not in key]
    hot = right.where(F.col(weight) * F.lit(shares) >= F.lit(total))
    cold = right.where(F.col(weight) * F.lit(shares) < F.lit(total))
    first = left.join(F.broadcast(hot.select(*key, *(F.col(c).alias(f"hot_{c}") for c in values))), key, "left")
    spread = [
        F.when(F.col(f"hot_{weight}").isNull(), F.struct(*key)).alias("join_key"),
        F.when(F.col(f"hot_{weight}").isNotNull(), F.monotonically_increasing_id()).alias("join_salt"),
    ]
    first = first.select("*", *spread)
    cold = cold.select(F.struct(*key).alias("join_key"), F.lit(None).cast("bigint").alias("join_salt"), *(F.col(c).alias(f"cold_{c}") for c in values))
    out = first.join(cold, first["join_key"].eqNullSafe(cold["join_key"]) & first["join_salt"].eqNullSafe(cold["join_salt"]), "left")
    return out.select(*left.columns, *(F.coalesce(f"hot_{c}", f"cold_{c}").alias(c) for c in values))


ROW_KEY = "kept_row_key"


def with_text_key(docs: DataFrame, key: Callable[[bytes], bytes], text_col: str) -> DataFrame:
    """All columns of docs and the key of each text, null as empty, in the column ROW_KEY."""
    schema = StructType([*docs.schema.fields, StructField(ROW_KEY, BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = pa.array([key(x.as_py() or b"") for x in batch.column(text_col).cast(pa.binary())], pa.binary())
            yield pa.RecordBatch.from_arrays([*batch.columns, keys], [*batch.schema.names, ROW_KEY])

    return docs.mapInArrow(run, schema)


def rows_that_stay(docs: DataFrame, stay: DataFrame, id_col: str, text_col: str, key: Callable[[bytes], bytes]) -> DataFrame:
    """The rows of docs whose id and text key are in the columns stay_id and stay_key, one of each, and all rows without an id.

    Two texts under one id are two rows; only the same text under the same id is a repeated row. One shuffle of the rows.
    """
    named = with_text_key(docs.where(F.col(id_col).isNotNull()), key, text_col)
    stay = stay.select("stay_id", "stay_key").distinct()
    found = named.join(stay, (named[id_col] == F.col("stay_id")) & (named[ROW_KEY] == F.col("stay_key")), "left_semi")
    return found.dropDuplicates([id_col, ROW_KEY]).drop(ROW_KEY).unionByName(docs.where(F.col(id_col).isNull()))


# --- bytes of a batch of texts -------------------------------------------------

SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
TO_SPACE = bytes(32 if SPACE[i] else i for i in range(256))
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def one_space(raw: bytes) -> bytes:
    """Each run of white space becomes one space."""
    raw = raw.translate(TO_SPACE)
    while b"  " in raw:
        raw = raw.replace(b"  ", b" ")
    return raw


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of splitmix64, for uint64 arrays."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


GOLDEN = np.uint64(0x9E3779B97F4A7C15)
#: The initial state of SipHash.
SIP_START = np.array([0x736F6D6570736575, 0x646F72616E646F6D, 0x6C7967656E657261, 0x7465646279746573], np.uint64)
#: The key of the words' fingerprints.
SALT = b"pagesketch-words"
#: Longer words are hashed one by one.
SIP_BYTES = 256


def _turn(x: np.ndarray, bits: int) -> np.ndarray:
    return x << np.uint64(bits) | x >> np.uint64(64 - bits)


def _sip_rounds(v: list[np.ndarray], times: int) -> list[np.ndarray]:
    a, b, c, d = v
    for _ in range(times):
        a, c = a + b, c + d
        b, d = _turn(b, 13) ^ a, _turn(d, 16) ^ c
        a, c = _turn(a, 32) + d, c + b
        b, d = _turn(b, 17) ^ c, _turn(d, 21) ^ a
        c = _turn(c, 32)
    return [a, b, c, d]


def siphash(data: np.ndarray, offsets: np.ndarray, key: bytes = SALT) -> np.ndarray:
    """SipHash-2-4, 64 bits, of the byte strings that lie end to end in data, all of them side by side."""
    sizes = np.diff(offsets)
    lanes = sizes // 8 + 1
    first = np.cumsum(lanes) - lanes
    body = np.zeros(int(lanes.sum()) * 8, np.uint8)
    body[np.arange(len(data)) + np.repeat(first * 8 - offsets[:-1], sizes)] = data
    body[(first + lanes) * 8 - 1] = sizes & 0xFF
    body = body.view("<u8")
    order = np.argsort(-lanes, kind="stable")
    first, lanes = first[order], lanes[order]
    k0, k1 = np.frombuffer(key, "<u8")
    v = [np.full(len(lanes), x ^ k) for x, k in zip(SIP_START, (k0, k1, k0, k1), strict=True)]
    for step in range(int(lanes.max(initial=0))):
        n = int(np.searchsorted(-lanes, -step, "left"))
        m = body[first[:n] + step]
        part = _sip_rounds([v[0][:n], v[1][:n], v[2][:n], v[3][:n] ^ m], 2)
        part[0] = part[0] ^ m
        for all_rows, rows in zip(v, part, strict=True):
            all_rows[:n] = rows
    v[2] = v[2] ^ np.uint64(0xFF)
    a, b, c, d = _sip_rounds(v, 4)
    out = np.empty(len(lanes), np.uint64)
    out[order] = a ^ b ^ c ^ d
    return out


def fingerprints(words: pa.Array) -> np.ndarray:
    """64 bits of a keyed hash of each byte string, so that no two words are known or can be built to have the same."""
    n = len(words)
    offsets = np.frombuffer(words.buffers()[1], np.int64, n + 1, words.offset * 8)
    sizes = np.diff(offsets)
    data = np.frombuffer(words.buffers()[2], np.uint8) if words.buffers()[2] is not None else np.zeros(0, np.uint8)
    long = np.flatnonzero(sizes > SIP_BYTES)
    if not len(long):
        return siphash(data[offsets[0] : offsets[-1]], offsets - offsets[0])
    keep = sizes <= SIP_BYTES
    mask = np.repeat(keep, sizes)
    out = np.empty(n, np.uint64)
    out[keep] = siphash(data[offsets[0] : offsets[-1]][mask], np.concatenate([[0], np.cumsum(sizes[keep])]))
    for i in long:
        out[i] = int.from_bytes(hashlib.blake2b(words[i].as_py(), digest_size=8, key=SALT).digest(), "little")
    return out


def text_digest(raw: bytes) -> bytes:
    """128 bits of a keyed BLAKE2b."""
    return hashlib.blake2b(raw, digest_size=16, key=SALT).digest()


class Texts:
    """The bytes of consecutive rows of one Arrow column of texts, null as empty."""

    def __init__(self, column: pa.Array):
        n = len(column)
        if pa.types.is_null(column.type):
            self.data, self.offsets = np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
            return
        column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
        column = column.fill_null(b"") if column.null_count else column
        offsets = np.frombuffer(column.buffers()[1], np.int64, n + 1, column.offset * 8) if n else np.zeros(1, np.int64)
        self.offsets = offsets - offsets[0]
        whole = np.frombuffer(column.buffers()[2], np.uint8) if n and column.buffers()[2] is not None else np.zeros(0, np.uint8)
        self.data = whole[offsets[0] : offsets[-1]]

    def __len__(self) -> int:
        return len(self.offsets) - 1

    def lowered(self) -> Texts:
        out = object.__new__(Texts)
        out.data, out.offsets = LOWER[self.data], self.offsets
        return out

    def words(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Start and end byte of every word, and the number of words before each text."""
        inner = ~SPACE[self.data]
        first = inner.copy()
        first[1:] &= ~inner[:-1]
        edges = self.offsets[:-1][self.offsets[:-1] < self.offsets[1:]]
        first[edges] = inner[edges]
        starts = np.flatnonzero(first)
        last = inner
        last[:-1] &= ~inner[1:] | first[1:]
        ends = np.flatnonzero(last) + 1
        return starts, ends, np.searchsorted(starts, self.offsets)

    def ranges(self, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, pa.Array]:
        """A number for each byte range [start, end), equal for equal bytes alone, and the distinct ranges' bytes by number."""
        after = np.concatenate([np.zeros(1, np.int64), np.cumsum(ends - starts, dtype=np.int64)])
        inner = ~SPACE[self.data]
        if int(inner.sum()) == after[-1]:  # the ranges are all but the white space
            body = self.data[inner]
        else:
            body = self.data[np.arange(after[-1]) + np.repeat(starts - after[:-1], ends - starts)]
        column = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(after), pa.py_buffer(body)])
        found = column.dictionary_encode()
        return found.indices.to_numpy().astype(np.int64), found.dictionary

    def hashes(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """64-bit fingerprints of the byte ranges [start, end)."""
        if not len(starts):
            return np.zeros(0, np.uint64)
        codes, distinct = self.ranges(starts, ends)
        return fingerprints(distinct)[codes]


def run_codes(codes: np.ndarray, text_of: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """The places at which runs of width codes inside one text begin, and a number for each, equal for equal runs alone."""
    at = np.arange(max(0, len(codes) - width + 1))
    at = at[text_of[at] == text_of[at + width - 1]] if len(at) else at
    out = codes[at]
    for shift in range(1, width):
        out = pd.factorize(out * (int(codes.max(initial=0)) + 1) + codes[at + shift])[0].astype(np.int64)
    return at, out


def chunks(batch: pa.RecordBatch, column: str, limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of a batch with at most so many bytes of text, or one row."""
    sizes = pa.compute.fill_null(pa.compute.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False) if not pa.types.is_null(batch.column(column).type) else np.zeros(batch.num_rows)
    total, lo = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)]), 0
    while lo < batch.num_rows:
        hi = max(lo + 1, int(np.searchsorted(total, total[lo] + limit, "right")) - 1)
        yield batch.slice(lo, hi - lo)
        lo = hi


def over_chunks(work: Callable[[pa.RecordBatch], pa.RecordBatch], column: str = "text", limit: int = CHUNK_BYTES):
    """A function for mapInArrow that works through slices of bounded size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, column, limit):
                yield work(part)

    return run

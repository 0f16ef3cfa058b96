"""What several operators of this subpackage share: tables, the shared folder, batches and packed arrays."""

from __future__ import annotations

import ctypes
import zlib
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from embedvocab.sources.shared import stored

U64 = np.uint64
#: The bytes 0x20 and 0x09-0x0D separate words; bytes.split() splits at exactly these.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def columns(df: DataFrame, **kinds: str) -> DataFrame:
    """Only the named columns, cast; extra columns of the input, whatever their names, go."""
    return df.select(*(F.col(f"`{c}`").cast(kind).alias(c) for c, kind in kinds.items()))


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def written(df: DataFrame) -> DataFrame:
    """df as a Parquet table in the shared folder: cuts the lineage and survives lost executors; it goes when the application ends."""
    return stored(df)


def crc_remainder(doc_id: Column, modulus: int) -> Column:
    """crc32 of the id as text, modulo; null ids count as remainder 0 of the empty string."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(modulus)).cast("int")


def held_out(doc_id: int | None, modulus: int, remainder: int) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % modulus == remainder


# ---------------------------------------------------------------- workers' memory

def trimmed() -> None:
    """Gives memory that a worker has freed back to the machine; workers outlive their tasks and stages."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library, which may return memory by itself
        pass


def grouped(f: Callable[..., pa.Table]) -> Callable[..., pa.Table]:
    """The same function of one or two tables, after which the worker's freed memory is given back."""
    if f.__code__.co_argcount == 2:
        def two(left: pa.Table, right: pa.Table) -> pa.Table:
            out = f(left, right)
            trimmed()
            return out

        return two

    def one(rows: pa.Table) -> pa.Table:
        out = f(rows)
        trimmed()
        return out

    return one


# ---------------------------------------------------------------- batches of documents

def batched(docs: DataFrame, per_partition: int = 2, carry: list[str] | None = None) -> tuple[DataFrame, int]:
    """Documents dealt into batches by a hash of id and text, one shuffle; the plan reuses it wherever it appears again.

    A batch (column ``k``) is a bounded share of a shuffle partition. It has the same rows whenever it is
    recomputed, so that a later pass over the same batch can apply replies that name local positions only. Columns
    to carry go along in the struct ``rest``.
    """
    n = shuffle_partitions(docs.sparkSession)
    rest = [F.struct(*(F.col(f"`{c}`") for c in carry)).alias("rest")] if carry else []
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *rest).withColumn(
        "k", F.pmod(F.xxhash64("doc_id", "text"), F.lit(n * per_partition)).cast("int"))
    return keyed.repartition(n, "k"), n * per_partition


def order_of(batch: pa.Table) -> tuple[list[int], list, list[bytes]]:
    """The order of a batch's rows by (id, text), nulls first, and the ids and UTF-8 texts in the batch's own order."""
    ids = batch.column("doc_id").to_pylist()
    texts = [b"" if t is None else t for t in batch.column("text").cast(pa.binary()).to_pylist()]
    return sorted(range(len(ids)), key=lambda i: (ids[i] is not None, ids[i] or 0, texts[i])), ids, texts


def in_order(batch: pa.Table) -> tuple[list, list[bytes]]:
    """Ids and texts of a batch in the same order in every pass."""
    order, ids, texts = order_of(batch)
    return [ids[i] for i in order], [texts[i] for i in order]


# ---------------------------------------------------------------- vectorised word hashes

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_BASE, _STEP = 0x9E3779B97F4A7C15, 0xD1342543DE82EF95


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """Finaliser of splitmix64."""
    x = x + U64((0x9E3779B97F4A7C15 * (salt + 1)) & (2**64 - 1))
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


_BYTE = mix(np.arange(256, dtype=U64), 7)
#: A second family of hashes, of other bytes' numbers and other multipliers, which collides independently of the first.
_BYTE2 = mix(np.arange(256, dtype=U64), 8)
_BASE2, _STEP2 = 0xA0761D6478BD642F, 0xE7037ED1A0B428DB


_SLICE = 1 << 19
_POWERS: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    if len(_POWERS.get(base, ())) < n:
        out = np.full(max(n, 1 << 16), base, U64)
        out[:1] = 1
        _POWERS[base] = np.multiply.accumulate(out)
    return _POWERS[base][:n]


def distinct(a: np.ndarray) -> np.ndarray:
    """The sorted distinct numbers of an array, by sorting, which is several times faster than np.unique's hash table."""
    a = np.sort(a)
    return a[np.concatenate([[True], a[1:] != a[:-1]])] if len(a) else a


class Words:
    """Word hashes of concatenated texts; word i of text d has index first[d] + i. The second hashes are made on request."""

    def __init__(self, texts: list[bytes], second: bool = False):
        buf = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
        n = len(buf)
        space = _SPACE[buf]
        before = np.empty(n, bool)
        before[0] = True
        before[1:] = space[:-1]
        starts = np.flatnonzero(before & ~space)
        ends = np.flatnonzero(space & ~before)
        self.hash = np.empty(len(starts), U64)
        self.hash2 = np.empty(len(starts) if second else 0, U64)
        # some bytes at a time, always whole words, so that the sums stay small
        cut = np.unique(np.concatenate([np.searchsorted(starts, np.arange(0, n, _SLICE)), [len(starts)]]))
        for i, j in zip(cut[:-1], cut[1:], strict=True):
            low, end = starts[i], ends[j - 1]
            for out, of_byte, base in ((self.hash, _BYTE, _BASE), (self.hash2, _BYTE2, _BASE2))[:1 + second]:
                part = of_byte[buf[low:end]]
                sums = np.zeros(len(part) + 1, U64)
                with np.errstate(over="ignore"):
                    part *= _powers(base, len(part))
                    np.cumsum(part, out=sums[1:])
                    inverse = _powers(pow(base, -1, 1 << 64), len(part))
                    out[i:j] = mix((sums[ends[i:j] - low] - sums[starts[i:j] - low]) * inverse[starts[i:j] - low])
        at = np.cumsum([0] + [len(t) + 1 for t in texts])
        self.first = np.searchsorted(starts, at)
        self.n = np.diff(self.first)

    def rolling(self, size: int, second: bool = False) -> np.ndarray:
        """At each word the hash of the run of so many words that starts there; runs may cross texts."""
        each, step = (self.hash2, _STEP2) if second else (self.hash, _STEP)
        n = len(each)
        if n < size:
            return np.zeros(0, U64)
        sums = np.zeros(n + 1, U64)
        with np.errstate(over="ignore"):
            np.cumsum(each * _powers(step, n), out=sums[1:])
            return (sums[size:] - sums[:-size]) * _powers(pow(step, -1, 1 << 64), n)[: n - size + 1]

    def text_of(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.n), dtype=np.int32), self.n)


# ---------------------------------------------------------------- packed sorted arrays

def pack(sorted_u64: np.ndarray) -> bytes:
    """Differences of sorted numbers by byte plane: high planes are zeros, which any codec removes."""
    if not len(sorted_u64):
        return b""
    deltas = np.diff(sorted_u64, prepend=U64(0)).astype("<u8")
    planes = np.ascontiguousarray(deltas.view(np.uint8).reshape(-1, 8).T)
    used = max((i + 1 for i in range(8) if planes[i].any()), default=1)
    return bytes([used]) + planes[:used].tobytes()


def unpack(packed: bytes) -> np.ndarray:
    if not packed:
        return np.zeros(0, U64)
    used = packed[0]
    planes = np.frombuffer(packed, np.uint8, offset=1).reshape(used, -1)
    deltas = np.zeros((planes.shape[1], 8), np.uint8)
    deltas[:, :used] = planes.T
    return np.cumsum(deltas.view("<u8").ravel(), dtype=U64)


def pack_counts(counts: np.ndarray) -> bytes:
    """Numbers of any order and up to 64 bits by byte plane, as many planes as the largest needs."""
    planes = np.ascontiguousarray(counts.astype("<u8").view(np.uint8).reshape(-1, 8).T)
    used = max((i + 1 for i in range(8) if planes[i].any()), default=1)
    return bytes([used]) + planes[:used].tobytes()


def unpack_counts(packed: bytes) -> np.ndarray:
    used = packed[0]
    planes = np.frombuffer(packed, np.uint8, offset=1).reshape(used, -1)
    out = np.zeros((planes.shape[1], 8), np.uint8)
    out[:, :used] = planes.T
    return out.view("<u8").ravel().astype(np.int64)


def pack_bits(flags: np.ndarray) -> bytes:
    return np.packbits(flags).tobytes()


def unpack_bits(packed: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(packed, np.uint8), count=n).astype(bool) if n else np.zeros(0, bool)


def ranges(sorted_u64: np.ndarray, bits: int, buckets: int) -> np.ndarray:
    """Where each bucket, an equal range of numbers of so many bits, begins in the sorted array; one more at the end."""
    bounds = np.array([-(-(i << bits) // buckets) for i in range(1, buckets)], U64)
    return np.concatenate([[0], np.searchsorted(sorted_u64, bounds), [len(sorted_u64)]])


def arrow_rows(schema: pa.Schema, rows: Iterable[tuple]) -> pa.Table:
    rows = list(rows)
    return pa.table([pa.array([r[i] for r in rows], f.type) for i, f in enumerate(schema)], schema=schema)


def per_document(docs: DataFrame, score: Callable[[list, list[bytes]], Iterable[tuple]], schema: pa.Schema, ddl: str, most: int = 8 << 20) -> DataFrame:
    """Rows that score makes from the ids and UTF-8 texts of the documents of a task, some MB of text at a time; no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1).cast(pa.binary())
            at = 0
            while at < len(ids):
                end, size = at, 0
                while end < len(ids) and (size < most or end == at):
                    size += len(texts[end].as_buffer() or b"") if texts[end].is_valid else 0
                    end += 1
                some = [b"" if t is None else t for t in texts.slice(at, end - at).to_pylist()]
                yield from arrow_rows(schema, score(ids.slice(at, end - at).to_pylist(), some)).to_batches()
                at = end
        trimmed()

    return columns(docs, doc_id="long", text="string").mapInArrow(run, ddl)

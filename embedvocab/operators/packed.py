"""Counts of runs of three words for every row of a text, sent as packed arrays.

Rows are cut into blocks. A block sends its distinct runs, as numbers of words and 64-bit hashes of these words, to buckets by the hash of
a pair of words; a bucket adds up what all blocks sent and answers each block in the order in which it asked. The rows themselves travel
packed, and meet the answers block by block. A common word or run is one entry of a block, so no bucket depends on how common it is.

Words are equal where their 64-bit hashes are: among 10^7 distinct words the chance of any two alike is 3e-6. Blocks that do not get all
answers raise an error.
"""

from __future__ import annotations

import ctypes
import struct
from collections.abc import Callable, Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: Rows of a block, and distinct words of one, three numbers of which fit 63 bits; a block of more words is halved.
BLOCK, WORDS = 1 << 20, (1 << 21) - 2
#: Rows of a batch that leaves a task.
BATCH = 1 << 15
#: Bytes of input to a bucket, whose requests share a list of words, least number of buckets, and bytes to a part of it, which is counted
#: at a time (less than a million runs).
BUCKET_BYTES, LEAST, PART_BYTES = 48_000_000, 16, 4_000_000
#: What is sent: a row's columns; runs by their first two words, by their last two, by the last word, by the word before it; sums of a bucket.
ROWS, TRIPLE, PAIR, WORD, CONTEXT, SUMS = range(6)
ASKED = (TRIPLE, PAIR, WORD, CONTEXT)
COUNTS = ["n_abw", "n_ab", "d_ab", "n_bw", "n_b", "n_w", "n_all", "c_bw", "c_b", "e_b", "c_w", "c_all"]
_SENT = "dest int, kind int, block string, bucket int, blob binary"


def buckets(df: DataFrame) -> tuple[int, int]:
    """How many buckets, and parts of a bucket, the size of df's sources asks for; any numbers give the same counts."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    size = sum(int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size()))
    if size >= 1 << 62:  # a source that does not know its size; words take some six bytes
        size = 6 * df.count()
    count = min(max(size // BUCKET_BYTES, LEAST), 1 << 12)
    return count, min(max(size // count // PART_BYTES, 1), 64)


def trimmed() -> None:
    """Gives memory that a worker has freed back to the machine; workers outlive their groups."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


# ---------------------------------------------------------------- arrays as bytes

def pack(*arrays: np.ndarray) -> bytes:
    """Arrays of whole numbers from zero, each in as few bytes as its largest takes, byte by byte of all numbers, compressed."""
    head, body = [struct.pack("<I", len(arrays))], []
    for x in arrays:
        x = np.asarray(x).astype(np.uint64)
        width = max(1, (int(x.max()).bit_length() + 7) // 8) if len(x) else 1
        head.append(struct.pack("<QB", len(x), width))
        body.append(np.ascontiguousarray(x.view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes())
    raw = b"".join(head + body)
    return struct.pack("<Q", len(raw)) + pa.compress(raw, "zstd", asbytes=True)


def unpack(blob: bytes | pa.Buffer, only: Callable[[int], slice | None] = lambda _: slice(None)) -> list[np.ndarray]:
    """The arrays, of each by its number what ``only`` says."""
    raw = pa.decompress(memoryview(blob)[8:], struct.unpack_from("<Q", blob)[0], "zstd", asbytes=True)
    n, at, out = struct.unpack_from("<I", raw)[0], 4, []
    sizes = [struct.unpack_from("<QB", raw, at + 9 * i) for i in range(n)]
    at += 9 * n
    for i, (size, width) in enumerate(sizes):
        planes = np.frombuffer(raw, np.uint8, size * width, at).reshape(width, size)[:, only(i) or slice(0)]
        x = np.zeros((planes.shape[1], 8), np.uint8)
        for k, plane in enumerate(planes):
            x[:, k] = plane
        out.append(x.view(np.uint64).reshape(-1))
        at += size * width
    return out


def signed(x: np.ndarray) -> np.ndarray:
    """Whole numbers, negative ones too, as numbers from zero; small ones stay small."""
    x = x.astype(np.int64)
    return ((x << 1) ^ (x >> 63)).view(np.uint64)


def unsigned(x: np.ndarray) -> np.ndarray:
    return (x >> np.uint64(1)).view(np.int64) ^ -(x & np.uint64(1)).view(np.int64)


# ---------------------------------------------------------------- blocks

def numbered(table: pa.Table) -> tuple[pa.Array, np.ndarray, list[np.ndarray]]:
    """The block's distinct words in the order of their hashes, the hashes, and the columns a, b and w as numbers of words, -1 for null."""
    n = table.num_rows
    a, b, w = (flat(table.column(c)) for c in ("a", "b", "w"))
    # most words before a word are the words of the rows before, and are not looked up again
    others = {k: np.flatnonzero(~np.concatenate([np.zeros(min(k, n), bool), pc.equal(x.slice(k), w.slice(0, max(0, n - k))).fill_null(False).to_numpy(zero_copy_only=False)])) for k, x in ((1, b), (2, a))}
    every = pa.concat_arrays([w, b.take(pa.array(others[1])), a.take(pa.array(others[2]))]).dictionary_encode()
    hashes = hashed(every.dictionary)
    order = np.argsort(hashes, kind="stable")
    rank = np.empty(len(order) + 1, np.int64)
    rank[order], rank[-1] = np.arange(len(order)), -1
    numbers = rank[every.indices.fill_null(len(order)).to_numpy(zero_copy_only=False)]
    of_w, at, out = numbers[:n], n, []
    for k in (1, 2):
        x = before(of_w, k)
        x[others[k]] = numbers[at : at + len(others[k])]
        at += len(others[k])
        out.append(x)
    return every.dictionary.take(pa.array(order)), hashes[order], [out[1], out[0], of_w]


def flat(x: pa.ChunkedArray) -> pa.Array:
    x = x.combine_chunks()
    return x if isinstance(x, pa.Array) else pa.concat_arrays(x.chunks) if x.num_chunks else pa.array([], x.type)


def hashed(words: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join([blake2b(w.encode(), digest_size=8).digest() for w in words.to_pylist()]), "<u8")


def before(x: np.ndarray, k: int) -> np.ndarray:
    """What lies so many rows before each row, -1 before the first."""
    return np.concatenate([np.full(min(k, len(x)), -1), x[: max(0, len(x) - k)]])


def rows_blob(table: pa.Table, words: pa.Array, numbers: list[np.ndarray]) -> bytes:
    """The rows; words before a word are kept as what differs from the row before, whole numbers as differences."""
    a, b, w = numbers
    own = pack(signed(a - before(w, 2)), signed(b - before(w, 1)), signed(w))
    others = {}
    for c in table.column_names:
        if c not in ("a", "b", "w"):
            x = flat(table.column(c))
            if pa.types.is_integer(x.type) and not x.null_count:
                v = x.to_numpy(zero_copy_only=False)
                x = pa.array(np.diff(v, prepend=v.dtype.type(0)), x.type)
            others[c] = x
    sink = pa.BufferOutputStream()
    options = pa.ipc.IpcWriteOptions(compression="zstd")
    for part in (pa.table({"words": words}), pa.table(others) if others else pa.table({"none": pa.nulls(0)})):
        with pa.ipc.new_stream(sink, part.schema, options=options) as out:
            out.write_table(part)
    return struct.pack("<Q", len(own)) + own + sink.getvalue().to_pybytes()


def rows_of(blob: bytes) -> tuple[pa.Array, list[np.ndarray], dict[str, pa.Array]]:
    size = struct.unpack("<Q", blob[:8])[0]
    a, b, w = (unsigned(x) for x in unpack(blob[8 : 8 + size]))
    source = pa.BufferReader(blob[8 + size :])
    words, others = (pa.ipc.open_stream(source).read_all() for _ in range(2))
    out = {}
    for c in others.column_names:
        x = flat(others.column(c))
        if pa.types.is_integer(x.type) and not x.null_count:
            v = x.to_numpy(zero_copy_only=False)
            x = pa.array(np.cumsum(v, dtype=v.dtype), x.type)
        out[c] = x
    return flat(words.column("words")), [a + before(w, 2), b + before(w, 1), w], out


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def part_of(mix: np.ndarray, parts: tuple[int, int]) -> np.ndarray:
    return ((mix >> np.uint64(20)) % np.uint64(parts[0] * parts[1])).astype(np.int64)


class Block:
    """Distinct runs of a block, and what it asks about them: per kind the entries (x, y, z), sorted, and the buckets that answer."""

    def __init__(self, hashes: np.ndarray, numbers: list[np.ndarray], follows: bool, parts: tuple[int, int]):
        self.hashes, self.follows, self.parts, self.size = hashes, follows, parts, len(hashes) + 1
        codes = self.code(*numbers)
        self.codes, self.each, self.uses = np.unique(codes, return_inverse=True, return_counts=True)
        s = self.size
        self.a, self.b, self.w = self.codes // (s * s) - 1, self.codes // s % s - 1, self.codes % s - 1

    def code(self, x: np.ndarray, y: np.ndarray, z: np.ndarray) -> np.ndarray:
        return ((x + 1) * self.size + (y + 1)) * self.size + (z + 1)

    def entries(self, kind: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """x, y, z of the entries, and the part of a bucket, counted through all buckets, that answers; which runs ask, and the entry of each."""
        none = np.full(len(self.codes), -1)
        x, y, z = {TRIPLE: (self.a, self.b, self.w), PAIR: (self.b, self.w, self.a if self.follows else none), WORD: (self.w, none, none), CONTEXT: (self.b, none, none)}[kind]
        asks = x >= 0
        if kind == TRIPLE or kind == PAIR and not self.follows:
            asks = asks & (y >= 0)
        asks = np.flatnonzero(asks)
        x, y, z = x[asks], y[asks], z[asks]
        if kind == TRIPLE:  # in order already
            entry = np.arange(len(x))
        elif kind == PAIR:
            found, entry = np.unique(self.code(x, y, z), return_inverse=True)
            s = self.size
            x, y, z = found // (s * s) - 1, found // s % s - 1, found % s - 1
        else:
            seen = np.zeros(self.size, bool)
            seen[x] = True
            entry, x = (np.cumsum(seen) - 1)[x], np.flatnonzero(seen)
            y = z = np.full(len(x), -1)
        hashes = np.append(self.hashes, np.uint64(0))  # -1 is null
        mix = mixed(hashes[x] + np.uint64(0x9E3779B97F4A7C15) * hashes[y]) if kind in (TRIPLE, PAIR) else mixed(hashes[x])
        return x, y, z, part_of(mix, self.parts), asks, entry

    def requests(self, fold: int) -> Iterator[tuple[int, int, bytes]]:
        """(kind, bucket, request); every bucket gets one of each kind, which also tells how many rows the block has."""
        for kind in ASKED:
            x, y, z, bucket, asks, entry = self.entries(kind)
            n = np.bincount(entry, weights=self.uses[asks], minlength=len(x)).astype(np.int64)
            order, (count, each) = np.argsort(bucket, kind="stable"), self.parts
            ends = np.searchsorted(bucket[order], np.arange(count * each + 1))
            for i in range(count):
                cuts = ends[i * each : (i + 1) * each + 1]
                at = order[cuts[0] : cuts[-1]]
                seen = np.zeros(self.size, bool)  # the last is null
                mine = [k[at] for k in (x, y, z)]
                for k in mine:
                    seen[k] = True
                seen[-1] = False
                used, local = np.flatnonzero(seen), np.cumsum(seen)
                local[-1] = 0
                counted = not (self.follows and kind != TRIPLE)
                yield kind, i, pack(signed(np.array([fold])), [int(self.uses.sum())], np.diff(cuts), np.diff(self.hashes[used], prepend=np.uint64(0)), *(local[k] for k in mine), n[at] if counted else n[:0])


def first_of_pairs(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Where a pair begins among sorted entries."""
    return np.flatnonzero(np.concatenate([[True], (x[1:] != x[:-1]) | (y[1:] != y[:-1])])) if len(x) else np.zeros(0, np.int64)


# ---------------------------------------------------------------- buckets

class Request:
    """A block's request: the fold and rows of the block, hashes of words, and the entries of each part."""

    def __init__(self, block: str, blob: bytes | pa.Buffer):
        fold, rows, cuts, hashes, *_ = unpack(blob, lambda k: slice(None) if k < 4 else None)
        self.block, self.blob, self.fold, self.rows = block, blob, int(unsigned(fold)[0]), int(rows[0])
        self.hashes, self.cuts = np.cumsum(hashes, dtype=np.uint64), np.concatenate([[0], np.cumsum(cuts.astype(np.int64))])

    def part(self, i: int) -> tuple[list[np.ndarray], np.ndarray]:
        at = slice(self.cuts[i], self.cuts[i + 1])
        *keys, n = (x.view(np.int64) for x in unpack(self.blob, lambda k: at if k > 3 else None)[4:])
        return keys, n if len(n) else np.zeros(at.stop - at.start, np.int64)


class Part:
    """What all blocks ask of a part of a bucket, under common numbers of words, pairs and entries."""

    def __init__(self, requests: list[Request], hashes: np.ndarray, names: list[np.ndarray], i: int):
        self.requests, self.hashes = requests, hashes
        self.folds, self.rows = np.array([r.fold for r in requests]), np.array([r.rows for r in requests])
        read = [r.part(i) for r in requests]
        x, y, z = (np.concatenate([name[keys[k]] for (keys, _), name in zip(read, names, strict=True)]) for k in range(3))
        self.lengths, self.n = np.array([len(n) for _, n in read]), np.concatenate([n for _, n in read])
        del read
        s = len(hashes) + 1
        if s < 1 << 21:
            found, self.entry = np.unique((x * s + y) * s + z, return_inverse=True)
            of_pair, self.named = found // s, found % s > 0
            first = np.concatenate([[True], of_pair[1:] != of_pair[:-1]]) if len(found) else np.zeros(0, bool)
            pairs, self.pair_of = of_pair[first], np.cumsum(first) - 1
            self.pair = self.pair_of[self.entry]
        else:
            pairs, self.pair = np.unique(x * s + y, return_inverse=True)
            found, self.entry = np.unique(self.pair * s + z, return_inverse=True)
            self.pair_of, self.named = found // s, found % s > 0
        self.x, self.y = pairs // s - 1, pairs % s - 1
        self.ends = np.cumsum(self.lengths)

    def rounds(self, held: bool, folds: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(fold, requests that count, requests that are answered): all, or for each fold the others and the fold's."""
        if not held:
            yield -1, np.ones(len(self.folds), bool), np.ones(len(self.folds), bool)
            return
        for fold in range(folds):
            yield fold, self.folds != fold, self.folds == fold

    def counted(self, use: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Of the requests that count: uses of each entry, uses of each pair, distinct third words of each pair, whether the pair occurs."""
        each = np.repeat(use, self.lengths)
        size = len(self.pair_of)
        n = np.bincount(self.entry[each], weights=self.n[each], minlength=size).astype(np.int64)
        seen = np.bincount(self.entry[each], minlength=size) > 0
        of = lambda mask, w=None: np.bincount(self.pair_of[mask], weights=None if w is None else w[mask], minlength=len(self.x)).astype(np.int64)
        return n, of(seen, n), of(seen & self.named), of(seen) > 0

    def answers(self, kind: int, follows: bool, held: bool, folds: int) -> Iterator[tuple[str, bytes]]:
        for _, use, asked in self.rounds(held, folds):
            if asked.any():
                n, of_pair, distinct, _ = self.counted(use)
                total = int(self.rows[use].sum())
                for i in np.flatnonzero(asked):
                    at = slice(self.ends[i] - self.lengths[i], self.ends[i])
                    pair = self.pair[at]
                    pair = pair[first_of_pairs(pair, pair)]
                    none = pair[:0]
                    yield self.requests[i].block, pack(n[self.entry[at]] if kind == TRIPLE else none, none if kind == PAIR and follows else of_pair[pair], distinct[pair] if follows else none, [total])

    def sums(self, parts: tuple[int, int], held: bool, folds: int) -> Iterator[tuple[int, bytes]]:
        """(bucket of words, sums): to each word how many words follow its pairs, how many of its pairs follow a word, and how many words it follows."""
        hashes = self.hashes
        bucket = part_of(mixed(hashes), parts) // parts[1]
        for fold, use, _ in self.rounds(held, folds):
            _, _, distinct, seen = self.counted(use)
            into = lambda at, w, mask: np.bincount(at[mask], weights=w[mask], minlength=len(hashes)).astype(np.int64)
            c, e = into(self.x, distinct, seen), into(self.x, distinct > 0, seen)
            f = into(self.y, seen, seen & (self.y >= 0))
            for i in range(parts[0]):
                at = np.flatnonzero((bucket == i) & ((c > 0) | (f > 0)))
                yield i, pack(signed(np.array([fold])), [int(seen.sum())], hashes[at], c[at], e[at], f[at])


def parts_of(table: pa.Table, each: int) -> Iterator[tuple[int, Part]]:
    """(part counted through all buckets, its requests) of a bucket."""
    blocks = table.column("block").to_pylist()
    blobs = [blob.as_buffer() for blob in table.column("blob")]
    requests = [Request(block, blob) for block, blob in sorted(zip(blocks, blobs, strict=True), key=lambda r: r[0])]
    hashes = np.unique(np.concatenate([r.hashes for r in requests]))
    names = [np.concatenate([[0], np.searchsorted(hashes, r.hashes) + 1]) for r in requests]
    bucket = table.column("bucket")[0].as_py()
    for i in range(each):
        yield bucket * each + i, Part(requests, hashes, names, i)
        trimmed()


def sent(rows: list[tuple[int, int, str, int, bytes]]) -> pa.Table:
    names, kinds = ("dest", "kind", "block", "bucket", "blob"), (pa.int32(), pa.int32(), pa.string(), pa.int32(), pa.binary())
    return pa.table({c: pa.array([r[i] for r in rows], k) for i, (c, k) in enumerate(zip(names, kinds, strict=True))})


def of_words(requests: list[tuple[int, str, int, bytes]], sums: list[bytes]) -> Iterator[tuple[str, int, int, bytes]]:
    """Answers about words from the sums of all buckets of pairs."""
    read: dict[int, list[list[np.ndarray]]] = {}
    for blob in sums:
        got = unpack(blob)
        read.setdefault(int(unsigned(got[0])[0]), []).append(got)
    tables = {}
    for fold, parts in read.items():
        words, at = np.unique(np.concatenate([p[2] for p in parts]), return_inverse=True)
        values = [np.bincount(at, weights=np.concatenate([p[k] for p in parts]).astype(np.float64), minlength=len(words)).astype(np.int64) for k in (3, 4, 5)]
        tables[fold] = words, values, sum(int(p[1][0]) for p in parts)
    for kind, block, bucket, blob in requests:
        request = Request(block, blob)
        fold = -1 if -1 in tables else request.fold
        if fold not in tables:
            continue  # rows that only train
        words, (c, e, f), total = tables[fold]
        for i in range(len(request.cuts) - 1):
            asked = request.hashes[request.part(i)[0][0] - 1]
            at = np.minimum(np.searchsorted(words, asked), max(len(words) - 1, 0))
            known = words[at] == asked if len(words) else np.zeros(len(asked), bool)
            value = lambda v: np.where(known, v[at], 0) if len(words) else np.zeros(len(asked), np.int64)  # noqa: B023, E731
            yield block, kind, bucket * (len(request.cuts) - 1) + i, pack(*((value(f), [total]) if kind == WORD else (value(c), value(e))))


# ---------------------------------------------------------------- plan

def counted(runs: DataFrame, follows: bool, folds: int = 0) -> DataFrame:
    """runs with the counts of all runs: of words, pairs and triples, or, if ``follows``, of triples and of how many words others follow.

    With folds, runs has a column ``_fold``; rows of each fold get the counts of all rows of others, and what comes out is distinct runs
    of blocks (a, b, w, _fold, _uses). Counts of nothing are null.
    """
    held, parts = folds > 0, buckets(runs)
    columns = [c for c in runs.columns if not held or c in ("a", "b", "w", "_fold")]
    wanted = ["n_abw", "n_ab", "d_ab", "c_bw", "c_b", "e_b", "c_w", "c_all"] if follows else ["n_abw", "n_ab", "n_bw", "n_b", "n_w", "n_all"]
    kept = [f for f in runs.schema.fields if f.name in columns]
    added = [T.StructField(c, T.LongType()) for c in (["_uses"] if held else []) + wanted]
    asking = _asking(held, follows, parts)
    asked = runs.select(*columns).mapInArrow(asking, _SENT)
    answered = asked.groupBy("dest").applyInArrow(_answering(held, folds, follows, parts[1]), _SENT)
    if follows:
        summed = asked.groupBy("dest").applyInArrow(_summing(held, folds, parts), _SENT)
        answered = answered.unionByName(summed.groupBy("dest").applyInArrow(_wording(), _SENT))
    schema = T.StructType(kept + added)
    return answered.groupBy("block").applyInArrow(_joining(held, follows, parts, columns, wanted), schema)


def _asking(held: bool, follows: bool, parts: tuple[int, int]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting: dict[int, list[pa.RecordBatch]] = {}
        rows: dict[int, int] = {}

        def block(fold: int) -> Iterator[pa.RecordBatch]:
            rows.pop(fold)
            yield from sent_block(fold, pa.Table.from_batches(waiting.pop(fold)))

        def sent_block(fold: int, table: pa.Table) -> Iterator[pa.RecordBatch]:
            words, hashes, numbers = numbered(table)
            if len(hashes) > WORDS:
                half = table.num_rows // 2
                for part in (table.slice(0, half), table.slice(half)):
                    yield from sent_block(fold, part)
                return
            blob = rows_blob(table, words, numbers)
            # the name is of the rows, so that a task that is run again and reads other rows first is noticed
            name = f"{_task()}-{fold}-{blake2b(blob, digest_size=12).hexdigest()}"
            out, size = [((int(name[-6:], 16) % parts[0]) * 8 + ROWS, ROWS, name, 0, blob)], len(blob)
            for kind, bucket, request in Block(hashes, numbers, follows, parts).requests(fold):
                out.append((bucket * 8 + kind, kind, name, bucket, request))
                size += len(request)
                if size > 1 << 24:
                    yield from sent(out).to_batches()
                    out, size = [], 0
            yield from sent(out).to_batches()
            trimmed()

        for batch in batches:
            pieces = [(0, batch)]
            if held:
                fold = batch.column(batch.schema.names.index("_fold")).to_numpy(zero_copy_only=False)
                pieces = [(int(f), batch.take(pa.array(np.flatnonzero(fold == f)))) for f in np.unique(fold)]
            for fold, piece in pieces:
                while piece.num_rows:
                    room = BLOCK - rows.get(fold, 0)
                    part, piece = piece.slice(0, room), piece.slice(room)
                    waiting.setdefault(fold, []).append(part)
                    rows[fold] = rows.get(fold, 0) + part.num_rows
                    if rows[fold] == BLOCK:
                        yield from block(fold)
        for fold in sorted(waiting):
            yield from block(fold)

    return run


def _task() -> int:
    from pyspark import TaskContext

    context = TaskContext.get()
    return context.partitionId() if context else 0


def _answering(held: bool, folds: int, follows: bool, each: int) -> Callable[[pa.Table], pa.Table]:
    def run(table: pa.Table) -> pa.Table:
        kind = table.column("kind")[0].as_py()
        if kind == ROWS:
            return table
        if follows and kind in (WORD, CONTEXT):
            return table.slice(0, 0)
        return sent([(0, kind, block, i, blob) for i, part in parts_of(table, each) for block, blob in part.answers(kind, follows, held, folds)])

    return run


def _summing(held: bool, folds: int, parts: tuple[int, int]) -> Callable[[pa.Table], pa.Table]:
    def run(table: pa.Table) -> pa.Table:
        kind = table.column("kind")[0].as_py()
        if kind in (WORD, CONTEXT):
            return table.set_column(0, "dest", table.column("bucket"))
        if kind != PAIR:
            return table.slice(0, 0)
        return sent([(to, SUMS, "", i, blob) for i, part in parts_of(table, parts[1]) for to, blob in part.sums(parts, held, folds)])

    return run


def _wording() -> Callable[[pa.Table], pa.Table]:
    def run(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        asked = [(r["kind"], r["block"], r["bucket"], r["blob"]) for r in rows if r["kind"] != SUMS]
        return sent([(0, kind, block, bucket, blob) for block, kind, bucket, blob in of_words(asked, [r["blob"] for r in rows if r["kind"] == SUMS])])

    return run


def _joining(held: bool, follows: bool, parts: tuple[int, int], columns: list[str], wanted: list[str]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(sent_here: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = {(r["kind"], r["bucket"]): r["blob"] for batch in sent_here for r in batch.select(["kind", "bucket", "blob"]).to_pylist()}
        if (ROWS, 0) not in got:
            raise RuntimeError("answers without their rows: the input was read again in another order")
        words, numbers, others = rows_of(got[(ROWS, 0)])
        fold = others["_fold"][0].as_py() if held else 0
        if len(got) == 1 and held:
            return  # rows that only train
        block = Block(hashed(words), numbers, follows, parts)
        found = {c: np.zeros(len(block.codes), np.int64) for c in wanted}
        for kind in ASKED:
            x, y, _, bucket, asks, entry = block.entries(kind)
            first = first_of_pairs(x, y)
            pair = np.cumsum(np.bincount(first, minlength=len(x))) - 1
            per_pair: list[np.ndarray] = [np.zeros(len(first), np.int64) for _ in range(2)]
            per_entry = np.zeros(len(x), np.int64)
            order, of_first = np.argsort(bucket, kind="stable"), bucket[first]
            order_first = np.argsort(of_first, kind="stable")
            numbered_parts = np.arange(parts[0] * parts[1] + 1)
            ends, ends_first = np.searchsorted(bucket[order], numbered_parts), np.searchsorted(of_first[order_first], numbered_parts)
            for i in range(parts[0] * parts[1]):
                if (kind, i) not in got:
                    raise RuntimeError("rows without all their answers: the input was read again in another order")
                values = [v.astype(np.int64) for v in unpack(got.pop((kind, i)))]
                mine, pairs = order[ends[i] : ends[i + 1]], order_first[ends_first[i] : ends_first[i + 1]]
                if kind in (WORD, CONTEXT) and follows:
                    per_pair[0][pairs] = values[0]
                    if kind == CONTEXT:
                        per_pair[1][pairs] = values[1]
                    else:
                        found["c_all"][:] = values[1][0]
                    continue
                n, of_pair, distinct, total = values
                if kind == TRIPLE:
                    per_entry[mine] = n
                if not (kind == PAIR and follows):
                    per_pair[0][pairs] = of_pair
                if follows:
                    per_pair[1][pairs] = distinct
                if kind == WORD:
                    found["n_all"][:] = total[0]
            if kind == TRIPLE:
                found["n_abw"][asks], found["n_ab"][asks] = per_entry[entry], per_pair[0][pair[entry]]
                if follows:
                    found["d_ab"][asks] = per_pair[1][pair[entry]]
            elif kind == PAIR:
                # what follows is null is a pair, but not one that is looked up
                found["c_bw" if follows else "n_bw"][asks] = np.where(block.w[asks] >= 0, per_pair[1 if follows else 0][pair[entry]], 0)
            elif kind == WORD:
                found["c_w" if follows else "n_w"][asks] = per_pair[0][pair[entry]]
            else:
                found["c_b" if follows else "n_b"][asks] = per_pair[0][pair[entry]]
                if follows:
                    found["e_b"][asks] = per_pair[1][pair[entry]]
        each = np.arange(len(block.codes)) if held else block.each
        numbers = [block.a, block.b, block.w] if held else numbers
        trimmed()
        for at in range(0, len(each), BATCH):
            part = slice(at, at + BATCH)
            named = {c: words.take(pa.array(x[part], mask=x[part] < 0)) for c, x in zip("abw", numbers, strict=True)}
            if held:
                rest = {"_fold": pa.array(np.full(len(each[part]), fold), others["_fold"].type), "_uses": pa.array(block.uses[part], pa.int64())}
            else:
                rest = {c: x.slice(at, BATCH) for c, x in others.items()}
            own = {c: v[each[part]] for c, v in found.items()}
            counts = {c: pa.array(v, pa.int64(), mask=v == 0) for c, v in own.items()}
            every = named | rest | counts
            yield pa.RecordBatch.from_pydict({c: every[c] for c in [*columns, *(["_uses"] if held else []), *wanted]})

    return run

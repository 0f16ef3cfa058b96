"""Cost-balanced packing of documents into token sequences.

A document is its token ids and an end id. Runs of a full sequence's length stand alone; what remains of each
document is packed: in descending order of length, each goes to the sequence of lowest estimated cost, linear
plus quadratic in the lengths packed there, that still has room for it. As many sequences are opened as the
tokens fill; a document that fits nowhere whole is cut over the sequences with the most room, so a round of
packing leaves less than one sequence of padding.

Rounds are made within a task from a bounded number of documents; nothing is shuffled. Ids come from the rank
file, which holds the same vocabulary as the tokenizer file and is the faster; texts with the end-of-text marker,
which the tokenizer file treats apart, go through that. A run between single spaces is encoded once and kept.

Null and empty texts are the end id alone. Rows with null ids and repeated rows are packed like others. Documents of equal length
are packed in the order in which they are read, and of sequences of equal cost the first is taken. A very long text is encoded
whole; all but its last part is written out at once. Extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import base64
import functools
import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from embedvocab.llm.common import arrow_rows, columns, trimmed

MARKER = "<|endoftext|>"
#: Runs of characters kept encoded in a worker before the store is emptied.
KEPT_RUNS = 400_000

_ODD_SPACE = re.compile(r"\s[^\S ]|[^\S ] |  |^ | $|[^\S ]$")


class TokenIds(dict):
    """Token ids as little-endian unsigned 32-bit bytes."""

    def __init__(self, vocabulary: str, ranks: str):
        super().__init__()
        import public_tokenizers
        import tiktoken

        with open(ranks, "rb") as f:
            merges = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.coder = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=merges, special_tokens={})
        self.vocabulary = vocabulary

    @functools.cached_property
    def whole(self):  # noqa: ANN201
        """The tokenizer file, which few texts need: loaded when the first comes."""
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.vocabulary)

    def __missing__(self, run: str) -> bytes:
        if len(self) >= KEPT_RUNS:
            self.clear()
        if "\n" in run and run != "\n":  # a single line end is a token by itself
            return self["\n"].join(map(self.__getitem__, run.split("\n")))
        if run[-1:] in (".", ",") and run[-2:-1].isalnum():  # marks after a letter or digit begin a token
            ids = self[run[:-1]] + self[run[-1]]
        elif run.lstrip(" ").isalpha():
            ids = array("I", self.coder._core_bpe.encode_single_piece(run.encode())).tobytes()
        else:
            ids = array("I", self.coder.encode_ordinary(run)).tobytes()
        if len(run) <= 40:
            self[run] = ids
        return ids

    def encode(self, text: str) -> bytes:
        if MARKER in text:
            return np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        if _ODD_SPACE.search(text):
            return array("I", self.coder.encode_ordinary(text)).tobytes()
        # a token begins at each single space, so the runs between them can be encoded alone
        first, *rest = text.split(" ")
        return b"".join([self[first], *map(self.__getitem__, map(" ".__add__, rest))])


_CODERS: dict[tuple[str, str], TokenIds] = {}


def token_ids(vocabulary: str | None = None, ranks: str | None = None) -> TokenIds:
    """The worker's coder for these files; by default the public byte-level vocabulary."""
    import public_tokenizers

    key = (vocabulary or public_tokenizers.path("byte_bpe_50k.json"), ranks or public_tokenizers.path("byte_bpe_50k.tiktoken"))
    if key not in _CODERS:
        _CODERS[key] = TokenIds(*key)
    return _CODERS[key]


def assign(lengths: list[int], capacity: int, quadratic: float) -> list[list[tuple[int, int, int, int]]]:
    """For each document its pieces (start, length, sequence, offset); sequences are numbered from 0."""
    total = sum(lengths)
    room = np.full(-(-total // capacity), capacity, np.int64)
    cost = np.zeros(len(room))
    out: list[list[tuple[int, int, int, int]]] = [[] for _ in lengths]

    def put(doc: int, start: int, n: int, at: int) -> None:
        out[doc].append((start, n, at, capacity - int(room[at])))
        room[at] -= n
        cost[at] += n + quadratic * n * n

    for doc in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        n = lengths[doc]
        fits = room >= n
        if fits.any():
            put(doc, 0, n, int(np.where(fits, cost, np.inf).argmin()))
            continue
        start = 0
        while start < n:
            at = int(room.argmax())
            size = min(n - start, int(room[at]))
            put(doc, start, size, at)
            start += size
    return out


def pack(docs: DataFrame, capacity: int = 1024, end_id: int = 0, quadratic: float = 1 / 1024, round_size: int = 8192, vocabulary: str | None = None, ranks: str | None = None) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset): a row a piece; no shuffle."""
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64())])
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = token_ids(vocabulary, ranks)
        used = TaskContext.get().partitionId() << 36
        rows: list[tuple] = []
        rest: list[tuple] = []

        def packed() -> None:
            nonlocal used
            pieces = assign([len(ids) // 4 for _, _, _, ids in rest], capacity, quadratic)
            for (doc_id, start, tokens, ids), own in zip(rest, pieces, strict=True):
                rows.extend((doc_id, start + s, n, zlib.crc32(ids[4 * s:4 * (s + n)]), tokens, used + at, offset) for s, n, at, offset in own)
            used += 1 + max((p[2] for own in pieces for p in own), default=-1)
            rest.clear()

        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = coder.encode(text.as_py() or "") + end
                tokens = len(ids) // 4
                full = tokens - tokens % capacity
                for s in range(0, full, capacity):
                    rows.append((doc_id, s, capacity, zlib.crc32(ids[4 * s:4 * (s + capacity)]), tokens, used, 0))
                    used += 1
                if full < tokens:
                    rest.append((doc_id, full, tokens, ids[4 * full:]))
                if len(rest) >= round_size:
                    packed()
                if len(rows) >= 20_000:
                    yield from arrow_rows(schema, rows).to_batches()
                    rows.clear()
        packed()
        yield from arrow_rows(schema, rows).to_batches()
        trimmed()

    return columns(docs, doc_id="long", text="string").mapInArrow(run, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")

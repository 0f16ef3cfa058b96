"""Substring dedup with fixed-block anchors.

Every text is cut into non-overlapping blocks of about half a window, so that each window of ``window`` words
holds one whole block of its own text. The blocks form the index; every rolling run of a block's length, of
every text, probes it. A block whose words also start elsewhere is an anchor. Anchors are extended to the left and to the right
to all windows that hold them; extensions are equal if two independent 64-bit hashes of their words are, and repeated windows
that touch join to maximal repeats. At 10^13 windows the chance that any two unequal ones agree in all 128 bits is 2e-13.

Nothing is compared in pairs. A batch of documents sends each distinct hash once to the task that owns its
range, with one bit for "more than once here", and gets one bit back for each hash it asked about; so a passage
in a third of all documents costs one entry a batch. The text is shuffled once; the three passes read the same
exchange.

Messages between batches and ranges are as many as the blocks of a shuffle of as many partitions. A very long text is one row of
its batch and takes memory of a small multiple of its length. Ties cannot occur: a word is in a repeat or not.

Nulls, empty and short texts have no window and stay whole. Repeated rows count as copies of each other. Rows
with null ids are documents like others. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from embedvocab.llm.common import (
    U64, Words, arrow_rows, batched, grouped, in_order, mix, order_of, pack, pack_bits, ranges, shuffle_partitions, unpack, unpack_bits,
)

#: Bits of the hashes that blocks are probed with; a false hit only adds a candidate.
PROBE_BITS = 48
#: Bits of the first hash of a window; all but in tests, which force it to collide.
WINDOW_MASK = U64(2**64 - 1)

_ASK = pa.schema([("bucket", pa.int32()), ("k", pa.int32()), ("kind", pa.int32()), ("hashes", pa.binary()),
                  ("checks", pa.binary()), ("many", pa.binary()), ("asked", pa.binary())])
_ASK_DDL = "bucket int, k int, kind int, hashes binary, checks binary, many binary, asked binary"
_REPLY = pa.schema([("k", pa.int32()), ("kind", pa.int32()), ("bucket", pa.int32()), ("bits", pa.binary())])
_REPLY_DDL = "k int, kind int, bucket int, bits binary"
_ANCHORS, _WINDOWS = 0, 1


class _Pass:
    """What each pass computes anew from the texts of a batch."""

    def __init__(self, batch: pa.Table, window: int, extends: bool = True):
        self.block = (window + 1) // 2
        self.window = window
        self.ids, self.texts = in_order(batch)
        self.words = w = Words(self.texts, extends)
        self.text = w.text_of()
        at = (np.arange(len(self.text)) - w.first[:-1][self.text]).astype(np.int32) if len(self.text) else np.zeros(0, np.int32)
        self.left = w.n.astype(np.int32)[self.text] - at if len(at) else at
        self.at, self.long = at, (w.n[self.text] >= window if len(at) else np.zeros(0, bool))

    def probes(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Distinct probe hashes, which occur more than once, which are asked about; the distinct number of each block."""
        h = mix(self.words.rolling(self.block)) >> U64(64 - PROBE_BITS)
        n = len(h)
        whole = (self.left[:n] >= self.block) & self.long[:n]
        distinct, counts = np.unique(h[whole], return_counts=True)
        self.block_at = np.flatnonzero(whole & (self.at[:n] % self.block == 0))
        which = np.searchsorted(distinct, h[self.block_at])
        many = counts > 1
        asked = np.zeros(len(distinct), bool)
        asked[which] = True
        return distinct, many, asked & ~many, which

    def candidates(self, hit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Positions and both hashes of the windows that extend blocks that hit; sorted by the hashes."""
        is_hit = np.zeros(len(self.at) + self.block, bool)
        is_hit[self.block_at[hit]] = True
        fits = np.flatnonzero((self.left >= self.window) & self.long)
        anchor = fits + (-self.at[fits]) % self.block
        at = fits[is_hit[anchor]]
        h, c = mix(self.words.rolling(self.window)[at], 1) & WINDOW_MASK, mix(self.words.rolling(self.window, second=True)[at], 2)
        order = np.lexsort((c, h))
        return at[order], h[order], c[order]


def _groups(h: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Where each run of equal (hash, check) begins."""
    if not len(h):
        return np.zeros(0, int)
    return np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (c[1:] != c[:-1])]))


def _rows(kind: int, k: int, buckets: int, bits: int, h: np.ndarray, c: np.ndarray | None, many: np.ndarray, asked: np.ndarray):
    cut = ranges(h, bits, buckets) if bits < 64 else np.searchsorted(h >> U64(16), [-(-(i << 48) // buckets) for i in range(buckets)] + [1 << 48])
    for b in range(buckets):
        s, e = cut[b], cut[b + 1]
        if e > s:
            yield b, k, kind, pack(h[s:e]), None if c is None else c[s:e].astype("<u8").tobytes(), pack_bits(many[s:e]), pack_bits(asked[s:e])


def _answers(rows: list[dict]) -> list[tuple]:
    """For each batch's hashes of a bucket, one bit for each asked: does it occur anywhere else?"""
    hs = [unpack(r["hashes"]) for r in rows]
    cs = [np.frombuffer(r["checks"], "<u8") if r["checks"] is not None else np.zeros(len(h), "<u8") for r, h in zip(rows, hs, strict=True)]
    h, c = np.concatenate(hs), np.concatenate(cs)
    weight = np.concatenate([1 + unpack_bits(r["many"], len(x)).astype(np.int8) for r, x in zip(rows, hs, strict=True)])
    order = np.lexsort((c, h)) if rows[0]["checks"] is not None else np.argsort(h, kind="stable")
    begin = _groups(h[order], c[order])
    repeated = np.zeros(len(h), bool)
    repeated[order] = np.repeat(np.add.reduceat(weight[order].astype(np.int64), begin) > 1, np.diff([*begin, len(h)]))
    at = np.cumsum([0] + [len(x) for x in hs])
    return [(r["k"], r["kind"], r["bucket"], pack_bits(repeated[at[i]:at[i + 1]][unpack_bits(r["asked"], len(hs[i]))])) for i, r in enumerate(rows)]


def _replies(replies: pa.Table, kind: int, asked_h: np.ndarray, buckets: int, bits: int) -> np.ndarray:
    """The bits of all buckets in the order of the hashes asked about."""
    cut = ranges(asked_h, bits, buckets) if bits < 64 else np.searchsorted(asked_h >> U64(16), [-(-(i << 48) // buckets) for i in range(buckets)] + [1 << 48])
    out = np.zeros(len(asked_h), bool)
    for r in replies.to_pylist():
        if r["kind"] == kind:
            s, e = cut[r["bucket"]], cut[r["bucket"] + 1]
            out[s:e] = unpack_bits(r["bits"], e - s)
    return out


def repeated_spans(docs: DataFrame, window: int = 35, kept_text: bool = True, carry: list[str] | None = None) -> DataFrame:
    """Per document its number of words, the maximal repeats in it, ``spans`` of (first word, words), and what is kept.

    A word is in a span if a window of ``window`` words that covers it also starts anywhere else. ``kept`` is the
    text without the spans, words joined by one space, or the text itself where there are none; it is null for null texts, and
    unless ``kept_text``. ``kept_sha256`` is of the joined words in any case. Columns to carry come back in ``rest``.
    """
    dealt, _ = batched(docs, carry=carry)
    buckets = shuffle_partitions(docs.sparkSession)

    def probe(batch: pa.Table) -> pa.Table:
        k = batch.column("k")[0].as_py()
        distinct, many, asked, _ = _Pass(batch, window, extends=False).probes()
        return arrow_rows(_ASK, _rows(_ANCHORS, k, buckets, PROBE_BITS, distinct, None, many, asked))

    def answer(rows: pa.Table) -> pa.Table:
        rows = rows.to_pylist()
        kept = [(r["k"], _ANCHORS, r["bucket"], r["hashes"]) for r in rows if r["kind"] == -1]
        asked = [r for r in rows if r["kind"] != -1]
        return arrow_rows(_REPLY, kept + (_answers(asked) if asked else []))

    def hits(p: _Pass, replies: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        distinct, many, asked, which = p.probes()
        repeated = many.copy()
        repeated[asked] = _replies(replies, _ANCHORS, distinct[asked], buckets, PROBE_BITS)
        return repeated[which], which

    def extend(batch: pa.Table, replies: pa.Table) -> pa.Table:
        if not batch.num_rows:
            return arrow_rows(_ASK, [])
        k = batch.column("k")[0].as_py()
        p = _Pass(batch, window)
        hit, _ = hits(p, replies)
        _, h, c = p.candidates(hit)
        begin = _groups(h, c)
        many = np.diff([*begin, len(h)]) > 1
        # the anchors that hit go along, so that the last pass need not ask for them again
        rows = [(k % buckets, k, -1, pack_bits(hit), None, None, None)]
        return arrow_rows(_ASK, rows + list(_rows(_WINDOWS, k, buckets, 64, h[begin], c[begin], many, ~many)))

    def mark(batch: pa.Table, replies: pa.Table) -> pa.Table:
        schema = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("spans", pa.list_(pa.list_(pa.int64()))), ("kept", pa.string()), ("kept_sha256", pa.string())])
        if not batch.num_rows:
            raise ValueError("replies without a batch")  # every reply is to a batch's question
        p = _Pass(batch, window)
        p.probes()
        hit = next((unpack_bits(r["bits"], len(p.block_at)) for r in replies.to_pylist() if r["kind"] == _ANCHORS), np.zeros(len(p.block_at), bool))
        at, h, c = p.candidates(hit)
        begin = _groups(h, c)
        sizes = np.diff([*begin, len(h)])
        many = sizes > 1
        repeated = many.copy()
        repeated[~many] = _replies(replies, _WINDOWS, h[begin][~many], buckets, 64)
        edge = np.zeros(len(p.at) + 1, np.int64)
        starts = at[np.repeat(repeated, sizes)]
        np.add.at(edge, starts, 1)
        np.add.at(edge, starts + window, -1)
        covered = np.cumsum(edge[:-1]) > 0
        first, order = p.words.first, pa.array(order_of(batch)[0])
        null = batch.column("text").is_null().take(order).to_pylist()

        def rows():
            for i, (doc_id, text) in enumerate(zip(p.ids, p.texts, strict=True)):
                own = covered[first[i]:first[i + 1]]
                jumps = np.flatnonzero(np.diff(np.concatenate([[0], own.astype(np.int8), [0]])))
                words = text.split()
                kept = b" ".join(compress(words, ~own) if len(jumps) else words)
                spans = [[int(s), int(e - s)] for s, e in zip(jumps[::2], jumps[1::2], strict=True)]
                yield doc_id, len(own), int(own.sum()), spans, (kept if spans else text).decode() if kept_text and not null[i] else None, hashlib.sha256(kept).hexdigest()

        out = arrow_rows(schema, rows())
        return out.append_column("rest", batch.column("rest").take(order)) if carry else out

    marked = T.StructType.fromDDL("doc_id long, n_words long, n_removed long, spans array<array<long>>, kept string, kept_sha256 string")
    if carry:
        marked = marked.add(dealt.schema["rest"])
    anchors = dealt.groupBy("k").applyInArrow(grouped(probe), _ASK_DDL).groupBy("bucket").applyInArrow(grouped(answer), _REPLY_DDL)
    windows = dealt.groupBy("k").cogroup(anchors.groupBy("k")).applyInArrow(grouped(extend), _ASK_DDL)
    answers = windows.groupBy("bucket").applyInArrow(grouped(answer), _REPLY_DDL)
    return dealt.groupBy("k").cogroup(answers.groupBy("k")).applyInArrow(grouped(mark), marked)


def remove_repeats(docs: DataFrame, window: int = 35) -> DataFrame:
    """(doc_id, kept, n_words, n_removed): the texts without the words that a repeated window covers."""
    return repeated_spans(docs, window).select("doc_id", "kept", "n_words", "n_removed")


def without_repeats(docs: DataFrame, window: int = 35) -> DataFrame:
    """docs with their texts less the repeats, n_chars brought up to date; texts of nothing else go, empty texts stay."""
    out = repeated_spans(docs, window, carry=[c for c in docs.columns if c != "text"]).filter("n_words = 0 or n_removed < n_words")
    new = {"text": F.col("kept").cast(docs.schema["text"].dataType)}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("n_removed") > 0, F.length("kept").cast("long")).otherwise(F.col("rest")["n_chars"])
    return out.select(*((new[c] if c in new else F.col("rest")[c]).alias(c) for c in docs.columns))


def digest(docs: DataFrame, window: int = 35) -> DataFrame:
    """The removal as (doc_id, n_words, n_removed, kept_sha256)."""
    return repeated_spans(docs, window, kept_text=False).select("doc_id", "n_words", "n_removed", "kept_sha256")


def brute_force(texts: list[tuple[int, str | None]], window: int = 35) -> list[tuple[int, int, int, str]]:
    """The definition, plainly, for tests."""
    words = {i: (t or "").encode().split() for i, t in texts}
    seen: dict[tuple, int] = {}
    for w in words.values():
        for i in range(len(w) - window + 1):
            seen[tuple(w[i:i + window])] = seen.get(tuple(w[i:i + window]), 0) + 1
    out = []
    for doc_id, w in words.items():
        gone = [False] * len(w)
        for i in range(len(w) - window + 1):
            if seen[tuple(w[i:i + window])] > 1:
                gone[i:i + window] = [True] * window
        kept = [x for x, g in zip(w, gone, strict=True) if not g]
        out.append((doc_id, len(w), sum(gone), hashlib.sha256(b" ".join(kept)).hexdigest()))
    return out

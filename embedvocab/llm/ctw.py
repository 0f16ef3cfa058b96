"""Language-model scores by context-tree weighting over bytes.

Each byte is decomposed into eight binary choices. Every node (context of up to ``depth`` bytes, choice) has a
Krichevsky-Trofimov estimate of its counts; a node's weighted probability mixes its estimate with the product of its
children's, half and half, so that all depths are mixed by how well they have coded the training text. A byte's
probability follows the path of its contexts from the root down with those posterior weights; where training has
not seen a deeper context, its parent's estimate stands in.

Training gathers counts of all (depth + 1)-byte runs of the training documents, dealt by the two bytes before the coded
one, so that all nodes of depth two and more of a path lie in one bucket; the tops of the tree, at most 256 x 255 nodes, are
summed for the driver. Scoring sends each batch's distinct runs to the buckets and gets one number back for each, so no
model is broadcast. The base score's word counts travel the same way. The text is shuffled once for scoring.

The scored text is the words in lower case (A-Z), joined by one space, and a line end; the context at its start is line
ends. Null and empty texts are the end alone. Rows with null ids are documents like others. Repeated rows are counted
and scored as often as they occur; equal texts have equal scores. A very long text is one row of its batch, whose runs are sorted
some megabytes at a time. A bucket holds the runs of the two-byte contexts that fall to it, a bounded number however large the
corpus, and batches send no text there. Extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from embedvocab.llm.common import (
    U64, Words, arrow_rows, batched, columns, distinct, grouped, held_out, in_order, mix, pack, pack_counts, shuffle_partitions, trimmed, unpack, unpack_counts, written,
)

DEPTH = 5
_END = b"\n"
_LN10 = math.log(10)


def normalised(text: bytes) -> bytes:
    return b" ".join(text.lower().split()) + _END


def grams(texts: list[bytes], depth: int) -> tuple[np.ndarray, np.ndarray]:
    """The code of each byte with the ``depth`` bytes before it, and how many bytes each text has."""
    lead = _END * depth
    buf = np.frombuffer(b"".join(lead + t for t in texts), np.uint8).astype(U64)
    sizes = np.array([len(t) for t in texts])
    code = np.zeros(max(0, len(buf) - depth), U64)
    for i in range(depth + 1):
        code = (code << U64(8)) | buf[i:len(buf) - depth + i]
    begin = np.cumsum(sizes + depth) - sizes - depth
    keep = np.ones(len(code), bool)
    for i in range(depth):  # places whose byte is the lead of the next text
        at = begin[1:] - depth + i
        keep[at[at >= 0]] = False
    return code[keep], sizes


def bucket_of(code: np.ndarray, buckets: int) -> np.ndarray:
    """By the two bytes before the coded one."""
    return (mix((code >> U64(8)) & U64(0xFFFF), 5) % U64(buckets)).astype(np.int64)


# ---------------------------------------------------------------- the tree

def _log_gamma(x: np.ndarray) -> np.ndarray:
    """Stirling's series after shifting small arguments up by eight."""
    shift = np.zeros_like(x)
    small = x < 8
    y = np.where(small, x + 8, x)
    for i in range(8):
        shift += np.where(small, np.log(np.where(small, x + i, 1.0)), 0.0)
    return (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5) - shift


def kt(zeros: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """Log of the Krichevsky-Trofimov probability of so many zeros and ones."""
    return _log_gamma(zeros + 0.5) + _log_gamma(ones + 0.5) - _log_gamma(zeros + ones + 1.0) - math.log(math.pi)


class Level:
    """All seen nodes of one depth: keys (context, choice), counts, and the log weight of their own estimate."""

    def __init__(self, key: np.ndarray, zeros: np.ndarray, ones: np.ndarray, log_children: np.ndarray | None):
        self.key, self.zeros, self.ones = key, zeros, ones
        own = kt(zeros, ones)
        if log_children is None:
            self.log_weighted, self.weight = own, np.ones(len(key))
        else:
            self.log_weighted = np.logaddexp(own, log_children) - math.log(2)
            self.weight = np.exp(own - math.log(2) - self.log_weighted)


def _nodes(code: np.ndarray, count: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Keys, zeros and ones of the nodes whose contexts are the last ``depth`` bytes before the coded ones."""
    symbol = code & U64(0xFF)
    context = (code >> U64(8)) & U64((1 << 8 * depth) - 1)
    merged, at = np.unique((context << U64(8)) | symbol, return_inverse=True)
    n = np.bincount(at, weights=count, minlength=len(merged))
    keys, bits, weights = [], [], []
    for b in range(8):
        prefix = (merged & U64(0xFF)) >> U64(8 - b)
        keys.append(((merged >> U64(8)) << U64(8)) | (U64(1 << b) | prefix))
        bits.append((merged >> U64(7 - b)) & U64(1))
        weights.append(n)
    key, at = np.unique(np.concatenate(keys), return_inverse=True)
    bit, weight = np.concatenate(bits).astype(float), np.concatenate(weights)
    return key, np.bincount(at, weights=weight * (1 - bit), minlength=len(key)), np.bincount(at, weights=weight * bit, minlength=len(key))


def build(code: np.ndarray, count: np.ndarray, depth: int, top: int) -> list[Level]:
    """Levels of depth ``top`` to ``depth``, in that order."""
    levels: list[Level] = []
    children: np.ndarray | None = None
    for d in range(depth, top - 1, -1):
        key, zeros, ones = _nodes(code, count, d)
        if levels:
            children = above(levels[0].key, levels[0].log_weighted, d, key)
        levels.insert(0, Level(key, zeros, ones, children))
    return levels


def above(key: np.ndarray, values: np.ndarray, depth: int, parents: np.ndarray) -> np.ndarray:
    """Sums of the values of nodes over their parents, whose contexts are one byte shorter."""
    parent = (((key >> U64(8)) & U64((1 << 8 * depth) - 1)) << U64(8)) | (key & U64(0xFF))
    return np.bincount(np.searchsorted(parents, parent), weights=values, minlength=len(parents))


def log_probability(code: np.ndarray, levels: list[Level]) -> np.ndarray:
    """Natural log of each code's byte given the bytes before it; levels[d] has the nodes of depth d."""
    total = np.zeros(len(code))
    for b in range(8):
        node = U64(1 << b) | ((code & U64(0xFF)) >> U64(8 - b))
        one = ((code >> U64(7 - b)) & U64(1)).astype(bool)
        p = np.full(len(code), 0.5)
        for d in range(len(levels) - 1, -1, -1):
            level = levels[d]
            key = (((code >> U64(8)) & U64((1 << 8 * d) - 1)) << U64(8)) | node
            at = np.minimum(np.searchsorted(level.key, key), max(len(level.key) - 1, 0))
            seen = level.key[at] == key if len(level.key) else np.zeros(len(code), bool)
            if d == len(levels) - 1:
                deeper = np.zeros(len(code), bool)
            if not seen.any():
                continue
            s, z, o, w = at[seen], level.zeros[at[seen]], level.ones[at[seen]], level.weight[at[seen]]
            own = (np.where(one[seen], o, z) + 0.5) / (z + o + 1.0)
            p[seen] = np.where(deeper[seen], w * own + (1 - w) * p[seen], own)
            deeper = deeper | seen
            del s
        total += np.log(p)
    return total


# ---------------------------------------------------------------- training

def train(docs: DataFrame, depth: int = DEPTH, modulus: int = 7, remainder: int = 2) -> tuple[DataFrame, list[Level]]:
    """The written table of run counts (bucket, codes, counts) and the levels of depth 0 and 1."""
    buckets = shuffle_partitions(docs.sparkSession)
    schema = pa.schema([("bucket", pa.int32()), ("codes", pa.binary()), ("counts", pa.binary())])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[bytes] = []
        size = 0

        def counted() -> Iterator[pa.RecordBatch]:
            code, _ = grams(held, depth)
            runs, n = np.unique(code, return_counts=True)
            b = bucket_of(runs, buckets)
            order = np.argsort(b, kind="stable")
            cut = np.searchsorted(b[order], np.arange(buckets + 1))
            rows = ((i, pack(runs[order[cut[i]:cut[i + 1]]]), n[order[cut[i]:cut[i + 1]]].astype("<u4").tobytes()) for i in range(buckets) if cut[i + 1] > cut[i])
            yield from arrow_rows(schema, rows).to_batches()
            held.clear()

        for batch in batches:
            for i, t in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if not held_out(i, modulus, remainder):
                    held.append(normalised((t.as_py() or "").encode()))
                    size += len(held[-1])
                    if size >= 12 << 20:
                        yield from counted()
                        size = 0
        if held:
            yield from counted()
        trimmed()

    def merge(rows: pa.Table) -> pa.Table:
        rows = rows.to_pylist()
        code, at = np.unique(np.concatenate([unpack(r["codes"]) for r in rows]), return_inverse=True)
        n = np.bincount(at, weights=np.concatenate([np.frombuffer(r["counts"], "<u4") for r in rows])).astype("<u8")
        return arrow_rows(schema, [(rows[0]["bucket"], pack(code), n.tobytes())])

    ddl = "bucket int, codes binary, counts binary"
    model = written(columns(docs, doc_id="long", text="string").mapInArrow(count, ddl).groupBy("bucket").applyInArrow(grouped(merge), ddl))

    def tops(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in b.to_pylist():
                code, n = unpack(row["codes"]), np.frombuffer(row["counts"], "<u8").astype(float)
                second = build(code, n, depth, 2)[0]
                key, zeros, ones = _nodes(code, n, 1)
                yield pa.record_batch([pa.array(key.astype(np.int64)), pa.array(zeros), pa.array(ones), pa.array(above(second.key, second.log_weighted, 1, key))], names=["key", "zeros", "ones", "children"])

    # at most 256 x 255 nodes, whatever the corpus
    first = model.mapInArrow(tops, "key long, zeros double, ones double, children double").groupBy("key").agg(*(F.sum(c).alias(c) for c in ("zeros", "ones", "children"))).orderBy("key").toPandas()
    level1 = Level(first.key.to_numpy(np.int64).astype(U64), first.zeros.to_numpy(float), first.ones.to_numpy(float), first.children.to_numpy(float))
    key, at = np.unique(level1.key & U64(0xFF), return_inverse=True)
    total = lambda x: np.bincount(at, weights=x, minlength=len(key)) if len(key) else np.zeros(0)
    level0 = Level(key, total(level1.zeros), total(level1.ones), total(level1.log_weighted))
    return model, [level0, level1]


# ---------------------------------------------------------------- scoring

_ASK = pa.schema([("bucket", pa.int32()), ("k", pa.int32()), ("trained_docs", pa.int64()), ("words", pa.binary()), ("trained", pa.binary()), ("codes", pa.binary())])
_ASK_DDL = "bucket int, k int, trained_docs long, words binary, trained binary, codes binary"
_REPLY = pa.schema([("k", pa.int32()), ("bucket", pa.int32()), ("trained_docs", pa.int64()), ("distinct", pa.int64()), ("total", pa.int64()), ("counts", pa.binary()), ("logs", pa.binary())])
_REPLY_DDL = "k int, bucket int, trained_docs long, distinct long, total long, counts binary, logs binary"
#: Bytes of text whose codes are sorted at once.
SLICE = 2 << 20


class _Batch:
    def __init__(self, batch: pa.Table, depth: int, buckets: int, modulus: int, remainder: int):
        self.ids, texts = in_order(batch)
        self.texts = [normalised(t) for t in texts]
        self.held = np.array([held_out(i, modulus, remainder) for i in self.ids], bool)
        self.words = w = Words(self.texts)
        self.distinct, self.word_at = np.unique(w.hash, return_inverse=True)
        trained = np.bincount(self.word_at, weights=~self.held[w.text_of()], minlength=len(self.distinct)) if len(w.hash) else np.zeros(0)
        self.trained = trained.astype("<u4")
        self.word_cut = np.searchsorted(self.distinct >> U64(16), [-(-(i << 48) // buckets) for i in range(buckets)] + [1 << 48])
        self.sizes = np.array([len(t) for t in self.texts])
        self.depth = depth
        # slices of the texts keep the sorted arrays small
        cut = np.unique(np.concatenate([np.searchsorted(np.cumsum(self.sizes), np.arange(0, self.sizes.sum(), SLICE)), [len(self.texts)]]))
        self.slices = [slice(a, b) for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)]
        self.codes = distinct(np.concatenate([distinct(grams(self.texts[x], depth)[0]) for x in self.slices]))
        bucket = bucket_of(self.codes, buckets)
        self.order = np.argsort(bucket, kind="stable")
        self.code_cut = np.searchsorted(bucket[self.order], np.arange(buckets + 1))

    def sums(self, logs: np.ndarray) -> np.ndarray:
        """Each text's sum of the numbers of its codes."""
        out = []
        for x in self.slices:
            code, sizes = grams(self.texts[x], self.depth)
            runs, at = np.unique(code, return_inverse=True)
            each = logs[np.searchsorted(self.codes, runs)][at]
            out.append(np.add.reduceat(each, np.cumsum(sizes) - sizes))
        return np.concatenate(out)


def scores(docs: DataFrame, depth: int = DEPTH, modulus: int = 7, remainder: int = 2) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, n_bytes, bits_per_byte) of every row."""
    model, tops = train(docs, depth, modulus, remainder)
    buckets = shuffle_partitions(docs.sparkSession)
    dealt, _ = batched(docs, per_partition=3)

    def ask(batch: pa.Table) -> pa.Table:
        k = batch.column("k")[0].as_py()
        b = _Batch(batch, depth, buckets, modulus, remainder)

        def rows() -> Iterator[tuple]:
            # every batch asks every bucket, so that it learns the totals of all
            for i in range(buckets):
                w, c = slice(b.word_cut[i], b.word_cut[i + 1]), slice(b.code_cut[i], b.code_cut[i + 1])
                yield i, k, int((~b.held).sum()), pack(b.distinct[w]), b.trained[w].tobytes(), pack(b.codes[b.order[c]])

        return arrow_rows(_ASK, rows())

    def answer(counted: pa.Table, asked: pa.Table) -> pa.Table:
        asked = asked.to_pylist()
        if not asked:
            return arrow_rows(_REPLY, [])
        words = [unpack(r["words"]) for r in asked]
        known, at = np.unique(np.concatenate(words), return_inverse=True)
        n = np.bincount(at, weights=np.concatenate([np.frombuffer(r["trained"], "<u4") for r in asked]), minlength=len(known)).astype(np.int64) if len(known) else np.zeros(0, np.int64)
        own = counted.to_pylist()
        code, count = (unpack(own[0]["codes"]), np.frombuffer(own[0]["counts"], "<u8").astype(float)) if own else (np.zeros(0, U64), np.zeros(0))
        levels = tops + build(code, count, depth, 2)
        codes = [unpack(r["codes"]) for r in asked]
        wanted = distinct(np.concatenate(codes))
        logs = np.concatenate([log_probability(wanted[i:i + 200_000], levels) for i in range(0, len(wanted), 200_000)] or [np.zeros(0)]).astype("<f4")
        start = np.cumsum([0] + [len(w) for w in words])
        trained_docs = sum(r["trained_docs"] for r in asked)
        return arrow_rows(_REPLY, ((r["k"], r["bucket"], trained_docs, int((n > 0).sum()), int(n.sum()), pack_counts(n[at[start[i]:start[i + 1]]]), logs[np.searchsorted(wanted, codes[i])].tobytes()) for i, r in enumerate(asked)))

    out = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64()), ("n_bytes", pa.int64()), ("bits_per_byte", pa.float64())])

    def score(batch: pa.Table, replies: pa.Table) -> pa.Table:
        if not batch.num_rows:
            return arrow_rows(out, [])
        b = _Batch(batch, depth, buckets, modulus, remainder)
        counts, logs = np.zeros(len(b.distinct), np.int64), np.zeros(len(b.codes))
        vocabulary = total = ends = 0
        for r in replies.to_pylist():
            i, ends = r["bucket"], r["trained_docs"]
            vocabulary, total = vocabulary + r["distinct"], total + r["total"]
            counts[b.word_cut[i]:b.word_cut[i + 1]] = unpack_counts(r["counts"])
            logs[b.order[b.code_cut[i]:b.code_cut[i + 1]]] = np.frombuffer(r["logs"], "<f4")
        # the end of a text is a token that every training document has once
        vocabulary, total = vocabulary + (ends > 0), total + ends
        text = b.words.text_of()
        n = len(b.ids)
        c = counts[b.word_at] if len(b.word_at) else np.zeros(0, np.int64)
        base = np.bincount(text, weights=np.log10(c + 1.0), minlength=n) + math.log10(ends + 1) - (b.words.n + 1) * math.log10(total + vocabulary + 1)
        known = np.bincount(text, weights=c > 0, minlength=n).astype(np.int64) + (ends > 0)
        each = b.sums(logs) / _LN10
        return arrow_rows(out, ((b.ids[i], bool(b.held[i]), int(b.words.n[i]) + 1, int(known[i]), int(total), float(base[i]), float(each[i]), int(b.sizes[i]), float(-each[i] * math.log2(10) / b.sizes[i])) for i in range(n)))

    asked = dealt.groupBy("k").applyInArrow(grouped(ask), _ASK_DDL)
    replies = model.groupBy("bucket").cogroup(asked.groupBy("bucket")).applyInArrow(grouped(answer), _REPLY_DDL)
    return dealt.groupBy("k").cogroup(replies.groupBy("k")).applyInArrow(grouped(score), "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, n_bytes long, bits_per_byte double")


def digest(docs: DataFrame) -> DataFrame:
    return scores(docs).select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score", "n_bytes", "bits_per_byte")


def brute_force(texts: list[tuple[int, str | None]], depth: int = DEPTH, modulus: int = 7, remainder: int = 2) -> list[tuple]:
    """The same scores from dictionaries, plainly, for tests."""
    from collections import Counter
    from functools import cache

    norm = [(i, normalised((t or "").encode())) for i, t in texts]
    counts: Counter[tuple[bytes, int, int]] = Counter()
    words: Counter[bytes] = Counter()
    children: dict[bytes, set[bytes]] = {}
    for i, t in norm:
        if held_out(i, modulus, remainder):
            continue
        words.update([*t.split(), _END])
        full = _END * depth + t
        for p in range(depth, len(full)):
            for d in range(depth + 1):
                context = full[p - d:p]
                if d:
                    children.setdefault(context[1:], set()).add(context)
                for b in range(8):
                    counts[context, 1 << b | full[p] >> 8 - b, full[p] >> 7 - b & 1] += 1

    def estimate(z: int, o: int) -> float:
        return math.lgamma(z + 0.5) + math.lgamma(o + 0.5) - math.lgamma(z + o + 1) - math.log(math.pi)

    @cache
    def weighted(context: bytes, node: int) -> tuple[float, float]:
        own = estimate(counts[context, node, 0], counts[context, node, 1])
        if len(context) == depth:
            return own, 1.0
        below = sum(weighted(c, node)[0] for c in sorted(children.get(context, ())) if counts[c, node, 0] + counts[c, node, 1])
        top = max(own, below)
        both = math.log(0.5) + top + math.log(math.exp(own - top) + math.exp(below - top))
        return both, math.exp(own + math.log(0.5) - both)

    @cache
    def log_of(context: bytes, symbol: int) -> float:
        total = 0.0
        for b in range(8):
            node, bit, p = 1 << b | symbol >> 8 - b, symbol >> 7 - b & 1, None
            for d in range(depth, -1, -1):
                c = context[depth - d:]
                n = counts[c, node, 0] + counts[c, node, 1]
                if n:
                    own = (counts[c, node, bit] + 0.5) / (n + 1)
                    w = weighted(c, node)[1]
                    p = own if p is None else w * own + (1 - w) * p
            total += math.log(0.5 if p is None else p)
        return total

    n, v = sum(words.values()), len(words)
    out = []
    for i, t in norm:
        tokens = [*t.split(), _END]
        full = _END * depth + t
        score = sum(log_of(full[p - depth:p], full[p]) for p in range(depth, len(full))) / _LN10
        base = sum(math.log10((words[w] + 1) / (n + v + 1)) for w in tokens)
        out.append((i, held_out(i, modulus, remainder), len(tokens), sum(words[w] > 0 for w in tokens), n, base, score))
    return out

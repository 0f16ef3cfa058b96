"""SimHash near-dedup by the generalised pigeonhole principle.

Fingerprints are majority bits of the shingles' XXH64 hashes. The 64 bits are grouped into partitions, correlated
bits together; if the thresholds of ``m`` partitions sum to ``radius - m + 1``, each pair within ``radius`` is within
the threshold of some partition. Unequal thresholds (-1 leaves a partition out) are allotted by dynamic
programming on the candidates that the partitions' histograms predict. Each distinct fingerprint is put under its
value in each partition and probes the values within the threshold; what meets there is verified on all bits.

A value that more than the mean task's rows share is split into fragments, and each pair of fragments becomes a
cell of its own; nothing is capped. A cell yields a spanning forest of its links, never all pairs. Components
are found by large-star/small-star rounds over tables in the shared folder. The driver sees 64 x 64 bit counts
and histograms of at most 2^16 values a partition, no fingerprints and no links. The number of partitions, four to eight, is the
cheapest by the counts of single bits. A large cell is compared by groups of the bits that vary in it, by the same principle once
more and inside the task, so that a row is sent once however many fingerprints meet.

Near copies (keep_one) are defined by the exact Jaccard of their sets of shingles. Candidates are found by the same search
over several independent fingerprints, of words, as words differ less than shingles do; each candidate pair that is not joined
yet is verified on the sets themselves.

Null texts are empty; a text without words has fingerprint zero and links like any other. A bit that half of the shingles set is 0.
Rows with null ids get the component of their fingerprint, whose id is null if no row of it has one. Repeated rows share a
fingerprint. A very long text is hashed whole; its bits are counted some thousand shingles at a time. Extra columns are ignored.
"""

from __future__ import annotations

import math
import struct
from collections.abc import Callable, Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from embedvocab.llm.common import U64, Words, arrow_rows, distinct, grouped, mix, per_document, shuffle_partitions, written

SEED = 42


def fingerprint(text: bytes, shingle: int = 3) -> int:
    """Majority bits over the hashes of all shingles, repeats included; A-Z count as a-z."""
    words = text.lower().split()
    if not words:
        return 0
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), SEED)
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = (ends - [len(w) + 1 for w in words])[: len(words) - shingle + 1].tolist()
    joined, n = b" ".join(words), len(starts)
    runs = map(joined.__getitem__, map(slice, starts, (ends[shingle - 1:] - 1).tolist()))
    hashes = np.fromiter(map(xxhash.xxh64_intdigest, runs, repeat(SEED)), U64, n)
    ones = np.zeros(64, np.int64)
    for at in range(0, n, 1 << 16):
        ones += np.unpackbits(hashes[at:at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.uint32)
    return int(np.packbits(ones * 2 > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed long."""
    schema = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64())])
    return per_document(docs, lambda ids, texts: ((i, int(np.uint64(fingerprint(t, shingle)).view(np.int64))) for i, t in zip(ids, texts, strict=True)), schema, "doc_id long, fp long")


# ---------------------------------------------------------------- partitions and thresholds

def bit_groups(ones: np.ndarray, both: np.ndarray, n: int, parts: int) -> list[list[int]]:
    """Bits dealt into partitions of equal width; each takes the bits most correlated with those it has."""
    p = ones / max(n, 1)
    sd = np.sqrt(np.maximum(p * (1 - p), 1e-9))
    corr = np.abs((both / max(n, 1) - np.outer(p, p)) / np.outer(sd, sd))
    np.fill_diagonal(corr, 0)
    free, out = set(range(64)), []
    for i in range(parts):
        width = len(free) // (parts - i)
        first = max(free, key=lambda b: (corr[b, sorted(free)].sum(), -b))
        group = [first]
        free.remove(first)
        while len(group) < width:
            best = max(free, key=lambda b: (corr[b, group].sum(), -b))
            group.append(best)
            free.remove(best)
        out.append(sorted(group))
    return out


def allot(costs: list[list[float]], radius: int) -> list[int]:
    """Thresholds -1..radius, one a partition, that sum to radius - m + 1 and cost least; costs[i][t + 1]."""
    best: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
    for own in costs:
        nxt: dict[int, tuple[float, list[int]]] = {}
        for spent, (cost, chosen) in best.items():
            for t in range(-1, radius + 1):
                key, total = spent + t, cost + own[t + 1]
                if key not in nxt or total < nxt[key][0]:
                    nxt[key] = (total, [*chosen, t])
        best = nxt
    return best[radius - len(costs) + 1][1]


def gather(fps: np.ndarray, bits: list[int]) -> np.ndarray:
    """The partition's bits of each fingerprint as a number."""
    out = np.zeros(len(fps), np.int64)
    for i, b in enumerate(bits):
        out |= ((fps >> U64(b)) & U64(1)).astype(np.int64) << i
    return out


def flips(width: int, most: int) -> list[int]:
    """All masks of one to ``most`` bits."""
    return [sum(1 << b for b in c) for t in range(1, most + 1) for c in combinations(range(width), t)]


def predicted(hist: np.ndarray, width: int, radius: int) -> list[float]:
    """Cost of candidates and rows at each threshold -1..radius, from how often each value of the partition occurs."""
    full = hist.astype(float)
    out, near, probes = [0.0], full.copy(), 1
    for t in range(radius + 1):
        if t:
            probes += math.comb(width, t)
            if t >= 3:  # the sums over so many neighbours cost more than they tell; counted as if all values met
                out.append(float(full.sum()) ** 2 / 2 + ROW_COST * probes * float(full.sum()))
                continue
            for m in (m for m in flips(width, t) if m.bit_count() == t):
                near = near + full[np.arange(1 << width) ^ m]
        out.append(float(full @ near) / 2 + ROW_COST * probes * float(full.sum()))
    return out


def finer(fps: np.ndarray, radius: int) -> list[np.ndarray] | None:
    """Keys of a cell's fingerprints such that each pair within the radius agrees on one of them; None if comparing all pairs is cheaper.

    The bits that vary are dealt into radius + 1 groups, of which so many differing bits leave one whole.
    """
    ones = np.unpackbits(fps.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    varying = sorted((int(b) for b in np.flatnonzero((ones > 0) & (ones < len(fps)))), key=lambda b: (abs(2 * int(ones[b]) - len(fps)), b))
    if len(varying) <= radius:
        return None
    keys = [gather(fps, varying[i::radius + 1]) for i in range(radius + 1)]
    pairs = sum(float((np.unique(k, return_counts=True)[1].astype(float) ** 2).sum()) for k in keys)
    return keys if pairs + SORT_COST * len(fps) * len(keys) < float(len(fps)) ** 2 else None


def deepened(costs: list[float], bits: list[int], radius: int, n: int) -> list[tuple[float, bool]]:
    """For each threshold the cheaper of comparing all pairs of a cell and of those that agree on a group of the other bits, see finer(), and which it is.

    With many fingerprints the values of one partition are too few: groups of other bits leave fewer candidates, in the same rows.
    """
    width, groups = (64 - len(bits)) // (radius + 1), radius + 1
    out, probes = [(0.0, False)], 0
    for t, cost in enumerate(costs[1:]):
        probes += math.comb(len(bits), t)
        rows = ROW_COST * probes * n
        deep = (cost - rows) * groups / 2**width + rows + rows * groups / 16
        out.append(min((cost, False), (deep, True)))
    return out


#: What a row that is sent costs, in comparisons of two fingerprints within a cell.
ROW_COST = 64.0
#: What a row's place in the order of one more key costs, in such comparisons.
SORT_COST = 32.0
#: Counts of a partition's values that travel as one row.
CHUNK = 256


def roughly(ones: np.ndarray, n: int, groups: list[list[int]], radius: int) -> float:
    """Cost of the best thresholds for these partitions, as if bits were independent."""
    costs = []
    for bits in groups:
        p = ones[bits] / max(n, 1)
        same = p * p + (1 - p) * (1 - p)
        within = np.zeros(radius + 1)  # chance of two values at each distance
        within[0] = 1.0
        for q in same:
            within[1:] = within[1:] * q + within[:-1] * (1 - q)
            within[0] *= q
        rows = np.cumsum([math.comb(len(bits), t) for t in range(radius + 1)])
        costs.append([0.0, *(np.cumsum(within) * n * n / 2 + ROW_COST * rows * n).tolist()])
    thresholds = allot(costs, radius)
    return sum(c[t + 1] for c, t in zip(costs, thresholds, strict=True))


class Plan:
    """How one column of fingerprints is searched: bits of each partition, thresholds, and into how many fragments heavy values are split."""

    def __init__(self, groups: list[list[int]], thresholds: list[int], heavy: list[np.ndarray]):
        self.groups, self.thresholds, self.heavy = groups, thresholds, heavy


def survey(nodes: DataFrame, names: list[str], radius: int, parts: range) -> list[Plan]:
    """A plan for each column of fingerprints, from counts of all of them; the number of partitions is the cheapest of ``parts``.

    The driver gets 64 x 64 bit counts and at most 2^18 value counts a column, whatever the corpus.
    """

    def count_bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        both, n = np.zeros((len(names), 64, 64)), 0
        for b in batches:
            for i in range(len(names)):
                bits = np.unpackbits(b.column(i).to_numpy().view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(np.float32)
                both[i] += bits.T @ bits
            n += b.num_rows
        counts = np.concatenate([both.ravel(), [n]]).astype(np.int64)
        yield pa.record_batch([pa.array(np.arange(len(counts)), pa.int32()), pa.array(counts)], names=["cell", "n"])

    prints = nodes.select(*names)
    counted = prints.mapInArrow(count_bits, "cell int, n long").groupBy("cell").agg(F.sum("n").alias("n")).toPandas()
    counts = np.zeros(len(names) * 4096 + 1)
    counts[counted["cell"]] = counted["n"]
    n = int(counts[-1])
    groups = []
    for both in counts[:-1].reshape(-1, 64, 64):
        ones = np.diag(both)
        groups.append(min((bit_groups(ones, both, n, k) for k in parts), key=lambda g: roughly(ones, n, g, radius)))

    schema = pa.schema([("name", pa.int32()), ("part", pa.int32()), ("chunk", pa.int32()), ("counts", pa.binary())])

    def values(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = [[np.zeros(1 << len(bits), np.int64) for bits in own] for own in groups]
        for b in batches:
            for i, own in enumerate(groups):
                fps = b.column(i).to_numpy().view(U64)
                for at, bits in zip(seen[i], own, strict=True):
                    at += np.bincount(gather(fps, bits), minlength=len(at))
        for i, own in enumerate(seen):
            chunks = ((i, j, k, at[k * CHUNK:(k + 1) * CHUNK].tobytes()) for j, at in enumerate(own) for k in range(-(-len(at) // CHUNK)))
            yield from arrow_rows(schema, chunks).to_batches()

    def add(rows: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(c.as_buffer(), np.int64) for c in rows.column("counts"))
        return arrow_rows(schema, [(*(rows.column(c)[0].as_py() for c in ("name", "part", "chunk")), total.tobytes())])

    ddl = "name int, part int, chunk int, counts binary"
    hists = [[np.zeros(1 << len(bits), np.int64) for bits in own] for own in groups]
    for r in prints.mapInArrow(values, ddl).groupBy("name", "part", "chunk").applyInArrow(grouped(add), ddl).collect():
        counts = np.frombuffer(r["counts"], np.int64)
        hists[r["name"]][r["part"]][r["chunk"] * CHUNK:r["chunk"] * CHUNK + len(counts)] = counts
    tasks = shuffle_partitions(nodes.sparkSession)
    out = []
    for i, own in enumerate(groups):
        costs = [deepened(predicted(h, len(g), radius), g, radius, n) for h, g in zip(hists[i], own, strict=True)]
        thresholds = allot([[c for c, _ in each] for each in costs], radius)
        rows = []  # of a value: its own and those that probe it
        for hist, bits, t in zip(hists[i], own, thresholds, strict=True):
            v, total = np.arange(len(hist)), hist.copy() if t >= 0 else np.zeros(len(hist), np.int64)
            for m in flips(len(bits), t) if t >= 0 else []:
                total += np.where(v ^ m > v, hist[v ^ m], 0)
            rows.append(total)
        most = max(1024, -(-sum(int(r.sum()) for r in rows) // tasks))
        out.append(Plan(own, thresholds, [np.maximum(1, -(-r // most)) for r in rows]))
    return out


def cells(nodes: DataFrame, names: list[str], plans: list[Plan]) -> DataFrame:
    """(bucket, cell, indexed, fp, node): each fingerprint under its value in each partition and under the values that it probes.

    A value that too many rows share is split into fragments; each pair of them is a cell of its own.
    """
    tasks = shuffle_partitions(nodes.sparkSession)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            node = b.column(len(names)).to_numpy()
            for name, plan in enumerate(plans):
                fps = b.column(name).to_numpy().view(U64)
                for i, (bits, t, heavy) in enumerate(zip(plan.groups, plan.thresholds, plan.heavy, strict=True)):
                    if t < 0:
                        continue
                    own = gather(fps, bits)
                    for m in [0, *flips(len(bits), t)]:
                        at = own ^ m
                        # a probe below its own value would meet the same pairs again
                        keep = np.arange(len(at)) if not m else np.flatnonzero(at < own)
                        s = heavy[at[keep]]
                        times = np.repeat(np.arange(len(keep)), s)
                        mine = (mix(fps[keep][times], 3) % s[times].astype(U64)).astype(np.int64)
                        other = np.arange(len(times)) - np.repeat(np.cumsum(s) - s, s)
                        cell = mix(at[keep][times].astype(U64) * U64(64 * 64) + U64(64 * name + i), 11)
                        cell = mix(cell + np.minimum(mine, other).astype(U64) * U64(1 << 32) + np.maximum(mine, other).astype(U64), 12)
                        which = keep[times]
                        columns = [pa.array((cell % U64(4 * tasks)).astype(np.int32)), pa.array(cell.view(np.int64)), pa.array(np.full(len(times), not m)), pa.array(fps[which].view(np.int64)), pa.array(node[which])]
                        yield pa.record_batch(columns, names=["bucket", "cell", "indexed", "fp", "node"])

    return nodes.select(*names, "node").mapInArrow(deal, "bucket int, cell long, indexed boolean, fp long, node long")


# ---------------------------------------------------------------- verified links

def _merge(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Joins the classes of a[i] and b[i]; labels stay the least index of their class."""
    while True:
        la, lb = label[a], label[b]
        apart = la != lb
        if not apart.any():
            return
        a, b, la, lb = a[apart], b[apart], la[apart], lb[apart]
        np.minimum.at(label, np.maximum(la, lb), np.minimum(la, lb))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label[:] = up


def _compare(label: np.ndarray, at: np.ndarray, key: np.ndarray, near: Callable[[np.ndarray, np.ndarray], np.ndarray], finer: Callable[[np.ndarray], list[np.ndarray] | None] | None = None) -> None:
    """Joins the labels of all places ``at``, ordered by key, that are linked and of equal key; finer gives a large key's places keys of which linked places share one."""
    n = len(at)
    begin = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if n else np.zeros(0, int)
    size = np.diff([*begin, n])
    small = np.repeat(size <= 48, size)
    for gap in range(1, 48):
        i = np.flatnonzero((key[:-gap] == key[gap:]) & small[:-gap]) if n > gap else np.zeros(0, int)
        if not len(i):
            break
        i = i[near(at[i], at[i + gap])]
        _merge(label, at[i], at[i + gap])
    for s, c in zip(begin[size > 48], size[size > 48], strict=True):
        own = at[s:s + c]
        if finer and (keys := finer(own)):
            inner = np.arange(c)
            for k in keys:
                order = np.argsort(k, kind="stable")
                _compare(inner, order, k[order], lambda a, b, own=own: near(own[a], own[b]))
            child = np.flatnonzero(inner != np.arange(c))
            _merge(label, own[child], own[inner[child]])
            continue
        for i in range(0, c, 256):
            linked = near(own[i:i + 256, None], own[None, i:])
            linked &= label[own[i:i + 256], None] != label[None, own[i:]]
            a, b = np.nonzero(linked)
            _merge(label, own[a + i], own[b + i])


def forest(cell: np.ndarray, near: Callable[[np.ndarray, np.ndarray], np.ndarray], split: Callable[[np.ndarray], list[np.ndarray] | None] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Edges, as pairs of places, that join all places linked within a cell; near tells of places, arrays that broadcast, which are linked.

    split gives keys of a large cell's places of which linked places share one at least, or None.
    """
    order = np.argsort(cell, kind="stable")
    label = np.arange(len(cell))
    _compare(label, label.copy(), cell[order], lambda a, b: near(order[a], order[b]), split and (lambda at: split(order[at])))
    child = np.flatnonzero(label != np.arange(len(cell)))
    return order[child], order[label[child]]


def within(fps: np.ndarray, indexed: np.ndarray, radius: int) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    """Links of fingerprints that differ in so many bits at most, of which at least one is indexed."""
    return lambda a, b: (np.bitwise_count(fps[a] ^ fps[b]) <= radius) & (indexed[a] | indexed[b])


def links(nodes: DataFrame, radius: int = 3, parts: range = range(4, 9)) -> DataFrame:
    """(a, b): edges between the nodes (node, fp) of distinct fingerprints whose closure is that of all pairs within radius.

    Fewer than four partitions would have histograms too large for the driver.
    """
    if not parts or min(parts) < 4 or max(parts) > 16:
        raise ValueError("between 4 and 16 partitions")

    def verify(rows: pa.Table) -> pa.Table:
        column = lambda c: rows.column(c).to_numpy()
        fps = column("fp").view(U64)
        a, b = forest(column("cell"), within(fps, column("indexed").astype(bool), radius), lambda at: finer(fps[at], radius))
        return pa.table({"a": column("node")[a], "b": column("node")[b]})

    return cells(nodes, ["fp"], survey(nodes, ["fp"], radius, parts)).groupBy("bucket").applyInArrow(grouped(verify), "a long, b long").distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, root): the least node that each node with an edge (a, b) reaches, by large-star/small-star rounds."""
    lower = lambda a, b: (F.greatest(a, b).alias("a"), F.least(a, b).alias("b"))
    now = written(edges.filter("a <> b").select(*lower(F.col("a"), F.col("b"))).distinct())
    state = None
    while True:
        ends = now.select(F.col("a").alias("u"), F.col("b").alias("v")).union(now.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = written(ends.groupBy("u").agg(F.least("u", F.min("v")).alias("m")))
        large = ends.filter("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).distinct()
        large = written(large)
        least = written(large.groupBy("a").agg(F.min("b").alias("m")))
        pairs = large.join(least, "a")
        now = written(pairs.select("a", F.col("m").alias("b")).union(pairs.filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))).distinct())
        new = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)"))).first()
        if new == state:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
        state = new


def classes(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(node, component_id): the least id that each node's documents reach over the edges; nodes has node and least_id."""
    roots = components(edges)
    rooted = written(nodes.join(roots.withColumnRenamed("node", "_n"), F.col("node") == F.col("_n"), "left").select("node", "least_id", F.coalesce("root", "node").alias("root")))
    least = written(rooted.groupBy("root").agg(F.min("least_id").alias("component_id")))
    return written(rooted.join(least, "root").select("node", "component_id"))


def near_duplicates(docs: DataFrame, shingle: int = 3, radius: int = 3, parts: range = range(4, 9)) -> DataFrame:
    """(doc_id, fp, component_id): the least id of all documents reachable over links of at most radius bits."""
    prints = written(fingerprints(docs, shingle))
    nodes = written(prints.groupBy(F.col("fp").alias("node")).agg(F.min("doc_id").alias("least_id"), F.first("fp").alias("fp")))
    found = classes(nodes, links(nodes, radius, parts))
    return prints.join(found, F.col("fp") == F.col("node")).select("doc_id", "fp", "component_id")


# ---------------------------------------------------------------- near copies by exact Jaccard

#: Independent fingerprints of a text's words that search for near copies, and the share of the hardest pairs they may miss.
PRINTS, MISS = 4, 0.2
#: Partitions of a print; with more, rows are fewer and candidates more.
PARTS = range(6, 7)
#: Members of a candidate group, and shingles of them all, beyond which it is split into fragments.
CELL, CELL_SHINGLES = 2048, 1 << 22
#: Distinct words whose bits are counted at once.
_AT_ONCE = 1 << 14


def radius_of(similarity: float, prints: int = PRINTS, miss: float = MISS) -> int:
    """The least radius at which no print of a pair lies within it with at most this chance.

    The hardest pair of a Jaccard similarity is a text and the same text with more at the end: one set holds the other,
    and each bit differs with the chance acos(sqrt(similarity)) / pi. Edits all over a text leave far more words alike.
    """
    p, below = math.acos(math.sqrt(similarity)) / math.pi, 0.0
    for r in range(64):
        below += math.comb(64, r) * p**r * (1 - p) ** (64 - r)
        if (1 - below) ** prints <= miss:
            return r
    return 64


def shingle_sets(texts: list[bytes], shingle: int) -> Iterator[np.ndarray]:
    """Of each text the sorted distinct hashes of its shingles; a text of fewer words is one shingle, one without words too. A-Z count as a-z."""
    w = Words([t.lower() for t in texts])
    runs = w.rolling(shingle)
    for a, b in zip(w.first[:-1], w.first[1:], strict=True):
        yield _shingles(w, runs, a, b, shingle)


def _shingles(w: Words, runs: np.ndarray, a: int, b: int, shingle: int) -> np.ndarray:
    if b - a >= shingle:
        return distinct(mix(runs[a:b - shingle + 1], 5))
    return np.array([np.bitwise_xor.reduce(mix(w.hash[a:b] + np.arange(b - a).astype(U64), 4))], U64)


def node_of(own: np.ndarray) -> int:
    return struct.unpack("<q", xxhash.xxh64_digest(own.tobytes(), SEED)[::-1])[0]


def word_prints(words: np.ndarray) -> np.ndarray:
    """PRINTS fingerprints, signed, of the distinct hashes of a text's words; zero without words."""
    if not len(words):
        return np.zeros(PRINTS, np.int64)
    ones = np.zeros((PRINTS, 64), np.int64)
    for at in range(0, len(words), _AT_ONCE):
        each = np.stack([mix(words[at:at + _AT_ONCE], 20 + i) for i in range(PRINTS)])
        ones += np.unpackbits(each.view(np.uint8).reshape(PRINTS, -1, 8), axis=2, bitorder="little").sum(axis=1, dtype=np.uint32)
    return np.packbits(ones * 2 > len(words), axis=1, bitorder="little").view("<i8").ravel()


def copy_prints(docs: DataFrame, shingle: int) -> DataFrame:
    """(_id, _hash, node, size, p0, p1, ...) of docs (doc_id, text): equal sets of shingles are one node; the hash is that of the text."""
    names = [f"p{i}" for i in range(PRINTS)]
    schema = pa.schema([("_id", pa.int64()), ("_hash", pa.int64()), ("node", pa.int64()), ("size", pa.int64()), *((c, pa.int64()) for c in names)])

    def run(ids: list, texts: list[bytes]) -> Iterator[tuple]:
        w = Words([t.lower() for t in texts])
        runs = w.rolling(shingle)
        for doc_id, text, a, b in zip(ids, texts, w.first[:-1], w.first[1:], strict=True):
            own = int(np.uint64(xxhash.xxh64_intdigest(text, SEED)).view(np.int64))
            shingles = _shingles(w, runs, a, b, shingle)
            yield doc_id, own, node_of(shingles), len(shingles), *word_prints(distinct(w.hash[a:b])).tolist()

    ddl = ", ".join(f"{f} long" for f in schema.names)
    return per_document(docs, run, schema, ddl, most=4 << 20)


def alike(sets: list[np.ndarray], label: np.ndarray, similarity: float) -> list[tuple[int, int]]:
    """Pairs of places whose sets have at least this Jaccard similarity, as many as join what such pairs join; equal labels are joined already."""
    n = np.array([len(s) for s in sets])
    flat, starts = np.unique(np.concatenate(sets), return_inverse=True)[1], np.cumsum(n) - n
    label, out = label.copy(), []
    seen = np.zeros(len(flat), bool)
    for i in range(len(sets) - 1):
        if (label[i + 1:] == label[i]).all():
            continue
        own = flat[starts[i]:starts[i] + n[i]]
        seen[own] = True
        both = np.add.reduceat(seen[flat], starts, dtype=np.int64)
        seen[own] = False
        for j in np.flatnonzero(both / (n + n[i] - both) >= similarity):
            if label[j] != label[i]:
                out.append((i, int(j)))
                label[label == label[j]] = label[i]
    return out


#: Which row a document is: rows without an id come after all ids, and rows that share one are told apart by their texts.
_WHO = ["_none", "_id", "_hash"]


def who(doc_id: Column, text_hash: Column) -> list[Column]:
    return [doc_id.isNull().alias("_none"), F.coalesce(doc_id.cast("long"), F.lit(0)).alias("_id"), text_hash.alias("_hash")]


#: Rows of a table that a join broadcasts, some 25 MB; beyond it both sides are shuffled.
SMALL = 1 << 20


def small(table: DataFrame) -> DataFrame:
    """A written table, to be broadcast if it is counted to be small, so that texts stay where they are."""
    return F.broadcast(table) if table.count() <= SMALL else table


def verified(cells: DataFrame, rows: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """(a, b) from cells (cell, node, root, _none, _id, _hash): edges of exact Jaccard that join, besides equal roots, all such pairs of each cell.

    rows (_none, _id, _hash, text) have the texts, which travel once to their row's cell.
    """
    tasks = shuffle_partitions(cells.sparkSession)

    def verify(table: pa.Table) -> pa.Table:
        table = table.sort_by([("cell", "ascending"), ("node", "ascending")])
        cell, node, root = (table.column(c).to_numpy() for c in ("cell", "node", "root"))
        first = np.concatenate([[True], (cell[1:] != cell[:-1]) | (node[1:] != node[:-1])])  # rows that repeat id and text
        table, cell, node, root = table.filter(pa.array(first)), cell[first], node[first], root[first]
        text = table.column("text").cast(pa.binary())
        edges: list[tuple[int, int]] = []
        for at, end in zip(begin := [0, *(np.flatnonzero(cell[1:] != cell[:-1]) + 1)], [*begin[1:], len(cell)], strict=True):
            sets = list(shingle_sets(text.slice(at, end - at).to_pylist(), shingle))
            edges += [(at + i, at + j) for i, j in alike(sets, root[at:end], similarity)]
        pairs = np.array(edges, int).reshape(-1, 2)
        return pa.table({"a": node[pairs[:, 0]], "b": node[pairs[:, 1]]})

    placed = written(cells.withColumn("bucket", F.pmod(F.xxhash64("cell"), F.lit(4 * tasks)).cast("int")))
    joined = rows.join(small(placed), _WHO).select("bucket", "cell", "node", "root", "text")
    return written(joined.groupBy("bucket").applyInArrow(grouped(verify), "a long, b long").distinct())


def wide_limit(similarity: float) -> int:
    """Bits of all prints together within which the hardest pairs of this similarity lie, see radius_of(), but for some 2 in 10,000."""
    p, n = math.acos(math.sqrt(similarity)) / math.pi, 64 * PRINTS
    return math.floor(n * p + 3.5 * math.sqrt(n * p * (1 - p)))


def candidate_groups(nodes: DataFrame, similarity: float) -> DataFrame:
    """(node, cell): groups of nodes such that pairs of which one print lies within the radius, and all together within the wide limit, share one; no pair is listed.

    In each cell of the search the links by one print join nodes to groups. These get all prints, by which most chance links fall
    apart. What is left of all cells joins to components, so that a node is in one group and its text travels to one place.
    """
    names, radius, limit = [f"p{i}" for i in range(PRINTS)], radius_of(similarity), wide_limit(similarity)

    def group(rows: pa.Table) -> pa.Table:
        cell, node = rows.column("cell").to_numpy(), rows.column("node").to_numpy()
        fps = rows.column("fp").to_numpy().view(U64)
        child, root = forest(cell, within(fps, rows.column("indexed").to_numpy().astype(bool), radius), lambda at: finer(fps[at], radius))
        heads = np.unique(root)
        head = np.concatenate([root, heads])
        name = mix(cell[head].view(U64) + mix(node[head].view(U64), 13), 14).view(np.int64)
        return pa.table({"cell": name, "node": node[np.concatenate([child, heads])]})

    def refine(rows: pa.Table) -> pa.Table:
        node = rows.column("node").to_numpy()
        fps = [rows.column(c).to_numpy().view(U64) for c in names]
        a, b = forest(rows.column("cell").to_numpy(), lambda a, b: sum(np.bitwise_count(f[a] ^ f[b]).astype(np.int16) for f in fps) <= limit)
        return pa.table({"a": node[a], "b": node[b]})

    found = written(cells(nodes, names, survey(nodes, names, radius, PARTS)).groupBy("bucket").applyInArrow(grouped(group), "cell long, node long"))
    tasks = shuffle_partitions(nodes.sparkSession)
    wide = found.join(nodes.select("node", *names), "node").withColumn("bucket", F.pmod(F.xxhash64("cell"), F.lit(4 * tasks)).cast("int"))
    links = wide.groupBy("bucket").applyInArrow(grouped(refine), "a long, b long")
    joined = components(links)
    return written(joined.select("node", F.col("root").alias("cell")).union(joined.select("root", "root").distinct()))


def copy_links(nodes: DataFrame, rows: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """(a, b): edges of exact Jaccard between nodes whose closure is that of all pairs in a candidate group; rows (_none, _id, _hash, text).

    A large group is split into fragments, by another hash in each. Pairs across fragments are compared afterwards
    where they are not joined yet, so that groups of copies cost little and no pair is left out.
    """
    groups = candidate_groups(nodes, similarity).join(nodes.select("node", "size", "least_id.*"), "node")
    per = groups.groupBy("cell").agg(F.greatest(F.ceil(F.count(F.lit(1)) / CELL), F.ceil(F.sum("size") / CELL_SHINGLES)).cast("int").alias("parts"))
    members = written(groups.join(per, "cell"))
    fragment = F.pmod(F.xxhash64("node", "cell"), F.col("parts")).cast("int")

    def compared(cells: DataFrame) -> DataFrame:
        """Cells whose members are joined already are not compared."""
        apart = cells.groupBy("cell").agg(F.min("root").alias("r"), F.max("root").alias("s")).filter("r <> s")
        return verified(cells.join(apart, "cell", "left_semi").select("cell", "node", "root", *_WHO), rows, shingle, similarity)

    edges = compared(members.select(F.when(F.col("parts") > 1, F.xxhash64("cell", fragment)).otherwise(F.col("cell")).alias("cell"), "node", F.col("node").alias("root"), *_WHO))
    large = members.filter("parts > 1")
    if large.isEmpty():
        return edges
    roots = components(edges).withColumnRenamed("node", "_n")
    large = large.join(roots, F.col("node") == F.col("_n"), "left").select("cell", "node", "parts", fragment.alias("own"), F.coalesce("root", "node").alias("root"), *_WHO)
    apart = large.groupBy("cell").agg(F.min("root").alias("r"), F.max("root").alias("s")).filter("r <> s")
    crossed = large.join(apart, "cell", "left_semi").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).filter("own <> other")
    return edges.unionByName(compared(crossed.select(F.xxhash64("cell", F.least("own", "other"), F.greatest("own", "other")).alias("cell"), "node", "root", *_WHO)))


def keep_one(docs: DataFrame, shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """The document with the least id of each group of near copies, all columns kept.

    Documents link if the exact Jaccard of their sets of shingles is at least ``similarity``. Candidates are pairs of which one of
    several fingerprints, made of the distinct words, lies within radius_of(similarity) bits. Rows without an id come after all ids;
    of rows that share an id and no likeness all stay, of rows that repeat id and text one. Null texts are empty, and all
    texts without words are copies of each other. Columns may have any names.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"), text.alias("text"), *who(F.col("doc_id"), F.xxhash64(text)))
    found = copy_prints(docs, shingle)
    names = [f"p{i}" for i in range(PRINTS)]
    prints = written(found.select(*who(F.col("_id"), F.col("_hash")), "node", "size", *names))
    least = F.struct(*_WHO)
    nodes = written(prints.groupBy("node").agg(F.min(least).alias("least_id"), *(F.first(c).alias(c) for c in ("size", *names))))
    found = classes(nodes, copy_links(nodes, rows.select(*_WHO, "text"), shingle, similarity))
    gone = written(prints.join(found, "node").filter(least != F.col("component_id")).select(*_WHO).distinct())
    again = written(prints.groupBy(*_WHO).count().filter("count > 1").select(*_WHO))
    again = small(again)
    kept = rows.drop("text").join(small(gone), _WHO, "left_anti")
    once = kept.join(again, _WHO, "left_anti")
    repeated = kept.join(again, _WHO, "left_semi").dropDuplicates(_WHO)
    return once.unionByName(repeated).select("_row.*")


def digest(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint as 16 hexadecimal digits, component_id)."""
    return near_duplicates(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def brute_force(texts: list[tuple[int, str | None]], shingle: int = 3, radius: int = 3) -> list[tuple[int, str, int]]:
    """The definition, plainly, for tests."""
    fps = []
    for i, t in texts:
        words = (t or "").encode().lower().split()
        runs = [words[j:j + shingle] for j in range(len(words) - shingle + 1)] or ([words] if words else [])
        hashes = [xxhash.xxh64_intdigest(b" ".join(r), SEED) for r in runs]
        fps.append((i, sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))))
    parent = list(range(len(fps)))

    def find(x: int) -> int:
        while parent[x] != x:
            x = parent[x]
        return x

    values = np.array([f for _, f in fps], U64)
    for x in range(len(fps)):
        for y in np.flatnonzero(np.bitwise_count(values[x + 1:] ^ values[x]) <= radius) + x + 1:
            a, b = find(x), find(int(y))
            parent[max(a, b)] = min(a, b)
    least: dict[int, int] = {}
    for x, (i, _) in enumerate(fps):
        least[find(x)] = min(i, least.get(find(x), i))
    return [(i, f"{f:016x}", least[find(x)]) for x, (i, f) in enumerate(fps)]

"""Word alignment by expectation maximisation, without a table of the pairs of words.

For one target word a round needs only its own probabilities, the pairs of sentences that hold it, and one sum for each source
word. So target words are dealt into groups, and a group is written once, as the bags of its pairs and the places of its words.
A round reads the groups and sends the sums of source words, nothing else; the probabilities of earlier rounds are made again
from the earlier rounds' sums, in memory, a few words at a time.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from embedvocab.sources.shared import new_path, stored

#: Words of bags and places of target words that a group holds, about; pairs of words that are formed at once.
BAGS, PLACES, BATCH = 1 << 25, 1 << 22, 1 << 19
#: Sums that travel together, and rows of a batch of results.
CHUNK, ROWS = 4096, 1 << 16

#: words: distinct target words; size: source words of each pair of sentences; e, n: these words, pair by pair, and their counts;
#: f, pair, m: which word occurs in which pair, how often.
Block = dict[str, pa.Array]


def _packed(block: Block) -> bytes:
    lists = [pa.ListArray.from_arrays(pa.array([0, len(a)], pa.int32()), a) for a in block.values()]
    row, out = pa.record_batch(lists, names=list(block)), pa.BufferOutputStream()
    with pa.ipc.new_stream(out, row.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
        w.write_batch(row)
    return out.getvalue().to_pybytes()


def _unpacked(data: bytes) -> Block:
    row = pa.ipc.open_stream(data).read_next_batch()
    return {name: row.column(i).flatten() for i, name in enumerate(row.schema.names)}


def _ints(a: np.ndarray) -> pa.Array:
    return pa.array(a.astype(np.int32))


def _spans(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Positions of all runs, one after the other."""
    return np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes - starts, sizes)


def _counted(lists: pa.Array, codes: np.ndarray, kinds: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(list, code, count) of the distinct codes of each list, in order."""
    at = pc.list_parent_indices(lists).to_numpy(zero_copy_only=False).astype(np.int64)
    key, n = np.unique(at * kinds + codes, return_counts=True)
    return key // kinds, key % kinds, n


def _parts(src: pa.Array, tgt: pa.Array, known: pa.Array, groups: int) -> Iterator[tuple[int, bytes]]:
    """(group, block) of pairs of sentences: a word's group follows from the word alone."""
    own = pc.index_in(src.flatten(), value_set=known).to_numpy(zero_copy_only=False)
    at, e, n = _counted(src, own, len(known))
    size = np.bincount(at, minlength=len(src))
    start = np.cumsum(size) - size
    coded = tgt.flatten().dictionary_encode()
    pair, f, m = _counted(tgt, coded.indices.to_numpy(zero_copy_only=False), max(1, len(coded.dictionary)))
    of = np.array([zlib.crc32(w.encode()) % groups for w in coded.dictionary.to_pylist()], np.int64)[f]
    order = np.argsort(of, kind="stable")
    there, first = np.unique(of[order], return_index=True)
    for g, rows in zip(there.tolist(), np.split(order, first[1:])):
        pairs, p = np.unique(pair[rows], return_inverse=True)
        words, w = np.unique(f[rows], return_inverse=True)
        cells = _spans(start[pairs], size[pairs])
        yield g, _packed({"words": coded.dictionary.take(pa.array(words)), "size": _ints(size[pairs]), "e": _ints(e[cells]), "n": _ints(n[cells]), "f": _ints(w), "pair": _ints(p), "m": _ints(m[rows])})


def _merged(parts: list[Block]) -> Block:
    """One block, its places in the order of their words."""
    words = pa.concat_arrays([b["words"] for b in parts]).dictionary_encode()
    codes, joined = words.indices.to_numpy(zero_copy_only=False), {k: np.concatenate([b[k].to_numpy() for b in parts]) for k in ("size", "e", "n", "f", "pair", "m")}
    n_words, n_pairs, n_rows = ([len(b[k]) for b in parts] for k in ("words", "size", "f"))
    f = codes[joined["f"] + np.repeat(np.cumsum(n_words) - n_words, n_rows)]
    pair = joined["pair"] + np.repeat(np.cumsum(n_pairs) - n_pairs, n_rows)
    order = np.argsort(f, kind="stable")
    return {"words": words.dictionary, "size": _ints(joined["size"]), "e": _ints(joined["e"]), "n": _ints(joined["n"]), "f": _ints(f[order]), "pair": _ints(pair[order]), "m": _ints(joined["m"][order])}


def _expected(block: Block, sums: list[np.ndarray], kinds: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(e, f, c): expected counts of all pairs of words after as many rounds as there are sums, some words' pairs at a time."""
    e, n, f, pair, m = (block[k].to_numpy() for k in ("e", "n", "f", "pair", "m"))
    size = block["size"].to_numpy().astype(np.int64)
    start = np.cumsum(size) - size
    heads = np.flatnonzero(np.diff(f, prepend=-1))  # where a word's places begin
    ends = np.append(heads[1:], len(f))
    upto = np.cumsum(size[pair])
    a = 0
    while a < len(heads):
        before = upto[heads[a]] - size[pair[heads[a]]]
        b = max(a + 1, int(np.searchsorted(upto[ends - 1], before + BATCH, "right")))
        rows = slice(heads[a], ends[b - 1])
        if upto[ends[b - 1] - 1] - before > BATCH:
            # one word in very many pairs: its places come in turns, its counts are as long as the vocabulary
            c, t = np.zeros(kinds), np.ones(kinds)
            cuts = np.searchsorted(upto[rows], np.arange(before + BATCH, upto[rows][-1], BATCH))
            turns = [x for x in np.split(np.arange(rows.start, rows.stop), cuts) if len(x)]
            for k in range(len(sums) + 1):
                if k:
                    t = np.divide(c, sums[k - 1], out=np.zeros(kinds), where=seen)
                c = np.zeros(kinds)
                for x in turns:
                    at = _spans(start[pair[x]], size[pair[x]])
                    c += _shared(n[at], t, e[at], size[pair[x]], m[x], kinds)
                if not k:
                    seen = c > 0
            own = np.flatnonzero(seen)
            yield own, np.full(len(own), f[rows.start]), c[own]
        else:
            sizes = size[pair[rows]]
            at = _spans(start[pair[rows]], sizes)
            key, cell = np.unique(np.repeat(f[rows].astype(np.int64), sizes) * kinds + e[at], return_inverse=True)
            own, counts = key % kinds, n[at]
            c, t = None, np.ones(len(key))
            for k in range(len(sums) + 1):
                t = c / sums[k - 1][own] if k else t
                c = _shared(counts, t, cell, sizes, m[rows], len(key))
            yield own, key // kinds, c
        a = b


def _shared(n: np.ndarray, t: np.ndarray, cell: np.ndarray, sizes: np.ndarray, m: np.ndarray, kinds: int) -> np.ndarray:
    """Each place's m occurrences, shared among the words of its bag by n times t, and summed by cell."""
    p = n * t[cell]
    p *= np.repeat(m / np.add.reduceat(p, np.cumsum(sizes) - sizes), sizes)
    return np.bincount(cell, p, minlength=kinds)


def merge_pairs(pairs: DataFrame) -> DataFrame:
    """(src, tgt) of (pair_id, src, tgt), with no word as a null before each src; rows of one id are one pair."""
    rows = pairs.filter("pair_id is not null").select(
        "pair_id", F.concat(F.array(F.lit(None).cast("string")), F.coalesce("src", F.array().cast("array<string>"))).alias("src"), F.array_compact(F.coalesce("tgt", F.array().cast("array<string>"))).alias("tgt"))
    if not pairs.groupBy("pair_id").count().filter("count > 1").isEmpty():
        rows = rows.groupBy("pair_id").agg(F.flatten(F.collect_list("src")).alias("src"), F.flatten(F.collect_list("tgt")).alias("tgt"))
    return rows.filter(F.size("tgt") > 0).select("src", "tgt")


def fit(pairs: DataFrame, iterations: int) -> DataFrame:
    """(e, f, t) of translate.fit_alignment()."""
    spark = pairs.sparkSession
    context = spark.sparkContext
    rows = stored(merge_pairs(pairs))
    # the first round's sums have a closed form, as all words of a bag share alike
    vocabulary = rows.select(F.explode("src").alias("e"), (F.size("tgt") / F.size("src")).alias("s")).groupBy("e").agg(F.count(F.lit(1)).alias("n"), F.sum("s").alias("s"))
    table = vocabulary.select("e", "n", "s").toArrow().sort_by([("n", "descending"), ("e", "ascending")])
    known = table.column("e").combine_chunks()
    kinds, sums = len(known), [table.column("s").to_numpy()] if iterations > 0 else []
    own, places = F.size(F.array_distinct("src")).cast("long"), F.size(F.array_distinct("tgt"))
    n = rows.agg(*(F.coalesce(F.sum(x), F.lit(0)).alias(k) for k, x in (("bags", own), ("places", places), ("cells", own * places)))).first()
    # a group holds a bag once, so all of them at most, and one for each place at most
    groups = max(1, -(-n.places // PLACES), -(-n.cells // BAGS) if n.bags > BAGS else 0)
    groups = -(-groups // context.defaultParallelism) * context.defaultParallelism
    words = context.broadcast(known)

    def parts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = list(_parts(b.column(0), b.column(1), words.value, groups))
            yield pa.record_batch([pa.array([g for g, _ in found], pa.int32()), pa.array([x for _, x in found], pa.binary())], names=["g", "block"])

    def merged(table: pa.Table) -> pa.Table:
        whole = _packed(_merged([_unpacked(x.as_py()) for x in table.column("block")]))
        return pa.table({"g": table.column("g").slice(0, 1), "block": pa.array([whole], pa.binary())})

    path = new_path(spark)
    blocks = rows.mapInArrow(parts, "g int, block binary").groupBy("g").applyInArrow(merged, "g int, block binary")
    blocks.write.option("maxRecordsPerFile", 1).parquet(path)  # a group a file, so that groups can be dealt evenly
    blocks = spark.read.schema(blocks.schema).parquet(path).select("block")

    def over(use: Callable[[Block], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
        return lambda batches: (out for b in batches for x in b.column(0) for out in use(_unpacked(x.as_py())))

    while len(sums) < iterations:
        known_sums = context.broadcast(sums)

        def totals(batches: Iterator[pa.RecordBatch], known_sums=known_sums) -> Iterator[pa.RecordBatch]:
            total = np.zeros(kinds)
            for b in batches:
                for x in b.column(0):
                    for e, _, c in _expected(_unpacked(x.as_py()), known_sums.value, kinds):
                        total += np.bincount(e, c, minlength=kinds)
            starts = range(0, kinds if total.any() else 0, CHUNK)
            yield pa.record_batch([pa.array([k // CHUNK for k in starts], pa.int32()), pa.array([total[k:k + CHUNK] for k in starts], pa.list_(pa.float64()))], names=["chunk", "xs"])

        sent = blocks.mapInArrow(totals, "chunk int, xs array<double>").repartition("chunk")
        summed = sent.select("chunk", F.posexplode("xs").alias("i", "x")).groupBy("chunk", "i").agg(F.sum("x").alias("s"))
        got = summed.select((F.col("chunk") * CHUNK + F.col("i")).alias("e"), "s").toArrow()
        new = np.zeros(kinds)
        new[got.column("e").to_numpy()] = got.column("s").to_numpy()
        sums = [*sums, new]

    known_sums = context.broadcast(sums)

    def results(block: Block) -> Iterator[pa.RecordBatch]:
        *before, last = known_sums.value or [None]
        for e, f, c in _expected(block, before, kinds):
            t = np.ones(len(c)) if last is None else c / last[e]
            for k in range(0, len(c), ROWS):
                yield pa.record_batch([words.value.take(pa.array(e[k:k + ROWS])), block["words"].take(pa.array(f[k:k + ROWS])), pa.array(t[k:k + ROWS])], names=["e", "f", "t"])

    return blocks.mapInArrow(over(results), "e string, f string, t double")

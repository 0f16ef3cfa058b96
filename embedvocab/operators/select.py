"""Choosing which occurrences to replace."""

from __future__ import annotations

import heapq

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from embedvocab.functions import memory, rng
from embedvocab.functions.memory import Boost


def scored(candidates: DataFrame, boost: Boost = Boost(), ablate: str | None = None, seed: int = 42, ahead: float = 0.0) -> DataFrame:
    """Candidates (doc_id, pos, lemma, r, g, half_life) with p, gamma and priority.

    Ablations: tutor_only drops the context, context_only the memory, random draws the priority. With ``ahead``, words that come up
    again soon gain that much of their priority for each doubling of their coming uses (upcoming, see lookahead()).
    """
    r = F.lit(0.0) if ablate == "context_only" else F.col("r")
    g = F.lit(0.0) if ablate == "tutor_only" else F.col("g")
    h = F.lit(boost.initial) if ablate == "context_only" else F.coalesce("half_life", F.lit(boost.initial))
    p, gamma = memory.understanding(r, g), memory.boost(h, r, boost)
    priority = rng.uniform(seed, F.col("doc_id"), F.col("pos")) if ablate == "random" else memory.priority(p, gamma)
    if ahead:
        priority = priority * (1 + ahead * F.log2(1 + F.coalesce(F.col("upcoming"), F.lit(0))))
    # rounded, so that equal scores tie whatever the last bit of a power
    return candidates.select("doc_id", "pos", "lemma", r.alias("r"), g.alias("g"), p.alias("p"), gamma.alias("gamma"), F.round(priority, 9).alias("priority"))


def top_k(rows: DataFrame, k: DataFrame, per_lemma: int | str | None = None) -> DataFrame:
    """The k best of each document by priority, earlier positions first, with their rank; k is (doc_id, k).

    ``per_lemma`` 1 keeps the best occurrence of each lemma; "all" shows every occurrence of the lemmas chosen so.
    """
    best = Window.partitionBy("doc_id").orderBy(F.desc("priority"), "pos")
    pool = rows
    if per_lemma is not None:
        pool = rows.withColumn("_o", F.row_number().over(Window.partitionBy("doc_id", "lemma").orderBy(F.desc("priority"), "pos"))).filter("_o = 1").drop("_o")
    ranked = pool.withColumn("rank", F.row_number().over(best))
    kept = ranked.join(k, "doc_id").filter(F.col("rank") <= F.col("k")).drop("k")
    if per_lemma == "all":
        return rows.join(kept.select("doc_id", "lemma", "rank"), ["doc_id", "lemma"])
    return kept


def rescored(rows: DataFrame, k: DataFrame, boost: Boost = Boost()) -> DataFrame:
    """(doc_id, pos, lemma, priority, rank): greedy choice where showing a lemma sets its recall to one for its later occurrences.

    One document at a time; its candidates are what one reader reads, so a group is bounded. A heap holds the candidates by their
    worth; showing a lemma changes the worth of its own occurrences only, and those are put in anew.
    """
    joined = rows.join(k, "doc_id").select("doc_id", "pos", "lemma", "r", "g", "half_life", "k")

    def choose(t: pa.Table) -> pa.Table:
        doc, pos, lemma, r, g, half, most = (t.column(c).to_pylist() for c in ("doc_id", "pos", "lemma", "r", "g", "half_life", "k"))
        gamma = lambda h, r: boost.a * h ** -boost.b * boost.c ** -r + boost.d

        def worth(i: int, first: int | None) -> float:
            recall, h = r[i], half[i] or boost.initial
            if first is not None:
                h *= gamma(h, recall)
                recall = 1.0 if pos[i] > first else recall
            return round((recall + g[i] - recall * g[i]) * gamma(h, recall), 9)

        now = [worth(i, None) for i in range(len(pos))]
        heap = [(-w, p, i) for i, (w, p) in enumerate(zip(now, pos, strict=True))]
        heapq.heapify(heap)
        of_lemma: dict[str, list[int]] = {}
        for i, name in enumerate(lemma):
            of_lemma.setdefault(name, []).append(i)
        first: dict[str, int] = {}
        taken, out = set(), []
        while heap and len(out) < most[0]:
            value, _, i = heapq.heappop(heap)
            if i in taken or -value != now[i]:
                continue  # an entry from before its lemma was shown
            taken.add(i)
            out.append((doc[i], pos[i], lemma[i], now[i], len(out) + 1))
            if lemma[i] not in first or pos[i] < first[lemma[i]]:
                first[lemma[i]] = pos[i]
                for j in of_lemma[lemma[i]]:
                    if j not in taken and (value := worth(j, pos[i])) != now[j]:
                        now[j] = value
                        heapq.heappush(heap, (-value, pos[j], j))
        return pa.table({n: pa.array([o[i] for o in out], kind) for i, (n, kind) in enumerate((("doc_id", pa.int64()), ("pos", pa.int32()), ("lemma", pa.string()), ("priority", pa.float64()), ("rank", pa.int32())))})

    return joined.groupBy("doc_id").applyInArrow(choose, "doc_id long, pos int, lemma string, priority double, rank int")


def lookahead(words: DataFrame, horizon: int = 2000, block: int = 1 << 20) -> DataFrame:
    """(doc_id, pos, lemma, upcoming) of number_words(): later occurrences of the lemma within the horizon of the reading order.

    Blocks of positions, each with a copy of the next one's first horizon, keep common lemmas apart.
    """
    if block < horizon:
        raise ValueError("a block must hold the horizon")
    own = words.withColumn("_b", F.floor(F.col("pos") / block)).withColumn("_copy", F.lit(False))
    copies = own.filter((F.col("_b") > 0) & (F.col("pos") % block < horizon)).withColumn("_b", F.col("_b") - 1).withColumn("_copy", F.lit(True))
    ahead = Window.partitionBy("lemma", "_b").orderBy("pos").rangeBetween(1, horizon)
    return own.unionByName(copies).withColumn("upcoming", F.count(F.lit(1)).over(ahead)).filter("not _copy").select("doc_id", "pos", "lemma", "upcoming")


def collocations(runs: DataFrame, min_count: int = 20, score: str = "npmi") -> DataFrame:
    """(w1, w2, n, npmi or llr) of context.trigrams(): pairs of neighbours that occur so often at least."""
    pairs = runs.filter("b is not null").groupBy(F.col("b").alias("w1"), F.col("w").alias("w2")).agg(F.count(F.lit(1)).alias("n"))
    left, right = pairs.groupBy("w1").agg(F.sum("n").alias("n1")), pairs.groupBy("w2").agg(F.sum("n").alias("n2"))
    total = pairs.agg(F.sum("n").alias("t"))
    rows = pairs.filter(F.col("n") >= min_count).join(left, "w1").join(right, "w2").crossJoin(F.broadcast(total))
    n, n1, n2, t = (F.col(c).cast("double") for c in ("n", "n1", "n2", "t"))
    if score == "npmi":
        return rows.select("w1", "w2", "n", (F.ln(n * t / (n1 * n2)) / -F.ln(n / t)).alias("npmi"))
    part = lambda k, e: F.when(k > 0, k * F.ln(k / e)).otherwise(0.0)
    cells = [(n, n1 * n2 / t), (n1 - n, n1 * (t - n2) / t), (n2 - n, (t - n1) * n2 / t), (t - n1 - n2 + n, (t - n1) * (t - n2) / t)]
    return rows.select("w1", "w2", "n", (2 * sum((part(k, e) for k, e in cells), F.lit(0.0))).alias("llr"))


def collocations_3(runs: DataFrame, min_count: int = 5) -> DataFrame:
    """(w1, w2, w3, n, npmi) of context.trigrams(): runs of three words that occur so often at least, against three independent words."""
    triples = runs.filter("a is not null").groupBy(F.col("a").alias("w1"), F.col("b").alias("w2"), F.col("w").alias("w3")).agg(F.count(F.lit(1)).alias("n"))
    total = triples.agg(F.sum("n").alias("t"))
    rows = triples.filter(F.col("n") >= min_count)
    for i in (1, 2, 3):
        rows = rows.join(triples.groupBy(f"w{i}").agg(F.sum("n").alias(f"n{i}")), f"w{i}")
    n, n1, n2, n3, t = (F.col(c).cast("double") for c in ("n", "n1", "n2", "n3", "t"))
    return rows.crossJoin(F.broadcast(total)).select("w1", "w2", "w3", "n", (F.ln(n * t * t / (n1 * n2 * n3)) / (-2 * F.ln(n / t))).alias("npmi"))

"""Simulated browsing: walks over a click graph, concatenated to corpora of sessions.

Given its start, the walks of a session are independent and alike, so the walks of all sessions advance together,
one page a step, and prefix sums cut each session where its words exceed the limit. Walks are dealt in rounds: as many as
a session is expected to need, then more to the sessions that are still short, until none is; nothing ends a walk
but a stop or enough words. A draw depends on (seed, session, walk, step) only; recomputing a lost task repeats it.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from embedvocab.functions import rng
from embedvocab.operators.corpus import running_total
from embedvocab.sources.shared import stored

#: A walk of so many steps without a stop or enough words means pages that hold neither.
ENDLESS = 100_000


def page_state(pages: int) -> Column:
    """The page that an event of a reader stands for: readers keep to a cluster of a hundred pages, and the clusters cover all pages."""
    return (((F.col("user_id") % max(1, math.ceil(pages / 100))) * 100 + F.col("lemma_id") % min(100, pages)) % pages).cast("int")


def click_edges(events: DataFrame, pages: int, hours: float = 12.0) -> DataFrame:
    """(u, v, n): page after page of each reader; v is null where the next is later than the pause."""
    turn = Window.partitionBy("user_id").orderBy("ts", "event_id")
    steps = events.select("user_id", "ts", "event_id", page_state(pages).alias("u")).withColumn("_v", F.lead("u").over(turn)).withColumn("_ts", F.lead("ts").over(turn))
    near = F.unix_micros("_ts") - F.unix_micros("ts") <= int(hours * 3_600_000_000)
    return steps.select("u", F.when(near, F.col("_v")).alias("v")).groupBy("u", "v").agg(F.count(F.lit(1)).alias("n"))


def transitions(edges: DataFrame) -> DataFrame:
    """(u, v, lo, hi): shares of a page's visits as adjoining intervals of [0, 1), in order of v, the stop last."""
    own = Window.partitionBy("u")
    upto = own.orderBy(F.col("v").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    cum, total = F.sum("n").over(upto), F.sum("n").over(own)
    return edges.select("u", "v", ((cum - F.col("n")) / total).alias("lo"), (cum / total).alias("hi"))


def starts(edges: DataFrame) -> DataFrame:
    """(u, lo, hi): pages by their share of all visits."""
    visits = edges.groupBy("u").agg(F.sum("n").alias("n"))
    placed = running_total(visits.withColumn("_all", F.lit(0)), ["_all"], ["u"], "n", F.floor(F.col("u") / 4096), "_before")
    total = visits.agg(F.sum("n").alias("_total"))
    return placed.crossJoin(F.broadcast(total)).select("u", (F.col("_before") / F.col("_total")).alias("lo"), ((F.col("_before") + F.col("n")) / F.col("_total")).alias("hi"))


def draw_starts(sessions: DataFrame, start_pages: DataFrame, seed: int = 42, cells: int = 1024) -> DataFrame:
    """(corpus_id, s, u) of (corpus_id, s): the start page of each session; an equi join on cells of the unit interval."""
    drawn = sessions.withColumn("_x", rng.uniform(seed, F.lit("s"), F.col("corpus_id"), F.col("s"))).withColumn("_cell", F.floor(F.col("_x") * cells))
    spans = start_pages.select(F.col("u").alias("start"), "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") * cells), F.least(F.floor(F.col("hi") * cells), F.lit(cells - 1)))).alias("_cell"))
    return drawn.join(spans, "_cell").filter("lo <= _x and _x < hi").select(*sessions.columns, F.col("start").alias("u"))


def walks(begun: DataFrame, moves: DataFrame, seed: int = 42, cut_every: int = 8) -> DataFrame:
    """(corpus_id, s, w, step, u, n) of (corpus_id, s, w, u, n): each walk until it stops or has itself more words than its session needs.

    moves are transitions with the words n of the page v; corpus_id is the limit. Some steps are one plan, in which a walk
    carries its path; what still walks afterwards goes on from a table.
    """
    moves = moves.select(F.col("u").alias("_u"), F.col("v").alias("_v"), "lo", "hi", F.col("n").alias("_n"))
    page = lambda step, u, n: F.array(F.struct(step.cast("int").alias("step"), u.alias("u"), n.alias("n")))
    counted = F.when(F.col("w") == 0, F.col("n")).otherwise(F.lit(0)).cast("long")
    now = begun.select("corpus_id", "s", "w", "u", counted.alias("words"), F.lit(0).alias("step"), page(F.lit(0), F.col("u"), F.col("n")).alias("path")).withColumn("open", F.col("words") <= F.col("corpus_id"))
    finished: list[DataFrame] = []
    while True:
        for _ in range(cut_every):
            x = rng.uniform(seed, F.lit("w"), F.col("corpus_id"), F.col("s"), F.col("w"), F.col("step") + 1)
            joined = now.withColumn("_x", x).join(moves, F.col("open") & (F.col("u") == F.col("_u")) & (F.col("lo") <= F.col("_x")) & (F.col("_x") < F.col("hi")), "left")
            moved, words = F.col("_v").isNotNull(), F.col("words") + F.coalesce("_n", F.lit(0))
            now = joined.select("corpus_id", "s", "w", F.coalesce("_v", "u").alias("u"), words.alias("words"), (F.col("step") + 1).alias("step"),
                                F.when(moved, F.concat("path", page(F.col("step") + 1, F.col("_v"), F.col("_n")))).otherwise(F.col("path")).alias("path"), (moved & (words <= F.col("corpus_id"))).alias("open"))
        table = stored(now)
        finished.append(table.select("corpus_id", "s", "w", F.explode("path").alias("p")).select("corpus_id", "s", "w", "p.step", "p.u", "p.n"))
        now = table.filter("open").withColumn("path", F.slice("path", 1, 0))
        if now.isEmpty():
            return reduce(DataFrame.unionByName, finished)
        if len(finished) * cut_every > ENDLESS:
            raise ValueError("walks reach pages without words that are never left")


def browse(edges: DataFrame, page_words: DataFrame, limits: tuple[int, ...], total: int, seed: int = 42) -> DataFrame:
    """(corpus_id, s, w, step, u, n): for each limit a corpus of sessions, which end with the page that brings them over the limit, until the total of words is reached.

    A session whose start is always followed by a stop can read that page only and stays short: see short_sessions().
    """
    spark = edges.sparkSession
    edges, lengths = stored(edges), stored(page_words.select(F.col("u").alias("_p"), F.col("n").cast("long").alias("_l")))
    with_words = lambda df, u: df.join(lengths, F.col(u) == F.col("_p"), "left").withColumn("n", F.coalesce("_l", F.lit(0))).drop("_p", "_l")
    moves = stored(with_words(transitions(edges), "v"))
    begin = stored(with_words(starts(edges), "u"))
    sinks = moves.groupBy("u").agg(F.max("v").alias("_out")).filter("_out is null").select("u")
    # what a page and a walk bring on average tells how many to deal; it changes how often the loops turn, not what they give
    visits = edges.withColumnRenamed("n", "visits")
    m = with_words(visits, "v").agg(F.sum(F.when(F.col("v").isNull(), F.col("visits"))).alias("stops"), F.sum("visits").alias("all"), F.sum(F.col("visits") * F.col("n")).alias("words"), F.sum(F.col("visits") * F.col("n") * F.col("n")).alias("squares")).first()
    stops, moved = max(1, m["stops"] or 0), max(1, (m["all"] or 0) - (m["stops"] or 0))
    page = max(1.0, (m["words"] or 0) / moved)
    a_walk, beyond = max(1.0, page * moved / stops), (m["squares"] or 0) / max(1, m["words"] or 0) / 2
    read: DataFrame | None = None
    dealt, missing, mean_session = dict.fromkeys(limits, 0), dict.fromkeys(limits, total), {n: n + beyond for n in limits}
    while missing:
        more = {n: math.ceil(1.3 * words / mean_session[n]) + 5 for n, words in missing.items()}
        plan = spark.createDataFrame([(n, dealt[n], dealt[n] + k - 1) for n, k in more.items()], "corpus_id int, a int, b int")
        wanted = stored(draw_starts(plan.select("corpus_id", F.explode(F.sequence("a", "b")).alias("s")), begin, seed))
        dealt |= {n: dealt[n] + k for n, k in more.items()}
        expected = lambda words: F.ceil(1.5 * words / a_walk).cast("int") + 2
        batch = wanted.select("corpus_id", "s", "u", F.lit(0).alias("first"), expected(F.col("corpus_id")).alias("last"))
        rounds: list[DataFrame] = []
        while True:
            begun = batch.select("corpus_id", "s", "u", F.explode(F.sequence("first", "last")).alias("w"))
            rounds.append(walks(with_words(begun, "u"), moves, seed))
            got = reduce(DataFrame.unionByName, rounds)
            sums = got.groupBy("corpus_id", "s").agg(F.sum(F.when((F.col("step") > 0) | (F.col("w") == 0), F.col("n")).otherwise(0)).alias("_got"), F.max("w").alias("_w"))
            short = stored(wanted.join(sums, ["corpus_id", "s"]).filter(F.col("_got") <= F.col("corpus_id")).join(sinks, "u", "left_anti"))
            if short.isEmpty():
                break
            batch = short.select("corpus_id", "s", "u", (F.col("_w") + 1).alias("first"), (F.col("_w") + expected(F.col("corpus_id") - F.col("_got")) + 8).alias("last"))
        whole = stored(sessions(got))
        read = whole if read is None else read.unionByName(whole)
        have = {r.corpus_id: (r.words, r.sessions) for r in read.groupBy("corpus_id").agg(F.sum("n").alias("words"), F.countDistinct("s").alias("sessions")).collect()}
        mean_session |= {n: max(1.0, words / count) for n, (words, count) in have.items()}
        left = {n: total - have.get(n, (0, 0))[0] for n in limits}
        if not any(words for words, _ in have.values()):
            break  # no page has a word, so no total is ever reached
        missing = {n: words for n, words in left.items() if words > 0}
    return corpus(read, total)


def sessions(walked: DataFrame, limit: str = "corpus_id") -> DataFrame:
    """(corpus_id, s, w, step, u, n) of walks: pages of a session up to the first that brings its words over the limit, a column.

    The start counts for the first walk only.
    """
    counted = walked.filter("step > 0 or w = 0")
    upto = Window.partitionBy("corpus_id", "s").orderBy("w", "step").rowsBetween(Window.unboundedPreceding, -1)
    return counted.withColumn("_before", F.coalesce(F.sum("n").over(upto), F.lit(0))).filter(F.col("_before") <= F.col(limit)).drop("_before")


def corpus(pages_read: DataFrame, total: int) -> DataFrame:
    """The pages of the sessions, in order, whose predecessors have fewer than the total of words."""
    sizes = pages_read.groupBy("corpus_id", "s").agg(F.sum("n").alias("_n"))
    placed = running_total(sizes, ["corpus_id"], ["s"], "_n", F.floor(F.col("s") / 4096), "_ahead").filter(F.col("_ahead") < total)
    return pages_read.join(placed.select("corpus_id", "s"), ["corpus_id", "s"])


def short_sessions(pages_read: DataFrame, limit: str = "corpus_id") -> DataFrame:
    """(corpus_id, sessions, short): how many sessions there are, and how many ended before they passed the limit."""
    sizes = pages_read.groupBy("corpus_id", "s").agg(F.sum("n").alias("_n"))
    return sizes.groupBy("corpus_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum(F.when(F.col("_n") <= F.col(limit), 1).otherwise(0)).alias("short"))

"""The memory model over a reader's exposures: replay, state as of a time, due lists and simulated readers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from embedvocab.functions import rng
from embedvocab.functions.memory import Boost, boost, due_after, recall

DAY = 86_400_000_000.0
KEY = ["user_id", "lemma_id"]


def in_days(ts: Column) -> Column:
    return F.unix_micros(ts) / F.lit(DAY)


def _step(state: Column, e: Column, p: Boost, feedback: str, lapse: str, first: str) -> Column:
    """The state after an exposure: half-life, day of the last revision (null before the first), exposures."""
    fresh = state["last"].isNull()
    r = recall(e["d"] - state["last"], state["h"])
    grown = F.when(fresh, F.lit(p.initial) * boost(F.lit(p.initial), F.lit(0.0), p) if first == "boost" else F.lit(p.initial)).otherwise(state["h"] * boost(state["h"], r, p))
    missed_h = {"keep": state["h"], "reset": F.lit(p.initial), "shrink": state["h"] / 2}[lapse]
    missed_last = state["last"] if lapse == "keep" else e["d"]
    ok = e["success"] if feedback == "explicit" else F.lit(True)
    return F.struct(F.when(ok, grown).otherwise(missed_h).alias("h"), F.when(ok, e["d"]).otherwise(missed_last).alias("last"), (state["n"] + 1).alias("n"))


def _histories(exposures: DataFrame) -> DataFrame:
    """Each pair's exposures in order; bounded by how often one reader meets one lemma in the replayed span."""
    event = F.struct(in_days(F.col("ts")).alias("d"), F.col("event_id"), F.coalesce("success", F.lit(True)).alias("success"), F.col("ts"))
    return exposures.filter("ts is not null").groupBy(*KEY).agg(F.array_sort(F.collect_list(event)).alias("es"))


def _start(p: Boost) -> Column:
    return F.struct(F.lit(p.initial).alias("h"), F.lit(None).cast("double").alias("last"), F.lit(0).alias("n"))


def replay(exposures: DataFrame, p: Boost = Boost(), feedback: str = "implicit", lapse: str = "keep", first: str = "init") -> DataFrame:
    """(user_id, lemma_id, exposures, half_life, last_day): the state after all exposures, in order of time and event.

    By default each exposure is a successful revision. With explicit feedback a lapse keeps, resets or halves the
    half-life. The fold is not associative, so a pair's exposures are folded together; yesterday's state can start it.
    """
    folded = _histories(exposures).withColumn("s", F.aggregate("es", _start(p), lambda s, e: _step(s, e, p, feedback, lapse, first)))
    return folded.select(*KEY, F.col("s.n").alias("exposures"), F.col("s.h").alias("half_life"), F.col("s.last").alias("last_day"))


def history(exposures: DataFrame, p: Boost = Boost()) -> DataFrame:
    """(user_id, lemma_id, ts, event_id, half_life, last_day): the state after each exposure."""
    kept = F.struct(_start(p).alias("s"), F.array().cast("array<struct<h:double,last:double,n:int>>").alias("all"))

    def grow(acc: Column, e: Column) -> Column:
        s = _step(acc["s"], e, p, "implicit", "keep", "init")
        return F.struct(s.alias("s"), F.concat(acc["all"], F.array(s)).alias("all"))

    rows = _histories(exposures).withColumn("st", F.aggregate("es", kept, grow, lambda a: a["all"]))
    return rows.select(*KEY, F.explode(F.arrays_zip("es", "st")).alias("x")).select(*KEY, "x.es.ts", "x.es.event_id", F.col("x.st.h").alias("half_life"), F.col("x.st.last").alias("last_day"))


def state_asof(states: DataFrame, reads: DataFrame) -> DataFrame:
    """(event_id, user_id, lemma_id, t_days, r, half_life) of each read: the last state before it; recall is 0 for lemmas never seen.

    Spark has no as-of join: both sides are ordered together and each read takes the last state above it.
    """
    a = states.select(*KEY, "ts", F.lit(1).alias("_side"), F.col("event_id"), "half_life", "last_day")
    b = reads.select(*KEY, "ts", F.lit(0).alias("_side"), F.col("event_id"), F.lit(None).cast("double").alias("half_life"), F.lit(None).cast("double").alias("last_day"))
    upto = Window.partitionBy(*KEY).orderBy("ts", "_side").rowsBetween(Window.unboundedPreceding, 0)
    seen = a.unionByName(b).withColumn("_h", F.last("half_life", ignorenulls=True).over(upto)).withColumn("_l", F.last("last_day", ignorenulls=True).over(upto)).filter("_side = 0")
    t = in_days(F.col("ts")) - F.col("_l")
    return seen.select("event_id", *KEY, t.alias("t_days"), F.coalesce(recall(t, F.col("_h")), F.lit(0.0)).alias("r"), F.col("_h").alias("half_life"))


def quiz_items(asked: DataFrame, options: int = 5, seed: int = 42) -> DataFrame:
    """(event_id, user_id, lemma_id, ts, slot): a small quiz on each word asked; the slot that holds its meaning is drawn."""
    slot = 1 + F.floor(rng.uniform(seed, F.lit("quiz"), F.col("event_id")) * options)
    return asked.select("event_id", *KEY, "ts", slot.cast("int").alias("slot"))


def quiz_feedback(items: DataFrame, picked: Column) -> DataFrame:
    """(event_id, user_id, lemma_id, ts, success): answered quizzes as explicit feedback for replay()."""
    return items.select("event_id", *KEY, "ts", (picked == F.col("slot")).alias("success"))


def recall_now(states: DataFrame, now: Column, p: Boost = Boost(), target: float = 0.9) -> DataFrame:
    """(user_id, lemma_id, r, gamma, due_day) of replay() at a day."""
    r = recall(now - F.col("last_day"), F.col("half_life"))
    return states.select(*KEY, r.alias("r"), boost(F.col("half_life"), r, p).alias("gamma"), (F.col("last_day") + due_after(F.col("half_life"), target)).alias("due_day"))


def due(states: DataFrame, now: Column, target: float = 0.9) -> DataFrame:
    """(user_id, lemma_id, overdue_days) of lemmas whose recall has fallen below the target."""
    late = now - (F.col("last_day") + due_after(F.col("half_life"), target))
    return states.select(*KEY, late.alias("overdue_days")).filter("overdue_days > 0")


def free_schedule(lemmas: DataFrame, revisions: int = 8, p: Boost = Boost(), target: float = 0.9) -> DataFrame:
    """(lemma_id, revision, day, half_life): flashcards revised exactly when due, the schedule that text cannot constrain."""
    start = F.struct(F.lit(0.0).alias("day"), F.lit(p.initial).alias("h"))
    first = F.struct(start.alias("s"), F.array(start).alias("all"))

    def step(acc: Column, _: Column) -> Column:
        s = F.struct((acc["s"]["day"] + due_after(acc["s"]["h"], target)).alias("day"), (acc["s"]["h"] * boost(acc["s"]["h"], F.lit(target), p)).alias("h"))
        return F.struct(s.alias("s"), F.concat(acc["all"], F.array(s)).alias("all"))

    plan = F.aggregate(F.sequence(F.lit(1), F.lit(revisions)), first, step, lambda a: a["all"])
    return lemmas.select("lemma_id", F.posexplode(plan).alias("revision", "x")).select("lemma_id", "revision", F.col("x.day").alias("day"), F.col("x.h").alias("half_life"))


def slack(exposures: DataFrame, p: Boost = Boost(), target: float = 0.9) -> DataFrame:
    """(user_id, lemma_id, delays, mean_delay): how long past its due time a lemma came back in what was really read."""
    own = Window.partitionBy(*KEY).orderBy("ts", "event_id")
    states = history(exposures, p).withColumn("_next", F.lead("ts").over(own)).filter("_next is not null")
    late = in_days(F.col("_next")) - (F.col("last_day") + due_after(F.col("half_life"), target))
    return states.groupBy(*KEY).agg(F.count(F.lit(1)).alias("delays"), F.avg(late).alias("mean_delay"))

"""Mixing sources to target weights with Efraimidis-Spirakis keys.

Targets come from source weights by water-filling: no source gives more than ``most_epochs`` times its size, and
the excess is reshared by weight. A source gives every document once for each complete epoch in its target; the
rest of the budget goes to the documents with the smallest exponential keys ``-ln(u) / weight``, whose order is a
weighted sample without replacement. The document at the edge of the budget is cut there, so that a source's
words equal its rounded target.

A document's weight is its quality: digest() takes it from the quality label, where there is one, and mix() from any
column, such as a classifier's score. Without either all documents weigh the same.

Nothing is sorted globally: keys fall into log-scaled buckets, and those into 4096 steps, whose sums tell the one step of each
source that the budget ends in; only its rows are ordered. A source of any size therefore never meets in one task. The
driver collects nothing.

Null texts have size zero. A null source is a source of its own, the last. Rows with null ids draw by their text and have no label.
Repeated rows are mixed like others; ties are broken by id, then size. A very long text is counted whole and may be the one that is
cut. Extra columns stay where they are, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from embedvocab.llm.common import WORD_PATTERN, columns, written

#: Buckets for each doubling of the key, and steps of a bucket.
PER_OCTAVE, STEPS = 256, 4096
#: Weights of documents labelled good, labelled bad, and not labelled.
GOOD, BAD, UNKNOWN = 1.0, 0.2, 0.6


def drawn(docs: DataFrame, seed: int, weight: Column | None, keep: bool) -> DataFrame:
    """doc_id, source, _size, _weight and _draw, and the whole row in _row if it is kept; the draw depends on seed, id and source only."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), F.col("text").cast("string").alias("text"),
                       (F.lit(1.0) if weight is None else weight).cast("double").alias("_weight"), *([F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row")] if keep else []))
    who = F.coalesce(F.col("doc_id").cast("string"), F.md5(F.col("text")), F.lit(""))
    hexes = F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), who, F.col("source"))), 1, 12)
    u = (F.conv(hexes, 16, 10).cast("double") + 0.5) / float(1 << 48)
    return rows.withColumn("_size", F.coalesce(F.regexp_count("text", F.lit(WORD_PATTERN)), F.lit(0)).cast("long")).withColumn("_draw", -F.ln(u)).drop("text")


def keyed(rows: DataFrame) -> DataFrame:
    """Drawn rows with _key, _bucket and the bucket's _step instead of draw and weight."""
    place = F.log2("_key") * PER_OCTAVE
    return (rows.withColumn("_key", F.col("_draw") / F.col("_weight")).withColumn("_bucket", F.floor(place).cast("int"))
            .withColumn("_step", F.floor((place - F.floor(place)) * STEPS).cast("int")).drop("_draw", "_weight"))


def targets(sizes: DataFrame, most_epochs: int = 3, weights: int = 3, total: float = 1.0) -> DataFrame:
    """(source, source_size, target) from (source, source_size): weights 1..weights repeat in code-point order, null last.

    One row a source, so that windows over all of them stay small.
    """
    by_name = Window.orderBy(F.col("source").isNull(), F.col("source"))
    filled = Window.orderBy("_full", F.col("source").isNull(), "source")
    before, behind = filled.rowsBetween(Window.unboundedPreceding, -1), filled.rowsBetween(0, Window.unboundedFollowing)
    whole = Window.partitionBy(F.lit(1))
    return (
        sizes.withColumn("_weight", (F.row_number().over(by_name) - 1) % weights + 1)
        .withColumn("_cap", F.col("source_size") * F.lit(most_epochs))
        .withColumn("_full", F.col("_cap") / F.col("_weight"))  # the level at which a source is full
        .withColumn("_level", (F.sum("source_size").over(whole) * total - F.coalesce(F.sum("_cap").over(before), F.lit(0))) / F.sum("_weight").over(behind))
        .withColumn("_level", F.min(F.when(F.col("_level") <= F.col("_full"), F.struct("_full", "_level"))).over(whole)["_level"])
        .select("source", "source_size", F.coalesce(F.least(F.col("_cap").cast("double"), F.col("_level") * F.col("_weight")), F.col("_cap").cast("double")).alias("target"))
    )


def _edge(sums: DataFrame, goal: DataFrame, place: str) -> DataFrame:
    """goal (source, _rest, ...) with the place, among sums (source, place, n), in which the rest ends, and what is _left of it there."""
    before = F.coalesce(F.sum("n").over(Window.partitionBy("source").orderBy(place).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    found = (sums.withColumn("_before", before).withColumnRenamed("source", "_s").join(goal.select("source", "_rest"), F.col("_s").eqNullSafe(F.col("source")))
             .filter("_before <= _rest and _rest < _before + n").select("_s", F.col(place).alias(f"_edge{place}"), (F.col("_rest") - F.col("_before")).alias("_left")))
    return goal.join(found, F.col("source").eqNullSafe(F.col("_s")), "left").drop("_s")


def budgets(rows: DataFrame, most_epochs: int = 3, weights: int = 3, total: float = 1.0) -> DataFrame:
    """A row a source: its target, its complete epochs, the bucket and the step that the rest of its budget ends in, what is left there. rows are keyed, and read twice."""
    sums = written(rows.groupBy("source", "_bucket").agg(F.sum("_size").alias("n")))
    goal = targets(sums.groupBy("source").agg(F.sum("n").alias("source_size")), most_epochs, weights, total)
    goal = (goal.withColumn("_words", F.round("target").cast("long"))
            .withColumn("_epochs", F.when(F.col("source_size") > 0, F.expr("_words div source_size")).otherwise(0))
            .withColumn("_rest", F.col("_words") - F.col("_epochs") * F.col("source_size")))
    coarse = written(_edge(sums, goal, "_bucket"))
    inside = rows.join(F.broadcast(coarse.select(F.col("source").alias("_s"), "_edge_bucket")), F.col("source").eqNullSafe(F.col("_s")) & (F.col("_bucket") == F.col("_edge_bucket")))
    steps = inside.groupBy("source", "_step").agg(F.sum("_size").alias("n"))
    fine = _edge(steps, coarse.select("source", F.col("_left").alias("_rest")), "_step").select(F.col("source").alias("_source"), "_edge_step", "_left")
    return written(coarse.drop("_left").join(fine, F.col("source").eqNullSafe(F.col("_source"))).select("_source", "source_size", "target", "_epochs", "_edge_bucket", "_edge_step", "_left"))


def mix(docs: DataFrame, seed: int = 17, weight: Column | None = None, most_epochs: int = 3, weights: int = 3, total: float = 1.0) -> DataFrame:
    """Each row in _row with _size, source_size, target, _epochs and _extra: what it gives besides its complete epochs, in words."""
    small = written(keyed(drawn(docs, seed, weight, keep=False)))
    return _taken(keyed(drawn(docs, seed, weight, keep=True)), budgets(small, most_epochs, weights, total))


def _taken(rows: DataFrame, per_source: DataFrame) -> DataFrame:
    # one row a source, of which there are few
    joined = rows.join(per_source, F.col("source").eqNullSafe(F.col("_source"))).drop("_source")
    edge = F.coalesce((F.col("_bucket") == F.col("_edge_bucket")) & (F.col("_step") == F.col("_edge_step")), F.lit(False))
    below = (F.col("_bucket") < F.col("_edge_bucket")) | ((F.col("_bucket") == F.col("_edge_bucket")) & (F.col("_step") < F.col("_edge_step")))
    order = Window.partitionBy("source").orderBy("_key", F.col("doc_id").asc_nulls_last(), "_size").rowsBetween(Window.unboundedPreceding, -1)
    inner = joined.filter(edge).withColumn("_extra", F.greatest(F.lit(0), F.least(F.col("_size"), F.col("_left") - F.coalesce(F.sum("_size").over(order), F.lit(0)))))
    outer = joined.filter(~edge).withColumn("_extra", F.when(below, F.col("_size")).otherwise(F.lit(0)))
    return outer.unionByName(inner)


def digest(docs: DataFrame, labels: DataFrame | None = None, weight: Column | None = None, seed: int = 17) -> DataFrame:
    """(doc_id, size, source_size, target, taken); weights are those of labels (doc_id, quality), or the column."""
    rows = drawn(docs, seed, weight, keep=False)
    if labels is not None:
        rows = written(rows)
        marks = columns(labels, doc_id="long", quality="int").filter("doc_id is not null and quality is not null").groupBy(F.col("doc_id").alias("_of")).agg(F.max("quality").alias("_quality"))
        by_label = F.when(F.col("_quality") == 1, GOOD).when(F.col("_quality") == 0, BAD).otherwise(UNKNOWN)
        known = rows.filter("doc_id is not null").join(marks, F.col("doc_id") == F.col("_of"), "left").withColumn("_weight", by_label).drop("_of", "_quality")
        rows = known.unionByName(rows.filter("doc_id is null").withColumn("_weight", F.lit(UNKNOWN)))
    rows = written(keyed(rows))
    return _taken(rows, budgets(rows)).select("doc_id", F.col("_size").alias("size"), "source_size", "target", (F.col("_epochs") * F.col("_size") + F.col("_extra")).cast("long").alias("taken"))


def materialise(mixed: DataFrame, columns: list[str]) -> DataFrame:
    """The mix itself: a row for each complete epoch, then one for the rest, cut where the budget ends."""
    text = F.col("_row")["text"]
    cut = F.array_join(F.slice(F.regexp_extract_all(text, F.lit(WORD_PATTERN), F.lit(0)), F.lit(1), F.col("_extra").cast("int")), " ")
    given = lambda c: (c <= F.col("_epochs")) | (F.col("_extra") > 0)
    copies = mixed.withColumn("_copy", F.explode(F.filter(F.sequence(F.lit(1), F.col("_epochs").cast("int") + 1), given)))
    part = (F.col("_copy") > F.col("_epochs")) & (F.col("_extra") < F.col("_size"))
    new = {"text": F.when(part, cut).otherwise(text)}
    if "n_chars" in columns:
        new["n_chars"] = F.when(part, F.length(cut).cast("long")).otherwise(F.col("_row")["n_chars"])
    return copies.select(*(new.get(c, F.col("_row")[c]).alias(c) for c in columns))


ORACLE = r"""
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
    -ln((('0x' || substr(md5(concat_ws('|', '17', coalesce(doc_id::VARCHAR, md5(text), ''), source)), 1, 12))::BIGINT::DOUBLE + 0.5) / 281474976710656.0)
      / CASE q.quality WHEN 1 THEN 1.0::DOUBLE WHEN 0 THEN 0.2::DOUBLE ELSE 0.6::DOUBLE END AS key
  FROM documents LEFT JOIN (SELECT doc_id, max(quality) AS quality FROM labels WHERE quality IS NOT NULL GROUP BY doc_id) q USING (doc_id)),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, (row_number() OVER (ORDER BY source IS NULL, encode(source)) - 1) % 3 + 1 AS weight FROM s),
v AS (SELECT a.source, a.source_size, a.weight, 3 * a.source_size AS cap,
    (SELECT sum(source_size) FROM s)::DOUBLE AS total FROM w a),
lv AS (SELECT v.*, (total - coalesce((SELECT sum(b.cap) FROM v b WHERE b.cap::DOUBLE / b.weight < v.cap::DOUBLE / v.weight), 0)::DOUBLE)
    / (SELECT sum(b.weight) FROM v b WHERE b.cap::DOUBLE / b.weight >= v.cap::DOUBLE / v.weight)::DOUBLE AS level FROM v),
l AS (SELECT arg_min(level, cap::DOUBLE / weight) AS level FROM lv WHERE level <= cap::DOUBLE / weight),
t AS (SELECT source, source_size, coalesce(least(cap::DOUBLE, (SELECT level FROM l) * weight), cap::DOUBLE) AS target FROM v),
g AS (SELECT *, CASE WHEN source_size > 0 THEN round(target)::BIGINT // source_size ELSE 0 END AS epochs FROM t),
p AS (SELECT d.*, g.source_size, g.target, g.epochs, round(g.target)::BIGINT - g.epochs * g.source_size AS rest,
    coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY key, doc_id NULLS LAST, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM d JOIN g ON d.source IS NOT DISTINCT FROM g.source)
SELECT doc_id, size, source_size, target, (epochs * size + greatest(0, least(size, rest - before)))::BIGINT AS taken FROM p
"""

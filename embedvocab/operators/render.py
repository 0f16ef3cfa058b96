"""Putting translations back into texts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from embedvocab.functions import text as txt


def _escaped(c: Column) -> Column:
    return F.replace(F.replace(F.replace(c, F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;")), F.lit(">"), F.lit("&gt;"))


def rewrite(docs: DataFrame, chosen: DataFrame, style: str = "plain", reveal: bool = True, counted: bool = False) -> DataFrame:
    """(doc_id, text) of docs (doc_id, text) with the words at (doc_id, pos) swapped for their ``target``; counted, with n_words and n_replaced.

    Everything between words stays. Marked text is escaped for HTML, and with reveal it keeps the original word for a click. A
    document without a choice keeps its text.
    """
    # one map a document, of at most k entries
    maps = chosen.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct(F.col("pos").cast("int"), "target"))).alias("_m"))
    rows = docs.select("doc_id", "text").join(maps, "doc_id", "left")
    parts = txt.segments(F.col("text"))
    # words and what is between them alternate, so a segment's index tells its word's number
    lead = F.when(F.element_at(parts, 1).rlike(r"^\p{L}"), 0).otherwise(1)

    def place(s: Column, i: Column) -> Column:
        to = F.when((i - F.col("_lead")) % 2 == 0, F.try_element_at(F.col("_m"), ((i - F.col("_lead")) / 2).cast("int")))
        if style == "plain":
            shown, kept = to, s
        else:
            mark = F.concat(F.lit('<mark data-original="'), _escaped(s), F.lit('">'), _escaped(to), F.lit("</mark>")) if reveal else F.concat(F.lit("<mark>"), _escaped(to), F.lit("</mark>"))
            shown, kept = mark, _escaped(s)
        return F.when(to.isNotNull(), shown).otherwise(kept)

    rows = rows.withColumn("_lead", F.when(F.size(parts) > 0, lead).otherwise(0))
    new = F.array_join(F.transform(parts, place), "")
    counts = F.coalesce(F.size(txt.tokenize(F.col("text"))), F.lit(0)).alias("n_words"), F.when(F.col("_m").isNull(), 0).otherwise(F.size("_m")).cast("long").alias("n_replaced")
    plain = F.col("text") if style == "plain" else _escaped(F.col("text"))
    return rows.select("doc_id", F.when(F.col("_m").isNull(), plain).otherwise(new).alias("text"), *(counts if counted else ()))

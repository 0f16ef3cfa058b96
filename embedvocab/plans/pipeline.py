"""The four stages end to end: remember, guess, select, translate; then the text is put together again."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from embedvocab.operators import render, select, translate


def rendered(docs: DataFrame, found: DataFrame, style: str = "plain") -> DataFrame:
    """(doc_id, n_words, n_replaced, text): docs with the translations found (doc_id, pos, target) in place."""
    return render.rewrite(docs, found, style, counted=True).select("doc_id", "n_words", "n_replaced", "text")


def augment(docs: DataFrame, candidates: DataFrame, k: DataFrame, backend: translate.LexiconBackend | translate.ServiceBackend, ablate: str | None = None, per_lemma: int | str | None = None, style: str = "plain", spare: int = 0, promote: bool = False) -> DataFrame:
    """(doc_id, n_words, n_replaced, text) of docs (doc_id, text).

    With ``promote`` only lemmas that the backend knows compete, so the next best takes the place of one without a translation.
    A service cannot be asked for its words; with ``spare``, so many more are translated, and the best k of those that have a
    translation are shown.
    """
    rows = select.scored(candidates.join(backend.known(), "lemma", "left_semi") if promote else candidates, ablate=ablate)
    chosen = select.top_k(rows, k.withColumn("k", F.col("k") + spare) if spare else k, per_lemma)
    found = translate.in_context(chosen, docs, backend)
    if spare:
        found = select.top_k(found.join(chosen.select("doc_id", F.col("pos").cast("int").alias("pos"), "priority"), ["doc_id", "pos"]), k)
    return rendered(docs, found, style)


def exposures(chosen: DataFrame, user: DataFrame, at) -> DataFrame:  # noqa: ANN001
    """(user_id, lemma, ts, success): shown words count as successful revisions; they feed the next replay."""
    return chosen.join(user.select("doc_id", "user_id"), "doc_id").select("user_id", "lemma", at.alias("ts"), F.lit(True).alias("success"))

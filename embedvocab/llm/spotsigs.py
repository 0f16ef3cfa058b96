"""SpotSigs document fingerprints, in DataFrame operations only.

A signature is an anchor, a very common word, and the chain of the two content words that follow it, other common words
left out; of several common words in a row the last one is the anchor. A fingerprint is the set of a text's
signatures, 32 bits each. Likeness is the Jaccard coefficient of two sets. Near duplicates are found
within bands of set length, since sets of likeness t differ in length by a factor of t at most, among sets that share one of their
rarest signatures, and verified.

A text without anchored chains is fingerprinted by all its word pairs, one with fewer than two words by itself.
Null texts are empty. For the next document in order of ids, documents are dealt into ranges of ids, each with a copy of
the next range's first, so that no task sees them all. Rows with null ids have no next document. Repeated ids are
ordered by their text. A very long text takes memory of a small multiple of its length. Signatures that are equally rare are
ordered by their value. Extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from embedvocab.llm.common import columns, shuffle_partitions, written

#: Common words of the four languages of the corpus.
ANCHORS = (
    "the of and a to in is was that it for on with as at by be this from are an or not "
    "der die das und den von zu mit ist im ein eine des auf für sich "
    "le la les de du et en un une est que dans pour par sur au "
    "el los las del y con por para se su al lo como es"
).split()
_MARK = "\x01"
#: A common word at the start of what follows a space or another common word; its space becomes the mark.
_COMMON = f"(?<= )({'|'.join(sorted(set(ANCHORS)))}) "
#: At a marked word: itself, the word after it and the next word; only the marked word is consumed, so that chains may overlap.
_CHAIN = f"(?<=[ {_MARK}])(?=([^ {_MARK}]+{_MARK}[^ {_MARK}]+ (?:[^ ]*{_MARK})?[^ {_MARK}]+) )[^ {_MARK}]+"
_PAIR = "(?<= )(?=([^ ]+ [^ ]+) )[^ ]+"


def signatures(text: Column) -> Column:
    """The sorted array of distinct signatures, ints; never empty."""
    plain = F.concat(F.lit(" "), F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+", " "), F.lit(" "))
    low = lambda h: F.shiftright(h, 32).cast("int")
    chain = lambda x: low(F.xxhash64(F.substring_index(x, " ", 1), F.substring_index(F.substring_index(x, _MARK, -1), " ", -1)))
    chains = F.regexp_extract_all(F.regexp_replace(plain, _COMMON, f"$1{_MARK}"), F.lit(_CHAIN), F.lit(1))
    pairs = F.regexp_extract_all(plain, F.lit(_PAIR), F.lit(1))
    found = F.when(F.size(chains) > 0, F.transform(chains, chain)).otherwise(
        F.when(F.size(pairs) > 0, F.transform(pairs, lambda x: low(F.xxhash64(x)))).otherwise(F.array(low(F.xxhash64(F.trim(plain))))))
    return F.array_sort(F.array_distinct(found))


def fingerprint(sigs: Column) -> Column:
    """The set as hexadecimal digits, eight a signature."""
    return F.lower(F.array_join(F.transform(sigs, lambda s: F.lpad(F.hex(s.cast("long").bitwiseAND(0xFFFFFFFF)), 8, "0")), ""))


def likeness(a: Column, b: Column) -> Column:
    """Jaccard coefficient of two sets without repeats."""
    shared = F.size(F.array_intersect(a, b)).cast("double")
    return F.coalesce(shared / (F.size(a) + F.size(b) - shared), F.lit(0.0))


def _range_of(doc_id: Column, bounds: list[int]) -> Column:
    """How many of the sorted bounds are at or below the id, found in two steps."""
    if not bounds:
        return F.lit(0)
    width = math.isqrt(len(bounds)) + 1
    coarse = F.array(*map(F.lit, bounds[::width]))
    at = F.greatest(F.size(F.filter(coarse, lambda b: b <= doc_id)) - 1, F.lit(0)) * width
    fine = F.slice(F.array(*map(F.lit, bounds)), at + 1, F.lit(width))
    return at + F.size(F.filter(fine, lambda b: b <= doc_id))


def with_next(docs: DataFrame) -> DataFrame:
    """(doc_id, text, next_text, next_sigs, sigs): each document beside the next by id, the last beside the first."""
    rows = columns(docs, doc_id="long", text="string").withColumn("text", F.coalesce("text", F.lit("")))
    n = 2 * shuffle_partitions(docs.sparkSession)
    cuts = rows.agg(F.min("doc_id").alias("first"), F.percentile_approx("doc_id", [i / n for i in range(1, n)], 10 * n).alias("cuts")).first()
    bounds = [] if cuts["first"] is None else sorted({cuts["first"], *cuts["cuts"]})
    own = rows.filter("doc_id is not null").withColumn("_range", _range_of(F.col("doc_id"), bounds)).withColumn("_copy", F.lit(0))
    if bounds:
        # a bound is the least id of its range: its row also goes last in the range before
        firsts = rows.filter(F.col("doc_id").isin(bounds)).withColumn("_range", _range_of(F.col("doc_id"), bounds) - 1).withColumn("_copy", F.lit(1))
        own = own.unionByName(firsts.withColumn("_range", F.when(F.col("_range") == 0, len(bounds)).otherwise(F.col("_range"))))
    order = Window.partitionBy("_range").orderBy("_copy", "doc_id", "text")
    beside = own.withColumn("next_text", F.lead("text").over(order)).withColumn("sigs", signatures(F.col("text"))).withColumn("next_sigs", F.lead("sigs").over(order))
    lone = rows.filter("doc_id is null").withColumn("sigs", signatures(F.col("text"))).withColumn("next_text", F.lit("")).withColumn("next_sigs", F.lit(None).cast("array<int>"))
    names = ("doc_id", "text", "next_text", "sigs", "next_sigs")
    return beside.filter("_copy = 0").select(*names).unionByName(lone.select(*names))


def digest(docs: DataFrame) -> DataFrame:
    """Fingerprints of each text and of its edited text, and how near they and the next document's are."""
    half = F.floor(F.length("text") / 2).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), F.length("text") - half), F.substring("next_text", F.lit(1), half))
    rows = with_next(docs).withColumn("edited", edited).withColumn("edited_sigs", signatures(F.col("edited")))
    return rows.select(
        "doc_id", F.length("text").cast("long").alias("n_chars"), F.sha2("edited", 256).alias("edited_sha256"),
        fingerprint(F.col("sigs")).alias("fingerprint"), fingerprint(F.col("edited_sigs")).alias("edited_fingerprint"),
        likeness(F.col("sigs"), F.col("edited_sigs")).alias("near_edited"), likeness(F.col("sigs"), F.col("next_sigs")).alias("near_next"))


def near_pairs(docs: DataFrame, threshold: float = 0.8) -> tuple[DataFrame, DataFrame]:
    """((doc_id, set_id) of every row, (a, b, likeness) between distinct sets at or above the threshold).

    Equal sets are one class from the start, so copies never meet in pairs.
    """
    sets = columns(docs, doc_id="long", text="string").select("doc_id", signatures(F.col("text")).alias("sigs")).withColumn("set_id", F.xxhash64("sigs"))
    members = written(sets)
    distinct = written(members.groupBy("set_id").agg(F.first("sigs").alias("sigs")))
    # lengths in one band differ by less than the factor, so a partner is in the same band or a neighbour
    band = F.floor(F.log(F.size("sigs").cast("double")) / math.log(1 / threshold)).cast("int")
    sized = distinct.withColumn("n", F.size("sigs")).withColumn("band", band)
    exploded = sized.select("set_id", "n", "band", F.explode("sigs").alias("sig"))
    counted = exploded.groupBy("sig").agg(F.count(F.lit(1)).alias("often"))
    rarest = Window.partitionBy("set_id").orderBy("often", "sig")
    prefix = (exploded.join(counted.filter("often > 1"), "sig", "left").withColumn("often", F.coalesce("often", F.lit(1)))
              .withColumn("rank", F.row_number().over(rarest)).filter(F.col("rank") <= F.col("n") - F.ceil(F.col("n") * threshold) + 1).filter("often > 1"))
    prefix = written(prefix.select("set_id", "n", "band", "sig"))
    left = prefix.select(F.col("set_id").alias("a"), F.col("n").alias("n_a"), "band", "sig")
    right = prefix.withColumn("band", F.explode(F.array("band", F.col("band") - 1))).select(F.col("set_id").alias("b"), F.col("n").alias("n_b"), "band", "sig")
    pairs = (left.join(right, ["sig", "band"]).filter((F.col("n_a") < F.col("n_b")) | ((F.col("n_a") == F.col("n_b")) & (F.col("a") < F.col("b"))))
             .filter(F.col("n_b") * threshold <= F.col("n_a")).select("a", "b").distinct())
    both = (pairs.join(distinct.select(F.col("set_id").alias("a"), F.col("sigs").alias("x")), "a").join(distinct.select(F.col("set_id").alias("b"), F.col("sigs").alias("y")), "b"))
    return members.select("doc_id", "set_id"), both.select("a", "b", likeness(F.col("x"), F.col("y")).alias("likeness")).filter(F.col("likeness") >= threshold)


def neighbours(docs: DataFrame, threshold: float = 0.8) -> DataFrame:
    """(doc_id, class_id, links) of every row: the least id of the rows with its set, and how many other sets are alike.

    Rows without an id are counted too; a class of such rows only has no id.
    """
    members, pairs = near_pairs(docs, threshold)
    pairs = written(pairs)
    degree = pairs.select(F.col("a").alias("_s")).union(pairs.select("b")).groupBy("_s").agg(F.count(F.lit(1)).alias("links"))
    classes = members.groupBy("set_id").agg(F.min("doc_id").alias("class_id"))
    return (members.join(classes, "set_id").join(degree, F.col("set_id") == F.col("_s"), "left")
            .select("doc_id", "class_id", F.coalesce("links", F.lit(0)).cast("long").alias("links")))

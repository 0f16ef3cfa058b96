"""Tokens, segments, sentences, lemmas and reading text of web pages."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Common English words that are no vocabulary to learn.
STOPWORDS = ("a an and are as at be but by for from had has have he her his i in is it its no not of on or she so that the their them they this to was we were what when which who will with you").split()
#: Spellings that cognates differ by, longest first.
FOLDS = (("ph", "f"), ("th", "t"), ("ck", "k"), ("qu", "k"), ("c", "k"), ("y", "i"), ("w", "v"), ("z", "s"))
_ACCENTS = ("àáâäãèéêëìíîïòóôöõùúûüçñß", "aaaaaeeeeiiiiooooouuuucns")


def tokenize(text: Column) -> Column:
    """Lower-cased letter runs; punctuation and numbers are dropped, so positions count words only."""
    return F.regexp_extract_all(F.lower(text), F.lit(r"\p{L}+"), F.lit(0))


def segments(text: Column) -> Column:
    """Letter runs and what is between them; their concatenation is the text."""
    return F.regexp_extract_all(text, F.lit(r"\p{L}+|[^\p{L}]+"), F.lit(0))


def sentences(text: Column) -> Column:
    """Runs up to and including marks that end a sentence."""
    return F.regexp_extract_all(text, F.lit(r"[^.!?]+[.!?]*"), F.lit(0))


def lemmatize(word: Column, method: str = "identity") -> Column:
    """``s_stem`` drops the plural endings of English: -ies to -y, -es to -e, -s, with their usual exceptions."""
    if method == "identity":
        return word
    if method != "s_stem":
        raise ValueError(f"no lemmatizer {method}; a dictionary is joined with lemmatize_by()")
    return (F.when(word.endswith("ies") & ~word.rlike("[ea]ies$"), F.regexp_replace(word, "ies$", "y"))
            .when(word.endswith("es") & ~word.rlike("[aeo]es$"), F.regexp_replace(word, "es$", "e"))
            .when(word.endswith("s") & ~word.rlike("[us]s$"), F.regexp_replace(word, "s$", "")).otherwise(word))


def lemmatize_by(words: DataFrame, dictionary: DataFrame) -> DataFrame:
    """words with lemmas from (word, lemma); words that are not listed are their own lemma."""
    return words.join(dictionary.select(F.col("word").alias("_w"), F.col("lemma").alias("_l")), F.col("lemma") == F.col("_w"), "left").withColumn("lemma", F.coalesce("_l", "lemma")).drop("_w", "_l")


def article_text(html: Column) -> Column:
    """The reading text of a page: its article, tags and entities replaced by spaces."""
    article = F.regexp_extract(html, r"(?s)<article>(.*)</article>", 1)
    return F.regexp_replace(F.regexp_replace(article, r"<[^>]+>", " "), r"&[a-z]+;", " ")


def fold(word: Column) -> Column:
    """Accents off and related spellings made one, before cognates are compared."""
    out = F.translate(word, *_ACCENTS)
    for a, b in FOLDS:
        out = F.replace(out, F.lit(a), F.lit(b))
    return out


def drop_stopwords(words: DataFrame) -> DataFrame:
    return words.filter(~F.col("lemma").isin(STOPWORDS))


def proper_nouns(docs: DataFrame, max_cap_share: float = 0.5, least: int = 1, among: DataFrame | None = None) -> DataFrame:
    """(lemma): written with a capital in more than the share of its uses inside sentences; of the words (lemma) among which to look, a small table, or of all."""
    inside = docs.select(F.explode(sentences(F.col("text"))).alias("s")).select(F.explode(F.slice(F.regexp_extract_all("s", F.lit(r"\p{L}+"), F.lit(0)), F.lit(2), F.lit(1 << 30))).alias("w"))
    if among is not None:
        inside = inside.join(F.broadcast(among.select(F.col("lemma").alias("_l"))), F.lower("w") == F.col("_l"), "left_semi")
    counted = inside.groupBy(F.lower("w").alias("lemma")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.when(F.col("w").rlike(r"^\p{Lu}"), 1).otherwise(0)).alias("caps"))
    return counted.filter((F.col("n") >= least) & (F.col("caps") > F.col("n") * max_cap_share)).select("lemma")


def cognates(lemmas: DataFrame, other: DataFrame, max_sim: float = 0.6) -> DataFrame:
    """(lemma) of those nearer to a word of the other vocabulary than the similarity; both have ``lemma``.

    The edits that make two words too different bound the difference of their lengths, so words are compared within all lengths
    that can be near; no pair that is near is left out. Both sides are the top of a vocabulary, hundreds of words.
    """
    own = lemmas.select("lemma", fold(F.col("lemma")).alias("f"))
    theirs = other.select(fold(F.col("lemma")).alias("g")).distinct().withColumn("len", F.length("g"))
    # levenshtein >= |difference of lengths|, and must be less than (1 - max_sim) times the longer length
    reach = F.ceil(F.length("f") / F.lit(max_sim)).cast("int")
    near = own.withColumn("len", F.explode(F.sequence(F.floor(F.length("f") * F.lit(max_sim)).cast("int"), reach))).join(theirs, "len")
    return near.filter(F.levenshtein("f", "g") < (1 - max_sim) * F.greatest(F.length("f"), F.length("g"))).select("lemma").distinct()

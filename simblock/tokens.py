"""Records and their tokens."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NGRAM_LIMIT = 100_000_000  # characters up to which n-gram models are considered


def words(text: Column) -> Column:
    """Lower-cased runs of letters and digits."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda t: t != "")


def squeezed(text: Column) -> Column:
    """Lower-cased text with single blanks between its parts."""
    return F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"\s+", " "))


def ngrams(text: Column, n: int = 3) -> Column:
    """Substrings of n code points after white space is squeezed; a shorter string gives itself."""
    clean = squeezed(text)
    # lambda variables hold the characters, which would else be worked out anew for each n-gram
    grams = F.transform(
        F.array(F.split(clean, "")),
        lambda c: F.when(F.size(c) <= n, F.array(F.array_join(c, ""))).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(F.size(c) - (n - 1), F.lit(1))), lambda i: F.concat(*[F.element_at(c, i + j) for j in range(n)]))),
    )
    return F.when(clean == "", F.array().cast("array<string>")).otherwise(grams[0])


TOKENIZERS = {"word": words, "trigram": ngrams}


def allow_ngrams(*frames: DataFrame, limit: int = NGRAM_LIMIT) -> bool:
    """Whether the collections hold few enough characters for n-gram models."""
    total = 0
    for df in frames:
        total += df.select(F.sum(F.length("text"))).first()[0] or 0
    return total < limit


def term_counts(records: DataFrame, tokenizer: str = "word") -> DataFrame:
    """``(rec_id, token, tf)``; texts are dealt by record, which is less to move than their tokens."""
    exploded = records.select("rec_id", "text").repartition("rec_id").select("rec_id", F.explode(TOKENIZERS[tokenizer](F.col("text"))).alias("token"))
    return exploded.groupBy("rec_id", "token").agg(F.count("*").alias("tf"))


#: n-grams are cut in Python from squeezed texts, which are less to move; words are split by Spark
GRAMS = {"trigram": 3}


def token_lists(records: DataFrame, tokenizer: str = "word", single: bool = False) -> DataFrame:
    """``(rec_id, t)``: all words of a record, or its squeezed texts for n-grams; its rows, if there are several, are put together.

    With ``single`` no id has two rows, and no text is moved.
    """
    t = F.array(squeezed(F.col("text"))) if tokenizer in GRAMS else TOKENIZERS[tokenizer](F.col("text"))
    if single:
        return records.select("rec_id", t.alias("t"))
    dealt = records.select("rec_id", "text").repartition("rec_id")
    return dealt.groupBy("rec_id").agg(F.flatten(F.collect_list(t)).alias("t"))

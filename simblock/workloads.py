"""The experiment workloads on the given tables, each with its matches."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .measures import binary_similarity
from .sources import load, records, strip_tags
from .tokens import words


@dataclass
class Workload:
    name: str
    a: DataFrame
    b: DataFrame | None
    truth: DataFrame

    @property
    def dedup(self) -> bool:
        return self.b is None

    def sizes(self) -> tuple[int, int]:
        n = self.a.count()
        return n, n if self.b is None else self.b.count()


def docs(spark: SparkSession, sf: str) -> DataFrame:
    return records(load(spark, sf, "documents"), "doc_id", ["text"])


def items(spark: SparkSession, sf: str) -> DataFrame:
    return records(load(spark, sf, "benchmark"), "item_id", ["text"])


def copies(df: DataFrame, least: float) -> DataFrame:
    """Pairs of word-set Jaccard ``least`` or more, smaller id first."""
    from .join import JoinConfig, directed_join, unordered
    from .weights import TokenModel, prepare

    p = prepare(df, None, TokenModel("word", "binary"), "jaccard")
    return unordered(directed_join(p, JoinConfig(tau=least))).select("a_id", "b_id")


def items_in_docs(spark: SparkSession, sf: str) -> Workload:
    """A small collection against a large one; a match is an item whose text a document contains."""
    a, b = items(spark, sf), docs(spark, sf)
    truth = F.broadcast(a.select(F.col("rec_id").alias("a_id"), F.col("text").alias("t"))).join(b.select(F.col("rec_id").alias("b_id"), "text"), F.expr("contains(text, t)")).select("a_id", "b_id")
    return Workload("items_in_docs", a, b, truth)


def docs_even_odd(spark: SparkSession, sf: str) -> Workload:
    """Two collections of like size."""
    both = docs(spark, sf)
    truth = copies(both, 0.5).where("(a_id + b_id) % 2 = 1")
    truth = truth.select(F.when(F.col("a_id") % 2 == 0, F.col("a_id")).otherwise(F.col("b_id")).alias("a_id"), F.when(F.col("a_id") % 2 == 0, F.col("b_id")).otherwise(F.col("a_id")).alias("b_id"))
    return Workload("docs_even_odd", both.where("rec_id % 2 = 0"), both.where("rec_id % 2 = 1"), truth)


def docs_dedup(spark: SparkSession, sf: str) -> Workload:
    df = docs(spark, sf)
    return Workload("docs_dedup", df, None, copies(df, 0.5))


def long_docs(spark: SparkSession, sf: str) -> Workload:
    """Long noisy texts."""
    table = load(spark, sf, "documents").where("n_chars >= 4000")
    both = records(table, "doc_id", ["text"])
    truth = copies(both, 0.5).where("(a_id + b_id) % 2 = 1")
    even = F.col("a_id") % 2 == 0
    truth = truth.select(F.when(even, F.col("a_id")).otherwise(F.col("b_id")).alias("a_id"), F.when(even, F.col("b_id")).otherwise(F.col("a_id")).alias("b_id"))
    return Workload("long_docs", both.where("rec_id % 2 = 0"), both.where("rec_id % 2 = 1"), truth)


def pages_dedup(spark: SparkSession, sf: str) -> Workload:
    df = load(spark, sf, "pages").select(F.col("page_id").alias("rec_id"), strip_tags(F.col("html")).alias("text"))
    return Workload("pages_dedup", df, None, copies(df, 0.4))


def parts_dedup(spark: SparkSession, sf: str) -> Workload:
    """Short strings with very long lists and many ties."""
    table = load(spark, sf, "part")
    df = records(table, "p_partkey", ["p_brand", "p_name", "p_type"])
    key = ["p_brand", "p_name", "p_type"]
    x, y = table.select(F.col("p_partkey").alias("a_id"), *key), table.select(F.col("p_partkey").alias("b_id"), *key)
    return Workload("parts_dedup", df, None, x.join(y, key).where("a_id < b_id").select("a_id", "b_id"))


def dirty(df: DataFrame) -> DataFrame:
    """Documents as multi-attribute records, with ``source`` moved into the text for a hashed half."""
    moved = F.substring(F.md5(F.col("doc_id").cast("string")), 1, 1).isin(*"01234567")
    return df.withColumn("text", F.when(moved, F.concat_ws(" ", "text", "source")).otherwise(F.col("text"))).withColumn("source", F.when(moved, F.lit(None)).otherwise(F.col("source")))


def docs_dirty(spark: SparkSession, sf: str, make_dirty: bool = True) -> Workload:
    """The even-odd workload over (lang, source, text), clean or dirty."""
    table = load(spark, sf, "documents")
    both = records(dirty(table) if make_dirty else table, "doc_id", ["lang", "source", "text"])
    truth = docs_even_odd(spark, sf).truth
    return Workload("docs_dirty" if make_dirty else "docs_attributes", both.where("rec_id % 2 = 0"), both.where("rec_id % 2 = 1"), truth)


def fraction(df: DataFrame, id_col: str, part: float) -> DataFrame:
    """A stable share of rows, nested for growing shares."""
    return df.where(F.conv(F.substring(F.md5(F.col(id_col).cast("string")), 1, 8), 16, 10).cast("long") < int(part * (1 << 32)))


def split_matches(truth: DataFrame, most: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(training, test) matches by a hash of the pair, about 3 to 1; training capped by hash order."""
    h = F.md5(F.concat_ws("-", "a_id", "b_id"))
    first = F.conv(F.substring(h, 1, 1), 16, 10).cast("int")
    train = truth.where(first < 12)
    if most is not None:
        train = train.orderBy(h).limit(most)
    return train, truth.where(first >= 12)


def similarity_table(spark: SparkSession, sf: str, measure: str) -> DataFrame:
    """Similarity without weights of every item and document that share a word."""
    a = items(spark, sf).select(F.col("rec_id").alias("a_id"), words(F.col("text")).alias("x"))
    b = docs(spark, sf).select(F.col("rec_id").alias("b_id"), words(F.col("text")).alias("y"))
    sim = binary_similarity(F.col("x"), F.col("y"), measure)
    return F.broadcast(a).crossJoin(b).select("a_id", "b_id", sim.alias("sim")).where("sim > 0")


WORKLOADS = {f.__name__: f for f in (items_in_docs, docs_even_odd, docs_dedup, long_docs, pages_dedup, parts_dedup, docs_dirty)}

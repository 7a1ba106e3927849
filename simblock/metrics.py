"""Accuracy and cost of candidate pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def evaluate(pairs: DataFrame, truth: DataFrame, n_a: int, n_b: int) -> DataFrame:
    """One row: recall, precision, pairs, effective cardinality and reduction rate."""
    p = pairs.select("a_id", "b_id").distinct()
    hits = truth.select("a_id", "b_id").distinct().join(p.withColumn("hit", F.lit(1)), ["a_id", "b_id"], "left")
    row = hits.agg(F.count("*").alias("matches"), F.count("hit").alias("found")).crossJoin(p.agg(F.count("*").alias("pairs")))
    return row.select(
        "matches", "found", "pairs",
        F.when(F.col("matches") > 0, F.col("found") / F.col("matches")).alias("recall"),
        F.when(F.col("pairs") > 0, F.col("found") / F.col("pairs")).alias("precision"),
        (F.col("pairs") / F.lit(float(min(n_a, n_b)))).alias("k_eff"),
        (1 - F.col("pairs") / F.lit(float(n_a) * n_b)).alias("reduction"),
    )


def tradeoff(scored: DataFrame, truth: DataFrame, by: str, grid: list[float], n_a: int, n_b: int) -> DataFrame:
    """(threshold, pairs, k_eff, recall) for each grid value, from one scored result.

    ``by`` is ``tau`` (similarity at least) or ``k`` (the first k of each probe).
    """
    from pyspark.sql import Window

    if by == "k":
        order = Window.partitionBy("a_id").orderBy(F.round("sim", 9).desc(), "b_id")
        scored = scored.withColumn("_v", F.row_number().over(order))
        test = lambda g: F.col("_v") <= g
    else:
        scored = scored.withColumn("_v", F.round("sim", 9))
        test = lambda g: F.col("_v") >= g
    flagged = scored.join(truth.select("a_id", "b_id").distinct().withColumn("hit", F.lit(1)), ["a_id", "b_id"], "left")
    total = max(1, truth.select("a_id", "b_id").distinct().count())
    row = flagged.agg(*[f.alias(f"{n}{i}") for i, g in enumerate(grid) for n, f in (("p", F.count_if(test(g))), ("h", F.count_if(test(g) & F.col("hit").isNotNull())))])
    points = F.array(*[F.struct(F.lit(float(g)).alias("threshold"), F.col(f"p{i}").alias("pairs"), (F.col(f"p{i}") / F.lit(float(min(n_a, n_b)))).alias("k_eff"), (F.col(f"h{i}") / F.lit(float(total))).alias("recall")) for i, g in enumerate(grid)])
    return row.select(F.explode(points).alias("x")).select("x.*")


def best_by_cost(front: DataFrame, costs: list[float]) -> DataFrame:
    """``(c_k, threshold, k_eff, recall)``: for each cost of a pair a record, the point of most recall less cost.

    Of equal points the one with fewer pairs, then the lesser threshold, is taken.
    """
    points = front.withColumn("c_k", F.explode(F.array(*[F.lit(float(c)) for c in costs])))
    value = F.round(F.col("recall") - F.col("c_k") * F.col("k_eff"), 9)
    best = points.groupBy("c_k").agg(F.max_by(F.struct("threshold", "k_eff", "recall"), F.struct(value, -F.col("k_eff"), -F.col("threshold"))).alias("x"))
    return best.select("c_k", "x.*")

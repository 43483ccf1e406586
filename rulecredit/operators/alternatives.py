"""Two simple measures of an element: its best rule, and what its removal costs the set."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rulecredit.functions.aggregates import set_aggregate, top_k_of


def i_top(rules: DataFrame, elements: DataFrame) -> DataFrame:
    """(elem_id, x): score of the best rule with the element."""
    best = rules.select(F.explode("items").alias("elem_id"), "score").groupBy("elem_id").agg(F.max("score").alias("x"))
    return elements.select("elem_id").join(best, "elem_id")


def influence(rules: DataFrame, elements: DataFrame, agg: str = "max") -> DataFrame:
    """(elem_id, x): interest of the set minus that of the rules without the element.

    Sums and averages subtract the element's own part. For max and top-k only an element
    of one of the best rules can matter, at most k times the largest rule; all others score 0.
    """
    ids = elements.select("elem_id")
    if agg in ("sum", "avg"):
        whole = rules.agg(F.coalesce(F.sum("score"), F.lit(0.0)).alias("s"), F.count("*").alias("n")).first()
        own = rules.select(F.explode("items").alias("elem_id"), "score").groupBy("elem_id").agg(
            F.sum("score").alias("s"), F.count("*").alias("n")
        )
        left_s, left_n = F.lit(whole["s"]) - F.col("s"), F.lit(whole["n"]) - F.col("n")
        if agg == "sum":
            x = F.lit(whole["s"]) - F.when(left_n > 0, left_s).otherwise(F.lit(0.0))
        else:
            x = F.lit(whole["s"] / whole["n"] if whole["n"] else 0.0) - F.when(left_n > 0, left_s / left_n).otherwise(F.lit(0.0))
        return ids.join(own, "elem_id", "left").select("elem_id", F.when(F.col("n").isNull(), F.lit(0.0)).otherwise(x).alias("x"))
    k = top_k_of(agg) or 1
    best = rules.orderBy(F.desc("score"), "lhs", "rhs").limit(k).collect()
    total = sum(r["score"] for r in best)
    candidates = sorted({i for r in best for i in r["items"]})
    if not candidates:
        return ids.select("elem_id", F.lit(0.0).alias("x"))

    # each candidate's best k rules among those without it; Spark keeps k a task and candidate before the shuffle
    lacking = rules.select(F.explode(F.array_except(F.array(*[F.lit(c) for c in candidates]), "items")).alias("elem_id"), "score")
    nth = F.row_number().over(Window.partitionBy("elem_id").orderBy(F.desc("score")))
    kept = lacking.withColumn("nth", nth).where(F.col("nth") <= k).groupBy("elem_id").agg(F.sum("score").alias("rest"))
    left = rules.sparkSession.createDataFrame([(c,) for c in candidates], "elem_id int").join(kept, "elem_id", "left").na.fill(0.0, ["rest"])
    joined = ids.join(F.broadcast(left), "elem_id", "left")
    return joined.select("elem_id", F.coalesce(F.lit(total) - F.col("rest"), F.lit(0.0)).alias("x"))


def interest_without(rules: DataFrame, elem_id: int, agg: str = "max") -> DataFrame:
    """The literal second term of the influence, for checks."""
    return rules.where(~F.array_contains("items", elem_id)).agg(F.coalesce(set_aggregate(agg), F.lit(0.0)).alias("interest"))

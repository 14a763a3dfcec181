"""Association rules from exact or reconstructed supports."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .reconstruct import subsets


def generate(frequent: DataFrame, dbsize: int, min_conf: float, strict: bool = False, clamp: bool = False) -> DataFrame:
    """All rules X => Y with X and Y disjoint, X with Y frequent, and enough confidence.

    ``frequent`` has itemset, k and est (a count; reconstructed ones may break monotonicity, so that a
    confidence exceeds 1: such rules are marked, or clipped with ``clamp``).
    """
    if not 0 <= min_conf <= 1:
        raise ValueError("min_conf must lie between 0 and 1")
    each = frequent.where("k > 1").select("itemset", F.col("est").alias("both"), F.explode(subsets()).alias("antecedent"))
    each = each.where("size(antecedent) > 0 AND size(antecedent) < size(itemset)")
    parts = frequent.select(F.col("itemset").alias("antecedent"), F.col("est").alias("part"))
    joined = each.join(parts, "antecedent").where("part > 0").withColumn("consequent", F.array_except("itemset", "antecedent"))
    conf = F.col("both") / F.col("part")
    joined = joined.where(~F.arrays_overlap("antecedent", "consequent")).where(conf > min_conf if strict else conf >= min_conf)
    return joined.select("antecedent", "consequent", (F.col("both") / dbsize).alias("support"), (F.least(conf, F.lit(1.0)) if clamp else conf).alias("confidence"), (conf > 1).alias("above_one"))

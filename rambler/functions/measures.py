"""How well drawn steps fit the exact law of their states."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def law_fit(observed: DataFrame, law: DataFrame, *state: str) -> DataFrame:
    """A row for each state of `law`: draws, chi_square, degrees (its choices less one), total_variation and strays (draws of what the law excludes).

    observed: (state..., dst), a row for each draw. law: (state..., dst, p), p > 0 and adding up to 1. A state without draws has
    chi_square 0 and total_variation null; states that only `observed` has are strays throughout and get a row too.
    Draws are counted before they meet the law, so a state however often drawn makes one row for each of its choices."""
    counts = observed.groupBy(*state, "dst").agg(F.count("*").alias("n"))
    drawn = counts.groupBy(*state).agg(F.sum("n").alias("draws"))
    both = counts.join(law.select(*state, "dst", "p"), [*state, "dst"], "full").join(drawn, [*state], "left").na.fill(0, ["n", "draws"])
    want = F.col("draws") * F.col("p")
    far = F.when(F.col("draws") > 0, F.abs(F.col("n") / F.col("draws") - F.coalesce("p", F.lit(0.0))))
    return both.groupBy(*state).agg(
        F.first("draws").alias("draws"),
        F.coalesce(F.sum(F.when(want > 0, (F.col("n") - want) * (F.col("n") - want) / want)), F.lit(0.0)).alias("chi_square"),
        (F.count("p") - 1).alias("degrees"),
        (F.sum(far) / 2).alias("total_variation"),
        F.sum(F.when(F.col("p").isNull(), F.col("n")).otherwise(0)).alias("strays"),
    )

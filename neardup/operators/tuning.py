"""Choice of bands and rows: by a grid against true pairs, or by the candidate curve."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.functions.sets import candidate_probability
from neardup.operators.candidates import banded
from neardup.operators.verify import first_bands
from neardup.session import materialize


def expected(pairs: DataFrame, grid: list[tuple[int, int]], thresholds: list[float]) -> DataFrame:
    """(t, b, r, candidates, false_candidates, misses): expected counts over scored pairs, by the curve; pairs may have a column n with how many a row stands for."""
    spark = pairs.sparkSession
    configs = spark.createDataFrame([(t, b, r) for t in thresholds for b, r in grid], "t double, n_bands int, n_rows int")
    p = candidate_probability(F.col("jaccard"), F.col("n_bands"), F.col("n_rows"))
    true = F.col("jaccard") > F.col("t")
    # Pairs of equal similarity count as one row with their number.
    rows = pairs.groupBy("jaccard").agg((F.sum("n") if "n" in pairs.columns else F.count("*")).alias("n")).crossJoin(F.broadcast(configs))  # a few dozen settings
    n = F.col("n")
    return rows.groupBy("t", F.col("n_bands").alias("b"), F.col("n_rows").alias("r")).agg(F.round(F.sum(n * p), 6).alias("candidates"), F.round(F.sum(F.when(true, 0.0).otherwise(n * p)), 6).alias("false_candidates"), F.round(F.sum(F.when(true, n * (1 - p)).otherwise(0.0)), 6).alias("misses"))


def measured(bands: DataFrame, bs: list[int], r: int, truth: DataFrame, thresholds: list[float]) -> DataFrame:
    """(t, b, r, candidates, false_candidates, misses) of the first b bands, for each b: larger b only adds candidates.

    The lowest band in which a pair agrees tells from which b on it is a candidate, so all b come from one count; only true pairs become rows.
    """
    spark = bands.sparkSession
    configs = F.broadcast(spark.createDataFrame([(t, b) for t in thresholds for b in bs], "t double, n_bands int"))  # a few dozen settings
    found = materialize(first_bands(bands, truth), "first")
    true = truth.select("a", "b", "jaccard").join(found.where("n = 0").select("a", "b", "first"), ["a", "b"], "left").groupBy("jaccard", "first").agg(F.count("*").alias("n"))
    rows = found.where("n > 0").select(F.lit(None).cast("double").alias("jaccard"), "first", "n").unionByName(true).crossJoin(configs)
    cand, above = F.coalesce(F.col("first") < F.col("n_bands"), F.lit(False)), F.col("jaccard") > F.col("t")
    total = lambda c: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0))
    every = rows.groupBy("t", "n_bands").agg(total(cand & F.col("jaccard").isNull()).alias("candidates"), total(cand & above).alias("hits"), total(~cand & above).alias("misses"))
    return every.select("t", F.col("n_bands").alias("b"), F.lit(r).alias("r"), "candidates", (F.col("candidates") - F.col("hits")).alias("false_candidates"), "misses")


def choose_bands(grid: DataFrame, most_misses: float = 0) -> DataFrame:
    """For each t the setting with the fewest values b * r among those with no more misses; ties by fewer false candidates."""
    ok = grid.where(F.col("misses") <= most_misses)
    return ok.groupBy("t").agg(F.min_by(F.struct("b", "r", "misses", "false_candidates"), F.struct(F.col("b") * F.col("r"), "false_candidates", "b")).alias("x")).select("t", "x.b", "x.r", "x.misses", "x.false_candidates")


def threshold_of(b: int, r: int) -> float:
    """Where the candidate curve is steepest, about."""
    return (1 / b) ** (1 / r)


def nested(bands: DataFrame, b1: int, b2: int) -> DataFrame:
    """Candidates of the first b1 bands that the first b2 >= b1 bands miss: none."""
    return banded(bands.where(F.col("band_id") < b1)).exceptAll(banded(bands.where(F.col("band_id") < b2)))

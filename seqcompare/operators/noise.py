"""Noise on matrices: chosen shares of entries take null values, or a uniform addition; losses against a gold standard."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..rng import BITS, draw, uniform

#: Ranks are counted within so many ranges of the draw, so that no window is over a whole matrix.
RANGES = 1024


def select(mat: DataFrame, levels: list[float], trials: int = 1, seed: int = 1, keys: tuple[str, ...] = ()) -> DataFrame:
    """(level, trial) and the matrix, with ``replaced`` on the first ceil(level * m) entries in order of their hash.

    The order of a trial is one for all levels, so what a level replaces, a higher one does too.
    """
    spark = mat.sparkSession
    tries = mat.select("*", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))).alias("trial")).withColumn("draw", draw(seed, F.col("trial"), F.col("i"), F.col("j")))
    tries = tries.withColumn("range", F.shiftright("draw", BITS - 10))
    group = [*keys, "fn", "trial"]
    counts = tries.groupBy(*group, "range").agg(F.count("*").alias("n"))
    over = Window.partitionBy(*group)
    before = counts.select(*group, "range", (F.sum("n").over(over.orderBy("range")) - F.col("n")).alias("before"), F.sum("n").over(over).alias("m"))
    place = F.row_number().over(Window.partitionBy(*group, "range").orderBy("draw", "i", "j"))
    ranked = tries.withColumn("place", place).join(before, [*group, "range"]).withColumn("rank", F.col("before") + F.col("place"))
    grid = ranked.join(F.broadcast(spark.createDataFrame([(float(x),) for x in levels], "level double")), F.lit(True))
    return grid.withColumn("replaced", F.col("rank") <= F.ceil(F.round(F.col("level") * F.col("m"), 9))).drop("rank", "m", "draw", "range", "place", "before")


def numbered(nulls: DataFrame, keys: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """Null values by number, in order of (replicate, i, j), and how many a function has: prefix sums over replicates, then over i."""
    real = nulls.where("value is not null")
    group = [*keys, "fn"]
    rows = real.groupBy(*group, "replicate", "i").agg(F.count("*").alias("n"))
    within = F.sum("n").over(Window.partitionBy(*group, "replicate").orderBy("i")) - F.col("n")
    whole = rows.groupBy(*group, "replicate").agg(F.sum("n").alias("all"))
    first = whole.select(*group, "replicate", (F.sum("all").over(Window.partitionBy(*group).orderBy("replicate")) - F.col("all")).alias("first"))
    starts = rows.select(*group, "replicate", "i", within.alias("within")).join(first, [*group, "replicate"])
    place = F.row_number().over(Window.partitionBy(*group, "replicate", "i").orderBy("j"))
    out = real.withColumn("place", place).join(starts, [*group, "replicate", "i"])
    return out.select(*group, F.col("value").alias("null_value"), (F.col("first") + F.col("within") + F.col("place")).alias("at")), whole.groupBy(*group).agg(F.sum("all").alias("many"))


def from_nulls(chosen: DataFrame, nulls: DataFrame, seed: int = 1, keys: tuple[str, ...] = ()) -> DataFrame:
    """Replaced entries take a value drawn from the function's null values."""
    ranked, sizes = numbered(nulls, keys)
    drawn = chosen.join(F.broadcast(sizes), [*keys, "fn"]).withColumn("at", F.when(F.col("replaced"), F.pmod(draw(seed, "value", F.col("trial"), F.col("i"), F.col("j")), F.col("many")) + 1))
    joined = drawn.join(ranked, [*keys, "fn", "at"], "left")
    return joined.withColumn("value", F.when(F.col("replaced"), F.col("null_value")).otherwise(F.col("value"))).drop("at", "many", "null_value")


def additive(chosen: DataFrame, noise_max: float | None = None, seed: int = 1, keys: tuple[str, ...] = ()) -> DataFrame:
    """Replaced entries gain a uniform value up to ``noise_max``, by default the largest of the matrix; null ones start from that."""
    largest = chosen.groupBy(*keys, "fn").agg(F.max("value").alias("largest"))
    top = F.lit(noise_max) if noise_max is not None else F.col("largest")
    start = F.coalesce("value", F.col("largest"))
    more: Column = start + top * uniform(seed, "add", F.col("trial"), F.col("i"), F.col("j"))
    return chosen.join(F.broadcast(largest), [*keys, "fn"]).withColumn("value", F.when(F.col("replaced"), more).otherwise(F.col("value"))).drop("largest")


def loss(scores: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, fn, builder, metric, level, trial, clean, noisy, delta, pct): against level 0 of the same trial."""
    by = [*keys, "fn", "builder", "metric", "trial"]
    clean = scores.where("level = 0").select(*by, F.col("score").alias("clean"))
    delta = F.col("score") - F.col("clean")
    pct = F.when(F.col("clean") == 0, F.when(delta == 0, "0.0").otherwise("Inf")).otherwise(F.format_string("%.1f", 100 * delta / F.col("clean")))
    return scores.join(clean, by).select(*by, "level", "clean", F.col("score").alias("noisy"), delta.alias("delta"), pct.alias("pct"))


def report(losses: DataFrame, band: float = 3, level: float = 0.1, keys: tuple[str, ...] = ()) -> DataFrame:
    """Changes at a level, with a dash for those within the band."""
    by = [*keys, "fn", "builder", "metric"]
    at = losses.where(F.abs(F.col("level") - level) < 1e-9).groupBy(*by).agg(F.avg("delta").alias("delta"), F.avg("clean").alias("clean"))
    pct = F.when(F.col("clean") == 0, "Inf").otherwise(F.format_string("%.1f", 100 * F.col("delta") / F.col("clean")))
    return at.select(*by, "delta", F.when(F.abs("delta") <= band, "-").otherwise(pct).alias("shown"))


def breakpoint(losses: DataFrame, worse: float = 0.1, keys: tuple[str, ...] = ()) -> DataFrame:
    """The least level at which the score is worse by ``worse`` of the clean one on average; null if none is."""
    by = [*keys, "fn", "builder", "metric"]
    levels = losses.groupBy(*by, "level").agg(F.avg("noisy").alias("noisy"), F.avg("clean").alias("clean"))
    bad = (F.col("level") > 0) & (F.col("noisy") >= (1 + worse) * F.col("clean")) & (F.col("noisy") > F.col("clean"))
    return levels.groupBy(*by).agg(F.min(F.when(bad, F.col("level"))).alias("level"))

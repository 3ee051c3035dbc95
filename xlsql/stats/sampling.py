"""Sample sizes, draws, intervals and agreement."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# Two-sided normal quantiles of the usual confidence levels.
Z = {0.90: 1.645, 0.95: 1.96, 0.99: 2.576}


def _c(x) -> Column:
    return x if isinstance(x, Column) else F.lit(float(x))


def sample_size_infinite(z=1.96, e=0.03, p=0.5) -> Column:
    """Sample size for a proportion from an unlimited population, rounded up."""
    z, e, p = _c(z), _c(e), _c(p)
    return F.ceil(F.round(z * z * p * (1 - p) / (e * e), 9)).cast("long")


def sample_size_finite(n0: Column, population: Column) -> Column:
    """Finite population correction of ``n0``, rounded up again."""
    return F.ceil(F.round(n0 / (1 + (n0 - 1) / population), 9)).cast("long")


def plan_sample(df: DataFrame, strata: str | None = None, confidence: float = 0.95, margin: float = 0.03, p: float = 0.5) -> DataFrame:
    """population, n0, n; with ``strata`` a row for each stratum, whose shares of n are proportional by largest remainders."""
    sizes = df.groupBy(*([strata] if strata else [])).agg(F.count("*").alias("population"))
    n0 = sample_size_infinite(Z[confidence], margin, p)
    if strata is None:
        return sizes.withColumn("n0", n0).withColumn("n", sample_size_finite(F.col("n0"), F.col("population")))
    # as many rows as strata
    whole = Window.partitionBy(F.lit(1))
    planned = sizes.withColumn("n0", n0).withColumn("n", sample_size_finite(F.col("n0"), F.sum("population").over(whole)))
    share = F.col("n") * F.col("population") / F.sum("population").over(whole)
    planned = planned.withColumn("low", F.floor(share)).withColumn("rest", F.round(share - F.floor(share), 9))
    left = F.col("n") - F.sum("low").over(whole)
    nth = F.row_number().over(Window.partitionBy(F.lit(1)).orderBy(F.desc("rest"), strata))
    return planned.withColumn("n_stratum", (F.col("low") + (nth <= left).cast("int")).cast("long")).select(strata, "population", "n0", "n", "n_stratum")


def draw_key(key: Column, seed: int, by_hash: str = "md5") -> Column:
    """Order of a reproducible draw: ``md5``, the same in every engine that has it, or ``xxhash64``, cheaper and as 16 hex digits too."""
    if by_hash == "xxhash64":
        return F.lower(F.lpad(F.hex(F.xxhash64(key.cast("string"), F.lit(seed))), 16, "0"))
    return F.md5(F.concat(key.cast("string"), F.lit(f":{seed}")))


def draw_sample(df: DataFrame, n: int | DataFrame, key: str, seed: int = 42, by: str | None = None, by_hash: str = "md5") -> DataFrame:
    """Exactly n rows (all, if there are fewer), first by ``draw_key``; ``by``: strata, n then a table (by, n_stratum[, population]).

    Of a stratum only rows whose key lies below a share somewhat above the wanted one are ranked, so that no task sorts a whole stratum. The
    share is checked by a count: if chance left any stratum short, all rows are ranked.
    """
    order = draw_key(F.col(key), seed, by_hash)
    if by is None:
        return df.orderBy(order, key).limit(n)
    # as many rows as strata
    wanted = n.select(by, "n_stratum", *(["population"] if "population" in n.columns else []))
    if "population" in n.columns:
        ample = F.col("n_stratum") + 8 * F.sqrt("n_stratum") + 40
        below = F.lpad(F.lower(F.hex(F.floor(F.least(F.lit(1.0), ample / F.col("population")) * (2**32 - 1)).cast("long"))), 8, "0")
        near = df.join(F.broadcast(wanted.withColumn("_below", below)), by).where(F.substring(order, 1, 8) <= F.col("_below")).drop("_below", "population")
        short = wanted.join(near.groupBy(by).agg(F.count("*").alias("_held")), by, "left").where(F.coalesce("_held", F.lit(0)) < F.least("n_stratum", "population"))
        if not short.isEmpty():
            return draw_sample(df, n.drop("population"), key, seed, by, by_hash)
    else:
        near = df.join(F.broadcast(wanted), by)
    ranked = near.withColumn("_nth", F.row_number().over(Window.partitionBy(by).orderBy(order, key)))
    return ranked.where("_nth <= n_stratum").select(*df.columns)


def bernoulli_sample(df: DataFrame, share: float | dict, seed: int = 42, by: str | None = None) -> DataFrame:
    """Each row by itself with probability ``share`` (``by``: a share for each stratum): one pass, no order, a number of rows that varies."""
    return df.sample(fraction=share, seed=seed) if by is None else df.sampleBy(by, share, seed)


def accuracy_interval(k: Column, n: Column, population: Column | None = None, z: float = 1.96, method: str = "wald") -> Column:
    """Struct low, high, half: interval of a proportion. wald (with finite correction if ``population`` is given), planned (p = 0.5), wilson."""
    p = k / n
    if method == "wilson":
        mid = (p + z * z / (2 * n)) / (1 + z * z / n)
        half = z * F.sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / (1 + z * z / n)
        return F.struct((mid - half).alias("low"), (mid + half).alias("high"), half.alias("half"))
    q = F.lit(0.5) if method == "planned" else p
    half = z * F.sqrt(q * (1 - q) / n)
    if population is not None:
        half = half * F.sqrt((population - n) / (population - 1))
    return F.struct((p - half).alias("low"), (p + half).alias("high"), half.alias("half"))


def observed_accuracy(verdicts: DataFrame, verdict: str = "correct") -> DataFrame:
    return verdicts.agg(F.sum(F.col(verdict).cast("long")).alias("k"), F.count(verdict).alias("n"), F.avg(F.col(verdict).cast("double")).alias("accuracy"))


def coverage(df: DataFrame, key: str, verdict: str, n: int, seeds: int, z: float = 1.96, fpc: bool = True) -> DataFrame:
    """seeds, hits, rate: how often the interval of a draw of n holds the census value. Draws are by seed, side by side."""
    census, population = df.agg(F.avg(F.col(verdict).cast("double")), F.count("*")).first()
    at = df.select(key, verdict).withColumn("seed", F.explode(F.sequence(F.lit(0), F.lit(seeds - 1))))
    order = F.md5(F.concat(F.col(key).cast("string"), F.lit(":"), F.col("seed").cast("string")))
    drawn = at.withColumn("nth", F.row_number().over(Window.partitionBy("seed").orderBy(order, key))).where(F.col("nth") <= n)
    p = drawn.groupBy("seed").agg(F.avg(F.col(verdict).cast("double")).alias("p"), F.count("*").alias("n"))
    half = z * F.sqrt(F.col("p") * (1 - F.col("p")) / F.col("n"))
    if fpc:
        half = half * F.sqrt((F.lit(float(population)) - F.col("n")) / F.lit(float(population - 1)))
    held = p.select((F.abs(F.col("p") - F.lit(census)) <= half + 1e-12).cast("long").alias("hit"))
    return held.agg(F.count("*").alias("seeds"), F.sum("hit").alias("hits"), F.round(F.avg("hit"), 6).alias("rate"))


def agreement(df: DataFrame, a: str, b: str) -> DataFrame:
    """n, raw agreement and Cohen's kappa of two 0/1 columns."""
    x, y = F.col(a).cast("double"), F.col(b).cast("double")
    s = df.agg(F.count("*").alias("n"), F.avg((x == y).cast("double")).alias("raw"), F.avg(x).alias("pa"), F.avg(y).alias("pb"))
    chance = F.col("pa") * F.col("pb") + (1 - F.col("pa")) * (1 - F.col("pb"))
    return s.select("n", F.round("raw", 6).alias("raw"), F.round((F.col("raw") - chance) / (1 - chance), 6).alias("kappa"))

"""Summaries over networks and models."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def compression_ratio(scores: DataFrame, null: DataFrame) -> DataFrame:
    """Adds dl_null and eta = dl / dl_null; below 1 there is structure (a weighted model stays a little below 1 without any)."""
    return scores.join(null.select("network_id", "dl_null"), "network_id").withColumn("eta", F.col("dl") / F.col("dl_null"))


def complexity(model: Column) -> Column:
    """Simplicity of a model's name, for ties: null, then flat, degree-corrected, ranked, nested."""
    return F.when(model == "null", 0).otherwise(1 + F.when(model.contains("dc"), 1).otherwise(0) + F.when(model.rlike("bm_n?r"), 2).otherwise(0) + F.when(model.rlike("bm_n"), 4).otherwise(0))


def best_model(scores: DataFrame) -> DataFrame:
    """(network_id, model, rep, b, dl) of the shortest length; ties to the simpler model, then by name."""
    key = F.struct(F.round("dl", 6).alias("d"), complexity(F.col("model")).alias("c"), "model", "rep")
    return scores.groupBy("network_id").agg(F.min_by(F.struct("model", "rep", "b", "dl"), key).alias("m")).select("network_id", "m.*")


def model_histogram(best: DataFrame, networks: DataFrame) -> DataFrame:
    return best.join(networks.select("network_id", "class"), "network_id").groupBy("class", "model").agg(F.count("*").alias("networks"))


def dl_ratio(a: DataFrame, b: DataFrame) -> DataFrame:
    """(network_id, ratio): lengths of a over b, one row of each for a network."""
    return a.select("network_id", F.col("dl").alias("x")).join(b.select("network_id", F.col("dl").alias("y")), "network_id").select("network_id", (F.col("x") / F.col("y")).alias("ratio"))


def dl_gap_per_node(a: DataFrame, b: DataFrame) -> DataFrame:
    """(network_id, gap): (dl of a - dl of b) / n."""
    return a.select("network_id", "n", F.col("dl").alias("x")).join(b.select("network_id", F.col("dl").alias("y")), "network_id").select("network_id", ((F.col("x") - F.col("y")) / F.col("n")).alias("gap"))


def rep_gap(scores: DataFrame) -> DataFrame:
    """(network_id, n, gap): best multigraph length minus best weighted length; above 0 the weighted form wins."""
    wide = scores.groupBy("network_id", "n").pivot("rep", ["mg", "w"]).agg(F.min("dl"))
    return wide.select("network_id", "n", (F.col("mg") - F.col("w")).alias("gap"))


def resolution_limits(scores: DataFrame) -> DataFrame:
    """Adds sqrt(N) and N / ln N, the most groups flat and nested models can see."""
    return scores.withColumn("flat_limit", F.sqrt("n")).withColumn("nested_limit", F.col("n") / F.log("n"))


def fit_line(scores: DataFrame, y: str, x: str, by: str = "model") -> DataFrame:
    return scores.groupBy(by).agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def scale_compare(fine: DataFrame, coarse: DataFrame) -> DataFrame:
    """(network_id, eta_fine, eta_coarse)."""
    return fine.select("network_id", F.col("eta").alias("eta_fine")).join(coarse.select("network_id", F.col("eta").alias("eta_coarse")), "network_id")


def histogram(rows: DataFrame, col: str, bins: int) -> DataFrame:
    """(bin, n) over 0..1; 1 falls in the last bin."""
    return rows.select(F.least(F.floor(F.col(col) * bins), F.lit(bins - 1)).cast("int").alias("bin")).groupBy("bin").agg(F.count("*").alias("n"))


def summarise(rows: DataFrame, col: str, by: str = "model") -> DataFrame:
    return rows.groupBy(by).agg(F.avg(col).alias("mean"), F.stddev_samp(col).alias("sd"), F.min(col).alias("low"), F.median(col).alias("median"), F.max(col).alias("high"), F.count("*").alias("n"))


def runtime_slope(runs: DataFrame) -> DataFrame:
    """(slope): of log seconds on log units."""
    return runs.agg(F.regr_slope(F.log("seconds"), F.log("n")).alias("slope"))

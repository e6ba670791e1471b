"""Baselines and measures: fraction error, recall, summaries, distributions, invariance and cost reports."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def mean_predictor(df: DataFrame, targets: list[str]) -> DataFrame:
    """``fold, target, pred``: the mean of all other folds, from one aggregate by fold."""
    sums = df.groupBy("fold").agg(F.count("*").alias("_n"), *(F.sum(t).alias(t) for t in targets))
    long = sums.unpivot(["fold", "_n"], targets, "target", "_s")
    whole = Window.partitionBy("target")
    n, s = F.sum("_n").over(whole) - F.col("_n"), F.sum("_s").over(whole) - F.col("_s")
    return long.select("fold", "target", F.try_divide(s, n).alias("pred"))


def long_targets(df: DataFrame, targets: list[str]) -> DataFrame:
    return df.select("structure_id", "fold", *targets).unpivot(["structure_id", "fold"], targets, "target", "calc")


def mean_predictions(df: DataFrame, targets: list[str]) -> DataFrame:
    """``structure_id, fold, split, target, calc, pred`` of the mean predictor on the test folds."""
    return long_targets(df, targets).join(mean_predictor(df, targets), ["fold", "target"]).select("structure_id", "fold", F.lit("test").alias("split"), "target", "calc", "pred")


def _relative(pred: str = "pred", calc: str = "calc") -> Column:
    return F.abs(F.try_divide(F.col(pred) - F.col(calc), F.col(calc)))


def fraction_error(df: DataFrame, by: list[str], pred: str = "pred", calc: str = "calc") -> DataFrame:
    """Mean of abs((pred - calc) / calc); rows whose calc is 0 are left out and counted."""
    return df.groupBy(*by).agg(F.avg(_relative(pred, calc)).alias("error"), F.count_if(F.col(calc) == 0).alias("undefined"), F.count("*").alias("n"))


def fold_summary(errors: DataFrame, by: list[str], value: str = "error") -> DataFrame:
    return errors.groupBy(*by).agg(F.avg(value).alias("mean"), F.stddev_samp(value).alias("std"), F.count("*").alias("folds"))


def recall_at(df: DataFrame, pct: float = 15, by: list[str] | None = None, pred: str = "pred", truth: str = "calc", direction: str = "asc", key: str = "structure_id") -> DataFrame:
    """Share of the true top ``pct`` percent that the predicted top holds; ties go to the smaller id."""
    by = by or []
    order = lambda c: Window.partitionBy(*by).orderBy(F.col(c).asc() if direction == "asc" else F.col(c).desc(), key)
    size = F.ceil(F.count("*").over(Window.partitionBy(*by)) * F.lit(pct / 100.0) - 1e-9)
    ranked = df.select("*", F.row_number().over(order(pred)).alias("_p"), F.row_number().over(order(truth)).alias("_t"), size.alias("_k"))
    return ranked.groupBy(*by).agg((F.count_if((F.col("_p") <= F.col("_k")) & (F.col("_t") <= F.col("_k"))) / F.max("_k")).alias("recall"), F.max("_k").alias("top"))


def recall_summary(recalls: DataFrame, by: list[str]) -> DataFrame:
    return recalls.groupBy(*by).agg(F.max("recall").alias("best"), F.avg("recall").alias("mean"), F.stddev_samp("recall").alias("std"))


def proxy_ranking(df: DataFrame, proxy: str, truth: str, pct: float = 15, by: list[str] | None = None) -> DataFrame:
    """Recall when a cheap energy stands for the costly one."""
    return recall_at(df, pct, by, proxy, truth)


def random_recall(pct: float) -> float:
    return pct / 100


def paired_gain(errors: DataFrame, base: DataFrame, by: list[str]) -> DataFrame:
    """Per fold difference to a baseline: mean, standard deviation and folds that improved."""
    joined = errors.select("fold", *by, F.col("error")).join(base.select("fold", "target", F.col("error").alias("_base")), ["fold", "target"])
    gain = F.col("_base") - F.col("error")
    return joined.groupBy(*by).agg(F.avg(gain).alias("gain"), F.stddev_samp(gain).alias("std"), F.count_if(gain > 0).alias("better"), F.count("*").alias("folds"))


def split_gap(errors: DataFrame, by: list[str]) -> DataFrame:
    """Test error less train error."""
    return errors.groupBy(*by).pivot("split", ["train", "test"]).agg(F.avg("error")).withColumn("gap", F.col("test") - F.col("train"))


def collision_rate(triplets: DataFrame) -> DataFrame:
    """Structures, different histograms, and the share of structures that share theirs."""
    rows = triplets.groupBy("structure_id").agg(F.sha2(F.to_json(F.sort_array(F.collect_list(F.struct("cell", "n")))), 256).alias("h"))
    groups = rows.groupBy("h").agg(F.count("*").alias("c"))
    return groups.agg(F.sum("c").alias("structures"), F.count("*").alias("histograms"), (F.sum(F.when(F.col("c") > 1, F.col("c")).otherwise(0)) / F.sum("c")).alias("collision_rate"))


def compare_histograms(a: DataFrame, b: DataFrame) -> DataFrame:
    """Per structure, atoms that fall in different bins of two histograms."""
    left, right = a.withColumnRenamed("n", "na"), b.withColumnRenamed("n", "nb")
    return left.join(right, ["structure_id", "cell"], "full").groupBy("structure_id").agg(F.sum(F.abs(F.coalesce("na", F.lit(0)) - F.coalesce("nb", F.lit(0)))).cast("bigint").alias("moved"))


def violin_bins(df: DataFrame, bins: int = 20, value: str = "value", by: list[str] | None = None) -> DataFrame:
    """Normalised histograms over the range that each group's values span together, with counts."""
    by = by or ["target"]
    span = Window.partitionBy(*by)
    lo, hi = F.min(value).over(span), F.max(value).over(span)
    cell = F.least(F.floor(F.try_divide(F.col(value) - lo, hi - lo) * bins), F.lit(bins - 1))
    binned = df.select(*by, "kind", F.coalesce(cell, F.lit(0)).cast("int").alias("bin"))
    counts = binned.groupBy(*by, "kind", "bin").agg(F.count("*").alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy(*by, "kind")))


def distribution_overlap(bins: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Common area of the calculated and predicted histograms, 0 to 1."""
    by = by or ["target"]
    wide = bins.groupBy(*by, "bin").pivot("kind", ["calc", "pred"]).agg(F.sum("share"))
    return wide.groupBy(*by).agg(F.sum(F.least(F.coalesce("calc", F.lit(0.0)), F.coalesce("pred", F.lit(0.0)))).alias("overlap"))


def sparsity(triplets: DataFrame, size: int) -> DataFrame:
    per = triplets.groupBy("structure_id").agg(F.count("*").alias("c"))
    return per.agg(F.count("*").alias("structures"), F.sum("c").alias("nonzeros"), F.avg("c").alias("per_structure"), (1 - F.sum("c") / (F.count("*") * F.lit(float(size)))).alias("zero_share"))


def regression_report(df: DataFrame, by: list[str]) -> DataFrame:
    """Mean absolute and root mean square error, R2 and Spearman's rank correlation."""
    w = Window.partitionBy(*by)
    ranked = df.select("*", F.rank().over(w.orderBy("pred")).alias("_rp"), F.rank().over(w.orderBy("calc")).alias("_rc"), F.avg("calc").over(w).alias("_mean"))
    return ranked.groupBy(*by).agg(
        F.avg(F.abs(F.col("pred") - F.col("calc"))).alias("mae"),
        F.sqrt(F.avg(F.pow(F.col("pred") - F.col("calc"), 2))).alias("rmse"),
        (1 - F.try_divide(F.sum(F.pow(F.col("pred") - F.col("calc"), 2)), F.sum(F.pow(F.col("calc") - F.col("_mean"), 2)))).alias("r2"),
        F.corr("_rp", "_rc").alias("spearman"),
    )


def funnel(df: DataFrame, stages: list[tuple[str, float]], key: str = "structure_id") -> DataFrame:
    """Keeps the lowest share of each stage's score in turn; cuts are exact, ties go to the smaller id.

    A cut that only needs the top is a sorted limit, never a sort of everything.
    """
    for score, pct in stages:
        n = df.count()
        k = int(-(-n * pct // 100)) if n else 0
        df = df.orderBy(F.col(score).asc(), key).limit(k)
    return df


def locality_report(pairs: DataFrame) -> DataFrame:
    """Correlation of the gap in index with the distance in space."""
    return pairs.agg(F.corr("index_gap", "distance").alias("correlation"), F.avg("index_gap").alias("mean_gap"), F.count("*").alias("pairs"))

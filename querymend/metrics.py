"""Measures over an ``outcomes`` table: method, level, truth_wrong, flagged,
refined_equals_gold, changed_result, ex. One aggregate each; empty
denominators give null."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def ratio(top: Column, bottom: Column) -> Column:
    return F.round(F.try_divide(top.cast("double"), bottom.cast("double")), 6)


def n(condition: Column) -> Column:
    return F.sum(F.when(condition, 1).otherwise(0)).cast("long")


def execution_accuracy(df: DataFrame, level: str = "level", ex: str = "ex", by: tuple[str, ...] = ("method",)) -> DataFrame:
    """Share of questions whose result equals gold's, by level and over all."""
    return df.groupingSets([[*map(F.col, by), F.col(level)], [*map(F.col, by)]], *by, level).agg(F.count("*").alias("questions"), ratio(n(F.col(ex)), F.count("*")).alias("ex"))


def detection_report(df: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """Confusion counts, precision, recall, accuracy and F1 of "is it wrong"."""
    w, f = F.col("truth_wrong"), F.col("flagged")
    c = df.groupBy(*by).agg(n(w & f).alias("tp"), n(~w & f).alias("fp"), n(w & ~f).alias("fn"), n(~w & ~f).alias("tn"))
    tp, fp, fn, tn = (F.col(x) for x in ("tp", "fp", "fn", "tn"))
    return c.select("*", ratio(tp, tp + fp).alias("precision"), ratio(tp, tp + fn).alias("recall"), ratio(tp + tn, tp + fp + fn + tn).alias("accuracy"), ratio(2 * tp, 2 * tp + fp + fn).alias("f1"))


def fixed_rate(df: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    hit = F.col("truth_wrong") & F.col("flagged")
    return df.groupBy(*by).agg(n(hit).alias("tp"), n(hit & F.col("refined_equals_gold")).alias("fixed")).withColumn("fixed_rate", ratio(F.col("fixed"), F.col("tp")))


def corruption_rate(df: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    hit = ~F.col("truth_wrong") & F.col("flagged")
    return df.groupBy(*by).agg(n(hit).alias("fp"), n(hit & F.col("changed_result")).alias("corrupted")).withColumn("corruption_rate", ratio(F.col("corrupted"), F.col("fp")))


def decompose_gain(df: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """The gain in execution accuracy two ways: (fixed - corrupted) / all, and
    the difference of the accuracies."""
    w, f = F.col("truth_wrong"), F.col("flagged")
    parts = df.groupBy(*by).agg(F.count("*").alias("questions"), n(w & f & F.col("refined_equals_gold")).alias("fixed"), n(~w & f & F.col("changed_result")).alias("corrupted"), n(F.col("ex")).alias("right_after"), n(~w).alias("right_before"))
    q = F.col("questions")
    return parts.select(*by, "questions", "fixed", "corrupted", ratio(F.col("fixed") - F.col("corrupted"), q).alias("gain_parts"), ratio(F.col("right_after") - F.col("right_before"), q).alias("gain_direct"))


def type_specific_accuracy(df: DataFrame, truth: str = "truth_types", found: str = "types", by: tuple[str, ...] = ()) -> DataFrame:
    """Share of the cases of each type whose detected set holds the type."""
    each = df.select(*by, F.explode(truth).alias("slot"), F.col(found).alias("found"))
    return each.groupBy(*by, "slot").agg(F.count("*").alias("cases"), ratio(n(F.array_contains("found", F.col("slot"))), F.count("*")).alias("tsa"))


def category_accuracy(df: DataFrame, category_of: dict[int, str], truth: str = "truth_types", found: str = "types", by: tuple[str, ...] = ("method",)) -> DataFrame:
    """The same by category: a case counts if a detected type falls into the
    category of the true one. The mapping has an entry for each type."""
    pairs = F.create_map(*[F.lit(x) for kv in category_of.items() for x in kv])
    named = F.transform(found, lambda s: pairs[s])
    each = df.select(*by, F.explode(F.array_distinct(F.transform(truth, lambda s: pairs[s]))).alias("category"), named.alias("found"))
    return each.groupBy(*by, "category").agg(F.count("*").alias("cases"), ratio(n(F.array_contains("found", F.col("category"))), F.count("*")).alias("tsa"))


def explicit_failure_share(df: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Share of wrong queries that fail when they are run."""
    return df.groupBy(*by).agg(n(F.col("truth_wrong")).alias("wrong"), n(F.col("truth_wrong") & F.col("failed")).alias("failing")).withColumn("share", ratio(F.col("failing"), F.col("wrong")))


def drop_correlation(df: DataFrame) -> DataFrame:
    return df.agg(F.round(F.corr("f1_drop", "ex_drop"), 6).alias("r"))

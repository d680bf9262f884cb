"""Churn models: how often a node changes in one execution, in millionths."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.portable import PPM
from ..sessions import STEPS, states

#: Candidates for profiling; the first three are the ones kept by default.
FEATURES = ("size", "length", "attr_len", "size_bucket", "digits", "upper", "spaces", "bars", "entropy", "var", "grp_hash", "age", "is_text", "id_hash")
KEPT = ("size", "length", "attr_len")


def constant_churn(ppm: int) -> Column:
    return F.lit(ppm).cast("long")


def collect_samples(base: DataFrame, steps: int = STEPS) -> DataFrame:
    """Every node before every step, labelled by whether the step changes it."""
    return states(base, steps).where("step > 0")


def features(rows: DataFrame) -> DataFrame:
    """rows (payload, size, kind, var, grp, node_key[, step, version]) with all candidate features."""
    p = F.col("payload")
    count = lambda chars: F.length(F.regexp_replace(p, f"[^{chars}]", ""))
    age = F.col("step") - F.col("version") if {"step", "version"} <= set(rows.columns) else F.lit(0)
    return rows.select(
        "*", F.length(p).alias("length"), F.size(F.split(p, "\\|")).alias("attr_len"), F.floor(F.log2("size")).cast("int").alias("size_bucket"), count("0-9").alias("digits"), count("A-Z").alias("upper"), count(" ").alias("spaces"),
        count("|").alias("bars"), F.size(F.array_distinct(F.split(p, ""))).alias("entropy"), F.pmod(F.xxhash64("grp"), F.lit(64)).cast("int").alias("grp_hash"), age.cast("int").alias("age"), (F.col("kind") == "text").cast("int").alias("is_text"), F.pmod(F.xxhash64("node_key"), F.lit(64)).cast("int").alias("id_hash"),
    )


def fit_bucket_churn(samples: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Smoothed empirical rate for each kind and size class: (changes + 1) / (exposures + 2) in ppm."""
    x = samples.withColumn("size_bucket", F.floor(F.log2("size")).cast("int")).withColumn("len_bucket", F.floor(F.log2(F.length("payload") + 1)).cast("int"))
    keys = ["kind", "size_bucket", "len_bucket", *by]
    return x.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), F.count_if("changed").alias("k")).select(*keys, F.expr(f"(k + 1) * {PPM} div (n + 2)").alias("churn_ppm"))


def apply_bucket_churn(rows: DataFrame, rates: DataFrame, default_ppm: int = 50_000) -> DataFrame:
    """churn_ppm by lookup; the table of rates has one row for each class, a few hundred at most."""
    x = rows.withColumn("size_bucket", F.floor(F.log2("size")).cast("int")).withColumn("len_bucket", F.floor(F.log2(F.length("payload") + 1)).cast("int"))
    return x.join(F.broadcast(rates), ["kind", "size_bucket", "len_bucket"], "left").withColumn("churn_ppm", F.coalesce("churn_ppm", F.lit(default_ppm).cast("long"))).drop("size_bucket", "len_bucket")


def _fit(samples: DataFrame, names, max_samples: int, trees: int, depth: int):
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import GBTRegressor

    rows = features(samples)
    n = rows.count()
    # A hash sample of at most about max_samples rows: the bound of the fit.
    if n > max_samples:
        rows = rows.where(F.pmod(F.xxhash64("node_key", "step"), F.lit(1_000_000)) < int(1_000_000 * max_samples / n))
    x = VectorAssembler(inputCols=list(names), outputCol="x").transform(rows.withColumn("y", F.col("changed").cast("double")).select(*names, "y"))
    return GBTRegressor(featuresCol="x", labelCol="y", maxIter=trees, maxDepth=depth, stepSize=0.3, seed=7).fit(x)


def _tree_column(node, names) -> Column:
    if node.numDescendants() == 0:
        return F.lit(float(node.prediction()))
    split = node.split()
    return F.when(F.col(names[split.featureIndex()]) <= float(split.threshold()), _tree_column(node.leftChild(), names)).otherwise(_tree_column(node.rightChild(), names))


def fit_gbt_churn(samples: DataFrame, names=KEPT, max_samples: int = 200_000, trees: int = 20, depth: int = 4) -> Column:
    """Boosted trees on the kept features, exported to one CASE expression so that scoring stays in generated code."""
    model = _fit(samples, names, max_samples, trees, depth)
    total = F.lit(0.0)
    for tree, weight in zip(model.trees, model.treeWeights, strict=True):
        total = total + F.lit(float(weight)) * _tree_column(tree._call_java("rootNode"), list(names))
    return (F.greatest(F.lit(0.0), F.least(F.lit(1.0), total)) * PPM).cast("long")


def profile_features(samples: DataFrame, max_samples: int = 200_000, keep: int = 3) -> DataFrame:
    """(feature, gain, kept) of all candidates, by their importance in one fit."""
    model = _fit(samples, FEATURES, max_samples, 5, 4)
    gain = model.featureImportances.toArray().tolist()
    best = sorted(range(len(FEATURES)), key=lambda i: (-gain[i], i))[:keep]
    return samples.sparkSession.createDataFrame([(f, round(g, 6), i in best) for i, (f, g) in enumerate(zip(FEATURES, gain, strict=True))], "feature string, gain double, kept boolean")

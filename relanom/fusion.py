"""Post-hoc fusion: rules join after the graph model has scored, for comparison with injection."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relanom.rules import RuleSet, satisfied


def weighted_sum(rows: DataFrame, rule_set: RuleSet) -> DataFrame:
    """Score scaled to [0, 1] plus the mean of the satisfied rules' confidences."""
    span = rows.agg(F.min("score").alias("_low"), F.max("score").alias("_high"))
    mean = sum((F.when(satisfied(t), F.lit(float(c))).otherwise(0.0) for t, c in zip(rule_set.texts, rule_set.confidences)), F.lit(0.0)) / max(1, len(rule_set.texts))
    scaled = F.coalesce(F.try_divide(F.col("score") - F.col("_low"), F.col("_high") - F.col("_low")), F.lit(0.0))
    return rows.join(F.broadcast(span)).withColumn("score", scaled + mean).drop("_low", "_high")


def logistic(valid: DataFrame, rows: DataFrame, rule_set: RuleSet) -> DataFrame:
    """Logistic regression on score and rule bits, fitted on the validation split."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector, vector_to_array

    features = lambda df: df.withColumn("features", array_to_vector(F.concat(F.array(F.col("score").cast("double")), rule_set.vector())))
    model = LogisticRegression(labelCol="y", regParam=0.01).fit(features(valid).withColumn("y", F.col("y").cast("double")))
    out = model.transform(features(rows))
    return out.withColumn("score", vector_to_array("probability")[1]).drop("features", "rawPrediction", "probability", "prediction")

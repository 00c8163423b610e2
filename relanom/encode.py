"""Feature encoding fitted on train rows only: coercion, imputation, vocabularies, scaling."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def coerce(df: DataFrame, columns: list[str]) -> DataFrame:
    return df.withColumns({c: F.expr(f"try_cast(`{c}` AS double)") for c in columns})


def admissible(columns: list[str], forbidden: set[str]) -> list[str]:
    """Feature columns without ids, times, labels and what lies in the future."""
    return [c for c in columns if c not in forbidden]


def imputer(train: DataFrame, columns: list[str], how: str = "median") -> dict[str, float]:
    agg = (lambda c: F.median(c)) if how == "median" else (lambda c: F.avg(c))
    row = train.agg(*[agg(c).alias(c) for c in columns]).first()
    return {c: float(row[c]) if row[c] is not None else 0.0 for c in columns}


def impute(df: DataFrame, values: dict[str, float]) -> DataFrame:
    return df.withColumns({c: F.coalesce(F.nanvl(F.col(c).cast("double"), F.lit(None)), F.lit(v)) for c, v in values.items()})


def vocabulary(train: DataFrame, column: str) -> DataFrame:
    """(value, code), codes by falling frequency."""
    counts = train.groupBy(F.col(column).alias("value")).agg(F.count("*").alias("n"))
    return counts.select("value", (F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.col("n").desc(), "value")) - 1).cast("long").alias("code"))


def index(df: DataFrame, column: str, vocab: DataFrame) -> DataFrame:
    """Code of each value; a value unseen in training has code -1."""
    v = vocab.withColumnRenamed("value", "_value").withColumnRenamed("code", f"{column}_code")
    return df.join(v, df[column] == v["_value"], "left").drop("_value").withColumn(f"{column}_code", F.coalesce(f"{column}_code", F.lit(-1)))


def scaler(train: DataFrame, columns: list[str]) -> dict[str, tuple[float, float]]:
    row = train.agg(*[F.avg(c).alias(f"m_{c}") for c in columns], *[F.stddev_pop(c).alias(f"s_{c}") for c in columns]).first()
    return {c: (float(row[f"m_{c}"] or 0), float(row[f"s_{c}"] or 0) or 1.0) for c in columns}


def standardize(df: DataFrame, scale: dict[str, tuple[float, float]]) -> DataFrame:
    return df.withColumns({c: (F.col(c).cast("double") - m) / s for c, (m, s) in scale.items()})


def profile(df: DataFrame, columns: list[str]) -> DataFrame:
    """One row per feature: min, max, mean, distinct values, share of nulls; one pass over the data."""
    parts = [F.struct(F.lit(c).alias("feature"), F.min(F.col(c).cast("double")).alias("low"), F.max(F.col(c).cast("double")).alias("high"), F.avg(F.col(c).cast("double")).alias("mean"), F.count_distinct(c).alias("distinct_values"), F.avg(F.col(c).isNull().cast("int")).alias("null_share")).alias(f"p{i}") for i, c in enumerate(columns)]
    return df.agg(*parts).select(F.explode(F.array(*[f"p{i}" for i in range(len(columns))])).alias("p")).select("p.*")


def assemble(df: DataFrame, columns: list[str], name: str = "x") -> DataFrame:
    """The columns as one array of doubles."""
    return df.withColumn(name, F.array(*(F.col(c).cast("double") for c in columns)))

"""A small trained scorer in place of a small language model: logistic regression over hashed words."""

from __future__ import annotations

from pyspark.ml import Pipeline
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import HashingTF, RegexTokenizer
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import ModelBackend, null_safe


class LinearModel(ModelBackend):
    """Trained on the rows of a labelled slice; gives a log-probability-like score for one text column."""

    def __init__(self, labelled: DataFrame, text: str, label: str, features: int = 1 << 12, rounds: int = 30) -> None:
        self.column, self.model_id = text, "linear"
        stages = [
            RegexTokenizer(inputCol="_t", outputCol="_w", pattern=r"\W+"),
            HashingTF(inputCol="_w", outputCol="_x", numFeatures=features, binary=True),
            LogisticRegression(featuresCol="_x", labelCol="_y", regParam=0.01, maxIter=rounds, probabilityCol="_p", rawPredictionCol="_r", predictionCol="_c"),
        ]
        rows = labelled.select(F.coalesce(text, F.lit("")).alias("_t"), F.col(label).cast("double").alias("_y")).filter("_y IS NOT NULL")
        self.model = Pipeline(stages=stages).fit(rows)

    def score(self, df, template, out="score"):
        scored = self.model.transform(df.withColumn("_t", F.coalesce(self.column, F.lit(""))))
        kept = scored.withColumn(out, vector_to_array("_p")[1]).drop("_t", "_w", "_x", "_p", "_r", "_c")
        return null_safe(kept, template, F.col(out), out)

    def label(self, df, template, out="label"):
        return self.score(df, template, "_s").withColumn(out, F.col("_s") >= 0.5).drop("_s")

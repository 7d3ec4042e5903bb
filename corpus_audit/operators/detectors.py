"""Stand-in detectors: linear models with the training variants (equal and class weights, sampling, cross-corpus)."""

from __future__ import annotations

from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import HashingTF
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import bucket, tokens
from .metrics import confusion, miss_rate_at_fpr, rates
from .pairwise import attach, pair_outcomes

WEIGHTS = (1.0, 5.0, 20.0, 30.0, 40.0)  # fixed values
LEARNING_RATE = 2e-5  # fixed value
EPOCHS = {"below 7B": 10, "7B": 4, "closed": 1}  # fixed values


def text_features(df: DataFrame, text: str = "text", width: int = 1 << 12) -> DataFrame:
    """features: hashed word counts."""
    words = df.withColumn("_words", tokens(F.lower(F.coalesce(text, F.lit("")))))
    return HashingTF(inputCol="_words", outputCol="features", numFeatures=width).transform(words).drop("_words")


def vector_features(df: DataFrame, vector: str = "embedding") -> DataFrame:
    return df.withColumn("features", array_to_vector(F.transform(vector, lambda x: x.cast("double"))))


def class_weight(label: Column, weight: float) -> Column:
    return F.when(label == 1, F.lit(float(weight))).otherwise(F.lit(1.0))


def fit_classifier(train: DataFrame, weight: float = 1.0, epochs: int = 20, shrink: float = 0.001):
    """Logistic regression on features and label; weight is the class weight of flawed samples."""
    weighted = train.withColumn("_w", class_weight(F.col("label"), weight)).withColumn("label", F.col("label").cast("double"))
    return LogisticRegression(maxIter=epochs, regParam=shrink, weightCol="_w", featuresCol="features", labelCol="label").fit(weighted.select("features", "label", "_w"))


def predict(model, df: DataFrame, threshold: float = 0.5) -> DataFrame:
    """df with score and pred."""
    scored = model.transform(df.drop("label")).select("sample_id", vector_to_array("probability")[1].alias("score"))
    return df.drop("features").join(scored, "sample_id").withColumn("pred", (F.col("score") >= threshold).cast("int"))


def predict_each(models: list, df: DataFrame) -> DataFrame:
    """df without features, with scores: those of all models in their order, from one reading of the features."""
    scored, columns = df, [c for c in df.columns if c != "features"]
    for i, model in enumerate(models):
        scored = model.copy().setPredictionCol("").setRawPredictionCol("").setProbabilityCol(f"_probability_{i}").transform(scored)
    return scored.select(*columns, F.array(*[vector_to_array(f"_probability_{i}")[1] for i in range(len(models))]).alias("scores"))


def predicted_by(scores: DataFrame, i: int, threshold: float = 0.5) -> DataFrame:
    """Rows of ``predict_each`` with score and pred of the i-th model."""
    return scores.withColumn("score", F.col("scores")[i]).withColumn("pred", (F.col("score") >= threshold).cast("int")).drop("scores")


def weighted_loss(df: DataFrame, weight: float, norm: str = "mean") -> DataFrame:
    """loss: class-weighted cross entropy of score against label; weight 1 is the plain loss."""
    q = F.least(F.greatest(F.col("score"), F.lit(1e-12)), F.lit(1 - 1e-12))
    y = F.col("label")
    each = -(F.lit(float(weight)) * y * F.ln(q) + (1 - y) * F.ln(1 - q))
    divisor = F.count(F.lit(1)) if norm == "mean" else F.sum(class_weight(y, weight))
    return df.agg(F.lit(float(weight)).alias("weight"), F.round(F.sum(each) / divisor, 6).alias("loss"))


def evaluate(predicted: DataFrame, name: str, setting: str) -> DataFrame:
    """Long form (run, setting, metric, value) of accuracy, f1, recall, fpr and the capped miss rate."""
    measured = rates(confusion(predicted)).crossJoin(miss_rate_at_fpr(predicted).select(F.col("fnr").alias("capped_miss")))
    return measured.select(F.lit(name).alias("run"), F.lit(setting).alias("setting"), F.expr("stack(5, 'accuracy', accuracy, 'f1', f1, 'recall', recall, 'fpr', fpr, 'capped_miss', capped_miss) AS (metric, value)"))


def evaluate_pairs(pairs: DataFrame, predicted: DataFrame, name: str, setting: str) -> DataFrame:
    """Long form of the four pair outcomes in percent and the numbers of pairs with and without both predictions."""
    measured = pair_outcomes(attach(pairs, predicted))
    return measured.select(F.lit(name).alias("run"), F.lit(setting).alias("setting"), F.expr("stack(6, 'p_c', p_c, 'p_v', p_v, 'p_b', p_b, 'p_r', p_r, 'n_pairs', double(n_pairs), 'n_missing', double(n_missing)) AS (metric, value)"))


def epochs_for(size: str) -> int:
    """Passes over the training data that the size class of a model takes."""
    return EPOCHS[size]


def sweep_class_weights(train: DataFrame, test: DataFrame, weights: tuple[float, ...] = WEIGHTS) -> DataFrame:
    out = None
    for w in weights:
        rows = evaluate(predict(fit_classifier(train, w), test), "class weight", str(int(w)))
        out = rows if out is None else out.unionByName(rows)
    return out


def cross_eval(corpora: dict[str, tuple[DataFrame, DataFrame]], weight: float = 1.0) -> DataFrame:
    """Fit on the train part of each corpus, measure on the test part of every one."""
    out = None
    for fitted, (train, _) in corpora.items():
        model = fit_classifier(train, weight)
        for tested, (_, test) in corpora.items():
            rows = evaluate(predict(model, test), fitted, tested)
            out = rows if out is None else out.unionByName(rows)
    return out


def holdout(df: DataFrame, seed: str = "h", key: str = "sample_id") -> tuple[DataFrame, DataFrame]:
    """80 / 20 by hash."""
    b = bucket(F.col(key), seed)
    return df.where(b < 8_000), df.where(b >= 8_000)

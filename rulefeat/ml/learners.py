"""Learners for generated features: Spark's own, with the settings that the experiments need."""

from __future__ import annotations

from pyspark.ml.classification import LogisticRegression, MultilayerPerceptronClassifier, RandomForestClassifier
from pyspark.ml.functions import vector_to_array
from pyspark.ml.regression import RandomForestRegressor
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import evaluate


def logistic(n: int, penalty: float = 1.0, l1: bool = True) -> LogisticRegression:
    """Penalty `penalty` on the summed loss: MLlib averages over the n rows, hence the division."""
    return LogisticRegression(labelCol="label", elasticNetParam=1.0 if l1 else 0.0, regParam=penalty / max(n, 1), maxIter=60, family="multinomial")


class EarlyStoppingPerceptron:
    """Two hidden layers of 30; short warm-started fits go on while the log-loss on a held-out part falls."""

    def __init__(self, hidden=(30, 30), burst: int = 15, bursts: int = 8, patience: int = 2, seed: int = 7):
        self.hidden, self.burst, self.bursts, self.patience, self.seed = hidden, burst, bursts, patience, seed

    def fit(self, train: DataFrame, held: DataFrame | None = None):
        if held is None:
            train, held = train.randomSplit([0.85, 0.15], self.seed)
        width, classes = len(train.select("features").first()[0]), int(train.agg(F.max("label")).first()[0]) + 1
        best, best_loss, weights, waited = None, float("inf"), None, 0
        for _ in range(self.bursts):
            fitter = MultilayerPerceptronClassifier(labelCol="label", layers=[width, *self.hidden, max(2, classes)], maxIter=self.burst, seed=self.seed, blockSize=128)
            if weights is not None:
                fitter.setInitialWeights(weights)
            model = fitter.fit(train)
            weights = model.weights
            loss = scores(model.transform(held), None)["log_loss"]
            if loss < best_loss - 1e-4:
                best, best_loss, waited = model, loss, 0
            else:
                waited += 1
                if waited >= self.patience:
                    break
        return best or model


def forest(task: str = "classification", trees: int = 50, seed: int = 7):
    return (RandomForestClassifier if task == "classification" else RandomForestRegressor)(labelCol="label", numTrees=trees, maxDepth=8, seed=seed)


def scores(predicted: DataFrame, binary_auc: bool | None = None) -> dict[str, float]:
    """log_loss and accuracy of classifier output, and both AUCs for binary labels; one aggregate for the first two."""
    p = F.get(vector_to_array("probability"), F.col("label").cast("int"))
    row = predicted.agg(evaluate.log_loss(F.coalesce(p, F.lit(0.0))).alias("log_loss"), evaluate.accuracy("label", "prediction").alias("accuracy")).first()
    out = {"log_loss": row["log_loss"], "accuracy": row["accuracy"]}
    if binary_auc:
        ranked = predicted.select("label", "prediction", vector_to_array("probability")[1].alias("s"))
        out["auc"] = evaluate.auc(ranked, "label", "s").first()[0]
        out["auc_hard"] = evaluate.auc_hard(ranked, "label", "prediction").first()[0]
    return out

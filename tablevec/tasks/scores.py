"""Training of all trials at once, and what is measured on them."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tablevec.tasks import nets

SCORES = "task string, method string, trial int, metric string, value double"
PREDICTIONS = "method string, trial int, item string, label string, pred string"


def predict(samples: DataFrame, kind: str, settings: nets.Settings | None = None) -> DataFrame:
    """(method, trial, item, label, pred) of the test rows; one network for each method and trial, side by side.

    samples: method, trial, split, item, features, label. A trial is a bounded sample, so it fits in one task.
    """
    chosen = settings or {"binary": nets.BINARY, "categories": nets.CATEGORIES, "regression": nets.REGRESSION, "link": nets.LINK}[kind]

    def work(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("item")
        fit, test = rows[rows["split"] == "train"], rows[rows["split"] == "test"]
        if not len(fit) or not len(test):
            return pd.DataFrame(columns=["method", "trial", "item", "label", "pred"])
        x, z = np.array(fit["features"].tolist(), dtype=float), np.array(test["features"].tolist(), dtype=float)
        names = sorted(fit["label"].unique())
        if kind == "regression":
            y = fit["label"].astype(float).to_numpy()
            scale = max(float(np.abs(y - np.median(y)).mean()), 1e-9)
            got = nets.train(kind, x, (y - np.median(y)) / scale, chosen).output(z)[:, 0] * scale + np.median(y)
            out = [repr(float(v)) for v in got]
        elif kind == "categories":
            index = {n: i for i, n in enumerate(names)}
            out = [names[i] for i in nets.train(kind, x, fit["label"].map(index).to_numpy(), chosen, len(names)).output(z).argmax(axis=1)]
        else:
            got = nets.train(kind, x, (fit["label"] == names[-1]).to_numpy(float), chosen).output(z)[:, 0]
            out = [names[-1] if v >= 0.5 else names[0] for v in got]
        return pd.DataFrame({"method": test["method"], "trial": test["trial"], "item": test["item"], "label": test["label"], "pred": out})

    rows = samples.select("method", F.col("trial").cast("int").alias("trial"), "split", F.col("item").cast("string").alias("item"), "features", F.col("label").cast("string").alias("label"))
    return rows.groupBy("method", "trial").applyInPandas(work, PREDICTIONS)


def accuracy(predictions: DataFrame, task: str) -> DataFrame:
    return predictions.groupBy("method", "trial").agg(F.avg((F.col("pred") == F.col("label")).cast("double")).alias("value")).select(F.lit(task).alias("task"), "method", "trial", F.lit("accuracy").alias("metric"), "value")


def mean_abs_error(predictions: DataFrame, task: str) -> DataFrame:
    gap = F.abs(F.col("pred").cast("double") - F.col("label").cast("double"))
    return predictions.groupBy("method", "trial").agg(F.avg(gap).alias("value")).select(F.lit(task).alias("task"), "method", "trial", F.lit("mae").alias("metric"), "value")


def score_spread(scores: DataFrame) -> DataFrame:
    """Least, quartiles, greatest, mean and deviation of each task, method and metric over its trials."""
    q = lambda p: F.percentile("value", p)
    return scores.groupBy("task", "method", "metric").agg(F.count(F.lit(1)).alias("n"), F.min("value").alias("low"), q(0.25).alias("q1"), q(0.5).alias("median"), q(0.75).alias("q3"), F.max("value").alias("high"), F.avg("value").alias("mean"), F.coalesce(F.stddev_samp("value"), F.lit(0.0)).alias("sd"))


def impute_mode(rows: DataFrame, label: str) -> DataFrame:
    """(trial, pred): the most frequent label of each trial's training rows, the smallest of equals."""
    counts = rows.where("split = 'train'").groupBy("trial", label).agg(F.count(F.lit(1)).alias("_n"))
    order = Window.partitionBy("trial").orderBy(F.desc("_n"), label)
    return counts.withColumn("_r", F.row_number().over(order)).where("_r = 1").select("trial", F.col(label).alias("pred"))


def impute_ngram(rows: DataFrame, text: str, label: str, encoder: str = "linear", features: int = 1 << 14, sizes: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """Predictions from character n-grams of the text columns of one table.

    'linear' (the default) is multinomial logistic regression on hashed counts; 'recurrent' a small recurrent network on
    characters, since no deep-learning library is at hand.
    """
    if encoder == "recurrent":

        def work(part: pd.DataFrame) -> pd.DataFrame:
            fit, test = part[part["split"] == "train"].sort_values("item"), part[part["split"] == "test"].sort_values("item")
            names = sorted(fit["label"].unique())
            y = fit["label"].map({n: i for i, n in enumerate(names)}).to_numpy()
            got = nets.Recurrent(len(names)).fit(fit["text"].tolist(), y).predict(test["text"].tolist())
            return pd.DataFrame({"method": "ngram_recurrent", "trial": test["trial"], "item": test["item"], "label": test["label"], "pred": [names[i] for i in got]})

        few = rows.select(F.col("trial").cast("int").alias("trial"), "split", F.col("item").cast("string").alias("item"), F.col(text).alias("text"), F.col(label).cast("string").alias("label"))
        return few.groupBy("trial").applyInPandas(work, PREDICTIONS)
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF, StringIndexer

    lower = F.lower(F.col(text))

    def runs(n: int):
        """All runs of n characters; the function's one parameter is the place, as transform asks."""
        return F.transform(F.sequence(F.lit(1), F.greatest(F.length(text) - n + 1, F.lit(1))), lambda i: F.substr(lower, i, F.lit(n)))

    grams = F.flatten(F.array(*map(runs, sizes)))
    own = rows.select(F.col("trial").cast("int").alias("trial"), "split", F.col("item").cast("string").alias("item"), F.col(label).cast("string").alias("label"), grams.alias("grams"))
    counted = HashingTF(numFeatures=features, inputCol="grams", outputCol="features").transform(own).drop("grams")
    out = None
    for k in [r["trial"] for r in own.select("trial").distinct().orderBy("trial").collect()]:  # the trials asked for
        part = counted.where(F.col("trial") == k)
        names = StringIndexer(inputCol="label", outputCol="y", stringOrderType="alphabetAsc", handleInvalid="keep").fit(part.where("split = 'train'"))
        model = LogisticRegression(labelCol="y", maxIter=15, regParam=1e-4).fit(names.transform(part.where("split = 'train'")))
        labels = F.array(*map(F.lit, names.labels))
        got = model.transform(part.where("split = 'test'")).select(F.lit("ngram").alias("method"), "trial", "item", "label", F.element_at(labels, (F.col("prediction") + 1).cast("int")).alias("pred"))
        out = got if out is None else out.union(got)
    return out


def probe(samples: DataFrame, kind: str = "categories") -> DataFrame:
    """Predictions by a linear model on the vectors, for each method and trial that the samples hold."""

    def work(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("item")
        fit, test = rows[rows["split"] == "train"], rows[rows["split"] == "test"]
        add = lambda v: np.column_stack([np.array(v.tolist(), dtype=float), np.ones(len(v))])
        x, z = add(fit["features"]), add(test["features"])
        left = x.T @ x + 1e-2 * np.eye(x.shape[1])
        if kind == "regression":
            out = [repr(float(v)) for v in z @ np.linalg.solve(left, x.T @ fit["label"].astype(float).to_numpy())]
        else:
            names = sorted(fit["label"].unique())
            y = np.array([[float(v == n) for n in names] for v in fit["label"]])
            out = [names[i] for i in (z @ np.linalg.solve(left, x.T @ y)).argmax(axis=1)]
        return pd.DataFrame({"method": test["method"] + "_linear", "trial": test["trial"], "item": test["item"], "label": test["label"], "pred": out})

    rows = samples.select("method", F.col("trial").cast("int").alias("trial"), "split", F.col("item").cast("string").alias("item"), "features", F.col("label").cast("string").alias("label"))
    return rows.groupBy("method", "trial").applyInPandas(work, PREDICTIONS)


def timed(f: Callable[[], DataFrame], repeats: int) -> list[float]:
    """Seconds of each run, written to nowhere."""
    import time

    out = []
    for _ in range(repeats):
        start = time.monotonic()
        f().write.format("noop").mode("overwrite").save()
        out.append(time.monotonic() - start)
    return out


def class_balance(rows: DataFrame, label: str) -> DataFrame:
    total = rows.count()
    return rows.groupBy(label).agg(F.count(F.lit(1)).alias("n")).withColumn("share", F.col("n") / F.lit(float(max(total, 1))))


def work_counters(links: DataFrame) -> DataFrame:
    """(rel, rel_inv, n_links, n_nonlinks): links that a sweep reads, and non-links that it does not have to."""
    from tablevec.operators.weights import group_sizes

    return group_sizes(links).select("rel", "rel_inv", "n_links", (F.col("n_src") * F.col("n_dst") - F.col("n_links")).alias("n_nonlinks"))


def oov_report(base: DataFrame, hits: DataFrame) -> DataFrame:
    """(category, n, n_oov, hits_per_value)."""
    counts = hits.groupBy("node_id").agg(F.count(F.lit(1)).alias("_h"))
    return base.join(counts, "node_id", "left").groupBy("category").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("is_oov").cast("long")).alias("n_oov"), F.avg(F.coalesce("_h", F.lit(0))).alias("hits_per_value"))


def train_distributed(rows: DataFrame, n_classes: int, hidden: tuple[int, ...] = (64,), rounds: int = 60, seed: int = 1):
    """Spark's own perceptron on (features, label index) for training sets that no task can hold; the fitted model."""
    from pyspark.ml.classification import MultilayerPerceptronClassifier
    from pyspark.ml.functions import array_to_vector

    width = rows.select(F.size("features")).first()[0]
    shaped = rows.select(array_to_vector("features").alias("features"), F.col("label").cast("double").alias("label"))
    return MultilayerPerceptronClassifier(layers=[width, *hidden, n_classes], maxIter=rounds, seed=seed).fit(shaped)


__all__ = ["predict", "accuracy", "mean_abs_error", "score_spread", "impute_mode", "impute_ngram", "probe", "timed", "class_balance", "work_counters", "oov_report", "train_distributed", "SCORES"]

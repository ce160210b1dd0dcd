"""Linear support vector machines over feature vectors, and repeated cross-validation."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.ml.classification import LinearSVC, OneVsRest
from pyspark.ml.feature import StringIndexer
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def linear_svm(train: DataFrame, test: DataFrame, reg: float = 0.01, max_iter: int = 15) -> DataFrame:
    """Predictions for test: seq_id, label, prediction (label names). One classifier against the rest for each class."""
    index = StringIndexer(inputCol="label", outputCol="y", handleInvalid="keep", stringOrderType="alphabetAsc").fit(train)
    model = OneVsRest(classifier=LinearSVC(regParam=reg, maxIter=max_iter), parallelism=8, labelCol="y", featuresCol="features").fit(index.transform(train).where(F.col("y") < len(index.labels)))
    names = F.array(*[F.lit(x) for x in index.labels])
    return model.transform(index.transform(test)).select("seq_id", "label", F.get(names, F.col("prediction").cast("int")).alias("prediction"))


def accuracy(predictions: DataFrame) -> DataFrame:
    return predictions.agg((100 * F.avg((F.col("label") == F.col("prediction")).cast("double"))).alias("accuracy"))


def fold_of(folds: int, rep: int, seed: int):
    return F.pmod(F.xxhash64(F.col("seq_id"), F.lit(rep), F.lit(seed)), F.lit(folds))


def repeated_cv(features_of: Callable[[DataFrame], DataFrame], labels: DataFrame, folds: int = 10, reps: int = 20, seed: int = 42) -> list[tuple[int, float]]:
    """(repetition, accuracy in percent). features_of(training labels) -> (seq_id, label, features) of all sequences, so that
    patterns come from training folds only."""
    return repeated_cv_of(lambda train: {"": lambda: features_of(train)}, labels, folds, reps, seed).get("", [(rep, 0.0) for rep in range(reps)])


def repeated_cv_of(features_of: Callable[[DataFrame], dict[str, Callable[[], DataFrame]]], labels: DataFrame, folds: int = 10, reps: int = 20, seed: int = 42, together: int = 4) -> dict[str, list[tuple[int, float]]]:
    """The same for several sources of features over the same folds: features_of gives a maker of features for each. Folds are
    independent; `together` of them run at the same time, since their jobs are mostly small."""

    def one(rep: int, fold: int) -> dict[str, tuple[int, int]]:
        marked = labels.withColumn("fold", fold_of(folds, rep, seed))
        out = {}
        for source, make in features_of(marked.where(F.col("fold") != fold).select("seq_id", "label")).items():
            rows = make().withColumn("fold", fold_of(folds, rep, seed)).persist()
            got = linear_svm(rows.where(F.col("fold") != fold), rows.where(F.col("fold") == fold))
            r = got.agg(F.sum((F.col("label") == F.col("prediction")).cast("int")), F.count(F.lit(1))).first()
            out[source] = r[0] or 0, r[1]
            rows.unpersist()
        return out

    with ThreadPoolExecutor(together) as pool:
        done = [[pool.submit(one, rep, fold) for fold in range(folds)] for rep in range(reps)]
        try:
            rows = [[x.result() for x in some] for some in done]
        except BaseException:
            pool.shutdown(cancel_futures=True)
            raise
    return {source: [(rep, 100.0 * sum(x[source][0] for x in some) / max(sum(x[source][1] for x in some), 1)) for rep, some in enumerate(rows)] for source in (rows[0][0] if rows and rows[0] else ())}

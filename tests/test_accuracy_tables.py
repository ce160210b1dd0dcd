"""Registered accuracy tables do the whole job."""

from __future__ import annotations

import inspect

from fixgap.operators import classify
from fixgap.plans import paper, workloads


def test_accuracy_tables_repeat_all_folds_for_all_sources(spark, small, monkeypatch):
    """They ran one repetition of two folds, for three of five sources, and gap coding ended after 16 joins without gain."""
    seen = []
    monkeypatch.setattr(classify, "repeated_cv_of", lambda make, labels, folds, reps: seen.append((folds, reps, set(make(labels)))) or {})
    for name in ("embeddings", "convlab"):
        paper.Q[f"tab_accuracy_{name}"](spark, small).collect()
    assert seen == [(10, 20, {"fixed_gap", "order_only", "singletons", "gap_coding", "dependency_test"})] * 2
    assert inspect.signature(workloads.accuracy).parameters["patience"].default is None


def test_sources_share_their_folds(spark):
    """Chosen episodes of a training fold serve two sources; results are those of one source at a time."""
    from pyspark.ml.linalg import Vectors

    rows = [(i, "ab"[i % 2], Vectors.dense([float(i % 2), float(i % 3)])) for i in range(40)]
    vec = spark.createDataFrame(rows, ["seq_id", "label", "features"])
    lab = vec.select("seq_id", "label")
    got = classify.repeated_cv_of(lambda train: {"x": lambda: vec, "y": lambda: vec}, lab, folds=2, reps=1)
    assert got == {"x": [(0, 100.0)], "y": [(0, 100.0)]}
    assert classify.repeated_cv(lambda train: vec, lab, folds=2, reps=1) == got["x"]

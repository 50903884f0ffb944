"""A fairness-aware variant: the plain model plus a penalty on the covariance of scores and a sensitive value.

This is not an adversarially trained model; it serves audits as the fairer of two models.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from ..operators.graph import AnchoredGraph
from .train import Gcn, Sample, fit_gcn, sample


def fair_gcn(graph: AnchoredGraph, sensitive: DataFrame, strength: float = 50.0, s: Sample | None = None, **how) -> Gcn:
    """``sensitive``: ``node_id`` of the nodes that hold the sensitive value; ``s`` is a sample already made."""
    s = sample(graph) if s is None else s
    t = sensitive.select("node_id").join(graph.nodes.sparkSession.createDataFrame([(int(i),) for i in s.ids], "node_id long"), "node_id", "left_semi").toArrow()
    return fit_gcn(s, sensitive=np.isin(s.ids, t.column(0).to_numpy()).astype(float), strength=strength, **how)

"""Queries of the caps read the vectors; they once made their rows up."""

import pytest

from lookalike.plans import method_queries  # noqa: F401
from lookalike.plans.registry import QUERIES


@pytest.mark.parametrize("name", ["cap_fraction", "cap_overlap"])
def test_caps_read_embeddings(spark, sf, name):
    assert any("embeddings.parquet" in f for f in QUERIES[name](spark, sf).inputFiles())

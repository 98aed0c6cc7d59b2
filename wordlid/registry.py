"""All queries of the engine's own operators, and their SQL."""

from __future__ import annotations

import importlib

from wordlid.plans import workloads

QUERIES: dict = dict(workloads.Q)
ORACLE: dict = dict(workloads.S)
for _module in ("relational", "streams", "models"):
    _found = importlib.import_module(f"wordlid.plans.{_module}")
    QUERIES |= _found.Q
    ORACLE |= _found.S


def flagship(spark, sf_dir):
    """Per-tag scores of naive Bayes on character n-grams, from raw comments to the measure."""
    return workloads.scores(spark, sf_dir, "b4")

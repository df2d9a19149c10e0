"""Every query of the engine beside its SQL; each module registers its own."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from slicecode.plans import base
from slicecode.plans import data, evaluation, formats, model_queries, surface, codes  # noqa: F401  they register themselves
from slicecode.plans.evaluation import flagship  # noqa: F401


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(base.QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(base.SQL)

"""Fitted models kept for a session, as a user would keep them in tables."""

from __future__ import annotations

from collections.abc import Callable, Hashable

from pyspark.sql import SparkSession

_models: dict = {}


def kept(spark: SparkSession, key: tuple[Hashable, ...], make: Callable):
    """What make() gave the first time for this key in this application."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _models:
        _models[key] = make()
    return _models[key]


def kept_all(spark: SparkSession, keys: list[tuple[Hashable, ...]], make: Callable) -> list:
    """As `kept` for several keys; make(places) gives what is missing, by place in `keys`, in one go."""
    own = [(spark.sparkContext.applicationId, *key) for key in keys]
    missing = [i for i, key in enumerate(own) if key not in _models]
    if missing:
        _models.update(zip([own[i] for i in missing], make(missing), strict=True))
    return [_models[key] for key in own]

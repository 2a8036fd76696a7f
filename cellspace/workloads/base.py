"""Registry of queries with their SQL, and indexes kept for the session."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from cellspace.functions.spaces import SPACES, FeatureSpace
from cellspace.operators.grid import LayeredGrid, build_layered_grid
from cellspace.operators.kdtree import KdTree, build_kdtree
from cellspace.plans.shared import spread, staged

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
_KEPT: dict[tuple, object] = {}


def query(name: str, oracle: str | None = None):
    def add(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def kept(spark: SparkSession, sf_dir: str, what: tuple, make: Callable):
    """An index is built once for a session and a folder; its files lie in the shared folder."""
    key = (spark.sparkContext.applicationId, sf_dir, *what)
    if key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT[key]


def space_rows(spark: SparkSession, sf_dir: str, space: FeatureSpace | str) -> DataFrame:
    """The rows of a space, made from their table once for a session and a folder."""
    s = SPACES[space] if isinstance(space, str) else space
    return kept(spark, sf_dir, ("space", s.name), lambda: staged(spread(s.frame(spark, sf_dir)), "space"))


def kd(spark: SparkSession, sf_dir: str, space: FeatureSpace | str, levels: int | None = None, method: str = "rank", axis_rule: str = "cycle") -> tuple[DataFrame, KdTree]:
    s = SPACES[space] if isinstance(space, str) else space
    return kept(spark, sf_dir, ("kd", s.name, levels, method, axis_rule), lambda: build_kdtree(space_rows(spark, sf_dir, s), s.cols, levels, method, axis_rule))


def grid(spark: SparkSession, sf_dir: str, space: FeatureSpace, base: int) -> LayeredGrid:
    return kept(spark, sf_dir, ("grid", space.name, base), lambda: build_layered_grid(space_rows(spark, sf_dir, space), space.cols, base))


def rows(spark: SparkSession, data: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(data, schema)

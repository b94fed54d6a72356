"""Filters on documents by what they have at a path."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .paths import path_values


def where_path(df: DataFrame, path: str, predicate: Callable[[Column], Column], quantifier: str = "any") -> DataFrame:
    values = path_values(df, path)
    return df.where(F.exists(values, predicate) if quantifier == "any" else F.forall(values, predicate))


def where_present(df: DataFrame, path: str) -> DataFrame:
    return df.where(F.size(path_values(df, path)) > 0)


def where_missing(df: DataFrame, path: str) -> DataFrame:
    return df.where(F.size(path_values(df, path)) == 0)


def where_like(df: DataFrame, path: str, pattern: str) -> DataFrame:
    return where_path(df, path, lambda v: v.like(pattern))


def where_matches(df: DataFrame, path: str, pattern: str) -> DataFrame:
    return where_path(df, path, lambda v: v.rlike(pattern))


def where_in(df: DataFrame, path: str, values: list) -> DataFrame:
    return where_path(df, path, lambda v: v.isin(values))


def where_between(df: DataFrame, path: str, low: object, high: object) -> DataFrame:
    return where_path(df, path, lambda v: v.between(low, high))

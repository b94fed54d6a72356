"""Paths into nested documents: parsing, leaf catalog and generated expressions.

A path starts at `$`; `.key` enters an object, `[*]` all elements of an array,
`[i]` one of them (from 0), `{key}` and `{value}` the entries of a map.  A key
that is not made of ASCII letters, digits, `_` and `-` is quoted: `['first name']`,
with a backslash before a quote or a backslash.
Evaluation is a generated nested expression; there is no user-defined function.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

_PLAIN = r"[A-Za-z0-9_\-]+"
_STEP = re.compile(rf"\.({_PLAIN})|\[(\*|\d+)\]|\{{(key|value)\}}|\['((?:[^'\\]|\\.)*)'\]", re.DOTALL)


class Mark(str):
    """A step that is no object key."""


EACH, KEY, VALUE = Mark("[*]"), Mark("{key}"), Mark("{value}")


def key_text(key: str) -> str:
    """How an object key stands in a path."""
    return f".{key}" if re.fullmatch(_PLAIN, key) else "['" + re.sub(r"(['\\])", r"\\\1", key) + "']"


@dataclass(frozen=True)
class PathExpr:
    """Steps: a name (object key), EACH, an int (position), KEY or VALUE."""

    steps: tuple

    def __str__(self) -> str:
        return "$" + "".join(f"[{s}]" if isinstance(s, int) else str(s) if isinstance(s, Mark) else key_text(s) for s in self.steps)

    @property
    def repeated(self) -> bool:
        """Does one document have a set of values here rather than at most one?"""
        return any(isinstance(s, Mark) for s in self.steps)


def parse_path(text: str) -> PathExpr:
    if not text.startswith("$"):
        raise ValueError(f"a path starts with $: {text!r}")
    steps, at = [], 1
    while at < len(text):
        m = _STEP.match(text, at)
        if not m:
            raise ValueError(f"no step at {text[at:]!r} in {text!r}")
        name, index, entry, quoted = m.groups()
        if quoted is not None:
            steps.append(re.sub(r"\\(.)", r"\1", quoted, flags=re.DOTALL))
        else:
            steps.append(name if name else Mark(f"{{{entry}}}") if entry else EACH if index == "*" else int(index))
        at = m.end()
    return PathExpr(tuple(steps))


def named(column: str) -> Column:
    """A top-level column of any name."""
    return F.col("`" + column.replace("`", "``") + "`")


def as_path(path: str | PathExpr) -> PathExpr:
    return parse_path(path) if isinstance(path, str) else path


def path_type(schema: T.DataType, path: str | PathExpr) -> T.DataType:
    """Data type of the values at a path."""
    kind = schema
    for step in as_path(path).steps:
        if step == EACH and isinstance(step, Mark) or isinstance(step, int):
            if not isinstance(kind, T.ArrayType):
                raise ValueError(f"{path}: {step} on {kind.simpleString()}")
            kind = kind.elementType
        elif isinstance(step, Mark):
            if not isinstance(kind, T.MapType):
                raise ValueError(f"{path}: {step} on {kind.simpleString()}")
            kind = kind.keyType if step == KEY else kind.valueType
        elif isinstance(kind, T.StructType):
            kind = kind[step].dataType
        else:
            raise ValueError(f"{path}: .{step} on {kind.simpleString()}")
    return kind


def leaf_paths(schema: T.DataType, exclude: tuple[str, ...] = (), inner_array: str = "wildcard", width: int = 2) -> list[PathExpr]:
    """All deepest paths in schema order; arrays in arrays by position if asked (first `width`)."""
    out: list[PathExpr] = []

    def walk(kind: T.DataType, steps: tuple, in_array: bool) -> None:
        if isinstance(kind, T.StructType):
            for f in kind.fields:
                walk(f.dataType, (*steps, f.name), False)
        elif isinstance(kind, T.ArrayType):
            each = range(width) if in_array and inner_array == "positional" else [EACH]
            for step in each:
                walk(kind.elementType, (*steps, step), True)
        elif isinstance(kind, T.MapType):
            walk(kind.keyType, (*steps, KEY), False)
            walk(kind.valueType, (*steps, VALUE), False)
        else:
            out.append(PathExpr(steps))

    walk(schema, (), False)
    return [p for p in out if str(p) not in exclude and p.steps[0] not in exclude]


def nesting_level(path: str | PathExpr) -> int:
    """Containers around a value: a top-level scalar has 1, an element of a top-level array 2."""
    return len(as_path(path).steps)


def _map_over(array: Column, rest: tuple, kind: T.DataType) -> tuple[Column, bool]:
    """Values below each element; a factory, so that each lambda has one parameter."""
    inner: list[bool] = []

    def each(x: Column) -> Column:
        value, many = _walk(x, rest, kind)
        inner.append(many)
        return value

    mapped = F.transform(array, each)
    return (F.flatten(F.filter(mapped, lambda x: x.isNotNull())) if inner[0] else mapped), True


def _walk(value: Column, steps: tuple, kind: T.DataType) -> tuple[Column, bool]:
    if not steps:
        return value, False
    step, rest = steps[0], steps[1:]
    if isinstance(step, int):
        return _walk(F.get(value, F.lit(step)), rest, kind.elementType)
    if step == EACH and isinstance(step, Mark):
        if rest and isinstance(kind.elementType, T.StructType) and len(rest) == 1:
            # The field of every element is one expression, which the scan can prune by.
            return value.getField(rest[0]), True
        return (value, True) if not rest else _map_over(value, rest, kind.elementType)
    if step == KEY and isinstance(step, Mark):
        return F.map_keys(value), True
    if step == VALUE and isinstance(step, Mark):
        return (F.map_values(value), True) if not rest else _map_over(F.map_values(value), rest, kind.valueType)
    return _walk(value.getField(step), rest, kind[step].dataType)


def path_raw(df: DataFrame, path: str | PathExpr) -> tuple[Column, bool]:
    """What stands at a path, nulls and all: one value, or (True) an array of values that may be null itself."""
    path = as_path(path)
    path_type(df.schema, path)  # a clear error for a wrong path
    first, rest = path.steps[0], path.steps[1:]
    return _walk(named(first), rest, df.schema[first].dataType)


def path_values(df: DataFrame, path: str | PathExpr) -> Column:
    """Array of the non-null values of each document at a path; empty if it has none."""
    path = as_path(path)
    value, many = path_raw(df, path)
    array = value if many else F.array(value)
    return F.coalesce(F.filter(array, lambda x: x.isNotNull()), F.array().cast(T.ArrayType(path_type(df.schema, path))))


def select_paths(df: DataFrame, paths: list[str], names: list[str] | None = None) -> DataFrame:
    return df.select(*[path_values(df, p).alias(n) for p, n in zip(paths, names or paths)])


def path_catalog(spark: SparkSession, schema: T.DataType, exclude: tuple[str, ...] = ()) -> DataFrame:
    rows = [(i, str(p), path_type(schema, p).simpleString(), nesting_level(p)) for i, p in enumerate(leaf_paths(schema, exclude))]
    return spark.createDataFrame(rows, "path_id int, path string, type string, level int")


def pruned_schema(schema: T.StructType, paths: list[str]) -> T.StructType:
    """The part of a schema that the paths need: read with it so that nested leaves are pruned in the scan."""

    def cut(kind: T.DataType, tails: list[tuple]) -> T.DataType:
        if any(not t for t in tails):
            return kind
        if isinstance(kind, T.ArrayType):
            return T.ArrayType(cut(kind.elementType, [t[1:] for t in tails]), kind.containsNull)
        if isinstance(kind, T.MapType):
            return kind
        names = {t[0] for t in tails}
        return T.StructType([T.StructField(f.name, cut(f.dataType, [t[1:] for t in tails if t[0] == f.name]), f.nullable) for f in kind.fields if f.name in names])

    return cut(schema, [as_path(p).steps for p in paths])

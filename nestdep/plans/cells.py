"""Dynamic and static unrolling of nested documents into (doc, path, value).

Dynamic unrolling is one narrow pass: every path's values stand side by side
in one generated array that is exploded once, so the work is the number of
values, never their product.  Static unrolling multiplies independent arrays
out into flat rows; it is the baseline, guarded by its closed-form size.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.paths import EACH, KEY, VALUE, PathExpr, as_path, leaf_paths, named, path_raw, path_type, path_values
from ..functions.values import keys_of, value_key


#: What a miner builds from cells and the number of paths, by name: see `register_metadata` and `build_metadata`.
METADATA: dict[str, Callable[[DataFrame, int], DataFrame]] = {}


def register_metadata(name: str) -> Callable:
    """Make a miner's metadata known: a function of cells(doc_id, path_id, value) and the number of paths."""

    def add(build: Callable[[DataFrame, int], DataFrame]) -> Callable[[DataFrame, int], DataFrame]:
        METADATA[name] = build
        return build

    return add


def build_metadata(name: str, df: DataFrame, doc_id: str, paths: list[str] | None = None) -> DataFrame:
    """One dynamic unrolling into the metadata of a miner."""
    return METADATA[name](unroll_dynamic(df, doc_id, paths), len(resolve(df, doc_id, paths)))


def resolve(df: DataFrame, doc_id: str, paths: list[str] | None) -> list[PathExpr]:
    return [as_path(p) for p in paths] if paths is not None else leaf_paths(df.schema, exclude=(doc_id,) if doc_id not in {f.name for f in df.schema} else ())


def _cell(key: Column, path_id: int) -> Column:
    return F.struct(F.lit(path_id).alias("path_id"), key.alias("value"))


def _cells_at(df: DataFrame, path: PathExpr, path_id: int) -> Column:
    """Array of the cells of a path, with null values: one lambda for an array, none for a single value."""
    kind = path_type(df.schema, path)
    value, many = path_raw(df, path)
    if not many:
        return F.array(_cell(value_key(value, kind), path_id))
    none = F.array().cast("array<struct<path_id:int,value:string>>")
    return F.coalesce(F.transform(value, lambda v: _cell(value_key(v, kind), path_id)), none)


def unroll_dynamic(df: DataFrame, doc_id: str, paths: list[str] | None = None, array_mode: str = "elements") -> DataFrame:
    """cells(doc_id, path_id, value): one row per value; missing and empty give none.

    array_mode "opaque" takes whole arrays as one value (the classical reading).
    """
    if array_mode == "opaque":
        names = paths or df.columns
        kinds = {f.name: f.dataType for f in df.schema}
        made = [
            F.concat(F.lit("a"), F.to_json(named(n))) if isinstance(kinds[n], (T.ArrayType, T.StructType, T.MapType)) else value_key(named(n), kinds[n])
            for n in names
        ]
        each = [F.array(_cell(x, i)) for i, x in enumerate(made)]
    else:
        each = [_cells_at(df, p, i) for i, p in enumerate(resolve(df, doc_id, paths))]
    # Missing values are dropped behind the generator, in compiled code.
    rows = df.select(named(doc_id).alias("doc_id"), F.explode(F.concat(*each)).alias("cell")).select("doc_id", "cell.path_id", "cell.value")
    return rows.where(F.col("value").isNotNull())


def profiles(df: DataFrame, doc_id: str, paths: list[str] | None = None) -> DataFrame:
    """doc_id and one array of distinct value keys per path (p0, p1, ...)."""
    chosen = resolve(df, doc_id, paths)
    return df.select(
        F.col(doc_id).alias("doc_id"), *[F.array_distinct(keys_of(path_values(df, p), path_type(df.schema, p))).alias(f"p{i}") for i, p in enumerate(chosen)]
    )


def expansion(df: DataFrame) -> Column:
    """Number of flat rows of each document: atomic 1, object product, array sum, empty 1."""

    def of(value: Column, kind: T.DataType) -> Column:
        if isinstance(kind, T.StructType):
            out = F.lit(1.0)
            for f in kind.fields:
                if isinstance(f.dataType, (T.StructType, T.ArrayType, T.MapType)):
                    out = out * of(value.getField(f.name), f.dataType)
            return F.coalesce(out, F.lit(1.0))
        if isinstance(kind, T.ArrayType):
            return sums(value, kind.elementType)
        if isinstance(kind, T.MapType):
            return sums(F.map_values(value), kind.valueType)
        return F.lit(1.0)

    def sums(array: Column, kind: T.DataType) -> Column:
        if isinstance(kind, (T.StructType, T.ArrayType, T.MapType)):
            total = F.aggregate(F.transform(array, lambda x: of(x, kind)), F.lit(0.0), lambda a, x: a + x)
        else:
            total = F.size(array).cast("double")
        return F.greatest(F.coalesce(total, F.lit(1.0)), F.lit(1.0))

    out = F.lit(1.0)
    for f in df.schema.fields:
        if isinstance(f.dataType, (T.StructType, T.ArrayType, T.MapType)):
            out = out * of(named(f.name), f.dataType)
    return out


def expansion_factor(df: DataFrame) -> DataFrame:
    """documents, rows after static unrolling, and their ratio; nothing is materialised."""
    rows = df.select(expansion(df).alias("r")).agg(F.count(F.lit(1)).alias("documents"), F.coalesce(F.sum("r"), F.lit(0.0)).alias("unrolled"))
    return rows.select("documents", F.col("unrolled").cast("long").alias("unrolled_rows"), F.round(F.col("unrolled") / F.col("documents"), 6).alias("expansion"))


class TooLarge(RuntimeError):
    """A plan was refused because its closed-form size passes the limit."""


def unroll_static(df: DataFrame, placeholder: str | None = None, map_mode: str = "entries", inner_array: str = "wildcard", row_limit: float | None = None) -> DataFrame:
    """Flat rows, one column per leaf path (named by the path); nulls fill what a document lacks.

    map_mode "keys" makes a column of each distinct key; inner_array "positional"
    makes a column of each position of an array in an array.
    """
    if row_limit is not None:
        total = df.select(F.sum(expansion(df))).first()[0] or 0
        if total > row_limit:
            raise TooLarge(f"static unrolling would make {total:.0f} rows; the limit is {row_limit:.0f}")
    serial = iter(range(1 << 30))
    out: list[Column] = []

    def visit(now: DataFrame, value: Column, kind: T.DataType, path: PathExpr, in_array: bool) -> DataFrame:
        if isinstance(kind, T.StructType):
            for f in kind.fields:
                now = visit(now, value.getField(f.name), f.dataType, PathExpr((*path.steps, f.name)), False)
        elif isinstance(kind, T.ArrayType) and in_array and inner_array == "positional":
            width = now.select(F.max(F.size(value))).first()[0] or 0
            for i in range(width):
                now = visit(now, F.get(value, F.lit(i)), kind.elementType, PathExpr((*path.steps, i)), True)
        elif isinstance(kind, T.ArrayType):
            name = f"_e{next(serial)}"
            now = now.select("*", F.explode_outer(value).alias(name))
            now = visit(now, F.col(name), kind.elementType, PathExpr((*path.steps, EACH)), True)
        elif isinstance(kind, T.MapType) and map_mode == "keys":
            keys = sorted(r[0] for r in now.select(F.explode(F.map_keys(value))).distinct().limit(1001).toLocalIterator())
            if len(keys) > 1000:
                raise TooLarge("over 1000 distinct keys: unroll this map by entries")
            for k in keys:
                now = visit(now, F.element_at(value, F.lit(k)), kind.valueType, PathExpr((*path.steps, str(k))), False)
        elif isinstance(kind, T.MapType):
            name = f"_e{next(serial)}"
            now = now.select("*", F.explode_outer(F.map_entries(value)).alias(name))
            now = visit(now, F.col(name)["key"], kind.keyType, PathExpr((*path.steps, KEY)), False)
            now = visit(now, F.col(name)["value"], kind.valueType, PathExpr((*path.steps, VALUE)), False)
        else:
            filled = value if placeholder is None else F.coalesce(value.cast("string"), F.lit(placeholder))
            out.append(filled.alias(str(path)))
        return now

    now = df
    for f in df.schema.fields:
        now = visit(now, named(f.name), f.dataType, PathExpr((f.name,)), False)
    return now.select(*out)


def cells_of_flat(flat: DataFrame, names: list[str] | None = None) -> DataFrame:
    """Unpivot flat rows to (path_id, value): the input of miners over static rows."""
    kinds = {f.name: f.dataType for f in flat.schema}
    each = [F.struct(F.lit(i).alias("path_id"), value_key(named(n), kinds[n]).alias("value")) for i, n in enumerate(names or flat.columns)]
    return flat.select(F.explode(F.array(*each)).alias("cell")).select("cell.path_id", "cell.value").where(F.col("value").isNotNull())


def _key_step(key: Column) -> Column:
    quoted = F.concat(F.lit("['"), F.regexp_replace(key, r"(['\\])", r"\\$1"), F.lit("']"))
    return F.when(key.rlike(r"^[A-Za-z0-9_\-]+$"), F.concat(F.lit("."), key)).otherwise(quoted)


def unroll_variant(df: DataFrame, column: str, max_depth: int = 4) -> DataFrame:
    """(doc_id, path, value) of JSON texts without a schema, level by level through variants."""
    spark = df.sparkSession
    now = df.select("doc_id", F.lit("$").alias("path"), F.try_parse_json(F.col(column)).alias("v")).where(F.col("v").isNotNull())
    found = None
    for _ in range(max_depth + 1):
        kind = F.schema_of_variant("v")
        inner = kind.startswith("OBJECT") | kind.startswith("ARRAY")
        tag = F.when(kind == "BOOLEAN", "b").when(kind == "STRING", "s").otherwise("n")
        text = F.when(tag == "n", value_key(F.try_variant_get("v", "$", "double"), T.DoubleType())).otherwise(F.concat(tag, F.try_variant_get("v", "$", "string")))
        leaves = now.where(~inner & (kind != "VOID")).select("doc_id", "path", text.alias("value"))
        found = leaves if found is None else found.unionAll(leaves)
        below = now.where(inner).alias("t")
        grown = below.lateralJoin(spark.tvf.variant_explode(F.col("t.v").outer())).select(
            "doc_id", F.when(F.col("key").isNull(), F.concat("path", F.lit("[*]"))).otherwise(F.concat("path", _key_step(F.col("key")))).alias("path"), F.col("value").alias("v")
        )
        now = grown
    return found

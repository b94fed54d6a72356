"""Names for SQL users: SQL functions written as expressions, and one table function for JSON texts."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

FUNCTIONS = {
    "nest_strength(included BIGINT, support BIGINT) RETURNS DOUBLE": "round(included / support, 6)",
    "nest_overlap(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS BOOLEAN": "arrays_overlap(a, b)",
    "nest_contained(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS BOOLEAN": "size(array_except(a, b)) = 0",
    "nest_mask_has(mask BIGINT, wanted BIGINT) RETURNS BOOLEAN": "(mask & wanted) = wanted",
    "nest_number_key(x DOUBLE) RETURNS STRING": "CASE WHEN NOT isnan(x) THEN concat('n', CASE WHEN x = floor(x) AND abs(x) < 9223372036854775808D THEN CAST(CAST(x AS BIGINT) AS STRING) ELSE CAST(x AS STRING) END) END",
}


@udtf(returnType="path string, value string")
class JsonPathCells:
    """path and value key of every atomic value of a JSON text; a broken text gives none."""

    def eval(self, text: str):  # noqa: ANN201
        import json

        from nestdep.functions.paths import key_text

        def walk(x, path):  # noqa: ANN001, ANN202
            if isinstance(x, dict):
                for k, v in x.items():
                    yield from walk(v, path + key_text(k))
            elif isinstance(x, list):
                for v in x:
                    yield from walk(v, f"{path}[*]")
            elif isinstance(x, bool):
                yield path, "b" + str(x).lower()
            elif isinstance(x, (int, float)):
                yield path, f"n{int(x)}" if float(x).is_integer() else f"n{x}"
            elif isinstance(x, str):
                yield path, "s" + x

        try:
            yield from walk(json.loads(text or ""), "$")
        except ValueError:
            return


def register_functions(spark: SparkSession) -> None:
    for signature, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {signature} RETURN {body}")
    spark.udtf.register("json_path_cells", JsonPathCells)

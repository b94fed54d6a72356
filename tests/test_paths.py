import pytest
from pyspark.sql import functions as F

from nestdep.functions import paths as P
from nestdep.functions.sql import register_functions
from nestdep.functions.values import value_key
from nestdep.operators.functional import mine_functional
from nestdep.operators.inclusion import mine_inclusion
from nestdep.plans import cells as plans
from nestdep.queries import nested_sample
from nestdep.sources.collections import build_collection, stored_collection


def test_parse_and_print():
    for text in ("$.a", "$.a[*].b", "$.a[*][1].c", "$.m{key}", "$.m{value}"):
        assert str(P.parse_path(text)) == text
    for bad in ("a.b", "$a", "$.a[x]"):
        with pytest.raises(ValueError):
            P.parse_path(bad)


def test_levels(spark):
    df = spark.createDataFrame([(1, [(1, "x"), (2, "y")], ["p", "q"])], "id long, authors array<struct<id:long,name:string>>, languages array<string>")
    level = {str(p): P.nesting_level(p) for p in P.leaf_paths(df.schema)}
    assert level == {"$.id": 1, "$.authors[*].id": 3, "$.authors[*].name": 3, "$.languages[*]": 2}
    cells = plans.unroll_dynamic(df, "id").count()
    assert cells == 7 and plans.unroll_static(df).count() == 4


def test_values_at_paths(spark):
    df = nested_sample(spark)
    row = df.select(
        P.path_values(df, "$.related.bought[*]").alias("a"), P.path_values(df, "$.categories[*][*]").alias("b"), P.path_values(df, "$.categories[*][1]").alias("c"),
        P.path_values(df, "$.ranks{key}").alias("d"), P.path_values(df, "$.ranks{value}").alias("e"),
    ).first()
    assert row["a"] == ["p1", "p2"] and row["b"] == ["Toys", "Puzzles", "Games", "Cards"] and row["c"] == ["Puzzles", "Cards"] and row["d"] == ["Toys"] and row["e"] == [7]


def test_value_identity(spark):
    rows = spark.sql("select 5 a, 5.0D b, '5' c, -0.0D d, 0 e, double('NaN') f, false g, '' h, cast(null as string) i, timestamp'2020-01-01 00:00:00' t, date'2020-01-01' u")
    kinds = {f.name: f.dataType for f in rows.schema}
    key = rows.select(*[value_key(F.col(c), kinds[c]).alias(c) for c in rows.columns]).first()
    assert key["a"] == key["b"] != key["c"] and key["d"] == key["e"] and key["f"] is None and key["g"] == "bfalse" and key["h"] == "s" and key["i"] is None and key["t"] == key["u"]


def test_missing_and_empty_give_no_cell(spark):
    df = spark.createDataFrame([(1, None, [], None), (2, "", [None], (None,)), (3, "x", [1, 1], (4,))], "id long, s string, a array<int>, o struct<v:int>")
    rows = {(r[0], r[1], r[2]) for r in plans.unroll_dynamic(df, "id", ["$.s", "$.a[*]", "$.o.v"]).collect()}
    assert rows == {(2, 0, "s"), (3, 0, "sx"), (3, 1, "n1"), (3, 2, "n4")}


def test_static_rows_follow_the_closed_form(spark, sf_dir):
    for name in ("order_docs", "customer_docs", "conversation_docs", "user_day_docs"):
        df = build_collection(name, spark, sf_dir)
        assert plans.expansion_factor(df).first()["unrolled_rows"] == plans.unroll_static(df).count()


def test_static_is_refused_beyond_its_limit(spark, sf_dir):
    with pytest.raises(plans.TooLarge):
        plans.unroll_static(build_collection("product_docs", spark, sf_dir), row_limit=1000)


def test_cells_plan_has_no_exchange_and_prunes(spark, sf_dir):
    df = build_collection("event_docs", spark, sf_dir)
    plan = plans.unroll_dynamic(df, "event_id", ["$.user_id"])._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Python" not in plan and "props" not in plan.split("ReadSchema")[1]


def test_pruned_schema(spark, sf_dir):
    df = build_collection("customer_docs", spark, sf_dir)
    cut = P.pruned_schema(df.schema, ["$.orders[*].items[*].partkey", "$.custkey"])
    assert cut.simpleString() == "struct<custkey:bigint,orders:array<struct<items:array<struct<partkey:bigint>>>>>"


def test_quoted_keys(spark):
    for text in ("$['first name']", "$.a[*]['x.y']['it\\'s']", "$['b\\\\c'].d", "$['[*]'][*]", "$['größe']"):
        assert str(P.parse_path(text)) == text
    df = spark.createDataFrame([(1, "x", [("p", "x")], "q"), (2, "y", [("x", "y")], "q")], "id long, `first name` string, items array<struct<`a.b`:string,`c d`:string>>, `[*]` string")
    paths = [str(p) for p in P.leaf_paths(df.schema)]
    assert paths == ["$.id", "$['first name']", "$.items[*]['a.b']", "$.items[*]['c d']", "$['[*]']"]
    cells = {(r[0], r[1], r[2]) for r in plans.unroll_dynamic(df, "id").collect()}
    assert {(1, 1, "sx"), (1, 2, "sp"), (2, 3, "sy"), (2, 4, "sq")} <= cells
    found = {(r["lhs"], r["rhs"]) for r in mine_inclusion(df, "id", paths=paths).where("valid").collect()}
    assert ("$['first name']", "$.items[*]['c d']") in found and ("$.items[*]['c d']", "$['first name']") in found
    assert mine_functional(df, "id", paths=paths[1:4]).count() and mine_functional(df, "id", unrolling="static", paths=paths[1:4], theta=1.0).count()
    assert plans.unroll_static(df).columns == paths


def test_quoted_keys_of_texts(spark):
    df = spark.createDataFrame([(1, '{"first name": {"a.b": [1]}, "it\'s": 2}')], "doc_id long, j string")
    want = {"$['first name']['a.b'][*]", "$['it\\'s']"}
    assert {r[1] for r in plans.unroll_variant(df, "j").collect()} == want
    register_functions(spark)
    assert {r[0] for r in spark.sql("SELECT path FROM {d} AS d, LATERAL json_path_cells(d.j)", d=df).collect()} == want
    assert all(str(P.parse_path(p)) == p for p in want)


def test_decimals_keep_their_digits(spark):
    rows = spark.sql(
        """select 12345678901234567890.1BD a, 12345678901234567891.1BD b, 1.50BD c, 1.5D d, 2.00BD e, 2 f, 9007199254740993L g, 9007199254740992D h, 9007199254740992L i,
           cast(0.1 as decimal(38,20)) j, 0.1D k, 9007199254740993.00BD l, cast(null as decimal(10,2)) m, -0.0BD n, 0 o, 100BD p, 100 q"""
    )
    kinds = {f.name: f.dataType for f in rows.schema}
    key = rows.select(*[value_key(F.col(c), kinds[c]).alias(c) for c in rows.columns]).first()
    assert key["a"] != key["b"] and key["c"] == key["d"] and key["e"] == key["f"] and key["g"] != key["h"] == key["i"]
    assert key["j"] == key["k"] and key["l"] == key["g"] and key["m"] is None and key["n"] == key["o"] and key["p"] == key["q"] == "n100"


def test_stored_collections_are_pruned(spark, sf_dir):
    paths = ["$.orders[*].items[*].partkey"]
    df = stored_collection("customer_docs", spark, sf_dir, paths)
    assert df.schema.simpleString() == "struct<custkey:bigint,orders:array<struct<items:array<struct<partkey:bigint>>>>>"
    whole = build_collection("customer_docs", spark, sf_dir)
    count = lambda x: x.select(F.sum(F.size(P.path_values(x, paths[0])))).first()[0]
    assert count(df) == count(whole)

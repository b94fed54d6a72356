"""Nested collections derived from the given flat tables, a dirt injector and a generator."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.paths import PathExpr, pruned_schema
from .tables import load, scratch, written


def order_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One document per order with its items (sorted on all fields, as keys repeat)."""
    item = F.struct(
        F.col("l_linenumber").alias("linenumber"), F.col("l_partkey").alias("partkey"), F.col("l_suppkey").alias("suppkey"),
        F.col("l_quantity").alias("quantity"), F.col("l_returnflag").alias("returnflag"), F.col("l_linestatus").alias("linestatus"),
    )
    items = load(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("orderkey")).agg(F.array_sort(F.collect_list(item)).alias("items"))
    orders = load(spark, sf_dir, "orders").select(
        F.col("o_orderkey").alias("orderkey"), F.col("o_custkey").alias("custkey"), F.col("o_orderstatus").alias("status"),
        F.col("o_orderpriority").alias("priority"), F.col("o_totalprice").alias("totalprice"), F.col("o_orderdate").alias("orderdate"),
    )
    out = orders.join(items, "orderkey", "left")
    empty = F.array().cast(out.schema["items"].dataType)
    out = out.withColumn("items", F.coalesce("items", empty))
    flags = F.array_sort(F.array_distinct(F.transform("items", lambda i: i["returnflag"])))
    return out.withColumn("flags", flags).withColumn("flag_or_status", F.array_union("flags", F.array("status")))


def customer_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = order_docs(spark, sf_dir).select(
        "custkey",
        F.struct(
            "orderkey", "custkey", "status",
            F.transform("items", lambda i: F.struct(i["partkey"].alias("partkey"), i["suppkey"].alias("suppkey"), i["returnflag"].alias("returnflag"))).alias("items"),
        ).alias("o"),
    )
    grouped = orders.groupBy("custkey").agg(F.array_sort(F.collect_list("o")).alias("orders"))
    places = F.broadcast(
        load(spark, sf_dir, "nation").join(load(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(
            F.col("n_nationkey").alias("c_nationkey"),
            F.struct(F.col("n_nationkey").alias("nationkey"), F.col("n_name").alias("name"), F.struct(F.col("r_regionkey").alias("regionkey"), F.col("r_name").alias("name")).alias("region")).alias("nation"),
        )
    )
    people = load(spark, sf_dir, "customer").join(places, "c_nationkey").select(F.col("c_custkey").alias("custkey"), F.col("c_mktsegment").alias("segment"), "nation")
    out = people.join(grouped, "custkey", "left")
    return out.withColumn("orders", F.coalesce("orders", F.array().cast(out.schema["orders"].dataType)))


def product_docs(spark: SparkSession, sf_dir: str, cap: int | None = None) -> DataFrame:
    """One document per part: parts ordered or returned with it, suppliers, categories, a map."""
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_returnflag"])
    one = lines.select("l_orderkey", F.col("l_partkey").alias("partkey"), (F.col("l_returnflag") == "R").alias("back"))
    two = lines.select("l_orderkey", F.col("l_partkey").alias("other"), (F.col("l_returnflag") == "R").alias("other_back"))
    pairs = one.join(two, "l_orderkey").where("partkey <> other")
    with_ = pairs.groupBy("partkey").agg(F.sort_array(F.collect_set("other")).alias("ordered_with"), F.sort_array(F.collect_set(F.when(F.col("back") & F.col("other_back"), F.col("other")))).alias("returned_with"))
    suppliers = lines.groupBy(F.col("l_partkey").alias("partkey")).agg(F.sort_array(F.collect_set("l_suppkey")).alias("suppliers"))
    part = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("partkey"), F.col("p_brand").alias("brand"), "p_type", "p_size", "p_name")
    out = part.join(with_, "partkey", "left").join(suppliers, "partkey", "left")
    none = F.array().cast("array<bigint>")
    docs = out.select(
        "partkey", "brand",
        F.struct(F.coalesce("ordered_with", none).alias("ordered_with"), F.coalesce("returned_with", none).alias("returned_with")).alias("related"),
        F.coalesce("suppliers", none).alias("suppliers"),
        F.array(F.array(F.col("p_type"), F.concat("p_type", F.lit("/"), F.element_at(F.split("p_name", " "), 1)))).alias("categories"),
        F.create_map(F.concat(F.lit("size"), (F.col("p_size") % 5).cast("string")), F.col("p_size")).alias("size_rank"),
    )
    return capped_products(docs, cap) if cap else docs


def capped_products(docs: DataFrame, cap: int) -> DataFrame:
    """Product documents with the first cap keys of each array; returned ones stay among the ordered ones."""
    ordered = F.slice("related.ordered_with", 1, cap)
    returned = F.array_intersect(F.slice("related.returned_with", 1, cap), ordered)
    return docs.withColumn("related", F.struct(ordered.alias("ordered_with"), returned.alias("returned_with"))).withColumn("suppliers", F.slice("suppliers", 1, cap))


def event_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").withColumn("props", F.from_json("props", "k bigint"))


def user_day_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = event_docs(spark, sf_dir).withColumn("day", F.to_date("ts"))
    item = F.struct("ts", "event_id", "event_type", F.col("props.k").alias("k"), "value")
    out = e.groupBy("user_id", "day").agg(F.array_sort(F.collect_list(item)).alias("es"))
    events = F.transform("es", lambda x: F.struct(x["event_type"].alias("event_type"), x["k"].alias("k"), x["value"].alias("value")))
    return out.select(F.concat_ws("@", F.col("user_id").cast("string"), F.col("day").cast("string")).alias("doc_key"), "user_id", "day", events.alias("events"))


def text_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = load(spark, sf_dir, "labels").select("doc_id", F.struct("quality", "toxic").alias("labels"))
    words = F.array_distinct(F.filter(F.split("text", r"[\x20\x09-\x0D]+"), lambda w: w != ""))
    docs = load(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars", words.alias("words"))
    return docs.join(labels, "doc_id", "left")


def conversation_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = load(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    return turns.withColumn("roles", F.array_sort(F.array_distinct(F.transform("turns", lambda t: t["role"]))))


def page_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    links = F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), F.lit(1))
    lang = F.regexp_extract("html", r'<html lang="([a-z]+)"', 1)
    return load(spark, sf_dir, "pages").select("page_id", F.expr("try_parse_url(url, 'HOST')").alias("host"), F.nullif(lang, F.lit("")).alias("lang"), links.alias("links"))


def vector_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    coords = F.transform("embedding", lambda x: F.floor(x * 100).cast("int"))
    return load(spark, sf_dir, "embeddings").select("vec_id", "label", coords.alias("coords"))


def geo_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five documents that hold all customers and orders: the deepest nesting, for small tables only."""
    keys = load(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.sort_array(F.collect_set("o_orderkey")).alias("orderkeys"))
    people = load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]).join(keys, "c_custkey", "left")
    people = people.groupBy(F.col("c_nationkey").alias("n_nationkey")).agg(
        F.array_sort(F.collect_list(F.struct(F.col("c_custkey").alias("custkey"), F.coalesce("orderkeys", F.array().cast("array<bigint>")).alias("orderkeys")))).alias("customers")
    )
    suppliers = load(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("n_nationkey")).agg(
        F.array_sort(F.collect_list(F.struct(F.col("s_suppkey").alias("suppkey"), F.col("s_nationkey").alias("nationkey")))).alias("suppliers")
    )
    nation = load(spark, sf_dir, "nation").join(suppliers, "n_nationkey", "left").join(people, "n_nationkey", "left")
    item = F.struct(F.col("n_nationkey").alias("nationkey"), F.col("n_name").alias("name"), "suppliers", "customers")
    nations = nation.groupBy(F.col("n_regionkey").alias("r_regionkey")).agg(F.array_sort(F.collect_list(item)).alias("nations"))
    return load(spark, sf_dir, "region").join(nations, "r_regionkey", "left").select(F.col("r_regionkey").alias("regionkey"), F.col("r_name").alias("name"), "nations")


def benchmark_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    words = F.array_distinct(F.filter(F.split("text", r"[\x20\x09-\x0D]+"), lambda w: w != ""))
    return load(spark, sf_dir, "benchmark").select("item_id", words.alias("words"))


COLLECTIONS = {
    "order_docs": (order_docs, "orderkey"),
    "customer_docs": (customer_docs, "custkey"),
    "product_docs": (product_docs, "partkey"),
    "event_docs": (event_docs, "event_id"),
    "user_day_docs": (user_day_docs, "doc_key"),
    "text_docs": (text_docs, "doc_id"),
    "conversation_docs": (conversation_docs, "conv_id"),
    "page_docs": (page_docs, "page_id"),
    "vector_docs": (vector_docs, "vec_id"),
    "geo_docs": (geo_docs, "regionkey"),
    "benchmark_docs": (benchmark_docs, "item_id"),
}


def build_collection(name: str, spark: SparkSession, sf_dir: str, cap: int | None = None) -> DataFrame:
    make, _ = COLLECTIONS[name]
    return make(spark, sf_dir, cap) if name == "product_docs" else make(spark, sf_dir)


_STORED: dict[tuple, str] = {}


def stored_collection(name: str, spark: SparkSession, sf_dir: str, paths: list[str] | None = None, cap: int | None = None) -> DataFrame:
    """The collection as nested Parquet in the shared folder, read with the leaves that the paths need only.

    It is built once an application for the same tables (which must not change
    meanwhile); miners then read documents, as they would where documents are
    what is given, and not the joins that made them.
    """
    place = spark.sparkContext.applicationId, name, sf_dir, cap
    if place not in _STORED:
        path = scratch(spark, f"collection-{name}")
        # As many files as the session has shuffle partitions or cores, dealt by key: small collections would else be one or two.
        parts = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
        # Capped products are cut from the stored whole ones, whose joins need not run again.
        cut = cap and name == "product_docs"
        docs = capped_products(stored_collection(name, spark, sf_dir), cap) if cut else build_collection(name, spark, sf_dir)
        docs.repartition(parts, COLLECTIONS[name][1]).write.parquet(path)
        _STORED[place] = path
    schema = spark.read.parquet(_STORED[place]).schema
    if paths is not None:
        schema = pruned_schema(schema, [*paths, str(PathExpr((COLLECTIONS[name][1],)))])
    return spark.read.schema(schema).parquet(_STORED[place])


def prefixes_by_time(df: DataFrame, column: str, sizes: list[int], key: str) -> list[DataFrame]:
    """For each size the first documents in time order: those up to the size-th, which is looked for in one range of the times.

    The times are dealt in ranges and written once for all sizes.
    """
    at = df.select(F.struct(column, key).alias("at"))
    parts = max(df.sparkSession.sparkContext.defaultParallelism, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    ranges = written(at.repartitionByRange(parts, "at").select("at", F.spark_partition_id().alias("part")), "times")
    counts = ranges.groupBy("part").agg(F.count(F.lit(1)).alias("n")).orderBy("part").collect()

    def prefix(n: int) -> DataFrame:
        left = n
        for r in counts:
            if left < r["n"]:
                after = ranges.where(F.col("part") == r["part"]).withColumn("k", F.row_number().over(Window.orderBy("at"))).where(F.col("k") == left + 1)
                return df.join(F.broadcast(after.select(F.col("at").alias("_after"))), F.struct(column, key) < F.col("_after"), "left_semi")
            left -= r["n"]
        return df

    return [prefix(n) for n in sizes]


def prefix_by_time(df: DataFrame, column: str, n: int, key: str) -> DataFrame:
    """The first n documents in time order."""
    return prefixes_by_time(df, column, [n], key)[0]


def dirty(key: str, per_mille: int) -> Column:
    """The documents that a rule changes: arithmetic, so SQL can repeat it."""
    return (F.col(key) * 7919) % 1000 < per_mille


def inject(df: DataFrame, key: str, column: str, rule: str, per_mille: int) -> DataFrame:
    """Dirt in a top-level column: "null" or "drop" it, or a "foreign" value."""
    kind = df.schema[column].dataType
    bad = {"null": F.lit(None).cast(kind), "drop": F.lit(None).cast(kind)}.get(rule)
    if rule == "foreign":
        bad = F.concat(F.lit("foreign"), F.col(key).cast("string")) if kind.simpleString() == "string" else (-F.col(key) - 1).cast(kind)
    if rule == "wrong_type":
        return df.withColumn(column, F.when(dirty(key, per_mille), F.concat(F.lit("x"), F.col(column).cast("string"))).otherwise(F.col(column).cast("string")))
    return df.withColumn(column, F.when(dirty(key, per_mille), bad).otherwise(F.col(column)))


def synthesize(spark: SparkSession, n: int, arrays: int = 2, width: int = 3, depth: int = 1) -> DataFrame:
    """n documents with independent arrays of some width, nested to some depth; values follow from the id."""
    return shaped(spark.range(n).withColumnRenamed("id", "doc_id"), arrays, width, depth)


def shaped(ids: DataFrame, arrays: int = 2, width: int = 3, depth: int = 1) -> DataFrame:
    """A document of that shape for each doc_id."""
    df = ids.withColumn("a", F.col("doc_id") % 97).withColumn("b", F.col("a") % 7)
    for k in range(arrays):
        value = _row(k, width)
        for level in range(1, depth):
            value = _wrapped(value, level)
        df = df.withColumn(f"arr{k}", value)
    return df


def _row(k: int, width: int) -> Column:
    base = F.col("doc_id") * (k + 1)
    return F.array(*[((base + i) % 1000).alias("v") for i in range(width)])


def _wrapped(value: Column, level: int) -> Column:
    return F.array(F.struct(value.alias(f"l{level}")), F.struct(F.slice(value, 1, 1).alias(f"l{level}")))

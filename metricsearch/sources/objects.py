"""Object sets (obj_id, obj) built from the given tables, with DuckDB twins of their building blocks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import columns
from .tables import load

#: Metric and degree/leaf size at small scale of each set.
SETS = {
    "part_paths": "sad", "week_paths": "sad", "supplier_paths": "sad", "part_scatter": "sad",
    "letter_hist": "l1", "embedding_l1": "l1", "line_words": "jaccard", "doc_words": "jaccard", "order_points": "euclid",
}
LETTERS = "abcdefghijklmnopqrstuvwxyz"


def packed(high: Column, low: Column, most: int) -> Column:
    """``high * most + low`` as one id; a ``low`` outside 0 to ``most`` - 1 would meet another id, and fails."""
    failed = F.raise_error(F.concat(F.lit(f"an id part outside 0 to {most - 1}: "), low.cast("string")))
    return F.when((low >= 0) & (low < most), (high * most + low).cast("long")).otherwise(failed.cast("long"))


def movements(vertices: DataFrame, by: str, mode: str = "time") -> DataFrame:
    """Movements (obj_id, obj) from a table (by, t, x, y): one shuffle by id, vertices sorted within it."""
    grouped = vertices.groupBy(by).agg(F.array_sort(F.collect_list(F.struct("t", "x", "y"))).alias("v"))
    return grouped.select(F.col(by).alias("obj_id"), columns.align(F.col("v"), mode).alias("obj"))


def _epoch(column: str) -> Column:
    return F.unix_micros(F.col(column).cast("timestamp"))


def line_vertices(spark: SparkSession, sf_dir: str, key: str, running: bool = True) -> DataFrame:
    """(key, t, x, y) for each part or supplier and ship date: quantity and price, summed up along the way or mean.

    Prices are summed as whole cents, so sums do not depend on the order of rows.
    """
    rows = load(spark, sf_dir, "lineitem", key, "l_shipdate", "l_quantity", "l_extendedprice")
    cents = F.round(F.col("l_extendedprice") * 100).cast("long")
    day = rows.groupBy(key, _epoch("l_shipdate").alias("t")).agg(F.sum("l_quantity").alias("q"), F.sum(cents).alias("c"), F.count("*").alias("n"))
    if not running:
        return day.select(key, "t", (F.col("q") / F.col("n")).alias("x"), (F.col("c") / F.col("n") / 100000.0).alias("y"))
    upto = Window.partitionBy(key).orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return day.select(key, "t", F.sum("q").over(upto).alias("x"), (F.sum("c").over(upto) / 1000000.0).alias("y"))


def week_vertices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, t, x, y) by user and 7-day block from 2024-01-01: running sums of value (cents) and of k in the properties."""
    rows = load(spark, sf_dir, "events", "user_id", "ts", "value", "props")
    block = F.floor((_epoch("ts") - F.lit(1704067200000000)) / F.lit(604800000000))
    rows = rows.select(packed(F.col("user_id"), block, 100).alias("id"), _epoch("ts").alias("t"), F.round(F.col("value") * 100).cast("long").alias("c"), F.get_json_object("props", "$.k").cast("long").alias("k"))
    upto = Window.partitionBy("id").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return rows.select("id", "t", (F.sum("c").over(upto) / 100.0).alias("x"), F.sum("k").over(upto).cast("double").alias("y"))


def words(text: Column) -> Column:
    return F.array_distinct(F.filter(F.split(F.lower(text), " "), lambda w: w != ""))


def objects(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of ``SETS`` as (obj_id, obj)."""
    if name in ("part_paths", "supplier_paths", "part_scatter"):
        key = "l_suppkey" if name == "supplier_paths" else "l_partkey"
        return movements(line_vertices(spark, sf_dir, key, name != "part_scatter"), key)
    if name == "week_paths":
        return movements(week_vertices(spark, sf_dir), "id")
    if name == "letter_hist":
        low = load(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", F.lower("text").alias("t"))
        counts = [(F.length("t") - F.length(F.replace("t", F.lit(c)))).cast("double") for c in LETTERS]
        return low.where("t is not null").select(F.col("doc_id").alias("obj_id"), F.array(*counts).alias("obj"))
    if name == "embedding_l1":
        return load(spark, sf_dir, "embeddings", "vec_id", "embedding").where("embedding is not null").select(F.col("vec_id").alias("obj_id"), F.col("embedding").cast("array<double>").alias("obj"))
    if name == "doc_words":
        return load(spark, sf_dir, "documents", "doc_id", "text").where("text is not null").select(F.col("doc_id").alias("obj_id"), words(F.col("text")).alias("obj"))
    if name == "line_words":
        rows = load(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", F.posexplode(F.split("text", r"[.!?]\s+|\n")))
        return rows.where(F.trim("col") != "").select(packed(F.col("doc_id"), F.col("pos"), 100000).alias("obj_id"), words(F.col("col")).alias("obj"))
    if name == "order_points":
        days = F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01").cast("date")).cast("double")
        return load(spark, sf_dir, "orders", "o_orderkey", "o_totalprice", "o_orderdate").select(F.col("o_orderkey").alias("obj_id"), F.struct((F.col("o_totalprice") / 1000.0).alias("x"), days.alias("y")).alias("obj"))
    raise ValueError(f"no object set {name!r}")


def cut_pieces(spark: SparkSession, sf_dir: str, size: int) -> DataFrame:
    """Supplier paths cut into pieces of ``size`` vertices, aligned anew; shorter rests are left out, as in the
    experiment on movements of a fixed number of points."""
    v = line_vertices(spark, sf_dir, "l_suppkey")
    place = F.row_number().over(Window.partitionBy("l_suppkey").orderBy("t")) - 1
    v = v.withColumn("piece", packed(F.col("l_suppkey"), F.floor(place / size), 10000))
    whole = v.groupBy("piece").count().where(F.col("count") == size).select("piece")
    return movements(v.join(whole, "piece", "left_semi"), "piece")


def pick(df: DataFrame, n: int, seed: int = 1, key: str = "obj_id") -> DataFrame:
    """The first n rows by md5 of id and seed: the same rows in any engine and layout."""
    return df.orderBy(F.md5(F.concat(F.col(key).cast("string"), F.lit(f"|{seed}"))), key).limit(n)


def close_gaps_units(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, n_units, closed): events as units of one hour by user, units put into gaps, and their summed length."""
    t = _epoch("ts")
    unit = F.struct(t.alias("t0"), (t + 3600000000).alias("t1"), F.lit(0.0).alias("x0"), F.lit(0.0).alias("y0"), F.col("value").alias("x1"), F.lit(0.0).alias("y1"), F.col("event_id").alias("id"))
    raw = load(spark, sf_dir, "events", "event_id", "user_id", "ts", "value").groupBy("user_id").agg(F.array_sort(F.collect_list(unit)).alias("u"))
    bare = F.transform("u", lambda u: F.struct(*[u[c].alias(c) for c in ("t0", "t1", "x0", "y0", "x1", "y1")]))
    both = raw.select("user_id", bare.alias("u"), columns.close_gaps(bare).alias("c"))
    total = lambda a: F.aggregate(a, F.lit(0).cast("long"), lambda s, u: s + u["t1"] - u["t0"])
    return both.select("user_id", F.size("c").cast("long").alias("n_units"), (total(F.col("c")) - total(F.col("u"))).alias("closed"))

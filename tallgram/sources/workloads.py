"""Workload matrices over the given tables, as labelled triplets (row_id, label, val)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallgram.operators.matrix import dense_rows, encode_columns, min_support, to_row_form
from tallgram.sources.tables import load_table


def _one():
    return F.lit(1.0).alias("val")


def users_by_hour(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Similar users: a row for each hour and event type, a column for each user."""
    e = load_table(spark, sf_dir, "events")
    hour = F.expr("cast((unix_micros(cast(ts as timestamp)) div 3600000000) as bigint)")
    kind = F.conv(F.substring(F.md5(F.coalesce("event_type", F.lit("")).cast("binary")), 1, 8), 16, 10).cast("long")  # any type has a number of its own
    return e.select((F.shiftleft(hour, 32) + kind).alias("row_id"), F.col("user_id").alias("label")).distinct().select("row_id", "label", _one())


def customers_by_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Similar customers: a row for each part, a column for each customer who ordered it."""
    lines = load_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    orders = load_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("l_partkey").alias("row_id"), F.col("o_custkey").alias("label")).distinct().select("row_id", "label", _one())


def words_of(df: DataFrame, row_id, text: str = "text") -> DataFrame:
    words = F.regexp_extract_all(F.lower(F.col(text)), F.lit(r"(\p{L}+)"), 1)
    return df.select(row_id.alias("row_id"), F.explode(F.array_distinct(words)).alias("label")).select("row_id", "label", _one())


def words_by_turn(spark: SparkSession, sf_dir: str, support: int = 20) -> DataFrame:
    """Similar words: a row for each conversation turn, a column for each word of ``support`` turns or more."""
    turns = load_table(spark, sf_dir, "conversations").select((F.shiftleft("conv_id", 24) + F.col("turn")).alias("id"), "text")
    return min_support(words_of(turns, F.col("id")), support)


def words_by_document(spark: SparkSession, sf_dir: str, support: int = 20) -> DataFrame:
    """The same over long texts: heavy rows."""
    return min_support(words_of(load_table(spark, sf_dir, "documents").select("doc_id", "text"), F.col("doc_id")), support)


def user_day(user: str, ts: str):
    """Row of a user's day: the day, counted from 1970, in the low 20 bits."""
    return F.shiftleft(F.col(user), 20) + F.unix_date(F.to_date(ts))


def props_by_user_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The daily job: a row for each user and day, a column for each key in the event's props."""
    e = load_table(spark, sf_dir, "events")
    label = F.get_json_object("props", "$.k").cast("int")
    return e.select(user_day("user_id", "ts").alias("row_id"), label.alias("label")).where("label is not null").distinct().select("row_id", "label", _one())


def brands_by_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tall case: a row for each order, a column for each of few brands."""
    lines = load_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    part = load_table(spark, sf_dir, "part").select("p_partkey", "p_brand")
    return lines.join(part, F.col("l_partkey") == F.col("p_partkey")).select(F.col("l_orderkey").alias("row_id"), F.col("p_brand").alias("label")).distinct().select("row_id", "label", _one())


def suppliers_by_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load_table(spark, sf_dir, "lineitem")
    return lines.select(F.col("l_orderkey").alias("row_id"), F.col("l_suppkey").alias("label")).distinct().select("row_id", "label", _one())


def quantity_by_order_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weighted: the sum of quantities (whole numbers)."""
    lines = load_table(spark, sf_dir, "lineitem")
    return lines.groupBy(F.col("l_orderkey").alias("row_id"), F.col("l_suppkey").alias("label")).agg(F.sum("l_quantity").alias("val"))


def parts_by_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many columns."""
    lines = load_table(spark, sf_dir, "lineitem")
    return lines.select(F.col("l_orderkey").alias("row_id"), F.col("l_partkey").alias("label")).distinct().select("row_id", "label", _one())


LABELLED: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "w1": users_by_hour, "w1b": customers_by_part, "w2": lambda s, d: words_by_turn(s, d, 5), "w2b": words_by_turn, "w2c": words_by_document, "w3": props_by_user_day,
    "w4": brands_by_order, "w4b": suppliers_by_order, "w4c": quantity_by_order_supplier, "w4d": parts_by_order,
}


def documents_by_toxicity(spark: SparkSession, sf_dir: str, toxic: int) -> DataFrame:
    """Words of the documents that carry one label only, those of ``support`` such documents or more."""
    labels = load_table(spark, sf_dir, "labels").where(F.col("toxic") == toxic).select("doc_id").distinct()
    docs = load_table(spark, sf_dir, "documents").select("doc_id", "text").join(labels, "doc_id", "left_semi")
    return min_support(words_of(docs, F.col("doc_id")), 10)


LABELLED["w10"] = lambda s, d: documents_by_toxicity(s, d, 1)


def matrix(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Row form of a workload, columns numbered by label order. w5: embeddings (dense, signed)."""
    if name == "w5":
        return dense_rows(load_table(spark, sf_dir, "embeddings"), "vec_id", "embedding")
    return to_row_form(encode_columns(LABELLED[name](spark, sf_dir))[0])


def dictionary(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return encode_columns(LABELLED[name](spark, sf_dir))[1]


def triplets(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return encode_columns(LABELLED[name](spark, sf_dir))[0]


def regression(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Row form with response y: quantity, discount, tax and 1 against the extended price of each line."""
    lines = load_table(spark, sf_dir, "lineitem")
    values = F.array("l_quantity", "l_discount", "l_tax", F.lit(1.0))
    entry = F.transform(values, lambda x, i: F.struct(i.cast("int").alias("col"), x.alias("val")))
    return lines.select((F.shiftleft("l_orderkey", 16) + F.col("l_linenumber")).alias("row_id"), F.filter(entry, lambda e: e["val"] != 0).alias("entries"), F.col("l_extendedprice").alias("y"))


def block_matrix(spark: SparkSession, n: int, row_max: int) -> DataFrame:
    """n/L groups of L equal columns, each group's row repeated L times: any algorithm must output n (L-1)/2 pairs."""
    if n % row_max:
        raise ValueError("row_max must divide n")
    entry = lambda g: F.transform(F.sequence(g * row_max, g * row_max + row_max - 1), lambda c: F.struct(c.cast("int").alias("col"), F.lit(1.0).alias("val")))
    return spark.range(n).select(F.col("id").alias("row_id"), entry(F.expr(f"id div {row_max}")).alias("entries"))


def blocks_of_customers(spark: SparkSession, sf_dir: str, row_max: int) -> tuple[DataFrame, DataFrame]:
    """The same over the customers: groups of row_max keys in a row, a row and a column for each customer, its group's columns in its row.

    With it (size, groups): how many groups have how many customers.
    """
    key = load_table(spark, sf_dir, "customer").where("c_custkey is not null").select(F.col("c_custkey").alias("row_id")).distinct()
    group = key.groupBy(F.expr(f"row_id div {int(row_max)}").alias("block")).agg(F.collect_list("row_id").alias("keys"))
    labelled = group.select("keys", F.explode("keys").alias("row_id")).select("row_id", F.explode("keys").alias("label"), _one())
    return to_row_form(encode_columns(labelled)[0]), group.groupBy(F.size("keys").alias("size")).agg(F.count("*").alias("groups"))

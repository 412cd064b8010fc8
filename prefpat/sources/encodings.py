"""Ten encodings of the given tables as transactions.

Each gives the long form ``(tid, item, label)``. They cover dense and sparse, short
and long data; the support threshold is found by calibration, never fixed.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefpat.operators.encode import EncodedDataset, binarise, encode


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokens(text):
    """Lower-case ASCII words of three letters or more."""
    return F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit("([a-z]{3,})"), 1))


def emb_sign(spark, sf):
    signs = F.filter(F.transform("embedding", lambda x, i: F.when(x > 0, F.concat(F.lit("d"), F.lpad(i.cast("string"), 2, "0")))), lambda x: x.isNotNull())
    return binarise(table(spark, sf, "embeddings"), F.col("vec_id"), signs, F.col("label") < 5)


def doc_words(spark, sf):
    """The join gets a document's different words as one text, which is shorter than its own."""
    words = table(spark, sf, "documents").select("doc_id", F.array_join(tokens(F.col("text")), " ").alias("words"))
    labelled = words.join(table(spark, sf, "labels").select("doc_id", "quality"), "doc_id")
    return binarise(labelled, F.col("doc_id"), F.when(F.col("words") != "", F.split("words", " ")), F.col("quality") == 1)


def conv_words(spark, sf):
    turns = table(spark, sf, "conversations")
    system = turns.groupBy("conv_id").agg(F.max((F.col("role") == "system").cast("int")).alias("label"))
    return binarise(turns.select("conv_id", "text").join(system, "conv_id"), F.col("conv_id"), tokens(F.col("text")), F.col("label"))


def page_words(spark, sf):
    text = F.regexp_replace("html", "<[^>]*>", " ")
    return binarise(table(spark, sf, "pages"), F.col("page_id"), tokens(text), F.instr("html", '<html lang="en"') > 0)


def user_slots(spark, sf):
    events = table(spark, sf, "events").select("user_id", "event_type", "ts", "value")
    mean = events.agg(F.avg("value")).first()[0]
    users = events.groupBy("user_id").agg((F.avg("value") >= F.lit(mean)).cast("int").alias("label"))
    slot = F.concat_ws("/", "event_type", F.floor(F.dayofmonth("ts") / 4).cast("string"))
    return events.select("user_id", slot.alias("item")).distinct().join(users, "user_id").select(F.col("user_id").alias("tid"), "item", "label")


def customer_lines(spark, sf, columns):
    """Customers with all their lines' parts; customers without lines stay."""
    lines = table(spark, sf, "lineitem").select("l_orderkey", "l_partkey")
    orders = table(spark, sf, "orders").select("o_orderkey", "o_custkey")
    parts = table(spark, sf, "part").select("p_partkey", "p_type", "p_brand", "p_size")
    bought = lines.join(orders, lines.l_orderkey == orders.o_orderkey).join(parts, F.col("l_partkey") == parts.p_partkey)
    return table(spark, sf, "customer").select("c_custkey", "c_mktsegment", "c_acctbal").join(bought, F.col("c_custkey") == F.col("o_custkey"), "left").select(*columns)


def cust_parts(spark, sf):
    item = F.when(F.col("p_type").isNotNull(), F.concat_ws("/", "p_type", F.floor(F.col("p_size") / 10).cast("string")))
    rows = customer_lines(spark, sf, [F.col("c_custkey"), item.alias("item"), (F.col("c_mktsegment") == "BUILDING").alias("label")])
    return binarise(rows, F.col("c_custkey"), [F.col("item")], F.col("label"))


def cust_brands(spark, sf):
    rows = customer_lines(spark, sf, [F.col("c_custkey"), F.col("p_brand").alias("item"), (F.col("c_acctbal") >= 5000).alias("label")])
    return binarise(rows, F.col("c_custkey"), [F.col("item")], F.col("label"))


def supp_dates(spark, sf):
    lines = table(spark, sf, "lineitem").where("l_returnflag = 'R' and l_discount >= 0.05").select("l_suppkey", "l_shipdate")
    nations = table(spark, sf, "nation").join(F.broadcast(table(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_regionkey")
    suppliers = table(spark, sf, "supplier").join(F.broadcast(nations), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "r_regionkey")
    item = F.when(F.col("l_shipdate").isNotNull(), F.concat_ws("/", F.year("l_shipdate").cast("string"), F.floor(F.month("l_shipdate") / 2).cast("string")))
    return binarise(suppliers.join(lines, F.col("s_suppkey") == F.col("l_suppkey"), "left"), F.col("s_suppkey"), [item], F.col("r_regionkey") < 2)


def order_lines(spark, sf):
    """One transaction a line; only four columns together tell lines apart."""
    lines = table(spark, sf, "lineitem")
    orders = table(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderpriority")
    customers = table(spark, sf, "customer").select("c_custkey", "c_mktsegment")
    parts = table(spark, sf, "part").select("p_partkey", "p_type", "p_size")
    rows = lines.join(orders, lines.l_orderkey == orders.o_orderkey).join(customers, F.col("o_custkey") == F.col("c_custkey")).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    named = lambda name, value: F.concat(F.lit(name + "="), value.cast("string"))
    items = [
        named("status", F.col("l_linestatus")), named("quantity", F.floor(F.col("l_quantity") / 10)), named("discount", F.round(F.col("l_discount") * 100).cast("int")),
        named("tax", F.round(F.col("l_tax") * 100).cast("int")), named("priority", F.col("o_orderpriority")), named("segment", F.col("c_mktsegment")),
        named("type", F.col("p_type")), named("size", F.floor(F.col("p_size") / 10)), named("year", F.year("l_shipdate")),
    ]
    return binarise(rows, F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"), items, F.col("l_returnflag") == "R")


def part_supp(spark, sf):
    lines = table(spark, sf, "lineitem").select("l_partkey", "l_suppkey")
    rows = table(spark, sf, "part").select("p_partkey", "p_size").join(lines, F.col("p_partkey") == F.col("l_partkey"), "left")
    return binarise(rows, F.col("p_partkey"), [F.concat(F.lit("s"), (F.col("l_suppkey") % 20).cast("string"))], F.col("p_size") <= 25)


ENCODINGS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "emb_sign": emb_sign, "doc_words": doc_words, "conv_words": conv_words, "page_words": page_words, "user_slots": user_slots,
    "cust_parts": cust_parts, "cust_brands": cust_brands, "supp_dates": supp_dates, "order_lines": order_lines, "part_supp": part_supp,
}


def word_transactions(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """``(tid)``: the transactions of a word encoding, without a look at the texts."""
    if name == "doc_words":
        rows = table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels").select("doc_id"), "doc_id")
    elif name == "conv_words":
        rows = table(spark, sf_dir, "conversations").select("conv_id").where("conv_id is not null")
    else:
        rows = table(spark, sf_dir, "pages").select("page_id")
    return rows.toDF("tid").distinct()


def dataset(spark: SparkSession, sf_dir: str, name: str, min_sup: int = 1) -> EncodedDataset:
    """An encoded dataset; word encodings need a ``min_sup`` that cuts rare words."""
    return encode(ENCODINGS[name](spark, sf_dir), name, min_sup)

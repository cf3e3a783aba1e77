"""The experiment workloads on the given tables: which rows make the two sets, and what is asked of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from setoverlap.functions import textsets
from setoverlap.operators import exact, pairstats, registers
from setoverlap.session import materialised
from setoverlap.sources.tables import load_table

M = 64

# SQL of the same rows as the functions below: elements and their sides.
S_YEAR = "SELECT o_custkey AS e, year(o_orderdate) = 1995 AS in_a, year(o_orderdate) = 1996 AS in_b FROM orders"
S_STATUS = "SELECT o_custkey AS e, o_orderstatus = 'F' AS in_a, o_orderstatus = 'O' AS in_b FROM orders"
S_RETURN = "SELECT l_orderkey AS e, l_returnflag = 'R' AS in_a, l_returnflag = 'A' AS in_b FROM lineitem"
S_KEYS = "SELECT l_orderkey AS e, true AS in_a, false AS in_b FROM lineitem UNION ALL SELECT o_orderkey, false, true FROM orders"
S_FLOWS = "SELECT strftime(ts, '%Y-%m-%d') AS day, user_id AS e, event_type = 'click' AS in_a, event_type = 'purchase' AS in_b FROM events"


def customers_by_year(spark: SparkSession, d: str) -> DataFrame:
    y = F.year("o_orderdate")
    return load_table(spark, d, "orders").select(F.col("o_custkey").alias("e"), (y == 1995).alias("in_a"), (y == 1996).alias("in_b"))


def customers_by_status(spark: SparkSession, d: str) -> DataFrame:
    s = F.col("o_orderstatus")
    return load_table(spark, d, "orders").select(F.col("o_custkey").alias("e"), (s == "F").alias("in_a"), (s == "O").alias("in_b"))


def orders_by_return(spark: SparkSession, d: str) -> DataFrame:
    s = F.col("l_returnflag")
    return load_table(spark, d, "lineitem").select(F.col("l_orderkey").alias("e"), (s == "R").alias("in_a"), (s == "A").alias("in_b"))


def join_keys(spark: SparkSession, d: str) -> DataFrame:
    """Both sides of a join on order keys: the line side lies inside the order side."""
    lines = load_table(spark, d, "lineitem").select(F.col("l_orderkey").alias("e"), F.lit(True).alias("in_a"), F.lit(False).alias("in_b"))
    return lines.unionByName(load_table(spark, d, "orders").select(F.col("o_orderkey").alias("e"), F.lit(False).alias("in_a"), F.lit(True).alias("in_b")))


def shared_flows(spark: SparkSession, d: str, a: str = "click", b: str = "purchase") -> DataFrame:
    t = F.col("event_type")
    return load_table(spark, d, "events").select(F.date_format("ts", "yyyy-MM-dd").alias("day"), F.col("user_id").alias("e"), (t == a).alias("in_a"), (t == b).alias("in_b"))


def controlled(spark: SparkSession, d: str, ratio: int, overlap: float, a: int) -> DataFrame:
    """A = keys below a; B = [a - n, a - n + ratio a) with n = overlap a: the intersection is n by construction."""
    k, n = F.col("o_orderkey"), int(round(overlap * a))
    return load_table(spark, d, "orders").select(k.alias("e"), (k < a).alias("in_a"), ((k >= a - n) & (k < a - n + ratio * a)).alias("in_b"))


def stats_of(df: DataFrame, by: list[str] | tuple = (), m: int = M, family: str = "md5", layout: str = "k_hash") -> DataFrame:
    return pairstats.pair_stats(registers.pair_registers(df, "e", F.col("in_a"), F.col("in_b"), by, m, family, 0, layout), by, m, family, layout)


def exact_of(df: DataFrame, by: list[str] | tuple = ()) -> DataFrame:
    return exact.exact_sizes(df, "e", F.col("in_a"), F.col("in_b"), by)


def language_words(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "documents").select("lang", F.explode(F.array_distinct(textsets.words(F.col("text")))).alias("e"))


def document_shingles(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "documents").select("doc_id", F.explode(textsets.shingles(F.col("text"))).alias("e"))


def document_rows(spark: SparkSession, d: str) -> DataFrame:
    """doc_id (distinct), texts: nothing is shuffled but the texts of ids that are in several rows."""
    docs = load_table(spark, d, "documents").select("doc_id", "text").where("doc_id is not null and text is not null")
    again = materialised(docs.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id"))
    once = docs.join(again, "doc_id", "left_anti").select("doc_id", F.array("text").alias("texts"))
    return once.unionByName(docs.join(again, "doc_id", "left_semi").groupBy("doc_id").agg(F.collect_list("text").alias("texts")))


def shingle_hashes(hashed=F.xxhash64) -> Column:
    """The shingles of `texts` as an ordered array of distinct hashes; hashed: from a shingle to its hash."""
    return F.array_sort(F.array_distinct(F.flatten(F.transform("texts", lambda t: F.transform(textsets.shingles(t), lambda e: hashed(e))))))

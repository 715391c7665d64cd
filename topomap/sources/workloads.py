"""Feature sets on the given tables that stand in for gridded cloud histograms, and lists made for hand-checked examples."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.features import BINS, SHAPE, joint_histogram, minmax_scale, to_class
from .io import load

#: Edges of the classes of event values, near their septiles (fixed values).
VALUE_EDGES = [8.0, 17.0, 28.0, 42.0, 63.0, 96.0]


def _line_classes():
    a = F.least(F.lit(5), F.floor((F.col("l_quantity") - 1) * 6 / 50)).cast("int")
    b = F.floor(F.round(F.col("l_discount") * 100) * 7 / 11).cast("int")
    return a, b


def cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(l_suppkey, period, n, features, cloud_fraction): supplier by month of shipping, quantity by discount class, returns left uncounted."""
    rows = load(spark, sf_dir, "lineitem", "l_suppkey", "l_quantity", "l_discount", "l_returnflag", "l_shipdate").withColumn("period", F.date_trunc("month", "l_shipdate").cast("date"))
    return joint_histogram(rows, ["l_suppkey", "period"], *_line_classes(), counted=F.col("l_returnflag") != "N")


def nations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(n_nationkey, period, n, features, cloud_fraction): the same by the supplier's nation."""
    rows = load(spark, sf_dir, "lineitem", "l_suppkey", "l_quantity", "l_discount", "l_returnflag", "l_shipdate").withColumn("period", F.date_trunc("month", "l_shipdate").cast("date"))
    nation = load(spark, sf_dir, "supplier", F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("n_nationkey"))
    return joint_histogram(rows.join(nation, "l_suppkey"), ["n_nationkey", "period"], *_line_classes(), counted=F.col("l_returnflag") != "N")


def docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, n, features, cloud_fraction): word length by vowel share of each document; only plain words count.

    A document is one row: its words become a string with a character per bin, whose counts are differences of lengths. No shuffle, no row per word.
    """

    def code(w):
        size = F.length(w)
        a = F.least(F.lit(5), F.floor((size - 1) / 2)).cast("int")
        b = F.least(F.lit(6), F.floor(12.0 * (size - F.length(F.translate(F.lower(w), "aeiou", ""))) / size)).cast("int")
        return F.when(w.rlike(r"^\p{L}+[.,]?$"), F.char(a * SHAPE[1] + b + 48)).otherwise("!")

    words = load(spark, sf_dir, "documents", "doc_id", F.filter(F.split("text", r"\s+"), lambda w: w != "").alias("words")).where(F.size("words") > 0)
    # exploding an array of one keeps Catalyst from repeating the coding wherever its result is used
    coded = words.select("doc_id", F.explode(F.array(F.array_join(F.transform("words", code), ""))).alias("codes")).withColumn("n", F.length("codes").cast("long"))
    count = lambda k: F.col("n") - F.length(F.replace("codes", F.lit(chr(48 + k)), F.lit("")))
    plain = F.length(F.replace("codes", F.lit("!"), F.lit("")))
    return coded.select("doc_id", "n", F.array(*[count(k) / F.col("n") for k in range(BINS)]).alias("features"), (plain / F.col("n")).alias("cloud_fraction"))


def vectors(spark: SparkSession, sf_dir: str, dim: int = 64) -> DataFrame:
    """(vec_id, features): embeddings scaled per component."""
    raw = load(spark, sf_dir, "embeddings", "vec_id", F.col("embedding").cast("array<double>").alias("features"))
    return minmax_scale(raw, dim)


LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(all columns of lineitem as the key, features): four scaled numbers per order line."""
    raw = load(spark, sf_dir, "lineitem", *LINE_KEY).withColumn("features", F.array("l_quantity", "l_extendedprice", "l_discount", "l_tax"))
    return minmax_scale(raw, 4)


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(o_orderkey, c_mktsegment, features): price, customer's balance and day of each order, scaled."""
    o = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_totalprice", "o_orderdate")
    c = load(spark, sf_dir, "customer", F.col("c_custkey").alias("o_custkey"), "c_acctbal", "c_mktsegment")
    day = F.unix_date(F.col("o_orderdate").cast("date")).cast("double")
    return minmax_scale(o.join(c, "o_custkey").select("o_orderkey", "c_mktsegment", F.array("o_totalprice", "c_acctbal", day).alias("features")), 3)


def shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(n_nationkey, features): shares of returned and of large order lines of each nation's suppliers, scaled; a short list."""
    rows = load(spark, sf_dir, "lineitem", "l_suppkey", "l_quantity", "l_returnflag").join(load(spark, sf_dir, "supplier", F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("n_nationkey")), "l_suppkey")
    of_nation = rows.groupBy("n_nationkey").agg(F.array(F.count_if(F.col("l_returnflag") != "N") / F.count("*"), F.count_if(F.col("l_quantity") > 25) / F.count("*")).alias("features"))
    return minmax_scale(of_nation, 2)


def event_classes():
    return F.floor(F.hour("ts") / 4).cast("int"), to_class(F.col("value"), VALUE_EDGES)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, day, n, features, cloud_fraction): hour band by value class of each user's day; errors aren't counted."""
    rows = load(spark, sf_dir, "events", "user_id", "ts", "event_type", "value").withColumn("day", F.col("ts").cast("date"))
    return joint_histogram(rows, ["user_id", "day"], *event_classes(), counted=F.col("event_type") != "error")


TOY4 = [(0.0, 0.0), (0.0, 1.0), (1.0, 0.0), (1.0, 1.0)]
TOYBLOBS = [(cx + dx, cy + dy) for cx, cy in ((0.1, 0.1), (0.5, 0.9), (0.9, 0.2)) for dx, dy in [(x, y) for x in (-0.02, 0.0, 0.02) for y in (-0.02, 0.0, 0.02)][:8]]


def toy(spark: SparkSession, points: list[tuple[float, ...]] = TOYBLOBS) -> DataFrame:
    """(sample_id, features) of a short list."""
    return spark.createDataFrame([(i, [float(x) for x in p]) for i, p in enumerate(points)], "sample_id bigint, features array<double>")

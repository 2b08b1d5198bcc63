"""The experiment workloads on the given tables: each returns a TensorFrame."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .sources.tables import load_table
from .tensor import TensorFrame, build_tensor

def K():  # noqa: N802
    return F.get_json_object("props", "$.k").cast("long")



def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "events", ["ts", "user_id", "event_type", "value", "props"])


def _sales(spark: SparkSession, sf_dir: str, cols: list[str]) -> DataFrame:
    """lineitem with its order; AQE picks the join by size."""
    lines = load_table(spark, sf_dir, "lineitem", ["l_orderkey", *[c for c in cols if c.startswith("l_")]])
    orders = load_table(spark, sf_dir, "orders", ["o_orderkey", *[c for c in cols if c.startswith("o_")]])
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def w1(spark: SparkSession, sf_dir: str) -> TensorFrame:
    """user × event type × (hour, k); log(1 + Σ value)"""
    return build_tensor(_events(spark, sf_dir), [F.col("user_id"), F.col("event_type"), 100 * F.hour("ts") + K()], F.col("value"), "log1p_sum")


def w2a(spark: SparkSession, sf_dir: str) -> TensorFrame:
    """clicks: user × hour × k; log(1 + Σ value)"""
    return build_tensor(_events(spark, sf_dir).where("event_type = 'click'"), [F.col("user_id"), F.hour("ts"), K()], F.col("value"), "log1p_sum")


def w2b(spark: SparkSession, sf_dir: str) -> TensorFrame:
    """customer × supplier × brand; log revenue"""
    parts = load_table(spark, sf_dir, "part", ["p_partkey", "p_brand"])
    rows = _sales(spark, sf_dir, ["l_suppkey", "l_partkey", "l_extendedprice", "o_custkey"]).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return build_tensor(rows, ["o_custkey", "l_suppkey", "p_brand"], F.col("l_extendedprice"), "log_sum")


def w3(spark: SparkSession, sf_dir: str) -> TensorFrame:
    """customer × supplier × order month; presence"""
    month = F.year("o_orderdate") * 12 + F.month("o_orderdate")
    return build_tensor(_sales(spark, sf_dir, ["l_suppkey", "o_custkey", "o_orderdate"]), [F.col("o_custkey"), F.col("l_suppkey"), month], F.lit(1.0), "presence", "binary")


def w4(spark: SparkSession, sf_dir: str) -> TensorFrame:
    """part × (return flag, line status) × supplier; presence"""
    rows = load_table(spark, sf_dir, "lineitem", ["l_partkey", "l_returnflag", "l_linestatus", "l_suppkey"])
    return build_tensor(rows, [F.col("l_partkey"), F.concat("l_returnflag", "l_linestatus"), F.col("l_suppkey")], F.lit(1.0), "presence", "binary")


def w5(spark: SparkSession, sf_dir: str) -> TensorFrame:
    """customer × supplier × part; log price"""
    return build_tensor(_sales(spark, sf_dir, ["l_suppkey", "l_partkey", "l_extendedprice", "o_custkey"]), ["o_custkey", "l_suppkey", "l_partkey"], F.col("l_extendedprice"), "log_sum")


def word_presence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct (doc_id, source, lang, word): words of four letters or more, without digits."""
    docs = load_table(spark, sf_dir, "documents", ["doc_id", "text", "lang", "source"])
    words = F.regexp_extract_all(F.lower("text"), F.lit(r"(?<![\p{L}\p{N}])\p{L}{4,}(?![\p{L}\p{N}])"), F.lit(0))
    return docs.select("doc_id", "source", "lang", F.explode(F.array_distinct(words)).alias("word"))


def w6(spark: SparkSession, sf_dir: str, top: int | None = 400, low: int = 10, high: int = 200) -> TensorFrame:
    """source × language × word; presence. ``top`` most frequent words of those in low..high documents (ties by word)."""
    rows = word_presence(spark, sf_dir)
    if top is not None:
        freq = rows.groupBy("word").agg(F.count("*").alias("n")).where(F.col("n").between(low, high))
        rows = rows.join(F.broadcast(freq.orderBy(F.desc("n"), "word").limit(top).select("word")), "word")
    return build_tensor(rows, ["source", "lang", "word"], F.lit(1.0), "presence", "binary")


def w7(spark: SparkSession, sf_dir: str) -> TensorFrame:
    """part × supplier × (flag, status, ship month); presence"""
    rows = load_table(spark, sf_dir, "lineitem", ["l_partkey", "l_suppkey", "l_returnflag", "l_linestatus", "l_shipdate"])
    what = F.concat_ws("-", "l_returnflag", "l_linestatus", F.date_format("l_shipdate", "yyyy-MM"))
    return build_tensor(rows, [F.col("l_partkey"), F.col("l_suppkey"), what], F.lit(1.0), "presence", "binary")


def w8(spark: SparkSession, sf_dir: str) -> TensorFrame:
    """user × k × hour × minute; click or not"""
    click = F.when(F.col("event_type") == "click", 1.0).otherwise(0.0)
    return build_tensor(_events(spark, sf_dir), [F.col("user_id"), K(), F.hour("ts"), F.minute("ts")], click, "max", "binary")


def w8_day(spark: SparkSession, sf_dir: str, day: str, dims: tuple[int, ...]) -> TensorFrame:
    """One day's events with raw ids as indices, all of ``dims`` in use by any day."""
    click = F.when(F.col("event_type") == "click", 1.0).otherwise(0.0)
    rows = _events(spark, sf_dir).where(F.to_date("ts") == F.lit(day).cast("date"))
    return build_tensor(rows, [F.col("user_id"), K(), F.hour("ts"), F.minute("ts")], click, "max", "binary", dims=dims)


def w10(spark: SparkSession, sf_dir: str, side: int = 100) -> TensorFrame:
    """W5 folded to side × side × side; mean"""
    rows = _sales(spark, sf_dir, ["l_suppkey", "l_partkey", "l_extendedprice", "o_custkey"])
    fold = lambda c: F.pmod(F.col(c), F.lit(side))
    return build_tensor(rows, [fold("o_custkey"), fold("l_suppkey"), fold("l_partkey")], F.log("l_extendedprice"), "avg", dims=(side,) * 3)


def tiny(spark: SparkSession, sf_dir: str) -> TensorFrame:
    """customer region × supplier region × part type; mean price: a full grid"""
    nations = load_table(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
    cust = load_table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]).join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", F.col("n_regionkey").alias("c_region"))
    supp = load_table(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"]).join(F.broadcast(nations), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", F.col("n_regionkey").alias("s_region"))
    parts = load_table(spark, sf_dir, "part", ["p_partkey", "p_type"])
    rows = _sales(spark, sf_dir, ["l_suppkey", "l_partkey", "l_extendedprice", "o_custkey"])
    rows = rows.join(cust, F.col("o_custkey") == F.col("c_custkey")).join(supp, F.col("l_suppkey") == F.col("s_suppkey")).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return build_tensor(rows, ["c_region", "s_region", "p_type"], F.col("l_extendedprice"), "avg")


def planted(t: TensorFrame, binary: bool = False) -> TensorFrame:
    """W16: the cells of ``t`` with a smooth nonlinear response of hidden per-index sines; its median cuts the binary one."""
    a = [F.sin(0.7 * F.col(m) + (k + 1)) for k, m in enumerate(t.modes[:3])]
    y = F.sin(2 * a[0] * a[1]) + F.cos(a[2] - a[0])
    df = t.df.withColumn("y", y)
    if binary:
        cut = df.agg(F.percentile("y", 0.5).alias("m"))
        df = df.crossJoin(F.broadcast(cut)).withColumn("y", (F.col("y") > F.col("m")).cast("double")).drop("m")
    return TensorFrame(df, t.dims, "binary" if binary else "real")


def embedding_inputs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W15: (vec_id, x array<double> of 8, y planted)"""
    e = load_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    a = [8 * F.col("embedding")[k].cast("double") for k in range(3)]
    return e.select("vec_id", F.transform(F.slice("embedding", 1, 8), lambda v: v.cast("double")).alias("x"), (F.sin(2 * a[0] * a[1]) + F.cos(a[2] - a[0])).alias("y"))


TENSORS = {"w1": w1, "w2a": w2a, "w2b": w2b, "w3": w3, "w4": w4, "w5": w5, "w6": w6, "w7": w7, "w8": w8, "w10": w10, "tiny": tiny}

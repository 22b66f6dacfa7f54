"""Point sets derived from the tables. Each gives pid, coordinates and w; lattices also the integer cells they come from."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DAY = 86_400_000_000


def load(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None, where=None) -> DataFrame:
    """A table with only the columns asked for; column list and filter reach the Parquet scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where is not None:
        df = df.where(where)
    return df.select(*cols) if cols else df


def days_since(ts, day: str):
    """Whole days from day to ts."""
    return F.datediff(F.to_date(ts), F.lit(day).cast("date")).cast("long")


def exact_days(ts, day: str):
    """Days from day to ts, as a double."""
    return (F.unix_micros(ts.cast("timestamp")) - F.unix_micros(F.lit(f"{day} 00:00:00+00:00").cast("timestamp"))) / F.lit(float(DAY))


def lattice2d(spark, sf_dir, qx: int = 1, qy: int = 2100) -> DataFrame:
    li = load(spark, sf_dir, "lineitem", ["l_quantity", "l_extendedprice"])
    cells = li.select(F.floor(F.col("l_quantity") / qx).alias("gx"), F.floor(F.col("l_extendedprice") / qy).alias("gy"))
    p = cells.groupBy("gx", "gy").agg(F.count("*").alias("w"))
    return p.select((F.col("gx") * 1000 + F.col("gy")).alias("pid"), "gx", "gy", F.col("gx").cast("double").alias("x"), F.col("gy").cast("double").alias("y"), "w")


def lattice3d(spark, sf_dir) -> DataFrame:
    li = load(spark, sf_dir, "lineitem", ["l_quantity", "l_extendedprice", "l_shipdate"])
    cells = li.select(F.floor(F.col("l_quantity") / 5).alias("gx"), F.floor(F.col("l_extendedprice") / 10500).alias("gy"), F.floor(days_since(F.col("l_shipdate"), "1995-01-01") / 90).alias("gz"))
    p = cells.groupBy("gx", "gy", "gz").agg(F.count("*").alias("w"))
    pid = ((F.col("gx") * 1000 + F.col("gy")) * 1000 + F.col("gz")).alias("pid")
    return p.select(pid, "gx", "gy", "gz", *(F.col(f"g{d}").cast("double").alias(d) for d in "xyz"), "w")


def events2d(spark, sf_dir) -> DataFrame:
    e = load(spark, sf_dir, "events", ["event_id", "ts", "value"])
    return e.select(F.col("event_id").alias("pid"), exact_days(F.col("ts"), "2024-01-01").alias("x"), (F.col("value") / 10).alias("y"), F.lit(1).cast("long").alias("w"))


def events3d(spark, sf_dir) -> DataFrame:
    e = load(spark, sf_dir, "events", ["event_id", "ts", "value"])
    return e.select(F.col("event_id").alias("pid"), exact_days(F.col("ts"), "2024-01-01").alias("x"), F.hour(F.col("ts")).cast("double").alias("y"), (F.col("value") / 10).alias("z"), F.lit(1).cast("long").alias("w"))


def orders2d(spark, sf_dir) -> DataFrame:
    o = load(spark, sf_dir, "orders", ["o_orderkey", "o_orderdate", "o_totalprice"])
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey"]).groupBy("l_orderkey").agg(F.count("*").alias("n"))
    j = o.join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    return j.select(F.col("o_orderkey").alias("pid"), days_since(F.col("o_orderdate"), "1995-01-01").cast("double").alias("x"), (F.col("o_totalprice") / 1000).alias("y"), F.coalesce("n", F.lit(1)).cast("long").alias("w"))


def parts2d(spark, sf_dir) -> DataFrame:
    p = load(spark, sf_dir, "part", ["p_partkey", "p_size", "p_retailprice"])
    return p.select(F.col("p_partkey").alias("pid"), F.col("p_size").cast("double").alias("x"), F.col("p_retailprice").alias("y"), F.lit(1).cast("long").alias("w"))


def customers2d(spark, sf_dir) -> DataFrame:
    c = load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey", "c_acctbal"])
    n = load(spark, sf_dir, "orders", ["o_custkey"]).groupBy("o_custkey").agg(F.count("*").alias("n"))
    j = c.join(n, F.col("c_custkey") == F.col("o_custkey"), "left")
    return j.select(F.col("c_custkey").alias("pid"), F.col("c_nationkey").cast("double").alias("x"), (F.col("c_acctbal") / 100).alias("y"), F.greatest(F.coalesce("n", F.lit(0)), F.lit(1)).cast("long").alias("w"))


def docs2d(spark, sf_dir) -> DataFrame:
    d = load(spark, sf_dir, "documents", ["doc_id", "text", "n_chars"])
    lines = (F.length("text") - F.length(F.replace(F.col("text"), F.lit("\n"), F.lit(""))) + 1).cast("double")
    return d.select(F.col("doc_id").alias("pid"), F.log(1 + F.col("n_chars").cast("double")).alias("x"), lines.alias("y"), F.greatest(F.col("n_chars"), F.lit(1)).alias("w"))


def turns2d(spark, sf_dir) -> DataFrame:
    c = load(spark, sf_dir, "conversations", ["conv_id", "turn", "text"])
    return c.select((F.col("conv_id") * 100 + F.col("turn")).alias("pid"), F.col("conv_id").cast("double").alias("x"), F.col("turn").cast("double").alias("y"), F.length("text").cast("long").alias("w"))


def pages2d(spark, sf_dir) -> DataFrame:
    p = load(spark, sf_dir, "pages", ["page_id", "url", "html"])
    depth = (F.length("url") - F.length(F.replace(F.col("url"), F.lit("/"), F.lit("")))).cast("double")
    return p.select(F.col("page_id").alias("pid"), (F.length("html").cast("double") / 1000).alias("x"), depth.alias("y"), F.length("html").cast("long").alias("w"))


def tiny(spark, sf_dir) -> DataFrame:
    b = load(spark, sf_dir, "benchmark", ["item_id", "text"])
    return b.select(F.col("item_id").alias("pid"), F.col("item_id").cast("double").alias("x"), F.length("text").cast("double").alias("y"), F.lit(1).cast("long").alias("w"))


def embeddings(spark, sf_dir) -> DataFrame:
    """pid, v (array of doubles), label."""
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("pid"), F.col("embedding").cast("array<double>").alias("v"), "label")


def check_points(p: DataFrame, dims: list[str], on_bad: str = "raise") -> DataFrame | tuple[DataFrame, DataFrame]:
    """Finite coordinates and positive weights, or an error; on_bad='drop' gives (good, rejects) instead."""
    bad = F.lit(False)
    for d in dims:
        bad = bad | F.col(d).isNull() | F.isnan(d) | (F.abs(F.col(d)) == float("inf"))
    bad = bad | F.col("w").isNull() | ~(F.col("w") > 0)
    if on_bad == "drop":
        return p.where(~bad), p.where(bad)
    if p.where(bad).limit(1).count():
        raise ValueError("points have null, infinite or NaN coordinates, or weights that are not positive")
    return p

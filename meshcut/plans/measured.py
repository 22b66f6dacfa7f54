"""Measurements of simple splits on the tables, in the form of the published ones: a row for each graph and method.

A graph is the lattice of the line items of one return flag and line number (cells of quantity and price), its class their
least line status; methods are closed formulas of a cell: squares, stripes along either axis and along the diagonal. `n` is the number of line items, `cut` the number of neighbouring cells in different blocks,
`total_comm` the number of distinct (cell, other block) and `max_comm` the largest of a block. All are whole numbers, kept as
doubles where the published ones are. Timings are spans: for each event type and user the seconds from the first to the last
event, against the number of events.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshcut.sources import points

#: Method: block of a cell (gx, gy below 64), as text that both dialects read.
BLOCKS = {"squares": "(gx // 16) * 4 + gy // 16", "columns": "gx // 4", "rows": "gy // 4", "diagonal": "(gx + gy) // 8"}
_CELLS = "SELECT l_returnflag || l_linenumber AS graph, floor(l_quantity)::BIGINT AS gx, floor(l_extendedprice/2100)::BIGINT AS gy, min(l_linestatus) AS class, count(*) AS n FROM lineitem GROUP BY ALL"
_WAYS = "SELECT * FROM (VALUES (1,0),(0,1),(1,1)) s(i, j)"


def _rows_sql() -> str:
    blocks = " UNION ALL ".join(f"SELECT graph, '{m}' AS method, gx, gy, {b} AS block FROM cells" for m, b in BLOCKS.items())
    return (
        f"(WITH cells AS MATERIALIZED ({_CELLS}), ways AS ({_WAYS}), b AS MATERIALIZED ({blocks}), "
        "c AS MATERIALIZED (SELECT a.graph, a.method, a.block AS b1, o.block AS b2, a.gx AS x1, a.gy AS y1, o.gx AS x2, o.gy AS y2 FROM b a CROSS JOIN ways JOIN b o ON o.graph = a.graph AND o.method = a.method AND o.gx = a.gx+i AND o.gy = a.gy+j WHERE a.block <> o.block), "
        "v AS (SELECT graph, method, block, count(*) AS comm FROM (SELECT DISTINCT * FROM (SELECT graph, method, b1 AS block, x1, y1, b2 AS other FROM c UNION ALL SELECT graph, method, b2, x2, y2, b1 FROM c)) GROUP BY ALL), "
        "g AS (SELECT graph, min(class) AS class, sum(n)::BIGINT AS n FROM cells GROUP BY graph) "
        "SELECT graph, class, method, n, cut, max_comm, total_comm FROM (SELECT graph, method, count(*)::DOUBLE AS cut FROM c GROUP BY ALL) JOIN (SELECT graph, method, max(comm)::DOUBLE AS max_comm, sum(comm)::DOUBLE AS total_comm FROM v GROUP BY ALL) USING (graph, method) JOIN g USING (graph))"
    )


ROWS_SQL = f"SELECT * FROM {_rows_sql()}"
SPANS_SQL = "SELECT event_type AS method, count(*) AS n, (max(epoch_us(ts)) - min(epoch_us(ts)))/1000000.0::DOUBLE AS seconds FROM events GROUP BY event_type, user_id HAVING max(ts) > min(ts)"


def splits(spark, d) -> DataFrame:
    li = points.load(spark, d, "lineitem", ["l_returnflag", "l_linenumber", "l_quantity", "l_extendedprice", "l_linestatus"])
    graph = F.concat("l_returnflag", F.col("l_linenumber").cast("string"))
    cells = li.select(graph.alias("graph"), F.floor("l_quantity").alias("gx"), F.floor(F.col("l_extendedprice") / 2100).alias("gy"), "l_linestatus").groupBy("graph", "gx", "gy").agg(F.min("l_linestatus").alias("class"), F.count("*").alias("n"))
    sets = F.array(*(F.struct(F.lit(m).alias("method"), F.expr(b.replace("//", "div")).alias("block")) for m, b in BLOCKS.items()))
    b = cells.select("graph", "gx", "gy", F.inline(sets))
    ways = F.array(*(F.struct((F.col("gx") + i).alias("x2"), (F.col("gy") + j).alias("y2")) for i, j in ((1, 0), (0, 1), (1, 1))))
    ahead = b.select("graph", "method", F.col("block").alias("b1"), F.col("gx").alias("x1"), F.col("gy").alias("y1"), F.inline(ways))
    c = ahead.join(b.select("graph", "method", F.col("block").alias("b2"), F.col("gx").alias("x2"), F.col("gy").alias("y2")), ["graph", "method", "x2", "y2"]).where("b1 <> b2")
    side = lambda own, x, y, other: c.select("graph", "method", F.col(own).alias("block"), F.col(x).alias("x"), F.col(y).alias("y"), F.col(other).alias("other"))
    comm = reduce(DataFrame.unionByName, [side("b1", "x1", "y1", "b2"), side("b2", "x2", "y2", "b1")]).distinct().groupBy("graph", "method", "block").agg(F.count("*").alias("comm"))
    volume = comm.groupBy("graph", "method").agg(F.max("comm").cast("double").alias("max_comm"), F.sum("comm").cast("double").alias("total_comm"))
    cut = c.groupBy("graph", "method").agg(F.count("*").cast("double").alias("cut"))
    g = cells.groupBy("graph").agg(F.min("class").alias("class"), F.sum("n").alias("n"))
    return cut.join(volume, ["graph", "method"]).join(g, "graph").select("graph", "class", "method", "n", "cut", "max_comm", "total_comm")


def spans(spark, d) -> DataFrame:
    e = points.load(spark, d, "events", ["event_type", "user_id", "ts"]).withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    s = e.groupBy("event_type", "user_id").agg(F.count("*").alias("n"), (F.max("us") - F.min("us")).alias("us")).where("us > 0")
    return s.select(F.col("event_type").alias("method"), "n", (F.col("us") / 1000000).alias("seconds"))

"""Published measurements as rows: (graph, class, method, n, seconds, cut, max_comm, total_comm), and the scaling series.

Method names: kmeans (balanced k-means), hilbert, jagged, rcb, rib. Fixed values, as printed, seven large or small graphs.
"""

from __future__ import annotations

ROWS = [
    ("planar_250M", "2D", "kmeans", 250000000, 0.8308, 2037960.0, 2183.0, 2033939.0),
    ("planar_250M", "2D", "hilbert", 250000000, 0.227387, 2356510.0, 2918.0, 2349673.0),
    ("planar_250M", "2D", "jagged", 250000000, 0.228118, 2118810.0, 2214.0, 2114657.0),
    ("planar_250M", "2D", "rcb", 250000000, 0.857324, 2118220.0, 2211.0, 2113916.0),
    ("planar_2B", "2D", "kmeans", 2000000000, 6.0989, 5771443.0, 6136.0, 5754364.0),
    ("planar_2B", "2D", "hilbert", 2000000000, 1.87662, 6335780.0, 6807.0, 6314790.0),
    ("planar_2B", "2D", "jagged", 2000000000, 1.71619, 5994110.0, 6164.0, 5976573.0),
    ("planar_2B", "2D", "rcb", 2000000000, 6.66174, 5995910.0, 6137.0, 5978340.0),
    ("trace_579M", "2D", "kmeans", 578551252, 3.5417, 1144423.0, 2205.0, 1948602.0),
    ("trace_579M", "2D", "hilbert", 578551252, 0.812107, 1467320.0, 4054.0, 2689631.0),
    ("trace_579M", "2D", "jagged", 578551252, 0.570606, 1521740.0, 4644.0, 2551801.0),
    ("trace_579M", "2D", "rcb", 578551252, 2.03696, 1314980.0, 6988.0, 2189002.0),
    ("climate_14M", "2.5D", "kmeans", 14349744, 0.7744, 33135424.0, 1539.0, 680638.0),
    ("climate_14M", "2.5D", "hilbert", 14349744, 0.0193754, 33749900.0, 1500.0, 735964.0),
    ("climate_14M", "2.5D", "jagged", 14349744, 0.019648, 27472100.0, 1111.0, 641574.0),
    ("climate_14M", "2.5D", "rcb", 14349744, 0.0821395, 30447900.0, 1524.0, 642714.0),
    ("airway_31M", "3D", "kmeans", 30959144, 0.3588, 5823055.0, 6508.0, 5403716.0),
    ("airway_31M", "3D", "hilbert", 30959144, 0.0352704, 6613710.0, 8275.0, 6802889.0),
    ("airway_31M", "3D", "jagged", 30959144, 0.0234486, 5364660.0, 6062.0, 5482086.0),
    ("airway_31M", "3D", "rcb", 30959144, 0.0966411, 6188060.0, 6526.0, 5825470.0),
]
#: (method, p, seconds): 250 000 points a process, p from 32 to 8192.
WEAK = [(m, 32 << i, s) for m, series in {
    "kmeans": (1.1777, 0.7332, 0.9879, 0.9169, 0.8486, 0.8308, 0.9861, 1.1534, 1.857),
    "jagged": (0.167088, 0.17899, 0.225048, 0.225066, 0.236598, 0.228118, 0.258429, 0.317737, 0.387967),
    "rcb": (0.233472, 0.385619, 0.498269, 0.574832, 0.628763, 0.857324, 1.29032, 3.0004, 8.25635),
    "rib": (0.289242, 0.418331, 0.527584, 0.648111, 0.68487, 0.931585, 1.29113, 2.74664, 7.62787),
    "hilbert": (0.189501, 0.249101, 0.218983, 0.230684, 0.222965, 0.227387, 0.285534, 0.392267, 0.493067),
}.items() for i, s in enumerate(series)]
#: (method, p, seconds): 2 000 000 000 points, p from 1024 to 16384.
STRONG = [(m, 1024 << i, s) for m, series in {
    "kmeans": (6.0989, 3.3637, 1.887, 1.857, 2.3413),
    "jagged": (1.71619, 0.966196, 0.560776, 0.387967, 0.445028),
    "rcb": (6.66174, 4.35643, 4.00006, 8.25635, 24.6478),
    "rib": (7.44088, 4.72432, 4.11693, 7.62787, 23.2226),
    "hilbert": (1.87662, 0.921476, 0.60041, 0.493067, 0.64755),
}.items() for i, s in enumerate(series)]
COLUMNS = "graph string, class string, method string, n long, seconds double, cut double, max_comm double, total_comm double"


def values(rows, names: str) -> str:
    """The rows as a SQL table; every number is a double but whole ones, which stay integers."""
    cell = lambda v: f"'{v}'" if isinstance(v, str) else f"{v!r}::DOUBLE" if isinstance(v, float) else f"{v}::BIGINT"
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(cell, r)) + ')' for r in rows)}) t({names})"


ROWS_SQL = values(ROWS, "graph, class, method, n, seconds, cut, max_comm, total_comm")
WEAK_SQL = values(WEAK, "method, p, seconds")
STRONG_SQL = values(STRONG, "method, p, seconds")


def published(spark):
    return spark.createDataFrame(ROWS, COLUMNS)


def weak(spark):
    return spark.createDataFrame(WEAK, "method string, p long, seconds double")


def strong(spark):
    return spark.createDataFrame(STRONG, "method string, p long, seconds double")

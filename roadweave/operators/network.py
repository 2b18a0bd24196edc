"""A lattice road network by rule, and trajectories planted on it.

Rows are joined by side streets; columns only by arterials, which are faster.
All values follow from integers, so any engine can replay them.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

#: Side of the lattice, zones a side, and the arterial columns: ``FIRST`` and every ``STEP``-th after it.
SIDE, ZONES, FIRST, STEP = 80, 5, 4, 9


def vertices(spark: SparkSession, *, side: int = SIDE, zones: int = ZONES) -> DataFrame:
    """``(v, row, col, zone)``."""
    own = spark.range(side * side).select(F.col("id").alias("v"), (F.col("id") / side).cast("int").alias("row"), (F.col("id") % side).cast("int").alias("col"))
    return zoned(own, rows=zones, cols=zones, x="col", y="row", width=side, height=side)


def zoned(df: DataFrame, *, rows: int, cols: int, x: str, y: str, width: float, height: float) -> DataFrame:
    """Cell of a grid of equal rectangles over the bounding box, as the column ``zone``."""
    cell = lambda c, n, size: F.least(F.floor(F.col(c) * n / size), F.lit(n - 1))
    return df.withColumn("zone", (cell(y, rows, height) * cols + cell(x, cols, width)).cast("int"))


def segments(spark: SparkSession, *, side: int = SIDE, first: int = FIRST, step: int = STEP) -> DataFrame:
    """``(s, src, dst, length, travel_time)`` of all directed segments."""
    n = side * (side - 1)
    ids = spark.range(2 * n).withColumn("back", (F.col("id") >= n).cast("long")).withColumn("k", F.col("id") % n)
    row, col = (F.col("k") / (side - 1)).cast("long"), F.col("k") % (side - 1)
    left = row * side + col
    streets = ids.select(F.col("id").alias("s"), (left + F.col("back")).alias("src"), (left + 1 - F.col("back")).alias("dst"), (100 + 10 * (row % 7)).cast("double").alias("length"), F.lit(3).cast("long").alias("travel_time"))
    columns = len(range(first, side, step))
    ids = spark.range(columns * 2 * (side - 1)).withColumn("a", (F.col("id") / (2 * (side - 1))).cast("long")).withColumn("k", F.col("id") % (2 * (side - 1)))
    down, row = (F.col("k") >= side - 1).cast("long"), F.col("k") % (side - 1)
    top = row * side + first + step * F.col("a")
    arterials = ids.select(
        (F.col("id") + 2 * n).alias("s"), (top + side * down).alias("src"), (top + side * (1 - down)).alias("dst"), F.lit(200.0).alias("length"), (1 + _pace(F.lit(first) + step * F.col("a"), step)).cast("long").alias("travel_time")
    )
    return streets.unionByName(arterials)


def first_arterials(roads: DataFrame, *, side: int = SIDE) -> DataFrame:
    """``roads`` with a weight ``ranked``: travel time and, of equal times, the route by the first arterial."""
    column = F.when(F.col("src") % side == F.col("dst") % side, F.col("src") % side).otherwise(0)
    # A route has fewer than side * side steps, so columns never add up to a unit of time.
    return roads.withColumn("ranked", F.col("travel_time") * side**3 + column)


def _pace(col: Column, step: int) -> Column:
    return F.floor(col / step) % 2


@dataclass(frozen=True)
class PlantedClass:
    """A class: its departure and arrival zones, and the ranks of the orders that belong to it."""

    klass: str
    departure: int
    arrival: int
    first: int
    last: int


#: Class sizes 14, 19, 20, 20, 12: two classes share a departure, one crosses them, two are inverted.
CLASSES = (PlantedClass("1", 19, 5, 1, 14), PlantedClass("2", 11, 4, 1, 19), PlantedClass("3", 11, 24, 20, 39), PlantedClass("4", 2, 22, 1, 20), PlantedClass("5", 22, 2, 1, 12))


def interacting(kind: str, *, size: int = 15) -> tuple[PlantedClass, ...]:
    """Two classes that are apart, diverge from a departure, converge on an arrival, or are inverted."""
    pairs = {"none": ((19, 5), (2, 4)), "diverge": ((11, 4), (11, 24)), "converge": ((19, 5), (2, 5)), "inverse": ((2, 22), (22, 2))}
    (a, b), (c, d) = pairs[kind]
    after = size if a == c else 0
    return PlantedClass("1", a, b, 1, size), PlantedClass("2", c, d, after + 1, after + size)


def zone_pairs(spark: SparkSession, classes: int, *, zones: int = ZONES * ZONES, low: int = 10, high: int = 25, seed: int = 42) -> tuple[PlantedClass, ...]:
    """Random departure and arrival zones, never equal, and class sizes between the bounds, by integer hashing."""
    grid = spark.range(zones).select(F.col("id").alias("a")).crossJoin(spark.range(zones).select(F.col("id").alias("b"))).where("a <> b")
    chosen = grid.orderBy(F.pmod((F.col("a") * 7919 + F.col("b") * 104729 + seed) * 2654435761, F.lit(1_000_003)), "a", "b").limit(classes).collect()
    used: dict[int, int] = {}
    out = []
    for k, r in enumerate(chosen):
        size = low + (r["a"] * 31 + r["b"] * 17 + seed) % (high - low + 1)
        start = used.get(r["a"], 0)
        used[r["a"]] = start + size
        out.append(PlantedClass(str(k + 1), r["a"], r["b"], start + 1, start + size))
    return tuple(out)


def _endpoint(zone: Column, index: Column, span: int, side: int, zones: int) -> Column:
    width = side // zones
    offset = (width - span) // 2
    row = (zone / zones).cast("long") * width + offset + (index / span).cast("long")
    return row * side + (zone % zones) * width + offset + index % span


def planted_pairs(orders: DataFrame, customers: DataFrame, *, classes: tuple[PlantedClass, ...] = CLASSES, span: int = 2, side: int = SIDE, zones: int = ZONES) -> DataFrame:
    """``(t, klass, src, dst)``: orders of customers of a departure nation, ranked, with endpoints in the middle of both zones."""
    spark = orders.sparkSession
    table = spark.createDataFrame([(c.klass, c.departure, c.arrival, c.first, c.last) for c in classes], "klass string, dep int, arr int, first int, last int")
    of = customers.select("c_custkey", F.col("c_nationkey").alias("dep")).join(F.broadcast(table.select("dep").distinct()), "dep")
    mine = orders.join(of, orders["o_custkey"] == of["c_custkey"]).withColumn("rank", F.row_number().over(Window.partitionBy("dep").orderBy("o_orderkey")))
    mine = mine.where(F.col("rank") <= max(c.last for c in classes)).join(F.broadcast(table), "dep").where("rank between first and last")
    square = span * span
    return mine.select(
        F.col("o_orderkey").cast("long").alias("t"),
        "klass",
        _endpoint(F.col("dep"), F.col("o_custkey") % square, span, side, zones).cast("long").alias("src"),
        _endpoint(F.col("arr"), (F.col("o_orderkey") * 31 + 7) % square, span, side, zones).cast("long").alias("dst"),
    )


def all_pairs(orders: DataFrame, *, side: int = SIDE) -> DataFrame:
    """Every order as a trajectory, for the larger runs: endpoints by integer hashing."""
    n = side * side
    src, dst = F.pmod(F.col("o_custkey") * 7919 + 13, F.lit(n)), F.pmod(F.col("o_orderkey") * 104729 + 7, F.lit(n))
    return orders.select(F.col("o_orderkey").cast("long").alias("t"), F.lit(None).cast("string").alias("klass"), src.cast("long").alias("src"), dst.cast("long").alias("dst"))


def noisy_labels(pairs: DataFrame, percent: int, *, side: int = SIDE) -> DataFrame:
    """A share of the trajectories ends anywhere on the lattice instead of in its zone."""
    odd = F.pmod(F.col("t") * 48271 + 11, F.lit(100)) < percent
    anywhere = F.pmod(F.col("t") * 69621 + 5, F.lit(side * side))
    return pairs.withColumn("dst", F.when(odd, anywhere).otherwise(F.col("dst")))


def noisy_paths(seq: DataFrame, percent: int) -> DataFrame:
    """A share of the path's segments is missing."""
    return seq.where(F.pmod((F.col("t") * 31 + F.col("pos")) * 48271 + 3, F.lit(100)) >= percent)

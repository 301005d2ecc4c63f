"""Counts over the plane of coordinates: estimates of valid sets, local density, a choice of method."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def grid(objects: DataFrame, cells: int = 64) -> tuple[DataFrame, tuple]:
    """(i, j, n) of objects with coordinates x and y in cells x cells of equal width, and the bounds (x0, width of i, y0, width of j). At most cells * cells rows."""
    x0, x1, y0, y1 = objects.agg(F.min("x"), F.max("x"), F.min("y"), F.max("y")).first()
    if x0 is None:
        x0 = x1 = y0 = y1 = 0.0
    frame = (x0, (x1 - x0) / cells or 1.0, y0, (y1 - y0) / cells or 1.0)
    n = objects.groupBy(place("x", frame[0], frame[1], cells).alias("i"), place("y", frame[2], frame[3], cells).alias("j")).agg(F.count(F.lit(1)).alias("n"))
    return n, frame


def place(c: str, low: float, width: float, cells: int):
    return F.least(F.greatest(F.floor((F.col(c) - F.lit(low)) / F.lit(width)), F.lit(-1)), F.lit(cells)).cast("int") if c.endswith("q") else F.least(F.floor((F.col(c) - F.lit(low)) / F.lit(width)), F.lit(cells - 1)).cast("int")


def bounds(queries: DataFrame, cells_n: DataFrame, frame: tuple, cells: int = 64) -> DataFrame:
    """qid, low, high: the valid objects of queries (qid, xq, yq) lie between the count of cells wholly inside their quadrant and of those it touches.

    The grid has a bounded number of rows, and is broadcast.
    """
    x0, w, y0, h = frame
    q = queries.select("qid", place("xq", x0, w, cells).alias("qi"), place("yq", y0, h, cells).alias("qj"))
    # The last cell also holds the greatest coordinate, so a query beyond it touches nothing, and one inside it touches the cell.
    touch = (F.col("i") >= F.least("qi", F.lit(cells - 1))) & (F.col("j") <= F.col("qj")) & (F.col("qi") <= cells)
    inside = (F.col("i") > F.col("qi")) & (F.col("j") < F.col("qj"))
    met = q.join(F.broadcast(cells_n), touch, "left")
    return met.groupBy("qid").agg(F.coalesce(F.sum(F.when(inside, F.col("n"))), F.lit(0)).alias("low"), F.coalesce(F.sum("n"), F.lit(0)).alias("high"))


def choose(est: DataFrame, scan_below: int) -> DataFrame:
    """qid, how: `empty` where nothing can be valid, `scan` where few can, else `walk`."""
    return est.select("qid", F.when(F.col("high") == 0, "empty").when(F.col("high") <= scan_below, "scan").otherwise("walk").alias("how"))


def density(objects: DataFrame, width: float) -> DataFrame:
    """oid, n: objects with y in [own y - width, own y]. Strips as wide as the range; each also gets the strip before it, so no window spans the table."""
    strip = F.floor(F.col("y") / width).cast("long")
    both = objects.select("oid", "y", F.explode(F.array(F.struct(strip.alias("strip"), F.lit(True).alias("own")), F.struct((strip + 1).alias("strip"), F.lit(False).alias("own")))).alias("z")).select("oid", "y", "z.*")
    n = F.expr(f"count(1) OVER (PARTITION BY strip ORDER BY y RANGE BETWEEN CAST({float(width)!r} AS DOUBLE) PRECEDING AND CURRENT ROW)")
    return both.withColumn("n", n).where("own").select("oid", "n")


def states(objects: DataFrame) -> DataFrame:
    """xs, ys: the numbers of thresholds, exact and by a sketch; their product bounds the states."""
    return objects.agg(F.count_distinct("x").alias("xs"), F.count_distinct("y").alias("ys"), F.approx_count_distinct("x", 0.02).alias("about_xs"), F.approx_count_distinct("y", 0.02).alias("about_ys"))


def successors(numbered: DataFrame) -> DataFrame:
    """val, next: each threshold (val, rank) and the one after it, by a join of ranks."""
    after = numbered.select((F.col("rank") - 1).alias("rank"), F.col("val").alias("next"))
    return numbered.join(after, "rank", "left").select("val", "next")

"""Regions of the map, and how many typical paths each gets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from ..functions.shared import ranked


def tile(rank, n, k: int):
    """Which of k tiles, from 0, a rank of n lies in; the first n % k tiles have one more."""
    rank = F.col(rank) if isinstance(rank, str) else rank
    small, more = F.floor(n / k), n % k
    wide = more * (small + 1)
    return F.when(rank < wide, F.floor(rank / (small + 1))).otherwise(more + F.floor((rank - wide) / F.nullif(small, F.lit(0)))).cast("bigint")


def grid(vertices: DataFrame, rows: int = 4, cols: int = 4, mode: str = "area") -> DataFrame:
    """Vertices with their region: equal-area cells of the bounding box, or stripes of equal vertex counts."""
    if mode == "count":
        n = vertices.count()
        striped = ranked(vertices, "y", "vid", name="_rank").withColumn("_row", tile("_rank", F.lit(n), rows)).drop("_rank")
        placed = ranked(striped, "_row", "x", "vid", name="_rank")
        inside = placed.groupBy("_row").agg(F.min("_rank").alias("_least"), F.count("*").alias("_n"))  # a row per stripe
        col = tile(F.col("_rank") - F.col("_least"), F.col("_n"), cols)
        return placed.join(F.broadcast(inside), "_row").withColumn("region", (F.col("_row") * cols + col).cast("int")).drop("_row", "_rank", "_least", "_n")
    box = vertices.agg(F.min("x").alias("x0"), F.min("y").alias("y0"), (F.max(F.greatest("x", "y")) + 1).alias("side"))
    placed = vertices.crossJoin(F.broadcast(box)).withColumn("width", F.col("side") - F.least("x0", "y0"))
    region = F.expr(f"cast(({rows} * (y - y0) div width) * {cols} + {cols} * (x - x0) div width as int)")
    return placed.withColumn("region", region).drop("x0", "y0", "side", "width")


def quota(regioned: DataFrame, pnum: int) -> DataFrame:
    """(region, quota): shares of `pnum` in proportion to vertices, largest remainders rounded up, total pnum."""
    count = regioned.groupBy("region").agg(F.count("*").alias("n"))
    share = count.crossJoin(count.agg(F.sum("n").alias("all"))).selectExpr("region", f"{pnum} * n div all as base", f"({pnum} * n) % all as rest")
    rank = F.row_number().over(Window.orderBy(F.desc("rest"), "region"))  # a row per region
    left = share.agg((F.lit(pnum) - F.sum("base")).alias("left"))
    return share.withColumn("rank", rank).crossJoin(left).select("region", (F.col("base") + F.when(F.col("rank") <= F.col("left"), 1).otherwise(0)).alias("quota"))

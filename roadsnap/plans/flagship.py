"""The headline query: vertex sets around the most fluctuating intersections, complete linkage, medoids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..sources import nets
from . import methods


def typical_quarters(spark: SparkSession, sf_dir: str, q: int = 8, k: int = 6) -> DataFrame:
    net = nets.grid_net(spark, sf_dir)
    return methods.select_typical(methods.Study(net, net.snapshots.count(), 60_000, q), "vertex_set", k)

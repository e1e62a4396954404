"""Path functions: native twins on arrays, and a table function for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def path_edges(paths: DataFrame, path: str = "path") -> DataFrame:
    """An array of nodes -> ``pos, fid, tid`` rows, natively; other columns stay."""
    pairs = F.zip_with(F.slice(path, F.lit(1), F.size(path) - 1), F.slice(path, F.lit(2), F.size(path) - 1), lambda a, b: F.struct(a.alias("fid"), b.alias("tid")))
    rest = [c for c in paths.columns if c != path]
    out = paths.where(F.size(path) > 1).select(*rest, F.posexplode(pairs).alias("pos", "edge"))
    return out.select(*rest, "pos", "edge.fid", "edge.tid")


def path_cost(costs: Column) -> Column:
    return F.aggregate(costs, F.lit(0).cast("long"), lambda a, x: a + x.cast("long"))


class _PathEdges:
    def eval(self, path: list) -> Iterator[tuple]:
        for k, (a, b) in enumerate(zip(path or (), (path or ())[1:], strict=False)):
            yield k, a, b


def register(spark: SparkSession) -> None:
    """``path_edges(array<bigint>)`` for SQL."""
    spark.udtf.register("path_edges", F.udtf(_PathEdges, returnType="pos int, fid bigint, tid bigint"))

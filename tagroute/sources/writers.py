from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_by_cell(df: DataFrame, path: str, groups: int = 64) -> None:
    """Parquet in files by group of cells: a group holds many cells, so files stay few and cells can be pruned by min/max."""
    df.withColumn("cell_group", F.pmod(F.hash("cell"), groups)).repartition("cell_group").sortWithinPartitions("cell").write.mode("overwrite").partitionBy("cell_group").parquet(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int = 32) -> None:
    """A table bucketed and sorted by a key, for joins without a shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(name)


def write_geojson_lines(routes: DataFrame, vertices: DataFrame, path: str) -> None:
    """One GeoJSON feature a line for each route of (qid, rank, path)."""
    points = routes.select("qid", "rank", F.posexplode("path").alias("i", "v")).join(vertices, "v")
    lines = points.groupBy("qid", "rank").agg(F.array_sort(F.collect_list(F.struct("i", "x", "y"))).alias("p")).select(
        F.to_json(F.struct(F.lit("Feature").alias("type"), F.struct("qid", "rank").alias("properties"), F.struct(F.lit("LineString").alias("type"), F.transform("p", lambda q: F.array(q["x"], q["y"])).alias("coordinates")).alias("geometry"))).alias("value")
    )
    lines.write.mode("overwrite").text(path)

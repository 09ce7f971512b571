"""Sinks: ratings by band, subset manifests, JSON-lines exports."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_ratings(ranked: DataFrame, path: str, bands: int = 10) -> None:
    """Partitioned by percentile band, so that a discarded head is never read again."""
    band = F.least(F.floor(F.col("pct") * bands), F.lit(bands - 1)).cast("int")
    ranked.withColumn("band", band).repartition(bands, "band").write.partitionBy("band").mode("overwrite").parquet(path)


def read_ratings(spark: SparkSession, path: str, from_pct: float = 0.0, bands: int = 10) -> DataFrame:
    """Whole bands below from_pct are pruned at the scan."""
    return spark.read.parquet(path).where((F.col("band") >= int(from_pct * bands)) & (F.col("pct") >= from_pct))


def export_subset(corpus: DataFrame, selected: DataFrame, id_col: str, path: str, form: str = "parquet") -> None:
    """The selected samples' rows; form json writes a training export of JSON lines."""
    kept = corpus.join(selected.select(id_col), id_col, "left_semi")
    kept.write.mode("overwrite").format(form).save(path)


def write_manifest(selected: DataFrame, id_col: str, path: str, version: str) -> None:
    selected.select(id_col, F.lit(version).alias("version")).write.mode("overwrite").parquet(path)

"""Clustering as a stage of a pipeline: fit on edges, transform rows with an ``id``."""

from __future__ import annotations

from pyspark.ml import Estimator, Model
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ripplegraph.operators.cluster import wave_cluster


class WaveModel(Model):
    """Labels of one graph; rows of unknown ids get nulls."""

    def __init__(self, labels: DataFrame | None = None) -> None:
        super().__init__()
        self.labels = labels

    def _transform(self, dataset: DataFrame) -> DataFrame:
        own = self.labels.select("id", "cluster", "group_rep", array_to_vector(F.col("bits").cast("array<double>")).alias("features"))
        return dataset.join(own, "id", "left")


class WaveClusterer(Estimator):
    """``fit`` takes edges ``(src, dst, w)``; options are those of ``wave_cluster``."""

    def __init__(self, **options) -> None:
        super().__init__()
        self.options = options

    def _fit(self, dataset: DataFrame) -> WaveModel:
        return WaveModel(wave_cluster(dataset.sparkSession, dataset, **self.options))


def as_arrays(df: DataFrame, column: str) -> DataFrame:
    """Vectors of a column as arrays of doubles; arrays stay as they are."""
    is_vector = "vector" in df.schema[column].dataType.simpleString()
    return df.withColumn(column, vector_to_array(column)) if is_vector else df

"""Results as text or tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def prediction_lines(predictions: DataFrame, sep: str = "\t") -> DataFrame:
    """(value): id, true label (empty if unknown) and predicted label."""
    cell = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    return predictions.select(F.concat_ws(sep, cell("sample_id"), cell("label"), cell("predicted")).alias("value"))


def write_predictions(predictions: DataFrame, path: str, sep: str = "\t", form: str = "parquet") -> None:
    if form == "text":
        prediction_lines(predictions, sep).write.mode("overwrite").text(path)
    else:
        predictions.write.mode("overwrite").format(form).save(path)

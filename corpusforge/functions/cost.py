"""What identification of a snapshot costs."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame


def wall_hours(documents, jobs, sentences_per_document, sentences_per_second, documents_per_second):
    """Hours for documents spread over jobs, each document costing one call and one more for each sentence. Numbers or columns."""
    return documents / jobs * (sentences_per_document / sentences_per_second + 1 / documents_per_second) / 3600


def rows_per_second(df: DataFrame, n: int) -> float:
    """Throughput of a plan into a sink that keeps nothing."""
    began = time.time()
    df.write.format("noop").mode("overwrite").save()
    return n / (time.time() - began)

"""Small helpers around the session: shared folder, sizes, document columns."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..plans.store import forget, keep, shared_folder, stored  # noqa: F401
from ._text import release


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def with_columns(docs: DataFrame, text_col: str, compute, new: StructType, *, replace: bool = False, rows: int = 1000) -> DataFrame:
    """All columns of ``docs`` and those that ``compute(texts)`` makes of the text column (an Arrow array).

    With ``replace`` its one result takes the place of the text column. Slices of ``rows``
    rows bound the memory of a worker.
    """
    at = docs.columns.index(text_col)
    schema = docs.schema if replace else StructType([*docs.schema.fields, *new.fields])
    names = schema.names

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, rows):
                part = batch.slice(a, rows)
                made = compute(part.column(at))
                columns = [made[0] if k == at else c for k, c in enumerate(part.columns)] if replace else [*part.columns, *made]
                yield pa.RecordBatch.from_arrays(columns, names=names)
            release()

    return docs.mapInArrow(run, schema)


def text_bytes(docs: DataFrame, text: str = "text") -> int:
    """Bytes of all texts; sizes chunks and buckets."""
    return int(docs.agg(F.sum(F.octet_length(F.col(text))).alias("b")).first()["b"] or 0)

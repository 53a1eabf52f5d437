"""Python functions at the edges of the design; none of them is in a loop."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def cosine_pd(a: pd.Series, b: pd.Series) -> pd.Series:
    """Cosine of two vector columns."""
    x, y = np.stack(a.to_numpy()).astype(float), np.stack(b.to_numpy()).astype(float)
    return pd.Series((x * y).sum(axis=1) / np.sqrt((x * x).sum(axis=1) * (y * y).sum(axis=1)))


@F.pandas_udf(T.LongType())
def min_label_pd(label: pd.Series) -> int:
    """Grouped minimum."""
    return int(label.min())


@F.udtf(returnType=T.StructType([T.StructField("line", T.StringType()), T.StructField("length", T.IntegerType())]))
class LineEdges:
    """The trimmed lines of a text that are long enough."""

    def eval(self, text: str, least: int):
        for line in (text or "").split("\n"):
            line = line.strip(" ")
            if len(line) >= least:
                yield line, len(line)


@F.pandas_udf(T.DoubleType())
def weight_pd(quantity: pd.Series, discount: pd.Series) -> pd.Series:
    """Weight of an edge from a line: its quantity after the discount."""
    return quantity * (1 - discount)


def local_contract(edges: DataFrame, most: int = 1_000_000) -> DataFrame:
    """Union-find inside each partition before anything is shuffled: same components, fewer edges.

    Up to ``most`` edges at a time merge into the stars of a forest; when these fill half
    of the room they leave as edges, so memory is bounded whatever the partition.
    """

    def stars(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Each vertex with the least of its component: labels fall by neighbours and jumps until they rest."""
        ids, code = np.unique(np.concatenate([src, dst]), return_inverse=True)
        a, b = code[: len(src)], code[len(src) :]
        label = np.arange(len(ids))
        while True:
            least = label.copy()
            low = np.minimum(label[a], label[b])
            np.minimum.at(least, label[a], low)
            np.minimum.at(least, label[b], low)
            least = least[least]
            if (least == label).all():
                break
            label = least
        return ids, ids[label]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        rows = 0

        def contracted() -> tuple[np.ndarray, np.ndarray]:
            return stars(*(np.concatenate(x) for x in zip(*held, strict=True)))

        for batch in batches:
            table = pa.Table.from_batches([batch]).drop_null()
            held.append((table["src"].to_numpy(), table["dst"].to_numpy()))
            rows += table.num_rows
            if rows > most:
                src, dst = contracted()
                if 2 * len(src) > most:  # little was won: make room
                    yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst)], names=["src", "dst"])
                    src, dst = src[:0], dst[:0]
                held, rows = [(src, dst)], len(src)
        src, dst = contracted()
        yield pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64())], names=["src", "dst"])

    return edges.select("src", "dst").mapInArrow(run, "src long, dst long")

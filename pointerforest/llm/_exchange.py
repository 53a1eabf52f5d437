"""Questions from chunks of documents to hash buckets, and the answers back.

Documents are dealt to chunks by the hash of their id (a few MB of text each). A
chunk combines what it knows before it asks: one entry for each distinct hash,
however often it occurs in the chunk. So a passage that a third of all documents
share costs a bucket one entry per chunk, and no key gathers its rows anywhere.
Entries travel as packed arrays, one row per (chunk, bucket).

Chunks and buckets grow with the bytes of text; their size stays.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import text_bytes
from ._text import release

CHUNK_BYTES = 4 << 20
#: Few chunks or buckets would leave cores idle.
LEAST = 96
MAIL = pa.schema([("to", pa.int32()), ("sender", pa.int32()), ("payload", pa.binary())])
MAIL_DDL = "to int, sender int, payload binary"


class Chunked:
    """Documents by chunk, and rounds of mail between chunks and buckets."""

    def __init__(self, docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", chunk_bytes: int = CHUNK_BYTES, extra: list | None = None, squeeze: bool = False, spread_nulls: bool = False):
        """``squeeze``: texts travel compressed one by one, which takes time and saves disk.
        ``spread_nulls``: rows without an id are dealt by their text; otherwise they share a chunk, as one document's rows do.
        """
        self.count = self.buckets = max(LEAST, -(-text_bytes(docs, text_col) // chunk_bytes))
        home = F.xxhash64(F.col(id_col))
        if spread_nulls:
            home = F.when(F.col(id_col).isNull(), F.xxhash64(F.col(text_col))).otherwise(home)
        key = F.pmod(home, F.lit(self.count)).cast("int")
        rows = docs.select(key.alias("chunk"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), *(extra or []))
        self.parts = max(16, self.count // 3)  # tasks grow with the text, whatever the session's shuffle partitions are
        self.squeezed = squeeze
        if squeeze:
            rows = squeezed(rows)
        self.rows = rows.repartition(self.parts, "chunk")

    def ask(self, emit: Callable[[pa.Table], pa.Table]) -> DataFrame:
        """First questions, from the documents alone."""
        return self.rows.groupBy("chunk").applyInArrow(_one(emit, self.squeezed), MAIL_DDL)

    def replies(self, asked: DataFrame, resolve: Callable[[list[bytes]], list[bytes]]) -> DataFrame:
        """Each bucket reads what all chunks sent and answers each of them.

        Mail to a negative number is a chunk's note to itself and passes through.
        """

        def run(key, table):
            table = table.combine_chunks()
            bucket = key[0].as_py()
            sender, payload = table["sender"], table["payload"].to_pylist()
            out = payload if bucket < 0 else resolve(payload)
            return pa.table([sender.combine_chunks(), pa.array([bucket] * len(out), pa.int32()), pa.array(out, pa.binary())], schema=MAIL)

        return self.dealt(asked).applyInArrow(run, MAIL_DDL)

    def dealt(self, asked: DataFrame):
        """Mail by its bucket, a few buckets a task."""
        return asked.repartition(self.parts, "to").groupBy("to")

    def then(self, answers: DataFrame, step: Callable[[pa.Table, dict], pa.Table], ddl: str = MAIL_DDL) -> DataFrame:
        """Documents of a chunk together with the answers it got."""
        return self.rows.groupBy("chunk").cogroup(answers.groupBy("to")).applyInArrow(_both(step, self.squeezed), ddl)


def _one(emit, squeeze: bool):
    def run(t):
        out = emit(in_order(unsqueezed(t) if squeeze else t))
        release()
        return out

    return run


def _both(step, squeeze: bool):
    def run(t, m):
        out = step(in_order(unsqueezed(t) if squeeze else t), mailbox(m))
        release()
        return out

    return run


def squeezed(rows: DataFrame) -> DataFrame:
    """Column ``text`` as zstd frames; null stays null."""

    def run(batches):
        import zstandard

        pack = zstandard.ZstdCompressor(level=3, write_content_size=True, write_checksum=False, write_dict_id=False)
        for batch in batches:
            at = batch.schema.get_field_index("text")
            for a in range(0, batch.num_rows, 2000):
                part = batch.slice(a, 2000)
                texts = pa.array([None if t is None else pack.compress(t) for t in part.column(at).cast(pa.binary()).to_pylist()], pa.binary())
                yield pa.RecordBatch.from_arrays([texts if k == at else part.column(k) for k in range(part.num_columns)], names=part.schema.names)

    kinds = ", ".join(f"{f.name} {'binary' if f.name == 'text' else f.dataType.simpleString()}" for f in rows.schema)
    return rows.mapInArrow(run, kinds)


def unsqueezed(table: pa.Table) -> pa.Table:
    import zstandard

    unpack = zstandard.ZstdDecompressor()
    at = table.schema.get_field_index("text")
    texts = pa.array([None if t is None else unpack.decompress(t) for t in table["text"].to_pylist()], pa.binary())
    return table.set_column(at, "text", texts)


def in_order(table: pa.Table) -> pa.Table:
    """Documents by id (nulls first), rows that repeat an id by text."""
    table = table.combine_chunks()
    return table.sort_by([("doc_id", "ascending"), ("text", "ascending")]) if table.num_rows > 1 and table["doc_id"].null_count == 0 else table.take(pc.sort_indices(table.select(["doc_id", "text"]), sort_keys=[("doc_id", "ascending"), ("text", "ascending")], null_placement="at_start")) if table.num_rows else table


def mailbox(table: pa.Table) -> dict[int, bytes]:
    """Payload by sender."""
    return dict(zip(table["sender"].to_pylist(), table["payload"].to_pylist(), strict=True))


def note_to_self(chunk: int) -> int:
    return -1 - chunk


def mail(sender: int, to: np.ndarray, payloads: list[bytes]) -> pa.Table:
    return pa.table([pa.array(to, pa.int32()), pa.array(np.full(len(to), sender), pa.int32()), pa.array(payloads, pa.binary())], schema=MAIL)


def cut(sorted_buckets: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bucket numbers that occur in a sorted array, with start and end of each."""
    edge = np.searchsorted(sorted_buckets, np.arange(buckets + 1))
    used = np.flatnonzero(edge[1:] > edge[:-1])
    return used, edge[used], edge[used + 1]


def repeated_elsewhere(payloads: list[bytes]) -> list[bytes]:
    """For sorted distinct 32-bit prints of each chunk: one bit each, set if another chunk has it too."""
    parts = [np.frombuffer(p, np.uint32) for p in payloads]
    both = np.concatenate(parts)
    order = np.argsort(both, kind="stable")
    ranked = both[order]
    same = ranked[1:] == ranked[:-1]
    flag = np.zeros(len(both), bool)
    flag[order[1:]] |= same
    flag[order[:-1]] |= same
    ends = np.cumsum([len(p) for p in parts])
    return [np.packbits(x).tobytes() for x in np.split(flag, ends[:-1])]


def ask_prints(sender: int, keys: np.ndarray, buckets: int) -> pa.Table:
    """Mail for sorted distinct keys made by ``print_keys``."""
    used, a, b = cut(keys >> np.uint64(32), buckets)
    low = keys.astype(np.uint32)
    return mail(sender, used, [low[i:j].tobytes() for i, j in zip(a, b, strict=True)])


def print_keys(hashes: np.ndarray, buckets: int) -> np.ndarray:
    """Bucket in the high half, a 32-bit print in the low half."""
    return (hashes % np.uint64(buckets)) << np.uint64(32) | hashes >> np.uint64(32)


def read_flags(keys: np.ndarray, box: dict[int, bytes], buckets: int) -> np.ndarray:
    """The answer to each of the sorted distinct keys."""
    flag = np.zeros(len(keys), bool)
    for bucket, a, b in zip(*cut(keys >> np.uint64(32), buckets), strict=True):
        flag[a:b] = np.unpackbits(np.frombuffer(box[int(bucket)], np.uint8), count=b - a).astype(bool)
    return flag

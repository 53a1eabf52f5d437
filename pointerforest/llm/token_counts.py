"""Token counts by rank-synchronous array merging.

``count_tokens`` gives, for every document, the number of tokens that the
word-end BPE file yields (no added special tokens; special strings inside a text
count as one token, as the library does by default).

A text is cut at white space; each distinct stretch is cut into pre-tokens and
merged once per Python worker, many stretches in step as ragged numpy arrays.
White space never lies inside a pre-token, so this equals encoding the whole text.

Defined results: null text counts as empty (0 bytes, 0 tokens); a null id stays
null; repeated rows each give a row; an empty table gives no rows; extra columns
are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._bpe import MergeTable
from ._spark import documents
from ._text import ids_of, ids_out

#: Entries of a worker's memo; beyond it the memo starts afresh (results do not change).
MEMO = 400_000
#: Separators that str.split() knows but the Unicode White_Space property does not.
_ODD = ("\x1c", "\x1d", "\x1e", "\x1f")

_tables: dict[str, tuple[MergeTable, dict[str, int]]] = {}


def stretches(table: MergeTable, text: str) -> list[str]:
    """Parts of a text between white space."""
    if any(c in text for c in _ODD):
        return [w for w in _white().split(text) if w]
    return text.split()


def _white():
    import regex

    return regex.compile(r"\p{White_Space}+")


def count_batch(table: MergeTable, memo: dict[str, int], texts: list[str]) -> np.ndarray:
    """Token count of each text; fills the memo."""
    parts = [stretches(table, t) if t else [] for t in texts]
    flat = [w for p in parts for w in p]
    new = [w for w in set(flat) if w not in memo]
    if len(memo) + len(new) > MEMO:
        memo.clear()
        new = list(set(flat))
    pre, owner, base = [], [], np.zeros(len(new), np.int64)
    for i, w in enumerate(new):
        found, base[i] = table.pretokens(w)
        pre += found
        owner += [i] * len(found)
    if pre:
        distinct: dict[str, int] = {}
        code = np.fromiter((distinct.setdefault(p, len(distinct)) for p in pre), np.int64, len(pre))
        got = table.count(list(distinct))[code]
        base += np.bincount(np.array(owner), weights=got, minlength=len(new)).astype(np.int64)
    memo.update(zip(new, base.tolist(), strict=True))
    sizes = np.fromiter(map(memo.__getitem__, flat), np.int64, len(flat))
    total = np.append(0, np.cumsum(sizes))
    ends = np.cumsum([len(p) for p in parts])
    return total[ends] - total[np.append(0, ends[:-1])] if len(parts) else np.zeros(0, np.int64)


def count_tokens(docs: DataFrame, vocabulary: str, *, id_col: str = "doc_id", text_col: str = "text", limit: int = 2048) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit (more than ``limit`` tokens).

    ``vocabulary``: path of the word-end BPE file, present on every executor.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if vocabulary not in _tables:
            _tables[vocabulary] = (MergeTable(vocabulary), {})
        table, memo = _tables[vocabulary]
        for batch in batches:
            for at in range(0, batch.num_rows, 2000):
                part = batch.slice(at, 2000)
                texts = part.column(1).fill_null("").to_pylist()
                n = count_batch(table, memo, texts)
                size = pc.binary_length(part.column(1)).fill_null(0).cast(pa.int64())
                yield pa.RecordBatch.from_arrays([ids_out(ids_of(part.column(0))), size, pa.array(n, pa.int64()), pa.array(n > limit)], names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def op8_token_counts(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return count_tokens(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))

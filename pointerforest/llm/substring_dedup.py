"""Removal of repeated word windows, found by level-wise doubling.

Windows of ``base`` words whose print occurs twice anywhere are candidates; two
neighbouring candidates make a candidate of twice the length, and only those are
looked at on the next level, until the wanted length is reached or no candidate
survives. On lower levels a 32-bit print within its bucket decides (false alarms
are possible and harmless: the next level looks again, misses are not). On the
last level windows are told apart by two polynomial prints, 96 bits in all, over 64-bit
hashes of their words.

Every word covered by a window of ``base * 2**k`` words whose words also start
earlier (smaller id, or same document and an earlier start) is removed; windows are
judged on the input.

Defined results: null and empty texts have no words (kept text empty); texts
shorter than a window keep everything; rows that repeat an id are ordered by text
and each gives a row, the later one counts as later; an empty table gives no rows;
extra columns are ignored; a null id sorts first and stays null.
"""

from __future__ import annotations

import hashlib
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ._exchange import Chunked, ask_prints, cut, mail, note_to_self, print_keys, read_flags, repeated_elsewhere
from ._spark import documents
from ._text import WORD_POWERS, WORD_POWERS_2, U, flat_bytes, hash_words, ids_of, ids_out, mix, prefix_hash, span_hash

_ENTRY = np.dtype([("hash", "<u8"), ("check", "<u4"), ("doc", "<i8")])


class Windows:
    """All words of a chunk and the windows over them."""

    def __init__(self, table: pa.Table):
        self.ids = ids_of(table["doc_id"])
        self.data, self.offsets = flat_bytes(table["text"])
        self.words, self.sizes = hash_words(self.data, self.offsets)
        self.end = np.repeat(np.cumsum(self.sizes), self.sizes)
        self.prefix = prefix_hash(self.words, WORD_POWERS)

    def fits(self, length: int) -> np.ndarray:
        """Whether a window of this length that starts here stays in its document."""
        return np.arange(len(self.words)) + length <= self.end

    def hashes(self, start: np.ndarray, length: int) -> np.ndarray:
        return mix(span_hash(self.prefix, start, start + length, WORD_POWERS))

    def checks(self, start: np.ndarray, length: int) -> np.ndarray:
        return (mix(span_hash(prefix_hash(self.words, WORD_POWERS_2), start, start + length, WORD_POWERS_2)) >> U(32)).astype(np.uint32)


def _candidates(w: Windows, start: np.ndarray, length: int, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct print keys of windows, which key each window has, and how often."""
    return np.unique(print_keys(w.hashes(start, length), buckets), return_inverse=True, return_counts=True) if len(start) else (np.zeros(0, U), np.zeros(0, np.int64), np.zeros(0, np.int64))


def _survivors(w: Windows, level: np.ndarray, length: int, box: dict[int, bytes], buckets: int) -> np.ndarray:
    """Starts of windows of twice ``length`` both halves of which are repeated."""
    start = np.flatnonzero(level)
    keys, which, count = _candidates(w, start, length, buckets)
    again = np.zeros(len(w.words) + length + 1, bool)
    again[start] = ((count > 1) | read_flags(keys, box, buckets))[which]
    return again[: len(w.words)] & again[length : length + len(w.words)] & w.fits(2 * length)


def _last_entries(w: Windows, level: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Starts; the distinct window each is; the first start of each; hashes of the distinct ones."""
    start = np.flatnonzero(level)
    hashes, checks = w.hashes(start, length), w.checks(start, length)
    order = np.lexsort((start, checks, hashes))
    h, c = hashes[order], checks[order]
    new = np.append(True, (h[1:] != h[:-1]) | (c[1:] != c[:-1])) if len(order) else np.zeros(0, bool)
    which = np.empty(len(order), np.int64)
    which[order] = np.cumsum(new) - 1
    return start, which, start[order[new]], np.rec.fromarrays([h[new], c[new]], names=["hash", "check"])


def _first_elsewhere(payloads: list[bytes]) -> list[bytes]:
    """One bit for each entry: another chunk has the same window in an earlier document."""
    parts = [np.frombuffer(p, _ENTRY) for p in payloads]
    both = np.concatenate(parts)
    order = np.lexsort((both["doc"], both["check"], both["hash"]))
    s = both[order]
    new = np.append(True, (s["hash"][1:] != s["hash"][:-1]) | (s["check"][1:] != s["check"][:-1]))
    flag = np.empty(len(both), bool)
    flag[order] = ~new
    return [np.packbits(x).tobytes() for x in np.split(flag, np.cumsum([len(p) for p in parts])[:-1])]


def remove_repeated_windows(docs: DataFrame, *, base: int = 10, doublings: int = 1, id_col: str = "doc_id", text_col: str = "text", digest: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed and the kept words joined by spaces (or their SHA-256).

    Windows are ``base * 2**doublings`` words long.
    """
    chunked = Chunked(docs, id_col=id_col, text_col=text_col)
    buckets, length = chunked.buckets, base << doublings

    def first(table: pa.Table) -> pa.Table:
        chunk, w = table["chunk"][0].as_py(), Windows(table)
        if not doublings:
            return ask_last(chunk, w, w.fits(base))
        return ask_prints(chunk, _candidates(w, np.flatnonzero(w.fits(base)), base, buckets)[0], buckets)

    def ask_last(chunk: int, w: Windows, level: np.ndarray) -> pa.Table:
        _, _, first_start, distinct = _last_entries(w, level, length)
        to = (distinct["hash"] % U(buckets)).astype(np.int64)
        order = np.argsort(to, kind="stable")
        doc = np.repeat(w.ids, w.sizes)
        entries = np.empty(len(order), _ENTRY)
        entries["hash"], entries["check"], entries["doc"] = distinct["hash"][order], distinct["check"][order], doc[first_start[order]]
        used, a, b = cut(to[order], buckets)
        notes = [np.packbits(level).tobytes()]
        return mail(chunk, np.append(used, note_to_self(chunk)), [entries[i:j].tobytes() for i, j in zip(a, b, strict=True)] + notes)

    def level_of(table: pa.Table, box: dict[int, bytes]) -> tuple[int, Windows, np.ndarray]:
        chunk, w = table["chunk"][0].as_py(), Windows(table)
        note = box.get(note_to_self(chunk))
        return chunk, w, w.fits(base) if note is None else np.unpackbits(np.frombuffer(note, np.uint8), count=len(w.words)).astype(bool)

    def step(k: int):
        def run(table: pa.Table, box: dict[int, bytes]) -> pa.Table:
            if not table.num_rows:
                return mail(0, np.zeros(0, np.int64), [])
            chunk, w, level = level_of(table, box)
            level = _survivors(w, level, base << k, box, buckets)
            if k + 1 == doublings:
                return ask_last(chunk, w, level)
            asked = ask_prints(chunk, _candidates(w, np.flatnonzero(level), base << k + 1, buckets)[0], buckets)
            return pa.concat_tables([asked, mail(chunk, np.array([note_to_self(chunk)]), [np.packbits(level).tobytes()])])

        return run

    def finish(table: pa.Table, box: dict[int, bytes]) -> pa.Table:
        schema = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept", pa.string())])
        if not table.num_rows:
            return schema.empty_table()
        _, w, level = level_of(table, box)
        start, which, first_start, distinct = _last_entries(w, level, length)
        to = (distinct["hash"] % U(buckets)).astype(np.int64)
        order = np.argsort(to, kind="stable")
        earlier = np.zeros(len(order), bool)
        for bucket, a, b in zip(*cut(to[order], buckets), strict=True):
            earlier[order[a:b]] = np.unpackbits(np.frombuffer(box[int(bucket)], np.uint8), count=b - a).astype(bool)
        gone = start[earlier[which] | (start != first_start[which])] if len(start) else start
        cover = np.zeros(len(w.words) + 1, np.int64)
        np.add.at(cover, gone, 1)
        np.subtract.at(cover, gone + length, 1)
        keep = np.cumsum(cover)[:-1] == 0
        at = np.append(0, np.cumsum(w.sizes))
        removed = w.sizes - (np.append(0, np.cumsum(keep))[at[1:]] - np.append(0, np.cumsum(keep))[at[:-1]])
        kept, raw = [], w.data.tobytes()
        for i in range(len(w.ids)):
            words = raw[w.offsets[i] : w.offsets[i + 1]].split()
            if removed[i]:
                words = compress(words, keep[at[i] : at[i + 1]].tolist())
            text = b" ".join(words)
            kept.append(hashlib.sha256(text).hexdigest() if digest else text.decode())
        return pa.table([ids_out(w.ids), pa.array(w.sizes, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.string())], schema=schema)

    answers = chunked.replies(chunked.ask(first), repeated_elsewhere if doublings else _first_elsewhere)
    for k in range(doublings):
        answers = chunked.replies(chunked.then(answers, step(k)), _first_elsewhere if k + 1 == doublings else repeated_elsewhere)
    return chunked.then(answers, finish, "doc_id long, n_words long, n_removed long, kept string")


def op5_substring_dedup(spark, sf_dir: str) -> DataFrame:
    out = remove_repeated_windows(documents(spark, sf_dir), base=10, doublings=1, digest=True)
    return out.withColumnRenamed("kept", "kept_sha256")

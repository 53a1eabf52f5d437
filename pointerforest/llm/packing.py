"""Packing of documents into fixed-length sequences: dominance reduction, then best fit.

The instance is a histogram of piece lengths (at most ``capacity`` counts, however
many documents there are), so planning runs on the driver over bounded data:

1. *Dominance reduction* (after Martello and Toth): sets that provably dominate
   every alternative are fixed for good, largest piece first: a piece with which
   nothing fits; a pair that fills a sequence exactly; a piece with its largest
   fitting partner where no two pieces fit beside it; and a piece with its largest
   fitting partner where two others fit beside it but never three, and no two that
   fit are longer together than that partner. Each fixed set shrinks the instance and the rest is
   examined again.
2. *Best fit, longest first*, over the counts of what is left: pieces of one
   length go, many at a time, to the open sequences with the least sufficient room.

The plan is a list of patterns (lengths that share a sequence, how often). Pieces
get their rank within their length by two distributed counts, and a rank falls in
exactly one place of one pattern.

Defined results: null text counts as empty (its end token alone); repeated rows
are pieces of their own; an empty table gives no rows; a null id stays null.
"""

from __future__ import annotations

import bisect
import os
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ._spark import documents, stored
from ._text import BYTE_CODE, BYTE_POWERS, U, flat_bytes, groups_of, ids_of, ids_out, mix, prefix_hash, release, span_hash, words_of

#: Entries, and ids in them, of a generation of a worker's memo of encoded stretches.
MEMO, MEMO_IDS = 500_000, 3_000_000
#: Bytes of text encoded together; some forty times as many are held while they are.
GROUP_BYTES = 1 << 20
_MARK = "\x01"
#: Below it, characters are letters or not whatever their neighbours are.
_SIMPLE = "\u0250"
_encoders: dict[str, tuple[object, Memo]] = {}
_ends: dict[int, np.ndarray] = {}


class Counts:
    """Multiset of lengths with neighbours by size."""

    def __init__(self, counts: dict[int, int]):
        self.n = {k: v for k, v in counts.items() if v > 0}
        self.keys = sorted(self.n)

    def take(self, size: int, k: int) -> None:
        self.n[size] -= k
        if not self.n[size]:
            del self.n[size]
            self.keys.pop(bisect.bisect_left(self.keys, size))

    def fitting(self, room: int) -> int | None:
        """Largest length of at most ``room``."""
        i = bisect.bisect_right(self.keys, room)
        return self.keys[i - 1] if i else None

    def least_two(self) -> int:
        """Sum of the two smallest pieces; beyond any room if there are none."""
        a = self.keys[0]
        return 2 * a if self.n[a] > 1 else a + self.keys[1] if len(self.keys) > 1 else 1 << 60

    def least_others(self, k: int, size: int) -> int:
        """Sum of the ``k`` smallest pieces beside one of ``size``; beyond any room if there are fewer."""
        total = 0
        for x in self.keys:
            some = min(k, self.n[x] - (x == size))
            total, k = total + some * x, k - some
            if not k:
                return total
        return 1 << 60

    def best_pair(self, room: int, size: int) -> int:
        """Largest sum of at most ``room`` of two pieces beside one of ``size``; 0 if no two fit."""
        best, i, j = 0, 0, bisect.bisect_right(self.keys, room) - 1
        while i <= j:
            x, y = self.keys[i], self.keys[j]
            if x + y > room:
                j -= 1
                continue
            if self.n[x] - (x == size) >= 1 + (i == j) and self.n[y] > (y == size):
                best = max(best, x + y)
                if best == room:
                    break
                i += 1
            elif self.n[x] == (x == size):  # only the piece itself
                i += 1
            else:
                j -= 1
        return best


def reduce_by_dominance(counts: Counts, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Fix dominating sets; what stays in ``counts`` is the reduced instance.

    A piece whose best set is not decided keeps its place; shorter pieces are still
    tried, as each rule speaks about one piece and everything that could join it.
    """
    plan: list[tuple[tuple[int, ...], int]] = []
    at = len(counts.keys) - 1
    while at >= 0 and counts.keys:
        at = min(at, len(counts.keys) - 1)
        size = counts.keys[at]
        room = capacity - size
        own = counts.n[size]
        partner = counts.fitting(room)
        if partner == size and own == 1:  # not with itself
            i = bisect.bisect_left(counts.keys, size)
            partner = counts.keys[i - 1] if i else None
        if partner is None:
            plan.append(((size,), own))
            counts.take(size, own)
        elif partner == room or counts.least_two() > room or (counts.least_others(3, size) > room and counts.best_pair(room, size) <= partner):
            # Exact fill, room for one other piece at most, or for two that the largest partner can stand in for.
            k = own // 2 if partner == size else min(own, counts.n[partner])
            if not k:
                at -= 1
                continue
            plan.append(((size, partner), k))
            counts.take(size, k * (2 if partner == size else 1))
            if partner != size:
                counts.take(partner, k)
            at = min(at, len(counts.keys) - 1)
            continue
        at -= 1
    return plan


def best_fit(counts: Counts, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best fit, longest first, on counts: open sequences of one pattern move together."""
    by_room: dict[int, list[list]] = {}
    rooms: list[int] = []
    done: list[tuple[tuple[int, ...], int]] = []

    def put(room: int, pattern: tuple[int, ...], k: int) -> None:
        if room not in by_room:
            by_room[room] = []
            bisect.insort(rooms, room)
        by_room[room].append([pattern, k])

    for size in reversed(counts.keys):
        left = counts.n[size]
        while left:
            i = bisect.bisect_left(rooms, size)
            if i == len(rooms):
                each = capacity // size
                whole, rest = divmod(left, each)
                if whole:
                    put(capacity - each * size, (size,) * each, whole)
                if rest:
                    put(capacity - rest * size, (size,) * rest, 1)
                break
            room = rooms[i]
            # A sequence that takes one piece stays the best fit for the next while there is room.
            pattern, k = by_room[room][-1]
            each = room // size
            if left >= each:
                used = min(k, left // each)
                take = each
            else:
                used, take = 1, left
            left -= used * take
            by_room[room][-1][1] -= used
            if not by_room[room][-1][1]:
                by_room[room].pop()
                if not by_room[room]:
                    del by_room[room]
                    rooms.pop(i)
            put(room - take * size, pattern + (size,) * take, used)
    for lists in by_room.values():
        done += [(p, k) for p, k in lists]
    return done


def plan_sequences(histogram: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Patterns (lengths in one sequence, how many such sequences) that use every piece once."""
    counts = Counts(histogram)
    fixed = reduce_by_dominance(counts, capacity)
    return fixed + best_fit(counts, capacity)


def slots_of(plan: list[tuple[tuple[int, ...], int]]) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each length: first rank of each slot range, its first sequence, and the place in it."""
    got: dict[int, list[tuple[int, int, int]]] = {}
    used: dict[int, int] = {}
    sequence = 0
    for pattern, k in plan:
        place = 0
        for size in pattern:
            got.setdefault(size, []).append((used.get(size, 0), sequence, place))
            used[size] = used.get(size, 0) + k
            place += size
        sequence += k
    return {s: tuple(np.array(c, np.int64) for c in zip(*x, strict=True)) for s, x in got.items()}


class Memo:
    """Ids of stretches met before, by 64-bit hash: sorted keys and places in one pool of ids.

    Two generations: what is asked for again moves to the young one; the old one goes when
    the young one holds ``MEMO`` entries or ``MEMO_IDS`` ids.
    """

    def __init__(self):
        self.young, self.old = _Generation(), _Generation()

    def fill(self, tokenizer, keys: np.ndarray, text_of: Callable[[np.ndarray], list[bytes]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(pool, start, size) of these sorted distinct keys; ``text_of`` gives the bytes of the unknown ones."""
        known = self.young.has(keys)
        missing = np.flatnonzero(~known)
        again = missing[self.old.has(keys[missing])]
        if len(again):
            self.young.add(keys[again], *self.old.take(keys[again]))
        new = np.setdiff1d(missing, again, assume_unique=True)
        if len(new):
            flat, size = encode_new(tokenizer, text_of(new))
            self.young.add(keys[new], flat, size)
        at = np.searchsorted(self.young.keys, keys)
        got = self.young.pool, self.young.start[at], self.young.size[at]
        if len(self.young.keys) >= MEMO or len(self.young.pool) >= MEMO_IDS:
            self.old, self.young = self.young, _Generation()
        return got


class _Generation:
    """Sorted hashes with the ids of each in a common pool."""

    def __init__(self):
        self.keys, self.start, self.size, self.pool = np.zeros(0, U), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, "<u4")

    def has(self, keys: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.zeros(len(keys), bool)
        return self.keys[np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)] == keys

    def take(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.searchsorted(self.keys, keys)
        return gathered(self.pool, self.start[at], self.size[at]), self.size[at]

    def add(self, keys: np.ndarray, flat: np.ndarray, size: np.ndarray) -> None:
        start = len(self.pool) + np.cumsum(size) - size
        at = np.searchsorted(self.keys, keys)
        self.keys, self.start, self.size = np.insert(self.keys, at, keys), np.insert(self.start, at, start), np.insert(self.size, at, size)
        self.pool = np.concatenate([self.pool, flat])


def gathered(pool: np.ndarray, start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The runs ``pool[start : start + size]`` one after another."""
    total = np.cumsum(size)
    return pool[np.repeat(start - total + size, size) + np.arange(total[-1] if len(total) else 0)]


def encode_new(tokenizer, new: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all stretches one after another, and how many each has.

    Stretches of letters alone are one pre-token each, whose last token says that a word
    ends there, so they are encoded many at a time with a space between. Others have a
    control character between that is a token of its own.
    """
    texts = [w.decode() for w in new]
    letters = [i for i, w in enumerate(texts) if w.isalpha() and (w.isascii() or max(w) < _SIMPLE and w.lower().isalpha())]
    got: dict[int, np.ndarray] = {}
    ends = word_ends(tokenizer)
    _encode_some(tokenizer, texts, letters, " ", lambda ids: np.flatnonzero(ends[ids]) + 1, 0, got)
    mark = tokenizer.encode(_MARK, add_special_tokens=False).ids
    if len(mark) != 1:
        raise ValueError("the vocabulary has no token of its own for the mark")
    rest = [i for i in range(len(texts)) if i not in got]
    _encode_some(tokenizer, texts, [i for i in rest if _MARK not in texts[i] and "<|" not in texts[i]], f" {_MARK} ", lambda ids: np.flatnonzero(ids == mark[0]), 1, got)
    for i in rest:
        if i not in got:
            got[i] = np.array(tokenizer.encode(texts[i], add_special_tokens=False).ids, "<u4")
    parts = [got[i] for i in range(len(texts))]
    return np.concatenate(parts), np.fromiter(map(len, parts), np.int64, len(parts))


def _encode_some(tokenizer, texts: list[str], who: list[int], between: str, ends_of, skip: int, got: dict[int, np.ndarray]) -> None:
    """64 stretches at a time; a group whose ends cannot be told is left to the caller."""
    for at in range(0, len(who), 64 * 256):
        groups = [who[i : i + 64] for i in range(at, min(len(who), at + 64 * 256), 64)]
        found = tokenizer.encode_batch_fast([between.join([*(texts[i] for i in g), ""]) for g in groups], add_special_tokens=False)
        for group, e in zip(groups, found, strict=True):
            ids = np.array(e.ids, "<u4")
            ends = ends_of(ids)
            if len(ends) == len(group) and (len(ids) == ends[-1] + skip):
                start = 0
                for i, end in zip(group, ends.tolist(), strict=True):
                    got[i] = ids[start:end]
                    start = end + skip


def word_ends(tokenizer) -> np.ndarray:
    """Which ids are the last of a pre-token."""
    if id(tokenizer) not in _ends:
        suffix = getattr(tokenizer.model, "end_of_word_suffix", None) or "\0"
        vocab = tokenizer.get_vocab(with_added_tokens=True)
        last = np.zeros(max(vocab.values(), default=0) + 1, bool)
        last[[i for w, i in vocab.items() if w.endswith(suffix)]] = True
        _ends[id(tokenizer)] = last
    return _ends[id(tokenizer)]


#: Marks that may follow a letter as a pre-token of their own: no apostrophe, no < and >.
_IS_TAIL = np.zeros(256, bool)
_IS_TAIL[[b for b in range(33, 127) if not chr(b).isalnum() and chr(b) not in "'<>"]] = True
_IS_UPPER, _IS_LETTER = np.zeros(256, bool), np.zeros(256, bool)
_IS_UPPER[65:91] = _IS_LETTER[65:91] = _IS_LETTER[97:123] = True
#: Characters of two bytes that are letters, also when lowered (a dotted capital I ends in a mark then).
_TWO_BYTES = np.array([chr(c).isalpha() and chr(c).lower().isalpha() for c in range(1 << 11)])


def cores_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(data, start, core, end, words per text) of the stretches between ASCII white space.

    ``core`` parts letters from a run of marks behind them, which is a pre-token of its
    own, so that few distinct stretches remain; capitals of ASCII stretches are lowered in
    ``data``, as the normalizer would. A stretch with < stays whole: special strings are literal.
    """
    start, end, counts = words_of(data, offsets)
    if not len(start):
        return data, start, start, end, counts
    place = np.where(_IS_TAIL[data], np.int32(-1), np.arange(len(data), dtype=np.int32 if len(data) < 1 << 31 else np.int64))
    np.maximum.accumulate(place, out=place)
    core = np.maximum(place[end - 1] + 1, start).astype(np.int64)
    last = data[np.maximum(core - 1, 0)]
    before = data[np.maximum(core - 2, 0)].astype(np.int64)
    letter = _IS_LETTER[last] | ((last >= 128) & (before >= 194) & (before < 224) & (core - 2 >= start) & _TWO_BYTES[(before & 31) << 6 | (last & 63)])
    core = np.where((core > start) & letter, core, end)
    odd = np.append(0, np.cumsum((data >= 128) | (data == 60), dtype=np.int32))
    upper = np.flatnonzero(_IS_UPPER[data])
    whose = np.searchsorted(start, upper, "right") - 1
    upper = upper[odd[end[whose]] == odd[start[whose]]]
    data = data.copy()
    data[upper] += 32
    return data, start, core, end, counts


def encode_all(tokenizer, memo: Memo, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all texts one after another, and n + 1 offsets into them; fills the memo.

    White space never lies inside a token of this tokenizer, so texts are encoded by
    the stretches between ASCII white space, each distinct one (told apart by a 64-bit
    hash) once.
    """
    parts = []
    for i, j in groups_of(offsets, 1 << 20):
        base = offsets[i]
        low, start, core, end, counts = cores_of(data[base : offsets[j]], offsets[i : j + 1] - base)
        prefix = prefix_hash(BYTE_CODE[low], BYTE_POWERS)
        hashes = mix(span_hash(prefix, np.concatenate([start, core]), np.concatenate([core, end]), BYTE_POWERS) + np.concatenate([core - start, end - core]).astype(U))
        parts.append((low, hashes, base + np.concatenate([start, core]), base + np.concatenate([core, end]), counts))
    if not parts:
        return np.zeros(0, "<u4"), np.zeros(len(offsets), np.int64)
    raw = np.concatenate([p[0] for p in parts]).tobytes()
    hashes, start, end, counts = (np.concatenate([p[k] for p in parts]) for k in (1, 2, 3, 4))
    words = [len(p[1]) // 2 for p in parts]
    which, keys = pd.factorize(hashes)
    first = np.empty(len(keys), np.int64)
    first[which[::-1]] = np.arange(len(which) - 1, -1, -1)
    order = np.argsort(keys)
    places = first[order]
    pool, at, size = memo.fill(tokenizer, keys[order], lambda new: [raw[a:b] for a, b in zip(start[places[new]].tolist(), end[places[new]].tolist(), strict=True)])
    rank = np.empty(len(keys), np.int64)
    rank[order] = np.arange(len(keys))
    which = rank[which]
    # Cores and tails take turns again.
    edge = np.append(0, np.cumsum([2 * n for n in words]))
    turn = np.concatenate([np.arange(2 * n).reshape(2, n).T.ravel() + e for n, e in zip(words, edge, strict=False)])
    at, size = at[which[turn]], size[which[turn]]
    total = np.append(0, np.cumsum(size))
    return gathered(pool, at, size), total[2 * np.append(0, np.cumsum(counts))]


def token_pieces(docs: DataFrame, vocabulary: str, *, capacity: int = 2048, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """Pieces of at most ``capacity`` tokens: doc_id, piece, start, length, ids_crc32 (and ids)."""
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        if vocabulary not in _encoders:
            from tokenizers import Tokenizer

            _encoders[vocabulary] = (Tokenizer.from_file(vocabulary), Memo())
        tokenizer, memo = _encoders[vocabulary]
        for batch in batches:
            data, offsets = flat_bytes(batch.column(1))
            all_ids = ids_of(batch.column(0))
            for first, last in groups_of(offsets, GROUP_BYTES):
                ids = all_ids[first:last]
                flat, places = encode_all(tokenizer, memo, data[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first])
                owner, piece, start, length, crc, raw = [], [], [], [], [], []
                for i in range(last - first):
                    e = flat[places[i] : places[i + 1]].tobytes() + end
                    for k, s in enumerate(range(0, len(e), 4 * capacity)):
                        x = e[s : s + 4 * capacity]
                        owner.append(i), piece.append(k), start.append(s // 4), length.append(len(x) // 4), crc.append(zlib.crc32(x))
                        if keep_ids:
                            raw.append(np.frombuffer(x, "<u4").astype(np.int64).tolist())
                out = [ids_out(ids[np.array(owner, np.int64)]), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())]
                names = ["doc_id", "piece", "start", "length", "ids_crc32"]
                if keep_ids:
                    out.append(pa.array(raw, pa.list_(pa.int64())))
                    names.append("ids")
                del flat, places
                release()
                yield pa.RecordBatch.from_arrays(out, names=names)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<long>" * keep_ids)


def pack(pieces: DataFrame, *, capacity: int = 2048) -> DataFrame:
    """Add sequence_id and offset to rows with a ``length`` of 1 to ``capacity``.

    Rows are written once to the shared folder, each with the number of the task
    that wrote it; ranks within a length are the rank inside (task, length) plus the
    counts of the tasks before, so no length gathers in one task.
    """
    rows = stored(pieces.withColumn("part", F.spark_partition_id()))
    counts = rows.groupBy("length", "part").agg(F.count(F.lit(1)).alias("n"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most capacity rows
    slots = slots_of(plan_sequences(histogram, capacity))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("length", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    inside = Window.partitionBy("part", "length").orderBy("doc_id", "piece")
    ranked = rows.withColumn("rank", F.row_number().over(inside) - 1).join(offsets, ["part", "length"])
    ranked = ranked.select(*[c for c in rows.columns if c != "part"], (F.col("rank") + F.col("base")).alias("rank"))
    names = [c for c in ranked.columns if c != "rank"]

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            size = batch.column(names.index("length")).to_numpy()
            rank = batch.column(len(names)).to_numpy()
            sequence, offset = np.zeros(len(size), np.int64), np.zeros(len(size), np.int64)
            for s in np.unique(size):
                who = np.flatnonzero(size == s)
                first, seq, at = slots[int(s)]
                i = np.searchsorted(first, rank[who], "right") - 1
                sequence[who], offset[who] = seq[i] + rank[who] - first[i], at[i]
            yield pa.RecordBatch.from_arrays([batch.column(i) for i in range(len(names))] + [pa.array(sequence), pa.array(offset)], names=[*names, "sequence_id", "offset"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in ranked.schema if f.name != "rank")
    return ranked.mapInArrow(place, f"{schema}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, vocabulary: str, *, capacity: int = 2048, **columns) -> DataFrame:
    """One row per piece of every document, with its place among the packed sequences."""
    return pack(token_pieces(docs, vocabulary, capacity=capacity, **columns), capacity=capacity)


def sequences(layout: DataFrame) -> DataFrame:
    """The packed sequences themselves, from a layout that carries ``ids``."""
    bag = F.array_sort(F.collect_list(F.struct("offset", "ids")))
    return layout.groupBy("sequence_id").agg(bag.alias("bag")).select("sequence_id", F.flatten(F.transform("bag", lambda x: x["ids"])).alias("ids"))


def op10_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack_documents(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))

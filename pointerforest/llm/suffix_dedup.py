"""Removal of byte strings repeated across documents, by a hash-compared suffix sort.

Every ``length``-byte window has an anchor: its leftmost ``gram``-byte piece of least
hash. Equal windows have equal anchors at equal places, so

1. chunks ask which anchor hashes occur in other chunks; windows whose anchor is in
   no other document drop out (a false alarm only costs work);
2. what is left travels, as the bytes around each anchor (at most
   ``2 * length - gram``), to the bucket of the anchor hash. Equal pieces of a chunk
   travel once, with their smallest id;
3. a bucket sorts the suffixes that start at the anchors, and the reversed prefixes
   that end there, by mergesort. A comparison finds the common extension by binary
   search over prefix polynomial hashes, so it takes a logarithmic number of
   probes; the order and every claimed common extension are then verified on the
   bytes. Windows are equal if they agree to the left and to the right of the anchor,
   which the two sorted orders tell as class numbers;
4. each chunk learns which windows occur in an earlier document.

A byte is removed if a window over it also starts in a document of smaller id; matches
never cross documents, and windows are judged on the input.

Defined results: null counts as empty; documents shorter than a window stay; rows
that repeat an id are one document for matching (no match between them) and each
gives a row; an empty table gives no rows; extra columns are ignored; a null id sorts
first and stays null. Very long documents are read in overlapping blocks.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ._exchange import Chunked, ask_prints, cut, mail, note_to_self, print_keys, read_flags, repeated_elsewhere
from ._spark import documents
from ._text import BYTE_CODE, BYTE_POWERS, U, flat_bytes, groups_of, ids_of, ids_out, mix, prefix_hash, span_hash

#: Bytes hashed at a time; small enough for the arrays to stay in cache.
_BLOCK = 1 << 17
_PLACE_BITS = U(24)


def sliding_least(x: np.ndarray, width: int) -> np.ndarray:
    """Least of x[i : i + width] for every full window."""
    n = len(x) - width + 1
    if n <= 0:
        return x[:0]
    pad = -len(x) % width
    blocks = np.append(x, np.full(pad, ~U(0))).reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[:n], ahead[width - 1 : width - 1 + n])


class Anchors:
    """Runs of windows of one document that share their anchor.

    place: first byte of the anchor; first, last: starts of the windows; value: anchor hash.
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray, length: int, gram: int):
        runs = [self._runs(data, offsets, a, e, upto, length, gram) for a, e, upto in self._blocks(offsets, length)]
        join = lambda k, kind: np.concatenate([r[k] for r in runs]) if runs else np.zeros(0, kind)
        self.place, self.first, self.last = (join(k, np.int64) for k in range(3))
        self.value = join(3, U)

    @staticmethod
    def _runs(data, offsets, a: int, e: int, upto: int, length: int, gram: int):
        part = data[a:e]
        prefix = prefix_hash(BYTE_CODE[part], BYTE_POWERS)
        n = max(0, len(part) - gram + 1)
        grams = (prefix[gram:] - prefix[:n]) * BYTE_POWERS.get(len(prefix))[1][:n] if n else np.zeros(0, U)
        grams ^= grams >> U(31)
        grams *= U(0xFF51AFD7ED558CCD)
        grams &= ~((U(1) << _PLACE_BITS) - U(1))
        grams |= np.arange(n, dtype=U)
        least = sliding_least(grams, length - gram + 1)[: upto - a]
        ok = np.ones(len(least), bool)
        inner = offsets[np.searchsorted(offsets, a, "right") : np.searchsorted(offsets, e)] - a
        if len(inner):  # windows over an edge between documents don't count
            edge = np.zeros(len(least) + 1, np.int64)
            np.add.at(edge, np.clip(inner - length + 1, 0, len(least)), 1)
            np.subtract.at(edge, np.clip(inner, 0, len(least)), 1)
            ok = np.cumsum(edge)[:-1] == 0
        new = ok.copy()
        new[1:] &= (least[1:] != least[:-1]) | ~ok[:-1]
        end = ok.copy()
        end[:-1] &= new[1:] | ~ok[1:]
        first, last = np.flatnonzero(new), np.flatnonzero(end)
        least = least[first]
        return (least & ((U(1) << _PLACE_BITS) - U(1))).astype(np.int64) + a, first + a, last + a, least >> _PLACE_BITS

    @staticmethod
    def _blocks(offsets: np.ndarray, length: int):
        """(first byte, last byte, end of the window starts) of runs of documents or parts of one."""
        for i, j in groups_of(offsets, _BLOCK):
            a, e = int(offsets[i]), int(offsets[j])
            for s in range(a, e, _BLOCK):
                yield s, min(e, s + _BLOCK + length - 1), min(e, s + _BLOCK)


def _common(ha: np.ndarray, a: np.ndarray, b: np.ndarray, width: int) -> np.ndarray:
    """Length of the common extension of rows a and b, by binary search over prefix hashes."""
    low, high = np.zeros(len(a), np.int64), np.full(len(a), width, np.int64)
    for _ in range(int(width).bit_length()):
        mid = (low + high + 1) >> 1
        same = ha[a, mid] == ha[b, mid]
        low, high = np.where(same, mid, low), np.where(same, high, mid - 1)
    return low


def suffix_order(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of byte rows, and common extension of each with the one before it.

    Rows are first dealt by their first eight bytes; rows that agree there are
    mergesorted bottom-up, all pairs of runs of a level at once: the place of a row is
    its own rank plus its rank in the other run, found by binary search.
    """
    n, width = rows.shape
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    hashes = np.zeros((n, width + 1), U)
    np.cumsum(BYTE_CODE[rows] * BYTE_POWERS.get(width)[0], axis=1, out=hashes[:, 1:])
    padded = np.zeros((n, width + 1), np.uint8)
    padded[:, :-1] = rows
    head = np.zeros((n, 8), np.uint8)
    head[:, : min(8, width)] = rows[:, :8]
    head = head.view(">u8").ravel().astype(U)
    order = np.argsort(head, kind="stable")
    begin = np.flatnonzero(np.append(True, head[order[1:]] != head[order[:-1]]))
    size = np.diff(np.append(begin, n))
    run = 1
    while run < size.max():
        live = np.repeat(size > run, size)  # places in groups that are not one run yet
        place = np.flatnonzero(live)
        base = np.repeat(begin, size)[place]
        end = base + np.repeat(size, size)[place]
        local = place - base
        left = (local // run) % 2 == 0
        other = base + np.where(left, local // run + 1, local // run - 1) * run
        low, high = np.minimum(other, end), np.minimum(other + run, end)
        from_ = low.copy()
        for _ in range(int(run).bit_length()):
            going = np.flatnonzero(low < high)
            if not len(going):
                break
            mid = (low[going] + high[going]) >> 1
            a, b = order[mid], order[place[going]]
            k = _common(hashes, a, b, width)
            # Of equals, the left run goes first.
            smaller = (padded[a, k] < padded[b, k]) | (k == width) & ~left[going]
            low[going] = np.where(smaller, mid + 1, low[going])
            high[going] = np.where(smaller, high[going], mid)
        target = base + local // (2 * run) * (2 * run) + local % run + (low - from_)
        merged = order.copy()
        merged[target] = order[place]
        order, run = merged, 2 * run
    common = np.append(0, _common(hashes, order[:-1], order[1:], width))
    # Verify on the bytes what the hashes claim.
    a, b = rows[order[:-1]], rows[order[1:]]
    true = np.where((a == b).all(axis=1), width, (a != b).argmax(axis=1))
    k = np.minimum(true, width - 1)
    pick = np.arange(n - 1)
    if (true != common[1:]).any() or (a[pick, k] > b[pick, k]).any():
        order = np.lexsort(rows.T[::-1])  # a hash collision: sort on the bytes themselves
        a, b = rows[order[:-1]], rows[order[1:]]
        true = np.where((a == b).all(axis=1), width, (a != b).argmax(axis=1))
    common[1:] = true
    return order, common


class Pieces:
    """Bytes around anchors: a matrix aligned on the anchor, with the extents at the end."""

    def __init__(self, length: int, gram: int):
        self.left, self.right = length - gram, length
        self.width = self.left + self.right + 2
        self.length = length

    def pack(self, rows: np.ndarray, doc: np.ndarray) -> bytes:
        """Only the bytes between the extents travel."""
        back, ahead = rows[:, -2], rows[:, -1]
        at = np.arange(-self.left, self.right)
        inside = (at >= -back[:, None].astype(np.int64)) & (at < ahead[:, None])
        low, high = (doc & 0xFFFFFFFF).astype("<u4"), (doc >> 32).astype("<i4")
        return np.array([len(rows)], "<i8").tobytes() + b"".join(x.tobytes() for x in (low, high, back, ahead, rows[:, :-2][inside]))

    def unpack(self, payload: bytes) -> tuple[np.ndarray, np.ndarray]:
        n = int(np.frombuffer(payload, "<i8", 1)[0])
        low, high = np.frombuffer(payload, "<u4", n, 8).astype(np.int64), np.frombuffer(payload, "<i4", n, 8 + 4 * n).astype(np.int64)
        extents = np.frombuffer(payload, np.uint8, 2 * n, 8 + 8 * n).reshape(2, n)
        rows = np.zeros((n, self.width), np.uint8)
        rows[:, -2], rows[:, -1] = extents
        at = np.arange(-self.left, self.right)
        inside = (at >= -extents[0][:, None].astype(np.int64)) & (at < extents[1][:, None])
        body = rows[:, :-2]
        body[inside] = np.frombuffer(payload, np.uint8, -1, 8 + 10 * n)
        return rows, high << 32 | low

    def cut(self, data: np.ndarray, place: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Rows for anchors at ``place`` whose windows start at first..last."""
        out = np.zeros((len(place), self.width), np.uint8)
        back, ahead = place - first, last + self.length - place
        for a in range(0, len(place), 1 << 15):
            b = slice(a, a + (1 << 15))
            at = place[b, None] + np.arange(-self.left, self.right)
            inside = (at >= first[b, None]) & (at < last[b, None] + self.length)
            out[b, :-2] = np.where(inside, data[np.clip(at, 0, max(0, len(data) - 1))], 0)
        out[:, -2], out[:, -1] = back, ahead
        return out

    def resolve(self, payloads: list[bytes]) -> list[bytes]:
        """For each piece, a 64-bit mask: bit k is set if its window that starts k bytes before the anchor occurs in an earlier document."""
        parts = [self.unpack(p) for p in payloads]
        own = np.concatenate([d for _, d in parts])
        rows, which = np.unique(np.concatenate([r for r, _ in parts]).view(f"V{self.width}").ravel(), return_inverse=True)
        rows = rows.view(np.uint8).reshape(-1, self.width)
        doc = np.full(len(rows), np.iinfo(np.int64).max)
        np.minimum.at(doc, which, own)
        right, right_common = suffix_order(rows[:, self.left : self.left + self.right])
        left, left_common = suffix_order(np.ascontiguousarray(rows[:, : self.left][:, ::-1]))
        back, ahead = rows[:, -2].astype(np.int64), rows[:, -1].astype(np.int64)
        least = np.zeros((self.left + 1, len(own)), bool)
        for k in range(self.left + 1):
            r = np.empty(len(rows), np.int64)
            r[right] = np.cumsum(right_common < self.length - k)
            q = np.empty(len(rows), np.int64)
            q[left] = np.cumsum(left_common < k)
            who = np.flatnonzero((back >= k) & (ahead >= self.length - k))
            if not len(who):
                continue
            key = q[who] * (len(rows) + 1) + r[who]
            order = np.argsort(key, kind="stable")
            ranked = key[order]
            new = np.append(True, ranked[1:] != ranked[:-1])
            first = np.minimum.reduceat(doc[who[order]], np.flatnonzero(new))
            smallest = np.full(len(rows), np.iinfo(np.int64).max)
            smallest[who[order]] = first[np.cumsum(new) - 1]
            least[k] = smallest[which] < own
        mask = np.zeros(len(own), U)
        for k in range(self.left + 1):
            mask |= least[k].astype(U) << U(k)
        return [x.tobytes() for x in np.split(mask, np.cumsum([len(d) for _, d in parts])[:-1])]


def remove_repeated_bytes(docs: DataFrame, *, length: int = 50, gram: int = 16, id_col: str = "doc_id", text_col: str = "text", digest: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans (maximal removed runs) and the kept bytes (or their SHA-256).

    ``length - gram`` is at most 63.
    """
    chunked = Chunked(docs, id_col=id_col, text_col=text_col)
    buckets, pieces = chunked.buckets, Pieces(length, gram)

    def read(table: pa.Table):
        data, offsets = flat_bytes(table["text"])
        ids = ids_of(table["doc_id"])
        w = Anchors(data, offsets, length, gram)
        keys, which = np.unique(print_keys(mix(w.value), buckets), return_inverse=True) if len(w.value) else (np.zeros(0, U), np.zeros(0, np.int64))
        return table["chunk"][0].as_py(), data, offsets, ids, w, keys, which

    def first(table: pa.Table) -> pa.Table:
        chunk, *_, keys, _ = read(table)
        return ask_prints(chunk, keys, buckets)

    def candidates(state, flags: np.ndarray):
        """Runs that stay, the distinct piece of each, and rows, smallest id and bucket of the pieces by bucket."""
        _, data, offsets, ids, w, keys, which = state
        # Documents by id: rows that repeat an id are one document.
        owner = np.searchsorted(offsets, w.first, "right") - 1
        number = np.cumsum(np.append(0, ids[1:] != ids[:-1]))[owner]
        low, high = np.full(len(keys), np.iinfo(np.int64).max), np.full(len(keys), -1)
        np.minimum.at(low, which, number)
        np.maximum.at(high, which, number)
        hit = np.flatnonzero((flags | (low != high))[which])
        rows = pieces.cut(data, w.place[hit], w.first[hit], w.last[hit])
        distinct, piece = np.unique(rows.view(f"V{pieces.width}").ravel(), return_inverse=True) if len(hit) else (rows, hit)
        distinct = distinct.view(np.uint8).reshape(-1, pieces.width)
        doc = np.full(len(distinct), np.iinfo(np.int64).max)
        np.minimum.at(doc, piece, ids[owner[hit]])
        value = np.zeros(len(distinct), U)
        value[piece] = w.value[hit]
        to = (mix(value ^ U(0x5851F42D4C957F2D)) % U(buckets)).astype(np.int64)
        order = np.argsort(to, kind="stable")
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        return hit, rank[piece], ids[owner[hit]], distinct[order], doc[order], to[order]

    def second(table: pa.Table, box: dict[int, bytes]) -> pa.Table:
        if not table.num_rows:
            return mail(0, np.zeros(0, np.int64), [])
        state = read(table)
        flags = read_flags(state[-2], box, buckets)
        *_, rows, doc, to = candidates(state, flags)
        used, a, b = cut(to, buckets)
        note = [np.packbits(flags).tobytes()]
        return mail(state[0], np.append(used, note_to_self(state[0])), [pieces.pack(rows[i:j], doc[i:j]) for i, j in zip(a, b, strict=True)] + note)

    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept", pa.string() if digest else pa.binary())])

    def finish(table: pa.Table, box: dict[int, bytes]) -> pa.Table:
        if not table.num_rows:
            return schema.empty_table()
        state = read(table)
        chunk, data, offsets, ids, w, keys, _ = state
        flags = np.unpackbits(np.frombuffer(box[note_to_self(chunk)], np.uint8), count=len(keys)).astype(bool)
        hit, piece, owner, _, doc, to = candidates(state, flags)
        place, a, b = w.place[hit], w.first[hit], w.last[hit]
        mask = np.zeros(len(doc), U)
        for bucket, i, j in zip(*cut(to, buckets), strict=True):
            mask[i:j] = np.frombuffer(box[int(bucket)], U)
        mask = mask[piece]
        # All windows of a piece that belongs to a later document of this chunk go too.
        mask[owner > doc[piece]] = ~U(0)
        some = np.flatnonzero(mask)
        width = (b - a + 1)[some]
        at = np.repeat(a[some] - np.append(0, np.cumsum(width)[:-1]), width) + np.arange(width.sum())
        at = at[(np.repeat(mask[some], width) >> (np.repeat(place[some], width) - at).astype(U) & U(1)).astype(bool)]
        cover = np.bincount(at, minlength=len(data) + 1) - np.bincount(at + length, minlength=len(data) + 1)
        dead = np.cumsum(cover)[: len(data)] > 0
        total = np.append(0, np.cumsum(dead))
        begins = dead & ~np.append(False, dead[:-1])
        heads = offsets[:-1][offsets[:-1] < len(data)]
        begins[heads] = dead[heads]
        spans = np.append(0, np.cumsum(begins))
        removed = total[offsets[1:]] - total[offsets[:-1]]
        kept = []
        for i in range(len(ids)):
            part = data[offsets[i] : offsets[i + 1]]
            part = (part[~dead[offsets[i] : offsets[i + 1]]] if removed[i] else part).tobytes()
            kept.append(hashlib.sha256(part).hexdigest() if digest else part)
        return pa.table([ids_out(ids), pa.array(np.diff(offsets), pa.int64()), pa.array(removed, pa.int64()), pa.array(spans[offsets[1:]] - spans[offsets[:-1]], pa.int64()), pa.array(kept, schema.field("kept").type)], schema=schema)

    known = chunked.replies(chunked.ask(first), repeated_elsewhere)
    sorted_ = chunked.replies(chunked.then(known, second), pieces.resolve)
    return chunked.then(sorted_, finish, f"doc_id long, n_bytes long, n_removed long, n_spans long, kept {'string' if digest else 'binary'}")


def op7_suffix_array_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeated_bytes(documents(spark, sf_dir), length=50, digest=True).withColumnRenamed("kept", "kept_sha256")

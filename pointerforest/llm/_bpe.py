"""Byte-pair merging over ragged numpy arrays, in step over many pre-tokens."""

from __future__ import annotations

import heapq
import json
import re
import unicodedata

import numpy as np
import regex

NO_RANK = np.iinfo(np.int32).max


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, extra = [""] * 256, 0
    for b in range(256):
        if b in plain:
            out[b] = chr(b)
        else:
            out[b] = chr(256 + extra)
            extra += 1
    return out


class MergeTable:
    """Vocabulary and merge ranks of a word-end BPE file, ready for array lookups."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab, merges = spec["model"]["vocab"], spec["model"]["merges"]
        suffix = spec["model"].get("end_of_word_suffix") or ""
        pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
        keys = np.array([vocab[a] << 32 | vocab[b] for a, b in pairs], np.int64)
        made = np.array([vocab[a + b] for a, b in pairs], np.int64)
        # A key stays with its lowest rank.
        keys, first = np.unique(keys, return_index=True)
        self.keys, self.rank, self.made = keys, first.astype(np.int32), made[first]
        self.lookup = {int(k): (int(r), int(m)) for k, r, m in zip(keys, self.rank, self.made, strict=True)}
        symbols = byte_symbols()
        self.inner = np.array([vocab[s] for s in symbols], np.int64)
        self.last = np.array([vocab[s + suffix] for s in symbols], np.int64)
        self.specials = [t["content"] for t in spec["added_tokens"]]
        self.special = re.compile("(" + "|".join(map(re.escape, self.specials)) + ")") if self.specials else None
        pattern = spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]
        self.pieces = regex.compile(pattern.replace(r"\s", r"\p{White_Space}"))

    def pretokens(self, word: str) -> tuple[list[str], int]:
        """Pre-tokens of a stretch without white space, and how many special tokens it holds."""
        found, special = [], 0
        for k, part in enumerate(self.special.split(word) if self.special and "<|" in word else [word]):
            if k % 2:
                special += 1
            elif part:
                if not part.isascii():
                    part = unicodedata.normalize("NFC", part).replace("Σ", "σ")
                found += self.pieces.findall(part.lower())
        return found, special

    def ranks_of(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = left << 32 | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.rank[at], NO_RANK), at

    def count(self, pretokens: list[str], long: int = 512) -> np.ndarray:
        """Number of symbols that survive in each pre-token.

        All sequences advance together: in each step every sequence merges all
        places of its own lowest-ranked pair, left to right without overlap, until
        no sequence has a pair in the table. Sequences beyond ``long`` symbols need
        many steps and go through a heap instead; the result is the same.
        """
        raw = [p.encode() for p in pretokens]
        size = np.fromiter(map(len, raw), np.int64, len(raw))
        out = size.copy()
        for i in np.flatnonzero(size > long):
            out[i] = self._count_long(raw[i])
        short = np.flatnonzero((size <= long) & (size > 1))
        for at in range(0, len(short), 1 << 17):
            who = short[at : at + (1 << 17)]
            out[who] = self._count_short([raw[i] for i in who], size[who])
        return out

    def _count_short(self, raw: list[bytes], size: np.ndarray) -> np.ndarray:
        ids = self.inner[np.frombuffer(b"".join(raw), np.uint8)]
        end = np.cumsum(size)
        ids[end - 1] = self.last[np.frombuffer(b"".join(raw), np.uint8)[end - 1]]
        owner = np.repeat(np.arange(len(raw)), size)
        out = size.copy()
        while len(ids) > 1:
            rank, at = self.ranks_of(ids[:-1], ids[1:])
            rank[owner[:-1] != owner[1:]] = NO_RANK
            rank = np.append(rank, NO_RANK)
            first = np.flatnonzero(np.append(True, owner[1:] != owner[:-1]))
            lowest = np.minimum.reduceat(rank, first)
            width = np.diff(np.append(first, len(ids)))
            going = np.repeat(lowest, width)
            hit = (rank == going) & (going != NO_RANK)
            # In a run of touching hits (a symbol paired with itself) every second one counts.
            where = np.flatnonzero(hit)
            if len(where):
                run = np.append(True, np.diff(where) != 1)
                place = np.arange(len(where)) - np.maximum.accumulate(np.where(run, np.arange(len(where)), 0))
                where = where[place % 2 == 0]
            ids[where] = self.made[at[where]]
            keep = np.ones(len(ids), bool)
            keep[where + 1] = False
            keep &= going != NO_RANK  # finished sequences leave
            out -= np.bincount(owner[where], minlength=len(raw))
            ids, owner = ids[keep], owner[keep]
        return out

    def _count_long(self, raw: bytes) -> int:
        ids = [int(self.inner[b]) for b in raw[:-1]] + [int(self.last[raw[-1]])]
        after, before = list(range(1, len(ids) + 1)), list(range(-1, len(ids) - 1))
        heap = [(*self.lookup[k], i) for i in range(len(ids) - 1) if (k := ids[i] << 32 | ids[i + 1]) in self.lookup]
        heap = [(r, i, m) for r, m, i in heap]
        heapq.heapify(heap)
        alive = len(ids)
        while heap:
            rank, i, made = heapq.heappop(heap)
            j = after[i]
            if ids[i] < 0 or j >= len(ids) or self.lookup.get(ids[i] << 32 | ids[j], (None,))[0] != rank:
                continue
            ids[i], ids[j], alive = made, -1, alive - 1
            after[i] = after[j]
            if after[j] < len(ids):
                before[after[j]] = i
            for a, b in ((before[i], i), (i, after[i])):
                if a >= 0 and b < len(ids) and (got := self.lookup.get(ids[a] << 32 | ids[b])):
                    heapq.heappush(heap, (got[0], a, got[1]))
        return alive

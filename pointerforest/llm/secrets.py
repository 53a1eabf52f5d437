"""Secret scans: fixed patterns, and a linear-chain conditional random field on top.

A sequence is one line of a text, its tokens the runs of letters, digits and ``_+/-``.
Each is tagged as begin, inside or outside of a secret from its own shape (length, kinds
of characters, how often they change, known prefixes), its neighbours (credential words
before it, the marks between) and the file (share of digits and of code marks). Weights
are fitted by gradient ascent on the conditional likelihood of generated lines: words,
numbers, names and code as they occur around secrets, with secrets of many formats.

Decoding is exact Viterbi. Most lines need none: a path that tags anything gains at most
the sum of its tokens' margins over "outside" plus transition gains, so a line without
a token whose margin makes up for the gain stays outside as a whole.

The field adds spans (kind ``crf``) where the patterns have none.

Defined results: null and empty texts have no spans; rows that repeat an id each give a
row; an empty table gives no rows; extra columns are ignored; a null id stays null.
Texts are read whole, whatever their length.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ._spark import documents, with_columns
from ._text import flat_bytes, groups_of, ids_of, ids_out, release

# The base patterns and the least length of what they must match.
KINDS = ("assign", "access", "hex")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")  # the runs of 32 or more
LEAST_VALUE, LEAST_ACCESS = 8, 16
_HINTS = ("passw", "secret", "token", "apikey", "api_key")

# Words that announce a credential, and how known credentials begin.
CREDENTIAL_WORDS = "password passwd pwd secret token apikey api_key key auth bearer credential credentials authorization access_key secret_key client_secret private_key signature"
PREFIXES = ("ghp_", "gho_", "sk_live_", "sk_test_", "xoxb-", "xoxp-", "AKIA", "ASIA", "eyJ", "AIza", "glpat-", "npm_", "SG")


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the fixed patterns, leftmost and non-overlapping per kind."""
    out = []
    low = text.lower()
    if any(h in low for h in _HINTS):
        out += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= LEAST_VALUE]
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST_ACCESS]
    out += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


def written(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def _table(chars: str) -> np.ndarray:
    t = np.zeros(256, bool)
    t[np.frombuffer(chars.encode(), np.uint8)] = True
    return t


_LOWER, _UPPER = _table("abcdefghijklmnopqrstuvwxyz"), _table("ABCDEFGHIJKLMNOPQRSTUVWXYZ")
_DIGIT, _JOIN = _table("0123456789"), _table("_+/-")
_HIGH = np.arange(256) >= 128
_TOKEN = _LOWER | _UPPER | _DIGIT | _JOIN | _HIGH
_ASSIGNS, _QUOTES, _CODE = _table("=:"), _table("\"'`"), _table("{}()[];=<>")
_NOT_HEX = _TOKEN & ~(_DIGIT | _table("abcdefABCDEF"))

LENGTHS = np.array([4, 8, 12, 16, 20, 24, 32, 40, 64])
NAMES = (
    [f"length>={n}" for n in LENGTHS] + ["digit", "lower", "upper", "joiner", "high", "no_letter", "hex_16", "digit_and_both_cases", "digits>=20%", "changes>=20%", "changes>=40%", "prefix", "credential_word"]
    + ["word_before", "word_two_before", "assign_before", "quote_before", "quote_after", "line_start", "word_before_assign", "long_and_digit_after_word", "after_point", "before_point", "previous_odd", "next_odd", "file_digits", "file_code"]
)
_ODD_AT = NAMES.index("digit_and_both_cases")


@dataclass
class Tokens:
    start: np.ndarray
    end: np.ndarray
    line: np.ndarray
    x: np.ndarray  # features, float32


_words: list[set[bytes]] = []


def file_shares(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Share of digits and of code marks in each text."""
    bytes_ = np.maximum(np.diff(offsets), 1)
    share = lambda t: ((c := np.append(0, np.cumsum(t[data], dtype=np.int64)))[offsets[1:]] - c[offsets[:-1]]) / bytes_
    return share(_DIGIT), share(_CODE)


def tokens(data: np.ndarray, offsets: np.ndarray, shares: tuple[np.ndarray, np.ndarray] | None = None) -> Tokens:
    """Tokens of all texts with their features; lines are numbered across texts.

    ``shares``: of the whole files, where these texts are parts of them.
    """
    digits, code = shares or file_shares(data, offsets)
    n = len(data)
    inside = _TOKEN[data]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    before = np.append(False, inside[:-1])[:n] & ~edge[:-1]
    after = np.append(inside[1:], False)[:n] & ~edge[1:]
    start, end = np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1
    breaks = np.append(0, np.cumsum((data == 10) | edge[:-1]))
    line = breaks[start + 1] if len(start) else start
    size = end - start
    total = lambda t: (c := np.append(0, np.cumsum(t[data], dtype=np.int32)))[end] - c[start]
    digit, lower, upper, join, high = (total(t) for t in (_DIGIT, _LOWER, _UPPER, _JOIN, _HIGH))
    kind = (_LOWER[data] * np.uint8(1) + _UPPER[data] * np.uint8(2) + _DIGIT[data] * np.uint8(3)).astype(np.uint8)
    change = np.append(0, np.cumsum(np.append(False, kind[1:] != kind[:-1])[:n], dtype=np.int32))
    changes = change[end] - change[np.minimum(start + 1, n)] if n else size
    left, right = np.maximum(start - 1, 0), np.minimum(end, max(n - 1, 0))
    first = np.append(True, line[1:] != line[:-1]) if len(line) else np.zeros(0, bool)
    last = np.append(first[1:], True) if len(line) else first
    gap = lambda t: (c := np.append(0, np.cumsum(t[data], dtype=np.int32)))[start] - np.where(first, c[left], c[np.append(0, end[:-1])[: len(start)]]) > 0

    # Only a token of letters up to a certain length can be a credential word, only a longer one can have a prefix.
    if not _words:
        _words.append({w.encode() for w in CREDENTIAL_WORDS.split()})
    credential, prefix = np.zeros(len(start), bool), np.zeros(len(start), bool)
    initial = np.zeros(256, bool)
    initial[[c for w in _words[0] for c in (w[0], w[0] - 32)]] = True
    raw = data.tobytes()
    for i in np.flatnonzero((size >= 3) & (size <= 16) & (digit == 0) & initial[data[start]] if n else np.zeros(0, bool)).tolist():
        credential[i] = raw[start[i] : end[i]].lower() in _words[0]
    begins = tuple(p.encode() for p in PREFIXES)
    opens = np.zeros(256, bool)
    opens[[p[0] for p in begins]] = True
    for i in np.flatnonzero((size >= 12) & (digit > 0) & opens[data[start]] if n else np.zeros(0, bool)).tolist():
        prefix[i] = raw.startswith(begins, start[i], end[i])

    previous = lambda v: np.where(first, False, np.append(False, v[:-1])[: len(v)])
    following = lambda v: np.where(last, False, np.append(v[1:], False)[: len(v)])
    odd = (digit > 0) & (lower > 0) & (upper > 0)
    word1 = previous(credential)
    word2 = previous(word1)
    assign = gap(_ASSIGNS)
    text = np.searchsorted(offsets, start, "right") - 1
    columns = [size >= k for k in LENGTHS] + [
        digit > 0, lower > 0, upper > 0, join > 0, high > 0, (lower + upper + high) == 0, (size >= 16) & (total(_NOT_HEX) == 0) & (digit > 0), odd, digit * 5 >= size, changes * 5 >= size, changes * 5 >= 2 * size, prefix, credential,
        word1, word2, assign, gap(_QUOTES), _QUOTES[data[right]] if n else first, first, word1 & assign, (word1 | word2) & (size >= 12) & (digit > 0), (data[left] == 46) & ~first if n else first, (data[right] == 46) & ~last if n else first, previous(odd), following(odd), (digits >= 0.03)[text], (code >= 0.02)[text],
    ]
    return Tokens(start, end, line, np.stack(columns, axis=1).astype(np.float32) if len(start) else np.zeros((0, len(NAMES)), np.float32))


@dataclass
class Field:
    """Weights of features for begin and inside (outside has none) and of transitions; tags O, B, I."""

    w: np.ndarray  # features x 3
    bias: np.ndarray
    step: np.ndarray  # 3 x 3

    def unary(self, x: np.ndarray) -> np.ndarray:
        return x @ self.w + self.bias


FORBIDDEN = -1e4  # inside can't follow outside, nor begin a line


def viterbi(unary: np.ndarray, step: np.ndarray) -> np.ndarray:
    """Best tags of one line."""
    n = len(unary)
    score = unary[0] + np.array([0.0, 0.0, FORBIDDEN])
    back = np.zeros((n, 3), np.int64)
    for t in range(1, n):
        s = score[:, None] + step
        back[t] = s.argmax(axis=0)
        score = s[back[t], [0, 1, 2]] + unary[t]
    tags = np.zeros(n, np.int64)
    tags[-1] = score.argmax()
    for t in range(n - 1, 0, -1):
        tags[t - 1] = back[t, tags[t]]
    return tags


def decode(field: Field, t: Tokens) -> list[tuple[int, int]]:
    """(start, end) in bytes of what is tagged."""
    if not len(t.start):
        return []
    u = field.unary(t.x)
    margin = np.maximum(u[:, 1], u[:, 2]) - u[:, 0]
    # What a tagged token can gain by its transitions at most: one into it and one out of its stretch.
    allowed = field.step.copy()
    allowed[0, 2] = -np.inf
    gain = max(0.0, float(allowed[:, 1:].max() - field.step[0, 0])) + max(0.0, float(allowed[1:, 0].max() - field.step[0, 0]))
    found = []
    edges = np.append(np.flatnonzero(np.append(True, t.line[1:] != t.line[:-1])), len(t.line))
    for k in np.unique(np.searchsorted(edges, np.flatnonzero(margin + gain >= 0), "right") - 1).tolist():
        a, b = int(edges[k]), int(edges[k + 1])
        tags = viterbi(u[a:b], field.step)
        i = 0
        while i < b - a:
            if tags[i] == 0:
                i += 1
                continue
            j = i + 1
            while j < b - a and tags[j] == 2:
                j += 1
            found.append((int(t.start[a + i]), int(t.end[a + j - 1])))
            i = j
    return found


def _lines(seed: int, count: int) -> list[tuple[str, list[tuple[int, int]]]]:
    """Generated lines with the places of their secrets."""
    rng = np.random.default_rng(seed)
    pick = lambda s: s[int(rng.integers(len(s)))]
    draw = lambda chars, a, b: "".join(pick(chars) for _ in range(int(rng.integers(a, b + 1))))
    small, big, nums = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    vowels = "aeiouéóäü"
    any_ = small + big + nums

    def word() -> str:
        w = "".join(pick("bcdfghlmnprstvwz") + pick(vowels) for _ in range(int(rng.integers(1, 6)))) + pick(["", "n", "t", "ing", "s", "ción", "ung"])
        return pick([w, w, w, w, w.capitalize(), w.upper(), w + pick(",.;!?")])

    def harmless() -> str:
        return pick([
            draw(nums, 1, 6), f"{draw(nums, 4, 4)}-{draw(nums, 2, 2)}-{draw(nums, 2, 2)}", f"+1 ({draw(nums, 3, 3)}) {draw(nums, 3, 3)}-{draw(nums, 4, 4)}", f"v{draw(nums, 1, 1)}.{draw(nums, 1, 2)}", f"{word()}@{draw(small, 4, 8)}.com", f"https://{draw(small, 4, 9)}.org/{draw(small, 3, 8)}/{draw(nums, 1, 5)}",
            word().capitalize() + word().capitalize(), f"{draw(small, 3, 7)}_{draw(small, 3, 7)}", draw(big, 2, 8), f"{draw(small, 3, 8)}{draw(nums, 1, 3)}", f"{draw(nums, 4, 4)} {draw(nums, 4, 4)} {draw(nums, 4, 4)} {draw(nums, 4, 4)}", f"{draw(nums, 1, 3)}.{draw(nums, 1, 3)}.{draw(nums, 1, 3)}.{draw(nums, 1, 3)}", "-".join(word() for _ in range(3)), f"{pick(CREDENTIAL_WORDS.split())} {word()}", f"{draw(small, 2, 5)}{draw(nums, 10, 14)}", draw(small, 14, 45), draw(big + "ÉÄÑ", 10, 30), draw(nums, 10, 16),
        ])

    def secret() -> tuple[str, str, str]:
        """(before, secret, after)"""
        value = pick([
            lambda: draw(any_, 20, 44), lambda: draw(any_ + "+/", 28, 64), lambda: draw("0123456789abcdef", 16, 31), lambda: "ghp_" + draw(any_, 30, 36), lambda: "sk_live_" + draw(any_, 20, 28), lambda: "xoxb-" + draw(nums, 10, 12) + "-" + draw(any_, 20, 24), lambda: "AIza" + draw(any_ + "_-", 32, 35),
            lambda: f"eyJ{draw(any_, 16, 40)}.{draw(any_, 20, 60)}.{draw(any_ + '_-', 20, 44)}", lambda: "AKIA" + draw(big + nums, 16, 16), lambda: draw("0123456789abcdef", 32, 64), lambda: draw(any_, 10, 16) + draw(nums, 1, 2) + pick(small) + pick(big),
        ])()
        key = pick(CREDENTIAL_WORDS.split())
        key = pick([key, key.upper(), key.capitalize(), f"{draw(small, 2, 5)} {key}"])
        before, after = pick([(f"{key}=", ""), (f"{key}: ", ""), (f'{key} = "', '"'), (f'"{key}": "', '",'), (f"{key} ", ""), (f"{key} is ", ""), ("", ""), ("Bearer ", ""), (f"export {key}=", "")])
        strong = value.startswith(PREFIXES) or len(value) >= 24
        return ("key=", value, "") if not before and not strong else (before, value, after)

    out = []
    for _ in range(count):
        parts, spans, at = [], [], 0
        code = rng.random() < 0.25
        n = int(rng.integers(2, 14))
        where = int(rng.integers(n)) if rng.random() < 0.55 else -1
        for i in range(n):
            if i == where:
                before, value, after = secret()
                spans.append((at + len(before.encode()), at + len((before + value).encode())))
                piece = before + value + after
            else:
                piece = harmless() if rng.random() < 0.25 else f"{word()}={word()};" if code else word()
            parts.append(piece)
            at += len(piece.encode()) + 1
        out.append((" ".join(parts), spans))
    return out


@lru_cache(maxsize=1)
def trained_field(lines: int = 1600, rounds: int = 120, seed: int = 7) -> Field:
    """Fit by Adam on the conditional log-likelihood, all lines at once (padded)."""
    made = _lines(seed, lines)
    data, offsets = flat_bytes(pa.array([t for t, _ in made], pa.string()))
    t = tokens(data, offsets)
    row = np.searchsorted(offsets, t.start, "right") - 1
    tag = np.zeros(len(row), np.int64)
    for i, (_, spans) in enumerate(made):
        for a, b in spans:
            who = np.flatnonzero((row == i) & (t.start >= offsets[i] + a) & (t.end <= offsets[i] + b))
            tag[who] = 2
            tag[who[:1]] = 1
    count = np.bincount(row, minlength=lines)
    width = int(count.max())
    place = np.arange(len(row)) - np.append(0, np.cumsum(count))[row]
    real = np.zeros((lines, width), bool)
    real[row, place] = True
    gold = np.zeros((lines, width, 3))
    gold[row, place, tag] = 1
    both = real[:, 1:] & real[:, :-1]
    gold_step = np.einsum("ntj,ntk,nt->jk", gold[:, :-1], gold[:, 1:], both)
    mask = np.zeros((3, 3))
    mask[0, 2] = FORBIDDEN
    w, bias, step = np.zeros((t.x.shape[1], 3)), np.array([0.0, -2.0, -2.0]), np.zeros((3, 3))
    params = [w, bias, step]
    m, v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    lse = lambda a, axis: (b := a.max(axis=axis, keepdims=True)).squeeze(axis) + np.log(np.exp(a - b).sum(axis=axis))
    for k in range(1, rounds + 1):
        u = np.zeros((lines, width, 3))
        u[row, place] = t.x @ params[0] + params[1]
        s = params[2] + mask
        forward, backward = np.zeros_like(u), np.zeros_like(u)
        forward[:, 0] = u[:, 0] + [0, 0, FORBIDDEN]
        for i in range(1, width):
            new = lse(forward[:, i - 1, :, None] + s, 1) + u[:, i]
            forward[:, i] = np.where(real[:, i, None], new, forward[:, i - 1])
        for i in range(width - 2, -1, -1):
            new = lse(s + (u[:, i + 1] + backward[:, i + 1])[:, None, :], 2)
            backward[:, i] = np.where(real[:, i + 1, None], new, 0)
        z = lse(forward[:, -1], 1)
        p = np.exp(forward + backward - z[:, None, None]) * real[..., None]
        pair = forward[:, :-1, :, None] + s + (u[:, 1:] + backward[:, 1:])[:, :, None, :] - z[:, None, None, None]
        pair = (np.exp(np.minimum(pair, 0)) * both[..., None, None]).sum(axis=(0, 1))
        rest = (gold * real[..., None] - p)[row, place]
        grads = [t.x.T @ rest, rest.sum(axis=0), gold_step - pair]
        grads[0][:, 0] = 0
        grads[1][0] = 0
        for j, g in enumerate(grads):
            g = g / lines - 1e-4 * params[j]
            m[j] = 0.9 * m[j] + 0.1 * g
            v[j] = 0.999 * v[j] + 0.001 * g * g
            params[j] += 0.15 * (m[j] / (1 - 0.9**k)) / (np.sqrt(v[j] / (1 - 0.999**k)) + 1e-8)
    return Field(params[0].astype(np.float32), params[1].astype(np.float32), params[2] + mask)


#: Bytes of one text whose tokens are held at a time (or one longer line).
LONG = 1 << 20


def field_spans(field: Field, data: np.ndarray, offsets: np.ndarray) -> dict[int, list[tuple[int, int]]]:
    """Text number -> (start, end) in code points of what the field tags."""
    if len(offsets) == 2 and len(data) > LONG:
        return {0: _long_spans(field, data)}
    out: dict[int, list[tuple[int, int]]] = {}
    found = decode(field, tokens(data, offsets))
    if found:
        points = np.append(0, np.cumsum((data & 0xC0) != 0x80))
        for a, b in found:
            i = int(np.searchsorted(offsets, a, "right")) - 1
            b = min(_padded(data, a, b), int(offsets[i + 1]))
            out.setdefault(i, []).append((int(points[a] - points[offsets[i]]), int(points[b] - points[offsets[i]])))
    return out


def _padded(data: np.ndarray, a: int, b: int) -> int:
    while b < len(data) and data[b] == 61 and (b - a) % 4:
        b += 1
    return b


def _long_spans(field: Field, data: np.ndarray) -> list[tuple[int, int]]:
    """The same for one text in runs of whole lines: nothing but the file's shares reaches beyond a line."""
    n, at, before, out = len(data), 0, 0, []
    count = lambda t: sum(int(np.count_nonzero(t[data[a : a + LONG]])) for a in range(0, n, LONG)) / n
    shares = np.array([count(_DIGIT)]), np.array([count(_CODE)])
    while at < n:
        end = min(n, at + LONG)
        if end < n:
            breaks = np.flatnonzero(data[at:end] == 10)
            while not len(breaks) and end < n:  # a line longer than a run
                breaks = np.flatnonzero(data[end : end + LONG] == 10)[:1] + (end - at)
                end = min(n, end + LONG)
            end = at + int(breaks[-1]) + 1 if len(breaks) else n
        part = data[at:end]
        points = np.append(0, np.cumsum((part & 0xC0) != 0x80))
        out += [(before + int(points[a]), before + int(points[_padded(part, a, b)])) for a, b in decode(field, tokens(part, np.array([0, len(part)]), shares))]
        at, before = end, before + int(points[-1])
    return out


def beside(own: list[tuple[int, int, str]], more: list[tuple[int, int]]) -> list[tuple[int, int, str]]:
    """Those of ``more`` that overlap none of ``own`` (sorted by start)."""
    starts = [a for a, _, _ in own]
    reach = list(accumulate((b for _, b, _ in own), max))
    free = lambda a, b: not (k := bisect_left(starts, b)) or reach[k - 1] <= a
    return [(a, b, "crf") for a, b in more if free(a, b)]


def spans_of(field: Field, texts: pa.Array) -> list[list[tuple[int, int, str]]]:
    """(start, end, kind) by start for each text: base patterns, and what the field adds where they have none."""
    data, offsets = flat_bytes(texts)
    out = []
    for i, j in groups_of(offsets, 1 << 19):
        more = field_spans(field, data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
        for k, text in enumerate(texts.slice(i, j - i).to_pylist()):
            own = base_spans(text) if text else []
            out.append(sorted(own + beside(own, more.get(k, [])), key=lambda s: (s[0], (*KINDS, "crf").index(s[2]))))
    return out


def find_secrets(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", field: Field | None = None) -> DataFrame:
    """doc_id, spans: array of (start, end, kind) by start; base patterns and added ones."""
    field = field or trained_field()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.string())]))
        for batch in batches:
            spans = [[{"start": a, "end": b, "kind": c} for a, b, c in s] for s in spans_of(field, batch.column(1))]
            yield pa.RecordBatch.from_arrays([ids_out(ids_of(batch.column(0))), pa.array(spans, kind)], names=["doc_id", "spans"])
            release()

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, spans array<struct<start:long,end:long,kind:string>>")


def mask_secrets(docs: DataFrame, *, text_col: str = "text", field: Field | None = None) -> DataFrame:
    """The documents, with all their columns, and every secret in the text masked."""
    field = field or trained_field()

    def mask(texts: pa.Array) -> list[pa.Array]:
        found = spans_of(field, texts)
        return [pa.array([redact(t, [s[:2] for s in spans]) if spans else t for t, spans in zip(texts.to_pylist(), found, strict=True)], pa.string())]

    return with_columns(docs, text_col, mask, StructType(), replace=True)


def redact(text: str, spans: list[tuple[int, int]]) -> str:
    """Text with the spans (merged where they overlap) replaced by [SECRET]."""
    out, at = [], 0
    for a, b in sorted(spans):
        if a >= at:
            out += [text[at:a], "[SECRET]"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def op1_secret_scan(spark, sf_dir: str) -> DataFrame:
    found = find_secrets(documents(spark, sf_dir))
    number = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    line = lambda c: F.concat_ws(",", F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))
    base = F.filter("spans", lambda s: s["kind"] != "crf")
    return found.select("doc_id", number("assign"), number("access"), number("hex"), F.sha2(line(base), 256).alias("base_sha256"), line("spans").alias("spans"))

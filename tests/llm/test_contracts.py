"""Each registered opN query, columns and all, against brute force over a folder of small tables."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from conftest import SF, rows_of
from test_operators import KINDS, ROWS, VOCABULARY, WORDS, base_by_hand, tokenizers

from pointerforest.llm import packing, queries
from pointerforest.llm._text import flat_bytes, groups_of

OPS = {int(re.match(r"op(\d+)_", n).group(1)): q for n, q in queries.queries().items()}
ODD = ["a", "B", "z", "É", "é", "ß", "Σ", "σ", "İ", "ŉ", "中", "1", "9", "'s", "'", "'T", ".", ",", "!", "%", "<|", "|>", "<|endoftext|>", "<|ENDOFTEXT|>", "<", "|", "̱", "̊", "̇", "\xa0", "\x85", "\x01", "\x00", "\x1c", "😀", "—", "-", "h", "I", "K", "े", " ", " ", "\n", "º"]


@pytest.fixture(scope="module")
def folder(tmp_path_factory):
    """Documents of ``ROWS`` and some with odd characters, spread over files; benchmark and labels."""
    where = tmp_path_factory.mktemp("tables")
    (where / "documents.parquet").mkdir()
    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string()), ("lang", pa.string()), ("source", pa.string()), ("n_chars", pa.int64())])
    for k in range(3):
        rows = TEXTS[k::3]
        pq.write_table(pa.table([[d for d, _ in rows], [t for _, t in rows], ["en"] * len(rows), ["s"] * len(rows), [len(t or "") for _, t in rows]], schema=schema), where / "documents.parquet" / f"part-{k}.parquet")
    pq.write_table(pa.table({"item_id": [1], "text": [ROWS[41][1]]}), where / "benchmark.parquet")
    pq.write_table(pa.table({"doc_id": [d for d, _ in TEXTS], "quality": pa.array([int(d % 7 != 0) for d, _ in TEXTS], pa.int32()), "toxic": pa.array([int(d % 5 == 0) for d, _ in TEXTS], pa.int32())}), where / "labels.parquet")
    return str(where)


_r = random.Random(5)
TEXTS = ROWS + [(100 + i, "".join(_r.choice(ODD) for _ in range(_r.randint(0, 60)))) for i in range(60)] + [(200, " ".join(_r.choice(WORDS) for _ in range(4000))), (201, "ab" * 30000)]


@pytest.fixture(scope="module")
def tokenizer():
    return tokenizers.Tokenizer.from_file(VOCABULARY)


def test_encoder_equals_the_library(tokenizer):
    r = random.Random(6)
    texts = ["".join(r.choice(ODD) for _ in range(r.randint(0, 40))) for _ in range(3000)] + [None, "", "Éa. " * 500]
    memo = packing.Memo()
    data, offsets = flat_bytes(pa.array(texts))
    for _ in range(2):  # from the library, then from the memo
        for a, b in groups_of(offsets, 1 << 14):
            flat, at = packing.encode_all(tokenizer, memo, data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
            for i in range(a, b):
                assert flat[at[i - a] : at[i - a + 1]].tolist() == tokenizer.encode(texts[i] or "", add_special_tokens=False).ids


def test_memo_forgets_and_results_stay(tokenizer, monkeypatch):
    monkeypatch.setattr(packing, "MEMO", 50)
    memo, texts = packing.Memo(), [" ".join(WORDS[i : i + 9]) + f" w{i}." for i in range(30)]
    data, offsets = flat_bytes(pa.array(texts))
    for a, b in groups_of(offsets, 200):
        flat, at = packing.encode_all(tokenizer, memo, data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
        assert [flat[x:y].tolist() for x, y in zip(at, at[1:], strict=False)] == [tokenizer.encode(t, add_special_tokens=False).ids for t in texts[a:b]]
    assert len(memo.young.keys) < 100


def test_op10_places_every_piece(spark, folder, tokenizer):
    got = OPS[10](spark, folder)
    assert got.columns[:7] == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    want = []
    for d, t in TEXTS:
        ids = np.array([*tokenizer.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        want += [(d, k, s, len(ids[s : s + 2048]), zlib.crc32(ids[s : s + 2048].tobytes())) for k, s in enumerate(range(0, len(ids), 2048))]
    rows = got.collect()
    assert Counter(tuple(r)[:5] for r in rows) == Counter(want)
    packed = {}
    for r in rows:
        packed.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in packed.values():
        parts.sort()
        assert all(a == sum(n for _, n in parts[:i]) for i, (a, _) in enumerate(parts)) and sum(n for _, n in parts) <= 2048


def test_op8_counts(spark, folder, tokenizer):
    sizes = {d: (len((t or "").encode()), len(tokenizer.encode(t or "", add_special_tokens=False).ids)) for d, t in TEXTS}
    got = OPS[8](spark, folder)
    assert got.columns[:4] == ["doc_id", "n_bytes", "n_tokens", "over_limit"]
    assert {tuple(r)[:4] for r in got.collect()} == {(d, b, n, n > 2048) for d, (b, n) in sizes.items()}


def test_op5_keeps_the_rest(spark, folder):
    seen, want = set(), set()
    for d, t in sorted(TEXTS):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        gone = set()
        for i in range(len(w) - 19):
            k = tuple(w[i : i + 20])
            if k in seen:
                gone.update(range(i, i + 20))
            seen.add(k)
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        want.add((d, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    got = OPS[5](spark, folder)
    assert got.columns[:4] == ["doc_id", "n_words", "n_removed", "kept_sha256"]
    assert {tuple(r)[:4] for r in got.collect()} == want


def test_op7_keeps_the_rest(spark, folder):
    first, want = {}, set()
    raw = {d: (t or "").encode() for d, t in TEXTS}
    for d in sorted(raw):
        for i in range(len(raw[d]) - 49):
            first.setdefault(raw[d][i : i + 50], d)
    for d, b in raw.items():
        gone = bytearray(len(b))
        for i in range(len(b) - 49):
            if first[b[i : i + 50]] < d:
                gone[i : i + 50] = b"\1" * 50
        runs = sum(g and (i == 0 or not gone[i - 1]) for i, g in enumerate(gone))
        want.add((d, len(b), sum(gone), runs, hashlib.sha256(bytes(c for c, g in zip(b, gone, strict=True) if not g)).hexdigest()))
    got = OPS[7](spark, folder)
    assert got.columns[:5] == ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
    assert {tuple(r)[:5] for r in got.collect()} == want


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_queries_with_sql(spark, duck, name):
    assert rows_of(queries.queries()[name](spark, SF).toPandas()) == rows_of(duck.sql(queries.oracle_sql()[name]).df())


def test_op1_base_columns(spark, folder):
    got = OPS[1](spark, folder)
    assert got.columns[:6] == ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"]
    texts = dict(TEXTS)
    for r in got.collect():
        assert tuple(r)[1:5] == base_by_hand(texts[r["doc_id"]])
        kinds = Counter(s.split(":")[0] for s in r["spans"].split(",") if s)
        assert all(kinds[k] == n for k, n in zip(KINDS, tuple(r)[1:4], strict=True))


def test_op3_statistics_and_verdict(spark, folder):
    got = OPS[3](spark, folder)
    assert got.columns[:8] == ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]
    texts = dict(TEXTS)
    for r in got.collect():
        t = texts[r["doc_id"]] or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        c = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
        covered = {i + k for i in range(len(w) - 2) if c[tuple(w[i : i + 3])] > 1 for k in range(3)}
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        failed = len(w) < 50 or 100 * len(covered) > 50 * len(w)
        assert tuple(r)[1:7] == (len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in t), len(lines) - len(set(lines)), len(covered), failed)
        assert not (failed and r["kept"])


def test_op4_base_and_score(spark, folder):
    got = OPS[4](spark, folder)
    assert got.columns[:7] == ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"]
    lower = lambda t: "".join(c.lower() if c.isascii() else c for c in t)
    toks = {d: [*re.findall(r"[^\x20\x09-\x0D]+", lower(t or "")), None] for d, t in TEXTS}
    held = {d: zlib.crc32(str(d).encode()) % 10 == 0 for d in toks}
    c = Counter(x for d, ts in toks.items() if not held[d] for x in ts)
    n, v = sum(c.values()), len(c)
    for r in got.collect():
        ts = toks[r["doc_id"]]
        assert tuple(r)[1:5] == (held[r["doc_id"]], len(ts), sum(c[x] > 0 for x in ts), n) and r["score"] < 0
        assert math.isclose(r["base_score"], sum(math.log10((c[x] + 0.1) / (n + 0.1 * (v + 1))) for x in ts), rel_tol=1e-9)


def test_op9_scores_and_predictions(spark, folder):
    got = OPS[9](spark, folder)
    assert got.columns[:4] == ["doc_id", "held_out", "score", "predicted"]
    rows = got.collect()
    assert Counter(r["doc_id"] for r in rows) == Counter(d for d, _ in TEXTS)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) and 0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in rows)

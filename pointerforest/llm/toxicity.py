"""Toxicity: gradient-boosted trees over dense text features, calibrated isotonically.

Features of a text (never its id, language, source or label): density, weight and
variety of lexicon words, lexicon words near a second-person word, capitals,
punctuation, and obfuscation (lexicon words that only show after digits and marks
inside a word are read as letters). The lexicon is learned from one half of the labelled
sample (words whose share of toxic documents stands out), the trees from most of the
other half, the calibration from the rest of it.

The labelled sample is bounded by ``max_rows`` (default 20,000 rows, chosen by the hash
of the id); counting and features run on the executors, only the lexicon and the
feature rows of the sample reach the driver.

Defined results: null counts as empty; an empty text gets the score of its all-zero
features; without labels of both kinds every score is the share of toxic labels (0 with
none); rows that repeat an id each give a row; an empty table gives no rows; extra
columns are ignored; a null id counts as held out and stays null.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from ._spark import documents, with_columns
from ._text import IS_SPACE, U, flat_bytes, groups_of, hash_words, ids_of, ids_out, lower_ascii, release, words_of

MAX_ROWS = 20_000
LEXICON = 400
#: Bytes of text looked at together, whatever the size of a batch; some forty times as many are held while they are.
GROUP_BYTES = 1 << 19

# Second-person words of the four languages, without case.
SECOND_PERSON = "you your yours yourself youre u ur du dich dir dein deine deinen deiner euch euer ihr tu te toi ton ta tes vous votre vos tú ti usted ustedes vosotros"
# What stands for which letter in disguised words.
DISGUISE = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s", "!": "i"}

_LETTER = np.zeros(256, bool)
_LETTER[65:91] = _LETTER[97:123] = _LETTER[128:] = True
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_MARK = ~(_LETTER | _DIGIT | IS_SPACE)

#: Only letters and digits, everything else a space.
_PLAIN = np.arange(256, dtype=np.uint8)
_PLAIN[_MARK] = 32
_READ = np.arange(256, dtype=np.uint8)
for _a, _b in DISGUISE.items():
    _READ[ord(_a)] = ord(_b)

FEATURES = (
    "log_words", "lexicon_hits", "lexicon_density", "lexicon_weight", "lexicon_most", "lexicon_variety", "near_second_person",
    "second_person_density", "capital_share", "mark_share", "exclamation_share", "disguised_hits", "mixed_word_share", "word_length",
)


def _hash_of(words: list[str]) -> np.ndarray:
    return hash_words(*flat_bytes(pa.array(words, pa.string())))[0]


def plain_words(data: np.ndarray, offsets: np.ndarray):
    """Hashes of lower-cased words between anything that is no letter or digit, and their number."""
    return hash_words(lower_ascii(_PLAIN[data]), offsets)


def disguised_words(data: np.ndarray, offsets: np.ndarray):
    """Hashes of space-separated words that mix letters with digits or marks, read as letters; and the text of each."""
    start, end, counts = words_of(data, offsets)
    total = lambda flag: (c := np.append(0, np.cumsum(flag)))[end] - c[start]
    # Marks that only end a word (a comma, a full stop) are no disguise.
    inner = np.zeros(len(data) + 1, np.int64)
    np.cumsum((_DIGIT | _MARK)[data], out=inner[1:])
    tail = np.maximum(end - 1, start)
    odd = np.flatnonzero((total(_LETTER[data]) > 0) & (inner[tail] - inner[start] > 0))
    owner = np.repeat(np.arange(len(counts)), counts)[odd]
    raw = data.tobytes()
    read = [_READ[np.frombuffer(raw[a:b], np.uint8)].tobytes() for a, b in zip(start[odd].tolist(), end[odd].tolist(), strict=True)]
    drop = bytes(i for i in range(128) if not chr(i).isalnum())
    words = [w.lower().translate(None, drop) for w in read]
    return hash_words(*flat_bytes(pa.array(words, pa.binary())))[0] if all(words) else _safe(words), owner, counts


def _safe(words: list[bytes]) -> np.ndarray:
    return hash_words(*flat_bytes(pa.array([w or b"-" for w in words], pa.binary())))[0]


@dataclass
class Lexicon:
    hashes: np.ndarray  # sorted
    weights: np.ndarray

    def find(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which words are in the lexicon, and their place there."""
        if not len(self.hashes):
            return np.zeros(len(words), bool), np.zeros(len(words), np.int64)
        at = np.minimum(np.searchsorted(self.hashes, words), len(self.hashes) - 1)
        return self.hashes[at] == words, at


_you: list[np.ndarray] = []


def features(lexicon: Lexicon, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One row of FEATURES for each text."""
    if not _you:
        _you.append(np.sort(_hash_of(SECOND_PERSON.split())))
    n = len(offsets) - 1
    words, counts = plain_words(data, offsets)
    owner = np.repeat(np.arange(n), counts)
    add = lambda who, w=None: np.bincount(who, weights=w, minlength=n)
    hit, at = lexicon.find(words)
    weight = np.where(hit, lexicon.weights[at], 0.0) if len(lexicon.hashes) else np.zeros(len(words))
    you = np.isin(words, _you[0])
    reach = np.append(0, np.cumsum(you))
    place = np.flatnonzero(hit)
    first = np.append(0, np.cumsum(counts))
    low, high = np.maximum(place - 4, first[owner[place]]), np.minimum(place + 5, first[owner[place] + 1])
    near = (reach[high] - reach[low]) > 0
    most = np.zeros(n)
    np.maximum.at(most, owner[place], weight[place])
    variety = np.bincount(np.unique(owner[place] * np.int64(1 << 20) + at[place]) >> 20, minlength=n) if len(place) else np.zeros(n)
    size = np.maximum(np.diff(offsets), 1)
    share = lambda flag: (c := np.append(0, np.cumsum(flag)))[offsets[1:]] - c[offsets[:-1]]
    odd, odd_owner, raw_counts = disguised_words(data, offsets)
    odd_hit, _ = lexicon.find(odd)
    letters = np.maximum(share(_LETTER[data]), 1)
    some = np.maximum(counts, 1)
    return np.stack([
        np.log1p(counts), add(owner[place]), add(owner[place]) / some, add(owner, weight), most, variety, add(owner[place][near]),
        add(owner, you.astype(float)) / some, share(_UPPER[data]) / letters, share(_MARK[data]) / size, share(data == 33) / size,
        add(odd_owner[odd_hit]), add(odd_owner) / np.maximum(raw_counts, 1), letters / some,
    ], axis=1)


@dataclass
class Trees:
    """Boosted trees of one depth, as arrays; and a calibration curve."""

    feature: np.ndarray  # trees x inner nodes
    threshold: np.ndarray
    leaf: np.ndarray  # trees x leaves
    start: float
    curve: tuple[np.ndarray, np.ndarray]

    def raw(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.start)
        rows = np.arange(len(x))
        depth = int(np.log2(self.leaf.shape[1])) if len(self.leaf) else 0
        for f, t, leaf in zip(self.feature, self.threshold, self.leaf, strict=True):
            node = np.zeros(len(x), np.int64)
            for _ in range(depth):
                node = 2 * node + 1 + (x[rows, f[node]] > t[node])
            out += leaf[node - (len(leaf) - 1)]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        """Calibrated probability; within a flat stretch of the curve the raw order stays."""
        p = 1 / (1 + np.exp(-self.raw(x)))
        return 0.999 * np.interp(p, *self.curve) + 0.001 * p


def boost(x: np.ndarray, y: np.ndarray, *, trees: int = 80, depth: int = 3, rate: float = 0.15, bins: int = 64, ridge: float = 1.0) -> Trees:
    """Newton boosting of the logistic loss on histograms of quantile bins."""
    n, m = x.shape
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins)[1:-1])) for j in range(m)]
    codes = np.stack([np.searchsorted(e, x[:, j], "left") for j, e in enumerate(edges)], axis=1)
    flat = codes + np.arange(m) * bins
    share = np.clip(y.mean(), 1e-4, 1 - 1e-4)
    start = float(np.log(share / (1 - share)))
    margin = np.full(n, start)
    inner = 2**depth - 1
    feature, threshold, leaf = np.zeros((trees, inner), np.int64), np.full((trees, inner), np.inf), np.zeros((trees, inner + 1))
    for k in range(trees):
        p = 1 / (1 + np.exp(-margin))
        g, h = p - y, np.maximum(p * (1 - p), 1e-6)
        node = np.zeros(n, np.int64)
        for level in range(depth):
            for i in range(2**level - 1, 2 ** (level + 1) - 1):
                who = np.flatnonzero(node == i)
                if len(who) >= 20:
                    at = flat[who].ravel()
                    hist = lambda v: np.bincount(at, np.repeat(v[who], m), m * bins).reshape(m, bins)  # noqa: B023, E731
                    gl, hl = np.cumsum(hist(g), axis=1), np.cumsum(hist(h), axis=1)
                    gt, ht = gl[:, -1:], hl[:, -1:]
                    gain = gl**2 / (hl + ridge) + (gt - gl) ** 2 / (ht - hl + ridge) - gt**2 / (ht + ridge)
                    gain[(hl < 1) | (ht - hl < 1)] = 0
                    j, b = np.unravel_index(int(gain.argmax()), gain.shape)
                    if gain[j, b] > 1e-6 and b < len(edges[j]):
                        feature[k, i], threshold[k, i] = j, edges[j][b]
            node = 2 * node + 1 + (x[np.arange(n), feature[k, node]] > threshold[k, node])
        place = node - inner
        leaf[k] = -rate * np.bincount(place, g, inner + 1) / (np.bincount(place, h, inner + 1) + ridge)
        margin += leaf[k, place]
    return Trees(feature, threshold, leaf, start, (np.array([0.0, 1.0]), np.array([0.0, 1.0])))


def isotonic(p: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool adjacent violators; the curve as points to interpolate between."""
    order = np.argsort(p, kind="stable")
    blocks: list[list[float]] = []  # sum of y, weight, sum of p
    for a, b in zip(p[order].tolist(), y[order].tolist(), strict=True):
        blocks.append([b, 1.0, a])
        while len(blocks) > 1 and blocks[-2][0] * blocks[-1][1] >= blocks[-1][0] * blocks[-2][1]:
            s, w, q = blocks.pop()
            blocks[-1][0] += s
            blocks[-1][1] += w
            blocks[-1][2] += q
    # Half a case at either side keeps the ends off 0 and 1.
    return np.array([q / w for _, w, q in blocks]), np.array([(s + 0.5 * s / w) / (w + 0.5) for s, w, _ in blocks])


@dataclass
class Model:
    lexicon: Lexicon
    trees: Trees
    prior: float

    def score(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        if not len(self.trees.leaf):
            return np.full(len(offsets) - 1, self.prior)
        return self.trees.score(features(self.lexicon, data, offsets))


def in_groups(texts: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of texts of ``GROUP_BYTES`` (or one longer text): first row, row after the last, bytes, offsets."""
    data, offsets = flat_bytes(texts)
    for i, j in groups_of(offsets, GROUP_BYTES):
        yield i, j, data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]


def word_counts(texts: pa.Array, toxic: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each group of texts its distinct words (hashes) and how many toxic and other texts have each."""
    for i, j, data, offsets in in_groups(texts):
        words, counts = plain_words(data, offsets)
        owner = np.repeat(np.arange(i, j), counts)
        order = np.lexsort((owner, words))
        w, o = words[order], owner[order]
        new = np.append(True, (w[1:] != w[:-1]) | (o[1:] != o[:-1])) if len(w) else np.zeros(0, bool)
        w, o = w[new], o[new]
        distinct, which = np.unique(w, return_inverse=True)
        bad = np.bincount(which, toxic[o], len(distinct)).astype(np.int64)
        yield distinct, bad, np.bincount(which, minlength=len(distinct)) - bad


def text_features(lexicon: Lexicon, texts: pa.Array) -> np.ndarray:
    parts = [features(lexicon, data, offsets) for _, _, data, offsets in in_groups(texts)]
    return np.concatenate(parts) if parts else np.zeros((0, len(FEATURES)))


def learn_lexicon(sample: DataFrame, *, size: int = LEXICON, least: int = 3, evidence: float = 12.0) -> Lexicon:
    """Words of (text, toxic) rows that stand out in toxic documents, weighed by the log of the ratio of shares.

    ``evidence``: least log-likelihood ratio (doubled) against an equal share.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            toxic = batch.column(1).to_numpy(zero_copy_only=False) > 0
            for word, bad, good in word_counts(batch.column(0), toxic):
                yield pa.RecordBatch.from_arrays([pa.array(word.view(np.int64)), pa.array(bad), pa.array(good)], names=["word", "bad", "good"])
            release()

    n = sample.agg(F.sum("toxic").alias("bad"), F.count(F.lit(1)).alias("n")).first()
    bad, good = float(n["bad"] or 0), float((n["n"] or 0) - (n["bad"] or 0))
    counted = sample.select("text", "toxic").mapInArrow(run, "word long, bad long, good long").groupBy("word").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    weight = F.log((F.col("bad") + 0.5) / (bad + 1)) - F.log((F.col("good") + 0.5) / (good + 1))
    both, share = F.col("bad") + F.col("good"), max(bad, 1) / max(bad + good, 1)
    ratio = 2 * (F.col("bad") * F.log(F.col("bad") / (both * share)) + F.when(F.col("good") > 0, F.col("good") * F.log(F.col("good") / (both * (1 - share)))).otherwise(0.0))
    top = counted.where(F.col("bad") >= least).withColumn("weight", weight).where("weight >= 1.5").where(ratio >= evidence).orderBy(F.desc("weight"), "word").limit(size).collect()
    hashes = np.array([r["word"] for r in top], np.int64).view(U)
    order = np.argsort(hashes)
    return Lexicon(hashes[order], np.array([r["weight"] for r in top], float)[order])


def train(docs: DataFrame, labels: DataFrame, *, max_rows: int = MAX_ROWS, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> Model:
    """Learn from labelled rows that are not held out, ``max_rows`` of them at most (in expectation)."""
    usable = labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("toxic")).where("id IS NOT NULL AND toxic IS NOT NULL AND NOT " + HELD_OUT.format("id"))
    usable = usable.groupBy("id").agg(F.max("toxic").alias("toxic"))
    n = usable.count()
    every = max(1, -(-n // max_rows))
    chosen = usable.where(F.pmod(F.xxhash64("id"), F.lit(every)) == 0)
    sample = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(chosen), "id")  # bounded by max_rows
    half = F.pmod(F.xxhash64("id", F.lit("half")), F.lit(8))
    lexicon = learn_lexicon(sample.where(half < 4))
    found = sample.where(half >= 4).select("text", "toxic", half.cast("long").alias("fold"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = text_features(lexicon, batch.column(0))
            yield pa.RecordBatch.from_arrays([batch.column(1), batch.column(2), pa.array(list(x), pa.list_(pa.float64()))], names=["toxic", "fold", "x"])
            release()

    rows = found.mapInArrow(run, "toxic int, fold long, x array<double>").collect()
    nothing = Trees(np.zeros((0, 1), np.int64), np.zeros((0, 1)), np.zeros((0, 2)), 0.0, (np.array([0.0, 1.0]), np.array([0.0, 1.0])))
    y = np.array([r["toxic"] for r in rows], float)
    prior = float(y.mean()) if len(y) else 0.0
    if not 0 < prior < 1:
        return Model(lexicon, nothing, prior)
    x, fold = np.array([r["x"] for r in rows]), np.array([r["fold"] for r in rows])
    order = np.lexsort((*x.T, y, fold))  # rows come in any order; the model must not depend on it
    x, y, fold = x[order], y[order], fold[order]
    fit = fold < 7
    if not 0 < y[fit].mean() < 1:
        return Model(lexicon, nothing, prior)
    trees = boost(x[fit], y[fit])
    if 0 < y[~fit].sum() < (~fit).sum():
        trees.curve = isotonic(1 / (1 + np.exp(-trees.raw(x[~fit]))), y[~fit])
    return Model(lexicon, trees, prior)


#: Rows that labels are never learned from.
HELD_OUT = "coalesce(crc32(cast({} AS string)) % 5 = 0, true)"


def score_texts(model: Model, texts: pa.Array) -> np.ndarray:
    parts = [model.score(data, offsets) for _, _, data, offsets in in_groups(texts)]
    return np.concatenate(parts) if parts else np.zeros(0)


def score_documents(docs: DataFrame, model: Model, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = score_texts(model, batch.column(1))
            yield pa.RecordBatch.from_arrays([ids_out(ids_of(batch.column(0))), batch.column(2), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])
            release()

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.expr(HELD_OUT.format(f"`{id_col}`")).alias("held_out"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def reject_toxic(docs: DataFrame, model: Model, *, text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """Documents below the threshold, with all their columns."""
    new = StructType([StructField("_toxicity_score", DoubleType())])
    return with_columns(docs, text_col, lambda texts: [pa.array(score_texts(model, texts))], new).where(F.col("_toxicity_score") < threshold).select(*docs.columns)


def op9_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return score_documents(docs, train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))

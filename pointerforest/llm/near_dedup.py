"""Near-duplicate documents: MinHash bands, odd sketches, exact confirmation, components.

A document's set holds its distinct five-word shingles (lower-cased A-Z). Documents
with a Jaccard similarity of at least ``percent`` / 100 are linked; the class of a
document is its connected component.

1. One pass gives each document its set's hash, the keys of 40 bands of 4 MinHash
   values, and an odd sketch: 256 MinHash samples folded into a bitmap of parities. The
   population count of the XOR of two sketches estimates high similarities closely.
2. Documents with equal sets are one vertex from here on, represented by one of its rows.
3. Every vertex of a band key is paired with that of the smallest document of the key (a star, not
   all pairs). Pairs that the sketches place five standard deviations below the bound
   drop out; the rest is confirmed on the full sets. Components follow.
4. Vertices of a key that are still in different components are compared by their
   sketches, in blocks of bounded size (keys of very many vertices block against block).
   Each vertex gets a list of what it may be linked with in each foreign
   component, and meets the sets of that component once, whatever the number of keys and
   pairs. Pairs inside a component need no confirmation, so a group of thousands of
   copies costs a star.

A pair at the bound is missed with a probability of 3e-7 by the bands
((1 - 0.75**4)**40) and as little by the sketches; every other pair is compared whatever
the size of its keys. On a key of very many vertices the comparisons of sketches grow with
the vertices times those outside the key's largest component.

Defined results: null and empty texts have an empty set, n_shingles 0, and are a
class of their own; with fewer than five words the whole sequence is the one shingle;
rows that repeat an id are one document: each of their texts counts for its links, and each
row gives a row; a null id is never linked (component null, kept true); an empty table
gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.accelerated import connected_components
from ..operators.edges import pairs
from ._spark import documents, forget, keep, stored
from ._text import WORD_POWERS, WORD_POWERS_2, U, flat_bytes, hash_words, ids_of, ids_out, lower_ascii, mix, prefix_hash, release, span_hash

SAMPLES, BANDS, ROWS, BITS = 256, 40, 4, 1024
#: Vertices of one key that one task compares by their sketches at a time, and texts of one component that one task confirms with.
BLOCK = 4096

_seed = mix(np.arange(1, 2 * SAMPLES + 1, dtype=U) * U(0x9E3779B97F4A7C15))
_A = (_seed[:SAMPLES] >> U(32)).astype(np.uint32) | np.uint32(1)
_B = (_seed[SAMPLES:] >> U(32)).astype(np.uint32)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, width: int = 5) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of every text."""
    words, sizes = hash_words(lower_ascii(data), offsets)
    prefix = prefix_hash(words, WORD_POWERS)
    out, at = [], 0
    for n in sizes.tolist():
        m = min(n, width)
        start = np.arange(at, at + n - m + 1) if n else np.zeros(0, np.int64)
        h = mix(span_hash(prefix, start, start + m, WORD_POWERS) + U(m))
        h.sort()
        out.append(h[np.append(True, h[1:] != h[:-1])] if n else h)
        at += n
    return out


def min_hashes(shingles: np.ndarray) -> np.ndarray:
    """SAMPLES minima over permutations of 32-bit shingle hashes."""
    low = (shingles >> U(16)).astype(np.uint32)
    least = np.full(SAMPLES, 0xFFFFFFFF, np.uint32)
    for a in range(0, len(low), 2048):
        np.minimum(least, (low[a : a + 2048, None] * _A + _B).min(axis=0), out=least)
    return least


_PLACE = np.arange(SAMPLES, dtype=U)
_BAND = np.arange(1, BANDS + 1, dtype=U) * U(0xD1B54A32D192ED03)


def band_keys(least: np.ndarray) -> np.ndarray:
    v = least[: BANDS * ROWS].reshape(BANDS, ROWS).astype(U)
    key = _BAND.copy()
    for r in range(ROWS):
        key = mix(key ^ v[:, r]) * U(3)
    return key.view(np.int64)


def odd_sketch(least: np.ndarray) -> np.ndarray:
    """Parity bitmap of the samples, as 64-bit words."""
    bit = (mix(least.astype(U) << U(16) ^ _PLACE) % U(BITS)).astype(np.int64)
    parity = np.bincount(bit, minlength=BITS) & 1
    return np.packbits(parity.astype(np.uint8), bitorder="little").view(np.int64)


def similarity(differing: np.ndarray | float):
    """Estimated Jaccard similarity from the population count of the XOR of two sketches."""
    share = np.clip(1 - 2 * np.asarray(differing) / BITS, 1e-3, 1)
    return 1 + BITS / 2 * np.log(share) / (2 * SAMPLES)


def most_differing(percent: int, deviations: float = 5.0) -> int:
    """Bits in which sketches of a pair at the bound differ at most, but for ``deviations``."""
    j = percent / 100
    spread = np.sqrt(j * (1 - j) / SAMPLES + (np.expm1(4 * (1 - j) * 2 * SAMPLES / BITS)) / (16 * SAMPLES**2 / BITS))
    least = max(0.0, j - deviations * spread)
    return int(np.ceil(BITS / 2 * (1 - np.exp(-2 * 2 * SAMPLES * (1 - least) / BITS))))


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("row"))


def signatures(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, row (hash of the text), n_shingles, h1, h2 (of the set), bands array<long>, sketch array<long>."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                sets = shingle_sets(*flat_bytes(part.column(1)))
                size = np.array([len(x) for x in sets], np.int64)
                bands, sketches = np.zeros((len(sets), BANDS), np.int64), np.zeros((len(sets), BITS // 64), np.int64)
                both = np.zeros((2, len(sets)), U)
                for i, x in enumerate(sets):
                    if len(x):
                        least = min_hashes(x)
                        bands[i], sketches[i] = band_keys(least), odd_sketch(least)
                        for k, p in enumerate((WORD_POWERS, WORD_POWERS_2)):
                            both[k, i] = mix(prefix_hash(x, p)[-1:])[0]
                ragged = lambda m: pa.ListArray.from_arrays(pa.array(np.arange(0, m.size + 1, m.shape[1]), pa.int32()), pa.array(m.ravel()))
                cols = [ids_out(ids_of(part.column(0))), part.column(2), pa.array(size), pa.array(both[0].view(np.int64)), pa.array(both[1].view(np.int64)), ragged(bands), ragged(sketches)]
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "row", "n_shingles", "h1", "h2", "bands", "sketch"])
            release()

    return _rows(docs, id_col, text_col).select("doc_id", "text", "row").mapInArrow(run, "doc_id long, row long, n_shingles long, h1 long, h2 long, bands array<long>, sketch array<long>")


def confirmed(tried: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """Those pairs (a, b) whose full sets are similar enough."""
    b = texts.select(F.col("doc_id").alias("b"), F.col("text").alias("tb"))
    a = texts.select(F.col("doc_id").alias("a"), F.col("text").alias("ta"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                ids = [part.column(k).to_numpy() for k in (0, 1)]
                sets: dict[int, np.ndarray] = {}
                for k in (0, 1):
                    who, first = np.unique(ids[k], return_index=True)
                    some = [i for i, w in zip(first, who.tolist(), strict=True) if w not in sets]
                    got = shingle_sets(*flat_bytes(part.column(2 + k).take(pa.array(some, pa.int64()))))
                    sets |= dict(zip(ids[k][some].tolist(), got, strict=True))
                good = []
                for x, y in zip(ids[0].tolist(), ids[1].tolist(), strict=True):
                    x, y = sets[x], sets[y]
                    common = len(np.intersect1d(x, y, assume_unique=True))
                    good.append(100 * common >= percent * (len(x) + len(y) - common))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1)], names=["a", "b"]).filter(pa.array(good, pa.bool_()))
            release()

    return tried.select("a", "b").join(b, "b").join(a, "a").select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long")


def _bits_apart(x: str, y: str):
    return F.aggregate(F.zip_with(x, y, lambda p, q: F.bit_count(p.bitwiseXOR(q))), F.lit(0), lambda s, c: s + c)


def open_lists(rows: DataFrame, most: int, block: int = BLOCK) -> DataFrame:
    """(comp, part, a, bs): documents of component ``comp`` that ``a`` of another one may be linked with.

    ``rows``: key, doc_id, comp, parts (of that component), sketch. Keys of any size are
    compared whole: with more than ``block`` documents block against block, each two in a
    task of their own.
    """
    sizes = rows.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi")
    every = rows.join(sizes.select("key", "n"), "key")
    blocks = F.ceil(F.col("n") / block)
    own = every.withColumn("mine", F.pmod(F.xxhash64("doc_id"), blocks)).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), blocks - 1)))
    own = own.withColumn("i", F.least("mine", "other")).withColumn("j", F.greatest("mine", "other"))

    def run(table):
        table = table.combine_chunks()
        doc, comp, mine, parts, own_part = (table[c].to_numpy() for c in ("doc_id", "comp", "mine", "parts", "part"))
        sketch = table["sketch"].combine_chunks().flatten().to_numpy().view(U).reshape(len(doc), -1)
        cross = table["i"][0].as_py() != table["j"][0].as_py()
        _, which, count = np.unique(comp, return_inverse=True, return_counts=True)
        weight = count[which] * np.int64(len(count)) + which  # the smaller component asks
        order = np.argsort(weight, kind="stable")
        out: list[tuple[int, int, int, list[int]]] = []
        asking = order[weight[order] < weight.max()]  # the largest component is only asked
        for x in range(0, len(asking), 256):
            u = asking[x : x + 256]
            apart = np.zeros((len(u), len(order)), np.int64)
            for k in range(sketch.shape[1]):
                apart += np.bitwise_count(sketch[u, k][:, None] ^ sketch[order, k][None, :])
            ok = (apart <= most) & (weight[u][:, None] < weight[order][None, :])
            if cross:
                ok &= mine[u][:, None] != mine[order][None, :]
            p, q = np.nonzero(ok)
            a, b = doc[u[p]], order[q]
            rank = np.lexsort((own_part[b], comp[b], a))
            a, b = a[rank], b[rank]
            if len(a):
                new = np.flatnonzero(np.append(True, (a[1:] != a[:-1]) | (comp[b[1:]] != comp[b[:-1]]) | (own_part[b[1:]] != own_part[b[:-1]])))
                for s, e in zip(new, np.append(new[1:], len(a)), strict=True):
                    out.append((int(comp[b[s]]), int(own_part[b[s]]), int(a[s]), doc[b[s:e]].tolist()))
        cols = list(zip(*out, strict=True)) if out else [(), (), (), ()]
        return pa.table([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.list_(pa.int64()))], names=["comp", "part", "a", "bs"])

    own = own.withColumn("part", F.pmod(F.xxhash64("doc_id"), F.col("parts")))
    return own.groupBy("key", "i", "j").applyInArrow(run, "comp long, part long, a long, bs array<long>")


def confirm_lists(lists: DataFrame, members: DataFrame, texts: DataFrame, percent: int, block: int) -> DataFrame:
    """Confirmed (a, b) of lists (comp, part, a, bs); each part of a component ships its texts once to each block of askers.

    ``members``: comp, part, b. Small components share a task.
    """
    asked = lists.groupBy("comp", "part", "a").agg(F.array_distinct(F.flatten(F.collect_list("bs"))).alias("bs"))
    asked, seen = keep(asked, n=F.count(F.lit(1)))
    sizes = asked.groupBy("comp", "part").agg(F.ceil(F.count(F.lit(1)) / (block // 2)).alias("salts"))
    tasks = max(64, seen["n"] // 500)

    def unit(df: DataFrame) -> DataFrame:
        whole = F.pmod(F.xxhash64("comp", "part"), F.lit(tasks))
        return df.withColumn("unit", F.when(F.col("salts") == 1, whole).otherwise(F.xxhash64("comp", "part", "salt")))

    left = unit(asked.join(sizes, ["comp", "part"]).withColumn("salt", F.pmod(F.xxhash64("a"), F.col("salts"))))
    left = left.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("ta")), "a").select("unit", "a", "bs", "ta")
    right = unit(members.join(sizes, ["comp", "part"]).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.col("salts") - 1))))
    right = right.join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("tb")), "b").select("unit", "b", "tb")

    def run(asks, has):
        pairs_a, pairs_b = [], []
        if asks.num_rows and has.num_rows:
            asks, has = asks.combine_chunks(), has.combine_chunks()
            sets = shingle_sets(*flat_bytes(has["tb"]))
            place = {b: i for i, b in enumerate(has["b"].to_pylist())}
            length = np.array([len(x) for x in sets])
            universe, code = np.unique(np.concatenate(sets), return_inverse=True)
            codes = np.split(code, np.cumsum(length)[:-1])
            mark = np.zeros(len(universe), np.int64)
            for at in range(0, asks.num_rows, 256):
                part = asks.slice(at, 256)
                for a, bs, own in zip(part["a"].to_pylist(), part["bs"].to_pylist(), shingle_sets(*flat_bytes(part["ta"])), strict=True):
                    found = np.minimum(np.searchsorted(universe, own), len(universe) - 1)
                    found = found[universe[found] == own]
                    mark[found] = 1
                    to = [place[b] for b in bs if b in place]
                    if to:
                        start = np.append(0, np.cumsum(length[to]))[:-1]
                        common = np.add.reduceat(mark[np.concatenate([codes[i] for i in to])], start)
                        good = 100 * common >= percent * (len(own) + length[to] - common)
                        pairs_b += [b for b, ok in zip([b for b in bs if b in place], good, strict=True) if ok]
                        pairs_a += [a] * int(good.sum())
                    mark[found] = 0
        return pa.table({"a": pa.array(pairs_a, pa.int64()), "b": pa.array(pairs_b, pa.int64())})

    return left.groupBy("unit").cogroup(right.groupBy("unit")).applyInArrow(run, "a long, b long")


def near_classes(docs: DataFrame, *, percent: int = 75, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK, tie_ids: bool = True) -> tuple[DataFrame, DataFrame]:
    """Signatures of all rows, and one row per distinct set: h1, h2, component_id (smallest id of its component),
    rep and row (the one row that stands for the set), lead (whether it stands for the component too).

    ``tie_ids``: rows of one id are linked whatever their texts.
    """
    most = most_differing(percent)
    sig = stored(signatures(docs, id_col=id_col, text_col=text_col))
    some = sig.where("n_shingles > 0 AND doc_id IS NOT NULL")
    # A table of its own, so that the join to a class of very many copies can be split; its vertex numbers stay as written.
    classes = some.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", "row")).alias("r"))
    classes = stored(classes.select("h1", "h2", F.col("r.doc_id").alias("rep"), F.col("r.row").alias("row"), F.monotonically_increasing_id().alias("v")))
    named = classes.withColumnRenamed("rep", "doc_id")
    reps = some.join(named, ["h1", "h2", "doc_id", "row"]).dropDuplicates(["v"])
    keyed = reps.select(F.col("v").alias("doc_id"), F.col("doc_id").alias("rep"), F.explode("bands").alias("key"))
    # The vertex of the least document of a key: what copies were made from comes before them, and is closest to all.
    pivots = keyed.groupBy("key").agg(F.min(F.struct("rep", "doc_id")).alias("a"), F.max(F.struct("rep", "doc_id")).alias("z")).where("a <> z").select("key", F.col("a.doc_id").alias("a"))
    # Keys that several vertices have; all later steps stay with these.
    shared, seen = keep(keyed.select("key", "doc_id").join(pivots, "key"), n=F.count(F.lit(1)))
    links = tied(some, classes) if tie_ids else docs.sparkSession.createDataFrame([], "a long, b long")
    if seen["n"]:
        wanted = shared.select("doc_id").distinct()
        picked = classes.select(F.col("rep").alias("_d"), F.col("row").alias("_row"), F.col("v").alias("_v")).join(wanted, F.col("_v") == F.col("doc_id"), "left_semi")
        source = _rows(docs, id_col, text_col)
        found = source.join(picked, (source["doc_id"] == F.col("_d")) & (source["row"] == F.col("_row")))
        texts = stored(found.select(F.col("_v").alias("doc_id"), "text").dropDuplicates(["doc_id"]))
        sketches = stored(reps.select(F.col("v").alias("doc_id"), "sketch").join(wanted, "doc_id", "left_semi"))
        stars = shared.where("doc_id <> a").select("a", F.col("doc_id").alias("b")).distinct()
        left, right = sketches.select(F.col("doc_id").alias("a"), F.col("sketch").alias("sa")), sketches.select(F.col("doc_id").alias("b"), F.col("sketch").alias("sb"))
        tried = stars.join(right, "b").join(left, "a").where(_bits_apart("sa", "sb") <= most).select("a", "b")
        links = stored(links.unionByName(confirmed(tried, texts, percent)))
        labels = connected_components(pairs(links, "a", "b")).labels

        comp = wanted.join(labels.withColumnRenamed("id", "doc_id"), "doc_id", "left").select("doc_id", F.coalesce("component", "doc_id").alias("comp"))
        parts = comp.groupBy("comp").agg(F.ceil(F.count(F.lit(1)) / block).alias("parts"))
        comp = stored(comp.join(parts, "comp"))
        rows = shared.select("key", "doc_id").join(comp, "doc_id").join(sketches, "doc_id")
        lists, seen = keep(open_lists(rows, most, block), n=F.count(F.lit(1)))
        if seen["n"]:
            inside = comp.select("comp", F.pmod(F.xxhash64("doc_id"), F.col("parts")).alias("part"), F.col("doc_id").alias("b"))
            links = stored(links.unionByName(confirm_lists(lists, inside, texts, percent, block)))
        for done in (texts, sketches, comp, lists):
            forget(done)
    forget(shared)
    labels = connected_components(pairs(links, "a", "b")).labels
    of = classes.join(labels.select(F.col("id").alias("v"), F.col("component").alias("c")), "v", "left").withColumn("c", F.coalesce("c", "v"))
    of, _ = keep(of)
    least = of.groupBy("c").agg(F.min(F.struct("rep", "row", "v")).alias("m")).select("c", F.col("m.rep").alias("component_id"), F.col("m.v").alias("first"))
    return sig, stored(of.join(least, "c").select("h1", "h2", "component_id", "rep", "row", (F.col("v") == F.col("first")).alias("lead")))


def tied(some: DataFrame, classes: DataFrame) -> DataFrame:
    """(a, b): the sets of every id that has several, each to its least."""
    own = some.select("doc_id", "h1", "h2").join(classes.select("h1", "h2", "v"), ["h1", "h2"]).select("doc_id", "v")
    several = own.groupBy("doc_id").agg(F.min("v").alias("a"), F.max("v").alias("z")).where("a <> z").select("doc_id", "a")
    several, seen = keep(several, n=F.count(F.lit(1)))
    if not seen["n"]:
        return several.select("a", F.col("doc_id").alias("b"))
    return own.join(several, "doc_id").where("v <> a").select("a", F.col("v").alias("b")).distinct()


def near_duplicates(docs: DataFrame, *, percent: int = 75, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest id of its class), kept."""
    sig, classes = near_classes(docs, percent=percent, id_col=id_col, text_col=text_col, block=block)
    of = classes.select("h1", "h2", "component_id")
    linked = sig.where("n_shingles > 0 AND doc_id IS NOT NULL").join(of, ["h1", "h2"]).select("doc_id", "n_shingles", "component_id")
    # A row without words belongs to what other rows of its id say, else to itself.
    empty = sig.where("n_shingles = 0 OR doc_id IS NULL").select("doc_id", "n_shingles")
    ids = empty.where("doc_id IS NOT NULL").select("doc_id").distinct()
    others = linked.join(ids, "doc_id", "left_semi").select("doc_id", "component_id").distinct()
    alone = empty.join(others, "doc_id", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
    out = linked.unionByName(alone)
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def drop_near_duplicates(docs: DataFrame, *, percent: int = 75, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK) -> DataFrame:
    """``docs`` with one row of each group of near-duplicate texts, of the smallest id.

    Texts decide, not ids: rows that repeat an id with different texts are judged apart, and
    of equal rows one stays. Rows without an id or without words are linked with nothing and stay.
    """
    sig, classes = near_classes(docs, percent=percent, id_col=id_col, text_col=text_col, block=block, tie_ids=False)
    lead = classes.where("lead").select(F.col("rep").alias("_d"), F.col("row").alias("_r"))
    bare = sig.where("n_shingles = 0 AND doc_id IS NOT NULL").select(F.col("doc_id").alias("_d"), F.col("row").alias("_r")).distinct()
    twice = sig.where("n_shingles > 0").groupBy(F.col("doc_id").alias("_d"), F.col("row").alias("_r")).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("_d", "_r")
    # The text's hash travels beside it, so that only rows that occur more than once are compared in full.
    rows = docs.withColumn("_row", F.xxhash64(F.col(text_col).cast("string")))
    same = (F.col(id_col).cast("long") == F.col("_d")) & (F.col("_row") == F.col("_r"))
    known = rows.join(lead.unionByName(bare), same, "left_semi")
    repeated = known.join(twice, same, "left_semi")
    first = F.row_number().over(Window.partitionBy(id_col, "_row").orderBy(text_col))
    once = repeated.withColumn("_first", first).where("_first = 1").drop("_first")
    return known.join(twice, same, "left_anti").unionByName(once).drop("_row").unionByName(docs.where(F.col(id_col).isNull()))


def op6_minhash_near_dedup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(documents(spark, sf_dir))


#: Exact on every pair that shares a shingle; components by keyed recursion.
OP6_SQL = r"""
WITH RECURSIVE d AS MATERIALIZED (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w
  FROM documents),
s AS MATERIALIZED (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS g FROM d),
n AS MATERIALIZED (SELECT doc_id, count(*) AS k FROM s GROUP BY doc_id),
e AS MATERIALIZED (
  SELECT a.doc_id AS x, b.doc_id AS y FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id
    JOIN n p ON p.doc_id = a.doc_id JOIN n q ON q.doc_id = b.doc_id
  GROUP BY a.doc_id, b.doc_id, p.k, q.k HAVING 100 * count(*) >= 75 * (p.k + q.k - count(*))),
cc(id, comp) USING KEY (id) AS (
  SELECT doc_id, doc_id FROM d
  UNION
  SELECT e.x, min(t.comp) FROM cc t JOIN e ON e.y = t.id JOIN recurring.cc o ON o.id = e.x
  WHERE t.comp < o.comp GROUP BY e.x, o.comp)
SELECT d.doc_id, coalesce(n.k, 0) AS n_shingles, cc.comp AS component_id, d.doc_id = cc.comp AS kept
FROM d JOIN cc ON cc.id = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id
"""

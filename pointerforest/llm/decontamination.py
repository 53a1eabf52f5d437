"""Benchmark decontamination with SimHash over item-sized windows, in Spark expressions only.

A benchmark item of m words is looked for in every window of m words of every document
(a shorter document is one window). Texts are lower-cased; shingles are five words.

1. *Where to look.* A window like enough to an item holds most of its shingles, so
   document shingles meet the item shingles in one join, and only window starts with enough
   hits to reach the wanted similarity at all go on (an upper bound, nothing is lost).
   Fingerprints of every window of every item size would cost a hundred times as much.
2. *SimHash.* Those windows and the items get 64-bit fingerprints: each bit is the sign of
   the sum of that bit's votes over all shingles.
3. *Multi-index search.* Fingerprints are cut into ``radius + 1`` blocks; two of them within
   ``radius`` bits of each other agree in one block at least. Windows meet all items of their
   size by (block, value), then by their distance. Two texts at the bound differ in 11 of
   64 bits on average, so the default radius of 26 misses one with a probability below 1e-5.
   At a similarity of 0.75 blocks are two or three bits wide and the index selects little by
   itself (a longer print has as many more blocks of that width); the distance then drops
   what is no match, before any shingle is compared.
4. *Verification.* The similarity is exact: shingles weigh as often as they occur,
   sum of minima over sum of maxima.

Memory of a task is bounded by one text: its windows are cut in blocks of ``SPAN`` starts, and
each block carries only its own words.

Defined results: null and empty texts match nothing; items with fewer than five words (or
null) are no evidence and match nothing; rows that repeat a document id are judged apart,
and the best match of the id is given, of equally good ones the first; repeated items each
match; empty tables give no rows; extra columns are ignored; a null document id is kept as null.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._spark import documents, keep, stored

WIDTH = 5
RADIUS = 26
#: Windows to look at (some 20 bytes each) whose rows are broadcast at most.
BROADCAST_WINDOWS = 1_000_000
#: Window starts of a text that are cut out of it together.
SPAN = 1024


def words_of(text: Column) -> Column:
    bare = F.btrim(F.lower(F.coalesce(text.cast("string"), F.lit(""))), F.lit(" \t\n\x0b\x0c\r"))
    return F.when(bare == "", F.array().cast("array<string>")).otherwise(F.split(bare, r"[\x20\x09-\x0D]+"))


def shingle_hashes(w: Column) -> Column:
    """64-bit hashes of all five-word shingles, in order."""
    n = F.size(w)
    each = F.transform(F.sequence(F.lit(0), n - WIDTH), lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(WIDTH)]))
    return F.when(n >= WIDTH, each).otherwise(F.array().cast("array<bigint>"))


def simhash(hashes: Column, most: int = (1 << 16) - 1) -> Column:
    """Bits in which most of the hashes (counted as often as they occur) have a one.

    Votes are counted for several bits at once, in lanes of a 64-bit sum that are wide enough
    for ``most`` hashes: four lanes of 16 bits, or two of 32.
    """
    width = 16 if most < 1 << 16 else 32
    ones = (1 << width) - 1
    lanes = sum(1 << i for i in range(0, 64, width))
    votes = lambda k: F.aggregate(hashes, F.lit(0).cast("long"), lambda s, h: s + F.call_function("shiftrightunsigned", h, k).bitwiseAND(F.lit(lanes).cast("long")))
    sums = F.transform(F.array(*[F.lit(k) for k in range(width)]), votes)
    # The lanes are named once, so that each sum is taken once.
    sign = lambda v, k, i: F.when(F.shiftrightunsigned(F.get(v, F.lit(k)), i).bitwiseAND(F.lit(ones).cast("long")) * 2 > F.size(hashes), F.lit(_signed(1 << k + i)).cast("long")).otherwise(F.lit(0).cast("long"))
    signs = lambda v: F.array(*[sign(v, k, i) for k in range(width) for i in range(0, 64, width)])
    return F.get(F.transform(F.array(sums), lambda v: F.aggregate(signs(v), F.lit(0).cast("long"), lambda s, x: s.bitwiseOR(x))), F.lit(0))


def _signed(x: int) -> int:
    return x if x < 1 << 63 else x - (1 << 64)


def blocks_of(fingerprint: Column, radius: int) -> Column:
    """(block, value) structs of ``radius + 1`` blocks of nearly equal width."""
    edges = [64 * i // (radius + 1) for i in range(radius + 2)]
    return F.array(*[F.struct(F.lit(i).alias("block"), F.shiftrightunsigned(fingerprint, a).bitwiseAND(F.lit((1 << b - a) - 1).cast("long")).alias("value")) for i, (a, b) in enumerate(zip(edges, edges[1:], strict=False))])


def weighted_similarity(a: Column, b: Column) -> Column:
    """Sum of the smaller over sum of the larger counts of all shingles."""
    count = lambda xs, s: F.size(F.filter(xs, lambda x: x == s))
    common = F.aggregate(F.array_intersect(a, b), F.lit(0), lambda t, s: t + F.least(count(a, s), count(b, s)))
    return common / F.greatest(F.size(a) + F.size(b) - common, F.lit(1))


def contaminated(docs: DataFrame, benchmark: DataFrame, *, percent: int = 75, radius: int = RADIUS, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """doc_id, item_id, similarity, start (word of the best window) of all pairs at ``percent`` or more."""
    items = benchmark.select(F.col(item_col).cast("long").alias("item_id"), words_of(F.col(item_text_col)).alias("iw"))
    items = items.where(F.size("iw") >= WIDTH).select("item_id", F.size("iw").alias("m"), shingle_hashes(F.col("iw")).alias("ih"))
    items = items.withColumn("print", simhash(F.col("ih"), (1 << 32) - 1))
    items, sizes = keep(items, longest=F.max("m"))
    longest = sizes["longest"]
    source = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).where("text IS NOT NULL")
    rows = source.select("doc_id", F.xxhash64("text").alias("row"), words_of(F.col("text")).alias("w"))
    placed = rows.select("doc_id", "row", F.size("w").alias("n"), F.posexplode(shingle_hashes(F.col("w"))).alias("at", "h"))
    wanted = items.select("item_id", "m", F.explode(F.array_distinct("ih")).alias("h"))
    hits = placed.join(wanted, "h").groupBy("doc_id", "row", "n", "item_id", "m").agg(F.sort_array(F.collect_set("at")).alias("at"))
    windows = stored(hits.select("doc_id", "row", "m", F.explode(likely_starts(F.col("at"), F.col("m"), F.col("n"), percent)).alias("start")).distinct())
    spans = windows.groupBy(F.col("doc_id").alias("d"), F.col("row").alias("r"), F.floor(F.col("start") / SPAN).cast("int").alias("span")).agg(F.collect_list(F.struct("m", "start")).alias("ws"))
    asked, seen = keep(spans.groupBy("d", "r").agg(F.collect_list(F.struct("span", "ws")).alias("spans")), n=F.sum(F.aggregate("spans", F.lit(0).cast("long"), lambda s, x: s + F.size(x["ws"]))))
    # What is asked for is little next to the documents; up to a fixed number of windows it travels to the texts, beyond it both meet by hash.
    asked = F.broadcast(asked) if seen["n"] <= BROADCAST_WINDOWS else asked
    own = source.withColumn("row", F.xxhash64("text"))
    cut = own.join(asked, (F.col("row") == F.col("r")) & F.col("doc_id").eqNullSafe(F.col("d"))).dropDuplicates(["doc_id", "row"])
    cut = cut.select("doc_id", "spans", words_of(F.col("text")).alias("w"))
    # First the words of each span, then the windows inside it.
    cut = cut.select("doc_id", F.explode(F.transform("spans", lambda x: F.struct(x["span"].alias("span"), x["ws"].alias("ws"), F.slice("w", x["span"] * SPAN + 1, F.lit(SPAN + longest)).alias("w")))).alias("x"))
    cut = cut.select("doc_id", "x.ws", (F.col("x.span") * SPAN).alias("base"), shingle_hashes(F.col("x.w")).alias("h"))
    window = lambda a: F.struct(a["m"].alias("m"), a["start"].alias("start"), F.slice("h", a["start"] - F.col("base") + 1, a["m"] - WIDTH + 1).alias("wh"))
    cut = cut.select("doc_id", F.inline(F.transform("ws", window)))
    printed = stored(cut.withColumn("print", simhash(F.col("wh"), longest)).withColumn("id", F.monotonically_increasing_id()))
    index = items.select("item_id", "m", F.col("print").alias("ip"), F.inline(blocks_of(F.col("print"), radius)))
    probe = printed.select("id", "m", "print", F.inline(blocks_of(F.col("print"), radius)))
    near = probe.join(index, ["m", "block", "value"]).where(F.bit_count(F.col("print").bitwiseXOR(F.col("ip"))) <= radius).select("id", "item_id").distinct()
    pairs = printed.select("id", "doc_id", "start", "wh").join(near, "id").join(items.select("item_id", "ih"), "item_id")
    scored = pairs.select("doc_id", "item_id", "start", weighted_similarity(F.col("wh"), F.col("ih")).alias("similarity")).where(F.col("similarity") * 100 >= percent)
    best = scored.groupBy("doc_id", "item_id").agg(F.max(F.struct(F.col("similarity"), (-F.col("start")).alias("s"))).alias("b"))
    return best.select("doc_id", "item_id", F.round("b.similarity", 6).alias("similarity"), (-F.col("b.s")).cast("long").alias("start"))


def likely_starts(at: Column, m: Column, n: Column, percent: int) -> Column:
    """Starts of windows of ``m`` words of a text of ``n`` that hold enough of the places ``at`` (sorted, distinct) of
    shared shingles: the share of common shingles bounds the similarity.

    ``need`` places from the i-th on that lie in one window allow the starts between the last
    one's first window and the i-th place; the union over i is all there are.
    """
    size = m - WIDTH + 1
    most = F.greatest(F.lit(0), n - m)
    here = F.greatest(F.least(size, n - WIDTH + 1), F.lit(1))
    need = F.greatest(F.ceil((here + size) * percent / (100 + percent)).cast("int"), F.lit(1))
    low = lambda i: F.greatest(F.lit(0), F.get(at, i + need - 1) - size + 1)
    high = lambda i: F.least(F.get(at, i), most)
    first = F.when(F.size(at) >= need, F.sequence(F.lit(0), F.size(at) - need)).otherwise(F.array().cast("array<int>"))
    some = F.filter(first, lambda i: low(i) <= high(i))
    return F.array_distinct(F.flatten(F.transform(some, lambda i: F.sequence(low(i), high(i)))))


def decontaminate(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """Documents without a match."""
    bad = contaminated(docs, benchmark, **options).select("doc_id").distinct()
    key = options.get("id_col", "doc_id")
    return docs.join(bad.withColumnRenamed("doc_id", "_bad"), docs[key].eqNullSafe(F.col("_bad")), "left_anti")


def op2_benchmark_decontamination(spark, sf_dir: str) -> DataFrame:
    return contaminated(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


#: Every window at every start that shares a shingle with the item, without fingerprints.
OP2_SQL = r"""
WITH d AS MATERIALIZED (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents WHERE text IS NOT NULL),
i AS MATERIALIZED (SELECT item_id, w, len(w) AS m FROM (SELECT item_id, list_filter(regexp_split_to_array(lower(text), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM benchmark WHERE text IS NOT NULL) WHERE len(w) >= 5),
ds AS MATERIALIZED (SELECT doc_id, len(w) AS n, unnest(range(0, len(w) - 4)) AS pos, w FROM d WHERE len(w) >= 5),
dg AS MATERIALIZED (SELECT doc_id, n, pos, array_to_string(w[pos + 1:pos + 5], ' ') AS g FROM ds),
ig AS MATERIALIZED (SELECT item_id, m, g, count(*) AS c FROM (SELECT item_id, m, array_to_string(w[k + 1:k + 5], ' ') AS g FROM (SELECT item_id, m, w, unnest(range(0, m - 4)) AS k FROM i)) GROUP BY ALL),
hit AS MATERIALIZED (SELECT dg.doc_id, dg.n, dg.pos, ig.item_id, ig.m, ig.g, ig.c FROM dg JOIN ig ON dg.g = ig.g),
span AS (SELECT doc_id, item_id, n, m, greatest(0, min(pos) - m + 5) AS lo, greatest(0, least(max(pos), n - m)) AS hi FROM hit GROUP BY doc_id, item_id, n, m),
win AS MATERIALIZED (SELECT doc_id, item_id, n, m, unnest(range(lo, hi + 1)) AS start FROM span),
part AS (SELECT w.doc_id, w.item_id, w.start, w.n, w.m, h.g, least(count(*), h.c) AS c FROM win w JOIN hit h ON h.doc_id = w.doc_id AND h.item_id = w.item_id AND h.pos >= w.start AND h.pos < w.start + w.m - 4 GROUP BY w.doc_id, w.item_id, w.start, w.n, w.m, h.g, h.c),
sim AS (SELECT doc_id, item_id, start, sum(c)::DOUBLE / (least(m - 4, n - 4 - start) + m - 4 - sum(c)) AS s FROM part GROUP BY doc_id, item_id, start, n, m)
SELECT doc_id, item_id, round(max(s), 6) AS similarity, arg_max(start, s * 1e9 - start)::BIGINT AS start FROM sim WHERE s * 100 >= 75 GROUP BY doc_id, item_id
"""

"""Quality rules as a learned decision list, in Spark expressions only.

Text statistics are columns; thresholds come from quantiles of a labelled sample; the
sample shrinks to counts per cell of binned statistics; sequential covering grows a
conjunction of threshold conditions on one part of the sample, prunes it on the other, and
goes on with what it does not cover. The list that results is one CASE expression:
the first rule that holds decides, and a text that no rule rejects is kept.

The labelled sample is bounded by ``max_rows`` (default 12,000 rows, chosen by the hash of
the id); only thresholds and cell counts reach the driver.

Defined results: null and empty texts have no words and fail the base rule; without
labels of both kinds the list is empty; rows that repeat an id each give a row; an empty
table gives no rows; extra columns are ignored; a null id stays null.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._spark import documents, stored

MAX_ROWS = 12_000
_WHITE = " \t\n\x0b\x0c\r"
#: Statistics that rules may use.
FEATURES = ("n_words", "repeat_share", "dup_line_share", "symbol_share", "upper_share", "word_length")


def _next(a: Column, k: int = 1) -> Column:
    return F.slice(a, k + 1, F.greatest(F.size(a), F.lit(1)))


def text_statistics(docs: DataFrame, *, text_col: str = "text", carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_upper, n_lines for every row.

    Words that lie in a three-word window found twice or more are counted without
    leaving the row: windows are hashed to 64 bits; only if some hash occurs twice, (hash, place)
    pairs are sorted, repeated places put in order, and the union of their windows measured.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(*carry, text.alias("t"))
    bare = F.btrim("t", F.lit(_WHITE))
    lines = F.filter(F.split("t", "\n"), lambda x: F.btrim(x, F.lit(_WHITE)) != "")
    rows = rows.select("*", F.when(bare == "", F.array().cast("array<string>")).otherwise(F.split(bare, r"[\x20\x09-\x0D]+")).alias("w"), lines.alias("l"))
    w = F.col("w")
    two = F.zip_with(w, _next(w), lambda a, b: F.xxhash64(a, b))
    three = F.slice(F.zip_with(two, _next(w, 2), lambda h, c: F.xxhash64(h, c)), 1, F.greatest(F.size(w) - 2, F.lit(0)))
    only = lambda kind: F.char_length(F.regexp_replace("t", f"[^{kind}]++", "")).cast("long")
    rows = rows.select(
        *carry,
        F.size(w).cast("long").alias("n_words"),
        F.char_length(F.array_join(w, "")).cast("long").alias("word_chars"),
        only("#*$%&|<>").alias("n_symbols"),
        only(r"\p{Lu}").alias("n_upper"),
        F.size("l").cast("long").alias("n_lines"),
        (F.size("l") - F.size(F.array_distinct("l"))).cast("long").alias("n_dup_lines"),
        three.alias("h"),
    )
    twice = F.size(F.array_distinct("h")) < F.size("h")
    ranked = F.when(twice, F.sort_array(F.transform("h", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))
    rows = rows.select(*[c for c in rows.columns if c != "h"], ranked.alias("s"))
    s = F.col("s")
    same = F.zip_with(s, _next(s), lambda a, b: F.coalesce(a["h"] == b["h"], F.lit(False)))
    rows = rows.withColumn("e", same)
    marked = F.zip_with(F.zip_with(s, "e", lambda a, e: F.struct(a["i"].alias("i"), e.alias("e"))), F.concat(F.array(F.lit(False)), F.slice("e", 1, F.greatest(F.size("e") - 1, F.lit(0)))), lambda a, p: F.when(a["e"] | p, a["i"]))
    rows = rows.withColumn("p", F.sort_array(F.filter(marked, lambda i: i.isNotNull()))).drop("s", "e")
    p = F.col("p")
    steps = F.zip_with(p, _next(p), lambda a, b: F.least(F.lit(3), F.coalesce(b - a, F.lit(3))))
    return rows.withColumn("n_repeat_words", F.coalesce(F.aggregate(steps, F.lit(0), lambda x, y: x + y), F.lit(0)).cast("long")).drop("p")


def features(stats: DataFrame) -> DataFrame:
    words, chars = F.greatest("n_words", F.lit(1)), F.greatest("word_chars", F.lit(1))
    return stats.select(
        "*",
        (F.col("n_repeat_words") / words).alias("repeat_share"),
        (F.col("n_dup_lines") / F.greatest("n_lines", F.lit(1))).alias("dup_line_share"),
        (F.col("n_symbols") / chars).alias("symbol_share"),
        (F.col("n_upper") / chars).alias("upper_share"),
        (F.col("word_chars") / words).alias("word_length"),
    )


@dataclass(frozen=True)
class Condition:
    feature: str
    at_least: bool
    value: float

    def expression(self) -> Column:
        c = F.col(self.feature)
        return c >= F.lit(self.value) if self.at_least else c < F.lit(self.value)

    def __str__(self) -> str:
        return f"{self.feature} {'>=' if self.at_least else '<'} {self.value:g}"


Rule = tuple[Condition, ...]


def as_expression(rules: list[Rule]) -> Column:
    """Number of the first rule that holds, 0 if none does."""
    out = None
    for i, rule in enumerate(rules, 1):
        holds = rule[0].expression()
        for c in rule[1:]:
            holds &= c.expression()
        out = F.when(holds, i) if out is None else out.when(holds, i)
    return out.otherwise(0) if out is not None else F.lit(0)


class _Cells:
    """Counts of good and bad rows per cell, for growing and for pruning."""

    def __init__(self, rows: list[tuple[tuple[int, ...], list[int]]]):
        self.rows = rows

    def counts(self, test, part: int) -> tuple[int, int]:
        """(bad, good) of the growing (0) or pruning (1) part."""
        bad = good = 0
        for bins, n in self.rows:
            if test(bins):
                bad, good = bad + n[2 * part], good + n[2 * part + 1]
        return bad, good


def cover(cells: list[tuple[tuple[int, ...], list[int]]], cuts: list[int], *, least: int = 5, precision: float = 0.9, longest: int = 4) -> list[list[tuple[int, bool, int]]]:
    """Sequential covering. A condition (feature, at_least, k) compares a bin with k.

    A rule grows by the information gained on bad rows, is pruned from its end by
    (bad - good) / (bad + good) on the other part, and joins the list if it covers ``least``
    bad rows with the wanted precision on both parts together.
    """
    from math import log2

    rules: list[list[tuple[int, bool, int]]] = []
    holds = lambda rule: lambda bins: all((bins[f] >= k) == up for f, up, k in rule)
    left = _Cells(cells)
    while len(rules) < 16:
        rule: list[tuple[int, bool, int]] = []
        inside = left
        bad, good = inside.counts(lambda _: True, 0)
        while good and bad and len(rule) < longest:
            best, gain = None, 1e-9
            for f, most in enumerate(cuts):
                # All thresholds of a feature from one pass over its bins.
                per = [[0, 0] for _ in range(most + 1)]
                for bins, n in inside.rows:
                    per[bins[f]][0] += n[0]
                    per[bins[f]][1] += n[1]
                b = g = 0
                for k in range(1, most + 1):
                    b, g = b + per[k - 1][0], g + per[k - 1][1]
                    for up, p, q in ((False, b, g), (True, bad - b, good - g)):
                        if p and (value := p * (log2(p / (p + q)) - log2(bad / (bad + good)))) > gain:
                            best, gain = (f, up, k), value
            if best is None:
                break
            rule.append(best)
            inside = _Cells([r for r in inside.rows if holds([best])(r[0])])
            bad, good = inside.counts(lambda _: True, 0)
        if not rule:
            break
        value = lambda r: (lambda b, g: (b - g) / (b + g) if b + g else -1.0)(*left.counts(holds(r), 1))
        scores = [value(rule[:k]) for k in range(1, len(rule) + 1)]
        rule = rule[: scores.index(max(scores)) + 1]
        grown, checked = left.counts(holds(rule), 0), left.counts(holds(rule), 1)
        b, g = grown[0] + checked[0], grown[1] + checked[1]
        if b < least or b < precision * (b + g):
            break
        rules.append(rule)
        test = holds(rule)
        left = _Cells([r for r in left.rows if not test(r[0])])
    return rules


def learn_rules(docs: DataFrame, labels: DataFrame, *, max_rows: int = MAX_ROWS, bins: int = 16, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> list[Rule]:
    """An ordered list of rules that reject, from a bounded labelled sample."""
    usable = labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("good")).where("id IS NOT NULL AND good IS NOT NULL").groupBy("id").agg(F.max("good").alias("good"))
    every = max(1, -(-usable.count() // max_rows))
    chosen = usable.where(F.pmod(F.xxhash64("id"), F.lit(every)) == 0)
    sample = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(F.broadcast(chosen), "id")  # bounded by max_rows
    table = stored(features(text_statistics(sample, carry=("id", "good"))).select("id", "good", *FEATURES))
    marks = [i / bins for i in range(1, bins)]
    quantiles = table.agg(*[F.percentile_approx(f, marks, 10_000).alias(f) for f in FEATURES], *[F.max(f).alias(f"max_{f}") for f in FEATURES]).first()
    # Between quantiles of the tail, so that a rare kind of text has thresholds too.
    cuts = [sorted({float(v) for v in (quantiles[f] or [])} | {float(quantiles[f"max_{f}"] or 0) * s for s in (0.02, 0.05, 0.1, 0.2, 0.3, 0.5, 0.7)} - {0.0}) for f in FEATURES]
    binned = [sum((F.when(F.col(f) >= v, 1).otherwise(0) for v in c), F.lit(0)).alias(f) for f, c in zip(FEATURES, cuts, strict=True)]
    prune = F.pmod(F.xxhash64("id", F.lit("prune")), F.lit(3)) == 0
    count = lambda part, good: F.count_if((prune if part else ~prune) & (F.col("good") == good)).alias(f"n{part}{good}")
    cells = table.select("id", "good", *binned).groupBy(*FEATURES).agg(count(0, 0), count(0, 1), count(1, 0), count(1, 1)).collect()  # at most max_rows
    cells = sorted((tuple(r[f] for f in FEATURES), [r["n00"], r["n01"], r["n10"], r["n11"]]) for r in cells)
    found = cover(cells, [len(c) for c in cuts])
    return [tuple(Condition(FEATURES[f], up, cuts[f][k - 1]) for f, up, k in rule) for rule in found]


def judge(docs: DataFrame, rules: list[Rule], *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Statistics, base_failed, rule (number of the first that rejects, 0 if none) and kept."""
    rows = features(text_statistics(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    rows = rows.withColumn("base_failed", failed).withColumn("rule", as_expression(rules).cast("int"))
    return rows.withColumn("kept", ~F.col("base_failed") & (F.col("rule") == 0))


def op3_quality_rules(spark, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    rules = learn_rules(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return judge(docs, rules).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rule")

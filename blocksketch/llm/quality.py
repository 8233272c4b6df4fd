"""Quality rules with adaptive thresholds from mergeable quantile sketches per language and source.

Every measure of a document goes into a sketch of logarithmic buckets (relative error 1 %): a count per bucket. Sketches
of parts of the data merge by adding counts, so one partly aggregated group-by builds the sketch of every (language,
source), and adding sources gives the language's and the whole corpus's sketch. A group's upper threshold for a measure
is q50 + spread * max(q50 - q25, floor), its lower one q50 - spread * max(q75 - q50, floor): each is set by the middle
and the half of the group away from it, so up to half of a group's documents may be bad on that side without moving it
beyond them. Neither lies further out than that of the group's language, so a group that is bad as a whole cannot widen
its own; a language is not held to the corpus, as languages differ in word length. A group of fewer than min_docs
documents takes its language's thresholds, and a small language takes the corpus's. A document is kept if it passes the
two fixed base rules and no measure lies outside its group's thresholds. Thresholds are joined to the measures; the
join's small side is one row per group.

Where more than three quarters of a group measure the same (mostly 0), the floor decides; spread times the floor lies
below the base rule for repeats, so that this measure acts too.

Defined results: a null text has no words (and fails the base rule of ten words). Null language or source is a group of
its own. Repeated rows count and are judged each. Empty tables give empty tables. Columns not named are not read.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from .common import WORDS, boxed, columns, same, small_batches, trim_memory

COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper"]
#: measure -> (expression, least distance of a quartile from the middle)
MEASURES = {
    "symbols": ("n_symbols / word_chars", 0.01),
    "dup_lines": ("n_dup_lines / n_lines", 0.04),
    "repeats": ("n_repeat_words / n_words", 0.02),
    "word_length": ("word_chars / n_words", 0.25),
    "upper": ("n_upper / word_chars", 0.008),
}
SPREAD, MIN_DOCS, ERROR, LARGE, BROADCAST_GROUPS = 6.0, 30, 0.01, 100_000, 20_000
LOG_GAMMA = math.log((1 + ERROR) / (1 - ERROR))
_UPPER = {c: None for c in range(65, 91)}


def _rank_pairs(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Equal numbers for equal pairs, and only for them."""
    return np.unique(a * np.int64(int(b.max()) + 1) + b, return_inverse=True)[1].astype(np.int64)


def repeated_words(words: list[str], n: int = 5) -> int:
    """Words covered by a window of n words whose word sequence the text has twice or more."""
    m = len(words) - n + 1
    if m < 2:
        return 0
    if m <= LARGE:
        grams = list(zip(*(words[i : i + m] for i in range(n))))
        if len(set(grams)) == m:
            return 0
        count = Counter(grams)
        twice = np.fromiter((count[g] > 1 for g in grams), dtype=bool, count=m)
    else:  # the same in flat arrays: ranks of pairs, of pairs of pairs, and so on
        ids: dict[str, int] = {}
        x = np.fromiter((ids.setdefault(w, len(ids)) for w in words), dtype=np.int64, count=len(words))
        r = x[:m]
        for i in range(1, n):
            r = _rank_pairs(r, x[i : i + m])
        twice = np.bincount(r)[r] > 1
    edge = np.zeros(len(words) + 1, dtype=np.int64)
    at = np.flatnonzero(twice)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + n, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def count_text(text: str | None) -> tuple[int, ...]:
    """The values of COUNTS."""
    if not text:
        return (0,) * len(COUNTS)
    words = WORDS.findall(text)
    seen: set[str] = set()
    dups = lines = 0
    for line in text.split("\n"):
        if WORDS.search(line):
            lines += 1
            if line in seen:
                dups += 1
            else:
                seen.add(line)
    upper = len(text) - len(text.translate(_UPPER))
    return len(words), sum(map(len, words)), sum(map(text.count, "#*$%&|<>")), dups, repeated_words(words), lines, upper


_STRUCT = T.StructType([T.StructField(c, T.LongType()) for c in COUNTS])


@F.arrow_udf(_STRUCT)
def text_counts(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
    for batch in texts:
        rows = [count_text(x.as_py()) for x in batch]
        yield pa.StructArray.from_arrays([pa.array(list(c), pa.int64()) for c in (zip(*rows) if rows else [()] * len(COUNTS))], COUNTS)
    trim_memory()


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def measured(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with the struct _q of COUNTS."""
    small_batches(docs.sparkSession)
    return docs.withColumn("_q", text_counts(F.col(text_col)))


def sketches(counts: DataFrame) -> DataFrame:
    """(lang, source, measure, bucket, n): the sketch of every group; counts has lang, source and COUNTS."""
    each = F.array(*[F.struct(F.lit(k).alias("measure"), F.expr(f"try_divide({e.split(' / ')[0]}, {e.split(' / ')[1]})").alias("x")) for k, (e, _) in MEASURES.items()])
    long = counts.select("lang", "source", F.explode(each).alias("m")).select("lang", "source", "m.measure", "m.x").filter("x is not null")
    bucket = F.when(F.col("x") <= 0, F.lit(-(2**31))).otherwise(F.ceil(F.log("x") / LOG_GAMMA)).cast("int")
    return long.groupBy("lang", "source", "measure", bucket.alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


def merged(sketch: DataFrame, *by: str) -> DataFrame:
    return sketch.groupBy(*by, "measure", "bucket").agg(F.sum("n").alias("n"))


def quartiles(sketch: DataFrame, *by: str) -> DataFrame:
    """(by, measure, n_docs, q25, q50, q75); a quantile is the middle of its bucket."""
    w = W.partitionBy(*by, "measure")
    run = sketch.withColumn("c", F.sum("n").over(w.orderBy("bucket").rowsBetween(W.unboundedPreceding, 0))).withColumn("n_docs", F.sum("n").over(w))
    middle = F.when(F.col("bucket") == -(2**31), 0.0).otherwise(F.exp(F.col("bucket") * LOG_GAMMA) * (1 - ERROR))
    at = lambda q: F.min(F.when(F.col("c") >= q * F.col("n_docs"), F.col("bucket")))
    value = lambda c: F.when(F.col(c) == -(2**31), 0.0).otherwise(F.exp(F.col(c) * LOG_GAMMA) * (1 - ERROR))
    return run.groupBy(*by, "measure").agg(F.max("n_docs").alias("n_docs"), at(0.25).alias("b25"), at(0.5).alias("b50"), at(0.75).alias("b75")).select(*by, "measure", "n_docs", value("b25").alias("q25"), value("b50").alias("q50"), value("b75").alias("q75"))


def thresholds(counts: DataFrame, spread: float = SPREAD, min_docs: int = MIN_DOCS) -> DataFrame:
    """(lang, source, fences map<string, struct<low, high>>): a row for each group that has a word."""
    from .common import cut

    sk = cut(sketches(counts))  # a few hundred counts for each group, whatever the number of documents
    own, lang, whole = quartiles(sk, "lang", "source"), quartiles(merged(sk, "lang"), "lang"), quartiles(merged(sk))
    l2 = lang.select(*[F.col(c).alias(f"l_{c}") for c in lang.columns])
    w2 = whole.select(*[F.col(c).alias(f"w_{c}") for c in whole.columns])
    j = own.join(l2, same(F.col("lang"), F.col("l_lang")) & (F.col("measure") == F.col("l_measure")), "left").join(w2, F.col("measure") == F.col("w_measure"), "left")
    floor = F.element_at(F.create_map(*[F.lit(x) for k, (_, f) in MEASURES.items() for x in (k, f)]), F.col("measure"))
    high = lambda p: F.col(f"{p}q50") + spread * F.greatest(F.col(f"{p}q50") - F.col(f"{p}q25"), floor)
    low = lambda p: F.col(f"{p}q50") - spread * F.greatest(F.col(f"{p}q75") - F.col(f"{p}q50"), floor)
    outer = lambda f: F.when(F.col("l_n_docs") >= min_docs, f("l_")).otherwise(f("w_"))
    large = F.col("n_docs") >= min_docs
    fence = F.struct(F.when(large, F.greatest(low(""), outer(low))).otherwise(outer(low)).alias("low"), F.when(large, F.least(high(""), outer(high))).otherwise(outer(high)).alias("high"))
    return cut(j.select("lang", "source", "measure", fence.alias("fence")).groupBy("lang", "source").agg(F.map_from_entries(F.collect_list(F.struct("measure", "fence"))).alias("fences")))


def verdicts(counts: DataFrame, fences: DataFrame) -> DataFrame:
    """counts with base_failed and kept."""
    f = fences.select(F.col("lang").alias("_f_lang"), F.col("source").alias("_f_source"), "fences")
    if f.limit(BROADCAST_GROUPS + 1).count() <= BROADCAST_GROUPS:  # a map of ten numbers each; more groups are joined by a shuffle
        f = F.broadcast(f)
    j = counts.join(f, same(F.col("lang"), F.col("_f_lang")) & same(F.col("source"), F.col("_f_source")), "left")
    over = F.lit(False)
    for k, (e, _) in MEASURES.items():
        a, b = e.split(" / ")
        x = F.expr(f"try_divide({a}, {b})")
        over = over | F.coalesce((x > F.col("fences")[k]["high"]) | (x < F.col("fences")[k]["low"]), F.lit(False))
    failed = base_failed()
    return j.select(*[F.col(f"`{c}`") for c in counts.columns], failed.alias("base_failed"), (~failed & ~over).alias("kept"))


def judge(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source", **how) -> DataFrame:
    """(doc_id, lang, source, COUNTS, base_failed, kept): a row for each row of docs."""
    counts = columns(docs, doc_id=id_col, text=text_col, lang=lang_col, source=source_col)
    counts = measured(counts).select("doc_id", "lang", "source", "_q.*").persist()  # eleven numbers a document, no text
    return verdicts(counts, thresholds(counts, **how))


def keep_good(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", source_col: str = "source", **how) -> DataFrame:
    """The rows of docs that are kept, with its columns. Texts are measured once for the sketches and once for the filter, so that no text is shuffled."""
    counts = measured(columns(docs, text=text_col, lang=lang_col, source=source_col)).select("lang", "source", "_q.*")
    fences = thresholds(counts, **how)
    rows = boxed(docs, _t=F.col(f"`{text_col}`"), lang=F.col(f"`{lang_col}`"), source=F.col(f"`{source_col}`"))
    rows = measured(rows, "_t").select("_row", "lang", "source", "_q.*")
    return verdicts(rows, fences).filter("kept").select("_row.*")


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return judge(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "lang", "source")

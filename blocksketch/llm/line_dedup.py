"""Line deduplication that returns keep bitmaps instead of text. DataFrame functions only.

Each line's key (stripped, ASCII lower case) becomes a 128-bit hash. Occurrences are range-partitioned by
(hash, document) and sorted by document and position within a partition, so even a line that stands in every document
is dealt over many tasks. One pass over the sorted stream gives, per hash and document, the first occurrence; per hash,
a partly aggregated count of documents and the first occurrence overall. The occurrences of the hashes that lose lines
go back to their documents as bits.

Every document (every distinct pair of id and text) has one bitmap: bit i is 1 if line i stays. It is compressed by
words of 64 lines: runs (word, times) in order, all-ones words joined into one run, so that a document that keeps all
its lines has two runs at most, and one that loses some a run or two for each word that lost any.

Defined results: a null or empty text is one empty line. Rows with equal doc_id (null counts as a value) are one
document for counting; each of the rows gets the bitmap of its own text. Empty tables give empty tables. Columns other
than the two named are not read; the user's columns may have any names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import LOWER, UPPER, WHITE, boxed, columns, cut, same


def line_key(line: Column) -> Column:
    """Stripped, A-Z in lower case. Lines of ASCII alone take lower(), which is the same there and much faster."""
    t = F.btrim(line, F.lit(WHITE))
    return F.when(F.octet_length(t) == F.length(t), F.lower(t)).otherwise(F.translate(t, UPPER, LOWER))


def _identified(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return columns(docs, doc_id=id_col, text=text_col).select("doc_id", text.alias("text"), F.xxhash64(text).alias("text_hash"))


def _bits(n: Column) -> Column:
    """The lowest n bits, n from 0 to 63."""
    return F.bitwise_not(F.call_function("shiftleft", F.lit(-1).cast("long"), n.cast("int")))


def _run(word: Column, times: Column) -> Column:
    return F.struct(word.cast("long").alias("word"), times.cast("long").alias("times"))


def compressed(n_lines: Column, lost: Column) -> Column:
    """The runs of a bitmap of n_lines ones but for the words of lost: a sorted array of (w, mask), mask the lines that go."""
    top = F.floor((n_lines - 1) / 64)
    full = lambda w: F.when((w < top) | (n_lines % 64 == 0), F.lit(-1).cast("long")).otherwise(_bits(n_lines % 64))
    before = lambda j: F.when(j == 0, F.lit(-1).cast("long")).otherwise(F.get(lost, j - 1)["w"])
    parts = F.transform(lost, lambda e, j: F.array(_run(F.lit(-1), e["w"] - before(j) - 1), _run(full(e["w"]).bitwiseAND(F.bitwise_not(e["mask"])), F.lit(1))))
    last = F.coalesce(F.get(lost, F.size(lost) - 1)["w"], F.lit(-1).cast("long"))
    tail = F.array(_run(F.lit(-1), top - last - 1), _run(full(top), F.when(last < top, 1).otherwise(0)))
    return F.filter(F.concat(F.flatten(parts), tail), lambda r: r["times"] > 0)


def expanded(runs: Column) -> Column:
    """The words of a bitmap."""
    return F.flatten(F.transform(runs, lambda r: F.array_repeat(r["word"], r["times"].cast("int"))))


def keep_bitmaps(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_docs: int = 10, min_chars: int = 1, keep: str = "none") -> DataFrame:
    """(doc_id, text_hash, n_lines, n_dropped, keep array<struct<word, times>>): a row for every distinct (doc_id, text).

    A key of min_chars code points or more that stands in min_docs documents or more loses all its lines (keep="none"),
    or all but its first line in the order of (doc_id, text_hash, position) (keep="first").
    """
    ids = _identified(docs, id_col, text_col)
    lines = ids.select("doc_id", "text_hash", F.posexplode(F.split("text", "\n", -1)).alias("pos", "line")).withColumn("line", line_key(F.col("line"))).filter(F.length("line") >= min_chars)
    # written once, as range bounds and two readers would each split the texts again; hashes and positions only
    occ = cut(lines.select(F.xxhash64("line").alias("k1"), F.xxhash64(F.lit("second"), "line").alias("k2"), "doc_id", "text_hash", "pos"))
    ranged = occ.repartitionByRange("k1", "k2", "doc_id").sortWithinPartitions("k1", "k2", "doc_id", "text_hash", "pos")
    per_doc = ranged.groupBy("k1", "k2", "doc_id").agg(F.min(F.struct("text_hash", "pos")).alias("first"))
    # element-wise structs keep the order (doc_id, text_hash, pos) with nulls first
    # written, so that both sides of the join below are plain shuffles and a hot line's partition can be split
    per_key = cut(per_doc.groupBy("k1", "k2").agg(F.count(F.lit(1)).alias("n_docs"), F.min(F.struct("doc_id", "first")).alias("overall")).filter(F.col("n_docs") >= min_docs).select("k1", "k2", "overall"))
    gone = occ.join(per_key, ["k1", "k2"])
    if keep == "first":
        gone = gone.filter(~(same(F.col("doc_id"), F.col("overall.doc_id")) & (F.col("text_hash") == F.col("overall.first.text_hash")) & (F.col("pos") == F.col("overall.first.pos"))))
    bit = F.expr("shiftleft(1L, cast(pos % 64 as int))")
    words = gone.groupBy("doc_id", "text_hash", F.expr("cast(pos div 64 as long)").alias("w")).agg(F.bit_or(bit).alias("mask"))
    lost = words.groupBy("doc_id", "text_hash").agg(F.array_sort(F.collect_list(F.struct("w", "mask"))).alias("lost"), F.sum(F.bit_count("mask")).alias("n_dropped"))
    lost = lost.select(F.col("doc_id").alias("l_doc"), F.col("text_hash").alias("l_hash"), "lost", "n_dropped")
    n_lines = F.octet_length("text") - F.octet_length(F.translate("text", "\n", "")) + 1
    every = ids.groupBy("doc_id", "text_hash").agg(F.max(n_lines).cast("long").alias("n_lines"))
    j = every.join(lost, same(F.col("doc_id"), F.col("l_doc")) & (F.col("text_hash") == F.col("l_hash")), "left")
    none = F.array().cast("array<struct<w: bigint, mask: bigint>>")
    return j.select("doc_id", "text_hash", "n_lines", F.coalesce("n_dropped", F.lit(0)).cast("long").alias("n_dropped"), compressed(F.col("n_lines"), F.coalesce("lost", none)).alias("keep"))


def apply_bitmaps(docs: DataFrame, bitmaps: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(_row struct of docs' own columns with the kept text in text_col, n_lines, n_dropped)."""
    text = F.coalesce(F.col(f"`{text_col}`"), F.lit(""))
    d = boxed(docs, text=text, text_hash=F.xxhash64(text), own_id=F.col(f"`{id_col}`"))
    b = bitmaps.select(F.col("doc_id").alias("b_doc"), F.col("text_hash").alias("b_hash"), "n_lines", "n_dropped", "keep")
    j = d.join(b, same(F.col("own_id"), F.col("b_doc")) & (F.col("text_hash") == F.col("b_hash")))
    bit = lambda words, i: F.get(words, F.floor(i / 64).cast("int")).bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), i % 64))
    left = F.transform(F.array(expanded(F.col("keep"))), lambda words: F.array_join(F.filter(F.split("text", "\n", -1), lambda _, i: bit(words, i) != 0), "\n"))[0]
    kept = F.when(F.col("n_dropped") == 0, F.col("text")).otherwise(left)
    row = F.struct(*[(kept if c == text_col else F.col("_row").getField(c)).alias(c) for c in docs.columns])
    return j.select(row.alias("_row"), "n_lines", "n_dropped")


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """docs with the lines dropped; the columns of docs."""
    return apply_bitmaps(docs, keep_bitmaps(docs, id_col, text_col, **how), id_col, text_col).select("_row.*")


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = apply_bitmaps(docs, keep_bitmaps(docs))
    return out.select("_row.doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("_row.text", F.lit("")), 256).alias("kept_sha256"))


SQL = """
WITH l AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
                  generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents),
k AS (SELECT doc_id, pos, line, translate(trim(line, chr(9) || chr(10) || chr(11) || chr(12) || chr(13) || ' '),
             'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
g AS (SELECT key FROM k WHERE length(key) >= 1 GROUP BY key HAVING count(DISTINCT doc_id) >= 10)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (key IN (SELECT key FROM g)) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (key NOT IN (SELECT key FROM g)), '')) AS kept_sha256
FROM k GROUP BY doc_id
"""

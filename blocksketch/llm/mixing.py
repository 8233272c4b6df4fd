"""Mixing sources to target weights by pivotal dependent rounding. DataFrame functions only.

Targets: sources in code-point order (null last) weigh 5, 2, 1, repeating, and share 150 % of all words; no target lies
above twice its source's size, and the excess is shared again by weight until none does (water filling, solved exactly
from prefix sums over the sources). A document's expected copies are its source's target / size, from 0 to 2: the whole
part is taken at once and the fraction is a probability.

Rounding: two documents of a source trade words: one's fraction rises and the other's falls by the same number of
words until one of them is whole; the direction is drawn so that each expectation stays as it was. The words of the
pair stay as they were, so a source's words come within one document's size of its target. Documents of a source are dealt to blocks of
about BLOCK; each block leaves one document that is not yet whole, those are dealt to blocks again, and so on up a
tree until one is left for each source, which is drawn by itself.

Draws come from hashes of the documents paired, so reruns agree, whatever the partitions. Equal rows of
(doc_id, size, source) are numbered, which makes them different documents.

Defined results: a null or empty text has size 0 and takes 0 words. Null doc_id and null source are values like others. A
source without words has target 0. An empty table gives an empty table. Other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import WHITE, boxed, columns, cut, running, same

WEIGHTS, SHARE, CAP, BLOCK = (5, 2, 1), 1.5, 2.0, 256
_WS = r"[\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    t = F.btrim(F.coalesce(text, F.lit("")), F.lit(WHITE))
    return F.when(t == "", F.lit(0)).otherwise(F.size(F.split(t, _WS))).cast("long")


def let(value: Column, body) -> Column:
    """body(value), with value computed once."""
    return F.transform(F.array(value), body)[0]


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """(source, source_size, target) from rows of (source, size): one row a source.

    Places and prefix sums over the sources come from range partitions and their totals, so that sources may be many
    (hosts, say): no window holds them all.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    placed = running(per, [F.asc_nulls_last("source")], {"place": F.lit(1).cast("long")})
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("place") % len(weights)).cast("int") + 1)
    w = placed.select("source", "source_size", weight.alias("weight"), (cap * F.col("source_size")).alias("most"))
    w = running(w, [(F.col("most") / F.col("weight")).asc(), F.asc_nulls_last("source")], {"full": F.col("most"), "lighter": F.col("weight")})
    whole = w.agg(F.sum("source_size").alias("all_words"), F.sum("weight").alias("all_weights"))  # one row
    w = w.crossJoin(F.broadcast(whole))
    # the level that fills the rest if all earlier sources are full; the first source that it doesn't fill sets it
    level = (share * F.col("all_words") - F.col("full")) / (F.col("all_weights") - F.col("lighter"))
    w = w.withColumn("level", F.when(level < F.col("most") / F.col("weight"), level))
    w = w.crossJoin(F.broadcast(w.agg(F.max("level").alias("reached"))))
    return w.select("source", "source_size", F.when(F.col("source_size") == 0, 0.0).otherwise(F.least("most", F.coalesce(F.col("reached") * F.col("weight"), F.col("most")))).alias("target"))


def _trade(a: Column, b: Column) -> tuple[Column, Column]:
    """Trade words between two documents (struct: key, size, x); the one that is whole, then the other."""
    unit = F.pmod(F.xxhash64(F.lit("trade"), a["key"], b["key"]), F.lit(1 << 52)) / float(1 << 52)
    up_a, down_a, up_b, down_b = (1 - a["x"]) * a["size"], a["x"] * a["size"], (1 - b["x"]) * b["size"], b["x"] * b["size"]

    def unit_of(key: Column, size: Column, x: Column) -> Column:
        return F.struct(key.alias("key"), size.alias("size"), x.alias("x"))

    def done(z: Column, x: float) -> Column:
        return unit_of(z["key"], z["size"], F.lit(x))

    def left(z: Column, words: Column) -> Column:
        return unit_of(z["key"], z["size"], F.least(F.greatest(words / z["size"], F.lit(0.0)), F.lit(1.0)))

    rise, fall = F.least(up_a, down_b), F.least(down_a, up_b)  # the most words that a can gain, and lose
    pair = lambda w, r: F.struct(w.alias("whole"), r.alias("rest"))
    gains = F.when(up_a <= down_b, pair(done(a, 1.0), left(b, down_b - up_a))).otherwise(pair(done(b, 0.0), left(a, down_a + down_b)))
    loses = F.when(down_a <= up_b, pair(done(a, 0.0), left(b, down_b + down_a))).otherwise(pair(done(b, 1.0), left(a, down_a - up_b)))
    return F.when(unit * (rise + fall) < fall, gains).otherwise(loses)


def _round_block(units: Column) -> Column:
    """struct(whole: array of units with x 0 or 1, rest: one unit) of an array of units."""
    first = units[0]
    start = F.struct(F.slice(units, 1, 0).alias("whole"), first.alias("rest"))
    step = lambda acc, u: let(_trade(acc["rest"], u), lambda t: F.struct(F.array_append(acc["whole"], t["whole"]).alias("whole"), t["rest"].alias("rest")))
    return F.aggregate(F.slice(units, 2, F.greatest(F.size(units), F.lit(1))), start, step)


def copies(sizes: DataFrame, **how) -> DataFrame:
    """(doc_id, size, source, n, source_size, target, copies): sizes has doc_id, size, source; n numbers equal rows from 0."""
    spark = sizes.sparkSession
    same_rows = cut(sizes.groupBy("doc_id", "size", "source").agg(F.count(F.lit(1)).alias("m")))  # four values a document; texts are read once
    rows = same_rows.select("doc_id", "size", "source", F.explode(F.sequence(F.lit(0).cast("long"), F.col("m") - 1)).alias("n"))
    aim = cut(targets(same_rows.select("source", (F.col("size") * F.col("m")).alias("size")), **how))  # a row a source
    a = aim.select(F.col("source").alias("a_source"), "source_size", "target")
    rows = rows.join(a, same(F.col("source"), F.col("a_source"))).drop("a_source")
    each = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    rows = rows.withColumn("each", each).withColumn("floor", F.floor("each"))
    open_ = rows.filter((F.col("size") > 0) & (F.col("each") > F.col("floor")))
    unit = F.struct(F.struct("doc_id", "n").alias("key"), F.col("size").cast("double").alias("size"), (F.col("each") - F.col("floor")).alias("x"))
    level = open_.select("source", unit.alias("u"))
    wholes, depth = None, 0
    while True:
        count = level.groupBy("source").agg(F.count(F.lit(1)).alias("c")).select(F.col("source").alias("c_source"), F.ceil(F.col("c") / BLOCK).alias("blocks"))
        top = count.agg(F.max("blocks")).first()[0] or 0
        b = level.join(count, same(F.col("source"), F.col("c_source"))).select("source", F.pmod(F.xxhash64(F.lit(depth), "u.key"), F.col("blocks")).alias("blk"), "u")
        # the largest first: a large document left open is filled by the small ones behind it
        rounded = b.groupBy("source", "blk").agg(F.array_sort(F.collect_list(F.struct((-F.col("u.size")).alias("o"), F.xxhash64("u.key").alias("h"), "u"))).alias("us"))
        rounded = cut(rounded.select("source", _round_block(F.transform("us", lambda z: z["u"])).alias("r")))  # a row for BLOCK documents
        whole = rounded.select("source", F.explode("r.whole").alias("u"))
        level = rounded.select("source", F.col("r.rest").alias("u"))
        wholes = whole if wholes is None else wholes.unionByName(whole)
        depth += 1
        if top <= 1:
            break
    draw = F.pmod(F.xxhash64(F.lit("last"), "u.key"), F.lit(1 << 52)) / float(1 << 52)
    last = level.select("source", F.struct("u.key", "u.size", F.when(draw < F.col("u.x"), 1.0).otherwise(0.0).alias("x")).alias("u"))
    extra = wholes.unionByName(last).select(F.col("source").alias("e_source"), F.col("u.key.doc_id").alias("e_doc"), F.col("u.key.n").alias("e_n"), F.col("u.size").cast("long").alias("e_size"), F.col("u.x").cast("long").alias("x")).filter("x > 0")
    j = rows.join(extra, same(F.col("doc_id"), F.col("e_doc")) & (F.col("n") == F.col("e_n")) & (F.col("size") == F.col("e_size")) & same(F.col("source"), F.col("e_source")), "left")
    return j.select("doc_id", "size", "source", "n", "source_size", "target", (F.col("floor") + F.coalesce("x", F.lit(0))).cast("long").alias("copies"))


def sizes_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    return columns(docs, doc_id=id_col, text=text_col, source=source_col).select("doc_id", word_count(F.col("text")).alias("size"), "source")


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **how) -> DataFrame:
    """The rows of docs, each as often as the mix takes it; the columns of docs.

    Documents and their copies meet by a 128-bit hash of (doc_id, size, source), so one shuffle of the texts serves the
    join and the numbering of rows that look alike.
    """

    def keys(*cols: Column) -> dict[str, Column]:
        parts = [x for c in cols for x in (c, c.isNull())]
        return {"k1": F.xxhash64(*parts), "k2": F.xxhash64(F.lit("second"), *parts)}

    c = copies(sizes_of(docs, id_col, text_col, source_col), **how).groupBy("doc_id", "size", "source").agg(F.sum("copies").alias("every"), F.count(F.lit(1)).alias("rows")).filter("every > 0")
    c = c.select(*[x.alias(n) for n, x in keys(F.col("doc_id"), F.col("size"), F.col("source")).items()], "every", "rows")
    text = F.col(f"`{text_col}`")
    d = boxed(docs, **keys(F.col(f"`{id_col}`"), word_count(text), F.col(f"`{source_col}`")), h=F.xxhash64(text))
    j = d.join(c, ["k1", "k2"]).withColumn("n", F.row_number().over(W.partitionBy("k1", "k2").orderBy("h")))
    times = (F.floor(F.col("every") / F.col("rows")) + (F.col("n") <= F.col("every") % F.col("rows")).cast("long")).cast("int")
    return j.select("_row", F.explode(F.array_repeat(F.lit(1), times))).select("_row.*")


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    c = copies(sizes_of(table(spark, sf_dir, "documents")))
    return c.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"), "source", "copies")

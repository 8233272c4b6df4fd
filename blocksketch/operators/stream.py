"""Edge-update streams: UPDATE rows (seq, u, v, delta, w) with u < v and delta +1 or -1."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def encode_id(key: Column, kind: int, kinds: int) -> Column:
    """A vertex number for each (kind, key): bijective, and plain arithmetic."""
    return key.cast("long") * kinds + kind


def text_id(text: Column) -> Column:
    """60 bits of a text's MD5, for vertices named by texts; the odds of a collision are V**2 / 2**61."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def canonical_edges(df: DataFrame, u: str, v: str, w: str | None = None) -> DataFrame:
    """(u, v, w): the lesser end first; self-loops cross no cut and go; rows with a null end are an error."""
    a, b = F.col(u).cast("long"), F.col(v).cast("long")
    checked = F.when(a.isNull() | b.isNull(), F.raise_error(F.lit("an edge has a null end")).cast("long"))
    weight = F.col(w).cast("double") if w else F.lit(1.0)
    return df.filter((a != b) | a.isNull() | b.isNull()).select(F.coalesce(checked, F.least(a, b)).alias("u"), F.greatest(a, b).alias("v"), weight.alias("w"))


def distinct_edges(df: DataFrame, u: str, v: str, w: str | None = None, weight: str = "min") -> DataFrame:
    e = canonical_edges(df, u, v, w)
    return e.groupBy("u", "v").agg(getattr(F, weight)("w").alias("w"))


def inserts(edges: DataFrame) -> DataFrame:
    """A stream that inserts each of the distinct edges once."""
    seq = F.lit(0).cast("long")
    return edges.select(seq.alias("seq"), "u", "v", F.lit(1).alias("delta"), (F.col("w") if "w" in edges.columns else F.lit(1.0)).alias("w"))


def toggle_stream(df: DataFrame, u: str, v: str, *order: str, seq: str | None = None) -> DataFrame:
    """Repeated pairs become a valid stream: odd occurrences in the given order insert, even ones delete."""
    a, b = F.col(u).cast("long"), F.col(v).cast("long")
    e = df.filter(a != b).select(F.least(a, b).alias("u"), F.greatest(a, b).alias("v"), *[F.col(c).alias(f"_o{i}") for i, c in enumerate(order)], *([F.col(seq).cast("long").alias("seq")] if seq else []))
    n = F.row_number().over(W.partitionBy("u", "v").orderBy(*[f"_o{i}" for i in range(len(order))]))
    # without a sequence number of its own a pair's occurrences are numbered; only their order within the pair matters
    return e.withColumn("_n", n).select((F.col("seq") if seq else F.col("_n").cast("long")).alias("seq"), "u", "v", F.when(F.col("_n") % 2 == 1, 1).otherwise(-1).alias("delta"), F.lit(1.0).alias("w"))


def validate_stream(updates: DataFrame) -> DataFrame:
    """Updates after which an edge's multiplicity is neither 0 nor 1."""
    run = F.sum("delta").over(W.partitionBy("u", "v").orderBy("seq").rowsBetween(W.unboundedPreceding, 0))
    return updates.withColumn("multiplicity", run).filter(~F.col("multiplicity").isin(0, 1))


def edges_at(updates: DataFrame, seq: int | None = None) -> DataFrame:
    """(u, v, w): the edges present after all updates, or after those up to seq."""
    if seq is not None:
        updates = updates.filter(F.col("seq") <= seq)
    return updates.groupBy("u", "v").agg(F.sum("delta").alias("m"), F.max("w").alias("w")).filter("m = 1").select("u", "v", "w")


def edge_records(updates: DataFrame) -> DataFrame:
    """Each update twice, once for either end: (x the end, sign opposite at the two ends)."""
    ends = F.explode(F.array(F.struct(F.col("u").alias("x"), F.lit(1).alias("sign")), F.struct(F.col("v").alias("x"), F.lit(-1).alias("sign"))))
    return updates.select("*", ends.alias("_e")).select(*updates.columns, F.col("_e.x").alias("x"), F.col("_e.sign").alias("sign"))

"""Exact duplicates by skew-safe combining.

Copies meet in three steps, and every step groups by the digest *and* the whole
normalised text, so a digest collision can never merge different texts:

1. each task combines its own copies (the map side of the first aggregation);
2. survivors of a salted digest group are merged, so that the copies of one very
   frequent text are spread over ``salts`` reducers;
3. the salt winners of a digest, at most ``salts`` for each text, are combined.

Only texts are shuffled in steps 2 and 3, never lists of rows. Rows learn their
winner through a join on the digest, which adaptive execution may split at hot
digests. The text itself takes part in that join only where two different texts
share a digest, which a SHA-256 rules out (``strong``).

Defined results: null text counts as empty; an empty table gives an empty
result; a null id is larger than any other and wins only a group of null ids;
rows that repeat an id and a text are one row and stay or go together, unless a
``key`` tells them apart; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import text_or_empty


def normalised(name: str = "text") -> Column:
    """Each run of blanks as one space; runs that are one space already cost nothing."""
    return F.regexp_replace(text_or_empty(name), r"[\x09-\x0D][ \x09-\x0D]*| [ \x09-\x0D]+", " ")


def sha256_of(text: Column) -> Column:
    return F.sha2(text.cast("binary"), 256)


def winners(docs: DataFrame, row_id: str, text: str, digest: Callable[[Column], Column], strong: bool, salts: int, key: str | None = None) -> DataFrame:
    """One row for each different text: w_digest, keep_id, group_size, w_text, and with ``key`` keep_key.

    w_text is null where no other text has the same digest.
    """
    rows = docs.select(F.col(row_id).alias("rid"), *([F.col(key).alias("k")] if key else []), normalised(text).alias("t"))
    rows = rows.select(*rows.columns, digest(F.col("t")).alias("w_digest"), (F.spark_partition_id() % salts).alias("salt"))
    # the key of a row with the least id; where all ids are null, the least key
    least = [F.coalesce(F.min_by("k", "rid"), F.min("k")).alias("k")] if key else []
    salted = rows.groupBy("w_digest", "t", "salt").agg(F.min("rid").alias("rid"), F.count(F.lit(1)).alias("n"), *least)
    last = [F.coalesce(F.min_by("k", "rid"), F.min("k")).alias("keep_key")] if key else []
    combined = salted.groupBy("w_digest", "t").agg(F.min("rid").alias("keep_id"), F.sum("n").alias("group_size"), *last)
    if strong:
        w_text = F.lit(None).cast("string")
    else:
        w_text = F.when(F.count(F.lit(1)).over(Window.partitionBy("w_digest")) > 1, F.col("t"))
    return combined.select("w_digest", "keep_id", "group_size", w_text.alias("w_text"), *(["keep_key"] if key else []))


def exact_dedup(
    docs: DataFrame, row_id: str = "doc_id", text: str = "text", digest: Callable[[Column], Column] = sha256_of, strong: bool = True, salts: int = 16, key: str | None = None
) -> DataFrame:
    """Per row: doc_id, keep_id, group_size, kept, digest (of the normalised text), and with ``key``, a column
    that tells rows apart, that key: then exactly one row of each text is kept, even where ids repeat.

    ``digest`` may be any function of the text, however weak, with ``strong=False``:
    the join that tells rows their winner then compares texts as well.
    """
    best = winners(docs, row_id, text, digest, strong, salts, key)
    rows = docs.select(F.col(row_id).alias("rid"), *([F.col(key).alias("k")] if key else []), normalised(text).alias("t")).withColumn("digest", digest(F.col("t")))
    on = F.col("digest") == F.col("w_digest")
    if not strong:
        on &= F.col("w_text").isNull() | (F.col("w_text") == F.col("t"))
    return rows.join(best, on).select(
        F.col("rid").alias("doc_id"), "keep_id", "group_size", (F.col("k") == F.col("keep_key") if key else F.col("rid").eqNullSafe(F.col("keep_id"))).alias("kept"), "digest", *([F.col("k").alias(key)] if key else [])
    )
